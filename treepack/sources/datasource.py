"""`treepack`: a Python data source over tables of encoded blocks.

Reading decodes: (stream_id, value_id, block_no, raw). Equality and range
filters on stream_id and block_no are pushed down to the files' scan, so blocks
that are not asked for are never decoded. Writing encodes rows of
(stream_id, value_id, block_no, raw) with one code per task and commits by
listing the finished files: what a failed or second attempt of a task wrote is
left out.

Files are opened by pyarrow, so `path` is a file system that it can reach; on
stores that only Spark reads, use blocks tables with encode_blocks and decode_blocks.
"""

from __future__ import annotations

import json
import os
import uuid
from dataclasses import dataclass

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, EqualTo, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual, WriterCommitMessage

SCHEMA = "stream_id string, value_id long, block_no long, raw binary"
FOOTER = "_footer.json"
VERSION = 1


def _local(path: str) -> str:
    return path.removeprefix("file://").removeprefix("file:")


@dataclass
class FilePart(InputPartition):
    path: str
    filters: list


@dataclass
class Written(WriterCommitMessage):
    file: str
    rows: int
    bytes: int


class TreepackSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "treepack"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema):
        return TreepackReader(self.options)

    def writer(self, schema, overwrite):
        return TreepackWriter(self.options, overwrite)


class TreepackReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.filters = _local(options["path"]), []

    def pushFilters(self, filters):
        ops = {EqualTo: "==", GreaterThan: ">", GreaterThanOrEqual: ">=", LessThan: "<", LessThanOrEqual: "<=", In: "in"}
        for f in filters:
            column = f.attribute[0] if len(f.attribute) == 1 else ""
            if type(f) in ops and column in ("stream_id", "block_no", "value_id"):
                self.filters.append((column, ops[type(f)], list(f.value) if isinstance(f, In) else f.value))
            else:
                yield f

    def partitions(self):
        with open(os.path.join(self.path, FOOTER)) as f:
            footer = json.load(f)
        if footer["version"] != VERSION:
            raise ValueError(f"version {footer['version']} of the format is not {VERSION}")
        return [FilePart(os.path.join(self.path, x["file"]), self.filters) for x in footer["files"]] or [FilePart("", [])]

    def read(self, partition):
        import pyarrow as pa
        import pyarrow.parquet as pq

        from treepack.operators.blocks import _by_book
        from treepack.operators.codec import decode_batch

        if not partition.path:
            return
        table = pq.read_table(partition.path, filters=partition.filters or None)
        for b in table.to_batches(max_chunksize=512):
            if not b.num_rows:
                continue
            payload, n = b.column("payload").to_pylist(), b.column("n").to_pylist()
            raw: list = [None] * len(n)
            for book, rows in _by_book(b):
                for i, r in zip(rows, decode_batch([payload[i] for i in rows], [n[i] for i in rows], book), strict=True):
                    raw[i] = r
            yield pa.RecordBatch.from_arrays([b.column("stream_id"), b.column("value_id"), b.column("block_no"), pa.array(raw, pa.binary())], names=["stream_id", "value_id", "block_no", "raw"])


class TreepackWriter(DataSourceWriter):
    def __init__(self, options, overwrite):
        self.path, self.overwrite = _local(options["path"]), overwrite

    def write(self, iterator):
        import zlib

        import numpy as np
        import pyarrow as pa
        import pyarrow.parquet as pq

        from treepack.operators.codec import encode_batch
        from treepack.plans import codebook as cb

        os.makedirs(self.path, exist_ok=True)
        name = f"blocks-{uuid.uuid4().hex}.parquet"
        rows = size = 0
        schema = pa.schema([("stream_id", pa.string()), ("value_id", pa.int64()), ("block_no", pa.int64()), ("n", pa.int32()), ("lengths", pa.binary()), ("payload", pa.binary()), ("crc", pa.int64())])
        with pq.ParquetWriter(os.path.join(self.path, name), schema) as out:
            part: list = []

            def flush():
                nonlocal rows, size
                if not part:
                    return
                raws = [bytes(r["raw"]) for r in part]
                counts = np.bincount(np.frombuffer(b"".join(raws), np.uint8), minlength=256)
                lengths = cb.pack_lengths(cb.fit_lengths(counts))
                payload = encode_batch(raws, lengths)
                out.write_batch(pa.RecordBatch.from_arrays([pa.array([r["stream_id"] for r in part]), pa.array([r["value_id"] for r in part], pa.int64()), pa.array([r["block_no"] for r in part], pa.int64()), pa.array(map(len, raws), pa.int32()), pa.array([lengths] * len(raws), pa.binary()), pa.array(payload, pa.binary()), pa.array([zlib.crc32(r) for r in raws], pa.int64())], schema=schema))
                rows, size = rows + len(part), size + sum(map(len, payload))
                part.clear()

            for r in iterator:
                part.append(r)
                if len(part) == 512:
                    flush()
            flush()
        return Written(name, rows, size)

    def commit(self, messages):
        files = []
        footer = os.path.join(self.path, FOOTER)
        if not self.overwrite and os.path.exists(footer):
            with open(footer) as f:
                files = json.load(f)["files"]
        files += [{"file": m.file, "rows": m.rows, "bytes": m.bytes} for m in messages if m and m.rows]
        os.makedirs(self.path, exist_ok=True)
        with open(footer + ".new", "w") as f:
            json.dump({"version": VERSION, "files": files}, f)
        os.replace(footer + ".new", footer)

    def abort(self, messages):
        for m in messages:
            if m and os.path.exists(p := os.path.join(self.path, m.file)):
                os.remove(p)


def register(spark) -> None:
    """Makes format("treepack") known to the session and lets its reader see filters."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(TreepackSource)
