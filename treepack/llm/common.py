"""Shared helpers: table access, staged tables in the shared folder, Arrow row mapping, run grouping."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import gc
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Characters that count as white space in the contracts of the operators.
SPACE = b"\x20\x09\x0a\x0b\x0c\x0d"
_STAGED: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; only where it is unset (tests) a folder under the warehouse."""
    return spark.conf.get("spark.checkpoint.dir", None) or (
        spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/treepack-shared"
    )


def stage(df: DataFrame, name: str) -> DataFrame:
    """Cut lineage: write df once as a table in the shared folder and read it again.

    A lost executor costs a re-read, never a recomputation of what lies before.
    The folder goes with the `scratch` block it was made in, or when the Python process ends.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/treepack-{uuid.uuid4().hex}/{name}"
    df.write.option("compression", "zstd").parquet(path)
    if not _STAGED:
        atexit.register(_clean, spark)
    _STAGED.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.staged_at = path
    return out


@contextlib.contextmanager
def scratch(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Tables staged in the block are deleted at its end, but for those passed to the function it gives."""
    first, kept = len(_STAGED), set()

    def keep(df: DataFrame) -> DataFrame:
        kept.add(df.staged_at)
        return df

    yield keep
    gone = [p for p in _STAGED[first:] if p not in kept]
    _delete(spark, gone)
    _STAGED[:] = [p for p in _STAGED if p not in set(gone)]


def _delete(spark: SparkSession, paths: list[str]) -> None:
    jvm, conf = spark._jvm, spark._jsparkSession.sessionState().newHadoopConf()
    for path in paths:
        p = jvm.org.apache.hadoop.fs.Path(path).getParent()
        p.getFileSystem(conf).delete(p, True)


def _clean(spark: SparkSession) -> None:
    with contextlib.suppress(Py4JError, OSError, AttributeError):  # the session has ended already; the folder's owner clears it
        _delete(spark, _STAGED)


def map_rows(df: DataFrame, row: Callable[..., tuple], schema: str, *, start: Callable | None = None, step: int = 512) -> DataFrame:
    """One output tuple for each input row.

    row(*values) gets the columns of df (binary for strings, None for null).
    start() makes a worker's state, passed as the first argument of row.
    """

    def many(*args):
        *state, rows = args
        return [row(*state, *r) for r in rows]

    return map_groups(df, many, schema, start=start, step=step)


def map_groups(df: DataFrame, many: Callable[..., list[tuple]], schema: str, *, start: Callable | None = None, step: int = 512, nbytes: int = 4 << 20) -> DataFrame:
    """many([state,] rows) -> output tuples, over groups of at most `step` rows and about `nbytes` bytes, so that memory stays bounded."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    out = StructType.fromDDL(schema)
    bounded_batches(df.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        arrow, state = to_arrow_schema(out), (start(),) if start else ()
        for batch in batches:
            for rows in groups(batch, step, nbytes):
                if got := many(*state, rows):
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*got, strict=True), arrow, strict=True)], schema=arrow)
        give_back()

    return df.mapInArrow(run, out)


def bounded_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Texts are long, so Arrow batches of this session hold at most `rows` rows: less for JVM buffers and workers to hold at once."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key, "10000")) <= rows:
        spark.conf.set(key, str(rows))


def give_back() -> None:
    """Returns freed memory to the system: workers live on between tasks, and so would what their largest task needed."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)


def groups(batch: pa.RecordBatch, step: int, nbytes: int) -> Iterator[list[tuple]]:
    for at in range(0, batch.num_rows, step):
        rows, size = [], 0
        for r in zip(*map(values, batch.slice(at, step).columns), strict=True):
            rows.append(r)
            size += sum(len(v) for v in r if isinstance(v, bytes))
            if size >= nbytes:
                yield rows
                rows, size = [], 0
        if rows:
            yield rows


def values(col: pa.Array) -> list:
    """Python values of an Arrow column; strings as their UTF-8 bytes."""
    if pa.types.is_string(col.type):
        col = col.cast(pa.binary())
    elif pa.types.is_large_string(col.type):
        col = col.cast(pa.large_binary())
    return col.to_pylist()


def whole_runs(batches: Iterable[pa.RecordBatch], keys: list[str], least: int = 1 << 15) -> Iterator[pa.Table]:
    """Tables of at least `least` rows (but the last) that never cut a run of equal keys; input sorted by keys."""
    held: list[pa.RecordBatch] = []
    rows = 0
    for batch in batches:
        held.append(batch)
        rows += batch.num_rows
        if rows < least:
            continue
        t = pa.Table.from_batches(held)
        cut, last = t.num_rows, [t.column(k)[t.num_rows - 1] for k in keys]
        lo, hi = 0, t.num_rows - 1  # first row of the last run, by bisection
        while lo < hi:
            mid = (lo + hi) // 2
            if all(t.column(k)[mid] == v for k, v in zip(keys, last, strict=True)):
                hi = mid
            else:
                lo = mid + 1
        cut = lo
        if cut:
            yield t.slice(0, cut).combine_chunks()
            held, rows = t.slice(cut).combine_chunks().to_batches(), t.num_rows - cut
    if rows:
        yield pa.Table.from_batches(held).combine_chunks()


def is_small(df: DataFrame, rows: int) -> bool:
    """Whether df has at most `rows` rows, so that it may be broadcast; counts no further than that."""
    return df.limit(rows + 1).count() <= rows


def maybe_broadcast(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if is_small(df, rows) else df
