"""The codecs compared with, and the lookup example."""

from __future__ import annotations

import zlib

from pyspark.sql import functions as F

from treepack.operators import baselines, probe, stats
from treepack.operators.blocks import decode_blocks, encode_blocks
from treepack.queries import sql
from treepack.queries.common import digests, encoded, hist_of, sizes
from treepack.registry import query
from treepack.sources.streams import build_stream, to_blocks
from treepack.sources.tables import load, scratch, small


def _classic(stream, cursors, decode):
    return lambda spark, d: digests(decode_blocks(encoded(spark, d, [stream], encoder=lambda raws, lengths: baselines.encode_classic(raws, lengths, cursors)), decode=decode))


query("base_bitwise", "H1", sql.md5_of(["doc_es"]))(_classic("doc_es", 1, baselines.decode_bitwise))
query("base_table11", "H2", sql.md5_of(["doc_de"]))(_classic("doc_de", 1, baselines.decode_table))
query("base_table_cursors", "H3", sql.md5_of(["doc_de"]))(_classic("doc_de", 4, lambda p, n, lengths: baselines.decode_table(p, n, lengths, cursors=4)))
query("base_table_double", "H4", sql.md5_of(["doc_de"]))(_classic("doc_de", 1, lambda p, n, lengths: baselines.decode_table(p, n, lengths, symbols_per_step=2)))


@query("base_huffman_sizes", "H5", f"WITH RECURSIVE src AS MATERIALIZED ({sql.rows(['doc_de'])}), {sql.codes(sql.hist('SELECT * FROM src'))} SELECT value_id, (pos // 8192)::BIGINT AS block_no, (4 + (sum(len) + 7) // 8)::BIGINT AS payload_bytes FROM src JOIN codes USING (stream_id, sym) GROUP BY ALL HAVING (sum(len) + 7) // 8 < count(*)")
def base_huffman_sizes(spark, d):
    hist = hist_of(spark, d, ["doc_de"])
    enc = encode_blocks(to_blocks(build_stream(spark, d, "doc_de")), stats.codebooks(hist, max_len=15, floor=4096), encoder=baselines.encode_classic)
    return enc.where("n > 0 and octet_length(payload) - 4 < n").select("value_id", "block_no", F.octet_length("payload").cast("long").alias("payload_bytes"))


@query("base_tans", "H7", sql.md5_of(["doc_fr"]))
def base_tans(spark, d):
    """Whole values up to 128 KB by one table each, two cursors."""
    values = build_stream(spark, d, "doc_fr")
    blocks = values.select("stream_id", "value_id", F.lit(0).cast("long").alias("block_no"), F.octet_length("raw").alias("n"), "raw")
    enc = encode_blocks(blocks, stats.codebooks(stats.byte_histogram(values)), encoder=lambda raws, lengths: baselines.encode_tans(raws))
    return digests(decode_blocks(enc, decode=baselines.decode_tans))


@query("base_incompressible", "H9", "SELECT true AS stored_as_is, true AS no_larger_than_raw_and_size")
def base_incompressible(spark, d):
    """A code that does not fit the data would make it larger: such blocks are stored as they are."""
    values = build_stream(spark, d, "emb_f4")
    flat = stats.codebooks(hist_of(spark, d, ["doc_en"]), smooth=True).withColumn("stream_id", F.lit("emb_f4"))
    enc = encode_blocks(to_blocks(values), flat)
    return enc.agg(F.min(F.octet_length("payload") == F.col("n") + 4).alias("stored_as_is"), F.min(F.octet_length("payload") <= F.col("n") + 4).alias("no_larger_than_raw_and_size"))


@query("base_parquet_codecs", "H10")
def base_parquet_codecs(spark, d):
    """Bytes of a text column under the sink's own codecs, and zlib's, next to node bitmaps."""
    docs = load(spark, d, "documents").where("lang = 'en'").select("text")
    raw = docs.agg(F.sum(F.octet_length("text"))).first()[0]
    rows = []
    for codec in ("none", "snappy", "gzip", "zstd"):
        path = scratch(spark)
        docs.write.option("compression", codec).option("parquet.enable.dictionary", "false").parquet(path)
        rows.append((f"parquet-{codec}", raw, spark.read.format("binaryFile").load(path).agg(F.sum("length")).first()[0]))

    def z(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([len(zlib.compress(t.encode(), 6)) for t in b.column("text").to_pylist() if t is not None], pa.int64())], names=["n"])

    rows.append(("zlib", raw, docs.mapInArrow(z, "n long").agg(F.sum("n")).first()[0]))
    rows.append(("node-bitmaps", raw, sizes(encoded(spark, d, ["doc_en"])).first()["enc_bytes"]))
    return spark.createDataFrame(rows, "codec string, raw_bytes long, enc_bytes long").withColumn("ratio", F.round(F.col("raw_bytes") / F.col("enc_bytes"), 4))


_LEFT = "SELECT l_orderkey, l_linenumber, l_partkey, CASE WHEN p_size % 2 = 0 THEN p_size END::BIGINT AS found FROM lineitem LEFT JOIN part ON l_partkey = p_partkey"


def _sides(spark, d):
    return load(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey"), load(spark, d, "part").where("p_size % 2 = 0").select(F.col("p_partkey").alias("l_partkey"), F.col("p_size").cast("long").alias("v"))


@query("probe_spark", "H11", _LEFT)
def probe_spark(spark, d):
    left, right = _sides(spark, d)
    return left.join(small(right), "l_partkey", "left").select("l_orderkey", "l_linenumber", "l_partkey", F.col("v").alias("found"))


@query("probe_vectorised", "H11", _LEFT)
def probe_vectorised(spark, d):
    left, right = _sides(spark, d)
    return probe.probe(left, right, "l_partkey", "v")


@query("probe_scalar", "H11", _LEFT)
def probe_scalar(spark, d):
    left, right = _sides(spark, d)
    return probe.probe(left, right, "l_partkey", "v", probe.scalar)


@query("probe_misses", "H11", "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem ANTI JOIN (SELECT p_partkey FROM part WHERE p_size % 2 = 0) p ON l_partkey = p_partkey")
def probe_misses(spark, d):
    left, right = _sides(spark, d)
    return probe.probe(left, right, "l_partkey", "v").where("found is null").drop("found")


@query("ablation_td", "H13 W5", "SELECT tree, primitive, true AS same FROM (VALUES ('naive'), ('flat_opt')) a(tree), (VALUES ('loop'), ('branchfree'), ('vector')) b(primitive)")
def ablation_td(spark, d):
    """Tree by primitive: all six give the same bytes."""
    from treepack.operators import codec

    out = None
    for tree in ("naive", "flat_opt"):
        enc = encoded(spark, d, ["doc_es"], shape=tree)
        for impl in ("loop", "branchfree", "vector"):
            how = dict(prefill=False, fuse=False) if tree == "naive" else {}
            dec = decode_blocks(enc.withColumn("stored", F.col("crc")), decode=lambda p, n, lengths, t=tree, i=impl, h=how: codec.decode_batch(p, n, lengths, t, "topdown", impl=i, **h))
            one = dec.agg(F.min(F.crc32("raw") == F.col("stored")).alias("same")).select(F.lit(tree).alias("tree"), F.lit(impl).alias("primitive"), "same")
            out = one if out is None else out.unionByName(one)
    return out
