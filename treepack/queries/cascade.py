"""Unary codes, LZ substreams, and questions answered on encoded data."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from treepack.operators import lz, queryops, stats, unary
from treepack.operators.blocks import decode_blocks, encode_blocks
from treepack.plans.selective import Gates
from treepack.queries import sql
from treepack.queries.common import codes_of, digests, encoded, sizes
from treepack.registry import query
from treepack.sources.streams import build_stream, to_blocks
from treepack.sources.tables import staged

# --- unary ---------------------------------------------------------------------

_GAPS = "SELECT p, list(g ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS g FROM (SELECT l_orderkey // 2048 AS p, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, least(coalesce(l_orderkey - lag(l_orderkey) OVER (PARTITION BY l_orderkey // 2048 ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice), 0), 255) AS g FROM lineitem) GROUP BY p"


def _pages(spark, d, fn, ddl: str):
    """fn(page, gaps) -> tuples, over the pages of key gaps."""
    names = [x.strip().split()[0] for x in ddl.split(",")]

    def run(batches):
        for b in batches:
            rows = [r for v, raw in zip(b.column("value_id").to_pylist(), b.column("raw").to_pylist(), strict=True) for r in fn(v, np.frombuffer(raw, np.uint8).astype(np.int64))]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], names=names)

    return build_stream(spark, d, "okdelta").mapInArrow(run, ddl)


@query("puc_bitmaps", "I1", f"SELECT p, j, sum((v >= j)::INT)::BIGINT AS bits, sum((v = j)::INT)::BIGINT AS set_bits FROM (SELECT p, unnest(g) AS v FROM ({_GAPS})), range(0, 20) r(j) GROUP BY p, j HAVING bits > 0")
def puc_bitmaps(spark, d):
    return _pages(spark, d, lambda v, g: [(v, j, len(b), int(b.sum())) for j, b in enumerate(unary.encode(g)[0])], "p long, j long, bits long, set_bits long")


_GAPSUM = f"SELECT p, len(g)::BIGINT AS n, list_sum(g)::BIGINT AS total, list_sum(list_transform(g, lambda x, i: x * i))::BIGINT AS weighted FROM ({_GAPS})"


def _digest(v, g):
    return [(v, len(g), int(g.sum()), int((g * np.arange(1, len(g) + 1)).sum()))]


_DDL = "p long, n long, total long, weighted long"
query("puc_roundtrip", "I2", _GAPSUM)(lambda spark, d: _pages(spark, d, lambda v, g: _digest(v, unary.from_bytes(unary.to_bytes(g))), _DDL))
query("puc_rice_roundtrip", "I4", _GAPSUM)(lambda spark, d: _pages(spark, d, lambda v, g: _digest(v, unary.from_bytes(unary.to_bytes(g, 2), 2)), _DDL))
query("golomb_naive", "H12", _GAPSUM)(lambda spark, d: _pages(spark, d, lambda v, g: _digest(v, unary.decode_naive(unary.plain_bits(g), len(g))), _DDL))
query("golomb_bytetable", "H12", _GAPSUM)(lambda spark, d: _pages(spark, d, lambda v, g: _digest(v, unary.decode_bytetable(unary.plain_bits(g), len(g))), _DDL))
query("golomb_bytetable_bf", "H12", _GAPSUM)(lambda spark, d: _pages(spark, d, lambda v, g: _digest(v, unary.decode_bytetable(unary.plain_bits(g), len(g), True)), _DDL))


def _ans_bitmaps(v, g):
    """Skewed bitmaps of the unary code by static tables, and back."""
    from treepack.functions import fsm
    from treepack.plans.selective import choose_table, passes

    out = []
    for j, bits in enumerate(unary.encode(g)[0]):
        n, r = np.array([len(bits)]), np.array([int(bits.sum())])
        if passes(n, r, j, Gates())[0]:
            ids, flip = choose_table(n, r)
            raw = np.packbits(bits, bitorder="little")
            raw = ~raw if flip[0] else raw
            size = np.array([len(raw)])
            back = fsm.decode(fsm.encode(raw, size, ids - 1, fsm.static_tables()), size, ids - 1, fsm.static_tables())
            bits = np.unpackbits(~back if flip[0] else back, bitorder="little", count=len(bits)).view(bool)
        out.append(bits)
    return _digest(v, unary.decode(out))


query("puc_ans", "I6", _GAPSUM)(lambda spark, d: _pages(spark, d, _ans_bitmaps, _DDL))

_GEOM = "SELECT m, least(floor(ln(1 - ((id * 2654435761) % 4294967296) / 4294967296.0) / ln(1 - 1 / m)), 250)::BIGINT AS v FROM range(100000) r(id), (VALUES (1.25::DOUBLE), (1.5), (2), (3), (4), (5)) t(m)"


@query("puc_sweep", "I5 W16", f"SELECT m, round(avg(v + 1), 6) AS mean_code_length, true AS decoders_agree FROM ({_GEOM}) GROUP BY m")
def puc_sweep(spark, d):
    """Geometric values whose unary codes have a given mean length; all four decoders agree."""
    rows = spark.range(100_000).crossJoin(F.broadcast(spark.createDataFrame([(m,) for m in (1.25, 1.5, 2.0, 3.0, 4.0, 5.0)], "m double")))
    u = F.expr("(id * 2654435761) % 4294967296") / 4294967296.0
    v = F.least(F.floor(F.ln(1 - u) / F.ln(1 - 1 / F.col("m"))), F.lit(250))
    pages = rows.select("m", F.expr("id div 4096").alias("p"), "id", v.alias("v")).groupBy("m", "p").agg(F.array_sort(F.collect_list(F.struct("id", "v"))).alias("r"))

    def run(batches):
        for b in batches:
            out = []
            for m, r in zip(b.column("m").to_pylist(), b.column("r").to_pylist(), strict=True):
                g = np.array([x["v"] for x in r], np.int64)
                bits = unary.plain_bits(g)
                ways = [unary.from_bytes(unary.to_bytes(g)), unary.decode_naive(bits, len(g)), unary.decode_bytetable(bits, len(g)), unary.decode_bytetable(bits, len(g), True)]
                out.append((m, len(g), int((g + 1).sum()), all((w == g).all() for w in ways)))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], names=["m", "n", "bits", "ok"])

    return pages.mapInArrow(run, "m double, n long, bits long, ok boolean").groupBy("m").agg(F.round(F.sum("bits") / F.sum("n"), 6).alias("mean_code_length"), F.min("ok").alias("decoders_agree"))


# --- LZ ------------------------------------------------------------------------


@query("lz_roundtrip", "J1", "SELECT value_id, n_bytes, digest FROM (" + sql.md5_of(["doc_de"]) + ")")
def lz_roundtrip(spark, d):
    back = lz.join_substreams(lz.substreams(build_stream(spark, d, "doc_de")))
    return back.select("value_id", F.octet_length("raw").cast("long").alias("n_bytes"), F.md5("raw").alias("digest"))


def _lz_streams(spark, d):
    return staged(lz.substreams(build_stream(spark, d, "html")).where("octet_length(raw) > 0"))


@query("lz_stream_stats", "J2")
def lz_stream_stats(spark, d):
    """Entropy, code length and gap of each substream, with the largest saving of a node."""
    from treepack.plans.selective import skew_report

    hist = stats.byte_histogram(_lz_streams(spark, d))
    codes = codes_of(stats.codebooks(hist))
    top = skew_report(hist, codes).groupBy("stream_id").agg(F.round(F.max("saving"), 6).alias("top_node"))
    return stats.entropy_report(hist, codes).join(top, "stream_id")


@query("lz_stream_relations", "J2 W13", "SELECT true AS literal_lengths_more_skewed_than_literals, true AS literals_more_skewed_than_offsets")
def lz_stream_relations(spark, d):
    """Which substreams hold skewed nodes: literal lengths more than literals, literals more than offsets."""
    top = lz_stream_stats(spark, d).groupBy().pivot("stream_id", ["lz/ll", "lz/lit", "lz/off"]).agg(F.first("top_node"))
    return top.select((F.col("lz/ll") > F.col("lz/lit")).alias("literal_lengths_more_skewed_than_literals"), (F.col("lz/lit") > F.col("lz/off")).alias("literals_more_skewed_than_offsets"))


@query("lz_stream_codecs", "J3 W13")
def lz_stream_codecs(spark, d):
    """Bytes of each substream by classic Huffman, node bitmaps, with gates, and whole-stream ANS."""
    from treepack.operators import baselines

    values = _lz_streams(spark, d)
    books = stats.codebooks(stats.byte_histogram(values))
    blocks = to_blocks(values)
    ways = {
        "classic": dict(encoder=baselines.encode_classic), "node-bitmaps": {}, "node-bitmaps-ans": dict(gates=Gates()),
        "ans": dict(encoder=lambda raws, lengths: baselines.encode_tans(raws)),
    }
    out = None
    for name, how in ways.items():
        s = sizes(encode_blocks(blocks, books, **how)).withColumn("codec", F.lit(name))
        out = s if out is None else out.unionByName(s)
    return out


@query("lz_streams_roundtrip", "J3", "SELECT stream_id, true AS same FROM (VALUES ('lz/lit'), ('lz/ll'), ('lz/ml'), ('lz/off')) t(stream_id)")
def lz_streams_roundtrip(spark, d):
    values = _lz_streams(spark, d)
    enc = encode_blocks(to_blocks(values), stats.codebooks(stats.byte_histogram(values)), gates=Gates())
    truth = values.select("stream_id", "value_id", F.md5("raw").alias("want"))
    return digests(decode_blocks(enc, gates=Gates())).join(truth, ["stream_id", "value_id"], "full").groupBy("stream_id").agg(F.min(F.coalesce(F.col("digest") == F.col("want"), F.lit(False))).alias("same"))


# --- compressed domain -------------------------------------------------------------

_CD = f"SELECT value_id, (pos // 8192)::BIGINT AS block_no, pos % 8192 AS spot, sym FROM ({sql.rows(['doc_fr'])})"
_ALL = "SELECT doc_id AS value_id, unnest(range(greatest(1, (strlen(text) + 8191) // 8192)))::BIGINT AS block_no FROM documents WHERE lang = 'fr' AND text IS NOT NULL"


def _enc(spark, d):
    return encoded(spark, d, ["doc_fr"])


def _count_oracle(where: str) -> str:
    return f"SELECT a.value_id, a.block_no, count(b.sym)::BIGINT AS found FROM ({_ALL}) a LEFT JOIN (SELECT * FROM ({_CD}) WHERE {where}) b USING (value_id, block_no) GROUP BY ALL"


query("cd_count_symbol", "N1", _count_oracle("sym = 101"))(lambda spark, d: queryops.count_symbol(_enc(spark, d), 101).drop("stream_id"))
query("cd_line_count", "N7", _count_oracle("sym = 10"))(lambda spark, d: queryops.line_count(_enc(spark, d)).drop("stream_id"))
query("cd_rank", "N4", _count_oracle("sym = 110 AND spot < 1000"))(lambda spark, d: queryops.rank(_enc(spark, d), 110, 1000).drop("stream_id"))
query("cd_positions", "N2", f"SELECT value_id, block_no, spot::BIGINT AS pos FROM ({_CD}) WHERE sym = 44")(lambda spark, d: queryops.positions(_enc(spark, d), 44).drop("stream_id"))
query("cd_filter_set", "N5", f"SELECT value_id, block_no, spot::BIGINT AS pos FROM ({_CD}) WHERE sym IN (65, 69, 73, 79, 85)")(lambda spark, d: queryops.positions(_enc(spark, d), {65, 69, 73, 79, 85}).drop("stream_id"))
query("cd_access", "N3", f"SELECT value_id, block_no, sym::BIGINT AS sym FROM ({_CD}) WHERE spot = 123")(lambda spark, d: queryops.access(_enc(spark, d), 123).drop("stream_id"))
query("cd_select", "N4", f"SELECT value_id, block_no, spot::BIGINT AS pos FROM (SELECT *, row_number() OVER (PARTITION BY value_id, block_no ORDER BY spot) AS k FROM ({_CD}) WHERE sym = 101) WHERE k = 10")(lambda spark, d: queryops.select(_enc(spark, d), 101, 9).drop("stream_id"))
query("cd_histogram", "N6", f"SELECT value_id, block_no, sym::BIGINT AS sym, count(*)::BIGINT AS cnt FROM ({_CD}) GROUP BY ALL")(lambda spark, d: queryops.histogram(_enc(spark, d)).drop("stream_id"))

