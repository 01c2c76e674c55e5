"""Counts, code lengths, canonical codes, tree shapes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treepack.operators import stats
from treepack.plans import codebook as cb
from treepack.plans import shape as sh
from treepack.queries import sql
from treepack.queries.common import books_of, codes_of, digests, hist_of
from treepack.registry import query
from treepack.sources.streams import TEXT_STREAMS, build_stream

WORDS = {"huffman": b"huffman", "coconut-papaya": b"coconut-papaya"}
_NUM = " UNION ALL ".join([sql.numbers("userid_le8", "events", "user_id", 8), sql.numbers("ok_le8", "lineitem", "l_orderkey", 8)])


@query("byte_histogram", "A1", sql.hist(sql.rows(TEXT_STREAMS) .replace("SELECT stream_id, value_id, u.i AS pos, ", "SELECT stream_id, ") + f" UNION ALL SELECT * FROM ({_NUM})"))
def byte_histogram(spark: SparkSession, d: str) -> DataFrame:
    return hist_of(spark, d, (*TEXT_STREAMS, "userid_le8", "ok_le8"))


@query("byte_histogram_rel", "A1b", sql.hist(sql.rows(["doc_es"])))
def byte_histogram_rel(spark, d):
    return stats.byte_histogram_sql(build_stream(spark, d, "doc_es"))


@query("sampled_codebook_roundtrip", "A1c", sql.md5_of(["doc_en"]))
def sampled_codebook_roundtrip(spark, d):
    from treepack.operators.blocks import decode_blocks, encode_blocks
    from treepack.sources.streams import to_blocks

    values = build_stream(spark, d, "doc_en")
    books = stats.codebooks(stats.byte_histogram(values, fraction=0.2), smooth=True)
    return digests(decode_blocks(encode_blocks(to_blocks(values), books)))


_LENS = ("doc_de", "doc_fr", "doc_es")


@query("huffman_lengths", "A2", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(_LENS)))} SELECT stream_id, sym, len FROM lens")
def huffman_lengths(spark, d):
    return stats.code_lengths(books_of(spark, d, _LENS, max_len=15, floor=4096)).select("stream_id", "sym", "len")


@query("limited_lengths", "A3", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(['doc_de', 'html'])))} SELECT stream_id, 1.0::DOUBLE AS kraft, true AS within, true AS not_below_optimum, sum(cnt * len)::BIGINT AS optimum FROM lifted JOIN lens USING (stream_id, sym) GROUP BY stream_id")
def limited_lengths(spark, d):
    """The optimal limited code against the unlimited optimum; Kraft sum, limit and cost."""
    hist = hist_of(spark, d, ("doc_de", "html"))
    total = F.sum("cnt").over(Window.partitionBy("stream_id"))  # 256 rows a stream
    hist = hist.withColumn("cnt", F.greatest("cnt", F.floor(total / 4096)))

    def cost(max_len, name):
        lens = stats.code_lengths(stats.codebooks(hist, max_len=max_len))
        return lens.join(hist, ["stream_id", "sym"]).groupBy("stream_id").agg(F.sum(F.col("cnt") * F.col("len")).alias(name), F.sum(F.pow(F.lit(2.0), -F.col("len"))).alias(f"k_{name}"), F.max("len").alias(f"m_{name}"))

    return cost(8, "limited").join(cost(15, "best"), "stream_id").select("stream_id", F.col("k_limited").alias("kraft"), (F.col("m_limited") <= 8).alias("within"), (F.col("limited") >= F.col("best")).alias("not_below_optimum"), F.col("best").alias("optimum"))


@query("repaired_lengths", "A3", "SELECT * FROM (VALUES ('doc_de', true, true), ('html', true, true)) t(stream_id, fits, near_optimum)")
def repaired_lengths(spark, d):
    hist = hist_of(spark, d, ("doc_de", "html"))
    cost = lambda m, name: stats.code_lengths(stats.codebooks(hist, max_len=8, method=m)).join(hist, ["stream_id", "sym"]).groupBy("stream_id").agg(F.sum(F.col("cnt") * F.col("len")).alias(name), F.sum(F.pow(F.lit(2.0), -F.col("len"))).alias(f"k_{name}"))
    return cost("quick", "a").join(cost("optimal", "b"), "stream_id").select("stream_id", (F.col("k_a") <= 1).alias("fits"), F.col("a").between(F.col("b"), F.col("b") * 1.05).alias("near_optimum"))


@query("canonical_codes", "A4", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(_LENS)))} SELECT stream_id, sym, len, code FROM codes")
def canonical_codes(spark, d):
    return codes_of(books_of(spark, d, _LENS, max_len=15, floor=4096))


@query("codebook_pack_roundtrip", "A5", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(['doc_fr'])))} SELECT sym, len, 128 AS table_bytes FROM lens")
def codebook_pack_roundtrip(spark, d):
    books = books_of(spark, d, ("doc_fr",), max_len=15, floor=4096)
    return stats.code_lengths(books).crossJoin(F.broadcast(books.select(F.octet_length("lengths").alias("table_bytes")))).select("sym", "len", "table_bytes")


def _word_stream(spark, words: dict[str, bytes]) -> DataFrame:
    return spark.createDataFrame([(k, 0, bytearray(v)) for k, v in words.items()], "stream_id string, value_id long, raw binary")


@query("golden_huffman_codes", "A2t", "SELECT * FROM (VALUES ('f','00'),('u','01'),('a','100'),('h','101'),('m','110'),('n','111')) t(symbol, code)")
def golden_huffman_codes(spark, d):
    books = stats.codebooks(stats.byte_histogram(_word_stream(spark, {"huffman": WORDS["huffman"]})))
    return codes_of(books).select(F.char("sym").alias("symbol"), "code")


EDGE = {"none": b"", "one_byte": b"a", "same": b"z" * 9000, "two": b"ab" * 5000, "all": bytes(range(256)) * 40, "below": b"ab c" * 2047 + b"xyz", "exact": b"ab c" * 2048, "above": b"ab c" * 2048 + b"x", "utf8": "née 😀".encode() * 700}


@query("degenerate_streams", "A6", "SELECT * FROM (VALUES " + ", ".join(f"('{k}', {len(v)}::BIGINT, '{__import__('hashlib').md5(v).hexdigest()}')" for k, v in EDGE.items()) + ") t(stream_id, n_bytes, digest)")
def degenerate_streams(spark, d):
    from treepack.operators.blocks import decode_blocks, encode_blocks
    from treepack.sources.streams import to_blocks

    values = _word_stream(spark, EDGE)
    hist = stats.byte_histogram(values)
    filler = spark.createDataFrame([("none", 0, 1)], "stream_id string, sym int, cnt long")  # a stream without symbols has no counts
    books = stats.codebooks(hist.unionByName(filler))
    return digests(decode_blocks(encode_blocks(to_blocks(values), books))).drop("value_id")


def _strings_cost(spark, rows) -> DataFrame:
    return spark.createDataFrame(rows, "word string, mode string, nodes int, ops long, ops_per_byte double")


def _topdown_rows(mode: str) -> list[tuple]:
    out = []
    for name, w in WORDS.items():
        c = np.bincount(np.frombuffer(w, np.uint8), minlength=256)
        ops = sh.ops_topdown(cb.huffman_lengths(c), c, mode)
        out.append((name, mode, None, ops, round(ops / len(w), 3)))
    return out


for _mode, _h, _c in (("naive", 25, 57), ("fused", 18, 46), ("prefill", 18, 43), ("flat", 14, 39), ("flat_opt", 14, 32)):
    _name = {"flat_opt": "flatopt"}.get(_mode, _mode)
    query(f"ops_topdown_{_name}", "B1-B5", f"SELECT word, '{_mode}' AS mode, NULL::INT AS nodes, ops::BIGINT AS ops, round(ops / n, 3) AS ops_per_byte FROM (VALUES ('huffman', {_h}, 7.0::DOUBLE), ('coconut-papaya', {_c}, 14.0::DOUBLE)) t(word, ops, n)")(
        lambda spark, d, m=_mode: _strings_cost(spark, _topdown_rows(m))
    )


@query("ops_bottomup_strings", "B6", "SELECT word, mode, nodes, ops::BIGINT AS ops, round(ops / n, 3) AS ops_per_byte FROM (VALUES ('huffman','naive',5,18,7.0::DOUBLE),('huffman','flat',3,14,7.0),('huffman','flat_opt',3,14,7.0),('coconut-papaya','naive',8,43,14.0),('coconut-papaya','flat',6,39,14.0),('coconut-papaya','flat_opt',4,32,14.0)) t(word, mode, nodes, ops, n)")
def ops_bottomup_strings(spark, d):
    out = []
    for name, w in WORDS.items():
        c = np.bincount(np.frombuffer(w, np.uint8), minlength=256)
        for mode in sh.MODES:
            nodes, ops = sh.ops_bottomup(sh.build_shape(cb.huffman_lengths(c), mode), c)
            out.append((name, mode, nodes, ops, round(ops / len(w), 3)))
    return _strings_cost(spark, out)


def ops_report(hist: DataFrame, books: DataFrame, modes=sh.MODES) -> DataFrame:
    """(stream_id, mode, nodes, n, ops, ops_per_byte), a task per stream over its counts."""
    import pandas as pd

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        c = np.zeros(256, np.int64)
        c[pdf["sym"].to_numpy()] = pdf["cnt"].to_numpy()
        lengths = cb.unpack_lengths(bytes(pdf["lengths"].iloc[0]))
        rows = [(pdf["stream_id"].iloc[0], m, *sh.ops_bottomup(sh.build_shape(lengths, m), c), int(c.sum())) for m in modes]
        return pd.DataFrame([(s, m, k, n, o, round(o / n, 6)) for s, m, k, o, n in rows], columns=["stream_id", "mode", "nodes", "n", "ops", "ops_per_byte"])

    return hist.join(books, "stream_id").groupBy("stream_id").applyInPandas(one, "stream_id string, mode string, nodes int, n long, ops long, ops_per_byte double")


@query("ops_bottomup", "B6 W6", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(_LENS)))} SELECT stream_id, 'naive' AS mode, (count(*) - 1)::INT AS nodes, sum(cnt)::BIGINT AS n, sum(cnt * len)::BIGINT AS ops, round(sum(cnt * len) / sum(cnt), 6) AS ops_per_byte FROM hist JOIN codes USING (stream_id, sym) GROUP BY stream_id")
def ops_bottomup(spark, d):
    hist = hist_of(spark, d, _LENS)
    return ops_report(hist, stats.codebooks(hist, max_len=15, floor=4096), ("naive",))


@query("ops_bottomup_all", "W6")
def ops_bottomup_all(spark, d):
    """Nodes and operations per byte of every stream and shape."""
    from treepack.sources.streams import STREAMS

    hist = hist_of(spark, d, list(STREAMS))
    return ops_report(hist, stats.codebooks(hist))


@query("shape_order", "B5 I5", "SELECT * FROM (VALUES " + ", ".join(f"('{s}', true, true)" for s in ("doc_de", "doc_en", "doc_es", "doc_fr", "geom80", "html", "lq_f8", "ok_le8", "props", "userid_le8")) + ") t(stream_id, flat_not_above_naive, flat_opt_not_above_flat)")
def shape_order(spark, d):
    """Which shape wins: operations per byte fall from naive to flat to flat_opt. The last one regroups by lengths
    alone, blind to counts, so where flat finds the same subtrees it may cost some operations in ten thousand more."""
    names = ("doc_de", "doc_en", "doc_es", "doc_fr", "geom80", "html", "lq_f8", "ok_le8", "props", "userid_le8")
    hist = hist_of(spark, d, names)
    wide = ops_report(hist, stats.codebooks(hist)).groupBy("stream_id").pivot("mode", list(sh.MODES)).agg(F.first("ops"))
    return wide.select("stream_id", (F.col("flat") <= F.col("naive")).alias("flat_not_above_naive"), (F.col("flat_opt") <= F.col("flat") * 1.001).alias("flat_opt_not_above_flat"))


@query("shape_from_lengths_only", "B5r", "SELECT * FROM (VALUES (0,0,'','merge_vec_cst_or_vec',0), (1,1,'0','flat_2',2), (2,1,'1','merge_vec_cst',0), (3,2,'10','flat_2',2), (4,2,'11','leaf',0)) t(node_id, depth, prefix, op, d)".replace("merge_vec_cst_or_vec", "merge_vec_vec"))
def shape_from_lengths_only(spark, d):
    c = np.bincount(np.frombuffer(WORDS["coconut-papaya"], np.uint8), minlength=256)
    rows = sh.plan_rows(sh.build_shape(cb.unpack_lengths(cb.pack_lengths(cb.huffman_lengths(c))), "flat_opt"))
    return spark.createDataFrame([(k, depth, p, op, dd) for k, depth, p, op, _, _, dd, _ in rows], "node_id int, depth int, prefix string, op string, d int")


@query("two_symbol_nodes_gated", "B8", "SELECT 'merge_cst_cst' AS op, true AS coded, true AS smaller")
def two_symbol_nodes_gated(spark, d):
    """A stream of two symbols stays one binary node, which skew lets be entropy-coded."""
    from treepack.operators.codec import encode_batch
    from treepack.plans.selective import Gates

    raw = (b"a" * 9 + b"b") * 800
    lengths = cb.pack_lengths(cb.fit_lengths(np.bincount(np.frombuffer(raw, np.uint8), minlength=256)))
    marks: list = []
    coded, plain = encode_batch([raw], lengths, gates=Gates(), markers=marks), encode_batch([raw], lengths)
    op = sh.operation(sh.shape_of(lengths))
    return spark.createDataFrame([(op, marks[0][4] > 0, len(coded[0]) < len(plain[0]))], "op string, coded boolean, smaller boolean")


@query("alphabet_report", "M6 W17", f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(_LENS)))} SELECT stream_id, count(*)::BIGINT AS symbols, min(len)::INT AS min_len, max(len)::INT AS max_len FROM lens GROUP BY stream_id")
def alphabet_report(spark, d):
    hist = hist_of(spark, d, _LENS)
    r = stats.entropy_report(hist, codes_of(stats.codebooks(hist, max_len=15, floor=4096)))
    return r.select("stream_id", "symbols", "min_len", "max_len")


_ENTROPY = f"""WITH RECURSIVE {sql.codes(sql.hist(sql.rows(_LENS)))}, t AS (SELECT stream_id, sum(cnt) AS n FROM hist GROUP BY 1),
r AS (SELECT stream_id, sum(-cnt / n * log2(cnt / n)) AS h, sum(cnt / n * len) AS l, any_value(n)::BIGINT AS n FROM hist JOIN codes USING (stream_id, sym) JOIN t USING (stream_id) GROUP BY 1)
SELECT stream_id, n, round(h, 6) AS h, round(l, 6) AS l, round(h / l, 6) AS efficiency, round(l - h, 6) AS gap FROM r"""


@query("entropy_report", "M1-M3", _ENTROPY)
def entropy_report(spark, d):
    hist = hist_of(spark, d, _LENS)
    return stats.entropy_report(hist, codes_of(stats.codebooks(hist, max_len=15, floor=4096))).select("stream_id", "n", "h", "l", "efficiency", "gap")
