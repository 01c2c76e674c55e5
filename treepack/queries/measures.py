"""Cost and accuracy measures, and the experiments as reports."""

from __future__ import annotations

import re
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from treepack.functions import fsm, kernels
from treepack.operators import baselines, codec, stats
from treepack.operators.blocks import encode_blocks
from treepack.plans import codebook as cb
from treepack.plans import shape as sh
from treepack.plans.selective import Gates, gate_nodes, skew_report
from treepack.queries import sql
from treepack.queries.common import codes_of, hist_of, sizes
from treepack.registry import query
from treepack.sources.streams import STREAMS, build_streams, to_blocks
from treepack.sources.tables import load, small, staged

HEADLINE = ("geom80", "userid_le8", "acgt", "okdelta", "letters", "doc_en", "html", "evjson", "emb_f4", "mixskew")


@query("entropy_gap_report", "W10 M1-M4")
def entropy_gap_report(spark, d):
    """Every stream's entropy, code length, gap, and the largest saving of one node."""
    hist = hist_of(spark, d, list(STREAMS))
    codes = codes_of(stats.codebooks(hist))
    top = skew_report(hist, codes).groupBy("stream_id").agg(F.round(F.max("saving"), 6).alias("top_node"))
    return stats.entropy_report(hist, codes).join(top, "stream_id")


def ratios(spark, d, names):
    """Bytes of each stream under the four codecs."""
    blocks = staged(to_blocks(build_streams(spark, d, names)))  # read by the count and by every codec
    books = staged(stats.codebooks(stats.byte_histogram(blocks)))
    ways = {"node-bitmaps": {}, "node-bitmaps-ans": dict(gates=Gates()), "classic": dict(encoder=baselines.encode_classic), "ans": dict(encoder=lambda raws, lengths: baselines.encode_tans(raws))}
    out = None
    for name, how in ways.items():
        s = sizes(encode_blocks(blocks, books, **how)).withColumn("codec", F.lit(name))
        out = s if out is None else out.unionByName(s)
    return out


@query("ratio_report", "M7 W12")
def ratio_report(spark, d):
    return ratios(spark, d, HEADLINE)


@query("ratio_relations", "M7 W12 I14", "SELECT * FROM (VALUES ('acgt', true, true, true), ('doc_en', false, true, true), ('geom80', true, true, true), ('okdelta', true, true, true), ('userid_le8', true, true, true)) t(stream_id, gates_gain_over_5_percent, gates_never_lose, near_classic)")
def ratio_relations(spark, d):
    """Which codec wins: gates gain on skewed streams, change text little, never lose; padding and headers cost little next to classic codes."""
    r = ratios(spark, d, ("acgt", "doc_en", "geom80", "okdelta", "userid_le8")).groupBy("stream_id").pivot("codec", ["node-bitmaps", "node-bitmaps-ans", "classic"]).agg(F.first("enc_bytes"))
    a, b, c = F.col("node-bitmaps"), F.col("node-bitmaps-ans"), F.col("classic")
    return r.select("stream_id", (b < a * 0.95).alias("gates_gain_over_5_percent"), (b <= a).alias("gates_never_lose"), (a < c * 1.08).alias("near_classic"))


@query("padding_report", "M15", f"""WITH RECURSIVE src AS MATERIALIZED ({sql.rows(['doc_de'])}), {sql.codes(sql.hist('SELECT * FROM src'))},
bits AS (SELECT value_id, pos // 8192 AS block_no, left(code, x.d) AS prefix FROM src JOIN codes USING (stream_id, sym), unnest(range(len)) AS x(d)), node AS (SELECT count(*) AS n FROM bits GROUP BY value_id, block_no, prefix)
SELECT 'doc_de' AS stream_id, count(*)::BIGINT AS bitmaps, sum(n)::BIGINT AS bits, sum(8 * ((n + 7) // 8) - n)::BIGINT AS padding_bits FROM node""")
def padding_report(spark, d):
    from treepack.queries.codec import _marker_rows

    m = _marker_rows(spark, d, None)
    return m.agg(F.count("*").alias("bitmaps"), F.sum("n").alias("bits"), F.sum(8 * F.col("body") - F.col("n")).alias("padding_bits")).select(F.lit("doc_de").alias("stream_id"), "bitmaps", "bits", "padding_bits")


_LANGS = ("doc_de", "doc_fr", "doc_es")


@query("op_mix_report", "M17", f"""WITH RECURSIVE {sql.codes(sql.hist(sql.rows(_LANGS)))}, leaf AS (SELECT stream_id, code FROM codes),
inner_ AS (SELECT stream_id, left(code, x.d) AS prefix, sum(cnt) AS n FROM hist JOIN codes USING (stream_id, sym), unnest(range(len)) AS x(d) GROUP BY ALL)
SELECT i.stream_id, 'merge_' || CASE WHEN l.code IS NULL THEN 'vec' ELSE 'cst' END || '_' || CASE WHEN r.code IS NULL THEN 'vec' ELSE 'cst' END AS op, count(*)::BIGINT AS nodes, sum(n)::BIGINT AS elements
FROM inner_ i LEFT JOIN leaf l ON l.stream_id = i.stream_id AND l.code = i.prefix || '0' LEFT JOIN leaf r ON r.stream_id = i.stream_id AND r.code = i.prefix || '1' GROUP BY ALL""")
def op_mix_report(spark, d):
    """Elements through each kind of merge, naive shape."""
    return op_mix(hist_of(spark, d, _LANGS), "naive")


def op_mix(hist, mode: str):
    import pandas as pd

    def one(pdf):
        c = np.zeros(256, np.int64)
        c[pdf["sym"].to_numpy()] = pdf["cnt"].to_numpy()
        root = sh.build_shape(cb.unpack_lengths(bytes(pdf["lengths"].iloc[0])), mode)
        w = sh.weights(root, c)
        rows = [(pdf["stream_id"].iloc[0], sh.operation(n), 1, w[n.prefix]) for n in root.walk() if not n.leaf]
        return pd.DataFrame(rows, columns=["stream_id", "op", "nodes", "elements"]).groupby(["stream_id", "op"], as_index=False).sum()

    return hist.join(stats.codebooks(hist, max_len=15, floor=4096), "stream_id").groupBy("stream_id").applyInPandas(one, "stream_id string, op string, nodes long, elements long")


@query("op_mix_flat_opt", "M17")
def op_mix_flat_opt(spark, d):
    return op_mix(hist_of(spark, d, list(HEADLINE)), "flat_opt")


@query("kernel_traffic", "M11", "SELECT * FROM (VALUES ('merge_vec_vec', 17, 8, 9), ('merge_cst_cst', 1, 8, 0), ('merge_cst_vec', 9, 8, 9), ('flat_2', 2, 8, 8), ('flat_3', 3, 8, 8), ('flat_4', 4, 8, 8), ('flat_5', 5, 8, 8), ('flat_6', 6, 8, 8), ('flat_7', 7, 8, 8), ('flat_8', 8, 8, 8)) t(kernel, in_bits, out_bits, lut_bits)")
def kernel_traffic(spark, d):
    return spark.createDataFrame([(k, *v) for k, v in kernels.TRAFFIC.items()], "kernel string, in_bits int, out_bits int, lut_bits int")


def timed(fn, n: int, runs: int = 5, clock=time.perf_counter) -> float:
    """ns per element, the best of a few runs."""
    best = float("inf")
    for _ in range(runs):
        t = clock()
        fn()
        best = min(best, clock() - t)
    return best / n * 1e9


def over_users(spark, d, fn, keys: str):
    """fn(users) gives (key.., seconds, elements) for a part of the users of all events; (key.., ns per element) over the whole table."""
    names = [k.split()[0] for k in keys.split(", ")]

    def run(batches):
        part, size, total = [], 0, {}

        def flush():
            for *key, seconds, n in fn(np.concatenate(part)):
                at = total.setdefault(tuple(key), [0.0, 0])
                at[0], at[1] = at[0] + seconds, at[1] + n

        for b in batches:
            part.append(b.column("user_id").to_numpy(zero_copy_only=False))
            size += b.num_rows
            if size >= 1 << 17:
                flush()
                part, size = [], 0
        if size:
            flush()
        if total:
            columns = [*zip(*total, strict=True), *zip(*total.values(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=[*names, "seconds", "elements"])

    users = load(spark, d, "events").where("user_id is not null").select(F.col("user_id").cast("long").alias("user_id"))
    return users.mapInArrow(run, f"{keys}, seconds double, elements long").groupBy(*names).agg((F.sum("seconds") / F.sum("elements") * 1e9).alias("ns"))


def once(fn) -> float:
    t = time.perf_counter()
    fn()
    return time.perf_counter() - t


def kernel_times(users: np.ndarray) -> list[tuple[str, float, int]]:
    """(kernel, seconds, elements) on the bytes of the users; the loops take them by blocks of 8192."""
    data = users.astype("<i8").view(np.uint8)
    bits, n = data % 5 < 2, len(data)
    idx = np.arange(n, dtype=np.int64)
    left, right, out = data[~bits], data[bits], np.zeros(n, np.uint8)
    parts = [(bits[a : a + 8192], np.arange(len(bits[a : a + 8192]), dtype=np.uint16)) for a in range(0, n, 8192)]
    rows = {
        "partition vector": (lambda: kernels.partition(bits, idx), n), "partition loop": (lambda: [kernels.partition(*x, "loop") for x in parts], n), "partition branchfree": (lambda: [kernels.partition(*x, "branchfree") for x in parts], n),
        "partition half": (lambda: kernels.partition_half(bits, idx, True), n), "scatter one": (lambda: kernels.scatter_one(out, idx, 7), n), "scatter two": (lambda: kernels.scatter_two(out, idx, bits, 3, 9), n),
        "scatter flat": (lambda: kernels.scatter_flat(out, idx, data & 15, data[:16]), n), "merge vec-vec": (lambda: kernels.merge_vec_vec(bits, left, right), n), "merge cst-vec": (lambda: kernels.merge_cst_vec(bits, 3, right), n),
        "merge cst-cst": (lambda: kernels.merge_cst_cst(bits, 3, 9), n), "merge plus one": (lambda: kernels.merge_vec_cst_plus1(bits, left), n),
        **{f"flat {k}": (lambda k=k, p=kernels.pack_codes(data & ((1 << k) - 1), k, np.array([n]))[0]: kernels.merge_flat(kernels.unpack_codes(p, k, np.array([n])), data[:256]), n) for k in range(2, 9)},
    }
    return [(k, once(f), m) for k, (f, m) in rows.items()]


@query("kernel_bench", "M10 W4 W7")
def kernel_bench(spark, d):
    """ns per element of each kernel, over the bytes of all events' users."""
    return over_users(spark, d, kernel_times, "kernel string").select("kernel", F.round("ns", 4).alias("ns_per_element"))


def speeds(raws: list[bytes], lengths: bytes, runs: int = 2, like: str = "") -> list[tuple[str, float]]:
    """MB/s of each codec whose name has `like` in it, encode and decode, on blocks in memory, after one call to warm up; the best of a few runs."""
    total, n = sum(map(len, raws)) / 1e6, [len(r) for r in raws]
    out = []

    def rate(name, fn):
        got = fn()
        if re.search(like, name):
            out.append((name, round(1000 / timed(fn, sum(n), runs), 2)))
        return got

    for shape in sh.MODES:
        e = rate(f"node-bitmaps {shape} encode", lambda s=shape: codec.encode_batch(raws, lengths, s))
        rate(f"node-bitmaps {shape} bottom-up", lambda s=shape, e=e: codec.decode_batch(e, n, lengths, s))
        rate(f"node-bitmaps {shape} top-down", lambda s=shape, e=e: codec.decode_batch(e, n, lengths, s, "topdown"))

    def end_to_end():
        counts = np.bincount(np.frombuffer(b"".join(raws), np.uint8), minlength=256)
        return codec.encode_batch(raws, cb.pack_lengths(cb.fit_lengths(counts)))

    rate("node-bitmaps encode, counting and code too", end_to_end)
    e = rate("node-bitmaps-ans encode", lambda: codec.encode_batch(raws, lengths, gates=Gates()))
    rate("node-bitmaps-ans bottom-up", lambda: codec.decode_batch(e, n, lengths, gates=Gates()))
    c = rate("classic encode", lambda: baselines.encode_classic(raws, lengths))
    rate("classic table", lambda: baselines.decode_table(c, n, lengths))
    rate("classic table, two symbols", lambda: baselines.decode_table(c, n, lengths, symbols_per_step=2))
    c4 = rate("classic encode, 4 cursors", lambda: baselines.encode_classic(raws, lengths, 4))
    rate("classic table, 4 cursors", lambda: baselines.decode_table(c4, n, lengths, cursors=4))
    if re.search(like, "classic bit by bit"):
        few, m = c[:4], n[:4]
        t = time.perf_counter()
        baselines.decode_bitwise(few, m, lengths)
        out.append(("classic bit by bit", round(sum(m) / 1e6 / (time.perf_counter() - t), 3)))
    return out


@query("bench_codecs", "W1-W3 W5 W8 W9 W12 M8 M9 M12")
def bench_codecs(spark, d):
    """MB/s of every codec and decoder on one core, of every stream. The views below measure their parts anew.

    What is timed is a bounded number of blocks of each stream, which is all a rate needs; codes come from the whole stream.
    """
    return codec_rates(spark, d, list(STREAMS))


def codec_rates(spark, d, names, blocks_each: int = 128, like: str = ""):
    import pandas as pd

    blocks = to_blocks(build_streams(spark, d, names)).where("n > 0")
    sized = blocks.groupBy("stream_id").agg(F.count("*").alias("all_blocks"))
    # an even hash below a bound that the stream's count sets: about as many blocks of each, wherever they lie
    even = F.shiftrightunsigned(F.xxhash64("value_id", "block_no"), 1) / F.lit(float(1 << 63))
    some = blocks.join(small(sized), "stream_id").where(even * F.col("all_blocks") <= blocks_each).drop("all_blocks")
    rows = some.join(small(stats.codebooks(hist_of(spark, d, names))), "stream_id")

    def one(pdf):
        raws = [bytes(r) for r in pdf["raw"]]
        got = speeds(raws, bytes(pdf["lengths"].iloc[0]), like=like)
        return pd.DataFrame([(pdf["stream_id"].iloc[0], len(raws), k, v) for k, v in got], columns=["stream_id", "blocks", "what", "mb_s"])

    return rows.groupBy("stream_id").applyInPandas(one, "stream_id string, blocks int, what string, mb_s double")


def _part(name: str, section: str, like: str):
    """A named part of the codec report."""

    def run(spark, d):
        return codec_rates(spark, d, list(STREAMS), like=like)

    query(name, section)(run)


_part("bench_baselines", "W1", "^classic")
_part("bench_td_naive", "W2", "naive top-down|classic table")
_part("bench_td_tree", "W3", "top-down")
_part("bench_bu", "W8", "bottom-up|classic table")
_part("bench_encode", "W9", "encode")
_part("bench_ans", "W12", "ans|flat_opt bottom-up")
query("bench_kernels_td", "W4")(lambda spark, d: kernel_bench(spark, d).where("kernel like 'partition%' or kernel like 'scatter%'"))
query("bench_kernels_bu", "W7")(lambda spark, d: kernel_bench(spark, d).where("kernel like 'merge%' or kernel like 'flat%'"))


@query("bench_td_grid", "W5 H13 M16")
def bench_td_grid(spark, d):
    """MB/s of top-down decoding, tree by primitive, on the lowest set bits of all events' users (0 to 5, each half as frequent)."""

    def run(users):
        low = np.minimum(5, np.bitwise_count((users & -users) - 1)).astype(np.uint8).tobytes()
        raws = [low[i : i + 8192] for i in range(0, len(low), 8192)]
        n, lengths = [len(r) for r in raws], cb.pack_lengths(cb.fit_lengths(np.bincount(np.frombuffer(low, np.uint8), minlength=256)))
        for tree in ("naive", "flat_opt"):
            enc = codec.encode_batch(raws, lengths, tree)
            for impl in ("loop", "branchfree", "vector"):
                how = dict(prefill=tree != "naive", fuse=tree != "naive", impl=impl)
                yield tree, impl, once(lambda e=enc, t=tree, h=how: codec.decode_batch(e, n, lengths, t, "topdown", **h)), len(low)

    return over_users(spark, d, run, "tree string, primitive string").select("tree", "primitive", F.round(1000 / F.col("ns"), 3).alias("mb_s"))


@query("bench_scaling", "W14")
def bench_scaling(spark, d):
    """Seconds to encode and decode the same blocks in one, two, four and eight partitions: work is map-only, so it divides."""
    from treepack.operators.blocks import decode_blocks

    names = ["doc_en", "html"]
    blocks = staged(to_blocks(build_streams(spark, d, names)))
    books = staged(stats.codebooks(hist_of(spark, d, names)))
    rows = []
    for parts in (1, 2, 4, 8):
        some = staged(blocks.repartition(parts))
        t = time.perf_counter()
        decode_blocks(encode_blocks(some, books)).write.format("noop").mode("overwrite").save()
        rows.append((parts, round(time.perf_counter() - t, 3)))
    return spark.createDataFrame(rows, "partitions int, seconds double")


@query("bench_tans_cursors", "W15 F16")
def bench_tans_cursors(spark, d):
    """MB/s of tabled ANS by cursors and unrolling: which events' users divide by five, in bitmaps of 2880 bytes of about 80 % zeros."""

    def run(users):
        data = np.packbits(users % 5 == 0)
        n = np.diff(np.append(np.arange(0, len(data), 2880), len(data)))
        t = np.full(len(n), 30)
        for x in (2, 4, 6, 8, 10, 12, 16):
            e = fsm.encode(data, n, t, fsm.static_tables(), x)
            for y in (1, 2, 4):
                yield x, y, once(lambda e=e, x=x, y=y: fsm.decode(e, n, t, fsm.static_tables(), x, y)), len(data)

    return over_users(spark, d, run, "cursors long, unroll long").select(F.col("cursors").cast("int").alias("cursors"), F.col("unroll").cast("int").alias("unroll"), F.round(1000 / F.col("ns"), 2).alias("mb_s"))


@query("bench_golomb", "W16 H12")
def bench_golomb(spark, d):
    """ns per symbol of the four unary decoders: remainders of all events' users, whose mean code length is (modulus + 1) / 2 where they are even."""
    from treepack.operators import unary

    def run(users):
        for m in (2, 3, 4, 6, 8, 9):
            g = users % m
            bits, packed = unary.plain_bits(g), unary.to_bytes(g)
            ways = {"naive": lambda b=bits, n=len(g): unary.decode_naive(b, n), "byte_table": lambda b=bits, n=len(g): unary.decode_bytetable(b, n), "byte_table_branch_free": lambda b=bits, n=len(g): unary.decode_bytetable(b, n, True), "pivoted": lambda p=packed: unary.from_bytes(p)}
            yield from (((m + 1) / 2, name, once(f), len(g)) for name, f in ways.items())

    wide = over_users(spark, d, run, "mean_code_length double, way string").groupBy("mean_code_length").pivot("way", ["naive", "byte_table", "byte_table_branch_free", "pivoted"]).agg(F.first("ns"))
    return wide.select("mean_code_length", *(F.round(c, 2).alias(c) for c in wide.columns[1:]))


@query("speed_order", "W2 W8", "SELECT * FROM (VALUES ('doc_en', true, true), ('geom80', true, true)) t(stream_id, bitmaps_beat_table, table_beats_bitwise)")
def speed_order(spark, d):
    """Which decoder wins: merging bitmaps over table lookups over bit by bit."""
    wide = codec_rates(spark, d, ["doc_en", "geom80"], like="flat_opt bottom-up|^classic table$|bit by bit").groupBy("stream_id").pivot("what", ["node-bitmaps flat_opt bottom-up", "classic table", "classic bit by bit"]).agg(F.first("mb_s"))
    return wide.select("stream_id", (F.col("node-bitmaps flat_opt bottom-up") > F.col("classic table")).alias("bitmaps_beat_table"), (F.col("classic table") > F.col("classic bit by bit")).alias("table_beats_bitwise"))


_ALL = ", ".join(f"('{x}')" for x in STREAMS)


@query("entropy_gap_relations", "W10 M1-M4", f"SELECT stream_id, true AS entropy_below_length, true AS gap_under_one_bit, true AS node_within_gap FROM (VALUES {_ALL}) t(stream_id)")
def entropy_gap_relations(spark, d):
    """Of every stream: codes are no shorter than the entropy, lose less than a bit, and no node saves more than the whole gap."""
    r = entropy_gap_report(spark, d)
    h, length, gap = F.col("h"), F.col("l"), F.col("gap")
    return r.select("stream_id", (h <= length + 1e-6).alias("entropy_below_length"), (gap < 1).alias("gap_under_one_bit"), (F.col("top_node") <= gap + 1e-5).alias("node_within_gap"))


@query("gated_nodes_relations", "W11 M13", "SELECT * FROM (VALUES ('acgt'), ('geom80'), ('lq_f8'), ('okdelta'), ('userid_le8')) t(stream_id)")
def gated_nodes_relations(spark, d):
    """The skewed streams, of which each has a node that the gates let through."""
    return gated_nodes_report(spark, d).select("stream_id").distinct()


@query("gated_nodes_report", "W11 M13")
def gated_nodes_report(spark, d):
    hist = hist_of(spark, d, ("userid_le8", "acgt", "geom80", "okdelta", "lq_f8"))
    return gate_nodes(skew_report(hist, codes_of(stats.codebooks(hist)))).where("gated")


