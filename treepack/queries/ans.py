"""Selective entropy coding of node bitmaps: skew, gates, tables, cursors."""

from __future__ import annotations


import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from treepack.functions import fsm
from treepack.operators import codec, stats
from treepack.operators.blocks import decode_blocks
from treepack.plans import selective
from treepack.plans.selective import Gates
from treepack.queries import sql
from treepack.queries.common import codes_of, digests, encoded, hist_of, roundtrip, sizes
from treepack.registry import query
from treepack.sources.tables import load, staged

_LANGS = ("doc_de", "doc_fr", "doc_es")


def _nodes(spark, d, names):
    hist = hist_of(spark, d, names)
    return selective.skew_report(hist, codes_of(stats.codebooks(hist, max_len=15, floor=4096)))


_BASE = f"WITH RECURSIVE {sql.codes(sql.hist(sql.rows(_LANGS)))}, {sql.NODES}, tot AS (SELECT stream_id, sum(cnt) AS total FROM hist GROUP BY 1), rep AS (SELECT stream_id, prefix, depth, n, n_right, greatest(n_right / n, 1 - n_right / n) AS skew, CASE WHEN n_right = 0 OR n_right = n THEN 0.0 ELSE -((n_right / n) * log2(n_right / n) + (1 - n_right / n) * log2(1 - n_right / n)) END AS h, total FROM nodes_ JOIN tot USING (stream_id)) "


@query("node_skew_report", "F2 M4 M13 W11", _BASE + "SELECT stream_id, prefix, depth, n, n_right, round(skew, 6) AS skew, round(h, 6) AS h, round(n / total * (1 - h), 6) AS saving FROM rep")
def node_skew_report(spark, d):
    r = _nodes(spark, d, _LANGS)
    return r.select("stream_id", "prefix", "depth", "n", "n_right", *(F.round(c, 6).alias(c) for c in ("skew", "h", "saving")))


@query("redundancy_decomposition", "F3", _BASE + ", l AS (SELECT stream_id, sum(cnt * len) / sum(cnt) AS l FROM hist JOIN codes USING (stream_id, sym) GROUP BY 1), e AS (SELECT stream_id, sum(-cnt / total * log2(cnt / total)) AS h FROM hist JOIN tot USING (stream_id) GROUP BY 1) SELECT stream_id, round(l - h, 6) AS gap, true AS savings_equal_gap FROM l JOIN e USING (stream_id)")
def redundancy_decomposition(spark, d):
    """The sum of all nodes' savings is the distance of the code from entropy."""
    hist = hist_of(spark, d, _LANGS)
    codes = codes_of(stats.codebooks(hist, max_len=15, floor=4096))
    gap = stats.entropy_report(hist, codes).select("stream_id", "gap")
    saved = selective.skew_report(hist, codes).groupBy("stream_id").agg(F.sum("saving").alias("saved"))
    return gap.join(saved, "stream_id").select("stream_id", "gap", (F.abs(F.col("saved") - F.col("gap")) < 2e-6).alias("savings_equal_gap"))


@query("ans_gate_nodes", "F4-F6", _BASE + "SELECT stream_id, prefix, (floor(n * 8192 / total) >= 256 AND skew > 0.625 AND (depth + h) / (depth + 1) < 0.95) AS gated FROM rep")
def ans_gate_nodes(spark, d):
    return selective.gate_nodes(_nodes(spark, d, _LANGS)).select("stream_id", "prefix", "gated")


#: example -> (rows of a node, which of them go right, depth), by blocks of 8192 events
_EXAMPLES = {
    "a fifth at depth 2, nine in ten one way": ("event_type = 'view'", "user_id % 10 = 0", 2),
    "a hundredth of a block": ("event_id % 100 = 7", "user_id % 20 = 0", 3),
    "a fifth at depth 5, a twelfth of a bit saved": ("event_type = 'error'", "user_id % 3 = 0", 5),
}
_EXAMPLE_COUNTS = " UNION ALL ".join(f"SELECT '{k}' AS example, {depth} AS depth, event_id {{div}} 8192 AS page, count(*) AS n, sum(CASE WHEN {right} THEN 1 ELSE 0 END) AS n_right FROM {{events}} WHERE {node} GROUP BY 3" for k, (node, right, depth) in _EXAMPLES.items())


@query("ans_gate_examples", "F6", f"""WITH c AS (SELECT *, greatest(n_right, n - n_right) / n AS major FROM ({_EXAMPLE_COUNTS.format(div="//", events="events")}))
SELECT example, page::BIGINT AS page, n::BIGINT AS n, n_right::BIGINT AS n_right, n >= 256 AND major > 0.625 AND (depth + CASE WHEN major = 1 THEN 0 ELSE -(major * log2(major) + (1 - major) * log2(1 - major)) END) / (depth + 1) < 0.95 AS coded FROM c""")
def ans_gate_examples(spark, d):
    """The gates on nodes of events: one they let through, one too small, one that saves too little."""
    counts = spark.sql(_EXAMPLE_COUNTS.format(div="div", events="{events}"), events=load(spark, d, "events"))

    def run(batches):
        for b in batches:
            n, right = (b.column(c).to_numpy() for c in ("n", "n_right"))
            ok = [bool(passes[0]) for passes in (selective.passes(n[i : i + 1], right[i : i + 1], k, Gates()) for i, k in enumerate(b.column("depth").to_pylist()))]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("example", "page", "n", "n_right")), pa.array(ok, pa.bool_())], names=["example", "page", "n", "n_right", "coded"])

    return counts.mapInArrow(run, "example string, page long, n long, n_right long, coded boolean")


@query("skewed_streams", "W10 W11", "SELECT * FROM (VALUES ('acgt', true), ('doc_en', false), ('geom80', true), ('html', false), ('okdelta', true), ('userid_le8', true)) t(stream_id, skewed)")
def skewed_streams(spark, d):
    """Which streams the gates pick on their counts: those where one or two nodes hold most of the gap."""
    g = selective.gate_nodes(_nodes(spark, d, ("acgt", "doc_en", "geom80", "html", "okdelta", "userid_le8")))
    return g.groupBy("stream_id").agg((F.coalesce(F.sum(F.when(F.col("gated"), F.col("saving"))), F.lit(0.0)) > 0.05).alias("skewed"))


@query("tans_roundtrip", "F1", sql.md5_of(["doc_fr"]))
def tans_roundtrip(spark, d):
    from treepack.operators import baselines

    enc = encoded(spark, d, ["doc_fr"], encoder=lambda raws, lengths: baselines.encode_tans(raws))
    return digests(decode_blocks(enc, decode=baselines.decode_tans))


@query("static_table_costs", "F9", "SELECT p, round(-(p / 100.0 * log2(p / 100.0) + (1 - p / 100.0) * log2(1 - p / 100.0)), 6) AS entropy, true AS close FROM range(50, 100) r(p)")
def static_table_costs(spark, d):
    """Expected bits per bit of each static table against the entropy: within 2 % of a bit."""
    costs = [(p, float(c)) for p, c in zip(range(50, 100), fsm.bit_costs(), strict=True)]
    rows = spark.createDataFrame(costs, "p long, cost double")
    q = F.col("p") / 100.0
    h = -(q * F.log2(q) + (1 - q) * F.log2(1 - q))
    return rows.select("p", F.round(h, 6).alias("entropy"), (F.col("cost").between(h - 1e-9, h + 0.02)).alias("close"))


@query("ans_roundtrip", "E3 F5", sql.md5_of(["doc_en"]))
def ans_roundtrip(spark, d):
    return roundtrip(spark, d, ["doc_en"], gates=Gates())


@query("ans_topdown_roundtrip", "E2 F5", sql.md5_of(["doc_de"]))
def ans_topdown_roundtrip(spark, d):
    return roundtrip(spark, d, ["doc_de"], gates=Gates(), decoder="topdown")


@query("ans_stream_scope_roundtrip", "F7", sql.md5_of(["doc_de"]))
def ans_stream_scope_roundtrip(spark, d):
    return roundtrip(spark, d, ["doc_de"], gates=Gates(scope="stream", min_skew=0.5), with_hist=True)


def _event_bits(spark, d, rows: int, test: str):
    """(page, bits) of blocks of `rows` events in order: a byte 1 where the test holds, else 0."""
    bit = F.struct("event_id", F.coalesce(F.expr(test), F.lit(False)).cast("byte").alias("b"))
    pages = load(spark, d, "events").groupBy(F.expr(f"event_id div {rows}").alias("page")).agg(F.array_sort(F.collect_list(bit)).alias("r"))
    return pages.select("page", F.transform("r", lambda x: x["b"]).alias("bits"))


@query("ans_xor_marker", "F11", "SELECT event_id // 8192 AS page, m AS mostly, true AS coded_if_large, true AS complements, true AS same, true AS equal_size FROM events, (VALUES ('zeros'), ('ones')) t(m) GROUP BY 1, 2")
def ans_xor_marker(spark, d):
    """Complementing a bitmap (views among 8192 events) flips the marker's top bit and nothing else."""
    from treepack.plans import codebook as cb

    lengths = cb.pack_lengths(cb.fit_lengths(np.bincount([97, 98], minlength=256)))

    def run(batches):
        for b in batches:
            views = [np.array(x, bool) for x in b.column("bits").to_pylist()]
            got = {}
            for name, all_ in (("zeros", views), ("ones", [~x for x in views])):
                raws = [np.where(x, 98, 97).astype(np.uint8).tobytes() for x in all_]
                marks: list = []
                enc = codec.encode_batch(raws, lengths, gates=Gates(), markers=marks)
                back = codec.decode_batch(enc, [len(r) for r in raws], lengths, gates=Gates())
                got[name] = {m[0]: (m[4], len(enc[m[0]]), back[m[0]] == raws[m[0]]) for m in marks if m[1] == ""}
            rows = []
            for i, page in enumerate(b.column("page").to_pylist()):
                zero, one = got["zeros"][i], got["ones"][i]
                flips = zero[0] ^ one[0] == (0x80 if zero[0] else 0)
                rows += [(page, name, got[name][i][0] & 0x7F > 0 or len(views[i]) < 1024, flips and (got[name][i][0] >= 0x80) == (name == "ones" and one[0] > 0), got[name][i][2], zero[1] == one[1]) for name in ("zeros", "ones")]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], names=["page", "mostly", "coded_if_large", "complements", "same", "equal_size"])

    return _event_bits(spark, d, 8192, "event_type = 'view'").mapInArrow(run, "page long, mostly string, coded_if_large boolean, complements boolean, same boolean, equal_size boolean")


def _better(name, section, streams, left: Gates | None, right: Gates | None, expect: dict[str, bool], with_hist=False):
    """Sizes under two settings; `expect`: where the second is smaller."""
    values = ", ".join(f"('{s}', {str(v).lower()})" for s, v in sorted(expect.items()))

    def run(spark, d):
        a = sizes(encoded(spark, d, streams, gates=left, with_hist=with_hist)).select("stream_id", F.col("enc_bytes").alias("a"))
        b = sizes(encoded(spark, d, streams, gates=right, with_hist=with_hist)).select("stream_id", F.col("enc_bytes").alias("b"))
        return a.join(b, "stream_id").select("stream_id", (F.col("b") < F.col("a")).alias("second_smaller"))

    query(name, section, f"SELECT * FROM (VALUES {values}) t(stream_id, second_smaller)")(run)


_better("ans_gate_scope_compare", "F7", ["geom80", "doc_en"], Gates(scope="stream"), Gates(scope="block"), {"geom80": False, "doc_en": True}, True)
_better("ans_local_vs_global", "F14 W12", ["mixskew"], Gates(scope="stream"), Gates(), {"mixskew": True}, True)
_better("ans_beats_plain", "I14 W12", ["geom80", "okdelta", "userid_le8"], None, Gates(), {"geom80": True, "okdelta": True, "userid_le8": True})
_better("ans_two_cursors", "F16", ["userid_le8"], Gates(), Gates(cursors=2), {"userid_le8": True})


@query("ans_gate_sweep", "F15")
def ans_gate_sweep(spark, d):
    """Size against gates: looser gates code more nodes."""
    out = None
    for skew in (0.55, 0.625, 0.75, 0.9):
        for cost in (0.8, 0.95, 0.99):
            s = sizes(encoded(spark, d, ["geom80", "acgt"], gates=Gates(min_skew=skew, max_cost_ratio=cost))).withColumns({"min_skew": F.lit(skew), "max_cost_ratio": F.lit(cost)})
            out = s if out is None else out.unionByName(s)
    return out


@query("ans_static_vs_custom", "F13 W19", """WITH c AS (SELECT event_id // 1024 AS page, count(*) AS n, sum(CASE WHEN event_type <> 'view' THEN 1 ELSE 0 END) AS k FROM events GROUP BY 1),
p AS (SELECT *, least(greatest(floor(100 * greatest(k, n - k) / n + 0.5), 50), 99) / 100 AS s FROM c)
SELECT page, n::BIGINT AS n, k::BIGINT AS k, round(CASE WHEN k = 0 OR k = n THEN 0 ELSE -(k * log2(k / n) + (n - k) * log2(1 - k / n)) END, 1)::DOUBLE AS custom_bits, round(-8 * (greatest(k, n - k) * log2(s) + least(k, n - k) * log2(1 - s)), 1)::DOUBLE AS static_bits, true AS custom_smaller FROM p""")
def ans_static_vs_custom(spark, d):
    """Blocks of 1024 events, a byte FF for each that is no view, else 00: a table made from them against the static one for their share of equal bits, in ideal bits."""

    def run(batches):
        for b in batches:
            rows = []
            for page, bits in zip(b.column("page").to_pylist(), b.column("bits").to_pylist(), strict=True):
                x = np.array(bits, np.uint8) * 255
                n, k = len(x), int((x > 0).sum())
                ids, flip = selective.choose_table(np.array([n]), np.array([k]))
                custom, s = 0.0 if k in (0, n) else -(k * np.log2(k / n) + (n - k) * np.log2(1 - k / n)), (ids[0] + 49) / 100
                static = -8 * (max(k, n - k) * np.log2(s) + min(k, n - k) * np.log2(1 - s))
                sizes_ = len(codec.custom_encode(x, Gates(cursors=1))), len(fsm.encode(~x if flip[0] else x, np.array([n]), ids - 1, fsm.static_tables(), 1)[0])
                rows.append((page, n, k, round(float(custom), 1), round(float(static), 1), sizes_[0] < sizes_[1]))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], names=["page", "n", "k", "custom_bits", "static_bits", "custom_smaller"])

    return _event_bits(spark, d, 1024, "event_type <> 'view'").mapInArrow(run, "page long, n long, k long, custom_bits double, static_bits double, custom_smaller boolean")


for _c in ("rle", "zlib", "custom_tans"):
    query(f"bitmap_codec_{_c}_roundtrip", "F17", sql.md5_of(["doc_es"]))(lambda spark, d, c=_c: roundtrip(spark, d, ["doc_es"], gates=Gates(coder=c)))


@query("ans_gate_relations", "F15", "SELECT * FROM (VALUES ('acgt', true, true), ('geom80', true, true)) t(stream_id, looser_skew_never_larger, looser_cost_never_larger)")
def ans_gate_relations(spark, d):
    """Looser gates code more nodes, and a node is coded only where it gets smaller."""
    r = staged(ans_gate_sweep(spark, d))
    before = lambda by, order: F.lag("enc_bytes").over(Window.partitionBy("stream_id", by).orderBy(order))
    ok = r.select("stream_id", (F.coalesce(before("max_cost_ratio", "min_skew"), "enc_bytes") <= F.col("enc_bytes")).alias("skew"), (F.coalesce(before("min_skew", "max_cost_ratio"), "enc_bytes") >= F.col("enc_bytes")).alias("cost"))
    return ok.groupBy("stream_id").agg(F.min("skew").alias("looser_skew_never_larger"), F.min("cost").alias("looser_cost_never_larger"))


@query("bitmap_codec_relations", "F17", "SELECT * FROM (VALUES ('doc_es', true, true), ('geom80', true, true), ('mixskew', true, true)) t(stream_id, tans_never_larger_than_raw, rle_never_larger_than_raw)")
def bitmap_codec_relations(spark, d):
    """A coder is used for a bitmap only where it pays, so none loses to plain bitmaps."""
    r = bitmap_codec_compare(spark, d).groupBy("stream_id").pivot("coder", ["raw", "tans", "rle", "zlib"]).agg(F.first("enc_bytes"))
    return r.select("stream_id", (F.col("tans") <= F.col("raw")).alias("tans_never_larger_than_raw"), (F.col("rle") <= F.col("raw")).alias("rle_never_larger_than_raw"))


@query("bitmap_codec_compare", "F17")
def bitmap_codec_compare(spark, d):
    out = None
    for coder in ("raw", "tans", "rle", "zlib"):
        s = sizes(encoded(spark, d, ["geom80", "doc_es", "mixskew"], gates=None if coder == "raw" else Gates(coder=coder))).withColumn("coder", F.lit(coder))
        out = s if out is None else out.unionByName(s)
    return out


@query("tans_cursor_grid", "F16 W15", "SELECT x AS cursors, y AS unroll, true AS same FROM (VALUES (2),(4),(6),(8),(10),(12),(16)) a(x), (VALUES (1),(2),(4)) b(y)")
def tans_cursor_grid(spark, d):
    """Every number of cursors and every unrolling gives back the bytes of a bitmap with 80 % zeros."""
    grid = spark.createDataFrame([(x, y) for x in (2, 4, 6, 8, 10, 12, 16) for y in (1, 2, 4)], "cursors int, unroll int")

    def run(batches):
        rng = np.random.default_rng(1)
        data = np.packbits(rng.random((8, 2880 * 8)) > 0.8)
        n, t = np.full(8, 2880), np.full(8, 30)
        for b in batches:
            ok = [bool((fsm.decode(fsm.encode(data, n, t, fsm.static_tables(), x), n, t, fsm.static_tables(), x, y) == data).all()) for x, y in zip(b.column("cursors").to_pylist(), b.column("unroll").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("cursors"), b.column("unroll"), pa.array(ok)], names=["cursors", "unroll", "same"])

    return grid.mapInArrow(run, "cursors int, unroll int, same boolean")


