"""Round trips of the two decoders, the relational forms, the container, blocks of every size."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treepack.functions import kernels
from treepack.operators import codec, relational, stats
from treepack.operators.blocks import chunk_encode, decode_blocks, encode_blocks
from treepack.operators.columns import decode_columns, encode_columns
from treepack.plans import codebook as cb
from treepack.plans import shape as sh
from treepack.plans.selective import Gates
from treepack.queries import sql
from treepack.queries.common import books_of, codes_of, digests, encoded, hist_of, roundtrip, sizes
from treepack.registry import query
from treepack.sources.streams import build_stream, to_blocks
from treepack.sources.tables import load, small, staged

_DOCS = ("doc_en", "doc_de", "doc_fr", "doc_es")


@query("nbh_bu_roundtrip", "E3", sql.md5_of(_DOCS))
def nbh_bu_roundtrip(spark, d) -> DataFrame:
    return roundtrip(spark, d, _DOCS)


@query("nbh_td_roundtrip", "E2", sql.md5_of(_DOCS))
def nbh_td_roundtrip(spark, d):
    return roundtrip(spark, d, _DOCS, decoder="topdown")


for _shape in sh.MODES:
    query(f"nbh_bu_{_shape}_roundtrip", "E3", sql.md5_of(["doc_de"]))(lambda spark, d, s=_shape: roundtrip(spark, d, ["doc_de"], shape=s))
    query(f"nbh_td_{_shape}_roundtrip", "E2", sql.md5_of(["doc_de"]))(lambda spark, d, s=_shape: roundtrip(spark, d, ["doc_de"], shape=s, decoder="topdown"))
for _name, _how in {"naive": dict(prefill=False, fuse=False), "fused": dict(prefill=False, fuse=True), "prefill": dict(prefill=True, fuse=True)}.items():
    query(f"nbh_td_{_name}_tree", "B1-B3", sql.md5_of(["doc_es"]))(lambda spark, d, h=_how: roundtrip(spark, d, ["doc_es"], shape="naive", decoder="topdown", **h))


@query("nbh_roundtrip_documents", "E9", "SELECT doc_id, strlen(text)::BIGINT AS n_bytes, md5(text) AS digest FROM documents WHERE text IS NOT NULL")
def nbh_roundtrip_documents(spark, d):
    """One code for all languages, by value."""
    values = load(spark, d, "documents").where("text is not null").select(F.lit("documents").alias("stream_id"), F.col("doc_id").alias("value_id"), F.col("text").cast("binary").alias("raw"))
    books = stats.codebooks(stats.byte_histogram(values))
    return digests(decode_blocks(encode_blocks(to_blocks(values), books))).select(F.col("value_id").alias("doc_id"), "n_bytes", "digest")


def _text_table(table: str, key: str, column: str):
    def run(spark, d):
        rows = load(spark, d, table).select(F.lit(table).alias("stream_id"), F.expr(key).cast("long").alias("value_id"), F.col(column).cast("binary").alias("raw"))
        books = stats.codebooks(stats.byte_histogram(rows))
        out = digests(decode_blocks(encode_blocks(to_blocks(rows.where("raw is not null")), books)))
        return out.select("value_id", "n_bytes", "digest")

    return run


for _t, _k, _c, _sql in (("pages", "page_id", "html", "page_id"), ("conversations", "conv_id * 1000 + turn", "text", "conv_id * 1000 + turn"), ("events", "event_id", "props", "event_id")):
    _q = {"events": "nbh_roundtrip_props"}.get(_t, f"nbh_roundtrip_{_t}")
    query(_q, "E9", f"SELECT ({_sql})::BIGINT AS value_id, strlen({_c})::BIGINT AS n_bytes, md5({_c}) AS digest FROM {_t} WHERE {_c} IS NOT NULL")(_text_table(_t, _k, _c))


# --- typed columns ----------------------------------------------------------------


def _typed(table: str, key_sql: str, prepare, columns: dict[str, str], types: dict[str, str]):
    def run(spark, d):
        df = prepare(load(spark, d, table))
        return decode_columns(encode_columns(df, "key_", columns), columns, types)

    return run


_TYPED = {
    "lineitem": (lambda t: t.select(F.expr("l_orderkey * 8 + l_linenumber").alias("key_"), "l_partkey", "l_linenumber", "l_quantity", F.unix_micros(F.col("l_shipdate").cast("timestamp")).alias("ship")), {"l_partkey": "<i8", "l_linenumber": "<i4", "l_quantity": "<f8", "ship": "<i8"}, {"l_partkey": "long", "l_linenumber": "int", "l_quantity": "double", "ship": "long"}, "SELECT l_orderkey * 8 + l_linenumber AS _k, l_partkey, l_linenumber, l_quantity, epoch_us(l_shipdate) AS ship FROM lineitem"),
    "orders": (lambda t: t.select(F.col("o_orderkey").alias("key_"), "o_custkey", "o_totalprice"), {"o_custkey": "<i8", "o_totalprice": "<f8"}, {"o_custkey": "long", "o_totalprice": "double"}, "SELECT o_orderkey AS _k, o_custkey, o_totalprice FROM orders"),
    "events": (lambda t: t.select(F.col("event_id").alias("key_"), F.expr("case when user_id % 7 = 0 then null else user_id end").alias("user_id"), "value", F.unix_micros(F.col("ts").cast("timestamp")).alias("us")), {"user_id": "<i8", "value": "<f8", "us": "<i8"}, {"user_id": "long", "value": "double", "us": "long"}, "SELECT event_id AS _k, CASE WHEN user_id % 7 = 0 THEN NULL ELSE user_id END AS user_id, value, epoch_us(ts) AS us FROM events"),
    "embeddings": (lambda t: t.select("vec_id", F.posexplode("embedding").alias("pos", "x")).select(F.expr("vec_id * 64 + pos").alias("key_"), "x"), {"x": "<f4"}, {"x": "float"}, "SELECT vec_id * 64 + k AS _k, embedding[k + 1] AS x FROM embeddings, range(64) r(k)"),
}
for _t, (_prep, _cols, _types, _o) in _TYPED.items():
    query(f"nbh_roundtrip_{_t}", "E10", _o)(_typed(_t, "", _prep, _cols, _types))


# --- sizes --------------------------------------------------------------------------

_SIZES = f"""WITH RECURSIVE src AS MATERIALIZED ({sql.rows(['doc_de'])}), {sql.codes(sql.hist('SELECT * FROM src'))},
bits AS (SELECT value_id, pos // 8192 AS block_no, left(code, x.d) AS prefix, substr(code, x.d + 1, 1) AS bit FROM src JOIN codes USING (stream_id, sym), unnest(range(len)) AS x(d)),
node AS (SELECT value_id, block_no, prefix, count(*) AS n FROM bits GROUP BY ALL),
inner_ AS (SELECT DISTINCT left(code, x.d) AS prefix FROM codes, unnest(range(len)) AS x(d)),
sized AS (SELECT value_id, block_no, (n + 7) // 8 + 1 + CASE WHEN prefix || '0' IN (SELECT prefix FROM inner_) AND prefix || '1' IN (SELECT prefix FROM inner_) THEN 2 ELSE 0 END AS s FROM node)
SELECT value_id, block_no::BIGINT AS block_no, (4 + sum(s))::BIGINT AS payload_bytes FROM sized GROUP BY ALL"""


@query("nbh_encode_sizes", "E1 G5", _SIZES)
def nbh_encode_sizes(spark, d):
    """Payload bytes of each block of the naive shape, which counts alone foretell."""
    books = books_of(spark, d, ["doc_de"], max_len=15, floor=4096)
    enc = encode_blocks(to_blocks(build_stream(spark, d, "doc_de")), books, encoder=lambda raws, lengths: codec.encode_batch(raws, lengths, "naive", fallback=False))
    return enc.where("n > 0").select("value_id", "block_no", F.octet_length("payload").cast("long").alias("payload_bytes"))


@query("encode_prebuilt", "A7", sql.md5_of(["doc_fr"]))
def encode_prebuilt(spark, d):
    """A code made from other text (smoothed, so it knows every symbol): no counting pass."""
    books = books_of(spark, d, ["doc_es"], smooth=True).withColumn("stream_id", F.lit("doc_fr"))
    return digests(decode_blocks(encode_blocks(to_blocks(build_stream(spark, d, "doc_fr")), books)))


@query("codebook_scope_compare", "A8", "SELECT * FROM (VALUES ('chunk', true), ('group', true), ('stream', true)) t(scope, same)")
def codebook_scope_compare(spark, d):
    """Stream, group (source) and chunk scope give back the same values."""
    docs = load(spark, d, "documents").where("lang = 'de' and text is not null")
    values = docs.select(F.lit("doc_de").alias("stream_id"), F.col("doc_id").alias("value_id"), F.col("text").cast("binary").alias("raw"))
    grouped = docs.select(F.col("source").alias("stream_id"), F.col("doc_id").alias("value_id"), F.col("text").cast("binary").alias("raw"))
    enc = {
        "stream": encode_blocks(to_blocks(values), stats.codebooks(stats.byte_histogram(values))),
        "group": encode_blocks(to_blocks(grouped), stats.codebooks(stats.byte_histogram(grouped))),
        "chunk": chunk_encode(to_blocks(values)),
    }
    truth = values.select("value_id", F.md5("raw").alias("want"))
    out = None
    for scope, e in enc.items():
        ok = digests(decode_blocks(e.select("stream_id", "value_id", "block_no", "n", "lengths", "payload", "crc"))).join(truth, "value_id", "full").agg(F.min(F.coalesce(F.col("digest") == F.col("want"), F.lit(False))).alias("same")).select(F.lit(scope).alias("scope"), "same")
        out = ok if out is None else out.unionByName(ok)
    return out


@query("decoders_agree", "E4", "SELECT stream_id, value_id, true AS agree FROM (SELECT 'doc_es' AS stream_id, * FROM (" + sql.TEXT["doc_es"] + "))")
def decoders_agree(spark, d):
    from treepack.operators import baselines

    base = digests(decode_blocks(encoded(spark, d, ["doc_es"], encoder=baselines.encode_classic), decode=baselines.decode_table)).withColumnRenamed("digest", "t")
    td = roundtrip(spark, d, ["doc_es"], decoder="topdown").withColumnRenamed("digest", "a")
    bu = roundtrip(spark, d, ["doc_es"]).withColumnRenamed("digest", "b")
    keys = ["stream_id", "value_id", "n_bytes"]
    return bu.join(td, keys).join(base, keys).select("stream_id", "value_id", ((F.col("a") == F.col("b")) & (F.col("b") == F.col("t"))).alias("agree"))


for _b in (1024, 2048, 4096, 16384, 65535):
    query(f"block_size_{_b}", "E8", sql.md5_of(["doc_es"]))(lambda spark, d, b=_b: roundtrip(spark, d, ["doc_es"], block_size=b))


@query("block_size_sweep", "E8")
def block_size_sweep(spark, d):
    """Ratio by block size: small blocks pay for headers and padding."""
    out = None
    for b in (1024, 2048, 4096, 8192, 16384, 65535):
        s = sizes(encoded(spark, d, ["doc_en", "geom80"], block_size=b)).withColumn("block_size", F.lit(b))
        out = s if out is None else out.unionByName(s)
    return out


@query("block_size_relations", "E8", "SELECT * FROM (VALUES ('doc_en', true), ('geom80', true)) t(stream_id, larger_blocks_never_larger)")
def block_size_relations(spark, d):
    r = staged(block_size_sweep(spark, d))
    before = F.lag("enc_bytes").over(Window.partitionBy("stream_id").orderBy("block_size"))
    return r.select("stream_id", (F.coalesce(before, "enc_bytes") >= F.col("enc_bytes")).alias("ok")).groupBy("stream_id").agg(F.min("ok").alias("larger_blocks_never_larger"))


@query("block_range_decode", "E11", "SELECT doc_id AS value_id, 1::BIGINT AS block_no, strlen(text)::BIGINT > 8192 AS present FROM documents WHERE lang = 'en' AND strlen(text) > 8192")
def block_range_decode(spark, d):
    """Second blocks alone, decoded without their first."""
    enc = encoded(spark, d, ["doc_en"]).where("block_no = 1")
    return decode_blocks(enc).select("value_id", "block_no", (F.octet_length("raw") > 0).alias("present"))


# --- relations ------------------------------------------------------------------------

_PIVOT = f"""WITH RECURSIVE src AS MATERIALIZED ({sql.rows(['doc_es'])}), {sql.codes(sql.hist('SELECT * FROM src'))},
bits AS (SELECT value_id, pos // 8192 AS block_no, pos, left(code, x.d) AS prefix, substr(code, x.d + 1, 1) AS bit FROM src JOIN codes USING (stream_id, sym), unnest(range(len)) AS x(d))
SELECT value_id, block_no::BIGINT AS block_no, prefix, md5(string_agg(bit, '' ORDER BY pos)) AS bitmap FROM bits GROUP BY ALL"""


def _blocks_and_codes(spark, d):
    values = build_stream(spark, d, "doc_es")
    codes = codes_of(stats.codebooks(stats.byte_histogram(values), max_len=15, floor=4096))
    return to_blocks(values), staged(codes)


@query("pivot_rel_bitmaps", "E5", _PIVOT)
def pivot_rel_bitmaps(spark, d):
    blocks, codes = _blocks_and_codes(spark, d)
    return relational.bitmaps(relational.pivot(relational.interleaved(blocks), codes)).select("value_id", "block_no", "prefix", F.md5("bitmap").alias("bitmap"))


_REL = f"SELECT value_id, (pos // 8192)::BIGINT AS block_no, (pos % 8192)::INT AS pos, sym FROM ({sql.rows(['doc_es'])})"


@query("pivot_rel_decode_td", "E6", _REL)
def pivot_rel_decode_td(spark, d):
    blocks, codes = _blocks_and_codes(spark, d)
    return relational.decode_topdown(relational.pivot(blocks, codes), codes).select("value_id", "block_no", "pos", "sym")


@query("pivot_rel_decode_bu", "E7", _REL)
def pivot_rel_decode_bu(spark, d):
    blocks, codes = _blocks_and_codes(spark, d)
    return relational.decode_bottomup(relational.pivot(blocks, codes), codes).select("value_id", "block_no", "pos", "sym")


# --- kernels, each on the bytes of real columns ------------------------------------------


def _kernel_rows(spark, d, fn):
    """fn(bytes) -> bytes, to be equal to the input's own bytes; (value_id, digest)."""
    values = build_stream(spark, d, "userid_le8")

    def run(batches):
        for b in batches:
            out = [hashlib.md5(fn(np.frombuffer(r, np.uint8))).hexdigest() for r in b.column("raw").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("value_id"), pa.array(out)], names=["value_id", "digest"])

    return values.select("value_id", "raw").mapInArrow(run, "value_id long, digest string")


_LE = "SELECT event_id // 1024 AS value_id, string_agg(" + " || ".join(f"chr(65 + ((user_id >> {4 * k}) & 15)::INT)" for k in (1, 0)) + ", '' ORDER BY event_id) AS s FROM events GROUP BY 1"
_KERNEL_ORACLE = f"SELECT value_id, md5(s) AS digest FROM ({_LE})"


def _low_bytes(a: np.ndarray) -> np.ndarray:
    """The lowest byte of each user_id: what the kernels below take apart and put together again."""
    return np.ascontiguousarray(a[::8])


def _letters(x: np.ndarray) -> bytes:
    """Two letters per byte, as the oracle spells it."""
    return np.stack([65 + (x >> 4), 65 + (x & 15)], axis=1).astype(np.uint8).tobytes()


def _one(n: int) -> np.ndarray:
    return np.array([n])


def _k_partition(impl):
    def fn(a):
        x = _low_bytes(a)
        bits = (x & 1).astype(bool)
        left, right = kernels.partition(bits, np.arange(len(x), dtype=np.uint16), impl)
        out = np.empty_like(x)
        out[left], out[right] = x[~bits], x[bits]
        assert (np.diff(left.astype(int)) > 0).all() and (np.diff(right.astype(int)) > 0).all()
        return _letters(out)

    return fn


def _k_root(a):
    x = _low_bytes(a)
    bits = (x & 2).astype(bool)
    left, right = kernels.partition_root(bits)
    out = np.empty_like(x)
    out[left], out[right] = x[~bits], x[bits]
    return _letters(out)


def _k_half(a):
    x = _low_bytes(a)
    bits = (x & 4).astype(bool)
    idx = np.arange(len(x))
    out = x.copy()
    for side in (False, True):
        part = kernels.partition_half(bits, idx, side)
        out[part] = x[bits if side else ~bits]
    return _letters(out)


def _k_scatter(a):
    x = _low_bytes(a)
    out = np.zeros_like(x)
    for s in np.unique(x).tolist():
        kernels.scatter_one(out, np.flatnonzero(x == s), s)
    return _letters(out)


def _k_scatter_two(a):
    x = _low_bytes(a)
    out = np.zeros_like(x)
    for s in np.unique(x >> 1).tolist():
        idx = np.flatnonzero(x >> 1 == s)
        kernels.scatter_two(out, idx, (x[idx] & 1).astype(bool), 2 * s, 2 * s + 1)
    return _letters(out)


def _k_scatter_flat(a):
    x = _low_bytes(a)
    packed, _ = kernels.pack_codes(x & 15, 4, _one(len(x)))
    out = np.zeros_like(x)
    kernels.scatter_flat(out, np.arange(len(x)), kernels.unpack_codes(packed, 4, _one(len(x))), np.arange(16, dtype=np.uint8))
    return _letters(out | (x & 0xF0))


def _k_merge(kind):
    def fn(a):
        x = _low_bytes(a)
        bits = (x & 1).astype(bool)
        left, right = x[~bits], x[bits]
        if kind == "vv":
            return _letters(kernels.merge_vec_vec(bits, left, right))
        if kind == "cv":
            return _letters(np.where(bits, kernels.merge_cst_vec(bits, 7, right), x))
        if kind == "vc":
            return _letters(np.where(bits, x, kernels.merge_vec_cst(bits, left, 7)))
        return _letters((x & 0xFE) | kernels.merge_cst_cst(bits, 0, 1))

    return fn


def _k_flat(dd):
    def fn(a):
        x = _low_bytes(a)
        low = x & ((1 << dd) - 1)
        packed, _ = kernels.pack_codes(low, dd, _one(len(x)))
        assert len(packed) == -(-len(x) * dd // 8)
        return _letters(kernels.merge_flat(kernels.unpack_codes(packed, dd, _one(len(x))), np.arange(1 << dd, dtype=np.uint8)) | (x & ~np.uint8((1 << dd) - 1)))

    return fn


def _k_plus1(a):
    """The low three bits as unary values, folded back."""
    from treepack.operators import unary

    x = _low_bytes(a)
    bitmaps, _ = unary.encode(x & 7)
    return _letters((unary.decode(bitmaps).astype(np.uint8)) | (x & 0xF8))


def _k_enc(a):
    x = _low_bytes(a).astype(np.uint16)
    bits, left, right = kernels.enc_partition(x, 7, "full")
    for keep in ("left", "right", "none"):
        b2, l2, r2 = kernels.enc_partition(x, 7, keep)
        assert (b2 == bits).all() and (l2 is None) == (keep != "left") and (r2 is None) == (keep != "right")
    return _letters(kernels.merge_vec_vec(bits, left.astype(np.uint8), right.astype(np.uint8)))


def _k_pack(a):
    x = _low_bytes(a)
    for dd in range(1, 9):
        low = x & np.uint8((1 << dd) - 1)
        packed, _ = kernels.pack_codes(low, dd, _one(len(x)))
        assert (kernels.unpack_codes(packed, dd, _one(len(x))) == low).all()
    return _letters(kernels.unpack_codes(kernels.pack_codes(x, 8, _one(len(x)))[0], 8, _one(len(x))))


def _k_planes(a):
    x = _low_bytes(a)
    return _letters(kernels.unpack_planes(kernels.pack_planes(x, 8), len(x)))


for _n, _f in {
    "kernel_partition": _k_partition("vector"), "kernel_partition_loop": _k_partition("loop"), "kernel_partition_branchfree": _k_partition("branchfree"),
    "kernel_partition_root": _k_root, "kernel_partition_half": _k_half, "kernel_scatter": _k_scatter, "kernel_scatter_two": _k_scatter_two, "kernel_scatter_flat": _k_scatter_flat,
    "kernel_merge_vv": _k_merge("vv"), "kernel_merge_cv": _k_merge("cv"), "kernel_merge_vc": _k_merge("vc"), "kernel_merge_cc": _k_merge("cc"),
    **{f"kernel_merge_flat_d{k}": _k_flat(k) for k in range(2, 9)}, "kernel_merge_plus1": _k_plus1, "kernel_enc_partition": _k_enc, "kernel_pack_unpack": _k_pack, "flat_bitsliced_roundtrip": _k_planes,
}.items():
    query(_n, "C1-C15", _KERNEL_ORACLE)(lambda spark, d, f=_f: _kernel_rows(spark, d, f))


# --- rejected variants, kept as options -----------------------------------------------------


def _decoder_roundtrip(decoder: str, *, shape: str = "flat_opt", gates: Gates | None = None, **how):
    return lambda spark, d: roundtrip(spark, d, ["doc_es"], decoder=decoder, shape=shape, gates=gates, **how)


query("shape_root_levels", "B9", sql.md5_of(["doc_es"]))(_decoder_roundtrip("topdown", shape="naive", prefill=False, root_levels=True))


def split_flat(root: sh.Node, counts: np.ndarray, skew: float = 0.625) -> sh.Node:
    """Flat nodes whose upper half is skewed become binary at their root; needs the counts at the decoder."""
    if root.inner:
        return sh.Node(root.prefix, left=split_flat(root.left, counts, skew), right=split_flat(root.right, counts, skew))
    if root.flat and root.d > 1:
        half = len(root.symbols) // 2
        parts = [root.symbols[:half], root.symbols[half:]]
        w = [sum(int(counts[s]) for s in p) for p in parts]
        if max(w) > skew * max(1, sum(w)):
            return sh.Node(root.prefix, left=sh.Node(root.prefix + "0", parts[0], root.d - 1), right=sh.Node(root.prefix + "1", parts[1], root.d - 1))
    return root


def left_heavy(root: sh.Node, counts: np.ndarray) -> sh.Node:
    """Children swapped so that the heavier is left, relabelled from the top; needs the counts at the decoder."""
    w = sh.weights(root, counts)

    def go(n: sh.Node, prefix: str) -> sh.Node:
        if not n.inner:
            return sh.Node(prefix, n.symbols, n.d)
        a, b = (n.left, n.right) if w[n.left.prefix] >= w[n.right.prefix] else (n.right, n.left)
        return sh.Node(prefix, left=go(a, prefix + "0"), right=go(b, prefix + "1"))

    return go(root, "")


def _reshaped(rule):
    def run(spark, d):
        import pandas as pd

        hist = hist_of(spark, d, ["doc_de", "geom80", "ok_le8"])

        def one(pdf):
            c = np.zeros(256, np.int64)
            c[pdf["sym"].to_numpy()] = pdf["cnt"].to_numpy()
            base = sh.build_shape(cb.fit_lengths(c))
            new = rule(base, c)
            same = sorted(s for x in new.walk() if not x.inner for s in x.symbols) == sorted(np.flatnonzero(c).tolist())
            cost = lambda r: sum((sh.weights(r, c)[x.prefix]) * (x.d if x.flat else 1) for x in r.walk() if not x.leaf)
            return pd.DataFrame([(pdf["stream_id"].iloc[0], bool(same), bool(cost(new) == cost(base)))], columns=["stream_id", "same_symbols", "same_bits"])

        return hist.groupBy("stream_id").applyInPandas(one, "stream_id string, same_symbols boolean, same_bits boolean")

    return run


for _n, _r in (("shape_fse_split", split_flat), ("shape_left_heavy", left_heavy)):
    query(_n, "B10", "SELECT * FROM (VALUES ('doc_de', true, true), ('geom80', true, true), ('ok_le8', true, true)) t(stream_id, same_symbols, same_bits)")(_reshaped(_r))


query("td_fused_pipeline", "C16", sql.md5_of(["doc_es"]))(_decoder_roundtrip("topdown_interleaved"))
query("bu_fused_tans_merge", "C17", sql.md5_of(["doc_es"]))(_decoder_roundtrip("bottomup_fused", gates=Gates(min_skew=0.5, max_cost_ratio=1.0)))


# --- the container ---------------------------------------------------------------------------


@query("wire_header", "G1", "SELECT 'huffman' AS word, '070000000300000ec90001' AS payload, 128 AS table_bytes")
def wire_header(spark, d):
    lengths = cb.pack_lengths(cb.huffman_lengths(np.bincount(np.frombuffer(b"huffman", np.uint8), minlength=256)))
    return spark.createDataFrame([("huffman", codec.encode_batch([b"huffman"], lengths, fallback=False)[0].hex(), len(lengths))], "word string, payload string, table_bytes int")


def _marker_rows(spark, d, gates):
    """(value_id, block_no, prefix, n, n_right, marker, body) of every inner node of every block."""
    enc_books = books_of(spark, d, ["doc_de"], max_len=15, floor=4096)
    blocks = to_blocks(build_stream(spark, d, "doc_de")).join(small(enc_books), "stream_id")

    def run(batches):
        for b in batches:
            raws, book = b.column("raw").to_pylist(), b.column("lengths")[0].as_py()
            marks: list = []
            codec.encode_batch(raws, book, "naive", gates, fallback=False, markers=marks)
            v, k = b.column("value_id").to_pylist(), b.column("block_no").to_pylist()
            rows = [(v[i], k[i], p, n, r, m, s) for i, p, n, r, m, s in marks]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], names=["value_id", "block_no", "prefix", "n", "n_right", "marker", "body"])

    return blocks.mapInArrow(run, "value_id long, block_no long, prefix string, n long, n_right long, marker long, body long")


_NODE_SQL = f"""WITH RECURSIVE src AS MATERIALIZED ({sql.rows(['doc_de'])}), {sql.codes(sql.hist('SELECT * FROM src'))},
bits AS (SELECT value_id, (pos // 8192)::BIGINT AS block_no, left(code, x.d) AS prefix, substr(code, x.d + 1, 1)::INT AS bit FROM src JOIN codes USING (stream_id, sym), unnest(range(len)) AS x(d)),
node AS (SELECT value_id, block_no, prefix, count(*) AS n, sum(bit)::BIGINT AS n_right FROM bits GROUP BY ALL) """


@query("wire_right_counts", "G3", _NODE_SQL + "SELECT value_id, block_no, prefix, n, n_right FROM node")
def wire_right_counts(spark, d):
    return _marker_rows(spark, d, None).select("value_id", "block_no", "prefix", "n", "n_right")


@query("ans_table_choice", "F10", _NODE_SQL + "SELECT value_id, block_no, least(greatest(floor(100 * greatest(n_right, n - n_right) / n + 0.5), 50), 99)::BIGINT - 49 AS table_id, n_right * 2 > n AS complemented FROM node WHERE prefix = ''")
def ans_table_choice(spark, d):
    """Table and complement bit of each block's root, by its popcount."""
    n, r = F.col("n"), F.col("n_right")
    return _marker_rows(spark, d, None).where("prefix = ''").select("value_id", "block_no", table_id(n, r).alias("table_id"), (r * 2 > n).alias("complemented"))


def table_id(n, n_right):
    """1 to 50 by the percentage of the commoner bit; one division, of integers, so a half is a half."""
    return F.least(F.greatest(F.floor(100 * F.greatest(n_right, n - n_right) / n + 0.5), F.lit(50)), F.lit(99)) - 49


@query("wire_markers", "G4", "SELECT true AS valid, true AS some_coded")
def wire_markers(spark, d):
    m = _marker_rows(spark, d, Gates())
    table = F.col("marker").bitwiseAND(0x7F)
    ok = (F.col("marker") == 0) & (F.col("body") == F.ceil(F.col("n") / 8)) | table.between(1, 50) & (F.col("body") < F.ceil(F.col("n") / 8)) & ((F.col("marker") >= 128) == (F.col("n_right") * 2 > F.col("n")))
    return m.agg(F.min(ok).alias("valid"), (F.max("marker") > 0).alias("some_coded"))


@query("wire_size_identity", "G5-G6", _NODE_SQL + ", inner_ AS (SELECT DISTINCT prefix FROM node) SELECT value_id, block_no, sum(n)::BIGINT AS bits, (4 + sum((n + 7) // 8 + 1 + CASE WHEN prefix || '0' IN (SELECT prefix FROM inner_) AND prefix || '1' IN (SELECT prefix FROM inner_) THEN 2 ELSE 0 END))::BIGINT AS bytes FROM node GROUP BY ALL")
def wire_size_identity(spark, d):
    rows = _marker_rows(spark, d, None)
    inner = rows.select("prefix").distinct()
    for side in "01":
        inner = inner.join(small(rows.select(F.expr("substring(prefix, 1, length(prefix) - 1)").alias("prefix"), F.expr("right(prefix, 1)").alias("s")).where(f"s = '{side}'").select("prefix").distinct().withColumn(f"has{side}", F.lit(2))), "prefix", "left")
    two = inner.select("prefix", F.when(F.col("has0").isNotNull() & F.col("has1").isNotNull(), 2).otherwise(0).alias("head"))
    return rows.join(small(two), "prefix").groupBy("value_id", "block_no").agg(F.sum("n").alias("bits"), (4 + F.sum(F.col("body") + 1 + F.col("head"))).alias("bytes"))


@query("wire_blocks", "G2", "SELECT true AS size_fields_agree, count(*)::BIGINT AS blocks FROM (SELECT unnest(range(greatest(1, (strlen(text) + 8191) // 8192))) FROM documents WHERE lang = 'fr' AND text IS NOT NULL)")
def wire_blocks(spark, d):
    enc = encoded(spark, d, ["doc_fr"])
    field = F.conv(F.concat(*(F.expr(f"hex(substring(payload, {k}, 1))") for k in (4, 3, 2, 1))), 16, 10).cast("long")
    return enc.agg(F.min(field.bitwiseAND(0x7FFFFFFF) == F.octet_length("payload") - 4).alias("size_fields_agree"), F.count("*").alias("blocks"))


@query("wire_crc", "G7", "SELECT 'doc_fr' AS stream_id, count(*)::BIGINT AS blocks, 0::BIGINT AS different FROM (SELECT unnest(range(greatest(1, (strlen(text) + 8191) // 8192))) FROM documents WHERE lang = 'fr' AND text IS NOT NULL)")
def wire_crc(spark, d):
    enc = encoded(spark, d, ["doc_fr"]).select("stream_id", "value_id", "block_no", "n", "lengths", "payload", F.col("crc").alias("stored"))
    return decode_blocks(enc).groupBy("stream_id").agg(F.count("*").alias("blocks"), F.sum((F.crc32("raw") != F.col("stored")).cast("long")).alias("different"))


@query("wire_walk", "G8", sql.md5_of(["doc_fr"]))
def wire_walk(spark, d):
    """Blocks read node by node in pre-order, from lengths alone."""
    return roundtrip(spark, d, ["doc_fr"], shape="flat")


@query("wire_corrupt_rows", "G9", "SELECT kind, count(*)::BIGINT AS rows_, sum(CASE WHEN kind = 'good' THEN 0 ELSE 1 END)::BIGINT AS corrupt FROM (SELECT CASE (doc_id + k) % 4 WHEN 0 THEN 'cut' WHEN 1 THEN 'flipped' WHEN 2 THEN 'empty' ELSE 'good' END AS kind FROM (SELECT doc_id, unnest(range(greatest(1, (strlen(text) + 8191) // 8192))) AS k FROM documents WHERE lang = 'es' AND text IS NOT NULL)) GROUP BY kind")
def wire_corrupt_rows(spark, d):
    """Cut, flipped and emptied payloads of blocks of any size: PERMISSIVE nulls just those rows."""
    enc = encoded(spark, d, ["doc_es"])
    kind = F.expr("case (value_id + block_no) % 4 when 0 then 'cut' when 1 then 'flipped' when 2 then 'empty' else 'good' end")
    p = F.col("payload")
    flipped_hex = F.lpad(F.hex(255 - F.conv(F.expr("hex(substring(payload, octet_length(payload), 1))"), 16, 10).cast("int")), 2, "0")
    broken = F.when(kind == "cut", F.expr("substring(payload, 1, octet_length(payload) - 3)")).when(kind == "empty", F.unhex(F.lit(""))).when(kind == "flipped", F.concat(F.expr("substring(payload, 1, octet_length(payload) - 1)"), F.unhex(flipped_hex))).otherwise(p)
    rows = enc.withColumn("payload", broken).withColumn("kind", kind)
    out = decode_blocks(rows, mode="PERMISSIVE")
    return out.groupBy("kind").agg(F.count("*").alias("rows_"), F.sum(F.col("raw").isNull().cast("long")).alias("corrupt"))

