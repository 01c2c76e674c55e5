import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from treepack.functions import fsm, kernels
from treepack.operators import baselines, codec, lz, unary
from treepack.plans import codebook as cb
from treepack.plans.selective import Gates, choose_table, passes
from treepack.plans.shape import MODES


def book(data: bytes) -> bytes:
    return cb.pack_lengths(cb.fit_lengths(np.bincount(np.frombuffer(data, np.uint8), minlength=256)))


def test_payload_of_the_worked_word():
    assert codec.encode_batch([b"huffman"], book(b"huffman"), fallback=False)[0].hex() == "070000000300000ec90001"


BLOCKS = st.lists(st.one_of(st.binary(max_size=600), st.text("aab c", max_size=3000).map(str.encode)), min_size=1, max_size=6)


@given(BLOCKS, st.sampled_from(MODES), st.sampled_from([None, Gates(min_bitmap_bytes=4), Gates(min_bitmap_bytes=4, cursors=3, span=2), Gates(coder="zlib", min_bitmap_bytes=4), Gates(coder="rle", min_bitmap_bytes=4)]), st.sampled_from(["bottomup", "topdown"]))
@settings(max_examples=120, deadline=None)
def test_decode_gives_back_what_encode_took(raws, shape, gates, decoder):
    lengths = book(b"".join(raws))
    enc = codec.encode_batch(raws, lengths, shape, gates)
    n = [len(r) for r in raws]
    assert codec.decode_batch(enc, n, lengths, shape, decoder, gates) == raws
    for e, m, r in zip(enc, n, raws):  # any block alone
        assert codec.decode_batch([e], [m], lengths, shape, decoder, gates) == [r]


@given(BLOCKS)
@settings(max_examples=40, deadline=None)
def test_baselines_agree(raws):
    lengths, n = book(b"".join(raws)), [len(r) for r in raws]
    enc = baselines.encode_classic(raws, lengths)
    assert baselines.decode_bitwise(enc, n, lengths) == baselines.decode_table(enc, n, lengths) == baselines.decode_table(enc, n, lengths, symbols_per_step=2) == raws
    assert baselines.decode_table(baselines.encode_classic(raws, lengths, 4), n, lengths, cursors=4) == raws
    assert baselines.decode_tans(baselines.encode_tans(raws), n) == raws


@pytest.mark.parametrize("size", [0, 1, 7, 8, 8191, 8192, 8193, 65535])
def test_block_boundaries(size):
    raw = (b"abcdab" * 11000)[:size]
    lengths = book(b"abcdab")
    assert codec.decode_batch(codec.encode_batch([raw], lengths), [size], lengths) == [raw]


def test_a_block_over_the_field_width_is_refused():
    with pytest.raises(ValueError, match="1 to 65535"):
        codec.encode_batch([b"ab" * 40000], book(b"ab"))


def test_a_symbol_without_code_is_refused():
    with pytest.raises(ValueError, match="has no code"):
        codec.encode_batch([b"abx"], book(b"abc"))


@pytest.mark.parametrize("damage", [lambda p: p[:-1], lambda p: p[:3], lambda p: p + b"x", lambda p: p[:4] + b"\xff\xff" + p[6:]])
def test_damaged_blocks_raise(damage):
    raw = b"the quick brown fox jumps over the lazy dog" * 20
    lengths = book(raw)
    with pytest.raises(codec.CorruptBlock):
        codec.decode_batch([damage(codec.encode_batch([raw], lengths)[0])], [len(raw)], lengths)


def test_gates_and_tables():
    gates = Gates()
    one = lambda n, r, depth: bool(passes(np.array([n]), np.array([r]), depth, gates)[0])
    assert one(2048, 117, 2) and not one(115, 2, 3) and not one(2048, 498, 5) and not one(4096, 2048, 0)
    ids, flip = choose_table(np.array([100, 100, 100]), np.array([20, 80, 0]))
    assert ids.tolist() == [31, 31, 50] and flip.tolist() == [False, True, False]


def test_static_tables_cost_little_more_than_entropy():
    p = np.arange(50, 100) / 100
    h = -(p * np.log2(p) + (1 - p) * np.log2(1 - p))
    assert (fsm.bit_costs() >= h - 1e-9).all() and (fsm.bit_costs() - h < 0.02).all()


@given(st.lists(st.binary(min_size=1, max_size=400), min_size=1, max_size=5), st.sampled_from([1, 2, 8, 12]), st.sampled_from([1, 2, 4]))
@settings(max_examples=60, deadline=None)
def test_tans(streams, cursors, unroll):
    data, sizes = np.frombuffer(b"".join(streams), np.uint8), np.array([len(s) for s in streams])
    table = np.arange(len(streams)) % 50
    enc = fsm.encode(data, sizes, table, fsm.static_tables(), cursors)
    assert (fsm.decode(enc, sizes, table, fsm.static_tables(), cursors, unroll) == data).all()


@given(st.lists(st.integers(0, 60), max_size=200), st.sampled_from([0, 2]))
@settings(max_examples=60, deadline=None)
def test_unary(values, k):
    v = np.array(values, np.int64)
    assert unary.from_bytes(unary.to_bytes(v, k), k).tolist() == values
    if values:
        bits = unary.plain_bits(v)
        for got in (unary.decode_naive(bits, len(v)), unary.decode_bytetable(bits, len(v)), unary.decode_bytetable(bits, len(v), True)):
            assert got.tolist() == values


@given(st.one_of(st.binary(max_size=500), st.text("ab", max_size=3000).map(str.encode)))
@settings(max_examples=80, deadline=None)
def test_lz(data):
    lit, runs, lens, offs = lz.parse(data)
    assert lz.rebuild(lit, lz.unvarbytes(lz.varbytes(runs)), lz.unvarbytes(lz.varbytes(lens)), offs) == data


@given(st.lists(st.integers(0, 40), min_size=1, max_size=8), st.integers(1, 8), st.randoms())
@settings(max_examples=60, deadline=None)
def test_packing_of_bits_and_codes(counts, d, rnd):
    codes = np.array([rnd.randrange(1 << d) for _ in range(sum(counts))], np.uint8)
    packed, sizes = kernels.pack_codes(codes, d, np.array(counts))
    assert sizes.tolist() == [-(-c * d // 8) for c in counts] and len(packed) == sizes.sum()
    assert (kernels.unpack_codes(packed, d, np.array(counts)) == codes).all()


def test_timing_protocol_on_a_false_clock():
    import bench

    ticks = iter(x for k in range(100) for x in (0.0, 10 - min(k, 25) * 0.2))
    calls = []
    assert bench.measure(lambda: calls.append(1), clock=lambda: next(ticks)) == pytest.approx(5.0, abs=0.3)
    assert 20 <= len(calls) <= 40 and len(bench.replicated(b"ab")) >= 1 << 20


def test_every_decoder_gives_the_same_blocks():
    """Levels decoded at once, two halves in turn, and merges that take coded bitmaps, next to the plain decoders."""
    rng = np.random.default_rng(5)
    data = np.minimum(11, rng.geometric(0.72, 70_000) - 1).astype(np.uint8)
    data[30_000:50_000] = rng.integers(0, 9, 20_000)
    raws = [data[a:b].tobytes() for a, b in ((0, 8192), (8192, 8193), (8193, 8193), (8193, 29_000), (29_000, 52_000), (52_000, 52_300), (52_300, 70_000))]
    n, lengths = [len(r) for r in raws], cb.pack_lengths(cb.fit_lengths(np.bincount(data, minlength=256)))
    some_coded = 0
    for shape in ("naive", "flat", "flat_opt"):
        plain = codec.encode_batch(raws, lengths, shape)
        assert codec.decode_batch(plain, n, lengths, shape, "topdown_interleaved") == raws
        for some in (1, 2, 5):
            assert codec.decode_batch(plain[:some], n[:some], lengths, shape, "topdown_interleaved") == raws[:some]
        for how in ({}, {"prefill": False, "fuse": False}):
            assert codec.decode_batch(plain, n, lengths, shape, "topdown", root_levels=True, **how) == raws
        for gates in (Gates(), Gates(min_skew=0.5, max_cost_ratio=1.0), Gates(scope="stream"), Gates(cursors=2), Gates(span=2)):
            marks: list = []
            coded = codec.encode_batch(raws, lengths, shape, gates, np.bincount(data, minlength=256), markers=marks)
            some_coded += any(m[4] for m in marks)
            assert codec.decode_batch(coded, n, lengths, shape, "bottomup_fused", gates) == raws
            assert codec.decode_batch(coded, n, lengths, shape, "bottomup", gates) == raws
    assert some_coded >= 9


def test_many_books_meet_their_blocks_by_salts(spark, monkeypatch):
    from pyspark.sql import functions as F

    from treepack.operators import blocks as ob
    from treepack.operators import stats
    from treepack.sources.streams import to_blocks

    values = spark.createDataFrame([("a" if k % 3 else "b", k, bytearray(f"text {k} " * 50, "ascii")) for k in range(60)], "stream_id string, value_id long, raw binary")
    hist = stats.byte_histogram(values)
    books = stats.codebooks(hist)
    monkeypatch.setattr(ob, "small", lambda df: df)
    enc = ob.encode_blocks(to_blocks(values), books, gates=Gates(scope="stream"), hist=hist)
    back = ob.decode_blocks(enc, gates=Gates(scope="stream")).groupBy().agg(F.count("*").alias("n"), F.sum(F.crc32("raw")).alias("s")).first()
    want = values.groupBy().agg(F.count("*").alias("n"), F.sum(F.crc32("raw")).alias("s")).first()
    assert tuple(back) == tuple(want)
