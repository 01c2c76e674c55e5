import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from treepack.plans import codebook as cb
from treepack.plans import shape as sh

counts_of = lambda w: np.bincount(np.frombuffer(w, np.uint8), minlength=256)
COUNTS = st.lists(st.integers(0, 10**6), min_size=2, max_size=256).map(lambda x: np.array(x + [0] * (256 - len(x)))).filter(lambda c: np.count_nonzero(c) > 1)


def test_codes_of_the_worked_word():
    codes = {chr(s): format(c, f"0{n}b") for s, (n, c) in cb.canonical(cb.huffman_lengths(counts_of(b"huffman"))).items()}
    assert codes == {"f": "00", "u": "01", "a": "100", "h": "101", "m": "110", "n": "111"}


@pytest.mark.parametrize(("mode", "ops"), [("naive", 57), ("fused", 46), ("prefill", 43), ("flat", 39), ("flat_opt", 32)])
def test_topdown_operations_of_the_worked_phrase(mode, ops):
    c = counts_of(b"coconut-papaya")
    assert sh.ops_topdown(cb.huffman_lengths(c), c, mode) == ops


@pytest.mark.parametrize(("mode", "nodes", "ops"), [("naive", 8, 43), ("flat", 6, 39), ("flat_opt", 4, 32)])
def test_bottomup_operations_of_the_worked_phrase(mode, nodes, ops):
    c = counts_of(b"coconut-papaya")
    assert sh.ops_bottomup(sh.build_shape(cb.huffman_lengths(c), mode), c) == (nodes, ops)


@given(COUNTS)
@settings(max_examples=60, deadline=None)
def test_lengths_make_a_full_code_within_the_limit(c):
    best, limited, quick = cb.huffman_lengths(c), cb.limited_lengths(c, 11), cb.repaired_lengths(c, 11)
    kraft = lambda x: sum(2.0 ** -int(n) for n in x if n)
    assert kraft(best) == kraft(limited) == 1 and kraft(quick) <= 1
    assert limited.max() <= 11 and quick.max() <= 11
    cost = lambda x: int((c * x).sum())
    assert cost(best) <= cost(limited) <= cost(quick)
    p = c[c > 0] / c.sum()
    h = -(p * np.log2(p)).sum()
    assert h - 1e-9 <= cost(best) / c.sum() < h + 1
    assert (cb.unpack_lengths(cb.pack_lengths(limited)) == limited).all()


@given(COUNTS)
@settings(max_examples=60, deadline=None)
def test_shapes_hold_all_symbols_and_flatter_ones_cost_no_more(c):
    lengths = cb.limited_lengths(c, 15)
    cost = {}
    for mode in sh.MODES:
        root = sh.build_shape(lengths, mode)
        where = sh.paths(root)
        assert sorted(where) == np.flatnonzero(c).tolist()
        assert all(len(p) + d == lengths[s] for s, (p, _, d) in where.items())  # mean length stays
        cost[mode] = sh.ops_bottomup(root, c)
    assert cost["naive"] == (np.count_nonzero(c) - 1, int((c * lengths).sum()))
    assert cost["flat"][1] <= cost["naive"][1]
    assert sh.ops_topdown(lengths, c, "naive") == int((c * (lengths + 1)).sum())


def test_no_and_one_symbol_need_no_plan():
    assert sh.build_shape(np.zeros(256, int)) is None
    assert sh.build_shape(cb.fit_lengths(counts_of(b"zzz"))) is None


def test_too_many_symbols_for_the_limit():
    with pytest.raises(ValueError, match="do not fit"):
        cb.limited_lengths(np.array([1 << min(k, 40) for k in range(256)]), 7)
