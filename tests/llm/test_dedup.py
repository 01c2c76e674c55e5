import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest
import xxhash

from treepack.llm import exact_dedup as ed
from treepack.llm import simhash as sh
from treepack.llm.suffix_dedup import anchor_runs, suffix_dedup

SCHEMA = "doc_id long, text string, len string, fp string"  # names that the operators use inside


def table(spark, rows, schema="doc_id long, text string"):
    return spark.createDataFrame(rows, schema)


def clashing(spark, rows):
    return spark.createDataFrame([(d, t, "x", "y") for d, t in rows], SCHEMA)


# --- exact -----------------------------------------------------------------------


def test_chunk_hashes_compose():
    data = random.Random(1).randbytes(20_000)
    whole = ed.chunk_hashes(data)
    for cut in (0, 1, 4095, 4096, 4097, 12_345, 20_000):
        a, b = ed.chunk_hashes(data[:cut]), ed.chunk_hashes(data[cut:])
        assert tuple(ed.join_hash(a[k], b[k], len(data) - cut, k) for k in (0, 1)) == whole
    x = 0
    for v in data:
        x = (x * ed.BASES[0] + v + 1) % ed.PRIMES[0]
    assert x == whole[0]


def brute_exact(rows):
    norm = lambda t: re.sub("[\x20\x09-\x0d]", "", t or "")
    groups = {}
    for d, t in rows:
        groups.setdefault(norm(t), []).append((d, t or ""))
    out = []
    for n, members in groups.items():
        best = min(members, key=lambda m: (-len(m[1]), m[0] is None, m[0] or 0))
        kept = False
        for d, _ in members:
            k = d == best[0] and not kept
            kept |= k
            out.append((d, best[0], len(members), k, hashlib.sha256(n.encode()).hexdigest()))
    return sorted(out, key=repr)


ROWS = [(1, "a b"), (2, "ab"), (3, " a  b "), (4, None), (5, ""), (6, " \t\n"), (7, "é x"), (8, "éx"), (9, "other"), (9, "other"), (None, "ab"), (10, "z" * 70_000), (11, "z" * 70_000 + " ")] + [(100 + k, "hot copy") for k in range(60)]


@pytest.mark.parametrize("how", [{}, {"per_salt": 7}, {"huge_bytes": 1000}, {"broadcast_rows": 0}])
def test_exact_dedup(spark, how):
    got = sorted((tuple(r[c] for c in ("doc_id", "keep_id", "group_size", "kept", "text_sha256")) for r in ed.exact_dedup(clashing(spark, ROWS), **how).collect()), key=repr)
    assert got == brute_exact(ROWS)


def test_colliding_fingerprints_stay_apart():
    """Texts that differ from their leader go on with their bytes; a leader from elsewhere is no member."""
    import pyarrow as pa

    rows = {"doc_id": [None, 1, 2, 3], "points": [0, 3, 3, 3], "text_sha256": [None, "x", "y", "x"], "fp": [7] * 4, "len": [3] * 4, "salt": [0] * 4, "guest": [True, False, False, False], "b": [b"abc", b"abc", b"abd", b"abc"]}
    (out,) = ed._against_leader([pa.RecordBatch.from_pydict(rows)])
    assert out.column("doc_id").to_pylist() == [1, 2, 3] and out.column("same").to_pylist() == [True, False, True] and out.column("b").to_pylist() == [None, b"abd", None]


def test_exact_dedup_of_nothing(spark):
    assert ed.exact_dedup(table(spark, [])).count() == 0


# --- simhash ---------------------------------------------------------------------------


def brute_simhash(rows, radius=4):
    fp = []
    for _, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        s = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or ([" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
        fp.append(sum(1 << b for b in range(64) if 2 * sum(v >> b & 1 for v in h) > len(h)))
    ids = [d for d, _ in rows]
    label = list(range(len(rows)))
    a = np.array(fp, np.uint64)
    near = np.bitwise_count(a[:, None] ^ a[None, :]) <= radius
    lab = np.array(label)
    while True:
        new = np.where(near, lab[None, :], 10**9).min(axis=1)
        if (new == lab).all():
            break
        lab = new
    comp = {k: min(ids[i] for i in range(len(ids)) if lab[i] == k) for k in set(lab.tolist())}
    return sorted((d, f"{f:016x}", comp[k]) for d, f, k in zip(ids, fp, lab.tolist()))


def near_copies():
    rnd = random.Random(5)
    words = [f"w{k}" for k in range(400)]
    rows = [(1, None), (2, ""), (3, "  \n"), (4, "One"), (5, "one two"), (5, "one two"), (6, "ONE  two"), (7, "É é x y z")]
    for k in range(60):
        base = [rnd.choice(words) for _ in range(rnd.choice([5, 80, 300]))]
        rows.append((100 + 3 * k, " ".join(base)))
        edited = list(base)
        edited[rnd.randrange(len(base))] = "edited"
        rows += [(101 + 3 * k, " ".join(edited)), (102 + 3 * k, "\t".join(base).upper())]
    return rows


@pytest.mark.parametrize("hot", [1 << 14, 3])
def test_simhash_against_all_pairs(spark, hot, monkeypatch):
    rows = near_copies()
    real = sh.links
    monkeypatch.setattr(sh, "links", lambda fps, radius=4: real(fps, radius=radius, hot=hot))
    got = sorted((r.doc_id, r.fingerprint, r.component_id) for r in sh.simhash_dedup(clashing(spark, rows)).collect())
    assert got == brute_simhash(rows)


def test_tiles_skip_nothing_within_the_radius():
    rng = np.random.default_rng(2)
    base = rng.integers(0, 2**63, 300, dtype=np.uint64)
    fp = np.unique(np.concatenate([base, base ^ np.uint64(0b1011), base ^ (np.uint64(1) << np.uint64(63))]))
    fp = fp[np.argsort(np.bitwise_count(fp), kind="stable")]
    forest = sh.Forest(len(fp))
    i, j = np.nonzero(np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 4)
    forest.add(i, j)
    other = sh.Forest(len(fp))
    links = np.array(sh.tile_links(fp[:, None], 4, tile=16))
    other.add(links[:, 0], links[:, 1])
    assert (forest.label == other.label).all() and len(links) < len(fp)


def test_simhash_of_nothing(spark):
    assert sh.simhash_dedup(table(spark, [])).count() == 0


# --- suffixes ---------------------------------------------------------------------------


def brute_suffix(texts, size):
    seen = Counter(t[i : i + size] for t in texts for i in range(len(t) - size + 1))
    out = []
    for t in texts:
        gone = bytearray(len(t))
        for i in range(len(t) - size + 1):
            if seen[t[i : i + size]] > 1:
                gone[i : i + size] = b"\1" * size
        spans = len(re.findall(b"\1+", bytes(gone)))
        out.append((len(t), sum(gone), spans, hashlib.sha256(bytes(b for b, g in zip(t, gone) if not g)).hexdigest()))
    return out


@pytest.mark.parametrize("size", [50, 120])
def test_suffix_dedup_against_all_windows(spark, size):
    rnd = random.Random(size)
    base = "".join(rnd.choice("abc dé") for _ in range(900))
    rows = [(None, None), (1, ""), (2, "x" * (size - 1)), (3, "y" * (3 * size)), (4, "ab" * size), (4, "ab" * size), (5, base * 3)]
    for k in range(60):
        a, b = sorted((rnd.randrange(900), rnd.randrange(900)))
        rows.append((10 + k, "".join(rnd.choice("abc dé") for _ in range(rnd.randrange(200))) + base[a:b] + str(k)))
    got = sorted(((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup(clashing(spark, rows), threshold=size).collect()), key=repr)
    assert got == sorted(((d, *x) for (d, _), x in zip(rows, brute_suffix([(t or "").encode() for _, t in rows], size))), key=repr)


def test_every_window_has_one_run(monkeypatch):
    from treepack.llm import suffix_dedup as sd

    monkeypatch.setattr(sd, "SEGMENT", 1 << 11)  # long texts go in overlapping segments
    texts = [random.Random(3).randbytes(9000), b"a" * 700, b"b" * 99]
    got = [(k, s) for k, _, _, lo, n, _ in anchor_runs(texts, 100) for s in range(lo, lo + n)]
    assert sorted(got) == [(k, s) for k, t in enumerate(texts) for s in range(len(t) - 99)]


def test_suffix_dedup_of_nothing(spark):
    assert suffix_dedup(table(spark, [])).count() == 0


# --- similarity --------------------------------------------------------------------------


def around_the_limit():
    """Groups of texts whose similarities lie on both sides of 0.8 and close to it."""
    rnd, rows = random.Random(11), [(1, ""), (2, None), (3, "one two"), (4, "One two")]
    for k in range(60):
        base = [f"w{rnd.randrange(3000)}" for _ in range(rnd.choice([30, 120, 400]))]
        for j in range(5):
            t = list(base)
            for _ in range(round(len(t) * j * rnd.uniform(0.004, 0.012))):
                t[rnd.randrange(len(t))] = f"x{rnd.randrange(3000)}"
            rows.append((100 + 10 * k + j, " ".join(t)))
    return rows


def brute_similar(rows):
    sets = [set(sh.shingle_hashes((t or "").encode(), 5).tolist()) for _, t in rows]
    up = list(range(len(rows)))
    near = []
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            both = len(a & b)
            if a == b or 5 * both >= 4 * (len(a) + len(b) - both):
                x, y = up[i], up[j]
                up = [min(x, y) if u in (x, y) else u for u in up]
            if a | b:
                near.append(both / (len(a) + len(b) - both))
    return {d: min(e for (e, _), v in zip(rows, up) if v == u) for (d, _), u in zip(rows, up)}, near


@pytest.mark.parametrize("how", [{}, {"hot": 3, "hot_sets": 3}])
def test_similarity_is_exact_at_the_limit(spark, how):
    rows = around_the_limit()
    want, near = brute_similar(rows)
    assert sum(0.8 <= x < 0.85 for x in near) > 20 and sum(0.75 <= x < 0.8 for x in near) > 20
    assert {r.doc_id: r.component_id for r in sh.similar_dedup(table(spark, rows), **how).collect()} == want


def test_majorities_and_set_hashes():
    import numpy as np

    from treepack.llm.simhash import majority_bits, set_hashes, shingle_hashes

    draw = np.random.default_rng(2)
    for n in (0, 1, 2, 254, 255, 256, 4080, 4081, 9000):
        h = draw.integers(0, 2**64, n, dtype=np.uint64)
        set_in = [sum(int(v) >> k & 1 for v in h) for k in range(64)]
        assert majority_bits(h) == sum(1 << k for k, c in enumerate(set_in) if 2 * c > n)
    for text in (None, b"", b" \n", b"one", b"a B a b", b"a b c d e", b"x " * 3000, b"p q r s t u " * 50 + b"v"):
        h = set_hashes(text, 5)
        assert len(h) == len(set(shingle_hashes(text, 5).tolist())) and (h[1:] > h[:-1]).all()
    assert (set_hashes(b"A b\tC d  e F", 5) == set_hashes(b"a B c D E f", 5)).all()
