"""SimHash near-duplicate detection with exact tiled Hamming comparison.

Every text gets a 64-bit fingerprint of its word shingles. Fingerprints are
made distinct first, so copies cost nothing. Radius r over r+2 blocks of bits
leaves two blocks untouched in any pair within r, so each fingerprint goes to
one bucket for every pair of blocks and every link is in some bucket. A bucket
is sorted by population count and compared tile by tile by exclusive-or and
bit counts; tile pairs whose counts lie further apart than the radius are
skipped. Of a bucket's links a spanning forest is kept, never all pairs.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import give_back, map_rows, maybe_broadcast, scratch, stage, whole_runs
from treepack.llm.graph import connected_components

SEED = 42
BITS = 64


def shingle_hashes(text: bytes | None, shingle: int = 4) -> np.ndarray:
    """XXH64 of the space-joined shingles of words; A-Z lower-cased, ASCII white space between words."""
    words = (text or b"").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    if len(words) <= shingle:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), SEED)], np.uint64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    begins = np.concatenate(([0], ends[:-1]))[: len(words) - shingle + 1].tolist()
    digest = xxhash.xxh64_intdigest
    return np.array([digest(joined[a:b], SEED) for a, b in zip(begins, (ends[shingle - 1 :] - 1).tolist(), strict=True)], np.uint64)


def majorities(h: np.ndarray) -> bytes:
    """Each bit of rows of whole words set in over half of the rows, as little-endian words; 255 rows at a time are counted in bytes."""
    n, width = len(h), h.shape[1] * BITS
    counts = np.zeros(width, np.int64)
    octets = np.ascontiguousarray(h, "<u8").view(np.uint8)
    for at in range(0, n, 4080):
        bits = np.unpackbits(octets[at : at + 4080], axis=1, bitorder="little")
        whole = len(bits) // 255 * 255
        counts += np.add.reduce(bits[:whole].reshape(-1, 255, width), axis=1, dtype=np.uint8).sum(axis=0, dtype=np.int64)
        counts += np.add.reduce(bits[whole:], axis=0, dtype=np.uint8)
    return np.packbits(2 * counts > n, bitorder="little").tobytes()


def majority_bits(h: np.ndarray) -> int:
    """Each bit set in over half of h; zero if there is none."""
    return int.from_bytes(majorities(h[:, None]), "little")


def fingerprints(docs: DataFrame, shingle: int = 4) -> DataFrame:
    """(doc_id long, fp long); null or wordless texts have fingerprint zero."""

    def row(doc_id, text):
        v = majority_bits(shingle_hashes(text, shingle))
        return doc_id, v - (1 << 64) if v >> 63 else v

    return map_rows(docs.select(F.col("doc_id").cast("long"), "text"), row, "doc_id long, fp long")


class Forest:
    """Union of small integer labels; keeps the links that joined two trees."""

    def __init__(self, n: int):
        self.label, self.links = np.arange(n), []

    def add(self, i: np.ndarray, j: np.ndarray) -> None:
        while True:
            a, b = self.label[i], self.label[j]
            differ = a != b
            if not differ.any():
                return
            i, j, a, b = i[differ], j[differ], a[differ], b[differ]
            # each label hooks to its least neighbour; labels only fall, so this ends
            hi, lo = np.maximum(a, b), np.minimum(a, b)
            to = np.arange(len(self.label))
            np.minimum.at(to, hi, lo)
            moved = np.flatnonzero(to != np.arange(len(to)))
            self.links += zip(moved.tolist(), to[moved].tolist(), strict=True)
            while True:
                again = to[to]
                if (again == to).all():
                    break
                to = again
            self.label = to[self.label]


def distance(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Differing bits of fingerprints of one or several words (the last axis)."""
    return np.bitwise_count(x ^ y).sum(axis=-1, dtype=np.int32)


def tile_links(fp: np.ndarray, radius: np.ndarray | int, tile: int = 512) -> list[tuple[int, int]]:
    """Links that span the components of one bucket; rows of fp (words of a fingerprint) in order of population count.

    radius is one for all or one for each row, of which the larger counts.
    Tiles whose rows are one component already hold no link that is needed.
    """
    pc, forest = np.bitwise_count(fp).sum(axis=1, dtype=np.int32), Forest(len(fp))
    reach = np.broadcast_to(radius, len(fp))
    for a in range(0, len(fp), tile):
        x, r, top = fp[a : a + tile], reach[a : a + tile], int(pc[min(a + tile, len(fp)) - 1])
        for b in range(a, len(fp), tile):
            if int(pc[b]) - top > int(reach.max()):
                break
            mine = forest.label[a : a + tile]
            if b > a and (mine == mine[0]).all() and (forest.label[b : b + tile] == mine[0]).all():
                continue
            y, q = fp[b : b + tile], reach[b : b + tile]
            apart = sum(np.bitwise_count(x[:, None, k] ^ y[None, :, k]).astype(np.int16) for k in range(fp.shape[1]))
            i, j = np.nonzero(apart <= np.maximum(r[:, None], q[None, :]))
            forest.add(i + a, j + b)
    return forest.links


def bucket_links(bucket: np.ndarray, fp: np.ndarray, radius: np.ndarray | int, small: int = 32) -> list[tuple[int, int]]:
    """Links within all runs of equal buckets of a table sorted by bucket and population count.

    A run of up to `small` rows is one tile; the diagonals of all such tiles are
    compared together, and a row leaves once the population counts of its run
    lie further apart than the radius. Longer runs go tile by tile.
    """
    n = len(fp)
    begin, length = runs_of(bucket)
    pc = np.bitwise_count(fp).sum(axis=1, dtype=np.int32)
    reach = np.broadcast_to(radius, n)
    left = np.repeat(length, length) - (np.arange(n) - np.repeat(begin, length))  # rows of the run from here on
    forest, i, far = Forest(n), np.flatnonzero(np.repeat(length <= small, length)), int(reach.max()) if n else 0
    for d in range(1, small):
        i = i[left[i] > d]
        i = i[pc[i + d] - pc[i] <= far]  # counts only rise along a run
        if not len(i):
            break
        near = distance(fp[i], fp[i + d]) <= np.maximum(reach[i], reach[i + d])
        forest.add(i[near], i[near] + d)
    links = forest.links
    for s, k in zip(begin[length > small].tolist(), length[length > small].tolist(), strict=True):
        links += [(s + i, s + j) for i, j in tile_links(fp[s : s + k], reach[s : s + k])]
    return links


def runs_of(bucket: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First rows and lengths of the runs of equal values."""
    begin = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1]))) if len(bucket) else np.empty(0, int)
    return begin, np.diff(np.concatenate((begin, [len(bucket)])))


def _bucket_links(batches: Iterable[pa.RecordBatch], radius: int) -> Iterator[pa.RecordBatch]:
    for t in whole_runs(batches, ["bucket"]):
        fp = t.column("fp").to_numpy()
        yield from _edges(fp, bucket_links(t.column("bucket").to_numpy(), fp.view(np.uint64)[:, None], radius))
    give_back()


def _blocks(radius: int) -> list[tuple[int, int]]:
    """(first bit, width) of radius + 2 blocks."""
    n = radius + 2
    return [(BITS * k // n, BITS * (k + 1) // n - BITS * k // n) for k in range(n)]


def links(fps: DataFrame, *, radius: int = 4, hot: int = 1 << 14) -> DataFrame:
    """Edges (a, b) that connect every two distinct fingerprints within the radius, directly or by a path of such links.

    Buckets of over `hot` fingerprints are cut into parts, and each two parts
    near enough in population count are compared in a task of their own.
    """
    cut = _blocks(radius)
    bits = lambda b: f"(shiftrightunsigned(fp, {b[0]}) & {(1 << b[1]) - 1})"
    width = max(w for _, w in cut)
    keys = [f"{k}L << {2 * width} | {bits(p)} << {width} | {bits(q)}" for k, (p, q) in enumerate(combinations(cut, 2))]
    rows = fps.select("fp", F.expr("bit_count(fp)").alias("pc"), F.explode(F.expr(f"array({', '.join(keys)})")).alias("bucket"))
    rows = rows.select("fp", "pc", "bucket")
    return _compared(rows, ["fp"], lambda it: _bucket_links(it, radius), hot)


def _compared(rows: DataFrame, columns: list[str], compare, hot: int) -> DataFrame:
    """Links of all buckets of rows(bucket, pc, columns..)."""
    heavy = stage(rows.groupBy("bucket").agg(F.count("*").alias("n")).where(F.col("n") > hot), "simhash-hot")
    linked = lambda r: r.sortWithinPartitions("bucket", "pc").select("bucket", *columns).mapInArrow(compare, "a long, b long")
    if heavy.isEmpty():
        return linked(rows.repartition("bucket"))
    known = maybe_broadcast(heavy, 1_000_000)
    plain = linked(rows.join(known, "bucket", "left_anti").repartition("bucket"))
    # hot buckets: cells of bounded size by a hash, each pair of cells a bucket of its own
    part = rows.join(known, "bucket").withColumn("cells", F.ceil(F.col("n") / hot).cast("int"))
    part = part.withColumn("cell", F.pmod(F.xxhash64(*columns), F.col("cells")).cast("int"))
    first = part.withColumn("other", F.explode(F.expr("sequence(0, cells - 1)")))
    pair = first.select(F.xxhash64("bucket", F.least("cell", "other"), F.greatest("cell", "other")).alias("bucket"), "pc", *columns)
    return plain.union(linked(pair.repartition("bucket")))


def simhash_dedup(docs: DataFrame, *, shingle: int = 4, radius: int = 4) -> DataFrame:
    """(doc_id, fingerprint, component_id) for each row.

    component_id is the smallest doc_id among all documents reachable by links.
    Null and wordless texts share fingerprint zero and link like any other;
    rows that repeat a doc_id each get a row; an empty table gives none. Other
    columns of docs are ignored.
    """
    with scratch(docs.sparkSession) as keep:
        fps = keep(stage(fingerprints(docs, shingle), "simhash-fp"))
        distinct = stage(fps.groupBy("fp").agg(F.min("doc_id").alias("first")), "simhash-distinct")
        comp = connected_components(links(distinct.select("fp"), radius=radius), "simhash-cc")
        linked = stage(distinct.join(comp, distinct.fp == comp.node).select("fp", "first", "root"), "simhash-linked")
        least = stage(linked.groupBy("root").agg(F.min("first").alias("component_id")), "simhash-least")
        of_linked = linked.join(maybe_broadcast(least, 500_000), "root").select("fp", "component_id")
        alone = distinct.join(linked, "fp", "left_anti").select("fp", F.col("first").alias("component_id"))
        of_fp = keep(stage(of_linked.unionByName(alone), "simhash-of"))
    return fps.join(maybe_broadcast(of_fp, 500_000), "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


# --- by similarity ---------------------------------------------------------------------

ROWS = 4
WIDE = 256
#: Radii over WIDE bits for sets of shingles as similar as 0.8. A bit differs in 15 % of such pairs, 19 % where sets are
#: small and majorities narrow; the radius lies five standard deviations over that.
REACH, SMALL_REACH, SMALL_SET = 72, 84, 16
_POLYNOMIAL = np.uint64(0x9E3779B97F4A7C15)


def bands_for(similarity: float, recall: float) -> int:
    """Bands of ROWS minima that a pair of this similarity needs to share one with probability `recall`."""
    return max(1, int(np.ceil(np.log(1 - recall) / np.log1p(-(similarity**ROWS)))))


def set_hashes(text: bytes | None, shingle: int) -> np.ndarray:
    """The distinct shingles of a text as sorted 64-bit hashes: its words' XXH64 by a rolling polynomial, then mixed.

    Fewer words than a shingle are one shingle; words as in shingle_hashes.
    """
    words = (text or b"").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    of = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    n = max(1, len(of) - shingle + 1)
    h = np.full(n, min(len(of), shingle), np.uint64)
    for k in range(min(len(of), shingle)):
        h = h * _POLYNOMIAL + of[k : k + n]
    return np.unique(_mixed(h))


@cache
def _multipliers(k: int) -> np.ndarray:
    return np.random.default_rng(SEED).integers(0, 2**63, k, dtype=np.uint64)[:, None] * np.uint64(2) + np.uint64(1)


def minima(h: np.ndarray, k: int) -> np.ndarray:
    """The least value of a set of shingle hashes under each of k odd multipliers, which permute all 64-bit values."""
    odd = _multipliers(k)
    least = np.full(k, 2**64 - 1, np.uint64)
    for at in range(0, len(h), 2048):
        np.minimum(least, (odd * h[at : at + 2048]).min(axis=1), out=least)
    return least


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(32)
    return x


def wide_fingerprint(h: np.ndarray) -> bytes:
    """A SimHash of WIDE bits: the shingle hashes and mixings of them give a word each."""
    return majorities(np.stack([h if k == 0 else _mixed(h + np.uint64(k)) for k in range(WIDE // BITS)], axis=1))


def _signed(v: int) -> int:
    return v - (1 << 64) if v >> 63 else v


def sketch(h: np.ndarray, bands: int) -> tuple[int, int, list[int], bytes]:
    """(node, size, band keys, fingerprint) of sorted distinct hashes; node names the set."""
    least = minima(h, bands * ROWS)
    keys = [_signed(xxhash.xxh64_intdigest(row.tobytes(), k)) for k, row in enumerate(least.reshape(bands, ROWS))]
    return _signed(xxhash.xxh64_intdigest(h.tobytes(), SEED)), len(h), keys, wide_fingerprint(h)


def _spanning(n: int, near) -> list[tuple[int, int]]:
    """Links that span the components of n members; near(i) tells which are linked to i.

    Members inside the largest component are asked last, and no more once all
    that are left are connected, so n close copies cost one question.
    """
    forest, left = Forest(n), np.arange(n)
    while True:
        label = forest.label[left]
        if not len(left) or (label == label[0]).all():
            return forest.links
        at = int(np.flatnonzero(label != np.bincount(label).argmax())[0])
        j = np.flatnonzero(near(int(left[at])))
        forest.add(np.full(len(j), left[at]), j)
        left = np.delete(left, at)


def _edges(node: np.ndarray, links: list[tuple[int, int]]) -> Iterator[pa.RecordBatch]:
    if links:
        e = np.array(links)
        yield pa.RecordBatch.from_arrays([pa.array(node[e[:, 0]]), pa.array(node[e[:, 1]])], names=["a", "b"])


def _wide_links(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links of members of a bucket whose wide fingerprints leave it open that they are similar."""
    for t in whole_runs(batches, ["bucket"]):
        fp = np.frombuffer(b"".join(t.column("fp").to_pylist()), np.uint64).reshape(-1, WIDE // BITS)
        reach = np.where(t.column("size").to_numpy() < SMALL_SET, SMALL_REACH, REACH)
        yield from _edges(t.column("node").to_numpy(), bucket_links(t.column("bucket").to_numpy(), fp, reach))
    give_back()


def _jaccard_links(batches: Iterable[pa.RecordBatch], similarity: float) -> Iterator[pa.RecordBatch]:
    """Links of members of a bucket whose sets have that Jaccard similarity or more: common elements are counted over posting lists."""
    for t in whole_runs(batches, ["bucket"], least=1 << 8):
        node, sets = t.column("node").to_numpy(), t.column("hashes")
        links = []
        for s, n in zip(*(x.tolist() for x in runs_of(t.column("bucket").to_numpy())), strict=True):
            if n < 2:
                continue
            some = [np.frombuffer(v.as_py(), np.uint64) for v in sets.slice(s, n).chunk(0)]
            size = np.array([len(v) for v in some])
            token = np.unique(np.concatenate(some), return_inverse=True)[1].astype(np.int32)
            where = np.cumsum(size) - size
            order = np.argsort(token, kind="stable")
            owner = np.repeat(np.arange(n, dtype=np.int32), size)[order]
            first = np.searchsorted(token[order], np.arange(token.max() + 2)) if len(token) else np.zeros(1, int)

            def near(i, token=token, size=size, where=where, owner=owner, first=first, n=n):
                mine = token[where[i] : where[i] + size[i]]
                common = np.zeros(n, np.int64)
                for at in range(0, len(mine), 1024):
                    a, k = first[mine[at : at + 1024]], first[mine[at : at + 1024] + 1] - first[mine[at : at + 1024]]
                    rows = np.repeat(a - np.cumsum(k) + k, k) + np.arange(k.sum())
                    common += np.bincount(owner[rows], minlength=n)
                return common >= similarity * (size + size[i] - common) - 1e-9

            links += [(s + i, s + j) for i, j in _spanning(n, near)]
        yield from _edges(node, links)
    give_back()


def similar_dedup(docs: DataFrame, *, shingle: int = 5, similarity: float = 0.8, recall: float = 1 - 1e-6, hot: int = 1 << 14, hot_sets: int = 1 << 11) -> DataFrame:
    """(doc_id, text_key, component_id, kept): components of texts linked by shingle sets of Jaccard similarity `similarity` or more.

    A SimHash radius for that similarity is a quarter of the bits, so blocks of
    equal bits can't find pairs, and comparing all tiles would grow with the
    square of the input. Bands of minima make the buckets instead: two sets at
    the limit share one with probability `recall`, more similar ones with a
    higher one. In a bucket, wide SimHash fingerprints are compared tile by
    tile; pairs beyond the radius are set aside, the rest form loose components.
    Each loose component is then linked anew from the sets themselves, so every
    link has its true similarity, and no pair in a loose component is missed.
    Sets travel once for each text that has a candidate; a component of over
    `hot_sets` texts is cut into parts, and each two parts are compared in a
    task of their own.
    Texts without words are alike. component_id is the least doc_id; kept marks
    the rows with that id and, of such, the least text_key (Spark's xxhash64 of
    the text), so rows that repeat an id with different texts are told apart.
    An empty table gives an empty result; other columns of docs are ignored.
    """
    bands = bands_for(similarity, recall)

    def row(doc_id, text_key, text):
        return doc_id, text_key, *sketch(set_hashes(text, shingle), bands)

    def with_set(root, text):
        h = set_hashes(text, shingle)
        return root, _signed(xxhash.xxh64_intdigest(h.tobytes(), SEED)), len(h), h.tobytes()

    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), "text")
    with scratch(docs.sparkSession) as keep:
        fps = keep(stage(map_rows(keyed, row, "doc_id long, text_key long, node long, size long, bands array<long>, fp binary"), "similar-fp"))
        distinct = fps.groupBy("node").agg(F.min(F.struct("doc_id", "text_key")).alias("first"), F.first("size").alias("size"), F.first("bands").alias("bands"), F.first("fp").alias("fp"))
        distinct = keep(stage(distinct, "similar-distinct"))
        rows = distinct.where("size > 0").withColumn("pc", _population("fp")).select("node", "size", "fp", "pc", F.explode("bands").alias("bucket"))
        loose = stage(connected_components(_compared(rows, ["node", "size", "fp"], _wide_links, hot), "similar-loose"), "similar-roots")
        wanted = distinct.join(loose, "node").select(F.col("first.text_key").alias("text_key"), "root").distinct()
        texts = keyed.select("text_key", "text").join(maybe_broadcast(wanted, 500_000), "text_key").select("root", "text")
        sets = stage(map_rows(texts, with_set, "bucket long, node long, pc long, hashes binary").dropDuplicates(["bucket", "node"]), "similar-sets")
        comp = connected_components(_compared(sets, ["node", "hashes"], lambda it: _jaccard_links(it, similarity), hot_sets), "similar-cc")
        linked = stage(distinct.join(comp, "node").select("node", "first", "root"), "similar-linked")
        least = stage(linked.groupBy("root").agg(F.min("first").alias("keep")), "similar-least")
        of_linked = linked.join(maybe_broadcast(least, 500_000), "root").select("node", "keep")
        alone = distinct.join(linked, "node", "left_anti").select("node", F.col("first").alias("keep"))
        of_node = keep(stage(of_linked.unionByName(alone), "similar-of"))
    out = fps.select("doc_id", "text_key", "node").join(maybe_broadcast(of_node, 500_000), "node")
    kept = F.col("doc_id").eqNullSafe(F.col("keep.doc_id")) & (F.col("text_key") == F.col("keep.text_key"))
    return out.select("doc_id", "text_key", F.col("keep.doc_id").alias("component_id"), kept.alias("kept"))


def _population(fp: str) -> Column:
    """Set bits of a binary column, as the sum over its 8-byte words."""
    word = lambda k: F.conv(F.hex(F.substring(fp, 8 * k + 1, 8)), 16, -10).cast("long")
    return sum((F.bit_count(word(k)) for k in range(1, WIDE // BITS)), F.bit_count(word(0)))
