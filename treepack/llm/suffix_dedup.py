"""Removal of repeated passages: depth-limited radix sort of suffixes.

Suffixes are ordered only through the first `threshold` bytes, by passes that
split groups of suffixes by their next digit; a group that is down to one
member stops, and groups that are equal through the threshold are exactly the
repeated windows. A pass's digit is the hash of a stretch of bytes, so one pass
is one DataFrame aggregation, and suffixes go in runs, not one by one:

* pass 0 splits by an anchor, the least k-gram of a suffix's window. Equal
  windows have equal anchors at equal distance, and about 190 neighbouring
  suffixes share one, so they travel as one row.
* pass 1 splits runs of one anchor by all their bytes. Equal runs are repeated
  as a whole; an anchor with one kind of run stops.
* pass 2 cuts the remaining runs into slices of 16 suffixes and splits by the
  bytes that all windows of a slice share, then by the slice's bytes.
* pass 3 splits the slices that agree in the former only into single windows.

Digits are 64-bit hashes on top of the 64-bit anchor hash.
"""

from __future__ import annotations

import hashlib

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import map_groups, stage

GRAM = 32
SLICE = 16
SEGMENT = 1 << 20
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53)]


def gram_hashes(data: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the GRAM bytes from each position, by doubling the span."""
    h = (data.astype(np.uint64) + np.uint64(1)) * _MIX[0]
    span, k = 1, 1
    while span < GRAM:
        h = h[:-span] * _MIX[k] + h[span:]
        h ^= h >> np.uint64(31)
        span, k = 2 * span, k + 1
    h *= _MIX[0]
    return h ^ (h >> np.uint64(29))


def window_anchors(h: np.ndarray, width: int) -> np.ndarray:
    """Position of the least hash, leftmost of equals, in each window of `width` hashes."""
    pos_bits = np.uint64(SEGMENT.bit_length())
    key = (h & ~np.uint64((1 << int(pos_bits)) - 1)) | np.arange(len(h), dtype=np.uint64)
    blocks = -(-len(key) // width)
    rows = np.full(blocks * width, np.iinfo(np.uint64).max, np.uint64)
    rows[: len(key)] = key
    rows = rows.reshape(blocks, width)
    ahead = np.minimum.accumulate(rows, axis=1).ravel()
    behind = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    n = len(key) - width + 1
    least = np.minimum(behind[:n], ahead[width - 1 : width - 1 + n])
    return (least & np.uint64((1 << int(pos_bits)) - 1)).astype(np.int64)


def anchor_runs(texts: list[bytes], threshold: int) -> list[tuple[int, int, int, int, int, int]]:
    """(text number, anchor hash, run hash, first start, number of starts, anchor minus first start).

    Texts are laid end to end into segments; a long text goes in overlapping
    segments, which may cut a run in two but loses no window.
    """
    out: list[tuple] = []
    block: list[tuple[int, int, bytes]] = []
    size = 0
    for k, t in enumerate(texts):
        for at in range(0, max(len(t) - threshold + 1, 0), SEGMENT - threshold + 1):
            part = t[at : at + SEGMENT] if len(t) > SEGMENT else t
            if size + len(part) > SEGMENT:
                out += _segment_runs(block, threshold)
                block, size = [], 0
            block.append((k, at, part))
            size += len(part)
            if part is t:
                break
    return out + _segment_runs(block, threshold)


def _segment_runs(block: list[tuple[int, int, bytes]], threshold: int) -> list[tuple]:
    if not block:
        return []
    data = b"".join(p for _, _, p in block)
    if len(data) < threshold:
        return []
    h = gram_hashes(np.frombuffer(data, np.uint8))
    anchor = window_anchors(h, threshold - GRAM + 1)
    size = np.array([len(p) for _, _, p in block])
    end = np.cumsum(size)
    begin = end - size
    ok = np.zeros(len(anchor) + 1, bool)
    for b, e in zip(begin.tolist(), end.tolist()):
        if e - b >= threshold:
            ok[b : e - threshold + 1] = True
    starts = np.flatnonzero(ok)
    starts = starts[starts < len(anchor)]
    if not len(starts):
        return []
    a = anchor[starts]
    new = np.concatenate(([True], (a[1:] != a[:-1]) | (starts[1:] != starts[:-1] + 1)))
    first = np.flatnonzero(new)
    count = np.diff(np.concatenate((first, [len(starts)])))
    lo, pos = starts[first], a[first]
    of = np.searchsorted(end, lo, side="right")
    digest = xxhash.xxh3_64_intdigest
    kh = h[pos].view(np.int64).tolist()
    out = []
    for g, s, n, off, d in zip(kh, lo.tolist(), count.tolist(), (pos - lo).tolist(), of.tolist(), strict=True):
        k, at, _ = block[d]
        out.append((k, g, signed(digest(data[s : s + n - 1 + threshold], off << 12 | n)), s - int(begin[d]) + at, n, off))
    return out


def signed(v: int) -> int:
    return v - (1 << 64) if v >> 63 else v


def _key(doc_id, text: bytes) -> tuple[int, int]:
    """Rows are told apart by id and text, so rows that repeat an id keep their own spans; a null id counts as -1 here."""
    return -1 if doc_id is None else doc_id, signed(xxhash.xxh64_intdigest(text, 42))  # as Spark's xxhash64


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "text", F.coalesce("doc_id", F.lit(-1)).alias("doc"), F.xxhash64("text").alias("th"))


def _runs(docs: DataFrame, threshold: int) -> DataFrame:
    """Pass 0: all runs of all texts."""

    def many(rows):
        texts = [t or b"" for _, t in rows]
        keys = [_key(d, t) for (d, _), t in zip(rows, texts, strict=True)]
        return [(*keys[k], g, c, lo, n, off) for k, g, c, lo, n, off in anchor_runs(texts, threshold)]

    return map_groups(docs, many, "doc long, th long, kh long, ch long, lo int, n int, off int", nbytes=1 << 21)


_RUN = ("doc", "th", "lo", "n")


def repeated_runs(docs: DataFrame, threshold: int = 400) -> DataFrame:
    """(doc, th, lo, n): runs of n starts from lo whose windows of `threshold` bytes all start elsewhere too."""
    runs = stage(_runs(docs, threshold), "suffix-runs")
    anchors = runs.groupBy("kh").agg(F.count("*").alias("c"), F.min("ch").alias("x"), F.max("ch").alias("y")).where("c > 1").select("kh", (F.col("x") != F.col("y")).alias("split"))
    anchors = stage(anchors, "suffix-anchors")  # apart, so that the join below may split a hot anchor
    alive = stage(runs.join(anchors, "kh"), "suffix-alive")
    same = alive.where("not split").select(*_RUN)
    # pass 1: kinds of runs of one anchor; one stands for all equal ones, with their number
    kinds = alive.where("split").groupBy("kh", "ch").agg(F.count("*").alias("w"), F.min(F.struct("doc", "th", "lo", "n", "off")).alias("one"))
    kinds = stage(kinds.select("kh", "ch", "w", "one.*"), "suffix-kinds")
    whole = alive.where("split").join(kinds.where("w > 1").select("kh", "ch"), ["kh", "ch"]).select(*_RUN)
    context = stage(_contexts(docs, kinds, threshold), "suffix-contexts")
    # pass 2: slices
    out = [same, whole]
    cut = lambda rows, width, name: stage(_cut(rows, width, threshold), name)
    slices = cut(context, SLICE, "suffix-slices")
    found, mixed = _split(slices)
    # pass 3: single windows of the slices that are neither repeated as a whole nor alone
    left = mixed.select("kh", "ch", "from", "many", "w")
    single = cut(context.drop("w", "from", "many").join(left, ["kh", "ch"]), 1, "suffix-single")
    last, _ = _split(single)
    return _union([*out, found, last])


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def _contexts(docs: DataFrame, kinds: DataFrame, threshold: int) -> DataFrame:
    """The bytes of each kind of run, from the text of the row that stands for it."""
    wanted = kinds.groupBy("doc", "th").agg(F.collect_list(F.struct("kh", "ch", "w", "lo", "n", "off")).alias("runs"))
    joined = _keyed(docs).join(wanted.hint("shuffle_hash"), ["doc", "th"]).select("doc", "th", "text", "runs")

    def many(rows):
        out = []
        for doc, th, text, runs in rows:
            out += [(doc, th, r["lo"], r["off"], r["kh"], r["ch"], r["w"], 0, r["n"], text[r["lo"] : r["lo"] + r["n"] - 1 + threshold]) for r in runs]
        return out

    one = map_groups(joined, many, "doc long, th long, lo int, off int, kh long, ch long, w long, from int, many int, b binary", nbytes=1 << 21, step=64)
    return one.dropDuplicates(["kh", "ch"])  # a row that repeats id and text stands twice


def _cut(rows: DataFrame, width: int, threshold: int) -> DataFrame:
    """Runs cut at multiples of `width` from their anchor: core is shared by all windows of a full slice, cls is the slice itself."""

    def many(group):
        out, digest = [], xxhash.xxh3_64_intdigest
        for doc, th, lo, off, kh, ch, w, at, n, b in group:
            s = at
            while s < at + n:
                cell = (s - off) // width  # the anchor is at off, so s - off is the start as seen from it
                e = min(at + n, (cell + 1) * width + off)
                last = (cell + 1) * width - 1 + off
                core = digest(b[max(last, 0) : cell * width + off + threshold], (kh & 0xFFFFFFFF) << 16 | (cell & 0xFFFF))
                cls = digest(b[s : e - 1 + threshold], (s - off) << 16 & 0xFFFFFFFF | (e - s))
                out.append((doc, th, lo, kh, ch, w, s, e - s, signed(core), signed(cls)))
                s = e
        return out

    columns = ["doc", "th", "lo", "off", "kh", "ch", "w", "from", "many", "b"]
    return map_groups(rows.select(*columns), many, "doc long, th long, lo int, kh long, ch long, w long, from int, many int, core long, cls long")


def _split(slices: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(repeated runs, one slice of each kind of the groups that hold several kinds)."""
    kinds = slices.groupBy("kh", "core", "cls").agg(F.sum("w").alias("total"), F.count("*").alias("rows"), F.min(F.struct("ch", "from", "many")).alias("one"))
    kinds = stage(kinds, "suffix-split")
    repeated = slices.where("w = 1").join(kinds.where("total > 1 and rows > 1").select("kh", "core", "cls"), ["kh", "core", "cls"])
    found = repeated.select("doc", "th", (F.col("lo") + F.col("from")).alias("lo"), F.col("many").alias("n"))
    several = kinds.groupBy("kh", "core").agg(F.count("*").alias("k")).where("k > 1").select("kh", "core")
    mixed = kinds.join(several, ["kh", "core"]).select("kh", F.col("one.ch").alias("ch"), F.col("one.from").alias("from"), F.col("one.many").alias("many"), F.col("total").alias("w"))
    return found, mixed


def kept_text(text: bytes, runs: list[tuple[int, int]], threshold: int) -> tuple[bytes, int, int]:
    """(what is left, removed bytes, maximal removed spans)."""
    spans: list[list[int]] = []
    for lo, n in sorted(runs):
        hi = lo + n - 1 + threshold
        if spans and lo <= spans[-1][1]:
            spans[-1][1] = max(spans[-1][1], hi)
        else:
            spans.append([lo, hi])
    at, kept = 0, []
    for a, b in spans:
        kept.append(text[at:a])
        at = b
    kept.append(text[at:])
    return b"".join(kept), sum(b - a for a, b in spans), len(spans)


def suffix_dedup(docs: DataFrame, *, threshold: int = 400, with_text: bool = False) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256[, kept binary]) for each row.

    Removed is each byte covered by a window of `threshold` bytes that starts
    anywhere else too, in any text or the same one; windows are judged on the
    input. Null and short texts lose nothing. Rows that repeat an id and text
    are copies of each other. An empty table gives an empty result.
    """
    docs = docs.select(F.col("doc_id").cast("long"), "text")
    runs = stage(repeated_runs(docs, threshold), "suffix-found")
    of_doc = runs.groupBy("doc", "th").agg(F.collect_set(F.struct("lo", "n")).alias("runs"))
    joined = _keyed(docs).join(of_doc.hint("shuffle_hash"), ["doc", "th"], "left").select("doc_id", "text", "runs")

    def many(rows):
        out = []
        for doc_id, text, mine in rows:
            text = text or b""
            kept, removed, spans = kept_text(text, [(r["lo"], r["n"]) for r in mine or ()], threshold)
            out.append((doc_id, len(text), removed, spans, hashlib.sha256(kept).hexdigest()) + ((kept,) if with_text else ()))
        return out

    return map_groups(joined, many, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * with_text, nbytes=1 << 21)
