"""Best-fit packing of documents into sequences by the sum of squares rule.

Tokenisation turns texts into pieces of at most `capacity` tokens. A packer
keeps N[g], the number of open bins with g places left, and puts each piece
where the sum of N[g]**2 becomes least; that keeps the gaps evenly spread and
so fillable. Pieces are packed in groups of bounded size, in parallel; what
stays open after a level is packed again, as a single piece per bin, with the
open bins of other groups, until one group holds all or a level saves too little.
"""

from __future__ import annotations

import zlib

import numpy as np
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import map_groups, stage

CAPACITY = 4096
END_OF_TEXT = 1
# Fixed value: how the tokenizer file splits text into words (white space drops out).
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\p{White_Space}\p{L}\p{N}]+"


class WordBPE:
    """A tokenizer file whose words are coded apart, so each different word is coded once per worker.

    A text that may hold one of the file's added tokens goes to the tokenizer as it is.
    """

    _made: dict = {}

    def __init__(self, path: str, keep_words: int = 600_000, block: int = 2000):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.added = [t.content[:2] for t in self.tok.get_added_tokens_decoder().values()]
        self.words, self.keep, self.block = regex.compile(WORDS), keep_words, block
        vocab = self.tok.get_vocab(with_added_tokens=True)
        self.last = np.zeros(max(vocab.values()) + 1, bool)  # tokens that end a word
        self.last[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self.ids: dict[str, bytes] = {}

    @classmethod
    def of(cls, path: str) -> WordBPE:
        if path not in cls._made:
            cls._made[path] = cls(path)
        return cls._made[path]

    def normal(self, text: str) -> str:
        """The tokenizer's own normaliser; of Latin-1 text all that matters is the lower case."""
        try:
            text.encode("latin-1")
            return text.lower()
        except UnicodeEncodeError:
            return self.tok.normalizer.normalize_str(text)

    def learn(self, words: set[str]) -> None:
        if len(self.ids) + len(words) > self.keep:
            self.ids.clear()
        new = sorted(w for w in words if w not in self.ids)
        blocks = [new[i : i + self.block] for i in range(0, len(new), self.block)]
        for block, e in zip(blocks, self.tok.encode_batch_fast([" ".join(b) for b in blocks], add_special_tokens=False), strict=True):
            ids = np.array(e.ids, "<u4")
            ends = (np.flatnonzero(self.last[ids]) + 1).tolist()
            if len(ends) == len(block):
                raw = ids.tobytes()
                self.ids.update(zip(block, [raw[4 * a : 4 * b] for a, b in zip([0, *ends], ends)], strict=True))
            else:  # a word without an ending token; code the words one by one
                self.ids.update((w, np.array(x.ids, "<u4").tobytes()) for w, x in zip(block, self.tok.encode_batch(block, add_special_tokens=False), strict=True))

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        odd = {k for k, t in enumerate(texts) if any(a in t for a in self.added)}
        words = [[] if k in odd else self.words.findall(self.normal(t)) for k, t in enumerate(texts)]
        if unknown := set().union(*words).difference(self.ids):
            self.learn(unknown)
        try:
            out = [b"".join(map(self.ids.__getitem__, w)) for w in words]
        except KeyError:  # the table of words was emptied
            self.learn(set().union(*words))
            out = [b"".join(map(self.ids.__getitem__, w)) for w in words]
        for k in odd:
            out[k] = np.array(self.tok.encode(texts[k], add_special_tokens=False).ids, "<u4").tobytes()
        return out


def pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32[, ids]): a document's ids and the end mark, cut only where over capacity."""
    end = np.array([END_OF_TEXT], "<u4").tobytes()

    def many(tok, rows):
        out = []
        for (doc_id, _), ids in zip(rows, tok.encode([(t or b"").decode() for _, t in rows]), strict=True):
            ids += end
            for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                part = ids[at : at + 4 * capacity]
                out.append((doc_id, k, at // 4, len(part) // 4, zlib.crc32(part)) + ((part,) if with_ids else ()))
        return out

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * with_ids
    return map_groups(docs.select(F.col("doc_id").cast("long"), "text"), many, schema, start=lambda: WordBPE.of(path))


class SumOfSquares:
    """Online packer: N counts the open bins of each gap, stacks hold which they are."""

    def __init__(self, capacity: int):
        self.capacity, self.n = capacity, np.zeros(capacity + 1, np.int64)
        self.open: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.bins = 0

    def place(self, size: int) -> tuple[int, int]:
        """(bin, offset). Moving a bin from gap g to g - size changes the sum by 2 (N[g-size] - N[g]) + 2; a new bin by 2 N[capacity-size] + 1."""
        n, c = self.n, self.capacity
        best_gap, best = 0, 2 * int(n[c - size]) + 1 if size < c else 0
        gaps = n[size:]
        if len(gaps):
            change = 2 * (n[: c + 1 - size] - gaps) + 2
            change[0] = 1 - 2 * gaps[0]  # a full bin no longer counts
            change[gaps == 0] = 1 << 60
            k = int(change.argmin())
            if change[k] <= best:
                best_gap = k + size
        if best_gap:
            b = self.open[best_gap].pop()
            n[best_gap] -= 1
        else:
            best_gap, b, self.bins = c, self.bins, self.bins + 1
        left = best_gap - size
        if left:
            n[left] += 1
            self.open[left].append(b)
        return b, c - best_gap


def pack_sizes(sizes: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray]:
    """(bin, offset) of each size, in the order given; placed from the largest to the smallest.

    The rule keeps bins of every gap open for what is still to come, and the
    small sizes that come last close them; of equal changes the tightest gap wins.
    """
    packer = SumOfSquares(capacity)
    where, offset = np.empty(len(sizes), np.int64), np.empty(len(sizes), np.int64)
    order = np.argsort(-sizes, kind="stable")
    for i, s in zip(order.tolist(), sizes[order].tolist(), strict=True):
        where[i], offset[i] = packer.place(s)
    return where, offset


def _pack_group(pdf, capacity: int):
    pdf = pdf.sort_values(["h", "id"], kind="stable")
    where, offset = pack_sizes(pdf["size"].to_numpy(), capacity)
    pdf["bin"], pdf["shift"] = (pdf["grp"].to_numpy() << 32) + where, offset
    return pdf[["id", "size", "bin", "shift"]]


def pack(items: DataFrame, *, capacity: int = CAPACITY, group: int = 8192, worth: int = 64) -> DataFrame:
    """items(id long unique, size long) -> (id, size, sequence_id, offset).

    Groups hold about `group` items, dealt by a hash of the id. A level packs
    all groups apart; the bins with room left are the items of the next level,
    which has few of them, and so on until a level has one group or joins fewer
    than one in `worth` of its items. Each level but the last is thus smaller by
    that share at least, so there are no more than log(items) / log(1 + 1 / worth).
    """
    level, items = 0, stage(items, "pack-items")
    total = items.count()
    placed = None
    while True:
        n = -(-total // group)
        h = F.xxhash64("id", F.lit(level))
        dealt = items.select("id", "size", h.alias("h"), F.pmod(h, F.lit(max(n, 1))).alias("grp"))
        done = dealt.groupBy("grp").applyInPandas(lambda pdf: _pack_group(pdf, capacity), "id long, size long, bin long, shift long")
        done = stage(done.withColumn("bin", F.lit(level << 56) + F.col("bin")), f"pack-{level}")
        if placed is None:
            placed = done.select("id", "size", F.col("bin").alias("sequence_id"), F.col("shift").alias("offset"))
        else:
            moved = done.select(F.col("id").alias("sequence_id"), "bin", "shift")
            placed = placed.join(moved, "sequence_id", "left").select("id", "size", F.coalesce("bin", "sequence_id").alias("sequence_id"), (F.col("offset") + F.coalesce("shift", F.lit(0))).alias("offset"))
        if n <= 1:
            return placed
        items = done.groupBy("bin").agg(F.sum("size").alias("size")).where(F.col("size") < capacity).select(F.col("bin").alias("id"), "size")
        items, level = stage(items, f"pack-open-{level}"), level + 1
        before, total = total, items.count()
        if total == 0 or (before - total) * worth < before:
            return placed


def pack_documents(docs: DataFrame, path: str, *, capacity: int = CAPACITY) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    A null text has the end mark alone. Only documents over capacity are cut,
    into pieces of capacity tokens and a rest. Rows that repeat a doc_id are
    packed each; an empty table gives an empty result.
    """
    cut = pieces(docs, path, capacity).withColumn("id", F.monotonically_increasing_id())
    cut = stage(cut, "pack-pieces")
    where = pack(cut.select("id", F.col("length").alias("size")), capacity=capacity)
    return cut.join(where.drop("size"), "id").drop("id")
