"""Exact deduplication by composable polynomial fingerprints.

A text is normalised by deleting white space and cut into chunks. A chunk's
hash is a polynomial in its bytes modulo two primes, all chunks of a text in
one matrix product; the hash of a joined text is `h(left) * base**len(right) +
h(right)`, so chunk hashes may come from anywhere. Texts over `huge_bytes` are
dealt out chunk by chunk to many tasks and their hashes joined by an ordered
fold. Texts with equal fingerprint and length meet the text of one of them,
their leader, and are compared with it chunk by chunk; those that differ from
it (colliding fingerprints) meet again under a leader of their own, so a
collision can't merge two texts.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterable, Iterator
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import SPACE, give_back, map_rows, maybe_broadcast, scratch, stage

# Two primes below 2**31 and a base for each.
PRIMES = (2147483647, 2147483629)
BASES = (1103515245, 1597334677)
#: 2**13 products of an 9-bit and a 31-bit number add up to less than 2**53, so float64 sums are exact.
CHUNK = 1 << 12
COMPARE = 1 << 16
_POWERS = np.array([[pow(r, CHUNK - 1 - i, p) for r, p in zip(BASES, PRIMES, strict=True)] for i in range(CHUNK)], dtype=np.float64)


def normalise(text: bytes | None) -> bytes:
    return (text or b"").translate(None, SPACE)


def chunk_hashes(data: bytes) -> tuple[int, int]:
    """Hash pair of one text: all chunk hashes at once, then joined left to right."""
    whole, rest = divmod(len(data), CHUNK)
    a = np.frombuffer(data, np.uint8).astype(np.float64) + 1.0
    parts = a[: whole * CHUNK].reshape(whole, CHUNK) @ _POWERS if whole else np.empty((0, 2))
    h = [0, 0]
    tail = a[whole * CHUNK :] @ _POWERS[CHUNK - rest :] if rest else None
    for k, (r, p) in enumerate(zip(BASES, PRIMES, strict=True)):
        shift, x = pow(r, CHUNK, p), 0
        for v in parts[:, k].astype(np.int64).tolist():
            x = (x * shift + v) % p
        h[k] = x if tail is None else join_hash(x, int(tail[k]) % p, rest, k)
    return h[0], h[1]


def join_hash(left: int, right: int, right_len: int, k: int) -> int:
    """Hash of a joined text from the hashes of its halves, modulus k."""
    return (left * pow(BASES[k], right_len, PRIMES[k]) + right) % PRIMES[k]


def _points(text: bytes) -> int:
    return len(text) - int(np.count_nonzero((np.frombuffer(text, np.uint8) & 0xC0) == 0x80))


_KEY = ("d", "no_id", "h1", "h2")


def _keyed(docs: DataFrame) -> DataFrame:
    """Rows named by id and two hashes of the text: rows that agree in them are copies, which may stand for one another."""
    doc_id = F.col("doc_id").cast("long")
    return docs.select(doc_id.alias("doc_id"), F.coalesce(doc_id, F.lit(0)).alias("d"), doc_id.isNull().alias("no_id"), F.xxhash64("text").alias("h1"), F.hash("text").alias("h2"), "text")


_FP = "doc_id long, d long, no_id boolean, h1 long, h2 int, points long, len long, fp long, text_sha256 string"


def fingerprints(docs: DataFrame, huge_bytes: int = 1 << 28, hashes: Callable[[bytes], tuple[int, int]] = chunk_hashes) -> DataFrame:
    """(doc_id, name of the row, points, len, fp, text_sha256) for each row; null text counts as empty."""

    def row(doc_id, d, no_id, h1, h2, text):
        data = normalise(text)
        h = hashes(data)
        return doc_id, d, no_id, h1, h2, _points(text or b""), len(data), h[0] << 31 | h[1], hashlib.sha256(data).hexdigest()

    docs = _keyed(docs)
    big = F.coalesce(F.octet_length("text"), F.lit(0)) > huge_bytes
    return map_rows(docs.where(~big), row, _FP).unionByName(huge_fingerprints(docs.where(big), hashes=hashes))


def huge_fingerprints(docs: DataFrame, piece: int = 1 << 22, hashes: Callable[[bytes], tuple[int, int]] = chunk_hashes) -> DataFrame:
    """The same from pieces spread over tasks: hash each, shift by the length of what follows, fold."""
    name = ["rid", "doc_id", *_KEY, "points", "text_sha256"]
    raw = docs.select(
        F.monotonically_increasing_id().alias("rid"), "doc_id", *_KEY, F.length("text").cast("long").alias("points"), F.sha2(_bare(), 256).alias("text_sha256"),
        F.col("text").cast("binary").alias("b"),
    )
    cut = raw.select(*name, "b", F.explode(F.expr(f"sequence(0, cast(octet_length(b) / {piece} as int))")).alias("k"))
    cut = cut.select(*name, "k", F.expr(f"substring(b, k * {piece} + 1, {piece})").alias("b")).repartition("rid", "k")

    def hashed(*cells):
        *same, k, b = cells
        data = normalise(b)
        return *(v.decode() if isinstance(v, bytes) else v for v in same), k, len(data), *hashes(data), *(pow(r, len(data), p) for r, p in zip(BASES, PRIMES, strict=True))

    part = map_rows(cut, hashed, "rid long, doc_id long, d long, no_id boolean, h1 long, h2 int, points long, text_sha256 string, k int, n long, x0 long, x1 long, s0 long, s1 long", step=4)
    whole = part.groupBy(*name).agg(F.array_sort(F.collect_list(F.struct("k", "n", "x0", "x1", "s0", "s1"))).alias("c"))
    fold = lambda i: F.expr(f"aggregate(c, 0L, (a, x) -> (a * x.s{i} + x.x{i}) % {PRIMES[i]}L)")
    return whole.select("doc_id", *_KEY, "points", F.expr("aggregate(c, 0L, (a, x) -> a + x.n)").alias("len"), F.shiftleft(fold(0), 31).bitwiseOR(fold(1)).alias("fp"), "text_sha256")


def _bare() -> Column:
    return F.translate(F.coalesce("text", F.lit("")), SPACE.decode(), "")


def _same(a: bytes, b: bytes) -> bool:
    """Chunkwise comparison; stops at the first chunk that differs."""
    x, y = memoryview(a), memoryview(b)
    return len(x) == len(y) and all(x[i : i + COMPARE] == y[i : i + COMPARE] for i in range(0, len(x), COMPARE))


_MEMBER = "doc_id long, points long, text_sha256 string, fp long, len long, salt long, same boolean, b binary"


def _against_leader(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (fp, len, salt), leader first: each is compared with the leader of its run, one text held at a time.

    A row that stands for a leader from elsewhere (`guest`) is not a member.
    Only texts that differ from their leader go on to the next round.
    """
    run, leader = None, b""
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            c = {name: part.column(name).to_pylist() for name in ("fp", "len", "salt", "guest", "b")}
            same = []
            for key, b in zip(zip(c["fp"], c["len"], c["salt"], strict=True), c["b"], strict=True):
                if key != run:
                    run, leader = key, b
                same.append(_same(leader, b))
            cells = [part.column(n) for n in ("doc_id", "points", "text_sha256", "fp", "len", "salt")]
            cells += [pa.array(same, pa.bool_()), pa.array([None if s else b for s, b in zip(same, c["b"], strict=True)], pa.binary())]
            out = pa.RecordBatch.from_arrays(cells, names=["doc_id", "points", "text_sha256", "fp", "len", "salt", "same", "b"])
            yield out.filter(pa.array([not g for g in c["guest"]], pa.bool_()))
    give_back()


def _round(rows: DataFrame) -> DataFrame:
    """rows(doc_id, points, text_sha256, fp, len, salt, salts, lead, b) compared with the leader of their (fp, len).

    Groups of several salts are dealt out by salt; each part gets a copy of the
    leader's text, so no task has more than a part.
    """
    columns = ["doc_id", "points", "text_sha256", "fp", "len", "salt", "b"]
    # of rows that bear the leader's name one text leads; the maximum is taken before the shuffle
    leaders = rows.where("lead and salts > 1").groupBy("fp", "len").agg(F.max("b").alias("b"), F.first("salts").alias("salts"))
    guests = leaders.select(F.lit(None).cast("long").alias("doc_id"), F.lit(0).cast("long").alias("points"), F.lit(None).cast("string").alias("text_sha256"), "fp", "len", F.explode(F.expr("sequence(0L, salts - 1)")).alias("salt"), "b")
    met = rows.select(*columns, F.lit(False).alias("guest")).unionByName(guests.select(*columns, F.lit(True).alias("guest")))
    met = met.repartition("fp", "len", "salt").sortWithinPartitions("fp", "len", "salt", F.desc("guest"))
    return met.mapInArrow(_against_leader, _MEMBER)


def exact_dedup(docs: DataFrame, *, huge_bytes: int = 1 << 28, per_salt: int = 512, broadcast_rows: int = 1_000_000, hashes: Callable[[bytes], tuple[int, int]] = chunk_hashes) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Equal are texts that are identical without white space (null: empty). Of a
    group the row with most code points, then smallest doc_id stays; of rows
    that repeat a doc_id with equal text, one is kept. A null doc_id sorts last.
    Groups of over per_salt rows are compared in salted parts, so no task gets a
    whole hot group. An empty table gives an empty result; other columns are
    ignored.
    """
    docs = docs.select("doc_id", "text")
    with scratch(docs.sparkSession) as keep:
        fps = keep(stage(fingerprints(docs, huge_bytes, hashes), "exact-fp"))
        many = fps.groupBy("fp", "len").agg(F.count("*").alias("n"), F.min(F.struct("no_id", "d", "h1", "h2")).alias("leader")).where("n > 1")
        many = keep(stage(many.select("fp", "len", F.ceil(F.col("n") / per_salt).alias("salts"), "leader"), "exact-many"))
        group = maybe_broadcast(many, broadcast_rows)
        named = fps.join(group, ["fp", "len"]).select(*_KEY, "points", "text_sha256", "fp", "len", "salts", (F.struct("no_id", "d", "h1", "h2") == F.col("leader")).alias("lead"))
        named = stage(named.distinct(), "exact-named")
        # copies lie in many partitions of the table, so its partitions make the salts
        texts = _keyed(docs).withColumn("part", F.spark_partition_id()).join(maybe_broadcast(named, broadcast_rows), list(_KEY))
        salt = F.pmod(F.xxhash64(*_KEY, "part"), F.col("salts"))
        rows = texts.select("doc_id", "points", "text_sha256", "fp", "len", salt.alias("salt"), "salts", "lead", _bare().cast("binary").alias("b"))
        found = []
        for k in count():
            now = keep(stage(_round(rows), f"exact-round-{k}"))
            found.append(now.where("same").select("doc_id", "points", "text_sha256", "fp", "len", F.lit(k).alias("cls")))
            left = now.where("not same")
            if left.isEmpty():  # always, but for colliding fingerprints; every round settles one text of each group
                break
            least = left.groupBy("fp", "len").agg(F.min("text_sha256").alias("leader"), F.ceil(F.count("*") / per_salt).alias("salts"))
            rows = left.join(least, ["fp", "len"]).select("doc_id", "points", "text_sha256", "fp", "len", F.pmod("salt", "salts").alias("salt"), "salts", (F.col("text_sha256") == F.col("leader")).alias("lead"), "b")
        members = found[0]
        for f in found[1:]:
            members = members.unionByName(f)
        members = keep(stage(members.withColumn("row", F.monotonically_increasing_id()), "exact-members"))
    best = F.min(F.struct((-F.col("points")).alias("p"), F.col("doc_id").isNull().alias("z"), F.col("doc_id").alias("d"), F.col("row").alias("row")))
    groups = members.groupBy("fp", "len", "cls").agg(F.count("*").alias("group_size"), best.alias("best"))
    groups = maybe_broadcast(stage(groups, "exact-groups"), broadcast_rows)
    copies = members.join(groups, ["fp", "len", "cls"]).select("doc_id", F.col("best.d").alias("keep_id"), "group_size", (F.col("row") == F.col("best.row")).alias("kept"), "text_sha256")
    single = fps.join(group, ["fp", "len"], "left_anti")
    lone = single.select("doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "text_sha256")
    return lone.unionByName(copies)
