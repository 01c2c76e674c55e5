"""Byte-level BPE by recursive DuckDB queries.

A worker holds one in-process DuckDB with two tables: the vocabulary and the
merges (every way to join two tokens into a third). Words that it has not seen
become token-position rows; a recursive query joins neighbouring rows to the
merges, contracts each word's leftmost pair of least rank, and goes on until no
word has a pair left. Words repeat, so their ids are kept in a bounded table; a
text is the concatenation of its words. Decoding takes any ids: token-position
rows join the vocabulary and are concatenated in order.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import threading

import duckdb
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import map_groups

# Fixed value: how many bits hold a position within a word in the query below.
_POS = 20
_ENCODE = f"""
WITH RECURSIVE whole AS MATERIALIZED (SELECT wid, id FROM words JOIN vocab ON token = word),
state AS (
  SELECT 0 AS step, (w.wid::BIGINT << {_POS}) + u.pos AS slot, s.id AS tok
  FROM (SELECT wid, hex(word) AS h, octet_length(word) AS n FROM words ANTI JOIN whole USING (wid)) w,
       unnest(range(w.n)) AS u(pos) JOIN single s ON s.h = substr(w.h, 2 * u.pos + 1, 2)
  UNION ALL
  (WITH best AS (
     SELECT l.slot >> {_POS} AS wid, min(m.into_id::BIGINT << {_POS} | (l.slot & {(1 << _POS) - 1})) AS r
     FROM state l JOIN state n ON n.slot = l.slot + 1 JOIN merge m ON m.pair = (l.tok::BIGINT << 20 | n.tok) GROUP BY 1),
   placed AS (SELECT step, slot, tok, slot & {(1 << _POS) - 1} AS pos, r & {(1 << _POS) - 1} AS hit, (r >> {_POS})::INT AS into_id
              FROM state JOIN best ON wid = slot >> {_POS})
   SELECT step + 1, slot - (pos > hit)::BIGINT, CASE WHEN pos = hit THEN into_id ELSE tok END FROM placed WHERE pos <> hit + 1)
)
SELECT slot >> {_POS} AS wid, string_agg(v.le, '' ORDER BY slot) AS ids FROM state
JOIN (SELECT slot >> {_POS} AS w, max(step) AS last FROM state GROUP BY 1) z ON w = slot >> {_POS} AND step = last
JOIN vocab v ON v.id = tok GROUP BY 1
UNION ALL SELECT wid, v.le FROM whole JOIN vocab v USING (id)
"""
_DECODE = "SELECT part, string_agg(v.h, '' ORDER BY pos) AS bytes FROM tokens JOIN vocab v USING (id) GROUP BY part"
#: Tokens that one decoding query takes.
_TOKENS = 1 << 20


class ByteBPE:
    """Encoder and decoder of one rank file; one per Python worker."""

    _made: dict = {}
    _lock = threading.Lock()

    def __init__(self, path: str, pattern: str, keep_words: int = 1_000_000, long_word: int = 1024, block: int = 16_384):
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.pattern, self.keep_words, self.long_word, self.block = regex.compile(pattern), keep_words, long_word, block
        self.most = max(self.ranks.values())
        self.known = np.zeros(self.most + 1, bool)
        self.known[list(self.ranks.values())] = True
        self.ids: dict[str, bytes] = {}
        self.db = duckdb.connect(config={"threads": 1, "memory_limit": "400MB", "temp_directory": ""})
        vocab_rows = pa.table(  # noqa: F841
            {
                "token": pa.array(list(self.ranks), pa.binary()), "id": pa.array(list(self.ranks.values()), pa.int32()),
                "h": [t.hex().upper() for t in self.ranks], "le": [i.to_bytes(4, "little").hex() for i in self.ranks.values()],
            }
        )
        self.db.execute("CREATE TABLE vocab AS SELECT * FROM vocab_rows")
        self.db.execute("CREATE TABLE single AS SELECT h, id FROM vocab WHERE octet_length(token) = 1")
        self.db.execute(
            "CREATE TABLE merge AS SELECT (l.id::BIGINT << 20 | r.id) AS pair, v.id AS into_id "
            "FROM (SELECT id, h, octet_length(token) AS n FROM vocab) v, unnest(range(1, v.n)) AS u(k) "
            "JOIN vocab l ON l.h = left(v.h, 2 * u.k) JOIN vocab r ON r.h = substr(v.h, 2 * u.k + 1)"
        )

    @classmethod
    def of(cls, path: str, pattern: str) -> ByteBPE:
        with cls._lock:
            if (path, pattern) not in cls._made:
                cls._made[path, pattern] = cls(path, pattern)
            return cls._made[path, pattern]

    def learn(self, words: set[str]) -> None:
        """Encode and decode words that are not known yet."""
        new = sorted(w for w in words if w not in self.ids)
        if len(self.ids) + len(new) > self.keep_words:
            self.ids.clear()
            new = sorted(words)
        data = [w.encode() for w in new]
        short = [i for i, b in enumerate(data) if len(b) <= self.long_word]
        for at in range(0, len(short), self.block):
            part = short[at : at + self.block]
            words = pa.table({"wid": pa.array(part, pa.int32()), "word": pa.array([data[i] for i in part], pa.binary())})
            self.db.register("words", words)
            self.ids.update((new[i], bytes.fromhex(ids)) for i, ids in self.db.execute(_ENCODE).fetchall())
        # the recursion writes a word anew at each step, too much for very long ones
        self.ids.update((new[i], np.array(merge_long(b, self.ranks), "<u4").tobytes()) for i, b in enumerate(data) if len(b) > self.long_word)

    def encode(self, texts: list[str]) -> list[list[bytes]]:
        """Of each text, the ids of each word as little-endian unsigned 32-bit integers. New words are learnt together."""
        words = [self.pattern.findall(t) for t in texts]
        if unknown := set().union(*words).difference(self.ids):
            self.learn(unknown)
        try:
            return [list(map(self.ids.__getitem__, w)) for w in words]
        except KeyError:  # the table of words was emptied
            self.learn(set().union(*words))
            return [list(map(self.ids.__getitem__, w)) for w in words]

    def decode(self, coded: list[bytes]) -> list[bytes]:
        """Bytes of each list of ids (little-endian unsigned 32-bit); ids that are not in the vocabulary raise."""
        out: list[list[bytes]] = [[] for _ in coded]
        parts = [(k, c[at : at + 4 * _TOKENS]) for k, c in enumerate(coded) for at in range(0, len(c), 4 * _TOKENS)]
        while parts:
            some, size = [], 0
            while parts and (not some or size + len(parts[0][1]) <= 4 * _TOKENS):
                some.append(parts.pop(0))
                size += len(some[-1][1])
            ids = np.frombuffer(b"".join(c for _, c in some), "<u4")
            if len(ids) and int(ids.max()) > self.most or not self.known[ids].all():
                raise ValueError("an id is not in the vocabulary")
            part = np.repeat(np.arange(len(some), dtype=np.int32), [len(c) // 4 for _, c in some])
            self.db.register("tokens", pa.table({"part": part, "pos": np.arange(len(ids), dtype=np.int32), "id": ids.astype(np.int32)}))
            for k, h in sorted(self.db.execute(_DECODE).fetchall()):
                out[some[k][0]].append(bytes.fromhex(h))
        return [b"".join(x) for x in out]


def merge_long(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The same merges for one very long word, with a heap of pairs: leftmost least rank first."""
    if word in ranks:
        return [ranks[word]]
    n = len(word)
    end = list(range(1, n + 1))  # where the token that begins here ends; 0: merged into an earlier one
    before = list(range(-1, n - 1))
    heap = [(ranks[word[i : i + 2]], i, i + 1, i + 2) for i in range(n - 1) if word[i : i + 2] in ranks]
    heapq.heapify(heap)
    while heap:
        _, a, b, c = heapq.heappop(heap)
        if end[a] != b or b >= n or end[b] != c:
            continue  # one of the two has changed since
        end[a], end[b] = c, 0
        if c < n:
            before[c] = a
            if (r := ranks.get(word[a : end[c]])) is not None:
                heapq.heappush(heap, (r, a, c, end[c]))
        if (p := before[a]) >= 0 and (r := ranks.get(word[p:c])) is not None:
            heapq.heappush(heap, (r, p, a, c))
    out, i = [], 0
    while i < n:
        out.append(ranks[word[i : end[i]]])
        i = end[i]
    return out


def byte_bpe(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, ids binary, n_tokens, decoded binary) of each text; null counts as empty, which has no ids.

    ids are little-endian unsigned 32-bit. Texts may be of any length; words are
    coded apart, so no text becomes a table of its own. Repeated rows repeat.
    """

    def many(bpe, rows):
        coded = [b"".join(c) for c in bpe.encode([(t or b"").decode() for _, t in rows])]
        return [(d, ids, len(ids) // 4, text) for (d, _), ids, text in zip(rows, coded, bpe.decode(coded), strict=True)]

    return map_groups(docs.select(F.col("doc_id").cast("long"), "text"), many, "doc_id long, ids binary, n_tokens long, decoded binary", start=lambda: ByteBPE.of(path, pattern))


def byte_bpe_decode(coded: DataFrame, path: str, pattern: str, ids: str = "ids") -> DataFrame:
    """(doc_id, decoded binary) of a stored column of ids; null or empty ids give no bytes, unknown ids raise."""

    def many(bpe, rows):
        return [(d, text) for (d, _), text in zip(rows, bpe.decode([bytes(c or b"") for _, c in rows]), strict=True)]

    return map_groups(coded.select(F.col("doc_id").cast("long"), ids), many, "doc_id long, decoded binary", start=lambda: ByteBPE.of(path, pattern))


def byte_bpe_digest(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): the digests are taken where the ids are, so they never move."""

    sha = lambda b: hashlib.sha256(b).hexdigest()

    def many(bpe, rows):
        coded = [b"".join(c) for c in bpe.encode([(t or b"").decode() for _, t in rows])]
        return [(d, len(ids) // 4, sha(ids), sha(text)) for (d, _), ids, text in zip(rows, coded, bpe.decode(coded), strict=True)]

    return map_groups(docs.select(F.col("doc_id").cast("long"), "text"), many, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", start=lambda: ByteBPE.of(path, pattern))
