import base64
import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from tokenizers import Tokenizer

from treepack.llm import byte_bpe, packing

RANKS = P.path("byte_bpe_50k.tiktoken")
WORDS = P.path("word_bpe_49k.json")
TEXTS = [
    None, "", "   ", "hello world, don't!", "é ñ 日本語 😀😀 \u0085 \x1c\x1d", "a" * 3000, "ab" * 900, "  \t\n  x", "<|endoftext|> <|startoftext|>", "a<|endoftext|>b <|ENDOFTEXT|> <|x ", "'s 'S it's 'LL !'s ''s", "İstanbul ΑΣ. ½ ① Ⅷ ß ﬁ", "word " * 9000,
    *("".join(random.Random(k).choice(["ab", "cde ", "é", "1234", "\n", " X", "!?"]) for _ in range(200)) for k in range(20)),
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(k, t, "x", 1) for k, t in enumerate(TEXTS)] + [(3, TEXTS[3], "x", 1), (None, "no id", "x", 1)]
    return rows, spark.createDataFrame(rows, "doc_id long, text string, piece string, length int")


def test_byte_bpe_as_the_library(docs):
    rows, df = docs
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = []
    for d, t, *_ in rows:
        ids = enc.encode_ordinary(t or "")
        want.append((d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    got = [tuple(r) for r in byte_bpe.byte_bpe_digest(df, RANKS, P.PATTERN).collect()]
    assert sorted(got, key=repr) == sorted(want, key=repr)
    coded = byte_bpe.byte_bpe(df, RANKS, P.PATTERN)
    back = {r.doc_id: bytes(r.decoded) for r in byte_bpe.byte_bpe_decode(coded.withColumnRenamed("ids", "part"), RANKS, P.PATTERN, "part").collect()}
    assert all(back[d] == (t or "").encode() for d, t, *_ in rows)


def test_decoding_of_any_ids(spark, monkeypatch):
    """Ids that no text gave, in parts of a few tokens; unknown ids raise."""
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    tokens, rnd = {i: t for t, i in ranks.items()}, random.Random(4)
    lists = [[rnd.choice(list(tokens)) for _ in range(n)] for n in (0, 1, 5, 40, 300)]
    bpe = byte_bpe.ByteBPE(RANKS, P.PATTERN)
    monkeypatch.setattr(byte_bpe, "_TOKENS", 7)
    assert bpe.decode([np.array(x, "<u4").tobytes() for x in lists]) == [b"".join(tokens[i] for i in x) for x in lists]
    for bad in (50256, 2**31):
        with pytest.raises(ValueError):
            bpe.decode([np.array([bad], "<u4").tobytes()])
    df = spark.createDataFrame([(1, None), (1, bytearray()), (None, bytearray(np.array([70], "<u4").tobytes()))], "doc_id long, ids binary")
    assert sorted((r.doc_id is None, bytes(r.decoded)) for r in byte_bpe.byte_bpe_decode(df, RANKS, P.PATTERN).collect()) == [(False, b""), (False, b""), (True, tokens[70])]


def test_small_word_table_and_heap_agree():
    bpe = byte_bpe.ByteBPE(RANKS, P.PATTERN, keep_words=20, long_word=12, block=7)
    other = byte_bpe.ByteBPE.of(RANKS, P.PATTERN)
    for t in TEXTS[3:]:
        assert bpe.encode([t]) == other.encode([t])


def pieces_of(rows):
    tok = Tokenizer.from_file(WORDS)
    out = []
    for d, t, *_ in rows:
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        out += [(d, k // 4096, k, len(ids[k : k + 4096]), zlib.crc32(ids[k : k + 4096].tobytes())) for k in range(0, len(ids), 4096)]
    return out


def test_packing_of_documents(docs):
    rows, df = docs
    got = packing.pack_documents(df, WORDS).collect()
    assert sorted(((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got), key=repr) == sorted(pieces_of(rows), key=repr)
    check_bins([(r.sequence_id, r.offset, r.length) for r in got], 4096)


def check_bins(rows, capacity):
    bins = {}
    for s, o, n in rows:
        bins.setdefault(s, []).append((o, n))
    for parts in bins.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= capacity
    return len(bins)


def test_levels_pack_close_to_the_bound(spark):
    items = spark.range(20_000).selectExpr("id", "cast(pmod(xxhash64(id), 1500) + 1 as long) as size")
    rows = packing.pack(items, group=2000).collect()
    assert len(rows) == 20_000
    n = check_bins([(r.sequence_id, r.offset, r.size) for r in rows], 4096)
    assert n <= 1.005 * sum(r.size for r in rows) / 4096 + 1


def test_sum_of_squares_rule():
    """Each placement is the one with the least sum, by trying all."""
    rnd, packer, c = random.Random(1), packing.SumOfSquares(30), 30
    for _ in range(400):
        size = rnd.randint(1, 30)
        before = packer.n.copy()

        def after(gap):
            n = before.copy()
            if gap < c or before[c]:
                n[gap] -= gap != c
            n[gap - size] += 1
            return int((n[1:c] ** 2).sum())

        best = min(after(g) for g in range(size, c + 1) if g == c or before[g])
        packer.place(size)
        assert int((packer.n[1:c] ** 2).sum()) == best


def test_nothing_to_pack(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert packing.pack_documents(empty, WORDS).count() == 0
    assert byte_bpe.byte_bpe_digest(empty, RANKS, P.PATTERN).count() == 0
