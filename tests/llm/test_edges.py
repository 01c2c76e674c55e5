"""Nulls, repeated rows, very long texts, clashing names and empty tables, for every operator and stage."""

import hashlib
import random
from collections import Counter

import numpy as np
import public_tokenizers as P
import pytest
import xxhash
from test_dedup import around_the_limit, brute_exact, brute_similar

from treepack.llm import byte_bpe, byte_cnn, exact_dedup, matroska, packing, pii, pu_quality, simhash, stages, suffix_dedup

RANKS, WORDS = P.path("byte_bpe_50k.tiktoken"), P.path("word_bpe_49k.json")
#: Names that operators and stages use inside.
NAMES = "_all _base _more _m_email _p_ip _email _added _nth _n row id sha key n n_spans n_added fp fp2 len h1 h2 d part salt salts lead node bucket size pc root lang score held score_ predicted spans keep best".split()
COLUMNS = ["doc_id long", "text string", *(f"{n} string" for n in NAMES if n != "lang"), "lang string"]
LONG = "mail a@b.com then " + " ".join(f"wort{k % 977} the{k % 31}" for k in range(60_000))


def rows_of(texts):
    filler = [str(k) for k in range(len(NAMES) - 1)]
    return [(d, t, *filler, "en" if d is None or d % 2 else None) for d, t in texts]


TEXTS = [(1, "one two three four five six seven"), (1, "one two three four five six seven"), (2, None), (3, ""), (None, "no id at all here"), (None, "no id at all here"), (4, LONG), (5, LONG + " end"), (6, "ONE  two"), (7, "12 34 !?")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows_of(TEXTS), ", ".join(COLUMNS)).repartition(3)


def values(df):
    return Counter(tuple(r) for r in df.collect())


def test_stages_leave_other_columns_alone(docs):
    before = values(docs)
    for f, kept in ((stages.keep_known_languages, 7), (stages.keep_one_of_equal, 7), (stages.keep_one_of_similar, 6)):
        out = f(docs)
        got = values(out)
        assert out.columns == docs.columns and not got - before, f.__name__
        assert sum(got.values()) == kept, f.__name__
    masked = stages.mask_personal_data(docs)
    assert masked.columns == docs.columns and masked.count() == len(TEXTS)
    assert values(masked.drop("text")) == values(docs.drop("text"))
    text = {r.doc_id: r.text for r in masked.collect()}
    assert text[4] == LONG.replace("a@b.com", "[EMAIL]") and text[2] is None and text[3] == ""
    packed = packing.pack_documents(docs, WORDS)
    assert packed.where("doc_id = 4").count() > 10


def test_stages_and_operators_on_nothing(docs):
    none = docs.where("false")
    for f in (stages.keep_known_languages, stages.keep_one_of_equal, stages.keep_one_of_similar, stages.mask_personal_data):
        out = f(none)
        assert out.columns == docs.columns and out.count() == 0
    net = byte_cnn.ByteCNN.new(["a", "b"])
    assert byte_cnn.language_id(none, net).count() == 0 and byte_cnn.train_with_limit(none) == (None, 0.0)
    assert pu_quality.quality_scores(none, None).count() == 0
    assert matroska.from_media(matroska.to_media(none)).count() == 0 and matroska.packet_table(matroska.to_media(none)).count() == 0


def test_row_operators_on_long_texts_and_clashing_names(docs):
    net = byte_cnn.ByteCNN.new(["a", "b"])
    got = byte_cnn.language_id(docs, net).collect()
    assert Counter(r.doc_id for r in got) == Counter(d for d, _ in TEXTS) and {r.lang_pred for r in got if r.doc_id in (2, 3, 7)} == {"und"}
    got = pu_quality.quality_scores(docs, None).collect()
    assert len(got) == len(TEXTS) and {r.score for r in got} == {0.5}
    got = {r.doc_id: r for r in matroska.from_media(matroska.to_media(docs)).collect()}
    assert all(r.payload_sha256 == hashlib.sha256(matroska.padded((dict(TEXTS)[d] or "").encode())).hexdigest() for d, r in got.items())
    got = {r.doc_id: r for r in byte_bpe.byte_bpe_digest(docs, RANKS, P.PATTERN).collect()}
    assert all(r.decoded_sha256 == hashlib.sha256((dict(TEXTS)[d] or "").encode()).hexdigest() for d, r in got.items())
    got = pii.personal_data(docs).collect()
    assert len(got) == len(TEXTS) and sum(r.n_email for r in got) == 2


def test_many_matches_in_one_text(spark):
    """Offsets stay right over several blocks of matches."""
    text = " ".join(f"u{k}@x{k}.com 10.0.{k % 256}.{k % 200}" for k in range(3000))
    (r,) = pii.personal_data(spark.createDataFrame([(1, text)], "doc_id long, text string")).collect()
    spans = [s.split(":") for s in r.spans.split(",")]
    assert (r.n_email, r.n_ip, r.n_spans) == (3000, 3000, 6000)
    assert all("@" in text[int(a) : int(b)] for k, a, b in spans if k == "email") and [text[int(a) : int(b)] for k, a, b in spans if k == "ip"] == text.split()[1::2]


def test_names_addresses_and_values_after_key_words(spark):
    rnd = random.Random(3)
    secret = lambda: "".join(rnd.choice("abcdefghijk") for _ in range(12))
    rows = [(k, f"he wrote password: {secret()}") for k in range(30)] + [(100 + k, "we met Dr. Alice Johnson there") for k in range(30)]
    rows += [(200 + k, f"she lives at {k + 1} Maple Avenue") for k in range(30)] + [(300 + k, f"see page {rnd.randrange(10**8, 10**9)} of the book") for k in range(60)]
    got = {r.doc_id: r for r in pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[k].spans == "secret:19:31" for k in range(30))
    assert all(got[100 + k].spans.startswith("person:7:") for k in range(30))
    assert all(got[200 + k].spans.startswith("address:13:") for k in range(30))
    assert all(got[300 + k].spans == "" for k in range(60))


def test_two_labelers_that_agree_outweigh_one():
    table = [("secret", (1, 1, 0, 0, 0, 0, 0, 0, 0), 50), ("secret", (-1, -1, 0, 0, 0, 0, 0, 0, 0), 50), ("secret", (1, -1, 0, 0, 0, 0, 0, 0, 0), 2)]
    model = pii.fit_votes(table, 102, 30, 100)
    assert model.votes["shape", 1] > 0 > model.votes["shape", -1] and model.reliability["length"][0] > 0.8 > 0.2 > model.reliability["length"][1]


# --- exact ---------------------------------------------------------------------------------


@pytest.mark.parametrize("how", [{"huge_bytes": 8}, {"per_salt": 2}, {"hashes": lambda b: (len(b) % 2, 7)}, {"hashes": lambda b: (0, 0), "per_salt": 2}])
def test_exact_rows_with_repeated_and_null_ids(spark, how):
    rows = [(1, "a" * 20), (1, "b" * 21), (None, "c" * 22), (2, "d"), (None, "c " * 22), (None, "c" * 22), (3, "e" * 21), (4, "b" * 21), (5, " " + "e" * 21)]
    got = exact_dedup.exact_dedup(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), **how)
    assert sorted((tuple(r) for r in got.select("doc_id", "keep_id", "group_size", "kept", "text_sha256").collect()), key=repr) == brute_exact(rows)


# --- similarity ----------------------------------------------------------------------------


def test_similar_stage_keeps_one_of_each_component(spark):
    rows = around_the_limit()
    want, _ = brute_similar(rows)
    got = [r.doc_id for r in stages.keep_one_of_similar(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    assert sorted(got) == sorted(set(want.values()))


def test_tiles_of_wide_fingerprints_against_all_pairs():
    rng = np.random.default_rng(4)
    base = rng.integers(0, 2**64, (120, 4), dtype=np.uint64)
    flip = base.copy()
    flip[:, 1] ^= np.uint64(0xFF00FF)
    fp = np.concatenate([base, flip])
    bucket = rng.integers(0, 3, len(fp))
    order = np.lexsort((np.bitwise_count(fp).sum(axis=1), bucket))
    fp, bucket = fp[order], bucket[order]
    for radius in (16, np.where(np.arange(len(fp)) % 2, 16, 3)):
        reach = np.broadcast_to(radius, len(fp))
        near = (simhash.distance(fp[:, None], fp[None]) <= np.maximum(reach[:, None], reach[None])) & (bucket[:, None] == bucket[None])
        want = simhash.Forest(len(fp))
        want.add(*np.nonzero(near))
        for small in (4, 500):
            got, links = simhash.Forest(len(fp)), np.array(simhash.bucket_links(bucket, fp, radius, small=small))
            got.add(links[:, 0], links[:, 1])
            assert (got.label == want.label).all()


# --- suffixes ------------------------------------------------------------------------------


def test_suffix_dedup_of_a_whole_table_by_all_windows(spark, sf):
    """Windows of 400 bytes over all documents, counted by their 128-bit digests."""
    df = spark.read.parquet(f"{sf.replace('sf0.001', 'sf0.01')}/documents.parquet").select("doc_id", "text")
    rows = [(r.doc_id, (r.text or "").encode()) for r in df.collect()]
    digest = xxhash.xxh3_128_intdigest
    seen = Counter(digest(t[i : i + 400]) for _, t in rows for i in range(len(t) - 399))
    want = {}
    for d, t in rows:
        gone = np.zeros(len(t) + 1, np.int32)
        for i in range(len(t) - 399):
            if seen[digest(t[i : i + 400])] > 1:
                gone[i] += 1
                gone[i + 400] -= 1
        gone = np.cumsum(gone)[: len(t)] > 0
        left = np.frombuffer(t, np.uint8)[~gone].tobytes()
        want[d] = (len(t), int(gone.sum()), int((gone & ~np.concatenate(([False], gone[:-1]))).sum()), hashlib.sha256(left).hexdigest())
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.suffix_dedup(df).collect()}
    assert got == want and sum(v[1] > 0 for v in want.values()) > 100


# --- models --------------------------------------------------------------------------------


def test_windows_score_as_by_plain_loops():
    net, rng = byte_cnn.ByteCNN.new(["a", "b", "c"], dim=4, filters=3), np.random.default_rng(1)
    net.bias += rng.standard_normal(9).astype(np.float32)
    x = rng.integers(0, 256, (3, 40)).astype(np.uint8)
    for row, got in zip(x, net.probabilities(x), strict=True):
        act = []
        for f in range(9):
            w = byte_cnn.WIDTHS[f // 3]
            k = net.kernel[: w * 4, f].reshape(w, 4)
            act.append(max(0.0, max(float((net.embed[row[s : s + w]] * k).sum()) for s in range(40 - 4 + 1)) + float(net.bias[f])))
        z = np.array(act) @ net.out + net.out_bias
        assert np.allclose(got, np.exp(z - z.max()) / np.exp(z - z.max()).sum(), rtol=1e-4)


def test_learnt_text_stays(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    n = docs.where("text rlike '[a-z]'").count()
    assert stages.keep_known_languages(docs).count() >= 0.98 * n


@pytest.mark.parametrize("prior", [0.3, 0.6, 0.85])
def test_prior_from_positives_and_unlabelled(prior):
    rng = np.random.default_rng(8)
    draw = lambda n, at: rng.standard_normal((n, pu_quality.WIDTH)) * 0.5 + at
    good = int(6000 * prior)
    u = np.concatenate([draw(good, 0.3), draw(6000 - good, -0.3)])
    assert abs(pu_quality.estimate_prior(draw(3000, 0.3), u) - prior) < 0.05


def test_fit_lowers_the_non_negative_risk():
    """The risk by its definition, over all rows, before and after."""
    rng = np.random.default_rng(2)
    p, n = rng.standard_normal((400, pu_quality.WIDTH)) + 0.2, rng.standard_normal((300, pu_quality.WIDTH)) - 0.2
    u = np.concatenate([rng.standard_normal((300, pu_quality.WIDTH)) + 0.2, n])

    def risk(net):
        good = lambda x: np.logaddexp(0, -net.margin(x)).mean()
        bad = lambda x: np.logaddexp(0, net.margin(x)).mean()
        return 0.5 * good(p) + max(0.0, bad(u) - 0.5 * bad(p))

    first, last = pu_quality.fit(p, u, 0.5, epochs=0), pu_quality.fit(p, u, 0.5, epochs=40)
    assert risk(last) < 0.5 * risk(first) and last.score(p).mean() > 0.8 > 0.3 > last.score(n).mean()
