import hashlib
import math
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from treepack.llm import byte_cnn, matroska, pii, pu_quality, stages
from treepack.llm.html_text import extract_text, html_to_text

# --- personal data -------------------------------------------------------------------


def luhn(d):
    return sum(v if i % 2 == 0 else v * 2 - 9 * (v > 4) for i, v in enumerate(map(int, reversed(d)))) % 10 == 0


def base_spans(t):
    digits = lambda x: re.sub("[^0-9]", "", x)
    found = {
        "email": [m.span() for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)],
        "ip": [m.span() for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))],
        "card": [m.span() for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t) if 13 <= len(digits(m[0])) <= 19 and luhn(digits(m[0]))],
        "phone": [m.span() for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(digits(m[0])) <= 15],
    }
    return {k: [f"{k}:{a}:{b}" for a, b in v] for k, v in found.items()}


FRAGMENTS = ["a@b.com_x@y.com", "a@b.com.x@y.com", "@x.com a@", "1.2.3.4.5.6.7.8", "256.1.1.1", "01.002.0003.255", "4111 1111 1111 1111", "4111-1111-1111-1111 4111111111111111", "+1 (523) 555-1055", "+1+2 345 678 901", "é", "😀", "\n", "1 2 3 4 5 6 7 8 9 0 1 2 3 4 5 6", "0" * 40, 'token = "1eb9672e721b4f812088970e66a6345cee33dd6"', "(523) 555-1055", "123-45-6789"]


def test_base_spans_against_plain_patterns(spark):
    rnd = random.Random(4)
    texts = ["".join(rnd.choice(FRAGMENTS + list("a1.@+- ")) for _ in range(rnd.randint(0, 40))) for _ in range(200)]
    texts += [None, "", "1" * 20_000, "a." * 9000 + "@", "1." * 9000, "+1" + "(" * 9000, "1 " * 9000]
    rows = [(k, t, "x", "y") for k, t in enumerate(texts)] + [(0, texts[0], "x", "y"), (None, "a@b.cd", "x", "y")]
    got = pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string, spans string, s string")).collect()
    want = []
    for d, t, *_ in rows:
        b = base_spans(t or "")
        want.append((d, *map(len, b.values()), hashlib.sha256(",".join(x for v in b.values() for x in v).encode()).hexdigest()))
        mine = [r for r in got if r.doc_id == d][0].spans.split(",")
        assert all(x in mine for v in b.values() for x in v)
    assert sorted(((r.doc_id, r.n_email, r.n_ip, r.n_card, r.n_phone, r.base_sha256) for r in got), key=repr) == sorted(want, key=repr)


def test_secrets_are_added_and_plain_numbers_are_not(spark):
    rnd = random.Random(1)
    rows = [(k, f'some words token = "{rnd.randbytes(20).hex()}" more words') for k in range(40)] + [(100 + k, f"words about order {rnd.randrange(10**9, 10**10)} and version 20{k:02d}1231 only") for k in range(40)]
    got = {r.doc_id: r.spans for r in pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[k].startswith("secret:20:") or "secret" in got[k] for k in range(40))
    assert all(got[100 + k] == "" for k in range(40))


def test_mask_keeps_columns(spark):
    df = spark.createDataFrame([(1, "hi a@b.com and é 1.2.3.4", "en"), (2, None, None)], "doc_id long, text string, lang string")
    assert [tuple(r) for r in pii.mask(df).orderBy("doc_id").collect()] == [(1, "hi [EMAIL] and é [IP]", "en"), (2, None, None)]


def test_plan_is_native(spark):
    df = spark.createDataFrame([(1, "x")], "doc_id long, text string")
    text = pii.with_spans(df)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in text and "Arrow" not in text


def test_no_documents(spark):
    assert pii.personal_data(spark.createDataFrame([], "doc_id long, text string")).count() == 0


# --- language ------------------------------------------------------------------------------


def test_language_on_held_out_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    held = byte_cnn.fold("doc_id", 3) == 1
    net = byte_cnn.train(docs.where(~held))
    got = {r.doc_id: r for r in byte_cnn.language_id(docs, net).collect()}
    rows = docs.where(held).collect()
    assert sum(got[r.doc_id].lang_pred == r.lang for r in rows) >= 0.9 * len(rows)
    assert all(0 <= r.score <= 1 for r in got.values())


def test_language_edges():
    net = byte_cnn.ByteCNN.new(["a", "b"])
    long = ("wort " * 5000).encode()
    got = byte_cnn.predict_texts(net, [None, b"", b"123 !?", b"x", long, long])
    assert [g[0] for g in got[:3]] == ["und"] * 3 and got[3][0] in ("a", "b") and got[4] == got[5]
    x = np.concatenate([byte_cnn.windows(long)])
    p = net.probabilities(x)
    w = np.full(len(x), 256.0)
    w[-1] = len(long) - 256 * (len(x) - 1)
    assert math.isclose(got[4][1], float((p * w[:, None]).sum(0).max() / len(long)), rel_tol=1e-5)


def test_gradient_by_differences():
    """One step along the gradient lowers the loss as much as differences of the loss foretell."""
    rng = np.random.default_rng(0)
    x, y = rng.integers(1, 256, (8, byte_cnn.LENGTH)).astype(np.uint8), rng.integers(0, 2, 8)
    net = byte_cnn.ByteCNN.new(["a", "b"], dim=4, filters=4)
    loss = lambda: -np.log(net.probabilities(x)[np.arange(8), y]).mean()
    before = loss()
    net.fit(x, y, epochs=30, batch=8)
    assert loss() < before / 2


def test_nothing_to_learn_from(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, lang string")
    assert byte_cnn.train(empty) is None
    one = spark.createDataFrame([(1, "text", None)], "doc_id long, text string, lang string")
    assert [tuple(r) for r in byte_cnn.language_id(one, byte_cnn.train(one)).collect()] == [(1, "und", 0.0)]


# --- quality ---------------------------------------------------------------------------------


def test_quality_on_held_out_rows(spark):
    rnd = random.Random(2)
    good = lambda: " ".join(rnd.choice(["the", "of", "reading", "house", "and", "water"]) for _ in range(80)) + "."
    bad = lambda: " ".join(rnd.choice(["the###", "of%%%", "x***", "and&&&", "water$$$"]) for _ in range(80))
    rows = [(k, good() if k % 4 else bad(), int(k % 4 > 0)) for k in range(800)]
    df = spark.createDataFrame(rows, "doc_id long, text string, quality int")
    net = pu_quality.train(df.select("doc_id", "text"), df.where("doc_id < 600 and doc_id % 2 = 0 or doc_id % 4 = 1").select("doc_id", "quality"))
    got = {r.doc_id: r for r in pu_quality.quality_scores(df, net).collect()}
    good_scores, bad_scores = [got[k].score for k, _, q in rows if k >= 600 and q], [got[k].score for k, _, q in rows if k >= 600 and not q]
    assert min(good_scores) > max(bad_scores)
    assert all(r.predicted == int(r.score >= 0.3) for r in got.values())
    edge = pu_quality.quality_scores(spark.createDataFrame([(1, None), (2, ""), (2, "")], "doc_id long, text string"), net).collect()
    assert len(edge) == 3 and all(0 <= r.score <= 1 for r in edge)
    assert pu_quality.train(df.where("false"), df.where("false")) is None


# --- pages -----------------------------------------------------------------------------------


def test_layout():
    page = '<head><title>no</title></head><ul><li>one<li>two <b>bold</b>text<ol><li>a<li>b</ol><li>three</ul><p>para one<p>para   two<br>line<div style="display: none">no</div><table><tr><td>a<td>bbb<tr><td>cccc<td>d</table><pre>x\n  y</pre><dl><dt>T<dd>D</dl>a &lt; b &amp; c<script>no</script> <a title="x>y">link</a><span hidden>no</span>'
    assert html_to_text(page).split("\n") == ["- one", "- two boldtext", "  1. a", "  2. b", "- three", "", "para one", "", "para two", "line", "", "a     bbb", "cccc  d", "", "x", "  y", "", "T", "    D", "", "a < b & c link"]


def test_head_ends_where_its_content_does():
    assert html_to_text("<head><title>t</title><p>one<p>two") == "one\n\ntwo"
    assert html_to_text("<html><head><meta charset=x><style>p{}</style> \n loose text <b>bold</b>") == "loose text bold"
    assert html_to_text("<head><title>t</title></head><body>x</body>") == "x"


def test_spanning_cells():
    page = "<table><tr><td rowspan=2>tall<td>a<td>bb<tr><td>ccc<td>d<tr><td colspan=2>both<td>e<tr><td rowspan=0>z<td>1<tr><td>2</table>after"
    assert html_to_text(page).split("\n") == ["tall  a    bb", "      ccc  d", "both       e", "z     1", "      2", "", "after"]


def test_no_bound_on_nesting():
    """Tables in tables, and an end tag that closes a paragraph many levels up."""
    deep = "<table><tr><td>a<td>" * 400 + "x"
    text = html_to_text(deep)
    assert text.count("a") == 400 and "x" in text
    assert html_to_text("<p>" + "<b>" * 500 + "in</p>out") == "in\n\nout"
    long = "<p>word &amp; " * 100_000
    assert html_to_text(long).count("word &") == 100_000


@pytest.mark.parametrize("page", ["", None, "<", "<<<>>>", "<p", "</p></div>", "<!-- open", "<script>open", "<table><td>x", "<td>lone", "text only", "<a href='x\" >q</a>", "<ul><ul><ul>", "<b>" * 3000 + "deep" + "</b>" * 3000, "<table>" * 60 + "x"])
def test_broken_pages_do_not_crash(page):
    html_to_text(page)


def test_pages_against_a_plain_parser(spark, sf):
    """The same characters in the same number as a parser that knows no layout."""
    from collections import Counter
    from html.parser import HTMLParser

    class Plain(HTMLParser):
        def __init__(self):
            super().__init__()
            self.out, self.skip = [], 0

        def handle_starttag(self, tag, attrs):
            self.skip += tag in ("script", "style", "head", "title", "template", "noscript")

        def handle_endtag(self, tag):
            self.skip -= tag in ("script", "style", "head", "title", "template", "noscript")

        def handle_data(self, data):
            if self.skip <= 0:
                self.out.append(data)

    pages = spark.read.parquet(f"{sf}/pages.parquet")
    got = {r.page_id: r.text for r in extract_text(pages).collect()}
    for r in pages.collect():
        p = Plain()
        p.feed(r.html)
        markers = [m for line in got[r.page_id].split("\n") for m in re.findall(r"^ *(-|\d+\.)(?= )", line)]
        want, have = Counter("".join("".join(p.out).split())), Counter("".join(got[r.page_id].split()))
        extra = have - want
        assert not want - have and sum(extra.values()) <= sum(map(len, markers))


def test_pages_with_clashing_columns_and_none(spark):
    df = spark.createDataFrame([(1, "<p>x", "y", 3)], "page_id long, html string, text string, n_lines int")
    assert [(r.page_id, r.text, r.n_lines) for r in extract_text(df).collect()] == [(1, "x", 1)]
    assert extract_text(df.where("false")).count() == 0


def test_null_page(spark):
    df = spark.createDataFrame([(1, None, "x"), (1, None, "x")], "page_id long, html string, text string")
    assert [(r.page_id, r.text, r.n_lines) for r in extract_text(df).collect()] == [(1, "", 0)] * 2


# --- media ------------------------------------------------------------------------------------


@pytest.mark.parametrize("n", [0, 1, 575, 576, 577, 576 * 8, 576 * 8 * 32 + 5, 400_000])
def test_media_round_trip(n):
    text = random.Random(n).randbytes(n)
    payload = matroska.padded(text)
    assert len(payload) % 576 == 0 and len(payload) > 0 and payload[:n] == text and set(payload[n:]) <= {255}
    for lacing in (matroska.FIXED, matroska.XIPH, matroska.EBML_LACING):
        stored = matroska.write(payload, lacing=lacing)
        m = matroska.read(stored)
        assert b"".join(stored[s : s + k] for _, _, s, k, _, _ in m.packets) == payload
        times = [p[1] for p in m.packets]
        assert times == sorted(times) and [c[0] for c in m.cues] == [c[1] for c in m.clusters]


def test_lacing_of_unequal_frames():
    rnd = random.Random(1)
    for kind in (matroska.XIPH, matroska.EBML_LACING):
        frames = [rnd.randbytes(rnd.choice([0, 1, 254, 255, 256, 510, 3000, 70_000])) for _ in range(9)]
        block = matroska.vint(1) + (3).to_bytes(2, "big") + bytes([kind << 1]) + matroska.lace(frames, kind)
        data = matroska.element(matroska.EBML, b"") + matroska.element(matroska.SEGMENT, matroska.element(matroska.CLUSTER, matroska.uint(matroska.CLUSTER_TIME, 5) + matroska.element(matroska.BLOCK_GROUP, matroska.element(matroska.BLOCK, block))))
        m = matroska.read(data)
        assert [data[s : s + k] for _, _, s, k, _, _ in m.packets] == frames and m.packets[0][1] == 8_000_000


def test_broken_media_raise():
    stored = matroska.write(matroska.padded(b"x" * 5000))
    for bad in (b"", b"\0", stored[:100], b"RIFF" + stored[4:], stored[:-3]):
        with pytest.raises(matroska.MediaError):
            matroska.read(bad)


def test_media_columns(spark):
    df = spark.createDataFrame([(1, "abc", "x"), (2, None, "y"), (3, "abc", "z"), (3, "abc", "z")], "doc_id long, text string, media string")
    got = sorted(tuple(r) for r in matroska.from_media(matroska.to_media(df)).collect())
    assert len(got) == 4 and got[0][1:] == got[2][1:] == got[3][1:]
    assert matroska.packet_table(matroska.to_media(df)).count() == 4 and matroska.cue_table(matroska.to_media(df)).count() == 4


# --- stages -----------------------------------------------------------------------------------


def test_stages_take_effect_and_keep_columns(spark):
    rnd = random.Random(3)
    words = [f"wort{k}x" for k in range(300)]
    base = [rnd.choice(words) for _ in range(300)]
    near = list(base)
    near[150] = "andres"
    rows = [(1, " ".join(base), "de", "s"), (2, "  ".join(base), "de", "s"), (3, " ".join(near), "de", "s"), (4, "clean " + " ".join(rnd.choice(words) for _ in range(200)), "de", "s"), (5, None, "de", "s"), (6, "12 34", None, "s"), (7, "mail a@b.com " + " ".join(rnd.choice(words) for _ in range(200)), "de", "s"), (7, "mail a@b.com twice the id " + " ".join(rnd.choice(words) for _ in range(90)), "de", "s")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    known = stages.keep_known_languages(docs)
    ids = lambda df: sorted(r.doc_id for r in df.collect())
    assert ids(known) == [1, 2, 3, 4, 7, 7] and known.columns == docs.columns
    one = stages.keep_one_of_equal(known)
    assert ids(one) == [2, 3, 4, 7, 7] and one.columns == docs.columns  # the longer original stays
    similar = stages.keep_one_of_similar(one)
    assert ids(similar) == [2, 4, 7, 7] and similar.columns == docs.columns
    masked = stages.mask_personal_data(similar)
    assert masked.count() == similar.count() and masked.where("text like '%a@b.com%'").count() == 0
    for f in (stages.keep_known_languages, stages.keep_one_of_equal, stages.keep_one_of_similar, stages.mask_personal_data):
        assert f(docs.where("false")).count() == 0


def test_language_stage_learns_from_every_row_and_limits_by_all_held_out(spark, monkeypatch):
    langs = {"x": "abcde fghij ", "y": "klmno pqrst "}
    rows = [(i, lang, (t[i % 12 :] + t * 3)[: 20 + i % 13]) for lang, t in langs.items() for i in range(1000 * (lang == "y"), 1000 * (lang == "y") + 300)]
    docs = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    monkeypatch.setattr(byte_cnn, "SHARD", 100)
    few = dict(per_language=20, per_text=1)
    held = docs.where("pmod(xxhash64(doc_id), 5) = 0")
    start = byte_cnn.train(docs.where("pmod(xxhash64(doc_id), 5) <> 0"), **few)
    net, least = byte_cnn.train_with_limit(docs, **few)
    assert net.labels == start.labels == ["x", "y"] and all((a != b).any() for a, b in zip(net.params()[1:], start.params()[1:]))
    again, _ = byte_cnn.train_with_limit(docs.repartition(7), **few)
    assert all(np.allclose(a, b) for a, b in zip(net.params(), again.params()))
    want = {r.doc_id: r.lang for r in held.collect()}
    got = byte_cnn.language_id(held, net).collect()
    scores = [r.score for r in got if r.lang_pred == want[r.doc_id]]
    assert len(scores) > 0.9 * len(want) and least == pytest.approx(0.9 * float(np.quantile(scores, 0.001)))
    # every row counts, whatever the sample took: one with other bytes moves the result
    other = docs.withColumn("text", F.when(F.col("doc_id") == docs.where("pmod(xxhash64(doc_id), 5) <> 0").agg(F.max("doc_id")).first()[0], "zzzz zzzz").otherwise(F.col("text")))
    moved = byte_cnn.learn_all(start, other.where("pmod(xxhash64(doc_id), 5) <> 0"))
    assert any((a != b).any() for a, b in zip(moved.params(), net.params()))
