"""Personal data by weak supervision, in DataFrame functions alone.

Base spans (email, ip, card, phone) come from fixed patterns with their checks.
Candidates for more (secrets, values after a key word, national phone numbers,
account and social security numbers, names of persons, street addresses) get a
vote, for, against or none, from each of nine labelers: three look at the span's
shape, four look words up in gazetteers of key words, plain words, given names
and places, two look at its context. Expectation-maximisation over the counts of
vote patterns, a table whose size the labelers bound, estimates how reliable
each one is, and its posteriors train a logistic span classifier, which decides.
Offsets count code points; the text itself is never moved between tasks.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import stage

# The base patterns. Possessive, and anchored where a run begins, they find the same
# matches as their plain forms but never read a run of characters more than once.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}"
CARD = r"[0-9](?:[ -]?[0-9]){12,}+"
PHONE = r"\+[0-9][ ().0-9-]+[0-9]"
BASE = {"email": EMAIL, "ip": IP, "card": CARD, "phone": PHONE}
KINDS = ("email", "ip", "card", "phone", "account", "secret", "ssn", "person", "address")
# Gazetteers, as alternatives of a pattern: what a secret is called, what stands before personal data and before plain
# numbers, given names, titles, places, and words that end the name of a street.
SECRETS = r"password|passwd|passphrase|passcode|pwd|secret|token|api[_ -]?key|access[_ -]?key|private[_ -]?key|credential|bearer"
KEY_WORDS = rf"(?i)\b(?:{SECRETS}|auth|ssn|social security|iban|account|passport|phone|mobile|tel|fax|call)\b"
PLAIN_WORDS = r"(?i)\b(?:version|page|pages|isbn|issn|doi|http|https|www|license|licensed|section|chapter|figure|table|year|volume|release|revision|model|part|item|order|build)\b"
GIVEN_NAMES = "|".join("""Alice Amanda Andrea Andrew Angela Anthony Antonio Barbara Benjamin Brian Carlos Caroline Catherine Charles Charlotte Christian
Christine Christopher Claire Daniel David Deborah Dennis Edward Elena Elizabeth Emily Emma Eric Fatima Francois Frank Gabriel George Hannah
Hans Heather Helen Henry Isabel Jacob James Jason Javier Jean Jennifer Jessica John Jonathan Jose Joseph Joshua Juan Julia Julie Karen Katherine
Kevin Klaus Laura Linda Louis Lucas Maria Mark Martin Mary Matthew Melissa Michael Michelle Mohammed Nancy Nicholas Olivia Pablo Patricia Patrick
Paul Pedro Peter Philip Pierre Rachel Rebecca Richard Robert Ronald Ruth Samuel Sandra Sarah Sophie Stephen Steven Susan Thomas Timothy Victoria
William Wolfgang""".split())
TITLES = r"(?:Mr|Mrs|Ms|Miss|Dr|Prof)\.?"
PLACES = "|".join("""Amsterdam Athens Barcelona Berlin Bogota Boston Brussels Buenos Cairo Chicago Cologne Copenhagen Dallas Delhi Dublin Frankfurt
Geneva Hamburg Houston Istanbul Lagos Lima Lisbon London Lyon Madrid Marseille Mexico Miami Milan Montreal Moscow Mumbai Munich Nairobi Oslo Paris
Prague Rome Santiago Seattle Seville Shanghai Singapore Stockholm Sydney Tokyo Toronto Valencia Vienna Warsaw Zurich""".split())
STREETS = "Street|St|Avenue|Ave|Road|Rd|Lane|Ln|Boulevard|Blvd|Drive|Court|Square"
# What candidates look like, each from where no letter or digit stands before.
_KEYED = rf"(?i:{SECRETS})[\"']?\s?[:=]\s?[\"']?"
_PERSON = rf"(?:{TITLES} [A-Z][a-z]++(?: [A-Z][a-z]++)?|(?:{GIVEN_NAMES}) [A-Z][a-z]++)(?![A-Za-z])"
_ADDRESS = rf"[0-9]{{1,5}} [A-Z][a-z]++(?: [A-Z][a-z]++)? (?:{STREETS})(?![A-Za-z])"
_PHONE = r"\(?[0-9]{3}\)?[ .-][0-9]{3}[ .-][0-9]{4}"
_SSN = r"[0-9]{3}-[0-9]{2}-[0-9]{4}"
_RUN = r"(?=[A-Za-z_/+-]*+[0-9])[A-Za-z0-9][A-Za-z0-9_/+-]{7,}+"
CANDIDATE = rf"(?<![A-Za-z0-9])(?:(?=[A-Za-z]){_KEYED}[A-Za-z0-9!@#$%^&*_/+-]{{6,}}+|{_PHONE}(?![A-Za-z0-9])|{_SSN}(?![A-Za-z0-9])|(?=[0-9]){_ADDRESS}|(?=[A-Z]){_PERSON}|{_RUN})"
#: How much of the text before a candidate is its context.
CONTEXT = 32
LABELERS = ("shape", "length", "mixture", "key_word", "plain_word", "given_name", "place", "assigned", "quoted")
_BLOCK = 256


def _spans(m: Column, pieces: Column) -> Column:
    """Matches with their place and the text before them: what lies between them, as split() gives it, tells where each begins.

    Matches go in blocks, so that a text of very many is not copied once for each.
    """
    kind = "struct<s: int, e: int, t: string, before: string>"
    none, no_block = F.expr(f"cast(array() as array<{kind}>)"), F.expr(f"cast(array() as array<array<{kind}>>)")
    pairs = F.arrays_zip(m.alias("t"), F.slice(pieces, 1, F.size(m)).alias("p"))
    last = lambda *parts: F.right(F.concat(*(F.right(p, F.lit(CONTEXT)) for p in parts)), F.lit(CONTEXT))

    def step(acc: Column, x: Column) -> Column:
        s = acc["at"] + F.char_length(x["p"])
        before = last(acc["tail"], x["p"])
        one = F.struct(s.alias("s"), (s + F.char_length(x["t"])).alias("e"), x["t"].alias("t"), before.alias("before"))
        return F.struct((s + F.char_length(x["t"])).alias("at"), last(acc["tail"], x["p"], x["t"]).alias("tail"), F.concat(acc["out"], F.array(one)).alias("out"))

    def block(acc: Column, k: Column) -> Column:
        start = F.struct(acc["at"].alias("at"), acc["tail"].alias("tail"), none.alias("out"))
        done = F.aggregate(F.slice(pairs, k * _BLOCK + 1, F.lit(_BLOCK)), start, step)
        return F.transform(F.array(done), lambda d: F.struct(d["at"].alias("at"), d["tail"].alias("tail"), F.concat(acc["out"], F.array(d["out"])).alias("out")))[0]

    blocks = F.sequence(F.lit(0), F.floor((F.size(m) - 1) / _BLOCK).cast("int"))
    zero = F.struct(F.lit(0).alias("at"), F.lit("").alias("tail"), no_block.alias("out"))
    return F.when(F.size(m) > 0, F.aggregate(blocks, zero, block, lambda acc: F.flatten(acc["out"]))).otherwise(none)


def _value(x: Column) -> Column:
    """A candidate without the key word and sign that it begins with, which belong to its context."""
    value = F.regexp_replace(x["t"], f"^{_KEYED}", "")
    cut = F.char_length(x["t"]) - F.char_length(value)
    before = F.right(F.concat(x["before"], F.substring(x["t"], F.lit(1), cut)), F.lit(CONTEXT))
    return F.struct((x["s"] + cut).alias("s"), x["e"].alias("e"), value.alias("t"), before.alias("before"))


def _valid(kind: str, x: Column) -> Column:
    digits = F.regexp_replace(x["t"], "[^0-9]", "")
    if kind == "ip":
        part = lambda q: F.regexp_replace(q, "^0+", "")
        return F.forall(F.split(x["t"], r"\."), lambda q: (F.length(part(q)) <= 3) & (F.coalesce(F.concat(F.lit("0"), part(q)).try_cast("int"), F.lit(999)) <= 255))
    if kind == "card":
        return F.length(digits).between(13, 19) & F.call_function("luhn_check", digits)
    if kind == "phone":
        return F.length(digits).between(9, 15)
    return F.lit(True)


def _check(kind: str):
    return lambda x: _valid(kind, x)


def _votes(x: Column) -> Column:
    """The candidate's kind and its labelers' votes."""
    t, before = x["t"], x["before"]
    vote = lambda yes, no=None: F.when(yes, 1).when(no, -1).otherwise(0) if no is not None else F.when(yes, 1).otherwise(0)
    digits_only = ~t.rlike("[A-Za-z]")
    ssn, phone, person, address = (t.rlike(f"^(?:{p})$") for p in (_SSN, _PHONE, _PERSON, _ADDRESS))
    words = person | address
    kind = F.when(ssn, "ssn").when(phone, "phone").when(person, "person").when(address, "address").when(digits_only, "account").otherwise("secret")
    changes = F.size(F.split(t, "(?<=[0-9])(?=[A-Za-z])|(?<=[A-Za-z])(?=[0-9])"))
    return F.struct(
        x["s"].alias("s"), x["e"].alias("e"), kind.alias("kind"),
        vote(ssn | phone | address | t.rlike("^[A-Za-z0-9+/_-]{24,}$") & (changes > 5), digits_only & ~ssn & ~phone).alias("shape"),
        vote(~words & (F.length(t) >= 20), ~words & (F.length(t) < 12)).alias("length"),
        vote(~words & (changes > 5), ~words & (changes < 3)).alias("mixture"),
        vote(before.rlike(KEY_WORDS)).alias("key_word"),
        F.when(before.rlike(PLAIN_WORDS), -1).otherwise(0).alias("plain_word"),
        vote(person & t.rlike(f"\\b(?:{GIVEN_NAMES})\\b")).alias("given_name"),
        vote(address | before.rlike(f"\\b(?:{PLACES})\\b")).alias("place"),
        vote(before.rlike("[=:] ?[\"'(]?$"), ~words & before.rlike("[A-Za-z,] $")).alias("assigned"),
        vote(before.rlike("[\"'`]$")).alias("quoted"),
    )


def with_spans(docs: DataFrame) -> DataFrame:
    """docs with columns _email, _ip, _card, _phone (spans) and _more (candidates with votes, apart from base spans); no other column of docs may begin with _."""
    text = F.coalesce(F.col("text"), F.lit(""))
    found = {**BASE, "more": CANDIDATE}
    likely = {"email": F.contains(text, F.lit("@")), "phone": F.contains(text, F.lit("+"))}
    empty = F.expr("cast(array() as array<string>)")
    at = lambda k, what: F.when(likely[k], what).otherwise(empty) if k in likely else what
    out = docs.withColumns({f"_m_{k}": at(k, F.regexp_extract_all(text, F.lit(r), F.lit(0))) for k, r in found.items()})
    out = out.withColumns({f"_p_{k}": F.when(F.size(f"_m_{k}") > 0, F.split(text, r, -1)).otherwise(empty) for k, r in found.items()})
    out = out.withColumns({f"_{k}": _spans(F.col(f"_m_{k}"), F.col(f"_p_{k}")) for k in found}).drop(*(f"_{w}_{k}" for k in found for w in "mp"))
    out = out.withColumns({f"_{k}": F.transform(F.filter(f"_{k}", _check(k)), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"))) for k in BASE})
    base = F.concat(*(F.col(f"_{k}") for k in BASE))
    out = out.withColumn("_more", F.transform("_more", _value))
    apart = F.filter("_more", lambda c: ~F.exists(base, lambda b: (b["s"] < c["e"]) & (c["s"] < b["e"])))
    return out.withColumn("_more", F.transform(apart, _votes))


@dataclass(frozen=True)
class SpanModel:
    """Weights of the logistic classifier: of each vote of each labeler, of each kind, and a constant."""

    votes: dict[tuple[str, int], float]
    kinds: dict[str, float]
    constant: float
    reliability: dict[str, tuple[float, float]]  # of each labeler: P(for | private), P(for | not)

    def probability(self, x) -> Column:
        z = F.lit(self.constant)
        for (name, v), w in self.votes.items():
            z = z + F.when(x[name] == v, w).otherwise(0.0)
        for kind, w in self.kinds.items():
            z = z + F.when(x["kind"] == kind, w).otherwise(0.0)
        return 1 / (1 + F.exp(-z))


_EXTRA = ("phone", "account", "secret", "ssn", "person", "address")
_LEVELS = (1, 0, -1)


def train(spans: DataFrame, rounds: int = 30, steps: int = 100) -> SpanModel | None:
    """The classifier from all candidates of a table with _more; None if it has none.

    All that leaves the tasks are counts of vote patterns, at most 3 ** 9 for
    each of six kinds, so the rounds are arithmetic on that small table.
    """
    rows = spans.select(F.explode("_more").alias("c")).select("c.kind", *(f"c.{n}" for n in LABELERS))
    counted = rows.groupBy("kind", *LABELERS).agg(F.count("*").alias("n")).collect()
    table = sorted((r["kind"], tuple(r[n] for n in LABELERS), r["n"]) for r in counted)
    total = sum(n for *_, n in table)
    return fit_votes(table, total, rounds, steps) if total else None


def fit_votes(table: list[tuple[str, tuple[int, ...], int]], total: int, rounds: int, steps: int) -> SpanModel:
    """Reliabilities by expectation-maximisation, from the start that a labeler is right more often than not; then weights by gradient steps on the soft labels."""
    prior = 0.5
    p1, p0 = ([{1: a, 0: b, -1: c} for _ in LABELERS] for a, b, c in ((0.5, 0.4, 0.1), (0.1, 0.5, 0.4)))
    posterior = [0.5] * len(table)
    for _ in range(rounds):
        odds = [[math.log(p1[i][v] / p0[i][v]) if v else math.log(p1[i][0] / p0[i][0]) for v in (0, 1, -1)] for i in range(len(LABELERS))]
        base = math.log(prior / (1 - prior))
        posterior = [_logistic(base + sum(odds[i][v] for i, v in enumerate(votes))) for _, votes, _ in table]
        good = sum(n * q for (*_, n), q in zip(table, posterior, strict=True))
        prior = min(max(good / total, 0.001), 0.999)
        for i in range(len(LABELERS)):
            for v in _LEVELS:
                mine = [(n, q) for (_, votes, n), q in zip(table, posterior, strict=True) if votes[i] == v]
                p1[i][v] = (sum(n * q for n, q in mine) + 1) / (good + 3)
                p0[i][v] = (sum(n * (1 - q) for n, q in mine) + 1) / (total - good + 3)
    weight = {(name, v): 0.0 for name in LABELERS for v in (1, -1)}
    kinds, constant, rate = dict.fromkeys(_EXTRA, 0.0), 0.0, 4.0
    for _ in range(steps):  # on the cross-entropy, with a little decay
        slope, by_kind, one = dict.fromkeys(weight, 0.0), dict.fromkeys(kinds, 0.0), 0.0
        for (kind, votes, n), q in zip(table, posterior, strict=True):
            z = constant + kinds[kind] + sum(weight[name, v] for name, v in zip(LABELERS, votes, strict=True) if v)
            off = n / total * (q - _logistic(z))
            one += off
            by_kind[kind] += off
            for name, v in zip(LABELERS, votes, strict=True):
                if v:
                    slope[name, v] += off
        weight = {k: w + rate * (slope[k] - 1e-3 * w) for k, w in weight.items()}
        kinds = {k: w + rate * (by_kind[k] - 1e-3 * w) for k, w in kinds.items()}
        constant += rate * one
    return SpanModel(weight, kinds, constant, {name: (p1[i][1], p0[i][1]) for i, name in enumerate(LABELERS)})


def _logistic(z: float) -> float:
    return 1 / (1 + math.exp(-max(min(z, 500.0), -500.0)))


def decide(spans: DataFrame, model: SpanModel | None, threshold: float = 0.5) -> DataFrame:
    """spans with _all: base spans and what the classifier adds, by kind as in KINDS, then start; _base: base spans alone."""
    named = lambda col, kind: F.transform(col, lambda x: F.struct(F.lit(kind).alias("kind"), x["s"].alias("s"), x["e"].alias("e")))
    base = [named(F.col(f"_{k}"), k) for k in BASE]
    out = spans.withColumn("_base", F.concat(*base))
    if model is None:
        return out.withColumn("_all", F.col("_base"))
    more = F.transform(F.filter("_more", lambda x: model.probability(x) >= threshold), lambda x: F.struct(x["kind"].alias("kind"), x["s"].alias("s"), x["e"].alias("e")))
    out = out.withColumn("_added", more)
    of = lambda kind: F.filter("_added", lambda x: x["kind"] == kind)
    parts = [F.array_sort(F.concat(b, of(k))) if k == "phone" else b for b, k in zip(base, BASE, strict=True)]
    return out.withColumn("_all", F.concat(*parts, *(of(k) for k in KINDS[4:])))


def _digest(col: str) -> Column:
    return F.array_join(F.transform(col, lambda x: F.concat_ws(":", x["kind"], x["s"].cast("string"), x["e"].cast("string"))), ",")


def personal_data(docs: DataFrame) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added, n_spans) for each row.

    The counts by kind are of base spans, n_added is of what the classifier adds, n_spans of all. Null counts as empty, which has no spans and
    the digest of the empty string. Repeated rows repeat; an empty table gives
    none; other columns of docs are ignored.
    """
    spans = stage(with_spans(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")).drop("text"), "pii-spans")
    out = decide(spans, train(spans))
    return out.select(
        "doc_id", *(F.size(f"_{k}").cast("long").alias(f"n_{k}") for k in BASE), F.sha2(_digest("_base"), 256).alias("base_sha256"),
        _digest("_all").alias("spans"), (F.size("_all") - F.size("_base")).cast("long").alias("n_added"), F.size("_all").cast("long").alias("n_spans"),
    )


def mask(docs: DataFrame) -> DataFrame:
    """docs, all columns kept, with every span of text replaced by its kind in brackets; a null text stays null."""
    columns = docs.columns
    spans = with_spans(docs.select(F.struct("*").alias("row"), F.col("text").alias("text")))
    out = decide(spans, train(spans.select("_more")))
    order = F.array_sort(F.transform("_all", lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["kind"].alias("kind"))))
    # pieces of text between spans that begin at or after the end of all before
    start = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<struct<a: int, b: int, kind: string>>)").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        part = F.struct(acc["at"].alias("a"), x["s"].alias("b"), x["kind"].alias("kind"))
        return F.struct(F.greatest(acc["at"], x["e"]).alias("at"), F.when(x["s"] < acc["at"], acc["out"]).otherwise(F.concat(acc["out"], F.array(part))).alias("out"))

    cut = F.aggregate(order, start, step)
    named = F.transform(cut["out"], lambda x: F.concat(F.substring(F.col("text"), x["a"] + 1, x["b"] - x["a"]), F.lit("["), F.upper(x["kind"]), F.lit("]")))
    whole = F.concat(F.array_join(named, ""), F.substring(F.col("text"), cut["at"] + 1, F.lit(2**31 - 1)))
    masked = F.when(F.size("_all") > 0, whole).otherwise(F.col("text"))
    return out.select(*(masked.alias(c) if c == "text" else F.col("row")[c].alias(c) for c in columns))
