"""Language identification by a byte convolutional network, trained and applied in numpy.

Bytes are embedded, filters of several widths slide over fixed-length windows,
each filter keeps its maximum, and a softmax layer gives the languages. Filters
of all widths sit in one matrix (narrow ones padded with zeros), so a batch of
windows is one matrix product. A text is all its windows, end to end; its
probabilities are the mean over windows, weighted by bytes.
"""

from __future__ import annotations

import copy
from dataclasses import dataclass

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treepack.llm.common import give_back, map_groups, maybe_broadcast, scratch, stage

LENGTH = 256
WIDTHS = (2, 3, 4)
_LETTER = regex.compile(r"\p{L}")


@dataclass
class ByteCNN:
    labels: list[str]
    embed: np.ndarray  # 256 x dim; row 0, the padding byte, stays zero
    kernel: np.ndarray  # widest * dim x filters
    bias: np.ndarray
    out: np.ndarray
    out_bias: np.ndarray

    @classmethod
    def new(cls, labels: list[str], dim: int = 8, filters: int = 16, seed: int = 7) -> ByteCNN:
        rng, widest, total = np.random.default_rng(seed), max(WIDTHS), filters * len(WIDTHS)
        draw = lambda *s, by: (rng.standard_normal(s) / np.sqrt(by)).astype(np.float32)
        net = cls(labels, draw(256, dim, by=dim), draw(widest * dim, total, by=widest), np.zeros(total, np.float32), draw(total, len(labels), by=total), np.zeros(len(labels), np.float32))
        net.embed[0] = 0
        net.kernel *= net.mask()
        return net

    def params(self) -> list[np.ndarray]:
        return [self.embed, self.kernel, self.bias, self.out, self.out_bias]

    def mask(self) -> np.ndarray:
        dim, per = self.embed.shape[1], self.kernel.shape[1] // len(WIDTHS)
        m = np.zeros_like(self.kernel)
        for k, w in enumerate(WIDTHS):
            m[: w * dim, k * per : (k + 1) * per] = 1
        return m

    def pooled(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(patches, maxima before the rectifier, where they are) of windows x."""
        n, length = x.shape
        widest, dim = max(WIDTHS), self.embed.shape[1]
        e = self.embed[x]
        steps = length - widest + 1
        patches = np.lib.stride_tricks.as_strided(e, (n, steps, widest * dim), e.strides[:2] + (e.strides[2],))
        conv = (patches.reshape(n * steps, -1) @ self.kernel).reshape(n, steps, -1)
        return patches, conv.max(axis=1), conv

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        _, top, _ = self.pooled(x)
        z = np.maximum(top + self.bias, 0) @ self.out + self.out_bias
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 8, batch: int = 64, rate: float = 3e-3, seed: int = 11) -> ByteCNN:
        """Adam on the cross-entropy; the gradient reaches only the patches that won the pooling."""
        rng, mask = np.random.default_rng(seed), self.mask()
        params = self.params()
        first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        dim, t = self.embed.shape[1], 0
        widest = max(WIDTHS)
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for at in range(0, len(x), batch):
                i = order[at : at + batch]
                patches, top, conv = self.pooled(x[i])
                where = conv.argmax(axis=1)
                act = np.maximum(top + self.bias, 0)
                z = act @ self.out + self.out_bias
                p = np.exp(z - z.max(axis=1, keepdims=True))
                p /= p.sum(axis=1, keepdims=True)
                p[np.arange(len(i)), y[i]] -= 1
                p /= len(i)
                up = (p @ self.out.T) * (act > 0)
                rows = np.arange(len(i))[:, None]
                won = patches[rows, where]  # windows x filters x (widest * dim)
                d_kernel = np.einsum("bf,bfk->kf", up, won) * mask
                d_patch = (up[:, :, None] * self.kernel.T[None]).reshape(-1, widest, dim)
                d_embed = np.zeros_like(self.embed)
                codes = x[i][rows[:, :, None], where[:, :, None] + np.arange(widest)].reshape(-1, widest)
                np.add.at(d_embed, codes.ravel(), d_patch.reshape(-1, dim))
                d_embed[0] = 0
                t += 1
                for q, (value, grad) in enumerate(zip(params, [d_embed, d_kernel, up.sum(0), act.T @ p, p.sum(0)], strict=True)):
                    first[q] = 0.9 * first[q] + 0.1 * grad
                    second[q] = 0.999 * second[q] + 0.001 * grad**2
                    value -= (rate * (first[q] / (1 - 0.9**t)) / (np.sqrt(second[q] / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
        return self


def has_letter(text: bytes) -> bool:
    return _LETTER.search(text.decode()) is not None


def windows(text: bytes) -> np.ndarray:
    """The whole text as rows of LENGTH bytes, the last one padded with zero bytes."""
    n = max(1, -(-len(text) // LENGTH))
    return np.frombuffer(text.ljust(n * LENGTH, b"\0"), np.uint8).reshape(n, LENGTH)


def predict_texts(net: ByteCNN, texts: list[bytes | None], batch: int = 512) -> list[tuple[str, float]]:
    """(language, probability) of each text; `und` with score 0 for a null text or one without a letter."""
    real = [t is not None and has_letter(t) for t in texts]
    used = [t for t, r in zip(texts, real, strict=True) if r]
    if not used:
        return [("und", 0.0)] * len(texts)
    rows = [windows(t) for t in used]
    n = np.array([len(r) for r in rows])
    x = np.concatenate(rows)
    p = np.concatenate([net.probabilities(x[a : a + batch]) for a in range(0, len(x), batch)]).astype(np.float64)
    weight = np.full(len(x), LENGTH, np.float64)
    last = np.cumsum(n) - 1
    weight[last] = [len(t) - LENGTH * (k - 1) for t, k in zip(used, n.tolist(), strict=True)]
    mean = np.add.reduceat(p * weight[:, None], last - n + 1) / np.array([len(t) for t in used])[:, None]
    found = iter(zip(mean.argmax(axis=1).tolist(), np.clip(mean.max(axis=1), 0, 1).tolist(), strict=True))
    return [(net.labels[(f := next(found))[0]], f[1]) if r else ("und", 0.0) for r in real]


def fold(column: str, of: int):
    """crc32 of the id's decimal text modulo `of`."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % of


def _sampled_ids(pool: DataFrame, most: int) -> DataFrame:
    """doc_id of up to `most` rows of each language, the least by a hash of the id.

    The hash is even, so with the languages' counts a bound on it leaves about
    twice as many rows as are wanted; only those meet by language.
    """
    counts = pool.groupBy("lang").agg(F.count("*").alias("n"))
    counts = maybe_broadcast(counts, 100_000)
    even = F.shiftrightunsigned(F.xxhash64("doc_id"), 1) / F.lit(float(1 << 63))
    some = pool.select("doc_id", "lang").join(counts, "lang").where(even * F.col("n") < 2 * most + 200)
    nth = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id"))
    return some.withColumn("nth", nth).where(F.col("nth") <= most).select("doc_id").distinct()


def training_windows(docs: DataFrame, *, per_language: int = 500, per_text: int = 4) -> list[tuple[int, str, bytes]]:
    """(doc_id, lang, window) of a bounded sample of labelled rows: of per_language rows of each language up to per_text windows. Rows without an id are not learnt from."""
    pool = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text").where("doc_id is not null and lang is not null and text is not null")
    some = pool.join(F.broadcast(_sampled_ids(pool, per_language)), "doc_id", "left_semi").select("doc_id", "lang", "text")

    def many(rows):
        out = []
        for doc_id, lang, text in rows:
            w = windows(text)
            full = max(1, len(text) // LENGTH)
            pick = sorted({int(k) for k in np.linspace(0, full - 1, per_text)})
            out += [(doc_id, lang.decode(), k, w[k].tobytes()) for k in pick]
        return out

    got = map_groups(some, many, "doc_id long, lang string, k int, b binary").collect()
    got.sort(key=lambda r: (r.doc_id, r.k, r.lang, r.b))
    return [(r.doc_id, r.lang, r.b) for r in got]


def fit_windows(sample: list[tuple[int, str, bytes]]) -> ByteCNN | None:
    if not sample:
        return None
    labels = sorted({lang for _, lang, _ in sample})
    at = {v: i for i, v in enumerate(labels)}
    return ByteCNN.new(labels).fit(np.frombuffer(b"".join(b for *_, b in sample), np.uint8).reshape(-1, LENGTH), np.array([at[lang] for _, lang, _ in sample]))


def train(docs: DataFrame, **sample) -> ByteCNN | None:
    return fit_windows(training_windows(docs, **sample))


#: Labelled rows that are learnt from together before networks are averaged.
SHARD = 4096


def learn_all(net: ByteCNN, rows: DataFrame, rate: float = 1e-3) -> ByteCNN:
    """The network after every window of every row(doc_id, lang, text) in net's languages.

    Rows are dealt by a hash to shards of about SHARD; each shard goes on from
    net over all its windows, and the mean of the shards' networks, weighted by
    windows, is what all have learnt. Order and partitions of rows don't matter.
    """
    at = {v: i for i, v in enumerate(net.labels)}
    known = rows.where(F.col("lang").isin(net.labels) & F.col("text").isNotNull())
    shards = max(1, known.count() // SHARD)

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        parts = sorted((t.encode(), at[lang]) for t, lang in zip(pdf["text"], pdf["lang"], strict=True))
        x = [windows(t) for t, _ in parts]
        y = np.repeat([k for _, k in parts], [len(w) for w in x])
        mine = copy.deepcopy(net).fit(np.concatenate(x), y, epochs=1, rate=rate)
        give_back()
        return pd.DataFrame({"shard": [pdf["shard"].iloc[0]], "n": [len(y)], "p": [np.concatenate([v.ravel() for v in mine.params()]).tobytes()]})

    dealt = known.select(F.pmod(F.xxhash64("doc_id", "text"), F.lit(shards)).alias("shard"), "lang", "text")
    got = sorted(dealt.groupBy("shard").applyInPandas(one, "shard long, n long, p binary").collect(), key=lambda r: r.shard)
    if not got:
        return net
    total, flat = sum(r.n for r in got), 0
    for r in got:
        flat = flat + np.frombuffer(r.p, np.float32).astype(np.float64) * (r.n / total)
    out, end = copy.deepcopy(net), 0
    for v in out.params():
        v[...] = flat[end : end + v.size].reshape(v.shape)
        end += v.size
    return out


def train_with_limit(docs: DataFrame, share: float = 0.001, **sample) -> tuple[ByteCNN | None, float]:
    """(net, score under which a text is in none of its languages), from all labelled rows.

    Rows whose id falls in one of five folds by its hash are held out. All
    others are learnt from, every window of them: a balanced sample gives only
    the parameters to start at. The limit lies a tenth under the score that all
    but `share` of the held-out texts reach that are recognised, so texts of
    the learnt languages stay.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text").where("lang is not null and text is not null")
    held = F.coalesce(F.pmod(F.xxhash64("doc_id"), F.lit(5)) == 0, F.lit(False)) & F.col("doc_id").isNotNull()
    start = train(rows.where(~held), **sample)
    if start is None:  # at most a few rows, all of one fold
        return train(rows, **sample), 0.0
    net = learn_all(start, rows.where(~held))

    def many(some):
        got = predict_texts(net, [t for _, t in some])
        return [(score,) for (lang, _), (found, score) in zip(some, got, strict=True) if lang.decode() == found]

    with scratch(docs.sparkSession):
        scores = stage(map_groups(rows.where(held).select("lang", "text"), many, "score double", nbytes=1 << 20), "language-scores")
        n = scores.count()
        if not n:
            return net, 0.0
        at = share * (n - 1)
        low = [r.score for r in scores.orderBy("score").limit(int(at) + 2).collect()]
    first = low[int(at)]
    return net, 0.9 * (first + (low[min(int(at) + 1, n - 1)] - first) * (at - int(at)))


def language_id(docs: DataFrame, net: ByteCNN | None) -> DataFrame:
    """(doc_id, lang_pred, score) for each row, from the text alone.

    `und` if the text is null or has no letter, and for every text if there was
    nothing to learn from. Repeated rows repeat; an empty table gives none.
    """

    def many(rows):
        texts = [t for _, t in rows]
        got = predict_texts(net, texts) if net else [("und", 0.0)] * len(rows)
        return [(d, *g) for (d, _), g in zip(rows, got, strict=True)]

    return map_groups(docs.select(F.col("doc_id").cast("long"), "text"), many, "doc_id long, lang_pred string, score double", nbytes=1 << 20)
