"""Quality scores by learning from positives and unlabelled text.

Trusted positives are rows labelled good; the unlabelled side is a sample of
all web text. With class prior p the risk of calling unlabelled text bad, less
p times the same risk on positives, estimates the risk on true negatives. It
can't be below zero, so where a batch's estimate is, the step goes the other
way: that keeps a flexible model from pushing the estimate below zero by
fitting the positives it has seen. The prior is estimated from the two samples:
where a score tells positives best, the share of unlabelled text above it over
that of positives bounds the prior from above. The scorer is a small network over shape statistics and the
byte histogram of the whole text.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import map_groups

WIDTH = 129 + 10


def features(text: bytes | None) -> np.ndarray:
    """Shares of ASCII bytes (roots) and of the rest, and the shape of words and lines; all zero for an empty text."""
    out = np.zeros(WIDTH, np.float32)
    if not text:
        return out
    a = np.frombuffer(text, np.uint8)
    n = len(a)
    hist = np.bincount(a, minlength=256)
    out[:128] = np.sqrt(hist[:128] / n)
    out[128] = hist[128:].sum() / n
    words = text.split()
    sizes = np.fromiter(map(len, words), np.int64, len(words)) if words else np.zeros(1, np.int64)
    lines = text.split(b"\n")
    ends = np.fromiter((w[-1] for w in words), np.uint8, len(words)) if words else np.zeros(1, np.uint8)
    alnum = (ends >= 128) | ((ends >= 97) & (ends <= 122)) | ((ends >= 65) & (ends <= 90)) | ((ends >= 48) & (ends <= 57))
    out[129:] = (
        np.log1p(n) / 10, np.log1p(len(words)) / 10, sizes.mean() / 10, sizes.std() / 10, (sizes <= 4).mean(), len(set(words)) / max(1, len(words)),
        len(set(lines)) / len(lines), np.log1p(n / len(lines)) / 10, 1 - alnum.mean(), np.log1p(len(lines)) / 10,
    )
    return out


@dataclass
class Scorer:
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: np.ndarray

    def margin(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(((x - self.mean) / self.scale) @ self.w1 + self.b1) @ self.w2 + self.b2[0]

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(x), -30, 30)))


def fit(positive: np.ndarray, unlabelled: np.ndarray, prior: float, *, hidden: int = 24, epochs: int = 60, batch: int = 256, rate: float = 2e-3, decay: float = 1e-3, seed: int = 5) -> Scorer:
    """Adam on the non-negative risk with logistic loss."""
    rng = np.random.default_rng(seed)
    mean, scale = unlabelled.mean(0), unlabelled.std(0) + 1e-2
    net = Scorer(mean, scale, rng.standard_normal((WIDTH, hidden)) / np.sqrt(WIDTH), np.zeros(hidden), np.zeros(hidden), np.zeros(1))
    params = [net.w1, net.b1, net.w2, net.b2]
    first, second, t = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
    p, u = (positive - mean) / scale, (unlabelled - mean) / scale
    steps = max(1, len(u) // batch)
    share = max(1, len(p) // steps)
    for _ in range(epochs):
        at_p, at_u = rng.permutation(len(p)), rng.permutation(len(u))
        for k in range(steps):
            xp, xu = p[at_p[k * share : (k + 1) * share]], u[at_u[k * batch : (k + 1) * batch]]
            if not len(xp) or not len(xu):
                continue
            x = np.concatenate([xp, xu])
            h = np.tanh(x @ net.w1 + net.b1)
            f = h @ net.w2 + net.b2[0]
            good = 1 / (1 + np.exp(-f))  # slope of the loss of calling a row bad; less 1, of calling it good
            np_, nu = len(xp), len(xu)
            loss = np.logaddexp(0, f)
            negative = loss[np_:].mean() - prior * loss[:np_].mean()
            g = np.zeros(len(x))
            if negative >= 0:
                g[:np_] = prior * (good[:np_] - 1) / np_ - prior * good[:np_] / np_
                g[np_:] = good[np_:] / nu
            else:
                g[:np_] = prior * good[:np_] / np_
                g[np_:] = -good[np_:] / nu
            dh = g[:, None] * net.w2 * (1 - h**2)
            t += 1
            for q, (value, grad) in enumerate(zip(params, [x.T @ dh + decay * net.w1, dh.sum(0), h.T @ g + decay * net.w2, np.array([g.sum()])], strict=True)):
                first[q] = 0.9 * first[q] + 0.1 * grad
                second[q] = 0.999 * second[q] + 0.001 * grad**2
                value -= rate * (first[q] / (1 - 0.9**t)) / (np.sqrt(second[q] / (1 - 0.999**t)) + 1e-8)
    return net


def estimate_prior(positive: np.ndarray, unlabelled: np.ndarray, *, folds: int = 2, steps: int = 300, rate: float = 0.05, seed: int = 3) -> float:
    """Share of positives in unlabelled text, from positives and unlabelled text alone.

    A logistic model tells the two samples apart, fitted on one part and applied
    to the other. For every threshold the unlabelled share above it is at least
    the prior times the positive share above it; the least such ratio over
    thresholds that half of the positives pass, where shares are well known, is
    the estimate, and the mean over the parts what is returned.
    """
    rng, ratio = np.random.default_rng(seed), []
    mean, scale = unlabelled.mean(0), unlabelled.std(0) + 1e-2
    p, u = (positive - mean) / scale, (unlabelled - mean) / scale
    part_p, part_u = rng.integers(0, folds, len(p)), rng.integers(0, folds, len(u))
    for k in range(folds):
        xp, xu, hp, hu = p[part_p != k], u[part_u != k], p[part_p == k], u[part_u == k]
        if not (len(xp) and len(xu) and len(hp) and len(hu)):
            continue
        x = np.concatenate([xp, xu])
        weight = np.concatenate([np.full(len(xp), 0.5 / len(xp)), np.full(len(xu), 0.5 / len(xu))])
        y = np.concatenate([np.ones(len(xp)), np.zeros(len(xu))])
        w, c = np.zeros(x.shape[1]), 0.0
        m, v = np.zeros(len(w) + 1), np.zeros(len(w) + 1)
        for t in range(1, steps + 1):
            off = weight * (1 / (1 + np.exp(-np.clip(x @ w + c, -30, 30))) - y)
            g = np.append(x.T @ off + 1e-3 * w, off.sum())
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g**2
            step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
            w, c = w - step[:-1], c - step[-1]
        sp, su = np.sort(hp @ w), np.sort(hu @ w)
        ratio.append([])
        for at in np.quantile(sp, np.linspace(0.01, 0.5, 50)):
            a, b = 1 - np.searchsorted(sp, at) / len(sp), 1 - np.searchsorted(su, at) / len(su)
            if a > 0:
                ratio[-1].append(b / a)
    least = [min(r) for r in ratio if r]
    return float(np.clip(np.mean(least), 0.01, 0.99)) if least else 0.5


def _sampled(docs: DataFrame, ids: DataFrame, rows: int) -> np.ndarray:
    """Features of the texts of at most `rows` ids, the least by a hash; in the order of that hash."""
    some = ids.select("doc_id").distinct().orderBy(F.xxhash64("doc_id", F.lit(1)), "doc_id").limit(rows)
    text = docs.select("doc_id", "text").join(F.broadcast(some), "doc_id", "left_semi").select(F.col("doc_id").cast("long"), "text")
    got = map_groups(text, lambda part: [(d, features(t).tobytes()) for d, t in part], "doc_id long, x binary").collect()
    got.sort(key=lambda r: (r.doc_id, r.x))
    return np.frombuffer(b"".join(r.x for r in got), np.float32).reshape(-1, WIDTH).astype(np.float64)


def train(docs: DataFrame, labels: DataFrame, *, positives: int = 4000, unlabelled: int = 8000) -> Scorer | None:
    """A scorer from labels(doc_id, quality), of which only the rows with quality 1 are used, and docs. Bounds are on the rows learnt from; None without positives or text."""
    known = labels.where("quality = 1 and doc_id is not null")
    docs = docs.where(F.col("doc_id").isNotNull())
    p = _sampled(docs, known, positives)
    u = _sampled(docs, docs, unlabelled)
    return fit(p, u, estimate_prior(p, u)) if len(p) and len(u) else None


def quality_scores(docs: DataFrame, net: Scorer | None, threshold: float = 0.3) -> DataFrame:
    """(doc_id, score, predicted) for each row; null counts as empty; without a model every score is 0.5."""

    def many(rows):
        x = np.stack([features(t) for _, t in rows]).astype(np.float64)
        s = net.score(x) if net else np.full(len(rows), 0.5)
        return [(d, v, int(v >= threshold)) for (d, _), v in zip(rows, s.tolist(), strict=True)]

    return map_groups(docs.select(F.col("doc_id").cast("long"), "text"), many, "doc_id long, score double, predicted int")
