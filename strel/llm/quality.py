"""Text quality by positive-unlabelled learning.

Trusted good texts and a sample of all texts, labels unseen, fit a scorer that minimises the
non-negative unbiased risk: prior * loss(good as good) + max(0, loss(all as bad) - prior *
loss(good as bad)). The class prior is estimated from scores of a first fit that tells good texts
from all texts: over thresholds, the smallest ratio between the share of all texts and the share
of good texts above the threshold, with confidence margins.

Features are shares and rates of characters, words and lines. They are computed once for every whole
text and stored; each is cut at its quantiles over all texts, and the scorer is linear in the cuts.
The class prior comes from the scores of all texts too. Only the two sides of the risk are samples:
at most ``FIT_GOOD`` good and ``FIT_ALL`` other texts (those of smallest hash).

Null and empty texts have all rates zero and are scored like any text; repeated rows get equal
scores, and of several texts of one doc_id all may teach. Without a good label every score is 0.5.
An empty table gives no row. Columns but the id and the text are not read.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strel.llm.encode import blocks, each
from strel.runtime import materialize, ship

FIT_GOOD, FIT_ALL = 8_000, 12_000
_CUTS = 12
_UPPER, _LOWER, _DIGITS = bytes(range(65, 91)), bytes(range(97, 123)), bytes(range(48, 58))
_HIGH = bytes(range(128, 256))
_MARKS = [bytes([c]) for c in b"|!$#%&*.,?<>{}@\\/=_~"]
NAMES = ["chars", "words", "upper", "lower", "digit", "high", "other", "space", "word_len", "distinct", "repeats", "pairs", "lines", "line_distinct", "top_word", "long_words", "ends", *(f"mark_{m.decode()}" for m in _MARKS)]


def features(t: bytes) -> list[float]:
    """Rates of one text; all are between 0 and 1 or logarithms."""
    n = len(t)
    if not n:
        return [0.0] * len(NAMES)
    ws = t.split()
    k = max(len(ws), 1)
    cut = lambda drop: (n - len(t.translate(None, drop))) / n
    upper, lower, digit, high = cut(_UPPER), cut(_LOWER), cut(_DIGITS), cut(_HIGH)
    marks = [t.count(m) / k for m in _MARKS]
    lines = [x for x in t.split(b"\n") if x.strip()]
    kinds = set(ws)
    repeats = sum(map(bytes.__eq__, ws, ws[1:])) / k
    pairs = len(set(zip(ws, ws[1:], strict=False))) / k
    size = sum(map(len, ws))
    top = max(Counter(ws).values(), default=0) / k
    return [
        np.log1p(n), np.log1p(len(ws)), upper, lower, digit, high, max(0.0, 1 - upper - lower - digit - high), 1 - size / n,
        np.log1p(size / k), len(kinds) / k, repeats, pairs, np.log1p(len(lines)), len(set(lines)) / max(len(lines), 1), top,
        sum(1 for w in kinds if len(w) > 20) / k, sum(1 for x in lines if x.rstrip()[-1:] in b".!?") / max(len(lines), 1), *marks,
    ]


@dataclass
class Scorer:
    cuts: np.ndarray  # features x cuts
    weights: np.ndarray
    bias: float
    prior: float

    def expand(self, x: np.ndarray) -> np.ndarray:
        return (x[:, :, None] > self.cuts[None]).reshape(len(x), -1).astype(np.float64)

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.expand(x) @ self.weights + self.bias, -30, 30)))


def _descend(grad, size: int, steps: int = 600, rate: float = 0.05) -> np.ndarray:
    """Adam on a full-batch gradient."""
    w, m, v = np.zeros(size), np.zeros(size), np.zeros(size)
    for t in range(1, steps + 1):
        g = grad(w)
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return w


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def estimate_prior(good: np.ndarray, every: np.ndarray, counts: np.ndarray | None = None, sure: float = 0.1) -> float:
    """Share of good ones among all, from scores that tell good ones from all.

    ``counts``: how many texts each value of ``every`` stands for.
    """
    good = np.sort(good)
    order = np.argsort(every)
    every, counts = every[order], (np.ones(len(every)) if counts is None else counts[order])
    below = np.concatenate([[0.0], np.cumsum(counts)])
    at = np.unique(np.concatenate([good, every]))
    qp = 1 - np.searchsorted(good, at, "left") / len(good)
    qu = 1 - below[np.searchsorted(every, at, "left")] / below[-1]
    margin = np.sqrt(np.log(4 / sure) / 2 / len(good)) + np.sqrt(np.log(4 / sure) / 2 / below[-1])
    ok = qp > max(0.02, 2 * margin)
    if not ok.any():
        return 0.5
    bound = (qu[ok] + margin) / qp[ok]
    k = int(np.argmin(bound))
    return float(np.clip((qu[ok] / qp[ok])[k], 0.02, 0.98))


def cuts_of(every: np.ndarray) -> np.ndarray:
    return np.quantile(every, np.linspace(0, 1, _CUTS + 2)[1:-1], axis=0).T


def first_scorer(good: np.ndarray, every: np.ndarray, cuts: np.ndarray, ridge: float = 2e-4) -> Scorer:
    """Tells good texts from all, without regard to the good among all; for the prior."""
    model = Scorer(cuts, np.zeros(cuts.size), 0.0, 0.5)
    a, u = (np.column_stack([np.ones(len(x)), model.expand(x)]) for x in (good, every))
    pen = np.full(a.shape[1], ridge)
    pen[0] = 0.0
    w = _descend(lambda w: a.T @ (_sigmoid(a @ w) - 1) / len(a) + u.T @ _sigmoid(u @ w) / len(u) + 10 * pen * w, a.shape[1], 300)
    return Scorer(cuts, w[1:], float(w[0]), 0.5)


def fit_scorer(good: np.ndarray, every: np.ndarray, prior: float | None = None, ridge: float = 2e-4, cuts: np.ndarray | None = None) -> Scorer:
    """Non-negative risk over rows of features; without a prior it is estimated from the rows."""
    cuts = cuts_of(every) if cuts is None else cuts
    if prior is None:  # fitted on one half and read on the other
        first = first_scorer(good[::2], every[::2], cuts, ridge)
        prior = estimate_prior(first.score(good[1::2]), first.score(every[1::2]))
    model = Scorer(cuts, np.zeros(cuts.size), 0.0, prior)
    a, u = (np.column_stack([np.ones(len(x)), model.expand(x)]) for x in (good, every))
    pen = np.full(a.shape[1], ridge)
    pen[0] = 0.0

    def grad(w: np.ndarray) -> np.ndarray:
        pa, pu = _sigmoid(a @ w), _sigmoid(u @ w)
        as_good = prior * (a.T @ (pa - 1)) / len(a)
        bad = u.T @ pu / len(u) - prior * (a.T @ pa) / len(a)
        risk = np.mean(np.logaddexp(0, u @ w)) - prior * np.mean(np.logaddexp(0, a @ w))
        # where the risk of the bad turns negative, step back instead of forward
        return (as_good + bad if risk >= 0 else -bad) + pen * w

    w = _descend(grad, a.shape[1])
    return Scorer(cuts, w[1:], float(w[0]), prior)


def _rates(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
    for b in batches:
        yield pa.array([features(t) for _, ts in blocks(range(len(b)), each(b)) for t in ts], pa.list_(pa.float32()))


def describe(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """doc_id and the features ``x`` of every whole text, stored."""
    ship(docs.sparkSession)
    return materialize(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.arrow_udf(_rates, "array<float>")(F.col(text_col).cast("string")).alias("x")), "features")


def _scorer(model: Scorer):
    @F.arrow_udf("double")
    def scores(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for b in batches:
            parts = [b.slice(at, 4096) for at in range(0, len(b), 4096)]
            yield pa.concat_arrays([pa.array(model.score(np.asarray(p.flatten(), np.float64).reshape(len(p), -1))) for p in parts]) if parts else pa.array([], pa.float64())

    return scores


def fit(described: DataFrame, labels: DataFrame, good_rows: int = FIT_GOOD, all_rows: int = FIT_ALL, bins: int = 4_000) -> Scorer | None:
    """A scorer from labels (doc_id, quality) of trusted good texts and the features of all texts.

    None if no text is labelled good.
    """
    rank = F.xxhash64("doc_id")
    good = labels.where("quality = 1 AND doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id")).distinct().orderBy(rank, "doc_id").limit(good_rows)
    a = described.join(F.broadcast(good), "doc_id", "left_semi").groupBy("doc_id").agg(F.min("x").alias("x")).collect()  # at most good_rows
    u = described.orderBy(F.xxhash64("doc_id", "x"), "doc_id").limit(all_rows).select("x").collect()
    if not a or not u:
        return None
    a, u = (np.array([r["x"] for r in rows], dtype=float) for rows in (a, u))
    qs = [float(q) for q in np.linspace(0, 1, _CUTS + 2)[1:-1]]
    row = described.agg(*[F.percentile_approx(F.col("x")[k], qs, 2000).alias(f"q{k}") for k in range(len(NAMES))]).first()
    cuts = np.array([row[f"q{k}"] for k in range(len(NAMES))], dtype=float)
    first = first_scorer(a[::2], u, cuts)
    seen = described.select(F.floor(_scorer(first)(F.col("x")) * bins).alias("bin")).groupBy("bin").agg(F.count(F.lit(1)).alias("n")).collect()  # at most bins + 1
    every, counts = (np.array(v, dtype=float) for v in zip(*((r["bin"], r["n"]) for r in seen), strict=True))
    prior = estimate_prior(np.floor(first.score(a[1::2]) * bins), every, counts) if len(a) > 1 else 0.5
    return fit_scorer(a, u, prior, cuts=cuts)


def score(described: DataFrame, model: Scorer | None) -> DataFrame:
    """doc_id and the score, from 0 to 1, of every whole text."""
    found = _scorer(model)(F.col("x")) if model is not None else F.lit(0.5)
    return described.select("doc_id", found.alias("score"))
