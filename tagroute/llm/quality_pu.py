"""Quality from positive and unlabelled texts, by the non-negative unbiased risk.

Trusted positives are labelled rows of quality 1; the unlabelled sample is drawn
from all documents, labels unseen; no label 0 is read anywhere.  With the class prior p, the risk of the
negative class is estimated as E_u[loss(-g)] - p E_p[loss(-g)]; as flexible
models drive that below zero, it is held at zero (and stepped back when it
falls below).  The prior itself is estimated from scores of a first fit: at
every threshold the share of unlabelled rows above it, over that of positives,
bounds the prior from above; the least such bound (with its deviation) counts.

A score is the logistic of the margin, shifted so that 0.7 is where the fitted
risk is indifferent between the classes, or lower, where that would lose more
than 2 in 1,000 of the trusted positives.

Features are counts over bytes, words and lines of the whole text, expanded
into bins between quantiles of the sample: an additive model.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textblocks import WORD_BY_SPACE, Words, slice_batches, tidy_map
from .toxicity_ws import bounded_sample

_CLASS = np.zeros(256, np.int64)
_CLASS[65:91], _CLASS[97:123], _CLASS[48:58], _CLASS[128:] = 1, 2, 3, 4
for _c, _k in {" ": 5, "\n": 6, ".": 7, ",": 7, "!": 8, "|": 9, "-": 11, "'": 11, '"': 11, "(": 11, ")": 11, ":": 11, ";": 11, "?": 11, "<": 12, ">": 12, "=": 12, "{": 12, "}": 12, "/": 12}.items():
    _CLASS[ord(_c)] = _k
for _c in "#$%&*@^~+_\\`[]":
    _CLASS[ord(_c)] = 10
_CLASSES = 13
#: Bins between quantiles of each feature.
BINS = 8


def features(texts: list[bytes]) -> np.ndarray:
    """One row of numbers a text; an empty text is all zeros but for its length."""
    n = len(texts)
    w = Words(texts, WORD_BY_SPACE, lower=False)
    raw = np.frombuffer(w.buffer, np.uint8)
    text_of = np.repeat(np.arange(n), np.diff(w.text_start))
    kinds = np.bincount(text_of * _CLASSES + _CLASS[raw], minlength=n * _CLASSES).reshape(n, _CLASSES).astype(float)
    kinds[:, 6] -= 1  # the separator
    size = np.maximum(kinds.sum(1), 1)
    words = np.diff(w.first)
    some = np.maximum(words, 1)
    of = np.repeat(np.arange(n), words)
    length = (w.end - w.start).astype(float)
    mean = lambda x: np.bincount(of, x, n) / some
    first, last = raw[w.start], raw[w.end - 1]
    class_first, class_last = _CLASS[first], _CLASS[last]
    upper = np.concatenate(([0], np.cumsum(_CLASS[raw] == 1)))
    lower = np.concatenate(([0], np.cumsum(_CLASS[raw] == 2)))
    ups, lows = upper[w.end] - upper[w.start], lower[w.end] - lower[w.start]
    again = np.zeros(len(w))
    again[1:] = (w.hash[1:] == w.hash[:-1]) & (of[1:] == of[:-1])
    pair_again = np.zeros(len(w))
    pair_again[2:] = (w.hash[2:] == w.hash[:-2]) & (of[2:] == of[:-2])
    order = np.lexsort((w.hash, of))
    h, o = w.hash[order], of[order]
    new = np.concatenate((np.ones(min(1, len(h)), bool), (h[1:] != h[:-1]) | (o[1:] != o[:-1])))
    distinct = np.bincount(o[new], minlength=n)
    times = np.diff(np.append(np.flatnonzero(new), len(h)))
    most = np.zeros(n)
    np.maximum.at(most, o[new], times)
    runs = w.runs(3)
    runs = runs[w.valid(3)[: len(runs)]] if len(runs) else runs
    three_of = of[: max(0, len(w) - 2)][w.valid(3)] if len(w) >= 3 else of[:0]
    order = np.lexsort((runs, three_of))
    r, t = runs[order], three_of[order]
    new3 = np.concatenate((np.ones(min(1, len(r)), bool), (r[1:] != r[:-1]) | (t[1:] != t[:-1])))
    threes = np.bincount(t, minlength=n)
    distinct3 = np.bincount(t[new3], minlength=n)
    lines, line_again, short_lines = np.zeros(n), np.zeros(n), np.zeros(n)
    for i, t in enumerate(texts):
        found = [x for x in t.split(b"\n") if x]
        lines[i], line_again[i] = len(found), len(found) - len(set(found))
        short_lines[i] = sum(len(x) < 30 for x in found)
    columns = [
        np.log1p(size), np.log1p(words), *(kinds[:, [1, 2, 3, 4, 5, 7, 8, 9, 10, 11, 12, 0]] / size[:, None]).T, kinds[:, 6] / some,
        mean(length), mean(length**2) - mean(length) ** 2, mean(length <= 2), mean(length >= 14), mean((ups > 1) & (lows == 0)), mean(class_first == 1), mean((class_first == 1) & (lows > 0)),
        mean(class_last == 8), mean(class_last == 9), mean(class_last == 10), mean(class_last == 7), mean((class_last == 7) & (last == 46)), mean(class_first == 3), mean(length == 1),
        mean(again), mean(pair_again), distinct / some, most / some, distinct3 / np.maximum(threes, 1), np.log1p(lines), line_again / np.maximum(lines, 1), short_lines / np.maximum(lines, 1), words / np.maximum(lines, 1),
    ]
    return np.nan_to_num(np.stack(columns, 1))


@dataclass
class Model:
    cuts: np.ndarray  # features x bins
    centre: np.ndarray
    scale: np.ndarray
    weight: np.ndarray
    bias: float
    shift: float
    prior: float

    def expand(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.centre) / self.scale, -6, 6)
        above = (x[:, :, None] > self.cuts[None]).reshape(len(x), -1)
        return np.concatenate((z, above), 1).astype(np.float32)

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self.expand(x) @ self.weight + self.bias

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(x) + self.shift, -30, 30)))


def _softplus(x: np.ndarray) -> np.ndarray:
    return np.logaddexp(0, x)


def fit_nnpu(positive: np.ndarray, unlabelled: np.ndarray, prior: float, l2: float = 1e-3, steps: int | None = None, rate: float = 0.05) -> tuple[np.ndarray, float, list[float]]:
    """Weights and bias that minimise the non-negative risk with the logistic loss, and the risk at each step."""
    k = positive.shape[1]
    steps = steps or int(np.clip(3_000_000 // len(unlabelled), 400, 2000))
    w = np.zeros(k + 1, np.float32)
    p1, u1 = np.column_stack((positive, np.ones(len(positive), np.float32))), np.column_stack((unlabelled, np.ones(len(unlabelled), np.float32)))
    m, v, risks = np.zeros(k + 1), np.zeros(k + 1), []
    sigmoid = lambda x: 1 / (1 + np.exp(-np.clip(x, -30, 30)))
    for t in range(1, steps + 1):
        gp, gu = p1 @ w, u1 @ w
        plus = prior * _softplus(-gp).mean()
        minus = _softplus(gu).mean() - prior * _softplus(gp).mean()
        risks.append(plus + max(0.0, minus))
        d_minus = sigmoid(gu) @ u1 / len(u1) - prior * sigmoid(gp) @ p1 / len(p1)
        g = -prior * sigmoid(-gp) @ p1 / len(p1) + d_minus if minus >= 0 else -d_minus
        g = g + l2 * np.append(w[:-1], 0)
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w = (w - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
    return w[:-1], float(w[-1]), risks


def estimate_prior(positive: np.ndarray, unlabelled: np.ndarray, deviation: float = 1.0) -> float:
    """Share of positives among the unlabelled, from scores: the least ratio of the shares above a threshold, with its deviation."""
    cuts = np.unique(np.quantile(positive, np.linspace(0, 0.95, 96)))
    a = np.array([(unlabelled >= c).mean() for c in cuts])
    b = np.array([(positive >= c).mean() for c in cuts])
    slack = deviation * (np.sqrt(np.log(20) / (2 * len(unlabelled))) + np.sqrt(np.log(20) / (2 * len(positive))))
    best = np.argmin((a + slack) / np.maximum(b, 1e-9))
    return float(np.clip(a[best] / max(b[best], 1e-9), 0.02, 0.98))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", folds: int = 4, held_out: int = 2, train_rows: int = 6000) -> Model | None:
    """A model from trusted positives (at most `train_rows` labelled rows of label 1 outside the held-out fold) and unlabelled texts
    (at most `train_rows` documents outside it, whatever label they may have). No label but 1 is read.

    None if there is no trusted positive with a text.
    """
    trusted = bounded_sample(labels.filter(F.col(label_col) == 1), label_col, folds, held_out, train_rows, id_col).select("id", F.lit(True).alias("positive"), F.lit(False).alias("web"))
    web = bounded_sample(docs.select(id_col, F.lit(0).alias("none")), "none", folds, held_out, train_rows, id_col).select("id", F.lit(False).alias("positive"), F.lit(True).alias("web"))
    chosen = trusted.unionByName(web).groupBy("id").agg(F.max("positive").alias("positive"), F.max("web").alias("web"))
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).join(F.broadcast(chosen), "id")

    def numbers(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slice_batches(batches, "text", 4 << 20):
            yield pa.record_batch({"id": part.column("id").cast(pa.string()), "positive": part.column("positive"), "web": part.column("web"), "x": pa.array([r.tobytes() for r in features(texts)], pa.binary())})

    got = sorted(rows.mapInArrow(tidy_map(numbers), "id string, positive boolean, web boolean, x binary").collect(), key=lambda r: (r["id"], r["x"]))
    if not any(r["positive"] for r in got):
        return None
    x = np.stack([np.frombuffer(r["x"]) for r in got])
    is_positive, is_web = np.array([r["positive"] for r in got]), np.array([r["web"] for r in got])
    base = x[is_web] if is_web.any() else x
    low, high = base.min(0), base.max(0)
    cuts = np.concatenate((np.quantile(base, np.linspace(0.02, 0.98, BINS), axis=0), [low + (high - low) / 12, low + (high - low) / 3]), 0).T
    model = Model(cuts, base.mean(0), base.std(0) + 1e-9, np.zeros(0), 0.0, 0.0, 0.5)
    positive, unlabelled = model.expand(x[is_positive]), model.expand(base)
    # half of the positives fit, half are told apart for the prior
    w, b, _ = fit_nnpu(positive[::2], unlabelled, 0.5, steps=100)
    apart = positive[1::2] if len(positive) > 1 else positive
    model.prior = estimate_prior(apart @ w + b, unlabelled @ w + b)
    model.weight, model.bias, _ = fit_nnpu(positive, unlabelled, model.prior)
    model.shift = _shift(positive @ model.weight + model.bias)
    return model


def _shift(positive: np.ndarray, at: float = 0.7, lost: float = 0.002) -> float:
    """What brings the margin's zero - where the fitted risk is indifferent - to a score of `at`; or a lower margin, if more than a share of `lost` of the trusted positives lies below zero."""
    return float(np.log(at / (1 - at)) - min(0.0, np.quantile(positive, lost)))


def score(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score) of every row: higher for likelier quality 1. Null texts score as empty ones; repeated rows score alike; without a model all score 0.5."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slice_batches(batches, "text", 1 << 20):
            s = sent.value.score(features(texts)) if sent.value else np.full(len(texts), 0.5)
            yield pa.record_batch([part.column("id"), pa.array(s, pa.float64())], ["id", "score"])

    return docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).mapInArrow(tidy_map(each), f"id {docs.schema[id_col].dataType.simpleString()}, score double")
