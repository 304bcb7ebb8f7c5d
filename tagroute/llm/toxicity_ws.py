"""Toxicity by weak supervision: lexicon and pattern voters, a generative label model, a linear classifier.

1. Lexicon.  Over a bounded sample of labelled rows, words and word heads (first
   4 to 7 bytes: the same stem takes many endings) are kept whose document
   frequency is much higher in toxic rows.  Entries are dealt out to voters by
   kind and by strength; further voters look at patterns (density of hits, hits
   that repeat, shouting, silence of the whole lexicon).
2. Label model.  A voter says toxic (1), clean (-1) or nothing (0).  The votes of
   the sample, labels unseen, are modelled as two classes with a mean vote for
   each voter and class - its accuracy - and one covariance - the voters'
   correlations - fitted by EM from the majority vote on.  Correlated voters
   share their weight, as the posterior uses the inverse covariance.
3. Classifier.  A logistic model over the lexicon entries and counts is trained
   on the posterior labels, and scores every whole text.

Only the sample is gathered on the driver: at most `train_rows` rows of numbers.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textblocks import WORD_LETTERS, Words, slice_batches, tidy_map

#: Byte lengths of word heads; 0 is the whole word.
HEADS = (0, 4, 5, 6, 7)
_EXTRA = 6


def _entries(w: Words) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(kind, word, hash) for whole words and for each length of head."""
    for kind, size in enumerate(HEADS):
        yield (kind, np.arange(len(w)), w.hash) if not size else (kind, *w.heads(size))


@dataclass
class Lexicon:
    hash: np.ndarray  # sorted
    voter: np.ndarray
    kind: np.ndarray
    n_voters: int

    def hits(self, w: Words, texts: int) -> tuple[np.ndarray, np.ndarray]:
        """(text, entry) of every hit; a word counts for each entry that it meets."""
        text, entry = [], []
        if len(self.hash) and len(w):
            quick = np.zeros(1 << 16, bool)
            quick[(self.hash >> np.uint64(48)).astype(np.int64)] = True
            for kind, word, h in _entries(w):
                maybe = np.flatnonzero(quick[(h >> np.uint64(48)).astype(np.int64)])
                at = np.minimum(np.searchsorted(self.hash, h[maybe]), len(self.hash) - 1)
                ok = (self.hash[at] == h[maybe]) & (self.kind[at] == kind)
                text.append(np.searchsorted(w.first, word[maybe[ok]], side="right") - 1)
                entry.append(at[ok])
        if not text:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        return np.concatenate(text), np.concatenate(entry)


def _shouting(text: bytes) -> float:
    """Upper-case letters over bytes, of the whole text."""
    raw = np.frombuffer(text, np.uint8)
    wide = re.sub(rb"[\x00-\x7f]+", b"", text).decode("utf-8", "ignore") if (raw > 127).any() else ""
    return (int(((raw >= 65) & (raw <= 90)).sum()) + sum(map(str.isupper, wide))) / max(1, len(raw))


def _numbers(lexicon: Lexicon, texts: list[bytes], voting: bool = True) -> tuple[np.ndarray | None, np.ndarray]:
    """Votes of each text (in training alone), and its features: entries present, then counts."""
    w = Words(texts, WORD_LETTERS, lower=True)
    n, k = len(texts), len(lexicon.hash)
    text, entry = lexicon.hits(w, n)
    present = np.zeros((n, k), np.float32)
    present[text, entry] = 1
    words = np.maximum(np.diff(w.first), 1)
    total = np.bincount(text, minlength=n)
    distinct = present.sum(1)
    counts = np.stack([np.log1p(total), np.log1p(distinct), np.minimum(total * 100 / words, 10), (total > 0), (distinct > 1), (distinct > 2)], 1)
    features = np.concatenate([present, counts.astype(np.float32)], 1)
    if not voting:
        return None, features
    by_voter = np.zeros((n, lexicon.n_voters), np.int64)
    np.add.at(by_voter, (text, lexicon.voter[entry]), 1)
    shout = np.array([_shouting(x) for x in texts])
    pattern = np.stack([
        np.where(total * 300 >= words, 1, np.where(total == 0, -1, 0)), np.where(distinct >= 3, 1, np.where(distinct == 0, -1, 0)),
        np.where(total > distinct, 1, 0), np.where(total == 0, -1, 0), np.where(shout > 0.5, -1, 0) * (total == 0), np.where(distinct >= 6, 1, 0),
    ], 1)
    votes = np.concatenate([np.where(by_voter > 0, 1, 0), pattern], 1)
    return votes.astype(np.float64), features


def label_model(votes: np.ndarray, rounds: int = 40) -> tuple[np.ndarray, dict[str, np.ndarray]]:
    """P(toxic) of each row from its votes alone, and what was estimated: mean votes by class and correlations."""
    lexical = votes[:, :-_EXTRA]
    post = np.clip((lexical.sum(1) > 0) * 0.8 + (lexical.sum(1) > 1) * 0.15 + 0.02, 0, 1)
    for _ in range(rounds):
        prior = np.clip(post.mean(), 1e-4, 1 - 1e-4)
        one, zero = post / max(post.sum(), 1e-9), (1 - post) / max((1 - post).sum(), 1e-9)
        m1, m0 = one @ votes, zero @ votes
        a, b = votes - m1, votes - m0
        cov = (a * post[:, None]).T @ a / len(votes) + (b * (1 - post)[:, None]).T @ b / len(votes)
        cov += np.eye(len(cov)) * 0.02
        weight = np.linalg.solve(cov, m1 - m0)
        logit = (votes - (m1 + m0) / 2) @ weight + np.log(prior / (1 - prior))
        new = 1 / (1 + np.exp(-np.clip(logit, -30, 30)))
        done = np.abs(new - post).max() < 1e-6
        post = new
        if done:
            break
    scale = np.sqrt(np.diag(cov))
    return post, {"toxic_votes": m1, "clean_votes": m0, "correlation": cov / np.outer(scale, scale), "weight": weight}


def fit_logistic(x: np.ndarray, y: np.ndarray, l2: float = 1e-3, steps: int = 400, rate: float = 0.05) -> tuple[np.ndarray, float]:
    """Weights and bias for soft labels, by full-batch Adam."""
    w, b = np.zeros(x.shape[1]), 0.0
    m, v = np.zeros(len(w) + 1), np.zeros(len(w) + 1)
    for t in range(1, steps + 1):
        p = 1 / (1 + np.exp(-np.clip(x @ w + b, -30, 30)))
        g = np.append((p - y) @ x / len(y) + l2 * w, (p - y).mean())
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w, b = w - step[:-1], b - step[-1]
    return w, b


def bounded_sample(labels: DataFrame, label_col: str, folds: int, held_out: int, rows: int, id_col: str = "doc_id") -> DataFrame:
    """(id, label) of at most `rows` labelled rows outside the held-out fold, chosen by hash of the id.

    Of many more rows a hash class with about twice as many is taken first, so that no task sorts what all tables' parts hold.
    """
    ok = labels.filter(F.col(label_col).isNotNull() & F.col(id_col).isNotNull() & (F.crc32(F.col(id_col).cast("string")) % folds != held_out))
    ok = ok.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("label"))
    classes = ok.count() // (2 * rows)
    if classes > 1:
        ok = ok.filter(F.pmod(F.xxhash64("id", F.lit(7)), F.lit(classes)) == 0)
    return ok.orderBy(F.xxhash64("id"), "id").limit(rows)


@dataclass
class Model:
    lexicon: Lexicon
    weight: np.ndarray
    bias: float
    learned: dict[str, np.ndarray]

    def score(self, texts: list[bytes]) -> np.ndarray:
        _, x = _numbers(self.lexicon, texts, voting=False)
        return 1 / (1 + np.exp(-np.clip(x @ self.weight + self.bias, -30, 30)))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", folds: int = 5, held_out: int = 0, train_rows: int = 8000, min_rows: int = 3, min_share: float = 0.02, log_odds: float = 3.0, most_clean: float = 2e-4) -> Model:
    """Lexicon, label model and classifier from at most `train_rows` labelled rows. Without such rows, nothing is ever toxic.

    An entry of the lexicon occurs in `min_rows` toxic rows and a share of `min_share` of them, in a
    share of `most_clean` of the clean rows at most, and has log odds of `log_odds` or more.
    All such entries count: as each takes a share of the toxic rows, there are at most
    1 / `min_share` times as many as a toxic row has entries, whatever the size of the corpus.
    """
    sample = bounded_sample(labels, label_col, folds, held_out, train_rows)
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text")).join(F.broadcast(sample), "id")

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """(kind, hash, toxic, clean): documents that hold an entry."""
        for part, texts in slice_batches(batches, "text", 4 << 20):
            w = Words(texts, WORD_LETTERS, lower=True)
            label = np.array(part.column("label").to_pylist())
            for kind, word, h in _entries(w):
                text = np.searchsorted(w.first, word, side="right") - 1
                order = np.lexsort((text, h))
                h, text = h[order], text[order]
                fresh = np.concatenate((np.ones(min(1, len(h)), bool), (h[1:] != h[:-1]) | (text[1:] != text[:-1])))
                h, y = h[fresh], label[text[fresh]]
                key, of = np.unique(h, return_inverse=True)
                toxic = np.bincount(of, y, len(key)).astype(np.int64)
                total = np.bincount(of, minlength=len(key))
                yield pa.record_batch({"kind": pa.array(np.full(len(key), kind), pa.int32()), "h": pa.array(key.view(np.int64)), "toxic": pa.array(toxic), "clean": pa.array(total - toxic)})

    sizes = {r[0]: r[1] for r in sample.groupBy("label").count().collect()}
    n1, n0 = sizes.get(1, 0), sizes.get(0, 0)
    odds = F.log((F.col("toxic") + 0.5) / (n1 + 1.0)) - F.log((F.col("clean") + 0.5) / (n0 + 1.0))
    found = (
        rows.mapInArrow(tidy_map(count), "kind int, h long, toxic long, clean long").groupBy("kind", "h").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))
        .filter(F.col("toxic") >= max(min_rows, min_share * n1)).withColumn("odds", odds).filter((F.col("odds") >= log_odds) & (F.col("clean") <= most_clean * n0))
        .orderBy(F.desc(F.col("toxic") * F.col("odds")), "h", "kind").collect()
    )
    n_voters = 24
    kinds = np.array([r["kind"] for r in found], np.int64)
    h = np.array([r["h"] for r in found], np.int64).view(np.uint64)
    # entries of like strength share a voter, so that the label model can tell weak ones: whole words first, then heads
    strength = np.array([r["odds"] for r in found])
    voter = np.zeros(len(found), np.int64)
    for whole, base, count_ in ((True, 0, 12), (False, 12, 12)):
        mine = np.flatnonzero((kinds == 0) == whole)
        voter[mine[np.argsort(-strength[mine], kind="stable")]] = base + np.arange(len(mine)) * count_ // max(1, len(mine))
    order = np.argsort(h, kind="stable")
    lexicon = Lexicon(h[order], voter[order], kinds[order], n_voters)
    sent = docs.sparkSession.sparkContext.broadcast(lexicon)

    def numbers(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slice_batches(batches, "text", 4 << 20):
            votes, x = _numbers(sent.value, texts)
            yield pa.record_batch({"id": part.column("id").cast(pa.string()), "votes": pa.array([v.astype(np.int8).tobytes() for v in votes], pa.binary()), "present": pa.array([np.flatnonzero(r[: len(lexicon.hash)]).astype(np.int32).tobytes() for r in x], pa.binary()), "counts": pa.array([r[len(lexicon.hash) :].tobytes() for r in x], pa.binary())})

    got = sorted(rows.select("id", "text").mapInArrow(tidy_map(numbers), "id string, votes binary, present binary, counts binary").collect(), key=lambda r: r[0])
    if not got or not len(h):
        return Model(lexicon, np.zeros(len(h) + 6), -30.0, {})
    votes = np.stack([np.frombuffer(r["votes"], np.int8) for r in got]).astype(np.float64)
    x = np.zeros((len(got), len(h) + 6))
    for i, r in enumerate(got):
        x[i, np.frombuffer(r["present"], np.int32)] = 1
        x[i, len(h) :] = np.frombuffer(r["counts"], np.float32)
    post, learned = label_model(votes)
    return Model(lexicon, *fit_logistic(x, post), learned)


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", keep: bool = False) -> DataFrame:
    """(id, score) of every row, or with `keep` the rows' own columns and toxic_score (ValueError if they have that, or _text, already). Null and empty texts score as texts without any hit; repeated rows score alike."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    if keep:
        if {"_text", "toxic_score"} & set(docs.columns):
            raise ValueError("columns _text and toxic_score are the operator's own")
        rows, schema = docs.withColumn("_text", text), ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields) + ", toxic_score double"
    else:
        rows, schema = docs.select(F.col(id_col).alias("id"), text.alias("_text")), f"id {docs.schema[id_col].dataType.simpleString()}, score double"

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in slice_batches(batches, "_text", 2 << 20):
            s = pa.array(sent.value.score(texts), pa.float64())
            kept = [n for n in part.schema.names if n != "_text"]
            yield pa.record_batch([*(part.column(n) for n in kept), s], [*kept, "toxic_score" if keep else "score"])

    return rows.mapInArrow(tidy_map(each), schema)
