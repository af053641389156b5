"""Toxicity by non-negative positive-unlabelled learning.

The classifier sees confirmed toxic examples and unlabelled text only. Its risk estimate corrects the unlabelled part by the share of toxic text (the class prior): prior * loss of positives as positive
+ max(0, loss of unlabelled as negative - prior * loss of positives as negative); when the bracket turns negative, its
gradient step is undone instead. The prior is a number that the method takes as known: the production query takes the
share of toxic rows among the labelled ones, the only use it makes of labels that say "not toxic". Where no such share is
known, `class_prior` estimates one from positives and unlabelled text alone (it errs to the high side on few examples).

Features are stems: whole words and word beginnings of several lengths, hashed. The stems that tell positives from
unlabelled text best are kept; a text's values are the logarithm of a stem's count and its share of the words.

Bounds of the fit, all parameters: POSITIVES and UNLABELLED rows (those of the smallest hash), STEMS kept: the width of
the model (README: what other widths give). Stems are counted over all rows of the fit, and every document is scored on
its whole text.

Defined cases: null and empty texts have no stems and get the score of that; null labels or ids teach nothing; without
positives or unlabelled text the score is the class prior; repeated rows each get their row; stems that tie go by their
hash; an empty table gives an empty result; only doc_id and text are read, so other columns may have any name; memory is
bounded by about 1 MB of text at once, or one text if that is longer.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from placelink.llm import common as c
from placelink.llm.boosting import held_out
from placelink.llm.common import bounded_ids, table
from placelink.operators.storage import forget

POSITIVES, UNLABELLED, STEMS = 3_000, 6_000, 800
#: Lengths in bytes of the word beginnings; 0 is the whole word.
LENGTHS = (0, 5, 6, 7, 8, 9)


def stems(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Stem hashes, the text of each, and the words of each text. Marks at a word's ends are not part of it."""
    data = c.lower_ascii(data)
    starts, ends, of = c.word_spans(data, at)
    letter = (data >= 0x80) | ((data >= ord("a")) & (data <= ord("z")))
    reach = np.concatenate([[0], np.cumsum(letter)])
    words = np.bincount(of, minlength=len(at) - 1)
    place = np.flatnonzero(letter)  # the word's first and last letter
    some = reach[ends] > reach[starts]
    starts, ends, of = starts[some], ends[some], of[some]
    first, last = place[reach[starts]], place[reach[ends] - 1] + 1
    hashes, texts = [], []
    for n in LENGTHS:
        fits = last - first > n
        span = last[fits] if n == 0 else first[fits] + n
        hashes.append(c.mix(c.span_hashes(data, first[fits], span) + np.uint64(n)))
        texts.append(of[fits])
    return np.concatenate(hashes), np.concatenate(texts), words


def _counts(hashes: np.ndarray, texts: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text, index in known (sorted) and count of every known stem of every text."""
    if not len(known) or not len(hashes):
        return (np.zeros(0, np.int64),) * 3
    spot = np.searchsorted(known, hashes)
    spot[spot == len(known)] = 0
    hit = known[spot] == hashes
    cell, count = np.unique(texts[hit].astype(np.int64) * len(known) + spot[hit], return_counts=True)
    return cell // len(known), cell % len(known), count


def _document_frequency(docs: DataFrame, name: str) -> DataFrame:
    """Documents by stem, summed within each batch before it is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, data, at in c.chunks(batch.column("text")):
                hashes, texts, _ = stems(data, at)
                _, once = np.unique(c.mix(hashes + c.mix(texts.astype(np.uint64))), return_index=True)
                stem, n = np.unique(hashes[once], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(stem.view(np.int64)), pa.array(n.astype(np.int64))], names=["stem", "n"])

    return docs.select("text").mapInArrow(run, "stem long, n long").groupBy("stem").agg(F.sum("n").alias(name))


@dataclass
class Model:
    known: np.ndarray
    weight: np.ndarray
    bias: float

    def score(self, data: np.ndarray, at: np.ndarray) -> np.ndarray:
        hashes, texts, words = stems(data, at)
        text, stem, count = _counts(hashes, texts, self.known)
        k = len(self.known)
        margin = self.bias + np.bincount(text, weights=_log(count) * self.weight[stem] + _share(count, words[text]) * self.weight[k + stem], minlength=len(words))
        return 1 / (1 + np.exp(-np.clip(margin, -30, 30)))


def _log(count: np.ndarray) -> np.ndarray:
    return np.log1p(count)


def _share(count: np.ndarray, words: np.ndarray) -> np.ndarray:
    return np.log1p(100 * count / np.maximum(words, 1))


def fit(positive: np.ndarray, unlabelled: np.ndarray, prior: float, rounds: int = 400, rate: float = 0.05, decay: float = 2e-4) -> tuple[np.ndarray, float]:
    """Weights and bias that minimise the non-negative risk estimate (logistic loss, Adam, full batches)."""
    width = positive.shape[1]
    if not len(positive) or not len(unlabelled):
        return np.zeros(width), float(np.log(prior / (1 - prior)))
    w, m, v = np.zeros(width + 1), np.zeros(width + 1), np.zeros(width + 1)
    w[-1] = np.log(prior / (1 - prior))
    positive, unlabelled = positive.astype(np.float32, copy=False), unlabelled.astype(np.float32, copy=False)
    up = lambda x, g: np.append(x.T @ g.astype(np.float32), g.sum()) / len(x)
    for step in range(1, rounds + 1):
        w32 = w[:-1].astype(np.float32)
        fp, fu = positive @ w32 + w[-1], unlabelled @ w32 + w[-1]
        sp, su = 1 / (1 + np.exp(-np.clip(fp, -30, 30))), 1 / (1 + np.exp(-np.clip(fu, -30, 30)))
        rest = np.logaddexp(0, fu).mean() - prior * np.logaddexp(0, fp).mean()
        negative = up(unlabelled, su) - prior * up(positive, sp)
        g = prior * up(positive, sp - 1) + negative if rest >= 0 else -negative
        g[:-1] += decay * w[:-1]
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    return w[:-1], float(w[-1])


def class_prior(positive: np.ndarray, unlabelled: np.ndarray, least: float = 0.3) -> float:
    """The share of positives in the unlabelled rows, from the two samples alone.

    Each half is scored by a classifier of the other. At a threshold that a share p of the positives passes, p * prior of
    the unlabelled rows pass at least, so the prior is their share over p at most; the smallest ratio over the thresholds
    that `least` of the positives or more pass is the estimate (with one row of doubt).
    """
    scores = [np.zeros(len(positive)), np.zeros(len(unlabelled))]
    for half in (0, 1):
        fit_on = [x[np.arange(len(x)) % 2 != half] for x in (positive, unlabelled)]
        if not len(fit_on[0]) or not len(fit_on[1]):
            return 0.5
        w, b = fit(*fit_on, 0.5, rounds=40)
        for s, x in zip(scores, (positive, unlabelled), strict=True):
            s[np.arange(len(x)) % 2 == half] = x[np.arange(len(x)) % 2 == half] @ w + b
    steps = np.sort(scores[0])[: max(1, int(len(positive) * (1 - least)))]
    passed = np.array([[(scores[0] >= t).mean(), ((scores[1] >= t).sum() + 1) / (len(unlabelled) + 1)] for t in steps[:: max(1, len(steps) // 200)]])
    return float(np.clip((passed[:, 1] / passed[:, 0]).min(), 0.001, 0.9))


def learn(docs: DataFrame, labels: DataFrame, may_learn, positives: int = POSITIVES, unlabelled: int = UNLABELLED, keep: int = STEMS, prior: float | None = None) -> Model:
    """labels: doc_id, y. may_learn: a condition on doc_id; rows outside it are neither examples nor unlabelled text."""
    toxic = labels.where(F.col("doc_id").isNotNull() & (F.col("y") == 1)).where(may_learn).select("doc_id").distinct()
    texts = docs.select("doc_id", "text").where(F.col("doc_id").isNotNull())
    confirmed = texts.join(F.broadcast(bounded_ids(toxic, "doc_id", positives)), "doc_id", "left_semi")
    others = texts.join(F.broadcast(bounded_ids(texts.select("doc_id").where(may_learn), "doc_id", unlabelled)), "doc_id", "left_semi")
    confirmed, others = c.stored(confirmed, "toxic-positive"), c.stored(others, "toxic-unlabelled")
    np_, nu = max(confirmed.count(), 1), max(others.count(), 1)
    seen = _document_frequency(confirmed, "tp").where("tp >= 2").join(_document_frequency(others, "tu"), "stem", "left")
    a, b = F.col("tp") / np_, F.coalesce(F.col("tu"), F.lit(0)) / nu
    worth = (a - b) * F.sqrt(F.greatest(a - b, F.lit(0.0)) / (a + b + 1e-9))
    best = seen.select("stem", worth.alias("worth")).orderBy(F.col("worth").desc(), "stem").limit(keep).toPandas()
    known = np.sort(best["stem"].to_numpy(np.int64).view(np.uint64))
    x = [_matrix(d, known) for d in (confirmed, others)]
    forget(confirmed, others)
    weight, bias = fit(x[0], x[1], class_prior(*x) if prior is None else prior)
    return Model(known, weight, bias)


def _matrix(docs: DataFrame, known: np.ndarray) -> np.ndarray:
    """The values of a bounded sample, collected as its non-zero cells."""
    k = len(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, data, at in c.chunks(batch.column("text")):
                hashes, texts, words = stems(data, at)
                text, stem, count = _counts(hashes, texts, known)
                cut = np.searchsorted(text, np.arange(len(words) + 1))
                rows = [(stem[i:j].tolist(), count[i:j].tolist()) for i, j in zip(cut[:-1], cut[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.list_(pa.int64())), pa.array([r[1] for r in rows], pa.list_(pa.int64())), pa.array(words.astype(np.int64))], names=["stem", "n", "words"])

    rows = docs.select("doc_id", "text").orderBy("doc_id", "text").mapInArrow(run, "stem array<long>, n array<long>, words long").toPandas()
    x = np.zeros((len(rows), 2 * k), np.float32)
    for i, (stem, n, words) in enumerate(rows.itertuples(index=False)):
        stem, n = np.asarray(stem, np.int64), np.asarray(n, np.float64)
        x[i, stem], x[i, k + stem] = _log(n), _share(n, np.float64(words))
    return x


def score(docs: DataFrame, model: Model, columns: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The given columns of every document and its score (0 to 1)."""
    return c.scored(docs, model.score, columns)


#: Fixed values of the contract: held-out fold and decision.
FOLDS, HELD_OUT, DECISION = 3, 1, 0.7


def toxicity_model(docs: DataFrame, labels: DataFrame) -> Model:
    may_learn = ~held_out(F.col("doc_id"), FOLDS, HELD_OUT)
    known = labels.select("doc_id", F.col("toxic").cast("int").alias("y"))
    n, toxic = known.where(may_learn & F.col("doc_id").isNotNull() & F.col("y").isNotNull()).agg(F.count("*"), F.coalesce(F.sum("y"), F.lit(0))).first()
    return learn(docs, known, may_learn, prior=float(np.clip((toxic + 0.5) / (n + 1), 0.001, 0.9)))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, toxicity_model(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id"), FOLDS, HELD_OUT).alias("held_out"), "score", (F.col("score") >= DECISION).cast("int").alias("predicted"))
