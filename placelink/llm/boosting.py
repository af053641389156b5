"""Quality classifier: histogram gradient-boosted trees over document statistics, traversed as flat arrays in numpy.

Statistics come from whole texts, a block of texts at once. The trees are fitted on the driver to at most
`FIT_ROWS` labelled rows (those of the smallest hash: a documented bound); every document is scored.

Defined cases: null and empty texts have zero statistics and a score like any other; rows whose label or id is null
teach nothing; with no labelled rows, or of one class only, the score is the smoothed share of label 1; repeated rows
each get their row, and all texts of a labelled id are learned from; the larger label counts where an id has several;
splits that tie go to the first statistic and the lowest threshold; an empty table gives an empty result; only doc_id
and text are read, so other columns may have any name; memory is bounded by about 1 MB of text at once, or one text if
that is longer.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from placelink.llm import common as c
from placelink.llm.common import bounded_ids, table
from placelink.llm.repetition import Words

#: The most labelled rows that a fit reads.
FIT_ROWS = 20_000


def _class(chars: str) -> np.ndarray:
    flags = np.zeros(256, bool)
    flags[[ord(x) for x in chars]] = True
    return flags


_CLASSES = {
    "symbols": _class("#*$%&<>"), "pipes": _class("|"), "upper": _class("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), "lower": _class("abcdefghijklmnopqrstuvwxyz"),
    "digits": _class("0123456789"), "calls": _class("!?"), "stops": _class("."), "commas": _class(",;:"), "brackets": _class("()[]{}=_/\\@+-"), "breaks": _class("\n"),
    "wide": np.arange(256) >= 0xC0,
}
FEATURES = ["log_words", "word_length", "long_words", "distinct", "top_word", "repeat_2", "repeat_5", "dup_lines", "dup_line_chars", "words_a_line", *_CLASSES]


def statistics(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """One row of FEATURES per text."""
    w = Words(data, at)
    n, size = np.maximum(w.n_words, 1), np.maximum(at[1:] - at[:-1], 1)
    chars = np.maximum(w.sum(w.chars), 1)
    _, keys = w.windows(1)
    _, first = np.unique(keys, return_index=True)
    distinct = np.bincount(w.of[first], minlength=w.texts)
    lines, line_chars = w.lines()
    breaks = c.per_text(_CLASSES["breaks"][data], at)
    columns = [
        np.log1p(w.n_words), chars / n, w.sum(w.chars > 12) / n, distinct / n, w.most_frequent(1) / chars, w.sum(w.covered(2)) / n, w.sum(w.covered(5)) / n,
        lines / (breaks + 1), line_chars / size, w.n_words / (breaks + 1), *[c.per_text(flags[data], at) / size for flags in _CLASSES.values()],
    ]
    return np.stack(columns, axis=1).astype(np.float64)


@dataclass
class Trees:
    """Complete binary trees as arrays: feature and threshold by tree and inner node, value by tree and leaf."""

    feature: np.ndarray
    threshold: np.ndarray
    value: np.ndarray
    start: float

    def score(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.start)
        rows = np.arange(len(x))
        inner = self.feature.shape[1]
        for feature, threshold, value in zip(self.feature, self.threshold, self.value, strict=True):
            node = np.zeros(len(x), np.int64)
            while len(x) and node[0] < inner:  # all rows are on one level
                node = 2 * node + 1 + (x[rows, feature[node]] > threshold[node])
            total += value[node - inner]
        return 1 / (1 + np.exp(-np.clip(total, -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, bins: int = 64, rate: float = 0.15, penalty: float = 1.0, least: float = 5.0) -> Trees:
    """Boosts trees on the logistic loss; splits are sought in histograms of the binned columns, all nodes of a level at once."""
    inner, leaves = 2**depth - 1, 2**depth
    share = (y.sum() + 1) / (len(y) + 2)
    start = float(np.log(share / (1 - share)))
    if len(y) == 0 or y.min() == y.max():
        return Trees(np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, leaves)), start)
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(x.shape[1])]
    binned = np.stack([np.searchsorted(e, x[:, f], side="left") for f, e in enumerate(edges)], axis=1)
    margin, built = np.full(len(y), start), []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        g, h = p - y, p * (1 - p)
        feature, threshold = np.zeros(inner, np.int64), np.full(inner, np.inf)
        node = np.zeros(len(y), np.int64)
        for level in range(depth):
            base, width = 2**level - 1, 2**level
            best = np.full(width, 1e-9)
            where = node - base
            for f, e in enumerate(edges):
                if not len(e):
                    continue
                key = where * bins + binned[:, f]
                sums = [np.bincount(key, weights=v, minlength=width * bins).reshape(width, bins).cumsum(axis=1) for v in (g, h)]
                (gl, hl), (gt, ht) = sums, [s[:, -1:] for s in sums]
                gain = gl**2 / (hl + penalty) + (gt - gl) ** 2 / (ht - hl + penalty) - gt**2 / (ht + penalty)
                gain[(hl < least / 10) | (ht - hl < least / 10)] = 0
                gain = gain[:, : len(e)]
                cut = gain.argmax(axis=1)
                top = gain[np.arange(width), cut]
                better = top > best
                best[better] = top[better]
                feature[base : base + width][better] = f
                threshold[base : base + width][better] = e[cut[better]]
            node = 2 * node + 1 + (x[np.arange(len(y)), feature[node]] > threshold[node])
        leaf = node - inner
        value = -rate * np.bincount(leaf, weights=g, minlength=leaves) / (np.bincount(leaf, weights=h, minlength=leaves) + penalty)
        margin += value[leaf]
        built.append((feature, threshold, value))
    return Trees(*(np.stack(part) for part in zip(*built, strict=True)), start)


def _features(docs: DataFrame) -> DataFrame:
    """doc_id and the statistics (array) of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, at in c.chunks(batch.column("text")):
                x = statistics(data, at)
                values = pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), x.shape[1]).cast(pa.list_(pa.float64()))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i).cast(pa.int64()), values], names=["doc_id", "x"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, x array<double>")


def learn(docs: DataFrame, labels: DataFrame, bound: int = FIT_ROWS) -> Trees:
    """labels: doc_id, y (0 or 1), only those that may be learned from. Rows with the same id and other texts all count."""
    known = labels.where("doc_id is not null and y is not null").groupBy("doc_id").agg(F.max("y").alias("y"))
    known = bounded_ids(known, "doc_id", bound)
    texts = docs.select("doc_id", "text").join(F.broadcast(known.select("doc_id")), "doc_id", "left_semi")  # at most `bound` ids
    rows = _features(texts).join(F.broadcast(known), "doc_id").orderBy("doc_id", "x").select("x", "y").toPandas()
    x = np.stack(rows["x"].to_numpy()) if len(rows) else np.zeros((0, len(FEATURES)))
    return fit(x, rows["y"].to_numpy(np.float64))


def score(docs: DataFrame, model: Trees, columns: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The given columns of every document and its score (0 to 1)."""
    return c.scored(docs, lambda data, at: model.score(statistics(data, at)), columns)


#: Fixed values of the contract: held-out fold and decision.
FOLDS, HELD_OUT, DECISION = 5, 0, 0.3


def held_out(doc_id: Column, folds: int = FOLDS, fold: int = HELD_OUT) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % folds == fold, F.lit(False))


def quality_model(docs: DataFrame, labels: DataFrame) -> Trees:
    return learn(docs, labels.where(~held_out(F.col("doc_id"))).select("doc_id", F.col("quality").cast("int").alias("y")))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, quality_model(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= DECISION).cast("int").alias("predicted"))
