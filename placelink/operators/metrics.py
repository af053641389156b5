"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from placelink.sources.tables import dataset_bytes, noop


def confusion_columns(match: Column, label: Column, weight: Column | None = None) -> list[Column]:
    w = weight if weight is not None else F.lit(1)
    cell = lambda c: F.coalesce(F.sum(F.when(c, w)), F.lit(0)).cast("bigint")
    return [cell(match & (label == 1)).alias("tp"), cell(match & (label == 0)).alias("fp"), cell(~match & (label == 1)).alias("fn"), cell(~match & (label == 0)).alias("tn")]


def confusion(pairs: DataFrame, label: str = "label", match: str = "match", by: tuple[str, ...] = ()) -> DataFrame:
    """tp, fp, fn, tn over the compared pairs (what blocking lost is not counted)."""
    return pairs.groupBy(*by).agg(*confusion_columns(F.col(match), F.col(label)))


def prf(counts: DataFrame) -> DataFrame:
    """precision, recall, f1 beside the counts; a zero denominator gives 0."""
    ratio = lambda a, b: F.round(F.coalesce(a / F.nullif(b, F.lit(0)), F.lit(0.0)), 6)
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return counts.withColumns({"precision": ratio(tp, tp + fp), "recall": ratio(tp, tp + fn), "f1": ratio(2 * tp, 2 * tp + fp + fn)})


def positive_share(pairs: DataFrame, label: str = "label") -> DataFrame:
    return pairs.agg(F.count("*").alias("pairs"), F.round(F.avg(label), 6).alias("positive_share"))


def blocking_recall(pairs: DataFrame, places: DataFrame) -> DataFrame:
    """Positives among the candidate pairs over all true pairs, counted per truth id without making them."""
    n = F.col("n")
    true = places.groupBy("truth_id").agg(F.count("*").alias("n")).agg(F.sum((n * (n - 1) / 2).cast("bigint")).alias("true_pairs"))
    return pairs.agg(F.coalesce(F.sum("label"), F.lit(0)).cast("bigint").alias("found")).join(F.broadcast(true)).withColumn("recall", F.round(F.col("found") / F.col("true_pairs"), 6))


def source_profile(places: DataFrame, positives: DataFrame) -> DataFrame:
    """Places and places with a match, by source."""
    matched = positives.select(F.col("eid_a").alias("eid")).unionByName(positives.select(F.col("eid_b").alias("eid"))).distinct().withColumn("has", F.lit(1))
    return places.join(matched, "eid", "left").groupBy("source").agg(F.count("*").alias("places"), F.count("has").alias("matched"))


def links_by_source(positives: DataFrame) -> DataFrame:
    """Links by (unordered) pair of sources."""
    return positives.groupBy(F.least("source_a", "source_b").alias("source_1"), F.greatest("source_a", "source_b").alias("source_2")).agg(F.count("*").alias("links"))


def dataset_size(df: DataFrame) -> int:
    """Bytes of the files behind a DataFrame."""
    return dataset_bytes(df)


def timeit(make: Callable[[], DataFrame]) -> float:
    """Seconds to run a plan without keeping its rows."""
    began = time.perf_counter()
    noop(make())
    return time.perf_counter() - began


def scaling(make: Callable[[int], DataFrame], sizes: tuple[int, ...]) -> list[tuple[int, float]]:
    """Seconds by size; the slope of their logarithms is the empirical order."""
    return [(n, timeit(lambda n=n: make(n))) for n in sizes]
