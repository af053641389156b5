"""Where to cut the layers: given, from labels (sweep, early stop) or from the distance between the two classes."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Row
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from placelink.operators.layers import _names, first_levels, layers


def _by_layer(*by: str):
    """Windows over the layers of a curve hold as many rows as there are layers, so one partition is enough for each."""
    return W.partitionBy(*by).orderBy("layer")


def _up_to(*by: str):
    return _by_layer(*by).rowsBetween(W.unboundedPreceding, W.currentRow)


def _every(*by: str):
    return W.partitionBy(*by).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)


#: Vectors that the distances between classes may broadcast (24 bytes each and up).
MOST_BROADCAST = 100_000


def _counts(layered: DataFrame, label: str | None) -> DataFrame:
    if "pairs" in layered.columns:
        return layered.where("layer is not null").groupBy("layer").agg(F.sum("pairs").alias("pairs"), F.sum("positives").alias("positives"))
    return layered.where("layer is not null").groupBy("layer").agg(F.count("*").alias("pairs"), F.sum(F.col(label).cast("bigint")).alias("positives"))


def level_curve(layered: DataFrame, label: str | None = None) -> DataFrame:
    """One row per layer k: counts, precision, recall and F1 of "layers 1 to k are matches", and the layer's hit rate."""
    c = _counts(layered, label)
    c = c.withColumns({"cum_pairs": F.sum("pairs").over(_up_to()), "tp": F.sum("positives").over(_up_to()), "all_pairs": F.sum("pairs").over(_every()), "all_positives": F.sum("positives").over(_every())})
    return c.select(
        "layer", "pairs", "positives", "cum_pairs", "tp", (F.col("cum_pairs") - F.col("tp")).alias("fp"), (F.col("all_positives") - F.col("tp")).alias("fn"),
        (F.col("all_pairs") - F.col("cum_pairs") - F.col("all_positives") + F.col("tp")).alias("tn"),
        F.round(F.col("tp") / F.col("cum_pairs"), 6).alias("precision"),
        F.round(F.coalesce(F.col("tp") / F.nullif("all_positives", F.lit(0)), F.lit(0.0)), 6).alias("recall"),
        (2 * F.col("tp") / (F.col("cum_pairs") + F.col("all_positives"))).alias("f1"),
        F.round(F.col("positives") / F.col("pairs"), 6).alias("hit_rate"),
    )


def cut(layered: DataFrame, k) -> DataFrame:
    """The pairs of layers 1 to k, k given."""
    return layered.where(F.col("layer") <= k)


def classify(pairs: DataFrame, vectors: DataFrame, attrs, k: int) -> DataFrame:
    """pairs with `layer` and `match`."""
    ranked = vectors.select(*_names(attrs), "layer")
    return pairs.join(ranked, _names(attrs), "left").withColumn("match", F.coalesce(F.col("layer") <= k, F.lit(False)))


def sweep_cut(levels: DataFrame) -> DataFrame:
    """One row: the layer of the largest F1, the smallest of equals."""
    best = levels.agg(F.max_by(F.struct("layer", "precision", "recall", "f1"), F.struct("f1", -F.col("layer"))).alias("b"), F.max("layer").alias("layers"))
    return best.select("b.layer", "b.precision", "b.recall", F.round("b.f1", 6).alias("f1"), "layers")


def stop_layer(levels: DataFrame, patience: int = 1) -> DataFrame:
    """One row: the peak before the first `patience` falls of F1 in a row (a plateau goes on), and where that was seen."""
    falls = levels.withColumn("fell", F.col("f1") < F.lag("f1").over(_by_layer()))
    for i in range(1, patience):
        falls = falls.withColumn(f"fell_{i}", F.lag("fell", i).over(_by_layer()))
    again = F.col("fell") if patience == 1 else F.expr(" and ".join(["fell", *(f"coalesce(fell_{i}, false)" for i in range(1, patience))]))
    seen = falls.agg(F.min(F.when(again, F.col("layer"))).alias("drop_at"), F.max("layer").alias("layers"))
    return seen.select("drop_at", F.coalesce(F.col("drop_at") - patience, F.col("layers")).alias("layer"), "layers")


def early_stop_levels(vectors: DataFrame, attrs, patience: int = 1) -> DataFrame:
    """The level curve up to where the early stop ends; recall and F1 count the positives of all vectors."""
    first = first_levels(vectors, attrs, patience)
    c = first.withColumns({"cum_pairs": F.sum("pairs").over(_up_to()), "tp": F.sum("positives").over(_up_to())})
    return c.withColumn("f1", 2 * F.col("tp") / (F.col("cum_pairs") + F.col("all_positives")))


def early_stop_cut(vectors: DataFrame, attrs, patience: int = 1, verify: bool = False) -> Row:
    """Takes layer after layer away until F1 falls. Returns layer, explored, f1 (and f1_loss).

    One job; its curve, a row per explored layer, is read here.
    """
    levels = early_stop_levels(vectors, attrs, patience).select("layer", "f1").orderBy("layer").collect()
    f1 = [r["f1"] for r in levels]
    stopped = len(f1) > patience and all(f1[-i] < f1[-i - 1] for i in range(1, patience + 1))
    k = len(f1) - patience if stopped else len(f1)
    row = {"layer": k or None, "explored": len(f1), "f1": f1[k - 1] if k else 0.0}
    if verify:
        row["f1_loss"] = sweep_cut(level_curve(layers(vectors, attrs))).first()["f1"] - row["f1"]
    return Row(**row)


NORMALIZERS = ("ranked", "explored", "cross", "remaining")
TRIGGERS = ("first_negative", "first_decrease", "negative_after_rise")


def cross_terms(ranked: DataFrame, attrs, metric: str = "euclidean") -> DataFrame:
    """layer, delta: by how much the sum of distances between the classes grows when the cut passes the layer.

    Vectors are broadcast while they are few; every task holds its own vectors against all, weighted by their pairs.
    """
    names = _names(attrs)
    rows = ranked.where("layer is not null").select(*[F.col(n).cast("double").alias(n) for n in names], "layer", F.col("pairs").cast("double").alias("w"))
    n = rows.count()
    if n > MOST_BROADCAST:
        raise ValueError(f"{n} distinct vectors; use metric='sqeuclidean' (closed form), round the similarities, or sample")
    table = rows.toPandas()
    x, layer, w = table[names].to_numpy(), table["layer"].to_numpy(), table["w"].to_numpy()
    shared = rows.sparkSession.sparkContext.broadcast((x, layer, w))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, layer, w = shared.value
        for batch in batches:
            own = np.stack([batch.column(k).to_numpy() for k in names], axis=1)
            of, weight = batch.column("layer").to_numpy(), batch.column("w").to_numpy()
            for i in range(0, len(own), 256):
                d = own[i : i + 256, None, :] - x[None, :, :]
                d = np.abs(d).sum(axis=2) if metric == "manhattan" else (d * d).sum(axis=2)
                d = np.sqrt(d) if metric == "euclidean" else d
                side = np.sign(layer[None, :] - of[i : i + 256, None])  # later: in the other class, earlier: no longer
                delta = weight[i : i + 256] * (d * side * w[None, :]).sum(axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(of[i : i + 256]), pa.array(delta)], names=["layer", "delta"])

    return rows.repartition(max(1, min(200, n // 512)), *names).mapInArrow(run, "layer int, delta double").groupBy("layer").agg(F.sum("delta").alias("delta"))


def sampled(ranked: DataFrame, attrs, share: float) -> DataFrame:
    """A share of every layer's vectors (one at least, those of the smallest hash), their pairs raised to the layer's total.

    Estimates the distances between classes where the vectors are too many to be held against each other.
    """
    of = W.partitionBy("layer")
    rows = ranked.where("layer is not null").withColumns({"__at": F.row_number().over(of.orderBy(F.xxhash64(*_names(attrs)), *_names(attrs))), "__n": F.count("*").over(of), "__pairs": F.sum("pairs").over(of)})
    kept = rows.where(F.col("__at") <= F.ceil(F.col("__n") * share))
    return kept.withColumn("pairs", F.col("pairs") * F.col("__pairs") / F.sum("pairs").over(of)).drop("__at", "__n", "__pairs")


def separation_sums(ranked: DataFrame, attrs, metric: str = "euclidean") -> DataFrame:
    """layer, pairs, total: the sum of distances between layers 1 to k and the rest."""
    per = _counts(ranked, None).select("layer", "pairs")
    if metric != "sqeuclidean":
        return per.join(cross_terms(ranked, attrs, metric), "layer").withColumn("total", F.sum("delta").over(_up_to())).drop("delta")
    # closed form: n2 * sum |p|^2 + n1 * sum |q|^2 - 2 * (sum p) . (sum q)
    names = _names(attrs)
    square = sum((F.col(n) * F.col(n) for n in names), F.lit(0.0))
    sums = ranked.where("layer is not null").groupBy("layer").agg(F.sum("pairs").alias("pairs"), F.sum(F.col("pairs") * square).alias("sq"), *[F.sum(F.col("pairs") * F.col(n)).alias(f"s_{n}") for n in names])
    before = {f"b_{c}": F.sum(c).over(_up_to()) for c in ["pairs", "sq", *(f"s_{n}" for n in names)]}
    after = {f"a_{c}": F.sum(c).over(_every()) - F.sum(c).over(_up_to()) for c in ["pairs", "sq", *(f"s_{n}" for n in names)]}
    sums = sums.withColumns(before | after)
    dot = sum((F.col(f"b_s_{n}") * F.col(f"a_s_{n}") for n in names), F.lit(0.0))
    return sums.select("layer", "pairs", (F.col("a_pairs") * F.col("b_sq") + F.col("b_pairs") * F.col("a_sq") - 2 * dot).alias("total"))


def separation_curve(ranked: DataFrame, attrs, metric: str = "euclidean", normalizer: str = "ranked") -> DataFrame:
    """layer, mu: the distance between the classes, over the number of pairs that the normalizer names."""
    return separation_sums(ranked, attrs, metric).select("layer", mean_distance(normalizer).alias("mu"))


def mean_distance(normalizer: str, by: tuple[str, ...] = ()) -> Column:
    """mu from the columns of separation_sums; `by` keeps several curves of one frame apart."""
    n1 = F.sum("pairs").over(_up_to(*by))
    every = F.sum("pairs").over(_every(*by))
    over = {"ranked": every, "explored": n1, "cross": n1 * (every - n1), "remaining": every - n1}[normalizer]
    return F.coalesce(F.col("total") / F.nullif(over, F.lit(0)), F.lit(0.0))


def derivative(curve: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """layer, mu, dmu: the forward difference (null on the last layer)."""
    return curve.withColumn("dmu", F.lead("mu").over(_by_layer(*by)) - F.col("mu"))


def gauss_smooth(curve: DataFrame, sigma: float = 1.0, window: int = 5, value: str = "dmu", out: str = "dmu_smooth", by: tuple[str, ...] = ()) -> DataFrame:
    """A Gaussian over `window` layers around each, renormalised where layers or values are missing."""
    half = window // 2
    top, bottom = F.lit(0.0), F.lit(0.0)
    for d in range(-half, half + 1):
        v = F.lag(value, -d).over(_by_layer(*by)) if d else F.col(value)
        weight = F.when(v.isNotNull(), math.exp(-d * d / (2 * sigma * sigma))).otherwise(0.0)
        top, bottom = top + weight * F.coalesce(v, F.lit(0.0)), bottom + weight
    return curve.withColumn(out, F.when(F.col(value).isNotNull(), top / F.nullif(bottom, F.lit(0.0))))


def separation_layer(smooth: DataFrame, trigger: str = "first_negative") -> DataFrame:
    """One row: the first layer where the trigger sees the classes grow together again; without any, the last layer."""
    return separation_layers(smooth, (trigger,)).select(F.col(trigger).alias("layer"))


def separation_layers(smooth: DataFrame, triggers: tuple[str, ...] = TRIGGERS, by: tuple[str, ...] = ()) -> DataFrame:
    """One row per curve: `by`, and the layer of every trigger, in a column of its name."""
    d = F.round("dmu_smooth", 9)
    hits = {
        "first_negative": d < 0,
        "first_decrease": d < F.lag(d).over(_by_layer(*by)),
        "negative_after_rise": (d < 0) & (F.max(d).over(_up_to(*by)) > 0),
    }
    if unknown := set(triggers) - set(hits):
        raise ValueError(", ".join(sorted(unknown)))
    hit = smooth.withColumns({f"__{t}": hits[t] for t in triggers})
    return hit.groupBy(*by).agg(*[F.coalesce(F.min(F.when(F.col(f"__{t}"), F.col("layer"))), F.max("layer")).alias(t) for t in triggers])


def separation_cut(ranked: DataFrame, attrs, metric: str = "euclidean", normalizer: str = "ranked", trigger: str = "first_negative", sigma: float = 1.0, window: int = 5) -> DataFrame:
    """One row with the layer of the unsupervised cut."""
    return separation_layer(gauss_smooth(derivative(separation_curve(ranked, attrs, metric, normalizer)), sigma, window), trigger)
