"""Score-based linkage baselines: additive, weighted top-k, belief. Pairs carry name_sim, address_sim, address_text, semantic_sim, dist_m."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from placelink.functions.similarity import geo_sim, rounded
from placelink.operators.metrics import confusion_columns, prf

#: The thresholds of the flexible sweep.
THRESHOLDS = tuple(round(0.5 + 0.05 * i, 2) for i in range(11))
ADDITIVE = {"A": ("name_sim", "address_text", "geo_sim"), "B": ("name_sim", "geo_sim")}


def additive_score(which: str, scale: float = 100.0) -> Column:
    parts = [geo_sim(F.col("dist_m"), scale) if c == "geo_sim" else F.col(c) for c in ADDITIVE[which]]
    total = parts[0]
    for p in parts[1:]:
        total = total + p
    return rounded(total / len(parts))


def additive(pairs: DataFrame, which: str, threshold: float = 0.75, scale: float = 100.0) -> DataFrame:
    return pairs.withColumn("score", additive_score(which, scale)).withColumn("match", F.col("score") >= threshold)


def additive_sweep(pairs: DataFrame, which: str, thresholds: tuple[float, ...] = THRESHOLDS, scale: float = 100.0) -> DataFrame:
    """Counts and measures at every threshold, in one pass over the pairs."""
    scored = pairs.select(additive_score(which, scale).alias("score"), "label")
    cells = [F.struct(F.lit(float(t)).alias("threshold"), *confusion_columns(F.col("score") >= float(t), F.col("label"))).alias(f"t{i}") for i, t in enumerate(thresholds)]
    row = scored.agg(*cells)
    each = row.select(F.explode(F.array(*[f"t{i}" for i in range(len(thresholds))])).alias("c")).select("c.*")
    return prf(each)


def best_threshold(sweep: DataFrame) -> DataFrame:
    return sweep.orderBy(F.col("f1").desc(), "threshold").limit(1)


def with_category(pairs: DataFrame, table: DataFrame, value: str = "resnik", out: str = "category_sim") -> DataFrame:
    """Pairs (keywords_a, keywords_b) with the best value of a table of term pairs (term_a <= term_b, value); 0 without one.

    Only the distinct pairs of keyword lists are looked up: far fewer than pairs.
    """
    lists = pairs.select(F.col("keywords_a").alias("__ka"), F.col("keywords_b").alias("__kb")).distinct()
    terms = lists.withColumn("__x", F.explode("__ka")).withColumn("__y", F.explode("__kb"))
    terms = terms.withColumns({"term_a": F.least("__x", "__y"), "term_b": F.greatest("__x", "__y")}).join(table, ["term_a", "term_b"])
    best = terms.groupBy("__ka", "__kb").agg(F.max(value).alias("__best"))
    found = pairs.join(best, (F.col("keywords_a") == F.col("__ka")) & (F.col("keywords_b") == F.col("__kb")), "left")
    return found.withColumn(out, F.coalesce("__best", F.lit(0.0))).drop("__ka", "__kb", "__best")


def weighted_scores(pairs: DataFrame, scale: float = 100.0) -> DataFrame:
    """Pairs with a common keyword or name token; two thirds for name, category and place, one third for the address.

    Name and address are compared by edits, the category by information content, the place by distance. Needs name_a,
    name_b, keywords_a, keywords_b and category_sim (with_category).
    """
    shared = F.arrays_overlap(F.split(F.lower("name_a"), " "), F.split(F.lower("name_b"), " ")) | F.arrays_overlap("keywords_a", "keywords_b")
    score = rounded((F.col("name_sim") + F.col("category_sim") + geo_sim(F.col("dist_m"), scale)) * (2 / 9) + F.col("address_text") * (1 / 3))
    return pairs.where(shared).withColumn("score", score)


def with_ranks(scored: DataFrame) -> DataFrame:
    """One row per pair of ids: `best`, the better of its two ranks among the pairs of its places (ties by the other id),

    and of how many rows (n) and positives it consists, as ids may repeat.
    """
    ends = F.explode(F.array(F.struct(F.col("eid_a").alias("side"), F.col("eid_b").alias("other")), F.struct(F.col("eid_b").alias("side"), F.col("eid_a").alias("other"))))
    ends = scored.select("eid_a", "eid_b", "score", "label", ends.alias("e")).select("eid_a", "eid_b", "score", "label", "e.side", "e.other")
    ranked = ends.withColumn("rank", F.row_number().over(W.partitionBy("side").orderBy(F.col("score").desc(), "other")))
    twice = lambda c: (c / 2).cast("bigint")
    return ranked.groupBy("eid_a", "eid_b").agg(F.min("rank").alias("best"), twice(F.count("*")).alias("n"), twice(F.sum(F.col("label").cast("bigint"))).alias("positives"))


def weighted_topk(pairs: DataFrame, k: int, scale: float = 100.0) -> DataFrame:
    """All pairs with `match`: among the k best of either place."""
    kept = with_ranks(weighted_scores(pairs, scale)).where(F.col("best") <= k).select("eid_a", "eid_b", F.lit(True).alias("kept"))
    return pairs.join(kept, ["eid_a", "eid_b"], "left").withColumn("match", F.coalesce("kept", F.lit(False))).drop("kept")


def weighted_topk_sweep(pairs: DataFrame, scale: float = 100.0) -> DataFrame:
    """Counts and measures for every k up to the largest number of pairs of a place."""
    total = pairs.agg(F.coalesce(F.sum(F.col("label").cast("bigint")), F.lit(0)).alias("all_positives"), F.count("*").alias("all_pairs"))
    per = with_ranks(weighted_scores(pairs, scale)).groupBy(F.col("best").alias("k")).agg(F.sum("n").alias("n"), F.sum("positives").alias("p"))
    up = W.orderBy("k").rowsBetween(W.unboundedPreceding, W.currentRow)  # a row per k
    c = per.select("k", F.sum("n").over(up).alias("n"), F.sum("p").over(up).alias("tp")).join(F.broadcast(total))
    c = c.select("k", "tp", (F.col("n") - F.col("tp")).alias("fp"), (F.col("all_positives") - F.col("tp")).alias("fn"), (F.col("all_pairs") - F.col("n") - F.col("all_positives") + F.col("tp")).alias("tn"))
    return prf(c)


#: How much each kind of evidence is trusted (the masses are not published: a choice).
RELIABILITY = {"name_sim": 0.8, "geo_sim": 0.4, "semantic_sim": 0.4}


def combine(a: tuple[Column, Column, Column], b: tuple[Column, Column, Column]) -> tuple[Column, Column, Column]:
    """Two bodies of evidence (for, against, undecided) into one, without their conflict."""
    conflict = a[0] * b[1] + a[1] * b[0]
    rest = F.greatest(1 - conflict, F.lit(1e-12))
    return (a[0] * b[0] + a[0] * b[2] + a[2] * b[0]) / rest, (a[1] * b[1] + a[1] * b[2] + a[2] * b[1]) / rest, a[2] * b[2] / rest


def belief(pairs: DataFrame, radius: float = 5.0, reliability: dict[str, float] | None = None) -> DataFrame:
    """Places at most `radius` apart match if the evidence for outweighs that against."""
    trust = reliability or RELIABILITY
    bodies = []
    for name, alpha in trust.items():
        s = geo_sim(F.col("dist_m"), radius) if name == "geo_sim" else F.col(name)
        bodies.append((s * alpha, (1 - s) * alpha, F.lit(1 - alpha)))
    total = bodies[0]
    for b in bodies[1:]:
        total = combine(total, b)
    near = F.col("dist_m") <= radius
    return pairs.withColumns({"belief": F.when(near, rounded(total[0])).otherwise(0.0), "disbelief": F.when(near, rounded(total[1])).otherwise(1.0)}).withColumn("match", F.col("belief") > F.col("disbelief"))
