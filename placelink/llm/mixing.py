"""Mixing sources to target weights by Pareto order sampling.

Every source has a target in words. Whole copies that the target covers are certain; what is left of it is met by a
sample without replacement: a document's rank is its random odds divided by the odds of its inclusion probability
(remaining share of the source times the document's preference), and the lowest ranks win until the words are met.

Defined cases: null sources are one source, ordered last; null and empty texts have size 0 and are never taken; repeated
rows are rows of their own, and of rows that tie in odds, id and size any may come first, as they are alike; a very long
text is one size like any other; an empty table gives an empty result; clashing column names do not matter, as only id,
source and size are read. The sources' own totals, one row each, pass through one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from placelink.llm.common import n_words, share_of, stored, table
from placelink.operators.running import running_before

#: Fixed values of the production mix: weights repeat over the ordered sources, no source is taken more than 3 times.
WEIGHTS, MAX_COPIES = (1, 2, 3), 3
#: Ranges of the logarithm of the odds, over 128 units of it.
BINS = 128 * 1024


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MAX_COPIES) -> DataFrame:
    """One row per source: source, source_size, target (double), words (long, the target in whole words).

    Targets share the total by weight and stop at `most` times the source's size; what is cut is shared again by weight.
    The sources that stop are the first ones in order of size over weight, so one ordered pass finds them all.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    place = W.orderBy(F.col("source").asc_nulls_last())  # one row per source only
    per = per.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), ((F.row_number().over(place) - 1) % len(weights) + 1).cast("int")).cast("long"))
    order = W.orderBy((F.col("source_size") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    earlier = order.rowsBetween(W.unboundedPreceding, -1)
    whole = W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing).partitionBy()
    per = per.withColumns({
        "left": F.sum("source_size").over(whole) - most * F.coalesce(F.sum("source_size").over(earlier), F.lit(0)),
        "weights": F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(earlier), F.lit(0)),
    })
    per = per.withColumn("stops", most * F.col("source_size") * F.col("weights") <= F.col("left") * F.col("weight"))
    free = F.coalesce(F.max(F.when(~F.col("stops"), F.struct(F.col("weights"), F.col("left")))).over(whole), F.struct(F.lit(1).cast("long").alias("weights"), F.lit(0).cast("long").alias("left")))
    per = per.withColumn("free", free)
    target = F.when(F.col("stops"), (most * F.col("source_size")).cast("double")).otherwise(F.col("free.left") * F.col("weight") / F.col("free.weights"))
    return per.withColumn("target", target).select("source", "source_size", "target", F.floor(F.col("target") + 0.5).cast("long").alias("words"))


def preference_by_size(size: Column) -> Column:
    """The production preference, in [0.5, 1.5): documents of more words are a little likelier."""
    return size / (size + F.lit(100.0)) + F.lit(0.5)


def mix(sizes: DataFrame, targets: DataFrame, preference: Column | None = None, salt: str = "mix:", cut: bool = True, ties: tuple[str, ...] = ()) -> DataFrame:
    """sizes (doc_id, source, size, more) with source_size, target, copies (whole ones), part (further words), taken.

    cut=True ends a source exactly at its target, inside its last document; cut=False takes that document whole if more
    than half of it fits (part is then 0 or the size). No document exceeds the copies of its source by more than one. Rows
    of equal odds, id and size are taken in the order of the columns `ties`.
    """
    t = targets.select(F.col("source").alias("__source"), "source_size", "target", "words")
    d = sizes.join(t, F.col("source").eqNullSafe(F.col("__source"))).drop("__source")
    d = d.withColumn("copies", F.when(F.col("source_size") > 0, F.floor(F.col("words") / F.greatest(F.col("source_size"), F.lit(1)))).otherwise(0).cast("long"))
    d = d.withColumn("rest", F.col("words") - F.col("copies") * F.col("source_size"))
    like = F.col("rest") / F.greatest(F.col("source_size"), F.lit(1)) * (preference if preference is not None else F.lit(1.0))
    like = F.least(F.greatest(like, F.lit(1e-9)), F.lit(1 - 1e-9))
    u = F.col("u")
    d = d.withColumn("u", share_of(F.col("doc_id"), salt))
    d = d.withColumn("odds", u / (1 - u) / (like / (1 - like)))
    # logarithms of random odds have a density of 1/4 at most, so no range of 1/1024 holds more than 0.025 % of a source,
    # whatever its target and its documents' preferences
    rank = (F.log(F.greatest("odds", F.lit(1e-25))) + 64) / 128
    d = running_before(d, ["source"], rank, [F.col("odds"), F.col("doc_id"), F.col("size"), *map(F.col, ties)], "size", "before", BINS)
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("rest") - F.col("before")))
    if not cut:
        part = F.when(2 * part > F.col("size"), F.col("size")).otherwise(F.lit(0))
    d = d.withColumn("part", part.cast("long"))
    return d.withColumn("taken", F.col("copies") * F.col("size") + F.col("part")).drop("u", "odds", "before", "rest", "words")


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    sizes = stored(docs.select("doc_id", "source", n_words(F.col("text")).alias("size")), "mix-sizes")
    return mix(sizes, source_targets(sizes), preference_by_size(F.col("size"))).select("doc_id", "size", "source_size", "target", "taken", "copies", "part")


OP3_SQL = r"""
WITH sizes AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents),
per AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sizes GROUP BY source),
weighed AS (SELECT *, CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS BIGINT) AS weight FROM per),
ranked AS (
  SELECT *, sum(source_size) OVER () - 3 * coalesce(sum(source_size) OVER o, 0) AS rest_words,
         sum(weight) OVER () - coalesce(sum(weight) OVER o, 0) AS rest_weights
  FROM weighed WINDOW o AS (ORDER BY source_size / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
judged AS (SELECT *, 3 * source_size * rest_weights <= rest_words * weight AS stops FROM ranked),
free AS (SELECT rest_words AS w, rest_weights AS g FROM judged WHERE NOT stops ORDER BY rest_weights DESC LIMIT 1),
targets AS (
  SELECT source, source_size, CASE WHEN stops THEN CAST(3 * source_size AS DOUBLE)
    ELSE CAST((SELECT w FROM free) * weight AS DOUBLE) / CAST((SELECT g FROM free) AS DOUBLE) END AS target FROM judged),
wanted AS (
  SELECT d.doc_id, d.source, d.size, t.source_size, t.target, CAST(floor(t.target + 0.5) AS BIGINT) AS words
  FROM sizes d JOIN targets t ON d.source IS NOT DISTINCT FROM t.source),
copied AS (SELECT *, CASE WHEN source_size > 0 THEN words // greatest(source_size, 1) ELSE 0 END AS copies FROM wanted),
odds AS (
  SELECT *, words - copies * source_size AS rest,
    CAST(('0x' || substr(md5('mix:' || CAST(doc_id AS VARCHAR)), 1, 13)) AS BIGINT) / 4503599627370496.0::DOUBLE AS u,
    least(greatest(CAST(words - copies * source_size AS DOUBLE) / CAST(greatest(source_size, 1) AS DOUBLE)
      * (CAST(size AS DOUBLE) / (CAST(size AS DOUBLE) + 100.0::DOUBLE) + 0.5::DOUBLE), 1e-9::DOUBLE), (1 - 1e-9::DOUBLE)) AS p
  FROM copied),
ordered AS (
  SELECT *, coalesce(sum(size) OVER (PARTITION BY source ORDER BY u / (1 - u) / (p / (1 - p)), doc_id, size
    ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM odds),
parts AS (SELECT *, CAST(greatest(0, least(size, rest - before)) AS BIGINT) AS part FROM ordered)
SELECT doc_id, size, source_size, target, CAST(copies * size + part AS BIGINT) AS taken, CAST(copies AS BIGINT) AS copies, part FROM parts
"""
