"""Taxonomies: paths from the root, Wu-Palmer and Resnik tables. A term with several parents has several paths."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from placelink.functions.similarity import wup

#: Terms whose pairs a table may hold; larger vocabularies compare the paths that ride with the places.
MOST_TERMS = 5_000


def term_paths(taxonomy: DataFrame, max_depth: int = 32, view: str = "taxonomy_edges") -> DataFrame:
    """term, path (array from the root) by a recursive query; one row per path."""
    taxonomy.createOrReplaceTempView(view)
    return taxonomy.sparkSession.sql(f"""
      with recursive walk(term, path) max recursion level {max_depth} as (
        select term, array(term) from {view} where parent is null
        union all
        select e.term, concat(w.path, array(e.term)) from walk w join {view} e on e.parent = w.term)
      select term, path from walk""")


def paths_by_term(taxonomy: DataFrame) -> DataFrame:
    """term, paths (array of paths)."""
    return term_paths(taxonomy).groupBy("term").agg(F.sort_array(F.collect_list("path")).alias("paths"))


def with_paths(places: DataFrame, taxonomy: DataFrame, column: str = "keywords", out: str = "paths") -> DataFrame:
    """Places with the paths of all their keywords, so that pairs need no lookup; unknown keywords have none."""
    known = paths_by_term(taxonomy)
    lists = places.select(F.col(column).alias("__list")).distinct()  # far fewer than places
    words = lists.select("__list", F.explode("__list").alias("term")).join(known, "term")
    own = words.groupBy("__list").agg(F.array_distinct(F.flatten(F.sort_array(F.collect_list("paths")))).alias(out))
    return places.join(own, F.col(column) == F.col("__list"), "left").drop("__list")


def _term_pairs(paths: DataFrame) -> DataFrame:
    if paths.select("term").distinct().count() > MOST_TERMS:
        raise ValueError(f"more than {MOST_TERMS} terms; compare paths on the pairs instead (with_paths)")
    return paths.select(F.col("term").alias("term_a"), F.col("path").alias("path_a")).join(paths.select(F.col("term").alias("term_b"), F.col("path").alias("path_b")), F.col("term_a") <= F.col("term_b"))


def wup_table(taxonomy: DataFrame) -> DataFrame:
    """term_a <= term_b, wup: the best over all paths."""
    pairs = _term_pairs(term_paths(taxonomy))
    return pairs.groupBy("term_a", "term_b").agg(F.round(F.max(wup(F.col("path_a"), F.col("path_b"))), 6).alias("wup"))


def resnik_table(taxonomy: DataFrame, frequency: DataFrame) -> DataFrame:
    """term_a <= term_b, resnik in [0, 1]: information of the most telling common ancestor, over the largest of all."""
    paths = term_paths(taxonomy)
    above = paths.select("term", F.explode("path").alias("ancestor")).distinct()
    counts = above.join(frequency, "term").groupBy("ancestor").agg(F.sum("n").alias("n"))
    total = frequency.agg(F.sum("n").alias("total"))
    info = counts.join(F.broadcast(total)).select("ancestor", (-F.log(F.col("n") / F.col("total"))).alias("ic"))
    a, b = above.select(F.col("term").alias("term_a"), "ancestor"), above.select(F.col("term").alias("term_b"), "ancestor")
    used = frequency.select("term")
    a, b = a.join(used.withColumnRenamed("term", "term_a"), "term_a", "left_semi"), b.join(used.withColumnRenamed("term", "term_b"), "term_b", "left_semi")
    best = a.join(b, "ancestor").where("term_a <= term_b").join(info, "ancestor").groupBy("term_a", "term_b").agg(F.max("ic").alias("ic"))
    top = best.agg(F.max("ic").alias("top"))
    return best.join(F.broadcast(top)).select("term_a", "term_b", F.round(F.coalesce(F.col("ic") / F.nullif("top", F.lit(0.0)), F.lit(0.0)) + 0.0, 6).alias("resnik"))


