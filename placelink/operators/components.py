"""Connected components by alternating stars: every round links nodes to smaller ones until all point to the least.

The number of rounds grows with the logarithm of a component's size. A hub is reduced to its minimum before it is
shuffled; the minima are stored before they are joined back, so that both sides of the join are plain exchanges, and
Spark's adaptive execution deals a hub's rows over several tasks. Each round is written to the shared folder, and the
round before is deleted.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from placelink.operators.storage import forget, stored


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """links (a, b: any ordered type; nulls and self-links count for nothing) to id, component: the least id reachable.

    Only ids that have a link appear, each once. An empty table gives an empty result.
    """
    e = links.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).distinct()
    e = stored(e, "components")
    mark = None
    while True:
        now = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == mark:
            return e.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(e.select(F.col("b").alias("id"), F.col("b").alias("component"))).distinct()
        mark = now
        both = e.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(e.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = stored(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "components-least")
        large = stored(both.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).distinct(), "components-large")
        low = stored(large.groupBy("a").agg(F.min("b").alias("m")), "components-low")
        small = large.join(low, "a").where("b != m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        done, e = e, stored(small.unionByName(low.select("a", F.col("m").alias("b"))).distinct(), "components")
        forget(done, least, large, low)
