"""Joins of rows with a table of one row per key, where a key may hold any share of the rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Keys that are dealt over several tasks are at most so many, whatever the input; a key with fewer rows than LEAST never is.
MOST_HOT, LEAST = 20_000, 1_000


def hot_limit(total: int) -> int:
    """Rows from which a key counts as hot: fewer than MOST_HOT keys of `total` rows can have as many."""
    return max(LEAST, total // MOST_HOT + 1)


def join_counted(rows: DataFrame, per: DataFrame, keys: list[str], total: int, how: str = "inner", n: str = "n") -> DataFrame:
    """rows joined with `per`, which has one row per key and in column `n` how many of the `total` rows have that key.

    Rows of a hot key are dealt over as many shares as keep each below hot_limit(total), by their content and the task
    they come from; the row of `per` is repeated for every share. Only hot keys and their numbers of shares are broadcast,
    MOST_HOT at most. how: "inner" or "left_semi"; null keys match nothing. The count does not come along.
    """
    if total < LEAST:
        return rows.join(per.drop(n), keys, how)
    shares = F.ceil(F.col(n) / hot_limit(total)).cast("int")
    hot = per.where(F.col(n) >= hot_limit(total)).select(*keys, shares.alias("__shares"))
    at = F.pmod(F.xxhash64(*rows.columns, F.spark_partition_id()), F.coalesce("__shares", F.lit(1))).cast("int")
    dealt = rows.join(F.broadcast(hot), keys, "left").withColumn("__share", at).drop("__shares")
    repeated = per.withColumn("__share", F.explode(F.sequence(F.lit(0), F.greatest(shares, F.lit(1)) - 1))).drop(n)
    return dealt.join(repeated, [*keys, "__share"], how).drop("__share")
