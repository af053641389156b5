"""Distributed running totals: no key, however hot, has to pass through one task in full."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def running_before(df: DataFrame, keys: list[str], rank: Column, order: list[Column], value: str, out: str, bins: int = 4096) -> DataFrame:
    """Adds `out`: the sum of `value` over the rows of the same keys that come before.

    Rows are ordered by `rank` (0 <= rank < 1), then by `order`. The rank is cut into `bins` ranges; ranges are summed
    first (one row per key and range), and only the rows of one range are ever sorted together. Null keys are a group
    of their own. Rows that tie in everything are alike and may swap.
    """
    bin_col, base = "__bin", "__base"
    binned = df.withColumn(bin_col, F.least(F.lit(bins - 1), F.floor(rank * bins)).cast("int"))
    sums = binned.groupBy(*keys, bin_col).agg(F.sum(value).alias("__sum"))
    before = W.partitionBy(*keys).orderBy(bin_col).rowsBetween(W.unboundedPreceding, -1)
    sums = sums.select(*[F.col(k).alias(f"__{k}") for k in keys], F.col(bin_col).alias("__of"), F.coalesce(F.sum("__sum").over(before), F.lit(0)).alias(base))
    on = F.col(bin_col) == F.col("__of")
    for k in keys:
        on = on & F.col(k).eqNullSafe(F.col(f"__{k}"))
    here = W.partitionBy(*keys, bin_col).orderBy(rank, *order).rowsBetween(W.unboundedPreceding, -1)
    return (
        binned.withColumn("__here", F.coalesce(F.sum(value).over(here), F.lit(0)))
        .join(sums, on)
        .withColumn(out, F.col(base) + F.col("__here"))
        .drop(bin_col, base, "__here", "__of", *[f"__{k}" for k in keys])
    )
