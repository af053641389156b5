"""SQL names for the library's functions: expressions that the optimizer inlines, and one table function."""

from __future__ import annotations

import math

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

#: name -> (parameters, return type, body); plain SQL, so that the optimizer sees through.
FUNCTIONS = {
    "text_sim": ("a string, b string", "double", "case when a is null or b is null then 0.0d when greatest(length(a), length(b)) = 0 then 1.0d else 1 - levenshtein(a, b) / greatest(length(a), length(b)) end"),
    "address_sim": ("a string, b string", "double", "case when a is null or b is null then 0.0d when a = b then 1.0d when a != '' and b != '' and (contains(a, b) or contains(b, a)) then 0.9d else 0.0d end"),
    "geo_sim": ("distance double, scale double", "double", "greatest(0.0d, 1 - distance / scale)"),
    "wup": ("shared int, depth_a int, depth_b int", "double", "2.0d * shared / (depth_a + depth_b)"),
    "euclid_m": ("xa double, ya double, xb double, yb double", "double", "sqrt((xa - xb) * (xa - xb) + (ya - yb) * (ya - yb))"),
}


def register(spark: SparkSession) -> list[str]:
    """Makes the functions and the table function `overlap_cells` known to SQL; returns their names."""
    for name, (parameters, returns, body) in FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}({parameters}) returns {returns} return {body}")
    spark.udtf.register("overlap_cells", OverlapCells)
    return [*FUNCTIONS, "overlap_cells"]


@udtf(returnType="level int, ix bigint, iy bigint")
class OverlapCells:
    """overlap_cells(x, y, x0, y0, x1, y1, level): the leaves of a point in the overlapping quadtree."""

    def eval(self, x: float, y: float, x0: float, y0: float, x1: float, y1: float, level: int):
        n = 2**level
        ranges = []
        for v, low, high in ((x, x0, x1), (y, y0, y1)):
            at = (v - low) / ((high - low) / n) if high > low else 0.5
            ranges.append(range(max(0, math.ceil(at - 1.5)), min(n - 1, math.floor(at + 0.5)) + 1))
        for ix in ranges[0]:
            for iy in ranges[1]:
                yield level, ix, iy
