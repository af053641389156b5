"""Blocking by quadtrees, with children that overlap or not.

Without a density limit all leaves lie on one level, so a place's leaves follow from arithmetic: one pass, no tree. With
a density limit (or a capacity) only cells that are still too full are split again, level by level.

A place belongs to a child if it lies in the child's box, enlarged on every side by `margin` times the parent's extent
(0 to 0.25; 0 is the plain tree); borders are closed. The boxes nest, so the rule has this closed form on every level.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from placelink.operators.storage import stored


@dataclass(frozen=True)
class Root:
    """The root's box in metres."""

    x0: float
    y0: float
    x1: float
    y1: float

    @property
    def diagonal(self) -> float:
        return math.hypot(self.x1 - self.x0, self.y1 - self.y0)

    def cell_diagonal(self, level: int) -> float:
        return self.diagonal / 2**level

    def sides(self, level: int) -> tuple[float, float]:
        return (self.x1 - self.x0) / 2**level, (self.y1 - self.y0) / 2**level

    def level(self, m: float, rule: str = "diagonal", max_level: int = 24) -> int:
        """The first level whose diagonal is at most m, or the deepest whose sides are all at least m ("cover")."""
        level = 0
        if rule == "diagonal":
            while self.cell_diagonal(level) > m and level < max_level:
                level += 1
        elif rule == "cover":
            while min(s for s in self.sides(level + 1) if s >= 0) >= m and level < max_level:
                level += 1
        else:
            raise ValueError(rule)
        return level


def root_box(places: DataFrame, root: str | Root = "bbox") -> Root:
    """The bounding box ("bbox"), the square around it ("square"), or a given one; one row reaches the driver."""
    if isinstance(root, Root):
        return root
    r = places.agg(F.min("x_m"), F.min("y_m"), F.max("x_m"), F.max("y_m")).first()
    x0, y0, x1, y1 = (float(v or 0) for v in r)
    if root == "square":
        half, cx, cy = max(x1 - x0, y1 - y0) / 2, (x0 + x1) / 2, (y0 + y1) / 2
        return Root(cx - half, cy - half, cx + half, cy + half)
    return Root(x0, y0, x1, y1)


def expected_depth(root: Root, c: float) -> float:
    """Levels until the diagonal is c: a half-split divides it by 2 per level."""
    return max(0.0, math.log2(root.diagonal / c)) + 1


def _range(v: Column, low: float, side: float, cells: int, margin: float) -> tuple[Column, Column]:
    """First and last index of the cells whose enlarged range holds v. `margin` is a share of the parent, so twice that of the cell."""
    if cells == 1 or side == 0:
        return F.lit(0).cast("bigint"), F.lit(0).cast("bigint")
    at = (v - F.lit(low)) / F.lit(side)
    home = F.least(F.floor(at), F.lit(cells - 1))
    if margin == 0:
        return home, home
    first = F.greatest(F.ceil(at - F.lit(1 + 2 * margin)), F.lit(0))
    last = F.least(F.floor(at + F.lit(2 * margin)), F.lit(cells - 1))
    return first.cast("bigint"), last.cast("bigint")


def home_cell(root: Root, level: int) -> tuple[Column, Column]:
    w, h = root.sides(level)
    ix, _ = _range(F.col("x_m"), root.x0, w, 2**level, 0)
    iy, _ = _range(F.col("y_m"), root.y0, h, 2**level, 0)
    return ix.cast("bigint"), iy.cast("bigint")


def assign_cells(places: DataFrame, root: Root, level: int, margin: float) -> DataFrame:
    """places with level, ix, iy (exploded), is_home, and low_ix, low_iy: the least of the place's cells on this level."""
    w, h = root.sides(level)
    fx, lx = _range(F.col("x_m"), root.x0, w, 2**level, margin)
    fy, ly = _range(F.col("y_m"), root.y0, h, 2**level, margin)
    hx, hy = home_cell(root, level)
    out = places.withColumns({"level": F.lit(level), "low_ix": fx, "low_iy": fy, "ix": F.explode(F.sequence(fx, lx))})
    out = out.withColumn("iy", F.explode(F.sequence(F.col("low_iy"), ly)))
    return out.withColumn("is_home", (F.col("ix") == hx) & (F.col("iy") == hy))


def overlap_blocks(
    places: DataFrame, m: float | None, density: float | None = None, margin: float = 0.25, root: str | Root = "bbox", mode: str = "bounded",
    level_rule: str = "diagonal", max_level: int = 24, density_basis: str = "assigned",
) -> DataFrame:
    """Blocks of places (eid, x_m, y_m, anything more): rows with level, ix, iy, is_home, low_ix, low_iy.

    m: longest diagonal (None: density alone). density: most places per 1000 square metres of a cell's own box, counted
    over all assigned places or over those physically inside. low_ix and low_iy are null where leaves differ in level.
    mode "half_plane" is the unbounded reading of the overlap: with a tree of ten levels, some forty rows per place.
    """
    box = root_box(places, root)
    if mode == "half_plane":
        return _half_plane(places, box, m, max_level)
    level = 0 if m is None else box.level(m, level_rule, max_level)
    if density is None:
        return assign_cells(places, box, level, margin)

    def full(cell: DataFrame, at: int) -> DataFrame:
        w, h = box.sides(at)
        count = F.count("*") if density_basis == "assigned" else F.count_if("is_home")
        return cell.groupBy("level", "ix", "iy").agg(count.alias("n")).where(F.col("n") > density * w * h / 1000)

    return _refine(places, box, level, margin, max_level, full)


def quadtree_blocks(places: DataFrame, m: float | None, density: float | None = None, **more) -> DataFrame:
    """The plain tree: every place has one leaf."""
    return overlap_blocks(places, m, density, margin=0.0, **more)


def capacity_quadtree(places: DataFrame, capacity: int, max_level: int = 24, root: str | Root = "bbox") -> DataFrame:
    """The classical tree: a cell splits when it holds more than `capacity` places."""
    full = lambda cell, at: cell.groupBy("level", "ix", "iy").agg(F.count("*").alias("n")).where(F.col("n") > capacity)
    return _refine(places, root_box(places, root), 0, 0.0, max_level, full)


def _refine(places: DataFrame, box: Root, level: int, margin: float, max_level: int, full) -> DataFrame:
    """Splits cells while `full` says so. Coincident places never get apart: max_level ends that."""
    cell = stored(assign_cells(places, box, level, margin), "blocks")
    leaves = []
    key = ["ix", "iy"]
    while True:
        split = stored(full(cell, level).select(*key), "full-cells") if level < max_level else None
        if split is None or split.isEmpty():
            leaves.append(cell)
            break
        leaves.append(cell.join(split, key, "left_anti"))
        inside = cell.join(split, key, "left_semi").withColumnRenamed("ix", "px").withColumnRenamed("iy", "py").drop("level", "is_home", "low_ix", "low_iy")
        level += 1
        finer = assign_cells(inside, box, level, margin)
        cell = stored(finer.where((F.floor(F.col("ix") / 2) == F.col("px")) & (F.floor(F.col("iy") / 2) == F.col("py"))).drop("px", "py"), "blocks")
    out = leaves[0]
    for more in leaves[1:]:
        out = out.unionByName(more)
    return out.withColumns({"low_ix": F.lit(None).cast("bigint"), "low_iy": F.lit(None).cast("bigint")}) if len(leaves) > 1 else out


def density_blocks(places: DataFrame, m: float, densities: tuple[float, ...], margin: float = 0.25, max_level: int = 24, root: str | Root = "bbox") -> DataFrame:
    """The trees of several density limits (ascending) in one: blocks of the last and loosest one, and `codes`.

    Boxes nest, so what a cell holds does not depend on the limit, and every stricter tree splits the leaves of a looser
    one. A cell is a leaf for the limits from the first it respects to the last that none of its ancestors respects.
    codes: all cells in which a place is in a leaf of some tree; two places share a leaf from the limit first_shared on.
    """
    box = root_box(places, root)
    level, key, leaves = box.level(m, "diagonal", max_level), ["ix", "iy"], []
    cell = assign_cells(places.select("eid", "x_m", "y_m"), box, level, margin).select("eid", "x_m", "y_m", *key, F.lit(len(densities) - 1).alias("last"))
    while True:
        w, h = box.sides(level)
        full = [(F.col("n") > d * w * h / 1000).cast("int") for d in densities] if level < max_level else []
        counts = cell.groupBy(*key).agg(F.count("*").alias("n")).select(*key, sum(full, F.lit(0)).alias("first"))
        cell = stored(cell.join(counts, key), "blocks")
        leaves.append(cell.where("first <= last").withColumn("level", F.lit(level)))
        inside = cell.where("first > 0")
        if level >= max_level or inside.isEmpty():
            break
        level += 1
        inside = inside.select("eid", "x_m", "y_m", F.col("ix").alias("px"), F.col("iy").alias("py"), F.least("last", F.col("first") - 1).alias("last"))
        finer = assign_cells(inside, box, level, margin).where((F.floor(F.col("ix") / 2) == F.col("px")) & (F.floor(F.col("iy") / 2) == F.col("py")))
        cell = finer.select("eid", "x_m", "y_m", *key, "last")
    out = leaves[0]
    for more in leaves[1:]:
        out = out.unionByName(more)
    # the first limit above, then level and indices: 24 levels have 2**24 cells a side
    code = F.shiftleft(F.col("first").cast("bigint"), 55) + F.shiftleft(F.col("level").cast("bigint"), 50) + F.shiftleft("ix", 25) + F.col("iy")
    loosest = F.when(F.col("last") == len(densities) - 1, F.struct("level", "ix", "iy"))
    own = out.groupBy("eid", "x_m", "y_m").agg(F.collect_set(code).alias("codes"), F.collect_set(loosest).alias("__leaves"))
    blocks = places.join(own, ["eid", "x_m", "y_m"]).withColumn("__leaf", F.explode("__leaves")).select("*", "__leaf.*").drop("__leaf", "__leaves")
    none = F.lit(None).cast("bigint")
    return blocks.withColumns({"low_ix": none, "low_iy": none})


def first_shared(a: Column, b: Column) -> Column:
    """The number of the first limit of density_blocks under which two places share a leaf, from their codes."""
    return F.shiftright(F.array_min(F.array_intersect(a, b)), 55).cast("int")


def _half_plane(places: DataFrame, box: Root, m: float, max_level: int) -> DataFrame:
    """A place goes to every child on whose side of the lines at a quarter and three quarters of the node it lies.

    Both axes decide alone, so a place's cells are all combinations of its columns and rows, which follow from its own
    coordinates in one pass; of each there are little more than half as many as the tree has levels.
    """
    level = box.level(m, "diagonal", max_level)

    @F.arrow_udf("array<bigint>")
    def held(v: pa.Array, low: pa.Array, size: pa.Array) -> pa.Array:
        """The indices of the last level that hold each value, ascending."""
        x, side = v.to_numpy(zero_copy_only=False), size[0].as_py() if len(size) else 0.0
        row = np.flatnonzero(v.is_valid().to_numpy(zero_copy_only=False))
        i, x0 = np.zeros(len(row), np.int64), low[0].as_py() if len(low) else 0.0
        for _ in range(level):
            side = side / 2  # of the children
            p = x0 + i * 2 * side
            left, right = x[row] <= p + 1.5 * side, ~(x[row] < p + 0.5 * side)
            row, i = np.repeat(row, 2), np.stack([2 * i, 2 * i + 1], axis=1).ravel()
            kept = np.stack([left, right], axis=1).ravel()
            row, i = row[kept], i[kept]
        ends = np.r_[0, np.cumsum(np.bincount(row, minlength=len(x)))].astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(ends), pa.array(i))

    w, h = box.sides(0)
    axis = lambda c, low, size: held(F.col(c).cast("double"), F.lit(low), F.lit(size)) if level else F.array(F.lit(0).cast("bigint"))
    hx, hy = home_cell(box, level)
    none = F.lit(None).cast("bigint")
    out = places.withColumns({"__xs": axis("x_m", box.x0, w), "__ys": axis("y_m", box.y0, h)})
    out = out.withColumn("ix", F.explode("__xs")).withColumn("iy", F.explode("__ys")).drop("__xs", "__ys")
    return out.withColumns({"level": F.lit(level), "is_home": (F.col("ix") == hx) & (F.col("iy") == hy), "low_ix": none, "low_iy": none})
