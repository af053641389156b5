"""Pareto layers of similarity vectors.

Layers rank distinct vectors, not pairs, so pairs are collapsed first; a vector's layer is one more than the deepest
layer among those that dominate it. Equal vectors share a layer. Pairs with a null similarity cannot be compared: they
are left out of the ranking and have a null layer.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from placelink.operators.storage import stored

#: Distinct vectors that one ranking task takes; more are an error: quantise the similarities or ask for the first layers only.
MOST_VECTORS = 2_000_000


@dataclass(frozen=True)
class Attribute:
    """A similarity column; direction "low" when small values speak for a match."""

    name: str
    direction: str = "high"

    def value(self) -> Column:
        return F.col(self.name) if self.direction == "high" else -F.col(self.name)


def _names(attrs) -> list[str]:
    return [a.name if isinstance(a, Attribute) else a for a in attrs]


def _attributes(attrs) -> list[Attribute]:
    return [a if isinstance(a, Attribute) else Attribute(a) for a in attrs]


def dominates(attrs, a: str = "a", b: str = "b") -> Column:
    """Whether row alias a is at least as good everywhere and better somewhere than row alias b."""
    as_good, better = F.lit(True), F.lit(False)
    for x in _attributes(attrs):
        p, q = F.col(f"{a}.{x.name}"), F.col(f"{b}.{x.name}")
        p, q = (p, q) if x.direction == "high" else (-p, -q)
        as_good, better = as_good & (p >= q), better | (p > q)
    return as_good & better


def collapse(pairs: DataFrame, attrs, label: str | None = None, round_to: int | None = None) -> DataFrame:
    """Distinct vectors with their number of pairs and of positives."""
    names = _names(attrs)
    if round_to is not None:
        pairs = pairs.withColumns({n: F.round(n, round_to) for n in names})
    positives = F.sum(F.col(label).cast("bigint")) if label else F.lit(0).cast("bigint")
    return pairs.groupBy(*names).agg(F.count("*").alias("pairs"), F.coalesce(positives, F.lit(0)).cast("bigint").alias("positives"))


def layer_numbers(x: np.ndarray) -> np.ndarray:
    """The layer of every row of x (larger is better). Rows are taken in descending order, so that dominators come first."""
    n, width = x.shape
    out = np.zeros(n, np.int32)
    if not n:
        return out
    order = np.lexsort([-x[:, k] for k in reversed(range(width))])
    if width == 1:
        values = x[order, 0]
        out[order] = np.r_[1, 1 + np.cumsum(values[1:] != values[:-1])]
        return out
    if width == 2:
        # the best second value of every layer falls with the layer, so the first layer below it is found by bisection
        best: list[float] = []  # negated: ascending
        import bisect

        last, last_layer = None, 0
        for i in order:
            row = (x[i, 0], x[i, 1])
            if row != last:
                k = bisect.bisect_right(best, -row[1])
                if k == len(best):
                    best.append(-row[1])
                else:
                    best[k] = min(best[k], -row[1])
                last, last_layer = row, k + 1
            out[i] = last_layer
        return out
    members = [np.empty((16, width - 1))]  # per layer; the first value is at least as good by the order
    sizes = [0]
    last, last_layer = None, 0
    for i in order:
        row = x[i]
        if last is None or (row != last).any():
            low, high = 0, len(members)
            while low < high:  # what is dominated in one layer is dominated in all before
                mid = (low + high) // 2
                if sizes[mid] and (members[mid][: sizes[mid]] >= row[1:]).all(axis=1).any():
                    low = mid + 1
                else:
                    high = mid
            if low == len(members):
                members.append(np.empty((16, width - 1)))
                sizes.append(0)
            if sizes[low] == len(members[low]):
                members[low] = np.concatenate([members[low], np.empty_like(members[low])])
            members[low][sizes[low]] = row[1:]
            sizes[low] += 1
            last, last_layer = row, low + 1
        out[i] = last_layer
    return out


def fronts(x: np.ndarray, step: int = 512) -> Iterator[np.ndarray]:
    """The rows of one layer after the other, each found when it is asked for (rows differ; larger is better)."""
    rest = np.lexsort([-x[:, k] for k in reversed(range(x.shape[1]))]) if len(x) else np.zeros(0, np.int64)
    while len(rest):
        front, beaten = np.empty((0, x.shape[1])), np.zeros(len(rest), bool)
        for i in range(0, len(rest), step):  # dominators come first in this order
            some = x[rest[i : i + step]]
            lost = np.zeros(len(some), bool)
            for j in range(0, len(front), step):
                lost |= (front[None, j : j + step] >= some[:, None]).all(axis=2).any(axis=1)
            left = np.flatnonzero(~lost)
            better = (some[left][None] >= some[left][:, None]).all(axis=2)
            np.fill_diagonal(better, False)
            lost[left[better.any(axis=1)]] = True
            front = np.concatenate([front, some[~lost]])
            beaten[i : i + step] = lost
        yield rest[~beaten]
        rest = rest[beaten]


def _whole(batches: Iterator[pa.RecordBatch]) -> pa.Table | None:
    """What one ranking task gets; more than MOST_VECTORS are refused before they fill its memory."""
    found, n = [], 0
    for b in batches:
        found.append(b)
        n += b.num_rows
        if n > MOST_VECTORS:
            raise ValueError(f"more than {MOST_VECTORS} distinct vectors in one ranking task; round the similarities or ask for the first layers")
    return pa.Table.from_batches(found).combine_chunks() if found else None


def _ranked(names: list[str], signs: list[int], most: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = _whole(batches)
        if t is None:
            return
        x = np.stack([s * t.column(n).to_numpy() for n, s in zip(names, signs, strict=True)], axis=1)
        layer = layer_numbers(x)
        keep = np.ones(len(layer), bool) if most is None else layer <= most
        t = t.select(names).append_column("layer", pa.array(layer)).filter(pa.array(keep))
        yield from t.to_batches()

    return run


def first_levels(vectors: DataFrame, attrs, patience: int = 1) -> DataFrame:
    """layer, pairs, positives of the first layers, up to the `patience`-th fall of F1 in a row, and all_positives.

    vectors: attributes, pairs, positives. One task takes layer after layer away and stops; deeper ones are never formed.
    """
    a = _attributes(attrs)
    names, signs = [x.name for x in a], [1 if x.direction == "high" else -1 for x in a]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = _whole(batches)
        if t is None:
            return
        x = np.stack([s * t.column(n).to_numpy() for n, s in zip(names, signs, strict=True)], axis=1)
        pairs, positives = t.column("pairs").to_numpy(), t.column("positives").to_numpy()
        total, seen, hits, best, falls, out = int(positives.sum()), 0, 0, -1.0, 0, []
        for k, rows in enumerate(fronts(x), 1):
            out.append((k, int(pairs[rows].sum()), int(positives[rows].sum()), total))
            seen, hits = seen + out[-1][1], hits + out[-1][2]
            f1 = 2 * hits / (seen + total)
            falls = falls + 1 if f1 < best else 0
            best = f1
            if falls >= patience:
                break
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in out], pa.int32()), *[pa.array([r[i] for r in out], pa.int64()) for i in (1, 2, 3)]], names=["layer", "pairs", "positives", "all_positives"])

    known = " and ".join(f"{n} is not null" for n in names)
    rows = vectors.where(known).select(*[F.col(n).cast("double").alias(n) for n in names], F.col("pairs").cast("bigint"), F.col("positives").cast("bigint"))
    return rows.coalesce(1).mapInArrow(run, "layer int, pairs bigint, positives bigint, all_positives bigint")


def layers(df: DataFrame, attrs, max_layer: int | None = None, join: bool = True) -> DataFrame:
    """df (pairs or vectors) with `layer`; with max_layer, rows of deeper layers are left out.

    One task ranks the distinct vectors (MOST_VECTORS at most) in a sorted pass. With max_layer, every partition first drops what is deeper
    already among its own vectors (a layer within a part is never deeper than in the whole).
    """
    a = _attributes(attrs)
    names, signs = [x.name for x in a], [1 if x.direction == "high" else -1 for x in a]
    known = " and ".join(f"{n} is not null" for n in names)
    vectors = df.where(known).select(*[F.col(n).cast("double").alias(n) for n in names]).distinct()
    schema = ", ".join([*(f"{n} double" for n in names), "layer int"])
    if max_layer is not None:
        vectors = prune_above(vectors, attrs, max_layer)
    ranked = vectors.coalesce(1).mapInArrow(_ranked(names, signs, max_layer), schema)
    if not join:
        return ranked
    return df.join(ranked, names, "inner" if max_layer is not None else "left")


def prune_above(vectors: DataFrame, attrs, k: int) -> DataFrame:
    """Vectors without those that k others of their own partition dominate one after the other."""
    a = _attributes(attrs)
    names, signs = [x.name for x in a], [1 if x.direction == "high" else -1 for x in a]
    schema = ", ".join([*(f"{n} double" for n in names), "layer int"])
    return vectors.select(*names).mapInArrow(_ranked(names, signs, k), schema).drop("layer")


def lattice_prefilter(vectors: DataFrame, attrs, bins: int = 16) -> DataFrame:
    """Vectors that can lie in the first layer: those whose cell no other cell beats in every coordinate."""
    a = _attributes(attrs)
    cell = {f"__{x.name}": F.floor(x.value() * bins) for x in a}
    binned = vectors.withColumns(cell)
    cells = binned.select(*cell).distinct()
    p, q = cells.alias("p"), cells.alias("q")
    beaten = F.lit(True)
    for c in cell:
        beaten = beaten & (F.col(f"q.{c}") > F.col(f"p.{c}"))
    return binned.join(p.join(q, beaten, "left_anti"), list(cell), "left_semi").drop(*cell)


def layers_peel(df: DataFrame, attrs, max_layer: int | None = None) -> DataFrame:
    """The reference form: take the front away again and again. For tests and few layers."""
    names = _names(attrs)
    rest, out, k = stored(df.select(*names).distinct(), "peel"), None, 0
    while not rest.isEmpty() and (max_layer is None or k < max_layer):
        k += 1
        front = stored(rest.alias("b").join(rest.alias("a"), dominates(attrs), "left_anti").withColumn("layer", F.lit(k)), "front")
        out = front if out is None else out.unionByName(front)
        rest = stored(rest.join(front, names, "left_anti"), "peel")
    if out is None:
        out = rest.withColumn("layer", F.lit(0))
    return df.join(out, names)


def layers_sql(df: DataFrame, attrs, view: str = "vectors_to_rank") -> DataFrame:
    """The SQL form: a vector lies one layer below the deepest of those that dominate it, relaxed until nothing moves.

    Spark's recursive queries only add rows (UNION ALL), which would walk every chain of dominance, so the rounds are
    statements of their own. One round per layer: for small data.
    """
    names = _names(attrs)
    spark = df.sparkSession
    rows = stored(df.select(*names).distinct().withColumn("id", F.row_number().over(W.orderBy(*names))), "sql-vectors")
    rows.createOrReplaceTempView(view)
    good = " and ".join(f"a.{n} >= b.{n}" for n in names)
    stored(spark.sql(f"select a.id p, b.id q from {view} a join {view} b on a.id != b.id and {good}"), "dominance").createOrReplaceTempView(f"{view}_dominance")
    spark.sql(f"select id, 1 layer from {view}").createOrReplaceTempView(f"{view}_layers")
    total = None
    while True:
        now = spark.sql(f"select sum(layer) from {view}_layers").first()[0]
        if now == total:
            return df.join(rows.join(spark.table(f"{view}_layers"), "id").drop("id"), names)
        total = now
        step = spark.sql(f"""
          select v.id, coalesce(max(l.layer), 0) + 1 layer from {view} v
          left join {view}_dominance d on d.q = v.id left join {view}_layers l on l.id = d.p group by v.id""")
        stored(step, "sql-layers").createOrReplaceTempView(f"{view}_layers")


def rank_by_sum(df: DataFrame, attrs, digits: int = 6) -> DataFrame:
    """The special case of utility as a plain sum: dense rank of the sum, over distinct sums."""
    total = F.round(sum((a.value() for a in _attributes(attrs)), F.lit(0.0)), digits)
    sums = df.select(total.alias("total")).distinct().withColumn("layer", F.dense_rank().over(W.orderBy(F.col("total").desc())))
    return df.withColumn("total", total).join(sums, "total")
