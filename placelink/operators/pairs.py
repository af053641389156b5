"""Candidate pairs: inside blocks, within a radius, or without any index; counts and coverage."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from placelink.functions.geo import euclid_m
from placelink.operators.storage import stored

SCOPES = ("all", "within", "cross")
#: Places of a cell that meet in one task; fuller cells are dealt into parts, and every two parts meet in a task of their own.
MOST_IN_CELL = 2_000
#: Fuller cells that are known by broadcast (20 MB); beyond, their numbers of parts are joined by cell.
MOST_HOT_CELLS = 500_000
#: Places of a chunk of the baseline without an index, and how many of them are compared with how many others at once.
CHUNK, STRIP, WIDTH = 32_768, 64, 8_192
#: Chunks of a side that a task of that baseline holds, parts of a side at least, and strips that are looked through at once.
CHUNKS_OF_TASK, LEAST_PARTS, AT_ONCE = 4, 8, 4_096


def _sides(df: DataFrame, columns: list[str]) -> tuple[DataFrame, DataFrame]:
    return tuple(df.select(*[F.col(c).alias(f"{c}_{s}") for c in columns]) for s in "ab")


def _with_parts(rows: DataFrame, cell: list[str], hot: DataFrame, n_hot: int) -> DataFrame:
    """rows with __parts, the number of parts of their cell (1 unless it is hot)."""
    parts = hot.select(*cell, F.ceil(F.col("n") / MOST_IN_CELL).cast("int").alias("__parts"))
    found = rows.join(F.broadcast(parts) if n_hot <= MOST_HOT_CELLS else parts, cell, "left")
    return found.withColumn("__parts", F.coalesce("__parts", F.lit(1)))


def candidate_pairs(blocks: DataFrame, scope: str = "all", max_dist_m: float | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """Every pair of places that shares a block, once: eid_a < eid_b, dist_m, and the carried columns of both.

    A pair with several common blocks belongs to the least of them, so no distinct is needed. On one level that block
    follows from the two places' least cells; with leaves of several levels a place's leaves ride along as an array.
    Cells of more than MOST_IN_CELL places are dealt into parts, so that no task compares more than two parts.
    """
    leaf = ["level", "ix", "iy"]
    cells = blocks.groupBy(*leaf).agg(F.count("*").alias("n"), F.max(F.col("low_ix").isNull()).alias("deep"))
    deep, n_hot = cells.agg(F.coalesce(F.max("deep"), F.lit(False)), F.count_if(F.col("n") > MOST_IN_CELL)).first()
    one_level, cut = not deep, []
    if not one_level:
        own = blocks.groupBy("eid").agg(F.collect_set(F.struct(*leaf)).alias("leaves"))  # a place has few leaves
        blocks = blocks.join(own, "eid")
    if n_hot:
        blocks = _with_parts(blocks, leaf, cells.where(F.col("n") > MOST_IN_CELL), n_hot)
        blocks = blocks.withColumn("part", F.pmod(F.xxhash64("eid", "x_m", "y_m"), F.col("__parts")).cast("int"))
        blocks = blocks.withColumn("__other", F.explode(F.sequence(F.lit(0), F.col("__parts") - 1)))
        blocks = blocks.withColumns({"low": F.least("part", "__other"), "high": F.greatest("part", "__other")})
        cut = ["low", "high"]
    columns = list(dict.fromkeys(["eid", *leaf, *cut, *(["part"] if cut else []), "x_m", "y_m", *(["low_ix", "low_iy"] if one_level else ["leaves"]), *(["source"] if scope != "all" else []), *carry]))
    a, b = _sides(blocks, columns)
    pairs = a.join(b, [a[f"{c}_a"] == b[f"{c}_b"] for c in [*leaf, *cut]]).where("eid_a < eid_b")
    if cut:  # two places of one part meet in that part's own task only
        pairs = pairs.where("low_a = high_a or part_a != part_b")
    if one_level:
        pairs = pairs.where((F.col("ix_a") == F.greatest("low_ix_a", "low_ix_b")) & (F.col("iy_a") == F.greatest("low_iy_a", "low_iy_b")))
    else:
        least = F.array_min(F.array_intersect("leaves_a", "leaves_b"))
        pairs = pairs.where((least["level"] == F.col("level_a")) & (least["ix"] == F.col("ix_a")) & (least["iy"] == F.col("iy_a")))
    if scope == "within":
        pairs = pairs.where("source_a = source_b")
    elif scope == "cross":
        pairs = pairs.where("source_a != source_b")
    pairs = pairs.withColumn("dist_m", euclid_m(F.col("x_m_a"), F.col("y_m_a"), F.col("x_m_b"), F.col("y_m_b")))
    if max_dist_m is not None:
        pairs = pairs.where(F.col("dist_m") <= max_dist_m)
    more = [f"{c}_{s}" for c in carry for s in "ab"]
    return pairs.select("eid_a", "eid_b", "dist_m", *more)


def comparison_count(blocks: DataFrame) -> DataFrame:
    """Comparisons inside blocks, repeated ones included, without making a pair."""
    n = F.col("n")
    return blocks.groupBy("level", "ix", "iy").agg(F.count("*").alias("n")).agg(F.coalesce(F.sum((n * (n - 1) / 2).cast("bigint")), F.lit(0)).alias("comparisons"))


def radius_pairs(places: DataFrame, r: float, strategy: str = "grid") -> DataFrame:
    """Pairs at most r apart: by a grid of cells of side r, or by sorting along a curve and sweeping."""
    if strategy == "grid":
        cell = places.select("eid", "x_m", "y_m", F.floor(F.col("x_m") / r).alias("cx"), F.floor(F.col("y_m") / r).alias("cy"))
        near = F.explode(F.sequence(F.lit(-1), F.lit(1)))
        a, b = _sides(cell, cell.columns)
        b = b.withColumn("dx", near).withColumn("dy", near).select("eid_b", "x_m_b", "y_m_b", (F.col("cx_b") + F.col("dx")).alias("cx"), (F.col("cy_b") + F.col("dy")).alias("cy"))
        a = a.withColumnsRenamed({"cx_a": "cx", "cy_a": "cy"})
        on = ["cx", "cy"]
        hot = cell.groupBy(*on).agg(F.count("*").alias("n")).where(F.col("n") > MOST_IN_CELL)
        n_hot = hot.count()
        if n_hot:  # a full cell's places are dealt into parts, and each part meets all that is near
            a = _with_parts(a, on, hot, n_hot).withColumn("part", F.pmod(F.xxhash64("eid_a", "x_m_a", "y_m_a"), F.col("__parts")).cast("int")).drop("__parts")
            b = _with_parts(b, on, hot, n_hot).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("__parts") - 1))).drop("__parts")
            on = [*on, "part"]
        pairs = a.join(b, on).where("eid_a < eid_b")
        pairs = pairs.withColumn("dist_m", euclid_m(F.col("x_m_a"), F.col("y_m_a"), F.col("x_m_b"), F.col("y_m_b")))
        return pairs.where(F.col("dist_m") <= r).select("eid_a", "eid_b", "dist_m")
    if strategy != "sorted":
        raise ValueError(strategy)
    # strips of 8 r; a place is also sent to the strip before its own if it lies within r of the border
    strip = F.floor(F.col("x_m") / (8 * r))
    halo = F.when(F.col("x_m") - strip * 8 * r <= r, F.array(strip, strip - 1)).otherwise(F.array(strip))
    tall = F.floor(F.col("y_m") / (64 * r))
    tall_halo = F.when(F.col("y_m") - tall * 64 * r <= r, F.array(tall, tall - 1)).otherwise(F.array(tall))
    rows = places.select("eid", F.col("x_m").cast("double"), F.col("y_m").cast("double"), strip.alias("own"), tall.alias("own_y"), F.explode(halo).alias("strip"), tall_halo.alias("t"))
    rows = rows.withColumn("tall", F.explode("t")).drop("t")

    def sweep(task: pa.Table) -> pa.Table:
        task = task.sort_by([("y_m", "ascending")])
        eid = np.array(task.column("eid").to_pylist(), dtype=object)
        x, y = task.column("x_m").to_numpy(), task.column("y_m").to_numpy()
        own, own_y = task.column("own").to_numpy(), task.column("own_y").to_numpy()
        here, high = task.column("strip")[0].as_py(), task.column("tall")[0].as_py()
        end = np.searchsorted(y, y + r, side="right")
        first, second, apart = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]
        for i in range(len(x)):
            j = np.arange(i + 1, end[i])
            # the pair belongs to the lesser strip of its two places, on both axes
            j = j[(np.minimum(own[i], own[j]) == here) & (np.minimum(own_y[i], own_y[j]) == high)]
            d = np.sqrt((x[j] - x[i]) * (x[j] - x[i]) + (y[j] - y[i]) * (y[j] - y[i]))
            j, d = j[d <= r], d[d <= r]
            first.append(np.full(len(j), i))
            second.append(j)
            apart.append(d)
        p, q, d = eid[np.concatenate(first)], eid[np.concatenate(second)], np.concatenate(apart)
        differ, swap = p != q, p > q
        p, q = np.where(swap, q, p)[differ], np.where(swap, p, q)[differ]
        return pa.table([pa.array(p, pa.string()), pa.array(q, pa.string()), pa.array(d[differ])], schema=pa.schema([("eid_a", pa.string()), ("eid_b", pa.string()), ("dist_m", pa.float64())]))

    return rows.groupBy("strip", "tall").applyInArrow(sweep, "eid_a string, eid_b string, dist_m double")


def _chunks(places: DataFrame) -> DataFrame:
    """Rows of CHUNK places each: a number, ids and coordinates. Places without an id or a coordinate are in no pair."""
    rows = places.select("eid", F.col("x_m").cast("double").alias("x"), F.col("y_m").cast("double").alias("y")).where("eid is not null and x is not null and y is not null")
    eid = rows.schema["eid"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        held, n, number = [], 0, TaskContext.get().partitionId() << 32

        def rows_of(t: pa.Table, number: int) -> pa.RecordBatch:
            lists = [pa.ListArray.from_arrays(pa.array([0, t.num_rows], pa.int32()), t.column(c).combine_chunks()) for c in ("eid", "x", "y")]
            return pa.RecordBatch.from_arrays([pa.array([number], pa.int64()), *lists], names=["chunk", "eid", "x", "y"])

        for batch in batches:
            held, n = [*held, batch], n + batch.num_rows
            while n >= CHUNK:
                t = pa.Table.from_batches(held)
                yield rows_of(t.slice(0, CHUNK), number)
                held, n, number = t.slice(CHUNK).to_batches(), n - CHUNK, number + 1
        if n:
            yield rows_of(pa.Table.from_batches(held), number)

    return rows.mapInArrow(run, f"chunk bigint, eid array<{eid}>, x array<double>, y array<double>")


def _rounded(v: np.ndarray, side: float, shift: float = 0.0) -> np.ndarray:
    """Multiples of side below v - shift * side, modulo 256."""
    with np.errstate(all="ignore"):
        n = np.floor(v / side - shift)
    return (np.where(np.isfinite(n), n, 0).astype(np.int64) & 255).astype(np.uint8)


def near_pairs(xa: np.ndarray, ya: np.ndarray, xb: np.ndarray, yb: np.ndarray, r: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Every place of a against every place of b: positions and distances of those at most r apart, some at a time.

    Both coordinates of every pair are first subtracted in bytes, as multiples of a little more than 2 r modulo 256. Those
    of a are taken half a multiple lower, so that what is at most r away on either side is 0 or 1 multiples above. The
    distances of all pairs that this leaves are formed in doubles.
    """
    most = max(float(np.abs(v[np.isfinite(v)]).max(initial=0)) for v in (xa, ya, xb, yb))
    side = max(2.02 * r, most * 2.0**-40) or 1.0  # quotients up to 2 ** 40 are rounded by far less than the hundredth
    strips = -(-len(xa) // STRIP)
    ca, da = (np.resize(_rounded(v, side, 0.5), (strips, STRIP)) for v in (xa, ya))  # the last strip is filled up
    cb, db = (_rounded(v, side) for v in (xb, yb))
    for left in range(0, len(xb), WIDTH):
        c, d = cb[left : left + WIDTH], db[left : left + WIDTH]
        (p, q), least = np.empty((2, STRIP, len(c)), np.uint8), np.empty((strips, len(c)), np.uint8)
        for k in range(strips):
            np.subtract(c, ca[k, :, None], out=p)
            np.subtract(d, da[k, :, None], out=q)
            np.bitwise_or(p, q, out=p)
            np.minimum.reduce(p, axis=0, out=least[k])
        found = np.flatnonzero(least < 2)
        for at in range(0, len(found), AT_ONCE):
            k, j = np.divmod(found[at : at + AT_ONCE], len(c))
            close = ((c[j, None] - ca[k]) | (d[j, None] - da[k])) < 2
            hit, i = np.divmod(np.flatnonzero(close), STRIP)
            i, j = k[hit] * STRIP + i, j[hit] + left
            i, j = i[i < len(xa)], j[i < len(xa)]
            with np.errstate(all="ignore"):
                dx, dy = xa[i] - xb[j], ya[i] - yb[j]
                apart = np.sqrt(dx * dx + dy * dy)
            near = apart <= r
            yield i[near], j[near], apart[near]


def all_pairs(places: DataFrame, r: float, most: int = 200_000, force: bool = False) -> DataFrame:
    """The baseline without an index: compares all places; refuses more than `most` unless forced.

    Every chunk of CHUNK places meets every other one and itself, and all their places are compared in arrays; nothing is
    skipped by where it lies. The chunks are stored, so that both sides of the join see the same ones; both sides are dealt
    into parts of a few chunks, and every two parts meet in a task of their own.
    """
    if not force and places.count() > most:
        raise ValueError(f"more than {most} places; pass force=True to compare them all")
    chunks = stored(_chunks(places), "chunks")
    n = chunks.count()
    parts = max(1, min(n, LEAST_PARTS), -(-n // CHUNKS_OF_TASK))
    a, b = (side.repartition(parts) for side in _sides(chunks, chunks.columns))
    eid = places.schema["eid"].dataType.simpleString()

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = {c: batch.column(c) for c in batch.schema.names}
            for k in range(batch.num_rows):
                one = {c: v[k].as_py() if c.startswith("chunk") else v[k].values for c, v in columns.items()}
                same = one["chunk_a"] == one["chunk_b"]
                for i, j, d in near_pairs(*(one[c].to_numpy() for c in ("x_a", "y_a", "x_b", "y_b")), r):
                    if same:
                        once = i < j
                        i, j, d = i[once], j[once], d[once]
                    p, q, d = one["eid_a"].take(pa.array(i)), one["eid_b"].take(pa.array(j)), pa.array(d)
                    less, more = pc.less(p, q), pc.greater(p, q)
                    for x, y, kept in ((p, q, less), (q, p, more)):
                        if pc.any(kept).as_py():
                            yield pa.RecordBatch.from_arrays([x.filter(kept), y.filter(kept), d.filter(kept)], names=["eid_a", "eid_b", "dist_m"])

    tiles = a.join(b.hint("shuffle_replicate_nl"), F.col("chunk_a") <= F.col("chunk_b"))
    return tiles.mapInArrow(compare, f"eid_a {eid}, eid_b {eid}, dist_m double")


def coverage(found: DataFrame, reference: DataFrame, radii: tuple[float, ...]) -> DataFrame:
    """Share of the reference pairs within each radius that were found."""
    hit = found.select("eid_a", "eid_b", F.lit(1).alias("hit"))
    both = reference.join(hit, ["eid_a", "eid_b"], "left").select(F.explode(F.array(*map(F.lit, map(float, radii)))).alias("radius"), "dist_m", "hit").where("dist_m <= radius")
    return both.groupBy("radius").agg(F.count("*").alias("reference_pairs"), F.count("hit").alias("found_pairs")).withColumn("coverage", F.round(F.col("found_pairs") / F.col("reference_pairs"), 6))
