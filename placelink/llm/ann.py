"""Approximate nearest neighbours by a hash-prefix forest (largest inner product).

Every tree hashes a vector to a string of 64 bits, one per random hyperplane, and keeps the strings in a sorted array. A
query descends to the longest prefix it shares with any string of a tree; from there all trees ascend together, one bit
at a time, and the ranges of strings that share the shorter prefix are its candidates. Of these, the ones whose whole
strings differ least from the query's (over SCREEN trees) are ranked by their exact inner products in double precision.

The ascent ends when the k-th best so far would have been met with a probability of at least 1 - `miss`: a vector at an
angle w shares one bit with probability 1 - w / pi, so all trees miss it at depth d with (1 - (1 - w / pi)^d)^trees. Near
neighbours end it early, whatever the size of the table; vectors without any near ones need wide ranges (README).

Vectors of different lengths are put on one sphere first (one more component makes up for what a vector lacks of the
longest one), so that the largest inner product is the nearest direction.

Rows and queries are dealt into blocks; every block of rows has a forest of its own and meets every block of queries, so
that each row is indexed and no task grows with the input. A row is sent to a task once for every BLOCK_QUERIES queries,
a query once for every BLOCK_ROWS rows.

Defined cases: vectors that are null, zero, of another dimension than most, or that hold null or non-finite components
take no part, neither as rows nor as queries; fewer rows than wanted are all returned; ties go to the smaller id;
repeated ids are rows of their own (a query leaves out all rows of its own id, and a repeated query has one list); an
empty table gives an empty result; columns other than vec_id and embedding may have any name, but for what is_query reads.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from placelink.llm.common import table

TREES, BITS, NEAREST = 48, 64, 20
#: Trees whose strings screen the candidates: 512 bits.
SCREEN = 8
#: Rows of a block with one forest, and queries of a block.
BLOCK_ROWS, BLOCK_QUERIES = 16_384, 65_536
#: Queries whose ranges in all trees a task holds at once (some 20 MB).
STRETCH = 1_024
#: The largest probability of missing the k-th neighbour; the share of a block's rows, and how often k at least, that are ranked exactly.
MISS, RANKED, LEAST_RANKED = 0.08, 0.1, 10


class Forest:
    """Sorted arrays of hash strings over one block of vectors."""

    def __init__(self, x: np.ndarray, longest: float, trees: int = TREES, seed: int = 11):
        self.x, self.longest, self.trees = x, longest, trees
        lacks = np.sqrt(np.maximum(longest**2 - (x * x).sum(axis=1), 0))
        rng = np.random.default_rng(seed)
        self.planes = np.stack([self._directions(rng, x.shape[1] + 1) for _ in range(trees)])
        self.own = self._strings(np.concatenate([x, lacks[:, None]], axis=1))
        self.order = [np.argsort(self.own[:, t], kind="stable") for t in range(trees)]
        self.sorted = [self.own[order, t] for t, order in enumerate(self.order)]
        self.screen = np.ascontiguousarray(self.own[:, :SCREEN])

    @staticmethod
    def _directions(rng: np.random.Generator, width: int) -> np.ndarray:
        """Hyperplanes that are at right angles to each other, as far as there is room."""
        parts = [np.linalg.qr(rng.standard_normal((width, width)))[0] for _ in range(-(-BITS // width))]
        return np.concatenate(parts, axis=1)[:, :BITS]

    def _strings(self, whole: np.ndarray) -> np.ndarray:
        """One string per vector and tree."""
        return np.stack([np.packbits(whole @ p > 0, axis=1).view(">u8").astype(np.uint64).ravel() for p in self.planes], axis=1)

    def strings_of(self, q: np.ndarray) -> np.ndarray:
        return self._strings(np.concatenate([q, np.zeros((len(q), 1))], axis=1))

    def candidates(self, ranges: np.ndarray) -> np.ndarray:
        """Rows in any of the trees' ranges (first entry, last one and one)."""
        mark = np.zeros(len(self.x), bool)
        for order, (low, high) in zip(self.order, ranges.tolist(), strict=True):
            if low < high:
                mark[order[low:high]] = True
        return np.flatnonzero(mark)

    def ranges(self, strings: np.ndarray, enough: int) -> np.ndarray:
        """The ranges by query, depth (from 0) and tree, down to where no query's hold `enough` entries in all."""
        found = []
        for depth in range(BITS + 1):
            below = np.uint64(2**64 - 1) if depth == 0 else np.uint64(2 ** (BITS - depth) - 1)
            low = [np.searchsorted(own, strings[:, t] & ~below, side="left") for t, own in enumerate(self.sorted)]
            high = [np.searchsorted(own, strings[:, t] | below, side="right") for t, own in enumerate(self.sorted)]
            found.append(np.stack([np.stack(low, axis=1), np.stack(high, axis=1)], axis=2).astype(np.int32))
            if not ((found[-1][:, :, 1] - found[-1][:, :, 0]).sum(axis=1) >= enough).any():
                break
        return np.stack(found, axis=1)

    def search(self, q: np.ndarray, string: np.ndarray, ranges: np.ndarray, k: int, skip: np.ndarray | None = None, miss: float = MISS, ranked: float = RANKED) -> tuple[np.ndarray, np.ndarray, int]:
        """Rows and scores that hold the query's k best (more where they tie), and how many rows were candidates.

        ranges: those of the query by depth and tree. skip: rows that count for nothing (the query itself).
        """
        length = float(np.sqrt(q @ q))
        entries = (ranges[:, :, 1] - ranges[:, :, 0]).sum(axis=1)
        depth = int(np.flatnonzero(entries >= min(4 * k + self.trees, entries[0])).max(initial=0))  # a query finds itself in every tree
        while True:
            c = found = self.candidates(ranges[depth])
            if skip is not None:
                c = c[~skip[c]]
            most = max(LEAST_RANKED * k, int(ranked * len(self.x)))
            if len(c) > most:  # ties with the last one come along
                unlike = np.bitwise_count(self.screen[c] ^ string[:SCREEN]).sum(axis=1, dtype=np.uint16)
                c = c[unlike <= np.partition(unlike, most - 1)[most - 1]]
            score = self.x[c] @ q
            if depth == 0:
                break
            if len(c) >= k:
                angle = np.arccos(np.clip(np.partition(score, -k)[-k] / (length * self.longest), -1, 1))
                if (1 - (1 - angle / np.pi) ** depth) ** self.trees <= miss:
                    break
            depth -= 1
        return c, score, len(found)


def _usable(vector: Column) -> Column:
    bad = lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))
    return vector.isNotNull() & ~F.exists(vector, bad) & F.exists(vector, lambda v: v != 0)


def nearest(vectors: DataFrame, is_query: Column, k: int = NEAREST, miss: float = MISS, trees: int = TREES, block_rows: int = BLOCK_ROWS, block_queries: int = BLOCK_QUERIES, ranked: float = RANKED) -> DataFrame:
    """vectors (vec_id, embedding) to query_id, rank (from 1), vec_id, score."""
    v = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks"))
    v = v.where(_usable(F.col("v")) & F.col("vec_id").isNotNull()).withColumn("dim", F.size("v"))
    dims = v.groupBy("dim").agg(F.count("*").alias("n"), F.count_if("asks").alias("q"), F.max(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)).alias("m"))
    top = dims.orderBy(F.col("n").desc(), "dim").first()
    if top is None:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    v = v.where(F.col("dim") == top["dim"])
    longest, row_blocks, query_blocks = float(np.sqrt(top["m"])), -(-top["n"] // block_rows), max(1, -(-top["q"] // block_queries))
    rows = v.select("vec_id", "v", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(row_blocks)).cast("int").alias("r"), F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1))).alias("q"), F.lit(False).alias("asks"))
    asks = v.where("asks").select("vec_id", "v", F.explode(F.sequence(F.lit(0), F.lit(row_blocks - 1))).alias("r"), F.pmod(F.xxhash64("vec_id", F.lit(2)), F.lit(query_blocks)).cast("int").alias("q"), F.lit(True).alias("asks"))

    def run(block: pa.Table) -> pa.Table:
        block = block.combine_chunks()
        ask = block.column("asks").to_numpy()
        ids = block.column("vec_id").to_numpy()
        x = block.column("v").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
        order = np.argsort(ids[~ask], kind="stable")
        row_ids, queries, query_ids = ids[~ask][order], x[ask], ids[ask]
        if not len(row_ids) or not len(query_ids):
            return _FOUND.empty_table()
        forest = Forest(x[~ask][order], longest, trees)
        out_q, out_id, out_score = [], [], []
        low, high = np.searchsorted(row_ids, query_ids, side="left"), np.searchsorted(row_ids, query_ids, side="right")
        skip = np.zeros(len(row_ids), bool)
        for i in range(len(query_ids)):
            if i % STRETCH == 0:
                strings = forest.strings_of(queries[i : i + STRETCH])
                ranges = forest.ranges(strings, 4 * k)
            skip[low[i] : high[i]] = True
            c, score, _ = forest.search(queries[i], strings[i % STRETCH], ranges[i % STRETCH], k, skip, miss, ranked)
            skip[low[i] : high[i]] = False
            if len(c) > k:  # all that may tie with the last one stay
                c = c[score >= np.partition(score, -k)[-k] - 1e-9 * longest * longest]
            score = (forest.x[c] * queries[i]).sum(axis=1)  # adds up every row alike, so that equal vectors tie
            best = np.lexsort((row_ids[c], -score))[:k]
            out_q += [query_ids[i]] * len(best)
            out_id.append(row_ids[c[best]])
            out_score.append(score[best])
        return pa.table([pa.array(out_q, pa.int64()), pa.array(np.concatenate(out_id)), pa.array(np.concatenate(out_score))], schema=_FOUND)

    found = rows.unionByName(asks).groupBy("r", "q").applyInArrow(run, "query_id long, vec_id long, score double")
    best = W.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


_FOUND = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])


def op2_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)
