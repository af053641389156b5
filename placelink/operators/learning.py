"""Supervised and clustering baselines on similarity vectors."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
from pyspark.ml.classification import DecisionTreeClassifier, LinearSVC, LogisticRegression, NaiveBayes
from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from placelink.operators.components import components
from placelink.operators.layers import _names
from placelink.operators.metrics import confusion, prf
from placelink.operators.storage import stored

MODELS = ("logreg", "svm", "tree", "bayes")
PROTOCOLS = ("full", "sample", "transfer")
SAMPLE = 1_500
#: Vectors whose matrix of all distances agglomeration holds at once (more are an error), and that DBSCAN takes to the driver.
MOST_CLUSTERED = 3_000
#: Numbers that k-medoids and DBSCAN hold at once for a stretch of distances.
STRETCH = 4_000_000


def checked_sample(pairs: DataFrame, n: int = SAMPLE) -> DataFrame:
    """The n pairs of the smallest md5: the stand-in for the hand-checked sample."""
    return pairs.orderBy(F.md5(F.concat("eid_a", "eid_b")), "eid_a", "eid_b").limit(n)


def fold(pairs: DataFrame, folds: int = 4) -> DataFrame:
    return pairs.withColumn("fold", F.pmod(F.xxhash64("eid_a", "eid_b"), F.lit(folds)).cast("int"))


def _model(name: str):
    common = {"featuresCol": "features", "labelCol": "label"}
    return {
        "logreg": lambda: LogisticRegression(**common), "svm": lambda: LinearSVC(maxIter=50, **common),
        "tree": lambda: DecisionTreeClassifier(maxDepth=6, seed=1, **common), "bayes": lambda: NaiveBayes(modelType="gaussian", **common),
    }[name]()


def supervised(pairs: DataFrame, model: str, attrs, protocol: str = "full", folds: int = 4) -> DataFrame:
    """One row: counts, precision, recall, F1 on held-out pairs.

    The sample has SAMPLE pairs, a third of all at most. "full" and "sample": each quarter is tested by a model of the other three; "transfer": learned on the sample, tested
    on everything else.
    """
    assembled, pairs = VectorAssembler(inputCols=_names(attrs), outputCol="features"), pairs.withColumn("label", F.col("label").cast("double"))
    ready = assembled.transform(pairs)
    few = min(SAMPLE, max(1, ready.count() // 3)) if protocol != "full" else 0
    if protocol == "transfer":
        sample = checked_sample(ready, few)
        tested = _model(model).fit(sample).transform(ready.join(sample.select("eid_a", "eid_b"), ["eid_a", "eid_b"], "left_anti"))
    else:
        data = stored(fold(checked_sample(pairs, few) if protocol == "sample" else pairs, folds), "folds")
        data = assembled.transform(data)
        tested = None
        for i in range(folds):
            part = _model(model).fit(data.where(F.col("fold") != i)).transform(data.where(F.col("fold") == i)).select("prediction", "label")
            tested = part if tested is None else tested.unionByName(part)
    out = tested.select((F.col("prediction") == 1.0).alias("match"), F.col("label").cast("int").alias("label"))
    return prf(confusion(out)).withColumns({"model": F.lit(model), "protocol": F.lit(protocol)})


def best_orientation(vectors: DataFrame, cluster: str = "cluster") -> DataFrame:
    """One row: either cluster may be the matches; the one with the larger F1 is reported. Weighted by pairs."""
    rows = None
    for c in (0, 1):
        hit = F.col(cluster) == c
        counts = vectors.agg(
            F.coalesce(F.sum(F.when(hit, F.col("positives"))), F.lit(0)).alias("tp"), F.coalesce(F.sum(F.when(hit, F.col("pairs") - F.col("positives"))), F.lit(0)).alias("fp"),
            F.coalesce(F.sum(F.when(~hit, F.col("positives"))), F.lit(0)).alias("fn"), F.coalesce(F.sum(F.when(~hit, F.col("pairs") - F.col("positives"))), F.lit(0)).alias("tn"),
        ).withColumn("positive_cluster", F.lit(c))
        rows = prf(counts) if rows is None else rows.unionByName(prf(counts))
    return rows.orderBy(F.col("f1").desc(), "positive_cluster").limit(1)


def cluster(vectors: DataFrame, method: str, attrs, **options) -> DataFrame:
    """vectors (attributes, pairs, positives) with `cluster` 0 or 1, by k-means, k-medoids, agglomeration or DBSCAN.

    Every vector gets a cluster. K-medoids reads the distinct vectors to the driver and takes time that grows with their
    square. Beyond MOST_CLUSTERED vectors DBSCAN finds the same clusters by joins, and agglomeration, which needs all
    distances at once, raises an error.
    """
    names = _names(attrs)
    if method == "kmeans":
        ready = VectorAssembler(inputCols=names, outputCol="features").transform(vectors)
        model = KMeans(k=2, seed=1, weightCol="pairs", featuresCol="features", predictionCol="cluster").fit(ready)
        return model.transform(ready).drop("features")
    if method == "dbscan" and vectors.count() > MOST_CLUSTERED:
        return dbscan_join(vectors, attrs, **options)
    found = vectors.orderBy(*names).toPandas()
    x, w = found[names].to_numpy(float), found["pairs"].to_numpy(float)
    found["cluster"] = {"kmedoids": k_medoids, "agglomerative": agglomerative, "dbscan": dbscan}[method](x, w, **options)
    return vectors.sparkSession.createDataFrame(found)


def _distances(x: np.ndarray, y: np.ndarray | None = None) -> np.ndarray:
    y = x if y is None else y
    return np.sqrt(np.maximum(((x[:, None] - y[None]) ** 2).sum(axis=2), 0))


def _stretches(x: np.ndarray) -> Iterator[np.ndarray]:
    """The matrix of all distances, some rows at a time."""
    step = max(1, STRETCH // max(1, x.size))
    for i in range(0, len(x), step):
        yield _distances(x[i : i + step], x)


def k_medoids(x: np.ndarray, w: np.ndarray, rounds: int = 50) -> np.ndarray:
    """Two medoids by alternation, from the most distant pair of a weighted start."""
    if len(x) < 2:
        return np.zeros(len(x), int)
    costs = lambda at: np.concatenate([(d * w[at]).sum(axis=1) for d in _stretches(x[at])])
    medoids = [int(costs(np.arange(len(x))).argmin())]
    medoids.append(int((_distances(x[medoids], x)[0] * w).argmax()))
    for _ in range(rounds):
        own = _distances(x[medoids], x).argmin(axis=0)
        new = [int(np.flatnonzero(own == c)[costs(np.flatnonzero(own == c)).argmin()]) if (own == c).any() else medoids[c] for c in (0, 1)]
        if new == medoids:
            break
        medoids = new
    return _distances(x[medoids], x).argmin(axis=0)


def agglomerative(x: np.ndarray, w: np.ndarray, linkage: str = "average") -> np.ndarray:
    """Joins the nearest groups until two are left (average, single or complete linkage, weighted)."""
    n = len(x)
    if n > MOST_CLUSTERED:
        raise ValueError(f"agglomeration holds all distances of {MOST_CLUSTERED} vectors at most, not of {n}")
    d, size, root = _distances(x), w.astype(float).copy(), list(range(n))
    np.fill_diagonal(d, np.inf)
    alive = np.ones(n, bool)
    near, at = d.min(axis=1), d.argmin(axis=1)
    for _ in range(n - 2):
        i = int(np.where(alive, near, np.inf).argmin())
        j = int(at[i])
        i, j = min(i, j), max(i, j)
        row = {"single": np.minimum(d[i], d[j]), "complete": np.maximum(np.where(np.isinf(d[i]), -1, d[i]), np.where(np.isinf(d[j]), -1, d[j])), "average": (size[i] * d[i] + size[j] * d[j]) / (size[i] + size[j])}[linkage]
        row[~alive] = np.inf
        row[[i, j]] = np.inf
        d[i], d[:, i] = row, row
        d[j], d[:, j] = np.inf, np.inf
        size[i] += size[j]
        alive[j] = False
        root[j] = i
        near[i], at[i] = d[i].min(), d[i].argmin()
        for k in np.flatnonzero(alive & ((at == i) | (at == j))):
            near[k], at[k] = d[k].min(), d[k].argmin()
        closer = alive & (d[:, i] < near)
        near[closer], at[closer] = d[closer, i], i

    def top(k: int) -> int:
        while root[k] != k:
            k = root[k]
        return k

    tops = [top(k) for k in range(n)]
    first = tops[0] if n else 0
    return np.array([int(t != first) for t in tops])


def dbscan(x: np.ndarray, w: np.ndarray, eps: float = 0.1, least: float = 5) -> np.ndarray:
    """Density clusters: the heaviest (by its core vectors) and what lies within eps of its cores is 0, all else 1."""
    if not len(x):
        return np.zeros(0, int)
    core = np.concatenate([((d <= eps) * w).sum(axis=1) for d in _stretches(x)]) >= least
    label = np.full(len(x), -1)
    current = 0
    for i in np.flatnonzero(core):
        if label[i] >= 0:
            continue
        queue = deque([i])
        label[i] = current
        while queue:
            k, free = queue.popleft(), np.flatnonzero(core & (label < 0))
            near = free[_distances(x[k : k + 1], x[free])[0] <= eps]
            label[near] = current
            queue.extend(near.tolist())
        current += 1
    if current == 0:
        return np.ones(len(x), int)
    own = x[label == int(np.argmax([w[label == c].sum() for c in range(current)]))]
    step = max(1, STRETCH // max(1, own.size))
    return np.concatenate([(_distances(x[i : i + step], own).min(axis=1) > eps).astype(int) for i in range(0, len(x), step)])


def dbscan_join(vectors: DataFrame, attrs, eps: float = 0.1, least: float = 5) -> DataFrame:
    """dbscan without a driver: neighbours by an equi-join of grid cells of side eps, clusters by connected components."""
    names = _names(attrs)
    v = stored(vectors.withColumn("__id", F.monotonically_increasing_id()), "dbscan-vectors")
    cells, x = [f"__c{i}" for i in range(len(names))], [f"__x{i}" for i in range(len(names))]
    cell = [F.floor(F.col(n) / eps).alias(c) for n, c in zip(names, cells, strict=True)]
    at = v.select(F.col("__id").alias("a"), *[F.col(n).alias(f"{k}a") for n, k in zip(names, x, strict=True)], *cell)
    near = v.select(F.col("__id").alias("b"), F.col("pairs").alias("w"), *[F.col(n).alias(f"{k}b") for n, k in zip(names, x, strict=True)], *cell)
    for c in cells:
        near = near.withColumn("__d", F.explode(F.array(*map(F.lit, (-1, 0, 1))))).withColumn(c, F.col(c) + F.col("__d")).drop("__d")
    apart = sum(((F.col(f"{k}a") - F.col(f"{k}b")) * (F.col(f"{k}a") - F.col(f"{k}b")) for k in x), F.lit(0.0))
    links = stored(at.join(near, cells).where(F.sqrt(apart) <= eps).select("a", "b", "w"), "dbscan-links")
    core = stored(links.groupBy("a").agg(F.sum("w").alias("n")).where(F.col("n") >= least).select("a"), "dbscan-cores")
    between = links.join(core, "a", "left_semi").join(core.withColumnRenamed("a", "b"), "b", "left_semi")
    joined = components(between.where("a != b"))
    own = core.join(joined, core["a"] == joined["id"], "left").select("a", F.coalesce("component", "a").alias("component"))
    own = stored(own.join(v.select(F.col("__id").alias("a"), F.col("pairs").alias("w")), "a"), "dbscan-clusters")
    top = own.groupBy("component").agg(F.sum("w").alias("w")).orderBy(F.col("w").desc(), "component").limit(1)
    heart = own.join(F.broadcast(top.select("component")), "component", "left_semi").select("a")  # one cluster's number
    inside = links.join(heart, "a", "left_semi").select(F.col("b").alias("__id")).distinct()
    return v.join(inside.withColumn("__in", F.lit(0)), "__id", "left").withColumn("cluster", F.coalesce("__in", F.lit(1))).drop("__id", "__in")


def dbscan_sweep(vectors: DataFrame, attrs, eps: tuple[float, ...] = (0.05, 0.1, 0.15, 0.2), least: tuple[int, ...] = (5, 20, 50)) -> DataFrame:
    """best_orientation for every setting."""
    out = None
    for e in eps:
        for m in least:
            row = best_orientation(cluster(vectors, "dbscan", attrs, eps=e, least=m)).withColumns({"eps": F.lit(e), "min_pairs": F.lit(m)})
            out = row if out is None else out.unionByName(row)
    return out
