"""Near-duplicate documents: MinHash bands for candidates, odd sketches to screen them, full sets to confirm.

A document's set holds the hashes (64 bits) of its shingles. Equal sets are one class. Every class gets MinHash samples
under many permutations, banded into bucket keys, and up to 8192 samples of one-permutation MinHash, folded into an odd
sketch: each sample flips one bit, so that the population count of the XOR of two sketches estimates the number of
differing samples, precisely so for high similarities. (The samples of the bands are too few for that: 120 of them tell a
similarity to within 0.04 only.) Candidates are screened by set sizes and by that estimate, with a margin of eight
deviations of the sampling and five of the bits that cancel, then confirmed by counting the intersection of the full sets.

Buckets are never expanded into all pairs. First every member is compared with a leader of its bucket; confirmed links
are merged into components. This repeats with other leaders. Then only members of different components that still share
a bucket are left, and those are compared in blocks of bounded size, by their sketches, before anything is emitted.
Tables of one row per class, bucket or document are stored before they are joined, so that both sides of every join are
plain exchanges, and Spark's adaptive execution deals a class, bucket or leader with very many rows over several tasks.

With 30 bands of 4 rows a pair of similarity 0.8 shares no bucket with a probability of about 1.4e-7.

Defined cases: null texts and texts without words have an empty set, link with nothing and stay; a null id is linked
with nothing and stays; rows that share an id are one document with several sets; repeated rows are alike; an empty
table gives an empty result; of documents that tie as a leader the least id leads; columns other than id and text are
not read, so they may have any name; a very long text is hashed a block at a time, and its set is what one task must hold.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from placelink.llm import common as c
from placelink.llm.common import stored, table
from placelink.operators.components import components
from placelink.operators.storage import forget

BANDS, ROWS, SKETCH_BITS, BIN_BITS = 30, 4, 4096, 13
SAMPLES, BINS = BANDS * ROWS, 1 << BIN_BITS
#: Rows of a bucket that are compared with each other in one task.
BLOCK = 2048
#: Rounds of comparing with a leader before the rest is compared in blocks.
LEADER_ROUNDS = 2

_SEEDS = np.random.default_rng(7).integers(0, 2**63, (2, SAMPLES), dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_sets(data: np.ndarray, at: np.ndarray, size: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of every text (lower-cased A-Z; fewer words than `size` are one shingle)."""
    data = c.lower_ascii(data)
    starts, ends, of = c.word_spans(data, at)
    hashes = c.span_hashes(data, starts, ends)
    rolled = c.runs(hashes, size)
    cut = np.searchsorted(of, np.arange(len(at)))
    out = []
    for i, j in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
        if j - i >= size:
            out.append(np.unique(rolled[i : j - size + 1]))
        elif j > i:
            short = np.uint64(j - i)
            for h in hashes[i:j]:
                short = c.mix(np.array([short]))[0] ^ h
            out.append(np.array([short]))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def minhash(sets: list[np.ndarray]) -> np.ndarray:
    """SAMPLES minima per (non-empty) set, each under a bijection of its own."""
    all_hashes = np.concatenate(sets)
    at = np.cumsum([0, *map(len, sets[:-1])])
    out = np.empty((len(sets), SAMPLES), np.uint64)
    for k in range(SAMPLES):
        out[:, k] = np.minimum.reduceat((all_hashes ^ _SEEDS[0, k]) * _SEEDS[1, k], at)
    return out


def band_keys(samples: np.ndarray) -> np.ndarray:
    keys = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64), (len(samples), BANDS)).copy()
    for r in range(ROWS):
        keys = c.mix(keys ^ samples[:, r::ROWS])
    return keys


def odd_sketch(members: np.ndarray) -> tuple[np.ndarray, int]:
    """The odd sketch of a (sorted) set, 64 bits a word, and its number of samples.

    The samples are those of one-permutation MinHash: the least hash in each of BINS ranges. Each flips one bit.
    """
    spot = members >> np.uint64(64 - BIN_BITS)
    least = members[np.r_[True, spot[1:] != spot[:-1]]]
    odd = (np.bincount((least % np.uint64(SKETCH_BITS)).astype(np.int64), minlength=SKETCH_BITS) & 1).astype(np.uint8)
    return np.packbits(odd).view(np.int64), len(least)


def most_bits(n_a, n_b, s_a, s_b, percent: int, m=np):
    """The largest population count that sets of n_a and n_b members, s_a and s_b samples show at that similarity.

    Expected samples that differ, plus eight deviations of sampling and five of bits that cancel. m: numpy or Spark functions.
    """
    j = percent / 100
    union = (n_a + n_b) / (1 + j)
    expected = BINS * (2 - m.exp(-n_a / BINS) - m.exp(-n_b / BINS))
    used = BINS * (1 - m.exp(-union / BINS)) * (s_a + s_b) / expected  # ranges in use, corrected by what the two show
    spread = m.sqrt(used * (j * (1 - j)) * (1 - used / (union + 1)) + 0.25)
    unlike = s_a + s_b - 2 * j * used + 8 * spread
    odd = SKETCH_BITS / 2 * (1 - m.exp(-2 * unlike / SKETCH_BITS)) + 5 * m.sqrt(unlike * unlike / SKETCH_BITS + 1)
    return np.minimum(odd, unlike) if m is np else F.least(odd, unlike)  # bits that cancel never add to the count


def sketch_similarity(bits: int, s_a: int, s_b: int) -> float:
    """Jaccard similarity of the samples of two odd sketches, from the population count of their XOR."""
    unlike = -SKETCH_BITS / 2 * math.log(max(1 - 2 * bits / SKETCH_BITS, 1e-9))
    same = max(0.0, (s_a + s_b - unlike) / 2)
    return same / max(1e-9, s_a + s_b - same)


def signatures(docs: DataFrame, size: int) -> DataFrame:
    """doc_id, n, set_a, set_b (128-bit identity of the set), bands, sketch, samples. Empty sets have null bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, at in c.chunks(batch.column("text")):
                sets = shingle_sets(data, at, size)
                full = [k for k, s in enumerate(sets) if len(s)]
                ids = np.zeros((len(sets), 2), np.int64)
                bands: list = [None] * len(sets)
                sketches: list = [None] * len(sets)
                samples = [0] * len(sets)
                if full:
                    for k, keys in zip(full, band_keys(minhash([sets[k] for k in full])).view(np.int64), strict=True):
                        ids[k] = np.frombuffer(xxhash.xxh3_128_digest(sets[k].tobytes()), np.int64)
                        bands[k], (sketches[k], samples[k]) = keys, odd_sketch(sets[k])
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(i, j - i).cast(pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array(ids[:, 0]), pa.array(ids[:, 1]), pa.array(bands, pa.list_(pa.int64())), pa.array(sketches, pa.list_(pa.int64())), pa.array(samples, pa.int64())],
                    names=["doc_id", "n", "set_a", "set_b", "bands", "sketch", "samples"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n long, set_a long, set_b long, bands array<long>, sketch array<long>, samples long")


def full_sets(docs: DataFrame, size: int) -> DataFrame:
    """doc_id and the full set of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, at in c.chunks(batch.column("text")):
                sets = shingle_sets(data, at, size)
                ends = np.cumsum([0, *map(len, sets)]).astype(np.int32)
                values = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(sets).view(np.int64) if sets else np.zeros(0, np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i).cast(pa.int64()), values], names=["doc_id", "members"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, members array<long>")


def _screen(pairs: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) that sizes and sketches allow."""
    side = lambda x: classes.select(F.col("rep").alias(x), F.col("n").alias(f"n_{x}"), F.col("samples").alias(f"s_{x}"), F.col("sketch").alias(f"sketch_{x}"))
    bits = F.aggregate(F.zip_with("sketch_a", "sketch_b", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
    sizes = 100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b")
    both = pairs.join(side("a"), "a").join(side("b"), "b")
    return both.where(sizes & (bits <= most_bits(F.col("n_a"), F.col("n_b"), F.col("s_a"), F.col("s_b"), percent, F))).select("a", "b")


def _confirmed(pairs: DataFrame, docs: DataFrame, size: int, percent: int) -> DataFrame:
    """Pairs (a, b) whose full sets reach the similarity; sets are built for the documents in question only."""
    pairs = stored(pairs, "neardup-pairs")
    ids = pairs.select(F.col("a").alias("doc_id")).distinct().unionByName(pairs.select(F.col("b").alias("doc_id")).distinct()).distinct()
    sets = stored(full_sets(docs.select("doc_id", "text").join(ids, "doc_id", "left_semi"), size), "neardup-sets", "lz4")
    both = pairs.join(sets.select(F.col("doc_id").alias("b"), F.col("members").alias("set_b")), "b")
    both = both.join(sets.select(F.col("doc_id").alias("a"), F.col("members").alias("set_a")), "a")
    common = F.size(F.array_intersect("set_a", "set_b"))
    out = stored(both.where(100 * common >= percent * (F.size("set_a") + F.size("set_b") - common)).select("a", "b").distinct(), "neardup-links")
    forget(pairs, sets)
    return out


def _blocks(members: DataFrame, total: int, percent: int) -> DataFrame:
    """members (key, parts, rep, comp, n, samples, sketch, bands), total rows: pairs of different components that sizes and sketches allow.

    A bucket of more than BLOCK members is dealt into parts; every two parts meet in a task of their own. A pair that
    shares several buckets belongs to the first of them.
    """

    def block(key: int, rep: np.ndarray, comp: np.ndarray, n: np.ndarray, part: np.ndarray, samples: np.ndarray, sketch: np.ndarray, bands: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of one block, its rows ordered by n."""
        two = part.min() != part.max()
        end = np.searchsorted(n, n * 100 // percent, side="right")
        for i in range(len(rep) - 1):
            j = np.arange(i + 1, max(i + 1, end[i]))
            j = j[comp[j] != comp[i]]
            if two:
                j = j[part[j] != part[i]]
            if len(j):
                j = j[np.bitwise_count(sketch[j] ^ sketch[i]).sum(axis=1) <= most_bits(n[i], n[j], samples[i], samples[j], percent)]
            if len(j):
                j = j[bands[i][(bands[j] == bands[i]).argmax(axis=1)] == key]
                yield np.minimum(rep[i], rep[j]), np.maximum(rep[i], rep[j])

    def run(task: pa.Table) -> pa.Table:
        task = task.sort_by([(k, "ascending") for k in ("key", "low", "high", "n", "rep")]).combine_chunks()
        key, low, high, *rest = (task.column(k).to_numpy() for k in ("key", "low", "high", "rep", "comp", "n", "part", "samples"))
        wide = [task.column(k).combine_chunks().flatten().to_numpy().reshape(len(key), -1) for k in ("sketch", "bands")]
        columns = [*rest, wide[0].view(np.uint64), wide[1]]
        cuts = np.flatnonzero((key[1:] != key[:-1]) | (low[1:] != low[:-1]) | (high[1:] != high[:-1])) + 1
        found = [p for i, j in zip([0, *cuts], [*cuts, len(key)], strict=True) for p in block(key[i], *(x[i:j] for x in columns))]
        none = np.zeros(0, np.int64)
        return pa.table({k: np.concatenate([none, *(p[x] for p in found)]) for x, k in enumerate("ab")})

    dealt = members.withColumn("part", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("parts") - 1))
    dealt = dealt.withColumn("other", other).withColumns({"low": F.least("part", "other"), "high": F.greatest("part", "other")})
    # small blocks share a task: what a task reads stays about one block of the largest size
    tasks = F.lit(1 + total // BLOCK)
    dealt = dealt.withColumn("task", F.pmod(F.xxhash64("key", "low", "high"), tasks))
    return dealt.groupBy("task").applyInArrow(run, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id (least id reachable over links), kept (the document that stays)."""
    found = stored(signatures(docs, size), "neardup-signatures")
    live = found.where("n > 0 and doc_id is not null")
    classes = stored(live.groupBy("set_a", "set_b").agg(F.min("doc_id").alias("rep")), "neardup-sets-by-id")
    equal = live.select("doc_id", "set_a", "set_b").join(classes, ["set_a", "set_b"])
    links = equal.where("doc_id != rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))  # equal sets
    firsts = live.join(classes.withColumnRenamed("rep", "doc_id"), ["set_a", "set_b", "doc_id"], "left_semi")
    reps = stored(firsts.dropDuplicates(["set_a", "set_b"]).select(F.col("doc_id").alias("rep"), "n", "samples", "bands", "sketch"), "neardup-classes")
    buckets = reps.select("rep", F.explode("bands").alias("key"))
    shared = stored(buckets.groupBy("key").agg(F.count("*").alias("members")).where("members > 1").select("key"), "neardup-shared")
    buckets = stored(buckets.join(shared, "key", "left_semi"), "neardup-buckets")

    found_links = None
    for turn in range(LEADER_ROUNDS + 1):
        if found_links is None:
            rest = buckets.withColumn("comp", F.col("rep"))
        else:
            comps = components(found_links)
            rest = stored(buckets.join(comps, buckets["rep"] == comps["id"], "left").select("rep", "key", F.coalesce("component", "rep").alias("comp")), "neardup-rest")
        first = F.struct(F.xxhash64("rep", F.lit(turn)) if turn else F.lit(0), F.col("rep"), F.col("comp"))
        per = rest.groupBy("key").agg(F.count("*").alias("n"), F.min("comp").alias("x"), F.max("comp").alias("y"), F.min(first).alias("leader"))
        per = stored(per.where("x != y").select("key", "n", F.col("leader.rep").alias("leader"), F.col("leader.comp").alias("of")), "neardup-leaders")
        if turn < LEADER_ROUNDS:
            pairs = rest.join(per, "key").where("comp != of").select(F.least("rep", "leader").alias("a"), F.greatest("rep", "leader").alias("b")).distinct()
            pairs = _screen(pairs, reps, percent)
        else:
            left = per.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
            rest = rest.join(per.select("key", F.ceil(F.col("n") / BLOCK).cast("int").alias("parts")), "key")
            sketches = reps.select("rep", "n", "samples", "sketch", "bands")
            pairs = _blocks(rest.join(sketches, "rep").select("key", "parts", "rep", "comp", "n", "samples", "sketch", "bands"), left, percent)
        new = _confirmed(pairs, docs, size, percent)
        found_links = new if found_links is None else found_links.unionByName(new)
    comps = components(found_links.unionByName(links))
    comps = comps.select(F.col("id").alias("doc_id"), "component")
    out = found.select("doc_id", F.col("n").alias("n_shingles")).join(comps, "doc_id", "left")
    out = out.withColumn("component_id", F.when(F.col("n_shingles") > 0, F.coalesce("component", "doc_id")).otherwise(F.col("doc_id")))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contract's shingles: two words."""
    return near_duplicates(table(spark, sf_dir, "documents"), size=2)


OP1_SQL = r"""
WITH RECURSIVE split AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS MATERIALIZED (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 1 THEN w ELSE list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) END) AS shingle FROM split),
sizes AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM sets GROUP BY doc_id),
links AS MATERIALIZED (
  SELECT a.doc_id AS a, b.doc_id AS b FROM (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM sets a JOIN sets b ON a.shingle = b.shingle AND a.doc_id < b.doc_id GROUP BY ALL) j
  JOIN sizes a ON a.doc_id = x JOIN sizes b ON b.doc_id = y WHERE 100 * c >= 80 * (a.n + b.n - c)),
both_ways AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach(x, y) AS (SELECT doc_id, doc_id FROM documents UNION SELECT x, b FROM reach JOIN both_ways ON y = a)
SELECT d.doc_id, coalesce(s.n, 0) AS n_shingles, r.least AS component_id, d.doc_id = r.least AS kept
FROM documents d LEFT JOIN sizes s USING (doc_id) JOIN (SELECT x AS doc_id, min(y) AS least FROM reach GROUP BY x) r USING (doc_id)
"""
