"""Streams of places and events: deduplication, linkage against a reference, windows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from placelink.functions.similarity import address_sim, clean_text, text_sim
from placelink.operators.blocking import Root, assign_cells
from placelink.operators.cutoff import MOST_BROADCAST


def read_stream(spark: SparkSession, path: str, schema: str, fmt: str = "parquet", files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.format(fmt).schema(schema).option("maxFilesPerTrigger", files_per_batch).load(path)


def dedup_places(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """The first arrival of every place within the watermark."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["eid"])


def arrivals(stream: DataFrame, kind: str = "tumbling", delay: str | None = "1 hour") -> DataFrame:
    """Arrivals by window: tumbling (1 hour), sliding (1 hour every 30 minutes) or session (gap 30 minutes, per user)."""
    marked = stream.withWatermark("ts", delay) if delay else stream
    if kind == "session":
        g = marked.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id")
        return g.agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")
    window = F.window("ts", "1 hour") if kind == "tumbling" else F.window("ts", "1 hour", "30 minutes")
    return marked.groupBy(window.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def link_stream(stream: DataFrame, reference: DataFrame, root: Root, level: int, ranked: DataFrame, k: int, attrs: tuple[str, ...] = ("name_sim", "address_sim")) -> DataFrame:
    """Arriving places against a reference set, on blocks of a fixed root; vectors are looked up in a frozen ranking.

    A vector that the ranking has not seen gets one more than the deepest layer of those that dominate it. The ranking's
    distinct vectors are broadcast; more than MOST_BROADCAST are an error.
    """
    cells = assign_cells(reference.select("eid", "x_m", "y_m", "name", "address"), root, level, 0.25)
    ref = cells.select(F.col("eid").alias("eid_b"), F.col("name").alias("name_b"), F.col("address").alias("address_b"), "ix", "iy", F.col("low_ix").alias("lx"), F.col("low_iy").alias("ly"))
    new = assign_cells(stream, root, level, 0.25)
    pairs = new.join(ref, ["ix", "iy"]).where((F.col("eid") != F.col("eid_b")) & (F.col("ix") == F.greatest("low_ix", "lx")) & (F.col("iy") == F.greatest("low_iy", "ly")))
    pairs = pairs.select(
        "eid", "eid_b",
        F.round(text_sim(clean_text(F.col("name")), clean_text(F.col("name_b"))), 6).alias("name_sim"),
        F.round(address_sim(F.col("address"), F.col("address_b")), 6).alias("address_sim"),
    )
    return placed(pairs, ranked, attrs).withColumn("match", F.col("layer") <= k)


def placed(pairs: DataFrame, ranked: DataFrame, attrs: tuple[str, ...]) -> DataFrame:
    """pairs with the layer that a frozen ranking gives their vectors; pairs may be a stream."""
    rows = ranked.where("layer is not null").select(*attrs, "layer").distinct()
    if rows.count() > MOST_BROADCAST:
        raise ValueError(f"more than {MOST_BROADCAST} distinct vectors; round the similarities of the ranking")
    known = rows.toPandas()
    shared = rows.sparkSession.sparkContext.broadcast((known[list(attrs)].to_numpy(float), known["layer"].to_numpy(int)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vectors, layer = shared.value
        for batch in batches:
            x = np.stack([batch.column(a).to_numpy(zero_copy_only=False) for a in attrs], axis=1)
            own, at = np.unique(x, axis=0, return_inverse=True)
            found = np.zeros(len(own), np.int32)
            for i, v in enumerate(own):
                above = (vectors >= v).all(axis=1)
                found[i] = layer[above].max(initial=0) + (not (vectors[above] == v).all(axis=1).any())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found[at.ravel()])], names=[*batch.schema.names, "layer"])

    return pairs.mapInArrow(run, T.StructType([*pairs.schema.fields, T.StructField("layer", T.IntegerType())]))


def sink(df: DataFrame, write, checkpoint: str, mode: str = "append"):
    """foreachBatch with a checkpoint: `write(batch, number)` runs once per batch number."""
    return df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).foreachBatch(write).start()
