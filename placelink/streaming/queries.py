"""Streaming workloads run to their end over the given events, so that they can be held against their batch form."""

from __future__ import annotations

import uuid
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from placelink.operators.blocking import root_box
from placelink.operators.cutoff import level_curve, sweep_cut
from placelink.operators.layers import collapse, layers
from placelink.operators.storage import shared_dir, stored
from placelink.plans.experiments import compared, places
from placelink.sources import fixtures
from placelink.sources.tables import events
from placelink.streaming.streams import arrivals, dedup_places, link_stream

#: Fixed value: how far the watermark stays behind where no row is to count as late.
LONG = "100000 days"


def place_events(s: SparkSession, d: str) -> DataFrame:
    """events as arriving places; the catalogue place whose number the event's is, modulo their count."""
    p = fixtures.places(s, d).where("source = 'catalog'").select("eid", "x_m", "y_m", "name", "address", F.col("truth_id").alias("i"))
    n = p.count()
    return events(s, d).select("event_id", "ts", "user_id", (F.col("event_id") % max(1, n)).alias("i")).join(p, "i").select("event_id", "ts", "user_id", "eid", "x_m", "y_m", "name", "address")


def _run(s: SparkSession, arriving: list[DataFrame], make, complete: bool = False) -> DataFrame:
    """Streams the frames one after the other, a batch for each, and returns what came out.

    Append mode goes to a file sink; complete mode keeps the result of the last batch.
    """
    at = f"{shared_dir(s)}/stream-{uuid.uuid4().hex}"
    for rows in arriving:
        (rows if len(arriving) == 1 else rows.coalesce(1)).write.mode("append").parquet(f"{at}/in")
    source = s.readStream.schema(arriving[0].schema)
    out = make((source if len(arriving) == 1 else source.option("maxFilesPerTrigger", 1)).parquet(f"{at}/in"))
    schema = T.StructType(out.schema.fields)
    writer = out.writeStream.option("checkpointLocation", f"{at}/state").trigger(availableNow=True)
    if complete:
        writer = writer.outputMode("complete").foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(f"{at}/out"))
    else:
        writer = writer.outputMode("append").format("parquet").option("path", f"{at}/out")
    writer.start().awaitTermination()
    return s.read.schema(schema).parquet(f"{at}/out")


def stream_places_dedup(s: SparkSession, d: str) -> DataFrame:
    """Each place once, whenever it arrives."""
    return _run(s, [place_events(s, d)], lambda x: dedup_places(x, LONG)).select("eid")


def stream_links(s: SparkSession, d: str) -> DataFrame:
    """Arriving catalogue places, each once, against the listings of the other sources.

    The ranking is that of the pairs at most 30 m apart, cut by their labels; farther pairs have vectors it has not seen.
    """
    attrs = ("name_sim", "address_sim")
    pairs = stored(compared(s, d).where("dist_m <= 30").select(*attrs, "label"), "stream-pairs")
    ranked = stored(layers(collapse(pairs, attrs, "label"), attrs), "stream-ranking")
    k = sweep_cut(level_curve(ranked)).first()["layer"] or 0
    box = root_box(fixtures.places(s, d).select("eid", "x_m", "y_m"))
    return _run(s, [place_events(s, d)], lambda x: link_stream(dedup_places(x, LONG), places(s, d).where("source != 'catalog'"), box, box.level(100), ranked, k, attrs))


def window_arrivals(s: SparkSession, d: str, kind: str) -> DataFrame:
    """The windows' counts of the whole stream."""
    return _run(s, [events(s, d).select("event_id", "ts", "user_id")], lambda x: arrivals(x, kind, LONG), complete=True)


def late_arrivals(s: SparkSession, d: str) -> DataFrame:
    """Hourly counts of a stream in which every fiftieth event before the last day comes after all others: too late.

    The watermark is an hour behind; windows it has not reached are not closed and not reported. Spark drops rows by the
    watermark of the batch before, so the newest events are a batch between.
    """
    e = events(s, d).select("event_id", "ts", "user_id")
    last = e.agg(F.max("ts").alias("last"))
    late = (F.col("event_id") % 50 == 0) & (F.col("ts") < F.col("last") - F.expr("interval 1 day"))
    turn = F.when(late, 2).when(F.col("ts") == F.col("last"), 1).otherwise(0)
    e = e.join(F.broadcast(last)).withColumn("turn", turn).drop("last")  # one row
    return _run(s, [e.where(F.col("turn") == i).drop("turn") for i in range(3)], lambda x: arrivals(x, "tumbling", "1 hour"))


QUERIES = {
    "stream_places_dedup": stream_places_dedup,
    "stream_links": stream_links,
    **{f"window_arrivals_{k}": partial(window_arrivals, kind=k) for k in ("tumbling", "sliding", "session")},
    "late_arrivals": late_arrivals,
}
