"""Reading places and the given tables; places from several sources keep their own attributes."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

PLACE_SCHEMA = (
    "eid string, source string, lon double, lat double, x_m double, y_m double, name string, address string, website string, "
    "phone string, keywords array<string>, opened date, hours array<struct<open:timestamp,close:timestamp>>, attrs map<string,string>, truth_id bigint"
)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_places(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = PLACE_SCHEMA, **options: str) -> DataFrame:
    """Places in parquet, orc, json or csv. The schema is explicit (csv has no arrays: give a flat one)."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def union_sources(*sources: DataFrame) -> DataFrame:
    """Places of several sources; attributes that a source lacks are null."""
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), sources)


def write_places(places: DataFrame, path: str, by: str = "source") -> None:
    places.write.mode("overwrite").partitionBy(by).parquet(path)


def write_pairs_bucketed(pairs: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed by the first id, so that later joins on it need no shuffle."""
    pairs.write.mode("overwrite").bucketBy(buckets, "eid_a").sortBy("eid_a").saveAsTable(name)


def dataset_bytes(df: DataFrame) -> int:
    """Bytes of the files a DataFrame reads, from the optimizer's statistics."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def noop(df: DataFrame) -> None:
    """Runs a plan and throws the rows away (benchmarks)."""
    df.write.format("noop").mode("overwrite").save()


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with their JSON attribute k."""
    return table(spark, sf_dir, "events").withColumns({"ts": F.col("ts").cast("timestamp")}).withColumn("k", F.from_json("props", "k int")["k"])
