"""A corpus pipeline over `documents`: filters, near-duplicates, mixing, packing.

Every stage works on all rows its predecessor kept, takes (spark, docs, sf_dir) and returns a DataFrame; run() writes
each result as Parquet in the shared folder and rereads it as the next stage's input.

Defined cases, of every stage: a row is a document of its own, whatever its id, so that null ids and ids that repeat, with
the same text or others, lose nothing and take nothing with them; a null text is judged, compared, measured and packed as
an empty one and comes out null; empty and very long texts are treated like others; a null source is a source; rows that
tie in all columns are alike, so that any of them may stay; an empty table gives an empty result; columns beyond those of
documents are dropped at the first stage, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from placelink.llm import boosting, mixing, neardup, packing, toxicity
from placelink.llm.common import n_words, stored, table
from placelink.operators.storage import forget

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: No SQL: the first stages are learned. tests/llm holds the stages against brute force.
ORACLE_SQL = None


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row is judged by its own text."""
    scored = toxicity.score(docs, toxicity.toxicity_model(docs, table(spark, sf_dir, "labels")), COLUMNS)
    return scored.where(F.col("score") < toxicity.DECISION).select(*COLUMNS)


def drop_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row is judged by its own text."""
    scored = boosting.score(docs, boosting.quality_model(docs, table(spark, sf_dir, "labels")), COLUMNS)
    return scored.where(F.col("score") >= boosting.DECISION).select(*COLUMNS)


def _keyed(docs: DataFrame, name: str) -> DataFrame:
    """The documents with a stored number of each row, __row, and a hash of what it says, __tie; ids may be null or repeat."""
    return stored(docs.select(*COLUMNS, F.monotonically_increasing_id().alias("__row"), F.xxhash64(*COLUMNS).alias("__tie")), name)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group stays, that of the least id (null last): five-word shingles, similarity 0.8.

    Rows are compared by their texts, whatever their ids; a row without words is in no group and stays.
    """
    rows = _keyed(docs, "pipeline-rows")
    groups = neardup.near_duplicates(rows.select(F.col("__row").alias("doc_id"), "text")).select(F.col("doc_id").alias("__row"), "component_id")
    first = F.min(F.struct(F.col("doc_id").isNull(), F.col("doc_id"), F.col("__tie"), F.col("__row"))).alias("first")
    stay = groups.join(rows.select("__row", "doc_id", "__tie"), "__row").groupBy("component_id").agg(first).select(F.col("first.__row").alias("__row"))
    return rows.join(stay, "__row", "left_semi").select(*COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Whole documents, as many copies as the mix takes; every row is a document of its own, whatever its id."""
    rows = _keyed(docs, "pipeline-rows")
    sizes = stored(rows.select("__row", "__tie", "doc_id", "source", n_words(F.col("text")).alias("size")), "pipeline-sizes")
    mix = mixing.mix(sizes, mixing.source_targets(sizes), mixing.preference_by_size(F.col("size")), cut=False, ties=("__tie",))
    copies = mix.select("__row", F.expr("cast(copies + if(part > 0, 1, 0) as int)").alias("__copies")).where("__copies > 0")
    return rows.join(copies, "__row").withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__copies")))).select(*COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("quality", drop_low_quality),
    ("near_duplicates", drop_near_duplicates),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        before, docs = docs, stored(stage(spark, docs, sf_dir), f"pipeline-{name}")
        forget(before)  # nothing reads a stage's input any more
    return STAGES[-1][1](spark, docs, sf_dir)
