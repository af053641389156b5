"""Test inputs derived from the given tables by integer arithmetic (FIXTURES.md)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from placelink.functions.similarity import clean_phone, clean_website
from placelink.sources.tables import table

TOWN, SPREAD = 900, 600
COUNTRY = "45"


def _bits(t: Column, first: int) -> Column:
    return sum((F.floor(t / 2 ** (first + 2 * i)) % 2 * 2**i for i in range(6)), F.lit(0)).cast("bigint")


def places(spark: SparkSession, sf_dir: str) -> DataFrame:
    """every part is a catalogue place; line items of 49 or more are listings of it in three more sources."""
    k, o, s = F.col("p_partkey"), F.col("l_orderkey"), F.col("l_suppkey")
    t = F.floor(k / 80).cast("bigint")
    part = table(spark, sf_dir, "part").select(
        "p_partkey", "p_size", "p_type", t.alias("t"), F.split("p_name", " ")[1].alias("noun"),
        F.concat("p_name", F.lit(" "), F.regexp_replace(F.lower("p_brand"), "brand#", "no")).alias("base"),
        (TOWN * _bits(t, 0) + k * 7919 % SPREAD).alias("x"), (TOWN * _bits(t, 1) + k * 104729 % SPREAD).alias("y"),
    )
    here = F.concat(F.lit("street "), F.col("p_size"), F.lit(" zone "), F.col("t"))
    number = (5550000 + 7 * k).cast("string")
    catalogue = part.select(
        F.concat(F.lit("C"), k).alias("eid"), F.lit("catalog").alias("source"), k.alias("truth_id"), F.col("x").alias("x_m"), F.col("y").alias("y_m"),
        F.col("base").alias("name"), here.alias("address"), F.array("noun").alias("keywords"),
        F.when(k % 6 != 0, number).alias("phone"), F.when(k % 4 != 0, F.concat(F.lit("http://www.place"), k, F.lit(".example.com"))).alias("website"),
    )
    lines = table(spark, sf_dir, "lineitem").where("l_quantity >= 49").select("l_orderkey", "l_linenumber", "l_suppkey", "l_partkey")
    far = F.when(o % 10 == 0, 3).otherwise(1)
    base = F.col("base")
    name = (
        F.when(o % 6 == 1, F.concat(base, F.lit(" ltd"))).when(o % 6 == 2, F.substring(base, 3, 1000)).when(o % 6 == 3, F.regexp_replace(base, "e", "a"))
        .when(o % 6 == 4, F.concat("noun", F.lit(" house"))).when(o % 6 == 5, F.concat("p_type", F.lit(" "), base)).otherwise(base)
    )
    wrong = F.concat(F.lit("street "), F.col("p_size") + 1, F.lit(" zone "), F.col("t"))
    address = F.when(s % 5 == 0, F.lit(None)).when(s % 5 == 1, F.concat(here, F.lit(" north"))).when(s % 5 == 2, wrong).otherwise(here)
    call = F.when(o % 23 == 0, 5550000 + 7 * (k + 1)).otherwise(5550000 + 7 * k).cast("string")
    shown = F.when(s % 3 == 0, F.concat(F.lit("+45 "), call)).when(s % 3 == 1, F.concat(F.lit("0045"), call)).otherwise(F.concat(F.substring(call, 1, 3), F.lit(" "), F.substring(call, 4, 9)))
    listings = lines.join(part, F.col("l_partkey") == k).select(
        F.concat(F.lit("L"), o, F.lit("-"), F.col("l_linenumber")).alias("eid"), F.concat(F.lit("src"), s % 3).alias("source"), k.alias("truth_id"),
        (F.col("x") + far * (31 * o % 61 - 30)).alias("x_m"), (F.col("y") + far * (17 * o % 61 - 30)).alias("y_m"),
        name.alias("name"), address.alias("address"), F.when(o % 7 == 0, F.array(F.lower("p_type"))).otherwise(F.array("noun")).alias("keywords"),
        F.when(s % 4 != 0, shown).alias("phone"), F.when(s % 3 != 0, F.concat(F.lit("https://m.place"), k, F.lit(".example.com/?ref="), s)).alias("website"),
    )
    out = catalogue.unionByName(listings)
    return out.withColumns({"phone_clean": clean_phone(F.col("phone"), COUNTRY), "website_clean": clean_website(F.col("website"))})


def places_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F1b: with degrees."""
    return places(spark, sf_dir).withColumns({"lon": 10.0 + F.col("x_m") / 60000, "lat": 57.0 + F.col("y_m") / 111000})


def places_coincident(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F1c: malls, many places on the same point."""
    return places(spark, sf_dir).withColumns({"x_m": F.col("x_m") - F.col("x_m") % 300, "y_m": F.col("y_m") - F.col("y_m") % 300})


def points(spark: SparkSession, sf_dir: str, copies: int = 1, side: int = 11_790) -> DataFrame:
    """points spread over an area of a given side, the orders replicated `copies` times."""
    o, u, r = F.col("o_orderkey"), F.col("o_custkey"), F.col("r")
    rows = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("r"))
    return rows.select((o * copies + r).alias("eid"), ((7919 + 2 * r) * o % side).alias("x_m"), ((104729 * u + (31 + 6 * r) * o) % side).alias("y_m"))


def doc_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """shares of letters, distinct words, distinct lines and length of labelled documents (ASCII letters only)."""
    d = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id")
    words, lines = F.split("text", " "), F.split("text", "\n")
    text = F.col("text")
    third = lambda c: F.floor(c * 1000 + 0.5) / 1000  # noqa: E731  rounds alike in every engine
    return d.select(
        "doc_id",
        third(F.length(F.regexp_replace(text, "[^A-Za-z]", "")) / F.greatest(F.length(text), F.lit(1))).alias("f_letters"),
        third(F.size(F.array_distinct(words)) / F.size(words)).alias("f_unique_words"),
        third(F.size(F.array_distinct(lines)) / F.size(lines)).alias("f_unique_lines"),
        third(F.least(F.length(text), F.lit(2000)) / 2000).alias("f_length"),
        F.col("quality").alias("label"),
    )


def embedding_pairs(spark: SparkSession, sf_dir: str, partners: int = 3) -> DataFrame:
    """cosines of four parts of the vectors, rescaled to [0, 1], of every vector and the next few ids; a control without signal."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    e = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v")).where("v is not null")
    a = e.select(F.col("vec_id").alias("id_a"), F.col("label").alias("label_a"), F.col("v").alias("va"), F.explode(F.sequence(F.col("vec_id") + 1, F.col("vec_id") + partners)).alias("id_b"))
    b = e.select(F.col("vec_id").alias("id_b"), F.col("label").alias("label_b"), F.col("v").alias("vb"))
    parts = {}
    for i in range(4):
        x, y = F.slice("va", 16 * i + 1, 16), F.slice("vb", 16 * i + 1, 16)
        parts[f"s{i + 1}"] = F.floor((dot(x, y) / F.sqrt(dot(x, x) * dot(y, y)) + 1) / 2 * 10000.0 + 0.5) / 10000.0
    return a.join(b, "id_b").select("id_a", "id_b", *[c.alias(n) for n, c in parts.items()], (F.col("label_a") == F.col("label_b")).cast("int").alias("label"))


def taxonomy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """term, parent. The root has no parent; `ring` and `rod` have two."""
    part, customer = table(spark, sf_dir, "part"), table(spark, sf_dir, "customer")
    own = lambda c, p: (F.lower(c).alias("term"), F.lit(p).alias("parent"))
    rows = spark.createDataFrame([("root", None), ("shape", "root"), ("make", "root"), ("trade", "root"), ("ring", "trade"), ("rod", "make")], "term string, parent string")
    rows = rows.unionByName(part.select(*own(F.split("p_name", " ")[1], "shape")).distinct()).unionByName(part.select(*own(F.col("p_type"), "make")).distinct())
    rows = rows.unionByName(customer.select(*own(F.col("c_mktsegment"), "trade")).distinct())
    region, nation = table(spark, sf_dir, "region"), table(spark, sf_dir, "nation")
    rows = rows.unionByName(region.select(F.lower("r_name").alias("term"), F.lit("root").alias("parent")))
    return rows.unionByName(nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")).select(F.lower("n_name").alias("term"), F.lower("r_name").alias("parent")))


def term_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """term, n."""
    part, customer = table(spark, sf_dir, "part"), table(spark, sf_dir, "customer")
    terms = part.select(F.lower(F.split("p_name", " ")[1]).alias("term")).unionByName(part.select(F.lower("p_type").alias("term"))).unionByName(customer.select(F.lower("c_mktsegment").alias("term")))
    return terms.groupBy("term").agg(F.count("*").alias("n"))


class PlaceFixtureSource(DataSource):
    """`spark.read.format("place_fixture").option("n", ...)`: places on the fly, without any table."""

    @classmethod
    def name(cls) -> str:
        return "place_fixture"

    def schema(self) -> str:
        return "eid string, source string, truth_id bigint, x_m bigint, y_m bigint, name string"

    def reader(self, schema) -> DataSourceReader:
        return _PlaceFixtureReader(int(self.options.get("n", 1000)), int(self.options.get("parts", 4)))


class _PlaceFixtureReader(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.n, self.parts = n, parts

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        for k in range(partition.value, self.n, self.parts):
            yield (f"G{k}", f"src{k % 3}", k // 2, 7919 * (k // 2) % 6000 + k % 2 * 5, 104729 * (k // 2) % 6000, f"place no{k // 2}")
