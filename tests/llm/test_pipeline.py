"""The pipeline's stages: schemas, decisions that take effect, and the same rows as stages run by hand."""

import corpus_pipeline as cp
from pyspark.sql import functions as F

from placelink.llm import mixing, neardup
from placelink.llm.common import n_words

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in cp.STAGES:
        before, docs = docs, cp.stored(stage(spark, docs, SF), f"test-{name}")
        if name != "packing":
            assert docs.columns == before.columns == list(cp.COLUMNS)
        if name in ("toxicity", "quality", "near_duplicates"):
            assert 0.6 * before.count() < docs.count() <= before.count()
            assert docs.exceptAll(before).count() == 0
        if name == "near_duplicates":
            kept = {r.doc_id for r in neardup.near_duplicates(before).where("kept").collect()}
            assert {r.doc_id for r in docs.collect()} == kept
        if name == "mixing":
            own = before.select("doc_id", "source", n_words(F.col("text")).alias("size"))
            target = {r.source: r.target for r in mixing.source_targets(own).collect()}
            taken = {r.source: r.n for r in docs.groupBy("source").agg(F.sum(n_words(F.col("text"))).alias("n")).collect()}
            longest = own.agg(F.max("size")).first()[0]
            assert all(abs(taken.get(s, 0) - t) <= longest for s, t in target.items())
    assert docs.select(F.sum("length")).first()[0] > 0


def text(seed, n=40):
    return " ".join(f"w{(seed * 7919 + i * i * 31 + i) % 99991}" for i in range(n))


def rows_of(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_mixing_keeps_null_repeated_and_conflicting_ids(spark):
    clean = [(i, text(i), "en", "ab"[i % 2], 1) for i in range(200)]
    null_ids = [(None, text(1000 + i), "en", "ab"[i % 2], 1) for i in range(60)]
    repeated = [(7, text(7), "en", "b", 1)] * 20
    conflicting = [(8, text(2000 + i), "en", "a", 1) for i in range(20)]
    docs = spark.createDataFrame(clean + null_ids + repeated + conflicting, "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    sizes = docs.select("doc_id", "source", n_words(F.col("text")).alias("size"))
    target = {r.source: r.target for r in mixing.source_targets(sizes).collect()}
    got = cp.mix_sources(spark, docs, SF)
    taken = {r.source: r.n for r in got.groupBy("source").agg(F.sum(n_words(F.col("text"))).alias("n")).collect()}
    assert all(abs(taken[s] - t) <= 40 for s, t in target.items())
    assert got.where("doc_id is null").count() > 0
    assert got.groupBy("doc_id", "text").count().where("doc_id != 7 or doc_id is null").agg(F.max("count")).first()[0] <= mixing.MAX_COPIES
    assert rows_of(got) == rows_of(cp.mix_sources(spark, docs.repartition(5), SF))


def test_near_duplicates_of_null_repeated_and_conflicting_ids(spark):
    near = text(1).rsplit(" ", 1)[0] + " other"
    rows = [
        (1, text(1), "en", "a", 1), (1, text(2), "en", "a", 1), (1, text(3), "en", "a", 1),  # different texts under one id
        (2, near, "en", "a", 1), (2, text(4), "en", "a", 1),  # only the first is a near-duplicate
        (3, text(5), "en", "a", 1), (3, text(5), "en", "a", 1),  # a repeated row
        (None, text(6), "en", "a", 1), (None, text(6), "en", "a", 1), (None, text(2), "en", "a", 1), (None, None, "en", "a", 1),
    ]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    want = [rows[0], rows[1], rows[2], rows[4], rows[5], rows[7], rows[10]]
    assert rows_of(cp.drop_near_duplicates(spark, docs, SF)) == sorted(want, key=repr)


def test_run_twice_agrees(spark):
    rows = lambda: sorted(map(tuple, cp.run(spark, SF).select("doc_id", "start", "length", "ids_crc32").collect()))
    assert rows() == rows()


ODD = [
    (1, None, None, None, None), (None, text(50), "en", "a", 12), (None, text(51), "en", "a", 12), (2, "", "en", None, 0), (3, " \n\t ", "en", "a", 4), (4, "one", "en", "a", 3),
    (5, text(52) + " word" * 60_000, "en", "b", 300_000), (6, "x" * 1_500_000, "en", "b", 1_500_000), (7, text(53), "en", "b", 23), (7, text(53), "en", "b", 23), (7, text(54), "en", "b", 23),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def test_filters_judge_every_row_by_its_own_text(spark):
    """A clean text that shares its id with a rejected one stays; the scores of a row are those of its text alone."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").select(*cp.COLUMNS)
    odd = spark.createDataFrame(ODD, SCHEMA)
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    toxic = cp.toxicity.score(docs, cp.toxicity.toxicity_model(docs, labels)).where("score >= 0.7").first().doc_id
    bad = docs.where(F.col("doc_id") == toxic).first()
    same_id = spark.createDataFrame([(None, bad.text, "en", "a", 1), (int(toxic), text(60), "en", "a", 1)], SCHEMA)
    every = docs.unionByName(odd).unionByName(same_id)
    for stage, module, model, keep in ((cp.drop_toxic, cp.toxicity, "toxicity_model", lambda s: s < 0.7), (cp.drop_low_quality, cp.boosting, "quality_model", lambda s: s >= 0.3)):
        fitted = getattr(module, model)(every, labels)
        rows = every.collect()
        alone = spark.createDataFrame([(i, r.text) for i, r in enumerate(rows)], "doc_id long, text string")
        score = {r.doc_id: r.score for r in module.score(alone, fitted).collect()}
        want = sorted(map(repr, (tuple(r) for i, r in enumerate(rows) if keep(score[i]))))
        assert sorted(map(repr, map(tuple, stage(spark, every, SF).collect()))) == want
    kept = cp.drop_toxic(spark, every, SF)
    assert kept.where(F.col("text") == text(60)).count() == 1 and kept.where(F.col("text") == bad.text).count() == 0


def test_stages_on_odd_and_empty_input(spark):
    odd = spark.createDataFrame(ODD, SCHEMA).withColumns({k: F.lit("clash") for k in ("score", "__row", "size", "queue", "n")})
    for name, stage in cp.STAGES:
        got, none = stage(spark, odd, SF), stage(spark, odd.limit(0), SF)
        assert none.count() == 0 and none.columns == got.columns
        if name == "near_duplicates":
            assert got.count() == len(ODD) - 1  # the repeated row
        if name == "packing":
            assert got.where("start = 0").count() == len(ODD) and got.agg(F.sum("length")).first()[0] > 60_000
        if name in ("toxicity", "quality"):
            assert got.exceptAll(odd.select(*cp.COLUMNS)).count() == 0
