"""Operators against brute force, exact round trips, held-out accuracy, and the defined cases of odd input."""

import collections
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from placelink.llm import ann, boosting, chat, licenses, mixing, neardup, packing, repetition, reputation, toxicity

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"
#: Nulls everywhere, empty and very long texts, ties and repeated rows.
ODD = [
    (1, None, None, None, None), (None, "no id at all", "en", "a", 12), (2, "", "en", None, 0), (3, " \n\t ", "en", "a", 4),
    (4, "one", "en", "a", 3), (5, "word " * 60_000, "en", "b", 300_000), (6, "x" * 1_500_000, "en", "b", 1_500_000),
    (7, "a b c d e f g h i j k l", "en", "b", 23), (7, "a b c d e f g h i j k l", "en", "b", 23), (8, "A B c d e f g h i j k l", "de", "c", 23),
    (9, "é ß ﬁ İ ΣΊΣ 😀 <|endoftext|> it's", "fr", "c", 30),
]


@pytest.fixture(scope="module")
def odd(spark):
    # columns with clashing names are not read
    return spark.createDataFrame(ODD, DOCS).withColumns({k: F.lit("clash") for k in ("n", "rep", "key", "size", "score", "kept", "queue", "task", "y", "x", "u")})


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def texts(df):
    return {r.doc_id: r.text or "" for r in df.collect()}


def shingles(text, size):
    w = WORD.findall("".join(c.lower() if c.isascii() else c for c in text))
    return frozenset(zip(*(w[i:] for i in range(size)), strict=False)) if len(w) >= size else frozenset([tuple(w)] if w else [])


def components(sets, percent=80):
    ids, root = sorted(sets), {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                p, q = find(a), find(b)
                root[max(p, q)] = min(p, q)
    return {i: find(i) for i in ids}


@pytest.mark.parametrize("size", [2, 5])
def test_near_duplicates_equal_brute_force(spark, docs, size):
    sets = {i: shingles(t, size) for i, t in texts(docs).items()}
    want = components(sets)
    got = neardup.near_duplicates(docs, size).collect()
    assert {r.doc_id: r.component_id for r in got} == want
    assert all(r.n_shingles == len(sets[r.doc_id]) and r.kept == (r.doc_id == want[r.doc_id]) for r in got)


def test_near_duplicates_in_blocks(spark, docs, monkeypatch):
    """The exact way of buckets larger than a block, without any round of leaders."""
    monkeypatch.setattr(neardup, "BLOCK", 3)
    monkeypatch.setattr(neardup, "LEADER_ROUNDS", 0)
    want = components({i: shingles(t, 2) for i, t in texts(docs).items()})
    assert {r.doc_id: r.component_id for r in neardup.near_duplicates(docs, 2).collect()} == want


def test_near_duplicates_odd(spark, odd):
    got = neardup.near_duplicates(odd, 2).collect()
    assert len(got) == len(ODD)
    by = {r.doc_id: r for r in got}
    assert by[1].n_shingles == by[2].n_shingles == by[3].n_shingles == 0 and by[4].n_shingles == by[6].n_shingles == 1
    assert by[8].component_id == 7 and not by[8].kept and by[None].kept and by[5].kept
    assert neardup.near_duplicates(odd.limit(0), 2).count() == 0


def test_odd_sketch_estimates_and_never_screens_out():
    rng = np.random.default_rng(3)
    for n in (5, 40, 150, 400, 1000, 6000):
        errors = []
        for _ in range(50):
            u = rng.integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2)
            a, b = np.unique(u[: int(n * 0.9)]), np.unique(u[int(n * 0.1) :])
            (x, sa), (y, sb) = neardup.odd_sketch(a), neardup.odd_sketch(b)
            bits = int(np.bitwise_count((x ^ y).view(np.uint64)).sum())
            j = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
            errors.append(abs(neardup.sketch_similarity(bits, sa, sb) - j))
            if j >= 0.8:
                assert bits <= neardup.most_bits(len(a), len(b), sa, sb, 80)
        assert np.mean(errors) < 0.03


def test_forest_recall_and_order(spark):
    v = spark.read.parquet(f"{SF}/embeddings.parquet")
    got = ann.nearest(v, F.col("vec_id") % 20 == 0).collect()
    rows = {r.vec_id: np.array(r.embedding, float) for r in v.collect()}
    ids = np.array(list(rows))
    x = np.stack(list(rows.values()))
    found = collections.defaultdict(list)
    for r in sorted(got, key=lambda r: (r.query_id, r.rank)):
        assert abs(r.score - rows[r.query_id] @ rows[r.vec_id]) < 1e-12
        found[r.query_id].append(r.vec_id)
    recall = []
    for q, mine in found.items():
        s = x @ rows[q]
        s[ids == q] = -9
        recall.append(len(set(ids[np.lexsort((ids, -s))[:20]]) & set(mine)) / 20)
    assert len(found) == sum(i % 20 == 0 for i in rows) and np.mean(recall) >= 0.9


def test_forest_odd(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (1, None), (2, [0.0, 0.0]), (3, [nan, 1.0]), (4, [inf, 1.0]), (5, [None, 1.0]), (6, [1.0]), (7, [2.0, 0.0]), (8, [0.5, 0.5]), (9, [0.5, 0.5]), (None, [1.0, 1.0]), (20, [1.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("score", F.lit("x"))
    got = [(r.query_id, r["rank"], r.vec_id, r.score) for r in ann.nearest(df, F.col("vec_id") % 20 == 0).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 7, 2.0), (0, 2, 20, 1.0), (0, 3, 8, 0.5), (0, 4, 9, 0.5), (20, 1, 7, 2.0), (20, 2, 0, 1.0), (20, 3, 8, 0.5), (20, 4, 9, 0.5)]
    assert ann.nearest(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0
    assert ann.nearest(df.where("vec_id = 1"), F.col("vec_id") % 20 == 0).count() == 0


def test_forest_in_blocks(spark):
    v = spark.read.parquet(f"{SF}/embeddings.parquet")
    got = ann.nearest(v, F.col("vec_id") % 20 == 0, block_rows=100, block_queries=7, miss=0.0, ranked=1.0).collect()
    rows = {r.vec_id: np.array(r.embedding, float) for r in v.collect()}
    for q in {r.query_id for r in got}:
        best = sorted((-(rows[q] @ rows[i]), i) for i in rows if i != q)[:20]
        assert [r.vec_id for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == q] == [i for _, i in best]


def test_mixing_meets_targets(spark, docs):
    sizes = docs.select("doc_id", "source", mixing.n_words(F.col("text")).alias("size"))
    got = mixing.mix(sizes, mixing.source_targets(sizes), mixing.preference_by_size(F.col("size"))).toPandas()
    by = got.groupby("source").agg(size=("size", "sum"), own=("source_size", "first"), target=("target", "first"), taken=("taken", "sum"))
    assert (by["size"] == by.own).all() and (abs(by.taken - by.target) <= 0.5).all() and (got.taken <= 3 * got["size"]).all()
    assert abs(by.target.sum() - by.own.sum()) < 1e-6 * by.own.sum()
    again = mixing.mix(sizes, mixing.source_targets(sizes), mixing.preference_by_size(F.col("size"))).toPandas()
    assert got.sort_values("doc_id").taken.tolist() == again.sort_values("doc_id").taken.tolist()


def test_mixing_targets_stop_at_three_times(spark):
    rows = [(i, s, n) for i, (s, n) in enumerate([("a", 10), ("b", 10), ("c", 1), (None, 400)])]
    t = {r.source: r.target for r in mixing.source_targets(spark.createDataFrame(rows, "doc_id long, source string, size long")).collect()}
    # a, b, c and null weigh 1, 2, 3, 1 of 421: all but null stop at 30, 30, 3, null gets the rest
    assert t == {"a": 30.0, "b": 30.0, "c": 3.0, None: 358.0}


def test_pareto_prefers_what_is_preferred(spark):
    rows = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("s").alias("source"), F.lit(10).cast("long").alias("size"), (F.col("id") % 2 * 0.8 + 0.6).alias("like"))
    t = spark.createDataFrame([("s", 40000, 8000.0, 8000)], "source string, source_size long, target double, words long")
    got = mixing.mix(rows, t, F.col("like")).groupBy("like").agg(F.avg(F.col("taken") / 10).alias("share")).collect()
    share = {round(r.like, 1): r.share for r in got}
    assert abs(share[0.6] - 0.12) < 0.03 and abs(share[1.4] - 0.28) < 0.03


def test_mixing_odd(spark, odd):
    sizes = odd.drop("size").select("doc_id", "source", "u", mixing.n_words(F.col("text")).alias("size"))
    got = mixing.mix(sizes, mixing.source_targets(sizes)).toPandas()
    assert len(got) == len(ODD) and (got[got["size"] == 0].taken == 0).all() and (got.taken <= 3 * got["size"]).all()
    empty = sizes.limit(0)
    assert mixing.mix(empty, mixing.source_targets(empty)).count() == 0


def brute_blocks(text):
    return [line for line in text.split("\n") if any(c in line.lower() for c in licenses.CUES)]


def test_licenses_find_every_planted_line(docs):
    spark = docs.sparkSession
    big = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = collections.defaultdict(list)
    for r in licenses.scan(big).collect():
        got[r.doc_id].append(r)
    lines = {"This work is licensed under the GNU General Public License, version 3.": "GPL-3.0", "Licensed under CC BY-NC 4.0.": "CC-BY-NC-4.0", "Released under the MIT License.": "MIT", "Licensed under the Apache License, Version 2.0.": "Apache-2.0"}
    n = 0
    for i, t in texts(big).items():
        want = {lines[x] for x in brute_blocks(t) if x in lines}
        n += len(want)
        assert {r.license for r in got[i]} >= want
        assert all(t[r.block_start : r.block_start + r.block_length] for r in got[i])
    assert n > 10


def test_licenses_judge_wording():
    s = licenses.Scanner()
    mit = licenses.TEMPLATES["MIT"][1]
    assert s.judge(mit)[0] == "MIT" and s.judge(mit)[5] == "exact"
    changed = s.judge(mit.replace("free of charge", "at no charge"))
    assert changed[0] == "MIT" and changed[5] == "variant" and "free" in changed[3] and "at" in changed[4]
    assert s.judge("This work is licensed under the GNU General Public License, version 2.")[0] == "GPL-2.0"
    assert s.judge("You may want to get a license for your dog before winter.")[0] is None
    wrapped = "\n".join(re.findall(r".{1,60}(?:\s|$)", licenses.TEMPLATES["Apache-2.0"][1]))
    assert {s.judge(wrapped[a:b])[0] for a, b in s.blocks("prose\n\n\n\n\n\n" + wrapped + "\n\n\n\n\n\nprose")} <= {"Apache-2.0", None}


def test_nearest_lists_are_full_in_small_tables():
    for seed in range(100):
        n = (15, 20, 22)[seed % 3]
        x = np.random.default_rng(seed).standard_normal((n, 64))
        forest = ann.Forest(x, float(np.sqrt((x * x).sum(axis=1).max())))
        strings = forest.strings_of(x)
        skip = np.zeros(n, bool)
        for i, ranges in enumerate(forest.ranges(strings, 4 * ann.NEAREST)):
            skip[i] = True
            assert len(forest.search(x[i], strings[i], ranges, ann.NEAREST, skip)[0]) >= min(ann.NEAREST, n - 1)
            skip[i] = False


@pytest.mark.parametrize("lengths", [False, True])
def test_forest_ends_early_on_clustered_vectors(lengths):
    """Near neighbours end the ascent: a small share of the rows is looked at, with the same recall."""
    rng = np.random.default_rng(0)
    centre = rng.standard_normal((100, 64))
    x = centre[rng.integers(0, 100, 8000)] + 0.3 * rng.standard_normal((8000, 64))
    x /= np.linalg.norm(x, axis=1)[:, None]
    if lengths:
        x *= rng.uniform(0.8, 1.0, (8000, 1))
    forest = ann.Forest(x, float(np.sqrt((x * x).sum(axis=1).max())))
    strings, recall, share, ranked = forest.strings_of(x[:60]), [], [], []
    for i, ranges in enumerate(forest.ranges(strings, 4 * ann.NEAREST)):
        c, _, n = forest.search(x[i], strings[i], ranges, ann.NEAREST)
        recall.append(len(set(np.argsort(-(x @ x[i]), kind="stable")[:20]) & set(c)) / 20)
        share.append(n / len(x))
        ranked.append(len(c) / len(x))
    assert np.mean(recall) >= 0.9 and np.mean(ranked) <= 0.11 and np.mean(share) < (0.4 if lengths else 0.05)


def test_nearest_of_twenty_rows_are_all_others(spark):
    for seed in (3, 5):
        x = np.random.default_rng(seed).standard_normal((20, 64))
        v = spark.createDataFrame([(i, e.tolist()) for i, e in enumerate(x)], "vec_id long, embedding array<double>")
        assert ann.nearest(v, F.lit(True)).count() == 20 * 19


PROSE = "The harbour was quiet that morning and the boats had not yet returned from the long night of fishing beyond the old grey lighthouse. Nobody on the pier could say how many had gone out, nor when the wind would turn. "


@pytest.mark.parametrize("line, name", [(t, n) for n, ts in licenses.TEMPLATES.items() for t in ts])
def test_licenses_are_not_diluted_by_prose(line, name):
    s = licenses.Scanner()
    for size in (0, 60, 140, 200, 900):
        before, after = (PROSE * 5)[:size], (PROSE * 5)[len(PROSE) : len(PROSE) + size]
        text = f"{before} {line} {after}"
        assert name in {s.judge(text[a:b])[0] for a, b in s.blocks(text)}, size
    assert s.judge(PROSE * 5 + "He had a license for his dog, and the copyright of a song.")[0] is None
    between = f"{line}\n{PROSE[:100]}\n{line}"
    assert name in {s.judge(between[a:b])[0] for a, b in s.blocks(between)}


def test_licenses_of_one_block_are_all_reported(spark):
    lines = {t: n for n, ts in licenses.TEMPLATES.items() for t in ts}
    everything = "\n".join(lines)
    dual = "Released under the MIT License.\nLicensed under the Apache License, Version 2.0."
    reserved = f"{PROSE}Licensed under CC BY 4.0. {PROSE[:90]}All rights reserved. Released under the MIT License."
    foreign = "Released under the MIT License.\nThe dog has a license of its own.\nReleased under the MIT License."
    got = collections.defaultdict(list)
    texts = {1: dual, 2: reserved, 3: everything, 4: foreign}
    for r in licenses.scan(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect():
        got[r.doc_id].append(r)
    names = {i: [r.license for r in sorted(rows, key=lambda r: r.block_start)] for i, rows in got.items()}
    assert names[1] == ["MIT", "Apache-2.0"]
    assert names[2] == ["CC-BY-4.0", "LicenseRef-All-rights-reserved", "MIT"]
    assert names[3] == list(lines.values())
    assert names[4] == ["MIT", None, "MIT"]
    for i, rows in got.items():
        spans = sorted((r.block_start, r.block_start + r.block_length) for r in rows)
        assert all(b <= c for (_, b), (c, _) in zip(spans, spans[1:], strict=False))
        for r in rows:
            part = texts[i][r.block_start : r.block_start + r.block_length]
            assert r.license is None or r.verdict == "exact" and any(t.startswith(part) and lines[t] == r.license for t in lines)


def test_licenses_odd(spark, odd):
    assert licenses.scan(odd).count() == 0 and licenses.scan(odd.limit(0)).count() == 0
    long = "x " * 500_000 + "Licensed under CC BY 4.0." + " y" * 500_000
    r = licenses.scan(spark.createDataFrame([(1, long)], "doc_id long, text string")).collect()
    assert len(r) == 1 and r[0].block_length < 1000 and r[0].license == "CC-BY-4.0"


def whole_ids(text):
    from tokenizers import Tokenizer

    if not hasattr(whole_ids, "t"):
        whole_ids.t = Tokenizer.from_file(packing.tokenizer_path())
    return [*whole_ids.t.encode(text, add_special_tokens=False).ids, 2]


def check_packing(pieces, ids_of):
    seqs = collections.defaultdict(list)
    for p in pieces:
        seqs[p.sequence_id].append(p)
    for s in seqs.values():
        at = 0
        for p in sorted(s, key=lambda p: p.offset):
            assert p.offset == at and p.length > 0
            at += p.length
        assert at <= packing.SIZE
    assert sum(p.length for p in pieces) > (len(seqs) - 1) * packing.SIZE
    by = collections.defaultdict(list)
    for p in pieces:
        by[p.doc_id].append(p)
    for i, ps in by.items():
        ids = np.array(ids_of[i], "<u4")
        for p in ps:
            assert p.doc_tokens == len(ids) and p.ids_crc32 == zlib.crc32(ids[p.start : p.start + p.length].tobytes())
        assert sorted(x for p in ps for x in range(p.start, p.start + p.length)) == sorted(list(range(len(ids))) * (len([1 for p in ps if p.start == 0])))


def test_packing_round_trip(spark, docs):
    check_packing(packing.pack_documents(docs).collect(), {i: whole_ids(t) for i, t in texts(docs).items()})


def test_packing_odd(spark, odd):
    got = packing.pack_documents(odd).collect()
    assert {p.doc_id for p in got} == {r[0] for r in ODD}
    check_packing(got, {r[0]: whole_ids(r[1] or "") for r in ODD})
    assert packing.pack_documents(odd.limit(0)).count() == 0


def test_packing_of_any_sizes_tiles_the_line():
    import random

    r = random.Random(1)
    for _ in range(25):
        totals = [int(r.choice([0, 1, 5, 300, 5000, 50_000]) * r.random()) for _ in range(r.choice([1, 2, 3, 7, 40, 300]))]
        plan = packing.phases(totals, None if r.random() < 0.6 else [r.random() + 0.01 for _ in totals])
        seen = np.zeros(sum(totals), int)
        for q, total in enumerate(totals):
            at = 0
            while at < total:
                n, end = min(total - at, r.randrange(1, 3000)), 0
                for start, length, line in packing.pieces_of(plan, q, at, n):
                    assert start == end and length > 0 and line // packing.SIZE == (line + length - 1) // packing.SIZE
                    seen[line : line + length] += 1
                    end += length
                assert end == n
                at += n
        assert (seen == 1).all()


def test_packing_is_exact_beyond_ten_to_the_thirteenth():
    totals = [2 * 10**13, 10**13, 7 * 10**9, 3, 10**13 - 17, 999]
    plan = packing.phases(totals)
    rounds = plan[0].rounds
    for j in (0, 1, rounds // 3, rounds - 1, rounds):
        assert packing.share(np.full(6, j), np.array(totals), rounds).tolist() == [j * t // rounds for t in totals]
    for q, total in enumerate(totals):
        for first in (0, total // 2, max(0, total - 6000)):
            n = min(5000, total - first)
            pieces = list(packing.pieces_of(plan, q, first, n))
            assert [p[0] for p in pieces] == list(np.cumsum([0, *[p[1] for p in pieces[:-1]]])) and sum(p[1] for p in pieces) == n
    for j in (5, rounds // 2, rounds - 2):  # the turns of a round lie end to end
        a, b = plan[0].given(j), plan[0].given(j + 1)
        tiles = sorted((at, at + n) for q in range(6) if b[q] > a[q] for _, n, at in packing.pieces_of(plan, q, int(a[q]), int(b[q] - a[q])))
        assert tiles[0][0] == a.sum() and tiles[-1][1] == b.sum() and all(x[1] == y[0] for x, y in zip(tiles, tiles[1:], strict=False))


def test_packing_of_many_sources_keeps_pieces_useful():
    plan = packing.phases([3000] * 1000)
    lengths = [n for q in range(0, 1000, 10) for _, n, _ in packing.pieces_of(plan, q, 0, 3000)]
    assert np.median(lengths) == packing.QUANTUM
    with pytest.raises(ValueError, match="positive weight"):
        packing.phases([5, 5], [1.0, 0.0])


def test_other_tokenizers_are_used_whole():
    from tokenizers import Tokenizer

    texts = ["Plain words, it's 42.", "two  spaces\nand lines\t", "é ß 😀 <|endoftext|>", ""]
    for name, short in (("word_bpe_49k.json", True), ("byte_bpe_50k.json", False)):
        path = packing.tokenizer_path(name)
        mine, whole = packing.PieceTokenizer(path), Tokenizer.from_file(path)
        assert mine.short == short
        assert all(np.frombuffer(mine.ids(t), "<u2").tolist() == whole.encode(t, add_special_tokens=False).ids for t in texts)


def test_packing_windows_meet_their_proportions(spark, docs):
    source = {r.doc_id: r.source for r in docs.collect()}
    pieces = packing.pack_documents(docs).toPandas()
    pieces["source"] = pieces.doc_id.map(source)
    share = pieces.groupby("source").length.sum() / pieces.length.sum()
    per = pieces.pivot_table(index="sequence_id", columns="source", values="length", aggfunc="sum", fill_value=0)[:-1]
    small = (share * packing.SIZE < packing.QUANTUM).sum()  # these have their turns in quanta, which also moves the others
    assert small <= 3 and (abs(per - share * packing.SIZE) <= len(share) + 2 + packing.QUANTUM * small).all().all()


def test_packing_phases_of_other_targets():
    plan = packing.phases([10_000, 30_000, 500], [1.0, 1.0, 2.0])
    assert [p.take.tolist() for p in plan] == [[250, 250, 500], [9750, 9750, 0], [0, 20_000, 0]]
    taken = sorted(x for q, n in enumerate([10_000, 30_000, 500]) for _, k, at in packing.pieces_of(plan, q, 0, n) for x in range(at, at + k))
    assert taken == list(range(40_500))


def test_url_parts_and_rules(spark):
    urls = [("http://A.Example.com/en/1?x#y", "a.example.com", "/en/1", "example.com/en/", "block"), ("https://www.example.com/en/", "www.example.com", "/en/", "www.example.com/en/", "allow"), ("http://x.net", "x.net", "", None, "allow"), (None, "", "", None, "allow"), ("nothing", "", "", None, "allow"), ("ftp://example.com?q=/en/", "example.com", "", None, "allow"), ("http://net/es/1", "net", "/es/1", "net/es/", "block"), ("http://notexample.com/en/", "notexample.com", "/en/", "com/", "allow"), ("http://a.com/x://b.net/es/", "a.com", "/x://b.net/es/", "com/", "allow")]
    pages = spark.createDataFrame([(i, u[0], "h", "v") for i, u in enumerate(urls)], "page_id long, url string, host string, verdict string")
    none = spark.createDataFrame([], "page_id long, bad int")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in reputation.judge(pages, none).collect()}
    assert got == {i: u[1:] for i, u in enumerate(urls)}
    assert reputation.judge(pages.limit(0), none).count() == 0


def test_reputation_shrinks_and_blocks(spark):
    rows = [(i, f"http://{h}.{d}.org/{i}") for i, (h, d) in enumerate([("bad", "one")] * 40 + [("good", "one")] * 40 + [("new", "one")] + [("once", "two")] + [("x", "two")] * 40)]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    out = spark.createDataFrame([(i, int("bad." in u or "once." in u)) for i, u in rows if "new." not in u], "page_id long, bad int")
    got = {r.host: r.verdict for r in reputation.judge(pages, out).collect()}
    assert got["bad.one.org"] == "block" and got["good.one.org"] == got["once.two.org"] == got["new.one.org"] == got["x.two.org"] == "allow"


def test_native_plans_have_no_python(spark):
    for q in (reputation.op6_url_reputation, chat.op7_chat):
        plan = q(spark, SF)._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Pandas|Arrow", plan)


def test_chat_events(spark):
    ev = [
        (1, 0, 0, "message", "user", "Hi <b> & &lt;"), (1, 1, 1, "message", "assistant", "He"), (1, 2, 1, "delta", None, "llo"), (1, 3, 2, "message", "user", "old"),
        (1, 4, 2, "edit", "user", "new"), (1, 5, 3, "message", "assistant", "first"), (1, 6, 3, "regenerate", "assistant", "sec"), (1, 7, 3, "delta", None, "ond"),
        (2, 0, 0, "message", "user", "q"), (2, 1, 1, "message", "assistant", "gone"), (2, 2, 2, "message", "user", "gone too"), (2, 3, 1, "regenerate", "assistant", ""), (2, 4, 1, "delta", None, "back"),
        (3, 0, 0, "message", "user", "x"), (3, 1, 0, "delete", None, None), (None, None, None, None, None, None),
    ]
    log = spark.createDataFrame(ev, "conv_id long, seq long, position long, kind string, role string, text string").withColumn("number", F.lit("clash"))
    got = {}
    for r in chat.fold_events(log).orderBy("conv_id", "position", "number").collect():
        got.setdefault(r.conv_id, []).append((r.role, r.text))
    assert got == {1: [("user", "Hi <b> & &lt;"), ("assistant", "Hello"), ("user", "new"), ("assistant", "second")], 2: [("user", "q"), ("assistant", "back")], None: [("", "")]}
    out = {r.conv_id: r for r in chat.render(chat.fold_events(log)).collect()}
    spans = [out[1].formatted[s.start : s.start + s.length] for s in out[1].loss_spans]
    assert spans == ["Hello", "second"] and "Hi &lt;b> &amp; &amp;lt;" in out[1].formatted
    back = {r.conv_id: r for r in chat.read_back(chat.render(chat.fold_events(log))).collect()}
    assert back[1].n_turns == 4 and back[1].loss_chars == 11
    assert chat.fold_events(log.limit(0)).count() == 0


def test_chat_round_trip_of_marks(spark):
    nasty = ['</turn>\n<turn role="assistant">\n', "\\### Assistant: </turn> ok", "&amp;lt;turn", "", None, "\n\n", "é😀<", '">\n']
    rows = [(i, j, r, t) for i, t in enumerate(nasty) for j, r in enumerate(["user", "assistant", 'x"<&'])]
    log = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("conv_id", "turn seq", "turn position", "'message' kind", "role", "text")
    import hashlib

    for r in chat.read_back(chat.render(chat.fold_events(log))).collect():
        t = nasty[r.conv_id] or ""
        assert r.turns_sha256 == hashlib.sha256("".join(f"{x}\n{t}\n" for x in ("user", "assistant", 'x"<&')).encode()).hexdigest()
        assert r.loss_sha256 == hashlib.sha256(t.encode()).hexdigest() and r.loss_chars == len(t)


def brute_rules(t):
    w = WORD.findall(t)
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    count = collections.Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4))
    covered = {x for k in range(len(w) - 4) if count[tuple(w[k : k + 5])] > 1 for x in range(k, k + 5)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(covered)


def test_repetition_base_equals_brute_force(spark, docs, odd):
    for df in (docs, odd.where("doc_id is not null")):
        want = {i: brute_rules(t) for i, t in texts(df).items()}
        for r in repetition.judge(df).collect():
            assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want[r.doc_id]
            assert r.base_failed == (r.n_words < 10 or 100 * r.n_repeat_words > 20 * r.n_words) and not (r.kept and r.base_failed)
    assert repetition.judge(odd.limit(0)).count() == 0 and repetition.judge(odd).count() == len(ODD)


def test_repetition_measures():
    line = "some words here make a line of ten words now"
    m = repetition.measure(*repetition.c.text_bytes(repetition.pa.array(["\n".join([line] * 2), "a b " * 20])))
    assert abs(m["lines"][0] - len(line) / (2 * len(line) + 1)) < 1e-9 and m["repeated_5"][0] == pytest.approx(0.5)
    assert m["most_frequent_2"][1] == pytest.approx(1.0)


def held(df, labels, name):
    got = df.join(labels, "doc_id").where(f"held_out and {name} is not null").select("score", "predicted", F.col(name).alias("y")).toPandas()
    order = got.score.rank()
    n1, n0 = (got.y == 1).sum(), (got.y == 0).sum()
    return (order[got.y == 1].sum() - n1 * (n1 + 1) / 2) / (n1 * n0), (got.predicted == got.y).mean()


def test_quality_held_out(spark):
    sf = "/root/testdata/sf0.01"
    auc, accuracy = held(boosting.op10_quality(spark, sf), spark.read.parquet(f"{sf}/labels.parquet"), "quality")
    assert auc > 0.97 and accuracy > 0.95


def test_toxicity_held_out(spark):
    sf = "/root/testdata/sf0.01"
    auc, accuracy = held(toxicity.op8_toxicity(spark, sf), spark.read.parquet(f"{sf}/labels.parquet"), "toxic")
    assert auc > 0.9 and accuracy > 0.93


def test_classifiers_odd(spark, odd):
    labels = spark.createDataFrame([(None, 1, 1), (4, None, None), (5, 1, 0), (7, 0, 1), (8, 1, 0)], "doc_id long, quality int, toxic int")
    for model, scores in ((boosting.quality_model, boosting.score), (toxicity.toxicity_model, toxicity.score)):
        for known in (labels, labels.limit(0)):
            got = scores(odd, model(odd, known)).toPandas()
            assert len(got) == len(ODD) and got.score.between(0, 1).all()
        assert scores(odd.limit(0), model(odd.limit(0), labels)).count() == 0


def test_trees_learn_a_rule_and_traverse_flat():
    rng = np.random.default_rng(0)
    x = rng.random((3000, 5))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.3)).astype(float)
    t = boosting.fit(x[:2000], y[:2000])
    assert ((t.score(x[2000:]) > 0.5) == y[2000:]).mean() > 0.97


def test_non_negative_risk_recovers_labels():
    rng = np.random.default_rng(0)
    p, n = rng.normal(2, 1, (400, 3)), rng.normal(-2, 1, (400, 3))
    u = np.concatenate([p[:100], n[:300]])
    w, b = toxicity.fit(p[100:200], u, 0.25)
    assert ((p[200:] @ w + b) > 0).mean() > 0.95 and ((n[300:] @ w + b) < 0).mean() > 0.95


def test_packing_refuses_more_sources_than_it_holds(spark, monkeypatch):
    monkeypatch.setattr(packing, "MAX_QUEUES", 3)
    tokenized = spark.createDataFrame([(i, f"s{i}", 0, 0, 3, b"") for i in range(4)], "doc_id long, queue string, task int, before long, tokens long, ids binary")
    with pytest.raises(ValueError, match="more than 3 sources"):
        packing.pack(tokenized)


def thue_morse():
    """Two texts of different letters that polynomials modulo a power of two cannot tell apart."""
    word = "a"
    for _ in range(12):
        word += word.translate(str.maketrans("ab", "ba"))
    return word, word.translate(str.maketrans("ab", "ba"))


def test_hashes_tell_apart_what_polynomials_of_powers_of_two_cannot(spark):
    a, b = thue_morse()
    rows = [(1, a), (2, b), (3, f"{a}\n{b}"), (4, f"{a} x\n{b} x\n{a} x"), (5, a * 30), (6, b * 30), (7, a * 30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in neardup.near_duplicates(docs, 2).collect()}
    assert {i: r.component_id for i, r in got.items()} == {1: 1, 2: 2, 3: 3, 4: 4, 5: 5, 6: 6, 7: 5}
    dup = {r.doc_id: r.n_dup_lines for r in repetition.judge(docs).collect()}
    assert dup[3] == 0 and dup[4] == 1


def test_span_hashes_are_polynomials_modulo_the_prime():
    from placelink.llm import common as c

    rng = np.random.default_rng(0)
    p = 2**61 - 1
    x, y = (np.r_[rng.integers(0, p, 500, dtype=np.uint64), [0, 1, p - 1]].astype(np.uint64) for _ in "ab")
    assert c.times(x, y).tolist() == [int(i) * int(j) % p for i, j in zip(x, y, strict=True)]
    assert int(c._pow()[765_432]) == pow(c._BASE, 765_432, p)
    words = ["w" * n for n in (1, 2, 65_536, 65_537, 200_000)] + ["", "other", "w"]
    every = {}
    for order in (words, words[::-1], ["pad " * 400_000, *words]):  # equal wherever they lie
        data, at = c.text_bytes(repetition.pa.array(order))
        found = dict(zip(order, c.span_hashes(data, at[:-1], at[1:]).tolist(), strict=True))
        assert len({found[w] for w in words}) == len(set(words))
        assert all(found[w] == every.setdefault(w, found[w]) for w in words)


def test_license_in_prose_of_any_length(spark):
    long = PROSE * 3000 + "Licensed under CC BY 4.0. " + PROSE * 3000 + "All rights reserved." + PROSE
    got = licenses.scan(spark.createDataFrame([(1, long)], "doc_id long, text string")).collect()
    assert sorted((r.license, r.block_start) for r in got) == [("CC-BY-4.0", len(PROSE) * 3000), ("LicenseRef-All-rights-reserved", long.index("All rights"))]


def brute_licenses(text):
    """Names of the templates whose words, in a row, a text holds."""
    own = licenses.words(text)
    out = set()
    for name, ts in licenses.TEMPLATES.items():
        for t in map(licenses.words, ts):
            if any(own[i : i + len(t)] == t for i in range(len(own) - len(t) + 1)):
                out.add(name)
    return out


def test_licenses_equal_brute_force(spark):
    big = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = collections.defaultdict(set)
    for r in licenses.scan(big).where("verdict = 'exact'").collect():
        got[r.doc_id].add(r.license)
    with_cue = {i: t for i, t in texts(big).items() if any(c in t.lower() for c in licenses.CUES)}
    assert len(with_cue) > 20 and set(got) <= set(with_cue)
    assert {i: got[i] for i in with_cue} == {i: brute_licenses(t) for i, t in with_cue.items()}


def brute_measures(t):
    """The method's measures of one text, counted word by word."""
    w = WORD.findall(t)
    chars = sum(map(len, w)) or 1
    out = {}
    for n in repetition.MOST_FREQUENT:
        count = collections.Counter(tuple(w[k : k + n]) for k in range(len(w) - n + 1))
        out[f"most_frequent_{n}"] = max((c * sum(map(len, g)) for g, c in count.items() if c > 1), default=0) / chars
    for n in repetition.REPEATED:
        seen, again = set(), set()
        for k in range(len(w) - n + 1):
            g = tuple(w[k : k + n])
            if g in seen:
                again |= set(range(k, k + n))
            seen.add(g)
        out[f"repeated_{n}"] = sum(len(w[k]) for k in again) / chars
    seen, lines = set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            lines += len(line) if line in seen else 0
            seen.add(line)
    return out | {"lines": lines / max(1, len(t))}


def test_repetition_verdicts_equal_brute_force(spark, docs, odd):
    for df in (docs, odd.where("doc_id is not null and doc_id != 5")):
        want = {i: brute_measures(t) for i, t in texts(df).items()}
        for r in repetition.judge(df).collect():
            m = {k: v / repetition.LIMITS[k] for k, v in want[r.doc_id].items()}
            assert r.worst_ratio == pytest.approx(max(m.values()), abs=1e-4) and m[r.worst_measure] == pytest.approx(max(m.values()), abs=1e-9)
            assert r.kept == (not r.base_failed and max(m.values()) <= 1)


def test_trees_equal_a_plain_walk(spark, docs):
    model = boosting.quality_model(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    rows = {r.doc_id: r.score for r in boosting.score(docs, model).collect()}
    from placelink.llm import common as c

    for i, t in list(texts(docs).items())[:60]:
        x = boosting.statistics(*c.text_bytes(repetition.pa.array([t])))[0]
        total = model.start
        for feature, threshold, value in zip(model.feature, model.threshold, model.value, strict=True):
            node = 0
            while node < len(feature):
                node = 2 * node + (2 if x[feature[node]] > threshold[node] else 1)
            total += value[node - len(feature)]
        assert rows[i] == pytest.approx(1 / (1 + np.exp(-total)), abs=1e-12)


def test_toxicity_scores_equal_a_plain_sum(spark, docs):
    from placelink.llm import common as c

    model = toxicity.toxicity_model(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    rows = {r.doc_id: r.score for r in toxicity.score(docs, model).collect()}
    at = {int(h): k for k, h in enumerate(model.known)}
    for i, t in list(texts(docs).items())[:60]:
        hashes, _, words = toxicity.stems(*c.text_bytes(repetition.pa.array([t])))
        margin = model.bias
        for h, n in collections.Counter(hashes.tolist()).items():
            if h in at:
                margin += np.log1p(n) * model.weight[at[h]] + np.log1p(100 * n / max(1, words[0])) * model.weight[len(at) + at[h]]
        assert rows[i] == pytest.approx(1 / (1 + np.exp(-margin)), abs=1e-9)


def test_class_prior_from_positives_and_unlabelled_text():
    rng = np.random.default_rng(0)
    for share in (0.1, 0.3):
        p, n = rng.normal(1.5, 1, (2000, 3)), rng.normal(-1.5, 1, (4000, 3))
        u = np.concatenate([p[: int(4000 * share)], n[: int(4000 * (1 - share))]])
        assert abs(toxicity.class_prior(p[-800:], u) - share) < 0.05


def test_ten_thousand_rules(spark):
    rules = [("block", f"h{i}.com/p{i}/") for i in range(10_000)] + [("allow", "h7.com/"), ("allow", "h8.com/p8/deep/")]
    urls = ["http://w.h1.com/p1/x", "http://h7.com/p7/", "http://h7.com/other", "http://h8.com/p8/deep/er", "http://h9.com/p", "http://xh1.com/p1/"]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: (r.rule, r.verdict) for r in reputation.judge(pages, spark.createDataFrame([], "page_id long, bad int"), rules).collect()}
    assert got == {0: ("h1.com/p1/", "block"), 1: ("h7.com/p7/", "block"), 2: ("h7.com/", "allow"), 3: ("h8.com/p8/deep/", "allow"), 4: (None, "allow"), 5: (None, "allow")}


def test_registered_domains(spark):
    want = {
        "a.b.co.uk": ("co.uk", "b.co.uk"), "co.uk": ("co.uk", "co.uk"), "x.example.com:80": ("com", "example.com"), "u@h.org": ("org", "h.org"), "10.0.0.1:99": ("(address)", "10.0.0.1"),
        "[::1]:8": ("(address)", "[::1]"), "": ("", ""), "com": ("com", "com"), "w.a.gov.in": ("gov.in", "a.gov.in"), "x.co.com": ("com", "co.com"), "a.b.city.example": ("city.example", "b.city.example"),
    }
    hosts = spark.createDataFrame([(h,) for h in want], "host string")
    got = hosts.select("host", reputation.suffix_of(F.col("host"), ["city.example"]).alias("s"), reputation.domain_of(F.col("host"), ["city.example"]).alias("d")).collect()
    assert {r.host: (r.s, r.d) for r in got} == want


def test_a_hot_host_and_a_hot_set_are_dealt_out(spark, monkeypatch):
    from placelink.operators import skew

    monkeypatch.setattr(skew, "LEAST", 10)
    rows = spark.range(3000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, F.lit("same words in every text here")).otherwise(F.concat_ws(" ", "id", F.col("id") * 7, F.col("id") * 11)).alias("text"))
    got = neardup.near_duplicates(rows, 2)
    assert got.where("component_id = 0").count() == 1000 and got.where("kept").count() == 2001
    pages = spark.range(500).select(F.col("id").alias("page_id"), F.when(F.col("id") % 2 == 0, F.lit("http://hot.org/")).otherwise(F.concat(F.lit("http://h"), "id", F.lit(".net/es/"))).alias("url"))
    out = reputation.judge(pages, pages.select("page_id", (F.col("page_id") % 2 == 0).cast("int").alias("bad")))
    assert out.count() == 500 and out.where("host = 'hot.org' and verdict = 'block'").count() == 250 and out.where("rule = 'net/es/'").count() == 250


def test_mixing_bins_are_even_whatever_the_target(spark):
    """A source whose target is a whole number of copies does not fall into one bin."""
    from placelink.operators import running

    rows = spark.range(20_000).select(F.col("id").alias("doc_id"), F.lit("s").alias("source"), F.lit(10).cast("long").alias("size"))
    seen = []
    real = running.running_before

    def spy(df, keys, rank, order, value, out, bins=4096):
        seen.append(df.select(F.floor(rank * bins).alias("bin")).groupBy("bin").count().agg(F.max("count")).first()[0])
        return real(df, keys, rank, order, value, out, bins)

    mixing.running_before, before = spy, mixing.running_before
    try:
        for words in (200_000, 600_000, 150_000):
            t = spark.createDataFrame([("s", 200_000, float(words), words)], "source string, source_size long, target double, words long")
            assert mixing.mix(rows, t, mixing.preference_by_size(F.col("size"))).agg(F.sum("taken")).first()[0] == words
    finally:
        mixing.running_before = before
    assert max(seen) < 25  # 5 on average at the densest


def test_chat_of_a_very_long_conversation(spark):
    import hashlib

    rows = spark.range(20_000).select(F.lit(1).cast("long").alias("conv_id"), F.col("id").alias("seq"), F.col("id").alias("position"), F.lit("message").alias("kind"), F.when(F.col("id") % 2 == 0, "user").otherwise("assistant").alias("role"), F.concat(F.lit("t<"), "id").alias("text"))
    r = chat.read_back(chat.render(chat.fold_events(rows))).first()
    want = "".join(f"{'user' if i % 2 == 0 else 'assistant'}\nt<{i}\n" for i in range(20_000))
    assert r.n_turns == 20_000 and r.turns_sha256 == hashlib.sha256(want.encode()).hexdigest()
    assert r.loss_sha256 == hashlib.sha256("".join(f"t<{i}" for i in range(1, 20_000, 2)).encode()).hexdigest()


def test_licenses_compete_by_compression():
    """Parts that overlap in one word: more short words on the one side, more bytes on the other."""
    short, long = "license a b c d e f g h", "Internationally unrestricted redistribution permission license"
    s = licenses.Scanner({"short": (short,), "long": (long,)})
    text = long + short.removeprefix("license")
    assert len(licenses.words(short)) > len(licenses.words(long))
    assert s.verdicts(text)[0][2:] == s.judge(text) and s.judge(text)[0] == "long" and s.judge(text)[5] == "exact"
    # the reported share is the one by which the part is ranked
    for name, line in ((n, t) for n, ts in licenses.TEMPLATES.items() for t in ts):
        whole = licenses.Scanner()
        start, length, found, gain = whole.verdicts(line)[0][:4]
        ranked = whole.reductions(line[start : start + length])
        assert found == name and gain == round(next(g for g, t in ranked if t.text == line), 4)
        assert gain == round(ranked[0][0], 4) or abs(gain - ranked[0][0]) * length < 5
