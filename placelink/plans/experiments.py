"""The experiment workloads on the given tables; every function takes (spark, sf_dir) and returns a DataFrame."""

from __future__ import annotations

from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from placelink.functions.geo import project, within_box, within_radius
from placelink.functions.similarity import clean_phone, clean_website, interval_sim
from placelink.operators import baselines, cutoff, learning, metrics
from placelink.operators.blocking import capacity_quadtree, density_blocks, first_shared, home_cell, overlap_blocks, quadtree_blocks, root_box
from placelink.operators.components import components
from placelink.operators.layers import collapse, layers, rank_by_sum
from placelink.operators.pairs import all_pairs, candidate_pairs, comparison_count, coverage, radius_pairs
from placelink.operators.storage import stored
from placelink.operators.taxonomies import resnik_table, term_paths, with_paths, wup_table
from placelink.plans.link import ATTRS, CARRIED, compare
from placelink.sources import fixtures
from placelink.sources.tables import events, table

#: The distances and densities of the experiments.
M_VALUES, CUT_M = (1, 20, 40, 60, 80, 100), (30, 50, 80, 100)
DENSITIES, RADII, TRIGGERS = (10, 20, 30, 40, 50, 60), (20, 30, 40, 50, 70, 100), cutoff.TRIGGERS
#: The fixture's towns are sparser than the published area, so densities are scaled by this.
DENSITY_SCALE = 0.5
#: The deepest level of the trees of the experiments.
MAX_LEVEL = 16
PLACE_COLUMNS = ["eid", "source", "truth_id", "x_m", "y_m", "name", "address", "keywords", "phone_clean", "website_clean"]


def places(s: SparkSession, d: str) -> DataFrame:
    return fixtures.places(s, d).select(*PLACE_COLUMNS)


def _xy(s, d):
    return fixtures.places(s, d).select("eid", "source", "x_m", "y_m")


def compared(s: SparkSession, d: str, m: float = 100, density: float | None = None) -> DataFrame:
    """Pairs of the overlap tree with similarities and labels."""
    blocks = overlap_blocks(with_paths(places(s, d), fixtures.taxonomy(s, d)), m, density, max_level=MAX_LEVEL)
    return compare(candidate_pairs(blocks, carry=CARRIED))


def data_set(s: SparkSession, d: str, m: float = 100, label: str = "label", sample: bool = False) -> DataFrame:
    """The full set or the checked sample, stored, with the chosen kind of label as `label`, and category_sim for the baselines."""
    pairs = compared(s, d, m)
    pairs = pairs.withColumn("label", F.col(label)).drop("paths_a", "paths_b", *(x for x in ("label_auto", "label_mixed")))
    if sample:
        pairs = learning.checked_sample(pairs)
    return stored(baselines.with_category(pairs, resnik_table(fixtures.taxonomy(s, d), fixtures.term_frequency(s, d))), "data-set")


def vectors(s, d, m=100, label="label", sample=False):
    pairs = compared(s, d, m)
    if sample:
        pairs = learning.checked_sample(pairs)
    return collapse(pairs, ATTRS, label)


def ranked(s, d, m=100, label="label", sample=False):
    return stored(layers(stored(vectors(s, d, m, label, sample), "vectors"), ATTRS), "ranked")


def levels(s, d, m=100, label="label", sample=False):
    return cutoff.level_curve(ranked(s, d, m, label, sample)).withColumn("f1", F.round("f1", 6))


def _raw_levels(s, d, m=100, label="label", sample=False):
    return cutoff.level_curve(ranked(s, d, m, label, sample))


def _union(frames):
    return reduce(lambda a, b: a.unionByName(b), frames)


# --- fixture and geometry -----------------------------------------------------------------------------------------


def places_by_source(s, d):
    return fixtures.places(s, d).groupBy("source").agg(F.count("*").alias("n"), F.countDistinct("truth_id").alias("truths"))


def source_rollup(s, d):
    town = F.floor(F.col("truth_id") / 80).cast("bigint")
    return fixtures.places(s, d).select("source", town.alias("town")).rollup("source", "town").agg(F.count("*").alias("n"))


def root_box_row(s, d):
    p = _xy(s, d)
    box = p.agg(F.min("x_m").cast("double").alias("x0"), F.min("y_m").cast("double").alias("y0"), F.max("x_m").cast("double").alias("x1"), F.max("y_m").cast("double").alias("y1"))
    return box.withColumn("level", F.lit(root_box(p).level(100)))


def points_within_radius(s, d):
    return _xy(s, d).where(within_radius(500.0, 500.0, 300.0)).select("eid", "x_m", "y_m")


def points_within_box(s, d):
    return _xy(s, d).where(within_box(100.0, 100.0, 600.0, 700.0)).select("eid", "x_m", "y_m")


def project_degrees(s, d):
    p = project(fixtures.places_degrees(s, d).select("eid", "lon", "lat"), 10.0, 57.0)
    return p.select("eid", F.round("x_m", 3).alias("px"), F.round("y_m", 3).alias("py"))


# --- blocking and pairs -------------------------------------------------------------------------------------------


def blocks_m100(s, d):
    return overlap_blocks(_xy(s, d), 100).select("level", "ix", "iy", "eid", "is_home")


def blocks_cover_m100(s, d):
    return overlap_blocks(_xy(s, d), 100, level_rule="cover").select("level", "ix", "iy", "eid", "is_home")


def quadtree_m100(s, d):
    return quadtree_blocks(_xy(s, d), 100).select("level", "ix", "iy", "eid")


def block_sizes(s, d):
    return blocks_m100(s, d).groupBy("level", "ix", "iy").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("blocks"))


def block_size_percentiles(s, d):
    sizes = blocks_m100(s, d).groupBy("level", "ix", "iy").agg(F.count("*").alias("size"))
    return sizes.agg(*[F.percentile("size", q / 100).alias(f"p{q}") for q in (50, 90, 99)], F.max("size").alias("largest"))


def home_leaf(s, d):
    p = _xy(s, d)
    box = root_box(p)
    ix, iy = home_cell(box, box.level(100))
    return p.select("eid", ix.alias("ix"), iy.alias("iy"))


def blocks_density(s, d):
    return overlap_blocks(_xy(s, d), 100, density=20 * DENSITY_SCALE, max_level=MAX_LEVEL).select("level", "ix", "iy", "eid", "is_home")


def blocks_density_alone(s, d):
    return overlap_blocks(_xy(s, d), None, density=20 * DENSITY_SCALE, max_level=MAX_LEVEL, density_basis="physical").select("level", "ix", "iy", "eid", "is_home")


def capacity_leaves(s, d):
    return capacity_quadtree(_xy(s, d), 50, max_level=MAX_LEVEL).groupBy("level", "ix", "iy").agg(F.count("*").alias("size"))


def blocks_half_plane(s, d):
    return overlap_blocks(_xy(s, d), 100, mode="half_plane").groupBy("level", "ix", "iy").agg(F.count("*").alias("size"))


def blocks_coincident(s, d):
    p = fixtures.places_coincident(s, d).select("eid", "x_m", "y_m")
    return overlap_blocks(p, 100, density=20 * DENSITY_SCALE, max_level=10).groupBy("level").agg(F.count("*").alias("rows"))


def pairs_m100(s, d, scope="all"):
    return candidate_pairs(overlap_blocks(_xy(s, d), 100), scope).withColumn("dist_m", F.round("dist_m", 6))


def pairs_cover_m100(s, d):
    return candidate_pairs(overlap_blocks(_xy(s, d), 100, level_rule="cover"), max_dist_m=100).withColumn("dist_m", F.round("dist_m", 6))


def pairs_density(s, d):
    return candidate_pairs(overlap_blocks(_xy(s, d), 100, density=20 * DENSITY_SCALE, max_level=MAX_LEVEL)).withColumn("dist_m", F.round("dist_m", 6))


def raw_comparisons(s, d):
    p = _xy(s, d)
    return comparison_count(overlap_blocks(p, 100)).withColumn("tree", F.lit("overlap")).unionByName(comparison_count(quadtree_blocks(p, 100)).withColumn("tree", F.lit("plain")))


def radius_pairs_100(s, d, strategy="grid"):
    return radius_pairs(_xy(s, d), 100, strategy).withColumn("dist_m", F.round("dist_m", 6))


def no_index_pairs(s, d):
    return all_pairs(_xy(s, d), 100, force=True).withColumn("dist_m", F.round("dist_m", 6))


def points_comparisons(s, d):
    """F2 in the published dense area, the orders seven times over (about 1,000,000 points at sf0.1): comparisons of both trees."""
    p = fixtures.points(s, d, copies=7)
    return comparison_count(overlap_blocks(p, 100)).withColumn("tree", F.lit("overlap")).unionByName(comparison_count(quadtree_blocks(p, 100)).withColumn("tree", F.lit("plain")))


def _overlap_and_plain(s, d):
    p = _xy(s, d)
    ids = ["eid_a", "eid_b"]
    return candidate_pairs(overlap_blocks(p, 100)).select(*ids), candidate_pairs(quadtree_blocks(p, 100)).select(*ids)


def pairs_only_overlap(s, d):
    a, b = _overlap_and_plain(s, d)
    return a.exceptAll(b)


def pairs_both(s, d):
    a, b = _overlap_and_plain(s, d)
    return a.intersect(b)


def pairs_either(s, d):
    a, b = _overlap_and_plain(s, d)
    return a.union(b).distinct()


def coverage_by_radius(s, d):
    p = _xy(s, d)
    near = radius_pairs(p, 100)
    a = coverage(candidate_pairs(overlap_blocks(p, 100)), near, RADII).withColumn("tree", F.lit("overlap"))
    return a.unionByName(coverage(candidate_pairs(quadtree_blocks(p, 100)), near, RADII).withColumn("tree", F.lit("plain")))


def blocking_recall(s, d):
    return metrics.blocking_recall(compared(s, d), places(s, d))


# --- similarities, cleaning, taxonomy, intervals --------------------------------------------------------------------


def similarity(s, d, column):
    return compared(s, d).select("eid_a", "eid_b", column)


def phone_equal(s, d):
    return compared(s, d).where("phone_clean_a = phone_clean_b").select("eid_a", "eid_b")


def website_equal(s, d):
    return compared(s, d).where("website_clean_a = website_clean_b").select("eid_a", "eid_b")


def geo_similarity(s, d):
    return compared(s, d).select("eid_a", "eid_b", F.round(baselines.geo_sim(F.col("dist_m"), 100), 6).alias("geo_sim"))


def pair_vectors(s, d):
    return compared(s, d).select("eid_a", "eid_b", *ATTRS, "label_auto", "label")


def positive_share(s, d):
    return metrics.positive_share(compared(s, d).select("label"))


def clean_urls(s, d):
    return table(s, d, "pages").select("page_id", clean_website(F.col("url")).alias("site"))


def url_hosts(s, d):
    return clean_urls(s, d).groupBy(F.substring_index("site", "/", 1).alias("host")).agg(F.count("*").alias("pages"))


def clean_phones(s, d):
    return fixtures.places(s, d).where("phone is not null").select("eid", clean_phone(F.col("phone"), fixtures.COUNTRY).alias("phone"))


def document_phones(s, d):
    found = F.regexp_extract_all("text", F.lit(r"\+1 \([0-9]{3}\) 555-[0-9]{4}"), 0)
    return table(s, d, "documents").select("doc_id", F.explode(found).alias("raw")).select("doc_id", clean_phone(F.col("raw"), "1").alias("phone")).distinct()


def term_depths(s, d):
    return term_paths(fixtures.taxonomy(s, d)).groupBy("term").agg(F.min(F.size("path")).alias("depth"), F.count("*").alias("paths"))


def wup_pairs(s, d):
    return wup_table(fixtures.taxonomy(s, d))


def resnik_pairs(s, d):
    return resnik_table(fixtures.taxonomy(s, d), fixtures.term_frequency(s, d))


def nation_similarity(s, d):
    own = table(s, d, "nation").select(F.lower("n_name").alias("t"))
    w = wup_table(fixtures.taxonomy(s, d))
    return w.join(own, w["term_a"] == own["t"], "left_semi").join(own, w["term_b"] == own["t"], "left_semi")


def user_sessions(s, d):
    at = F.unix_micros("ts")
    by = W.partitionBy("user_id").orderBy("ts", "event_id")
    e = events(s, d).withColumn("new", F.when(at - F.lag(at).over(by) <= 1_800_000_000, 0).otherwise(1))
    e = e.withColumn("session", F.sum("new").over(by.rowsBetween(W.unboundedPreceding, W.currentRow)))
    return e.groupBy("user_id", "session").agg(F.min("ts").alias("open"), F.max("ts").alias("close"), F.count("*").alias("events"))


def session_overlap(s, d):
    """Pairs of sessions of different users that overlap in time: an interval join by hours, each pair in its first common hour."""
    u = user_sessions(s, d).select("user_id", "session", F.struct("open", "close").alias("i"), (F.unix_seconds("open") / 3600).cast("bigint").alias("first"), (F.unix_seconds("close") / 3600).cast("bigint").alias("last"))
    u = u.withColumn("hour", F.explode(F.sequence("first", "last")))
    a, b = (u.select(*[F.col(c).alias(f"{c}_{x}") for c in u.columns]) for x in "ab")
    pairs = a.join(b, (a["hour_a"] == b["hour_b"]) & (a["user_id_a"] < b["user_id_b"])).where(F.col("hour_a") == F.greatest("first_a", "first_b"))
    return pairs.where(interval_sim(F.col("i_a"), F.col("i_b")) == 1.0).select("user_id_a", "session_a", "user_id_b", "session_b")


def last_event_before(s, d):
    """For every error the user's last click before it: an as-of join as one window, without a join."""
    by = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    e = events(s, d).withColumn("click", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(by))
    return e.where("event_type = 'error'").select("event_id", "user_id", "click")


# --- ranking ------------------------------------------------------------------------------------------------------


def vector_layers(s, d):
    return ranked(s, d).select(*ATTRS, "pairs", "positives", "layer")


def first_front(s, d):
    return layers(vectors(s, d), ATTRS, max_layer=1).select(*ATTRS)


def pair_layers(s, d):
    pairs = stored(compared(s, d).select("eid_a", "eid_b", *ATTRS), "pairs")
    return layers(pairs, ATTRS).select("eid_a", "eid_b", "layer")


def layer_sizes(s, d):
    return ranked(s, d).groupBy("layer").agg(F.count("*").alias("vectors"), F.sum("pairs").alias("pairs"))


def sum_rank(s, d):
    return rank_by_sum(vectors(s, d), ATTRS).select(*ATTRS, "total", "layer")


DOC_ATTRS = ("f_letters", "f_unique_words", "f_unique_lines", "f_length")


def doc_layers(s, d):
    v = collapse(fixtures.doc_vectors(s, d), DOC_ATTRS, "label")
    return layers(v, DOC_ATTRS).select(*DOC_ATTRS, "pairs", "positives", "layer")


EMBEDDING_ATTRS = ("s1", "s2", "s3", "s4")


def embedding_layers(s, d):
    v = collapse(fixtures.embedding_pairs(s, d), EMBEDDING_ATTRS, "label")
    return layers(v, EMBEDDING_ATTRS).groupBy("layer").agg(F.count("*").alias("vectors"), F.sum("pairs").alias("pairs"), F.sum("positives").alias("positives"))


def quantised_layers(s, d):
    """Similarities rounded to 1, 2 and 3 digits: layers, and the share of pairs that change sides of the sweep cut."""
    v = stored(vectors(s, d), "vectors")
    own = stored(layers(v, ATTRS), "ranked")
    own = own.withColumn("match", F.col("layer") <= cutoff.sweep_cut(cutoff.level_curve(own)).first()["layer"])
    out = []
    for digits in (1, 2, 3):
        names = [f"{n}_q" for n in ATTRS]
        few = own.select(*[F.floor(F.col(n) * 10**digits + 0.5).alias(q) for n, q in zip(ATTRS, names, strict=True)], "pairs", "positives", "match")
        ranked_few = stored(layers(few.groupBy(*names).agg(F.sum("pairs").alias("pairs"), F.sum("positives").alias("positives")), names), "ranked")
        k = cutoff.sweep_cut(cutoff.level_curve(ranked_few)).select(F.col("layer").alias("k"), "f1", "layers")
        both = few.join(ranked_few.select(*names, "layer"), names).join(F.broadcast(k))
        moved = F.sum(F.when(F.col("match") != (F.col("layer") <= F.col("k")), F.col("pairs")).otherwise(0)) / F.sum("pairs")
        out.append(both.agg(F.lit(digits).alias("digits"), F.first("layers").alias("layers"), F.first("f1").alias("f1"), F.round(moved, 6).alias("displaced_share")))
    return _union(out)


# --- cut-offs -----------------------------------------------------------------------------------------------------


def hit_rates(s, d):
    rate = F.col("positives") / F.col("pairs")
    c = _raw_levels(s, d).select("layer", "hit_rate", rate.alias("r"))
    return c.select("layer", "hit_rate", (F.col("r") > F.lag("r").over(W.orderBy("layer"))).alias("rises"))


def fixed_cut_10(s, d):
    return cutoff.cut(pair_layers(s, d), 10)


def sweep_cut(s, d, m=100, label="label", sample=False):
    return cutoff.sweep_cut(_raw_levels(s, d, m, label, sample))


def sweep_by_m(s, d):
    out = []
    for m in M_VALUES:
        lv = _raw_levels(s, d, m)
        n = lv.agg(F.max("tp").alias("positives"), F.max("cum_pairs").alias("pairs"))
        out.append(cutoff.sweep_cut(lv).join(F.broadcast(n)).withColumn("m", F.lit(m)))
    return _union(out)


def sweep_by_density(s, d):
    """Trees of stricter limits split those of looser ones, so pairs are made and compared once, for the loosest limit."""
    blocks = density_blocks(with_paths(places(s, d), fixtures.taxonomy(s, d)), 100, tuple(x * DENSITY_SCALE for x in DENSITIES), max_level=MAX_LEVEL)
    pairs = candidate_pairs(stored(blocks, "blocks"), carry=(*CARRIED, "codes")).withColumn("first", first_shared(F.col("codes_a"), F.col("codes_b")))
    every = stored(collapse(compare(pairs), (*ATTRS, "first"), "label"), "vectors")
    out = []
    for i, x in enumerate(DENSITIES):
        v = every.where(F.col("first") <= i).groupBy(*ATTRS).agg(F.sum("pairs").alias("pairs"), F.sum("positives").alias("positives"))
        n = v.agg(F.sum("pairs").alias("pairs"), F.sum("positives").alias("positives"))
        out.append(cutoff.sweep_cut(cutoff.level_curve(layers(v, ATTRS))).join(F.broadcast(n)).withColumn("density", F.lit(x)))
    return _union(out)


def _stop_row(lv: DataFrame) -> DataFrame:
    best, stop = cutoff.sweep_cut(lv).select(F.col("layer").alias("best"), F.col("f1").alias("best_f1")), cutoff.stop_layer(lv)
    at = lv.select(F.col("layer"), F.round("f1", 6).alias("f1"))
    out = stop.join(F.broadcast(at), "layer").join(F.broadcast(best))
    share = F.round(F.coalesce("drop_at", "layers") / F.col("layers"), 6)
    return out.select("layer", "layers", "f1", "best", "best_f1", share.alias("explored_share"), F.round(F.col("best_f1") - F.col("f1"), 6).alias("f1_loss"))


def early_stop_by_m(s, d):
    return _union([_stop_row(_raw_levels(s, d, m)).withColumn("m", F.lit(m)) for m in CUT_M])


def early_stop_cut(s, d):
    """The production form: layer after layer until F1 falls."""
    r = cutoff.early_stop_cut(vectors(s, d), ATTRS)
    return s.createDataFrame([(int(r["layer"]), round(float(r["f1"]), 6))], "layer int, f1 double")


def cuts_by_protocol(s, d):
    """The two cuts under the supervised protocols at 30 m: full, checked sample, tuned on the sample and tested on the rest.

    Ranking needs no labels, so the transfer ranks all pairs and takes only the sweep's layer number from the sample.
    """
    pairs = stored(compared(s, d, 30).select("eid_a", "eid_b", *ATTRS, "label"), "pairs")
    few = learning.checked_sample(pairs, max(1, min(learning.SAMPLE, pairs.count() // 3))).withColumn("checked", F.lit(True))
    pairs = stored(pairs.join(few.select("eid_a", "eid_b", "checked"), ["eid_a", "eid_b"], "left").withColumn("checked", F.coalesce("checked", F.lit(False))), "pairs")
    out = []
    for protocol in learning.PROTOCOLS:
        own = pairs.where("checked") if protocol == "sample" else pairs
        r = stored(layers(collapse(own, ATTRS, "label"), ATTRS), "ranked")
        placed = stored(own.join(r.select(*ATTRS, "layer"), list(ATTRS)), "placed")
        tuned = cutoff.sweep_cut(cutoff.level_curve(placed.where("checked") if protocol == "transfer" else placed, "label"))
        for method, k in (("sweep", tuned), ("separation", cutoff.separation_cut(r, ATTRS))):
            tested = placed.where("not checked") if protocol == "transfer" else placed
            tested = tested.join(F.broadcast(k.select(F.col("layer").alias("k")))).withColumn("match", F.col("layer") <= F.col("k"))
            out.append(metrics.prf(metrics.confusion(tested)).withColumns({"method": F.lit(method), "protocol": F.lit(protocol)}))
    return _union(out)


def mu_curve(s, d, metric="euclidean", normalizer="ranked"):
    return cutoff.separation_curve(ranked(s, d), ATTRS, metric, normalizer).withColumn("mu", F.round("mu", 6) + F.lit(0.0))


def mu_curve_sampled(s, d, share=0.5):
    """The curve from half of every layer's vectors, beside the exact one."""
    r = ranked(s, d)
    exact = cutoff.separation_curve(r, ATTRS).select("layer", F.round("mu", 6).alias("mu"))
    return exact.join(cutoff.separation_curve(cutoff.sampled(r, ATTRS, share), ATTRS).select("layer", F.round("mu", 6).alias("mu_sampled")), "layer")


def mu_variants(s, d):
    r = ranked(s, d)
    return _union([cutoff.separation_curve(r, ATTRS, "sqeuclidean", n).select("layer", (F.round("mu", 4) + F.lit(0.0)).alias("mu"), F.lit(n).alias("normalizer")) for n in cutoff.NORMALIZERS])


def mu_derivative(s, d):
    c = cutoff.derivative(cutoff.separation_curve(ranked(s, d), ATTRS))
    return c.select("layer", F.round("dmu", 6).alias("dmu"))


def mu_smoothed(s, d):
    c = cutoff.gauss_smooth(cutoff.derivative(cutoff.separation_curve(ranked(s, d), ATTRS)))
    return c.select("layer", F.round("dmu_smooth", 6).alias("dmu_smooth"))


def separation_cut(s, d):
    return cutoff.separation_cut(ranked(s, d), ATTRS)


def _gap(r: DataFrame) -> DataFrame:
    lv = cutoff.level_curve(r)
    own = cutoff.separation_cut(r, ATTRS).select(F.col("layer").alias("unsupervised"))
    best = cutoff.sweep_cut(lv).select(F.col("layer").alias("best"), F.col("f1").alias("best_f1"), "layers")
    at = lv.select(F.col("layer").alias("unsupervised"), F.round("f1", 6).alias("f1"))
    return own.join(at, "unsupervised").join(F.broadcast(best)).select("unsupervised", "best", "layers", "f1", "best_f1", F.abs(F.col("unsupervised") - F.col("best")).alias("gap"), F.round(F.col("best_f1") - F.col("f1"), 6).alias("f1_loss"))


def separation_by_m(s, d):
    return _union([_gap(ranked(s, d, m)).withColumn("m", F.lit(m)) for m in CUT_M])


def cut_gap(s, d):
    return _gap(ranked(s, d))


def separation_grid(s, d):
    """Every normalizer, trigger and width beside the label-tuned best, in one table.

    The distances are summed once for each m; all curves are smoothed and cut in one frame, apart by m and normalizer.
    """
    found = {m: ranked(s, d, m) for m in (30, 100)}
    of = lambda frames: _union([x.withColumn("m", F.lit(m)) for m, x in frames.items()])
    lv = stored(of({m: cutoff.level_curve(r).select("layer", "f1") for m, r in found.items()}), "levels")
    sums = of({m: cutoff.separation_sums(r, ATTRS) for m, r in found.items()})
    mus = sums.select("m", "layer", *[cutoff.mean_distance(n, ("m",)).alias(n) for n in cutoff.NORMALIZERS])
    by = ("m", "normalizer")
    curve = stored(cutoff.derivative(mus.unpivot(["m", "layer"], list(cutoff.NORMALIZERS), "normalizer", "mu"), by), "curve")
    cuts = [cutoff.separation_layers(cutoff.gauss_smooth(curve, x, 2 * int(2 * x) + 1, by=by), TRIGGERS, by).withColumn("sigma", F.lit(x)) for x in (1.0, 3.0, 6.0)]
    rows = _union(cuts).unpivot([*by, "sigma"], list(TRIGGERS), "trigger", "layer")
    return rows.join(F.broadcast(lv), ["m", "layer"]).select("m", "normalizer", "trigger", "sigma", "layer", F.round("f1", 6).alias("f1"))  # a row per layer


# --- classes ------------------------------------------------------------------------------------------------------


def _classified(s, d, method, m=100):
    pairs = stored(compared(s, d, m).select("eid_a", "eid_b", "source_a", "source_b", *ATTRS, "address_text", "dist_m", "label", "name_a", "name_b", "keywords_a", "keywords_b"), "pairs")
    r = stored(layers(collapse(pairs, ATTRS, "label"), ATTRS), "ranked")
    k = (cutoff.sweep_cut(cutoff.level_curve(r)) if method == "sweep" else cutoff.separation_cut(r, ATTRS)).select(F.col("layer").alias("k"))
    # one row with the cut; the driver need not see it
    return pairs.join(r.select(*ATTRS, "layer"), list(ATTRS), "left").join(F.broadcast(k)).withColumn("match", F.coalesce(F.col("layer") <= F.col("k"), F.lit(False)))


def matches(s, d, method="sweep"):
    return _classified(s, d, method).where("match").select("eid_a", "eid_b", "layer", "label")


def confusion_by_method(s, d):
    both = _union([_classified(s, d, x).select(F.lit(x).alias("method"), (F.col("source_a") == F.col("source_b")).alias("same_source"), "match", "label") for x in ("sweep", "separation")])
    both.createOrReplaceTempView("classified_pairs")
    g = s.sql("""select method, same_source, count_if(match and label = 1) tp, count_if(match and label = 0) fp, count_if(not match and label = 1) fn,
                 count_if(not match and label = 0) tn from classified_pairs group by grouping sets ((method), (method, same_source))""")
    return metrics.prf(g)


def class_grid(s, d):
    bin_ = lambda c: F.floor(F.col(c) * 5).cast("int").alias(c.replace("_sim", "_bin"))
    c = _classified(s, d, "sweep").select(bin_("name_sim"), bin_("address_sim"), "match", "label")
    return c.cube("name_bin", "address_bin").agg(F.count("*").alias("pairs"), F.sum("label").cast("bigint").alias("positives"), F.count_if("match").alias("matches"))


def links_by_source(s, d):
    return metrics.links_by_source(compared(s, d).where("label = 1"))


def source_profile(s, d):
    return metrics.source_profile(places(s, d), compared(s, d).where("label = 1"))


def _linked_ids(s, d):
    hit = compared(s, d).where("label = 1")
    return hit.select(F.col("eid_a").alias("eid")).union(hit.select(F.col("eid_b").alias("eid"))).distinct()


def matched_places(s, d):
    return _xy(s, d).select("eid", "source").join(_linked_ids(s, d), "eid", "left_semi")


def unmatched_places(s, d):
    return _xy(s, d).select("eid", "source").join(_linked_ids(s, d), "eid", "left_anti")


def prediction_vs_truth(s, d):
    """Full outer join of predicted links and all true pairs, blocking losses included."""
    found = matches(s, d).select("eid_a", "eid_b", F.lit(True).alias("predicted"))
    p = places(s, d).select("eid", "truth_id")
    a, b = p.select(F.col("eid").alias("eid_a"), "truth_id"), p.select(F.col("eid").alias("eid_b"), "truth_id")
    true = a.join(b, "truth_id").where("eid_a < eid_b").select("eid_a", "eid_b", F.lit(True).alias("true"))
    both = found.join(true, ["eid_a", "eid_b"], "full_outer").select(F.coalesce("predicted", F.lit(False)).alias("predicted"), F.coalesce("true", F.lit(False)).alias("true"))
    return both.groupBy("predicted", "true").agg(F.count("*").alias("pairs"))


# --- baselines ----------------------------------------------------------------------------------------------------


def additive(s, d, which):
    return baselines.additive(compared(s, d), which).where("match").select("eid_a", "eid_b", "score")


def additive_sweep(s, d, which, sample=False):
    pairs = compared(s, d)
    return baselines.additive_sweep(learning.checked_sample(pairs) if sample else pairs, which)


def additive_pivot(s, d):
    """F1 by threshold, one column per baseline."""
    both = _union([additive_sweep(s, d, w).select("threshold", "f1", F.lit(w.lower()).alias("which")) for w in "AB"])
    return both.groupBy("threshold").pivot("which", ["a", "b"]).agg(F.first("f1")).select("threshold", F.col("a").alias("f1_a"), F.col("b").alias("f1_b"))


def weighted_topk(s, d):
    return baselines.weighted_topk(data_set(s, d), 3).where("match").select("eid_a", "eid_b")


def weighted_topk_sweep(s, d, label="label", sample=False):
    return baselines.weighted_topk_sweep(data_set(s, d, label=label, sample=sample))


def belief_links(s, d):
    near = compared(s, d).where("dist_m <= 5")  # goes below the comparison
    return baselines.belief(near).where("match").select("eid_a", "eid_b", "belief", "disbelief")


def baseline_summary(s, d, label="label", sample=False):
    """Precision, recall and F1 of all methods on the same pairs: the full set or the checked sample, with either kind of label."""
    pairs = data_set(s, d, label=label, sample=sample)
    r = stored(layers(collapse(pairs, ATTRS, "label"), ATTRS), "ranked")
    placed = pairs.join(r.select(*ATTRS, "layer"), list(ATTRS), "left").select("layer", "label")
    one = lambda df, name: metrics.prf(metrics.confusion(df)).withColumn("method", F.lit(name))
    best = lambda sweep, name: sweep.orderBy(F.col("f1").desc(), sweep.columns[0]).limit(1).select("tp", "fp", "fn", "tn", "precision", "recall", "f1").withColumn("method", F.lit(name))
    rows = [one(baselines.additive(pairs, w), f"additive {w} .75") for w in "AB"] + [best(baselines.additive_sweep(pairs, w), f"additive {w} best") for w in "AB"]
    rows += [best(baselines.weighted_topk_sweep(pairs), "weighted top-k best"), one(baselines.belief(pairs), "belief")]
    for name, k in (("sweep cut", cutoff.sweep_cut(cutoff.level_curve(r))), ("separation cut", cutoff.separation_cut(r, ATTRS))):
        cut_at = placed.join(F.broadcast(k.select(F.col("layer").alias("k")))).withColumn("match", F.coalesce(F.col("layer") <= F.col("k"), F.lit(False)))
        rows.append(one(cut_at, name))
    return _union(rows)


def supervised(s, d, model, protocol):
    pairs = stored(compared(s, d, 30).select("eid_a", "eid_b", *ATTRS, "label"), "pairs")
    return learning.supervised(pairs, model, ATTRS, protocol)


def clustered(s, d, method, label="label", sample=False, **options):
    v = stored(vectors(s, d, 30, label, sample), "vectors")
    return learning.best_orientation(learning.cluster(v, method, ATTRS, **options))


def dbscan_links(s, d, label="label", sample=False):
    return learning.dbscan_sweep(stored(vectors(s, d, 30, label, sample), "vectors"), ATTRS).orderBy(F.col("f1").desc(), "eps", "min_pairs")


# --- after linkage ------------------------------------------------------------------------------------------------


def link_groups(s, d):
    links = matches(s, d)
    c = components(links, "eid_a", "eid_b")
    p = _xy(s, d).select("eid")
    return p.join(c, p["eid"] == c["id"], "left").select("eid", F.coalesce("component", "eid").alias("group"))


def whole_method(s, d, method="separation"):
    """The scalable chain: cover blocks, pairs within 100 m, unsupervised cut."""
    from placelink.plans.link import link

    out = link(places(s, d), fixtures.taxonomy(s, d), method=method)
    return metrics.prf(metrics.confusion(out)).withColumn("method", F.lit(method))


QUERIES = {
    "places": places, "places_by_source": places_by_source, "source_rollup": source_rollup, "root_box": root_box_row, "within_radius": points_within_radius, "within_box": points_within_box,
    "project_degrees": project_degrees, "blocks_m100": blocks_m100, "blocks_cover_m100": blocks_cover_m100, "quadtree_m100": quadtree_m100, "block_sizes": block_sizes,
    "block_size_percentiles": block_size_percentiles, "home_leaf": home_leaf, "blocks_density": blocks_density, "blocks_density_alone": blocks_density_alone, "capacity_leaves": capacity_leaves,
    "blocks_half_plane": blocks_half_plane, "blocks_coincident": blocks_coincident, "pairs_m100": pairs_m100, "pairs_cross_source": partial(pairs_m100, scope="cross"),
    "pairs_within_source": partial(pairs_m100, scope="within"), "pairs_cover_m100": pairs_cover_m100, "pairs_density": pairs_density, "raw_comparisons": raw_comparisons, "radius_pairs_100": radius_pairs_100,
    "radius_pairs_sorted": partial(radius_pairs_100, strategy="sorted"), "no_index_pairs": no_index_pairs, "points_comparisons": points_comparisons, "pairs_only_overlap": pairs_only_overlap,
    "pairs_both": pairs_both, "pairs_either": pairs_either, "coverage_by_radius": coverage_by_radius, "blocking_recall": blocking_recall,
    "name_similarity": partial(similarity, column="name_sim"), "address_similarity": partial(similarity, column="address_sim"), "address_as_text": partial(similarity, column="address_text"),
    "keyword_similarity": partial(similarity, column="semantic_sim"), "phone_equal": phone_equal, "website_equal": website_equal, "geo_similarity": geo_similarity, "pair_vectors": pair_vectors,
    "positive_share": positive_share, "clean_urls": clean_urls, "url_hosts": url_hosts, "clean_phones": clean_phones, "document_phones": document_phones, "term_depths": term_depths, "wup_pairs": wup_pairs,
    "resnik_pairs": resnik_pairs, "nation_similarity": nation_similarity, "user_sessions": user_sessions, "session_overlap": session_overlap, "last_event_before": last_event_before,
    "distinct_vectors": vectors, "vector_layers": vector_layers, "first_front": first_front, "pair_layers": pair_layers, "layer_sizes": layer_sizes, "sum_rank": sum_rank, "doc_layers": doc_layers,
    "embedding_layers": embedding_layers, "level_curve_full": levels, "level_curve_auto": partial(levels, label="label_auto"), "level_curve_sample": partial(levels, sample=True), "hit_rates": hit_rates,
    "fixed_cut_10": fixed_cut_10, "sweep_cut_full": sweep_cut, "sweep_cut_auto": partial(sweep_cut, label="label_auto"), "sweep_cut_sample": partial(sweep_cut, sample=True), "early_stop_cut": early_stop_cut,
    "early_stop_by_m": early_stop_by_m, "sweep_by_m": sweep_by_m, "sweep_by_density": sweep_by_density, "mu_curve": mu_curve, "mu_curve_squared": partial(mu_curve, metric="sqeuclidean"),
    "mu_curve_manhattan": partial(mu_curve, metric="manhattan"), "mu_variants": mu_variants, "mu_derivative": mu_derivative, "mu_smoothed": mu_smoothed, "separation_cut": separation_cut,
    "separation_by_m": separation_by_m, "separation_grid": separation_grid, "cut_gap": cut_gap, "matches_sweep": matches, "matches_separation": partial(matches, method="separation"),
    "confusion_by_method": confusion_by_method, "class_grid": class_grid, "links_by_source": links_by_source, "source_profile": source_profile, "matched_places": matched_places,
    "unmatched_places": unmatched_places, "prediction_vs_truth": prediction_vs_truth, "additive_a": partial(additive, which="A"), "additive_b": partial(additive, which="B"),
    "additive_a_sweep": partial(additive_sweep, which="A"), "additive_b_sweep": partial(additive_sweep, which="B"), "additive_pivot": additive_pivot, "weighted_topk": weighted_topk,
    "weighted_topk_sweep": weighted_topk_sweep, "weighted_topk_sweep_sample": partial(weighted_topk_sweep, sample=True), "weighted_topk_sweep_auto": partial(weighted_topk_sweep, label="label_auto"),
    "additive_a_sweep_sample": partial(additive_sweep, which="A", sample=True), "additive_b_sweep_sample": partial(additive_sweep, which="B", sample=True),
    "belief_links": belief_links, "baseline_summary": baseline_summary, "baseline_summary_auto": partial(baseline_summary, label="label_auto"),
    "baseline_summary_mixed": partial(baseline_summary, label="label_mixed"), "baseline_summary_sample": partial(baseline_summary, sample=True), "cuts_by_protocol": cuts_by_protocol,
    "level_curve_mixed": partial(levels, label="label_mixed"), "sweep_cut_mixed": partial(sweep_cut, label="label_mixed"), "mu_curve_sampled": mu_curve_sampled, "quantised_layers": quantised_layers,
    **{f"{m}_links_sample": partial(clustered, method=m, sample=True) for m in ("kmeans", "kmedoids", "agglomerative")}, "dbscan_links_sample": partial(dbscan_links, sample=True),
    **{f"{m}_links_auto": partial(clustered, method=m, label="label_auto") for m in ("kmeans", "kmedoids", "agglomerative")}, "dbscan_links_auto": partial(dbscan_links, label="label_auto"),
    "link_groups": link_groups, "whole_method": whole_method,
    **{f"{m}_{p}": partial(supervised, model=m, protocol=p) for m in learning.MODELS for p in learning.PROTOCOLS},
    "kmeans_links": partial(clustered, method="kmeans"), "kmedoids_links": partial(clustered, method="kmedoids"), "agglomerative_links": partial(clustered, method="agglomerative"), "dbscan_links": dbscan_links,
}
