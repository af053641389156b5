"""Comparison of candidate pairs, and the whole chain from places to matches."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from placelink.functions.similarity import address_sim, clean_text, semantic_sim, text_sim
from placelink.operators import cutoff
from placelink.operators.blocking import Root, overlap_blocks
from placelink.operators.layers import collapse, layers
from placelink.operators.pairs import candidate_pairs
from placelink.operators.storage import stored
from placelink.operators.taxonomies import with_paths

ATTRS = ("name_sim", "address_sim", "semantic_sim")
#: Fixed value: one of so many pairs is checked by hand, the label of the others is automatic.
CHECKED = 78
CARRIED = ("source", "name", "address", "paths", "keywords", "phone_clean", "website_clean", "truth_id")


def compare(pairs: DataFrame, places: DataFrame | None = None, digits: int = 6, missing: str = "zero") -> DataFrame:
    """Similarities and labels of pairs. The attributes ride with the pairs, or are joined from `places` by id."""
    if places is not None:
        side = lambda s: places.select(*[F.col(c).alias(f"{c}_{s}") for c in ("eid", *CARRIED)])
        pairs = pairs.join(side("a"), "eid_a").join(side("b"), "eid_b")
    c = lambda name: (F.col(f"{name}_a"), F.col(f"{name}_b"))
    name = [clean_text(x) for x in c("name")]
    checked = F.conv(F.substring(F.md5(F.concat("eid_a", "eid_b")), 1, 7), 16, 10).cast("bigint") % CHECKED == 0
    same = lambda n: F.coalesce(F.col(f"{n}_a") == F.col(f"{n}_b"), F.lit(False))
    return pairs.withColumns({
        "name_sim": F.round(text_sim(*name, missing=missing), digits),
        "address_sim": F.round(address_sim(*c("address"), missing=missing), digits),
        "address_text": F.round(address_sim(*c("address"), mode="text", missing=missing), digits),
        "semantic_sim": F.round(semantic_sim(*c("paths"), missing=missing), digits),
        "label_auto": (same("phone_clean") | same("website_clean")).cast("int"),
        "label": same("truth_id").cast("int"),
        "label_mixed": F.when(checked, same("truth_id")).otherwise(same("phone_clean") | same("website_clean")).cast("int"),
    })


@dataclass
class Blocking:
    """How places are blocked; "cover" with a distance limit gives exactly the pairs within m, in one pass."""

    m: float = 100.0
    density: float | None = None
    root: str | Root = "square"
    level_rule: str = "cover"
    scope: str = "all"
    max_dist_m: float | None = 100.0
    more: dict = field(default_factory=dict)


def link(places: DataFrame, taxonomy: DataFrame, blocking: Blocking | None = None, attrs=ATTRS, method: str = "separation", label: str = "label", k: int | None = None) -> DataFrame:
    """Compared pairs with layer and match.

    method: "separation" (no labels), "sweep", "early_stop" (labels), or "fixed" with k. The driver reads one layer number.
    """
    b = blocking or Blocking()
    blocks = overlap_blocks(with_paths(places, taxonomy), b.m, b.density, root=b.root, level_rule=b.level_rule, **b.more)
    pairs = stored(compare(candidate_pairs(blocks, b.scope, b.max_dist_m, CARRIED)).drop("paths_a", "paths_b"), "pairs")
    vectors = collapse(pairs, attrs, label)
    if method == "early_stop":
        vectors = stored(vectors, "vectors")
        k = cutoff.early_stop_cut(vectors, attrs)["layer"] or 0
        ranked = layers(vectors, attrs, max_layer=max(1, k))
    else:
        ranked = stored(layers(vectors, attrs), "layers")
        if method == "sweep":
            row = cutoff.sweep_cut(cutoff.level_curve(ranked)).first()
            k = row["layer"] or 0 if row else 0
        elif method == "separation":
            row = cutoff.separation_cut(ranked, attrs).first()
            k = row["layer"] or 0 if row else 0
        elif method != "fixed" or k is None:
            raise ValueError(method)
    return cutoff.classify(pairs, ranked, attrs, k)
