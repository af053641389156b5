"""Similarities in [0, 1] as column expressions. A missing value is no evidence: 0, unless `missing` says otherwise."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MISSING = {"zero": 0.0, "neutral": 0.5, "null": None}


def _or_missing(sim: Column, a: Column, b: Column, missing: str) -> Column:
    return F.when(a.isNull() | b.isNull(), F.lit(MISSING[missing]).cast("double")).otherwise(sim)


def rounded(c: Column, digits: int = 6) -> Column:
    """Rounds halves up in binary, so that every engine agrees where decimals tie."""
    return F.floor(c * 10.0**digits + 0.5) / 10.0**digits


def clean_text(c: Column) -> Column:
    """Lower case, one space between words, no other marks."""
    return F.trim(F.regexp_replace(F.lower(c), r"[^\p{L}\p{N}]+", " "))


def text_sim(a: Column, b: Column, min_sim: float | None = None, missing: str = "zero") -> Column:
    """1 - edits / longer length; two empty texts are alike. With min_sim the search for edits ends early, below it is 0."""
    longer = F.greatest(F.char_length(a), F.char_length(b))
    if min_sim is None:
        edits = F.levenshtein(a, b)
        sim = F.when(longer == 0, 1.0).otherwise(1 - edits / longer)
        return _or_missing(sim, a, b, missing)
    # the length difference alone may settle it; 64 edits bound the band for the rest
    close = F.least(F.char_length(a), F.char_length(b)) >= longer * min_sim
    edits = F.levenshtein(a, b, 64)
    sim = F.when(longer == 0, 1.0).when(~close | (edits < 0), 0.0).otherwise(1 - edits / longer)
    return _or_missing(F.when(sim >= min_sim, sim).otherwise(0.0), a, b, missing)


def address_sim(a: Column, b: Column, mode: str = "rule", missing: str = "zero") -> Column:
    """Equal 1.0, one inside the other 0.9, else 0; mode "text" is the edit similarity instead. Empty is inside nothing."""
    a, b = clean_text(a), clean_text(b)
    if mode == "text":
        return text_sim(a, b, missing=missing)
    inside = (F.contains(a, b) | F.contains(b, a)) & (a != "") & (b != "")
    return _or_missing(F.when(a == b, 1.0).when(inside, 0.9).otherwise(0.0), a, b, missing)


def equal_sim(a: Column, b: Column, missing: str = "zero") -> Column:
    return _or_missing(F.when(a == b, 1.0).otherwise(0.0), a, b, missing)


def geo_sim(distance: Column, scale: float) -> Column:
    return F.greatest(F.lit(0.0), 1 - distance / F.lit(float(scale)))


def interval_sim(a: Column, b: Column, mode: str = "overlap") -> Column:
    """Structs (open, close): equal, one inside the other, or overlapping, as 1 or 0."""
    equal = (a["open"] == b["open"]) & (a["close"] == b["close"])
    within = ((a["open"] >= b["open"]) & (a["close"] <= b["close"])) | ((b["open"] >= a["open"]) & (b["close"] <= a["close"]))
    over = (a["open"] < b["close"]) & (b["open"] < a["close"])
    return F.coalesce({"equal": equal, "contained": within, "overlap": over | equal}[mode], F.lit(False)).cast("double")


def intervals_sim(a: Column, b: Column, mode: str = "overlap") -> Column:
    """Arrays of intervals: 1 if any pair agrees."""
    return F.coalesce(F.exists(a, lambda x: F.exists(b, lambda y: interval_sim(x, y, mode) == 1.0)), F.lit(False)).cast("double")


def clean_phone(c: Column, country: str) -> Column:
    """Digits without the country's prefix, written +cc or 00cc."""
    digits = F.regexp_replace(c, "[^0-9]", "")
    n = len(country)
    return F.when(F.trim(c).startswith("+" + country), F.substring(digits, n + 1, 64)).when(digits.startswith("00" + country), F.substring(digits, n + 3, 64)).otherwise(digits)


def clean_website(c: Column) -> Column:
    """Host and path without scheme, query, fragment, leading www. or m., .html and closing slashes."""
    c = F.regexp_replace(F.lower(F.trim(c)), "^[a-z]+://", "")
    c = F.regexp_replace(c, "[?#].*$", "")
    c = F.regexp_replace(c, "^(www|m)[.]", "")
    return F.regexp_replace(F.regexp_replace(c, "[.]html$", ""), "/+$", "")


def shared_prefix(a: Column, b: Column) -> Column:
    """Length of the common beginning of two arrays."""
    same = F.zip_with(F.slice(a, 1, F.least(F.size(a), F.size(b))), F.slice(b, 1, F.least(F.size(a), F.size(b))), lambda x, y: x == y)
    return F.coalesce(F.nullif(F.array_position(same, False), F.lit(0)) - 1, F.size(same).cast("bigint"))


def wup(a: Column, b: Column) -> Column:
    """Wu-Palmer similarity of two paths from the root: twice the depth of the last common term over both depths."""
    return 2 * shared_prefix(a, b) / (F.size(a) + F.size(b))


def semantic_sim(a: Column, b: Column, missing: str = "zero") -> Column:
    """The best Wu-Palmer similarity between the keywords' paths of two places (arrays of paths)."""
    best = F.array_max(F.flatten(F.transform(a, lambda p: F.transform(b, lambda q: wup(p, q)))))
    value = MISSING[missing]
    return best if value is None else F.coalesce(best, F.lit(value))
