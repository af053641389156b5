"""URL filters: explicit rules first, else an empirical-Bayes reputation of the host.

Labelled page outcomes (bad or not) are counted by host, registered domain and public suffix. Each level is a
beta-binomial whose prior is the level above, as strong as the spread between its members tells (method of moments);
a page without a rule is blocked when the lower posterior bound of its host's bad rate exceeds a limit.

Rules are looked up by host: every host's suffixes are joined with the rules' hosts, and each host carries the rules that
may fit its pages, so that any number of rules costs one join over hosts, not an expression over pages.

Registered domains stand below a public suffix: the last label, or the last two where they look like `co.uk` (a country
code below a label of SECOND_LEVELS), or one given in `suffixes`. User names and ports do not count; an address in numbers
is its own domain, below the suffix `(address)`.

Defined cases: a null url, or one without `://`, has an empty host and path, fits no rule and has the reputation of all
pages; a host without labels inherits its domain's reputation; ids that are null or repeat are rows of their own; an
outcome that is null is no outcome, and a page with several outcomes counts as many; without any outcome every host has
the neutral prior and is allowed; rules of equal length that both fit cannot differ; a rule given twice is one, and counts
as block if its verdicts differ; very long urls are judged whole; an empty table gives an empty result; only page_id, url
and the outcomes' page_id and bad are read, so other columns may have any name.
Only DataFrame functions are used; a hot host is summed before it is shuffled, and its pages are joined in shares.
"""

from __future__ import annotations

import json
import string
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from placelink.llm.common import stored, table
from placelink.operators.skew import join_counted

#: Fixed values of the production filter.
RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))
#: Labels that registrations stand below when a country code follows them.
SECOND_LEVELS = ("ac", "co", "com", "edu", "go", "gob", "gouv", "gov", "ltd", "me", "mil", "ne", "net", "nhs", "nom", "or", "org", "plc", "sch")
_TWO_LABELS = rf"^(?:.*[.])?((?:{'|'.join(SECOND_LEVELS)})[.][a-z][a-z])$"
_ADDRESS = r"^(?:[0-9]{1,3}[.]){3}[0-9]{1,3}$|^\[.*\]$"
_URL = r"(?s)^.*?://([^/?#]*)([^?#]*)"
#: What is not part of a host's name: the user before it and the port after it.
_NO_NAME = r"^.*@|:[0-9]*$"


def url_host(url: Column) -> Column:
    host = F.regexp_extract(F.coalesce(url, F.lit("")), _URL, 1)
    return F.translate(host, string.ascii_uppercase, string.ascii_lowercase)


def url_path(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), _URL, 2)


def rules_by_host(hosts: DataFrame, rules: Sequence[tuple[str, str]] = RULES) -> DataFrame:
    """hosts (host, each once) with `rules`: array of (size, rule, below, verdict) of all rules whose host is a suffix of it."""
    rows = [{"size": len(name), "rule": name, "at": name.partition("/")[0], "below": "/" + name.partition("/")[2], "verdict": verdict} for name, verdict in {n: v for v, n in sorted(rules)}.items()]
    schema = "array<struct<size int, rule string, at string, below string, verdict string>>"
    known = hosts.sparkSession.range(1).select(F.inline(F.from_json(F.lit(json.dumps(rows)), schema)))
    labels = F.split("host", "[.]")
    ends = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    found = hosts.select("host", F.explode(ends).alias("at")).join(F.broadcast(known), "at")  # the rules are the caller's own list
    found = found.groupBy("host").agg(F.collect_list(F.struct("size", "rule", "below", "verdict")).alias("rules"))
    return hosts.join(found, "host", "left")


def rule_of(rules: Column, path: Column) -> Column:
    """The longest of a host's rules that fits a path (struct, null if none)."""
    return F.array_max(F.filter(rules, lambda r: path.startswith(r["below"])))


def _name(host: Column) -> Column:
    return F.regexp_replace(host, _NO_NAME, "")


def _two_labels(host: Column, suffixes: Sequence[str]) -> Column:
    """The public suffix of two labels, or more if given, that a host ends in; empty if it has one of one label."""
    two = F.regexp_extract(_name(host), _TWO_LABELS, 1)
    for s in sorted(suffixes, key=len):
        two = F.when((_name(host) == s) | _name(host).endswith("." + s), F.lit(s)).otherwise(two)
    return two


def suffix_of(host: Column, suffixes: Sequence[str] = ()) -> Column:
    two = _two_labels(host, suffixes)
    return F.when(_name(host).rlike(_ADDRESS), F.lit("(address)")).when(two != "", two).otherwise(F.substring_index(_name(host), ".", -1))


def domain_of(host: Column, suffixes: Sequence[str] = ()) -> Column:
    """The suffix and one label more; the whole host if it has no more."""
    name = _name(host)
    labels = F.size(F.split(suffix_of(host, suffixes), "[.]")) + 1
    return F.when(name.rlike(_ADDRESS), name).otherwise(F.array_join(F.slice(F.split(name, "[.]"), F.greatest(F.size(F.split(name, "[.]")) - labels, F.lit(0)) + 1, labels), "."))


def _strength(level: DataFrame, out: str) -> DataFrame:
    """One row: how many outcomes (2 to 999) the prior of this level is worth, from the spread of its members around their parents."""
    v = F.col("prior") * (1 - F.col("prior"))
    spread = F.col("n") * (F.col("bad") / F.col("n") - F.col("prior")) * (F.col("bad") / F.col("n") - F.col("prior"))
    seen = level.where("n > 0").agg(F.coalesce(F.sum(spread - v) / F.nullif(F.sum(v * (F.col("n") - 1)), F.lit(0.0)), F.lit(0.0)).alias("rho"))
    rho = F.greatest(F.lit(0.001), F.least(F.lit(0.333), F.round("rho", 6)))
    return seen.select((1 / rho - 1).alias(out))


def _with_mean(level: DataFrame) -> DataFrame:
    level = level.join(F.broadcast(_strength(level, "m")))  # one row
    return level.withColumn("mean", (F.col("bad") + F.col("m") * F.col("prior")) / (F.col("n") + F.col("m")))


def host_reputation(hosts: DataFrame, quantile: float = 1.645, suffixes: Sequence[str] = ()) -> DataFrame:
    """hosts (host, n, bad: labelled outcomes) to host, mean, lower: posterior mean and lower bound of the bad rate."""
    hosts = hosts.select("host", "n", "bad", domain_of(F.col("host"), suffixes).alias("domain"), suffix_of(F.col("host"), suffixes).alias("suffix"))
    total = hosts.agg(((F.coalesce(F.sum("bad"), F.lit(0)) + 1) / (F.coalesce(F.sum("n"), F.lit(0)) + 2)).alias("prior"))
    known = hosts.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).join(F.broadcast(total))
    known = _with_mean(known).select("suffix", F.col("mean").alias("prior"))
    domains = hosts.groupBy("suffix", "domain").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).join(known, "suffix")
    domains = _with_mean(domains).select("domain", F.col("mean").alias("prior"))
    hosts = _with_mean(hosts.join(domains, "domain"))
    deviation = F.sqrt(F.col("mean") * (1 - F.col("mean")) / (F.col("n") + F.col("m") + 1))
    return hosts.select("host", "mean", (F.col("mean") - quantile * deviation).alias("lower"))


def judge(pages: DataFrame, outcomes: DataFrame, rules: Sequence[tuple[str, str]] = RULES, limit: float = 0.5, suffixes: Sequence[str] = ()) -> DataFrame:
    """pages (page_id, url), outcomes (page_id, bad 0/1) to page_id, host, path, rule, verdict, bad_rate_bound."""
    at = pages.select("page_id", url_host(F.col("url")).alias("host"), url_path(F.col("url")).alias("path"))
    labelled = outcomes.where(F.col("bad").isNotNull() & F.col("page_id").isNotNull()).select("page_id", F.col("bad").cast("int").alias("bad"))
    no = F.lit(0).cast("long")
    found = at.select("page_id", "host").join(labelled, "page_id").select("host", F.lit(1).cast("long").alias("n"), F.col("bad").cast("long").alias("bad"), no.alias("pages"))
    every = at.select("host", no.alias("n"), no.alias("bad"), F.lit(1).cast("long").alias("pages")).unionByName(found)
    hosts = stored(every.groupBy("host").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"), F.sum("pages").alias("pages")), "reputation-hosts")
    total = hosts.agg(F.coalesce(F.sum("pages"), no)).first()[0]
    known = host_reputation(hosts.select("host", "n", "bad"), suffixes=suffixes).join(rules_by_host(hosts.select("host"), rules), "host")
    known = stored(known.join(hosts.select("host", "pages"), "host"), "reputation")
    fits = rule_of(F.col("rules"), F.col("path"))
    out = join_counted(at, known, ["host"], total, n="pages").withColumn("fits", fits)
    return out.select(
        "page_id", "host", "path", F.col("fits.rule").alias("rule"),
        F.coalesce(F.col("fits.verdict"), F.when(F.col("lower") > limit, F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"),
        F.round("lower", 4).alias("bad_rate_bound"),
    )


def op6_url_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Outcomes: the quality labels that carry a page's id; quality 0 is a bad outcome."""
    outcomes = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("page_id"), (1 - F.col("quality")).alias("bad"))
    return judge(table(spark, sf_dir, "pages"), outcomes)


def _sql_level(name: str, key: str, source: str) -> str:
    return f"""
{name}_rho AS (SELECT coalesce(sum(n * (bad / n - prior) * (bad / n - prior) - prior * (1 - prior)) / nullif(sum(prior * (1 - prior) * (n - 1)), 0), 0) AS rho
  FROM {source} WHERE n > 0),
{name}_m AS (SELECT 1 / greatest(0.001::DOUBLE, least(0.333::DOUBLE, round(rho, 6))) - 1 AS m FROM {name}_rho),
{name} AS (SELECT {key}, n, m, (bad + m * prior) / (n + m) AS mean FROM {source}, {name}_m)"""


OP6_SQL = rf"""
WITH parsed AS (
  SELECT page_id, translate(regexp_extract(coalesce(url, ''), '{_URL}', 1), '{string.ascii_uppercase}', '{string.ascii_lowercase}') AS host,
         regexp_extract(coalesce(url, ''), '{_URL}', 2) AS path FROM pages),
rules(what, name, rule_host, rule_path) AS (VALUES {", ".join(f"('{w}', '{r}', '{r.partition('/')[0]}', '/{r.partition('/')[2]}')" for w, r in RULES)}),
fits AS (
  SELECT a.page_id, max_by(r.name, len(r.name)) AS rule, max_by(r.what, len(r.name)) AS what FROM parsed a JOIN rules r
  ON (a.host = r.rule_host OR ends_with(a.host, '.' || r.rule_host)) AND starts_with(a.path, r.rule_path) GROUP BY ALL),
counted AS (
  SELECT host, count(quality) AS n, coalesce(sum(1 - quality), 0)::DOUBLE AS bad FROM parsed LEFT JOIN labels ON doc_id = page_id GROUP BY ALL),
named AS (
  SELECT *, regexp_replace(regexp_replace(host, '^.*@', ''), ':[0-9]*$', '') AS plain FROM counted),
labelled AS (
  SELECT *, string_split(plain, '.') AS labels, regexp_matches(plain, '{_ADDRESS}') AS is_address,
    list_contains([{", ".join(f"'{x}'" for x in SECOND_LEVELS)}], string_split(plain, '.')[-2]) AND regexp_full_match(string_split(plain, '.')[-1], '[a-z][a-z]') AS two FROM named),
hosts0 AS (
  SELECT host, n, bad, CASE WHEN is_address THEN '(address)' WHEN two THEN array_to_string(labels[-2:], '.') ELSE labels[-1] END AS suffix,
    CASE WHEN is_address THEN plain WHEN two THEN array_to_string(labels[-3:], '.') ELSE array_to_string(labels[-2:], '.') END AS domain FROM labelled),
total AS (SELECT (coalesce(sum(bad), 0) + 1) / (coalesce(sum(n), 0) + 2) AS prior FROM hosts0),
suffixes0 AS (SELECT suffix, sum(n) AS n, sum(bad) AS bad, any_value(prior) AS prior FROM hosts0, total GROUP BY suffix),
{_sql_level("suffixes", "suffix", "suffixes0")},
domains0 AS (SELECT suffix, domain, sum(h.n) AS n, sum(bad) AS bad, any_value(mean) AS prior FROM hosts0 h JOIN suffixes USING (suffix) GROUP BY ALL),
{_sql_level("domains", "domain", "domains0")},
hosts1 AS (SELECT host, h.n, h.bad, d.mean AS prior FROM hosts0 h JOIN domains d USING (domain)),
{_sql_level("hosts", "host", "hosts1")}
SELECT a.page_id, a.host, a.path, f.rule,
  coalesce(f.what, CASE WHEN mean - 1.645::DOUBLE * sqrt(mean * (1 - mean) / (n + m + 1)) > 0.5 THEN 'block' ELSE 'allow' END) AS verdict,
  round(mean - 1.645::DOUBLE * sqrt(mean * (1 - mean) / (n + m + 1)), 4) AS bad_rate_bound
FROM parsed a JOIN hosts USING (host) LEFT JOIN fits f USING (page_id)
"""
