"""DuckDB SQL for the queries of the experiments, composed of common table expressions; each one stands alone."""

from __future__ import annotations

import math

from placelink.operators.baselines import RELIABILITY, THRESHOLDS

_M_VALUES, _CUT_M, _RADII = (1, 20, 40, 60, 80, 100), (30, 50, 80, 100), (20, 30, 40, 50, 70, 100)


def _bits(t: str, first: int) -> str:
    return " + ".join(f"(({t}) // {2 ** (first + 2 * i)}) % 2 * {2**i}" for i in range(6))


_WORDS = r"trim(regexp_replace(lower({0}), '[^\p{{L}}\p{{N}}]+', ' ', 'g'))"
_SITE = r"regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(lower(trim({0})), '^[a-z]+://', ''), '[?#].*$', ''), '^(www|m)[.]', ''), '[.]html$', ''), '/+$', '')"


def _phone(c: str, cc: str) -> str:
    digits = f"regexp_replace({c}, '[^0-9]', '', 'g')"
    return f"CASE WHEN starts_with(trim({c}), '+{cc}') THEN substr({digits}, {len(cc) + 1}) WHEN starts_with({digits}, '00{cc}') THEN substr({digits}, {len(cc) + 3}) ELSE {digits} END"


PLACES = f"""
part0 AS (
  SELECT p_partkey k, p_partkey // 80 t, p_size, p_type, split_part(p_name, ' ', 2) noun,
    p_name || ' ' || replace(lower(p_brand), 'brand#', 'no') base,
    900 * ({_bits("p_partkey // 80", 0)}) + 7919 * p_partkey % 600 x, 900 * ({_bits("p_partkey // 80", 1)}) + 104729 * p_partkey % 600 y FROM part),
listed AS (
  SELECT l_orderkey o, l_linenumber n, l_suppkey s, CASE WHEN l_orderkey % 10 = 0 THEN 3 ELSE 1 END far, p.* FROM lineitem JOIN part0 p ON l_partkey = k WHERE l_quantity >= 49),
raw_places AS (
  SELECT 'C' || k AS eid, 'catalog' AS source, k AS truth_id, x AS x_m, y AS y_m, base AS name, 'street ' || p_size || ' zone ' || t AS address, [noun] AS keywords,
    CASE WHEN k % 6 != 0 THEN CAST(5550000 + 7 * k AS VARCHAR) END AS phone, CASE WHEN k % 4 != 0 THEN 'http://www.place' || k || '.example.com' END AS website FROM part0
  UNION ALL
  SELECT 'L' || o || '-' || n, 'src' || (s % 3), k, x + far * (31 * o % 61 - 30), y + far * (17 * o % 61 - 30),
    CASE o % 6 WHEN 0 THEN base WHEN 1 THEN base || ' ltd' WHEN 2 THEN substr(base, 3) WHEN 3 THEN replace(base, 'e', 'a') WHEN 4 THEN noun || ' house' ELSE p_type || ' ' || base END,
    CASE s % 5 WHEN 0 THEN NULL WHEN 1 THEN 'street ' || p_size || ' zone ' || t || ' north' WHEN 2 THEN 'street ' || (p_size + 1) || ' zone ' || t ELSE 'street ' || p_size || ' zone ' || t END,
    CASE WHEN o % 7 = 0 THEN [lower(p_type)] ELSE [noun] END,
    CASE WHEN s % 4 = 0 THEN NULL WHEN s % 3 = 0 THEN '+45 ' || call WHEN s % 3 = 1 THEN '0045' || call ELSE substr(call, 1, 3) || ' ' || substr(call, 4) END,
    CASE WHEN s % 3 != 0 THEN 'https://m.place' || k || '.example.com/?ref=' || s END
  FROM (SELECT *, CAST(CASE WHEN o % 23 = 0 THEN 5550000 + 7 * (k + 1) ELSE 5550000 + 7 * k END AS VARCHAR) AS call FROM listed)),
places AS (SELECT *, row_number() OVER (ORDER BY eid, x_m, y_m, name, website) AS rid, {_phone("phone", "45")} AS phone_clean, {_SITE.format("website")} AS website_clean FROM raw_places)"""

BOX = """
box AS (SELECT CAST(min(x_m) AS DOUBLE) x0, CAST(min(y_m) AS DOUBLE) y0, CAST(max(x_m) AS DOUBLE) x1, CAST(max(y_m) AS DOUBLE) y1 FROM places)"""


def blocks(m: float = 100, margin: float = 0.25, rule: str = "diagonal", name: str = "blocks") -> str:
    if rule == "diagonal":
        level = f"(SELECT min(l) FROM range(25) r(l) WHERE sqrt((x1 - x0) ** 2 + (y1 - y0) ** 2) / (2 ** l) <= {m})"
    else:
        level = f"(SELECT max(l) FROM range(25) r(l) WHERE least(x1 - x0, y1 - y0) / (2 ** l) >= {m})"
    first, last = (f"greatest(ceil(%s - {1 + 2 * margin}), 0)", f"least(floor(%s + {2 * margin}), n - 1)") if margin else ("least(floor(%s), n - 1)",) * 2
    cast = lambda e: f"CAST({e} AS BIGINT)"
    return f"""
{name}_level AS (SELECT *, CAST({level} AS INTEGER) AS level FROM box),
{name}_at AS (SELECT p.*, level, CAST(2 ** level AS BIGINT) n, (x_m - x0) / ((x1 - x0) / (2 ** level)) ax, (y_m - y0) / ((y1 - y0) / (2 ** level)) ay FROM places p, {name}_level),
{name}_range AS (
  SELECT *, {cast(first % "ax")} low_ix, {cast(last % "ax")} high_ix, {cast(first % "ay")} low_iy, {cast(last % "ay")} high_iy,
    {cast("least(floor(ax), n - 1)")} hx, {cast("least(floor(ay), n - 1)")} hy FROM {name}_at),
{name} AS (
  SELECT *, (ix = hx AND iy = hy) AS is_home FROM (
    SELECT *, unnest(range(low_iy, high_iy + 1)) AS iy FROM (SELECT *, unnest(range(low_ix, high_ix + 1)) AS ix FROM {name}_range)))"""


def pairs(source: str = "blocks", name: str = "pairs") -> str:
    return f"""
{name} AS (
  SELECT a.eid eid_a, b.eid eid_b, sqrt(CAST((a.x_m - b.x_m) * (a.x_m - b.x_m) + (a.y_m - b.y_m) * (a.y_m - b.y_m) AS DOUBLE)) dist_m, a.source source_a, b.source source_b, a.rid rid_a, b.rid rid_b
  FROM {source} a JOIN {source} b ON a.ix = b.ix AND a.iy = b.iy AND a.eid < b.eid
  WHERE a.ix = greatest(a.low_ix, b.low_ix) AND a.iy = greatest(a.low_iy, b.low_iy))"""


_CATS = """
edges AS (
  SELECT 'root' term, NULL parent UNION ALL VALUES ('shape', 'root'), ('make', 'root'), ('trade', 'root'), ('ring', 'trade'), ('rod', 'make')
  UNION ALL SELECT DISTINCT lower(split_part(p_name, ' ', 2)), 'shape' FROM part UNION ALL SELECT DISTINCT lower(p_type), 'make' FROM part
  UNION ALL SELECT DISTINCT lower(c_mktsegment), 'trade' FROM customer UNION ALL SELECT lower(r_name), 'root' FROM region
  UNION ALL SELECT lower(n_name), lower(r_name) FROM nation JOIN region ON n_regionkey = r_regionkey),
paths AS (SELECT term, [term] AS path FROM edges WHERE parent IS NULL UNION ALL SELECT e.term, list_append(w.path, e.term) FROM paths w JOIN edges e ON e.parent = w.term),
wup AS (
  SELECT a.term ta, b.term tb, max(2 * len(list_filter(a.path, lambda x, i: a.path[1:i] = b.path[1:i])) / (len(a.path) + len(b.path))) sim
  FROM paths a, paths b GROUP BY ALL)"""

_TEXT = "CASE WHEN {a} IS NULL OR {b} IS NULL THEN 0.0 WHEN greatest(length({a}), length({b})) = 0 THEN 1.0 ELSE 1 - levenshtein({a}, {b}) / greatest(length({a}), length({b})) END"
COMPARED = f"""
side AS (SELECT *, {_WORDS.format("name")} AS name_c, {_WORDS.format("address")} AS address_c FROM places),
compared AS (
  SELECT p.*, a.name name_a, b.name name_b, a.keywords keywords_a, b.keywords keywords_b,
    a.phone_clean phone_a, b.phone_clean phone_b, a.website_clean site_a, b.website_clean site_b,
    round({_TEXT.format(a="a.name_c", b="b.name_c")}, 6)::DOUBLE AS name_sim,
    CASE WHEN a.address IS NULL OR b.address IS NULL THEN 0.0 WHEN a.address_c = b.address_c THEN 1.0
      WHEN a.address_c != '' AND b.address_c != '' AND (contains(a.address_c, b.address_c) OR contains(b.address_c, a.address_c)) THEN 0.9 ELSE 0.0 END::DOUBLE AS address_sim,
    round({_TEXT.format(a="a.address_c", b="b.address_c")}, 6)::DOUBLE AS address_text,
    round(coalesce(w.sim, 0.0), 6)::DOUBLE AS semantic_sim,
    CAST(coalesce(a.phone_clean = b.phone_clean, false) OR coalesce(a.website_clean = b.website_clean, false) AS INTEGER) AS label_auto,
    CAST(a.truth_id = b.truth_id AS INTEGER) AS label,
    CAST(CASE WHEN CAST('0x' || substr(md5(a.eid || b.eid), 1, 7) AS BIGINT) % 78 = 0 THEN a.truth_id = b.truth_id
      ELSE coalesce(a.phone_clean = b.phone_clean, false) OR coalesce(a.website_clean = b.website_clean, false) END AS INTEGER) AS label_mixed
  FROM pairs p JOIN side a ON p.rid_a = a.rid JOIN side b ON p.rid_b = b.rid LEFT JOIN wup w ON w.ta = a.keywords[1] AND w.tb = b.keywords[1])"""
SAMPLE = "compared_sample AS (SELECT * FROM compared ORDER BY md5(eid_a || eid_b), eid_a, eid_b LIMIT 1500)"


def vectors(label: str = "label", source: str = "compared") -> str:
    return f"""
vectors AS (SELECT name_sim, address_sim, semantic_sim, count(*) AS pairs, CAST(sum({label}) AS BIGINT) AS positives FROM {source} GROUP BY ALL)"""


def layered(attrs: tuple[str, ...] = ("name_sim", "address_sim", "semantic_sim")) -> str:
    good = " AND ".join(f"a.{x} >= b.{x}" for x in attrs)
    return f"""
numbered AS (SELECT *, row_number() OVER (ORDER BY {", ".join(attrs)}) AS id FROM vectors),
over_ AS (SELECT a.id p, b.id q FROM numbered a JOIN numbered b ON a.id != b.id AND {good}),
chain(id, depth) AS (SELECT id, 1 FROM numbered UNION SELECT q, depth + 1 FROM chain JOIN over_ ON id = p),
ranked AS (SELECT n.*, c.layer FROM numbered n JOIN (SELECT id, CAST(max(depth) AS INTEGER) AS layer FROM chain GROUP BY id) c USING (id))"""


LEVELS = """
per_layer AS (SELECT layer, CAST(sum(pairs) AS BIGINT) pairs, CAST(sum(positives) AS BIGINT) positives FROM ranked GROUP BY layer),
summed AS (SELECT *, sum(pairs) OVER u cum_pairs, sum(positives) OVER u tp, sum(pairs) OVER () n, sum(positives) OVER () t FROM per_layer WINDOW u AS (ORDER BY layer)),
levels AS (
  SELECT layer, pairs, positives, CAST(cum_pairs AS BIGINT) cum_pairs, CAST(tp AS BIGINT) tp, CAST(cum_pairs - tp AS BIGINT) fp, CAST(t - tp AS BIGINT) fn, CAST(n - cum_pairs - t + tp AS BIGINT) tn,
    round(tp / cum_pairs, 6) AS precision, round(coalesce(tp / nullif(t, 0), 0), 6) AS recall, 2 * tp / (cum_pairs + t) AS f1, round(positives / pairs, 6) AS hit_rate FROM summed)"""
BEST = """
best AS (SELECT layer, precision, recall, round(f1, 6) AS f1, (SELECT max(layer) FROM levels) AS layers FROM levels ORDER BY levels.f1 DESC, layer LIMIT 1)"""


def mu(metric: str = "euclidean", normalizer: str = "s.n", digits: int | None = None) -> str:
    square = " + ".join(f"(a.{x} - b.{x}) * (a.{x} - b.{x})" for x in ("name_sim", "address_sim", "semantic_sim"))
    d = {"euclidean": f"sqrt({square})", "sqeuclidean": f"({square})", "manhattan": "(" + " + ".join(f"abs(a.{x} - b.{x})" for x in ("name_sim", "address_sim", "semantic_sim")) + ")"}[metric]
    return f"""
deltas AS (SELECT a.layer, sum(CAST(a.pairs AS DOUBLE) * b.pairs * sign(b.layer - a.layer) * {d}) AS delta FROM ranked a, ranked b GROUP BY a.layer),
totals AS (SELECT layer, sum(delta) OVER (ORDER BY layer) AS total FROM deltas),
mus AS (SELECT layer, s.n, s.cum_pairs, coalesce(total / nullif({normalizer}, 0), 0) AS mu FROM totals JOIN summed s USING (layer)),
dmus AS (SELECT *, lead(mu) OVER (ORDER BY layer) - mu AS dmu FROM mus)"""


def _smooth(sigma: float = 1.0, half: int = 2) -> str:
    top, bottom = [], []
    for x in range(-half, half + 1):
        w = repr(math.exp(-x * x / (2 * sigma * sigma)))
        v = f"lead(dmu, {x}) OVER o" if x > 0 else f"lag(dmu, {-x}) OVER o" if x < 0 else "dmu"
        top.append(f"{w}::DOUBLE * coalesce({v}, 0)")
        bottom.append(f"CASE WHEN {v} IS NOT NULL THEN {w}::DOUBLE ELSE 0 END")
    return f"""
smooths AS (SELECT *, CASE WHEN dmu IS NOT NULL THEN ({" + ".join(top)}) / ({" + ".join(bottom)}) END AS dmu_smooth FROM dmus WINDOW o AS (ORDER BY layer)),
unsup AS (SELECT coalesce(min(layer) FILTER (WHERE round(dmu_smooth, 9) < 0), max(layer)) AS layer FROM smooths)"""


def _with(*parts: str) -> str:
    return "WITH RECURSIVE " + ",".join(parts) + "\n"


_GRID = (PLACES, BOX)
_PAIRS = (*_GRID, blocks(), pairs())


def _compared(m: float = 100) -> tuple[str, ...]:
    return (PLACES, BOX, blocks(m), pairs(), _CATS, COMPARED)


def _ranked(m: float = 100, label: str = "label", sample: bool = False) -> tuple[str, ...]:
    base = (*_compared(m), SAMPLE) if sample else _compared(m)
    return (*base, vectors(label, "compared_sample" if sample else "compared"), layered())


def _levels(m: float = 100, label: str = "label", sample: bool = False) -> tuple[str, ...]:
    return (*_ranked(m, label, sample), LEVELS)


def _prf(tp: str, fp: str, fn: str) -> str:
    return f"round(coalesce({tp} / nullif({tp} + {fp}, 0), 0), 6) AS precision, round(coalesce({tp} / nullif({tp} + {fn}, 0), 0), 6) AS recall, round(coalesce(2 * {tp} / nullif(2 * {tp} + {fp} + {fn}, 0), 0), 6) AS f1"


def _confusion(match: str) -> str:
    cells = (("tp", "{m} AND label = 1"), ("fp", "{m} AND label = 0"), ("fn", "NOT ({m}) AND label = 1"), ("tn", "NOT ({m}) AND label = 0"))
    return ", ".join(f"CAST(count(*) FILTER (WHERE {c.format(m=match)}) AS BIGINT) AS {n}" for n, c in cells)


_LEVEL_OUT = "SELECT layer, pairs, positives, cum_pairs, tp, fp, fn, tn, precision, recall, round(f1, 6) AS f1, hit_rate FROM levels"
_SEPARATION = (*_levels(), mu(), _smooth())
_JOIN_RANKED = "compared c JOIN ranked r ON c.name_sim = r.name_sim AND c.address_sim = r.address_sim AND c.semantic_sim = r.semantic_sim"
_STOP = """
stops AS (
  SELECT coalesce(min(layer) FILTER (WHERE fell), 0) AS drop_at, max(layer) AS layers FROM (SELECT layer, f1 < lag(f1) OVER (ORDER BY layer) AS fell FROM levels)),
stop AS (SELECT CASE WHEN drop_at = 0 THEN layers ELSE drop_at - 1 END AS layer, CASE WHEN drop_at = 0 THEN layers ELSE drop_at END AS seen, layers FROM stops)"""


def _stop_row(m: float) -> str:
    return f"""SELECT * FROM ({_with(*_levels(m), BEST, _STOP)}
      SELECT CAST({m} AS INTEGER) AS m, s.layer, s.layers, round(l.f1, 6) AS f1, b.layer AS best, b.f1 AS best_f1, round(s.seen / s.layers, 6) AS explored_share, round(b.f1 - round(l.f1, 6), 6) AS f1_loss
      FROM stop s JOIN levels l ON l.layer = s.layer, best b)"""


_GAP = """SELECT u.layer AS unsupervised, b.layer AS best, b.layers, round(l.f1, 6) AS f1, b.f1 AS best_f1, abs(u.layer - b.layer) AS gap, round(b.f1 - round(l.f1, 6), 6) AS f1_loss
  FROM unsup u JOIN levels l ON l.layer = u.layer, best b"""


def _gap_row(m: float) -> str:
    return f"SELECT * FROM ({_with(*_levels(m), BEST, mu(), _smooth())} SELECT CAST({m} AS INTEGER) AS m, g.* FROM ({_GAP}) g)"


_GEO = "greatest(0.0, 1 - dist_m / 100.0::DOUBLE)"
_ADDITIVE = {"a": f"floor(((name_sim + address_text + {_GEO}) / 3) * 1000000.0::DOUBLE + 0.5::DOUBLE) / 1000000.0::DOUBLE", "b": f"floor(((name_sim + {_GEO}) / 2) * 1000000.0::DOUBLE + 0.5::DOUBLE) / 1000000.0::DOUBLE"}


def _additive_sweep(which: str) -> str:
    return f"""SELECT threshold, tp, fp, fn, tn, {_prf("tp", "fp", "fn")} FROM (
      SELECT threshold, {_confusion("score >= threshold")} FROM (SELECT {_ADDITIVE[which]} AS score, label FROM compared), (SELECT unnest([{", ".join(f"{t}::DOUBLE" for t in THRESHOLDS)}]) AS threshold) GROUP BY threshold)"""


_RESNIK = """
freq AS (SELECT term, count(*) AS n FROM (SELECT lower(split_part(p_name, ' ', 2)) AS term FROM part UNION ALL SELECT lower(p_type) FROM part UNION ALL SELECT lower(c_mktsegment) FROM customer) GROUP BY term),
above AS (SELECT DISTINCT term, unnest(path) AS ancestor FROM paths),
info AS (SELECT ancestor, -ln(sum(n) / (SELECT sum(n) FROM freq)) AS ic FROM above JOIN freq USING (term) GROUP BY ancestor),
told AS (SELECT a.term AS ta, b.term AS tb, max(ic) AS ic FROM above a JOIN above b USING (ancestor) JOIN info USING (ancestor) JOIN freq f ON f.term = a.term JOIN freq g ON g.term = b.term WHERE a.term <= b.term GROUP BY ALL),
resnik AS (SELECT ta AS term_a, tb AS term_b, round(coalesce(ic / nullif((SELECT max(ic) FROM told), 0), 0) + 0.0::DOUBLE, 6) AS resnik FROM told)"""
# name, category (information content) and place: two thirds; address (edits): one third
_TOPK = f"""{_RESNIK},
scored AS (
  SELECT *, floor(((name_sim + coalesce(resnik, 0.0) + {_GEO}) * {2 / 9!r}::DOUBLE + address_text * {1 / 3!r}::DOUBLE) * 1000000.0::DOUBLE + 0.5::DOUBLE) / 1000000.0::DOUBLE AS score FROM compared
  LEFT JOIN resnik ON term_a = least(keywords_a[1], keywords_b[1]) AND term_b = greatest(keywords_a[1], keywords_b[1])
  WHERE list_has_any(string_split(lower(name_a), ' '), string_split(lower(name_b), ' ')) OR list_has_any(keywords_a, keywords_b)),
ends AS (SELECT eid_a, eid_b, score, eid_a AS side, eid_b AS other FROM scored UNION ALL SELECT eid_a, eid_b, score, eid_b, eid_a FROM scored),
placed AS (SELECT *, row_number() OVER (PARTITION BY side ORDER BY score DESC, other) AS rank FROM ends),
topped AS (SELECT s.*, t.k FROM scored s JOIN (SELECT eid_a, eid_b, min(rank) AS k FROM placed GROUP BY ALL) t USING (eid_a, eid_b))"""
_TOPK_SWEEP = f"""SELECT CAST(k AS INTEGER) AS k, tp, fp, fn, tn, {_prf("tp", "fp", "fn")} FROM (
  SELECT k, CAST(t AS BIGINT) AS tp, CAST(n - t AS BIGINT) AS fp, CAST(p - t AS BIGINT) AS fn, CAST(a - n - p + t AS BIGINT) AS tn
  FROM (SELECT k, sum(count(*)) OVER (ORDER BY k) AS n, sum(sum(label)) OVER (ORDER BY k) AS t FROM topped GROUP BY k), (SELECT count(*) AS a, sum(label) AS p FROM compared))"""


def _belief() -> str:
    parts = []
    for i, (name, alpha) in enumerate(RELIABILITY.items()):
        s = "greatest(0.0, 1 - dist_m / 5.0::DOUBLE)" if name == "geo_sim" else name
        parts.append((f"({s}) * {alpha}::DOUBLE", f"(1 - ({s})) * {alpha}::DOUBLE", f"{1 - alpha!r}::DOUBLE"))
    sql = f"near0 AS (SELECT *, {parts[0][0]} AS f0, {parts[0][1]} AS g0, {parts[0][2]} AS u0 FROM compared WHERE dist_m <= 5)"
    for i, (f, g, u) in enumerate(parts[1:], 1):
        a, b, c = f"f{i - 1}", f"g{i - 1}", f"u{i - 1}"
        sql += f""",
near{i} AS (SELECT *, ({a} * nf + {a} * nu + {c} * nf) / rest AS f{i}, ({b} * ng + {b} * nu + {c} * ng) / rest AS g{i}, {c} * nu / rest AS u{i}
  FROM (SELECT *, greatest(1 - ({a} * ng + {b} * nf), 1e-12::DOUBLE) AS rest FROM (SELECT * EXCLUDE (rest, nf, ng, nu), {f} AS nf, {g} AS ng, {u} AS nu FROM near{i - 1}{"" if i > 1 else "_pad"})))"""
        if i == 1:
            sql = sql.replace("near1 AS", "near0_pad AS (SELECT *, 0 AS rest, 0 AS nf, 0 AS ng, 0 AS nu FROM near0),\nnear1 AS", 1)
    return sql


_LAST = len(RELIABILITY) - 1
_BELIEF = _belief()
_MATCHED = (*_levels(), BEST)
_CLASSES = (*_SEPARATION, BEST)
_RADIUS = """
near AS (
  SELECT a.eid eid_a, b.eid eid_b, sqrt(CAST((a.x_m - b.x_m) * (a.x_m - b.x_m) + (a.y_m - b.y_m) * (a.y_m - b.y_m) AS DOUBLE)) dist_m
  FROM places a JOIN places b ON a.eid < b.eid AND abs(a.x_m - b.x_m) <= 100 AND abs(a.y_m - b.y_m) <= 100
  WHERE (a.x_m - b.x_m) * (a.x_m - b.x_m) + (a.y_m - b.y_m) * (a.y_m - b.y_m) <= 10000)"""
_NEAR_OUT = "SELECT eid_a, eid_b, round(dist_m, 6) AS dist_m FROM near"
_TWO = (*_PAIRS, blocks(margin=0.0, name="plain"), pairs("plain", "plain_pairs"))
_SESSIONS = """
fresh AS (SELECT *, CASE WHEN ts - lag(ts) OVER b <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW b AS (PARTITION BY user_id ORDER BY ts, event_id)),
sessions AS (
  SELECT user_id, session, min(ts) AS open, max(ts) AS close, count(*) AS events
  FROM (SELECT *, CAST(sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS session FROM fresh) GROUP BY ALL)"""
_RAW = """SELECT '{1}' AS tree, CAST(coalesce(sum(c * (c - 1) // 2), 0) AS BIGINT) AS comparisons FROM (SELECT count(*) AS c FROM {0} GROUP BY ix, iy)"""
_COVER = """SELECT '{1}' AS tree, CAST(radius AS DOUBLE) AS radius, count(*) AS reference_pairs, count(p.eid_a) AS found_pairs, round(count(p.eid_a) / count(*), 6) AS coverage
  FROM (SELECT unnest([{2}]) AS radius), near n LEFT JOIN {0} p ON n.eid_a = p.eid_a AND n.eid_b = p.eid_b WHERE n.dist_m <= radius GROUP BY radius"""
_LINKED = "linked AS (SELECT eid_a AS eid FROM compared WHERE label = 1 UNION SELECT eid_b FROM compared WHERE label = 1)"
_POINTS = "places AS (SELECT o_orderkey * 7 + r AS eid, '' AS source, (7919 + 2 * r) * o_orderkey % 11790 AS x_m, (104729 * o_custkey + (31 + 6 * r) * o_orderkey) % 11790 AS y_m FROM orders, range(7) t(r))"


def _classified(cut: str) -> str:
    return f"SELECT c.*, r.layer, r.layer <= (SELECT layer FROM {cut}) AS match FROM {_JOIN_RANKED}"


def _column(c: str) -> str:
    return _with(*_compared()) + f"SELECT eid_a, eid_b, {c} FROM compared"


def _mu_variant(name: str, over: str) -> str:
    return f"SELECT layer, round(coalesce(total / nullif({over}, 0), 0), 4) + 0.0::DOUBLE AS mu, '{name}' AS normalizer FROM totals JOIN summed s USING (layer)"


_DOC = """
vectors AS (
  SELECT f_letters, f_unique_words, f_unique_lines, f_length, count(*) AS pairs, CAST(sum(label) AS BIGINT) AS positives FROM (
    SELECT floor((length(regexp_replace(text, '[^A-Za-z]', '', 'g')) / greatest(length(text), 1)) * 1000 + 0.5) / 1000 AS f_letters,
      floor((len(list_distinct(string_split(text, ' '))) / len(string_split(text, ' '))) * 1000 + 0.5) / 1000 AS f_unique_words,
      floor((len(list_distinct(string_split(text, chr(10)))) / len(string_split(text, chr(10)))) * 1000 + 0.5) / 1000 AS f_unique_lines,
      floor((least(length(text), 2000) / 2000) * 1000 + 0.5) / 1000 AS f_length, quality AS label FROM documents JOIN labels USING (doc_id)) GROUP BY ALL)"""
_DOC_ATTRS = ("f_letters", "f_unique_words", "f_unique_lines", "f_length")

ORACLES = {
    "places": _with(PLACES) + "SELECT eid, source, truth_id, x_m, y_m, name, address, keywords, phone_clean, website_clean FROM places",
    "places_by_source": _with(PLACES) + "SELECT source, count(*) AS n, count(DISTINCT truth_id) AS truths FROM places GROUP BY source",
    "source_rollup": _with(PLACES) + "SELECT source, truth_id // 80 AS town, count(*) AS n FROM places GROUP BY ROLLUP (source, truth_id // 80)",
    "root_box": _with(*_GRID, blocks()) + "SELECT x0, y0, x1, y1, level FROM blocks_level",
    "within_radius": _with(PLACES) + "SELECT eid, x_m, y_m FROM places WHERE (x_m - 500) * (x_m - 500) + (y_m - 500) * (y_m - 500) <= 90000",
    "within_box": _with(PLACES) + "SELECT eid, x_m, y_m FROM places WHERE x_m BETWEEN 100 AND 600 AND y_m BETWEEN 100 AND 700",
    "project_degrees": _with(PLACES) + "SELECT eid, round(radians((10.0::DOUBLE + x_m / 60000) - 10.0::DOUBLE) * cos(radians(57.0::DOUBLE)) * 6371008.8::DOUBLE, 3) AS px, round(radians((57.0::DOUBLE + y_m / 111000) - 57.0::DOUBLE) * 6371008.8::DOUBLE, 3) AS py FROM places",
    "blocks_m100": _with(*_GRID, blocks()) + "SELECT level, ix, iy, eid, is_home FROM blocks",
    "blocks_cover_m100": _with(*_GRID, blocks(rule="cover")) + "SELECT level, ix, iy, eid, is_home FROM blocks",
    "quadtree_m100": _with(*_GRID, blocks(margin=0.0)) + "SELECT level, ix, iy, eid FROM blocks",
    "block_sizes": _with(*_GRID, blocks()) + "SELECT size, count(*) AS blocks FROM (SELECT count(*) AS size FROM blocks GROUP BY ix, iy) GROUP BY size",
    "block_size_percentiles": _with(*_GRID, blocks()) + "SELECT quantile_cont(size, 0.5)::DOUBLE AS p50, quantile_cont(size, 0.9)::DOUBLE AS p90, quantile_cont(size, 0.99)::DOUBLE AS p99, max(size) AS largest FROM (SELECT count(*) AS size FROM blocks GROUP BY ix, iy)",
    "home_leaf": _with(*_GRID, blocks()) + "SELECT eid, hx AS ix, hy AS iy FROM blocks_range",
    "pairs_m100": _with(*_PAIRS) + "SELECT eid_a, eid_b, round(dist_m, 6) AS dist_m FROM pairs",
    "pairs_cross_source": _with(*_PAIRS) + "SELECT eid_a, eid_b, round(dist_m, 6) AS dist_m FROM pairs WHERE source_a != source_b",
    "pairs_within_source": _with(*_PAIRS) + "SELECT eid_a, eid_b, round(dist_m, 6) AS dist_m FROM pairs WHERE source_a = source_b",
    "pairs_cover_m100": _with(PLACES, _RADIUS) + _NEAR_OUT,
    "raw_comparisons": _with(*_GRID, blocks(), blocks(margin=0.0, name="plain")) + _RAW.format("blocks", "overlap") + " UNION ALL " + _RAW.format("plain", "plain"),
    "points_comparisons": _with(_POINTS, BOX, blocks(), blocks(margin=0.0, name="plain")) + _RAW.format("blocks", "overlap") + " UNION ALL " + _RAW.format("plain", "plain"),
    "radius_pairs_100": _with(PLACES, _RADIUS) + _NEAR_OUT,
    "radius_pairs_sorted": _with(PLACES, _RADIUS) + _NEAR_OUT,
    "no_index_pairs": _with(PLACES, _RADIUS) + _NEAR_OUT,
    "pairs_only_overlap": _with(*_TWO) + "SELECT eid_a, eid_b FROM pairs EXCEPT SELECT eid_a, eid_b FROM plain_pairs",
    "pairs_both": _with(*_TWO) + "SELECT eid_a, eid_b FROM pairs INTERSECT SELECT eid_a, eid_b FROM plain_pairs",
    "pairs_either": _with(*_TWO) + "SELECT eid_a, eid_b FROM pairs UNION SELECT eid_a, eid_b FROM plain_pairs",
    "coverage_by_radius": _with(*_TWO, _RADIUS) + _COVER.format("pairs", "overlap", ", ".join(map(str, _RADII))) + " UNION ALL " + _COVER.format("plain_pairs", "plain", ", ".join(map(str, _RADII))),
    "blocking_recall": _with(*_compared()) + "SELECT found, true_pairs, round(found / true_pairs, 6) AS recall FROM (SELECT CAST(sum(label) AS BIGINT) AS found FROM compared), (SELECT CAST(sum(n * (n - 1) // 2) AS BIGINT) AS true_pairs FROM (SELECT count(*) AS n FROM places GROUP BY truth_id))",
    "name_similarity": _column("name_sim"),
    "address_similarity": _column("address_sim"),
    "address_as_text": _column("address_text"),
    "keyword_similarity": _column("semantic_sim"),
    "phone_equal": _with(*_compared()) + "SELECT eid_a, eid_b FROM compared WHERE phone_a = phone_b",
    "website_equal": _with(*_compared()) + "SELECT eid_a, eid_b FROM compared WHERE site_a = site_b",
    "geo_similarity": _column(f"round({_GEO}, 6) AS geo_sim"),
    "pair_vectors": _column("name_sim, address_sim, semantic_sim, label_auto, label"),
    "positive_share": _with(*_compared()) + "SELECT count(*) AS pairs, round(avg(label), 6) AS positive_share FROM compared",
    "clean_urls": f"SELECT page_id, {_SITE.format('url')} AS site FROM pages",
    "url_hosts": f"SELECT split_part({_SITE.format('url')}, '/', 1) AS host, count(*) AS pages FROM pages GROUP BY ALL",
    "clean_phones": _with(PLACES) + "SELECT eid, phone_clean AS phone FROM places WHERE phone IS NOT NULL",
    "document_phones": rf"SELECT DISTINCT doc_id, {_phone('raw', '1')} AS phone FROM (SELECT doc_id, unnest(regexp_extract_all(text, '\+1 \([0-9]{{3}}\) 555-[0-9]{{4}}')) AS raw FROM documents)",
    "term_depths": _with(_CATS) + "SELECT term, CAST(min(len(path)) AS INTEGER) AS depth, count(*) AS paths FROM paths GROUP BY term",
    "wup_pairs": _with(_CATS) + "SELECT ta AS term_a, tb AS term_b, round(sim, 6) AS wup FROM wup WHERE ta <= tb",
    "resnik_pairs": _with(_CATS, _RESNIK) + "SELECT term_a, term_b, resnik FROM resnik",
    "nation_similarity": _with(_CATS) + "SELECT ta AS term_a, tb AS term_b, round(sim, 6) AS wup FROM wup WHERE ta <= tb AND ta IN (SELECT lower(n_name) FROM nation) AND tb IN (SELECT lower(n_name) FROM nation)",
    "user_sessions": _with(_SESSIONS) + "SELECT user_id, session, open, close, events FROM sessions",
    "session_overlap": _with(_SESSIONS) + "SELECT a.user_id AS user_id_a, a.session AS session_a, b.user_id AS user_id_b, b.session AS session_b FROM sessions a JOIN sessions b ON a.user_id < b.user_id AND ((a.open < b.close AND b.open < a.close) OR (a.open = b.open AND a.close = b.close))",
    "last_event_before": "SELECT event_id, user_id, click FROM (SELECT *, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS click FROM events) WHERE event_type = 'error'",
    "distinct_vectors": _with(*_compared(), vectors()) + "SELECT * FROM vectors",
    "vector_layers": _with(*_ranked()) + "SELECT name_sim, address_sim, semantic_sim, pairs, positives, layer FROM ranked",
    "first_front": _with(*_ranked()) + "SELECT name_sim, address_sim, semantic_sim FROM ranked WHERE layer = 1",
    "pair_layers": _with(*_ranked()) + f"SELECT eid_a, eid_b, layer FROM {_JOIN_RANKED}",
    "layer_sizes": _with(*_ranked()) + "SELECT layer, count(*) AS vectors, CAST(sum(pairs) AS BIGINT) AS pairs FROM ranked GROUP BY layer",
    "sum_rank": _with(*_compared(), vectors()) + "SELECT name_sim, address_sim, semantic_sim, total, CAST(dense_rank() OVER (ORDER BY total DESC) AS INTEGER) AS layer FROM (SELECT *, round(0.0::DOUBLE + name_sim + address_sim + semantic_sim, 6) AS total FROM vectors)",
    "doc_layers": _with(_DOC, layered(_DOC_ATTRS)) + "SELECT f_letters, f_unique_words, f_unique_lines, f_length, pairs, positives, layer FROM ranked",
    "level_curve_full": _with(*_levels()) + _LEVEL_OUT,
    "level_curve_auto": _with(*_levels(label="label_auto")) + _LEVEL_OUT,
    "level_curve_sample": _with(*_levels(sample=True)) + _LEVEL_OUT,
    "hit_rates": _with(*_levels()) + "SELECT layer, hit_rate, positives / pairs > lag(positives / pairs) OVER (ORDER BY layer) AS rises FROM levels",
    "fixed_cut_10": _with(*_ranked()) + f"SELECT eid_a, eid_b, layer FROM {_JOIN_RANKED} WHERE layer <= 10",
    "sweep_cut_full": _with(*_levels(), BEST) + "SELECT * FROM best",
    "sweep_cut_auto": _with(*_levels(label="label_auto"), BEST) + "SELECT * FROM best",
    "sweep_cut_sample": _with(*_levels(sample=True), BEST) + "SELECT * FROM best",
    "early_stop_cut": _with(*_levels(), _STOP) + "SELECT s.layer, round(l.f1, 6) AS f1 FROM stop s JOIN levels l ON l.layer = s.layer",
    "early_stop_by_m": " UNION ALL ".join(_stop_row(m) for m in _CUT_M),
    "sweep_by_m": " UNION ALL ".join(f"SELECT * FROM ({_with(*_levels(m), BEST)} SELECT CAST({m} AS INTEGER) AS m, b.*, (SELECT max(tp) FROM levels) AS positives, (SELECT max(cum_pairs) FROM levels) AS pairs FROM best b)" for m in _M_VALUES),
    "mu_curve": _with(*_levels(), mu()) + "SELECT layer, round(mu, 6) + 0.0::DOUBLE AS mu FROM mus",
    "mu_curve_squared": _with(*_levels(), mu("sqeuclidean")) + "SELECT layer, round(mu, 6) + 0.0::DOUBLE AS mu FROM mus",
    "mu_curve_manhattan": _with(*_levels(), mu("manhattan")) + "SELECT layer, round(mu, 6) + 0.0::DOUBLE AS mu FROM mus",
    "mu_variants": _with(*_levels(), mu("sqeuclidean")) + " UNION ALL ".join(_mu_variant(n, o) for n, o in (("ranked", "s.n"), ("explored", "s.cum_pairs"), ("cross", "s.cum_pairs * (s.n - s.cum_pairs)"), ("remaining", "s.n - s.cum_pairs"))),
    "mu_derivative": _with(*_levels(), mu()) + "SELECT layer, round(dmu, 6) AS dmu FROM dmus",
    "mu_smoothed": _with(*_SEPARATION) + "SELECT layer, round(dmu_smooth, 6) AS dmu_smooth FROM smooths",
    "separation_cut": _with(*_SEPARATION) + "SELECT layer FROM unsup",
    "separation_by_m": " UNION ALL ".join(_gap_row(m) for m in _CUT_M),
    "cut_gap": _with(*_CLASSES) + _GAP,
    "matches_sweep": _with(*_MATCHED) + f"SELECT eid_a, eid_b, layer, label FROM ({_classified('best')}) WHERE match",
    "matches_separation": _with(*_SEPARATION) + f"SELECT eid_a, eid_b, layer, label FROM ({_classified('unsup')}) WHERE match",
    "confusion_by_method": _with(*_CLASSES) + f"""SELECT method, same_source, tp, fp, fn, tn, {_prf("tp", "fp", "fn")} FROM (
      SELECT method, source_a = source_b AS same_source, {_confusion("match")} FROM (SELECT 'sweep' AS method, * FROM ({_classified("best")}) UNION ALL SELECT 'separation', * FROM ({_classified("unsup")})) GROUP BY GROUPING SETS ((method), (method, source_a = source_b)))""",
    "class_grid": _with(*_MATCHED) + f"SELECT name_bin, address_bin, count(*) AS pairs, CAST(sum(label) AS BIGINT) AS positives, count(*) FILTER (WHERE match) AS matches FROM (SELECT *, CAST(floor(name_sim * 5) AS INTEGER) AS name_bin, CAST(floor(address_sim * 5) AS INTEGER) AS address_bin FROM ({_classified('best')})) GROUP BY CUBE (name_bin, address_bin)",
    "links_by_source": _with(*_compared()) + "SELECT least(source_a, source_b) AS source_1, greatest(source_a, source_b) AS source_2, count(*) AS links FROM compared WHERE label = 1 GROUP BY ALL",
    "source_profile": _with(*_compared(), _LINKED) + "SELECT source, count(*) AS places, count(l.eid) AS matched FROM places p LEFT JOIN linked l ON p.eid = l.eid GROUP BY source",
    "matched_places": _with(*_compared(), _LINKED) + "SELECT eid, source FROM places WHERE eid IN (SELECT eid FROM linked)",
    "unmatched_places": _with(*_compared(), _LINKED) + "SELECT eid, source FROM places WHERE eid NOT IN (SELECT eid FROM linked)",
    "prediction_vs_truth": _with(*_MATCHED) + f"""SELECT coalesce(predicted, false) AS predicted, coalesce("true", false) AS "true", count(*) AS pairs FROM (SELECT eid_a, eid_b, true AS predicted FROM ({_classified("best")}) WHERE match) FULL JOIN
      (SELECT a.eid AS eid_a, b.eid AS eid_b, true AS "true" FROM places a JOIN places b ON a.truth_id = b.truth_id AND a.eid < b.eid) USING (eid_a, eid_b) GROUP BY ALL""",
    "additive_a": _with(*_compared()) + f"SELECT eid_a, eid_b, {_ADDITIVE['a']} AS score FROM compared WHERE {_ADDITIVE['a']} >= 0.75",
    "additive_b": _with(*_compared()) + f"SELECT eid_a, eid_b, {_ADDITIVE['b']} AS score FROM compared WHERE {_ADDITIVE['b']} >= 0.75",
    "additive_a_sweep": _with(*_compared()) + _additive_sweep("a"),
    "additive_b_sweep": _with(*_compared()) + _additive_sweep("b"),
    "additive_pivot": _with(*_compared()) + f"SELECT threshold, a.f1 AS f1_a, b.f1 AS f1_b FROM ({_additive_sweep('a')}) a JOIN ({_additive_sweep('b')}) b USING (threshold)",
    "weighted_topk": _with(*_compared(), _TOPK) + "SELECT eid_a, eid_b FROM topped WHERE k <= 3",
    "weighted_topk_sweep": _with(*_compared(), _TOPK) + _TOPK_SWEEP,
    "belief_links": _with(*_compared(), _BELIEF) + f"SELECT * FROM (SELECT eid_a, eid_b, floor((f{_LAST}) * 1000000.0::DOUBLE + 0.5::DOUBLE) / 1000000.0::DOUBLE AS belief, floor((g{_LAST}) * 1000000.0::DOUBLE + 0.5::DOUBLE) / 1000000.0::DOUBLE AS disbelief FROM near{_LAST}) WHERE belief > disbelief",
    "link_groups": _with(*_MATCHED) + f""", links AS (SELECT eid_a AS a, eid_b AS b FROM ({_classified("best")}) WHERE match),
      both_ways AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links), reach(x, y) AS (SELECT eid, eid FROM places UNION SELECT x, b FROM reach JOIN both_ways ON y = a)
      SELECT eid, g AS "group" FROM places JOIN (SELECT x, min(y) AS g FROM reach GROUP BY x) ON x = eid""",
}

ORACLES |= {
    "stream_places_dedup": _with(PLACES) + "SELECT DISTINCT eid FROM events JOIN places ON source = 'catalog' AND truth_id = event_id % (SELECT count(*) FROM part)",
    "window_arrivals_tumbling": "SELECT date_trunc('hour', ts) AS start, (date_trunc('hour', ts) + INTERVAL 1 HOUR) AS \"end\", count(*) AS n FROM events GROUP BY ALL",
    "window_arrivals_sliding": "SELECT s AS start, (s + INTERVAL 1 HOUR) AS \"end\", count(*) AS n FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - x * INTERVAL 30 MINUTE AS s FROM events, range(2) r(x)) GROUP BY ALL",
    "window_arrivals_session": """SELECT user_id, min(ts) AS start, (max(ts) + INTERVAL 30 MINUTE) AS "end", count(*) AS n FROM (
      SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (
        SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, session""",
}


# --- trees whose leaves lie on several levels: one set of common table expressions per level --------------------------

_MAX_LEVEL, _DENSITY_SCALE = 16, 0.5
_START = "start AS (SELECT CAST(coalesce(min(l) FILTER (WHERE sqrt((x1 - x0) ** 2 + (y1 - y0) ** 2) / (2 ** l) <= 100), 24) AS INTEGER) AS level, any_value(x0) x0, any_value(y0) y0, any_value(x1) x1, any_value(y1) y1 FROM box, range(25) r(l))"


def tree(full: str, count: str = "count(*)", margin: float = 0.25, start: str = "(SELECT level FROM start)", top: int = _MAX_LEVEL, name: str = "leaves") -> str:
    """leaves(level, ix, iy, eid, is_home, x_m, y_m, source, rid): a cell splits while its count exceeds `full` (of w and h)."""
    parts = []
    for x in range(top + 1):
        n = 2**x
        at = lambda v, low, high: f"({v} - {low}) / nullif(({high} - {low}) / {n}, 0)"
        ax, ay = at("x_m", "x0", "x1"), at("y_m", "y0", "y1")
        first, last = (f"greatest(ceil(%s - {1 + 2 * margin}), 0)", f"least(floor(%s + {2 * margin}), {n - 1})") if margin else (f"least(floor(%s), {n - 1})",) * 2
        span = lambda a: f"unnest(range(CAST(coalesce({first % a}, 0) AS BIGINT), CAST(coalesce({last % a}, 0) AS BIGINT) + 1))"
        home = lambda a: f"CAST(coalesce(least(floor({a}), {n - 1}), 0) AS BIGINT)"
        if x == 0:
            cells = f"SELECT eid, x_m, y_m, source, rid, CAST(0 AS BIGINT) ix, CAST(0 AS BIGINT) iy, true AS is_home FROM places WHERE {start} = 0"
        else:
            every = f"SELECT *, {span(ay)} AS iy FROM (SELECT p.*, x0, y0, x1, y1, {home(ax)} hx, {home(ay)} hy, {span(ax)} AS ix FROM places p, start)"
            cells = f"SELECT eid, x_m, y_m, source, rid, ix, iy, ix = hx AND iy = hy AS is_home FROM ({every}) c WHERE {start} = {x} OR {start} < {x} AND EXISTS (SELECT 1 FROM {name}_split{x - 1} s WHERE s.ix = c.ix // 2 AND s.iy = c.iy // 2)"
        parts.append(f"{name}_cells{x} AS MATERIALIZED ({cells})")
        if x < top:
            w, h = f"((SELECT x1 - x0 FROM start) / {n})", f"((SELECT y1 - y0 FROM start) / {n})"
            parts.append(f"{name}_split{x} AS MATERIALIZED (SELECT ix, iy FROM {name}_cells{x} GROUP BY ix, iy HAVING {count} > {full.format(w=w, h=h)})")
    left = lambda x: f"SELECT CAST({x} AS INTEGER) AS level, * FROM {name}_cells{x}" + (f" WHERE (ix, iy) NOT IN (SELECT (ix, iy) FROM {name}_split{x})" if x < top else "")
    parts.append(f"{name} AS MATERIALIZED (" + " UNION ALL ".join(map(left, range(top + 1))) + ")")
    return ",\n".join(parts)


def _dense(d: float = 20, **more) -> str:
    return tree(f"{d * _DENSITY_SCALE!r}::DOUBLE * {{w}} * {{h}} / 1000", **more)


_LEAF_PAIRS = """
common AS (SELECT a.eid AS ea, b.eid AS eb, min((a.level, a.ix, a.iy)) AS least FROM leaves a JOIN leaves b ON a.level = b.level AND a.ix = b.ix AND a.iy = b.iy AND a.eid < b.eid GROUP BY ALL),
pairs AS (
  SELECT a.eid eid_a, b.eid eid_b, sqrt(CAST((a.x_m - b.x_m) * (a.x_m - b.x_m) + (a.y_m - b.y_m) * (a.y_m - b.y_m) AS DOUBLE)) dist_m, a.source source_a, b.source source_b, a.rid rid_a, b.rid rid_b
  FROM leaves a JOIN leaves b ON a.level = b.level AND a.ix = b.ix AND a.iy = b.iy AND a.eid < b.eid JOIN common c ON c.ea = a.eid AND c.eb = b.eid AND c.least = (a.level, a.ix, a.iy))"""


def _half_plane() -> str:
    parts = ["half0 AS (SELECT eid, x_m, y_m, CAST(0 AS BIGINT) ix, CAST(0 AS BIGINT) iy FROM places)"]
    sides = lambda v, p, s, i: f"unnest(list_filter([CASE WHEN {v} <= {p} + 1.5 * {s} THEN 2 * {i} END, CASE WHEN {v} >= {p} + 0.5 * {s} THEN 2 * {i} + 1 END], lambda z: z IS NOT NULL))"
    for x in range(1, _MAX_LEVEL + 1):
        w, h = f"((x1 - x0) / {2**x})", f"((y1 - y0) / {2**x})"
        parts.append(f"""half{x} AS MATERIALIZED (SELECT eid, x_m, y_m, nx AS ix, {sides("y_m", f"(y0 + iy * 2 * {h})", h, "iy")} AS iy FROM (
          SELECT *, {sides("x_m", f"(x0 + ix * 2 * {w})", w, "ix")} AS nx FROM half{x - 1}, start WHERE level >= {x}))""")
    return ",\n".join(parts)


def _half_plane_out() -> str:
    return " UNION ALL ".join(f"SELECT CAST({x} AS INTEGER) AS level, ix, iy, count(*) AS size FROM half{x} WHERE (SELECT level FROM start) = {x} GROUP BY ix, iy" for x in range(_MAX_LEVEL + 1))


_GRID_AT = (PLACES, BOX, _START)
_LEAVES_OUT = "SELECT level, ix, iy, eid, is_home FROM leaves"
_COINCIDENT = PLACES.replace("\nplaces AS (SELECT *,", "\nplaces AS (SELECT * REPLACE (x_m - x_m % 300 AS x_m, y_m - y_m % 300 AS y_m),")


def _density_row(d: float) -> str:
    return f"""SELECT * FROM ({_with(*_GRID_AT, _dense(d), _LEAF_PAIRS, _CATS, COMPARED, vectors(), layered(), LEVELS, BEST)}
      SELECT CAST({d} AS INTEGER) AS density, b.*, (SELECT max(tp) FROM levels) AS positives, (SELECT max(cum_pairs) FROM levels) AS pairs FROM best b)"""


ORACLES |= {
    "blocks_density": _with(*_GRID_AT, _dense()) + _LEAVES_OUT,
    "blocks_density_alone": _with(*_GRID_AT, _dense(count="count(*) FILTER (WHERE is_home)", start="0")) + _LEAVES_OUT,
    "capacity_leaves": _with(*_GRID_AT, tree("50", margin=0.0, start="0")) + "SELECT level, ix, iy, count(*) AS size FROM leaves GROUP BY level, ix, iy",
    "blocks_half_plane": _with(*_GRID_AT, _half_plane()) + _half_plane_out(),
    "blocks_coincident": _with(_COINCIDENT, BOX, _START, _dense(top=10)) + "SELECT level, count(*) AS rows FROM leaves GROUP BY level",
    "pairs_density": _with(*_GRID_AT, _dense(), _LEAF_PAIRS) + "SELECT eid_a, eid_b, round(dist_m, 6) AS dist_m FROM pairs",
    "sweep_by_density": " UNION ALL ".join(_density_row(d) for d in (10, 20, 30, 40, 50, 60)),
}

# --- both data sets, all kinds of labels ------------------------------------------------------------------------------


def _data_set(label: str = "label", sample: bool = False, m: float = 100) -> tuple[str, ...]:
    """compared, with the chosen label as `label`, of all pairs or of the checked sample."""
    some = " ORDER BY md5(eid_a || eid_b), eid_a, eid_b LIMIT 1500" if sample else ""
    return (PLACES, BOX, blocks(m), pairs(), _CATS, COMPARED.replace("\ncompared AS", "\ncompared_all AS"), f"compared AS (SELECT * REPLACE ({label} AS label) FROM compared_all{some})")


def _summary(label: str = "label", sample: bool = False) -> str:
    base = _with(*_data_set(label, sample), _TOPK, vectors(), layered(), LEVELS, BEST, mu(), _smooth(), _BELIEF)
    out = f"tp, fp, fn, tn, {_prf('tp', 'fp', 'fn')}"
    rows = [f"SELECT 'additive {w.upper()} .75' AS method, {out} FROM (SELECT {_confusion(f'{_ADDITIVE[w]} >= 0.75')} FROM compared)" for w in "ab"]
    rows += [f"SELECT * FROM (SELECT 'additive {w.upper()} best' AS method, tp, fp, fn, tn, precision, recall, f1 FROM ({_additive_sweep(w)}) ORDER BY f1 DESC, threshold LIMIT 1)" for w in "ab"]
    rows.append(f"SELECT * FROM (SELECT 'weighted top-k best' AS method, tp, fp, fn, tn, precision, recall, f1 FROM ({_TOPK_SWEEP}) ORDER BY f1 DESC, k LIMIT 1)")
    near = f"floor((f{_LAST}) * 1000000.0::DOUBLE + 0.5::DOUBLE) > floor((g{_LAST}) * 1000000.0::DOUBLE + 0.5::DOUBLE)"
    rows.append(f"""SELECT 'belief' AS method, {out} FROM (SELECT (SELECT count(*) FROM near{_LAST} WHERE {near} AND label = 1) AS tp, (SELECT count(*) FROM near{_LAST} WHERE {near} AND label = 0) AS fp,
      (SELECT count(*) FROM compared WHERE label = 1) - (SELECT count(*) FROM near{_LAST} WHERE {near} AND label = 1) AS fn, (SELECT count(*) FROM compared WHERE label = 0) - (SELECT count(*) FROM near{_LAST} WHERE {near} AND label = 0) AS tn)""")
    rows += [f"SELECT '{n} cut' AS method, {out} FROM levels WHERE layer = (SELECT layer FROM {t})" for n, t in (("sweep", "best"), ("separation", "unsup"))]
    return base + " UNION ALL ".join(rows)


def _protocol_row(protocol: str) -> str:
    own = "WHERE checked" if protocol == "sample" else ""
    curve = "WHERE checked" if protocol == "transfer" else ""
    tested = "WHERE NOT checked" if protocol == "transfer" else ""
    base = _with(
        PLACES, BOX, blocks(30), pairs(), _CATS, COMPARED.replace("\ncompared AS", "\ncompared_all AS"),
        "numbered_pairs AS (SELECT *, row_number() OVER (ORDER BY md5(eid_a || eid_b), eid_a, eid_b) <= greatest(1, least(1500, (SELECT count(*) FROM compared_all) // 3)) AS checked FROM compared_all)",
        f"compared AS (SELECT * FROM numbered_pairs {own})", vectors(), layered(), LEVELS, BEST, mu(), _smooth(),
        f"placed_pairs AS (SELECT c.*, r.layer FROM {_JOIN_RANKED})",
        f"tuned_per AS (SELECT layer, count(*) n, sum(label) t FROM placed_pairs {curve} GROUP BY layer)",
        "tuned AS (SELECT layer FROM (SELECT layer, 2 * sum(t) OVER (ORDER BY layer) / (sum(n) OVER (ORDER BY layer) + sum(t) OVER ()) AS f1 FROM tuned_per) ORDER BY f1 DESC, layer LIMIT 1)",
    )
    cuts = [f"SELECT '{protocol}' AS protocol, '{n}' AS method, tp, fp, fn, tn, {_prf('tp', 'fp', 'fn')} FROM (SELECT {_confusion(f'layer <= (SELECT layer FROM {t})')} FROM placed_pairs {tested})" for n, t in (("sweep", "tuned"), ("separation", "unsup"))]
    return f"SELECT * FROM ({base} {' UNION ALL '.join(cuts)})"


def _grid_rows(m: float) -> str:
    parts, rows = list(_levels(m)), []
    deltas = mu()
    parts.append(deltas[: deltas.index(",\nmus AS")])
    for n, over in (("ranked", "s.n"), ("explored", "s.cum_pairs"), ("cross", "s.cum_pairs * (s.n - s.cum_pairs)"), ("remaining", "s.n - s.cum_pairs")):
        parts.append(f"mus_{n} AS (SELECT layer, coalesce(total / nullif({over}, 0), 0) AS mu FROM totals JOIN summed s USING (layer))")
        parts.append(f"dmus_{n} AS (SELECT *, lead(mu) OVER (ORDER BY layer) - mu AS dmu FROM mus_{n})")
        for sigma in (1.0, 3.0, 6.0):
            smooth = _smooth(sigma, int(2 * sigma))
            smooth = smooth[: smooth.index(",\nunsup AS")].replace("smooths AS", f"sm_{n}_{sigma:.0f} AS MATERIALIZED").replace("FROM dmus ", f"FROM dmus_{n} ")
            parts.append(smooth)
            d = "round(dmu_smooth, 9)"
            for trigger, hit in (("first_negative", "v < 0"), ("first_decrease", "v < before"), ("negative_after_rise", "v < 0 AND highest > 0")):
                rows.append(f"""SELECT '{n}' AS normalizer, '{trigger}' AS trigger, {sigma!r}::DOUBLE AS sigma, coalesce(min(layer) FILTER (WHERE {hit}), max(layer)) AS layer
                  FROM (SELECT layer, {d} AS v, lag({d}) OVER (ORDER BY layer) AS before, max({d}) OVER (ORDER BY layer) AS highest FROM sm_{n}_{sigma:.0f})""")
    return f"SELECT * FROM ({_with(*parts)} SELECT CAST({m} AS INTEGER) AS m, normalizer, trigger, sigma, layer, round(l.f1, 6) AS f1 FROM ({' UNION ALL '.join(rows)}) JOIN levels l USING (layer))"


_NEAR_PAIRS = """
pairs AS (
  SELECT a.eid eid_a, b.eid eid_b, sqrt(CAST((a.x_m - b.x_m) * (a.x_m - b.x_m) + (a.y_m - b.y_m) * (a.y_m - b.y_m) AS DOUBLE)) dist_m, a.source source_a, b.source source_b, a.rid rid_a, b.rid rid_b
  FROM places a JOIN places b ON a.eid < b.eid AND abs(a.x_m - b.x_m) <= 100 AND abs(a.y_m - b.y_m) <= 100
  WHERE (a.x_m - b.x_m) * (a.x_m - b.x_m) + (a.y_m - b.y_m) * (a.y_m - b.y_m) <= 10000)"""
_DOT = "list_sum(list_transform(range(1, 17), lambda i: {a}[{o} + i] * {b}[{o} + i]))"
_EMBEDDING = (
    "e AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS v FROM embeddings WHERE embedding IS NOT NULL)",
    "cosines AS (SELECT "
    + ", ".join(f"floor(({_DOT.format(a='a.v', b='b.v', o=o)} / sqrt({_DOT.format(a='a.v', b='a.v', o=o)} * {_DOT.format(a='b.v', b='b.v', o=o)}) + 1) / 2 * 10000.0::DOUBLE + 0.5::DOUBLE) / 10000.0::DOUBLE AS s{o // 16 + 1}" for o in (0, 16, 32, 48))
    + ", CAST(a.label = b.label AS INTEGER) AS label FROM e a JOIN e b ON b.vec_id BETWEEN a.vec_id + 1 AND a.vec_id + 3)",
    "vectors AS (SELECT s1, s2, s3, s4, count(*) AS pairs, CAST(sum(label) AS BIGINT) AS positives FROM cosines GROUP BY ALL)",
)
_STREAM_RANKED = (
    "near_pairs AS (SELECT * FROM compared WHERE dist_m <= 30)",
    "vectors AS (SELECT name_sim, address_sim, count(*) AS pairs, CAST(sum(label) AS BIGINT) AS positives FROM near_pairs GROUP BY ALL)",
    layered(("name_sim", "address_sim")), LEVELS, BEST,
    "arrived AS (SELECT DISTINCT event_id % (SELECT count(*) FROM part) AS i FROM events)",
    "linked_pairs AS (SELECT c.*, a.truth_id FROM compared c JOIN places a ON a.rid = c.rid_a WHERE source_a = 'catalog' AND source_b != 'catalog' AND a.truth_id IN (SELECT i FROM arrived))",
    "known AS (SELECT v.name_sim, v.address_sim, coalesce(max(r.layer), 0) + CAST(count(*) FILTER (WHERE r.name_sim = v.name_sim AND r.address_sim = v.address_sim) = 0 AS INTEGER) AS layer FROM (SELECT DISTINCT name_sim, address_sim FROM linked_pairs) v LEFT JOIN ranked r ON r.name_sim >= v.name_sim AND r.address_sim >= v.address_sim GROUP BY ALL)",
)

ORACLES |= {
    "baseline_summary": _summary(),
    "baseline_summary_auto": _summary("label_auto"),
    "baseline_summary_mixed": _summary("label_mixed"),
    "baseline_summary_sample": _summary(sample=True),
    "weighted_topk_sweep_sample": _with(*_data_set(sample=True), _TOPK) + _TOPK_SWEEP,
    "weighted_topk_sweep_auto": _with(*_data_set("label_auto"), _TOPK) + _TOPK_SWEEP,
    "additive_a_sweep_sample": _with(*_data_set(sample=True)) + _additive_sweep("a"),
    "additive_b_sweep_sample": _with(*_data_set(sample=True)) + _additive_sweep("b"),
    "level_curve_mixed": _with(*_levels(label="label_mixed")) + _LEVEL_OUT,
    "sweep_cut_mixed": _with(*_levels(label="label_mixed"), BEST) + "SELECT * FROM best",
    "cuts_by_protocol": " UNION ALL ".join(map(_protocol_row, ("full", "sample", "transfer"))),
    "separation_grid": " UNION ALL ".join(map(_grid_rows, (30, 100))),
    "whole_method": _with(PLACES, _NEAR_PAIRS, _CATS, COMPARED, vectors(), layered(), LEVELS, mu(), _smooth()) + f"SELECT 'separation' AS method, tp, fp, fn, tn, {_prf('tp', 'fp', 'fn')} FROM levels WHERE layer = (SELECT layer FROM unsup)",
    "embedding_layers": _with(*_EMBEDDING, layered(("s1", "s2", "s3", "s4"))) + "SELECT layer, count(*) AS vectors, CAST(sum(pairs) AS BIGINT) AS pairs, CAST(sum(positives) AS BIGINT) AS positives FROM ranked GROUP BY layer",
    "stream_links": _with(*_compared(), *_STREAM_RANKED) + "SELECT eid_a AS eid, eid_b, p.name_sim, p.address_sim, CAST(k.layer AS INTEGER) AS layer, k.layer <= (SELECT layer FROM best) AS match FROM linked_pairs p JOIN known k ON k.name_sim = p.name_sim AND k.address_sim = p.address_sim",
    "late_arrivals": """SELECT date_trunc('hour', ts) AS start, (date_trunc('hour', ts) + INTERVAL 1 HOUR) AS "end", count(*) AS n FROM events, (SELECT max(ts) AS last FROM events)
      WHERE NOT (event_id % 50 = 0 AND ts < last - INTERVAL 1 DAY) AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= last - INTERVAL 1 HOUR GROUP BY ALL""",
}
