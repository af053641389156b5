"""Quality rules on repetition, measured with rolling hashes of whole batches in numpy.

A text fails when too many of its characters lie in its most frequent n-gram (n 2 to 4), in n-grams that it had before
(n 5 to 10) or in lines that it had before: what could go without loss. N-grams are windows of words; their hashes roll over the word hashes of a
block of texts at once (each length from the one before), keyed by text, so that one sort finds what repeats.

Defined cases: a null text is empty, has no words and is not kept (it fails the base rule of ten words); repeated rows
and null ids pass through as they are; of measures that tie as the worst the first of LIMITS is named; a measure at its
limit passes; an empty table gives an empty result; only doc_id and text are read, so other columns may have any name;
memory is bounded by about 1 MB of text at once, or one text if that is longer.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from placelink.llm import common as c
from placelink.llm.common import table

#: Symbols of the base rule, and the largest shares of characters (published web-text quality rules).
SYMBOLS = "#*$%&|<>"
MOST_FREQUENT = {2: 0.20, 3: 0.18, 4: 0.16}
REPEATED = {5: 0.15, 6: 0.14, 7: 0.13, 8: 0.12, 9: 0.11, 10: 0.10}
REPEATED_LINES = 0.20

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(x) for x in SYMBOLS]] = True

SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, worst_measure string, worst_ratio double"


class Words:
    """The words of some texts: spans, hashes, characters, and sums by text."""

    def __init__(self, data: np.ndarray, at: np.ndarray):
        self.data, self.at, self.texts = data, at, len(at) - 1
        self.starts, self.ends, self.of = c.word_spans(data, at)
        self.hashes = c.span_hashes(data, self.starts, self.ends)
        self.leads = np.zeros(len(data) + 1, np.int64)  # code points before each byte
        np.cumsum((data & 0xC0) != 0x80, out=self.leads[1:])
        self.chars = self.leads[self.ends] - self.leads[self.starts]
        self.bounds = np.searchsorted(self.of, np.arange(self.texts + 1))
        self.n_words = np.diff(self.bounds)
        self.rolled, self.length = self.hashes, 1

    def windows(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """First word and key of every window of n words; cheapest when asked for in ascending order."""
        if n < self.length:
            self.rolled, self.length = self.hashes, 1
        while self.length < n:
            self.length += 1
            self.rolled = c.longer(self.rolled, self.hashes, self.length)
        return c.windows(self.rolled, self.of, n)

    def sum(self, values: np.ndarray) -> np.ndarray:
        sums = np.zeros(len(values) + 1, np.int64)
        np.cumsum(values, out=sums[1:])
        return sums[self.bounds[1:]] - sums[self.bounds[:-1]]

    def covered(self, n: int, first_too: bool = True) -> np.ndarray:
        """Whether each word lies in a window of n words that its text has twice or more, the first one included or not."""
        first, keys = self.windows(n)
        twice = c.repeated(keys)
        first, keys = first[twice], keys[twice]
        if not first_too:
            order = np.argsort(keys, kind="stable")
            first = first[order[1:]][keys[order[1:]] == keys[order[:-1]]]
        edge = np.zeros(len(self.hashes) + 1, np.int64)
        np.add.at(edge, first, 1)
        np.add.at(edge, first + n, -1)
        return np.cumsum(edge[:-1]) > 0

    def most_frequent(self, n: int) -> np.ndarray:
        """Characters of each text in its most frequent window of n words, if it has that twice or more."""
        first, keys = self.windows(n)
        out = np.zeros(self.texts, np.int64)
        twice = c.repeated(keys)
        first, keys = first[twice], keys[twice]
        if len(keys):
            order = np.argsort(keys, kind="stable")
            keys, first = keys[order], first[order]
            run = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
            total = np.r_[0, np.cumsum(self.chars)]
            chars = np.diff(np.r_[run, len(keys)]) * (total[first[run] + n] - total[first[run]])
            np.maximum.at(out, self.of[first[run]], chars)
        return out

    def lines(self) -> tuple[np.ndarray, np.ndarray]:
        """Number and characters of each text's lines that have a word and equal an earlier line."""
        breaks = np.flatnonzero(self.data == 10)
        starts = np.unique(np.concatenate([self.at[:-1], breaks + 1]))
        starts = starts[starts < len(self.data)]
        of = np.searchsorted(self.at, starts, side="right") - 1
        ends = np.minimum(np.r_[breaks, len(self.data)][np.searchsorted(breaks, starts)], self.at[of + 1])
        worded = np.searchsorted(self.starts, ends) > np.searchsorted(self.starts, starts)
        starts, ends, of = starts[worded], ends[worded], of[worded]
        keys = c.mix(c.span_hashes(self.data, starts, ends) + c.mix(of.astype(np.uint64)))
        order = np.argsort(keys, kind="stable")
        again = order[1:][keys[order][1:] == keys[order][:-1]]
        count = np.bincount(of[again], minlength=self.texts)
        chars = np.bincount(of[again], weights=self.leads[ends[again]] - self.leads[starts[again]], minlength=self.texts)
        return count.astype(np.int64), chars.astype(np.int64)


def measure(data: np.ndarray, at: np.ndarray) -> dict[str, np.ndarray]:
    """The base counts of every text and its shares of repeated characters."""
    w = Words(data, at)
    chars = w.sum(w.chars)
    n_lines, line_chars = w.lines()
    out = {"n_words": w.n_words, "word_chars": chars, "n_symbols": c.per_text(_SYMBOL[data], at), "n_dup_lines": n_lines}
    share = np.maximum(chars, 1)
    out["lines"] = line_chars / np.maximum(w.leads[at[1:]] - w.leads[at[:-1]], 1)
    for n in MOST_FREQUENT:
        out[f"most_frequent_{n}"] = w.most_frequent(n) / share
    for n in REPEATED:
        if n == 5:
            out["n_repeat_words"] = w.sum(w.covered(n))
        out[f"repeated_{n}"] = w.sum(w.covered(n, first_too=False) * w.chars) / share
    return out


LIMITS = {"lines": REPEATED_LINES} | {f"most_frequent_{n}": x for n, x in MOST_FREQUENT.items()} | {f"repeated_{n}": x for n, x in REPEATED.items()}


def judge(documents: DataFrame, limits: dict[str, float] = LIMITS) -> DataFrame:
    """doc_id, the base counts, base_failed, kept, and the measure that comes nearest to (or farthest over) its limit."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = list(limits)
        for batch in batches:
            for i, j, data, at in c.chunks(batch.column("text")):
                m = measure(data, at)
                ratio = np.stack([m[k] / limits[k] for k in names])
                worst = ratio.argmax(axis=0)
                failed = (m["n_words"] < 10) | (100 * m["n_repeat_words"] > 20 * m["n_words"])
                arrays = [batch.column("doc_id").slice(i, j - i).cast(pa.int64())]
                arrays += [pa.array(m[k].astype(np.int64)) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
                arrays += [pa.array(failed), pa.array(~failed & (ratio.max(axis=0) <= 1)), pa.array([names[k] for k in worst]), pa.array(np.floor(ratio.max(axis=0) * 10_000 + 0.5) / 10_000)]
                yield pa.RecordBatch.from_arrays(arrays, names=[x.split()[0] for x in SCHEMA.split(", ")])

    return documents.select("doc_id", "text").mapInArrow(run, SCHEMA)


def op9_repetition(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"))


def _sql() -> str:
    grams = lambda n: f"grams_{n} AS MATERIALIZED (SELECT doc_id, i, array_to_string(w[i : i + {n - 1}], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - {n - 2})) AS i FROM split))"
    parts = [grams(n) for n in (*MOST_FREQUENT, *REPEATED)]
    parts += [f"most_frequent_{n} AS (SELECT doc_id, max(c * (len(g) - {n - 1})) AS x FROM (SELECT doc_id, g, count(*) AS c FROM grams_{n} GROUP BY ALL) WHERE c > 1 GROUP BY doc_id)" for n in MOST_FREQUENT]
    for n in REPEATED:
        again = f"SELECT doc_id, i, row_number() OVER (PARTITION BY doc_id, g ORDER BY i) AS turn FROM grams_{n}"
        parts.append(f"repeated_{n} AS (SELECT doc_id, sum(size) AS x FROM (SELECT DISTINCT doc_id, unnest(range(i, i + {n})) AS i FROM ({again}) WHERE turn > 1) JOIN words USING (doc_id, i) GROUP BY doc_id)")
    measures = [*(f"most_frequent_{n}" for n in MOST_FREQUENT), *(f"repeated_{n}" for n in REPEATED)]
    ratios = ", ".join(["coalesce(l.chars, 0) / greatest(d.chars, 1) / " + f"{REPEATED_LINES}::DOUBLE", *(f"coalesce({m}.x, 0) / greatest(coalesce(t.word_chars, 0), 1) / {LIMITS[m]}::DOUBLE" for m in measures)])
    joins = " ".join(f"LEFT JOIN {m} USING (doc_id)" for m in measures)
    names = ", ".join(f"'{k}'" for k in LIMITS)
    return rf"""
WITH split AS (
  SELECT doc_id, coalesce(text, '') AS text, len(coalesce(text, '')) AS chars, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
words AS MATERIALIZED (SELECT doc_id, unnest(range(1, len(w) + 1)) AS i, len(unnest(w)) AS size FROM split),
totals AS (SELECT doc_id, sum(size) AS word_chars FROM words GROUP BY doc_id),
lines AS (SELECT doc_id, len(line) AS size, row_number() OVER (PARTITION BY doc_id, line) > 1 AS again FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM split) WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
dup AS (SELECT doc_id, count(*) AS n, sum(size) AS chars FROM lines WHERE again GROUP BY doc_id),
{", ".join(parts)},
windows AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM grams_5),
covered AS (SELECT doc_id, count(DISTINCT k) AS n FROM (SELECT doc_id, unnest(range(i, i + 5)) AS k FROM windows WHERE c > 1) GROUP BY doc_id),
judged AS (
  SELECT doc_id, len(d.w) AS n_words, coalesce(t.word_chars, 0) AS word_chars, len(regexp_extract_all(d.text, '[#*$%&|<>]')) AS n_symbols, coalesce(l.n, 0) AS n_dup_lines, coalesce(c.n, 0) AS n_repeat_words, [{ratios}] AS ratios
  FROM split d LEFT JOIN totals t USING (doc_id) LEFT JOIN dup l USING (doc_id) LEFT JOIN covered c USING (doc_id) {joins})
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words,
  n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed, NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND list_max(ratios) <= 1 AS kept,
  [{names}][list_position(ratios, list_max(ratios))] AS worst_measure, floor(list_max(ratios) * 10000.0::DOUBLE + 0.5::DOUBLE) / 10000.0::DOUBLE AS worst_ratio
FROM judged
"""


OP9_SQL = _sql()
