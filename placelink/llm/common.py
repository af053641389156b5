"""What several operators share: the shared folder, cut lineage, and hash arithmetic on whole batches of texts.

Texts are handled as the UTF-8 bytes of an Arrow batch: words are maximal runs without the bytes 0x20 and 0x09-0x0D,
which are all ASCII, so byte positions are safe cuts. A null text counts as an empty one.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from placelink.operators.storage import shared_dir, stored

__all__ = ["shared_dir", "stored"]

#: Fixed value: a word is a run of other characters than these.
WORD = r"[^\x20\x09-\x0D]+"

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
_BLOCK = 1 << 20
#: Spans of more bytes are hashed one by one.
_LONG = 1 << 16
#: Fixed value: the Mersenne prime of the span hashes, and the base of their polynomials.
_PRIME = np.uint64(2**61 - 1)
_BASE = 0x12F2A7C5D1B3E947 % (2**61 - 1)
_HALF, _LOW = np.uint64(32), np.uint64(2**32 - 1)


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def share_of(id_col: Column, salt: str) -> Column:
    """A uniform number in [0, 1) of 52 bits, the same on every run and in other engines (md5 of the id)."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt), F.coalesce(id_col.cast("string"), F.lit("")))), 1, 13), 16, 10).cast("long") / F.lit(2.0**52)


def bounded_ids(df: DataFrame, id_col: str, bound: int) -> DataFrame:
    """At most bound rows, those of the smallest hash: a documented bound for fitting, nothing else."""
    return df.orderBy(F.xxhash64(id_col), id_col).limit(bound)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scored(docs: DataFrame, score: Callable[[np.ndarray, np.ndarray], np.ndarray], columns: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The given columns of every row of docs and the score of its text (a function of a block of texts)."""
    rows = docs.select(*columns, *(["text"] if "text" not in columns else []))
    schema = T.StructType([*(rows.schema[k] for k in columns), T.StructField("score", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, data, at in chunks(batch.column("text")):
                own = [batch.column(k).slice(i, j - i) for k in columns]
                yield pa.RecordBatch.from_arrays([*own, pa.array(score(data, at))], names=[*columns, "score"])

    return rows.mapInArrow(run, schema)


# --- bytes of a batch -------------------------------------------------------------------------------------------


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column end to end, and where each text starts (one more entry than texts)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.fill_null("").cast(pa.large_string())
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    at = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8)[at[0] : at[-1]] if column.buffers()[2] else np.zeros(0, np.uint8)
    return data, at - at[0]


def chunks(column: pa.Array, most: int = _BLOCK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Rows [i, j) of about `most` bytes at once (a longer text stands alone): i, j, bytes, starts."""
    data, at = text_bytes(column)
    i, n = 0, len(at) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(at, at[i] + most, side="right")) - 1)
        yield i, j, data[at[i] : at[j]], at[i : j + 1] - at[i]
        i = j


def _reduced(x: np.ndarray) -> np.ndarray:
    """Values below 2^64 modulo the prime."""
    x = (x & _PRIME) + (x >> np.uint64(61))
    return np.where(x >= _PRIME, x - _PRIME, x)


def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products modulo the prime of values below it, in halves of 31 and 30 bits."""
    thirty, low, most = np.uint64(30), np.uint64(2**30 - 1), np.uint64(2**31 - 1)
    a1, a0, b1, b0 = a >> np.uint64(31), a & most, b >> np.uint64(31), b & most
    middle = a1 * b0 + a0 * b1
    # 2^61 counts as 1: the upper product comes twice, the middle one is split at 30 bits
    return _reduced(_reduced(a1 * b1 * np.uint64(2) + (middle >> thirty) + ((middle & low) << np.uint64(31))) + a0 * b0)


_powers: list[np.ndarray] = []


def _pow() -> np.ndarray:
    """The powers of the base up to the bytes that a block of spans can have."""
    if not _powers:
        power = np.ones(1, np.uint64)
        while len(power) <= _BLOCK + _LONG:
            top = np.array([pow(_BASE, len(power), 2**61 - 1)], np.uint64)
            power = np.concatenate([power, times(power, np.broadcast_to(top, len(power)))])
        _powers.append(power[: _BLOCK + _LONG + 1])
    return _powers[0]


def mix(h: np.ndarray) -> np.ndarray:
    """Spreads 64-bit values (a bijection), so that arithmetic patterns vanish."""
    h = h ^ (h >> np.uint64(31))
    h = h * np.uint64(0x7FB5D329728EA185)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x81DADEF4BC2DD44D)
    return h ^ (h >> np.uint64(33))


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes of each span; spans are ordered and do not overlap.

    Short spans are polynomials modulo a prime, from running sums over a block of them, brought to one power of the base;
    long ones are hashed one by one.
    """
    out = np.zeros(len(starts), np.uint64)
    long = ends - starts > _LONG
    for k in np.flatnonzero(long):
        out[k] = xxhash.xxh3_64_intdigest(data[starts[k] : ends[k]].tobytes())
    spot = np.flatnonzero(~long)
    starts, ends = starts[spot], ends[spot]
    power, k = _pow(), 0
    while k < len(starts):
        last = max(k + 1, int(np.searchsorted(ends, starts[k] + _BLOCK, side="right")))
        a, b = int(starts[k]), int(ends[last - 1])
        digit = data[a:b].astype(np.uint64) + np.uint64(1)
        s, e = starts[k:last] - a, ends[k:last] - a
        whole = np.zeros(last - k, np.uint64)
        for shift, part in ((32, power[: b - a] >> _HALF), (0, power[: b - a] & _LOW)):  # at most 2^21 sums of 2^41
            sums = np.zeros(b - a + 1, np.uint64)
            np.cumsum(digit * part, out=sums[1:])
            piece = _reduced(sums[e] - sums[s])
            whole = _reduced(whole + (times(piece, np.full(len(piece), 2**32, np.uint64)) if shift else piece))
        out[spot[k:last]] = mix(times(whole, power[len(power) - 1 - s]) + ((e - s).astype(np.uint64) << np.uint64(43)))
        k = last
    return out


def word_spans(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end (byte positions) and number of text of every word."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, none
    space = _SPACE[data]
    before = np.empty(len(data), bool)
    before[0], before[1:] = True, space[:-1]
    cuts = at[:-1][at[:-1] < len(data)]
    before[cuts] = True
    after = np.empty(len(data), bool)
    after[-1], after[:-1] = True, before[1:]
    after[:-1] |= space[1:]
    word = ~space
    starts, ends = np.flatnonzero(word & before), np.flatnonzero(word & after) + 1
    return starts, ends, np.searchsorted(at, starts, side="right") - 1


def lower_ascii(data: np.ndarray) -> np.ndarray:
    return _LOWER[data]


def per_text(flags: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Sums of flags over the bytes of each text."""
    sums = np.zeros(len(flags) + 1, np.int64)
    np.cumsum(flags, out=sums[1:])
    return sums[at[1:]] - sums[at[:-1]]


def longer(rolled: np.ndarray, hashes: np.ndarray, n: int) -> np.ndarray:
    """Hashes of all runs of n words from those of all runs of n - 1 words."""
    m = max(0, len(hashes) - n + 1)
    return mix(rolled[:m] * np.uint64(0x9E3779B97F4A7C15) + hashes[n - 1 : n - 1 + m])


def runs(hashes: np.ndarray, n: int) -> np.ndarray:
    """Hashes of all runs of n words."""
    rolled = hashes
    for k in range(2, n + 1):
        rolled = longer(rolled, hashes, k)
    return rolled


def windows(rolled: np.ndarray, of: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """First word and hash of every run of n words that lies within a text; equal only inside one text."""
    m = len(rolled)
    if m <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    first = np.flatnonzero(of[:m] == of[n - 1 :])
    return first, mix(rolled[first] + mix(of[first].astype(np.uint64) + np.uint64(n)))


def repeated(keys: np.ndarray) -> np.ndarray:
    """Whether each key occurs twice or more."""
    if len(keys) < 2:
        return np.zeros(len(keys), bool)
    ordered = np.sort(keys)
    twice = ordered[1:][ordered[1:] == ordered[:-1]]
    if not len(twice):
        return np.zeros(len(keys), bool)
    spot = np.searchsorted(twice, keys)
    spot[spot == len(twice)] = 0
    return twice[spot] == keys
