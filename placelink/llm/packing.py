"""Packing into token sequences by deficit round-robin over source queues.

Texts are tokenized once. Each source is a queue; a round (one sequence of `size` tokens, on average) adds to the deficit
of every queue its target share of a window. A queue whose share is QUANTUM tokens or more is served its whole deficit
in every round; one with less keeps its deficit until it has QUANTUM tokens, so that many small sources are not cut to
shreds, and queues begin with different deficits, so that their turns spread over the rounds. In closed form: after j of
W rounds a queue of T tokens that began with d has been given floor((floor(j * T / W) + d) / q) * q tokens, T at most, all
of them after the last round (q: 1 or QUANTUM). What it has been owed beyond that is its deficit, which it carries across
windows and partitions alike. Rounds are laid end to end and cut at multiples of `size`, so that all sequences but the
last are full. With target weights other than the queues' own sizes, queues run out one after the other: each such phase
is a round-robin of its own over the queues that remain.

Because the plan is closed, a task needs only the totals per queue and where its rows start in their queues; token ids
are written once and never shuffled. The arithmetic is exact up to 10^16 tokens.

Defined cases: a null text is empty and has the end id only; null sources are one queue; more than MAX_QUEUES sources are
an error, as one number for each reaches every task (group them first); repeated rows are documents of their own, also
where their ids are null; documents of one source are packed in the order of their partitions; a very long text is
tokenized whole and may fill many sequences; an empty table gives no pieces; only doc_id, text and source are read, so
other columns may have any name.
"""

from __future__ import annotations

import json
import re
import zlib
from array import array
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from placelink.llm.common import stored, table

SIZE, END_ID, QUANTUM = 4096, 2, 64
#: Sources that can be queues of their own: their totals go to the driver and to every task (1 MB).
MAX_QUEUES = 65_536
TOKENIZER = "word_bpe_49k.json"

#: Rows (queue, task, base) up to which the starts of the tasks are broadcast: some 20 MB.
BROADCAST_ROWS = 500_000
_CACHE_ENTRIES = 250_000
#: Numbers that remembered rounds of the plan may hold (some 24 MB).
_ROUND_NUMBERS = 1_000_000


class _Remembered(dict):
    """Answers by key, made when missing; all are forgotten when there are too many."""

    def __init__(self, make):
        super().__init__()
        self.make = make

    def __missing__(self, key: str) -> bytes:
        if len(self) >= _CACHE_ENTRIES:
            self.clear()
        self[key] = value = self.make(key)
        return value


#: The pre-tokenizer that PieceTokenizer knows a short way for, as tokenizer files spell it, and the same
#: pattern over lower-cased ASCII and Latin letters.
_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_SHORT_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ſ]+|[0-9]|[^ \n\t\ra-zß-öø-ſ0-9]+"


def _known(spec: dict) -> bool:
    """Whether a tokenizer file splits and normalises as the short way does."""
    split = {"type": "Split", "pattern": {"Regex": _PATTERN}, "behavior": "Removed", "invert": True}
    level = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}
    normal = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]
    model = spec.get("model") or {}
    return (
        (spec.get("normalizer") or {}).get("normalizers") == normal and (spec.get("pre_tokenizer") or {}).get("pretokenizers") == [split, level]
        and spec.get("post_processor") is None and model.get("type") == "BPE" and not model.get("dropout")
        and all(t["content"].startswith("<|") and not t["normalized"] for t in spec.get("added_tokens", []))
    )


class PieceTokenizer:
    """Ids of a tokenizer, the short way where its file is of the kind whose pieces never cross white space.

    There, texts of plain ASCII and Latin letters take the pre-tokenizer's own pattern, then the library's model on each
    piece, remembered piece by piece. Of other texts, each word between spaces goes the same way if it can, else through
    the whole tokenizer. All give the ids of the whole text. Any other tokenizer is always used whole.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        if self.whole.get_vocab_size() > 1 << 16:
            raise ValueError("ids are kept in 16 bits; the vocabulary has more than 65,536")
        with open(path, encoding="utf-8") as f:
            self.short = _known(json.load(f))
        self.model = self.whole.model
        self.pieces, self.others = _Remembered(self._piece), _Remembered(self._other)
        self.split = re.compile(_SHORT_PATTERN).findall
        self.simple = re.compile(r"[!-~ \n\t\rÀ-ÖØ-öø-įı-ſ]*").fullmatch
        # bytes as the characters that byte-level models use for them: printable ones as they are, others from 256 on
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        self.as_char = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(x for x in range(256) if x not in plain)}

    def _piece(self, piece: str) -> bytes:
        chars = piece if piece.isascii() else "".join(map(self.as_char.__getitem__, piece.encode()))
        return array("H", [t.id for t in self.model.tokenize(chars)]).tobytes()

    def _other(self, word: str) -> bytes:
        return array("H", self.whole.encode(word, add_special_tokens=False).ids).tobytes()

    def ids(self, text: str) -> bytes:
        """The ids of a text as little-endian 16-bit numbers."""
        if not self.short:
            return self._other(text)
        if self.simple(text) and "<|" not in text:
            return b"".join(map(self.pieces.__getitem__, self.split(text.lower())))
        parts = text.replace("\n", " ").split(" ")
        if len(parts) == 1:
            return self.others[text] if len(text) <= 64 else self._other(text)
        return b"".join(map(self.ids, parts))


_loaded: dict[str, PieceTokenizer] = {}


def _tokenizer(path: str) -> PieceTokenizer:
    """One per Python worker and file: workers are reused, so their memory of pieces is too."""
    if path not in _loaded:
        _loaded[path] = PieceTokenizer(path)
    return _loaded[path]


def tokenize(docs: DataFrame, path: str, end_id: int = END_ID) -> DataFrame:
    """doc_id, queue, task, before (tokens of the same queue earlier in this task), tokens, ids (16-bit)."""
    queue = F.coalesce(F.concat(F.lit("s"), F.col("source").cast("string")), F.lit("null"))
    end = np.uint16(end_id).tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer, so_far, task = _tokenizer(path), {}, TaskContext.get().partitionId()
        for batch in batches:
            ids, before, tokens = [], [], []
            of = batch.column("queue").to_pylist()
            for q, text in zip(of, batch.column("text"), strict=True):
                ids.append(tokenizer.ids(text.as_py() or "") + end)
                tokens.append(len(ids[-1]) // 2)
                before.append(so_far.get(q, 0))
                so_far[q] = before[-1] + tokens[-1]
                if len(ids) >= 512:
                    yield _tokenized(batch, len(ids), ids, before, tokens, task)
                    batch = batch.slice(len(ids))
                    ids, before, tokens = [], [], []
            if ids:
                yield _tokenized(batch, len(ids), ids, before, tokens, task)

    return docs.select("doc_id", queue.alias("queue"), "text").mapInArrow(run, "doc_id long, queue string, task int, before long, tokens long, ids binary")


def _tokenized(batch: pa.RecordBatch, n: int, ids: list, before: list, tokens: list, task: int) -> pa.RecordBatch:
    some = batch.slice(0, n)
    return pa.RecordBatch.from_arrays(
        [some.column("doc_id").cast(pa.int64()), some.column("queue").cast(pa.string()), pa.array([task] * n, pa.int32()), pa.array(before, pa.int64()), pa.array(tokens, pa.int64()), pa.array(ids, pa.binary())],
        names=["doc_id", "queue", "task", "before", "tokens", "ids"],
    )


def share(j: np.ndarray, take: np.ndarray, rounds: int) -> np.ndarray:
    """floor(j * take / rounds), without numbers beyond 64 bits while rounds are fewer than 10^12."""
    whole, part = take // rounds, take % rounds
    high, low = j >> 20, j & (1 << 20) - 1
    x, y = high * part // rounds, high * part % rounds
    return j * whole + (x << 20) + ((y << 20) + low * part) // rounds


@dataclass
class Phase:
    """A round-robin over some queues: what each has given before, what it gives now, and where the phase starts."""

    done: np.ndarray
    take: np.ndarray
    start: int
    rounds: int

    def __post_init__(self) -> None:
        n = np.arange(len(self.take))
        small = self.take < QUANTUM * max(1, self.rounds)
        self.quantum = np.where(small, QUANTUM, 1)
        self.first = np.where(small, (n * 0.6180339887498949 % 1 * QUANTUM).astype(np.int64), 0)  # spreads the turns
        self.rows: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}

    def given(self, j: int) -> np.ndarray:
        """Tokens that each queue has given after j rounds."""
        if j >= self.rounds:
            return self.take
        owed = share(np.full(len(self.take), j, np.int64), self.take, self.rounds) + self.first
        return np.minimum(self.take, owed // self.quantum * self.quantum)

    def round(self, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """What each queue has given before round k and after it, and where its turn starts on the line; remembered for a while."""
        if k not in self.rows:
            if len(self.rows) * len(self.take) > _ROUND_NUMBERS:
                self.rows.clear()
            given, after = self.given(k), self.given(k + 1)
            turns = after - given
            self.rows[k] = given, after, self.start + given.sum() + turns.cumsum() - turns
        return self.rows[k]

    def rounds_of(self, q: int, lo: int, hi: int) -> list[int]:
        """The rounds in which queue q gives its tokens lo to hi - 1, in order. Python's integers: any size."""
        take, quantum, first, rounds = int(self.take[q]), int(self.quantum[q]), int(self.first[q]), self.rounds
        if quantum == 1:  # the largest j with floor(j * take / rounds) <= token
            return list(range(((lo + 1) * rounds - 1) // take, (hi * rounds - 1) // take + 1))
        turns = range(lo // quantum, (hi - 1) // quantum + 1)
        return sorted({min(rounds, max(1, -(-((c + 1) * quantum - first) * rounds // take))) - 1 for c in turns})


def phases(totals: Sequence[int], weights: Sequence[float] | None = None, size: int = SIZE) -> list[Phase]:
    """The plan for queues of so many tokens. weights: target proportions (default: the totals, one phase)."""
    left = np.array(totals, np.int64)
    w = np.array(totals if weights is None else weights, float)
    if len(w) and not (w[left > 0] > 0).all():
        raise ValueError("every queue that has tokens needs a positive weight")
    out, done, start = [], np.zeros(len(left), np.int64), 0
    while left.sum():
        active = left > 0
        ratio = np.where(active, left / np.where(active, w, 1), np.inf)
        level = ratio.min()
        ends = active & (ratio <= level * (1 + 1e-12))
        take = np.where(ends, left, np.where(active, np.minimum(left, np.floor(level * w)), 0)).astype(np.int64)
        out.append(Phase(done.copy(), take, start, int(-(-take.sum() // size))))
        done, left, start = done + take, left - take, start + int(take.sum())
    return out


def pieces_of(plan: list[Phase], q: int, first: int, tokens: int, size: int = SIZE) -> Iterator[tuple[int, int, int]]:
    """(start in the document, length, place on the line of all sequences) of a document at `first` in queue q."""
    for p in plan:
        a, b = max(first, int(p.done[q])), min(first + tokens, int(p.done[q] + p.take[q]))
        if a >= b:
            continue
        done = int(p.done[q])
        for k in p.rounds_of(q, a - done, b - done):
            given, after, line = (int(v[q]) for v in p.round(k))
            x, y = max(a - done, given), min(b - done, after)
            at = line + x - given
            while x < y:  # a turn may lie across the end of a sequence
                n = min(y - x, size - at % size)
                yield x + done - first, n, at
                x, at = x + n, at + n


def pack(tokenized: DataFrame, weights: dict[str, float] | None = None, size: int = SIZE) -> DataFrame:
    """Pieces: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset. `tokenized` must be a stored table."""
    parts = tokenized.groupBy("queue", "task").agg(F.sum("tokens").alias("n"))
    totals = parts.groupBy("queue").agg(F.sum("n").alias("n")).orderBy("queue").limit(MAX_QUEUES + 1).toPandas()
    if len(totals) > MAX_QUEUES:
        raise ValueError(f"more than {MAX_QUEUES} sources; group them into fewer queues first")
    number = {q: i for i, q in enumerate(totals["queue"])}
    plan = phases(totals["n"].to_numpy(np.int64), None if weights is None else [weights.get(q, 1.0) for q in totals["queue"]], size)
    earlier = W.partitionBy("queue").orderBy("task").rowsBetween(W.unboundedPreceding, -1)
    bases = parts.select("queue", "task", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("base"))
    if parts.count() <= BROADCAST_ROWS:  # else Spark picks a join that shuffles
        bases = F.broadcast(bases)
    rows = tokenized.join(bases, ["queue", "task"]).select("doc_id", "queue", (F.col("base") + F.col("before")).alias("first"), "tokens", "ids")
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            columns = [batch.column(k) for k in ("doc_id", "queue", "first", "tokens", "ids")]
            for doc, q, first, tokens, ids in zip(*columns[:4], columns[4], strict=True):
                ids = np.frombuffer(ids.as_buffer(), "<u2").astype("<u4")
                doc, tokens = doc.as_py(), tokens.as_py()
                for start, n, at in pieces_of(plan, number[q.as_py()], first.as_py(), tokens, size):
                    out.append((doc, start, n, zlib.crc32(ids[start : start + n]), tokens, at // size, at % size))
                if len(out) > 20_000:
                    yield _rows(out, names)
                    out = []
            if out:
                yield _rows(out, names)

    return rows.mapInArrow(run, ", ".join(f"{k} long" for k in names))


def _rows(out: list[tuple], names: list[str]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*out, strict=True)], names=names)


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def pack_documents(docs: DataFrame, path: str | None = None) -> DataFrame:
    return pack(stored(tokenize(docs, path or tokenizer_path()), "packing-ids"))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
