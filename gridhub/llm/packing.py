"""Mixture-controlled packing by deficit round-robin over source queues.

Time runs in windows of some sequences.  In every window each source may send its share of
the window's tokens; what rounding keeps from it is a deficit that it carries into the next
window.  Shares are taken by nested floors, so the tokens sent by the first ``j`` sources
until window ``k`` are a monotone function of ``k`` alone: any task can tell, for any place
in any queue, the window that sends it, with all deficits of earlier windows and other
partitions inside.  Only prefix sums of token counts per block and source are exchanged.

Documents are queued block by block, a block being one input task.  Token ids are computed
once and staged; cutting reads them back.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridhub.llm.arrow import SLICE_BYTES, column, filled, text_slices
from gridhub.llm.tokens import slice_ids, word_tokenizer
from gridhub.plans.staging import stage

SEQUENCE = 4096
#: Sequences in one window of the round-robin.
WINDOW = 64
#: Rows of (block, source) offsets that are broadcast, a few MB.
BROADCAST_ROWS = 100_000
#: Numbers of windows and sources that a task remembers.
LEVELS = 1 << 21
#: Fixed value: the id that closes a document.
END_ID = 2


def _encode_documents(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, sent = TaskContext.get().partitionId(), {}
        for part in text_slices(batches, limit=2 * SLICE_BYTES):
            offsets, ids = slice_ids(filled(part), path)
            small = ids.astype("<u2") if not len(ids) or ids.max() < 65536 else ids.astype("<u4")
            wide = small.itemsize
            closed = np.insert(small, offsets[1:], end_id)  # the end id after each document
            ends = (offsets + np.arange(len(offsets))) * wide
            coded = pa.LargeBinaryArray.from_buffers(pa.large_binary(), part.num_rows, [None, pa.py_buffer(ends), pa.py_buffer(closed)]).cast(pa.binary())
            counts = (np.diff(offsets) + 1).tolist()
            starts = []
            for s, n in zip(column(part, "source").to_pylist(), counts):
                at = sent.get(s, 0)
                starts.append(at)
                sent[s] = at + n
            yield pa.RecordBatch.from_pydict({
                "block": pa.array([block] * part.num_rows, pa.int32()), "doc_id": column(part, "doc_id"), "source": column(part, "source"),
                "n": pa.array(counts, pa.int64()), "at": pa.array(starts, pa.int64()), "wide": pa.array([wide] * part.num_rows, pa.int32()), "ids": coded,
            })

    return run


def phases(totals: list[int], weights: list[float] | None) -> list[list[int]]:
    """Tokens that each source sends while the set of non-empty queues stays the same.

    Without weights every source has its natural share and all queues end together.  With
    weights, queues run dry one after the other and the rest go on by their weights.
    """
    if weights is None:
        return [list(totals)]
    left, out = list(totals), []
    while any(left):
        live = [i for i, n in enumerate(left) if n]
        shares = {i: weights[i] for i in live}
        if not sum(shares.values()):
            shares = dict.fromkeys(live, 1.0)
        first = min((i for i in live if shares[i]), key=lambda i: left[i] / shares[i])
        level = left[first] / shares[first]
        sends = [min(left[i], round(level * shares.get(i, 0.0))) if i in shares else 0 for i in range(len(left))]
        sends[first] = left[first]
        out.append(sends)
        left = [a - b for a, b in zip(left, sends)]
    return out


class RoundRobin:
    """Where every token of every queue goes."""

    def __init__(self, sends: list[list[int]], sequence: int = SEQUENCE, window: int = WINDOW):
        self.sequence, self.span = sequence, sequence * window
        self.upto, self.begin, self.first = [], [], []
        queue, position = [0] * len(sends[0]) if sends else [], 0
        for phase in sends:
            upto = [0]
            for n in phase:
                upto.append(upto[-1] + n)
            self.upto.append(upto)
            self.begin.append(list(queue))
            self.first.append(position)
            queue = [a + b for a, b in zip(queue, phase)]
            position += upto[-1]
        self.total, self._levels = position, {}
        tail = position % sequence
        self.tail_at = position - tail
        sizes = [1 << b for b in range(sequence.bit_length(), -1, -1) if tail >> b & 1]
        self.tail_cuts = [self.tail_at + sum(sizes[:i]) for i in range(len(sizes) + 1)]

    def levels(self, phase: int, k: int) -> list[int]:
        """Tokens sent by the first j sources in windows before the k-th of a phase."""
        known = self._levels.get((phase, k))
        if known is None:
            upto = self.upto[phase]
            known = [0] * len(upto)
            known[-1] = min(k * self.span, upto[-1])
            for j in range(len(upto) - 1, 0, -1):
                known[j - 1] = known[j] * upto[j - 1] // upto[j] if upto[j] else 0
            if len(self._levels) * len(upto) > LEVELS:
                self._levels.clear()
            self._levels[phase, k] = known
        return known

    def runs(self, source: int, start: int, stop: int) -> Iterator[tuple[int, int, int]]:
        """(queue place, place in the packed stream, length) for places start..stop."""
        for phase, upto in enumerate(self.upto):
            begin, many = self.begin[phase][source], upto[source + 1] - upto[source]
            a, b = max(start, begin) - begin, min(stop, begin + many) - begin
            if a >= b:
                continue
            sent = lambda k: self.levels(phase, k)[source + 1] - self.levels(phase, k)[source]  # noqa: E731, B023
            k = a * upto[-1] // many // self.span
            while k and sent(k) > a:
                k -= 1
            while sent(k + 1) <= a:
                k += 1
            while a < b:
                here, after = self.levels(phase, k), self.levels(phase, k + 1)
                upper = min(b, after[source + 1] - after[source])
                if upper > a:
                    place = self.first[phase] + here[-1] + (after[source] - here[source]) + a - (here[source + 1] - here[source])
                    yield begin + a, place, upper - a
                    a = upper
                k += 1

    def pieces(self, source: int, start: int, stop: int) -> Iterator[tuple[int, int, int, int]]:
        """(queue place, length, sequence, offset), cut at the ends of sequences."""
        open_piece: list[int] = []
        for at, place, n in self.runs(source, start, stop):
            while n:
                if place < self.tail_at:
                    seq, off = divmod(place, self.sequence)
                    room = self.sequence - off
                else:  # what is left over fills sequences of powers of two
                    i = max(i for i, c in enumerate(self.tail_cuts) if c <= place)
                    seq, off, room = self.tail_at // self.sequence + i, place - self.tail_cuts[i], self.tail_cuts[i + 1] - place
                take = min(n, room)
                if open_piece and open_piece[2] == seq and open_piece[3] + open_piece[1] == off:
                    open_piece[1] += take
                else:
                    if open_piece:
                        yield tuple(open_piece)
                    open_piece = [at, take, seq, off]
                at, place, n = at + take, place + take, n - take
        if open_piece:
            yield tuple(open_piece)


def pack(docs: DataFrame, weights: dict | None = None, path: str | None = None, end_id: int = END_ID, sequence: int = SEQUENCE, window: int = WINDOW, keep_ids: bool = False) -> DataFrame:
    """Cut all documents into sequences of at most ``sequence`` tokens.

    Needs ``doc_id, source, text``; null text counts as empty and still sends its end id,
    a null source is a source of its own, repeated rows are packed each.  ``weights``
    sets target proportions by source (missing: 0, sent when nothing else is left);
    without it every window holds the corpus' own proportions.  All sequences are full
    but those of the last remainder, whose lengths are powers of two: nothing is padding.

    Returns per piece ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id,
    offset`` and with ``keep_ids`` the ids as little-endian uint32.
    """
    path = path or word_tokenizer()
    schema = "block int, doc_id long, source string, n long, at long, wide int, ids binary"
    cast = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), "text")
    coded = stage(cast.mapInArrow(_encode_documents(path, end_id), schema), "ids")

    held = coded.groupBy("source", "block").agg(F.sum("n").alias("held"))
    before = F.coalesce(F.sum("held").over(Window.partitionBy("source").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    bases = stage(held.select(F.col("source").alias("s"), F.col("block").alias("b"), before.alias("base")), "base")
    if bases.count() <= BROADCAST_ROWS:  # beyond it, an equi-join on block and source
        bases = F.broadcast(bases)
    # one row per source comes to the driver, as for any list of sources
    totals = sorted(((r["source"], int(r["n"])) for r in coded.groupBy("source").agg(F.sum("n").alias("n")).collect()), key=lambda x: (x[0] is None, x[0] or ""))
    number = {s: i for i, (s, _) in enumerate(totals)}
    plan = RoundRobin(phases([n for _, n in totals], None if weights is None else [float(weights.get(s, 0.0)) for s, _ in totals]), sequence, window)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = {k: [] for k in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "ids")}
            for doc, source, n, at, base, wide, data in zip(*(column(batch, c).to_pylist() for c in ("doc_id", "source", "n", "at", "base", "wide", "ids"))):
                ids = np.frombuffer(data, f"<u{wide}").astype("<u4")
                begin = base + at
                for place, length, seq, off in plan.pieces(number[source], begin, begin + n):
                    start = place - begin
                    part = ids[start : start + length].tobytes()
                    for k, v in zip(rows, (doc, start, length, zlib.crc32(part), n, seq, off, part if keep_ids else None)):
                        rows[k].append(v)
            kind = {k: pa.array(v, pa.binary() if k == "ids" else pa.int64()) for k, v in rows.items() if keep_ids or k != "ids"}
            yield pa.RecordBatch.from_pydict(kind)

    joined = coded.join(bases, (F.col("block") == F.col("b")) & F.col("source").eqNullSafe(F.col("s"))).drop("b", "s")
    out = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + ", ids binary" * keep_ids
    return joined.mapInArrow(cut, out)


def sequences(pieces: DataFrame) -> DataFrame:
    """Packed sequences from pieces with ids: ``sequence_id, length, ids``."""
    parts = pieces.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("ps"), F.sum("length").alias("length"))
    joined = F.aggregate("ps", F.lit(b"").cast("binary"), lambda a, p: F.concat(a, p["ids"]))
    return parts.select("sequence_id", "length", joined.alias("ids"))


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` packed into sequences of 4096 tokens."""
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
