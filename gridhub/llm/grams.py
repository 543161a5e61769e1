"""Character n-grams over the open vocabulary of all code points.

Counting adds up inside each task before the exchange.  Looking n-grams up is a join with
the sharded table: the most frequent ones, a fixed number, are broadcast and settled
inside the scan, which takes the hot keys out of the join, and the others travel as
``(row, n-gram, times)``.  Values are whole numbers, so sums don't depend on their order.

N-grams are known by a 64-bit polynomial of their code points.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridhub.llm.arrow import column, filled, text_slices
from gridhub.plans.staging import stage

#: Stands before the start of a text; a noncharacter, which interchanged text doesn't hold.
PAD = "￿"
#: Bytes of text that one pass over arrays takes.
GRAM_SLICE = 1 << 20
#: N-grams that are broadcast with their values, 16 bytes each and one more number a value.
HOT = 1 << 18
#: Distinct n-grams that a task holds before it adds them up again.
HELD = 1 << 20
_STEP, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


def slice_grams(texts: pa.Array, order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(offsets per text, key at every code point, where each n-gram starts, padded code points)."""
    many = len(texts)
    lead = PAD * (order - 1)
    points = np.frombuffer("".join(lead + t for t in texts.to_pylist()).encode("utf-32-le", "surrogatepass"), "<u4")
    region = np.zeros(many + 1, np.int64)
    if many:
        region[1:] = np.cumsum(pc.utf8_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
    at = np.arange(region[-1]) + np.repeat(np.arange(many) * (order - 1), np.diff(region))
    keys = np.zeros(max(0, len(points) - order + 1), np.uint64)
    for k in range(order):
        keys *= _STEP
        keys += points[k : k + len(keys)] + np.uint64(1)
    return region, keys[at], at, points


def gram_counts(docs: DataFrame, order: int, flags: tuple[str, ...] = ()) -> DataFrame:
    """``key, gram, n`` over whole texts, and for each boolean column the n of its rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def added() -> tuple:
            keys, first, back = np.unique(np.concatenate([h[0] for h in held]), return_index=True, return_inverse=True)
            sums = [np.bincount(back, np.concatenate([h[2][i] for h in held]), len(keys)).astype(np.int64) for i in range(len(flags) + 1)]
            return keys, np.concatenate([h[1] for h in held])[first], sums

        for part in text_slices(batches, limit=GRAM_SLICE):
            region, keys, at, points = slice_grams(filled(part), order)
            if not len(keys):
                continue
            coded = pa.array(keys).dictionary_encode()
            unique, back = coded.dictionary.to_numpy(), coded.indices.to_numpy()
            first = np.zeros(len(unique), np.int64)
            first[back[::-1]] = np.arange(len(keys))[::-1]
            sums = [np.bincount(back, minlength=len(unique))]
            for f in flags:
                flag = np.repeat(column(part, f).to_numpy(zero_copy_only=False).astype(bool), np.diff(region))
                sums.append(np.bincount(back[flag], minlength=len(unique)))
            held.append((unique, points[at[first][:, None] + np.arange(order)], sums))
            if sum(len(h[0]) for h in held) > HELD and len(held) > 1:
                held = [added()]
                if len(held[0][0]) > HELD // 2:
                    yield batch(*held.pop())
        if held:
            yield batch(*added())

    def batch(keys: np.ndarray, points: np.ndarray, sums: list[np.ndarray]) -> pa.RecordBatch:
        line = np.ascontiguousarray(points).astype("<u4").tobytes().decode("utf-32-le", "surrogatepass")
        grams = [line[i : i + order] for i in range(0, len(line), order)]
        return pa.RecordBatch.from_pydict({"key": pa.array(keys.view(np.int64)), "gram": pa.array(grams, pa.string())} | {c: pa.array(s.astype(np.int64)) for c, s in zip(("n", *flags), sums)})

    schema = ", ".join(["key long", "gram string", "n long", *(f"`{f}` long" for f in flags)])
    found = docs.select("text", *flags).mapInArrow(run, schema)
    return found.groupBy("key", "gram").agg(*[F.sum(c).alias(c) for c in ("n", *flags)])


class KeyTable:
    """Open addressing over 64-bit keys, looked up for whole arrays."""

    def __init__(self, keys: np.ndarray):
        bits = max(4, int(len(keys)).bit_length() + 1)
        self.shift, self.mask, self.probes = np.uint64(64 - bits), (1 << bits) - 1, 0
        self.keys, self.places = np.zeros(1 << bits, np.uint64), np.full(1 << bits, -1, np.int32)
        left = np.arange(len(keys))
        while len(left):
            slot = (self._home(keys[left]) + self.probes) & self.mask
            free = self.places[slot] < 0
            _, first = np.unique(slot[free], return_index=True)
            won = np.flatnonzero(free)[first]
            self.keys[slot[won]], self.places[slot[won]] = keys[left[won]], left[won]
            left = np.delete(left, won)
            self.probes += 1

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys ^ (keys >> np.uint64(29))) * _MIX >> self.shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Number of each key in the table's order, or -1."""
        out = np.full(len(keys), -1, np.int32)
        home, open_at = self._home(keys), np.arange(len(keys))
        for probe in range(self.probes):
            slot = (home[open_at] + probe) & self.mask
            place = self.places[slot]
            same = (self.keys[slot] == keys[open_at]) & (place >= 0)
            out[open_at[same]] = place[same]
            open_at = open_at[~same & (place >= 0)]
            if not len(open_at):
                break
        return out


def gram_sums(docs: DataFrame, table: DataFrame, order: int, values: tuple[str, ...], carry: tuple[str, ...] = (), hot: int = HOT) -> DataFrame:
    """Sums of the table's whole-number values over the n-grams of every whole text.

    ``table`` has ``key, n`` and the values, a row for every n-gram of ``docs``.  Returns
    ``doc_id``, the carried columns, ``n_symbols`` and the sums, a row for a row.
    """
    spark = docs.sparkSession
    head = table.orderBy(F.desc("n"), "key").limit(hot).select("key", *values).toArrow()
    sent = spark.sparkContext.broadcast((head["key"].to_numpy().view(np.uint64), [head[v].to_numpy() for v in values]))  # HOT rows at most
    kinds = dict(docs.dtypes)
    tables: list[KeyTable] = []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, numbers = sent.value
        if not tables:
            tables.append(KeyTable(known))
        row = TaskContext.get().partitionId() << 33
        for part in text_slices(batches, limit=GRAM_SLICE):
            region, keys, _, _ = slice_grams(filled(part), order)
            place = tables[0].find(keys)
            rows = row + np.arange(part.num_rows)
            row += part.num_rows
            out = {"row": pa.array(rows), "key": pa.nulls(len(rows), pa.int64()), "times": pa.array(np.diff(region))}
            out |= {"doc_id": column(part, "doc_id")} | {c: column(part, c) for c in carry}
            for v, x in zip(values, numbers):
                run_sum = np.r_[0, np.cumsum(np.where(place >= 0, x[place] if len(x) else 0, 0))]
                out[v] = pa.array(run_sum[region[1:]] - run_sum[region[:-1]])
            yield pa.RecordBatch.from_pydict(out)
            lost = np.flatnonzero(place < 0)
            if len(lost):
                owner = np.searchsorted(region, lost, side="right") - 1
                code = np.lexsort((keys[lost], owner))
                k, o = keys[lost][code], owner[code]
                new = np.flatnonzero(np.r_[True, (k[1:] != k[:-1]) | (o[1:] != o[:-1])])
                out = {c: pa.nulls(len(new), x.type) for c, x in out.items()}
                out |= {"row": pa.array(rows[o[new]]), "key": pa.array(k[new].view(np.int64)), "times": pa.array(np.diff(np.r_[new, len(k)]))}
                yield pa.RecordBatch.from_pydict(out)

    schema = ", ".join(["row long", "key long", "times long", "doc_id long", *(f"`{c}` {kinds[c]}" for c in carry), *(f"`{v}` long" for v in values)])
    found = stage(docs.select(F.col("doc_id").cast("long").alias("doc_id"), *carry, "text").mapInArrow(run, schema), "grams")
    rare = found.where("key is not null").select("row", "key", "times").join(table.select("key", *values), "key")
    rare = rare.select("row", *[(F.col("times") * F.col(v)).alias(v) for v in values]).groupBy("row").agg(*[F.sum(v).alias(f"{v}_rare") for v in values])
    base = found.where("key is null").withColumnRenamed("times", "n_symbols").drop("key")
    joined = base.join(rare, "row", "left")
    return joined.select("doc_id", *carry, "n_symbols", *[(F.col(v) + F.coalesce(f"{v}_rare", F.lit(0))).alias(v) for v in values])
