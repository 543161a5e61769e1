"""Exact dedup: binary-fuse filters over an immutable snapshot screen a new batch.

The snapshot holds one row per distinct text.  Its digests are dealt into shards and every
shard gets a static 3-wise binary fuse filter of 8-bit fingerprints.  A batch is first
grouped by itself; its distinct digests then pass the filters.  What a filter turns down
is new for certain and never meets the snapshot; the positives join the exact bucket of
their digest, and the bytes of both whole normalised texts are compared there.
"""

from __future__ import annotations

from string import ascii_lowercase, ascii_uppercase

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridhub.llm.joins import BROADCAST_IDS, join_hot_apart
from gridhub.plans.staging import stage

#: Digests that one filter holds, about; a shard is one task's group.
SHARD_KEYS = 500_000


def _mix(keys: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit finaliser over the digests."""
    with np.errstate(over="ignore"):
        x = keys ^ np.uint64(seed * 0x9E3779B97F4A7C15 & (2**64 - 1))
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
        return x ^ (x >> np.uint64(33))


class FuseFilter:
    """A static set of 64-bit keys: no false negatives, about 1/256 false positives."""

    def __init__(self, seed: int, segment: int, segments: int, table: np.ndarray):
        self.seed, self.segment, self.segments, self.table = seed, segment, segments, table

    @staticmethod
    def _places(keys: np.ndarray, seed: int, segment: int, segments: int) -> tuple[np.ndarray, np.ndarray]:
        """Three slots in consecutive segments, and the fingerprint, for every key."""
        h = _mix(keys, seed)
        first = ((h >> np.uint64(32)) * np.uint64(segments) >> np.uint64(32)).astype(np.int64)
        mask = np.uint64(segment - 1)
        slots = np.stack([(first + i) * segment + ((h >> np.uint64(18 * i)) & mask ^ (_mix(h, i + 1) & mask)).astype(np.int64) for i in range(3)])
        return slots, (_mix(h, 99) & np.uint64(255)).astype(np.uint8)

    @classmethod
    def build(cls, keys: np.ndarray) -> FuseFilter:
        keys = np.unique(keys.astype(np.uint64))
        n = max(1, len(keys))
        segment = 1 << int(max(2, min(18, np.floor(np.log(n) / np.log(3.33) + 2.25))))
        factor = max(1.125, 0.875 + 0.25 * np.log(1e6) / np.log(max(2, n)))
        segments = max(1, int(np.ceil(n * factor / segment)) - 2)
        for seed in range(1, 200):
            slots, prints = cls._places(keys, seed, segment, segments)
            size = (segments + 2) * segment
            layers = cls._peel(slots, size)
            if layers is None:
                segments += max(1, segments // 50)
                continue
            table = np.zeros(size, np.uint8)
            for own, at in reversed(layers):
                others = table[slots[0, own]] ^ table[slots[1, own]] ^ table[slots[2, own]]
                table[at] = prints[own] ^ others  # table[at] is still zero
            return cls(seed, segment, segments, table)
        raise RuntimeError("the filter could not be built")

    @staticmethod
    def _peel(slots: np.ndarray, size: int) -> list | None:
        """Layers of (key, its lonely slot); each layer is peeled at once."""
        n = slots.shape[1]
        alive, layers = np.ones(n, bool), []
        degree = np.bincount(slots.ravel(), minlength=size)
        total = np.zeros(size, np.int64)
        for row in slots:
            np.add.at(total, row, np.arange(n))
        lonely = np.flatnonzero(degree == 1)
        while len(lonely):
            own, pick = np.unique(total[lonely], return_index=True)
            at = lonely[pick]
            layers.append((own, at))
            alive[own] = False
            touched = slots[:, own]
            for row in touched:
                np.subtract.at(degree, row, 1)
                np.subtract.at(total, row, own)
            near = np.unique(touched.ravel())
            lonely = near[degree[near] == 1]
        return None if alive.any() else layers

    def contains(self, keys: np.ndarray) -> np.ndarray:
        slots, prints = self._places(keys.astype(np.uint64), self.seed, self.segment, self.segments)
        return (self.table[slots[0]] ^ self.table[slots[1]] ^ self.table[slots[2]]) == prints

    def to_bytes(self) -> bytes:
        return np.array([self.seed, self.segment, self.segments], "<i8").tobytes() + self.table.tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> FuseFilter:
        seed, segment, segments = np.frombuffer(data[:24], "<i8").tolist()
        return cls(seed, segment, segments, np.frombuffer(data, np.uint8, offset=24))


def text_digests(docs: DataFrame, carry: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id, row, sha, bytes, normal``: the whole text with A-Z lower-cased; null is empty.

    ``row`` numbers the input rows, so that repeated rows stay apart.  It is stable only
    once the result is staged.  ``carry`` names further columns to keep.  Texts stay in
    Spark's own rows: no second copy of them waits in Arrow buffers or Python workers.
    """
    text = F.coalesce("text", F.lit(""))
    ascii_only = F.length(text) == F.octet_length(text)  # there, lower() touches A-Z only and is faster
    normal = F.when(ascii_only, F.lower(text)).otherwise(F.translate(text, ascii_uppercase, ascii_lowercase)).cast("binary")
    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.monotonically_increasing_id().alias("row"), normal.alias("normal"), *[F.col(f"`{c}`") for c in carry])
    sha = F.unhex(F.sha2("normal", 256))
    return kept.select("doc_id", "row", sha.alias("sha"), F.octet_length("normal").cast("long").alias("bytes"), "normal", *[F.col(f"`{c}`") for c in carry])


def distinct_texts(digests: DataFrame) -> DataFrame:
    """One row per text: the greatest (doc_id, row) and the number of rows."""
    return digests.groupBy("sha", "bytes").agg(F.max(F.struct("doc_id", "row")).alias("top"), F.count("*").alias("n"))


def _key() -> F.Column:
    return F.conv(F.substr(F.hex("sha"), F.lit(1), F.lit(15)), 16, 10).cast("long")


def build_filters(snapshot: DataFrame, shards: int) -> DataFrame:
    """``(shard, filter)`` from the snapshot's digests; one bounded group per shard."""

    def build(table: pa.Table) -> pa.Table:
        keys = table["key"].to_numpy()
        return pa.table({"shard": pa.array([table["shard"][0].as_py()], pa.int64()), "filter": pa.array([FuseFilter.build(keys).to_bytes()], pa.binary())})

    keyed = snapshot.select(F.pmod("key", F.lit(shards)).alias("shard"), "key")
    return keyed.groupBy("shard").applyInArrow(build, "shard long, filter binary")


def screen(batch: DataFrame, filters: DataFrame, shards: int) -> DataFrame:
    """Adds ``maybe``: whether the filter of the row's shard knows the digest."""

    def test(left: pa.Table, right: pa.Table) -> pa.Table:
        known = FuseFilter.from_bytes(right["filter"][0].as_py()).contains(left["key"].to_numpy()) if right.num_rows else np.zeros(left.num_rows, bool)
        return pa.table({"sha": left["sha"], "bytes": left["bytes"], "maybe": pa.array(known)})

    keyed = batch.select(F.pmod("key", F.lit(shards)).alias("shard"), "key", "sha", "bytes")
    return keyed.groupBy("shard").cogroup(filters.groupBy("shard")).applyInArrow(test, "sha binary, bytes long, maybe boolean")


def _texts_of(digests: DataFrame, rows: DataFrame) -> DataFrame:
    """``row, normal`` of the given rows; texts stay in place while the rows are few."""
    wanted = rows.select("row").distinct()
    if rows.count() <= BROADCAST_IDS:
        wanted = F.broadcast(wanted)
    return digests.select("row", "normal").join(wanted, "row", "left_semi")


def same_bytes(pairs: DataFrame, old: DataFrame, new: DataFrame) -> DataFrame:
    """Pairs (``old_row``, ``new_row``) whose normalised texts are equal byte by byte."""
    left = _texts_of(old, pairs.select(F.col("old_row").alias("row"))).withColumnsRenamed({"row": "old_row", "normal": "old_text"})
    right = _texts_of(new, pairs.select(F.col("new_row").alias("row"))).withColumnsRenamed({"row": "new_row", "normal": "new_text"})
    return pairs.join(left, "old_row").join(right, "new_row").where("old_text = new_text").drop("old_text", "new_text")


def exact_duplicates(snapshot: DataFrame, batch: DataFrame, shard_keys: int = SHARD_KEYS) -> DataFrame:
    """Groups of equal texts over a snapshot and a batch, both from ``text_digests``.

    A batch text whose digest, but not whose bytes, is known would stay a group of its own.
    Returns ``doc_id, row, sha, bytes``, what the digests carry, and ``keep_id, keep_row,
    group_size`` with one row per input row; the greatest (doc_id, row) of a group stays.  A null id sorts first.
    Either side may be empty.
    """
    old = stage(distinct_texts(snapshot).withColumn("key", _key()), "snap")
    new = stage(distinct_texts(batch).withColumn("key", _key()), "batch")
    shards = max(1, -(-max(old.count(), new.count()) // shard_keys))
    seen = screen(new, build_filters(old, shards), shards)
    positive = new.join(seen.where("maybe"), ["sha", "bytes"], "left_semi")
    met = stage(positive.select("sha", "bytes", F.col("top").alias("new_top"), F.col("n").alias("new_n"), F.col("top.row").alias("new_row")).join(old.select("sha", "bytes", "top", "n", F.col("top.row").alias("old_row")), ["sha", "bytes"]), "bucket")
    merged = stage(same_bytes(met, snapshot, batch).select("sha", "bytes", F.greatest("top", "new_top").alias("top"), (F.col("n") + F.col("new_n")).alias("n")), "met")
    # a group that both sides share answers for both, any other for its own side
    sides = old.withColumn("side", F.lit(0)).unionByName(new.withColumn("side", F.lit(1))).select("sha", "bytes", "side", "top", "n")
    rest = sides.join(merged.select("sha", "bytes"), ["sha", "bytes"], "left_anti")
    both = merged.withColumn("side", F.explode(F.array(F.lit(0), F.lit(1))))
    groups = both.unionByName(rest).select("sha", "bytes", "side", F.col("top.doc_id").alias("keep_id"), F.col("top.row").alias("keep_row"), F.col("n").alias("group_size"))
    rows = snapshot.drop("normal").withColumn("side", F.lit(0)).unionByName(batch.drop("normal").withColumn("side", F.lit(1)))
    return join_hot_apart(rows, stage(groups, "groups"), ["sha", "bytes", "side"], "group_size").select(*[c for c in rows.columns if c != "side"], "keep_id", "keep_row", "group_size")


def dedup_documents(docs: DataFrame, snapshot_parts: int = 2, carry: tuple[str, ...] = ()) -> DataFrame:
    """``exact_duplicates`` for one table: a part of the ids as snapshot, the rest as batch."""
    digests = stage(text_digests(docs, carry), "digest")
    old = F.coalesce(F.pmod(F.xxhash64("doc_id"), F.lit(snapshot_parts)), F.lit(0)) == 0
    return exact_duplicates(digests.where(old), digests.where(~old))


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Equal texts of all ``documents``; one row per document, dropped ones too."""
    found = dedup_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", "keep_id", "group_size", (F.col("row") == F.col("keep_row")).alias("kept"), F.lower(F.hex("sha")).alias("text_sha256"))


OP8_SQL = """
WITH d AS (
  SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256 FROM documents
)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""
