"""Semi-joins of documents with ids that don't move texts while the ids are few."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridhub.plans.staging import stage

#: Rows from which on a key is joined apart from the others.
HOT_ROWS = 1_000_000
#: Ids that are broadcast, tens of MB at most; more of them go through a shuffled join.
BROADCAST_IDS = 1_000_000


def with_ids(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Rows of ``docs`` whose ``doc_id`` is in ``ids``; a null id matches a null id.

    ``ids`` should be staged: it is counted first.  An id that several rows share stays
    with all of them.
    """
    wanted = ids.select(F.col("doc_id").cast("long").alias("_wanted")).distinct()
    if ids.count() <= BROADCAST_IDS:
        wanted = F.broadcast(wanted)
    return docs.join(wanted, F.col("doc_id").cast("long").eqNullSafe(F.col("_wanted")), "left_semi")


def with_flag(docs: DataFrame, ids: DataFrame, flag: str) -> DataFrame:
    """``docs`` and whether its ``doc_id`` is among ``ids``, a staged table; null ids are not.

    Ids are broadcast if they are few, so texts don't move.
    """
    wanted = ids.select(F.col("doc_id").cast("long").alias("_wanted")).where("_wanted is not null").distinct().withColumn(flag, F.lit(True))
    if ids.count() <= BROADCAST_IDS:
        wanted = F.broadcast(wanted)
    joined = docs.join(wanted, F.col("doc_id").cast("long") == F.col("_wanted"), "left")
    return joined.withColumn(flag, F.coalesce(flag, F.lit(False))).drop("_wanted")


def good_ids(labels: DataFrame) -> DataFrame:
    """Ids of documents labelled as of good quality."""
    return labels.where("quality = 1").select(F.col("doc_id").cast("long").alias("doc_id")).distinct()


def with_row_key(docs: DataFrame) -> DataFrame:
    """Adds ``_key``, a hash of the whole row: rows that share it and ``doc_id`` are alike."""
    plain = [c for c, t in docs.dtypes if "map<" not in t and "variant" not in t]
    return docs.withColumn("_key", F.xxhash64(*[F.col(f"`{c}`") for c in plain]))


def take_rows(docs: DataFrame, decided: DataFrame, alike_once: bool = False) -> DataFrame:
    """Each row of ``docs`` as often as ``decided`` says, in the columns of ``docs``.

    ``decided`` is staged and has ``doc_id, _key, copies``, one row per row of ``docs``;
    so a decision is a row's own even where ids repeat or are null.  Rows that are alike in
    everything share the sum of their copies, or with ``alike_once`` the largest number.
    """
    total = F.max("copies") if alike_once else F.sum("copies")
    sums = decided.groupBy("doc_id", "_key").agg(total.cast("int").alias("_copies"), F.count("*").alias("_rows"))
    wanted = stage(sums.where("_copies > 0").withColumnRenamed("doc_id", "_id").withColumnRenamed("_key", "_k"), "taken")
    keyed = with_row_key(docs)
    alike = wanted.where("_rows > 1")
    single = wanted if alike.isEmpty() else wanted.where("_rows = 1")

    def met(some: DataFrame) -> DataFrame:
        few = F.broadcast(some) if wanted.count() <= BROADCAST_IDS else some
        return keyed.join(few, (F.col("_key") == F.col("_k")) & F.col("doc_id").cast("long").eqNullSafe(F.col("_id")))

    taken = met(single)
    if single is not wanted:
        taken = taken.unionByName(met(alike).dropDuplicates(["_id", "_k"]))
    if wanted.where("_copies > 1").isEmpty():
        return taken.select(*docs.columns)
    return taken.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies")))).select(*docs.columns)


def join_hot_apart(rows: DataFrame, table: DataFrame, keys: list[str], size: str) -> DataFrame:
    """``rows`` joined with ``table``, which is staged and has one row a key and its rows' number.

    Keys of more than HOT_ROWS rows, so at most one in HOT_ROWS of them all, are broadcast
    and their rows stay where they are; the others meet by key.
    """
    hot = table.where(F.col(size) > HOT_ROWS)
    many = hot.count()
    if not 0 < many <= BROADCAST_IDS:
        return rows.join(table, keys)
    rest = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(table.where(F.col(size) <= HOT_ROWS), keys)
    return rows.join(F.broadcast(hot), keys).unionByName(rest)
