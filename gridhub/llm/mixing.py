"""Mixing sources to target weights: capped water-filling, then seeded repetitions.

Native: DataFrame functions only.  A source gets ``min(cap, level * weight)`` where the
cap is ``max_epochs`` times its size and the level is the one at which the targets add up
to the wanted total.  Its documents are then taken a whole number of times each, and the
rest of the target comes from one more pass over the documents in a seeded order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridhub.plans.staging import stage

#: Hex digits of the seeded order that name a bucket of documents.
BUCKET_DIGITS = 3


def word_count(text: Column) -> Column:
    """Number of runs of characters other than ASCII white space; null counts as empty."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("long")


def water_fill(sources: DataFrame, share: float = 1.5, max_epochs: float = 2.0) -> DataFrame:
    """Targets from ``(source, weight, source_size)``: adds ``target``.

    Sources are filled in the order of the level at which each meets its cap.  Those that
    meet it before the final level are clamped and what they leave is shared by weight
    among the rest, which is the fixed point of clamping and resharing over and over.
    One row per source, so the windows without a key stay as small as the source list.
    """
    caps = sources.withColumn("cap", F.lit(float(max_epochs)) * F.col("source_size")).withColumn("total", F.lit(float(share)) * F.sum("source_size").over(Window.partitionBy()))
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source"))
    run = caps.withColumn("clamped", F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))).withColumn("open", F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
    level = run.withColumn("level", F.greatest(F.lit(0.0), (F.col("total") - F.col("clamped")) / F.col("open")))
    # the level seen from a source is right if the source itself stays open there
    first_open = level.withColumn("stays", F.col("level") * F.col("weight") <= F.col("cap")).withColumn("final", F.min(F.when(F.col("stays"), F.struct(F.col("cap") / F.col("weight"), F.col("source"), F.col("level")))).over(Window.partitionBy())["level"])
    return first_open.withColumn("target", F.least("cap", F.coalesce(F.col("final") * F.col("weight"), F.col("cap")))).select(*sources.columns, "target")


def cycled_weights(sources: DataFrame, weights: tuple[float, ...] = (5.0, 2.0, 1.0)) -> DataFrame:
    """Give the sources, by code point and null last, the weights in turn."""
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    return sources.withColumn("weight", F.get(F.array(*[F.lit(float(w)) for w in weights]), (rank % len(weights)).cast("int")))


def seeded_order(doc: Column, seed: int) -> Column:
    """A reproducible place of a document in its source: hex digest of seed and id."""
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc.cast("string"), F.lit(""))))


def mix_copies(docs: DataFrame, weights: tuple[float, ...] = (5.0, 2.0, 1.0), share: float = 1.5, max_epochs: float = 2.0, seed: int = 17, carry: tuple[str, ...] = ()) -> DataFrame:
    """How often each document enters the mix.

    Needs ``doc_id, source, text``; other columns are ignored.  Null text has size 0, null
    source is a source of its own, equal ids tie and are ordered by size.  Returns
    ``doc_id, size, source, source_size, target, copies`` and the columns that ``carry``
    names, with one row per input row.

    The last, partial pass takes the documents of a source in the seeded order while at
    least half of a document lies below the target.  Running sums go over buckets of that
    order first and over documents only inside the one bucket that the target cuts, so no
    task ever sorts a source.
    """
    sized = stage(docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), seeded_order(F.col("doc_id"), seed).alias("place"), *carry), "mix")
    totals = cycled_weights(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights)
    targets = water_fill(totals, share, max_epochs).withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("int")).withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size")).select(F.col("source").alias("s"), "source_size", "target", "whole", "rest")

    keyed = sized.withColumn("bucket", F.substr("place", F.lit(1), F.lit(BUCKET_DIGITS)))
    buckets = keyed.groupBy("source", "bucket").agg(F.sum("size").alias("held"))
    below = F.coalesce(F.sum("held").over(Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    cut = (
        buckets.withColumn("below", below).join(F.broadcast(targets), F.col("source").eqNullSafe(F.col("s")))
        .where("below <= rest and rest < below + held")
        .groupBy("s").agg(F.min("bucket").alias("cut"), F.min_by("below", "bucket").alias("cut_below"))
    )
    plan = targets.join(cut.withColumnRenamed("s", "cs"), F.col("s").eqNullSafe(F.col("cs")), "left").drop("cs")
    rows = keyed.join(F.broadcast(plan), F.col("source").eqNullSafe(F.col("s"))).drop("s")

    inside = Window.partitionBy("source", "bucket").orderBy("place", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    edge = rows.where("bucket = cut").withColumn("before", F.col("cut_below") + F.coalesce(F.sum("size").over(inside), F.lit(0))).withColumn("extra", ((F.col("rest") > 0) & (F.col("before") + F.col("size") / 2 <= F.col("rest"))).cast("int")).drop("before")
    clear = rows.where("cut is null or bucket <> cut").withColumn("extra", F.when(F.col("cut").isNull(), (F.col("rest") > 0).cast("int")).otherwise((F.col("bucket") < F.col("cut")).cast("int")))
    return clear.unionByName(edge).select("doc_id", "size", "source", "source_size", "target", (F.col("whole") + F.col("extra")).alias("copies"), *carry)


def op4_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mix of all ``documents``: words taken from each, repeats counted."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mix_copies(docs).select("doc_id", "size", "source_size", F.round("target", 3).alias("target"), (F.col("size") * F.col("copies")).alias("taken"))


OP4_SQL = r"""
WITH RECURSIVE sized AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
    md5('17:' || coalesce(doc_id::VARCHAR, '')) AS place FROM documents
), totals AS (
  SELECT source, sum(size)::BIGINT AS source_size,
    CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5.0 WHEN 1 THEN 2.0 ELSE 1.0 END::DOUBLE AS weight
  FROM sized GROUP BY source
), filled(round, source, source_size, weight, clamped) AS (
  SELECT 0, source, source_size, weight, false FROM totals
  UNION ALL
  SELECT round + 1, source, source_size, weight,
    clamped OR weight * greatest(0, (1.5 * sum(source_size) OVER () - coalesce(sum(2.0 * source_size) FILTER (WHERE clamped) OVER (), 0)))
      / nullif(sum(weight) FILTER (WHERE NOT clamped) OVER (), 0) > 2.0 * source_size
  FROM filled WHERE round < 64
), final AS (
  SELECT source, source_size, CASE WHEN clamped THEN 2.0 * source_size ELSE weight * (1.5 * sum(source_size) OVER ()
      - coalesce(sum(2.0 * source_size) FILTER (WHERE clamped) OVER (), 0)) / sum(weight) FILTER (WHERE NOT clamped) OVER () END::DOUBLE AS target
  FROM filled WHERE round = 64
), run AS (
  SELECT z.*, source_size, target, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END AS whole,
    coalesce(sum(size) OVER (PARTITION BY z.source ORDER BY place, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below
  FROM sized z JOIN final f ON z.source IS NOT DISTINCT FROM f.source
)
SELECT doc_id, size, source_size, round(target, 3) AS target,
  (size * (whole + CASE WHEN target - whole * source_size > 0 AND below + size / 2.0 <= target - whole * source_size THEN 1 ELSE 0 END))::BIGINT AS taken
FROM run
"""
