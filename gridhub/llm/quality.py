"""Quality by an interpolated modified Kneser-Ney model of trusted text.

Tokens are code points, whatever the script.  Counts of all orders, their continuation
counts and their context sums are tables sharded by n-gram, context and suffix; joins of
them give the probability of every n-gram that occurs in any document, backing off by a
join with the next lower order where trusted text lacks it.  Another join, of the
documents' n-grams with that table, gives perplexities.  A document stays if its
perplexity is not above the quantile of its language among trusted documents that the
model was not trained on.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridhub.llm.grams import gram_counts, gram_sums
from gridhub.llm.joins import BROADCAST_IDS, good_ids, with_flag
from gridhub.plans.staging import stage

ORDER = 5
#: Share of held-out trusted documents of a language that the threshold lets through.
QUANTILE = 0.98
#: One of so many trusted documents, by a hash of the id, is held out for the thresholds.
FOLDS = 5
#: Losses are whole millionths of a bit; log-perplexities are ranked in thousandths.
UNIT, STEP = 1_000_000, 1000


def _discounts(counts: DataFrame) -> list[float]:
    """The three discounts of an order, from how many n-grams occur 1 to 4 times."""
    row = counts.agg(*[F.count_if(F.col("n") == k).alias(f"n{k}") for k in (1, 2, 3, 4)]).first()
    n1, n2, n3, n4 = (row[f"n{k}"] for k in (1, 2, 3, 4))
    if not (n1 and n2 and n3):
        return [0.5, 0.75, 0.9]
    y = n1 / (n1 + 2 * n2)
    found = [1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3]
    return [float(np.clip(d, 0.05, k - 0.05)) for k, d in zip((1, 2, 3), found)]


def kneser_ney(counts: DataFrame, order: int = ORDER) -> DataFrame:
    """``gram, p`` for every row of ``gram, n``, where ``n`` is 0 for what the model never met.

    The n-grams of lower orders are the suffixes, counted by how many different code points
    come before them in trusted text; below the lowest order stands a uniform share of all
    code points that occur.
    """
    levels = [counts.select("gram", "n")]
    for k in range(order - 1, 0, -1):
        suffix = F.expr(f"substring(gram, 2, {k})")
        levels.insert(0, stage(levels[0].groupBy(suffix.alias("gram")).agg(F.count_if(F.col("n") > 0).alias("n")), "kn"))
    lower, kinds = None, max(1, levels[0].count())
    for k, level in enumerate(levels, 1):
        d = _discounts(level)
        context = F.expr(f"substring(gram, 1, {k - 1})").alias("context")
        sums = level.where("n > 0").groupBy(context).agg(F.sum("n").alias("total"), *[F.count_if((F.col("n") == i) if i < 3 else (F.col("n") >= 3)).alias(f"k{i}") for i in (1, 2, 3)])
        sums = sums.select("context", "total", ((d[0] * F.col("k1") + d[1] * F.col("k2") + d[2] * F.col("k3")) / F.col("total")).alias("back"))
        cut = F.when(F.col("n") == 1, d[0]).when(F.col("n") == 2, d[1]).otherwise(d[2])
        seen = level.select("gram", context, "n", cut.alias("cut")).join(sums, "context", "left")
        if lower is None:
            seen = seen.withColumn("under", F.lit(1.0 / kinds))
        else:
            seen = seen.withColumn("suffix", F.expr(f"substring(gram, 2, {k - 1})")).join(lower.select(F.col("gram").alias("suffix"), F.col("p").alias("under")), "suffix")
        p = F.greatest(F.col("n") - F.col("cut"), F.lit(0.0)) / F.col("total") + F.col("back") * F.col("under")
        lower = stage(seen.select("gram", F.coalesce(p, F.col("under")).alias("p")), "knp")
    return lower


def language_thresholds(scored: DataFrame, quantile: float = QUANTILE) -> DataFrame:
    """``lang_key, threshold`` from ``lang, bits`` of trusted documents, exact to a step."""
    steps = scored.where("bits is not null").groupBy(F.coalesce("lang", F.lit("")).alias("lang_key"), F.round(F.col("bits") * STEP).cast("long").alias("step")).agg(F.count("*").alias("n"))
    order = Window.partitionBy("lang_key").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    ranked = steps.withColumn("upto", F.sum("n").over(order)).withColumn("all", F.sum("n").over(Window.partitionBy("lang_key")))
    return ranked.where(F.col("upto") >= quantile * F.col("all")).groupBy("lang_key").agg((F.min("step") / STEP).alias("threshold"))


def held_out(doc_id: F.Column, folds: int = FOLDS) -> F.Column:
    return F.pmod(F.xxhash64(doc_id.cast("long"), F.lit(29)), F.lit(folds)) == 0


def judge_quality(docs: DataFrame, trusted: DataFrame, quantile: float = QUANTILE, order: int = ORDER) -> DataFrame:
    """Perplexity of every document and whether it stays.

    ``docs`` needs ``doc_id, lang, text``, ``trusted`` ``doc_id`` of rows of ``docs``.  A
    null language is a language of its own; one without held-out trusted documents uses the
    threshold over all of them; with none at all everything with a text stays.  Null text
    counts as empty; an empty text has no perplexity and does not stay.  Repeated rows give
    repeated rows, and each counts in the model; a row at its threshold stays.  Returns
    ``doc_id, lang, n_symbols, perplexity, threshold, keep``.
    """
    ids = stage(trusted.select(F.col("doc_id").cast("long").alias("doc_id")).distinct(), "good")
    flagged = with_flag(docs.select("doc_id", "lang", "text"), ids, "is_trusted")
    flagged = flagged.withColumn("model", F.col("is_trusted") & ~held_out(F.col("doc_id")))
    universe = stage(gram_counts(flagged.select("text", "model"), order, ("model",)), "universe")
    p = kneser_ney(universe.select("gram", F.col("model").alias("n")), order)
    table = universe.select("key", "gram", "n").join(p, "gram").select("key", "n", F.round(-F.log2("p") * UNIT).cast("long").alias("loss"))
    scored = gram_sums(flagged, stage(table, "losses"), order, ("loss",), ("lang", "is_trusted"))
    scored = stage(scored.withColumn("bits", F.when(F.col("n_symbols") > 0, F.col("loss") / F.col("n_symbols") / UNIT)), "ppl")
    judges = scored.where("is_trusted").where(held_out(F.col("doc_id")))
    own = stage(language_thresholds(judges, quantile), "own")
    if own.count() <= BROADCAST_IDS:
        own = F.broadcast(own)
    overall = language_thresholds(judges.withColumn("lang", F.lit("")), quantile).select(F.col("threshold").alias("overall"))
    joined = scored.withColumn("lang_key", F.coalesce("lang", F.lit(""))).join(own, "lang_key", "left").join(F.broadcast(overall), F.lit(True), "left")
    limit = F.coalesce("threshold", "overall", F.lit(float("inf")))
    return joined.select("doc_id", "lang", "n_symbols", F.round(F.pow(F.lit(2.0), F.col("bits")), 6).alias("perplexity"), F.round(F.pow(F.lit(2.0), limit), 6).alias("threshold"), F.coalesce(F.round("bits", 3) <= limit, F.lit(False)).alias("keep"))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` judged by a model of the texts that ``labels`` calls good."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    return judge_quality(docs, good_ids(labels))
