"""A corpus from raw documents: five stages, each an operator of ``gridhub.llm``."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridhub.llm.exact import dedup_documents
from gridhub.llm.joins import take_rows, with_row_key
from gridhub.llm.mixing import mix_copies
from gridhub.llm.packing import pack
from gridhub.llm.simhash import similar_documents
from gridhub.llm.toxicity import score_texts, train
from gridhub.plans.staging import stage

# Every stage decides row by row, so a null or repeated id never lends its row another's
# decision; of rows alike in all columns the two dedup stages keep one.  Null texts count as
# empty, extra columns pass through, an empty table gives an empty one.


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the toxicity model scores below 0.5; an empty text gets the model's bias."""
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score_texts(docs, model, whole=True).where("score < 0.5").select("doc.*")


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of texts equal but for the case of A-Z, the row with the largest id; null ids come last."""
    found = dedup_documents(with_row_key(docs), carry=("_key",))
    return take_rows(docs, stage(found.select("doc_id", "_key", (F.col("row") == F.col("keep_row")).cast("int").alias("copies")), "kept"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of every near-duplicate component, the row with the least id; a null id comes after all."""
    found = similar_documents(with_row_key(docs), carry=("_key",))
    return take_rows(docs, stage(found.select("doc_id", "_key", F.col("kept").cast("int").alias("copies")), "near"), alike_once=True)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row as often as the mix takes it; empty texts cost nothing and follow their source."""
    return take_rows(docs, stage(mix_copies(with_row_key(docs), carry=("_key",)).select("doc_id", "_key", "copies"), "mixed"))


def pack_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences."""
    return pack(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_copies),
    ("near_dedup", drop_near_copies),
    ("source_mixing", mix_sources),
    ("packing", pack_documents),
]

#: No SQL: a trained classifier and a tokenizer decide rows.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
