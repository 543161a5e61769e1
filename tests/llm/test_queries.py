"""The registered queries on the smallest tables, and the pipeline stage by stage."""

import glob
import os

import duckdb
import numpy as np
import pytest

from pyspark.sql import functions as F

import corpus_pipeline
from gridhub.llm import registry, simhash, tokens, toxicity
from gridhub.plans.staging import stage


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_sql_agrees(spark, tiny, name):
    con = duckdb.connect()
    for f in glob.glob(f"{tiny}/*.parquet"):
        con.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    got, want = registry.QUERIES[name](spark, tiny), con.sql(registry.SQL[name])
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    rows = [tuple(r[want.columns.index(c)] for c in cols) for r in want.fetchall()]
    assert sorted(map(repr, map(tuple, got.select(*cols).collect()))) == sorted(map(repr, rows))


@pytest.mark.parametrize("name", ["op2_simhash_groups", "op3_toxicity", "op5_lm_scores", "op6_packing", "op7_token_counts", "op9_quality"])
def test_every_document_is_in_the_result(spark, tiny, name):
    ids = {r.doc_id for r in spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id").collect()}
    assert {r.doc_id for r in registry.QUERIES[name](spark, tiny).select("doc_id").collect()} == ids


def test_pipeline_stages(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    columns, seen = docs.columns, []
    for name, step in corpus_pipeline.STAGES:
        before = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()} if "text" in docs.columns else {}
        docs = stage(step(spark, docs, tiny), name)
        seen.append(name)
        if name != "packing":
            assert docs.columns == columns
            after = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
            assert all(before[i] == t for i, t in after) and after
        if name == "exact_dedup":
            low = [t.encode().lower() for _, t in after]
            assert len(set(low)) == len(low) == len({t.encode().lower() for t in before.values()})
        if name == "near_dedup":
            fp = np.array([simhash.fingerprint(t) for _, t in after], np.uint64)
            assert (np.bitwise_count(fp[:, None] ^ fp[None]) <= 2).sum() == len(fp)
    assert seen == ["toxicity", "exact_dedup", "near_dedup", "source_mixing", "packing"]
    assert docs.agg({"length": "sum"}).first()[0] > 0 and tokens.word_tokenizer().endswith(".json")


DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def rows_of(df):
    return sorted(((r.doc_id is None, r.doc_id or 0, r.text or "") for r in df.collect()))


def test_pipeline_decides_row_by_row(spark, tiny, monkeypatch):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    model = toxicity.train(docs, spark.read.parquet(f"{tiny}/labels.parquet"))
    scored = toxicity.score_texts(docs, model, whole=True).select("doc.text", "score").where("text is not null and octet_length(text) > 200").orderBy("score").collect()
    clean, toxic = scored[0].text, scored[-1].text
    assert scored[0].score < 0.5 <= scored[-1].score
    other = " ".join(f"w{i}" for i in range(60))
    rows = [(7, toxic), (7, clean), (None, toxic), (None, clean.upper()), (8, clean), (8, clean), (9, other), (None, other + " more"), (9, other), (10, None), (10, ""), (None, None)]
    made = spark.createDataFrame([(i, t, "en", None if k % 4 == 0 else "a", 1) for k, (i, t) in enumerate(rows)], DOCS).withColumn("copies", F.lit("clash"))
    monkeypatch.setattr(corpus_pipeline, "train", lambda docs, labels: model)
    empty_kept = toxicity.score_texts(made, model).where("doc_id = 10").first().score < 0.5
    kept = stage(corpus_pipeline.drop_toxic(spark, made, tiny), "t")
    assert kept.columns == made.columns
    assert rows_of(kept) == sorted((i is None, i or 0, t or "") for i, t in rows if t != toxic and (t or empty_kept))
    # one of the texts equal but for case, the largest id; null and empty texts are equal
    kept = stage(corpus_pipeline.drop_copies(spark, made, tiny), "t")
    assert rows_of(kept) == sorted([(False, 7, toxic), (False, 8, clean), (False, 9, other), (True, 0, other + " more"), (False, 10, "")])
    # near copies: the least id, a null id after all others
    kept = stage(corpus_pipeline.drop_near_copies(spark, made, tiny), "t")
    assert [(n, i) for n, i, _ in rows_of(kept)] == [(False, 7), (False, 7), (False, 9), (False, 10)]
    words = lambda df: sum(len((r.text or "").split()) for r in df.collect())
    mixed = stage(corpus_pipeline.mix_sources(spark, made, tiny), "t")
    most = max(words(made.where(F.col("doc_id") == i)) for i in (7, 8, 9))
    assert abs(words(mixed) - 1.5 * words(made)) <= 2 * most and mixed.columns == made.columns
    for name, step in corpus_pipeline.STAGES[:-1]:
        made = stage(step(spark, made, tiny), name)
    assert corpus_pipeline.pack_documents(spark, made, tiny).select("doc_id", "start").distinct().count() > 0


def test_pipeline_of_nothing(spark, tiny):
    empty = spark.createDataFrame([], DOCS)
    for _, step in corpus_pipeline.STAGES:
        assert step(spark, empty, tiny).count() == 0


def test_near_dedup_stage_drops_what_overlaps(spark, tiny):
    rng = np.random.default_rng(4)
    texts = []
    for size in (30, 60, 200, 700):
        for _ in range(6):
            base = [f"w{i}" for i in rng.integers(0, 5000, size)]
            texts.append(" ".join(base))
            for edits in (1, 2, 4, 8):
                copy = list(base)
                for at in rng.choice(size, max(1, edits * size // 200), replace=False):
                    copy[at] = f"e{rng.integers(0, 9999)}"
                texts.append(" ".join(copy) if edits % 4 else " ".join(copy).upper() + " more")
    line = "one line that very many of the texts hold in the same words "
    texts += [line + " ".join(f"u{i}x{j}" for j in range(12)) for i in range(40)] + ["", " ", "a b", "A  b"]
    sets = []
    for t in texts:
        w = t.lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    label = list(range(len(texts)))
    while True:
        new = [min([label[j] for j in range(len(texts)) if 10 * len(a & sets[j]) >= 8 * len(a | sets[j])]) for a in sets]
        if new == label:
            break
        label = new
    docs = spark.createDataFrame([(i, t, "en", "a", 0) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, tiny).collect()}
    assert kept == set(label) and len(kept) < len(texts) - 20
