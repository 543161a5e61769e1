"""Toxicity by subword bags: averaged embeddings under a linear softmax, trained in numpy.

A word is the bag of its character n-grams with boundary marks, hashed into a fixed table
of vectors, and of itself; a document is the average of its words; a softmax over two
classes reads it.  Table and softmax are trained jointly, so a misspelling that was never
seen still shares most n-gram vectors with the words it came from.  As the softmax is
linear, a trained model boils down to one number per word, which is what tasks look up.
"""

from __future__ import annotations

import zlib
from array import array
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from gridhub.llm.arrow import column, filled, text_slices, word_lists

#: Rows of the vector table; n-grams are hashed into it.
BUCKETS = 1 << 17
DIM = 8
GRAMS = (3, 4, 5)
#: Bounds of the labelled sample that the model is fitted on: documents of each class, and
#: bytes of a document (the sample is drawn among documents up to that; all are scored whole).
FIT_DOCS, FIT_BYTES = 3_000, 20_000
#: Characters up to which a word's score is kept for its next occurrence, and of a longer
#: word the characters that are taken at a time.
MEMO_CHARS, CHUNK_CHARS = 64, 1 << 16
#: A word that occurs n times in a document weighs n to this power in the average.
DAMPING = 0.5


def _long_grams(data: str) -> np.ndarray:
    """Table rows of a long marked word's distinct n-grams, chunks overlapping by a gram less one."""
    found = np.array([zlib.crc32(data.encode("utf-8", "surrogatepass"))], np.uint32)
    for a in range(0, len(data), CHUNK_CHARS):
        part = data[a : a + CHUNK_CHARS + max(GRAMS) - 1]
        mine = {part[i : i + n] for n in GRAMS for i in range(min(CHUNK_CHARS, len(part) - n + 1))}
        found = np.union1d(found, np.array([zlib.crc32(g.encode("utf-8", "surrogatepass")) for g in mine], np.uint32))
    return (found % BUCKETS).astype(np.int32)


def _grams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, table rows) of the n-grams of each whole word."""
    rows, sizes = array("i"), array("i")
    for w in words:
        data = f"<{w}>"
        if len(w) > MEMO_CHARS:
            long = _long_grams(data)
            rows.frombytes(long.tobytes())
            sizes.append(len(long))
            continue
        mine = {data} | {data[i : i + n] for n in GRAMS for i in range(len(data) - n + 1)}
        rows.extend(zlib.crc32(g.encode("utf-8", "surrogatepass")) % BUCKETS for g in sorted(mine))
        sizes.append(len(mine))
    return np.r_[0, np.cumsum(np.frombuffer(sizes, np.int32), dtype=np.int64)], np.frombuffer(rows, np.int32)


def _words(texts: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """Lower-cased words, freed of ASCII punctuation at both ends."""
    bounds, words = word_lists(pc.utf8_lower(texts), unicode=True)
    bare = pc.ascii_trim(words, "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~")
    return bounds, pc.if_else(pc.equal(pc.binary_length(bare), 0), words, bare)


def document_means(bounds: np.ndarray, which: np.ndarray, each: np.ndarray) -> np.ndarray:
    """Damped average of ``each[which]`` per document; 0 where there is no word."""
    docs = len(bounds) - 1
    key = np.repeat(np.arange(docs), np.diff(bounds)) * max(1, len(each)) + which
    pairs, many = np.unique(key, return_counts=True)
    doc, weight = pairs // max(1, len(each)), many**DAMPING
    total = np.bincount(doc, weight * each[pairs % max(1, len(each))], docs)
    return total / np.maximum(np.bincount(doc, weight, docs), 1e-12)


@dataclass
class SubwordModel:
    table: np.ndarray  # float32 [BUCKETS]: the table read by the softmax's weight difference
    bias: float

    def word_scores(self, words: list[str]) -> np.ndarray:
        if not words:
            return np.zeros(0)
        offsets, rows = _grams(words)
        return np.add.reduceat(self.table[rows], offsets[:-1]) / np.diff(offsets)


def fit(texts: pa.Array, labels: np.ndarray, prior: float | None = None, epochs: int = 6, rate: float = 0.3, batch: int = 32, seed: int = 5, decay: float = 0.005) -> SubwordModel:
    """Joint training of vectors and softmax by AdaGrad on the cross-entropy."""
    if not len(texts) or len(set(labels.tolist())) < 2:
        share = float(np.clip(np.mean(labels) if len(labels) else 0.0, 1e-6, 1 - 1e-6))
        return SubwordModel(np.zeros(BUCKETS, np.float32), float(np.log(share / (1 - share))))
    bounds, flat = _words(texts)
    coded = flat.dictionary_encode()
    which = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    g_off, g_row = _grams(coded.dictionary.to_pylist())
    g_len = np.diff(g_off)
    rng = np.random.default_rng(seed)
    vectors = np.zeros((BUCKETS, DIM), np.float32)  # an n-gram that the fit never met says nothing
    soft, bias = rng.normal(0, 1, (DIM, 2)).astype(np.float32), np.zeros(2, np.float32)
    sum_v, sum_s, sum_b = np.full(BUCKETS, 1e-6, np.float32), np.full(soft.shape, 1e-6), np.full(2, 1e-6)
    prior = float(np.clip(labels.mean() if prior is None else prior, 0.01, 0.99))
    weight = np.where(labels == 1, prior / labels.mean(), (1 - prior) / (1 - labels.mean()))
    docs = np.flatnonzero(np.diff(bounds) > 0)

    def counted(d: int) -> tuple[np.ndarray, np.ndarray]:
        words, many = np.unique(which[bounds[d] : bounds[d + 1]], return_counts=True)
        return words.astype(np.int32), many.astype(np.float32) ** DAMPING

    def bag(words: np.ndarray, many: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Table rows of a document and the weight of each in its average."""
        lens = g_len[words]
        at = np.repeat(g_off[words] - np.cumsum(lens) + lens, lens) + np.arange(lens.sum())
        return g_row[at], np.repeat(many / lens / many.sum(), lens).astype(np.float32)

    held = {d: counted(d) for d in docs}
    del which, flat, coded
    for epoch in range(epochs):
        rng.shuffle(docs)
        step = rate * (1 - epoch / epochs)
        for i in range(0, len(docs), batch):
            some = docs[i : i + batch]
            bags = [bag(*held[d]) for d in some]
            rows = np.concatenate([b[0] for b in bags])
            share = np.concatenate([b[1] for b in bags])
            sizes = np.array([len(b[0]) for b in bags])
            hidden = np.add.reduceat(vectors[rows] * share[:, None], np.cumsum(sizes) - sizes)
            logit = hidden @ soft + bias
            p = np.exp(logit - logit.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(some)), labels[some]] -= 1
            p *= weight[some, None]
            g_soft, g_bias, g_hidden = hidden.T @ p, p.sum(0), p @ soft.T
            sum_s += g_soft**2
            sum_b += g_bias**2
            soft -= (step * g_soft / np.sqrt(sum_s)).astype(np.float32)
            bias -= (step * g_bias / np.sqrt(sum_b)).astype(np.float32)
            g_rows = np.repeat(g_hidden, sizes, axis=0) * share[:, None]
            unique, back = np.unique(rows, return_inverse=True)
            total = np.stack([np.bincount(back, g_rows[:, k], len(unique)) for k in range(DIM)], 1)
            sum_v[unique] += (total**2).mean(1)
            vectors[unique] -= (step * (total / np.sqrt(sum_v[unique])[:, None] + decay * vectors[unique])).astype(np.float32)
    return SubwordModel((vectors @ (soft[:, 1] - soft[:, 0])).astype(np.float32), float(bias[1] - bias[0]))


def learnable(labels: DataFrame, folds: int = 5) -> DataFrame:
    """``doc_id, toxic`` outside the held-out fold; of repeated ids the larger label."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("toxic in (0, 1)")
    return known.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds != 0).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))


def labelled_sample(docs: DataFrame, labels: DataFrame, folds: int = 5) -> DataFrame:
    """Bounded fit sample: rows whose id's CRC-32 is not 0 modulo ``folds``.

    Labels of documents within FIT_BYTES are drawn by a hash of the id, at most FIT_DOCS of
    each class; the texts come by a broadcast of those ids.  Rows without text or label
    take no part.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where(F.octet_length("text") <= FIT_BYTES)
    known = learnable(labels, folds).join(texts.select("doc_id"), "doc_id", "left_semi").withColumn("place", F.xxhash64("doc_id", F.lit(11)))
    sides = [known.where(F.col("toxic") == c).orderBy("place", "doc_id").limit(FIT_DOCS).select("doc_id", "toxic") for c in (0, 1)]
    drawn = F.broadcast(sides[0].unionByName(sides[1]))  # 2 * FIT_DOCS ids at most
    return texts.join(drawn, "doc_id").select("text", "toxic")


def train(docs: DataFrame, labels: DataFrame) -> SubwordModel:
    """Fit on the bounded sample, weighted to the share of toxic rows among all labelled.

    One task fits and sends back the words' table, BUCKETS numbers, and the bias behind
    them; repeated rows of the sample count each, and rows are sorted, so reruns agree.
    """
    share = learnable(labels).agg(F.avg("toxic")).first()[0]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(list(batches), pa.schema([("text", pa.string()), ("toxic", pa.int32())])).sort_by([("text", "ascending"), ("toxic", "ascending")])
        text = rows["text"].combine_chunks()
        model = fit(text if isinstance(text, pa.Array) else pa.array([], pa.string()), rows["toxic"].to_numpy().astype(np.int64), share)
        numbers = np.r_[model.table.astype(np.float64), model.bias]
        full = np.flatnonzero(numbers)
        yield pa.RecordBatch.from_pydict({"at": pa.array(full), "number": pa.array(numbers[full])})

    found = labelled_sample(docs, labels).repartition(1).mapInArrow(run, "at long, number double").toArrow()
    numbers = np.zeros(BUCKETS + 1)
    numbers[found["at"].to_numpy()] = found["number"].to_numpy()
    return SubwordModel(numbers[:-1].astype(np.float32), float(numbers[-1]))


def score_texts(docs: DataFrame, model: SubwordModel, whole: bool = False) -> DataFrame:
    """``doc_id, score``, or with ``whole`` the row as struct ``doc`` and its ``score``.

    The score is the softmax of the whole text's average.  Null and empty texts have no
    words and get the score of the bias alone.  Every row is scored by itself, so repeated
    rows repeat, equal texts get equal scores and a null id stays null.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)  # BUCKETS floats, whatever the corpus

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo: dict[str, float] = {}
        for part in text_slices(read(batches)):
            bounds, flat = _words(filled(part))
            coded = flat.dictionary_encode()
            words = coded.dictionary.to_pylist()
            lacking = [w for w in words if w not in memo and len(w) <= MEMO_CHARS]
            if len(memo) > 300_000:
                memo.clear()
                lacking = [w for w in words if len(w) <= MEMO_CHARS]
            memo.update(zip(lacking, sent.value.word_scores(lacking).tolist()))
            each = np.fromiter((memo[w] if len(w) <= MEMO_CHARS else sent.value.word_scores([w])[0] for w in words), np.float64, len(words))
            logit = sent.value.bias + document_means(bounds, coded.indices.to_numpy(zero_copy_only=False), each)
            score = pa.array(np.round(1 / (1 + np.exp(-np.clip(logit, -30, 30))), 9))
            yield pa.RecordBatch.from_pydict({kept: column(part, kept), "score": score})

    if whole:
        kept, source = "doc", docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("doc"))
        at = [c.lower() for c in docs.columns].index("text")
        # the text goes to Python once, within its row
        read = lambda batches: (pa.RecordBatch.from_arrays([b.column(0), b.column(0).field(at)], ["doc", "text"]) for b in batches)
        return source.mapInArrow(run, StructType([source.schema["doc"], StructField("score", DoubleType())]))
    kept, read = "doc_id", iter
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return source.mapInArrow(run, "doc_id long, score double")


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of all ``documents``; a fifth of the ids is held out of the fit."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    scored = score_texts(docs, train(docs, labels))
    return scored.select("doc_id", (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
