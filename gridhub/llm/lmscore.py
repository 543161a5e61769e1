"""Cross-entropy difference of two matched n-gram models of words.

Target and background share one open vocabulary, the words of all documents, the order
(two words) and the smoothing: a pair's share of its first word's pairs is mixed with a
unigram share, as if that had been seen ALPHA times.  The HEAD most frequent words have
unigram shares of their own, all others of a model the same share.  A document is left out
of the pair counts that it is scored by, so neither model has seen what it judges.  The
score is the mean over its words of the loss under the target less the loss under the
background: the lower, the more it reads like the target.

All pair counts grow with the corpus and are never gathered.  ``(document, pair, times)``
rows meet by the pair's first word, where one sort serves the sums of pairs and of first
words.  Rows of a frequent first word meet by the whole pair, as its total is among the
broadcast ones, and pairs that a sample finds frequent are counted inside the scans: no
key holds more than a small share of the rows.  Sums are whole millionths of a bit, so
reruns agree.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridhub.llm.arrow import column, filled, text_slices, word_lists
from gridhub.llm.grams import KeyTable
from gridhub.llm.joins import good_ids, with_flag
from gridhub.plans.staging import stage

#: Times that a unigram share counts in its pair's share.
ALPHA = 4.0
#: Words with unigram shares and first-word totals of their own, known to every task.
HEAD = 1 << 16
#: Pairs counted inside the scans, and texts of the sample that names them: speed only.
HOT_PAIRS, SAMPLE_TEXTS = 1 << 20, 20_000
#: Losses are whole millionths of a bit.
UNIT = 1_000_000
#: Bytes of text taken at a time, and keys that a task holds before it sends them on.
WORD_SLICE, HELD = 2 << 20, 1 << 20
#: Key of the word that stands before every text.
START = np.uint64(0x9AE16A3B2F90404F)
#: Characters of scripts without spaces are words of their own.
SPLIT = r"([\p{Han}\p{Hiragana}\p{Katakana}\p{Thai}\p{Lao}\p{Khmer}\p{Myanmar}])"
#: ASCII signs at both ends of a word are no part of it, unless there is nothing else.
SIGNS = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_STEP = np.uint64(0x9E3779B97F4A7C15)
#: Codes of rows: one of a document's two, and the step between first words' head numbers.
LONE, WIDE = -(1 << 63), 1 << 25
#: A first word's times below SMALL travel in a number's upper bytes.
SMALL, UPPER = 1 << 14, 48


def word_keys(words: pa.Array) -> np.ndarray:
    """Key of each word, which does not depend on the signs at its ends."""
    bare = pc.utf8_trim(words, SIGNS)
    held = pc.if_else(pc.equal(pc.binary_length(bare), 0), words, bare).cast(pa.large_binary())
    _, ends, data = held.buffers()
    ends = np.frombuffer(ends, np.int64)[held.offset : held.offset + len(held) + 1].tolist() if len(held) else [0]
    line, digest = data.to_pybytes() if data else b"", xxhash.xxh64_intdigest
    return np.fromiter((digest(line[a:b]) for a, b in zip(ends, ends[1:])), np.uint64, len(held))


def slice_words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(offsets per text, code of every word, sorted key of each code, START's code) of whole texts, lower-cased."""
    bounds, words = word_lists(pc.replace_substring_regex(pc.utf8_lower(texts), SPLIT, r" \1 "), unicode=True)
    coded = words.dictionary_encode()
    keys, code = np.unique(np.r_[word_keys(coded.dictionary), START], return_inverse=True)  # words apart by their signs alone share a code
    return bounds, code[coded.indices.to_numpy()], keys, int(code[-1])


def _firsts(bounds: np.ndarray, words: np.ndarray, start: int) -> tuple[np.ndarray, np.ndarray]:
    """Code of the word before every word, and the text each word is in."""
    first = np.r_[start, words[:-1]] if len(words) else words
    sizes = np.diff(bounds)
    first[bounds[:-1][sizes > 0]] = start
    return first, np.repeat(np.arange(len(sizes)), sizes)


def _pair_keys(keys: np.ndarray, first: np.ndarray, words: np.ndarray) -> np.ndarray:
    return keys[first] * _STEP ^ keys[words]


def _distinct(by: np.ndarray, first: np.ndarray, words: np.ndarray, kinds: int) -> tuple[np.ndarray, ...]:
    """Distinct (by, first, word), sorted, how often each comes, and how often its (by, first)."""
    if len(by) and (int(by.max()) + 1) * kinds * kinds < 1 << 63:  # one sort of plain numbers
        whole = np.sort((by * kinds + first) * kinds + words)
        new = np.flatnonzero(np.r_[True, whole[1:] != whole[:-1]])
        head, w = np.divmod(whole[new], kinds)
        x, f = np.divmod(head, kinds)
    else:
        order = np.lexsort((words, first, by))
        x, f, w = by[order], first[order], words[order]
        new = np.flatnonzero(np.r_[True, (x[1:] != x[:-1]) | (f[1:] != f[:-1]) | (w[1:] != w[:-1])][: len(x)])
        x, f, w = x[new], f[new], w[new]
    n = np.diff(np.r_[new, len(by)])
    group = np.cumsum(np.r_[True, (x[1:] != x[:-1]) | (f[1:] != f[:-1])][: len(x)]) - 1
    return x, f, w, n, np.bincount(group, n).astype(np.int64)[group]


class _Tally:
    """Adds up columns by key in a task, within a bound."""

    def __init__(self, columns: int):
        self.columns, self.held, self.size = columns, [], 0

    def add(self, keys: np.ndarray, *sums: np.ndarray) -> None:
        coded = pa.array(keys).dictionary_encode()
        back = coded.indices.to_numpy()
        unique = coded.dictionary.to_numpy()
        self.held.append((unique, *[np.bincount(back, s, len(unique)).astype(np.int64) for s in sums]))
        self.size += len(unique)

    def take(self, last: bool = False) -> tuple | None:
        """The sums, when there are too many keys or at the end."""
        if not self.held or not (last or self.size > HELD):
            return None
        keys, back = np.unique(np.concatenate([h[0] for h in self.held]), return_inverse=True)
        whole = (keys, *[np.bincount(back, np.concatenate([h[i + 1] for h in self.held]), len(keys)).astype(np.int64) for i in range(self.columns)])
        self.held, self.size = ([], 0) if last or len(keys) > HELD // 2 else ([whole], len(keys))
        return whole if not self.held else None


def frequent_pairs(docs: DataFrame) -> np.ndarray:
    """Keys of pairs that a bounded sample of texts shows to be frequent."""
    every = max(1, docs.count() // SAMPLE_TEXTS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally = _Tally(1)
        for part in text_slices(batches, limit=WORD_SLICE):
            bounds, words, keys, start = slice_words(filled(part))
            first, text = _firsts(bounds, words, start)
            _, f, w, n, _ = _distinct(np.zeros_like(text), first, words, len(keys))
            tally.add(_pair_keys(keys, f, w), n)
            if (found := tally.take()) is not None:
                yield batch(*found)
        if (found := tally.take(True)) is not None:
            yield batch(*found)

    def batch(keys: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        many = n > 1
        return pa.RecordBatch.from_pydict({"pair": pa.array(keys[many].view(np.int64)), "n": pa.array(n[many])})

    drawn = docs.where(F.pmod(F.xxhash64("doc_id", F.lit(31)), F.lit(every)) == 0).select("text")
    counts = drawn.mapInArrow(run, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n")).where("n > 2")
    return np.sort(counts.orderBy(F.desc("n"), "pair").limit(HOT_PAIRS).select("pair").toArrow()["pair"].to_numpy().view(np.uint64))


def counted(docs: DataFrame, hot: np.ndarray) -> DataFrame:
    """Exact counts over all texts: ``kind, key, n, n_target, firsts, firsts_target``.

    Kind 0 are words, with how often they come and how often they are a pair's first;
    kind 1 are the pairs of ``hot``.  Needs ``text, in_target``.
    """
    sent = docs.sparkSession.sparkContext.broadcast(hot)  # HOT_PAIRS keys at most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words_in, pairs_in = _Tally(4), _Tally(2)
        table = KeyTable(sent.value)
        for part in text_slices(batches, limit=WORD_SLICE):
            bounds, words, keys, start = slice_words(filled(part))
            first, text = _firsts(bounds, words, start)
            flag = column(part, "in_target").to_numpy(zero_copy_only=False).astype(np.int64)[text]
            sums = [np.bincount(c, w, len(keys)) for c in (words, first) for w in (None, flag)]
            seen = sums[0] + sums[2] > 0
            words_in.add(keys[seen], *[c[seen] for c in sums])
            mine, f, w, n, _ = _distinct(flag, first, words, len(keys))
            pair = _pair_keys(keys, f, w)
            known = table.find(pair) >= 0
            pairs_in.add(pair[known], n[known], (n * mine)[known])
            for kind, tally in ((0, words_in), (1, pairs_in)):
                if (found := tally.take()) is not None:
                    yield batch(kind, *found)
        for kind, tally in ((0, words_in), (1, pairs_in)):
            if (found := tally.take(True)) is not None:
                yield batch(kind, *found)

    def batch(kind: int, keys: np.ndarray, *sums: np.ndarray) -> pa.RecordBatch:
        sums = (*sums, *[np.zeros(len(keys), np.int64)] * (4 - len(sums)))
        out = {"kind": pa.array(np.full(len(keys), kind, np.int32)), "key": pa.array(keys.view(np.int64))}
        return pa.RecordBatch.from_pydict(out | {c: pa.array(s) for c, s in zip(names, sums)})

    names = ("n", "n_target", "firsts", "firsts_target")
    found = docs.select("text", "in_target").mapInArrow(run, "kind int, key long, " + ", ".join(f"{c} long" for c in names))
    return found.groupBy("kind", "key").agg(*[F.sum(c).alias(c) for c in names])


class Shared:
    """What every task knows of both models, background first: the head words and hot pairs."""

    def __init__(self, counts: DataFrame, head: int):
        words = counts.where("kind = 0")
        total, target, kinds = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("n_target"), F.lit(0)), F.count_if(F.col("n") > 0)).first()
        top = words.orderBy(F.desc(F.col("n") + F.col("firsts")), "key").limit(head).toArrow()
        hot = counts.where("kind = 1").toArrow()  # HOT_PAIRS rows at most
        numbers = lambda t, c: t[c].to_numpy().astype(np.float64)
        self.words, self.pairs = top["key"].to_numpy().view(np.uint64), hot["key"].to_numpy().view(np.uint64)
        self.firsts = [numbers(top, "firsts"), numbers(top, "firsts_target")]
        self.counts = [numbers(hot, "n"), numbers(hot, "n_target")]
        self.unigram = []
        real = numbers(top, "n") > 0  # START is never predicted
        for name, mass in (("n", total), ("n_target", target)):
            own = (numbers(top, name) + 1) * real
            rest = max(1, kinds - int(real.sum()))
            other = (mass - numbers(top, name).sum() + rest) / rest
            self.unigram.append(np.r_[own, other] / (mass + max(1, kinds)))


def upper(times: np.ndarray) -> np.ndarray:
    """Numbers below SMALL in the upper bytes, next to the number behind them; others as they are."""
    return np.where(times < SMALL, times << UPPER, times)


def from_upper(name: str) -> F.Column:
    """What ``upper`` was given; no text has 2**UPPER words."""
    return F.when(F.col(name) >= 1 << UPPER, F.shiftright(name, UPPER)).otherwise(F.col(name))


def pair_losses(docs: DataFrame, shared: Shared) -> DataFrame:
    """Rows of documents with their hot pairs settled, and one a document and other pair.

    All go through one exchange as ``n, nctx, p, row, g, code``: what varies lies side by
    side, which compresses, and for that ``upper`` moves a pair's ``nctx``.  A pair's row: its
    document's row, ``p`` where it meets its likes (the first word's key, or the pair's if
    that is a head word), ``g`` the pair's key in the first case, its times ``n`` and its
    first word's times ``nctx`` in the document, and ``code``: head numbers of both words
    and whether in the target.  Two head words meet by their numbers instead, below -1,
    with 1 as ``g`` and no numbers in ``code``, which takes half the bytes.  A document's two rows have p = row: doc_id, words, loss
    under the background, and -1 less the loss under the target as code; then under the
    least code the number of pairs that no other document has.
    """
    sent = docs.sparkSession.sparkContext.broadcast(shared)  # HEAD words and HOT_PAIRS pairs at most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = sent.value
        head, hot = KeyTable(s.words), KeyTable(s.pairs)
        row = TaskContext.get().partitionId() << 33
        for part in text_slices(batches, limit=WORD_SLICE):
            bounds, words, keys, start = slice_words(filled(part))
            first, text = _firsts(bounds, words, start)
            many = part.num_rows
            rows, row = row + np.arange(many), row + many
            flag = column(part, "in_target").to_numpy(zero_copy_only=False).astype(np.int64)
            x, f, w, n, nctx = _distinct(text, first, words, len(keys))
            place, g = head.find(keys), _pair_keys(keys, f, w)
            h1, h2, at, f = place[f], place[w], hot.find(g), keys[f]
            settled = (h1 >= 0) & (at >= 0)
            near = np.flatnonzero(settled)
            sums = []
            for model in (0, 1):
                own = n[near] if model == 0 else n[near] * flag[x[near]]
                ctx = nctx[near] if model == 0 else nctx[near] * flag[x[near]]
                c = s.counts[model][at[near]] - own
                p = (c + ALPHA * s.unigram[model][h2[near]]) / (s.firsts[model][h1[near]] - ctx + ALPHA)
                sums.append(np.bincount(x[near], n[near] * np.round(-np.log2(p) * UNIT), many).astype(np.int64))
                if model == 0:
                    lone = np.bincount(x[near], n[near] * (c == 0), many).astype(np.int64)
            yield batch(rows, rows, column(part, "doc_id"), np.diff(bounds), sums[0], -1 - sums[1])
            nothing = np.zeros(many, np.int64)
            yield batch(rows, rows, pa.nulls(many, pa.int64()), lone, nothing, np.full(many, LONE))
            far = np.flatnonzero(~settled)
            common, both = h1[far] >= 0, (h1[far] >= 0) & (h2[far] >= 0)
            numbers = h1[far].astype(np.int64), h2[far].astype(np.int64)
            meet = np.where(both, -2 - (numbers[0] * WIDE + numbers[1]), np.where(common, g[far], f[far]).view(np.int64))
            code = np.where(both, 0, ((numbers[0] + 1) * WIDE + numbers[1] + 1) * 2) + flag[x[far]]
            pair_key = np.where(both, 1, np.where(common, 0, g[far].view(np.int64)))
            by = np.argsort(meet)  # alike rows side by side compress
            far, meet, pair_key, code = far[by], meet[by], pair_key[by], code[by]
            yield batch(rows[x[far]], meet, pa.array(pair_key), n[far], upper(nctx[far]), code)

    def batch(row, p, g, n, nctx, code) -> pa.RecordBatch:
        whole = {"n": n, "nctx": nctx, "p": p, "row": row, "g": g, "code": code}
        return pa.RecordBatch.from_pydict({c: v.cast(pa.int64()) if isinstance(v, pa.Array) else pa.array(np.asarray(v, np.int64)) for c, v in whole.items()})

    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "in_target")
    return source.mapInArrow(run, "n long, nctx long, p long, row long, g long, code long")


def cross_entropy_difference(docs: DataFrame, head: int = HEAD) -> DataFrame:
    """Score every row of ``docs`` by both models.

    Needs ``doc_id, text`` and a boolean ``in_target``; the background is every row, the
    target the flagged ones.  Null text counts as empty and a null flag as false; a text
    without words gets null losses; with no target row its model is the smoothing alone.
    Repeated rows are rows of their own, each left out only of its own scoring; a null id
    stays null; other columns are ignored.  Row numbers follow the scan, which must deal
    the same rows to the same task when it is run again, as files do.  Returns ``doc_id,
    n_words, lone_pairs`` (pairs no other row has), ``target_loss, background_loss,
    difference``.
    """
    spark = docs.sparkSession
    docs = docs.withColumn("in_target", F.coalesce("in_target", F.lit(False)))
    shared = Shared(stage(counted(docs, frequent_pairs(docs)), "words"), head)
    met = pair_losses(docs, shared).repartition("p").sortWithinPartitions("p", "g")
    pair, word = Window.partitionBy("p", "g"), Window.partitionBy("p")
    pairs, docs_rows = F.col("code") >= 0, (F.col("code") < 0) & (F.col("code") > LONE)
    both = F.col("code").isin(0, 1) & (F.col("g") == 1) & (F.col("p") < -1)
    numbers = -2 - F.col("p")
    bits, last = WIDE.bit_length() - 1, F.lit(WIDE - 1).cast("long")
    h2 = F.when(both, numbers.bitwiseAND(last)).otherwise(F.shiftright("code", 1).bitwiseAND(last) - 1)
    h1 = F.when(both, F.shiftright(numbers, bits)).otherwise(F.shiftright("code", bits + 1) - 1)
    t = F.col("code").bitwiseAND(F.lit(1).cast("long"))
    met = met.withColumn("n_t", F.col("n") * t)  # all that the windows carry besides the rows
    met = met.withColumns({"c0": F.sum("n").over(pair), "c1": F.sum("n_t").over(pair)})
    met = met.withColumns({"w0": F.sum("n").over(word), "w1": F.sum("n_t").over(word)})
    met = met.withColumns({"h2": h2, "h1": h1})
    places = np.arange(len(shared.words))
    firsts = spark.createDataFrame(pa.table({"f_id": places, "f0": shared.firsts[0], "f1": shared.firsts[1]}))
    unigram = spark.createDataFrame(pa.table({"u_id": np.r_[places, -1], "u0": shared.unigram[0], "u1": shared.unigram[1]}))
    met = met.join(F.broadcast(firsts), F.col("h1") == F.col("f_id"), "left").join(F.broadcast(unigram), F.col("h2") == F.col("u_id"), "left")  # HEAD rows at most

    def loss(model: int) -> F.Column:
        own = F.lit(1) if model == 0 else t
        c = F.col(f"c{model}") - F.col("n") * own
        total = F.coalesce(f"f{model}", F.col(f"w{model}").cast("double")) - from_upper("nctx") * own
        bits = -F.log2((c + ALPHA * F.col(f"u{model}")) / (total + ALPHA))
        return F.col("n") * F.round(bits * UNIT).cast("long")

    sums = met.groupBy("row").agg(
        F.max(F.when(docs_rows, F.col("g"))).alias("doc_id"),
        F.max(F.when(docs_rows, F.col("n"))).alias("n_words"),
        F.sum(F.when(pairs, F.when(F.col("c0") == F.col("n"), F.col("n")).otherwise(0)).when(F.col("code") == LONE, F.col("n")).otherwise(0)).alias("lone_pairs"),
        F.sum(F.when(pairs, loss(1)).when(docs_rows, -1 - F.col("code")).otherwise(0)).alias("target"),
        F.sum(F.when(pairs, loss(0)).when(docs_rows, F.col("nctx")).otherwise(0)).alias("background"),
    )
    mean = lambda c: F.when(F.col("n_words") > 0, F.round(F.col(c) / F.col("n_words") / UNIT, 6))
    scored = sums.select("doc_id", "n_words", "lone_pairs", mean("target").alias("target_loss"), mean("background").alias("background_loss"))
    return scored.withColumn("difference", F.round(F.col("target_loss") - F.col("background_loss"), 6))


def op5_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` against the texts that ``labels`` calls good."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    return cross_entropy_difference(with_flag(docs.select("doc_id", "text"), stage(good_ids(labels), "good"), "in_target"))
