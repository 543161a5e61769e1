"""Near copies by shingle overlap: every pair whose Jaccard index reaches a bound is linked.

All shingles of all texts have one order: those that a sample finds in many texts come
last, the others go by their hash.  Two sets that overlap enough share a shingle among the
first few of both, however the sample falls, so these few are what is dealt into buckets.
Pairs of a bucket are thinned by size and by a sketch, a parity bit for each of some bins,
whose distance never exceeds that of the sets; the rest is settled by the whole sets.  In a
bucket everything is first compared with one leader, and what the links found join needs no
comparison any more, so a large group of near copies is not written out as pairs.  Buckets
that are still apart are compared pair by pair inside tasks, which write the pairs of small
ones and of others only what hangs together, at most a row a key.  What hangs together over
all buckets is then brought to one task with its whole sets, or block against block if it
is much, and compared pair by pair once more; again only what hangs together is written.
Only sets in the most crowded buckets, as a passage in very many texts makes them, are dealt
once more, in the order that their own counts give.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridhub.llm.arrow import column, filled, text_slices
from gridhub.llm.joins import with_ids
from gridhub.operators.components import star_components
from gridhub.operators.unionfind import join_labels
from gridhub.plans.staging import release, stage

#: Words of a shingle, and the least Jaccard index of near copies in percent.
WIDTH, PERCENT = 5, 80
#: Texts of the sample that tells common shingles, in how many of them a shingle is common,
#: and how many of the commonest are put last.  They bear on speed only.
SAMPLE_TEXTS, COMMON_IN, COMMON_KEPT = 10_000, 5, 200_000
#: Least bits of a sketch, and rounds of leaders.
LEAST_BITS, ROUNDS = 256, 2
#: Keys of a bucket up to which its pairs are written out where sketches leave them, and up to
#: which what hangs together is written; larger ones are dealt anew.
PAIR_BUCKET, TASK_BUCKET = 16, 512
#: Pairs whose sketches a task holds at a time, and rows compared with all others at a time.
PAIR_SLICE, ROW_SLICE = 1 << 16, 256
#: Keys and shingles of a block; a group of more is compared block against block.
BLOCK_KEYS, BLOCK_SHINGLES = 2048, 1 << 20


def shingle_set(text: str, width: int = WIDTH, seed: int = 42) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a whole text's word shingles; a shorter text is one."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    line = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]).tolist()
    starts = [0, *ends[: max(0, len(words) - width)]]
    stops = ends[width - 1 :] if len(words) >= width else ends[-1:]
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(line[a : b - 1], seed) for a, b in zip(starts, stops)], np.uint64))


def majority(hashes: np.ndarray) -> int:
    """64-bit SimHash of hashes: the bits that over half of them have."""
    total, step = np.zeros(64, np.int64), 1 << 18
    for i in range(0, len(hashes), step):
        total += np.unpackbits(hashes[i : i + step].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * total > len(hashes), bitorder="little").view(np.uint64)[0])


def _set_key(s: np.ndarray) -> int:
    """Signed 64-bit digest that names a set; equal sets are one node."""
    return int(np.uint64(xxhash.xxh3_64_intdigest(s.tobytes())).astype(np.int64))


def sketch(s: np.ndarray) -> bytes:
    """Whether an odd number of hashes falls into each of a power of two of bins, a bit a bin."""
    bins = max(LEAST_BITS, 1 << len(s).bit_length())
    found = np.bincount((s & np.uint64(bins - 1)).astype(np.int64), minlength=bins)
    return np.packbits((found & 1).astype(np.uint8), bitorder="little").tobytes()


def _folded(sketches: list[bytes], width: int) -> np.ndarray:
    """Rows of 64-bit words; sketches, all of one length, are folded to ``width`` bytes."""
    return np.bitwise_xor.reduce(np.frombuffer(b"".join(sketches), np.uint64).reshape(len(sketches), -1, width // 8), axis=1)


def distances(one: list[bytes], other: list[bytes]) -> np.ndarray:
    """A lower bound of each pair's symmetric difference; wider sketches are folded."""
    out = np.zeros(len(one), np.int64)
    size = np.array([[len(x), len(y)] for x, y in zip(one, other)], np.int64).reshape(-1, 2)
    for m, k in np.unique(size, axis=0).tolist():
        if m and k:
            at = np.flatnonzero((size[:, 0] == m) & (size[:, 1] == k))
            for part in np.array_split(at, max(1, len(at) * max(m, k) >> 22)):
                x, y = (_folded([side[i] for i in part], min(m, k)) for side in (one, other))
                out[part] = np.bitwise_count(x ^ y).sum(1, dtype=np.int64)
    return out


def common_shingles(docs: DataFrame, width: int) -> np.ndarray:
    """Sorted shingles that occur in several texts of a bounded sample."""
    every = max(1, docs.count() // SAMPLE_TEXTS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in text_slices(batches):
            sets = [shingle_set(t, width) for t in filled(part).to_pylist()]
            shingle, many = np.unique(np.concatenate(sets), return_counts=True)
            yield pa.RecordBatch.from_pydict({"shingle": pa.array(shingle.view(np.int64)), "n": pa.array(many.astype(np.int64))})

    drawn = docs.where(F.pmod(F.xxhash64("doc_id", F.lit(23)), F.lit(every)) == 0).select("text")
    counts = drawn.mapInArrow(run, "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n")).where(F.col("n") >= COMMON_IN)
    top = counts.orderBy(F.desc("n"), "shingle").limit(COMMON_KEPT).select("shingle").toArrow()
    return np.sort(top["shingle"].to_numpy().view(np.uint64))


def described(docs: DataFrame, width: int, percent: int, carry: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id, key, n, bins, fp, first`` of every row and what ``carry`` names.

    Digest, size, sketch, SimHash fingerprint and first shingles of its set.
    """
    kinds = dict(docs.dtypes)
    sent = docs.sparkSession.sparkContext.broadcast(common_shingles(docs, width))  # COMMON_KEPT numbers at most

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common = sent.value
        for part in text_slices(batches):
            keys, sizes, bins, prints, first = [], [], [], [], []
            for t in filled(part).to_pylist():
                s = shingle_set(t, width)
                keys.append(_set_key(s))
                sizes.append(len(s))
                bins.append(sketch(s))
                prints.append(majority(s))
                late = common[np.minimum(np.searchsorted(common, s), len(common) - 1)] == s if len(common) else np.zeros(len(s), bool)
                many = len(s) + (percent * len(s)) // -100 + 1 if len(s) else 0
                first.append(np.concatenate([s[~late], s[late]])[:many].view(np.int64))
            yield pa.RecordBatch.from_pydict({
                "doc_id": column(part, "doc_id"), "key": pa.array(keys, pa.int64()), "n": pa.array(sizes, pa.int64()), "bins": pa.array(bins, pa.binary()), "fp": pa.array(np.array(prints, np.uint64).view(np.int64)),
                "first": pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum([len(f) for f in first])], pa.int32()), pa.array(np.concatenate(first))),
            } | {c: column(part, c) for c in carry})

    schema = ", ".join(["doc_id long, key long, n long, bins binary, fp long, first array<long>", *(f"`{c}` {kinds[c]}" for c in carry)])
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *carry).mapInArrow(run, schema)


def _sets(texts: DataFrame, width: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in text_slices(batches):
            sets = [shingle_set(t, width) for t in filled(part).to_pylist()]
            yield pa.RecordBatch.from_pydict({"key": pa.array([_set_key(s) for s in sets], pa.int64()), "shingles": pa.array([s.tobytes() for s in sets], pa.binary())})

    return texts.select("text").mapInArrow(run, "key long, shingles binary")


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Distinct rows of tokens that several keys have; rows come sorted by token and key."""
    last: dict[str, np.ndarray] | None = None  # the last distinct row, and whether it was sent
    for b in batches:
        if not b.num_rows:
            continue
        rows = {c: column(b, c).to_numpy() for c in ("token", "key", "n")}
        sent = False
        if last is not None:
            sent = bool(last["sent"][0])
            rows = {c: np.r_[last[c], rows[c]] for c in rows}
        new = np.r_[True, (rows["token"][1:] != rows["token"][:-1]) | (rows["key"][1:] != rows["key"][:-1])]
        rows = {c: x[new] for c, x in rows.items()}
        same = rows["token"][1:] == rows["token"][:-1]
        out = np.r_[False, same] | np.r_[same, False]
        last = {c: x[-1:] for c, x in rows.items()} | {"sent": np.array([out[-1] or (sent and len(out) == 1)])}
        if sent:
            out[0] = False
        yield pa.RecordBatch.from_pydict({c: pa.array(x[out]) for c, x in rows.items()})


def _tokens(texts: DataFrame, width: int) -> DataFrame:
    """``key, n, token`` of every distinct shingle of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in text_slices(batches):
            sets = [shingle_set(t, width) for t in filled(part).to_pylist()]
            sizes = [len(s) for s in sets]
            key = np.repeat(np.array([_set_key(s) for s in sets], np.int64), sizes)
            yield pa.RecordBatch.from_pydict({"key": pa.array(key), "n": pa.array(np.repeat(sizes, sizes).astype(np.int64)), "token": pa.array(np.concatenate(sets).view(np.int64))})

    return texts.select("text").mapInArrow(run, "key long, n long, token long")


def rare_buckets(docs: DataFrame, known: DataFrame, keys: DataFrame, width: int, percent: int) -> DataFrame:
    """``token, key, n`` as first dealt, for some keys, with their shingles in the order of how many of them have each.

    What a passage brings into a large bucket comes last in this order, so sets that share
    no more than that don't meet.  A shingle of one set alone takes a place among its first
    and needs no bucket.  A row that is repeated counts twice, which only keeps more.
    """
    ids = stage(known.join(keys, "key", "left_semi").groupBy("key").agg(F.min("doc_id").alias("doc_id")), "ids")
    tokens = _tokens(with_ids(docs, ids), width)
    shared = tokens.groupBy("token").agg(F.count("*").alias("df")).where("df > 1")
    met = tokens.join(shared, "token")
    first = F.col("n") - F.ceil(F.col("n") * percent / 100) + 1
    alone = F.col("n") - F.count("*").over(Window.partitionBy("key"))
    place = F.row_number().over(Window.partitionBy("key").orderBy("df", "token"))
    return met.withColumns({"alone": alone, "place": place}).where(F.col("place") <= first - F.col("alone")).select("token", "key", "n")


def _close(n_a: np.ndarray, n_b: np.ndarray, bins_a: list[bytes], bins_b: list[bytes], percent: int) -> np.ndarray:
    """Whether sets of these sizes and sketches may reach the bound."""
    return distances(bins_a, bins_b) * (100 + percent) <= (n_a + n_b) * (100 - percent)


def _whole(batches: Iterator[pa.RecordBatch], by: tuple[str, ...]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by some columns; a group of them that a batch cuts is carried into the next."""

    def change(b: pa.RecordBatch) -> np.ndarray:
        ids = [column(b, c).to_numpy() for c in by]
        return np.flatnonzero(np.any([x[1:] != x[:-1] for x in ids], axis=0)) + 1

    kept: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        kept.append(b)
        if all(column(kept[0], c)[0].equals(column(b, c)[-1]) for c in by):
            continue
        whole = pa.concat_batches(kept)
        cut = int(change(whole)[-1])
        yield whole.slice(0, cut)
        kept = [whole.slice(cut)]
    if kept:
        yield pa.concat_batches(kept)


def _spans(b: pa.RecordBatch, by: tuple[str, ...]) -> Iterator[pa.RecordBatch]:
    """The groups of a batch of whole groups."""
    ids = [column(b, c).to_numpy() for c in by]
    starts = [0, *(np.flatnonzero(np.any([x[1:] != x[:-1] for x in ids], axis=0)) + 1).tolist()]
    for start, stop in zip(starts, [*starts[1:], b.num_rows]):
        yield b.slice(start, stop - start)


def bucket_pairs(rows: DataFrame, known: DataFrame, percent: int) -> DataFrame:
    """Pairs ``src, dst`` of the same ``token`` and different ``root`` that sizes and sketches leave.

    Sketches go to the buckets, so the pairs of a bucket are written only where they pass.
    For small buckets: many near copies of each other give as many pairs (``bucket_groups``).
    """

    def pairs(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        token, key, n, root = (column(b, c).to_numpy() for c in ("token", "key", "n", "root"))
        bins = column(b, "bins").to_pylist()
        starts = np.flatnonzero(np.r_[True, token[1:] != token[:-1]])
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def passed() -> Iterator[pa.RecordBatch]:
            one, other = (np.concatenate(x) for x in zip(*held))
            held.clear()
            for k in range(0, len(one), PAIR_SLICE):
                i, j = one[k : k + PAIR_SLICE], other[k : k + PAIR_SLICE]
                near = _close(n[i], n[j], [bins[x] for x in i.tolist()], [bins[x] for x in j.tolist()], percent)
                i, j = key[i[near]], key[j[near]]
                yield pa.RecordBatch.from_pydict({"src": pa.array(np.minimum(i, j)), "dst": pa.array(np.maximum(i, j))})

        for start, stop in zip(starts.tolist(), [*starts[1:].tolist(), len(token)]):
            m, r = n[start:stop], root[start:stop]
            fits = (np.minimum(m[:, None], m) * 100 >= np.maximum(m[:, None], m) * percent) & (r[:, None] != r)
            i, j = np.nonzero(np.triu(fits, 1))
            held.append((i + start, j + start))
            if sum(len(x[0]) for x in held) > PAIR_SLICE:
                yield from passed()
        if held:
            yield from passed()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _whole(batches, ("token",)):
            yield from pairs(b)

    facts = known.select("key", "bins").dropDuplicates(["key"])
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = rows.select("token", "key", "n", "root").join(facts, "key").repartition(tasks, "token").sortWithinPartitions("token")
    return met.select("token", "key", "n", "root", "bins").mapInArrow(run, "src long, dst long")


def _near(n: np.ndarray, root: np.ndarray, block: np.ndarray, bins: list[bytes], percent: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of a group's rows, sorted by ``n``, of different roots that sizes and sketches leave.

    Each pair comes once, with the shorter sketch first.  A group of two blocks gives those
    between the blocks only.
    """
    width = np.array([len(x) for x in bins], np.int64)
    crossed = bool((block != block[0]).any())
    cuts = np.unique(np.r_[np.arange(0, len(n), ROW_SLICE), np.flatnonzero(np.diff(width)) + 1, len(n)])
    for start, stop in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
        end = int(np.searchsorted(n * percent, int(n[stop - 1]) * 100, side="right"))
        mine = _folded(bins[start:stop], int(width[start]))
        turns = np.unique(np.r_[start, np.flatnonzero(np.diff(width[start:end])) + 1 + start, end])
        theirs = np.concatenate([_folded(bins[a:b], int(width[start])) for a, b in zip(turns[:-1].tolist(), turns[1:].tolist())])
        apart = np.zeros((stop - start, end - start), np.int32)
        for k in range(mine.shape[1]):
            apart += np.bitwise_count(mine[:, k, None] ^ theirs[None, :, k])
        m, all_n = n[start:stop, None], n[None, start:end]
        fits = (apart * np.int64(100 + percent) <= (m + all_n) * (100 - percent)) & (m * 100 >= all_n * percent)
        fits &= root[start:stop, None] != root[None, start:end]
        if crossed:
            fits &= block[start:stop, None] != block[None, start:end]
        i, j = np.nonzero(np.triu(fits, 1))
        if len(i):
            yield i + start, j + start


def _in_blocks(rows: DataFrame, by: str, blocks: Column) -> DataFrame:
    """Rows in order of the groups ``by, cell`` of tasks: of several blocks, each with each other and itself."""
    many = rows.withColumn("_many", blocks.cast("long"))
    many = many.withColumn("block", F.pmod(F.xxhash64("key", F.lit(41)), "_many"))
    lo, hi = F.least("block", "_other"), F.greatest("block", "_other")
    dealt = many.withColumn("_other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_many") - 1))).withColumn("cell", lo * F.col("_many") + hi)
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return dealt.drop("_many", "_other").repartition(tasks, by, "cell").sortWithinPartitions(by, "cell", "n")


def bucket_groups(rows: DataFrame, known: DataFrame, percent: int) -> DataFrame:
    """Edges ``src, dst`` that join all pairs of ``bucket_pairs``, fewer in a bucket than its keys.

    An edge's ends need not be a pair themselves; every key of a pair is in an edge.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in _whole(batches, ("token", "cell")):
            src, dst = [], []
            for b in _spans(whole, ("token", "cell")):
                key, n, root, block = (column(b, c).to_numpy() for c in ("key", "n", "root", "block"))
                label = np.arange(len(key))
                for i, j in _near(n, root, block, column(b, "bins").to_pylist(), percent):
                    join_labels(label, i, j)
                moved = np.flatnonzero(label != np.arange(len(key)))
                src.append(key[label[moved]])
                dst.append(key[moved])
            yield pa.RecordBatch.from_pydict({"src": pa.array(np.concatenate(src)), "dst": pa.array(np.concatenate(dst))})

    facts = known.select("key", "bins").dropDuplicates(["key"])
    met = _in_blocks(rows.select("token", "key", "n", "root", "held").join(facts, "key"), "token", F.ceil(F.col("held") / BLOCK_KEYS))
    return met.select("token", "cell", "block", "key", "n", "root", "bins").mapInArrow(run, "src long, dst long")


def _joined(n: np.ndarray, root: np.ndarray, block: np.ndarray, sets: list[np.ndarray], percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows ``a, b`` of a group, sorted by ``n``, whose edges join the roots that true links join."""
    sizes = np.array([len(s) for s in sets], np.int64)
    starts = np.cumsum(sizes) - sizes
    shingles, flat = np.unique(np.concatenate(sets), return_inverse=True)
    _, first, at = np.unique(root, return_index=True, return_inverse=True)
    own = first[at]
    label, mark = own.copy(), np.zeros(len(shingles), bool)
    for rows, others in _near(n, root, block, [sketch(s) for s in sets], percent):
        edges = [0, *(np.flatnonzero(np.diff(rows)) + 1).tolist(), len(rows)]
        for lo, hi in zip(edges[:-1], edges[1:]):
            i, j = int(rows[lo]), others[lo:hi]
            j = j[label[own[j]] != label[own[i]]]
            if not len(j):
                continue
            mine = flat[starts[i] : starts[i] + sizes[i]]
            mark[mine] = True
            ends = np.cumsum(sizes[j])
            both = np.add.reduceat(mark[flat[np.repeat(starts[j] - ends + sizes[j], sizes[j]) + np.arange(ends[-1])]].astype(np.int64), ends - sizes[j])
            mark[mine] = False
            j = j[both * (100 + percent) >= percent * (sizes[i] + sizes[j])]
            join_labels(label, np.full(len(j), own[i]), own[j])
    moved = np.flatnonzero((label[own] != own) & (own == np.arange(len(own))))
    return label[moved], moved


def group_links(docs: DataFrame, known: DataFrame, rooted: DataFrame, likely: DataFrame, width: int, percent: int) -> DataFrame:
    """Edges ``src, dst`` that join what true links within the groups of ``likely`` join.

    ``likely`` are edges whose components hold all pairs in question; ``rooted`` has the
    ``root`` of each ``key`` in what is joined already.  A set goes to its group's task, or
    to as many as the group has blocks; edges are fewer than the roots they join.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in _whole(batches, ("grp", "cell")):
            src, dst = [], []
            for b in _spans(whole, ("grp", "cell")):
                key, n, root, block = (column(b, c).to_numpy() for c in ("key", "n", "root", "block"))
                sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in column(b, "shingles")]
                one, other = _joined(n, root, block, sets, percent)
                src.append(key[one])
                dst.append(key[other])
            yield pa.RecordBatch.from_pydict({"src": pa.array(np.concatenate(src)), "dst": pa.array(np.concatenate(dst))})

    groups = star_components(likely).select(F.col("node").alias("key"), F.col("root").alias("grp"))
    sizes = known.select("key", "n", "doc_id").join(groups, "key").groupBy("key", "grp").agg(F.min("n").alias("n"), F.min("doc_id").alias("doc_id"))
    held = stage(sizes.join(rooted, "key"), "ids")
    blocks = held.groupBy("grp").agg(F.ceil(F.greatest(F.count("*") / BLOCK_KEYS, F.sum("n") / BLOCK_SHINGLES)).alias("blocks"))
    sets = stage(_sets(with_ids(docs, held), width).join(held.select("key"), "key", "left_semi").dropDuplicates(["key"]), "sets")
    met = _in_blocks(held.drop("doc_id").join(blocks, "grp").join(sets, "key"), "grp", F.col("blocks"))
    found = stage(met.select("grp", "cell", "block", "key", "n", "root", "shingles").mapInArrow(run, "src long, dst long"), "true")
    release(held, sets)
    return found


def _pairs_where(test: Callable[[pa.RecordBatch], np.ndarray]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield b.select(["src", "dst"]).filter(pa.array(test(b)))

    return run


def true_links(docs: DataFrame, known: DataFrame, pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """Those of the pairs ``src, dst`` whose whole sets reach the bound."""

    def close(b: pa.RecordBatch) -> np.ndarray:
        return _close(*(column(b, c).to_numpy() for c in ("n_a", "n_b")), *(column(b, c).to_pylist() for c in ("bins_a", "bins_b")), percent)

    def overlap(b: pa.RecordBatch) -> np.ndarray:
        out = np.zeros(b.num_rows, bool)
        for i, (x, y) in enumerate(zip(column(b, "set_a").to_pylist(), column(b, "set_b").to_pylist())):
            x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
            both = len(x) + len(y) - len(np.union1d(x, y))
            out[i] = both * (100 + percent) >= percent * (len(x) + len(y))
        return out

    facts = known.select("key", "n", "bins").dropDuplicates(["key"])
    sides = [facts.select(F.col("key").alias(k), F.col("n").alias(f"n_{s}"), F.col("bins").alias(f"bins_{s}")) for k, s in (("src", "a"), ("dst", "b"))]
    likely = stage(pairs.join(sides[0], "src").join(sides[1], "dst").mapInArrow(_pairs_where(close), "src long, dst long"), "likely")
    wanted = likely.select(F.explode(F.array("src", "dst")).alias("key")).distinct()
    ids = stage(known.join(wanted, "key", "left_semi").groupBy("key").agg(F.min("doc_id").alias("doc_id")), "ids")
    sets = stage(_sets(with_ids(docs, ids), width).join(ids.select("key"), "key", "left_semi").dropDuplicates(["key"]), "sets")
    sides = [sets.select(F.col("key").alias(k), F.col("shingles").alias(s)) for k, s in (("src", "set_a"), ("dst", "set_b"))]
    found = stage(likely.join(sides[0], "src").join(sides[1], "dst").mapInArrow(_pairs_where(overlap), "src long, dst long"), "true")
    release(likely, ids, sets)
    return found


def similar_texts(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT, first: Callable[[DataFrame], DataFrame] | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """Documents in one component when a chain of pairs of that overlap joins them.

    Needs ``doc_id, text``.  Texts without words are equal; shingles and sets are compared
    by 64-bit hashes; repeated rows stay repeated, and a null id comes after all others.
    ``first`` may name likely pairs ``src, dst`` of the keys of ``described``, which are
    checked before the buckets are and leave them less to do.  Returns ``doc_id,
    component_id`` (the least id), what ``carry`` names, and ``kept``: the first row of each
    component by id, set and carried columns; rows alike in these are all first.
    """
    known = stage(described(docs, width, percent, carry), "known")
    links = None
    if first is not None:
        pairs = stage(first(known), "pair")
        links = true_links(docs, known, pairs, width, percent)
        release(pairs)
    tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = known.select(F.explode("first").alias("token"), "key", "n").repartition(tasks, "token").sortWithinPartitions("token", "key")
    buckets = stage(dealt.mapInArrow(_shared, "token long, key long, n long"), "shared")
    near_size = (F.least("n", "m") * 100 >= F.greatest("n", "m") * percent) & (F.col("root") != F.col("other_root"))
    pair = [F.least("key", "other").alias("src"), F.greatest("key", "other").alias("dst")]

    def small(rows: DataFrame) -> DataFrame:
        return bucket_pairs(rows.where(F.col("held") <= PAIR_BUCKET), known, percent)

    def large(rows: DataFrame) -> DataFrame:
        return bucket_groups(rows.where(F.col("held") > PAIR_BUCKET), known, percent)

    def partners(rows: DataFrame) -> DataFrame:
        return rows.select("token", F.col("key").alias("other"), F.col("n").alias("m"), F.col("root").alias("other_root"))

    def apart(rows: DataFrame) -> DataFrame:
        """Rows with their roots, of the buckets that the links found do not join as a whole."""
        rooted = rows.withColumn("root", F.col("key"))
        if links is not None:
            rooted = rows.join(star_components(links).withColumnRenamed("node", "key"), "key", "left").withColumn("root", F.coalesce("root", "key"))
        over = rooted.groupBy("token").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count("*").alias("held")).where("lo <> hi")
        return stage(rooted.join(over.select("token", "held"), "token"), "open")

    for turn in range(ROUNDS + 1):
        open_rows = apart(buckets)
        if open_rows.isEmpty():
            break
        if turn < ROUNDS:  # everything meets one leader of its bucket
            lot = F.xxhash64("other", F.lit(turn))
            leaders = partners(open_rows).groupBy("token").agg(F.min(F.struct(lot.alias("lot"), "other", "m", "other_root")).alias("top")).select("token", "top.other", "top.m", "top.other_root")
            pairs = stage(open_rows.join(leaders, "token").where(near_size).select(*pair).distinct(), "pair")
            found = true_links(docs, known, pairs, width, percent)
        else:  # and what is still apart meets in pairs
            met = open_rows.where(F.col("held") <= TASK_BUCKET)
            pairs = small(met).unionByName(large(met))
            crowd = stage(open_rows.where(F.col("held") > TASK_BUCKET).select("key").distinct(), "crowd")
            if not crowd.isEmpty():
                rare = apart(stage(rare_buckets(docs, known, crowd, width, percent), "rare"))
                pairs = pairs.unionByName(small(rare)).unionByName(large(rare))
            pairs = stage(pairs.distinct(), "pair")
            found = group_links(docs, known, open_rows.select("key", "root").distinct(), pairs, width, percent)
        links = found if links is None else stage(links.unionByName(found), "links")
        release(pairs, open_rows)
    release(buckets)
    roots = star_components(links).withColumnRenamed("node", "key") if links is not None else None
    rows = known.select("doc_id", "key", *carry)
    rows = rows.withColumn("root", F.col("key")) if roots is None else rows.join(roots, "key", "left").withColumn("root", F.coalesce("root", "key"))
    rows = rows.withColumn("order", F.struct(F.col("doc_id").isNull().alias("late"), "doc_id", "key", *carry))
    least = rows.groupBy("root").agg(F.min("order").alias("least"))
    return rows.join(least, "root").select("doc_id", F.col("least.doc_id").alias("component_id"), *carry, F.col("order").eqNullSafe(F.col("least")).alias("kept"))
