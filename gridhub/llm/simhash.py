"""SimHash near-dedup by anchor points of a covering code.

Two blocks of 23 bits of a fingerprint are covered by the perfect binary Golay code, whose
covering radius is 3; the other 18 bits need no anchor.  A fingerprint lives at the pair of
code words nearest to its blocks.  It is replicated to each pair of code words that lies,
block by block, within the covering radius plus a share of the threshold, the shares adding
up to the threshold at most; these are the homes of everything within the threshold.  All
fingerprints at one anchor are compared there, and each anchor reports a spanning forest of
its links, so no group of near copies is written out as pairs.

An anchor with many homes is split by the 18 bits that need no anchor: each of its
fingerprints goes to the parts named by those bits and by each change of one of them.  Two
fingerprints that differ there in two bits at most meet in a part, and no task holds a
whole crowded anchor.  Visitors of an anchor are compared with its homes block by block, so
a worker holds some numbers a member, whatever their number.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations, product

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridhub.llm.arrow import column, filled, text_slices
from gridhub.llm.joins import BROADCAST_IDS, join_hot_apart
from gridhub.llm.overlap import PERCENT, WIDTH, similar_texts
from gridhub.operators.components import star_components
from gridhub.plans.staging import stage

#: Generator polynomial of the (23, 12) Golay code and its covering radius.
GOLAY_POLY, GOLAY_BITS, GOLAY_RADIUS = 0b101011100011, 23, 3
THRESHOLD = 2
#: Homes from which on an anchor is split, and the bits it is split by.
HOT_HOMES = 4096
FREE_BITS = 64 - 2 * GOLAY_BITS


def fingerprint(text: str, width: int = 3, seed: int = 42) -> int:
    """64-bit SimHash of a whole text over its word shingles, repeats included."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    line = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]).tolist()
    n = max(1, len(words) - width + 1)
    starts = [0, *ends[: n - 1]]
    stops = ends[width - 1 :] if len(words) >= width else ends[-1:]
    digest, total, step = xxhash.xxh64_intdigest, np.zeros(64, np.int64), 1 << 18
    for i in range(0, n, step):
        h = np.array([digest(line[a : b - 1], seed) for a, b in zip(starts[i : i + step], stops[i : i + step])], np.uint64)
        total += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * total > n, bitorder="little").view(np.uint64)[0])


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in text_slices(batches):
        prints = np.array([fingerprint(t) for t in filled(part).to_pylist()], np.uint64)
        yield pa.RecordBatch.from_pydict({"doc_id": column(part, "doc_id"), "fp": pa.array(prints.view(np.int64))})


def document_fingerprints(docs: DataFrame) -> DataFrame:
    """``doc_id, fp`` with the fingerprint as a signed long; null text counts as empty."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_fingerprints, "doc_id long, fp long")


def _syndrome(words: np.ndarray) -> np.ndarray:
    """Remainder of each 23-bit word by the generator polynomial."""
    rest = words.copy()
    for bit in range(GOLAY_BITS - 1, 10, -1):
        rest = np.where(rest >> bit & 1, rest ^ (GOLAY_POLY << (bit - 11)), rest)
    return rest


@lru_cache(1)
def _coset_tables() -> tuple[list[np.ndarray], list[np.ndarray]]:
    """For excess 0, 1, 2: error patterns of that weight beyond the radius, by syndrome.

    Excess 0 is the one pattern of weight 3 or less, the way to the home code word.
    Returns flat patterns sorted by syndrome, and the offsets of each syndrome.
    """
    by_weight = [np.array([sum(1 << i for i in c) for c in combinations(range(GOLAY_BITS), w)], np.int64) for w in range(GOLAY_RADIUS + THRESHOLD + 1)]
    groups = [np.concatenate(by_weight[: GOLAY_RADIUS + 1]), *by_weight[GOLAY_RADIUS + 1 :]]
    flat, offsets = [], []
    for g in groups:
        s = _syndrome(g)
        order = np.argsort(s, kind="stable")
        flat.append(g[order])
        offsets.append(np.r_[0, np.cumsum(np.bincount(s, minlength=2048))])
    return flat, offsets


def anchors_of(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(index of the fingerprint, anchor, whether it is the home) for uint64 fingerprints."""
    flat, offsets = _coset_tables()
    low = (prints & np.uint64(0x7FFFFF)).astype(np.int64)
    high = (prints >> np.uint64(23) & np.uint64(0x7FFFFF)).astype(np.int64)
    s_low, s_high = _syndrome(low), _syndrome(high)
    own, out, home = [], [], []
    for i in range(THRESHOLD + 1):
        for j in range(THRESHOLD + 1 - i):
            many_l = offsets[i][s_low + 1] - offsets[i][s_low]
            many_h = offsets[j][s_high + 1] - offsets[j][s_high]
            many = many_l * many_h
            idx = np.repeat(np.arange(len(prints)), many)
            nth = np.arange(len(idx)) - np.repeat(np.cumsum(many) - many, many)
            a = low[idx] ^ flat[i][offsets[i][s_low[idx]] + nth // many_h[idx]]
            b = high[idx] ^ flat[j][offsets[j][s_high[idx]] + nth % many_h[idx]]
            own.append(idx)
            out.append(a >> 11 | (b >> 11) << 12)  # a code word is known by its top 12 bits
            home.append(np.full(len(idx), i + j == 0))
    return np.concatenate(own), np.concatenate(out), np.concatenate(home)


def _replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        prints = column(batch, "fp").to_numpy()
        for i in range(0, len(prints), 20_000):
            part = prints[i : i + 20_000]
            own, anchor, home = anchors_of(part.view(np.uint64))
            yield pa.RecordBatch.from_pydict({"anchor": pa.array(anchor.astype(np.int32)), "fp": pa.array(part[own]), "home": pa.array(home)})


def _home_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    flat, offsets = _coset_tables()
    for batch in batches:
        bits = column(batch, "fp").to_numpy().view(np.uint64)
        words = [(bits >> np.uint64(s) & np.uint64(0x7FFFFF)).astype(np.int64) for s in (0, GOLAY_BITS)]
        low, high = (w ^ flat[0][offsets[0][_syndrome(w)]] for w in words)
        anchor, many = np.unique(low >> 11 | (high >> 11) << 12, return_counts=True)
        yield pa.RecordBatch.from_pydict({"anchor": pa.array(anchor.astype(np.int32)), "n": pa.array(many.astype(np.int64))})


def _forest(homes: np.ndarray, guests: np.ndarray, block: int = 512, width: int = 8192) -> list[tuple[np.ndarray, np.ndarray]]:
    """Edges that span the links between the homes of an anchor and all that visit it.

    However many visit, what is held is some numbers a member and one block of distances.
    """
    members = np.unique(np.concatenate([homes, guests]))
    label = np.arange(len(members))
    place = np.searchsorted(members, homes)
    bits = members.view(np.uint64)
    edges = []
    for i, left in product(range(0, len(place), block), range(0, len(members), width)):
        near = np.bitwise_count(bits[place[i : i + block], None] ^ bits[None, left : left + width]) <= THRESHOLD
        rows, cols = np.nonzero(near)
        mine, cols = place[i : i + block][rows], cols + left
        other = mine != cols
        mine, cols = mine[other], cols[other]
        while len(mine):  # hook the larger label to the smaller, then shorten
            a, b = label[mine], label[cols]
            apart = a != b
            if not apart.any():
                break
            mine, cols, a, b = mine[apart], cols[apart], a[apart], b[apart]
            np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
            while True:
                up = label[label]
                if (up == label).all():
                    break
                label = up
    moved = np.flatnonzero(label != np.arange(len(members)))
    if len(moved):
        edges.append((members[label[moved]], members[moved]))
    return edges


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by anchor; a group that a batch cuts is carried into the next."""
    kept: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    empty = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool))

    def links(anchor: np.ndarray, fp: np.ndarray, home: np.ndarray) -> Iterator[pa.RecordBatch]:
        starts = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]]) if len(anchor) else np.zeros(0, np.int64)
        stops = np.r_[starts[1:], len(anchor)].astype(np.int64)
        homes = np.add.reduceat(home.astype(np.int64), starts) if len(starts) else starts
        small, sides = (homes == 1) & (stops - starts > 1), []
        if small.any():  # one home: compare all of these anchors at once
            size = (stops - starts)[small]
            at = np.repeat(starts[small], size) + np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            own = np.repeat(np.add.reduceat(np.where(home[at], fp[at], 0), np.cumsum(size) - size), size)
            near = (np.bitwise_count(own.view(np.uint64) ^ fp[at].view(np.uint64)) <= THRESHOLD) & (own != fp[at])
            sides.append((own[near], fp[at][near]))
        for g in np.flatnonzero((homes > 1) & (stops - starts > 1)):
            part = slice(starts[g], stops[g])
            sides += _forest(fp[part][home[part]], fp[part])
        if sides:
            a, b = (np.concatenate(x) for x in zip(*sides))
            if len(a):
                yield pa.RecordBatch.from_pydict({"src": pa.array(a), "dst": pa.array(b)})

    for batch in batches:
        kept.append(tuple(column(batch, c).to_numpy(zero_copy_only=False) for c in ("part", "fp", "home")))
        if kept[0][0][0] == kept[-1][0][-1]:
            continue
        whole = [np.concatenate(x) for x in zip(*kept)]
        cut = int(np.searchsorted(whole[0], whole[0][-1]))
        yield from links(*(x[:cut] for x in whole))
        kept = [tuple(x[cut:] for x in whole)]
    yield from links(*([np.concatenate(x) for x in zip(*kept)] if kept else empty))


def fingerprint_links(distinct: DataFrame) -> DataFrame:
    """Edges ``src, dst`` that connect all distinct ``fp`` within the threshold."""
    spread = distinct.select("fp").mapInArrow(_replicate, "anchor int, fp long, home boolean")
    counted = distinct.select("fp").mapInArrow(_home_counts, "anchor int, n long").groupBy("anchor").agg(F.sum("n").alias("n"))
    hot = stage(counted.where(F.col("n") > HOT_HOMES).select("anchor", F.lit(True).alias("hot")), "hot")
    place = F.col("anchor").cast("long") * (1 << (FREE_BITS + 1))
    many = hot.count()
    if many:
        free = F.shiftrightunsigned("fp", 2 * GOLAY_BITS)
        parts = F.array(free + 1, *[free.bitwiseXOR(F.lit(1 << i).cast("long")) + 1 for i in range(FREE_BITS)])
        spread = spread.join(F.broadcast(hot) if many <= BROADCAST_IDS else hot, "anchor", "left")
        spread = spread.withColumn("_p", F.explode(F.when(F.col("hot"), parts).otherwise(F.array(F.lit(0).cast("long")))))
        place = F.col("anchor").cast("long") * (1 << (FREE_BITS + 1)) + F.col("_p")
    keyed = spread.select(place.alias("part"), "fp", "home")
    tasks = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return keyed.repartition(tasks, "part").sortWithinPartitions("part").mapInArrow(_compare, "src long, dst long").distinct()


def near_duplicates(docs: DataFrame) -> DataFrame:
    """Documents in one component when a chain of links joins their fingerprints.

    Needs ``doc_id, text``.  Null and empty texts have fingerprint zero and link like any
    other; equal fingerprints always link; repeated rows stay repeated; a null id takes no
    part in the choice of the least id.  Returns ``doc_id, fp, component_id``.
    """
    prints = stage(document_fingerprints(docs), "fp")
    groups = stage(prints.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("rows")), "fpd")
    roots = star_components(stage(fingerprint_links(groups), "link"))
    labelled = groups.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    named = labelled.groupBy("root").agg(F.min("least").alias("component_id"))
    by_print = stage(labelled.join(named, "root").select("fp", "component_id", "rows"), "named")
    return join_hot_apart(prints, by_print, ["fp"], "rows").select("doc_id", "fp", "component_id")


def anchor_pairs(known: DataFrame) -> DataFrame:
    """Pairs of keys whose fingerprints are equal or linked at an anchor; spans, not all pairs."""
    prints = stage(known.groupBy("fp").agg(F.min("key").alias("lead")), "fpd")
    same = known.select("key", "fp").distinct().join(prints, "fp").where("key <> lead").select(F.col("lead").alias("src"), F.col("key").alias("dst"))
    ends = prints.select(F.col("fp").alias("src"), F.col("lead").alias("a")), prints.select(F.col("fp").alias("dst"), F.col("lead").alias("b"))
    near = fingerprint_links(prints).join(ends[0], "src").join(ends[1], "dst")
    return same.unionByName(near.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))).distinct()


def similar_documents(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT, carry: tuple[str, ...] = ()) -> DataFrame:
    """Components of documents whose shingle sets overlap by ``percent`` (Jaccard index), exactly.

    The anchors bring together what differs in THRESHOLD bits at most, and whole sets
    confirm it.  Sets that overlap by 80 % differ in some ten of 64 bits, more than any
    covering radius that still parts a corpus, so the other pairs come by buckets of
    shared shingles (``overlap``).  See ``similar_texts`` for rows and edge cases.
    """
    return similar_texts(docs, width, percent, anchor_pairs, carry)


def op2_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate components of all ``documents``."""
    found = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
