"""Exact token ids and exact token counts at every prefix of a text.

White space never takes part in a token of the word vocabulary and parts everything that
the normaliser and the pre-tokeniser look at, so the ids of a text are the ids of its
chunks, one after the other.  Each distinct chunk goes through the tokenizer library once
and is kept in a bounded memo.

For prefixes, ``count[i] = count[start of the open chunk] + tokens(open chunk up to i)``.
The second term is memoised over all chunk prefixes, which distinct chunks share like the
branches of a trie.  A long chunk is read character by character as the pre-tokeniser
would, and every open run goes through a second dynamic program over byte-pair tokens: the
encoding of a prefix ends in the one token that its predecessor's encoding accepts.  What
normalisation changes is settled inside the few characters that it joins, so one odd
character costs nothing elsewhere.
"""

from __future__ import annotations

import json
import os
import re
import struct
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridhub.llm.arrow import column, filled, text_slices, word_lists

#: Entries in one generation of a worker's memo.
MEMO = 300_000
#: Chunks that go through the library as one text.
JOINED = 20_000
#: Chunks up to this many code points take all prefixes from the library.
SHORT = 48
#: Longest chunk that a memo keeps, so that its bytes are bounded too.
KEPT = 1024


def word_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


@lru_cache(4)
def _library(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def _encode(path: str, texts: list[str]) -> list[list[int]]:
    return [e.ids for e in _library(path).encode_batch_fast(texts, add_special_tokens=False)]


def _strings(array: pa.Array) -> list[str]:
    return array.to_numpy(zero_copy_only=False).tolist()


def _encode_chunks(path: str, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(ids, number of the chunk each belongs to) for chunks without white space.

    Many chunks go through the library as one text; the offsets say whose an id is.
    """
    ids, owners = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for i in range(0, len(chunks), JOINED):
        some = chunks[i : i + JOINED]
        coded = _library(path).encode(" ".join(some), add_special_tokens=False)
        ends = np.cumsum(np.fromiter(map(len, some), np.int64, len(some)) + 1)
        starts = np.fromiter((o[0] for o in coded.offsets), np.int64, len(coded.ids))
        ids.append(np.array(coded.ids, np.int64))
        owners.append(i + np.searchsorted(ends, starts, side="right"))
    return np.concatenate(ids), np.concatenate(owners)


def _count_chunks(path: str, chunks: list[str]) -> np.ndarray:
    """Tokens of each chunk.

    A run of letters is one pre-token, so for those the library's word numbers say whose a
    token is, which is cheaper than its offsets; should a letter fall apart in the
    normaliser, the numbers don't add up and the offsets are asked.
    """
    letters = [c.isalpha() for c in chunks]
    out = np.zeros(len(chunks), np.int64)
    for wanted in (True, False):
        at = [i for i, x in enumerate(letters) if x is wanted]
        for k in range(0, len(at), JOINED):
            some = at[k : k + JOINED]
            texts = [chunks[i] for i in some]
            if wanted:
                words = np.array(_library(path).encode(" ".join(texts), add_special_tokens=False).word_ids, np.int64)
                if words[-1] + 1 == len(texts):
                    out[some] = np.bincount(words, minlength=len(texts))
                    continue
            out[some] = np.bincount(_encode_chunks(path, texts)[1], minlength=len(texts))
    return out


def _normal_chunks(unique: pa.Array) -> tuple[list[str], list[str]]:
    """Chunks as body and closing punctuation, fit for the memo.

    A cut between a letter or digit and ``.,;:!?`` is one of the pre-tokeniser's own, and
    the normaliser lower-cases, so both may be done before looking a chunk up.  The letters
    are those whose lower case is one letter: U+0130 ends in a mark, which the following
    punctuation joins.  Chunks that could hold a special string stay as they are.
    """
    body = pc.ascii_rtrim(unique, ".,;:!?")
    safe = pc.and_(pc.match_substring_regex(body, "[A-Za-z0-9À-ÖØ-öø-įı-ſ]$"), pc.invert(pc.match_substring(unique, "<|")))
    kept = pc.if_else(safe, body, unique)
    tails = [w[n:] for w, n in zip(_strings(unique), pc.utf8_length(kept).to_numpy(zero_copy_only=False).tolist())]
    return _strings(pc.if_else(safe, pc.ascii_lower(kept), kept)), tails


class _Memo:
    """A bounded dict in two generations: what was used since the last turn survives it."""

    def __init__(self, make, limit: int = MEMO):
        self.make, self.limit, self.young, self.old = make, limit, {}, {}

    def get(self, keys: list[str]) -> list:
        if len(self.young) + len(keys) > self.limit:
            self.young, self.old = {}, self.young
        young, old = self.young, self.old
        lacking = [k for k in keys if k not in young]
        if lacking:
            if old:
                young.update((k, old[k]) for k in lacking if k in old)
                lacking = [k for k in lacking if k not in young]
            lacking = list(dict.fromkeys(lacking))
            young.update(zip(lacking, self.make(lacking)))
        found = [young[k] for k in keys]
        for k in lacking:
            if len(k) > KEPT:
                del young[k]
        return found


@lru_cache(4)
def _id_memo(path: str) -> _Memo:
    def make(chunks: list[str]) -> list[bytes]:
        ids, owners = _encode_chunks(path, chunks)
        data, ends = ids.astype("<u4").tobytes(), (4 * np.searchsorted(owners, np.arange(len(chunks) + 1))).tolist()
        return [data[a:b] for a, b in zip(ends, ends[1:])]

    return _Memo(make, 2 * MEMO)


def slice_ids(texts: pa.Array, path: str) -> tuple[np.ndarray, np.ndarray]:
    """(token offsets per text, all ids as uint32) for an array of non-null texts."""
    bounds, words = word_lists(texts)
    coded = words.dictionary_encode()
    bodies, tails = _normal_chunks(coded.dictionary)
    memo = _id_memo(path)
    marks = sorted(set(tails) - {""})
    closing = dict(zip(marks, memo.get(marks))) | {"": b""}
    known = [b + closing[t] for b, t in zip(memo.get(bodies), tails)]
    sizes = np.fromiter(map(len, known), np.int64, len(known)) // 4
    flat = np.frombuffer(b"".join(known), "<u4")
    starts = np.cumsum(sizes) - sizes
    which = coded.indices.to_numpy(zero_copy_only=False)
    many = sizes[which]
    ends = np.r_[0, np.cumsum(many)]
    at = np.repeat((starts[which] - ends[:-1]).astype(np.int32), many)  # a slice is far below 2^31
    at += np.arange(len(at), dtype=np.int32)
    return ends[bounds], flat[at]


class PairMerger:
    """Byte-pair merges of the word vocabulary, and which token may follow which."""

    def __init__(self, path: str):
        model = json.load(open(path))["model"]
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        extra = [b for b in range(256) if b not in plain]
        to_byte = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(extra)}
        self.end = model["end_of_word_suffix"]
        read = lambda t: (bytes(to_byte[c] for c in t.removesuffix(self.end)), t.endswith(self.end))
        self.rank = {}
        for i, m in enumerate(model["merges"]):
            a, b = m.split(" ") if isinstance(m, str) else m
            self.rank.setdefault((read(a), read(b)), i)
        self.vocab = {read(t) for t in model["vocab"] if all(c in to_byte for c in t.removesuffix(self.end))}
        self.merge = lru_cache(200_000)(self._merge)
        self.accepts = lru_cache(200_000)(self._accepts)
        self.by_tail: tuple[dict[bytes, list[int]], dict[bytes, list[int]]] = ({}, {})
        for t, ended in sorted(self.vocab, key=lambda v: -len(v[0])):
            if len(t) > 2 and len(t) not in (sizes := self.by_tail[ended].setdefault(t[-3:], [])):
                sizes.append(len(t))

    def _merge(self, data: bytes, ended: bool) -> tuple:
        parts = [(data[i : i + 1], ended and i == len(data) - 1) for i in range(len(data))]
        while len(parts) > 1:
            best = min(range(len(parts) - 1), key=lambda i: self.rank.get((parts[i], parts[i + 1]), 1 << 60))
            if (parts[best], parts[best + 1]) not in self.rank:
                break
            parts[best : best + 2] = [(parts[best][0] + parts[best + 1][0], parts[best + 1][1])]
        return tuple(parts)

    def _accepts(self, left: bytes, right: bytes, ended: bool) -> bool:
        return self.merge(left + right, ended) == ((left, False), (right, ended))


@lru_cache(2)
def _merger(path: str) -> PairMerger:
    return PairMerger(path)


class _Run:
    """Byte-pair encoding of one growing word: last token and token count of every prefix."""

    def __init__(self, merger: PairMerger):
        self.merger, self.data, self.last, self.many = merger, bytearray(), [b""], [0]

    def _final(self, j: int, ended: bool) -> bytes:
        m = self.merger
        for size in (*m.by_tail[ended].get(bytes(self.data[max(0, j - 3) : j]), ()), 2, 1):
            if size <= j:
                t = bytes(self.data[j - size : j])
                if (t, ended) in m.vocab and len(m.merge(t, ended)) == 1 and (size == j or m.accepts(self.last[j - size], t, ended)):
                    return t
        raise ValueError("no token ends this prefix")

    def extend(self, more: bytes) -> None:
        for b in more:
            self.data.append(b)
            t = self._final(len(self.data), False)
            self.last.append(t)
            self.many.append(self.many[len(self.data) - len(t)] + 1)

    def tokens(self) -> int:
        """Tokens of all bytes so far as a word that ends here."""
        return self.many[len(self.data) - len(self._final(len(self.data), True))] + 1 if self.data else 0

    def cut(self, size: int) -> None:
        del self.data[size:], self.last[size + 1 :], self.many[size + 1 :]


#: Fixed value: suffixes that the word vocabulary's pre-tokeniser cuts off as one piece.
CLITICS = ("'s", "'t", "'re", "'ve", "'m", "'ll", "'d")


class _Scanner:
    """Reads normalised characters and knows the token count of all that was read.

    The open pre-token is a run of letters or of other signs; a digit is a run of its own.
    ``clitic`` holds an apostrophe that began a pre-token and the letter after it, with the
    count before both, until it is clear whether they are one of the clitics.
    """

    def __init__(self, path: str):
        self.path, self.merger = path, _merger(path)
        self.before, self.kind, self.run, self.clitic = 0, "", None, None

    def mark(self) -> tuple:
        return self.before, self.kind, self.run, len(self.run.data) if self.run else 0, self.clitic

    def back(self, mark: tuple) -> None:
        self.before, self.kind, self.run, size, self.clitic = mark
        if self.run:
            self.run.cut(size)

    def count(self) -> int:
        return self.before + (self.run.tokens() if self.run else 0)

    def read(self, c: str) -> None:
        clitic, self.clitic = self.clitic, None
        if clitic:
            said, before = clitic[0] + c, clitic[1]
            if said in CLITICS:
                whole = _Run(self.merger)
                whole.extend(said.encode())
                self.before, self.kind, self.run = before + whole.tokens(), "", None
                return
            if any(x.startswith(said) for x in CLITICS):
                self.clitic = said, before
        kind = _kind(self.path, c)
        if kind != self.kind or kind == "N":
            self.before = self.count()
            self.kind, self.run = kind, _Run(self.merger) if kind else None
            if c == "'":
                self.clitic = c, self.before
        if kind:
            self.run.extend(c.encode("utf-8", "surrogatepass"))


@lru_cache(50_000)
def _kind(path: str, c: str) -> str:
    """How the pre-tokeniser takes a normalised character: L letter, N number, O other, or white space."""
    cut = _library(path).pre_tokenizer.pre_tokenize_str
    if not cut(c):
        return ""
    return "L" if len(cut("a" + c)) == 1 else "O" if len(cut("!" + c)) == 1 else "N"


@lru_cache(50_000)
def _alone(path: str, piece: str) -> str:
    return _library(path).normalizer.normalize_str(piece)


@lru_cache(1)
def _joining() -> frozenset[str]:
    """Starters that may compose with what comes before them."""
    pairs = (unicodedata.decomposition(chr(c)).split() for c in range(0x110000))
    found = {chr(int(p[1], 16)) for p in pairs if len(p) == 2 and not p[0].startswith("<")}
    return frozenset(found) | {chr(c) for c in (*range(0x1161, 0x1176), *range(0x11A8, 0x11C3))}


@lru_cache(50_000)
def _stands_alone(c: str) -> bool:
    """Whether normalisation never joins or reorders ``c`` with what comes before it."""
    return c < "\u0300" or not (unicodedata.combining(c) or c in _joining() or unicodedata.category(c) == "Cn")


def _plain_counts(text: str, path: str) -> list[int]:
    """Token counts of ``text[:i]`` for i = 1 .. len(text); special strings are plain text."""
    scanner, out, a = _Scanner(path), [], 0
    while a < len(text):
        b = a + 1
        while b < len(text) and not _stands_alone(text[b]):
            b += 1
        whole = _alone(path, text[a:b])
        start, read = scanner.mark(), ""
        for n in range(a + 1, b):  # prefixes that end inside what normalisation joins
            part = _alone(path, text[a:n])
            if not part.startswith(read):
                scanner.back(start)
                read = ""
            for c in part[len(read) :]:
                scanner.read(c)
            read = part
            out.append(scanner.count())
        if not whole.startswith(read):
            scanner.back(start)
            read = ""
        for c in whole[len(read) :]:
            scanner.read(c)
        out.append(scanner.count())
        a = b
    return out


def long_chunk_counts(chunk: str, path: str) -> np.ndarray:
    """Token counts of ``chunk[:i]`` for i = 1 .. len(chunk).

    Time is linear in the chunk, but for the marks on one base character: prefixes that end
    among marks which normalisation reorders are normalised one by one.
    """
    special = [t.content for t in _library(path).get_added_tokens_decoder().values()]
    cuts = re.compile("|".join(map(re.escape, sorted(special, key=len, reverse=True))))
    out, at, before = np.zeros(len(chunk), np.int32), 0, 0
    for m in cuts.finditer(chunk):
        ordinary = _plain_counts(chunk[at : m.end() - 1], path)  # up to one character short of the special string
        out[at : m.end() - 1] = before + np.array(ordinary, np.int32)
        before += (ordinary[m.start() - at - 1] if m.start() > at else 0) + 1
        out[m.end() - 1], at = before, m.end()
    out[at:] = before + np.array(_plain_counts(chunk[at:], path), np.int32)
    return out


class PrefixMemo:
    """Token counts of all prefixes of short chunks, two bytes each, as a bounded trie.

    A chunk walks back to its longest known prefix; only what lies beyond is encoded, and
    a prefix's counts are those of its parent and one more.  Normalising makes at most 18
    bytes, hence tokens, of a code point, so the counts of SHORT of them fit.  Two
    generations, as above.
    """

    def __init__(self, path: str, limit: int = 3 * MEMO):
        self.path, self.limit, self.young, self.old = path, limit, {}, {}

    def get(self, chunks: list[str]) -> list[bytes]:
        if len(self.young) + len(chunks) > self.limit:
            self.young, self.old = {}, self.young
        young, old, lacking = self.young, self.old, {}
        for c in chunks:
            if c in young:
                continue
            head = c
            while head and head not in young and head not in lacking:
                if head in old:
                    young[head] = old[head]
                    break
                lacking[head] = None
                head = head[:-1]
        heads = sorted(lacking, key=len)
        if heads:
            counts = _count_chunks(self.path, heads).astype("<u2").tobytes()
            for i, head in enumerate(heads):
                young[head] = (young[head[:-1]] if len(head) > 1 else b"") + counts[2 * i : 2 * i + 2]
        young[""] = b""
        return [young[c] for c in chunks]


@lru_cache(2)
def _prefix_memo(path: str) -> PrefixMemo:
    return PrefixMemo(path)


@lru_cache(2)
def _long_memo(path: str) -> _Memo:
    return _Memo(lambda chunks: [long_chunk_counts(c, path) for c in chunks], 2_000)


def _chunk_tables(unique: pa.Array, path: str) -> tuple[np.ndarray, np.ndarray]:
    """(code points per distinct chunk, counts of all their prefixes, one after the other)."""
    bodies, tails = _normal_chunks(unique)
    memo = _prefix_memo(path)
    marks = sorted(m for m in set(tails) if 0 < len(m) <= SHORT)
    closing = {m: np.frombuffer(x, "<u2").tolist() for m, x in zip(marks, memo.get(marks))}
    long = [len(b) > SHORT or len(t) > SHORT for b, t in zip(bodies, tails)]
    brief = memo.get(["" if x else b for b, x in zip(bodies, long)] if any(long) else bodies)
    out = []
    for body, tail, known, wide in zip(bodies, tails, brief, long):
        if wide:
            table = _long_memo(path).get([body])[0]
            if tail:
                table = np.concatenate([table, _long_memo(path).get([tail])[0] + table[-1]])
            out.append(table.astype("<i4").tobytes())
        elif tail:
            last = known[-2] + 256 * known[-1]
            more = closing[tail]
            out.append(known + struct.pack(f"<{len(more)}H", *[last + x for x in more]))
        else:
            out.append(known)
    if not any(long):
        flat = np.frombuffer(b"".join(out), "<u2").astype(np.int32)
        return np.fromiter(map(len, out), np.int64, len(out)) // 2, flat
    parts = [np.frombuffer(x, "<i4" if w else "<u2").astype(np.int32) for x, w in zip(out, long)]
    return np.array([len(x) for x in parts], np.int64), np.concatenate(parts)


def slice_prefix_counts(texts: pa.Array, path: str) -> tuple[np.ndarray, np.ndarray]:
    """(code point offsets per text, tokens of the text up to and with each code point)."""
    bounds, words = word_lists(texts)
    coded = words.dictionary_encode()
    sizes, flat = _chunk_tables(coded.dictionary, path)
    starts = np.cumsum(sizes) - sizes
    totals = flat[starts + sizes - 1].astype(np.int64)
    which = coded.indices.to_numpy(zero_copy_only=False)
    many = sizes[which]
    ends = np.cumsum(many)
    at = np.repeat((starts[which] - (ends - many)).astype(np.int32), many)
    at += np.arange(len(at), dtype=np.int32)
    done = np.r_[0, np.cumsum(totals[which])]  # tokens before each chunk of the slice
    open_chunk = flat[at] + np.repeat(done[:-1], many)

    raw = np.frombuffer(b"".join(t.encode("utf-8", "surrogatepass") for t in texts.to_pylist()), np.uint8)
    points = raw[(raw & 0xC0) != 0x80]
    blank = (points == 32) | ((points >= 9) & (points <= 13))
    lengths = pc.utf8_length(texts).to_numpy(zero_copy_only=False).astype(np.int64)
    edges = np.r_[0, np.cumsum(lengths)]
    counts = np.empty(len(points), np.int64)
    counts[~blank] = open_chunk
    first = ~blank & np.r_[True, blank[:-1]] if len(points) else blank
    if len(points):
        first[edges[:-1][lengths > 0]] |= ~blank[edges[:-1][lengths > 0]]
    counts[blank] = done[np.cumsum(first)[blank]]
    counts -= np.repeat(done[bounds[:-1]], lengths)
    return edges, counts


def token_answers(docs: DataFrame, budgets: tuple[int, ...] = (2048,), path: str | None = None, tables: bool = False) -> DataFrame:
    """Exact counts from the prefix table of every whole text.

    Needs ``doc_id, text``; null text counts as empty.  Returns ``doc_id, n_bytes,
    n_tokens``, an array ``fits`` with, for each budget, the longest prefix in code points
    that stays within it, and with ``tables`` the table itself as ``prefix_tokens``: one
    little-endian int32 per code point.  Repeated rows give repeated rows.
    """
    path = path or word_tokenizer()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in text_slices(batches):
            texts = filled(part)
            edges, counts = slice_prefix_counts(texts, path)
            spans = [counts[a:b] for a, b in zip(edges[:-1], edges[1:])]
            total = [int(c[-1]) if len(c) else 0 for c in spans]
            fits = [[len(c) if n <= b else int(np.flatnonzero(c <= b)[-1]) + 1 if (c <= b).any() else 0 for b in budgets] for c, n in zip(spans, total)]
            out = {"doc_id": column(part, "doc_id"), "n_bytes": pc.binary_length(texts).cast(pa.int64()), "n_tokens": pa.array(total, pa.int64()), "fits": pa.array(fits, pa.list_(pa.int64()))}
            if tables:
                out["prefix_tokens"] = pa.array([c.astype("<i4").tobytes() for c in spans], pa.binary())
            yield pa.RecordBatch.from_pydict(out)

    schema = "doc_id long, n_bytes long, n_tokens long, fits array<long>" + ", prefix_tokens binary" * tables
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)


def tokens_of_prefix(table: F.Column, chars: F.Column) -> F.Column:
    """Look up a stored ``prefix_tokens``: tokens of the first ``chars`` code points."""
    piece = lambda i: F.conv(F.hex(F.substr(table, (chars - 1) * 4 + i, F.lit(1))), 16, 10).cast("long")
    return F.when(chars < 1, F.lit(0)).otherwise(piece(1) + piece(2) * 256 + piece(3) * 65536 + piece(4) * 16777216)


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token counts of all ``documents`` and whether they pass 2048."""
    found = token_answers(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > 2048).alias("over_limit"), F.col("fits")[0].alias("fits_2048_chars"))
