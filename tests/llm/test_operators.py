"""The ten operators against brute force, round trips and hand-made edge cases."""

import hashlib
import re
import time
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import regex
import xxhash
from pyspark.sql import functions as F

from gridhub.llm import chat, exact, grams, joins, lmscore, mixing, neighbors, overlap, packing, quality, simhash, tokens, toxicity
from gridhub.llm.arrow import word_lists
from gridhub.plans.staging import stage

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [None, "", " \n\t ", "one", "Two words", "the cat sat on the mat " * 400, "x" * 5000, "日本語 テキスト 　", "it's I'D don't 'stuff'", "a<|endoftext|>b", "́é café İstanbul", "nul\x00byte \x1c \x85"]


def frame(spark, texts, ids=None, extra=False):
    rows = [(i, t, "en" if k % 3 else None, f"s{k % 3}" if k % 5 else None, 0) for k, (i, t) in enumerate(zip(ids or range(len(texts)), texts))]
    df = spark.createDataFrame(rows, DOCS)
    return df.withColumns({"n": F.lit(1), "row": F.lit(2), "label": F.lit("x"), "fp": F.lit(0)}) if extra else df


@pytest.fixture(scope="module")
def odd(spark):
    return frame(spark, ODD + ["Two words", "two WORDS"], extra=True)


# ---------------------------------------------------------------- chat


def test_chat_reads_back_everything(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "user", r"a\b <s> \</s> [INST] x"), (1, 2, "assistant", "</s>"), (1, 3, "assistant", "\\"), (2, 1, None, None), (2, 0, "sys[INST]\n", ""), (None, 5, "assistant", "né👍"), (3, None, "user", "late"), (3, 0, "assistant", "</s>[INST] ok [/INST]"), (3, 0, "assistant", "</s>[INST] ok [/INST]")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit("clash"))
    done = chat.format_chats(df).withColumn("turns", chat.read_back(F.col("formatted"))).collect()
    for r in done:
        mine = sorted(((t is not None, t or 0, role or "", x or "") for c, t, role, x in rows if c == r.conv_id))
        assert [(t.role, t.text) for t in r.turns] == [(role, x) for _, _, role, x in mine]
        learned = [re.sub(r"(?s)\\(.)", r"\1", r.formatted[s.start : s.start + s.length]) for s in r.loss_spans]
        assert learned == [x for _, _, role, x in mine if role == "assistant"]
    assert "<s>[INST] user [/INST]hi<s>" in {r.conv_id: r for r in done}[1].formatted


def test_chat_spans_of_a_long_conversation(spark):
    rows = [(1, i, "assistant" if i % 3 else "user", f"t{i}<s>" * (i % 4)) for i in range(20_000)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    began = time.perf_counter()
    r = chat.format_chats(df).first()
    assert time.perf_counter() - began < 60
    learned = [re.sub(r"(?s)\\(.)", r"\1", r.formatted[s.start : s.start + s.length]) for s in r.loss_spans]
    assert learned == [x for _, _, role, x in rows if role == "assistant"]


def test_chat_of_nothing(spark):
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert chat.format_chats(empty).count() == 0


# ---------------------------------------------------------------- SimHash


def plain_fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    sh = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) > 2 else [" ".join(w)] if w else []
    h = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in sh]
    return sum(1 << b for b in range(64) if h and 2 * sum(v >> b & 1 for v in h) > len(h))


def test_fingerprints_and_components(spark, odd):
    got = {(r.doc_id): r for r in simhash.near_duplicates(odd).collect()}
    texts = ODD + ["Two words", "two WORDS"]
    for i, t in enumerate(texts):
        assert got[i].fp & (2**64 - 1) == plain_fingerprint(t)
    assert got[0].component_id == got[1].component_id == got[2].component_id == 0 and got[13].component_id == got[12].component_id == 4
    assert simhash.near_duplicates(odd.where("doc_id < 0")).count() == 0


@pytest.mark.parametrize("spread, hot", [(1, 4096), (1, 3), (3, 4096), (3, 1)])
def test_anchor_covering_finds_every_link(spark, monkeypatch, spread, hot):
    monkeypatch.setattr(simhash, "HOT_HOMES", hot)
    rng = np.random.default_rng(spread)
    base = rng.integers(0, 2**64, 60, dtype=np.uint64)
    prints = [int(b) for b in base]
    for b in base[:20]:
        for _ in range(25):
            x = int(b)
            for bit in rng.choice(64, spread, replace=False):
                x ^= 1 << int(bit)
            prints.append(x)
    fp = np.array(sorted(set(prints)), np.uint64)
    df = spark.createDataFrame([(int(x),) for x in fp.view(np.int64)], "fp long")
    edges = {frozenset((r.src, r.dst)) for r in simhash.fingerprint_links(df).collect()}
    near = np.bitwise_count(fp[:, None] ^ fp[None]) <= 2
    label = np.arange(len(fp))
    while (new := np.array([label[near[i]].min() for i in range(len(fp))])).tolist() != label.tolist():
        label = new
    place = {int(v): i for i, v in enumerate(fp.view(np.int64))}
    own = list(range(len(fp)))

    def find(i):
        while own[i] != i:
            i = own[i]
        return i

    for e in edges:
        a, b = (find(place[x]) for x in e)
        own[max(a, b)] = min(a, b)
    assert [find(i) for i in range(len(fp))] == label.tolist()


def test_golay_code_covers():
    flat, offsets = simhash._coset_tables()
    assert len(flat[0]) == 2048 and (np.diff(offsets[0]) == 1).all()
    own, anchor, home = simhash.anchors_of(np.array([0, 5, 2**63], np.uint64))
    assert home.sum() == 3 and len(own) == len(anchor)


def test_crowded_buckets_are_compared_without_dealing_every_shingle(spark, monkeypatch):
    def never(*_):
        raise AssertionError("all shingles of the crowd were dealt once more")

    monkeypatch.setattr(overlap, "rare_buckets", never)
    monkeypatch.setattr(overlap, "COMMON_IN", 10**9)  # the passage stays among the first shingles
    rng = np.random.default_rng(11)
    passage, texts = [f"p{i}" for i in range(60)], []
    for i in range(30):
        own = [f"u{i}x{j}" for j in range(60)]
        texts.append(passage + own)
        if i % 2:
            at = int(rng.integers(10, 50))
            texts.append(passage + own[:at] + ["other"] + own[at + 1 :])
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in texts]
    least = [min(j for j, b in enumerate(sets) if 10 * len(a & b) >= 8 * len(a | b)) for a in sets]
    docs = frame(spark, [" ".join(w) for w in texts])
    assert {r.doc_id: r.component_id for r in overlap.similar_texts(docs).collect()} == dict(enumerate(least))


def test_bucket_pairs_carries_buckets_across_batches(spark):
    bins = bytes(range(16)), bytes(range(15, -1, -1))  # far apart
    known = spark.createDataFrame([(k, bytearray(bins[k % 2]) if k % 5 else bytearray()) for k in range(90)], "key long, bins binary")
    rows = [(t, k, 200 if k < 80 else 90, k if k % 7 else 0) for t in (-5, 3, 8) for k in range(90) if (k + t) % 4]
    near = lambda a, b: not (a % 5 and b % 5) or a % 2 == b % 2
    root = lambda k: k if k % 7 else 0
    want = {(a, b) for t, a, n, _ in rows for u, b, m, _ in rows if t == u and a < b and n == m and root(a) != root(b) and near(a, b)}
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 7)
    try:
        found = overlap.bucket_pairs(spark.createDataFrame(rows, "token long, key long, n long, root long"), known, 80).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert {(r.src, r.dst) for r in found} == want


def _roots(n, edges):
    own = list(range(n))

    def find(i):
        while own[i] != i:
            i = own[i]
        return i

    for a, b in edges:
        a, b = find(a), find(b)
        own[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


@pytest.mark.parametrize("task_bucket, block_keys", [(512, 2048), (512, 7), (20, 2048), (20, 7)])
def test_texts_about_a_passage_are_compared_without_a_row_a_pair(spark, monkeypatch, task_bucket, block_keys):
    written, real = [], overlap.stage

    def counted(df, name="t", *more):
        out = real(df, name, *more)
        if name in ("pair", "likely", "true"):
            written.append(out.count())
        return out

    monkeypatch.setattr(overlap, "stage", counted)
    monkeypatch.setattr(overlap, "COMMON_IN", 10**9)  # the passage stays among the first shingles
    monkeypatch.setattr(overlap, "TASK_BUCKET", task_bucket)
    monkeypatch.setattr(overlap, "BLOCK_KEYS", block_keys, raising=False)
    rng = np.random.default_rng(29)
    passage = [f"p{i}" for i in range(60)]
    texts = [passage + [f"u{i}x{j}" for j in range(int(rng.integers(4, 12)))] for i in range(90)]
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in texts]
    close = [(i, j) for j in range(len(sets)) for i in range(j) if 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j])]
    assert len(close) > 5 * len(texts)
    docs = frame(spark, [" ".join(w) for w in texts])
    assert {r.doc_id: r.component_id for r in overlap.similar_texts(docs).collect()} == dict(enumerate(_roots(len(texts), close)))
    if block_keys > len(texts):  # blocks give as many rows a key as there are blocks
        assert max(written) <= 2 * len(texts)


@pytest.mark.parametrize("block_keys", [2048, 9])
def test_bucket_groups_joins_what_bucket_pairs_pairs(spark, monkeypatch, block_keys):
    monkeypatch.setattr(overlap, "BLOCK_KEYS", block_keys)
    rng = np.random.default_rng(31)
    sets, kind = [], [np.unique(rng.integers(0, 2**63, n).astype(np.uint64)) for n in (230, 240, 250, 270, 60)]
    for i in range(80):  # sketches of 256 and 512 bits
        s = kind[i % 5].copy()
        s[rng.integers(0, len(s), i % 30)] = rng.integers(0, 2**63, i % 30).astype(np.uint64)
        sets.append(np.unique(s))
    known = spark.createDataFrame([(k, bytearray(overlap.sketch(s))) for k, s in enumerate(sets)], "key long, bins binary")
    rows = [(t, k, len(sets[k]), k % 40 if k % 3 else k, 60) for t in (-4, 9) for k in range(80) if (k + t) % 7]
    df = spark.createDataFrame(rows, "token long, key long, n long, root long, held long")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 11)
    try:
        pairs = [(r.src, r.dst) for r in overlap.bucket_pairs(df, known, 80).collect()]
        edges = [(r.src, r.dst) for r in overlap.bucket_groups(df, known, 80).collect()]
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert len(pairs) > 300 and _roots(80, edges) == _roots(80, pairs)
    assert {k for e in edges for k in e} == {k for p in pairs for k in p}
    if block_keys > 80:
        assert len(edges) < 2 * 80


def test_sketches_never_exceed_the_symmetric_difference():
    rng = np.random.default_rng(37)
    for n in (1, 40, 255, 256, 300, 2100):
        a = np.unique(rng.integers(0, 2**63, n).astype(np.uint64))
        for m in (0, n // 10, n):
            b = np.unique(np.r_[a[m:], rng.integers(0, 2**63, n // 5).astype(np.uint64)])
            far = len(np.setxor1d(a, b))
            bound = overlap.distances([overlap.sketch(a), overlap.sketch(b)], [overlap.sketch(b), overlap.sketch(b)])
            assert bound[1] == 0 and bound[0] <= far and (far + bound[0]) % 2 == 0 and (m == n or far // 2 <= bound[0])


# ---------------------------------------------------------------- toxicity


def test_misspellings_share_grams_and_labels_stay_out(spark):
    rng = np.random.default_rng(0)
    clean = ["table", "river", "green", "music", "paper", "window", "garden"]
    made, labels = [], []
    for i in range(300):
        words = list(rng.choice(clean, 30))
        bad = i % 3 == 0
        if bad:
            words[4] = words[11] = "horridfool"
        made.append(" ".join(words))
        labels.append((i, int(bad)))
    docs = frame(spark, made + ["table horidfool river horridfoool green", "table river green music", None, ""])
    lab = spark.createDataFrame([*labels, (None, 1), (5, None), (999_999, 1)], "doc_id long, toxic int")
    model = toxicity.train(docs, lab)
    got = {r.doc_id: r.score for r in toxicity.score_texts(docs, model).collect()}
    held = [i for i in range(300) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert all((got[i] >= 0.5) == (i % 3 == 0) for i in held)
    assert got[300] > 0.5 > got[301] and got[302] == got[303] and 0 <= min(got.values()) and max(got.values()) <= 1


@pytest.mark.parametrize("gap", ["", "\u00a0", "\u3000"])
def test_toxicity_reads_texts_without_ascii_spaces_to_their_end(spark, monkeypatch, gap):
    rng = np.random.default_rng(1)
    clean, bad, made = ["\u5927\u5730\u5c71", "\u6cb3\u6d41\u6c34", "\u82b1\u8349\u6728", "\u97f3\u4e50\u5bb6"], "\u6076\u6bd2\u8bcd\u8bed", []
    head = gap.join(clean * 8)
    for i in range(200):
        middle = gap.join(rng.choice(clean, 12))
        made.append(head + gap + middle + gap + (gap.join([bad] * 4) if i % 2 else clean[0]))
    docs = frame(spark, made)
    got = {r.doc_id: r.score for r in toxicity.score_texts(docs, toxicity.train(docs, spark.createDataFrame([(i, i % 2) for i in range(200)], "doc_id long, toxic int"))).collect()}
    assert all((got[i] >= 0.5) == (i % 2 == 1) for i in range(200))
    whole = toxicity._grams([made[1] * 5])[1]
    monkeypatch.setattr(toxicity, "CHUNK_CHARS", 7)
    assert np.array_equal(np.sort(whole), np.sort(toxicity._grams([made[1] * 5])[1]))


def test_scores_match_a_plain_scorer(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "CHUNK_CHARS", 37)
    rng = np.random.default_rng(12)
    model = toxicity.SubwordModel(rng.normal(0, 3, toxicity.BUCKETS).astype(np.float32), 0.3)
    texts = ["Good, GOOD words! and (good)", "字" * 64 + "毒" * 50, "字" * 64, "x" * 200 + " y", "...", "a\u00a0b\u3000c d", None, "", "Straße Éx " * 30]
    got = {r.doc_id: r.score for r in toxicity.score_texts(frame(spark, texts, extra=True), model).collect()}
    for i, t in enumerate(texts):
        bags = Counter()
        for w in (t or "").lower().split():
            bags[w.strip("!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~") or w] += 1
        each = {}
        for w in bags:
            data = f"<{w}>"
            grams_of = {data} | {data[k : k + n] for n in (3, 4, 5) for k in range(len(data) - n + 1)}
            rows = [zlib.crc32(g.encode()) % toxicity.BUCKETS for g in grams_of]
            rows = set(rows) if len(w) > toxicity.MEMO_CHARS else rows
            each[w] = np.mean([model.table[r] for r in rows])
        weight = sum(n**0.5 for n in bags.values())
        logit = 0.3 + (sum(n**0.5 * each[w] for w, n in bags.items()) / weight if weight else 0)
        assert got[i] == pytest.approx(1 / (1 + np.exp(-np.clip(logit, -30, 30))), abs=2e-6), t


def test_whole_rows_send_their_text_once(spark, odd):
    rng = np.random.default_rng(7)
    model = toxicity.SubwordModel(rng.normal(0, 3, toxicity.BUCKETS).astype(np.float32), 0.3)
    docs = odd.withColumn("doc", F.lit(1)).withColumnRenamed("text", "Text").select("Text", "doc", "doc_id", "lang")
    found = toxicity.score_texts(docs, model, whole=True)
    (sent,) = found._jdf.queryExecution().optimizedPlan().children().apply(0).output().mkString("|").split("|")
    assert sent.startswith("doc#")
    alone = {r.doc_id: r.score for r in toxicity.score_texts(odd, model).collect()}
    assert {r.doc.doc_id: r.score for r in found.collect()} == alone
    assert {r.doc.doc_id: r.doc.Text for r in found.collect()} == {r.doc_id: r.text for r in odd.collect()}


def test_toxicity_without_labels(spark):
    docs = frame(spark, ["a", "b"])
    model = toxicity.train(docs, spark.createDataFrame([], "doc_id long, toxic int"))
    assert toxicity.score_texts(docs, model).count() == 2
    assert toxicity.score_texts(docs.where("doc_id < 0"), model).count() == 0


# ---------------------------------------------------------------- mixing


def plain_targets(sizes, weights, share=1.5, cap=2.0):
    total, clamped = share * sum(sizes.values()), {}
    while True:
        left = {s: weights[s] for s in sizes if s not in clamped}
        rest = total - sum(clamped.values())
        now = {s: rest * w / sum(left.values()) for s, w in left.items()}
        over = [s for s, t in now.items() if t > cap * sizes[s] + 1e-9]
        if not over:
            return clamped | now
        clamped |= {s: cap * sizes[s] for s in over}


def test_mix_meets_its_targets(spark):
    rng = np.random.default_rng(1)
    rows, sizes = [], {}
    for s, n in ((None, 40), ("a", 400), ("b", 30), ("é", 80), ("z", 5)):
        for _ in range(n):
            k = int(rng.integers(0, 60))
            rows.append((len(rows), "w " * k if k else None, s))
            sizes[s] = sizes.get(s, 0) + k
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumn("size", F.lit("clash"))
    got = mixing.mix_copies(df)
    weights = dict(zip(sorted((s for s in sizes if s), key=lambda s: s.encode()), (5, 2, 1, 5))) | {None: 2}
    want = plain_targets(sizes, weights)
    for r in got.groupBy("source").agg(F.max("target").alias("t"), F.sum(F.col("size") * F.col("copies")).alias("taken"), F.max("copies").alias("c")).collect():
        assert r.t == pytest.approx(want[r.source]) and abs(r.taken - r.t) <= 60 and r.c <= 2
    again = mixing.mix_copies(df.repartition(3))
    assert got.exceptAll(again).count() == 0
    assert mixing.mix_copies(df.where("doc_id < 0")).count() == 0


def test_mix_of_empty_texts_and_equal_rows(spark):
    df = spark.createDataFrame([(1, None, "a"), (1, None, "a"), (None, "x y", "a"), (None, "x y", "a")], "doc_id long, text string, source string")
    got = mixing.mix_copies(df).collect()
    assert len(got) == 4 and all(r.copies <= 2 for r in got)


# ---------------------------------------------------------------- language models


def plain_words(text):
    return [w.strip(lmscore.SIGNS) or w for w in regex.sub(lmscore.SPLIT, r" \1 ", (text or "").lower()).split()]


def plain_differences(texts, flags, head):
    """Dirichlet-smoothed word pairs in plain dicts, every text left out of its own counts."""
    lists = [plain_words(t) for t in texts]
    pairs = [Counter(zip(["", *w[:-1]], w)) for w in lists]
    firsts = [Counter(["", *w[:-1]] if w else []) for w in lists]
    words, target = Counter(x for w in lists for x in w), Counter(x for w, f in zip(lists, flags) if f for x in w)
    alone = {x for x in words if x in head}
    out = []
    for i, w in enumerate(lists):
        means = []
        for chosen, unigram in ((flags, target), ([True] * len(texts), words)):
            rest = max(1, len(words) - len(alone))
            other = (sum(unigram.values()) - sum(unigram[x] for x in alone) + rest) / rest
            loss = 0
            for (a, b), n in pairs[i].items():
                c = sum(p[a, b] for j, p in enumerate(pairs) if chosen[j] and j != i)
                t = sum(p[a] for j, p in enumerate(firsts) if chosen[j] and j != i)
                q = (unigram[b] + 1 if b in alone else other) / (sum(unigram.values()) + len(words))
                loss -= n * np.log2((c + lmscore.ALPHA * q) / (t + lmscore.ALPHA))
            means.append(loss / len(w) if w else None)
        lone = sum(n for k, n in pairs[i].items() if sum(p[k] for p in pairs) == n)
        out.append((len(w), lone, *means))
    return out


LM_TEXTS = ["the cat sat on the mat, the end.", "zq9 $$ xkcd %% ##", None, "", "the rat sat on the hat", "the rat sat on the hat", "\u0442\u0435\u043a\u0441\u0442 \u043e \u043c\u0438\u0440\u0435", "\u043c\u0438\u0440 \u0431\u0435\u0437 \u0442\u0435\u043a\u0441\u0442\u0430 \u043e \u043c\u0438\u0440\u0435", "日本語テキスト", "日本の海", " \u00a0\n", "on the mat " * 30, "A a a A."]


@pytest.mark.parametrize("head, hot", [(1 << 16, 1 << 18), (6, 1 << 18), (6, 0), (1, 3)])
def test_word_pair_losses_match_plain_dicts(spark, monkeypatch, head, hot):
    monkeypatch.setattr(lmscore, "HOT_PAIRS", hot)
    flags = [i in (0, 4, 8, 11) for i in range(len(LM_TEXTS))]
    docs = frame(spark, LM_TEXTS, extra=True).withColumn("in_target", F.col("doc_id").isin(0, 4, 8, 11)).repartition(3)
    shared = lmscore.Shared(stage(lmscore.counted(docs, np.zeros(0, np.uint64))), head)
    named = {"": int(lmscore.START)} | {w: xxhash.xxh64_intdigest(w) for t in LM_TEXTS for w in plain_words(t)}
    want = plain_differences(LM_TEXTS, flags, {w for w, k in named.items() if w and k in set(shared.words.tolist())})
    got = {r.doc_id: r for r in lmscore.cross_entropy_difference(docs, head).collect()}
    assert len(got) == len(LM_TEXTS)
    for i, (n, lone, t, b) in enumerate(want):
        assert (got[i].n_words, got[i].lone_pairs) == (n, lone)
        for mine, plain in ((got[i].target_loss, t), (got[i].background_loss, b)):
            assert mine is None if plain is None else abs(mine - plain) < 2e-6, (i, got[i], want[i])
    assert got[6].background_loss != got[7].background_loss and got[8].difference != got[9].difference


def test_differences_of_no_target_and_of_nothing(spark):
    docs = frame(spark, LM_TEXTS[:5]).withColumn("in_target", F.lit(None).cast("boolean"))
    assert lmscore.cross_entropy_difference(docs).count() == 5
    assert lmscore.cross_entropy_difference(docs.where("doc_id > 99")).count() == 0
    same = frame(spark, ["a b c", "a b c", "a b c"], ids=[1, 1, None]).withColumn("in_target", F.lit(True))
    got = lmscore.cross_entropy_difference(same).collect()
    assert sorted((r.doc_id or 0) for r in got) == [0, 1, 1] and len({(r.difference, r.lone_pairs) for r in got}) == 1


def plain_kneser_ney(seen, universe, order):
    """Probabilities of n-grams by modified Kneser-Ney, in plain dicts."""
    levels = {order: Counter(seen)}
    for k in range(order - 1, 0, -1):
        levels[k] = Counter(g[1:] for g in levels[k + 1])
    kinds = len({g[-1] for g in universe})

    def cuts(k):
        n = [sum(v == i for v in levels[k].values()) for i in range(5)]
        if not (n[1] and n[2] and n[3]):
            return [0.5, 0.75, 0.9]
        y = n[1] / (n[1] + 2 * n[2])
        return [min(max(i - (i + 1) * y * n[i + 1] / n[i], 0.05), i - 0.05) for i in (1, 2, 3)]

    d = {k: cuts(k) for k in levels}

    def p(g):
        if not g:
            return 1 / kinds
        k = len(g)
        same = {h: n for h, n in levels[k].items() if h[:-1] == g[:-1]}
        if not same:
            return p(g[1:])
        total = sum(same.values())
        back = sum(d[k][min(n, 3) - 1] for n in same.values()) / total
        n = levels[k].get(g, 0)
        return max(n - (d[k][min(n, 3) - 1] if n else 0), 0) / total + back * p(g[1:])

    return p


@pytest.mark.parametrize("order, hot", [(3, 1 << 18), (5, 40), (2, 0)])
def test_kneser_ney_and_perplexity_match_plain_dicts(spark, monkeypatch, order, hot):
    texts = LM_TEXTS + [f"the {a} {b} on the {c}" for a in ("cat", "dog") for b in ("sat", "ran") for c in ("mat", "hat")]
    docs = frame(spark, texts, extra=True).repartition(3)
    trusted = docs.where("doc_id % 2 = 0").select("doc_id")
    out = {r.doc_id for r in trusted.where(quality.held_out(F.col("doc_id"))).collect()}
    pad = lambda t: grams.PAD * (order - 1) + (t or "")
    cut = lambda t: [pad(t)[i : i + order] for i in range(len(t or ""))]
    p = plain_kneser_ney(Counter(g for i, t in enumerate(texts) if i % 2 == 0 and i not in out for g in cut(t)), {g for t in texts for g in cut(t)}, order)
    monkeypatch.setattr(grams.gram_sums, "__defaults__", ((), hot))
    got = {r.doc_id: r for r in quality.judge_quality(docs, trusted, 0.9, order).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        losses = [-np.log2(p(g)) for g in cut(t)]
        assert got[i].n_symbols == len(losses)
        assert got[i].perplexity is None if not losses else abs(np.log2(got[i].perplexity) - np.mean(losses)) < 2e-6
    contexts = {g[:-1] for t in texts for g in cut(t)}
    for c in list(contexts)[:20]:
        assert abs(sum(p(c + x) for x in {x for t in texts for x in t or ""}) - 1) < 1e-9


def test_quality_keeps_trusted_text(spark):
    good = [f"the {a} {b} on the {c}" for a in ("cat", "dog", "rat") for b in ("sat", "ran", "hid") for c in ("mat", "hat", "bed")]
    docs = frame(spark, good + ["%%% $$$ ### @@@ !!!", None, "zzqxj kkvwq"])
    got = {r.doc_id: r for r in quality.judge_quality(docs, docs.where("doc_id < 27"), 0.95).collect()}
    assert sum(got[i].keep for i in range(27)) >= 20 and not got[27].keep and not got[28].keep and not got[29].keep
    assert quality.judge_quality(docs, docs.where("doc_id < 0")).where("keep").count() == 29
    assert quality.judge_quality(docs.where("doc_id < 0"), docs).count() == 0
    cyrillic = frame(spark, ["\u0442\u0435\u043a\u0441\u0442 \u043e \u043c\u0438\u0440\u0435", "\u0449\u044a\u044b \u044d \u044e\u0444\u0446\u0445"] + ["\u0442\u0435\u043a\u0441\u0442 \u043e \u043c\u043e\u0440\u0435"] * 8)
    one, other = (r.perplexity for r in quality.judge_quality(cyrillic, cyrillic.where("doc_id > 1")).orderBy("doc_id").limit(2).collect())
    assert one < other
    twice = frame(spark, ["a b", "a b"], ids=[1, 1])
    assert quality.judge_quality(twice, twice).count() == 2


def test_key_table_finds_every_key():
    rng = np.random.default_rng(3)
    keys = np.unique(np.r_[np.arange(50, dtype=np.uint64), rng.integers(0, 1 << 63, 5000).astype(np.uint64)])
    table = grams.KeyTable(keys[::2])
    assert (table.find(keys[::2]) == np.arange(len(keys[::2]))).all() and (table.find(keys[1::2]) == -1).all()
    assert (grams.KeyTable(keys[:0]).find(keys) == -1).all()


def test_words_are_hashed_without_a_string_each(monkeypatch):
    words = ["one", "(one)", "...", "'stuff'", "é", "日本", "a--b", "", "#né!", "x" * 9000]
    want = [xxhash.xxh64_intdigest(w.strip(lmscore.SIGNS) or w) for w in words]
    for some, hashes in ((pa.array(words), want), (pa.array(words).slice(3, 4), want[3:7]), (pa.array([], pa.string()), []), (pa.array([""]), want[7:8])):
        assert lmscore.word_keys(some).tolist() == hashes


def test_windows_of_pair_losses_carry_no_numbers_of_words(spark, capsys):
    lmscore.cross_entropy_difference(frame(spark, ODD).withColumn("in_target", F.col("doc_id") < 4)).explain("formatted")
    windows = [x for x in capsys.readouterr().out.split("\n\n") if re.match(r"\(\d+\) Window", x)]
    assert len(windows) == 2 and not any(re.search(r"\b(h1|h2|t)#|_w\d+#", x) for x in windows)


# ---------------------------------------------------------------- tokens, packing


def library_ids(text):
    return tokens._library(tokens.word_tokenizer()).encode(text or "", add_special_tokens=False).ids


def test_ids_and_prefix_counts_are_the_library_s(spark, odd):
    got = {r.doc_id: r for r in tokens.token_answers(odd, (3, 2048), tables=True).collect()}
    for i, t in enumerate(ODD):
        t = t or ""
        table = np.frombuffer(got[i].prefix_tokens, "<i4").tolist()
        assert got[i].n_tokens == len(library_ids(t)) and got[i].n_bytes == len(t.encode()) and len(table) == len(t)
        for n in {*range(1, min(len(t), 40) + 1), len(t)} - {0}:
            assert table[n - 1] == len(library_ids(t[:n])), (i, n)
        assert got[i].fits[1] == max([n for n, c in enumerate([0, *table]) if c <= 2048])
    looked = tokens.token_answers(odd.where("doc_id = 4"), tables=True).select(tokens.tokens_of_prefix(F.col("prefix_tokens"), F.lit(3))).first()[0]
    assert looked == len(library_ids("Two"))
    assert tokens.token_answers(odd.where("doc_id < 0")).count() == 0


def test_long_runs_by_the_second_program():
    path = tokens.word_tokenizer()
    for text in ("internationalization" * 4, "=-=" * 40, "don't" * 20, "日本語テキスト処理" * 8, "ab1cd2" * 12):
        got = tokens.long_chunk_counts(text, path).tolist()
        assert got == [len(library_ids(text[:n])) for n in range(1, len(text) + 1)]


#: Pieces that normalisation, the pre-tokeniser or the special strings treat oddly.
PIECES = ["İ", "ı", "ſ", "K", "\ufb2c", "\U0001d160", "\u0958", "ᄀ", "ᅡ", "ᆨ", "가", "e\u0301", "\u0301", "\u0323", "\u0307", "a\u0323\u0307", "ǆ", "ß", "字", "毒", "д", "ω", "٣", "9", "½", "'", "'s", "'S", "'re", "'lx", "!", ".,;", ":?", "…", "—", "👍", "👩\u200d🚀", "\u00a0", "\u3000", "\u1680", "\x1c", "\x85", "<|endoftext|>", "<|startoftext|>", "<|endoftext", "|>", "<|ENDOFTEXT|>", "a", "B", "the", "ing", "Rİ.", "\u0378"]


def test_ids_and_counts_of_odd_texts():
    path, rng = tokens.word_tokenizer(), np.random.default_rng(8)
    texts = ["İ.", "Aİ!", "Rİ. Sİ,", "\ufb2c" * 48, "\U0001d160" * 40, "x" * 47 + "\u0301!!", "." * 60, "a" + "!" * 60]
    for size in [3] * 150 + [12] * 100 + [70] * 40:
        texts.append("".join(PIECES[i] + (" " if rng.random() < 0.1 else "") for i in rng.integers(0, len(PIECES), size)))
    ends, ids = tokens.slice_ids(pa.array(texts), path)
    edges, counts = tokens.slice_prefix_counts(pa.array(texts), path)
    for i, t in enumerate(texts):
        assert ids[ends[i] : ends[i + 1]].tolist() == library_ids(t), t
        want = [len(library_ids(t[:n])) for n in range(1, len(t) + 1)]
        assert counts[edges[i] : edges[i + 1]].tolist() == want, t
        if t and " " not in t:
            assert tokens.long_chunk_counts(t, path).tolist() == want, t


@pytest.mark.parametrize("odd_piece", ["e\u0301", "İ", "<|endoftext|>", "'s"])
def test_one_odd_piece_in_a_long_chunk_costs_no_more(odd_piece):
    path = tokens.word_tokenizer()
    text = "unbroken" * 4000 + odd_piece + "字毒x1" * 4000
    began = time.perf_counter()
    edges, counts = tokens.slice_prefix_counts(pa.array([text]), path)
    assert time.perf_counter() - began < 30
    for n in (1, 31_999, 32_000, 32_001, 32_002, 32_010, len(text)):
        assert counts[n - 1] == len(library_ids(text[:n]))


@pytest.mark.parametrize("weights", [None, {"s0": 3.0, "s1": 1.0}])
def test_packing_places_every_id_once(spark, odd, weights):
    got = packing.pack(odd, weights, sequence=64, window=2, keep_ids=True).orderBy("sequence_id", "offset").collect()
    by_seq, by_doc = {}, {}
    for r in got:
        assert r.offset == by_seq.get(r.sequence_id, 0) and r.ids_crc32 == zlib.crc32(r.ids) and len(r.ids) == 4 * r.length
        by_seq[r.sequence_id] = r.offset + r.length
        by_doc.setdefault(r.doc_id, []).append((r.start, r.ids, r.doc_tokens))
    assert all(n == 64 or n & (n - 1) == 0 for n in by_seq.values()) and sorted(by_seq) == list(range(len(by_seq)))
    for i, t in enumerate(ODD + ["Two words", "two WORDS"]):
        parts = sorted(by_doc[i])
        ids = np.frombuffer(b"".join(p[1] for p in parts), "<u4").tolist()
        assert ids == [*library_ids(t), 2] and parts[0][2] == len(ids)
    whole = packing.sequences(packing.pack(odd, weights, sequence=64, window=2, keep_ids=True))
    assert whole.agg(F.sum("length")).first()[0] == sum(by_seq.values())
    assert packing.pack(odd.where("doc_id < 0")).count() == 0


def test_windows_hold_the_target_proportions():
    totals = [5000, 3000, 41, 1]
    plan = packing.RoundRobin(packing.phases(totals, None), 64, 4)
    seen = np.zeros((4, -(-sum(totals) // 256)), int)
    taken = np.zeros(sum(totals), int)
    for s, n in enumerate(totals):
        for cut in (0, n // 3, n):
            pass
        for a, b in ((0, n // 3), (n // 3, n)):
            for at, place, length in plan.runs(s, a, b):
                taken[place : place + length] += 1
                for p in range(place, place + length):
                    seen[s, p // 256] += 1
    assert (taken == 1).all()
    share = np.array(totals)[:, None] / sum(totals) * 256
    assert (abs(seen[:, :-1] - share) <= 4).all()


def test_weighted_phases_send_everything():
    totals = [100, 700, 50]
    parts = packing.phases(totals, [2.0, 1.0, 0.0])
    assert np.array(parts).sum(0).tolist() == totals and parts[0][0] == 100 and abs(parts[0][1] - 50) <= 1


@pytest.mark.parametrize("kinds", [9, 1 << 40])
def test_distinct_pairs_match_a_plain_count(kinds):
    rng = np.random.default_rng(8)
    for n in (0, 1, 500):
        by, first, words = np.sort(rng.integers(0, 6, n)), rng.integers(0, 9, n), rng.integers(0, 9, n)
        plain, heads = Counter(zip(by, first, words)), Counter(zip(by, first))
        x, f, w, times, ctx = lmscore._distinct(by, first, words, kinds)
        assert list(zip(x, f, w)) == sorted(plain)
        assert [plain[k] for k in zip(x, f, w)] == times.tolist() and [heads[k] for k in zip(x, f)] == ctx.tolist()


def test_times_come_back_from_upper_bytes(spark):
    times = np.array([1, 2, lmscore.SMALL - 1, lmscore.SMALL, lmscore.SMALL + 1, 1 << 31, 1 << 40])
    sent = spark.createDataFrame(pa.table({"nctx": lmscore.upper(times), "is": times}))
    assert sent.where(lmscore.from_upper("nctx") != F.col("is")).isEmpty()
    assert (lmscore.upper(times)[:3] >= 1 << lmscore.UPPER).all()


def test_words_apart_by_signs_share_a_code():
    bounds, words, keys, start = lmscore.slice_words(pa.array(["Cat cat, (cat)", "", "dog"]))
    assert bounds.tolist() == [0, 3, 3, 4] and len(set(words[:3])) == 1 and words[3] not in (words[0], start)
    assert [int(k) for k in keys[words[[0, 3]]]] == [xxhash.xxh64_intdigest(w) for w in ("cat", "dog")] and keys[start] == lmscore.START


# ---------------------------------------------------------------- exact dedup


def test_filter_has_no_false_negative():
    rng = np.random.default_rng(3)
    for n in (0, 1, 2, 7, 60, 3000, 40_000):
        keys = rng.integers(0, 2**63, n).astype(np.uint64)
        f = exact.FuseFilter.from_bytes(exact.FuseFilter.build(keys).to_bytes())
        assert f.contains(keys).all() and f.contains(rng.integers(0, 2**63, 5000).astype(np.uint64)).mean() < 0.02
        assert len(f.table) <= 1.5 * n + 64


@pytest.mark.parametrize("parts", [1, 2, 5])
def test_groups_match_a_plain_dict(spark, odd, parts):
    docs = odd.unionByName(odd.where("doc_id in (4, 5)")).unionByName(odd.limit(1).withColumn("doc_id", F.lit(None).cast("long")))
    got = exact.dedup_documents(docs, parts).collect()
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    groups = {}
    for i, t in rows:
        groups.setdefault(hashlib.sha256((t or "").encode().lower()).digest(), []).append(i)
    assert len(got) == len(rows)
    for r in got:
        mine = groups[bytes(r.sha)]
        assert r.group_size == len(mine) and r.keep_id == max((i for i in mine if i is not None), default=None)
    assert sum(r.row == r.keep_row for r in got) == len(groups)
    assert exact.dedup_documents(docs.where("doc_id < 0"), parts).count() == 0


def test_digests_keep_texts_in_spark_s_rows(spark):
    texts = [*ODD, "𝔸BC😀Z", "ＡＺ ẞ K Å", "ÀÉ ABC", "@AZ[`az{"]
    found = exact.text_digests(frame(spark, texts, extra=True), carry=("n",))
    assert "InArrow" not in found._jdf.queryExecution().executedPlan().toString()
    got = found.collect()
    for r in got:
        normal = (texts[r.doc_id] or "").encode().lower()
        assert (bytes(r.normal), bytes(r.sha), r.bytes, r.n) == (normal, hashlib.sha256(normal).digest(), len(normal), 1)
    assert len({r.row for r in got}) == len(texts)


# ---------------------------------------------------------------- top-k


@pytest.mark.parametrize("k, many", [(3, 150), (10, 5)])
def test_top_k_is_exact(spark, monkeypatch, k, many):
    monkeypatch.setattr(neighbors, "SLICE_ROWS", 40)
    monkeypatch.setattr(neighbors, "GROUP_QUERIES", 20)
    monkeypatch.setattr(neighbors, "PIVOTS", 9)
    rng = np.random.default_rng(k)
    x = rng.normal(0, 0.2, (many, 8)).round(3)
    x[1::4] = x[0]  # ties
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)]
    rows += [(900, None), (901, [1.0, None]), (902, [float("nan")] * 8), (903, [float("inf")] * 8)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("x", F.lit(1))
    q = neighbors.quantised(df)
    assert q.count() == many
    got = neighbors.top_k(q.where("vec_id % 5 = 0"), q, k).orderBy("query_id", "rank").collect()
    v = np.floor(1024 * x).astype(np.int64)
    want = []
    for i in range(0, many, 5):
        s = v @ v[i]
        best = sorted((j for j in range(many) if j != i), key=lambda j: (-s[j], j))[:k]
        want += [(i, n + 1, j, int(s[j])) for n, j in enumerate(best)]
    assert [tuple(r) for r in got] == want
    assert neighbors.top_k(q.where("vec_id < 0"), q).count() == 0 and neighbors.top_k(q, q.where("vec_id < 0")).count() == 0


def test_top_k_with_a_crowded_cell_and_large_components(spark, monkeypatch):
    monkeypatch.setattr(neighbors, "GROUP_QUERIES", 16)
    monkeypatch.setattr(neighbors, "SLICE_ROWS", 40)
    rng = np.random.default_rng(9)
    v = np.concatenate([rng.integers(-5, 5, (300, 6)) + 1000, rng.integers(-900, 900, (200, 6))])
    huge = [[2**62, 1, 0, 0, 0, 0], [-(2**62), 2**61, 3, 0, 0, 0], [2**40] * 6]
    rows = [(i, list(map(int, x))) for i, x in enumerate([*v, *huge])]
    df = spark.createDataFrame(rows, "vec_id long, v array<long>")
    got = {}
    for r in neighbors.top_k(df.where("vec_id % 2 = 0"), df, 5).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    low, high = -(2**63), 2**63 - 1
    for q, x in rows[::2]:
        all_of = sorted((-max(low, min(high, sum(a * b for a, b in zip(x, y)))), i) for i, y in rows if i != q)
        assert sorted(got[q]) == [(n + 1, i, -s) for n, (s, i) in enumerate(all_of[:5])]


def test_hot_keys_are_joined_apart(spark, monkeypatch):
    monkeypatch.setattr(joins, "HOT_ROWS", 3)
    rows = spark.createDataFrame([(k, i) for k in (1, 1, 1, 1, 2, 2, 3) for i in range(1)], "k long, v long")
    table = stage(spark.createDataFrame([(1, 4, "a"), (2, 2, "b"), (3, 1, "c")], "k long, size long, name string"))
    got = joins.join_hot_apart(rows, table, ["k"], "size").select("k", "name").collect()
    assert sorted(map(tuple, got)) == sorted((k, "abc"[k - 1]) for k in (1, 1, 1, 1, 2, 2, 3))


def test_an_anchor_with_many_guests_is_compared_in_blocks():
    rng = np.random.default_rng(4)
    homes = rng.integers(0, 1 << 62, 30)
    guests = np.concatenate([homes ^ (1 << int(b)) for b in rng.integers(0, 62, 20)] + [rng.integers(0, 1 << 62, 500)])
    spans = []
    for block, width in ((512, 8192), (7, 13)):
        edges = simhash._forest(homes, guests, block, width)
        spans.append({(min(a, b), max(a, b)) for x, y in edges for a, b in zip(x.tolist(), y.tolist())})
    assert len(spans[0]) == len(spans[1]) > 400


def test_words_end_at_all_white_space():
    blanks = [chr(c) for c in range(0x3001) if chr(c).isspace()]
    texts = ["a" + b + "b" + b for b in blanks] + [" \u00a0\n", "\n", "", "a\u200bb"]
    rng = np.random.default_rng(1)
    for _ in range(300):
        some = [texts[i] for i in rng.integers(0, len(texts), 4)]
        bounds, words = word_lists(pa.array(some), unicode=True)
        assert [words.to_pylist()[a:b] for a, b in zip(bounds, bounds[1:])] == [t.split() for t in some]


def test_semi_join_by_id(spark, monkeypatch):
    docs = frame(spark, ["a", "b", "c"], ids=[1, None, 2])
    ids = spark.createDataFrame([(1,), (None,), (1,)], "doc_id long")
    assert joins.with_ids(docs, ids).count() == 2
    monkeypatch.setattr(joins, "BROADCAST_IDS", 0)
    assert joins.with_ids(docs, ids).count() == 2


@pytest.mark.parametrize("copies", [2, 11, 15])
def test_top_k_with_repeated_query_rows(spark, copies):
    data = [(0, [1000, 0])] * copies + [(i, [1000 - 10 * i, i]) for i in range(1, 31)]
    df = spark.createDataFrame(data, "vec_id long, v array<long>")
    got = [(r["rank"], r.vec_id, r.score) for r in neighbors.top_k(df.where("vec_id = 0"), df).orderBy("rank").collect()]
    assert got == [(i, i, 1000 * (1000 - 10 * i)) for i in range(1, 11)]


def test_pairs_of_head_words_travel_as_numbers(spark):
    docs = spark.createDataFrame([(1, "a b a b", True), (2, "a b", False)], "doc_id long, text string, in_target boolean")
    shared = lmscore.Shared(stage(lmscore.counted(docs, np.zeros(0, np.uint64))), 100)
    rows = lmscore.pair_losses(docs, shared).where("code >= 0").collect()
    assert rows and all(r.p < -1 and r.g == 1 and r.code in (0, 1) for r in rows)
