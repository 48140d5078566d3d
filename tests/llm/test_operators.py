"""Each operator against a brute-force version, on rows with nulls, blanks, repeats, copies and long texts."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from dyngraph import storage
from dyngraph.llm import brown_lm, column_bwt, common, decontaminate, fuzzy_lines, quality_ftrl, shard_ring, simhash_tiles, string_kernel, term_topk, vector_packing


def key(x):
    return (x is not None, x)


# ---- sharing code -----------------------------------------------------------------------------------------------------


def test_components(spark):
    pairs = [(5, 9), (9, 2), (7, 8), (4, 4), (20, 21), (21, 22), (22, 23), (23, 24), (24, 25), (-3, 25)]
    got = dict(common.components(spark.createDataFrame(pairs, "u long, v long")).collect())
    assert got == {2: 2, 5: 2, 9: 2, 7: 7, 8: 7, **{k: -3 for k in (-3, 20, 21, 22, 23, 24, 25)}}


def test_block_masks_leave_one_clean():
    rng = np.random.default_rng(1)
    for count in (10, 1 << 26, 1 << 35):
        masks = [m & (1 << 64) - 1 for m in common.block_masks(count, 3)]
        for _ in range(200):
            flip = sum(1 << int(b) for b in rng.choice(64, 3, replace=False))
            assert any(flip & m == 0 for m in masks)


def test_ranked_is_gapless(spark):
    df = spark.range(500).selectExpr("id % 3 AS k", "id AS x").repartition(7)
    got = collections.defaultdict(list)
    for r in common.ranked(df, ["k"], ["x"], salts=5).collect():
        got[r["k"]].append(r["rank"])
    assert all(sorted(v) == list(range(len(v))) for v in got.values())


# ---- 1 ----------------------------------------------------------------------------------------------------------------


def test_sharding(docs, rows, empty):
    got = shard_ring.shard_documents(docs, 5).collect()
    assert len(got) == len(rows)
    sizes = collections.Counter(r["shard"] for r in got)
    assert max(sizes.values()) - min(sizes.values()) <= 1
    for s in range(5):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sizes[s]))
    expect = sorted(((d, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for d, t in rows), key=lambda r: (key(r[0]), r))
    assert sorted(((r["doc_id"], r["size"], r["text_crc32"]) for r in got), key=lambda r: (key(r[0]), r)) == expect
    assert shard_ring.shard_documents(empty).count() == 0


def test_ring_moves_little_with_slack():
    counts = {p: 3 for p in range(0, shard_ring.POSITIONS, 7)}
    total = sum(counts.values())

    def owner(shards):
        out = {}
        for p, a, b, s, _, _ in shard_ring.walk(counts, shard_ring.ring(shards), shard_ring.capacities(total, shards, 0.25)):
            for i in range(a, b):
                out[p, i] = s
        return out

    a, b = owner(10), owner(11)
    load = collections.Counter(b.values())
    assert max(load.values()) <= math.ceil(1.25 * total / 11)
    assert sum(a[k] != b[k] for k in a) / total < 2.5 / 11


def test_ring_overflow_goes_clockwise():
    nodes = [(10, 0), (20, 1), (30, 2)]
    runs = shard_ring.walk({5: 5, 15: 1}, nodes, [2, 2, 2])
    assert runs == [(5, 0, 2, 0, 0, 0), (5, 2, 4, 1, 0, 0), (5, 4, 5, 2, 0, 0), (15, 0, 1, 2, 1, 1)]


# ---- 2 ----------------------------------------------------------------------------------------------------------------


def words(t):
    import regex

    return regex.sub(r"[^\p{L}\p{N}]+", " ", (t or "").lower()).split()


def grams(ws, n):
    return {" ".join(ws[i : i + n]) for i in range(len(ws) - n + 1)}


def test_decontamination(spark, docs, rows, empty):
    by = dict(rows)
    items = [(1, by[103]), (2, " ".join(by[103].split()[:20])), (3, "Two, words!"), (4, None), (5, "!!"), (6, "never seen in any of these"), (7, " ".join(by[300].split()[50:90]) + " new tail words"), (None, by[103])]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r[0], r[1]): r[2] for r in decontaminate.contaminated(docs, bench).collect()}
    expect = {}
    for d, t in rows:
        for i, x in items:
            if d is None or i is None or not words(x):
                continue
            n = min(5, len(words(x)))
            want = grams(words(x), n)
            share = len(want & grams(words(t), n)) / len(want)
            if share >= 0.8:
                expect[d, i] = max(share, expect.get((d, i), 0))
    assert got == pytest.approx(expect) and (300, 7) in got and (206, 3) in got and (301, 1) in got
    kept = {r["doc_id"] for r in decontaminate.clean(docs, bench).collect()}
    assert kept == {d for d, _ in rows} - {d for d, _ in expect}
    assert decontaminate.contaminated(docs, bench.limit(0)).count() == 0
    assert decontaminate.contaminated(empty, bench).count() == 0
    big = decontaminate.BROADCAST_ROWS
    try:
        decontaminate.BROADCAST_ROWS = 0  # the shuffled way gives the same
        assert {(r[0], r[1]) for r in decontaminate.contaminated(docs, bench).collect()} == set(expect)
    finally:
        decontaminate.BROADCAST_ROWS = big


# ---- 3 and 8 ------------------------------------------------------------------------------------------------------------


def test_quality(spark, docs, rows, empty):
    labels = spark.createDataFrame([(d, int("a" in (t or "")[:20]), 0) for d, t in rows if d is not None and d < 40] + [(None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    got = quality_ftrl.classify(docs, labels).collect()
    assert len(got) == len(rows)
    for r in got:
        assert 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.3)
        assert r["held_out"] == (r["doc_id"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0)
    assert quality_ftrl.classify(empty, labels).count() == 0
    assert quality_ftrl.classify(docs, labels.limit(0)).count() == len(rows)


def test_quality_learns(spark, sf):
    d, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    got = quality_ftrl.classify(d, labels).join(labels, "doc_id").toPandas()
    a, b = got[got.quality == 1].score.to_numpy(), got[got.quality == 0].score.to_numpy()
    assert (a[:, None] > b).mean() > 0.9


def test_ftrl_matches_the_closed_form():
    m = quality_ftrl.Ftrl(3, alpha=0.3, beta=1.0, l1=0.05, l2=0.2)
    rng = np.random.default_rng(0)
    grads, total, weights = np.zeros(4), np.zeros(4), []
    for _ in range(30):
        at, x, y = np.array([0, 2]), rng.uniform(size=2), float(rng.integers(2))
        full = np.array([0, 2, 3])
        w = m.weights(full)
        g = np.zeros(4)
        g[full] = (quality_ftrl.sigmoid(w @ np.append(x, 1)) - y) * np.append(x, 1)
        before, after = np.sqrt(total), np.sqrt(total + g * g)
        wfull = np.zeros(4)
        wfull[full] = w
        grads += g - (after - before) / 0.3 * wfull
        total += g * g
        m.learn(at, x, y)
    assert np.allclose(grads, m.z) and np.allclose(total, m.n)


def test_language(docs, rows, empty):
    got = string_kernel.predict(docs).collect()
    assert len(got) == len(rows)
    for r in got:
        text = dict(rows)[r["doc_id"]]
        assert (r["lang_pred"] == "und") == (not any(c.isalpha() for c in text or ""))
        assert r["lang_pred"] in ("en", "de", "und") and 0 <= r["score"] <= 1
    assert string_kernel.predict(empty).count() == 0
    assert {r["lang_pred"] for r in string_kernel.identify(docs, None).collect()} == {"und"}


def test_language_learns(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    got = string_kernel.predict(d).join(d.select("doc_id", "lang"), "doc_id").where("held_out")
    assert got.where("lang = lang_pred").count() >= 0.95 * got.count()


def test_presence_counts_distinct_grams():
    a, b = string_kernel.presence("Ab, ab"), string_kernel.presence("ab")
    assert a.sum() >= b.sum() and (a[b == 1] == 1).all() and string_kernel.presence("12 ?") is None


# ---- 4 ----------------------------------------------------------------------------------------------------------------


def test_language_model(docs, rows, empty):
    got = brown_lm.evaluate(docs, types=50, classes=4, held=80).collect()
    token = lambda t: (t or "").encode().lower().split() + [b"\n"]
    seen = collections.Counter()
    for d, t in rows:
        if d is not None and zlib.crc32(str(d).encode()) % 7 != 2:
            seen.update(token(t))
    n, v = sum(seen.values()), len(seen)
    texts = collections.defaultdict(list)
    for d, t in rows:
        texts[d].append(t)
    assert len(got) == len(rows)
    for r in got:
        ts = token(texts[r["doc_id"]][0])
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(ts), sum(seen[w] > 0 for w in ts), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((seen[w] + 1) / (n + v + 1)) for w in ts))
        assert r["score"] < 0 and math.isfinite(r["score"])
    assert brown_lm.evaluate(empty).count() == 0


def test_language_model_against_plain_counts(spark, docs, rows):
    """Classes of the words outside the first exchange, and every text's score, from token sequences in plain loops."""
    learn = docs.where(F.col("doc_id").isNotNull() & ~brown_lm.held_out(7, 2))
    counts, model = brown_lm.train(learn, types=40, classes=4, held=120)
    texts = [brown_lm.tokens(r["text"]) + [brown_lm.END.encode()] for r in learn.select("text").collect()]
    words = model["words"].split(b"\n")
    place, classes, end = {w: i for i, w in enumerate(words)}, 4, 4 + brown_lm.FORMS
    width = end + 1
    assert len(words) == 120 and len(model["class"]) == 120 and set(model["class"]) <= set(range(4))

    def label(w, of):
        return end if w == brown_lm.END.encode() else of[place[w]] if w in place and place[w] < len(of) else classes + brown_lm.form(w)

    def transitions(of):
        m = np.zeros((width, width))
        for t in texts:
            for a, b in zip([end] + [label(w, of) for w in t], [label(w, of) for w in t]):
                m[a, b] += 1
        return m

    first, m = model["class"][:40], transitions(model["class"][:40])
    for w in words[40:]:
        before, after = np.zeros(width), np.zeros(width)
        for t in texts:
            c = [end] + [label(x, first) for x in t] + [end]
            for i, x in enumerate(t):
                if x == w:
                    before[c[i]] += 1
                    after[c[i + 2]] += 1
        x = lambda v: v * math.log(v) if v > 0 else 0.0
        gain = [
            sum(x(m[k, j] + after[j]) - x(m[k, j]) + x(m[j, k] + before[j]) - x(m[j, k]) for j in range(width))
            - x(m[k].sum() + after.sum()) + x(m[k].sum()) - x(m[:, k].sum() + before.sum()) + x(m[:, k].sum())
            for k in range(classes)
        ]
        assert gain[model["class"][place[w]]] == pytest.approx(max(gain), abs=1e-9)
    m = transitions(model["class"])
    n = collections.Counter(w for t in texts for w in t)
    seen = m.sum(0)
    unigram = (seen + 0.5) / (seen.sum() + 0.5 * width)
    log_t = np.log10((m + unigram) / (m.sum(1, keepdims=True) + 1))
    inside = [sum(n[w] for w in words if model["class"][place[w]] == k) for k in range(classes)]
    types = collections.Counter(brown_lm.form(w) for w in n if w not in place and w != brown_lm.END.encode())
    expect = collections.Counter()
    for d, text in rows:
        t = brown_lm.tokens(text) + [brown_lm.END.encode()]
        c = [end] + [label(w, model["class"]) for w in t]
        total = sum(log_t[a, b] for a, b in zip(c, c[1:]))
        for w, k in zip(t[:-1], c[1:]):
            total += math.log10(n[w] / inside[k]) if w in place else math.log10((n[w] + 1) / (seen[k] + types[k - classes] + 1))
        expect[d, round(total, 6)] += 1
    got = collections.Counter((r["doc_id"], round(r["score"], 6)) for r in brown_lm.score(docs, counts, model).collect())
    assert got == expect


def test_every_word_has_a_learnt_class(docs, rows):
    """However few words are held: classes and scores from token sequences in plain loops."""
    learnt = F.col("doc_id").isNotNull() & ~brown_lm.held_out(7, 2)
    _, model = brown_lm.fit(docs, learnt, types=40, classes=4, held=100_000)
    words, end = model["words"].split(b"\n"), 4 + brown_lm.FORMS
    of, width = dict(zip(words, model["class"].tolist())), end + 1
    split = lambda t: brown_lm.tokens(t) + [brown_lm.END.encode()]
    texts = [split(t) for d, t in rows if d is not None and zlib.crc32(str(d).encode()) % 7 != 2]
    n = collections.Counter(w for t in texts for w in t)
    assert set(n) == {*words, brown_lm.END.encode()} and len(words) > 120
    first = {w: of[w] if i < 40 else 4 + brown_lm.form(w) for i, w in enumerate(words)} | {brown_lm.END.encode(): end}
    m, near = np.zeros((width, width)), collections.defaultdict(lambda: np.zeros((2, width)))
    for t in texts:
        c = [end] + [first[w] for w in t]
        for a, b in zip(c, c[1:]):
            m[a, b] += 1
        for i, w in enumerate(t[:-1]):
            near[w][0, c[i]] += 1
            near[w][1, c[i + 2]] += 1
    x = lambda v: v * np.log(np.maximum(v, 1e-300))
    for w in words[40:]:
        before, after = near[w]
        gain = [
            (x(m[k] + after) - x(m[k]) + x(m[:, k] + before) - x(m[:, k])).sum() - x(m[k].sum() + after.sum()) + x(m[k].sum()) - x(m[:, k].sum() + before.sum()) + x(m[:, k].sum())
            for k in range(4)
        ]
        assert gain[of[w]] == pytest.approx(max(gain), abs=1e-6)
    # a word that training has once counts as a new one of its form too
    m = np.zeros((width, width))
    label = lambda w: [end] if w == brown_lm.END.encode() else [of[w], 4 + brown_lm.form(w)] if n[w] == 1 else [of[w]]
    for t in texts:
        c = [[end]] + [label(w) for w in t]
        for a, b in zip(c, c[1:]):
            for i in a:
                for j in b:
                    m[i, j] += 1
    seen = m.sum(0)
    log_t = np.log10((m + (seen + 0.5) / (seen.sum() + 0.5 * width)) / (m.sum(1, keepdims=True) + 1))
    inside = [sum(n[w] for w in words if of[w] == k) for k in range(4)]
    expect = collections.Counter()
    for d, t in rows:
        c, total = [end], 0.0
        for w in split(t):
            c.append(end if w == brown_lm.END.encode() else of.get(w, 4 + brown_lm.form(w)))
            total += log_t[c[-2], c[-1]]
            if c[-1] != end:
                total += math.log10(n[w] / inside[of[w]]) if w in of else -math.log10(seen[c[-1]] + 1)
        expect[d, round(total, 5)] += 1
    for held in (50, 100_000):
        got = brown_lm.evaluate(docs, types=40, classes=4, held=held).collect()
        assert collections.Counter((r["doc_id"], round(r["score"], 5)) for r in got) == expect


def test_exchange_never_lowers_the_likelihood():
    rng = np.random.default_rng(2)
    pairs = rng.poisson(2.0, (30, 30)).astype(float)
    pairs[:10, 10:20] += 20
    pairs[10:20, :10] += 20

    def likelihood(of, size):
        m = np.eye(size)[of].T @ pairs @ np.eye(size)[of]
        f = lambda x: (x * np.log(np.maximum(x, 1e-300))).sum()
        return f(m) - f(m.sum(0)) - f(m.sum(1))

    start = np.concatenate([np.arange(25) % 3, 3 + np.arange(5)])
    of = brown_lm.exchange(pairs, 25, 3, 5)
    assert likelihood(of, 8) > likelihood(start, 8)
    for w in range(25):  # no single move is better
        for c in range(3):
            other = of.copy()
            other[w] = c
            assert likelihood(other, 8) <= likelihood(of, 8) + 1e-6


def test_forms_agree(spark):
    ws = ["a.", "b,", "c!", "d", "é", "é.", "x]", "~", "9"]
    got = spark.createDataFrame([(w,) for w in ws], "token string").select("token", brown_lm.form_sql(F.col("token")).alias("f")).collect()
    assert all(brown_lm.form(r["token"].encode()) == r["f"] for r in got)


# ---- 5 ----------------------------------------------------------------------------------------------------------------


def slow_print(t):
    ws = (t or "").encode().lower().split()
    if not ws:
        return 0
    hs = [xxhash.xxh64_intdigest(b" ".join(ws[i : i + 3]), 42) for i in range(max(1, len(ws) - 2))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def linked(values, radius):
    values = sorted(set(values))
    root = {v: v for v in values}

    def find(v):
        while root[v] != v:
            v = root[v]
        return v

    for i, a in enumerate(values):
        for b in values[:i]:
            if (a ^ b).bit_count() <= radius:
                root[find(a)] = find(b)
    return {v: find(v) for v in values}


@pytest.mark.parametrize("tile", [2, 1024])
def test_simhash(docs, rows, empty, tile):
    got = simhash_tiles.near_duplicates(docs, tile=tile).collect()
    prints = [(d, slow_print(t)) for d, t in rows]
    root = linked([p for _, p in prints], 3)
    least = {}
    for d, p in prints:
        if d is not None:
            least[root[p]] = min(d, least.get(root[p], d))
    expect = sorted(((d, f"{p:016x}", least.get(root[p])) for d, p in prints), key=lambda r: (key(r[0]), r))
    assert sorted(map(tuple, got), key=lambda r: (key(r[0]), r)) == expect
    assert simhash_tiles.near_duplicates(empty).count() == 0


def test_tiles_lose_no_link(spark):
    rng = np.random.default_rng(4)
    base = rng.integers(0, 1 << 63, 30, dtype=np.uint64)
    some = [int(b) for b in base]
    for b in base[:10]:
        for _ in range(8):
            some.append(int(b) ^ sum(1 << int(i) for i in rng.choice(64, int(rng.integers(1, 5)), replace=False)))
    signed = [(v - (1 << 64) if v >> 63 else v,) for v in set(some)]
    links = simhash_tiles.links(spark.createDataFrame(signed, "fp long"), 3, 4)
    got = dict(common.components(links).collect())
    root = linked([v for (v,) in ((x & (1 << 64) - 1,) for (x,) in signed)], 3)
    groups = collections.defaultdict(set)
    for v, r in root.items():
        groups[r].add(v - (1 << 64) if v >> 63 else v)
    for g in groups.values():
        assert len({got.get(v, v) for v in g}) == 1
    assert len({got.get(v, v) for (v,) in signed}) == len(groups)


# ---- 6 ----------------------------------------------------------------------------------------------------------------


def slow_removal(rows, length):
    first, out = {}, []
    texts = [(d, (t or "").encode()) for d, t in rows]
    for d, b in texts:
        if d is not None:
            for s in range(len(b) - length + 1):
                w = b[s : s + length]
                first[w] = min(d, first.get(w, d))
    for d, b in texts:
        cover = bytearray(len(b))
        for s in range(len(b) - length + 1) if d is not None else ():
            if first[b[s : s + length]] < d:
                cover[s : s + length] = b"\1" * length
        kept = bytes(x for x, c in zip(b, cover) if not c)
        out.append((d, len(b), len(b) - len(kept), sum(1 for i, c in enumerate(cover) if c and (not i or not cover[i - 1])), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=lambda r: (key(r[0]), r))


@pytest.mark.parametrize("flush", [50, 700_000])
def test_passages(docs, rows, empty, monkeypatch, flush):
    got = column_bwt.report(docs)
    assert sorted(map(tuple, got.collect()), key=lambda r: (key(r[0]), r)) == slow_removal(rows, 50)
    assert column_bwt.report(empty).count() == 0


def test_passages_in_repetitive_texts(spark):
    rows = [(1, "ab" * 60), (2, "ab" * 40 + "c"), (3, "x" + "ab" * 30), (4, "a" * 200), (5, "a" * 60), (6, "ß" * 40), (7, "ß" * 30), (7, "other text under the same id " * 4), (8, "other text under the same id " * 3)]
    got = column_bwt.report(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted(map(tuple, got.collect()), key=lambda r: (key(r[0]), r)) == slow_removal(rows, 50)


def test_suffix_order_is_sorted():
    rng = np.random.default_rng(7)
    for _ in range(20):
        pieces = [bytes(rng.integers(97, 99, int(rng.integers(0, 15))).astype(np.uint8)) for _ in range(25)]
        piece, start = column_bwt.suffix_order(pieces)
        got = [(pieces[p][s:], p) for p, s in zip(piece, start)]
        assert got == sorted(got) and len(got) == sum(map(len, pieces))


def test_spans_cover_each_passage_once():
    rng = np.random.default_rng(8)
    data = bytes(rng.integers(97, 123, 700_000).astype(np.uint8))  # more than two chunks
    _, _, at, n = column_bwt.spans(data)
    assert at[0] == 0 and (at[1:] == at[:-1] + n[:-1]).all() and at[-1] + n[-1] == len(data) - 49 and n.max() <= 27
    assert len(column_bwt.spans(b"short")[0]) == 0


# ---- 7 ----------------------------------------------------------------------------------------------------------------


def check_bins(histogram, rows, cap, docs, attention):
    bins = collections.defaultdict(list)
    ranks = collections.defaultdict(list)
    for length, lo, hi, first, each, offset in rows:
        for r in range(lo, hi):
            bins[first + (r - lo) // each].append((offset + (r - lo) % each * length, length))
        ranks[length] += range(lo, hi)
    assert {k: sorted(v) for k, v in ranks.items()} == {k: list(range(v)) for k, v in histogram.items()}
    for items in bins.values():
        items.sort()
        at = 0
        for offset, length in items:
            assert offset == at
            at += length
        assert at <= cap and len(items) <= docs and sum(x**2 for _, x in items) <= attention
    return len(bins)


@pytest.mark.parametrize("rule", ["norm", "dot"])
def test_best_fit(rule):
    rng = np.random.default_rng(5)
    for limits in ((100, 100, 10_000), (100, 3, 10_000), (100, 100, 4000)):
        lengths = rng.integers(1, 60, 400)
        histogram = dict(collections.Counter(lengths.tolist()))
        rows = vector_packing.choose(histogram, *limits, rule=rule, weights=(1.0, 0.3, 0.3))
        n = check_bins(histogram, rows, *limits)
        if rule == "norm" and limits[1] == 100 and limits[2] == 10_000:
            assert n <= math.ceil(lengths.sum() / 100) + 1
    with pytest.raises(ValueError):
        vector_packing.choose({101: 1}, 100)


def test_packing(docs, rows, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    got = vector_packing.pack_documents(docs, max_tokens=512).collect()
    expect = collections.Counter()
    for d, t in rows:
        ids = model.encode(t or "", add_special_tokens=False).ids + [1]
        for p, at in enumerate(range(0, len(ids), 512)):
            part = np.array(ids[at : at + 512], "<u4")
            expect[d, p, at, len(part), zlib.crc32(part.tobytes())] += 1
    assert collections.Counter(tuple(r)[:5] for r in got) == expect
    by = collections.defaultdict(list)
    for r in got:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for places in by.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 512
    assert len(by) <= math.ceil(sum(r["length"] for r in got) / 512) + 1
    assert vector_packing.pack_documents(empty).count() == 0


@pytest.mark.parametrize("limits", [{"max_docs": 3}, {"max_attention": 60_000}, {"max_docs": 4, "max_attention": 90_000, "rule": "dot"}])
def test_packing_under_every_capacity(docs, limits):
    """Document and attention capacities that bind, through the whole operator; weights of capacities that don't bind cost no sequence."""
    sequences = lambda **how: vector_packing.pack_documents(docs, max_tokens=512, piece_tokens=200, **how)
    bins = collections.defaultdict(list)
    for r in sequences(**limits).collect():
        bins[r["sequence_id"]].append(r["length"])
    for b in bins.values():
        assert sum(b) <= 512 and len(b) <= limits.get("max_docs", 512) and sum(x * x for x in b) <= limits.get("max_attention", 512**2)
    plain, full = (sequences(weights=w).select("sequence_id").distinct().count() for w in ((1.0, 0.0, 0.0), (1.0, 0.3, 0.3)))
    assert full <= plain < len(bins)


def test_tokens_by_word_equal_whole_texts():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    model = Tokenizer.from_file(path)
    texts = ["It's A Test: don't, 'll ÄÖ ß İ ΣΑΣ", "a<|endoftext|>b <|ENDOFTEXT|>", "x y z\tw\r\nv", "é ́ ﬁ ①", "A<|endoftext|> Upper Stays", ""]
    for t, b in zip(texts, vector_packing.token_bytes(texts, path)):
        assert np.frombuffer(b, "<u4").tolist() == model.encode(t, add_special_tokens=False).ids, t


# ---- 9 ----------------------------------------------------------------------------------------------------------------


def test_top_k(spark):
    rng = np.random.default_rng(6)
    vectors = [(i, [float(x) for x in np.round(rng.normal(size=6), 2)]) for i in range(120)]
    vectors += [(200 + i, vectors[0][1]) for i in range(9)] + [(300, None), (301, [1.0, None, 2.0, 0.0, 0.0, 0.0]), (302, [float("nan")] * 6), (303, [float("inf")] * 6), (350, [0.5, -0.25]), (400, []), (None, [1.0] * 6)]
    df = spark.createDataFrame(vectors, "vec_id long, embedding array<float>").selectExpr("*", "1 AS score", "2 AS rank").repartition(5)
    ok = {i: [math.floor(256 * float(np.float32(x))) for x in v] for i, v in vectors if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)}
    expect = []
    for q, a in ok.items():
        if q % 50 == 0:
            scored = sorted((-sum(x * y for x, y in zip(a, b)), i) for i, b in ok.items() if i != q)
            expect += [(q, r + 1, i, -s) for r, (s, i) in enumerate(scored[:5])]
    got = term_topk.top_k(df, candidates=16, queries=2).collect()
    assert sorted(map(tuple, got)) == sorted(expect)
    assert term_topk.top_k(df.limit(0)).count() == 0
    assert term_topk.top_k(df.where("vec_id in (50, 51)")).count() == 1


# ---- 10 ---------------------------------------------------------------------------------------------------------------


def slow_lines(rows, similarity=0.8):
    """Removed lines by doc_id if all pairs of lines of that edit similarity are linked."""
    import regex

    lines = []
    for d, t in rows:
        for i, x in enumerate((t or "").split("\n")):
            norm = regex.sub(r"[^\p{L}\p{N}]+", " ", x.lower()).strip()
            if norm and d is not None:
                lines.append((d, i, norm))
    lines.sort()
    first = {}
    for d, i, norm in lines:
        first.setdefault(norm, (d, i))

    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, c in enumerate(a, 1):
            new = [i]
            for j, e in enumerate(b, 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != e)))
            row = new
        return row[-1]

    names = list(first)
    root = list(range(len(names)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(names):
        for j in range(i):
            b = names[j]
            if abs(len(a) - len(b)) <= max(len(a), len(b)) * (1 - similarity) + 1e-9 and distance(a, b) <= max(len(a), len(b)) * (1 - similarity) + 1e-9:
                root[find(i)] = find(j)
    keep = {}
    for i, x in enumerate(names):
        keep[find(i)] = min(first[x], keep.get(find(i), first[x]))
    at = {x: i for i, x in enumerate(names)}
    gone = collections.defaultdict(set)
    for d, i, norm in lines:
        if keep[find(at[norm])] != (d, i):
            gone[d].add(i)
    return gone


@pytest.fixture(scope="module")
def lined(spark, docs):
    """The odd rows, and a long line in many variants of one letter or word."""
    base = "the quick brown fox jumps over the lazy dog and then it runs back to the old house near the river where all of its friends wait for it every single evening " * 6
    variants = [(1000 + i, base.strip() + f" tail{i % 9}", "en", "s", 0) for i in range(20)] + [(1100, "UPPER, " + base, "en", "s", 0), (1101, "a\r\n\r\nB  b\r\na", "en", "s", 0)]
    more = spark.createDataFrame(variants, "doc_id long, text string, lang string, source string, n_chars long")
    return docs.select("doc_id", "text", "lang", "source", "n_chars", "removed_lines").unionByName(more.selectExpr("*", "'x' AS removed_lines"))


def test_lines(lined, empty):
    rows = [(r["doc_id"], r["text"]) for r in lined.collect()]
    gone = slow_lines(rows)
    got = {r["doc_id"]: set(r["removed"]) for r in fuzzy_lines.decisions(lined).collect()}
    assert got == {d: gone[d] for d, _ in rows if d is not None}
    assert sum(map(len, gone.values())) > 20
    cleaned = collections.Counter((r["doc_id"], r["text"]) for r in fuzzy_lines.clean(lined).collect())
    expect = collections.Counter()
    for d, t in rows:
        expect[d, t if t is None else "\n".join(x for i, x in enumerate(t.split("\n")) if i not in gone.get(d, ()))] += 1
    assert cleaned == expect
    assert fuzzy_lines.decisions(empty).count() == 0 and fuzzy_lines.clean(empty).count() == 0


def test_native_plans(docs, spark):
    bench = spark.createDataFrame([(1, "a b c d e f")], "item_id long, text string")
    for df in (decontaminate.contaminated(docs, bench), fuzzy_lines.decisions(docs)):
        assert not re.search("Python|Arrow|Pandas", df._jdf.queryExecution().executedPlan().toString())


def edit_similarity(a, b):
    row = np.arange(len(b) + 1)
    for i, c in enumerate(a, 1):
        best = np.minimum(row[1:] + 1, row[:-1] + np.array([c != e for e in b], int))
        row = np.minimum.accumulate(np.concatenate([[i], best]) - np.arange(len(b) + 1)) + np.arange(len(b) + 1)
    return 1 - row[-1] / max(len(a), len(b), 1)


def test_similar_lines_are_found(spark):
    """Letters changed in lines of many lengths, of one word or in a script without spaces too."""
    rng = random.Random(8)
    word = lambda n, of="abcdefghijklmnoprstu": "".join(rng.choice(of) for _ in range(n))
    bases = [word(n) for n in range(5, 60)] + [word(n, "".join(map(chr, range(0x4E00, 0x5000)))) for n in range(12, 40)]
    bases += [" ".join(word(rng.randint(2, 9)) for _ in range(n)) for n in range(2, 40) for _ in range(3)]
    pairs = []
    for base in bases:
        for share in (0, 0.07):  # one letter, or seven of a hundred
            out = list(base)
            letters = [i for i, c in enumerate(out) if c != " "]
            for i in rng.sample(letters, max(1, int(len(out) * share))):
                out[i] = "z"
            pairs.append((base, "".join(out), share))
    rows = [(i, a) for i, (a, _, _) in enumerate(pairs)] + [(10000 + i, b) for i, (_, b, _) in enumerate(pairs)]
    gone = {r["doc_id"] for r in fuzzy_lines.decisions(spark.createDataFrame(rows, "doc_id long, text string")).where("n_removed > 0").collect()}
    assert all(edit_similarity(a, b) >= 0.8 for a, b, _ in pairs)
    found = lambda share: [10000 + i in gone for i, p in enumerate(pairs) if p[2] == share]
    assert all(10000 + i in gone for i, p in enumerate(pairs) if len(p[0]) <= 14)
    assert np.mean(found(0)) >= 0.98 and np.mean(found(0.07)) >= 0.9


def test_lines_need_little_disk(spark, sf):
    """What stands written at once is less than 2.1 times the normalised lines (2.4 when rows of keys were written three times)."""
    docs = common.table(spark, sf, "documents")
    with storage.peak() as all_written:
        assert fuzzy_lines.decisions(docs).agg(F.sum("n_removed")).first()[0] == 322
    with storage.peak() as lines:
        common.written(fuzzy_lines.occurrences(docs).select("norm"), "lines")
    assert all_written["bytes"] < 2.1 * lines["bytes"]


def test_no_other_lines_are_linked(spark):
    rng = random.Random(9)
    word = lambda n: "".join(rng.choice("abcd") for _ in range(n))
    names = sorted({word(rng.randint(2, 9)) for _ in range(80)} | {word(5) + " " + word(rng.randint(4, 8)) for _ in range(60)})
    got = {r["doc_id"] for r in fuzzy_lines.decisions(spark.createDataFrame(list(enumerate(names)), "doc_id long, text string")).where("n_removed > 0").collect()}
    root = list(range(len(names)))
    for i, a in enumerate(names):
        for j in range(i):
            if edit_similarity(a, names[j]) >= 0.8 - 1e-9:
                x, y = sorted((root[i], root[j]))
                root = [x if r == y else r for r in root]
    expect = {i for i in range(len(names)) if root[i] != i}
    assert got <= expect and {i for i in expect if len(names[i]) <= 11} <= got


def test_beginnings_reject_no_similar_lines(spark):
    """Lines are told apart by their beginnings only if all of their letters tell them apart too, which settles most unlike pairs."""
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcdefghijkl\u00f6") for _ in range(rng.randint(1, 9)))
    rows = []
    for n in (1, 2, 5, 20, 60):
        for _ in range(40):
            a = " ".join(word() for _ in range(n))
            b = list(a)
            for _ in range(rng.randint(0, len(a) // 3)):  # letters go, come, change, at one end or anywhere
                at = rng.choice((0, len(b), rng.randint(0, len(b))))
                b[at : at + rng.randint(0, 1)] = rng.choice(("", "x", "xy"))
            rows += [(a, "".join(b), False), (a, " ".join(word() for _ in range(n)), n >= 20)]
    df = spark.createDataFrame(rows, "a string, b string, unlike boolean").withColumn("allowed", F.floor(F.greatest(F.length("a"), F.length("b")) * 0.2 + 1e-9).cast("int"))
    df = df.select("unlike", F.expr("levenshtein(a, b) <= allowed").alias("similar"), fuzzy_lines._apart("a", "b", "allowed", 0.8).alias("apart"))
    got = df.collect()
    assert not [r for r in got if r["similar"] and r["apart"]] and sum(r["similar"] for r in got) > 60
    assert sum(r["apart"] for r in got if r["unlike"]) > 0.9 * sum(r["unlike"] for r in got)


def test_lines_of_repeated_words(spark):
    """Repeats count, so that lines that differ in a rare word beside a frequent one stay alike."""
    pairs = [("no no no no no yes", "no no no no no yep"), ("la " * 40 + "one two three", "la " * 40 + "one two tree")]
    rows = [(10 * j + i, line) for i, p in enumerate(pairs) for j, line in enumerate(p)]
    got = {r["doc_id"] for r in fuzzy_lines.decisions(spark.createDataFrame(rows, "doc_id long, text string")).where("n_removed > 0").collect()}
    assert got == {10, 11}
