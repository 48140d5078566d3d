"""The pipeline's stages, each against what its operator alone says, and the whole run."""

import collections
import random

import corpus_pipeline
from dyngraph.llm import registry
from pyspark.sql import functions as F


def test_stages(spark, sf, docs):
    base = spark.read.parquet(f"{sf}/documents.parquet").limit(60)
    odd = docs.select(*base.columns)
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "line_dedup", "simhash_dedup", "decontamination", "packing"]
    now = base.unionByName(odd)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r["doc_id"] for r in now.select("doc_id").collect()}
        out = stage(spark, now, sf)
        assert out.columns == base.columns
        assert {r["doc_id"] for r in out.select("doc_id").collect()} <= before
        now = corpus_pipeline.written(out, name)
        if name == "language_id":
            assert not {200, 201, 202, 203} & {r["doc_id"] for r in now.collect()}
        if name == "line_dedup":
            assert now.where("n_chars <> length(text)").count() == 0
        if name == "simhash_dedup":
            assert {r["doc_id"] for r in now.where("doc_id in (3, 100)").collect()} <= {3}
    packed = corpus_pipeline.STAGES[-1][1](spark, now, sf)
    kept = collections.Counter(r["doc_id"] for r in now.collect())
    assert collections.Counter(r["doc_id"] for r in packed.where("piece = 0").collect()) == kept


def test_run_and_registry(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    assert out.count() > 0 and out.agg(F.max(F.col("offset") + F.col("length"))).first()[0] <= 4096
    names = registry.queries()
    assert {f"op{i}" for i in range(1, 11)} == {n.split("_")[0] for n in names if n.startswith("op")} and "pipeline" in names


def test_near_copies_go(spark):
    """Planted copies with single words altered, and unlike documents, against exact Jaccard similarity of all pairs."""
    rng = random.Random(12)
    vocabulary = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 8))) for _ in range(900)]
    texts = [[rng.choice(vocabulary) for _ in range(rng.choice((3, 8, 200, 300, 400)))] for _ in range(60)]
    for words in texts[:60]:
        copy = list(words)
        for _ in range(rng.randint(1, 5)):
            copy[rng.randrange(len(copy))] = "altered"
        texts.append(copy)
    texts += [[], [], texts[0]]
    rows = [(i, " ".join(w)) for i, w in enumerate(texts)] + [(9000, None), (None, "no id")]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set() for w in [*texts, []]]
    ids = [i for i, _ in rows[:-1]]
    root = list(range(len(sets)))
    for i, a in enumerate(sets):
        for j in range(i):
            if len(a & sets[j]) >= 0.8 * len(a | sets[j]):
                x, y = sorted((root[i], root[j]))
                root = [x if r == y else r for r in root]
    expect = {ids[i] for i in range(len(sets)) if root[i] == i} | {None}
    assert sum(root[60 + i] == root[i] for i in range(60)) > 20
    got = corpus_pipeline.drop_near_duplicates(spark, spark.createDataFrame(rows, "doc_id long, text string"), "")
    assert {r["doc_id"] for r in got.collect()} == expect


def test_fingerprints_find_near_copies(spark):
    """The document stage's SimHash tiles alone give the pairs of a long text and its copies, equal fingerprints included."""
    from dyngraph.llm import simhash_tiles

    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 8)))
    words = [word() for _ in range(3000)]
    texts = [words, words[:-1] + ["altered"], [word() for _ in range(3000)], words]
    prints = [simhash_tiles.fingerprint(" ".join(w), 5) for w in texts]
    assert (prints[0] ^ prints[1]).bit_count() <= 3 < (prints[0] ^ prints[2]).bit_count()
    signed = [x - (1 << 64) if x >> 63 else x for x in prints]
    pairs = simhash_tiles.printed_pairs(spark.createDataFrame(list(enumerate(signed)), "id long, fp long")).collect()
    group = {0}
    for _ in pairs:
        group |= {i for p in pairs for i in p if set(p) & group}
    assert group == {0, 1, 3}


def test_sets_of_shingles_need_little_disk(spark):
    """What the document stage has written at once is less than 0.9 of its texts: sets of shingles are kept of candidates only."""
    from dyngraph import storage

    rng = random.Random(4)
    texts = [[rng.choice("abcdefghijklmnopqrstuvwxyz") + str(rng.randrange(10**6)) for _ in range(600)] for _ in range(200)]
    texts += [words[:-2] + ["altered"] for words in texts[:3]]
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(texts)] + [(0, " ".join(texts[0]))] * 3, "doc_id long, text string")
    with storage.peak() as all_texts:
        docs = storage.written(docs, "texts")
    with storage.peak() as all_written:
        got = corpus_pipeline.drop_near_duplicates(spark, docs, "")
    assert sorted(r["doc_id"] for r in got.collect()) == list(range(200))
    assert all_written["bytes"] < 0.9 * all_texts["bytes"]


def test_language_stage_sends_no_text(spark, sf):
    """The rejected documents are few and are broadcast, so that the stage has no shuffle of texts."""
    out = corpus_pipeline.identify_language(spark, spark.read.parquet(f"{sf}/documents.parquet"), sf)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "hashpartitioning" not in plan
