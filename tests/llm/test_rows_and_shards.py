"""Rows that share ids, sets that share hashes, several shards, and the registered queries against brute force."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import public_tokenizers as P
from tests.llm.test_operators import DOC, ODD, brute_components, brute_passages, brute_spans, check_packing, docs, prose

DOCS = "documents"


def test_classes_survive_equal_fingerprints(spark, monkeypatch):
    """With fingerprints of a few bits, nodes of different sets must be told apart by the second hash."""
    from boxprune.llm import jaccard

    real = jaccard._fingerprints

    def weak(own, sh, n):
        size, node, more = real(own, sh, n)
        return size, node % np.uint64(7), more

    monkeypatch.setattr(jaccard, "_fingerprints", weak)
    rng = np.random.default_rng(1)
    texts = [prose(rng, 40) for _ in range(20)]
    texts += [f"{texts[2]} more", texts[3]]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.jaccard_components(docs(spark, texts)).collect()}
    assert got == dict(enumerate(brute_components(texts, 3, 90, 100)))


def test_rows_without_id_and_with_equal_ids(spark):
    from boxprune.llm.jaccard import jaccard_components

    text = "one two three four five six seven eight nine ten eleven twelve"
    rows = [(None, text), (5, text), (7, f"{text} end"), (7, "a b c d"), (None, None), (None, "x y z w"), (None, "x y z w")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r.n_shingles, r.component_id or -1) for r in jaccard_components(df).collect())
    assert got == sorted([(10, 5), (10, 5), (11, 5), (2, 7), (0, -1), (2, -1), (2, -1)])


def test_pipeline_judges_rows_not_ids(spark):
    import corpus_pipeline as c

    rng = np.random.default_rng(2)
    good = [prose(rng, 60, 3000) for _ in range(4)]
    rows = [(1, good[0]), (1, "short"), (None, good[1]), (None, "short"), (2, good[2]), (3, f"{good[2]} end"), (3, good[3]), (4, good[3]), (4, good[3]), (None, good[0]), (1, good[0])]
    df = spark.createDataFrame([(i, t, "en", "h", 1) for i, t in rows], DOC)
    kept = c.quality_stage(spark, df, "")
    assert kept.columns == df.columns and sorted(r.text for r in kept.collect()) == sorted(t for _, t in rows if t != "short")
    left = c.near_duplicate_stage(spark, kept, "")
    assert left.columns == df.columns
    assert sorted((r.doc_id or -1, r.text) for r in left.collect()) == sorted([(1, good[0]), (-1, good[1]), (2, good[2]), (3, good[3])])


def test_a_host_fails_by_any_rule(spark):
    from boxprune.llm.quality import HOST_RULES, keep_good, quality_verdicts

    rng = np.random.default_rng(3)
    fine = [prose(rng, 60, 5000) for _ in range(80)]
    noisy = [" ".join(f"{w}#$" for w in prose(rng, 60, 5000).split()) for _ in range(70)]  # passes the base rule, fails that of symbols
    df = docs(spark, fine[:40], ["ok"]).union(docs(spark, noisy + fine[40:50], ["noisy"]).withColumn("doc_id", F.col("doc_id") + 100))
    by = lambda rules: {r.host: r.k for r in quality_verdicts(df, rules=rules).groupBy("host").agg(F.count_if("kept").alias("k")).collect()}
    from boxprune.llm.quality import BASE

    assert by(BASE) == {"ok": 40, "noisy": 80} and by(HOST_RULES) == {"ok": 40, "noisy": 0}
    assert keep_good(df).count() == 40 and keep_good(df.limit(0)).count() == 0


def test_long_texts_hash_like_short_ones(monkeypatch):
    import pyarrow as pa

    from boxprune.llm import kernels

    text = " ".join(f"word{i % 977}" for i in range(4000)) + " \u00e9nd"
    whole = next(iter(kernels.slices(pa.array([text]))))[1].words()
    monkeypatch.setattr(kernels, "SLICE_BYTES", 500)
    cut = next(iter(kernels.slices(pa.array([text]))))[1].words()
    assert all((a == b).all() for a, b in zip(whole, cut, strict=True))


def test_training_runs_come_from_the_whole_text():
    from boxprune.llm.langid import RUN_WORDS, TEXT_RUNS, text_runs

    text = " ".join(f"w{i}" for i in range(20_000))
    at = sorted(int(r.split()[0][1:]) for r in text_runs(text))
    assert len(at) == TEXT_RUNS and at[0] < 4000 and at[-1] > 16_000 and all(len(r.split()) == RUN_WORDS for r in text_runs(text))
    assert text_runs("") == [] == text_runs("1 2") and text_runs("a 1 b") == ["a b"]


def brute_nearest(x, q, k):
    d = np.sqrt(((x - x[q]) ** 2).sum(axis=1))
    d[q] = np.inf
    return set(np.lexsort((np.arange(len(x)), d))[:k].tolist())


def test_shards_are_merged(spark, monkeypatch):
    """Several shards, vectors in tight groups far from zero."""
    from boxprune.llm import hnsw

    monkeypatch.setattr(hnsw, "SHARD_ROWS", 300)
    monkeypatch.setattr(hnsw, "QUERY_ROWS", 40)
    monkeypatch.setattr(hnsw.build_index, "__defaults__", (300,))
    rng = np.random.default_rng(4)
    x = 5000 + np.repeat(rng.normal(size=(40, 16)) * 8, 40, axis=0) + rng.normal(size=(1600, 16))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    assert hnsw.build_index(hnsw.usable_vectors(df, "vec_id", "embedding"), 10).count() > 3
    got = {}
    for r in hnsw.nearest_neighbours(df, F.col("id") % 16 == 0).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    assert all(len(v) == 10 for v in got.values()) and len(got) == 100
    assert sum(len(v & brute_nearest(x, q, 10)) for q, v in got.items()) / 1000 >= 0.95


def read(spark, sf, name):
    return spark.read.parquet(f"{sf}/{name}.parquet")


def test_registered_search_equals_brute_force(spark, sf):
    from boxprune.llm.queries import op10_hnsw_shards

    rows = read(spark, sf, "embeddings").orderBy("vec_id").collect()
    ids, x = [r.vec_id for r in rows], np.array([r.embedding for r in rows], np.float64)
    got = {}
    for r in op10_hnsw_shards(spark, sf).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    assert sorted(got) == [i for i in ids if i % 100 == 0]
    hit = sum(len(v & {ids[j] for j in brute_nearest(x, ids.index(q), 10)}) for q, v in got.items())
    assert hit / (10 * len(got)) >= 0.9


def test_registered_tokens_equal_the_libraries(spark, sf):
    import tiktoken
    from tokenizers import Tokenizer

    from boxprune.llm.bpe import load_ranks
    from boxprune.llm.queries import op4_pack_patterns, op5_segment_tree_bpe

    ref = tiktoken.Encoding("ref", pat_str=P.PATTERN, mergeable_ranks=load_ranks(P.path("byte_bpe_50k.tiktoken")), special_tokens={})
    tok = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    texts = {r.doc_id: r.text or "" for r in read(spark, sf, DOCS).collect()}
    for r in op5_segment_tree_bpe(spark, sf).collect():
        ids = ref.encode_ordinary(texts[r.doc_id])
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(texts[r.doc_id].encode()).hexdigest())
    rows = op4_pack_patterns(spark, sf).collect()
    size = {}
    for r in rows:
        size[r.doc_id] = size.get(r.doc_id, 0) + r.length
    assert size == {i: len(tok.encode(t, add_special_tokens=False).ids) + 1 for i, t in texts.items()}
    assert check_packing(rows, 1024) <= 1.03 * -(-sum(size.values()) // 1024) + 1


def test_registered_spans_equal_brute_force(spark, sf):
    from boxprune.llm.queries import op9_boosted_pii

    texts = {r.doc_id: r.text or "" for r in read(spark, sf, DOCS).collect()}
    for r in op9_boosted_pii(spark, sf).collect():
        want = brute_spans(texts[r.doc_id])
        digest = ",".join(f"{kind}:{a}:{b}" for a, _, b, kind in want)
        assert r.base_sha256 == hashlib.sha256(digest.encode()).hexdigest()
        assert [s for s in r.spans.split(",") if s and not s.startswith("secret")] == digest.split(",") * bool(digest)


def test_registered_languages_held_out(spark, sf):
    from boxprune.llm.queries import op2_crf_language

    lang = {r.doc_id: r.lang for r in read(spark, sf, DOCS).collect()}
    held = [r for r in op2_crf_language(spark, sf).collect() if r.held_out and lang[r.doc_id] and r.lang_pred != "und"]
    assert len(held) > 30 and np.mean([r.lang_pred == lang[r.doc_id] for r in held]) >= 0.95


def test_hot_passages_equal_brute_force(spark, monkeypatch):
    """Passages with many surroundings, over windows of one and of several distances, split into groups and single windows."""
    from boxprune.llm import substring

    rng = np.random.default_rng(16)
    line, passage, long = (prose(rng, n, 3000) for n in (12, 56, 130))
    texts = [*ODD, "loop " * 130, "loop " * 70 + "end"]
    for i in range(90):
        around = [prose(rng, int(rng.integers(0, 70)), 3000 if i % 3 else 2) for _ in range(3)]
        texts.append(" ".join([around[0], (line, passage, long)[i % 3], around[1], (passage, line, line)[i // 3 % 3], around[2]]))
    texts += [t + " again" for t in texts[-20:]]
    want = dict(enumerate(brute_passages(texts, 50)))
    for hot, listed in ((1, substring.LISTED), (20, substring.LISTED), (3, 0)):
        monkeypatch.setattr(substring, "LISTED", listed)
        got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring.repeated_passages(docs(spark, texts), hot=hot).collect()}
        assert got == want, hot


def test_hot_anchor_is_dealt_to_many(spark):
    from boxprune.llm import substring

    rng = np.random.default_rng(17)
    passage = prose(rng, 56, 3000)
    texts = [f"{prose(rng, 50, 10**6)} {passage} {prose(rng, 50, 10**6)}" for _ in range(300)]
    sizes = []
    real = substring._shard_runs

    def counted(contexts, shards, width):
        sizes.append(contexts.groupBy("anchor").agg(F.countDistinct("context").alias("n")).agg(F.max("n")).first()[0])
        return real(contexts, shards, width)

    substring._shard_runs = counted
    try:
        substring.repeated_passages(docs(spark, texts)).count()
        substring.repeated_passages(docs(spark, texts), hot=10).count()
    finally:
        substring._shard_runs = real
    assert sizes[0] == 300 and sizes[1] <= 10


def test_hot_anchors_are_told_to_tasks(spark):
    """Groups of hot anchors are counted where the texts lie: no join carries the texts for it, unless there are too many anchors to tell."""
    from boxprune.llm import substring

    rng = np.random.default_rng(18)
    passage = prose(rng, 56, 3000)
    texts = [f"{prose(rng, 20, 10**6)} {passage} {prose(rng, 20, 10**6)}" for _ in range(60)]
    plans = []
    real = substring._group_rows

    def seen(texts, *more):
        plans.append(texts._jdf.queryExecution().optimizedPlan().toString())
        return real(texts, *more)

    substring._group_rows = seen
    try:
        got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring.repeated_passages(docs(spark, texts), hot=10).collect()}
    finally:
        substring._group_rows = real
    assert got == dict(enumerate(brute_passages(texts, 50)))
    assert len(plans) == 1 and "Inner" not in plans[0]
