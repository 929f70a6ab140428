"""The pipeline's near-duplicate stage against brute force over planted near copies."""

import brute as B
import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline
from curvesolve.llm import near_copies


def grams(text):
    w = B.WORDS.findall((text or "").lower())
    return {tuple(w[i:i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} - {()}


def kept(rows):
    ids = [i for i, _ in rows if i is not None]
    sets = [grams(t) for i, t in rows if i is not None]
    pairs = [(a, b) for b in range(len(ids)) for a in range(b) if ids[a] == ids[b] or 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])]
    root = B.components(len(ids), pairs)
    low = {}
    for k, r in enumerate(root):
        low[r] = min(low.get(r, ids[k]), ids[k])
    return {i for k, i in enumerate(ids) if low[root[k]] == i}


def test_stage_links_planted_near_copies(spark):
    rng = np.random.default_rng(4)
    rows = []
    for base in range(12):
        words = [f"w{x}" for x in rng.integers(0, 3000, 200)]
        for copy in range(9):
            new = list(words)
            for at in rng.integers(0, 200, copy):
                new[at] = f"z{rng.integers(10**6)}"
            rows.append((100 * copy + base, " ".join(new) + "\ncommon line at the end of all of these texts"))
    # A chain: each is near the next, the ends are not near each other.
    chain = [f"c{k}" for k in range(140)]
    rows += [(2000 - k, " ".join(chain[2 * k:2 * k + 100])) for k in range(20)]
    rows += [(3000, None), (3001, ""), (3002, "two words"), (3003, "Two  words"), (3004, "other words"), (3005, rows[0][1].upper()), (3005, rows[0][1].upper())]
    rows += [(3010 + k, " ".join(f"q{x}" for x in range(20_000)) + f" tail{k}") for k in range(2)]
    df = spark.createDataFrame([*rows, (None, rows[0][1])], "doc_id long, text string")
    got = [r["doc_id"] for r in corpus_pipeline.drop_copies(spark, df, "").collect()]
    assert got.count(None) == 1 and set(got) - {None} == kept(rows)
    assert corpus_pipeline.drop_copies(spark, df.limit(0), "").count() == 0


def test_prefixes_leave_every_similar_pair_and_few_others(spark):
    rng = np.random.default_rng(5)
    sets = []
    for base in range(30):
        words = rng.integers(0, 1 << 63, rng.integers(5, 200))
        for drop in (0, 1, len(words) // 12, len(words) // 9, len(words) // 5, len(words) // 2):
            # One element is common to all sets, as by chance.
            sets.append(np.unique(np.r_[words[drop:], rng.integers(0, 1 << 63, drop // 2), 7].astype(np.uint64)))
    none = np.zeros(0, np.uint64)
    rows = [(k, len(x), near_copies.prefix(x, none, none).view(np.int64).tolist()) for k, x in enumerate(sets)]
    alone = spark.createDataFrame(rows, "doc_id long, n int, keys array<long>")
    every = [(a, b) for b in range(len(sets)) for a in range(b)]
    got = {tuple(r) for r in near_copies.possible(spark.createDataFrame(every, "u long, v long"), alone).collect()}
    shared = {(a, b): len(np.intersect1d(sets[a], sets[b])) for a, b in every}
    near = {(a, b) for a, b in every if 5 * shared[a, b] >= 4 * (len(sets[a]) + len(sets[b]) - shared[a, b])}
    sized = {(a, b) for a, b in every if 5 * min(len(sets[a]), len(sets[b])) >= 4 * max(len(sets[a]), len(sets[b]))}
    assert near and near <= got <= sized and 3 * len(got) < len(sized)


def test_candidates_are_found_without_moving_texts(spark):
    """However many ids: a join that exchanges rows would move all texts in each round."""
    pairs = spark.range(150_000).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    texts = spark.createDataFrame([(5, "a"), (150_000, "b"), (150_001, "c"), (10**9, "d")], "doc_id long, text string")
    found = near_copies._likely_in(pairs, texts)
    assert {5, 150_000} <= {r["doc_id"] for r in found.collect()}
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "hashpartitioning" not in plan
