import numpy as np

import corpus_pipeline
from blockgraph.llm import simhash, similar

from .test_simhash import brute_components


def brute_set(text):
    w = (text or "").lower().split()
    return {tuple(w)} - {()} if len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def brute(texts):
    s = [brute_set(t) for t in texts]
    near = lambda a, b: 5 * len(a & b) >= 4 * len(a | b)
    root = list(range(len(s)))
    for i in range(len(s)):
        for j in range(i):
            if near(s[i], s[j]) and root[i] != root[j]:
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    return root


def corpus():
    rng = np.random.default_rng(11)
    words, tail = [f"w{i}" for i in range(3000)], " ".join(f"t{i}" for i in range(30))
    texts = [" ".join(rng.choice(words, rng.integers(20, 300))) + (" " + tail) * (d % 2) for d in range(80)]
    for d in range(160):  # up to a tenth of the five-word shingles changed, either side of 0.8
        w = texts[int(rng.integers(0, 80))].split()
        for i in rng.integers(0, len(w), 1 + int(rng.integers(0, max(1, len(w) // 25)))):
            w[int(i)] = "changed"
        texts.append(" ".join(w))
    base = texts[0].split()
    for d in range(40):  # a large group of near copies
        texts.append(" ".join([*base[: d + 5], f"x{d}", *base[d + 6 :]]))
    return texts + [None, "", "  \n", "two words", "Two  words"]


def test_prefix():
    for n in range(1, 300):
        assert similar.prefix(n) == n - -(-4 * n // 5) + 1
    assert similar.prefix(0) == 0


def test_radius_keeps_similar_sets():
    """Sets at 0.8 and a little above stay within the radius, those of
    unrelated texts mostly don't."""
    rng = np.random.default_rng(3)
    near, far = [], []
    for _ in range(3000):
        n = int(rng.integers(5, 400))
        k = n // 10 + 1
        while (n - k) / (n + k) < 0.8:
            k -= 1
        a = rng.integers(0, 2**64, n, dtype=np.uint64)
        b = np.concatenate([a[k:], rng.integers(0, 2**64, k, dtype=np.uint64)])
        bits = lambda x, y: (simhash.majority(x) ^ simhash.majority(y)).bit_count()
        near.append(bits(a, b))
        far.append(bits(a, rng.integers(0, 2**64, n, dtype=np.uint64)))
    assert max(near) <= similar.RADIUS
    assert np.mean(np.array(far) <= similar.RADIUS) < 0.05


def test_groups_dealt_in_parts(spark):
    texts = corpus()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = brute(texts)
    got = {r.doc_id: r.component_id for r in similar.near_duplicates(df, block=8).collect()}
    assert [got[i] for i in range(len(texts))] == want


def test_stage_is_exact(spark):
    texts = corpus()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    want = brute(texts)
    assert len(set(want)) < len(texts) - 60
    got = {r.doc_id: r.component_id for r in similar.near_duplicates(df).collect()}
    assert [got[i] for i in range(len(texts))] == want
    few = {r.doc_id: r.component_id for r in similar.near_duplicates(df, broadcast_ids=0).collect()}
    assert few == got
    kept = corpus_pipeline.simhash_stage(spark, df, "")
    assert sorted(r.doc_id for r in kept.collect()) == sorted(set(want))
    # what four bits of 64 leave apart
    assert simhash.keep_one(df).count() > len(set(want))


def test_ids_and_empty(spark):
    df = spark.createDataFrame([(1, "x", "o"), (1, "x", "o"), (2, "x", "p"), (None, "x", "q")], "doc_id long, text string, `a.b` string")
    assert sorted(map(tuple, corpus_pipeline.simhash_stage(spark, df, "").collect()), key=str) == [(1, "x", "o"), (None, "x", "q")]
    assert similar.near_duplicates(df.limit(0)).collect() == []
