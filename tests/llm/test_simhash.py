import numpy as np
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from blockgraph.llm import simhash


def brute_fp(text):
    words = (text or "").encode().translate(bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))).split()
    grams = [words] if 0 < len(words) < 4 else [words[i : i + 4] for i in range(len(words) - 3)]
    hs = [xxhash.xxh64_intdigest(b" ".join(g), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_components(fps, radius=4):
    root = list(range(len(fps)))
    for i in range(len(fps)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= radius:
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    return root


@given(st.text(alphabet="ab AB\n\té", max_size=60))
def test_fingerprint(text):
    assert simhash.majority(simhash.shingle_hashes(text)) == brute_fp(text)


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 2**32), st.integers(1, 300), st.integers(1, 6))
def test_forest(seed, n, radius):
    rng = np.random.default_rng(seed)
    fp = rng.integers(0, 2**63, max(1, n // 10), dtype=np.uint64)[rng.integers(0, max(1, n // 10), n)]
    for _ in range(4):
        fp = fp ^ np.where(rng.random(n) < 0.7, np.uint64(1) << rng.integers(0, 64, n, dtype=np.uint64), np.uint64(0))
    group = np.sort(rng.integers(0, 3, n))
    label = simhash.forest(fp, group, radius)
    for g in range(3):
        at = np.flatnonzero(group == g)
        if len(at):
            want = brute_components([int(x) for x in fp[at]], radius)
            assert [int(at[w]) for w in want] == label[at].tolist()


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 2**32), st.integers(1, 300), st.integers(1, 40), st.integers(1, 30))
def test_asked_pairs(seed, n, m, radius):
    rng = np.random.default_rng(seed)
    fp, asked = (rng.integers(0, 2**64, size, dtype=np.uint64) & rng.integers(0, 2**64, size, dtype=np.uint64) for size in (n, m))
    group, asked_group = np.sort(rng.integers(0, 4, n)), np.sort(rng.integers(0, 5, m))
    got = {(int(i), int(j)) for a, b in simhash.asked_pairs(fp, group, asked, asked_group, radius, 7) for i, j in zip(a, b)}
    assert got == {(i, j) for i in range(m) for j in range(n) if group[j] == asked_group[i] and int(asked[i] ^ fp[j]).bit_count() <= radius}


def test_query(spark):
    rng = np.random.default_rng(5)
    words = [f"w{i}" for i in range(400)]
    rows = []
    for d in range(150):
        rows.append((d, " ".join(rng.choice(words, rng.integers(0, 120)))))
    for d in range(150, 300):
        w = rows[int(rng.integers(0, 150))][1].split()
        if w:
            w[int(rng.integers(0, len(w)))] = "changed"
        rows.append((d, " ".join(w)))
    rows += [(300, None), (301, ""), (302, "   \n"), (7, rows[7][1])]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    fps = [brute_fp(t) for _, t in rows]
    root = brute_components(fps)
    ids = [d for d, _ in rows]
    low = {r: min(i for i, q in zip(ids, root) if q == r) for r in set(root)}
    want = sorted((d, f, low[r]) for d, f, r in zip(ids, fps, root))
    for block in (4096, 8):
        prints = simhash.fingerprints(df)
        nodes = prints.groupBy("fp").agg({"doc_id": "min"}).toDF("fp", "node")
        from blockgraph.llm.components import components

        roots = {r.node: r.root for r in components(simhash.link_forest(nodes, 4, block)).collect()}
        got = sorted((r.node, roots.get(r.node, r.node)) for r in nodes.collect())
        assert got == sorted({(min(i for i, g in zip(ids, fps) if g == f), low[r]) for f, r in zip(fps, root)})
    got = sorted((r.doc_id, r.fp % 2**64, r.component_id) for r in simhash.near_duplicates(df).collect())
    assert got == want
    for limit in (500_000, 0):
        kept = simhash.keep_one(df, broadcast_ids=limit)
        assert kept.columns == df.columns and sorted(r.doc_id for r in kept.collect()) == sorted(set(low.values()))
    extra = spark.createDataFrame([(1, "x", "o"), (1, "x", "o"), (2, "x", "p"), (None, "x", "q")], "doc_id long, text string, `a.b` string")
    assert sorted(map(tuple, simhash.keep_one(extra).collect()), key=str) == [(1, "x", "o"), (None, "x", "q")]


def test_empty(spark):
    df = spark.createDataFrame([], "doc_id long, text string, fp string")
    assert simhash.near_duplicates(df).collect() == []
