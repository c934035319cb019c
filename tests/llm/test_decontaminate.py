import numpy as np
from hypothesis import given
from hypothesis import strategies as st

from blockgraph.llm import decontaminate as dec


def brute_lcs(a, b):
    t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
    return t[-1][-1]


@given(st.lists(st.sampled_from("abcd"), max_size=12), st.lists(st.sampled_from("abcd"), max_size=12))
def test_lcs(a, b):
    mask = dec.lcs_mask(a, b)
    want = brute_lcs(a, b)
    assert len(mask) == want and mask == sorted(set(mask))
    it = iter(b)
    assert all(a[i] in it for i in mask)
    where = {}
    for i, x in enumerate(a):
        where[x] = where.get(x, 0) | 1 << i
    assert dec.lcs_length(where, len(a), b) == want


def test_planted(spark):
    rng = np.random.default_rng(3)
    words = [f"{a}{b}{c}{e}" for a in "bcdfg" for b in "aeiou" for c in "lmnrstvz" for e in "aeioudgkx"] + ["the", "of", "and"] * 60
    text = lambda n: " ".join(rng.choice(words, n))
    items = [(i, text(rng.integers(20, 90))) for i in range(30)] + [(30, None), (31, "")]
    rows, leaks = [], set()
    for d in range(300):
        body = text(rng.integers(30, 400))
        if d % 3 == 0:
            i = int(rng.integers(0, 30))
            w = items[i][1].split()
            if d % 2:  # a paraphrase: some words exchanged, some dropped
                w = [x if rng.random() > 0.1 else "swapped" for x in w if rng.random() > 0.05]
            cut = int(rng.integers(0, len(body)))
            body = body[:cut] + "\n" + " ".join(w).upper() + ".\n" + body[cut:]
            leaks.add((d, i))
        rows.append((d, body))
    rows += [(900, None), (901, ""), (902, "..."), (None, items[0][1])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in dec.find_leaks(docs, bench).collect()}
    # brute force over all windows of all documents decides what is right
    want = set()
    for d, t in rows:
        w = dec.words_of(t)
        for i, s in items:
            p = dec.words_of(s)
            for k in range(max(1, -(-len(p) // 64))):
                n = max(1, -(-len(p) // 64))
                part = p[len(p) * k // n : len(p) * (k + 1) // n]
                if not part or d is None:
                    continue
                for a in range(0, max(1, len(w) - 64), 32):
                    m = dec.lcs_mask(part, w[a : a + 96])
                    tail = min(8, len(part))
                    if len(m) >= 0.7 * len(part) or len(m) >= 0.6 * len(part) and sum(x >= len(part) - tail for x in m) >= 0.75 * tail:
                        want.add((d, i))
    assert leaks <= want
    assert got == want
    left = {r.doc_id for r in dec.remove_leaks(docs, bench).collect()}
    assert left == {d for d, _ in rows} - {d for d, _ in want}


def test_recall_with_more_items_than_the_rank(spark):
    """Paraphrases of 400 items among documents in a space of rank 64, held
    against brute force; and the same in parts of the benchmark."""
    rng = np.random.default_rng(8)
    rare = [f"{a}{b}{c}{e}" for a in "bcdfgh" for b in "aeiou" for c in "lmnrstvz" for e in "aeioudgkx"]
    common = ["the", "of", "and", "to", "in", "is", "was", "for"]
    text = lambda n: " ".join(rng.choice(rare if rng.random() < 0.5 else common) for _ in range(n))
    items = [(i, text(int(rng.integers(25, 60)))) for i in range(400)]
    rows = []
    for d in range(500):
        w = items[d % 400][1].split()
        w = [x if rng.random() > 0.15 else str(rng.choice(rare)) for x in w if rng.random() > 0.05]
        rows.append((d, f"{text(int(rng.integers(0, 120)))} {' '.join(w) if d % 2 else ''} {text(40)}"))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    bench = spark.createDataFrame(items, "item_id long, text string")
    passages = dec.Passages(items, 32)
    want = set()
    for d, t in rows:
        w = dec.words_of(t)
        for i, (p, where) in enumerate(zip(passages.words, passages.where)):
            for a in range(0, max(1, len(w) - 64), 32):
                part = w[a : a + 96]
                ratio, tail = dec.lcs_length(where, len(p), part) / len(p), min(8, len(p))
                if ratio >= 0.7 or ratio >= 0.6 and sum(x >= len(p) - tail for x in dec.lcs_mask(p, part)) >= 0.75 * tail:
                    want.add((d, passages.item[i]))
    found = lambda **o: {(r.doc_id, r.item_id) for r in dec.find_leaks(docs, bench, max_df=0.05, rank=64, **o).collect()}
    whole = found()
    assert len(want) > 150 and whole <= want and len(whole) >= 0.98 * len(want)
    parts = found(items_at_once=150)
    assert parts <= want and len(parts) >= 0.98 * len(want)


def test_empty(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, terms int")
    bench = spark.createDataFrame([(1, "some words of an item")], "item_id long, text string")
    assert dec.find_leaks(docs, bench).collect() == []
    assert dec.find_leaks(docs, bench.limit(0)).collect() == []


def test_texts_are_cut_into_words_once(spark, monkeypatch):
    item = " ".join(f"word{i}" for i in range(40))
    docs = spark.createDataFrame([(i, f"some text {i} " * 20 + (item if i == 3 else "")) for i in range(6)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    ids = {w.encode(): i for i, w in enumerate(dec.Passages([(1, item)], 32).vocabulary())}
    rows = {r.doc_id: r.ids for r in dec.numbered(docs, ids).collect()}
    assert len(rows[3]) == 2 * (60 + 40) and rows[0] == b"\xff\xff" * 60
    kept = []
    monkeypatch.setattr(dec, "materialise", lambda df, name, keep=dec.materialise: kept.append((name, df.columns)) or keep(df, name))
    assert [(r.doc_id, r.item_id) for r in dec.find_leaks(docs, bench).collect()] == [(3, 1)]
    assert kept == [("words", ["doc_id", "ids"]), ("windows", ["terms"])]
