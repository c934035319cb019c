import hashlib
from collections import Counter, defaultdict

import corpus_pipeline
from blockgraph.llm import bpe, decontaminate as dec, queries
from blockgraph.llm.common import documents

from .test_similar import brute

SF = "/root/testdata/sf0.001"


def good(text):
    t = text or ""
    w = [x.decode() for x in t.encode().split()]
    n = len(w)
    if n < 50:
        return False
    tri = Counter(zip(w, w[1:], w[2:]))
    covered = {j for i in range(n - 2) if tri[w[i], w[i + 1], w[i + 2]] > 1 for j in (i, i + 1, i + 2)}
    up, low = sum("A" <= c <= "Z" for c in t), sum("a" <= c <= "z" for c in t)
    lines = [x for x in t.split("\n") if x.encode().split()]
    chars = sum(map(len, w))
    return not (
        2 * len(covered) > n or sum(c in "#*$%&|<>" for c in t) > n / 4 or up > (up + low) / 2 or not 2 * n <= chars <= 20 * n or len(lines) - len(set(lines)) > (t.count("\n") + 1) / 2
    )


def test_run(spark):
    rows = [r for r in documents(spark, SF).collect() if good(r.text)]
    distinct = {(r.source, r.text) for r in rows}
    pages, on = Counter(s for s, _ in distinct), Counter()
    key = lambda x: x.strip(" \t\r")
    for s, t in distinct:
        on.update({(s, key(x)) for x in t.split("\n") if key(x)})
    text = {r.doc_id: "\n".join(x for x in r.text.split("\n") if not (on[r.source, key(x)] >= 3 and on[r.source, key(x)] > 0.05 * pages[r.source])) for r in rows}
    ids = sorted(text)
    root = brute([text[d] for d in ids])
    ids = [d for i, d in enumerate(ids) if root[i] == i]
    clean = []
    items = [dec.words_of(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    parts = [w[len(w) * i // n : len(w) * (i + 1) // n] for w in items for n in [max(1, -(-len(w) // 64))] for i in range(n)]
    for d in ids:
        w = dec.words_of(text[d])

        def leaks(p):
            for a in range(0, max(1, len(w) - 64), 32):
                if len(set(p) & set(w[a : a + 96])) < 0.3 * len(set(p)):
                    continue
                m = dec.lcs_mask(p, w[a : a + 96])
                tail = min(8, len(p))
                if len(m) >= 0.7 * len(p) or len(m) >= 0.6 * len(p) and sum(x >= len(p) - tail for x in m) >= 0.75 * tail:
                    return True
            return False

        if not any(map(leaks, parts)):
            clean.append(d)
    enc = bpe.tokenizer(*queries.rank_file())
    want = []
    for d in clean:
        i = enc.encode_ordinary(text[d])
        want.append((d, len(i), hashlib.sha256(",".join(map(str, i)).encode()).hexdigest(), hashlib.sha256(text[d].encode()).hexdigest()))
    got = sorted(tuple(r) for r in corpus_pipeline.run(spark, SF).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256").collect())
    assert 0 < len(want) < 200
    assert got == sorted(want)


def test_stages_keep_columns(spark):
    docs = documents(spark, SF)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs.limit(0), SF).columns == docs.columns
        assert stage(spark, docs, SF).columns == docs.columns
