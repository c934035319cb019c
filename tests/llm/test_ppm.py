import math
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockgraph.llm import ppm
from blockgraph.llm.common import crc_fold

ROWS = [
    (0, "the cat sat on the mat"), (1, "the dog sat on the log\nand ran"), (2, "THE CAT ran, été"), (3, ""), (4, None), (5, "a"),
    (6, "the cat sat on the mat"), (7, "zebra quux 漢字"), (8, "aaaaaaaaaaaaaaaaaaaaaaaa"), (9, "\x00\x01 odd"), (None, "no id here"), (11, "the the the the"),
]


def brute_trie(texts, order):
    trie = defaultdict(Counter)
    for t in texts:
        s = b"\xff" * order + t + b"\xff"
        for i in range(order, len(s)):
            for k in range(order + 1):
                trie[s[i - k : i]][s[i]] += 1
    return trie


@pytest.mark.parametrize("order,escape", [(2, "C"), (4, "C"), (4, "D"), (5, "C")])
def test_scores(spark, order, escape):
    df = spark.createDataFrame(ROWS, "doc_id long, text string")
    held = crc_fold(F.col("doc_id")) == 1
    got = {r.doc_id: r for r in ppm.score(df, ~held, order, escape).collect()}
    train = [(t or "").encode() for d, t in ROWS if d is None or zlib.crc32(str(d).encode()) % 5 != 1]
    assert len(train) < len(ROWS)
    trie = brute_trie(train, order)
    low = lambda b: bytes(c + 32 if 65 <= c <= 90 else c for c in b)
    count = Counter(w for t in train for w in [*low(t).split(), None])
    total, v = sum(count.values()), len(count)
    for d, t in ROWS:
        b = (t or "").encode()
        s = b"\xff" * order + b + b"\xff"
        want = sum(ppm.symbol_log10(trie, s[i - order : i], s[i], escape) for i in range(order, len(s)))
        assert got[d].score == pytest.approx(want, abs=1e-9), (d, t)
        tokens = [*low(b).split(), None]
        assert got[d].n_tokens == len(tokens) and got[d].n_known == sum(count[w] > 0 for w in tokens) and got[d].train_tokens == total
        assert got[d].base_score == pytest.approx(sum(math.log10((count[w] + 0.5) / (total + 0.5 * (v + 1))) for w in tokens))


@pytest.mark.parametrize("escape", ["C", "D"])
def test_distribution_sums_to_one(escape):
    trie = brute_trie([b"abracadabra", b"alakazam"], 3)
    for context in (b"abr", b"zzz", b"\xff\xff\xff", b"xab"):
        assert sum(10 ** ppm.symbol_log10(trie, context, s, escape) for s in range(256)) == pytest.approx(1)


def test_adaptive(spark):
    df = spark.createDataFrame([(0, "ab" * 200), (1, None), (2, "q8#zL!0p")], "doc_id long, text string")
    got = {r.doc_id: r for r in ppm.adaptive(df, 3).collect()}
    assert got[1].score == pytest.approx(-math.log10(256)) and got[1].n_bytes == 0
    assert got[0].score / 401 > got[2].score / 9


def test_empty(spark):
    df = spark.createDataFrame([], "doc_id long, text string, train string")
    assert ppm.score(df, F.lit(True)).collect() == []


def test_lookup():
    rng = np.random.default_rng(0)
    keys = np.unique(rng.integers(0, 2**40, 5000))
    values = rng.random(len(keys))
    assert (ppm.StringTable(keys, values).get(keys[::-1].copy()) == values[::-1]).all()


def test_squeezed_values():
    rng = np.random.default_rng(1)
    for x in (rng.random(5000), rng.random(20)[rng.integers(0, 20, 5000)], np.empty(0), np.array([-0.5])):
        assert (ppm.unsqueeze_values(ppm.squeeze_values(x)) == x).all() and len(ppm.unsqueeze_values(ppm.squeeze_values(x))) == len(x)
    assert len(ppm.squeeze_values(rng.random(20)[rng.integers(0, 20, 5000)])) < 8000
