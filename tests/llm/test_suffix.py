import hashlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from blockgraph.llm import suffix_dedup as sd


@given(st.binary(max_size=80).map(lambda b: bytes(x % 3 for x in b)), st.lists(st.integers(0, 80), max_size=4))
def test_suffix_array_and_prefixes(data, cuts):
    text = np.frombuffer(data, np.uint8)
    sa = sd.suffix_array(text)
    assert sa.tolist() == sorted(range(len(data)), key=lambda i: data[i:])
    starts = np.array(sorted({0, *(c for c in cuts if c < len(data))}), np.int64)
    common = lambda a, b: next((k for k, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
    want = [0] + [common(data[a:], data[b:]) for a, b in zip(sa, sa[1:])] if len(data) else []
    assert sd.common_prefixes(text, sa, starts).tolist() == want
    assert sd.common_prefixes(text, sa, starts, 5).tolist() == [min(5, x) for x in want]


def brute(rows, length):
    seen, out = set(), {}
    for i, (d, t) in sorted(enumerate(rows), key=lambda x: (x[1][0] is None, x[1][0] or 0)):
        b = (t or "").encode()
        mark = bytearray(len(b))
        for s in range(len(b) - length + 1):
            w = b[s : s + length]
            if w in seen:
                mark[s : s + length] = b"\1" * length
            seen.add(w)
        kept = bytes(x for x, m in zip(b, mark) if not m)
        out[i] = (d, len(b), sum(mark), sum(1 for j, m in enumerate(mark) if m and (j == 0 or not mark[j - 1])), hashlib.sha256(kept).hexdigest())
    return sorted(out.values(), key=str)


def texts(rng, n):
    common = ["".join(rng.choice(list("abcdé "), 230)) for _ in range(6)]
    rows = []
    for d in range(n):
        parts = []
        for _ in range(int(rng.integers(1, 5))):
            k = rng.random()
            if k < 0.4:
                c = common[int(rng.integers(0, 6))]
                a = int(rng.integers(0, 90))
                parts.append(c[a : a + int(rng.integers(60, 140))])
            elif k < 0.5:
                parts.append("xy" * int(rng.integers(30, 120)))
            else:
                parts.append("".join(rng.choice(list("abcdefgh\n "), rng.integers(0, 300))))
        rows.append((d, "".join(parts)))
    return rows


@pytest.mark.parametrize("hot", [20_000, 3])
def test_query(spark, hot, monkeypatch):
    monkeypatch.setattr(sd, "BODY_BYTES", 2000)
    rng = np.random.default_rng(hot)
    rows = texts(rng, 120)
    rows += [(200, rows[3][1]), (201, rows[3][1][:150]), (202, None), (203, ""), (204, "short"), (None, rows[5][1]), (205, "z" * 1000), (206, "z" * 99), (207, "z" * 100)]
    rng.shuffle(rows)
    rows = [(None if d is None else int(d), t) for d, t in rows]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    out = sd.remove_repeats(df, 100, chunk_bytes=20_000, hot=hot, buckets=7).collect()
    got = sorted(((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in out), key=str)
    assert got == brute(rows, 100)
    for r in out:
        assert hashlib.sha256(r.kept).hexdigest() == r.kept_sha256 and sum(s.end - s.start for s in r.spans) == r.n_removed


def test_empty(spark):
    assert sd.remove_repeats(spark.createDataFrame([], "doc_id long, text string, blob int")).collect() == []


@settings(max_examples=30)
@given(st.integers(0, 2**30), st.integers(0, 3000))
def test_runs_in_slices(seed, n):
    data = np.random.default_rng(seed).integers(0, 2, n, dtype=np.uint8)
    a, b = sd.runs(data, 100), sd.runs(data, 100, 512)
    assert a[1].sum() == b[1].sum() == max(0, n - 99)
