import hashlib
import uuid
from collections import Counter

from hypothesis import given
from hypothesis import strategies as st
from pyspark.sql import functions as F

from blockgraph.llm import bpe, line_dedup, quality, queries, token_rollup
from blockgraph.llm.common import at_exit, shared_dir

ODD = [(0, None), (1, ""), (2, "   \n\t"), (3, "one"), (4, "a b"), (5, "a b c a b c a b c"), (6, "é x y z"), (7, "x\n\nx\n x\nx"), (8, "#a $b %c |"), (None, "no id"), (9, "w " * 30000), (9, "w " * 30000)]


def brute_base(text):
    t = text or ""
    w = [x.decode() for x in t.encode().split()]
    n = len(w)
    tri = Counter(zip(w, w[1:], w[2:]))
    cover = {j for i in range(n - 2) if tri[tuple(w[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    lines = [x for x in t.split("\n") if x.encode().split()]
    return n, sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(cover)


def test_quality_base(spark):
    df = spark.createDataFrame([(d, t, "x", 1) for d, t in ODD], "doc_id long, text string, `__words` string, n_words int")
    got = sorted((tuple(r) for r in quality.judge(df).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept").collect()), key=str)
    want = []
    for d, t in ODD:
        b = brute_base(t)
        failed = b[0] < 50 or 100 * b[4] > 50 * b[0]
        want.append((d, *b, failed))
    assert [g[:-1] for g in got] == sorted(want, key=str)
    assert not any(g[-1] and g[-2] for g in got)
    assert quality.judge(df.limit(0)).collect() == [] and quality.keep_good(df.limit(0)).collect() == []


def test_cascade_order_and_columns(spark):
    good = " ".join(f"word{i}" for i in range(80))
    df = spark.createDataFrame([(1, good, "s"), (2, good.upper(), "s"), (3, " ".join(f"#{i}" for i in range(80)), "s"), (4, "short", "s"), (5, "a b c " * 60, "s")], "doc_id long, text string, `odd.name` string")
    kept = quality.keep_good(df)
    assert kept.columns == df.columns and [r.doc_id for r in kept.collect()] == [1]
    rules = [quality.Rule("a", F.col("doc_id") > 4), quality.Rule("b", F.col("doc_id") > 1)]
    est = [{"rule": "a", "rejects": 0.2, "cost_s": 1.0}, {"rule": "b", "rejects": 0.8, "cost_s": 1.0}]
    assert [r.name for r in quality.order_rules(rules, est)] == ["b", "a"]
    for order in (rules, rules[::-1]):
        assert {r.doc_id for r in quality.cascade(df, order).where("rejected_by is null").collect()} == {1}


def test_slow_rule_that_rejects_nothing_goes_last(spark):
    text = F.col("text")
    slow = text
    for _ in range(60):
        slow = F.sha2(F.concat(slow, text), 512)
    rules = [quality.Rule("slow", slow == "none"), quality.Rule("slow_good", (slow != "none") & (F.length(text) > 0)), quality.Rule("quick", F.length(text) > 0)]
    df = spark.createDataFrame([(i, f"{i} some text " * 50) for i in range(2000)], "doc_id long, text string")
    assert [r.name for r in quality.plan_cascade(df, rules)] == ["quick", "slow_good", "slow"]
    long = spark.createDataFrame([(1, "lorem " * 400_000), (2, "a\n" * 200_000)], "doc_id long, text string")
    assert quality.keep_good(long).collect() == [] and {r.doc_id: r.n_words for r in quality.judge(long).collect()} == {1: 400_000, 2: 200_000}


def test_line_dedup(spark):
    rows = [(i, "h1", f"own {i}\nMENU \nshared") for i in range(10)] + [(20, "h2", "MENU\nx"), (21, None, "a\nb"), (22, None, None), (23, "h1", ""), (24, "h1", "own 1\n\n MENU")]
    df = spark.createDataFrame([(*r, "k") for r in rows], "doc_id long, source string, text string, n_lines string")
    for limit in (200_000, 0):
        got = {r.doc_id: r for r in line_dedup.clean(df, F.col("source"), ratio=0.5, broadcast_lines=limit).collect()}
        assert got[3].text == "own 3" and (got[3].n_lines, got[3].n_dropped) == (3, 2)
        assert got[20].text == "MENU\nx" and got[22].text is None and got[22].n_lines == 0 and got[23].text == "" and got[24].text == "own 1\n"
    assert line_dedup.clean(df.limit(0), F.col("source")).collect() == []
    assert line_dedup.clean(df, F.col("source"), counts=False).columns == df.columns


def test_copies_are_not_boilerplate(spark):
    rows = [(i, "h", "first of it\nsecond of it") for i in range(8)] + [(20 + i, "h", f"own {i}\nMENU") for i in range(12)] + [(40, "h", None)]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string")
    got = {r.doc_id: r.text for r in line_dedup.clean(df, F.col("source"), ratio=0.3, distinct_pages=True).collect()}
    assert got[0] == "first of it\nsecond of it" and got[20] == "own 0" and got[40] is None
    assert {r.text for r in line_dedup.clean(df, F.col("source"), ratio=0.3).where("doc_id < 8").collect()} == {""}


def test_hosts(spark):
    df = spark.createDataFrame([("https://A.b.com:80/x?y",), ("http://u@c.de",), ("nothing",), (None,)], "url string")
    assert [r.h for r in df.select(line_dedup.host_of_url(F.col("url")).alias("h")).collect()] == ["a.b.com", "c.de", None, None]


@given(st.text(alphabet="aé1 '\n\tx!sZ漢", max_size=300), st.integers(1, 20))
def test_safe_cuts(text, size):
    enc = bpe.tokenizer(*queries.rank_file())
    assert bpe.encode_text(enc, text, size) == enc.encode_ordinary(text)


def test_bpe(spark):
    enc = bpe.tokenizer(*queries.rank_file())
    rows = [*ODD[:-2], (10, "long " * 40000 + "x" * 3000 + "🙂<|endoftext|>")]
    df = spark.createDataFrame([(d, t, "clash") for d, t in rows], "doc_id long, text string, ids string")
    got = {r.doc_id: r for r in bpe.digests(df, *queries.rank_file(), piece_chars=1000).collect()}
    for d, t in rows:
        ids = enc.encode_ordinary(t or "")
        assert (got[d].n_tokens, got[d].ids_sha256) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest())
        assert got[d].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    both = bpe.decode(bpe.encode(df, *queries.rank_file()), *queries.rank_file())
    assert {r.doc_id: bytes(r.bytes) for r in both.collect()} == {d: (t or "").encode() for d, t in rows}
    assert bpe.digests(df.limit(0), *queries.rank_file()).collect() == []


SCHEMA = "op string, doc_id long, source string, lang string, tokenizer string, old_tokens long, new_tokens long"


def test_rollup(spark):
    r = token_rollup.TokenRollup(spark, at_exit(spark, f"{shared_dir(spark)}/rollup-{uuid.uuid4().hex}"))
    frame = lambda rows: spark.createDataFrame(rows, SCHEMA)
    assert r.totals().collect() == []
    a = [("insert", i, "s1", "en", "t1", None, 10) for i in range(5)] + [("insert", 9, None, None, "t1", None, None), ("other", 1, "s1", "en", "t1", 5, 5), (None, 1, "s1", "en", "t1", 5, 5)]
    assert r.apply("a", frame(a)) and not r.apply("a", frame(a))
    assert r.apply("b", frame([("delete", 0, "s1", "en", "t1", 10, None), ("revise", 1, "s1", "en", "t1", 10, 14), ("insert", 1, "s2", "de", "t2", None, 3)]))
    want = {("s1", "en", "t1"): (4, 44), (None, None, "t1"): (1, 0), ("s2", "de", "t2"): (1, 3)}
    totals = lambda: {(x.source, x.lang, x.tokenizer): (x.n_docs, x.n_tokens) for x in r.totals().collect()}
    assert totals() == want
    r.compact()
    assert totals() == want and not r.apply("b", frame(a)) and r.committed() == ["a", "b"]
    assert r.apply("c", frame([("delete", 1, "s2", "de", "t2", 3, None)])) and r.apply("empty", frame([]))
    want.pop(("s2", "de", "t2"))
    assert totals() == want
    r.compact()
    assert totals() == want and r.committed() == ["a", "b", "c", "empty"]


def test_rollup_query(spark):
    sf = "/root/testdata/sf0.001"
    enc = bpe.tokenizer(*queries.rank_file())
    docs = spark.read.parquet(f"{sf}/documents.parquet").collect()
    labels = {x.doc_id: x for x in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    want: dict = {}
    for d in docs:
        lab = labels.get(d.doc_id)
        if lab and lab.toxic == 1:
            continue
        words = len(d.text.encode().split()) + bool(lab and lab.quality == 1 and lab.toxic == 0)
        for tok, n in (("ws-words@1", words), ("byte-bpe-multi-50k@1", len(enc.encode_ordinary(d.text)))):
            k = (d.source, d.lang, tok)
            a, b = want.get(k, (0, 0))
            want[k] = (a + 1, b + n)
    got = {(r.source, r.lang, r.tokenizer): (r.n_docs, r.n_tokens) for r in queries.op10_token_counts(spark, sf).collect()}
    assert got == want
