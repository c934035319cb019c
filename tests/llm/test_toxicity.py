import numpy as np
from hypothesis import given
from hypothesis import strategies as st

from blockgraph.llm import queries, toxicity as tox


def test_grammar_marks():
    m = tox.Model(set(tox.INSULTS), weights=tox.prior_weights())
    s = tox.Scorer(m)
    hit = lambda t: np.flatnonzero(s.features(t)[:16]).tolist()
    assert hit("you are an idiot") == [tox.DIRECTED]
    assert hit("an idiot") == [0]
    assert hit("not an idiot") == [tox.NEGATED]
    assert hit("she said idiot once") == [tox.REPORTED | tox.DIRECTED]
    assert hit("idiot, that is what you are") == [tox.DIRECTED] and hit("idiot, which is not what you are") == [0]
    assert hit('"idiot" is a word') == [tox.REPORTED]
    assert hit("not here. idiot") == [0]
    assert hit("they will kill") == [8 + tox.DIRECTED]
    assert hit("nothing here") == [] and hit(None) == [] and hit("") == []
    assert s.score(s.features("you idiot")) > 0.5 > s.score(s.features("hello"))
    assert s.score(s.features("not an idiot")) < s.score(s.features("an idiot"))


KINDS = {"idiot": 1, "kill": 2, "you": 3, "not": 4, "said": 5, '"': 6, "word": 0}


@given(st.lists(st.sampled_from([*KINDS, "."]), max_size=40))
def test_marks_by_definition(tokens):
    """What the machines mark, by looking at the tokens around each match."""
    want = np.zeros(tox.FEATURES)
    clause: list[str] = []
    for t in [*tokens, "."]:
        if t != ".":
            clause.append(t)
            continue
        hits = [i for i, w in enumerate(clause) if w in ("idiot", "kill")]
        for i in hits:
            near = lambda kind, back: kind in clause[max(0, i - back) : i]
            marks = tox.NEGATED * near("not", 3) | tox.REPORTED * (near("said", 5) or clause[:i].count('"') % 2) | tox.DIRECTED * (near("you", 4) or "you" in clause[i + 1 : i + 5])
            want[8 * (clause[i] == "kill") + int(marks)] += 1
        want[16] += bool(hits)
        want[17] = max(want[17], len(hits))
        clause = []
    scorer = tox.Scorer(tox.Model(set(tox.INSULTS), weights=tox.prior_weights()))
    assert np.allclose(scorer.features(" ".join(tokens)), np.log1p(want))


def test_targets_on_both_sides():
    s = tox.Scorer(tox.Model(set(tox.INSULTS), weights=tox.prior_weights()))
    score = lambda t: s.score(s.features(t))
    assert score("idiot, that is what you are") == score("you are an idiot") > 0.5 > score("stupid pet tricks were fun")


def test_equal_texts_and_odd_tables(spark):
    """Labels of equal texts that disagree, long texts, clashing columns."""
    rows = [(i, "you zorgle fool", "x") for i in range(6)] + [(9, "fine words here " * 20000, "y"), (10, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, toxic string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(6)] + [(9, 0), (3, None)], "doc_id long, toxic int")
    got = [{r.doc_id: r.score for r in tox.score(docs.repartition(n), tox.fit(docs.repartition(n), labels)).collect()} for n in (1, 3)]
    assert got[0] == got[1] and len({got[0][i] for i in range(6)}) == 1 and got[0][0] > got[0][9]


def test_held_out(spark):
    sf = "/root/testdata/sf0.1"
    got = queries.op9_toxicity(spark, sf)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert got.count() == docs.count()
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    rows = got.where("held_out").join(labels, "doc_id").collect()
    right = sum(r.predicted == r.toxic for r in rows)
    caught = [r.predicted for r in rows if r.toxic == 1]
    print(len(rows), right / len(rows), np.mean(caught))
    assert right / len(rows) > 0.98 and np.mean(caught) > 0.85
    assert all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows)


def test_no_labels_and_empty(spark):
    docs = spark.createDataFrame([(1, "you idiot"), (2, None), (None, "")], "doc_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    got = {r.doc_id: r.predicted for r in tox.score(docs, tox.fit(docs, labels)).collect()}
    assert got == {1: 1, 2: 0, None: 0}
    assert tox.score(docs.limit(0), tox.fit(docs.limit(0), labels)).collect() == []
