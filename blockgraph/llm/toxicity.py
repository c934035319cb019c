"""Toxicity by a weighted finite-state grammar over clauses.

Tokens become classes (insult, threat, target, negator, report, quote, other).
Small transducers read the classes of a clause: one marks what stands in the
scope of a negation, one what is reported or quoted, one what is aimed at a
target in front of it. They are composed into one machine, whose output at an
insult or threat is its class with the marks it has collected; a second machine
reads the clause backwards and marks what is aimed at a target behind it. A clause without an insult or
threat has no match and no score. Documents are scored from their matched
clauses by a logistic function of the counts of each output.

The lexicon of insults starts from a short public list and is extended from
labelled documents: words and word stems (4 to 6 letters) that occur in toxic
ones far more than chance allows and with several different words in front of
them, so a document copied many times teaches nothing. Words that the labels
contradict are taken off the list. ``fit`` reads at most ``max_toxic`` and
``max_clean`` labelled documents, chosen by a hash of the id; these bounds
bound the lexicon, which is broadcast.

Edge cases: null and empty texts have no clause and get the base score; labels
that are null are left out, of several labels of a document, or of equal texts,
the highest counts; very long texts are read whole, a clause at a time;
without labels the public list and prior weights are used; repeated rows are
scored each; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, portions

OTHER, INSULT, THREAT, TARGET, NEGATOR, REPORT, QUOTE = range(7)
NEGATED, REPORTED, DIRECTED = 1, 2, 4

# Fixed word lists.
INSULTS = "idiot idiots moron morons stupid dumb loser losers scum trash pathetic disgusting worthless clown clowns fool fools jerk jerks imbecile bastard bastards".split()
THREATS = "kill murder hurt stab shoot strangle exterminate tuer assassiner étrangler töten umbringen erwürgen matar asesinar estrangular".split()
TARGETS = "you your you're u he she they them him her his their these those people vous tu toi ils elles ihr euch du dich sie tú usted ustedes ellos ellas".split()
NEGATORS = "not no never isn't aren't wasn't don't doesn't cannot can't nobody pas jamais aucun nicht kein keine keinen nie nunca jamás tampoco".split()
REPORTS = "said says say called calls wrote writes claimed claims quoted quote quoting reported allegedly dit écrit sagte sagt schrieb dijo dice escribió".split()

CLAUSE = re.compile(r"[.!?;:\n]+")
WORD = re.compile(r"[\w'’]+|[\"“”«»]")
STEMS = (4, 5, 6)


class Transducer:
    """A deterministic machine: (state, class) -> (state, marks)."""

    def __init__(self, arcs: dict[tuple[int, int], tuple[int, int]], states: int):
        self.arcs, self.states = arcs, states


def scope(opens: tuple[int, ...], mark: int, length: int) -> Transducer:
    """Marks insults and threats up to ``length`` tokens behind an opener."""
    arcs = {}
    for s in range(length + 1):
        for c in range(7):
            if c in opens:
                arcs[s, c] = (length, 0)
            else:
                arcs[s, c] = (max(0, s - 1), mark if s and c in (INSULT, THREAT) else 0)
    return Transducer(arcs, length + 1)


def quoted() -> Transducer:
    """Marks what stands between quotation marks."""
    arcs = {}
    for s in (0, 1):
        for c in range(7):
            arcs[s, c] = (1 - s, 0) if c == QUOTE else (s, REPORTED if s and c in (INSULT, THREAT) else 0)
    return Transducer(arcs, 2)


def compose(a: Transducer, b: Transducer) -> Transducer:
    """Both machines read the same classes, their marks are united; states
    that can't be reached are left out."""
    number, todo, arcs = {(0, 0): 0}, [(0, 0)], {}
    while todo:
        s = todo.pop()
        for c in range(7):
            (x, m), (y, n) = a.arcs[s[0], c], b.arcs[s[1], c]
            if (x, y) not in number:
                number[x, y] = len(number)
                todo.append((x, y))
            arcs[number[s], c] = (number[x, y], m | n)
    return Transducer(arcs, len(number))


def grammar() -> Transducer:
    out = scope((NEGATOR,), NEGATED, 3)
    for t in (scope((REPORT,), REPORTED, 5), quoted(), scope((TARGET,), DIRECTED, REACH)):
        out = compose(out, t)
    return out


#: How many tokens may lie between a target and what is aimed at it, plus one.
REACH = 4


def backward_grammar() -> Transducer:
    return scope((TARGET,), DIRECTED, REACH)


FEATURES = 2 * 8 + 2


@dataclass
class Model:
    words: set[str]
    stems: set[str] = field(default_factory=set)
    threats: set[str] = field(default_factory=lambda: set(THREATS))
    weights: np.ndarray | None = None


def prior_weights() -> np.ndarray:
    """Bias, insults and threats by marks, matched clauses, most in a clause."""
    w = np.zeros(FEATURES + 1)
    w[0] = -3.0
    for kind, base in ((0, 4.0), (1, 3.0)):
        for marks in range(8):
            w[1 + 8 * kind + marks] = base * (0.25 if marks & NEGATED else 1) * (0.35 if marks & REPORTED else 1) * (1.2 if marks & DIRECTED else 0.7)
    return w


class Scorer:
    def __init__(self, model: Model):
        self.model, self.machine, self.backward = model, grammar(), backward_grammar()
        self.fixed: dict[str, int] = {}
        for words, c in ((TARGETS, TARGET), (NEGATORS, NEGATOR), (REPORTS, REPORT)):
            self.fixed.update(dict.fromkeys(words, c))
        self.fixed.update(dict.fromkeys('"“”«»', QUOTE))
        self.fixed.update(dict.fromkeys(model.threats, THREAT))
        self.fixed.update(dict.fromkeys(model.words, INSULT))
        self.cache: dict[str, bool] = {}

    def bad(self, word: str) -> bool:
        """Whether a word as it stands between spaces holds an insult or threat."""
        got = self.cache.get(word)
        if got is None:
            if len(self.cache) > 500_000:
                self.cache.clear()
            got = self.cache[word] = any(self.cls(w) in (INSULT, THREAT) for w in WORD.findall(word.lower()))
        return got

    def cls(self, word: str) -> int:
        c = self.fixed.get(word)
        if c is None:
            c = INSULT if self.model.stems and any(word[:k] in self.model.stems for k in STEMS if len(word) >= k) else OTHER
        return c

    def features(self, text: str | None) -> np.ndarray:
        out = np.zeros(FEATURES)
        if not text:
            return out
        bad = self.bad
        if not any(map(bad, set(text.split()))):
            return out
        arcs = self.machine.arcs
        for clause in CLAUSE.split(text):
            if not any(map(bad, clause.split())):
                continue
            hits = 0
            classes = list(map(self.cls, WORD.findall(clause.lower())))
            behind, state = [], 0
            for c in reversed(classes):
                state, marks = self.backward.arcs[state, c]
                behind.append(marks)
            state = 0
            for c, more in zip(classes, reversed(behind)):
                state, marks = arcs[state, c]
                if c == INSULT or c == THREAT:
                    out[8 * (c - INSULT) + (marks | more)] += 1
                    hits += 1
            if hits:
                out[16] += 1
                out[17] = max(out[17], hits)
        return np.log1p(out)

    def score(self, x: np.ndarray) -> float:
        z = self.model.weights[0] + float(self.model.weights[1:] @ x)
        return 1 / (1 + math.exp(-max(-500.0, min(500.0, z))))


def logistic(x: np.ndarray, y: np.ndarray, w: np.ndarray, start: np.ndarray, ridge: float = 0.5, steps: int = 50) -> np.ndarray:
    """Weighted ridge-to-prior logistic regression by Newton steps."""
    a, beta = np.c_[np.ones(len(x)), x], start.copy()
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ beta, -30, 30)))
        grad = a.T @ (w * (p - y)) + ridge * (beta - start)
        hess = (a * (w * p * (1 - p) + 1e-9)[:, None]).T @ a + ridge * np.eye(len(beta))
        move = np.linalg.solve(hess, grad)
        beta -= np.clip(move, -2, 2)
        if np.abs(move).max() < 1e-6:
            break
    return beta


def entries(text: str | None) -> dict[str, int]:
    """Words and stems of a text, each with the hashed words in front of it
    as bits."""
    out: dict[str, int] = {}
    before = ""
    for w in WORD.findall((text or "").lower()):
        bit = 1 << (xxhash.xxh32_intdigest(before) & 31)
        out[w] = out.get(w, 0) | bit
        for k in STEMS:
            if len(w) >= k:
                key = w[:k] + "*"
                out[key] = out.get(key, 0) | bit
        before = w
    return out


def _counts(texts: DataFrame, only: set[str] | None) -> DataFrame:
    """(entry, n, seen): documents with the entry, bits of the words before."""

    def run(batches):
        n, seen = Counter(), {}
        for b in batches:
            for t in b.column(0).to_pylist():
                found = entries(t)
                for e, bits in found.items():
                    if only is None or e in only:
                        n[e] += 1
                        seen[e] = seen.get(e, 0) | bits
        names = list(n)
        for i in range(0, len(names), 50_000):
            part = names[i : i + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array([n[e] for e in part], pa.int64()), pa.array([seen[e] for e in part], pa.int64())], names=["entry", "n", "seen"])

    return texts.select("text").mapInArrow(run, "entry string, n long, seen long").groupBy("entry").agg(F.sum("n").alias("n"), F.expr("bit_or(seen)").alias("seen"))


def _divergence(p: float, base: float) -> float:
    out = p * math.log(p / base) if p else 0.0
    return out + ((1 - p) * math.log((1 - p) / (1 - base)) if p < 1 else 0.0)


def fit(docs: DataFrame, labels: DataFrame, max_toxic: int = 4000, max_clean: int = 8000, min_contexts: int = 3) -> Model:
    """docs: doc_id, text; labels: doc_id, toxic (of the rows to learn from)."""
    spark = docs.sparkSession
    known = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    size = {r.toxic: r.n for r in known.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    share = {t: min(1.0, m / size[t]) if size.get(t) else 0.0 for t, m in ((1, max_toxic), (0, max_clean))}
    dice = F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000))
    # at most about max_toxic + max_clean ids, whatever the input: safe to broadcast
    chosen = known.where((dice < 1_000_000 * F.when(F.col("toxic") == 1, F.lit(share[1])).otherwise(F.lit(share[0]))) & F.col("toxic").isin(0, 1))
    # a text that is there several times counts once, by the highest label
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("text").agg(F.max("toxic").alias("toxic"))
    rows = materialise(sample.select("text", "toxic").repartition(max(4, spark.sparkContext.defaultParallelism)), "labelled")
    n = {r.toxic: r.n for r in rows.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    model = Model(set(INSULTS))
    toxic, clean = n.get(1, 0), n.get(0, 0)
    if not toxic or not clean:
        model.weights = prior_weights()
        return model
    base = toxic / (toxic + clean)
    found = {r.entry: (r.n, r.seen) for r in _counts(rows.where("toxic = 1"), None).where("n >= 3 or entry in (" + ",".join(f"'{w}'" for w in (*INSULTS, *THREATS)) + ")").collect()}
    against = {r.entry: r.n for r in _counts(rows.where("toxic = 0"), {*found, *INSULTS, *THREATS}).collect()}
    limit = math.log(max(len(found), 1) / 0.01)
    for e, (t, seen) in found.items():
        c = against.get(e, 0)
        p = t / (t + c)
        if p >= 0.9 and seen.bit_count() >= min_contexts and (t + c) * _divergence(p, base) > limit:
            (model.stems if e.endswith("*") else model.words).add(e.rstrip("*"))
    for words in (model.words, model.threats):
        for w in list(words):
            t, c = found.get(w, (0, 0))[0], against.get(w, 0)
            if t + c >= 10 and t < 0.5 * (t + c):
                words.discard(w)
    model.words -= {*TARGETS, *NEGATORS, *REPORTS}
    start = Model(model.words, model.stems, model.threats, prior_weights())

    def run(batches):
        scorer = Scorer(start)
        for b in portions(batches):
            x = np.array([scorer.features(t) for t in b.column(0).to_pylist()]).reshape(-1, FEATURES)
            yield pa.RecordBatch.from_arrays([pa.array(x.tolist(), pa.list_(pa.float64())), b.column(1)], names=["x", "toxic"])

    got = rows.mapInArrow(run, "x array<double>, toxic int").groupBy("x", "toxic").agg(F.count(F.lit(1)).alias("n")).collect()
    x, y, m = np.array([r.x for r in got]), np.array([r.toxic for r in got], float), np.array([r.n for r in got], float)
    # undo the sampling, so that the base rate is that of the labels
    m *= np.where(y == 1, size[1] / toxic, size[0] / clean) / (size[1] + size[0]) * (toxic + clean)
    model.weights = logistic(x, y, m, prior_weights())
    return model


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, score, predicted) of every row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        scorer = Scorer(sent.value)
        for b in portions(batches):
            s = [scorer.score(scorer.features(t)) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s, pa.float64()), pa.array([int(x >= 0.5) for x in s], pa.int32())], names=["doc_id", "score", "predicted"])

    src = docs.select(F.col(id_col).alias("doc_id"), F.col(text).cast("string").alias("text"))
    return src.mapInArrow(run, f"doc_id {src.dtypes[0][1]}, score double, predicted int")
