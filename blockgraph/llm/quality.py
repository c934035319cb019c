"""Quality rules as a short-circuit cascade, in DataFrame expressions only.

Each rule is a boolean expression that says "reject". The cost and the
selectivity of every rule are estimated on a sample of raw texts: selectivity in
one aggregation, cost by timing each rule from the text on, the best of several
runs after a first one, less the time of a job that only reads the texts. Rules
are then ordered by rejection rate per cost and evaluated as one CASE chain, which
the JVM leaves at the first rule that rejects; a rule behind it isn't evaluated
for that row. The order changes the time and the ``rejected_by`` column, never the
verdict, which is the disjunction of all rules.

``keep_good`` is the cascade proper: what a rule needs is computed when it is its
turn. ``judge`` returns the base columns of every row, so it has to compute them
all, and its chain only spares the rules that aren't made of these.

Words are maximal runs of characters other than U+0020 and U+0009 to U+000D.

Edge cases: a null or empty text has no words and is rejected by ``few_words``;
a text of fewer than three words has no windows; very long texts are judged whole; ties and repeated rows are
judged each by itself; an empty table needs no estimates and keeps the given
order; extra columns pass through, and columns of the result replace those of
the same name.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, discard, materialise


@dataclass(frozen=True)
class Rule:
    name: str
    reject: Column


def word_array(text: Column) -> Column:
    """The words of a text, in order."""
    parts = F.split(F.coalesce(text, F.lit("")), f"[{SPACE}]+")
    return F.filter(parts, lambda w: w != "")


def let(value: Column, body) -> Column:
    """body(value) with value computed once: a lambda's variable is bound to
    it, where a repeated expression would be evaluated again each time."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def with_words(df: DataFrame, text: str = "text") -> DataFrame:
    return df.withColumn("__bg_words", word_array(F.col(text)))


def n_symbols(text: Column) -> Column:
    t = F.coalesce(text, F.lit(""))
    return (F.length(t) - F.length(F.translate(t, "#*$%&|<>", ""))).cast("long")


def n_dup_lines(text: Column) -> Column:
    """Lines with a word that equal an earlier line."""
    t = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(t, "\n"), lambda x: F.rlike(x, F.lit(f"[^{SPACE}]")))
    return F.when(F.contains(t, F.lit("\n")), let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x)))).otherwise(0).cast("long")


def windows(words: Column) -> Column:
    """All runs of three words; a word holds no space, so the joined string is
    the run."""
    n = F.size(words)
    return F.transform(F.slice(words, 1, F.greatest(n - 2, F.lit(0))), lambda w, i: F.concat_ws(" ", w, F.get(words, i + 1), F.get(words, i + 2)))


def _covered(ranked: Column) -> Column:
    marked = F.filter(
        F.transform(ranked, lambda x, j: F.when((x["w"] == F.get(ranked, j - 1)["w"]) | (x["w"] == F.get(ranked, j + 1)["w"]), x["i"])),
        lambda i: i.isNotNull(),
    )
    return F.size(F.array_distinct(F.flatten(F.transform(marked, lambda i: F.array(i, i + 1, i + 2)))))


def covered_words(words: Column) -> Column:
    """Words inside windows that occur more than once, all occurrences
    counted: equal windows meet in a sorted copy and their positions are
    marked. The sort is left out where no window repeats."""
    ranked = lambda wins: F.array_sort(F.transform(wins, lambda w, i: F.struct(w.alias("w"), i.alias("i"))))
    count = lambda wins: F.when(F.size(F.array_distinct(wins)) == F.size(wins), F.lit(0)).otherwise(let(ranked(wins), _covered))
    return let(words, lambda w: let(windows(w), count))


def base_columns(df: DataFrame, text: str = "text") -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (all
    long) and base_failed."""
    t = F.col(text)
    out = with_words(df, text).withColumns({
        "n_words": F.size("__bg_words").cast("long"),
        "word_chars": F.length(F.translate(F.coalesce(t, F.lit("")), " \t\n\x0b\x0c\r", "")).cast("long"),
        "n_symbols": n_symbols(t),
        "n_dup_lines": n_dup_lines(t),
        "n_repeat_words": covered_words(F.col("__bg_words")).cast("long"),
    })
    return out.withColumn("base_failed", (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))).drop("__bg_words")


def base_rules() -> list[Rule]:
    return [
        Rule("few_words", F.col("n_words") < 50),
        Rule("repeated_words", 100 * F.col("n_repeat_words") > 50 * F.col("n_words")),
    ]


def text_rules(text: str = "text", max_symbols: float = 0.25, max_upper: float = 0.5, mean_word: tuple[float, float] = (2.0, 20.0), max_dup_lines: float = 0.5) -> list[Rule]:
    """Rules behind the base: symbols for each word, share of capitals among
    cased ASCII letters, mean word length and share of repeated lines."""
    t = F.coalesce(F.col(text), F.lit(""))
    upper = F.length(t) - F.length(F.translate(t, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", ""))
    lower = F.length(t) - F.length(F.translate(t, "abcdefghijklmnopqrstuvwxyz", ""))
    chars = F.col("word_chars")
    lines = F.length(t) - F.length(F.translate(t, "\n", "")) + 1
    return [
        Rule("symbols", F.col("n_symbols") > max_symbols * F.col("n_words")),
        Rule("capitals", upper > max_upper * (upper + lower)),
        Rule("word_length", (chars < mean_word[0] * F.col("n_words")) | (chars > mean_word[1] * F.col("n_words"))),
        Rule("repeated_lines", F.col("n_dup_lines") > max_dup_lines * lines),
    ]


def estimate(sample: DataFrame, rules: list[Rule], repeats: int = 3, read: Column | None = None) -> list[dict]:
    """Selectivity and cost of each rule on a materialised sample. ``read``
    stands for reading what the rules read; its time is taken off."""
    count = lambda x: F.sum(F.coalesce(x, F.lit(False)).cast("long"))
    n, *hits = sample.agg(F.count(F.lit(1)), *(count(r.reject) for r in rules)).first()

    def seconds(x: Column) -> float:
        plan, best = sample.agg(count(x)), float("inf")
        for run in range(repeats + 1):  # the first run compiles
            began = time.perf_counter()
            plan.collect()
            best = min(best, time.perf_counter() - began) if run else best
        return best

    idle = seconds(F.lit(False) if read is None else read)
    # below a hundredth of an idle job, times are noise
    return [{"rule": r.name, "rejects": (h or 0) / n if n else 0.0, "cost_s": max(seconds(r.reject) - idle, idle / 100)} for r, h in zip(rules, hits)]


def order_rules(rules: list[Rule], estimates: list[dict]) -> list[Rule]:
    """By rejections for each second, most first; ties keep the given order."""
    gain = {e["rule"]: e["rejects"] / max(e["cost_s"], 1e-9) for e in estimates}
    return sorted(rules, key=lambda r: -gain[r.name])


def plan_cascade(df: DataFrame, rules: list[Rule], sample_rows: int = 2000, seed: int = 7, read: Column | None = None) -> list[Rule]:
    """Order the rules by what a sample of about sample_rows rows shows."""
    n = df.count()
    if not n:
        return rules
    sample = materialise(df.sample(min(1.0, sample_rows / n), seed=seed).repartition(1), "rule-sample")
    ordered = order_rules(rules, estimate(sample, rules, read=read))
    discard(sample)
    return ordered


def plan_texts(df: DataFrame, text: str, sample_rows: int) -> list[str]:
    """Names of the rules in the order to apply them, by their cost on texts."""
    rules = [Rule(n, let(word_array(F.col(text)), r)) for n, r in lazy_rules(text).items()]
    return [r.name for r in plan_cascade(df.select(text), rules, sample_rows, read=F.octet_length(F.col(text)) < 0)]


def cascade(df: DataFrame, rules: list[Rule]) -> DataFrame:
    """Adds rejected_by (null if kept): the first rule, in the given order,
    that rejects the row."""
    chain = F.when(F.coalesce(rules[0].reject, F.lit(False)), rules[0].name)
    for r in rules[1:]:
        chain = chain.when(F.coalesce(r.reject, F.lit(False)), r.name)
    return df.withColumn("rejected_by", chain)


def lazy_rules(text: str = "text") -> dict:
    """All rules as functions of the words, for a filter that needs no base
    columns: an expensive one is only computed for rows that get there."""
    t = F.coalesce(F.col(text), F.lit(""))
    chars = F.length(F.translate(t, " \t\n\x0b\x0c\r", ""))
    upper = F.length(t) - F.length(F.translate(t, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", ""))
    lower = F.length(t) - F.length(F.translate(t, "abcdefghijklmnopqrstuvwxyz", ""))
    lines = F.length(t) - F.length(F.translate(t, "\n", "")) + 1
    return {
        "few_words": lambda w: F.size(w) < 50,
        "symbols": lambda w: n_symbols(t) > 0.25 * F.size(w),
        "capitals": lambda w: upper > 0.5 * (upper + lower),
        "word_length": lambda w: (chars < 2.0 * F.size(w)) | (chars > 20.0 * F.size(w)),
        "repeated_lines": lambda w: n_dup_lines(t) > 0.5 * lines,
        "repeated_words": lambda w: 100 * covered_words(w) > 50 * F.size(w),
    }


def rejected_by(text: str, rules: dict) -> Column:
    """The first rule that rejects, as one expression; the words are split once
    and bound to a variable, so that no plan rewrite splits them again."""

    def chain(words):
        out = None
        for name, rule in rules.items():
            fails = F.coalesce(rule(words), F.lit(False))
            out = F.when(fails, name) if out is None else out.when(fails, name)
        return out

    return let(word_array(F.col(text)), chain)


def judge(df: DataFrame, text: str = "text", sample_rows: int = 2000) -> DataFrame:
    """The base columns, the cascade over all rules and ``kept``."""
    based = base_columns(df, text)
    rules = {r.name: r for r in (*base_rules(), *text_rules(text))}
    out = cascade(based, [rules[n] for n in plan_texts(df, text, sample_rows)])
    return out.withColumn("kept", ~F.col("base_failed") & F.col("rejected_by").isNull())


def keep_good(df: DataFrame, text: str = "text", sample_rows: int = 2000) -> DataFrame:
    """The rows that no rule rejects, with the columns of df; the cascade runs
    on lazy rules, so most bad rows never reach the expensive ones."""
    rules = lazy_rules(text)
    return df.where(rejected_by(text, {n: rules[n] for n in plan_texts(df, text, sample_rows)}).isNull())
