"""Quality rules as a short-circuit cascade, in DataFrame expressions only.

A rule is a boolean expression that is true where a text fails. The cascade measures on a bounded
sample how long each rule takes and how often it rejects, orders the rules by rejections per cost and
folds them into one nested conditional, so that a text rejected early never pays for the later rules.
The order changes the cost only: the verdict is that of all rules together.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, column, packed, words

#: Characters that count as symbols, and the length of the repeated windows.
SYMBOLS = "#*$%&|<>"
WINDOW = 8
#: Rows of the sample on which costs and selectivities are measured.
SAMPLE_ROWS = 500


def bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` evaluated once: inside higher-order functions an expression that
    is written out again would be evaluated again for each element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def repeated_words(w: Column, window: int = WINDOW) -> Column:
    """Words that lie in windows of ``window`` words found twice or more in the text, the first
    included. Linear but for one sort of the window hashes, which only texts with a repeat pay."""
    n = F.size(w) - F.lit(window)

    def from_hashes(h: Column) -> Column:
        return F.when(F.size(F.array_distinct(h)) < F.size(h), bound(F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i")))), from_sorted)).otherwise(F.lit(0).cast("bigint"))

    def from_sorted(s: Column) -> Column:
        same = F.filter(s, lambda x, i: F.coalesce(F.get(s, i - 1)["h"] == x["h"], F.lit(False)) | F.coalesce(F.get(s, i + 1)["h"] == x["h"], F.lit(False)))
        return bound(F.array_sort(F.transform(same, lambda x: x["i"])), covered)

    def covered(p: Column) -> Column:
        steps = F.transform(p, lambda x, i: F.least(F.lit(window), F.coalesce(F.get(p, i + 1) - x, F.lit(window))).cast("bigint"))
        return F.aggregate(steps, F.lit(0).cast("bigint"), lambda a, x: a + x)

    hashes = lambda x: F.transform(F.sequence(F.lit(1), F.size(x) - F.lit(window - 1)), lambda i: F.xxhash64(F.slice(x, i, window)))
    # Words become numbers first: windows of them are cut without a copy of the words' bytes.
    return F.when(n < 1, F.lit(0).cast("bigint")).otherwise(bound(F.transform(w, lambda x: F.xxhash64(x)), lambda x: bound(hashes(x), from_hashes)))


def counts(text: str = "text", w: Column | None = None) -> dict[str, Column]:
    """The base counts as expressions of the text, all long; a null text counts as empty. w: its words, if
    they are at hand."""
    t, w = F.coalesce(column(text), F.lit("")), words(column(text)) if w is None else w
    lines = F.filter(F.split(t, "\n"), lambda x: F.translate(x, SPACES, "") != "")
    return {
        "n_words": F.size(w).cast("bigint"),
        "word_chars": F.length(F.translate(t, SPACES, "")).cast("bigint"),
        "n_symbols": (F.length(t) - F.length(F.translate(t, SYMBOLS, ""))).cast("bigint"),
        "n_dup_lines": bound(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("bigint"),
        "n_repeat_words": repeated_words(w).cast("bigint"),
    }


def with_base_counts(df: DataFrame, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``keep`` (by default all columns) and the base counts; the words are cut once."""
    cut = packed(df.select(*[column(c) for c in (df.columns if keep is None else keep)]), t=column(text), w=words(column(text)))
    names = df.columns if keep is None else keep
    return cut.select(*[F.col(f"row.c{i}").alias(c) for i, c in enumerate(names)], *[v.alias(k) for k, v in counts("t", F.col("w")).items()])


def base_failed(c: dict[str, Column]) -> Column:
    return (c["n_words"] < 20) | (100 * c["n_repeat_words"] > 30 * c["n_words"])


@dataclass(frozen=True)
class Rule:
    """fails: true where a text is rejected, an expression of the text or of counts already taken."""

    name: str
    fails: Column


def default_rules(text: str = "text", c: dict[str, Column] | None = None) -> list[Rule]:
    """The rules over the counts ``c``: columns if those are wanted for every row anyway, else (by default)
    expressions that a row pays for only when the cascade comes to them."""
    t, c = F.coalesce(column(text), F.lit("")), counts(text) if c is None else c
    letters = F.length(F.regexp_replace(t, "\\P{L}", ""))
    upper = F.length(F.regexp_replace(t, "\\P{Lu}", ""))
    n_lines = F.size(F.filter(F.split(t, "\n"), lambda x: F.translate(x, SPACES, "") != ""))
    return [
        Rule("too_short", c["n_words"] < 20),
        Rule("repeated_windows", 100 * c["n_repeat_words"] > 30 * c["n_words"]),
        Rule("symbols", 10 * c["n_symbols"] > c["n_words"]),
        Rule("word_length", (c["word_chars"] < 2 * c["n_words"]) | (c["word_chars"] > 12 * c["n_words"])),
        Rule("repeated_lines", (c["n_dup_lines"] > 3) & (10 * c["n_dup_lines"] > 3 * n_lines)),
        Rule("upper_case", 10 * upper > 5 * letters),
        Rule("few_letters", 10 * letters < 5 * c["word_chars"]),
        Rule("exclamations", 4 * (F.length(t) - F.length(F.translate(t, "!", ""))) > c["n_words"]),
    ]


@dataclass(frozen=True)
class Measured:
    """A rule with its cost (seconds a sampled row) and its selectivity (share of rows it rejects)."""

    rule: Rule
    cost: float
    rejects: float

    @property
    def rate(self) -> float:
        """Rejections per second."""
        return self.rejects / self.cost


def sampled(df: DataFrame, rows: int = SAMPLE_ROWS, seed: int = 7) -> DataFrame:
    """About ``rows`` rows drawn from the whole table, by one pass over it; the limit only bounds a draw
    that has gone far astray."""
    n = df.count()
    return df.sample(min(1.0, rows / n), seed=seed).limit(2 * rows) if n > rows else df


def measure(few: DataFrame, rules: list[Rule], repeats: int = 2) -> list[Measured]:
    """Cost and selectivity of each rule over a sample of few rows, kept in memory as one partition. A cost
    is the least of some runs, less that of a run which only reads the sample, so that
    starting a job does not count; selectivity is drawn in by one rejection in the sample, so that a rule
    which rejects nothing there still has its place by cost."""
    sample = few.coalesce(1).cache()

    def run(fails: Column) -> tuple[float, int]:
        best, k = float("inf"), 0
        for _ in range(repeats):
            began = time.perf_counter()
            k = sample.agg(F.sum(F.coalesce(fails, F.lit(False)).cast("int"))).first()[0] or 0
            best = min(best, time.perf_counter() - began)
        return best, k

    try:
        n = max(1, sample.count())
        idle, _ = run(F.length(column(sample.columns[0]).cast("string")) < 0)
        out = []
        for r in rules:
            seconds, k = run(r.fails)
            out.append(Measured(r, max(1e-5, seconds - idle) / n, (k + 1) / (n + 2)))
        return out
    finally:
        sample.unpersist()


def ordered(measured: list[Measured]) -> list[Measured]:
    return sorted(measured, key=lambda m: (-m.rate, m.rule.name))


def cascade(rules: list[Rule]) -> Column:
    """Name of the first rule that rejects, in the order given; null if none does. A conditional evaluates
    no branch behind the one that holds, so a rejected text never pays for the later rules."""
    out = F.lit(None).cast("string")
    for rule in reversed(rules):
        out = F.when(F.coalesce(rule.fails, F.lit(False)), F.lit(rule.name)).otherwise(out)
    return out


def apply_rules(df: DataFrame, text: str = "text", with_counts: bool = True, rules: list[Rule] | None = None, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """Adds kept and rejected_by (string, null if kept); ``with_counts`` also the base counts and base_failed.

    Costs and selectivities are those of a sample (``sample_rows``, of the whole table): with counts the rules
    read them as columns, which every row has to have; without, each rule takes the counts it needs
    and a rejected row takes no more. Null and empty texts fail (too short). Every row comes back,
    repeated rows as often as they came; an empty table gives an empty result. Further columns stay, unless
    they bear one of the names added here, which are then replaced. Which of several failed rules is named
    depends on the measured order; kept does not.
    """
    names = list(counts(text)) if with_counts else []
    taken = {k: F.col(k) for k in names} if with_counts else counts(text)
    rules = default_rules(text, taken) if rules is None else rules
    few = sampled(df.select(column(text).alias(text)), sample_rows)
    kept = [c for c in df.columns if c not in {*names, "base_failed", "rejected_by", "kept"} or c == text]
    out = with_base_counts(df, text, kept) if with_counts else df.select(*[column(c) for c in kept])
    order = [m.rule for m in ordered(measure(with_base_counts(few, text) if with_counts else few, rules))]
    named = cascade(order)
    if with_counts:
        out = out.withColumn("base_failed", base_failed(taken))
        named = F.when(F.col("base_failed"), F.when(taken["n_words"] < 20, F.lit("too_short")).otherwise(F.lit("repeated_windows"))).otherwise(named)
    return out.withColumn("rejected_by", named).withColumn("kept", F.col("rejected_by").isNull())
