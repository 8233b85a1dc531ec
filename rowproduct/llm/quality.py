"""Document quality rules as a short-circuit cascade, in native expressions only.

What each group of measures costs and which rows each rule rejects is estimated on a random sample of bounded size.
Rules are then picked one by one: the most rejections among the sample's rows still alive, for the cost of the groups
that no earlier pick has paid for. A document that one rule rejects is spared every later rule's
measures. The order never changes a verdict: a document is kept if no rule rejects it.

Defined results: null and empty text has no words, so the first base rule rejects it; very
long texts are measured whole; repeated rows are judged alike; an empty table stays empty;
other columns pass through (`with_verdict`; a column `kept` is replaced) or are dropped (`measure`), whatever their names.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WS = "\x20\t\n\x0b\x0c\r"
WINDOW = 5


@dataclass(frozen=True)
class Rule:
    """rejects: SQL over measure columns; needs: the measure groups it reads."""

    name: str
    rejects: str
    needs: tuple[str, ...]


#: Groups of measures, each from the text or from earlier groups.
GROUPS = {"words": (), "symbols": (), "lines": (), "repeats": ("words",), "letters": ("words",)}
#: Groups whose measures `measure` returns for every text.
RETURNED = ("words", "symbols", "lines", "repeats")
SAMPLE_ROWS = 400
BASE_RULES = (
    Rule("few_words", "n_words < 10", ("words",)),
    Rule("repeated_windows", "100 * n_repeat_words > 20 * n_words", ("words", "repeats")),
)
#: The method's own rules: symbol-heavy text, text that is mostly repeated lines, words of odd length, words without letters.
OWN_RULES = (
    Rule("symbols", "10 * n_symbols > word_chars", ("words", "symbols")),
    Rule("duplicate_lines", "10 * n_dup_lines > 3 * n_lines", ("lines",)),
    Rule("long_words", "word_chars > 25 * n_words", ("words",)),
    Rule("short_words", "word_chars < 2 * n_words", ("words",)),
    Rule("few_letters", "2 * n_letter_words < n_words", ("words", "letters")),
)


def _add(df: DataFrame, group: str, alive: Column) -> DataFrame:
    """The group's measures where alive, else null. Each layer is a projection of its own, so that nothing is computed twice."""
    t, gate = F.col("_q_text"), lambda c: F.when(alive, c)
    if group == "words":
        body = F.btrim(t, F.lit(WS))
        df = df.withColumn("_q_words", gate(F.when(body == "", F.array().cast("array<string>")).otherwise(F.split(body, f"[{WS}]+"))))
        return df.withColumn("n_words", gate(F.size("_q_words").cast("long"))).withColumn("word_chars", gate(F.length(F.array_join("_q_words", "")).cast("long")))
    if group == "symbols":
        return df.withColumn("n_symbols", gate(F.regexp_count(t, F.lit(r"[#*$%&|<>]")).cast("long")))
    if group == "lines":
        df = df.withColumn("_q_lines", gate(F.filter(F.split(t, "\n", -1), lambda x: F.btrim(x, F.lit(WS)) != "")))
        return df.withColumn("n_lines", gate(F.size("_q_lines").cast("long"))).withColumn("n_dup_lines", gate((F.size("_q_lines") - F.size(F.array_distinct("_q_lines"))).cast("long")))
    w = F.col("_q_words")
    if group == "letters":  # a letter: A-Z, a-z or anything beyond ASCII
        return df.withColumn("n_letter_words", gate(F.size(F.filter(w, lambda x: x.rlike(r"[^\x00-\x40\x5B-\x60\x7B-\x7F]"))).cast("long")))
    window = lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(WINDOW)])
    df = df.withColumn("_q_h", gate(F.when(F.size(w) > WINDOW, F.transform(F.sequence(F.lit(0), F.size(w) - WINDOW), window))))
    # Only texts with a repeated window are sorted: windows by (hash, place), then the places whose hash has a neighbour.
    df = df.withColumn("_q_s", F.when(F.size(F.array_distinct("_q_h")) < F.size("_q_h"), F.sort_array(F.transform("_q_h", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    df = df.withColumn("_q_eq", F.zip_with("_q_s", F.slice("_q_s", 2, F.size("_q_s")), lambda a, b: F.coalesce(a["h"] == b["h"], F.lit(False))))
    twice = F.zip_with("_q_s", F.zip_with("_q_eq", F.concat(F.array(F.lit(False)), "_q_eq"), lambda a, b: F.coalesce(a, F.lit(False)) | F.coalesce(b, F.lit(False))), lambda s, two: F.when(two, s["i"]))
    df = df.withColumn("_q_p", F.sort_array(F.filter(twice, lambda i: i.isNotNull())))
    steps = F.zip_with("_q_p", F.slice("_q_p", 2, F.greatest(F.size("_q_p"), F.lit(1))), lambda a, b: F.least(F.lit(WINDOW), F.coalesce(b - a, F.lit(WINDOW))))
    return df.withColumn("n_repeat_words", gate(F.coalesce(F.aggregate(steps, F.lit(0), lambda x, y: x + y), F.lit(0)).cast("long")))


def _with_groups(df: DataFrame, needs, done: set[str], alive: Column) -> DataFrame:
    for g in GROUPS:  # a group stands after those that it needs
        if g in _closure(needs) and g not in done:
            df, _ = _add(df, g, alive), done.add(g)
    return df


def _closure(needs) -> set[str]:
    """The groups with those that they stand on."""
    return set(needs).union(*(GROUPS[g] for g in needs))


def sampled(df: DataFrame, text: str = "text", sample_rows: int = SAMPLE_ROWS, seed: int = 17) -> DataFrame:
    """`_q_text` of about sample_rows random rows of the whole table (all, if fewer; never over twice as many), held by the driver."""
    own = df.select(F.coalesce(text, F.lit("")).alias("_q_text"))
    total = df.count()
    got = (own if total <= sample_rows else own.sample(sample_rows / total, seed)).limit(2 * sample_rows).collect()
    return df.sparkSession.createDataFrame([(r[0],) for r in got], "_q_text string").coalesce(1)


def estimate(sample: DataFrame, rules, costs: dict[str, float] | None = None, paid=()) -> tuple[dict[str, float], list[tuple[bool, ...]]]:
    """(seconds of each group on the sample that the rules need and nobody has paid for, for each of its rows which rules
    reject it). costs: taken instead of clock times, which makes the order repeatable."""
    rejects = [F.coalesce(F.expr(r.rejects), F.lit(False)).alias(f"r{k}") for k, r in enumerate(rules)]
    wanted = set().union(*(_closure(r.needs) for r in rules))
    rows = [tuple(r) for r in _with_groups(sample, wanted, set(), F.lit(True)).select(*rejects).collect()]
    if costs is not None:
        return costs, rows
    known: dict[frozenset, float] = {}

    def took(groups: frozenset) -> float:
        if groups not in known:
            known[groups] = float("inf")
            for _ in range(2):  # the first run compiles
                t = time.perf_counter()
                _with_groups(sample, groups, set(), F.lit(True)).drop("_q_text").withColumn("_q_one", F.lit(1)).write.format("noop").mode("overwrite").save()
                known[groups] = min(known[groups], time.perf_counter() - t)
        return known[groups]

    # A group alone: without those that it stands on.
    return {g: max(took(frozenset(_closure((g,)))) - took(frozenset(GROUPS[g])), 1e-6) for g in GROUPS if g in wanted - set(paid)}, rows


def pick_order(rules, costs: dict[str, float], rows: list[tuple[bool, ...]], paid=()) -> list[Rule]:
    """Rules by rejections among rows still alive per cost of groups not yet paid for; ties keep the given order. A rule whose
    groups are all paid for costs a thousandth of the cheapest group."""
    left, out, paid = list(enumerate(rules)), [], set(paid)
    least = min(costs.values(), default=1.0) / 1000
    while left:
        rate = [(sum(x[k] for x in rows) / (sum(costs[g] for g in sorted(_closure(r.needs) - paid)) + least), -k) for k, r in left]
        k = -max(rate)[1]
        rule = rules[k]
        out.append(rule)
        paid |= _closure(rule.needs)
        rows = [x for x in rows if not x[k]]
        left = [x for x in left if x[0] != k]
    return out


def order_rules(df: DataFrame, rules, text: str = "text", sample_rows: int = SAMPLE_ROWS, costs: dict[str, float] | None = None, paid=()) -> list[Rule]:
    sample = sampled(df, text, sample_rows)
    return pick_order(rules, *estimate(sample, rules, costs, paid), paid)


def with_verdict(df: DataFrame, rules=BASE_RULES + OWN_RULES, text: str = "text", ordered: list[Rule] | None = None) -> DataFrame:
    """df with `kept`. Each rule runs only where no earlier rule has rejected."""
    ordered = ordered if ordered is not None else order_rules(df, rules, text)
    names = [c for c in df.columns if c != "kept"]
    out = df.select(F.struct(*[F.col(c) for c in names]).alias("_q_row"), F.coalesce(text, F.lit("")).alias("_q_text"), F.lit(True).alias("_q_alive"))
    out = _cascade(out, ordered, set())
    # A filter on the verdict must not be pushed below: it would copy every measure into one predicate. The
    # optimizer leaves filters above values that may differ by row place, as this one formally does.
    verdict = F.when(F.monotonically_increasing_id() >= 0, F.col("_q_alive"))
    return out.select(*[F.col("_q_row").getField(c).alias(c) for c in names], verdict.alias("kept"))


def _cascade(df: DataFrame, ordered, done: set[str]) -> DataFrame:
    """`_q_alive` after the rules; groups that are not done yet are measured only where it still holds."""
    for r in ordered:
        df = _with_groups(df, r.needs, done, F.col("_q_alive"))
        df = df.withColumn("_q_alive", F.when(F.col("_q_alive"), ~F.coalesce(F.expr(r.rejects), F.lit(False))).otherwise(F.lit(False)))
    return df


def measure(df: DataFrame, id_col: str = "doc_id", text: str = "text", own=OWN_RULES, ordered: list[Rule] | None = None) -> DataFrame:
    """The RETURNED measures of every text, whether the base rules reject it, and the cascade's verdict: the own rules
    run where the base rules do not reject, in order, and their further measures only where no earlier one has rejected."""
    ordered = ordered if ordered is not None else order_rules(df, tuple(own), text, paid=RETURNED)
    done: set[str] = set()
    out = _with_groups(df.select(F.col(id_col), F.coalesce(text, F.lit("")).alias("_q_text")), RETURNED, done, F.lit(True))
    out = out.withColumn("base_failed", F.expr(" or ".join(f"({r.rejects})" for r in BASE_RULES))).withColumn("_q_alive", ~F.col("base_failed"))
    out = _cascade(out, [r for r in ordered if r not in BASE_RULES], done)
    return out.select(id_col, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", F.col("_q_alive").alias("kept"))
