"""Quality rules with risk-controlled thresholds (operator 5), in DataFrame functions only.

Each rule has a row of cutoffs, from lenient to strict; at level n all rules use their n-th
cutoff (or their last), and a document that any rule rejects is rejected. In each stratum
(language) levels are tried from the most lenient inwards on labelled holdout documents of good
quality. A level is certified when the exact binomial tail says that, were its false rejection
rate as high as `risk`, so few rejections by all rules together would have a chance of at most
`delta` shared among the strata (Bonferroni). Trials stop at the first that fails, so this fixed
sequence needs no further correction. With probability 1 - delta, in every stratum, at most
`risk` of the good documents are rejected by the certified level. A stratum without enough
labelled documents (ln(strata / delta) / risk, if none is rejected) certifies nothing and
rejects nothing beyond the base rules.

Measures are computed in one pass over whole texts. A null text has no words. Rows that
share a doc_id stay separate rows; a null language is a stratum of its own. Labels that are
null, or conflict to a mean under 0.5, do not count as good.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize

WORD = r"[^\x20\x09-\x0D]+"
#: Rule -> (numerator, denominator, whether high values are bad, cutoffs from lenient to strict).
RULES: dict[str, tuple[str, str, bool, tuple[float, ...]]] = {
    "symbols": ("n_symbols", "word_chars", True, tuple(k / 100 for k in (40, 30, 25, 20, 15, 12, 10, 8, 6, 5, 4, 3, 2))),
    "repeat_words": ("n_repeat_words", "n_words", True, tuple(k / 100 for k in (95, 90, 80, 70, 60, 50, 45, 40, 35, 30, 25, 20))),
    "dup_lines": ("n_dup_lines", "n_lines", True, tuple(k / 100 for k in (95, 90, 80, 70, 60, 50, 40, 30, 25, 20, 15, 10))),
    "capitals": ("n_capitals", "word_chars", True, tuple(k / 100 for k in (95, 90, 80, 70, 60, 50, 40, 30, 25, 20, 15))),
    "word_length": ("word_chars", "n_words", True, tuple(float(k) for k in (30, 25, 20, 18, 16, 14, 12, 11, 10, 9, 8))),
    "bang_marks": ("n_marks", "n_words", True, tuple(k / 100 for k in (95, 90, 80, 70, 60, 50, 40, 30, 20, 15, 10))),
}

LEVELS = max(len(c) for *_, c in RULES.values())


def _count_of(text: Column, characters: str) -> Column:
    return (F.length(text) - F.length(F.translate(text, characters, ""))).cast("long")


def _let(value: Column, use) -> Column:
    """use(value), with value computed once; a plain column could be inlined at each of its uses."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _repeated(words: Column) -> Column:
    """Words in 3-word windows that occur twice or more: hashes of windows sorted with their places, equal neighbours marked.

    Neighbours with equal hashes are compared word by word.
    """
    n = F.size(words)
    pairs = F.zip_with(F.slice(words, 1, n - 2), F.slice(words, 2, n - 2), lambda a, b: F.xxhash64(a, b))
    windows = F.zip_with(pairs, F.slice(words, 3, n - 2), lambda h, c: F.xxhash64(h, c))
    placed = F.sort_array(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    first = F.array(F.struct(F.lit(0).cast("long").alias("h"), F.lit(-1).alias("i")))

    def same(a: Column, b: Column) -> Column:
        return (b["i"] >= 0) & (a["h"] == b["h"]) & (F.slice(words, a["i"] + 1, 3) == F.slice(words, b["i"] + 1, 3))

    def twins(s: Column) -> Column:
        """Places of neighbours with the same window, twice where a window has more than two."""
        both = F.zip_with(s, F.slice(F.concat(first, s), 1, F.size(s)), lambda a, b: F.when(same(a, b), F.array(b["i"], a["i"])))
        return F.sort_array(F.array_distinct(F.flatten(F.filter(both, lambda x: x.isNotNull()))))

    def covered(places: Column) -> Column:
        gaps = F.zip_with(places, F.slice(F.concat(F.array(F.lit(-3)), places), 1, F.size(places)), lambda a, b: F.least(a - b, F.lit(3)))
        return F.aggregate(gaps, F.lit(0), lambda s, x: s + x)

    return F.when(n < 3, F.lit(0)).otherwise(_let(_let(placed, twins), covered))


def measures(docs: DataFrame, keep: tuple[str, ...] = ("doc_id", "lang"), text: str = "text") -> DataFrame:
    """keep, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, the other measures of RULES, and levels of its rules."""
    t = F.coalesce(F.col(text), F.lit(""))
    full = F.filter(F.split(t, "\n", -1), lambda x: F.length(F.translate(x, " \t\x0b\x0c\r", "")) > 0)
    lines = _let(full, lambda x: F.struct(F.size(x).alias("n"), (F.size(x) - F.size(F.array_distinct(x))).alias("dup")))
    split = F.filter(F.split(F.translate(t, "\t\n\x0b\x0c\r", "     "), " ", -1), lambda w: w != "")
    words = _let(split, lambda w: F.struct(F.size(w).alias("n"), _repeated(w).alias("repeat")))
    counted = docs.select(
        *keep,
        F.length(F.translate(t, " \t\n\x0b\x0c\r", "")).cast("long").alias("word_chars"),
        _count_of(t, "#*$%&|<>").alias("n_symbols"),
        _count_of(t, "!").alias("n_marks"),
        _count_of(t, "ABCDEFGHIJKLMNOPQRSTUVWXYZ").alias("n_capitals"),
        lines.alias("_l"),
        words.alias("_w"),
    )
    parts = {"n_lines": "_l.n", "n_dup_lines": "_l.dup", "n_words": "_w.n", "n_repeat_words": "_w.repeat"}
    named = counted.select(*keep, "word_chars", "n_symbols", "n_marks", "n_capitals", *(F.col(c).cast("long").alias(n) for n, c in parts.items()))
    return named.select("*", rule_levels().alias("levels"))


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 50)


def ratio(rule: str) -> Column:
    over, under, high, _ = RULES[rule]
    value = F.when(F.col(under) > 0, F.col(over) / F.col(under)).otherwise(F.lit(0.0))
    return value if high else -value


def binomial_tail(k: Column, n: Column, p: float) -> Column:
    """P(X <= k) for X binomial (n, p), by its terms' logarithms."""
    odds = math.log(p / (1 - p))
    start = F.struct((n * math.log1p(-p)).alias("term"), F.exp(n * math.log1p(-p)).alias("sum"))

    def step(s: Column, i: Column) -> Column:
        term = s["term"] + F.log((n - i + 1).cast("double") / i) + odds
        return F.struct(term.alias("term"), (s["sum"] + F.exp(term)).alias("sum"))

    some = F.when(k > 0, F.sequence(F.lit(1).cast("long"), k)).otherwise(F.array().cast("array<bigint>"))
    return F.aggregate(some, start, step, lambda s: F.least(s["sum"], F.lit(1.0)))


def rule_levels() -> Column:
    """By rule, the first level whose cutoff a document's measure passes; LEVELS and more: none."""
    each = []
    for rule, (_, _, high, cutoffs) in RULES.items():
        value = ratio(rule)
        below = F.size(F.filter(F.array(*(F.lit(c if high else -c) for c in cutoffs)), lambda c: value <= c))  # noqa: B023 - called at once
        each.append(F.when(below < len(cutoffs), below).otherwise(F.lit(LEVELS)).alias(rule))
    return F.struct(*each)


def certify(measured: DataFrame, labels: DataFrame, risk: float = 0.01, delta: float = 0.1, key: str = "doc_id", stratum: str = "lang", label: str = "quality") -> DataFrame:
    """stratum, level (the strictest certified), rejected, holdout (good documents) of each stratum that has one.

    measured: rows of measures(). A document is rejected from the least of its rules' levels on.
    """
    good = labels.where(F.col(key).isNotNull()).groupBy(key).agg(F.avg(label).alias("y")).where("y >= 0.5").select(key)
    # the labels' side is of any size: a join by key of two narrow tables
    rows = measured.where(~base_failed()).join(good, key).select(stratum, F.least(*(F.col(f"levels.{r}") for r in RULES)).alias("level"))
    upto = F.array(*(F.sum(F.when(F.col("level") <= n, 1).otherwise(0)).cast("long") for n in range(LEVELS)))
    counted = rows.groupBy(stratum).agg(F.count("*").alias("n"), upto.alias("k"))
    counted = counted.withColumn("strata", F.count("*").over(Window.partitionBy()))
    trial = counted.select(stratum, "n", "strata", F.posexplode("k").alias("level", "k"))
    trial = trial.withColumn("fits", binomial_tail(F.col("k"), F.col("n"), risk) <= F.lit(delta) / F.col("strata"))
    inward = Window.partitionBy(stratum).orderBy("level")
    run = trial.withColumn("ok", F.min(F.col("fits").cast("int")).over(inward)).where("ok = 1")
    return run.groupBy(stratum).agg(F.max("level").alias("level"), F.max("k").alias("rejected"), F.max("n").alias("holdout"))


def judge(measured: DataFrame, certified: DataFrame, stratum: str = "lang") -> DataFrame:
    """measured with base_failed, kept and failed_rules."""
    levels = certified.select(F.col(stratum).alias("_s"), F.col("level").alias("_certified"))
    rows = measured.join(levels, F.col(stratum).eqNullSafe(F.col("_s")), "left")
    failed = F.filter(F.array(*(F.when(F.col(f"levels.{r}") <= F.col("_certified"), F.lit(r)) for r in RULES)), lambda r: r.isNotNull())
    rows = rows.withColumn("base_failed", base_failed()).withColumn("failed_rules", failed)
    return rows.withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0)).drop("_s", "_certified", "levels")


def quality(docs: DataFrame, labels: DataFrame, risk: float = 0.01, delta: float = 0.1) -> DataFrame:
    """doc_id, lang, the measures, base_failed, failed_rules, kept of each row."""
    measured = materialize(measures(docs), "measures")
    return judge(measured, materialize(certify(measured, labels, risk, delta), "levels"))
