"""Measures of accuracy, stability, space and time."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from termatlas.functions import geo


def relative_error(models: DataFrame, truth: DataFrame) -> DataFrame:
    """focus_error, focus_sd, spread_error, spread_sd, terms: relative to the reference models."""
    t = truth.select("term", F.col("focus").alias("f0"), F.col("spread").alias("s0"))
    rows = models.join(t, "term").select((F.abs(F.col("focus") - F.col("f0")) / F.col("f0")).alias("f"), F.when(F.col("s0") > 0, F.abs(F.col("spread") - F.col("s0")) / F.col("s0")).alias("s"))
    return rows.agg(F.avg("f").alias("focus_error"), F.stddev_samp("f").alias("focus_sd"), F.avg("s").alias("spread_error"), F.stddev_samp("s").alias("spread_sd"), F.count("*").alias("terms"))


def center_accuracy(models: DataFrame, truth: DataFrame, size_e6: int = geo.SIZE) -> DataFrame:
    """exact, within_one: percent of terms whose centre is the reference's, or at most a cell's step away."""
    t = truth.select("term", F.col("center_cell").alias("c0"))
    rows = models.join(t, "term")
    near = geo.squared_steps("center_cell", "c0", size_e6) <= 2
    return rows.agg((100 * F.avg((F.col("center_cell") == F.col("c0")).cast("double"))).alias("exact"), (100 * F.avg(near.cast("double"))).alias("within_one"))


def recall(found: DataFrame, truth: DataFrame, by: tuple[str, ...] = ("term", "cell")) -> DataFrame:
    """hits, wanted, recall of the true rows among the found ones."""
    t = truth.select(*by).distinct().join(found.select(*by).distinct().withColumn("hit", F.lit(1)), list(by), "left")
    return t.agg(F.sum(F.coalesce("hit", F.lit(0))).alias("hits"), F.count("*").alias("wanted"), F.avg(F.coalesce("hit", F.lit(0)).cast("double")).alias("recall"))


def frequency_errors(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """abs_error, abs_sd, log_error (estimates from 1e-9 up), log_error_one (from 1 up), pairs; truth: qid, n > 0."""
    rows = answers.join(truth.select("qid", "n"), "qid").where("n > 0").withColumn("est", F.coalesce("est", F.lit(0.0)))
    log = lambda low: F.abs(F.log10(F.greatest("est", F.lit(low))) - F.log10(F.col("n")))
    error = F.abs(F.col("est") - F.col("n"))
    return rows.agg(F.avg(error).alias("abs_error"), F.stddev_samp(error).alias("abs_sd"), F.avg(log(1e-9)).alias("log_error"), F.avg(log(1.0)).alias("log_error_one"), F.count("*").alias("pairs"))


def top_k_accuracy(found: DataFrame, truth: DataFrame, bins: DataFrame | None = None) -> DataFrame:
    """accuracy: per bin (qid, bin), share of queries with a found cell among the true best cells (ties count)."""
    t = truth.select("qid", "cell").distinct()
    hit = found.join(t, ["qid", "cell"], "left_semi").groupBy("qid").agg(F.lit(1.0).alias("hit"))
    every = t.select("qid").distinct() if bins is None else bins
    rows = every.join(hit, "qid", "left")
    by = [] if bins is None else ["bin"]
    return rows.groupBy(*by).agg(F.avg(F.coalesce("hit", F.lit(0.0))).alias("accuracy"), F.count("*").alias("asked"))


def overlap_at_k(found: DataFrame, truth: DataFrame) -> DataFrame:
    """qid, overlap: share of the true best cells found."""
    both = truth.select("qid", "cell").join(found.select("qid", "cell", F.lit(1).alias("hit")), ["qid", "cell"], "left")
    return both.groupBy("qid").agg(F.avg(F.coalesce("hit", F.lit(0)).cast("double")).alias("overlap"))


def replacement_curve(snapshots: DataFrame, k: int = 3) -> DataFrame:
    """part, changed, replaced: share of terms' top k that differ from the slice before, and mean replacements in the slice."""
    order = Window.partitionBy("term").orderBy("part")
    top = F.slice("top", 1, k)
    rows = snapshots.withColumn("was", F.lag(top).over(order)).withColumn("before", F.coalesce(F.lag("replaced").over(order), F.lit(0)))
    changed = F.when(F.col("was").isNull(), F.lit(1.0)).otherwise(1 - F.size(F.array_intersect(top, F.col("was"))) / F.greatest(F.size(top), F.lit(1)))
    return rows.groupBy("part").agg(F.avg(changed).alias("changed"), F.avg(F.col("replaced") - F.col("before")).alias("replaced"))


def stable_fraction(snapshots: DataFrame, models: DataFrame, slices: int = 20) -> DataFrame:
    """term, focus, spread, fraction: part of the stream after which half of the final centres are there to stay."""
    last = snapshots.where(F.col("part") == slices).select("term", F.col("centers").alias("final"))
    rows = snapshots.join(last, "term").withColumn("same", F.size(F.array_intersect("centers", "final")) * 2 >= F.size("final"))
    # the first slice from which on every slice keeps half
    bad = rows.groupBy("term").agg(F.max(F.when(~F.col("same"), F.col("part")).otherwise(0)).alias("bad"))
    return bad.join(models.select("term", "focus", "spread"), "term").select("term", "focus", "spread", (F.least(F.col("bad") + 1, F.lit(slices)) / slices).alias("fraction"))


def state_space(summary: DataFrame) -> DataFrame:
    """term, words, bytes: 3 words a counter and one a band, of 8 bytes."""
    words = F.size("centers") * 3 + F.aggregate("centers", F.lit(0), lambda s, c: s + F.size(c["rings"]))
    return summary.select("term", words.cast("long").alias("words"), (words * 8).cast("long").alias("bytes"))


def evaluations(models: DataFrame) -> DataFrame:
    """source, likelihood, models, n_eval: likelihood terms computed, a cost that hardware doesn't change."""
    return models.groupBy("source", "likelihood").agg(F.count("*").alias("models"), F.sum("n_eval").alias("n_eval"))


def invariants(summary: DataFrame, counts: DataFrame) -> DataFrame:
    """Violations of the summaries' guarantees by exact counts, all 0 for policies that count every arrival in a counter."""
    from termatlas.operators import counters

    own = counters.exploded(summary).join(counts, ["term", "cell"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    inside = own.agg(F.sum(((F.col("f") < F.col("n")) | (F.col("f") - F.col("err") > F.col("n"))).cast("long")).alias("interval"))
    absent = counts.join(counters.exploded(summary).select("term", "cell"), ["term", "cell"], "left_anti").join(summary.select("term", "total", "capacity", counters.absent_bound().alias("bound")), "term")
    outside = absent.agg(F.coalesce(F.sum((F.col("n") > F.col("bound")).cast("long")), F.lit(0)).alias("absent"), F.coalesce(F.sum((F.col("n") > F.col("total") / F.col("capacity")).cast("long")), F.lit(0)).alias("frequent"))
    sums = summary.agg(F.sum((counters.total() != F.col("total")).cast("long")).alias("totals"), F.sum((counters.largest_error() > F.col("total") / F.col("capacity")).cast("long")).alias("errors"))
    return inside.join(outside, F.lit(True)).join(sums, F.lit(True))


def timed(run: Callable[[], object]) -> tuple[object, float]:
    """A result and the seconds it took."""
    began = time.perf_counter()
    return run(), time.perf_counter() - began
