"""Exact counts, posting lists and answers: the detailed map that summaries replace."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def counts(occ: DataFrame) -> DataFrame:
    """term, cell, n: one shuffle of partial counts."""
    return occ.where(F.col("term").isNotNull() & F.col("cell").isNotNull()).groupBy("term", "cell").agg(F.count("*").alias("n"))


def posting_lists(occ: DataFrame) -> DataFrame:
    """term, postings (cell, n): an inverted index of cells; collects counted cells, never arrivals."""
    return counts(occ).groupBy("term").agg(F.array_sort(F.collect_list(F.struct("cell", "n"))).alias("postings"))


def totals(count: DataFrame) -> DataFrame:
    return count.groupBy("term").agg(F.sum("n").alias("total"))


def hot_places(count: DataFrame, k: int) -> DataFrame:
    """term, rank, cell, n."""
    order = Window.partitionBy("term").orderBy(F.desc("n"), "cell")
    return count.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("term", "rank", "cell", "n")


def place_frequency(count: DataFrame, asked: DataFrame) -> DataFrame:
    """qid, term, cell, n of asked (qid, term, cell); 0 where the term never was."""
    return asked.join(count, ["term", "cell"], "left").select("qid", "term", "cell", F.coalesce("n", F.lit(0)).alias("n"))


def joint_counts(occ: DataFrame, asked: DataFrame, kind: str = "min") -> DataFrame:
    """qid, cell, n of pairs of terms (qid, a, b): the smaller of both counts, or messages that have both."""
    if kind == "min":
        c = counts(occ)
        rows = asked.join(c.select(F.col("term").alias("a"), "cell", F.col("n").alias("na")), "a").join(c.select(F.col("term").alias("b"), "cell", F.col("n").alias("nb")), ["b", "cell"])
        return rows.select("qid", "cell", F.least("na", "nb").alias("n"))
    one = occ.select("msg_id", "cell", "term").distinct()
    pairs = asked.join(one.select(F.col("term").alias("a"), "msg_id", "cell"), "a").join(one.select(F.col("term").alias("b"), "msg_id", F.col("cell").alias("cb")), ["b", "msg_id"])
    return pairs.where("cell = cb").groupBy("qid", "cell").agg(F.count("*").alias("n"))


def term_pairs(occ: DataFrame, terms: DataFrame) -> DataFrame:
    """a, b (a < b), n_places, joint, n_a, n_b, ratio: pairs of given terms with a common place.

    joint sums the smaller counts over places; ratio is joint over the larger of both totals.
    The terms are a chosen list: a self-join on cell gives at most (terms of a cell)**2 / 2 rows a cell,
    summed on the map side to one a pair. Terms above a share of the messages are bounded by that share.
    """
    c = counts(occ.join(terms.select("term"), "term", "left_semi"))
    t = totals(c)
    x, y = c.select(F.col("term").alias("a"), "cell", F.col("n").alias("x")), c.select(F.col("term").alias("b"), "cell", F.col("n").alias("y"))
    rows = x.join(y, "cell").where("a < b").groupBy("a", "b").agg(F.count("*").alias("n_places"), F.sum(F.least("x", "y")).alias("joint"))
    rows = rows.join(t.select(F.col("term").alias("a"), F.col("total").alias("n_a")), "a").join(t.select(F.col("term").alias("b"), F.col("total").alias("n_b")), "b")
    return rows.withColumn("ratio", F.col("joint") / F.greatest("n_a", "n_b"))
