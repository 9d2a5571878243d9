"""Answers from summaries and models: hot places, place frequencies, several terms, and the model-free baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.operators import counters
from termatlas.operators.model import counts_of

HOW = ("auto", "counter", "model", "bound", "zero", "neighbours")


def hot_places(summary: DataFrame, k: int = 10, terms: list[str] | None = None) -> DataFrame:
    """term, rank, cell, est, lower, upper: the first k counters; the true count lies within the bounds."""
    s = summary if terms is None else summary.where(F.col("term").isin(terms))
    rows = s.select("term", F.posexplode(F.slice("centers", 1, k)).alias("rank", "c"))
    return rows.select("term", (F.col("rank") + 1).alias("rank"), "c.cell", F.col("c.f").alias("est"), (F.col("c.f") - F.col("c.err")).alias("lower"), F.col("c.f").alias("upper"))


def frequent_places(summary: DataFrame, eps: float) -> DataFrame:
    """term, cell, f, err, guaranteed of counters with a share of eps or more; guaranteed where the lower bound has it too."""
    rows = counters.exploded(summary).where(F.col("f") >= F.lit(eps) * F.col("total"))
    return rows.select("term", "cell", "f", "err", (F.col("f") - F.col("err") >= F.lit(eps) * F.col("total")).alias("guaranteed"))


def neighbour_means(counts: DataFrame, asked: DataFrame, radius: int = 1, missing: str = "zero", size_e6: int = geo.SIZE) -> DataFrame:
    """qid and the mean count of the cells around the asked one; cells without a counter are 0, or ignored.

    Asked cells fan out to their (2 radius + 1)**2 - 1 neighbours, an equi-join by cell.
    """
    n_cols, n_rows = geo.columns(size_e6), geo.rows(size_e6)
    steps = [(dr, dc) for dr in range(-radius, radius + 1) for dc in range(-radius, radius + 1) if (dr, dc) != (0, 0)]
    around = asked.select("qid", "term", "cell", F.explode(F.array(*(F.struct(F.lit(a).alias("dr"), F.lit(b).alias("dc")) for a, b in steps))).alias("s"))
    row, col = geo.cell_row("cell", size_e6) + F.col("s.dr"), F.pmod(geo.cell_col("cell", size_e6) + F.col("s.dc"), F.lit(n_cols))
    around = around.select("qid", "term", (row * n_cols + col).alias("cell"), row.between(0, n_rows - 1).alias("on_map")).where("on_map")
    found = around.join(counts.select("term", "cell", "n"), ["term", "cell"], "left")
    mean = F.sum(F.coalesce("n", F.lit(0))) / F.count("*") if missing == "zero" else F.coalesce(F.avg("n"), F.lit(0.0))
    return found.groupBy("qid").agg(mean.alias("mean"))


def place_frequency(summary: DataFrame, asked: DataFrame, models: DataFrame | None = None, how: str = "auto", size_e6: int = geo.SIZE, radius: int = 1, missing: str = "zero") -> DataFrame:
    """qid, term, cell, est, lower, upper, how of asked (qid, term, cell).

    A stored cell answers with its counter (but how='model' never uses it). Others answer with
    the model's total * p ('auto', 'model'), the smallest counter ('bound'), 0 ('zero'), the
    mean of the cells around ('neighbours'), or nothing ('counter': null).
    """
    if how not in HOW:
        raise ValueError(f"how {how!r} is none of {HOW}")
    own = counters.exploded(summary).select("term", "cell", "f", "err")
    rows = asked.select("qid", "term", "cell").join(own, ["term", "cell"], "left")
    rows = rows.join(summary.select("term", "total", counters.absent_bound().alias("bound")), "term", "left")
    other, name = F.lit(None).cast("double"), "none"
    if how in ("auto", "model"):
        rows = rows.join(models.select("term", "center_cell", "focus", "spread"), "term", "left")
        other, name = F.col("total") * geo.decay(geo.cell_distance("center_cell", "cell", size_e6), "focus", "spread"), "model"
    elif how == "bound":
        other, name = F.col("bound").cast("double"), "bound"
    elif how == "zero":
        other, name = F.lit(0.0), "zero"
    elif how == "neighbours":
        rows = rows.join(neighbour_means(counts_of(summary), asked, radius, missing, size_e6), "qid", "left")
        other, name = F.coalesce("mean", F.lit(0.0)), "neighbours"
    stored = F.col("f").isNotNull() & F.lit(how != "model")
    return rows.select("qid", "term", "cell", F.when(stored, F.col("f").cast("double")).otherwise(other).alias("est"), F.when(F.col("f").isNotNull(), F.col("f") - F.col("err")).otherwise(0).alias("lower"), F.coalesce("f", "bound").alias("upper"), F.when(stored, F.lit("counter")).otherwise(F.lit(name)).alias("how"))


def region_frequency(summary: DataFrame, models: DataFrame, regions: DataFrame, how: str = "auto", size_e6: int = geo.SIZE) -> DataFrame:
    """region, term, est: sums over the cells of regions (region, cell) for every modelled term."""
    cells = geo.on_every_cell(regions.select("cell").distinct(), models.select("term").distinct()).withColumn("qid", F.monotonically_increasing_id())
    est = place_frequency(summary, cells, models, how, size_e6).select("term", "cell", "est")
    return est.join(regions, "cell").groupBy("region", "term").agg(F.sum("est").alias("est"))


def joint(models: DataFrame, asked: DataFrame, cells: DataFrame, dependence: str = "independent", pairing: str = "best", k: int = 1, size_e6: int = geo.SIZE) -> DataFrame:
    """qid, rank, cell, p: joint probability of the terms of asked (qid, terms) on the cells given.

    independent: the product; bound: the smallest. pairing 'rank' joins the models of equal
    rank of the terms (k ranks), 'best' each term's likeliest. Queries in which a term has no model
    have no rows. Queries are broadcast to the cells where they are few (geo.MOST_ON_CELLS).
    """
    m = models.select("term", "rank", "center_cell", "focus", "spread", "loglik")
    if pairing == "best":
        m = m.groupBy("term").agg(F.max_by(F.struct("center_cell", "focus", "spread"), F.struct("loglik", -F.col("rank"))).alias("m")).select("term", F.lit(0).alias("rank"), "m.*")
    m = m.where(F.col("rank") < k) if pairing == "rank" else m
    t = asked.select("qid", F.array_distinct("terms").alias("terms")).select("qid", F.size("terms").alias("wanted"), F.explode("terms").alias("term"))
    each = t.join(m, "term").groupBy("qid", "rank", "wanted").agg(F.collect_list(F.struct("center_cell", "focus", "spread")).alias("ms")).where(F.size("ms") == F.col("wanted"))
    rows = geo.on_every_cell(cells, each)
    # a query's models on one row: the joint value needs no shuffle of the surface
    ps = F.transform("ms", lambda x: geo.decay(geo.cell_distance(x["center_cell"], F.col("cell"), size_e6), x["focus"], x["spread"]))
    p = F.aggregate(ps, F.lit(1.0), lambda s, x: s * x) if dependence == "independent" else F.array_min(ps)
    return rows.select("qid", "rank", "cell", p.alias("p"))


def hot_places_multi(models: DataFrame, asked: DataFrame, cells: DataFrame, k: int = 1, dependence: str = "independent", pairing: str = "best", size_e6: int = geo.SIZE) -> DataFrame:
    """qid, rank, cell, p: the k cells of the highest joint probability, or one for each of k paired ranks."""
    p = joint(models, asked, cells, dependence, pairing, k, size_e6)
    if pairing == "rank":
        best = p.groupBy("qid", "rank").agg(F.max(F.struct(F.col("p"), -F.col("cell"))).alias("b"))
        return best.select("qid", (F.col("rank") + 1).alias("rank"), (-F.col("b.col2")).alias("cell"), "b.p")
    order = Window.partitionBy("qid").orderBy(F.desc("p"), "cell")
    return p.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("qid", "rank", "cell", "p")


def place_frequency_multi(models: DataFrame, totals: DataFrame, asked: DataFrame, dependence: str = "independent", size_e6: int = geo.SIZE) -> DataFrame:
    """qid, cell, est of asked (qid, terms, cell): joint probability times the smallest of the terms' totals."""
    best = models.groupBy("term").agg(F.max_by(F.struct("center_cell", "focus", "spread"), F.struct("loglik", -F.col("rank"))).alias("m")).select("term", "m.*")
    t = asked.select("qid", "cell", F.explode(F.array_distinct("terms")).alias("term")).join(best, "term", "left").join(totals.select("term", "total"), "term", "left")
    p = geo.decay(geo.cell_distance("center_cell", "cell", size_e6), "focus", "spread")
    both = F.exp(F.sum(F.log(p))) if dependence == "independent" else F.min(p)
    every = F.count(p) == F.count("*")
    return t.groupBy("qid", "cell").agg(F.when(every, both * F.min("total")).otherwise(0.0).alias("est"))


def intersect_summaries(summary: DataFrame, asked: DataFrame, k: int = 1) -> DataFrame:
    """qid, rank, cell, n without a model: cells stored for every term of asked (qid, terms), counted by the smallest counter."""
    t = asked.select("qid", F.array_distinct("terms").alias("terms")).select("qid", F.size("terms").alias("wanted"), F.explode("terms").alias("term"))
    rows = t.join(counts_of(summary), "term").groupBy("qid", "wanted", "cell").agg(F.count("*").alias("held"), F.min("n").alias("n")).where("held = wanted")
    order = Window.partitionBy("qid").orderBy(F.desc("n"), "cell")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("qid", "rank", "cell", "n")


def spark_top_k(occ: DataFrame, k: int = 10) -> DataFrame:
    """term, rank, cell, n by Spark's own approx_top_k sketch, for comparison."""
    rows = occ.where(F.col("cell").isNotNull()).groupBy("term").agg(F.expr(f"approx_top_k(cell, {k})").alias("top"))
    return rows.select("term", F.posexplode("top").alias("rank", "t")).select("term", (F.col("rank") + 1).alias("rank"), F.col("t.item").alias("cell"), F.col("t.count").alias("n"))


def spark_sketch(occ: DataFrame, eps: float = 0.01, confidence: float = 0.95, seed: int = 42) -> DataFrame:
    """term, sketch: Spark's count-min sketch of a term's cells, for comparison."""
    return occ.where(F.col("cell").isNotNull()).groupBy("term").agg(F.count_min_sketch("cell", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))


def register(spark: SparkSession, **frames: DataFrame) -> None:
    """Views for SQL: occ, counts, summary_flat, models, cells, whatever is given."""
    geo.register_sql(spark)
    for name, frame in frames.items():
        frame.createOrReplaceTempView(name)
