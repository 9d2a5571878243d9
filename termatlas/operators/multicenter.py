"""Terms with several centres: chances combine as those of independent causes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.functions.scratch import materialize
from termatlas.operators import model as M
from termatlas.operators import rings as R

MULTI = "term string, centers array<struct<center_cell:int,focus:double,spread:double>>, loglik double, total long"


def combine(ps: Column) -> Column:
    """1 - product of (1 - p) over an array of probabilities."""
    return 1 - F.aggregate(ps, F.lit(1.0), lambda s, p: s * (1 - p))


def probability(centers: Column, cell: Column, size_e6: int = geo.SIZE) -> Column:
    """Chance of a term of several centres at a cell."""
    return combine(F.transform(centers, lambda c: geo.decay(geo.cell_distance(c["center_cell"], cell, size_e6), c["focus"], c["spread"])))


def distant_centres(counts: DataFrame, k: int, apart: float = 5.0, candidates: int = 50, size_e6: int = geo.SIZE) -> DataFrame:
    """term, rank (from 0), cell, total: frequent cells, each at least `apart` from the better ones; of a bounded candidate list a term."""
    top = M.top_cells(counts, candidates).join(counts, ["term", "cell"]).select("term", "total", "rank", "cell")
    rows = top.groupBy("term", "total").agg(F.array_sort(F.collect_list(F.struct("rank", "cell"))).alias("cs"))

    def add(kept: Column, c: Column) -> Column:
        near = F.exists(kept, lambda o: geo.cell_distance(o, c["cell"], size_e6) < apart)
        return F.when((F.size(kept) >= k) | near, kept).otherwise(F.concat(kept, F.array(c["cell"])))

    kept = F.aggregate("cs", F.array().cast("array<int>"), add)
    return rows.select("term", "total", F.posexplode(kept).alias("rank", "cell"))


def fit_joint(counts: DataFrame, centres: DataFrame, grid: DataFrame, rounds: int = 12, size_e6: int = geo.SIZE, fine: int = 96) -> DataFrame:
    """MULTI: the parameters of all centres of a term together, by coordinate ascent of the trial likelihood.

    Cells enter as classes of equal distance bands to every centre, counted over the grid in
    Spark; a term's classes are bounded by fine ** centres and by the cells.
    """
    radii = M.fine_radii(n=fine)
    c = centres.groupBy("term", "total").agg(F.array_sort(F.collect_list(F.struct("rank", "cell"))).alias("cs")).select("term", "total", F.transform("cs", lambda x: x["cell"]).alias("cs"))
    d = F.transform("cs", lambda x: geo.cell_distance(x, F.col("cell"), size_e6))
    cells = geo.on_every_cell(grid, c).join(counts, ["term", "cell"], "left").withColumn("d", d)
    key = F.transform("d", lambda x: F.coalesce(R.band(x, radii), F.lit(-1)))
    classes = cells.groupBy("term", "total", "cs", key.alias("key")).agg(F.count("*").alias("cells"), F.sum(F.coalesce("n", F.lit(0))).alias("n"), F.max("d").alias("d"))
    rows = classes.groupBy("term", "total", "cs").agg(F.collect_list(F.struct("d", "n", "cells")).alias("classes"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for r in frame.itertuples(index=False):
                x = np.log(np.maximum(np.array([e["d"] for e in r.classes], float), 1.0))
                n, cells_ = np.array([e["n"] for e in r.classes], float), np.array([e["cells"] for e in r.classes], float)
                focus, spread, loglik = ascend(x, n, r.total * cells_ - n, rounds)
                yield pd.DataFrame([{"term": r.term, "centers": [{"center_cell": int(c), "focus": float(a), "spread": float(b)} for c, a, b in zip(r.cs, focus, spread, strict=True)], "loglik": loglik, "total": r.total}])

    return rows.select("term", "total", "cs", "classes").mapInPandas(run, MULTI)


def ascend(x: np.ndarray, hit: np.ndarray, miss: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray, float]:
    """Coordinate ascent: each centre's (log focus, spread) by shrinking steps around the best so far."""
    k = x.shape[1]
    focus, spread = np.full(k, np.log(0.05)), np.full(k, 2.0)

    def value(f: np.ndarray, s: np.ndarray) -> float:
        p = np.exp(np.minimum(f[None] - x * s[None], np.log(1 - 1e-9)))
        q = np.clip(1 - np.prod(1 - p, axis=1), 1e-300, 1 - 1e-12)
        return float((hit * np.log(q) + miss * np.log1p(-q)).sum())

    best, step = value(focus, spread), np.array([1.0, 1.0])
    for _ in range(rounds * 4):
        moved = False
        for c in range(k):
            for df, ds in ((1, 0), (-1, 0), (0, 1), (0, -1), (1, 1), (-1, -1), (1, -1), (-1, 1)):
                f, s = focus.copy(), spread.copy()
                f[c], s[c] = min(f[c] + df * step[0], np.log(0.999)), max(s[c] + ds * step[1], 0.0)
                if (v := value(f, s)) > best + 1e-9:
                    best, focus, spread, moved = v, f, s, True
        if not moved:
            step = step / 2
            if step.max() < 1e-4:
                break
    return np.exp(focus), spread, best


def assign_refit(counts: DataFrame, centres: DataFrame, table: DataFrame, radii: list[float], rounds: int = 3, size_e6: int = geo.SIZE) -> DataFrame:
    """MODEL of each centre: fitted apart, cells given to their most probable centre, fitted again; tables are written each round."""
    own = counts.join(centres.select("term", "total", "rank", F.col("cell").alias("center_cell")), "term")
    models = materialize(M.fit(M.cell_rows(counts, centres, table, radii, size_e6), source="assigned"), "centres")
    for _ in range(rounds):
        p = geo.decay(geo.cell_distance("center_cell", "cell", size_e6), "focus", "spread")
        chance = own.join(models.select("term", "center_cell", "focus", "spread"), ["term", "center_cell"]).withColumn("p", p)
        best = chance.groupBy("term", "cell", "n").agg(F.max_by(F.struct("rank", "center_cell"), F.struct("p", -F.col("rank"))).alias("b"))
        mine = materialize(best.select(F.concat_ws("\x1f", "term", F.col("b.rank").cast("string")).alias("term"), "cell", "n"), "assigned")
        split = centres.withColumn("term", F.concat_ws("\x1f", "term", F.col("rank").cast("string")))
        fitted = M.fit(M.cell_rows(mine, split, table, radii, size_e6), source="assigned")
        models = materialize(fitted.withColumn("term", F.substring_index("term", "\x1f", 1)), "centres")
    return models


def grow(counts: DataFrame, grid: DataFrame, threshold: float, most: int = 4, apart: float = 5.0, size_e6: int = geo.SIZE) -> tuple[DataFrame, list[float]]:
    """Centres are added until the mean absolute error at counted cells is under the threshold: MULTI, and the errors by number."""
    errors, models = [], None
    for k in range(1, most + 1):
        models = materialize(fit_joint(counts, distant_centres(counts, k, apart, size_e6=size_e6), grid, size_e6=size_e6), "multi")
        est = counts.join(models, "term").withColumn("est", F.col("total") * probability(F.col("centers"), F.col("cell"), size_e6))
        errors.append(est.agg(F.avg(F.abs(F.col("est") - F.col("n")))).first()[0] or 0.0)
        if errors[-1] < threshold:
            break
    return models, errors


def surface(models: DataFrame, grid: DataFrame, size_e6: int = geo.SIZE) -> DataFrame:
    """term, cell, p, est of MULTI on every cell."""
    p = probability(F.col("centers"), F.col("cell"), size_e6)
    return geo.on_every_cell(grid, models).select("term", "cell", p.alias("p"), (p * F.col("total")).alias("est"))


def strongest(models: DataFrame) -> DataFrame:
    """The likeliest centre of each term among MODELs."""
    order = Window.partitionBy("term").orderBy(F.desc("loglik"), "rank")
    return models.withColumn("_r", F.row_number().over(order)).where("_r = 1").drop("_r")
