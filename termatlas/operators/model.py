"""Decay models: a term's probability at a distance, fitted by maximum likelihood.

A fit takes rows (term, rank, center_cell, total, bands), bands an array of
(d, n, cells, occ): distance, arrivals, cells of the map and cells with arrivals. One band per
distinct distance is the fit on cells, a few bands the ring fit; the work is one
logarithm pair a band and evaluation, which n_eval counts, at the most steps that a fit may take.

Likelihoods, by how arrivals at cells are read (results name theirs):
  trial       every arrival of the term is a trial for each cell            (default)
  occurrence  arrivals in a band, and its cells less these as empty ones, not below 0
  presence    cells with and without arrivals
  share       cells compete; the focus is the factor that makes probabilities sum to 1
  literal_bands  counts inside the logarithms: constants, so the best parameters do not
              depend on the data; kept as a negative example
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.functions.scratch import materialize
from termatlas.operators import rings as R

LIKELIHOODS = ("trial", "occurrence", "presence", "share", "literal_bands")
ALPHA_MAX, ALPHA_STEPS, FOCUS_STEPS, FOCUS_NEAR = 8.0, 32, 32, 1e-9  # a spread to 2e-6, a focus to less than 1e-9 of itself
BANDS = "array<struct<d:double,n:double,cells:double,occ:double>>"
MODEL = "term string, rank int, center_cell int, focus double, spread double, loglik double, total long, likelihood string, source string, n_eval long, fitted_at long"


def _weights(likelihood: str, n: np.ndarray, cells: np.ndarray, occ: np.ndarray, total: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hits and misses of each band: the factors of ln p and ln(1 - p)."""
    if likelihood == "trial":
        return n, np.maximum(total[:, None] * cells - n, 0)
    if likelihood == "occurrence":
        return n, np.maximum(cells - n, 0)
    if likelihood == "presence":
        return occ, np.maximum(cells - occ, 0)
    if likelihood == "literal_bands":
        return (cells > 0).astype(float), (cells > 0).astype(float)
    raise ValueError(likelihood)


def fit_arrays(d: np.ndarray, n: np.ndarray, cells: np.ndarray, occ: np.ndarray, total: np.ndarray, likelihood: str = "trial", min_distance: float = 1.0, alpha_max: float = ALPHA_MAX) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """focus, spread, log-likelihood of each row of arrays (rows, bands), and the evaluations of a row.

    For a fixed spread the best focus is the root of a monotone function, found by Newton's steps of logarithms, few
    of the FOCUS_STEPS that evaluations count; the spread is found by golden sections of what remains, whose steps are fixed.
    Bands without cells are padding.
    """
    x = np.log(np.maximum(d, min_distance))
    near = np.where(cells > 0, x, np.inf).min(axis=1, keepdims=True)
    near = np.where(np.isfinite(near), near, 0.0)

    def best(alpha: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if likelihood == "share":
            w = -alpha[:, None] * x
            top = np.where(cells > 0, w, -np.inf).max(axis=1)
            top = np.where(np.isfinite(top), top, 0.0)
            mass = top + np.log(np.maximum((cells * np.exp(w - top[:, None])).sum(axis=1), 1e-300))
            return np.minimum(np.exp(-mass), 1.0), (n * w).sum(axis=1) - n.sum(axis=1) * mass
        hit, miss = _weights(likelihood, n, cells, occ, total)
        w = np.exp(-alpha[:, None] * x)
        high = np.minimum(np.exp(alpha * near[:, 0]), 1.0) * (1 - 1e-9)  # p is at most 1 everywhere
        low, hits = high * 1e-12, hit.sum(axis=1)
        # in logarithms the sum is convex, its slope at least 1 and its root at most where p is small everywhere, so steps only come down to the root
        c = np.clip(hits / np.maximum(np.einsum("ij,ij->i", miss, w), 1e-300), low, high)
        odds, rest = np.empty_like(w), np.empty_like(w)
        for _ in range(FOCUS_STEPS):
            np.multiply(c[:, None], w, out=odds)
            np.subtract(1, odds, out=rest)
            np.divide(odds, rest, out=odds)
            got = np.maximum(np.einsum("ij,ij->i", miss, odds), 1e-300)
            np.divide(odds, rest, out=rest)
            last, c = c, np.clip(c * (hits / got) ** (got / np.maximum(np.einsum("ij,ij->i", miss, rest), got)), low, high)
            if (np.abs(c - last) <= FOCUS_NEAR * last).all():
                break
        p = np.clip(c[:, None] * w, 1e-300, 1 - 1e-12)
        return c, (hit * np.log(p) + miss * np.log1p(-p)).sum(axis=1)

    g = (5**0.5 - 1) / 2
    a, b = np.zeros(len(d)), np.full(len(d), alpha_max)
    s, t = b - g * (b - a), a + g * (b - a)
    fs, ft = best(s)[1], best(t)[1]
    for _ in range(ALPHA_STEPS):
        left = fs >= ft
        a, b = np.where(left, a, s), np.where(left, t, b)
        new = np.where(left, b - g * (b - a), a + g * (b - a))
        f_new = best(new)[1]
        s, t, fs, ft = np.where(left, new, t), np.where(left, s, new), np.where(left, f_new, ft), np.where(left, fs, f_new)
    alpha = (a + b) / 2
    focus, loglik = best(alpha)
    return focus, alpha, loglik, (ALPHA_STEPS + 3) * (1 if likelihood == "share" else FOCUS_STEPS + 1)


PARTS, ROOM = ("d", "n", "cells", "occ"), 1 << 16


def _padded(part: pd.DataFrame) -> list[np.ndarray]:
    """Arrays (rows, bands) of the bands' fields; missing bands have no cells."""
    size = part.d.map(len).to_numpy()
    here = np.arange(max(size.max(initial=0), 1)) < size[:, None]
    out = []
    for name in PARTS:
        x = np.zeros(here.shape)
        x[here] = np.nan_to_num(np.concatenate([np.asarray(v, float) for v in part[name]]))
        out.append(x)
    out[0][out[0] == 0] = 1.0
    return out


def fit(rows: DataFrame, likelihood: str = "trial", min_distance: float = 1.0, alpha_max: float = ALPHA_MAX, source: str = "rings", keep: str | None = None) -> DataFrame:
    """MODEL of each row: term, rank, center_cell, total, bands (arrays of d, n, cells, occ) and optional fitted_at.

    keep: an int column that models keep.
    """
    if likelihood not in LIKELIHOODS:
        raise ValueError(f"likelihood {likelihood!r} is none of {LIKELIHOODS}")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            step = max(8, ROOM // int(frame.d.map(len).max())) if len(frame) else 1  # wide fits stay small in memory
            for at in range(0, len(frame), step):
                part = frame.iloc[at : at + step]
                d, n, cells, occ = _padded(part)
                focus, spread, loglik, evals = fit_arrays(d, n, cells, occ, part.total.to_numpy(float), likelihood, min_distance, alpha_max)
                out = pd.DataFrame({
                    "term": part.term, "rank": part["rank"], "center_cell": part.center_cell, "focus": focus, "spread": spread, "loglik": loglik, "total": part.total,
                    "likelihood": likelihood, "source": source, "n_eval": evals * part.d.map(len), "fitted_at": part.fitted_at,
                })
                yield out if keep is None else out.assign(**{keep: part[keep]})

    if "fitted_at" not in rows.columns:
        rows = rows.withColumn("fitted_at", F.col("total"))
    kept = [] if keep is None else [keep]
    given = rows.select("term", F.col("rank").cast("int").alias("rank"), "center_cell", "total", F.col("bands").cast(BANDS).alias("bands"), F.col("fitted_at").cast("long").alias("fitted_at"), *kept)
    # a field at a time: numbers reach numpy without a look at each band
    fields = (F.col(f"bands.{name}").alias(name) for name in PARTS)
    # fits are long for their few bytes, so tasks are not merged by size
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return given.select("term", "rank", "center_cell", "total", "fitted_at", *fields, *kept).repartition(tasks, "term", "center_cell").mapInPandas(run, MODEL if keep is None else f"{MODEL}, {keep} int")


def best_center(models: DataFrame) -> DataFrame:
    """The likeliest model of each term; ties to the better rank."""
    names = [c for c in models.columns if c != "term"]
    return models.groupBy("term").agg(F.max_by(F.struct(*names), F.struct("loglik", -F.col("rank"))).alias("m")).select("term", "m.*").select(*models.columns)


def _first(candidates: int | None):
    return F.col("centers") if candidates is None else F.slice("centers", 1, candidates)


def ring_rows(summary: DataFrame, table: DataFrame, radii: list[float], candidates: int | None = None, size_e6: int = geo.SIZE, distances: str = "cells", include_center: bool = False) -> DataFrame:
    """Fit rows from the bands of all centres, or the first `candidates`. table: row, band, cells, mean_dist, small and broadcast.

    distances: 'cells' takes the mean distance of a band's cells, 'mid' the band's middle.
    Likelihoods can only be compared of centres that saw about the same arrivals: a counter that was taken
    late may hold next to none, and is left out when it saw less than half of what the fullest did.
    """

    def seen(c: Column) -> Column:
        return c["f"] + F.aggregate(c["rings"], F.lit(0.0), lambda s, x: s + x)

    each = summary.select("term", "total", F.array_max(F.transform("centers", seen)).alias("most"), F.posexplode(_first(candidates)).alias("rank", "c"))
    c = each.where(2 * seen(F.col("c")) >= F.col("most")).select("term", "total", "rank", F.col("c.cell").alias("center_cell"), F.col("c.f").alias("f"), F.col("c.rings").alias("rings"))
    mids = R.mean_distance(radii, distances)
    place = F.col("mean_dist") if mids is None else F.element_at(F.array(*map(F.lit, mids)), F.col("band") + 1)
    by_row = table.select("row", F.struct("band", place.alias("d"), "cells").alias("t")).groupBy("row").agg(F.array_sort(F.collect_list("t")).alias("ts"))
    rows = c.withColumn("row", geo.cell_row("center_cell", size_e6)).join(F.broadcast(by_row), "row")
    # only few centres have arrivals counted by cell here, so occ is left at n where it would be needed
    bands = F.transform("ts", lambda t: F.struct(t["d"].alias("d"), F.coalesce(F.element_at("rings", t["band"] + 1), F.lit(0.0)).alias("n"), t["cells"].cast("double").alias("cells"), F.least(F.coalesce(F.element_at("rings", t["band"] + 1), F.lit(0.0)), t["cells"].cast("double")).alias("occ")))
    if include_center:
        bands = F.concat(F.array(F.struct(F.lit(1.0).alias("d"), F.col("f").cast("double").alias("n"), F.lit(1.0).alias("cells"), F.lit(1.0).alias("occ"))), bands)
    return rows.select("term", "rank", "center_cell", "total", bands.alias("bands"))


FINE = 480


def fine_radii(outer: float = 181.0, n: int = FINE) -> list[float]:
    """Bands so narrow that cells of one band lie at all but the same distance."""
    ratio = (0.9 / outer) ** (1 / (n - 1))
    return [outer * ratio**k for k in range(n - 1, -1, -1)]


def cell_rows(counts: DataFrame, centres: DataFrame, table: DataFrame, radii: list[float], size_e6: int = geo.SIZE, include_center: bool = True) -> DataFrame:
    """Fit rows on cells, equal distances collapsed: counts (term, cell, n), centres (term, rank, cell, total), table of the fine bands."""
    hit = R.exact(counts, centres, radii, size_e6=size_e6, with_cells=True)
    c = centres.select("term", "rank", F.col("cell").alias("center_cell"), "total", geo.cell_row("cell", size_e6).alias("row"))
    every = c.join(F.broadcast(table), "row").join(hit, ["term", "center_cell", "band"], "left")
    own = F.struct(F.col("mean_dist").alias("d"), F.coalesce("n", F.lit(0)).cast("double").alias("n"), F.col("cells").cast("double").alias("cells"), F.coalesce("occ_cells", F.lit(0)).cast("double").alias("occ"))
    rows = every.groupBy("term", "rank", "center_cell", "total").agg(F.collect_list(own).alias("bands"))
    if include_center:
        at = counts.select("term", F.col("cell").alias("center_cell"), F.col("n").alias("own"))
        rows = rows.join(at, ["term", "center_cell"], "left")
        first = F.struct(F.lit(1.0).alias("d"), F.coalesce("own", F.lit(0)).cast("double").alias("n"), F.lit(1.0).alias("cells"), (F.coalesce("own", F.lit(0)) > 0).cast("double").alias("occ"))
        rows = rows.withColumn("bands", F.concat(F.array(first), "bands")).drop("own")
    return rows


BLOCK = 512


def fit_cells(counts: DataFrame, centres: DataFrame, table: DataFrame, radii: list[float], likelihood: str = "trial", source: str = "rings", size_e6: int = geo.SIZE) -> DataFrame:
    """fit(cell_rows(...)) without a row for each pair of a centre and a cell.

    A term's counts, at most one for each cell of the map, meet BLOCK of its centres at a time. Bands of all
    distances from a row of the grid are looked up once a block, so a pair costs a look into them.
    """
    n_rows, n_cols, n = geo.rows(size_e6), geo.columns(size_e6), len(radii)
    sphere, ends = R.Sphere(size_e6), np.asarray(radii, float)
    # the table is rows of the grid times bands, which joins broadcast
    got = table.select("row", "band", "cells", "mean_dist").toPandas()
    cells_of, far = np.zeros((n_rows, n)), np.ones((n_rows, n))
    cells_of[got.row, got.band], far[got.row, got.band] = got.cells, got.mean_dist

    def run(own: pd.DataFrame, given: pd.DataFrame) -> pd.DataFrame:
        cell, k = given.cell.to_numpy(), given.n.to_numpy(float)
        row, col = cell // n_cols, cell % n_cols
        own = own.sort_values("cell", kind="stable")
        centre = own.cell.to_numpy()
        counted, seen, at = np.zeros((len(own), n + 1)), np.zeros((len(own), n + 1)), -1
        mine = np.zeros(len(own))
        used, where = np.unique(row, return_inverse=True)
        turns = np.arange(n_cols)
        for i, c in enumerate(centre.tolist()):
            if c // n_cols != at:
                at = c // n_cols
                d = sphere.between(sphere.place(at * n_cols), sphere.place(used[:, None] * n_cols + turns[None, :]))
                looked = np.where(d > 0, np.minimum(np.searchsorted(ends, d), n - 1), n)
            band = looked[where, (col - c % n_cols) % n_cols]
            counted[i], seen[i] = np.bincount(band, k, n + 1), np.bincount(band, minlength=n + 1)
            mine[i] = counted[i, n]
        rows = centre // n_cols
        there = cells_of[rows] > 0
        # the centre's own cell comes first, at distance 1
        first = np.ones((len(own), 1))
        d, cells = np.hstack([first, far[rows]]), np.hstack([first, cells_of[rows]])
        hits, occ = np.hstack([mine[:, None], counted[:, :n] * there]), np.hstack([(mine > 0)[:, None], seen[:, :n] * there])
        total, step, fits = own.total.to_numpy(float), max(8, ROOM // (n + 1)), []
        for i in range(0, len(own), step):
            b = slice(i, i + step)
            fits.append(fit_arrays(d[b], hits[b], cells[b], occ[b], total[b], likelihood))
        focus, spread, loglik = (np.concatenate([f[j] for f in fits]) for j in range(3))
        return pd.DataFrame({
            "term": own.term, "rank": own["rank"], "center_cell": own.cell, "focus": focus, "spread": spread, "loglik": loglik, "total": own.total,
            "likelihood": likelihood, "source": source, "n_eval": fits[0][3] * (there.sum(axis=1) + 1), "fitted_at": own.total,
        })

    if likelihood not in LIKELIHOODS:
        raise ValueError(f"likelihood {likelihood!r} is none of {LIKELIHOODS}")
    order = Window.partitionBy("term").orderBy("cell", "rank")
    dealt = centres.select("term", "total", "rank", "cell", F.floor((F.row_number().over(order) - 1) / BLOCK).cast("int").alias("block"))
    dealt = materialize(dealt, "blocks")
    seen = dealt.select("term", F.col("block").alias("part")).distinct()
    # fits are long for their few bytes, so tasks are not merged by size
    tasks = 4 * int(counts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    own = dealt.repartition(tasks, "term", "block").groupBy("term", "block")
    cells = counts.select("term", "cell", "n").join(F.broadcast(seen), "term").repartition(tasks, "term", "part").groupBy("term", "part")

    def both(own: pd.DataFrame, given: pd.DataFrame) -> pd.DataFrame:
        return run(own, given) if len(own) else pd.DataFrame({})

    return own.cogroup(cells).applyInPandas(both, MODEL)


def counts_of(summary: DataFrame) -> DataFrame:
    """The counters as counts: term, cell, n."""
    return summary.select("term", F.explode("centers").alias("c")).select("term", "c.cell", F.col("c.f").alias("n"))


def centres_of(summary: DataFrame, candidates: int | None = None) -> DataFrame:
    """term, total, rank (from 0), cell of all counters, or the first."""
    return summary.select("term", "total", F.posexplode(_first(candidates)).alias("rank", "c")).select("term", "total", "rank", "c.cell")


def top_cells(counts: DataFrame, k: int | None) -> DataFrame:
    """term, total, rank (from 0), cell: the k cells with the most arrivals (None: all), by exact counts."""
    order = Window.partitionBy("term").orderBy(F.desc("n"), "cell")
    ranked = counts.withColumn("rank", F.row_number().over(order) - 1)
    ranked = ranked if k is None else ranked.where(F.col("rank") < k)
    return ranked.join(counts.groupBy("term").agg(F.sum("n").alias("total")), "term").select("term", "total", "rank", "cell")


SCREEN, REFINED = 64, 5


def screened(counts: DataFrame, centres: DataFrame, likelihood: str = "trial", size_e6: int = geo.SIZE, table: DataFrame | None = None) -> DataFrame:
    """Of each term's centres (term, total, rank, cell) the REFINED likeliest by a fit on SCREEN bands, which are a few cells wide at most.

    All centres are fitted; only the finer fit, which tells near ones apart, is left to the best of them.
    table: the band table of the SCREEN radii, where it is at hand.
    """
    wide = fine_radii(n=SCREEN)
    table = R.band_tables(counts.sparkSession, [wide], size_e6) if table is None else table
    models = fit_cells(counts, centres, table, wide, likelihood, size_e6=size_e6)
    order = Window.partitionBy("term").orderBy(F.desc("loglik"), "rank")
    best = models.withColumn("place", F.row_number().over(order)).where(F.col("place") <= REFINED)
    return materialize(best.select("term", "total", "rank", F.col("center_cell").alias("cell")), "centres")


def fit_exact(counts: DataFrame, table: DataFrame, radii: list[float], candidates: int | None = None, likelihood: str = "trial", size_e6: int = geo.SIZE, screen: DataFrame | None = None) -> DataFrame:
    """Reference models from all occurrences: the likeliest of all cells with arrivals as centre, or of the `candidates` most frequent."""
    centres = top_cells(counts, candidates)
    centres = screened(counts, centres, likelihood, size_e6, screen) if candidates is None else centres
    return best_center(fit_cells(counts, centres, table, radii, likelihood, source="all", size_e6=size_e6))


def fit_sides(sides: list[tuple[DataFrame, DataFrame, str]], table: DataFrame, radii: list[float], screen: DataFrame | None = None, likelihood: str = "trial") -> list[DataFrame]:
    """The likeliest models of several (counts, centres, source), which share terms, by one fit for all; screened where `screen` is given."""
    key = lambda df, i: df.withColumn("term", F.concat(F.lit(f"{i}:"), "term"))
    counts, centres = (reduce(DataFrame.unionByName, (key(side[k].select(*names), i) for i, side in enumerate(sides))) for k, names in ((0, ["term", "cell", "n"]), (1, ["term", "total", "rank", "cell"])))
    centres = centres if screen is None else screened(counts, centres, likelihood, table=screen)
    models = materialize(best_center(fit_cells(counts, centres, table, radii, likelihood)), "models")
    own = lambda i: models.where(F.col("term").startswith(f"{i}:")).withColumn("term", F.substr("term", F.lit(len(f"{i}:") + 1)))
    return [own(i).withColumn("source", F.lit(source)) for i, (_, _, source) in enumerate(sides)]


def single_cell_rows(counts: DataFrame, centres: DataFrame, grid: DataFrame, size_e6: int = geo.SIZE) -> DataFrame:
    """Fit rows with one band for each cell of the map, nothing collapsed: the fit as first published, for a few centres.

    centres: term, total, rank, cell. Each row holds as many bands as the map has cells.
    """
    c = centres.select("term", "total", "rank", F.col("cell").alias("center_cell"))
    rows = c.join(grid.select("cell"), F.lit(True)).join(counts, ["term", "cell"], "left")
    d = F.when(F.col("cell") == F.col("center_cell"), F.lit(1.0)).otherwise(geo.cell_distance("center_cell", "cell", size_e6))
    n = F.coalesce("n", F.lit(0)).cast("double")
    one = F.struct(d.alias("d"), n.alias("n"), F.lit(1.0).alias("cells"), (n > 0).cast("double").alias("occ"))
    return rows.groupBy("term", "total", "rank", "center_cell").agg(F.collect_list(one).alias("bands"))


def band_loglik(bands: Column, total: Column, focus: Column, spread: Column, likelihood: str = "trial", min_distance: float = 1.0) -> Column:
    """Log-likelihood of bands under given parameters, by higher-order functions."""

    def term(b: Column) -> Column:
        p = F.greatest(F.least(geo.decay(b["d"], focus, spread, min_distance), F.lit(1 - 1e-12)), F.lit(1e-300))
        if likelihood == "trial":
            hit, miss = b["n"], F.greatest(total * b["cells"] - b["n"], F.lit(0.0))
        elif likelihood == "presence":
            hit, miss = b["occ"], F.greatest(b["cells"] - b["occ"], F.lit(0.0))
        else:
            hit, miss = b["n"], F.greatest(b["cells"] - b["n"], F.lit(0.0))
        return hit * F.log(p) + miss * F.log1p(-p)

    return F.aggregate(bands, F.lit(0.0), lambda s, b: s + term(b))


def cell_loglik(counts: DataFrame, params: DataFrame, grid: DataFrame, likelihood: str = "trial", size_e6: int = geo.SIZE) -> DataFrame:
    """term, center_cell, loglik over every cell of the grid: one distance a cell. params: term, center_cell, focus, spread, total."""
    cells = geo.on_every_cell(grid, params).join(counts, ["term", "cell"], "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("double"))
    p = F.greatest(F.least(geo.decay(geo.cell_distance("center_cell", "cell", size_e6), "focus", "spread"), F.lit(1 - 1e-12)), F.lit(1e-300))
    if likelihood == "trial":
        hit, miss = F.col("n"), F.col("total") - F.col("n")
    elif likelihood == "presence":
        hit, miss = (F.col("n") > 0).cast("double"), (F.col("n") == 0).cast("double")
    else:
        hit, miss = F.col("n"), (F.col("n") == 0).cast("double")
    return cells.groupBy("term", "center_cell").agg(F.sum(hit * F.log(p) + miss * F.log1p(-p)).alias("loglik"))


def fit_lattice(rows: DataFrame, spreads: list[float], focuses: list[float], likelihood: str = "trial") -> DataFrame:
    """term, rank, center_cell, focus, spread, loglik: the best point of a lattice, without Python.

    Log-likelihoods are compared at six decimals, ties to the smaller spread, then focus.
    """
    lattice = rows.withColumn("spread", F.explode(F.array(*map(F.lit, spreads)))).withColumn("focus", F.explode(F.array(*map(F.lit, focuses))))
    lattice = lattice.withColumn("loglik", F.round(band_loglik(F.col("bands"), F.col("total"), F.col("focus"), F.col("spread"), likelihood), 6))
    best = lattice.groupBy("term", "rank", "center_cell").agg(F.max(F.struct("loglik", (-F.col("spread")).alias("s"), (-F.col("focus")).alias("c"))).alias("b"))
    return best.select("term", "rank", "center_cell", (-F.col("b.c")).alias("focus"), (-F.col("b.s")).alias("spread"), "b.loglik")


def fit_two_stage(rows: DataFrame, steps: int = 12, alpha_max: float = ALPHA_MAX, likelihood: str = "trial") -> DataFrame:
    """Coarse, then fine lattice around the coarse optimum; both in DataFrame functions."""
    step_a, step_c = alpha_max / steps, 6.0 / steps
    coarse = fit_lattice(rows, [k * step_a for k in range(steps + 1)], [10 ** (-6 + k * step_c) * 0.999 for k in range(steps + 1)], likelihood)
    near = rows.join(coarse.select("term", "rank", F.col("spread").alias("s0"), F.col("focus").alias("c0")), ["term", "rank"])
    moves = F.array(*(F.lit(k / steps) for k in range(-steps, steps + 1)))
    fine = near.withColumn("u", F.explode(moves)).withColumn("v", F.explode(moves))
    fine = fine.withColumn("spread", F.greatest(F.lit(0.0), F.col("s0") + F.col("u") * step_a)).withColumn("focus", F.least(F.col("c0") * F.pow(F.lit(10.0), F.col("v") * step_c), F.lit(0.999)))
    fine = fine.withColumn("loglik", F.round(band_loglik(F.col("bands"), F.col("total"), F.col("focus"), F.col("spread"), likelihood), 6))
    best = fine.groupBy("term", "rank", "center_cell").agg(F.max(F.struct("loglik", (-F.col("spread")).alias("s"), (-F.col("focus")).alias("c"))).alias("b"))
    return best.select("term", "rank", "center_cell", (-F.col("b.c")).alias("focus"), (-F.col("b.s")).alias("spread"), "b.loglik")


def surface(models: DataFrame, grid: DataFrame, size_e6: int = geo.SIZE) -> DataFrame:
    """term, cell, p, est of each model on every cell."""
    d = geo.cell_distance("center_cell", "cell", size_e6)
    rows = geo.on_every_cell(grid, models.select("term", "center_cell", "focus", "spread", "total"))
    return rows.withColumn("p", geo.decay(d, "focus", "spread")).select("term", "cell", "p", (F.col("p") * F.col("total")).alias("est"))


def stale(totals: DataFrame, models: DataFrame, tolerance: float = 0.1) -> DataFrame:
    """term, total, fitted_at of terms whose arrivals since their latest fit pass the tolerance, or that have none."""
    last = models.groupBy("term").agg(F.max("fitted_at").alias("fitted_at"))
    rows = totals.select("term", "total").join(last, "term", "left")
    return rows.where(F.col("fitted_at").isNull() | (F.col("total") - F.col("fitted_at") > F.lit(tolerance) * F.col("fitted_at")))


def as_of(asked: DataFrame, models: DataFrame, at: str = "at") -> DataFrame:
    """Each asked row (qid, term, at) with the latest model fitted by then: one sort by term and time, no range join."""
    fields = [c for c in models.columns if c not in ("term", "fitted_at")]
    q = asked.select("qid", "term", F.col(at).alias("t"), F.lit(1).alias("side"), F.lit(None).cast(models.select(F.struct("fitted_at", *fields).alias("m")).schema["m"].dataType).alias("m"))
    m = models.select(F.lit(None).cast(asked.schema["qid"].dataType).alias("qid"), "term", F.col("fitted_at").alias("t"), F.lit(0).alias("side"), F.struct("fitted_at", *fields).alias("m"))
    last = Window.partitionBy("term").orderBy("t", "side").rowsBetween(Window.unboundedPreceding, 0)
    return q.unionByName(m).withColumn("m", F.last("m", ignorenulls=True).over(last)).where("side = 1").select("qid", "term", F.col("t").alias(at), "m.*")


def disc_mean(spark: SparkSession, points: int = 200_000, seed: int = 42) -> DataFrame:
    """ratio: mean distance to the centre of uniform points in a unit disc, by sampling; tends to two thirds."""
    return spark.range(points).select(F.sqrt(F.rand(seed)).alias("d")).agg(F.avg("d").alias("ratio"))
