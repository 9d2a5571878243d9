"""Methods end to end: arrivals to summaries to models to answers."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.functions.scratch import materialize
from termatlas.operators import answers, counters, exact
from termatlas.operators import model as M
from termatlas.operators import rings as R


@dataclass
class Atlas:
    """What a method keeps: the summary its bounds come from and a model a term."""

    summary: DataFrame
    models: DataFrame
    candidates: DataFrame

    def hot_places(self, k: int = 10) -> DataFrame:
        return answers.hot_places(self.summary, k)

    def place_frequency(self, asked: DataFrame, how: str = "auto") -> DataFrame:
        return answers.place_frequency(self.summary, asked, self.models, how)

    def hot_places_multi(self, asked: DataFrame, cells: DataFrame, **options) -> DataFrame:
        return answers.hot_places_multi(self.candidates, asked, cells, **options)


def tables(spark: SparkSession, radii: list[float], size_e6: int = geo.SIZE) -> DataFrame:
    """The cells-per-band table of the radii, written once: rows of the grid times bands."""
    return materialize(R.band_table(spark, radii, size_e6), "bands")


def many_tables(spark: SparkSession, lists: list[list[float]], size_e6: int = geo.SIZE) -> list[DataFrame]:
    """The tables of several lists of radii, written once, together."""
    every = materialize(R.band_tables(spark, lists, size_e6), "bands")
    return [every.where(F.col("list") == i).drop("list") for i in range(len(lists))]


def cell_model(occ: DataFrame, capacity: int, table: DataFrame, radii: list[float] | None = None, candidates: int | None = None, likelihood: str = "trial", screen: DataFrame | None = None) -> Atlas:
    """Counters only; models see a counter's cell by itself and every other cell of the map as empty.

    The centre is the likeliest of all stored cells, or of the first `candidates`.
    """
    radii = radii or M.fine_radii()
    summary = materialize(counters.build(occ, capacity), "summary")
    counts, centres = M.counts_of(summary), M.centres_of(summary, candidates)
    centres = M.screened(counts, centres, likelihood, table=screen) if candidates is None else centres
    models = materialize(M.fit_cells(counts, centres, table, radii, likelihood, source="cells"), "models")
    return Atlas(summary, M.best_center(models), models)


def ring_model(occ: DataFrame, capacity: int, table: DataFrame, radii: list[float] | None = None, policy: str = "transfer", candidates: int | None = None, likelihood: str = "trial", **options) -> Atlas:
    """Counters with bands, by replay in arrival order; a model sees a few bands a centre."""
    radii = radii or R.edges()
    summary = materialize(R.build(occ, capacity, radii, policy, **options), "summary")
    return fitted(summary, table, radii, candidates, likelihood)


def fitted(summary: DataFrame, table: DataFrame, radii: list[float], candidates: int | None = None, likelihood: str = "trial") -> Atlas:
    """The models of a summary's bands."""
    models = materialize(M.fit(M.ring_rows(summary, table, radii, candidates), likelihood), "models")
    return Atlas(summary, M.best_center(models), models)


def ring_model_exact(occ: DataFrame, capacity: int, table: DataFrame, radii: list[float] | None = None, candidates: int | None = None, likelihood: str = "trial") -> Atlas:
    """Bands by two passes of counting instead of a replay: no order, no skew by term, only sums; the form for stored data."""
    radii = radii or R.edges()
    counts = materialize(exact.counts(occ), "counts")
    top = materialize(M.top_cells(counts, capacity), "centres")
    got = R.exact(counts, top, radii)
    filled = got.groupBy("term", "center_cell").agg(F.map_from_entries(F.collect_list(F.struct("band", F.col("n").cast("double")))).alias("m"))
    rings = F.transform(F.sequence(F.lit(0), F.lit(len(radii) - 1)), lambda b: F.coalesce(F.element_at("m", b), F.lit(0.0)))
    rows = top.join(counts, ["term", "cell"]).join(filled, (top["term"] == filled["term"]) & (top["cell"] == filled["center_cell"]), "left").select(top["term"], "total", "rank", top["cell"], "n", F.coalesce(rings, F.array_repeat(F.lit(0.0), len(radii))).alias("rings"))
    centre = F.struct("rank", F.struct("cell", F.col("n").alias("f"), F.lit(0).cast("long").alias("err"), "rings", F.lit(0).cast("long").alias("born_seq")).alias("c"))
    summary = rows.groupBy("term", "total").agg(F.transform(F.array_sort(F.collect_list(centre)), lambda x: x["c"]).alias("centers"))
    summary = materialize(summary.select("term", "total", F.lit(capacity).alias("capacity"), F.lit("exact").alias("policy"), F.lit(0).cast("long").alias("n_replaced"), F.lit(False).alias("frozen"), F.col("centers").cast(f"array<{counters.CENTRE}>").alias("centers")), "summary")
    models = materialize(M.fit(M.ring_rows(summary, table, radii, candidates), likelihood, source="exact_rings"), "models")
    return Atlas(summary, M.best_center(models), models)
