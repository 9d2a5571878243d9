"""Grid and sphere as Columns: cells, distances, decay, levels. All exact parts are integers.

Locations are longitudes and latitudes in micro-degrees. A cell is row * columns + column
of a uniform grid, rows from the south, columns from the west. Distances of the metric
`arc` are great-circle degrees over the cell size, those of `grid` are planar in cells;
both are in cell units.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

DEGREE, SIZE = 1_000_000, 1_000_000


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def columns(size_e6: int = SIZE) -> int:
    return -(-360 * DEGREE // size_e6)


def rows(size_e6: int = SIZE) -> int:
    return -(-180 * DEGREE // size_e6)


def cell_id(lon_e6: Column | str, lat_e6: Column | str, size_e6: int = SIZE) -> Column:
    """The cell of a point; longitudes wrap, latitudes are clamped to the poles; null gives null."""
    lon = F.pmod(_c(lon_e6) + F.lit(180 * DEGREE), F.lit(360 * DEGREE))
    lat = F.greatest(F.lit(0), F.least(_c(lat_e6) + F.lit(90 * DEGREE), F.lit(180 * DEGREE - 1)))
    lat = F.when(_c(lat_e6).isNotNull(), lat)
    return (F.floor(lat / size_e6) * columns(size_e6) + F.floor(lon / size_e6)).cast("int")


def cell_row(cell: Column | str, size_e6: int = SIZE) -> Column:
    return F.floor(_c(cell) / columns(size_e6)).cast("int")


def cell_col(cell: Column | str, size_e6: int = SIZE) -> Column:
    return F.pmod(_c(cell), F.lit(columns(size_e6))).cast("int")


def centre_lat(cell: Column | str, size_e6: int = SIZE) -> Column:
    return (cell_row(cell, size_e6) + 0.5) * (size_e6 / DEGREE) - 90.0


def centre_lon(cell: Column | str, size_e6: int = SIZE) -> Column:
    return (cell_col(cell, size_e6) + 0.5) * (size_e6 / DEGREE) - 180.0


def arc(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Great-circle degrees between two points in degrees, by the haversine formula."""
    a, b = F.radians(lat1), F.radians(lat2)
    h = F.pow(F.sin((b - a) / 2), 2) + F.cos(a) * F.cos(b) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return F.degrees(2 * F.asin(F.sqrt(F.least(h, F.lit(1.0)))))


def cell_distance(a: Column | str, b: Column | str, size_e6: int = SIZE, metric: str = "arc") -> Column:
    """Distance of two cells' centres in cell units."""
    a, b = _c(a), _c(b)
    if metric == "grid":
        return F.sqrt(squared_steps(a, b, size_e6).cast("double"))
    return arc(centre_lat(a, size_e6), centre_lon(a, size_e6), centre_lat(b, size_e6), centre_lon(b, size_e6)) * (DEGREE / size_e6)


def squared_steps(a: Column | str, b: Column | str, size_e6: int = SIZE) -> Column:
    """Squared planar distance of two cells in cells, an integer."""
    dr, dc = (f(a, size_e6).cast("long") - f(b, size_e6) for f in (cell_row, cell_col))
    return dr * dr + dc * dc


def decay(distance: Column | str, focus: Column | str, spread: Column | str, min_distance: float = 1.0) -> Column:
    """focus * distance ** -spread, distances clamped from below, at most 1; null if any of them is."""
    d, p = _c(distance), _c(focus) * F.pow(F.greatest(_c(distance), F.lit(min_distance)), -_c(spread))
    return F.when(d.isNotNull() & p.isNotNull(), F.least(p, F.lit(1.0)))


MOST_ON_CELLS = 10_000


def on_every_cell(grid: DataFrame, rows: DataFrame, most: int = MOST_ON_CELLS) -> DataFrame:
    """Each of rows with each cell of the grid. At most `most` rows are broadcast to the cells; of more, both sides stay
    distributed and Spark chooses by their sizes."""
    cells = grid.select("cell")
    return cells.join(F.broadcast(rows), F.lit(True)) if rows.limit(most + 1).count() <= most else rows.crossJoin(cells)


def register_sql(spark: SparkSession) -> None:
    """cell_id, arc_cells and decay_prob as SQL functions; Catalyst inlines their bodies."""
    n = columns()
    for name, args, kind, body in (
        ("cell_id", "lon BIGINT, lat BIGINT", "INT", f"CAST(floor(greatest(0, least(lat + 90000000, 179999999)) / 1000000) * {n} + floor(pmod(lon + 180000000, 360000000) / 1000000) AS INT)"),
        ("arc_cells", "lat1 DOUBLE, lon1 DOUBLE, lat2 DOUBLE, lon2 DOUBLE", "DOUBLE", "degrees(2 * asin(sqrt(least(1D, pow(sin(radians(lat2 - lat1) / 2), 2) + cos(radians(lat1)) * cos(radians(lat2)) * pow(sin(radians(lon2 - lon1) / 2), 2)))))"),
        ("decay_prob", "d DOUBLE, focus DOUBLE, spread DOUBLE", "DOUBLE", "least(1D, focus * pow(greatest(d, 1D), -spread))"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")


def with_place(df: DataFrame, dim: DataFrame, key: str, place: str = "place") -> DataFrame:
    """A level of a gazetteer instead of the grid: the dimension's place as the cell. dim: key, place."""
    return df.join(dim.select(key, place), key).withColumn("cell", F.col(place))


def roll_up(answers: DataFrame, dim: DataFrame, level: str, value: str = "est", by: tuple[str, ...] = ("term",)) -> DataFrame:
    """Sums of cells' values over the places of a coarser level. dim: cell, level."""
    return answers.join(dim.select("cell", level), "cell").groupBy(*by, level).agg(F.sum(value).alias(value))


def drill_down(answers: DataFrame, factor: int, size_e6: int = SIZE, value: str = "est") -> DataFrame:
    """Each cell's value split evenly over factor * factor cells of a finer grid."""
    fine = size_e6 // factor
    k = F.col("_k")
    sub = (cell_row("cell", size_e6) * factor + F.floor(k / factor)) * columns(fine) + cell_col("cell", size_e6) * factor + F.pmod(k, F.lit(factor))
    return answers.withColumn("_k", F.explode(F.sequence(F.lit(0), F.lit(factor * factor - 1)))).withColumn("sub_cell", sub.cast("int")).withColumn(value, F.col(value) / (factor * factor)).drop("_k")
