"""Functions for SQL: inlined SQL bodies where Catalyst can see through, Arrow and table functions where not."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from termatlas.functions import geo


def decay_fit():
    """decay_fit(total, d array, n array, cells array) -> struct(focus, spread): the trial fit of one row's bands."""
    from termatlas.operators.model import fit_arrays

    @F.pandas_udf("focus double, spread double")
    def fit(total: pd.Series, d: pd.Series, n: pd.Series, cells: pd.Series) -> pd.DataFrame:
        width = max((len(x) for x in d), default=0) or 1
        pad = lambda s, v: np.array([[*map(float, x), *[v] * (width - len(x))] for x in s], float).reshape(len(s), width)
        arrivals = pad(n, 0.0)
        focus, spread, _, _ = fit_arrays(pad(d, 1.0), arrivals, pad(cells, 0.0), arrivals, total.to_numpy(float))
        return pd.DataFrame({"focus": focus, "spread": spread})

    return fit


def counter_summary(capacity: int = 50):
    """counter_summary(cell) -> array of struct(cell, f, err): a grouped aggregate for groups that fit in memory, in the order given.

    Use operators.counters.build for whole streams; this one is for small, interactive groups.
    """
    from termatlas.operators.counters import Counters

    @F.pandas_udf("array<struct<cell:int,f:bigint,err:bigint>>")
    def summary(cell: pd.Series) -> list:
        core = Counters(capacity)
        for c in cell.dropna():
            core.observe(int(c))
        return [{"cell": x["cell"], "f": x["f"], "err": x["err"]} for x in core.row("")["centers"]]

    return summary


class Surface:
    """surface(center_cell, focus, spread, least): rows (cell, p) of one-degree cells with at least that probability."""

    def eval(self, center_cell: int, focus: float, spread: float, least: float):  # noqa: ANN201
        from termatlas.operators.rings import Sphere

        sphere, cells = Sphere(), np.arange(180 * 360)
        d = np.maximum(sphere.between(sphere.place(center_cell), sphere.place(cells)), 1.0)
        p = np.minimum(focus * d**-spread, 1.0)
        for c in np.flatnonzero(p >= least):
            yield int(c), float(p[c])


def register(spark: SparkSession) -> None:
    """cell_id, arc_cells, decay_prob, decay_fit, counter_summary and surface for SQL."""
    geo.register_sql(spark)
    spark.udf.register("decay_fit", decay_fit())
    spark.udf.register("counter_summary", counter_summary())
    spark.udtf.register("surface", F.udtf(Surface, returnType="cell int, p double"))
