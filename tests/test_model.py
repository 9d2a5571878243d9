import numpy as np
import pytest
from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.operators import answers, exact, multicenter
from termatlas.operators import model as M
from termatlas.operators import rings as R


def bands_of(focus, spread, total, d, cells):
    return total * cells * np.minimum(focus * d**-spread, 1)


D = np.array([1.0, 2.0, 4.0, 8.0, 16.0, 40.0])
CELLS = np.array([1.0, 8.0, 40.0, 150.0, 600.0, 4000.0])


@pytest.mark.parametrize("focus,spread", [(0.1, 2.5), (0.3, 3.2), (0.05, 2.0), (0.02, 5.5)])
def test_fit_recovers_the_parameters(focus, spread):
    n = bands_of(focus, spread, 1e6, D, CELLS)
    c, a, _, evals = M.fit_arrays(D[None], n[None], CELLS[None], n[None], np.array([1e6]))
    assert abs(a[0] - spread) < 0.05 * spread and abs(c[0] - focus) < 0.05 * focus and evals > 0


def test_share_normalises():
    n = bands_of(0.1, 2.5, 1e5, D, CELLS)
    c, a, _, _ = M.fit_arrays(D[None], n[None], CELLS[None], n[None], np.array([1e5]), "share")
    assert abs((c[0] * D ** -a[0] * CELLS).sum() - 1) < 1e-6


def test_literal_bands_do_not_depend_on_the_data():
    out = [M.fit_arrays(D[None], n[None], CELLS[None], n[None], np.array([1e5]), "literal_bands")[:2] for n in (np.arange(6.0), np.arange(6.0)[::-1].copy())]
    assert np.allclose(out[0][0], out[1][0]) and np.allclose(out[0][1], out[1][1])


def test_padding_changes_nothing():
    n = bands_of(0.1, 2.5, 1e5, D, CELLS)
    pad = lambda x, v: np.append(x, [v, v])[None]
    a = M.fit_arrays(D[None], n[None], CELLS[None], n[None], np.array([1e5]))
    b = M.fit_arrays(pad(D, 1.0), pad(n, 0.0), pad(CELLS, 0.0), pad(n, 0.0), np.array([1e5]))
    assert np.allclose(a[0], b[0]) and np.allclose(a[1], b[1])


def test_decay(spark):
    r = spark.range(1).select(geo.decay(F.lit(0.0), F.lit(0.3), F.lit(2.0)).alias("z"), geo.decay(F.lit(1.0), F.lit(0.3), F.lit(2.0)).alias("o"), geo.decay(F.lit(10.0), F.lit(0.3), F.lit(2.0)).alias("t")).first()
    assert r.z == r.o == 0.3 and abs(r.t - 0.003) < 1e-12


def test_two_thirds(spark):
    assert abs(M.disc_mean(spark).first().ratio - R.DISC_MEAN_RATIO) < 0.005


def rows(spark):
    n = bands_of(0.1, 2.5, 10_000, D, CELLS)
    bands = [{"d": float(a), "n": float(b), "cells": float(c), "occ": float(b)} for a, b, c in zip(D, n, CELLS, strict=True)]
    return spark.createDataFrame([("t", 0, 500, 10_000, bands)], f"term string, rank int, center_cell int, total long, bands {M.BANDS}")


def test_lattice_and_solver_agree(spark):
    solved = M.fit(rows(spark)).first()
    two = M.fit_two_stage(rows(spark)).first()
    assert abs(two.spread - solved.spread) < 0.15 and two.loglik <= solved.loglik + 1e-3
    assert solved.n_eval % len(D) == 0


def test_joint_probabilities_are_ordered(spark):
    models = spark.createDataFrame([("a", 0, 40_000, 0.3, 2.0, 0.0, 10), ("b", 0, 40_010, 0.2, 2.5, 0.0, 20)], "term string, rank int, center_cell int, focus double, spread double, loglik double, total long")
    asked = spark.createDataFrame([(1, ["a", "b"]), (2, ["a", "x"])], "qid long, terms array<string>")
    cells = spark.range(39_990, 40_020).select(F.col("id").cast("int").alias("cell"))
    p = {d: {r.cell: r.p for r in answers.joint(models, asked, cells, d).collect()} for d in ("independent", "bound")}
    assert len(p["bound"]) == 30 and all(0 <= p["independent"][c] <= p["bound"][c] <= 1 for c in p["bound"])
    best = answers.hot_places_multi(models, asked, cells, 1).first()
    assert best.qid == 1 and best.cell == max(p["independent"], key=lambda c: (p["independent"][c], -c))
    by_rank = answers.hot_places_multi(models, asked, cells, 1, pairing="rank").first()
    assert by_rank.cell == best.cell
    one = asked.withColumn("cell", F.lit(40_005))
    est = {r.qid: r.est for r in answers.place_frequency_multi(models, models, one).collect()}
    assert abs(est[1] - 10 * p["independent"][40_005]) < 1e-9 and est[2] == 0.0


def test_two_centres_beat_the_parts(spark):
    ps = F.array(F.lit(0.2), F.lit(0.5))
    assert abs(spark.range(1).select(multicenter.combine(ps).alias("p")).first().p - 0.6) < 1e-12
    x = np.array([[1.0, 9.0], [9.0, 1.0], [4.0, 4.0]])
    focus, spread, value = multicenter.ascend(np.log(x), np.array([50.0, 30.0, 5.0]), np.array([50.0, 70.0, 900.0]), 12)
    assert (focus > 0).all() and np.isfinite(value)


def test_stale_and_as_of(spark):
    models = spark.createDataFrame([("a", 100, 1), ("a", 150, 2), ("b", 10, 3)], "term string, fitted_at long, version long")
    totals = spark.createDataFrame([("a", 155), ("b", 20), ("c", 1)], "term string, total long")
    assert {r.term for r in M.stale(totals, models, 0.1).collect()} == {"b", "c"}
    asked = spark.createDataFrame([(1, "a", 120), (2, "a", 150), (3, "a", 5), (4, "z", 9)], "qid long, term string, at long")
    assert {r.qid: r.version for r in M.as_of(asked, models).collect()} == {1: 1, 2: 2, 3: None, 4: None}


def test_neighbours_and_exact_answers(spark):
    counts = spark.createDataFrame([("a", 40_000, 8), ("a", 40_001, 4)], "term string, cell int, n long")
    asked = spark.createDataFrame([(1, "a", 40_000)], "qid long, term string, cell int")
    assert answers.neighbour_means(counts, asked).first().mean == 0.5
    assert answers.neighbour_means(counts, asked, missing="ignore").first().mean == 4.0
    assert exact.place_frequency(counts, asked).first().n == 8


def test_the_focus_is_the_root_also_next_to_certainty():
    rng = np.random.default_rng(4)
    d, cells = np.sort(rng.uniform(1, 180, (300, 10)), axis=1), rng.integers(1, 400, (300, 10)).astype(float)
    n = rng.poisson(rng.uniform(0, 3, (300, 1)) * 200 * d ** -rng.uniform(0.2, 4, (300, 1))).astype(float)
    d[:, 0], cells[:, 0], n[:20, 1:], n[:20, 0] = 1.0, 1.0, 0, np.arange(20)
    total = n.sum(axis=1) * np.where(np.arange(300) % 3, 1.0, 1.02)
    focus, spread, _, _ = M.fit_arrays(d, n, cells, n, total)
    p = focus[:, None] * d ** -spread[:, None]
    got = ((total[:, None] * cells - n) * p / (1 - p)).sum(axis=1)
    inside = (p.max(axis=1) < 0.9) & (n.sum(axis=1) > 0)
    assert inside.sum() > 100 and np.allclose(got[inside], n.sum(axis=1)[inside], rtol=1e-9)
    # elsewhere it ends at a probability of all but 1, where hits are not reached yet
    assert (got <= n.sum(axis=1) * (1 + 1e-4))[(p.max(axis=1) > 1 - 2e-9)].all()
