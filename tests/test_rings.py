import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.operators import counters, exact
from termatlas.operators import rings as R
from tests.test_counters import random_rows, stream


def test_published_ring_counts_and_equal_space():
    assert [R.count_for(r) for r in (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.9)] == [3, 4, 5, 7, 8, 10, 10]
    assert [R.capacity_for_budget(648, n) for n in (0, 5, 7, 8, 10)] == [216, 81, 65, 59, 50]
    e = R.edges(98, 0.6)
    assert len(e) == 10 and e[-1] == 98 and all(abs(a / b - 0.6) < 1e-12 for a, b in zip(e, e[1:], strict=False))


def test_overlap_agrees_with_sampling():
    radii, d, rng = np.array([1.0, 2.5, 6.0]), 3.0, np.random.default_rng(42)
    x, y = rng.uniform(-6, 6, (2, 400_000))
    old = np.searchsorted(radii, np.hypot(x, y))
    new = np.searchsorted(radii, np.hypot(x - d, y))
    got = R.planar_overlap(radii, d)
    for i in range(3):
        for k in range(3):
            share = ((new == i) & (old == k)).mean() * 144
            assert abs(got[i, k] - share) < 0.35


def test_transfer_at_no_distance_far_away_and_in_between():
    radii, old = np.array([1.0, 2.5, 6.0]), np.array([3.0, 5.0, 7.0])
    assert np.allclose(R.transfer(old, radii, 0.0), old)
    assert np.allclose(R.transfer(old, radii, 20.0), 0)
    new = R.transfer(old, radii, 2.0)
    assert (new >= 0).all() and new.sum() <= old.sum() + 1e-9


def test_band_lookups_agree(spark):
    radii = R.edges()
    d = spark.range(4000).select((F.col("id") / 20.0).alias("d")).unionByName(spark.createDataFrame([(r,) for r in radii], "d double"))
    rows = d.select("d", *(R.band("d", radii, m).alias(m) for m in ("linear", "binary", "closed")))
    assert rows.where("not (linear <=> binary) or not (binary <=> closed)").count() == 0
    assert rows.where("d = 0").first().linear is None
    assert {r.linear for r in rows.where("d > 98").collect()} == {9}
    assert d.select(R.band("d", radii, overflow="drop").alias("b")).where("b is null").count() > 1000


def test_exact_bands_account_for_every_arrival(spark):
    occ = stream(spark, [(t, 40_000 + c * 7) for t, c in random_rows()])
    c = exact.counts(occ)
    top = exact.hot_places(c, 3)
    bands = R.exact(c, top, R.edges()).groupBy("term", "center_cell").agg(F.sum("n").alias("n"))
    rows = bands.join(top.withColumnRenamed("cell", "center_cell").select("term", "center_cell", F.col("n").alias("own")), ["term", "center_cell"]).join(exact.totals(c), "term")
    assert rows.where("n + own <> total").count() == 0 and rows.count() == 6


def replay(policy, cells, m=6, **options):
    s = R.RingState(m, R.edges(), policy, **options)
    for i, c in enumerate(cells):
        s.observe(c, 1, i)
    return s


def cells_of(n=600, seed=3):
    rng = random.Random(seed)
    return [(90 + int(rng.gauss(0, 6))) * 360 + 180 + int(rng.gauss(0, 6)) for _ in range(n)]


def test_policies_differ_only_as_stated():
    cells = cells_of()
    a, b = replay("transfer", cells), replay("reset", cells)
    assert a.slot == b.slot and (a.f == b.f).all() and (a.err == b.err).all() and a.rings.sum() >= b.rings.sum()
    frozen = replay("freeze", cells, freeze_after=100)
    first = replay("transfer", cells[:100])
    assert set(frozen.slot) == set(first.slot) and frozen.replaced == first.replaced and frozen.total == len(cells)
    skip = replay("nearby_skip", cells)
    at = [skip.sphere.place(c) for c in skip.slot]
    kept = replay("nearby_skip", cells[:0])
    assert kept.total == 0 and len(at) == 6 and skip.replaced <= a.replaced
    near = replay("nearby_skip", cells, skip_to="nearest")
    assert near.f.sum() == len(cells)
    with pytest.raises(ValueError):
        R.RingState(3, [1.0], "other")


def test_counters_of_the_ring_core_are_the_plain_ones():
    cells, plain = cells_of(), counters.Counters(6)
    for c in cells:
        plain.observe(c)
    s = replay("transfer", cells)
    assert {c: (int(s.f[k]), int(s.err[k])) for c, k in s.slot.items()} == {c: (plain.f[c], plain.err[c]) for c in plain.f}


def test_runs_count_alike_at_once_and_backfill_is_exact():
    a, b = R.RingState(4, R.edges()), R.RingState(4, R.edges())
    for c, n in ((100, 3), (105, 2), (100, 1), (470, 4), (900, 2), (105, 5), (3000, 2)):
        a.observe(c, n)
        for _ in range(n):
            b.observe(c)
    assert a.slot == b.slot and np.allclose(a.rings, b.rings)
    full = replay("transfer", cells_of(40), m=100, backfill=True)
    assert np.allclose(full.rings[: len(full.slot)].sum(axis=1) + full.f[: len(full.slot)], full.total)


@pytest.mark.parametrize("options", [{"geometry": "cells"}, {"transfer_from": "nearest"}, {"transfer_from": "mean_all"}, {"transfer_center": True}, {"overflow": "drop"}, {"metric": "grid"}])
def test_options_run_and_keep_mass_finite(options):
    s = replay("transfer", cells_of(80), m=4, **options)
    assert np.isfinite(s.rings).all() and (s.rings >= 0).all()


def test_masked_geometry_ignores_masked_cells():
    mask = np.zeros(180 * 360, bool)
    mask[: 100 * 360] = True
    s = replay("transfer", cells_of(60), m=4, geometry="cells", mask=mask)
    assert (s.rings >= 0).all()


def test_band_table_counts_the_whole_map(spark):
    t = R.band_table(spark, R.edges(), size_e6=10_000_000)
    assert {r.n for r in t.groupBy("row").agg(F.sum("cells").alias("n")).collect()} == {18 * 36 - 1}
    grid = R.cells(spark, 10_000_000, mask=F.col("row") < 2)
    m = R.masked_band_table(grid, spark.createDataFrame([("a", 300)], "term string, cell int"), R.edges(), 10_000_000)
    assert m.agg(F.sum("cells")).first()[0] == 16 * 36 - 1


def test_distances_and_levels(spark):
    a, b = 90 * 360 + 10, 90 * 360 + 13
    row = spark.range(1).select(geo.cell_distance(F.lit(a), F.lit(b)).alias("arc"), geo.cell_distance(F.lit(a), F.lit(b), metric="grid").alias("grid")).first()
    sphere = R.Sphere()
    assert row.grid == 3.0 and math.isclose(row.arc, float(sphere.between(sphere.place(a), sphere.place(b))), rel_tol=1e-9) and abs(row.arc - 3) < 0.01
    one = spark.createDataFrame([("a", a, 8.0)], "term string, cell int, est double")
    fine = geo.drill_down(one, 2)
    assert fine.agg(F.sum("est")).first()[0] == 8.0 and fine.select("sub_cell").distinct().count() == 4


def test_one_replay_serves_several_lists_of_radii(spark):
    occ, lists = stream(spark, [(t, 40_000 + c * 7) for t, c in random_rows()]), [R.edges(ratio=0.3), R.edges(), [2.0, 40.0]]
    every = R.build_each(occ, 5, lists).collect()
    for i, radii in enumerate(lists):
        want = {r.term: r for r in R.build(occ, 5, radii).collect()}
        got = {r.term: r for r in every if r.list == i}
        assert got.keys() == want.keys() and len(got) > 1
        for t, r in got.items():
            assert [(c.cell, c.f, c.err) for c in r.centers] == [(c.cell, c.f, c.err) for c in want[t].centers]
            assert all(np.allclose(a.rings, b.rings) and len(a.rings) == len(radii) for a, b in zip(r.centers, want[t].centers, strict=True))


@pytest.mark.parametrize("policy", ["transfer", "reset", "nearby_skip"])
def test_a_replay_measures_distances_many_at_a_time(policy):
    cells, calls = np.array(cells_of(5000)), []
    s = R.RingState(6, R.edges(), policy)
    between = s.sphere.between
    s.sphere.between = lambda *a: calls.append(1) or between(*a)
    s.observe_all(cells, np.ones(5000, int), np.arange(5000))
    one = replay(policy, cells.tolist())
    assert s.slot == one.slot and np.allclose(s.rings, one.rings) and s.replaced > 500
    assert len(calls) < 1000


def test_replays_of_runs_longer_than_the_buffer_and_of_many_cells(monkeypatch):
    monkeypatch.setattr(R, "WAITING", 64)
    monkeypatch.setattr(R, "ROOM", 100)
    cells = np.array(cells_of(900))
    whole, want = R.RingState(6, R.edges()), replay("transfer", cells.tolist())
    monkeypatch.setattr(R, "WIDE", 10)
    direct = R.RingState(6, R.edges())
    for s in (whole, direct):
        s.observe_all(cells, np.ones(900, int), np.arange(900))
        assert s.slot == want.slot and np.allclose(s.rings, want.rings) and (s.born == want.born).all()
