import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from termatlas.operators import answers, counters, exact, metrics
from termatlas.operators.counters import Counters


def stream(spark, rows):
    return spark.createDataFrame([(i, t, c) for i, (t, c) in enumerate(rows)], "seq long, term string, cell int").withColumns({"msg_id": F.col("seq"), "ts": F.timestamp_seconds("seq")})


def random_rows(n=1500, cells=60, terms=("a", "b"), seed=42):
    rng = random.Random(seed)
    return [(rng.choice(terms), int(rng.paretovariate(1.1)) % cells) for _ in range(n)]


def test_worked_stream_before_and_after_the_last_arrival():
    core, names = Counters(3), ["columbus", "dallas", "dallas", "new york", "columbus", "dallas"]
    for x in names:
        core.observe(x)
    assert {c: (core.f[c], core.err[c]) for c in core.f} == {"dallas": (3, 0), "columbus": (2, 0), "new york": (1, 0)}
    assert core.observe("chicago") == "new york"
    assert {c: (core.f[c], core.err[c]) for c in core.f} == {"dallas": (3, 0), "columbus": (2, 0), "chicago": (2, 1)}


@pytest.mark.parametrize("eps,m", [(0.02, 50), (0.05, 20), (0.1, 10), (0.3, 4)])
def test_capacity(eps, m):
    assert counters.capacity(eps) == m


def test_guarantees_hold_on_random_streams(spark):
    occ = stream(spark, random_rows())
    row = metrics.invariants(counters.build(occ, 12), exact.counts(occ)).first()
    assert set(row.asDict().values()) == {0}
    assert counters.error_bound(counters.build(occ, 12)).where("not holds").count() == 0


def test_a_roomy_summary_is_exact_and_replay_equals_the_core(spark):
    rows = random_rows()
    occ = stream(spark, rows)
    got = {(r.term, r.cell): (r.f, r.err) for r in counters.exploded(counters.build(occ, 500)).collect()}
    assert got == {k: (n, 0) for k, n in Counter(rows).items()}
    small = {(r.term, r.cell): (r.f, r.err) for r in counters.exploded(counters.build(occ, 7)).collect()}
    for t in ("a", "b"):
        core = Counters(7)
        for term, cell in rows:
            if term == t:
                core.observe(cell)
        assert {c: (core.f[c], core.err[c]) for c in core.f} == {c: v for (x, c), v in small.items() if x == t}


def test_equal_arrivals_in_a_row_count_alike_at_once():
    one, many = Counters(3), Counters(3)
    for cell, n in ((1, 4), (2, 1), (3, 2), (4, 3), (1, 1), (5, 2)):
        one.observe(cell, n)
        for _ in range(n):
            many.observe(cell)
    assert one.f == many.f and one.err == many.err


def test_merged_panes_keep_the_bounds(spark):
    occ = stream(spark, random_rows(3000))
    merged = counters.build(occ, 15, panes=5)
    own = counters.exploded(merged).join(exact.counts(occ), ["term", "cell"])
    assert own.where("f < n or f - err > n").count() == 0
    assert merged.where(counters.largest_error() > 2 * F.col("total") / F.col("capacity")).count() == 0
    every = exact.counts(occ).join(merged.select("term", "total"), "term").where("n > 2 * total / 15").join(counters.exploded(merged).select("term", "cell"), ["term", "cell"], "left_anti")
    assert every.count() == 0


def test_answers_without_a_model(spark):
    occ = stream(spark, [("a", 1000)] * 5 + [("a", 1001)] * 3 + [("a", 2000)] * 2)
    s = counters.build(occ, 2)
    asked = spark.createDataFrame([(1, "a", 1000), (2, "a", 1001), (3, "none", 5)], "qid long, term string, cell int")
    got = {h: {r.qid: r.est for r in answers.place_frequency(s, asked, how=h).collect()} for h in ("counter", "zero", "bound", "neighbours")}
    assert got["counter"] == {1: 5.0, 2: None, 3: None} and got["zero"][2] == 0.0
    assert got["bound"][2] == 5.0 and got["neighbours"][2] == 5 / 8
    hot = answers.hot_places(s, 5).collect()
    assert [(r.cell, r.est, r.lower) for r in sorted(hot, key=lambda r: r["rank"])] == [(1000, 5, 5), (2000, 5, 2)] or {r.cell for r in hot} == {1000, 2000}
    with pytest.raises(ValueError):
        answers.place_frequency(s, asked, how="guess")


def test_nulls_and_empty_streams(spark):
    occ = stream(spark, [("a", None), (None, 3), ("a", 4)])
    assert [(r.term, r.cell, r.f) for r in counters.exploded(counters.build(occ, 3)).collect()] == [("a", 4, 1)]
    assert counters.build(occ.where("1 = 0"), 3).count() == 0
    assert counters.build(occ.where("1 = 0"), 3, panes=4).count() == 0


def test_heavy_terms_and_windows(spark):
    occ = stream(spark, [("a", 1)] * 9 + [("b", 2)])
    assert [r.term for r in counters.heavy_terms(occ, 0.5).collect()] == ["a"]
    assert counters.only_heavy(occ, 0.5).count() == 9
    w = counters.windowed(occ, 5, "4 seconds", "2 seconds").where("term = 'a'").select(F.unix_seconds("window_start").alias("s"), "total").collect()
    assert {r.s: r.total for r in w} == {-2: 2, 0: 4, 2: 4, 4: 4, 6: 3, 8: 1}


def test_replays_of_gathered_arrivals_equal_those_of_occ(spark, monkeypatch):
    import random

    from pyspark.sql import functions as F

    from termatlas.operators import counters
    from termatlas.operators import rings as R

    monkeypatch.setattr(counters, "PIECE", 7)
    rng = random.Random(4)
    rows = [(k // 3, rng.choice("aaab") if k % 50 else None, rng.choice([45_000 + rng.randrange(40), 300]) if k % 70 else None) for k in range(1500)]
    occ = spark.createDataFrame(rows, "seq long, term string, cell int").select("*", F.timestamp_seconds("seq").alias("ts"), F.col("seq").alias("msg_id"))
    once = counters.gathered(occ)
    assert once.count() > 150 and once.where(F.size("cells") > 7).count() == 0
    read = lambda df: sorted(map(str, df.collect()))
    assert read(counters.build(once, 6)) == read(counters.build(occ, 6))
    for policy in ("transfer", "reset", "nearby_skip"):
        assert read(R.build(once, 6, policy=policy).drop("centers")) == read(R.build(occ, 6, policy=policy).drop("centers"))
        assert read(counters.exploded(R.build(once, 6, policy=policy)).drop("rings")) == read(counters.exploded(R.build(occ, 6, policy=policy)).drop("rings"))
    for more in ({"freeze_fraction": 0.2}, {"freeze_fraction": 0.33}, {"freeze_after_rows": 400}):
        a, b = (R.build(x, 6, policy="freeze", **more) for x in (once, occ))
        assert read(a.drop("centers")) == read(b.drop("centers"))
        a, b = (sorted(counters.exploded(x).collect()) for x in (a, b))
        for x, y in zip(a, b, strict=True):
            assert x[:-1] == y[:-1] and max(abs(p - q) for p, q in zip(x.rings, y.rings, strict=True)) < 1e-6


def test_many_arrivals_equal_those_one_by_one():
    import numpy as np

    from termatlas.operators import rings as R

    rng = np.random.default_rng(7)
    cells, sizes = rng.integers(45_000, 45_060, 3000), rng.integers(1, 4, 3000)
    for policy in ("transfer", "reset", "nearby_skip"):
        for radii in (R.edges(), [R.edges(ratio=0.3), R.edges()][: 1 + (policy != "nearby_skip")]):
            many, single = R.RingState(9, radii, policy), R.RingState(9, radii, policy)
            for a in range(0, 3000, 700):
                many.observe_all(cells[a : a + 700], sizes[a : a + 700], np.arange(a, min(a + 700, 3000)))
            for k, (c, n) in enumerate(zip(cells.tolist(), sizes.tolist(), strict=True)):
                single.observe(c, n, k)
            for i in range(len(many.lists)):
                a, b = many.row("t", i), single.row("t", i)
                assert {k: v for k, v in a.items() if k != "centers"} == {k: v for k, v in b.items() if k != "centers"}
                for x, y in zip(a["centers"], b["centers"], strict=True):
                    assert np.allclose(x.pop("rings"), y.pop("rings")) and x == y
