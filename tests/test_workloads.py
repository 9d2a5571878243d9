"""Searches for passages against Python's `in`, and cells with many rows."""

from __future__ import annotations

import itertools
import random

from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.operators import counters
from termatlas.operators import model as M
from termatlas.operators import rings as R
from termatlas.plans import workloads
from termatlas.sources import adapters


def test_holding_equals_brute_force(spark):
    rng = random.Random(3)
    words = ["aa", "b", "cab", "d", "a"]
    texts = [rng.choice(["", " ", "\n"]) + "".join(rng.choice(words) + rng.choice([" ", "  ", "\n", "\t"]) for _ in range(rng.randrange(40))) for _ in range(150)]
    cuts = [t[rng.randrange(len(t)) :][: rng.randrange(1, 30)] for t in texts if len(t) > 5]
    passages = cuts + cuts[:5] + ["aa b cab d a aa b cab nowhere", "", None]
    docs = [(k, t) for k, t in enumerate(texts)] + [(900, None), (901, "x" * 100_000 + " " + texts[0])]
    got = workloads.holding(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame([(p,) for p in passages], "text string"))
    want = lambda ps: {k for (k, t), p in itertools.product(docs, ps) if t is not None and p is not None and p in t}
    assert {r.doc_id for r in got.collect()} == want(passages)
    long = [p for p in passages if p and len(p.split()) >= 6]
    got = workloads.holding(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame([(p,) for p in long], "text string"))
    assert {r.doc_id for r in got.collect()} == want(long) and len(want(long)) < len(docs)


def test_every_cell_with_few_and_with_many_rows(spark):
    grid, rows = R.cells(spark).where("cell < 30"), spark.range(20).withColumnRenamed("id", "k")
    few, many = (geo.on_every_cell(grid, rows, most=m) for m in (100, 5))
    assert {(r.cell, r.k) for r in few.collect()} == {(r.cell, r.k) for r in many.collect()} and many.count() == 600


def test_tables_of_many_lists_equal_those_of_one(spark):
    lists = [R.edges(), R.edges(ratio=0.9), M.fine_radii(n=64)]
    size = 5_000_000
    every = R.band_tables(spark, lists, size).collect()
    for i, radii in enumerate(lists):
        got = {(r.row, r.band): (r.cells, r.mean_dist) for r in every if r.list == i}
        want = {(r.row, r.band): (r.cells, r.mean_dist) for r in R.band_table(spark, radii, size).collect()}
        assert got.keys() == want.keys() and all(got[k][0] == want[k][0] and abs(got[k][1] - want[k][1]) < 1e-9 for k in want)
    some = R.band_tables(spark, [[2.0, 9.0]], size, overflow="drop")
    assert {(r.row, r.band, r.cells) for r in some.collect()} == {(r.row, r.band, r.cells) for r in R.band_table(spark, [2.0, 9.0], size, overflow="drop").collect()}


def test_fits_of_cells_equal_those_of_rows(spark, monkeypatch):
    monkeypatch.setattr(M, "BLOCK", 7)
    rng = random.Random(5)
    cells = [rng.randrange(180 * 360) for _ in range(20)]
    counts = spark.createDataFrame([(t, c, rng.randrange(1, 40)) for t in "abc" for c in rng.sample(cells, 15)] + [("d", 0, 3)], "term string, cell int, n long")
    radii = M.fine_radii(n=64)
    table, centres = R.band_table(spark, radii), M.top_cells(counts, None)
    for likelihood in ("trial", "presence", "share"):
        want = {(r.term, r.center_cell): r for r in M.fit(M.cell_rows(counts, centres, table, radii), likelihood, source="cells").collect()}
        got = {(r.term, r.center_cell): r for r in M.fit_cells(counts, centres, table, radii, likelihood, source="cells").collect()}
        assert got.keys() == want.keys() and len(got) == 46
        for k, w in want.items():
            g = got[k]
            assert (g["rank"], g.total, g.n_eval, g.source, g.fitted_at) == (w["rank"], w.total, w.n_eval, w.source, w.fitted_at)
            assert abs(g.loglik - w.loglik) <= 1e-8 * abs(w.loglik) and abs(g.focus - w.focus) <= 1e-5 * w.focus and abs(g.spread - w.spread) < 1e-4


def test_heavy_terms_of_gathered_messages(spark, sf):
    once = [(1, ["a", "b"]), (2, ["a"]), (3, ["a", "c"]), (4, []), (5, ["b"])]
    for rows in (once, [*once, (1, ["a", "d"]), (2, ["a"])], [*once, (None, ["a", "c"])]):
        docs = spark.createDataFrame(rows, "msg_id long, terms array<string>")
        for share in (0.3, 0.5):
            want = counters.heavy_terms(docs.select("msg_id", F.explode("terms").alias("term")), share)
            assert sorted(counters.heavy_gathered(docs, share).collect()) == sorted(want.collect())
    docs = adapters.gathered_documents(spark, sf)
    names = ["seq", "ts", "msg_id", "cell", "term"]
    got = docs.select(*names[:4], F.explode("terms").alias("term"))
    want = adapters.documents(spark, sf).select(*names)
    assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0
    assert sorted(workloads.sampled_terms(docs, n=50).collect()) == sorted(workloads.sampled_terms(adapters.documents(spark, sf), n=50).collect())


def test_one_replay_of_several_settings_equals_those_of_each(spark, monkeypatch):
    monkeypatch.setattr(R, "WAITING", 500)
    monkeypatch.setattr(R, "PARTS", 64)
    rng = random.Random(8)
    cells = [rng.randrange(180 * 360) for _ in range(40)]
    rows = [(k // 3, k, k, t, rng.choice(cells)) for k in range(1500) for t in "abc"[: rng.randrange(1, 4)]]
    occ = spark.createDataFrame(rows, "ts long, seq long, msg_id long, term string, cell int").withColumn("ts", F.timestamp_seconds("ts"))
    settings = [(27, None), (10, R.edges(ratio=0.3, n=5)), (6, R.edges()), (50, R.edges(ratio=0.5, n=8))]
    got = R.build_every(counters.gathered(occ), settings).collect()
    assert len(got) == 12
    for i, (m, radii) in enumerate(settings):
        want = {r.term: r for r in (counters.build(occ, m) if radii is None else R.build(occ, m, radii)).collect()}
        for g in (r for r in got if r.list == i):
            w = want[g.term]
            assert (g.total, g.capacity, g.policy, g.n_replaced) == (w.total, w.capacity, w.policy, w.n_replaced)
            assert [(c.cell, c.f, c.err, c.born_seq) for c in g.centers] == [(c.cell, c.f, c.err, c.born_seq) for c in w.centers]
            assert all(abs(x - y) < 1e-6 for c, e in zip(g.centers, w.centers, strict=True) for x, y in zip(c.rings, e.rings, strict=True))


def test_gathered_arrivals_of_a_frequent_term_are_several_tasks(spark):
    rng = random.Random(2)
    rows = [(rng.randrange(300), k % 70, rng.randrange(500), rng.choice(["a"] * 9 + ["b", None]), rng.choice([None, *range(9)])) for k in range(6000)]
    occ = spark.createDataFrame(rows, "ts long, seq long, msg_id long, term string, cell int").withColumn("ts", F.timestamp_seconds("ts"))
    pieces = counters.gathered(occ.repartition(3)).collect()
    for t in "ab":
        own = sorted((p for p in pieces if p.term == t), key=lambda p: p.part)
        want = sorted((r for r in rows if r[3] == t and r[4] is not None), key=lambda r: (r[0], r[1], r[2], r[4]))
        assert [x for p in own for x in zip(p.cells, p.seqs, strict=True)] == [(r[4], r[1]) for r in want] and max(len(p.cells) for p in own) <= counters.PIECE
    assert len(pieces) == len({p.part for p in pieces}) and len({p.part >> 40 for p in pieces if p.term == "a"}) > 1


def test_gathered_messages_are_their_arrivals_in_order(spark, monkeypatch):
    monkeypatch.setattr(counters, "PIECE", 7)
    rng = random.Random(9)
    rows = [(rng.randrange(40), k % 50, rng.choice([k, None]), rng.choice([None, *range(9)]), rng.sample("abcdef", rng.randrange(6))) for k in range(300)]
    docs = spark.createDataFrame(rows, "ts long, seq long, msg_id long, cell int, terms array<string>").withColumn("ts", F.timestamp_seconds("ts"))
    terms = ["a", "c", "f"]
    pieces = counters.gathered_messages(counters.coded_messages(docs.repartition(5), terms), terms).collect()
    got = {t: [x for p in sorted((p for p in pieces if p.term == t), key=lambda p: p.part) for x in zip(p.cells, p.seqs, strict=True)] for t in terms}
    low = lambda x: (x is not None, x or 0)
    order = sorted((r for r in rows if r[3] is not None), key=lambda r: (r[0], r[1], low(r[2]), r[3]))
    assert got == {t: [(r[3], r[1]) for r in order if t in r[4]] for t in terms}
    assert {p.term for p in pieces} == set(terms) and max(len(p.cells) for p in pieces) == 7


def test_fits_of_several_sides_equal_those_of_each(spark):
    rng = random.Random(6)
    counts = [spark.createDataFrame([(t, rng.randrange(180 * 360), rng.randrange(1, 60)) for t in "ab" for _ in range(n)], "term string, cell int, n long") for n in (4, 9)]
    radii = M.fine_radii(n=64)
    table = R.band_table(spark, radii)
    got = M.fit_sides([(c, M.top_cells(c, None), s) for c, s in zip(counts, ("cells", "all"), strict=True)], table, radii, table)
    for g, c, s in zip(got, counts, ("cells", "all"), strict=True):
        want = {r.term: r for r in M.fit_exact(c, table, radii, screen=table).collect()}
        assert {r.term: (r.center_cell, r.focus, r.spread, r.source) for r in g.collect()} == {t: (r.center_cell, r.focus, r.spread, s) for t, r in want.items()}
