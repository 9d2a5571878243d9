"""Queries of the place engine and, where SQL expresses them, the same results in DuckDB's SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from termatlas.functions import geo
from termatlas.functions.scratch import materialize
from termatlas.operators import answers, counters, exact, metrics, multicenter
from termatlas.operators import model as M
from termatlas.operators import rings as R
from termatlas.plans import methods, workloads
from termatlas.sources import adapters
from termatlas.sources.tables import read
from termatlas.streaming import summaries

Query = Callable[[SparkSession, str], DataFrame]
GRID_EDGES = (1.5, 3.0, 6.0, 12.0, 24.0)  # in cells; squares of cell distances never fall on their squares

# --- SQL of the adapters -------------------------------------------------------------------------

_ANCHORS = ", ".join(f"('{k}', {a}, {b}, {c})" for k, (a, b, c) in adapters.ANCHORS.items())
_BEARINGS = ", ".join(f"({k}, {x}, {y})" for k, (x, y) in enumerate(adapters.BEARINGS))
_LANGUAGES = ", ".join(f"('{k}', {a}, {b})" for k, (a, b) in adapters.LANGUAGES.items())
_CELL = "(((lat_e6 + 90000000) // 1000000) * 360 + (((lon_e6 + 180000000) % 360000000 + 360000000) % 360000000) // 1000000)::INTEGER"


def _events_sql(drift: str = "0") -> str:
    return f"""
occ AS (SELECT *, {_CELL} AS cell FROM (
  SELECT epoch_us(e.ts) AS seq, e.event_id AS msg_id, e.event_type AS term,
    a.lon * 1000000 + 500000 + (cast(round(e.value * 100) AS BIGINT) * b.dx * a.scale + 100000000000000) // 100 - 1000000000000 + {drift} AS lon_e6,
    a.lat * 1000000 + 500000 + (cast(round(e.value * 100) AS BIGINT) * b.dy * a.scale + 100000000000000) // 100 - 1000000000000 AS lat_e6
  FROM events e JOIN (VALUES {_ANCHORS}) a(term, lon, lat, scale) ON a.term = e.event_type
  JOIN (VALUES {_BEARINGS}) b(k, dx, dy) ON b.k = cast(json_extract_string(e.props, '$.k') AS INTEGER)))"""


_DOCS = f"""
placed AS (SELECT d.doc_id AS msg_id, d.text, (l.lon + s.n % 5 - 2) * 1000000 + 500000 AS lon_e6, (l.lat + s.n // 5 - 2) * 1000000 + 500000 AS lat_e6
  FROM documents d JOIN (VALUES {_LANGUAGES}) l(lang, lon, lat) ON l.lang = d.lang
  JOIN (SELECT doc_id, cast(regexp_extract(source, '([0-9]+)$', 1) AS BIGINT) % 20 AS n FROM documents) s ON s.doc_id = d.doc_id),
occ AS (SELECT msg_id AS seq, msg_id, term, lon_e6, lat_e6, {_CELL} AS cell FROM (
  SELECT DISTINCT msg_id, lon_e6, lat_e6, unnest(regexp_extract_all(lower(text), '[a-zà-öø-ÿ]{{3,}}')) AS term FROM placed))"""

_NATION_LON = "(n.n_regionkey * 60 - 150 + (n.n_nationkey % 5) * 3 + {k} % 3) * 1000000 + 500000"
_NATION_LAT = "(n.n_regionkey * 10 - 20 + (n.n_nationkey // 5) * 3 + {k} // 3) * 1000000 + 500000"
_GAZ = f"""
gaz AS (SELECT {_CELL} AS cell, nation, region FROM (
  SELECT {_NATION_LON.format(k="k.k")} AS lon_e6, {_NATION_LAT.format(k="k.k")} AS lat_e6, n.n_name AS nation, r.r_name AS region
  FROM nation n JOIN region r ON r.r_regionkey = n.n_regionkey CROSS JOIN (SELECT unnest(range(9)) AS k) k))"""
_ORDERS = f"""
occ AS (SELECT *, {_CELL} AS cell FROM (
  SELECT o.o_orderkey AS msg_id, unnest([o.o_orderpriority, c.c_mktsegment]) AS term, {_NATION_LON.format(k="(c.c_custkey % 9)")} AS lon_e6, {_NATION_LAT.format(k="(c.c_custkey % 9)")} AS lat_e6
  FROM orders o JOIN customer c ON c.c_custkey = o.o_custkey JOIN nation n ON n.n_nationkey = c.c_nationkey))"""
_LINEITEM = f"""
occ AS (SELECT *, {_CELL} AS cell FROM (
  SELECT i.l_orderkey * 8 + i.l_linenumber AS msg_id, unnest(list_distinct(list_append(string_split(lower(p.p_name || ' ' || p.p_type), ' '), lower(p.p_brand)))) AS term,
    {_NATION_LON.format(k="(s.s_suppkey % 9)")} AS lon_e6, {_NATION_LAT.format(k="(s.s_suppkey % 9)")} AS lat_e6
  FROM lineitem i JOIN part p ON p.p_partkey = i.l_partkey JOIN supplier s ON s.s_suppkey = i.l_suppkey JOIN nation n ON n.n_nationkey = s.s_nationkey))"""
_COUNTS = "counts AS (SELECT term, cell, count(*) AS n FROM occ GROUP BY term, cell)"
_TOTALS = "totals AS (SELECT term, sum(n)::BIGINT AS total FROM counts GROUP BY term)"
_RANKED = "ranked AS (SELECT *, row_number() OVER (PARTITION BY term ORDER BY n DESC, cell) AS rank FROM counts)"
EVENTS = f"WITH {_events_sql()}, {_COUNTS}, {_TOTALS}, {_RANKED} "


def _replay(m: int, more: str = "", occ: str | None = None) -> str:
    """A replay of the counters: one step an arrival and term; counters are (f, c, d) so that they sort by count, then cell."""
    return f"""
WITH RECURSIVE {occ or _events_sql()}, {_COUNTS}, {_TOTALS},
a AS (SELECT term, cell, row_number() OVER (PARTITION BY term ORDER BY seq, msg_id, cell) AS k FROM occ),
r AS (
  SELECT term, 0::BIGINT AS k, cast([] AS STRUCT(f BIGINT, c INTEGER, d BIGINT)[]) AS cs FROM (SELECT DISTINCT term FROM a)
  UNION ALL
  SELECT r.term, a.k, CASE
    WHEN len(list_filter(cs, lambda x: x.c = a.cell)) > 0 THEN list_transform(cs, lambda x: CASE WHEN x.c = a.cell THEN struct_pack(f := x.f + 1, c := x.c, d := x.d) ELSE x END)
    WHEN len(cs) < {m} THEN list_append(cs, struct_pack(f := 1::BIGINT, c := a.cell, d := 0::BIGINT))
    ELSE list_append(list_sort(cs)[2:], struct_pack(f := list_sort(cs)[1].f + 1, c := a.cell, d := list_sort(cs)[1].f)) END
  FROM r JOIN a ON a.term = r.term AND a.k = r.k + 1),
last AS (SELECT r.term, r.cs FROM r JOIN (SELECT term, max(k) AS k FROM a GROUP BY term) e ON e.term = r.term AND e.k = r.k),
summary AS (SELECT term, u.c AS cell, u.f AS f, u.d AS err FROM (SELECT term, unnest(cs) AS u FROM last)){more} """


def _band_replay(m: int, policy: str) -> str:
    """A replay with planar bands (b), where they are whole numbers: for reset, and for a freeze before any replacement."""
    d2 = "((x.c // 360 - a.cell // 360) * (x.c // 360 - a.cell // 360) + (x.c % 360 - a.cell % 360) * (x.c % 360 - a.cell % 360))"
    grown = f"list_transform(x.b, lambda v, i: v + CASE WHEN i = {_band_sql(d2)} + 1 THEN 1 ELSE 0 END)"
    counted = f"CASE WHEN x.c = a.cell THEN struct_pack(f := x.f + 1, c := x.c, d := x.d, b := x.b) ELSE struct_pack(f := x.f, c := x.c, d := x.d, b := {grown}) END"
    fresh = f"struct_pack(f := {{f}}, c := a.cell, d := {{d}}, b := list_transform(range({len(GRID_EDGES)}), lambda i: 0::BIGINT))"
    frozen = f"WHEN a.k - 1 >= {m} THEN list_transform(cs, lambda x: {counted})" if policy == "freeze" else ""
    return f"""
WITH RECURSIVE {_events_sql()},
a AS (SELECT term, cell, row_number() OVER (PARTITION BY term ORDER BY seq, msg_id, cell) AS k FROM occ),
r AS (
  SELECT term, 0::BIGINT AS k, cast([] AS STRUCT(f BIGINT, c INTEGER, d BIGINT, b BIGINT[])[]) AS cs FROM (SELECT DISTINCT term FROM a)
  UNION ALL
  SELECT r.term, a.k, CASE
    WHEN len(list_filter(cs, lambda x: x.c = a.cell)) > 0 THEN list_transform(cs, lambda x: {counted})
    {frozen}
    WHEN len(cs) < {m} THEN list_append(list_transform(cs, lambda x: {counted}), {fresh.format(f="1::BIGINT", d="0::BIGINT")})
    ELSE list_append(list_transform(list_sort(cs)[2:], lambda x: {counted}), {fresh.format(f="list_sort(cs)[1].f + 1", d="list_sort(cs)[1].f")}) END
  FROM r JOIN a ON a.term = r.term AND a.k = r.k + 1),
last AS (SELECT r.term, r.cs FROM r JOIN (SELECT term, max(k) AS k FROM a GROUP BY term) e ON e.term = r.term AND e.k = r.k)
SELECT term, u.c AS cell, u.f AS f, u.d AS err, array_to_string(u.b, ' ') AS bands FROM (SELECT term, unnest(cs) AS u FROM last)"""


def _band_sql(d2: str, edges: tuple[float, ...] = GRID_EDGES) -> str:
    return "CASE " + " ".join(f"WHEN {d2} <= {e * e} THEN {k}" for k, e in enumerate(edges[:-1])) + f" ELSE {len(edges) - 1} END"


# --- small frames ---------------------------------------------------------------------------------


def _occ(spark: SparkSession, sf: str) -> DataFrame:
    return adapters.events(spark, sf)


def _summary(spark: SparkSession, sf: str, m: int) -> DataFrame:
    return counters.build(_occ(spark, sf), m)


def _asked(counts: DataFrame) -> DataFrame:
    """Ten places a term: five by rank, and their eastern neighbours five cells away."""
    top = exact.hot_places(counts, 5)
    return top.select((F.col("cell") * 10 + F.col("rank")).cast("long").alias("qid"), "term", F.explode(F.array("cell", F.col("cell") + 5)).alias("cell")).withColumn("qid", F.col("cell").cast("long"))


_ASKED = "asked AS (SELECT x.term, unnest([x.cell, x.cell + 5]) AS cell FROM ranked x WHERE x.rank <= 5)"

QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def _counted(occ: DataFrame) -> DataFrame:
    return occ.groupBy("term", "cell").agg(F.count("*").alias("n"), F.sum("lon_e6").alias("lon_sum"), F.sum("lat_e6").alias("lat_sum"))


_OCC_OUT = "SELECT term, cell, count(*) AS n, sum(lon_e6)::BIGINT AS lon_sum, sum(lat_e6)::BIGINT AS lat_sum FROM occ GROUP BY term, cell"


@query(f"WITH {_events_sql()} {_OCC_OUT}")
def occ_events(spark, sf):
    return _counted(_occ(spark, sf))


@query("WITH " + _events_sql("(epoch_us(e.ts) - epoch_us(TIMESTAMP '2024-01-01')) // 259200000000 * 1000000") + f" {_OCC_OUT}")
def occ_drifting(spark, sf):
    return _counted(adapters.drifting(spark, sf))


@query(f"WITH {_DOCS} {_OCC_OUT}")
def occ_documents(spark, sf):
    return _counted(adapters.documents(spark, sf))


@query(f"WITH {_ORDERS} {_OCC_OUT}")
def occ_orders(spark, sf):
    return _counted(adapters.orders(spark, sf))


@query(f"WITH {_LINEITEM} {_OCC_OUT}")
def occ_lineitem(spark, sf):
    return _counted(adapters.lineitem(spark, sf))


_TERMS = "unnest(list_distinct(regexp_extract_all(lower(coalesce({}, '')), '[a-zà-öø-ÿ]{{3,}}'))) AS term"
_TURNS = f"""
occ AS (SELECT *, {_CELL} AS cell FROM (
  SELECT conv_id * 1000 + turn AS msg_id, ((conv_id * 37) % 360 - 180) * 1000000 + 500000 AS lon_e6, (30 + (conv_id * 11) % 120 - 90) * 1000000 + 500000 AS lat_e6, {_TERMS.format("text")} FROM conversations))"""
_PAGES = f"""
occ AS (SELECT *, {_CELL} AS cell FROM (
  SELECT p.page_id AS msg_id, (l.lon + p.page_id % 20 % 5 - 2) * 1000000 + 500000 AS lon_e6, (l.lat + p.page_id % 20 // 5 - 2) * 1000000 + 500000 AS lat_e6,
    {_TERMS.format("regexp_replace(regexp_replace(regexp_replace(html, '<script.*?</script *>', ' ', 'gis'), '<style.*?</style *>', ' ', 'gis'), '<[^>]*>', ' ', 'gs')")}
  FROM pages p LEFT JOIN (VALUES {_LANGUAGES}) l(lang, lon, lat) ON l.lang = regexp_extract(p.html, 'lang="([a-z]{{2}})"', 1)))"""


@query(f"WITH {_TURNS} {_OCC_OUT}")
def occ_conversations(spark, sf):
    return _counted(adapters.conversations(spark, sf))


@query(f"WITH {_PAGES} {_OCC_OUT}")
def occ_pages(spark, sf):
    return _counted(adapters.pages(spark, sf))


@query(EVENTS + ", every AS (SELECT cell, sum(n)::BIGINT AS n FROM counts GROUP BY cell) SELECT i::INTEGER AS cell, (i // 360)::INTEGER AS row, (i % 360)::INTEGER AS col, i // 360 + 0.5::DOUBLE - 90 AS lat, i % 360 + 0.5::DOUBLE - 180 AS lon, coalesce(e.n, 0) AS n FROM range(64800) t(i) LEFT JOIN every e ON e.cell = i")
def cells_dim(spark, sf):
    """All cells of the map with their arrivals of any term."""
    n = exact.counts(_occ(spark, sf)).groupBy("cell").agg(F.sum("n").alias("n"))
    return R.cells(spark).join(n, "cell", "left").withColumn("n", F.coalesce("n", F.lit(0)))


@query(f"WITH {_GAZ} SELECT * FROM gaz")
def gazetteer_dim(spark, sf):
    return adapters.gazetteer(spark, sf)


@query(EVENTS + "SELECT * FROM counts")
def exact_counts(spark, sf):
    return exact.counts(_occ(spark, sf))


@query(EVENTS + "SELECT term, count(*) AS cells, sum(n)::BIGINT AS total FROM counts GROUP BY term")
def posting_lists_size(spark, sf):
    p = exact.posting_lists(_occ(spark, sf))
    return p.select("term", F.size("postings").cast("long").alias("cells"), F.aggregate("postings", F.lit(0).cast("long"), lambda s, x: s + x["n"]).alias("total"))


@query(EVENTS + "SELECT term, rank::INTEGER AS rank, cell, n FROM ranked WHERE rank <= 10")
def exact_hot_places(spark, sf):
    return exact.hot_places(exact.counts(_occ(spark, sf)), 10)


@query(EVENTS + f", {_ASKED} SELECT a.cell::BIGINT AS qid, a.term, a.cell, coalesce(c.n, 0) AS n FROM asked a LEFT JOIN counts c ON c.term = a.term AND c.cell = a.cell")
def exact_place_frequency(spark, sf):
    c = exact.counts(_occ(spark, sf))
    return exact.place_frequency(c, _asked(c))


@query(f"WITH {_DOCS} SELECT term, count(DISTINCT msg_id) AS n FROM occ GROUP BY term HAVING count(DISTINCT msg_id) >= 0.02 * (SELECT count(DISTINCT msg_id) FROM occ)")
def heavy_terms(spark, sf):
    return counters.heavy_terms(adapters.documents(spark, sf), 0.02)


@query(EVENTS + "SELECT term, count(*) AS places FROM counts GROUP BY term")
def distinct_places(spark, sf):
    return exact.counts(_occ(spark, sf)).groupBy("term").agg(F.count("*").alias("places"))


@query(_replay(10) + "SELECT term, cell, f, err FROM summary")
def counter_summary_small(spark, sf):
    return counters.exploded(_summary(spark, sf, 10)).select("term", "cell", "f", "err")


@query(EVENTS + "SELECT term, cell, n AS f, 0::BIGINT AS err FROM counts")
def counter_summary_roomy(spark, sf):
    return counters.exploded(_summary(spark, sf, 4096)).select("term", "cell", "f", "err")


@query(_replay(10) + "SELECT term, rank::INTEGER AS rank, cell, f AS est, f - err AS lower, f AS upper FROM (SELECT *, row_number() OVER (PARTITION BY term ORDER BY f DESC, err, cell) AS rank FROM summary) WHERE rank <= 5")
def hot_places(spark, sf):
    return answers.hot_places(_summary(spark, sf, 10), 5)


@query(_replay(10) + "SELECT s.term, s.cell, s.f, s.err, s.f - s.err >= 0.1 * t.total AS guaranteed FROM summary s JOIN totals t USING (term) WHERE s.f >= 0.1 * t.total")
def frequent_places(spark, sf):
    return answers.frequent_places(_summary(spark, sf, 10), 0.1)


@query(_replay(10) + "SELECT term, CASE WHEN count(*) >= 10 THEN min(f) ELSE 0 END AS bound FROM summary GROUP BY term")
def absent_bound(spark, sf):
    return _summary(spark, sf, 10).select("term", counters.absent_bound().alias("bound"))


@query(EVENTS + "SELECT term, total, total AS counted FROM totals")
def term_totals(spark, sf):
    return _summary(spark, sf, 10).select("term", "total", counters.total().alias("counted"))


@query("SELECT 0::BIGINT AS interval, 0::BIGINT AS absent, 0::BIGINT AS frequent, 0::BIGINT AS totals, 0::BIGINT AS errors")
def error_bound_check(spark, sf):
    occ = _occ(spark, sf)
    return metrics.invariants(counters.build(occ, 20), exact.counts(occ))


_DAYS = f"""
occ AS (SELECT epoch_us(ts) AS seq, event_id AS msg_id, strftime(ts, '%Y-%m-%d') AS term, list_position({list(adapters.ANCHORS)}, event_type)::INTEGER AS cell FROM events WHERE event_type IN {tuple(adapters.ANCHORS)})"""


@query(_replay(3, occ=_DAYS) + f"SELECT term AS day, {list(adapters.ANCHORS)}[cell] AS place, f, err FROM summary")
def small_stream_example(spark, sf):
    """Few places and three counters: each day's events as a stream whose places are the types."""
    kinds = F.array(*map(F.lit, adapters.ANCHORS))
    day = F.date_format("ts", "yyyy-MM-dd").alias("term")
    occ = read(spark, sf, "events").select(F.unix_micros("ts").alias("seq"), "ts", F.col("event_id").alias("msg_id"), day, F.array_position(kinds, F.col("event_type")).cast("int").alias("cell"))
    out = counters.exploded(counters.build(occ.where("cell > 0"), 3))
    return out.select(F.col("term").alias("day"), F.element_at(kinds, F.col("cell")).alias("place"), "f", "err")


_FROM_TOP = "(r.cell // 360 - c.cell // 360) * (r.cell // 360 - c.cell // 360) + (r.cell % 360 - c.cell % 360) * (r.cell % 360 - c.cell % 360)"
_EDGES_CASE = "CASE " + " ".join(f"WHEN d2 <= pow(98 * pow(0.6, {9 - k}), 2) THEN {k}" for k in range(9)) + " ELSE 9 END"


@query(
    EVENTS
    + f", hit AS (SELECT term, {_EDGES_CASE} AS band, sum(n)::BIGINT AS n FROM (SELECT c.term, c.n, {_FROM_TOP} AS d2 FROM counts c JOIN ranked r ON r.term = c.term AND r.rank = 1) WHERE d2 > 0 GROUP BY ALL) "
    "SELECT t.term, b.band::INTEGER AS band, round(98 * pow(0.6, 9 - b.band), 6) AS radius, coalesce(h.n, 0) AS n FROM totals t CROSS JOIN range(10) b(band) LEFT JOIN hit h ON h.term = t.term AND h.band = b.band"
)
def ring_edges(spark, sf):
    """The radii, and each term's arrivals between them, in planar steps from its hottest cell."""
    c = materialize(exact.counts(_occ(spark, sf)), "counts")
    radii = spark.createDataFrame(list(enumerate(R.edges())), "band int, radius double")
    every = c.select("term").distinct().join(F.broadcast(radii), F.lit(True))
    hit = R.exact(c, exact.hot_places(c, 1), R.edges(), metric="grid").select("term", "band", "n")
    return every.join(hit, ["term", "band"], "left").select("term", "band", F.round("radius", 6).alias("radius"), F.coalesce("n", F.lit(0)).alias("n"))


@query(
    EVENTS
    + f", far AS (SELECT term, max(d2) AS d2 FROM (SELECT c.term, {_FROM_TOP} AS d2 FROM counts c JOIN ranked r ON r.term = c.term AND r.rank = 1) GROUP BY term) "
    "SELECT term, k / 10::DOUBLE AS ratio, least(10, 1 + ceil(ln(greatest(sqrt(d2), 1)) / ln(10 / k::DOUBLE) - 1e-9))::INTEGER AS rings FROM far, range(1, 10) t(k)"
)
def ring_counts_by_ratio(spark, sf):
    """Bands from each term's farthest place down to one cell, by the ratio of neighbouring radii."""
    c = exact.counts(_occ(spark, sf))
    rows = c.join(exact.hot_places(c, 1).select("term", F.col("cell").alias("top")), "term")
    far = rows.groupBy("term").agg(F.max(geo.cell_distance("top", "cell", metric="grid")).alias("outer"))
    ratios = far.withColumn("ratio", F.explode(F.array(*(F.lit(k / 10) for k in range(1, 10)))))
    return ratios.select("term", "ratio", R.count_for_column("ratio", "outer").alias("rings"))


@query(EVENTS + "SELECT t.term, s.rings, s.counters, least(s.counters, t.cells) AS used FROM (SELECT term, count(*) AS cells FROM counts GROUP BY term) t CROSS JOIN (VALUES (0, 216), (5, 81), (7, 65), (8, 59), (10, 50)) s(rings, counters)")
def equal_space_capacity(spark, sf):
    """Counters of equal space by their bands, and how many of them each term has places for."""
    splits = spark.createDataFrame([(r, R.capacity_for_budget(648, r)) for r in (0, 5, 7, 8, 10)], "rings int, counters int")
    cells = exact.counts(_occ(spark, sf)).groupBy("term").agg(F.count("*").alias("cells"))
    return cells.join(F.broadcast(splits), F.lit(True)).select("term", "rings", "counters", F.least("counters", "cells").alias("used"))


_STEPS = "(a.row - r.o) * (a.row - r.o) + (180 - c.c) * (180 - c.c)"
_TABLE = f"""tab AS (SELECT row::INTEGER AS row, {_band_sql("d2")} AS band, count(*) AS cells FROM (
  SELECT a.row, {_STEPS} AS d2 FROM range(180) a(row), range(180) r(o), range(360) c(c)) WHERE d2 > 0 GROUP BY ALL)"""


@query(EVENTS + f", {_TABLE}, held AS (SELECT cell // 360 AS row, sum(n)::BIGINT AS arrivals FROM counts GROUP BY 1) SELECT t.row, t.band, t.cells, coalesce(h.arrivals, 0) AS arrivals FROM tab t LEFT JOIN held h ON h.row = t.row")
def band_table(spark, sf):
    """Cells of each band around a centre in each row of the map, and the arrivals in that row."""
    held = exact.counts(_occ(spark, sf)).groupBy(geo.cell_row("cell").alias("row")).agg(F.sum("n").alias("arrivals"))
    table = R.band_table(spark, list(GRID_EDGES), metric="grid").select("row", "band", "cells")
    return table.join(held, "row", "left").select("row", "band", "cells", F.coalesce("arrivals", F.lit(0)).alias("arrivals"))


_PAIR = "(c.cell // 360 - t.cell // 360) * (c.cell // 360 - t.cell // 360) + (c.cell % 360 - t.cell % 360) * (c.cell % 360 - t.cell % 360)"
_EXACT = f"bands AS (SELECT term, center_cell, {_band_sql('d2')} AS band, sum(n)::BIGINT AS n FROM (SELECT c.term, t.cell AS center_cell, c.n, {_PAIR} AS d2 FROM counts c JOIN ranked t ON t.term = c.term AND t.rank <= 3) WHERE d2 > 0 GROUP BY ALL)"


def _three(counts: DataFrame) -> DataFrame:
    return exact.hot_places(counts, 3)


@query(EVENTS + f", {_EXACT} SELECT * FROM bands")
def exact_rings(spark, sf):
    c = exact.counts(_occ(spark, sf))
    return R.exact(c, _three(c), list(GRID_EDGES), metric="grid")


@query(EVENTS + f", {_EXACT}, {_TABLE} SELECT b.term, b.center_cell, b.band, b.n, t.cells, t.cells - b.n AS empty FROM bands b JOIN tab t ON t.row = b.center_cell // 360 AND t.band = b.band")
def empty_cells(spark, sf):
    c = exact.counts(_occ(spark, sf))
    bands = R.exact(c, _three(c), list(GRID_EDGES), metric="grid")
    return R.empty_cells(bands, R.band_table(spark, list(GRID_EDGES), metric="grid"))


@query(EVENTS + f"SELECT term, cell, {_band_sql('d2')} AS band FROM (SELECT c.term, c.cell, {_FROM_TOP} AS d2 FROM counts c JOIN ranked r ON r.term = c.term AND r.rank = 1) WHERE d2 > 0")
def band_of_pairs(spark, sf):
    """Bands of each place around its term's hottest by all three ways of looking them up, where they agree."""
    radii, c = list(GRID_EDGES), exact.counts(_occ(spark, sf))
    rows = c.join(exact.hot_places(c, 1).select("term", F.col("cell").alias("top")), "term").withColumn("d", geo.cell_distance("top", "cell", metric="grid"))
    rows = rows.where("d > 0").withColumns({m: R.band("d", radii, m) for m in ("linear", "binary", "closed")})
    return rows.where("linear = binary and binary = closed").select("term", "cell", F.col("binary").alias("band"))


def _lens_sql(p: str, q: str) -> str:
    """Area common to discs of radii p and q, centres d apart."""
    x, y = (f"acos(greatest(-1, least(1, (d * d + {a} * {a} - {b} * {b}) / (2 * d * {a}))))" for a, b in ((p, q), (q, p)))
    root = f"sqrt(greatest(({p} + {q} - d) * (d + {p} - {q}) * (d - {p} + {q}) * (d + {p} + {q}), 0))"
    return f"(CASE WHEN least({p}, {q}) = 0 OR d >= {p} + {q} THEN 0 WHEN d <= abs({p} - {q}) THEN pi() * pow(least({p}, {q}), 2) ELSE {p} * {p} * {x} + {q} * {q} * {y} - {root} / 2 END)"


_RADII = ", ".join(f"({k}, {a}::DOUBLE, {b}::DOUBLE)" for k, (a, b) in enumerate(zip((0.0, *GRID_EDGES), GRID_EDGES, strict=False)))
_OVERLAP = f"greatest({_lens_sql('i.hi', 'k.hi')} - {_lens_sql('i.lo', 'k.hi')} - {_lens_sql('i.hi', 'k.lo')} + {_lens_sql('i.lo', 'k.lo')}, 0)"


@query(
    EVENTS
    + f""", {_EXACT}, radii(band, lo, hi) AS (VALUES {_RADII}),
two AS (SELECT r.term, r.cell AS old, c.cell AS new, sqrt(({_FROM_TOP})::DOUBLE) AS d FROM ranked r JOIN ranked c ON c.term = r.term AND c.rank = 2 WHERE r.rank = 1)
SELECT t.term, i.band::INTEGER AS band, round(sum({_OVERLAP} / (pi() * (k.hi * k.hi - k.lo * k.lo)) * coalesce(b.n, 0)), 4) AS n
FROM two t CROSS JOIN radii i CROSS JOIN radii k LEFT JOIN bands b ON b.term = t.term AND b.center_cell = t.old AND b.band = k.band GROUP BY t.term, i.band"""
)
def ring_transfer_example(spark, sf):
    """The bands around each term's hottest cell, moved to its second hottest by shares of areas."""
    radii, c = list(GRID_EDGES), exact.counts(_occ(spark, sf))
    top = exact.hot_places(c, 2)
    one, two = (top.where(F.col("rank") == k).select("term", F.col("cell").alias(name)) for k, name in ((1, "center_cell"), (2, "new")))
    bands = R.exact(c, exact.hot_places(c, 1), radii, metric="grid").groupBy("term", "center_cell").agg(F.map_from_entries(F.collect_list(F.struct("band", "n"))).alias("m"))
    old = F.transform(F.sequence(F.lit(0), F.lit(len(radii) - 1)), lambda b: F.coalesce(F.element_at("m", b), F.lit(0)).cast("double"))
    rows = one.join(two, "term").join(bands, ["term", "center_cell"]).select("term", geo.cell_distance("center_cell", "new", metric="grid").alias("d"), old.alias("old"))
    return rows.mapInPandas(R.moved(radii), "term string, band int, n double").withColumn("n", F.round("n", 4))


@query()
def ring_summary_transfer(spark, sf):
    return _rings_out(R.build(_occ(spark, sf), 50))


def _rings_out(summary: DataFrame) -> DataFrame:
    return counters.exploded(summary).select("term", "rank", "cell", "f", "err", F.transform("rings", lambda x: F.round(x, 4)).alias("rings"))




def _planar_bands(spark: SparkSession, sf: str, policy: str, **options) -> DataFrame:
    rows = counters.exploded(R.build(_occ(spark, sf), 10, list(GRID_EDGES), policy, metric="grid", **options))
    return rows.select("term", "cell", "f", "err", F.array_join(F.transform("rings", lambda x: x.cast("long").cast("string")), " ").alias("bands"))


@query(_band_replay(10, "reset"))
def ring_summary_reset(spark, sf):
    """Counters and planar bands of the reset policy."""
    return _planar_bands(spark, sf, "reset")


@query(_band_replay(10, "freeze"))
def ring_bands_frozen(spark, sf):
    """Counters and planar bands of the freeze policy, frozen after ten arrivals: replayed before, counted after."""
    return _planar_bands(spark, sf, "freeze", freeze_after_rows=10)


@query()
def ring_summary_frozen(spark, sf):
    return _rings_out(R.build(_occ(spark, sf), 50, policy="freeze", freeze_fraction=0.2))


@query()
def ring_summary_nearby_skip(spark, sf):
    return _rings_out(R.build(_occ(spark, sf), 50, policy="nearby_skip"))


def _grid_fit_rows(spark: SparkSession, sf: str) -> DataFrame:
    """Fit rows of each term's hottest cell with exact planar bands, distances at bands' middles."""
    c = exact.counts(_occ(spark, sf))
    centre = M.top_cells(c, 1)
    bands = R.exact(c, centre, list(GRID_EDGES), metric="grid")
    tab = R.band_table(spark, list(GRID_EDGES), metric="grid").select("row", "band", "cells")
    mids = R.mean_distance(list(GRID_EDGES))
    every = centre.withColumn("row", geo.cell_row("cell")).join(F.broadcast(tab), "row").join(bands.withColumnRenamed("center_cell", "cell"), ["term", "cell", "band"], "left")
    one = F.struct(F.element_at(F.array(*map(F.lit, mids)), F.col("band") + 1).alias("d"), F.coalesce("n", F.lit(0)).cast("double").alias("n"), F.col("cells").cast("double").alias("cells"), F.lit(0.0).alias("occ"))
    return every.groupBy("term", "rank", "total", F.col("cell").alias("center_cell")).agg(F.array_sort(F.collect_list(one)).alias("bands"))


_SPREADS, _FOCUSES = tuple(k / 4 for k in range(4, 25)), tuple(k / 100 for k in (1, 2, 3, 5, 8, 12, 18, 27, 40))
_MIDS = "CASE band " + " ".join(f"WHEN {k} THEN {d}" for k, d in enumerate(R.mean_distance(list(GRID_EDGES)))) + " END"


_LATTICE = f"""{_EXACT}, {_TABLE}, fitrows AS (
  SELECT r.term, r.cell AS center_cell, t.total, {_MIDS.replace("band", "tab.band", 1)}::DOUBLE AS d, coalesce(b.n, 0)::DOUBLE AS n, tab.cells::DOUBLE AS cells
  FROM ranked r JOIN totals t ON t.term = r.term JOIN tab ON tab.row = r.cell // 360 LEFT JOIN bands b ON b.term = r.term AND b.center_cell = r.cell AND b.band = tab.band WHERE r.rank = 1),
lattice AS (
  SELECT f.term, f.center_cell, s.spread::DOUBLE AS spread, c.focus::DOUBLE AS focus,
    round(sum(f.n * ln(least(c.focus * pow(greatest(f.d, 1), -s.spread), 1 - 1e-12)) + greatest(f.total * f.cells - f.n, 0) * ln(1 - least(c.focus * pow(greatest(f.d, 1), -s.spread), 1 - 1e-12))), 3) AS loglik
  FROM fitrows f, (SELECT unnest({list(_SPREADS)}) AS spread) s, (SELECT unnest({list(_FOCUSES)}) AS focus) c GROUP BY ALL),
best AS (SELECT *, row_number() OVER (PARTITION BY term ORDER BY loglik DESC, spread, focus) AS r FROM lattice)"""


def _arc_sql(a: str, b: str) -> str:
    """Great-circle distance of two cells' centres in cells of one degree."""
    lat, lon = ((f"({c} // 360 - 89.5)::DOUBLE" for c in (a, b)), (f"({c} % 360 - 179.5)::DOUBLE" for c in (a, b)))
    (lat_a, lat_b), (lon_a, lon_b) = lat, lon
    h = f"pow(sin((radians({lat_b}) - radians({lat_a})) / 2), 2) + cos(radians({lat_a})) * cos(radians({lat_b})) * pow(sin(radians({lon_b} - {lon_a}) / 2), 2)"
    return f"degrees(2 * asin(sqrt(least({h}, 1.0))))"


def _decay_sql(a: str, b: str, focus: str, spread: str) -> str:
    return f"least({focus} * pow(greatest({_arc_sql(a, b)}, 1.0), -({spread})), 1.0)"


_MODELS = f"{_LATTICE}, models AS MATERIALIZED (SELECT b.term, b.center_cell, b.focus, b.spread, t.total FROM best b JOIN totals t ON t.term = b.term WHERE r = 1)"


@query(EVENTS + f", {_LATTICE} SELECT term, center_cell, focus, spread, round(loglik, 1) AS loglik FROM best WHERE r = 1")
def fit_lattice_rings(spark, sf):
    fitted = M.fit_lattice(_grid_fit_rows(spark, sf), list(_SPREADS), list(_FOCUSES))
    return fitted.select("term", "center_cell", "focus", "spread", F.round("loglik", 1).alias("loglik"))


def _lattice_models(spark: SparkSession, sf: str) -> DataFrame:
    """Each term's model of the lattice fit, with its total."""
    fitted = M.fit_lattice(_grid_fit_rows(spark, sf), list(_SPREADS), list(_FOCUSES))
    totals = exact.counts(_occ(spark, sf)).groupBy("term").agg(F.sum("n").alias("total"))
    return materialize(fitted.join(totals, "term"), "models")


@query()
def fit_lattice_two_stage(spark, sf):
    return M.fit_two_stage(_grid_fit_rows(spark, sf))


def _fitted(likelihood: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        out = M.fit(_grid_fit_rows(spark, sf), likelihood)
        return out.select("term", "center_cell", F.round("focus", 4).alias("focus"), F.round("spread", 4).alias("spread"), F.round("loglik", 3).alias("loglik"), "likelihood", "n_eval")

    run.__name__ = f"fit_{likelihood}"
    return run


for _name in M.LIKELIHOODS:
    query()(_fitted(_name))


@query()
def fit_cells(spark, sf):
    radii = M.fine_radii()
    s = counters.build(_occ(spark, sf), 216)
    return M.fit(M.cell_rows(M.counts_of(s), M.centres_of(s, 1), R.band_table(spark, radii), radii), source="cells")


@query()
def fit_all_occurrences(spark, sf):
    radii = M.fine_radii()
    return M.fit_exact(materialize(exact.counts(_occ(spark, sf)), "counts"), methods.tables(spark, radii), radii)


@query(EVENTS + "SELECT term, cell AS center_cell FROM ranked WHERE rank = 1")
def best_center(spark, sf):
    """The likeliest of all stored centres, which on these peaked terms is the most frequent cell."""
    radii = R.edges()
    return methods.ring_model_exact(_occ(spark, sf), 50, R.band_table(spark, radii), radii).models.select("term", "center_cell")


_AT = _decay_sql("r.cell", "g.i", "0.08", "2.8")


@query(
    EVENTS
    + f""", every AS (SELECT r.term, r.cell AS center_cell, t.total, coalesce(c.n, 0)::DOUBLE AS n, greatest(least({_AT}, 1 - 1e-12), 1e-300) AS p
  FROM ranked r JOIN totals t ON t.term = r.term CROSS JOIN (SELECT i::INTEGER AS i FROM range(64800) t(i)) g LEFT JOIN counts c ON c.term = r.term AND c.cell = g.i WHERE r.rank = 1)
SELECT term, center_cell, round(sum(n * ln(p) + (total - n) * ln(1 - p)), 2) AS loglik FROM every GROUP BY term, center_cell"""
)
def cell_loglik(spark, sf):
    """Log-likelihood over every cell of the map at fixed parameters: one distance a cell."""
    c = exact.counts(_occ(spark, sf))
    params = M.top_cells(c, 1).select("term", F.col("cell").alias("center_cell"), F.lit(0.08).alias("focus"), F.lit(2.8).alias("spread"), "total")
    return M.cell_loglik(c, params, R.cells(spark)).withColumn("loglik", F.round("loglik", 2))


def _frequency(how: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        occ = _occ(spark, sf)
        c = exact.counts(occ)
        return answers.place_frequency(counters.build(occ, 10), _asked(c), how=how).select("qid", "term", "cell", "est", "lower", "upper", "how")

    run.__name__ = f"place_frequency_{how}"
    return run


def _frequency_sql(other: str, how: str, more: str = "") -> str:
    return _replay(10, f", {_RANKED}, {_ASKED}, low AS (SELECT term, min(f) AS bound FROM summary GROUP BY term){more}") + (
        f"SELECT a.cell::BIGINT AS qid, a.term, a.cell, coalesce(s.f::DOUBLE, {other}) AS est, coalesce(s.f - s.err, 0) AS lower, coalesce(s.f, l.bound) AS upper, CASE WHEN s.f IS NOT NULL THEN 'counter' ELSE '{how}' END AS how "
        "FROM asked a LEFT JOIN summary s ON s.term = a.term AND s.cell = a.cell JOIN low l ON l.term = a.term" + (" LEFT JOIN around g ON g.term = a.term AND g.cell = a.cell" if more else "")
    )


_AROUND = """, around AS (SELECT a.term, a.cell, sum(coalesce(s.f, 0)) / 8.0::DOUBLE AS mean FROM asked a CROSS JOIN (SELECT unnest([-361, -360, -359, -1, 1, 359, 360, 361]) AS step) t
  LEFT JOIN summary s ON s.term = a.term AND s.cell = a.cell + t.step GROUP BY a.term, a.cell)"""
query(_frequency_sql("0", "zero"))(_frequency("zero"))
query(_frequency_sql("l.bound::DOUBLE", "bound"))(_frequency("bound"))
query(_frequency_sql("NULL::DOUBLE", "none"))(_frequency("counter"))
query(_frequency_sql("coalesce(g.mean, 0)", "neighbours", _AROUND))(_frequency("neighbours"))


def _ring_atlas(spark: SparkSession, sf: str) -> methods.Atlas:
    radii = R.edges()
    return methods.ring_model(_occ(spark, sf), 50, methods.tables(spark, radii), radii)


@query()
def place_frequency_auto(spark, sf):
    return _ring_atlas(spark, sf).place_frequency(_asked(exact.counts(_occ(spark, sf))))


@query()
def place_frequency_model(spark, sf):
    return _ring_atlas(spark, sf).place_frequency(_asked(exact.counts(_occ(spark, sf))), how="model")


_MODEL_AT = f", {_MODELS}, around AS (SELECT a.term, a.cell, m.total * {_decay_sql('m.center_cell', 'a.cell', 'm.focus', 'm.spread')} AS mean FROM asked a JOIN models m ON m.term = a.term)"


@query("SELECT qid, term, cell, round(est, 6) AS est, lower, upper, how FROM (" + _frequency_sql("g.mean", "model", _MODEL_AT) + ")")
def place_frequency_lattice(spark, sf):
    """Counters where they are kept, elsewhere the lattice models."""
    occ = _occ(spark, sf)
    got = answers.place_frequency(counters.build(occ, 10), _asked(exact.counts(occ)), _lattice_models(spark, sf))
    return got.withColumn("est", F.round("est", 6))


@query(EVENTS + f", {_MODELS}, {_ASKED} SELECT a.cell::BIGINT AS qid, a.term, a.cell, round(m.total * {_decay_sql('m.center_cell', 'a.cell', 'm.focus', 'm.spread')}, 6) AS est FROM asked a JOIN models m ON m.term = a.term")
def place_frequency_lattice_only(spark, sf):
    """The lattice models alone, counters unused."""
    occ = _occ(spark, sf)
    got = answers.place_frequency(counters.build(occ, 10), _asked(exact.counts(occ)), _lattice_models(spark, sf), how="model")
    return got.select("qid", "term", "cell", F.round("est", 6).alias("est"))


@query(
    EVENTS
    + f", {_MODELS} SELECT 'box' AS region, m.term, round(sum(m.total * {_decay_sql('m.center_cell', 'g.i', 'm.focus', 'm.spread')}), 4) AS est "
    "FROM models m, (SELECT i::INTEGER AS i FROM range(64800) t(i) WHERE i // 360 BETWEEN 120 AND 149 AND i % 360 BETWEEN 160 AND 219) g GROUP BY m.term"
)
def region_frequency_lattice(spark, sf):
    """Expected arrivals of a box by the lattice models."""
    boxes = R.cells(spark).where("lat between 30 and 60 and lon between -20 and 40").select(F.lit("box").alias("region"), "cell")
    got = answers.region_frequency(counters.build(_occ(spark, sf), 10), _lattice_models(spark, sf), boxes, how="model")
    return got.withColumn("est", F.round("est", 4))


_PAIRS = (("purchase", "view"), ("click", "view"), ("error", "view"), ("click", "signup"))


def _pairs(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(k, a, b) for k, (a, b) in enumerate(_PAIRS)], "qid long, a string, b string")


_HEAVY_PAIRS = """heavy AS (SELECT term FROM occ GROUP BY term HAVING count(DISTINCT msg_id) >= 0.02 * (SELECT count(DISTINCT msg_id) FROM occ)),
heavy_counts AS MATERIALIZED (SELECT c.term, c.cell, c.n FROM counts c JOIN heavy USING (term)),
pairs AS (SELECT x.term AS a, y.term AS b, count(*) AS n_places, sum(least(x.n, y.n))::BIGINT AS joint FROM heavy_counts x JOIN heavy_counts y ON x.cell = y.cell AND x.term < y.term GROUP BY ALL),
binned AS (SELECT *, (floor(4 * (rank() OVER (ORDER BY joint) - 1) / count(*) OVER ()) + 1)::INTEGER AS bin FROM pairs),
asked AS MATERIALIZED (SELECT a || ' ' || b AS qid, a, b, n_places, joint, bin FROM (SELECT *, row_number() OVER (PARTITION BY bin ORDER BY md5(a || ' ' || b), a, b) AS r FROM binned) WHERE r <= 100)"""
_DOC_PAIRS = f"WITH {_DOCS}, {_COUNTS}, {_HEAVY_PAIRS} "


def _word_pairs(occ: DataFrame) -> DataFrame:
    """A hundred pairs of each of four bins, of all heavy terms with a common place."""
    return materialize(workloads.binned_pairs(occ), "asked")


@query(_DOC_PAIRS + "SELECT q.qid, x.cell, least(x.n, y.n) AS n FROM asked q JOIN heavy_counts x ON x.term = q.a JOIN heavy_counts y ON y.term = q.b AND y.cell = x.cell")
def joint_min_counts(spark, sf):
    occ = adapters.documents(spark, sf)
    return exact.joint_counts(occ, _word_pairs(occ).select("qid", "a", "b"))


@query(_DOC_PAIRS + "SELECT q.qid, x.cell, count(*) AS n FROM asked q JOIN occ x ON x.term = q.a JOIN occ y ON y.term = q.b AND y.msg_id = x.msg_id AND y.cell = x.cell GROUP BY ALL")
def cooccurrence_messages(spark, sf):
    occ = adapters.documents(spark, sf)
    return exact.joint_counts(occ, _word_pairs(occ).select("qid", "a", "b"), kind="message")


@query(_DOC_PAIRS + "SELECT a, b, n_places, joint, bin FROM asked")
def pair_bins(spark, sf):
    return _word_pairs(adapters.documents(spark, sf)).select("a", "b", "n_places", "joint", "bin")


@query(_DOC_PAIRS + "SELECT count(*) AS pairs, sum(joint)::BIGINT AS joint, count(DISTINCT a) AS terms FROM pairs")
def pair_totals(spark, sf):
    """All pairs of heavy terms with a common place, in sum."""
    occ = materialize(adapters.documents(spark, sf), "occ")
    pairs = exact.term_pairs(occ, counters.heavy_terms(occ, 0.02))
    return pairs.agg(F.count("*").alias("pairs"), F.sum("joint").alias("joint"), F.count_distinct("a").alias("terms"))


@query(_DOC_PAIRS + "SELECT qid, rank::INTEGER AS rank, cell, n FROM (SELECT q.qid, x.cell, least(x.n, y.n) AS n, row_number() OVER (PARTITION BY q.qid ORDER BY least(x.n, y.n) DESC, x.cell) AS rank FROM asked q JOIN heavy_counts x ON x.term = q.a JOIN heavy_counts y ON y.term = q.b AND y.cell = x.cell) WHERE rank <= 3")
def multi_intersection(spark, sf):
    """Intersections of summaries with room for every place, so equal to those of counts."""
    occ = materialize(adapters.documents(spark, sf), "occ")
    asked = _word_pairs(occ)
    used = asked.select(F.explode("terms").alias("term")).distinct()
    return answers.intersect_summaries(counters.build(occ.join(used, "term", "left_semi"), 128), asked.select("qid", "terms"), 3)


def _multi(dependence: str, pairing: str = "best") -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        asked = _pairs(spark).select("qid", F.array("a", "b").alias("terms"))
        return _ring_atlas(spark, sf).hot_places_multi(asked, R.cells(spark), k=3, dependence=dependence, pairing=pairing)

    run.__name__ = f"hot_places_multi_{dependence}" + ("" if pairing == "best" else "_by_rank")
    return run


for _dep in ("independent", "bound"):
    query()(_multi(_dep))
query()(_multi("independent", "rank"))


@query()
def place_frequency_multi(spark, sf):
    atlas = _ring_atlas(spark, sf)
    asked = _pairs(spark).select("qid", F.array("a", "b").alias("terms"), F.explode(F.array(F.lit(46906), F.lit(49862))).alias("cell"))
    return answers.place_frequency_multi(atlas.candidates, atlas.summary, asked)


_ASKED_PAIRS = "pairs(qid, a, b) AS (VALUES " + ", ".join(f"({k}, '{a}', '{b}')" for k, (a, b) in enumerate(_PAIRS)) + ")"


def _joint_sql(cell: str) -> dict[str, str]:
    x, y = (_decay_sql(f"{m}.center_cell", cell, f"{m}.focus", f"{m}.spread") for m in "xy")
    return {"independent": f"{x} * {y}", "bound": f"least({x}, {y})"}


def _joint_surface(dependence: str) -> None:
    sql = f"""{EVENTS}, {_MODELS}, {_ASKED_PAIRS}, surface AS (SELECT q.qid, g.i AS cell, {_joint_sql("g.i")[dependence]} AS p
  FROM pairs q JOIN models x ON x.term = q.a JOIN models y ON y.term = q.b CROSS JOIN (SELECT i::INTEGER AS i FROM range(64800) t(i)) g)
SELECT qid::BIGINT AS qid, cell, round(p * 1e9, 3) AS p_e9 FROM surface"""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        asked = _pairs(spark).select("qid", F.array("a", "b").alias("terms"))
        p = answers.joint(_lattice_models(spark, sf), asked, R.cells(spark), dependence)
        return p.select("qid", "cell", F.round(F.col("p") * 1e9, 3).alias("p_e9"))

    run.__name__ = f"joint_surface_{dependence}"
    query(sql)(run)


for _dep in ("independent", "bound"):
    _joint_surface(_dep)


@query(
    EVENTS
    + f", {_MODELS}, {_ASKED_PAIRS} "
    + " UNION ALL ".join(
        f"SELECT q.qid::BIGINT AS qid, g.cell, '{k}' AS dependence, round({p} * least(x.total, y.total), 6) AS est FROM pairs q JOIN models x ON x.term = q.a JOIN models y ON y.term = q.b CROSS JOIN (SELECT unnest([46906, 49862])::INTEGER AS cell) g"
        for k, p in _joint_sql("g.cell").items()
    )
)
def place_frequency_multi_lattice(spark, sf):
    """Two terms at two places by the lattice models, independent and at most."""
    models = _lattice_models(spark, sf)
    asked = _pairs(spark).select("qid", F.array("a", "b").alias("terms"), F.explode(F.array(F.lit(46906), F.lit(49862))).alias("cell"))
    each = [answers.place_frequency_multi(models, models, asked, k).select("qid", "cell", F.lit(k).alias("dependence"), F.round("est", 6).alias("est")) for k in ("independent", "bound")]
    return each[0].unionByName(each[1])


@query()
def two_center_surface(spark, sf):
    c = exact.counts(adapters.two_centres(spark, sf))
    grid = R.cells(spark)
    models = multicenter.fit_joint(c, multicenter.distant_centres(c, 2), grid)
    return multicenter.surface(materialize(models, "multi"), grid).where("p >= 0.0001")


@query()
def multicenter_assign(spark, sf):
    c = materialize(exact.counts(adapters.two_centres(spark, sf)), "counts")
    radii = M.fine_radii(n=96)
    return multicenter.assign_refit(c, multicenter.distant_centres(c, 2), methods.tables(spark, radii), radii)


_HIER = f"WITH {_GAZ}, {_ORDERS}, {_COUNTS} "


@query(_HIER + "SELECT g.region, g.nation, c.cell, sum(c.n)::BIGINT AS n FROM counts c JOIN gaz g ON g.cell = c.cell GROUP BY ROLLUP (g.region, g.nation, c.cell)")
def rollup_levels(spark, sf):
    rows = exact.counts(adapters.orders(spark, sf)).join(F.broadcast(adapters.gazetteer(spark, sf)), "cell")
    return rows.rollup("region", "nation", "cell").agg(F.sum("n").alias("n"))


@query(_HIER + "SELECT c.term, g.region, sum(c.n)::BIGINT AS n FROM counts c JOIN gaz g ON g.cell = c.cell GROUP BY CUBE (c.term, g.region)")
def cube_term_level(spark, sf):
    rows = exact.counts(adapters.orders(spark, sf)).join(F.broadcast(adapters.gazetteer(spark, sf)), "cell")
    return rows.cube("term", "region").agg(F.sum("n").alias("n"))


@query(_HIER + "SELECT c.term, g.region, g.nation, sum(c.n)::BIGINT AS n FROM counts c JOIN gaz g ON g.cell = c.cell GROUP BY GROUPING SETS ((c.term, g.region), (g.nation), ())")
def grouping_sets_levels(spark, sf):
    exact.counts(adapters.orders(spark, sf)).join(F.broadcast(adapters.gazetteer(spark, sf)), "cell").createOrReplaceTempView("ta_levels")
    return spark.sql("SELECT term, region, nation, sum(n) AS n FROM ta_levels GROUP BY GROUPING SETS ((term, region), (nation), ())")


@query(EVENTS + "SELECT term, sub_cell::INTEGER AS sub_cell, n / 4::DOUBLE AS est FROM (SELECT term, n, ((cell // 360) * 2 + k // 2) * 720 + (cell % 360) * 2 + k % 2 AS sub_cell FROM ranked, range(4) t(k) WHERE rank <= 3)")
def drill_down(spark, sf):
    top = exact.hot_places(exact.counts(_occ(spark, sf)), 3).select("term", "cell", F.col("n").cast("double").alias("est"))
    return geo.drill_down(top, 2).select("term", "sub_cell", "est")


@query(_HIER + "SELECT c.term, g.nation, sum(c.n)::BIGINT AS n FROM counts c JOIN gaz g ON g.cell = c.cell GROUP BY c.term, g.nation")
def region_frequency(spark, sf):
    """Summaries with room are exact, so sums over a nation's cells are too."""
    return geo.roll_up(exact.counts(adapters.orders(spark, sf)), adapters.gazetteer(spark, sf), "nation", "n")


@query()
def region_frequency_model(spark, sf):
    atlas = _ring_atlas(spark, sf)
    boxes = R.cells(spark).where("lat between 30 and 60 and lon between -20 and 40").select(F.lit("box").alias("region"), "cell")
    return answers.region_frequency(atlas.summary, atlas.models, boxes)


@query(EVENTS + "SELECT i::INTEGER AS cell FROM range(64800) t(i) WHERE i // 360 BETWEEN 120 AND 140 AND NOT EXISTS (SELECT 1 FROM counts c WHERE c.cell = i)")
def absent_cells_anti(spark, sf):
    box = R.cells(spark).where(F.col("row").between(120, 140)).select("cell")
    return box.join(exact.counts(_occ(spark, sf)), "cell", "left_anti")


@query(f"WITH {_DOCS} SELECT cell, count(DISTINCT msg_id) AS messages FROM occ WHERE msg_id IN (SELECT doc_id FROM labels WHERE quality = 1) GROUP BY cell")
def labelled_semi(spark, sf):
    good = read(spark, sf, "labels").where("quality = 1").select(F.col("doc_id").alias("msg_id"))
    return adapters.documents(spark, sf).join(good, "msg_id", "left_semi").groupBy("cell").agg(F.count_distinct("msg_id").alias("messages"))


@query("""WITH e AS (SELECT event_type AS term, epoch_us(ts) AS t, event_id FROM events), m AS (SELECT term, max(t) AS t, arg_max(event_id, (t, event_id)) AS version FROM e GROUP BY term, t // 86400000000)
SELECT e.event_id AS qid, e.term, e.t AS at, arg_max(m.version, m.t) AS version FROM e LEFT JOIN m ON m.term = e.term AND m.t <= e.t GROUP BY e.event_id, e.term, e.t""")
def asof_model(spark, sf):
    """For every event the latest model version of its term by then; a term's model is fitted anew by each day's last event."""
    e = read(spark, sf, "events").select(F.col("event_type").alias("term"), F.unix_micros("ts").alias("t"), "event_id")
    versions = e.groupBy("term", F.floor(F.col("t") / 86_400_000_000)).agg(F.max("t").alias("fitted_at"), F.max_by("event_id", F.struct("t", "event_id")).alias("version"))
    asked = e.select(F.col("event_id").alias("qid"), "term", F.col("t").alias("at"))
    return M.as_of(asked, versions.select("term", "fitted_at", "version")).select("qid", "term", "at", "version")


_TOP_TWO = "tops AS (SELECT term, row_number() OVER (ORDER BY sum(n) DESC, term) AS place FROM counts GROUP BY term), one AS (SELECT term FROM tops WHERE place = 1), two AS (SELECT term FROM tops WHERE place = 2)"


def _top_two(occ: DataFrame) -> list[str]:
    return [r.term for r in occ.groupBy("term").count().orderBy(F.desc("count"), "term").limit(2).collect()]


@query(f"WITH {_DOCS}, {_COUNTS}, {_TOP_TWO} SELECT a.term AS a, b.term AS b, a.cell, a.msg_id AS msg_a, b.msg_id AS msg_b FROM occ a JOIN occ b ON b.cell = a.cell AND b.seq >= a.seq AND b.seq <= a.seq + 3600 WHERE a.term = (FROM one) AND b.term = (FROM two)")
def interval_pairs(spark, sf):
    occ = adapters.documents(spark, sf)
    one, two = _top_two(occ)
    return summaries.co_occurrence(occ.where(F.col("term") == one), occ.where(F.col("term") == two))


@query(f"WITH {_events_sql()}, m AS (SELECT *, CASE WHEN lag(cell) OVER w = cell THEN 0 ELSE 1 END AS fresh FROM occ WINDOW w AS (PARTITION BY term ORDER BY seq, msg_id, cell)), r AS (SELECT *, sum(fresh) OVER (PARTITION BY term ORDER BY seq, msg_id, cell) AS run FROM m) SELECT term, run::BIGINT AS run, cell, min(seq) AS seq, count(*) AS n FROM r GROUP BY term, run, cell")
def run_collapse(spark, sf):
    return counters.collapse_runs(_occ(spark, sf).withColumn("pane", F.lit(0))).select("term", "run", "cell", "seq", "n")


@query(f"WITH {_events_sql()} SELECT msg_id, term, ceil(20 * row_number() OVER (PARTITION BY term ORDER BY seq, msg_id) / count(*) OVER (PARTITION BY term))::BIGINT AS part FROM occ")
def stream_fraction(spark, sf):
    from pyspark.sql import Window

    order = Window.partitionBy("term").orderBy("seq", "msg_id")
    n = F.count("*").over(Window.partitionBy("term"))
    return _occ(spark, sf).select("msg_id", "term", F.ceil(20 * F.row_number().over(order) / n).alias("part"))


@query(f"WITH {_events_sql()} SELECT a.term AS a, b.term AS b, a.cell, a.msg_id AS msg_a, b.msg_id AS msg_b FROM occ a JOIN occ b ON b.cell = a.cell AND b.seq >= a.seq AND b.seq <= a.seq + 3600000000 WHERE a.msg_id < b.msg_id")
def interval_pairs_all(spark, sf):
    occ = materialize(_occ(spark, sf), "occ")
    return summaries.co_occurrence(occ, occ).where("msg_a < msg_b")


@query()
def replacement_curve(spark, sf):
    return metrics.replacement_curve(R.snapshots(_occ(spark, sf), 50))


_DAY = "epoch_us(date_trunc('day', make_timestamp(seq)))"


@query(f"WITH {_events_sql()} SELECT {_DAY} AS window_start, term, cell, count(*) AS n FROM occ GROUP BY ALL")
def tumbling_counts(spark, sf):
    return summaries.tumbling_counts(_occ(spark, sf)).withColumn("window_start", F.unix_micros("window_start"))


@query(f"WITH {_events_sql()} SELECT {_DAY} - k * 86400000000 AS window_start, term, count(*) AS n FROM occ, range(7) t(k) GROUP BY ALL")
def sliding_counts(spark, sf):
    return summaries.sliding_counts(_occ(spark, sf)).withColumn("window_start", F.unix_micros("window_start"))


@query(f"WITH {_events_sql()}, m AS (SELECT *, CASE WHEN seq - lag(seq) OVER (PARTITION BY term ORDER BY seq, msg_id) < 600000000 THEN 0 ELSE 1 END AS fresh FROM occ), r AS (SELECT *, sum(fresh) OVER (PARTITION BY term ORDER BY seq, msg_id) AS run FROM m) SELECT term, min(seq) AS started, max(seq) + 600000000 AS ended, count(*) AS n FROM r GROUP BY term, run")
def session_bursts(spark, sf):
    return summaries.session_bursts(_occ(spark, sf)).select("term", F.unix_micros("started").alias("started"), F.unix_micros("ended").alias("ended"), "n")


@query()
def merged_panes(spark, sf):
    """Summaries of eight panes a term, merged."""
    return counters.exploded(counters.build(_occ(spark, sf), 50, panes=8)).select("term", "rank", "cell", "f", "err")


@query(EVENTS + "SELECT term, cell, n AS f, 0::BIGINT AS err FROM counts")
def merged_panes_roomy(spark, sf):
    """Panes with room for every place merge to the counts."""
    return counters.exploded(counters.build(_occ(spark, sf), 4096, panes=8)).select("term", "cell", "f", "err")


@query(f"""WITH {_events_sql("(epoch_us(e.ts) - epoch_us(TIMESTAMP '2024-01-01')) // 259200000000 * 1000000")},
w AS (SELECT {_DAY} - k * 86400000000 AS window_start, term, cell, count(*) AS f FROM occ, range(7) t(k) GROUP BY ALL)
SELECT window_start, term, arg_max(cell, (f, -cell)) AS cell, max(f) AS f FROM w GROUP BY window_start, term""")
def windowed_summaries(spark, sf):
    """The hottest place of each week's window, by daily summaries with room for every place."""
    return workloads.moving(spark, sf, capacity=1024).withColumn("window_start", F.unix_micros("window_start"))


@query()
def merged_ring_panes(spark, sf):
    """Ring summaries of eight panes a term, merged: bands are scaled by the arrivals their panes saw."""
    return _rings_out(R.build(_occ(spark, sf), 50, panes=8))


@query()
def spark_sketch(spark, sf):
    """Spark's count-min sketch of each term's places, in bytes."""
    return answers.spark_sketch(_occ(spark, sf)).select("term", F.length("sketch").alias("bytes"))


@query()
def single_cell_fit(spark, sf):
    """The fit on every single cell of the map beside the one on narrow bands of cells, and their gap."""
    occ = materialize(_occ(spark, sf), "occ")
    counts = materialize(exact.counts(occ), "counts")
    top, fine = M.top_cells(counts, 1), M.fine_radii()
    one = M.fit(M.single_cell_rows(counts, top, R.cells(spark)), source="single_cells")
    narrow = M.fit(M.cell_rows(counts, top, methods.tables(spark, fine), fine), source="cells").select("term", F.col("focus").alias("f0"), F.col("spread").alias("s0"), F.col("n_eval").alias("n_eval_bands"))
    gap = lambda a, b: (F.abs(F.col(a) - F.col(b)) / F.col(a))
    return one.join(narrow, "term").select("term", "center_cell", "focus", "spread", gap("focus", "f0").alias("focus_gap"), gap("spread", "s0").alias("spread_gap"), "n_eval", "n_eval_bands")


@query()
def spark_top_k(spark, sf):
    return answers.spark_top_k(_occ(spark, sf))


#: Streams of the experiments: all terms of the events, of the drifting events, of line items, and 1000 draws from the messages' terms.
def _events_bench(spark: SparkSession, sf: str) -> workloads.Bench:
    return workloads.Bench(_occ(spark, sf))


def _drifting_bench(spark: SparkSession, sf: str) -> workloads.Bench:
    return workloads.Bench(adapters.drifting(spark, sf))


def _lineitem_bench(spark: SparkSession, sf: str) -> workloads.Bench:
    return workloads.Bench(adapters.lineitem(spark, sf))


def _messages_bench(spark: SparkSession, sf: str) -> workloads.Bench:
    docs = materialize(adapters.gathered_documents(spark, sf), "docs")
    drawn = materialize(workloads.sampled_terms(docs, n=1000), "terms")
    occ = docs.select("seq", "ts", "msg_id", "cell", F.explode("terms").alias("term"))
    # as many terms as there are draws at most
    return workloads.Bench(occ.join(F.broadcast(drawn.select("term")), "term", "left_semi"), times=drawn, messages=docs)


def _workload(name: str, bench: Callable[[SparkSession, str], workloads.Bench], run: Callable[[workloads.Bench], DataFrame], sql: str | None = None) -> None:
    def q(spark: SparkSession, sf: str) -> DataFrame:
        return run(bench(spark, sf))

    q.__name__ = name
    query(sql)(q)


def _recall_sql(occ: str, settings: tuple[tuple[float, int], ...] = ((0.02, 50), (0.05, 20), (0.1, 10))) -> str:
    """With 1 / eps counters no eps-frequent place is missed, so the hits are all that exact counts want."""
    parts = " UNION ALL ".join(f"SELECT {e}::DOUBLE AS eps, {m} AS counters, CASE WHEN count(*) > 0 THEN count(*) END AS hits, count(*) AS wanted, CASE WHEN count(*) > 0 THEN 1.0::DOUBLE END AS recall FROM counts JOIN totals USING (term) WHERE n >= {e} * total" for e, m in settings)
    return f"WITH {occ}, {_COUNTS}, {_TOTALS} {parts}"


#: The messages have 80 places, so a budget of 81 words (27 counters, or 6 with ten bands) is what evicts any.
WORDS_FEW, FEW, FEW_CELLS = 81, 6, 27
_workload("ratio_sweep", _events_bench, workloads.ratio_sweep)
_workload("equal_space_table", _events_bench, workloads.equal_space)
_workload("frequent_recall", _events_bench, workloads.frequent_recall, _recall_sql(_events_sql()))
_workload("accuracy_frequency", _events_bench, workloads.frequency_accuracy)
_workload("policy_table", _events_bench, workloads.policy_table)
_workload("run_times", _events_bench, workloads.run_times)
_workload("replacements", _events_bench, workloads.replacements)
_workload("stability", _events_bench, workloads.stability)
_workload("maps", _events_bench, workloads.maps)
_workload("ratio_sweep_documents", _messages_bench, lambda b: workloads.ratio_sweep(b, FEW))
_workload("equal_space_documents", _messages_bench, lambda b: workloads.equal_space(b, words=WORDS_FEW))
_workload("accuracy_documents", _messages_bench, lambda b: workloads.frequency_accuracy(b, FEW, FEW_CELLS))
_workload("policy_table_documents", _messages_bench, lambda b: workloads.policy_table(b, FEW))
_workload("run_times_documents", _messages_bench, lambda b: workloads.run_times(b, FEW, FEW_CELLS))
_workload("replacements_documents", _messages_bench, lambda b: workloads.replacements(b, FEW))
_workload("stability_documents", _messages_bench, lambda b: workloads.stability(b, FEW))
_workload("policy_table_drifting", _drifting_bench, workloads.policy_table)
_workload("replacements_drifting", _drifting_bench, workloads.replacements)
_workload("frequent_recall_lineitem", _lineitem_bench, workloads.frequent_recall, _recall_sql(_LINEITEM))
_workload("frequent_recall_documents", lambda spark, sf: workloads.Bench(adapters.documents(spark, sf)), workloads.frequent_recall, _recall_sql(_DOCS))
_workload("run_times_lineitem", _lineitem_bench, workloads.run_times)


@query()
def multi_term_accuracy(spark, sf):
    return workloads.multi_term(adapters.documents(spark, sf), FEW, FEW_CELLS)


@query()
def several_centres(spark, sf):
    return workloads.several_centres(spark, sf)


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Hot places and asked place frequencies of every event type by the ring model."""
    atlas = _ring_atlas(spark, sf)
    hot = atlas.hot_places(5).select("term", "cell", F.col("est").cast("double").alias("est"), F.lit("hot_place").alias("how"))
    return hot.unionByName(atlas.place_frequency(_asked(exact.counts(_occ(spark, sf)))).select("term", "cell", "est", "how"))


# --- relational surroundings ------------------------------------------------------------------------


@query(_replay(10) + "SELECT coalesce(s.term, c.term) AS term, coalesce(s.cell, c.cell) AS cell, s.f, c.n FROM (SELECT * FROM summary) s FULL OUTER JOIN counts c ON c.term = s.term AND c.cell = s.cell")
def summary_vs_truth_outer(spark, sf):
    """Every stored or counted place, with both numbers where both exist."""
    occ = _occ(spark, sf)
    return M.counts_of(counters.build(occ, 10)).withColumnRenamed("n", "f").join(exact.counts(occ), ["term", "cell"], "full_outer").select("term", "cell", "f", "n")


@query(f"WITH {_DOCS}, {_COUNTS}, {_TOP_TWO} SELECT cell FROM (SELECT cell FROM counts WHERE term = (FROM one) INTERSECT SELECT cell FROM counts WHERE term = (FROM two))")
def shared_cells_intersect(spark, sf):
    c = materialize(exact.counts(adapters.documents(spark, sf)), "counts")
    one, two = [r.term for r in c.groupBy("term").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "term").limit(2).collect()]
    return c.where(F.col("term") == one).select("cell").intersect(c.where(F.col("term") == two).select("cell"))


@query(EVENTS + "SELECT cell FROM counts WHERE term = 'error' EXCEPT ALL SELECT cell FROM counts WHERE term <> 'error'")
def own_cells_except(spark, sf):
    c = exact.counts(_occ(spark, sf))
    return c.where("term = 'error'").select("cell").exceptAll(c.where("term <> 'error'").select("cell"))


@query(EVENTS + "SELECT term, (ntile(4) OVER (PARTITION BY term ORDER BY n, cell))::INTEGER AS quarter, cell, n, rank() OVER (PARTITION BY term ORDER BY n DESC)::INTEGER AS rank, dense_rank() OVER (PARTITION BY term ORDER BY n DESC)::INTEGER AS dense FROM counts")
def place_ranks(spark, sf):
    from pyspark.sql import Window

    w = Window.partitionBy("term")
    down = w.orderBy(F.desc("n"))
    return exact.counts(_occ(spark, sf)).select("term", F.ntile(4).over(w.orderBy("n", "cell")).alias("quarter"), "cell", "n", F.rank().over(down).alias("rank"), F.dense_rank().over(down).alias("dense"))


@query(EVENTS + "SELECT cell, sum(CASE WHEN term = 'click' THEN n END)::BIGINT AS click, sum(CASE WHEN term = 'error' THEN n END)::BIGINT AS error, sum(CASE WHEN term = 'view' THEN n END)::BIGINT AS view FROM counts WHERE term IN ('click', 'error', 'view') GROUP BY cell")
def term_pivot(spark, sf):
    c = exact.counts(_occ(spark, sf)).where(F.col("term").isin("click", "error", "view"))
    return c.groupBy("cell").pivot("term", ["click", "error", "view"]).agg(F.sum("n"))


@query(f"WITH {_events_sql()} SELECT msg_id, term, count(*) OVER (PARTITION BY term ORDER BY seq RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour FROM occ")
def hourly_range_frame(spark, sf):
    from pyspark.sql import Window

    w = Window.partitionBy("term").orderBy("seq").rangeBetween(-3_600_000_000, Window.currentRow)
    return _occ(spark, sf).select("msg_id", "term", F.count("*").over(w).alias("last_hour"))


@query(f"WITH {_DOCS} SELECT cell, count(DISTINCT msg_id) AS messages FROM occ WHERE msg_id NOT IN (SELECT d.doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM benchmark b WHERE contains(d.text, b.text))) GROUP BY cell")
def uncontaminated_anti(spark, sf):
    """Messages without a passage of the benchmark."""
    hit = workloads.holding(read(spark, sf, "documents"), read(spark, sf, "benchmark")).select(F.col("doc_id").alias("msg_id"))
    return adapters.documents(spark, sf).join(hit, "msg_id", "left_anti").groupBy("cell").agg(F.count_distinct("msg_id").alias("messages"))


@query(EVENTS + "SELECT c.term, c.cell, c.n FROM counts c WHERE c.n > (SELECT avg(d.n) FROM counts d WHERE d.term = c.term) AND NOT EXISTS (SELECT 1 FROM counts o WHERE o.cell = c.cell AND o.term <> c.term)")
def sql_own_hot_cells(spark, sf):
    """SQL over the views: places above their term's mean that no other term has."""
    answers.register(spark, counts=exact.counts(_occ(spark, sf)))
    return spark.sql("SELECT c.term, c.cell, c.n FROM counts c WHERE c.n > (SELECT avg(d.n) FROM counts d WHERE d.term = c.term) AND NOT EXISTS (SELECT 1 FROM counts o WHERE o.cell = c.cell AND o.term <> c.term)")


@query(f"WITH {_events_sql()} SELECT term, cell, count(*) AS n FROM occ GROUP BY term, cell")
def sql_cell_function(spark, sf):
    """Cells by the SQL function, inlined into the plan."""
    answers.register(spark, occ=_occ(spark, sf))
    return spark.sql("SELECT term, cell_id(lon_e6, lat_e6) AS cell, count(*) AS n FROM occ GROUP BY 1, 2")


@query(EVENTS + f"SELECT term, cell, round(p, 9) AS p FROM (SELECT r.term, i::INTEGER AS cell, {_decay_sql('r.cell', 'i', '0.09', '3.2')} AS p FROM ranked r, range(64800) t(i) WHERE r.rank = 1) WHERE p >= 0.0001")
def sql_surface(spark, sf):
    """The table function for each term's hottest cell."""
    from termatlas.functions import sql

    sql.register(spark)
    answers.register(spark, ta_tops=exact.hot_places(exact.counts(_occ(spark, sf)), 1))
    return spark.sql("SELECT t.term, s.cell, round(s.p, 9) AS p FROM ta_tops t, LATERAL surface(t.cell, 0.09D, 3.2D, 0.0001D) s")


@query(EVENTS + "SELECT term, least(50, count(*)) * 13 AS words, least(50, count(*)) * 13 * 8 AS bytes FROM counts GROUP BY term")
def state_space(spark, sf):
    """Words and bytes of ring summaries of 50 counters and 10 bands."""
    return metrics.state_space(R.build(_occ(spark, sf), 50))


@query()
def likelihood_terms(spark, sf):
    """Likelihood terms of a fit on bands and on cells: the cost that doesn't depend on hardware."""
    occ = materialize(_occ(spark, sf), "occ")
    ring, fine = R.edges(), M.fine_radii()
    s = materialize(R.build(occ, 50, ring), "summary")
    rows = M.fit(M.ring_rows(s, methods.tables(spark, ring), ring, 1)).unionByName(M.fit(M.cell_rows(M.counts_of(s), M.centres_of(s, 1), methods.tables(spark, fine), fine), source="cells"))
    # a fit on single cells would take every cell of the map at each evaluation
    return metrics.evaluations(rows).withColumn("cells_of_the_map", F.lit(geo.rows() * geo.columns()))


# --- the experiments where the decay law is true ---------------------------------------------------


def _power_law(name: str, run: Callable[[workloads.Bench], DataFrame]) -> None:
    def q(spark: SparkSession, sf: str) -> DataFrame:
        return run(workloads.Bench(adapters.power_law(spark)))

    q.__name__ = f"power_law_{name}"
    query()(q)


_power_law("multi_term", lambda b: workloads.multi_term(b.occ, capacity=50, cell_capacity=216, share=0.0, per_bin=100))
_power_law("accuracy", lambda b: workloads.frequency_accuracy(b, terms=60))
_power_law("equal_space", workloads.equal_space)
_power_law("policies", workloads.policy_table)
_power_law("ratio_sweep", lambda b: workloads.ratio_sweep(b))
_power_law("stability", workloads.stability)


# --- streams ------------------------------------------------------------------------------------------


@query(_replay(10) + "SELECT term, cell, f, err FROM summary")
def stream_counters(spark, sf):
    """Counters kept by a stateful stream over the table's files, as its sink holds them at the end: those of the replay in order."""
    import uuid

    from termatlas.functions.scratch import shared_dir
    from termatlas.sources import sinks, tables

    key, store = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    was = spark.conf.get(key, None)
    place = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    spark.conf.set(key, store)
    try:
        occ = adapters.located_events(tables.stream(spark, f"{sf}/events.parque[t]", "events", 100))
        summaries.start(occ, f"{place}/out", f"{place}/checkpoint", capacity=10, policy="reset", watermark="100 days").awaitTermination()
    finally:
        spark.conf.set(key, was) if was else spark.conf.unset(key)
    return counters.exploded(sinks.latest(spark, f"{place}/out")).select("term", "cell", "f", "err")
