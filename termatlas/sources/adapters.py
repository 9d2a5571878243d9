"""Streams of (term, location) on the given tables: seq, ts, msg_id, term, lon_e6, lat_e6, cell.

None of the tables has coordinates; each adapter derives them by integer arithmetic, alike
in Spark and in SQL. Plans are projections with joins of small dimensions, so time ranges and
filters on terms reach the scan.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from termatlas.functions import geo, text
from termatlas.sources.tables import read

#: event type -> longitude, latitude, scale of its spread
ANCHORS = {"click": (-74, 40, 40), "view": (2, 48, 80), "purchase": (139, 35, 20), "signup": (-46, -23, 60), "error": (18, -33, 120)}
#: k of 0..99 -> thousandths of cosine and sine
BEARINGS = [(round(1000 * math.cos(2 * math.pi * k / 100)), round(1000 * math.sin(2 * math.pi * k / 100))) for k in range(100)]
LANGUAGES = {"en": (-100, 38), "fr": (2, 46), "de": (10, 51), "es": (-4, 40)}
OCC = ("seq", "ts", "msg_id", "term", "lon_e6", "lat_e6", "cell")


def _pick(key: Column, table: dict, part: int) -> Column:
    return F.coalesce(*(F.when(key == k, F.lit(v[part])) for k, v in table.items()))


def _located(df: DataFrame, *keep: str) -> DataFrame:
    return df.withColumn("cell", geo.cell_id("lon_e6", "lat_e6")).select(*OCC, *keep)


def _offset(value: Column, step: Column, scale: Column) -> Column:
    """floor(cents * step * scale / 100), in micro-degrees; shifted so that no side divides below zero."""
    shift = 10**12
    return F.floor((F.round(value * 100).cast("long") * step * scale + F.lit(shift * 100)).cast("decimal(38,0)") / 100).cast("long") - F.lit(shift)


def located_events(events: DataFrame, drift: bool = False) -> DataFrame:
    """A1; with drift A7: longitudes move east by a degree every three days."""
    kind = F.col("event_type")
    # a projection of its own, so that each event's JSON is parsed once
    events = events.withColumn("_k", F.get_json_object("props", "$.k").cast("int"))
    k = F.col("_k")
    at = k.isNotNull() & k.between(0, 99)
    step = [F.element_at(F.array(*(F.lit(b[i]) for b in BEARINGS)), F.when(at, k + 1)) for i in (0, 1)]
    scale = _pick(kind, ANCHORS, 2)
    lon, lat = (_pick(kind, ANCHORS, i).cast("long") * 1_000_000 + 500_000 + _offset(F.col("value"), step[i].cast("long"), scale.cast("long")) for i in (0, 1))
    if drift:
        lon = lon + F.floor((F.unix_micros("ts") - F.unix_micros(F.lit("2024-01-01 00:00:00").cast("timestamp"))) / F.lit(3 * 86_400_000_000)).cast("long") * 1_000_000
    rows = events.select(F.unix_micros("ts").alias("seq"), "ts", F.col("event_id").alias("msg_id"), kind.alias("term"), lon.alias("lon_e6"), lat.alias("lat_e6"))
    return _located(rows)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return located_events(read(spark, sf_dir, "events"))


def drifting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return located_events(read(spark, sf_dir, "events"), drift=True)


def two_centres(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A1's click and view under one term, mix."""
    return events(spark, sf_dir).where(F.col("term").isin("click", "view")).withColumn("term", F.lit("mix"))


def _language_place(lang: Column, number: Column) -> tuple[Column, Column]:
    lon = (_pick(lang, LANGUAGES, 0).cast("long") + F.pmod(number, F.lit(5)) - 2) * 1_000_000 + 500_000
    lat = (_pick(lang, LANGUAGES, 1).cast("long") + F.floor(number / 5).cast("long") - 2) * 1_000_000 + 500_000
    return lon, lat


def located_messages(docs: DataFrame) -> DataFrame:
    """Documents as messages at a place of their language and source: seq, ts, msg_id, text, lon_e6, lat_e6."""
    number = F.pmod(F.coalesce(F.regexp_extract("source", r"(\d+)$", 1).try_cast("int"), F.lit(0)), F.lit(20))
    lon, lat = _language_place(F.col("lang"), number)
    return docs.select(F.col("doc_id").alias("seq"), F.timestamp_seconds("doc_id").alias("ts"), F.col("doc_id").alias("msg_id"), "text", lon.alias("lon_e6"), lat.alias("lat_e6"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A2: the distinct terms of each document."""
    rows = located_messages(read(spark, sf_dir, "documents")).withColumn("term", F.explode(text.distinct_terms("text")))
    return _located(rows)


def gathered_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A2 with a row for each document: seq, ts, msg_id, cell, terms, n_terms; exploded, they are the arrivals of `documents`."""
    rows = located_messages(read(spark, sf_dir, "documents"))
    rows = rows.select("seq", "ts", "msg_id", geo.cell_id("lon_e6", "lat_e6").alias("cell"), text.distinct_terms("text").alias("terms"))
    return rows.withColumn("n_terms", F.size("terms"))


def gazetteer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """cell, nation, region: nine cells of each nation in a block of its region."""
    n, r = read(spark, sf_dir, "nation"), read(spark, sf_dir, "region")
    rows = n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(8))))
    lon, lat = _nation_place(F.col("n_nationkey"), F.col("n_regionkey"), F.col("k"))
    return rows.select(geo.cell_id(lon, lat).alias("cell"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))


def _nation_place(nation: Column, region: Column, k: Column) -> tuple[Column, Column]:
    lon = (region.cast("long") * 60 - 150 + F.pmod(nation, F.lit(5)) * 3 + F.pmod(k, F.lit(3))) * 1_000_000 + 500_000
    lat = (region.cast("long") * 10 - 20 + F.floor(nation / 5).cast("long") * 3 + F.floor(k / 3).cast("long")) * 1_000_000 + 500_000
    return lon, lat


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A3: priority and segment of each order at its customer's place; with nation and region."""
    o, c, n = (read(spark, sf_dir, t) for t in ("orders", "customer", "nation"))
    rows = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    lon, lat = _nation_place(F.col("c_nationkey"), F.col("n_regionkey"), F.pmod("c_custkey", F.lit(9)))
    rows = rows.select(F.col("o_orderkey").alias("seq"), F.col("o_orderdate").alias("ts"), F.col("o_orderkey").alias("msg_id"), F.explode(F.array("o_orderpriority", "c_mktsegment")).alias("term"), lon.alias("lon_e6"), lat.alias("lat_e6"))
    return _located(rows)


def lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A4: words of the part's name, type and brand at the supplier's place."""
    i, p, s, n = (read(spark, sf_dir, t) for t in ("lineitem", "part", "supplier", "nation"))
    rows = i.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate").join(p.select("p_partkey", "p_name", "p_type", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    rows = rows.join(s.select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey"))
    lon, lat = _nation_place(F.col("s_nationkey"), F.col("n_regionkey"), F.pmod("s_suppkey", F.lit(9)))
    words = F.array_distinct(F.concat(F.split(F.lower(F.concat_ws(" ", "p_name", "p_type")), " "), F.array(F.lower("p_brand"))))
    number = F.col("l_orderkey") * 8 + F.col("l_linenumber")
    return _located(rows.select(number.alias("seq"), F.col("l_shipdate").alias("ts"), number.alias("msg_id"), F.explode(words).alias("term"), lon.alias("lon_e6"), lat.alias("lat_e6")))


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A5: terms of turns at an arbitrary place of their conversation."""
    c = read(spark, sf_dir, "conversations")
    number = F.col("conv_id") * 1000 + F.col("turn")
    lon, lat = (F.pmod(F.col("conv_id") * 37, F.lit(360)) - 180) * 1_000_000 + 500_000, (30 + F.pmod(F.col("conv_id") * 11, F.lit(120)) - 90) * 1_000_000 + 500_000
    return _located(c.select(number.alias("seq"), F.timestamp_seconds(number).alias("ts"), number.alias("msg_id"), F.explode(text.distinct_terms("text")).alias("term"), lon.alias("lon_e6"), lat.alias("lat_e6")))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A6: terms of web pages at a place of their language."""
    p = read(spark, sf_dir, "pages")
    lang = F.regexp_extract("html", 'lang="([a-z]{2})"', 1)
    lon, lat = _language_place(lang, F.pmod("page_id", F.lit(20)))
    return _located(p.select(F.col("page_id").alias("seq"), F.timestamp_seconds("page_id").alias("ts"), F.col("page_id").alias("msg_id"), F.explode(text.distinct_terms(text.strip_markup("html"))).alias("term"), lon.alias("lon_e6"), lat.alias("lat_e6")))


def power_law(spark: SparkSession, terms: int = 60, arrivals: int = 1500, places: int = 12, seed: int = 42) -> DataFrame:
    """A generated stream in which the decay law is true: term i has a spread between 1.6 and 3.6 around one of `places` centres.

    A distance's density is d ** (1 - spread) between half a cell and 90 cells, by inverse
    transform; bearings are uniform. Terms of a place are a few cells apart, so pairs co-occur
    near it. Some terms are several times more frequent. Everything is a hash of numbers.
    """

    def uniform(*of: Column) -> Column:
        return (F.pmod(F.xxhash64(*of, F.lit(seed)), F.lit(1 << 40)) + 0.5) / float(1 << 40)

    t = F.col("t")
    rows = spark.range(terms).select(F.col("id").cast("int").alias("t")).withColumn("k", F.explode(F.sequence(F.lit(0), (F.lit(arrivals) * (1 + 3 * F.pmod(t, F.lit(4)))).cast("int") - 1)))
    place = F.pmod(t, F.lit(places))
    spread = 1.6 + 2.0 * uniform(t, F.lit("spread"))
    step = 2.0 - spread
    step = F.when(F.abs(step) < 1e-3, F.lit(1e-3)).otherwise(step)
    lo, hi = F.pow(F.lit(0.5), step), F.pow(F.lit(90.0), step)
    d = F.pow(lo + uniform(t, F.col("k"), F.lit("d")) * (hi - lo), 1 / step)
    turn = uniform(t, F.col("k"), F.lit("turn")) * (2 * math.pi)
    lat0 = F.pmod(place * 17, F.lit(50)) - 25 + F.floor(uniform(t, F.lit("lat")) * 5) + 0.5
    lon0 = place * 29 - 175 + F.floor(uniform(t, F.lit("lon")) * 5) + 0.5
    lat = F.greatest(F.lit(-89.5), F.least(lat0 + d * F.sin(turn), F.lit(89.5)))
    lon = lon0 + d * F.cos(turn) / F.greatest(F.cos(F.radians(lat)), F.lit(0.05))
    seq = F.pmod(F.xxhash64("t", "k", F.lit(seed + 1)), F.lit(1 << 45))
    out = rows.select(seq.alias("seq"), F.timestamp_micros(seq).alias("ts"), seq.alias("msg_id"), F.concat(F.lit("t"), t.cast("string")).alias("term"), F.floor(lon * 1e6).cast("long").alias("lon_e6"), F.floor(lat * 1e6).cast("long").alias("lat_e6"))
    return _located(out)
