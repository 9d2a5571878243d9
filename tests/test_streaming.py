import shutil

from pyspark.sql import functions as F

from termatlas.operators import counters
from termatlas.operators import rings as R
from termatlas.sources import adapters, sinks, tables
from termatlas.streaming import summaries


def parts(spark, sf, folder, n=4):
    events = spark.read.parquet(f"{sf}/events.parquet")
    for k in range(n):
        events.where(f"event_id % {n} = {k}").coalesce(1).write.parquet(f"{folder}/part{k}.tmp")
    return events


def test_a_stream_in_order_equals_the_batch_and_survives_a_restart(spark, sf, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    src = tmp_path / "in"
    src.mkdir()
    events = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts", "event_id")
    rows = events.toPandas()
    cuts = [0, len(rows) // 2, len(rows)]

    def put(k):
        events.where(F.col("event_id").isin(rows.event_id[cuts[k] : cuts[k + 1]].tolist())).coalesce(1).write.parquet(str(tmp_path / f"w{k}"))
        for f in (tmp_path / f"w{k}").glob("*.parquet"):
            shutil.copy(f, src / f"{k}.parquet")

    for k in range(2):
        put(k)
        occ = adapters.located_events(tables.stream(spark, str(src), "events", 10))
        q = summaries.start(occ, str(tmp_path / "out"), str(tmp_path / "ck"), capacity=10, watermark="100 days")
        q.awaitTermination()
    got = {r.term: {(c.cell, c.f, c.err) for c in r.centers} for r in sinks.latest(spark, str(tmp_path / "out")).collect()}
    want = {r.term: {(c.cell, c.f, c.err) for c in r.centers} for r in R.build(adapters.events(spark, sf), 10).collect()}
    assert got == want


def test_repeated_messages_count_once(spark, sf, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    src = str(tmp_path / "in")
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.unionByName(events).coalesce(1).write.parquet(src)
    occ = adapters.located_events(tables.stream(spark, src, "events", 10))
    summaries.start(occ, str(tmp_path / "out"), str(tmp_path / "ck"), capacity=10, watermark="100 days").awaitTermination()
    totals = {r.term: r.total for r in sinks.latest(spark, str(tmp_path / "out")).collect()}
    assert totals == {r.term: r.total for r in counters.build(adapters.events(spark, sf), 10).collect()}


def test_sinks(spark, sf, tmp_path):
    s = counters.build(adapters.events(spark, sf), 5)
    sinks.write_by_bucket(s, str(tmp_path / "b"), 4)
    assert spark.read.parquet(str(tmp_path / "b")).count() == 5
    maps = sinks.map_features(counters.exploded(s).select("term", "cell", F.col("f").cast("double").alias("est")))
    assert maps.count() == 25 and '"Point"' in maps.first().feature


def test_pairs_within_hours_meet_by_slices_of_time(spark):
    import random

    from termatlas.streaming import summaries

    rng, hour = random.Random(7), 3600
    edges = [k * hour + d for k in range(-2, 3) for d in (-1, 0, 1)]  # on both sides of the slices' borders
    rows = [(i, rng.choice("xy"), rng.randrange(3), t) for i, t in enumerate(edges * 2 + [rng.randrange(-9 * hour, 9 * hour) for _ in range(120)])]
    occ = spark.createDataFrame(rows, "msg_id long, term string, cell int, at long").withColumn("ts", F.timestamp_seconds("at"))
    for hours in (1, 2):
        got = summaries.co_occurrence(occ, occ, hours)
        want = sorted((a[0], b[0]) for a in rows for b in rows if a[2] == b[2] and a[3] <= b[3] <= a[3] + hours * hour)
        assert sorted((r.msg_a, r.msg_b) for r in got.collect()) == want
        keys = got._jdf.queryExecution().executedPlan().toString()
        assert "slice" in keys
