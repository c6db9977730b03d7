import datetime as dt

import pytest
from pyspark.sql import functions as F

from simcluster.functions import geom as G
from simcluster.functions import sqlfuncs
from simcluster.functions import text as X
from simcluster.operators import relational as R
from simcluster.operators.grid import Grid, candidate_pairs, grid_granularity
from simcluster.sources import tables
from simcluster.streaming import assign


def test_files_round_trip(spark, d2, tmp_path):
    shapes = d2.sources.select(F.col("sid").alias("id"), "geom")
    tables.write_wkt_csv(shapes, f"{tmp_path}/wkt")
    tables.write_geojson(shapes, f"{tmp_path}/geojson")
    want = {r["id"]: r["a"] for r in shapes.select("id", G.area(F.col("geom")).alias("a")).collect()}
    for back in (tables.read_wkt_csv(spark, f"{tmp_path}/wkt"), tables.read_geojson(spark, f"{tmp_path}/geojson")):
        assert {r["id"]: r["a"] for r in back.select("id", G.area(F.col("geom")).alias("a")).collect()} == pytest.approx(want)
    tables.write_results(d2.clusters.withColumn("part", F.col("cid") % 3), f"{tmp_path}/out", ("part",))
    assert spark.read.parquet(f"{tmp_path}/out").count() == 454


def test_null_and_odd_text(spark):
    rows = spark.createDataFrame([(None,), ("",), ("CIRCLE (1 2)",)], "t string").select(X.from_wkt(F.col("t")).alias("g"), X.from_geojson(F.col("t")).alias("h"))
    assert all(r["g"] is None and r["h"] is None for r in rows.collect())


def test_range_and_interval_joins(spark):
    a = spark.createDataFrame([(1, 0.0, 2.0), (2, 5.0, 5.0), (3, -3.0, 9.0)], "a long, lo double, hi double")
    b = spark.createDataFrame([(7, 2.0, 3.0), (8, 5.0, 6.0)], "b long, lo double, hi double")
    assert sorted((r["a"], r["b"]) for r in R.range_join(a, b, 1.5).collect()) == [(1, 7), (2, 8), (3, 7), (3, 8)]


def test_interval_query_joins_every_order(spark, sf_dir):
    from simcluster.plans.queries import QUERIES

    events = [(r["event_id"], r["ts"]) for r in spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("ts")).collect()]
    base, hour = 1_704_067_200_000_000, 3_600_000_000
    starts = [(r["o_orderkey"], base + r["o_orderkey"] % 720 * hour) for r in spark.read.parquet(f"{sf_dir}/orders.parquet").collect()]
    want = sorted((e, k) for e, t in events for k, s in starts if s <= t < s + 5 * hour)
    assert sorted(tuple(r) for r in QUERIES["interval_events"](spark, sf_dir).collect()) == want and any(k % 50 for _, k in want)


def test_asof_join(spark):
    t = lambda m: dt.datetime(2024, 1, 1, 0, m)
    left = spark.createDataFrame([(1, "u", t(5)), (2, "u", t(1)), (3, "v", t(9))], "id long, k string, ts timestamp")
    right = spark.createDataFrame([("u", t(2), 20.0), ("u", t(5), 50.0), ("w", t(0), 1.0)], "k string, ts timestamp, v double")
    assert {r["id"]: r["v"] for r in R.asof_join(left, right, "ts", "k", "v").collect()} == {1: 50.0, 2: None, 3: None}


def test_rollups_and_sets(spark):
    rows = spark.createDataFrame([("a", "x", 1.0), ("a", "y", 3.0), ("b", "x", 5.0)], "p string, q string, si double")
    assert [R.rollup_result(rows, ("p", "q"), m).count() for m in ("rollup", "cube", "sets")] == [6, 8, 5]
    out = R.compare_results(rows.select("p"), rows.filter("q = 'x'").select("p"), multiset=True)
    assert out["only_a"].count() == 1 and out["both"].count() == 2
    assert R.top_k_per(rows, "p", 1, F.desc("si")).count() == 2


def test_sql_functions(spark):
    sqlfuncs.register(spark)
    row = spark.sql("SELECT sc_area(array(0d, 2d, 2d, 0d), array(0d, 0d, 2d, 2d)) AS a, sc_intersection(array(0d, 2d, 2d, 0d), array(0d, 0d, 2d, 2d), array(1d, 3d, 3d, 1d), array(1d, 1d, 3d, 3d)) AS i, size(sc_fourier(array(0d, 2d, 2d), array(0d, 0d, 2d))) AS f").head()
    assert row["a"] == 4 and abs(row["i"] - 1) < 1e-9 and row["f"] == 8
    assert spark.sql("SELECT * FROM sc_tiles(0.5D, 0.5D, 2.5D, 1.5D, 1.0D, 1.0D)").count() == 6
    assert spark.sql("SELECT sc_si(v) AS m FROM VALUES (1.0D), (0.5D) t(v)").head()["m"] == 0.75


@pytest.fixture
def event_folder(spark, sf_dir, tmp_path):
    events = spark.read.parquet(f"{sf_dir}/events.parquet").orderBy("ts").coalesce(1)
    rows = events.collect()
    for i in range(3):
        part = spark.createDataFrame(rows[i * len(rows) // 3 : (i + 1) * len(rows) // 3], events.schema)
        part.coalesce(1).write.mode("append").parquet(f"{tmp_path}/events")
    return f"{tmp_path}/events", events


def test_stream_assignment_equals_batch(spark, d2, event_folder):
    folder, events = event_folder
    grid = grid_granularity(d2.sources)
    assign.run_to_end(assign.assign_stream(assign.point_targets(assign.read_events(spark, folder)), d2.sources, grid), "assigned")
    batch = candidate_pairs(d2.sources, assign.point_targets(events), grid).filter("mbr_hit").select("tid", "sid")
    assert spark.table("assigned").exceptAll(batch).isEmpty() and spark.table("assigned").count() == batch.count()


def test_assigned_pairs_are_unfolded_not_written(spark, d2, event_folder, tmp_path):
    folder, events = event_folder
    boxes = d2.sources.select("sid", "mbr").unionByName(d2.sources.limit(100).select((F.col("sid") + 1_000_000).alias("sid"), F.expr("named_struct('x1', -1e4D, 'y1', -1e4D, 'x2', 1e4D, 'y2', 1e4D)").alias("mbr")))
    grid = Grid(0.0005, 0.0005)
    got = assign.assign_to_files(assign.point_targets(assign.read_events(spark, folder)), boxes, grid)
    want = candidate_pairs(boxes, assign.point_targets(events), grid).filter("mbr_hit").select("tid", "sid")
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
    files = [f.removeprefix("file:") for f in got.inputFiles() if "/stream-" in f]
    n = events.count()
    assert got.count() >= 100 * n and 0 < sum(spark.read.parquet(f"file:{f}" if f.startswith("/") else f).count() for f in files) <= n


def test_streams_into_files(spark, event_folder):
    folder, events = event_folder
    read = lambda: assign.read_events(spark, folder)
    daily = assign.run_to_files(assign.windowed_counts(read(), "1 day"), "complete")
    assert daily.agg(F.sum("n")).head()[0] == events.count()
    pairs = assign.run_to_files(assign.join_streams(read(), read(), 1800))
    rows = [(r["event_id"], r["user_id"], r["ts"]) for r in events.collect()]
    want = {(a[0], b[0]) for a in rows for b in rows if a[1] == b[1] and 0 < (b[2] - a[2]).total_seconds() <= 1800}
    assert {tuple(r) for r in pairs.collect()} == want
    sessions = assign.run_to_files(assign.session_counts(read(), "1 hour", "0 seconds"))
    assert sessions.agg(F.sum("n")).head()[0] <= events.count() and sessions.count() > 0


def test_lines_of_events_as_targets(spark, event_folder):
    folder, _ = event_folder
    lines = assign.run_to_files(assign.event_lines(assign.read_events(spark, folder), "0 seconds"))
    assert lines.columns == ["tid", "geom", "mbr"] and lines.count() > 0


def test_keys_that_do_not_fit_are_refused(spark):
    from simcluster.sources.fixtures import packing

    cols = "l_orderkey long, l_partkey long, l_suppkey long"
    assert packing(spark.createDataFrame([(600_000, 20_000, 1000)], cols)) == (1_000_000_000, 1001)
    assert packing(spark.createDataFrame([(6_000_000, 200_000, 10_000)], cols)) == (1_000_000_000, 10_001)
    with pytest.raises(ValueError, match="do not fit"):
        packing(spark.createDataFrame([(6_000_000_000, 200_000_000, 10_000_000)], cols))


def test_items_keep_their_numbers_on_larger_tables(spark, tmp_path):
    from simcluster.sources.fixtures import lift_targets

    def lifted(name: str, items: list[tuple]) -> list:
        spark.createDataFrame([(1, 1, 1.0, dt.datetime(2024, 1, 1))], "o_orderkey long, o_custkey long, o_totalprice double, o_orderdate timestamp").write.parquet(f"{tmp_path}/{name}/orders.parquet")
        spark.createDataFrame([(*x, 7.0, "O") for x in items], "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double, l_linestatus string").write.parquet(f"{tmp_path}/{name}/lineitem.parquet")
        return [(r["tid"], r["n"]) for r in lift_targets(spark, f"{tmp_path}/{name}").select("tid", G.n_points(F.col("geom")).alias("n")).orderBy("tid").collect()]

    number = lambda o, n, p, s: o * 8 + n + 1_000_000_000 * (p * 1001 + s)
    apart = [(5, 1, 3, 60_000), (6, 2, 1_200_000, 999), (7, 1, 9, 1001)]  # the largest times 12 fits no long
    assert lifted("apart", apart) == sorted((number(*x), 3 + number(*x) % 10) for x in apart)
    clash = [(5, 1, 3, 2001), (5, 1, 4, 1000)]
    assert number(*clash[0]) == number(*clash[1]) and len({tid for tid, _ in lifted("clash", clash)}) == 2


def test_stream_windows_and_state(spark, event_folder):
    folder, events = event_folder
    assign.run_to_end(assign.windowed_counts(assign.read_events(spark, folder), "1 day"), "daily", "complete")
    assert spark.table("daily").agg(F.sum("n")).head()[0] == events.count()
    values = assign.read_events(spark, folder).select("event_type", (F.col("value") / 1000).alias("v"))
    assign.run_to_end(assign.running_histogram(values, "event_type", "v"), "bins", "update")
    last = spark.table("bins").groupBy("event_type", "bin").agg(F.max("n").alias("n"))
    assert last.agg(F.sum("n")).head()[0] == events.filter("value is not null").count()


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    t = lambda day, h=0: dt.datetime(2024, 1, day, h)
    # a batch drops rows by the watermark of the batch before it, so the late row comes two batches after the jump
    parts = [[(1, 1, t(1), "a", 1.0, "{}")], [(2, 1, t(9), "a", 1.0, "{}")], [(3, 1, t(10), "a", 1.0, "{}")], [(4, 1, t(2), "a", 1.0, "{}"), (5, 1, t(11), "a", 1.0, "{}")], [(6, 1, t(13), "a", 1.0, "{}")]]
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, assign.EVENTS).coalesce(1).write.parquet(f"{tmp_path}/{i}")
    stream = spark.readStream.schema(assign.EVENTS).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/*")
    query = assign.run_to_end(assign.windowed_counts(stream, "1 day"), "late", "append")
    assert assign.late_rows(query) == 1
    assert spark.table("late").filter("start_ts = '2024-01-02'").isEmpty()


def test_registry_is_complete():
    import __spark_entry__ as entry

    q, s = entry.queries(), entry.oracle_sql()
    assert set(s) <= set(q) and len(q) > 95 and "search_end_to_end" in q


def test_windows_of_equal_bounds_are_joined_as_one(spark, monkeypatch):
    from simcluster.operators import relational

    monkeypatch.setattr(relational, "WINDOWS_AT_ONCE", 3)
    hour = lambda h: dt.datetime(2024, 1, 1) + dt.timedelta(hours=h)
    rows = [(i, f"n{i}", hour(2 * (i % 2)), hour(5)) for i in range(10)] + [(10, None, hour(3), hour(3)), (10, None, hour(0), hour(9)), (10, None, hour(0), hour(9))]
    windows = spark.createDataFrame(rows, "w long, name string, start_ts timestamp, end_ts timestamp")
    events = spark.createDataFrame([(e, hour(h)) for e, h in ((1, 0), (2, 2), (3, 4.99), (4, 5), (5, 9))], "e long, ts timestamp")
    got = relational.interval_join(events, windows, 3600)
    want = [(e["e"], e["ts"], *w) for e in events.collect() for w in windows.collect() if w["start_ts"] <= e["ts"] < w["end_ts"]]
    assert got.columns == ["e", "ts", *windows.columns]
    assert sorted(map(repr, map(tuple, got.collect()))) == sorted(map(repr, want))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Generate explode") < plan.index("Join Inner"), plan  # unfolded after the join
