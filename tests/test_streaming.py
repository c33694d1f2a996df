"""Streams: online EM, late rows, dwell state; sources and the SQL surface."""

import numpy as np

from nodeweave.functions.states import Options
from nodeweave.operators import estimators as est
from nodeweave.operators import signals as sig
from nodeweave.plans import sql
from nodeweave.sources import tables
from nodeweave.sources.planted import plant_signals, plant_truth
from nodeweave.streaming import streams


def test_online_mixture_is_idempotent(spark):
    truth = plant_truth(2, 3, 12, 0)
    rows = plant_signals(spark.range(400).withColumnRenamed("id", "sample_id"), truth).persist()
    online = streams.OnlineMixture(Options(m=2, k=3, membership_update="disjoint"))
    for i in range(4):
        online.update(rows.filter(f"sample_id % 4 = {i}"), i)
    before = [w.copy() for w in online.params.w]
    online.update(rows, 2)  # a batch that was seen
    assert all(np.array_equal(a, b) for a, b in zip(before, online.params.w, strict=True)) and np.isfinite(online.stats.nll)


def test_late_rows_are_dropped(spark, tmp_path):
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    import datetime as dt

    day = dt.datetime(2024, 1, 1)
    for i, hours in enumerate(([0, 1, 30], [31], [0, 32])):  # the last file's first row is a day late
        spark.createDataFrame([(j, day + dt.timedelta(hours=h), 1, "a", 1.0, "") for j, h in enumerate(hours)], schema).coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    source = streams.event_stream(spark, f"{tmp_path}/in/*")
    q = streams.windowed_bins(source).writeStream.format("memory").queryName("late_bins").outputMode("append").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination()
    rows = {r["w"]["start"].hour: r["n"] for r in spark.table("late_bins").collect()}
    assert rows.get(0) == 1 and rows.get(1) == 1


def test_dwell_state(spark, tmp_path):
    spark.createDataFrame([(1, i, s) for i, s in enumerate([0, 0, 1, 1, 1])], "unit long, step long, state int").coalesce(1).write.parquet(f"{tmp_path}/in")
    source = spark.readStream.schema("unit long, step long, state int").parquet(f"{tmp_path}/in")
    q = streams.dwell_stream(source).writeStream.format("memory").queryName("dwell").outputMode("append").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination()
    assert sorted(map(tuple, spark.table("dwell").collect())) == [(1, 0, 2, True), (1, 1, 3, False)]


def test_signal_files(spark, tmp_path):
    rows = spark.createDataFrame([(1, [1.0, 2.0]), (2, [3.0, 4.0])], tables.SIGNALS)
    for fmt in ("parquet", "orc", "json"):
        tables.write_signals(rows, f"{tmp_path}/{fmt}", fmt=fmt)
        assert sorted(map(tuple, tables.read_signals(spark, f"{tmp_path}/{fmt}", fmt).collect())) == sorted(map(tuple, rows.collect()))
    tables.write_signals(rows.selectExpr("sample_id", "x", "'u' as unit"), f"{tmp_path}/long", "long", "unit")
    assert spark.read.parquet(f"{tmp_path}/long").count() == 4
    (tmp_path / "t.txt").write_text("1 2\n3 4\n")
    (tmp_path / "t.csv").write_text("sample_id,a,b\n1,1,2\n2,3,4\n")
    assert sorted(r["x"] for r in tables.read_signals(spark, f"{tmp_path}/t.txt", "text").collect()) == [[1.0, 2.0], [3.0, 4.0]]
    assert sorted(r["x"] for r in tables.read_signals(spark, f"{tmp_path}/t.csv", "csv").collect()) == [[1.0, 2.0], [3.0, 4.0]]


def test_planted_source_and_sql(spark):
    tables.register_planted_source(spark)
    rows = spark.read.format("planted").option("n", 60).option("p", 12).option("k", 3).load().persist()
    assert rows.count() == 60 and len(rows.first()["x"]) == 12
    model = est.StateNetworkMixture(2, 3, max_iter=2).fit(rows.select("sample_id", "x"))
    sql.register(spark, model, rows.select("sample_id", "x"))
    assert sql.scored(spark, 0.0).count() == 60
    assert spark.sql("SELECT node_of(0, 3) AS n").first()["n"] == int(model.params.w[0][3].argmax())
    assert spark.sql("SELECT * FROM edge_rows(array(1D, 0.5D, 0.5D, 1D), 2)").count() == 1


def test_standardize_and_noise(spark):
    rows = spark.createDataFrame([(i, [float(i), 5.0]) for i in range(10)], tables.SIGNALS)
    z = np.array([r["x"] for r in sig.standardize(rows).orderBy("sample_id").collect()])
    assert np.allclose(z.mean(axis=0), 0) and np.allclose(z[:, 0].std(), 1) and np.allclose(z[:, 1], 0)
    assert sig.variance_mask(rows) == [0]
    a, b = (sig.add_noise(rows.repartition(n), 1.0, 3).orderBy("sample_id").collect() for n in (1, 4))
    assert a == b and a[0]["x"] != [0.0, 5.0]
    units = sig.with_units(sig.to_long(rows), __import__("pyspark.sql.functions", fromlist=["x"]).expr("cast(sample_id % 2 as string)"))
    assert sorted({r["sample_id"] for r in units.collect()}) == list(range(10))


def test_online_model_goes_on_after_a_restart(spark, tmp_path):
    """Two batches by one object, and by two objects with one path, give one model; a batch seen before changes nothing."""
    from nodeweave.functions.states import Options

    rows = plant_signals(spark.range(120).withColumnRenamed("id", "sample_id"), plant_truth(2, 3, 12, 0)).persist()
    first, second = rows.filter("sample_id < 60"), rows.filter("sample_id >= 60")
    opt = Options(m=2, k=3, density="residual", refresh=())
    whole = streams.OnlineMixture(opt)
    whole.update(first, 0)
    whole.update(second, 1)
    streams.OnlineMixture(opt, path=f"{tmp_path}/model").update(first, 0)
    again = streams.OnlineMixture(opt, path=f"{tmp_path}/model")
    again.update(first, 0)
    again.update(second, 1)
    for a, b in zip(whole.params.w + whole.params.omega, again.params.w + again.params.omega, strict=True):
        assert np.allclose(a, b)
    assert again.seen == 1 and np.allclose(whole.stats.mass, again.stats.mass)


def test_stream_results_never_reach_the_driver(spark, sf):
    """Results of every row of a stream are files that executors write, not tables in the driver's memory."""
    from nodeweave import queries as q

    events = spark.read.parquet(f"{sf}/events.parquet").count()
    for name, mode in (("append", "append"), ("complete", "complete")):
        build = (lambda s: s.select("event_id")) if mode == "append" else (lambda s: s.groupBy("event_id").count())
        rows = q._run_stream(spark, sf, build, f"kept_{name}", mode)
        assert rows.count() == events and rows.select("event_id").distinct().count() == events
        assert rows.inputFiles() and not any(t.name.startswith(f"kept_{name}") for t in spark.catalog.listTables())
