"""What survives a lost driver, what a first batch writes, what the manifest reads, and laws of drawn keys."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from streamsample import queries as Q
from streamsample.functions import skips, sqlapi
from streamsample.functions import variates as V
from streamsample.operators import localres, reservoir
from streamsample.operators.estimate import inclusion_law, largest_z, relative_error
from streamsample.plans import cost
from streamsample.plans import workloads as W
from streamsample.plans.batches import DAY, items, keyed, replay, valid
from streamsample.sources import manifest
from streamsample import around  # noqa: F401  registers its queries
from streamsample.streaming import stream


@pytest.fixture(scope="module")
def events(spark, sf):
    return spark.read.parquet(f"{sf}/events.parquet")


def ids(df):
    return [r["item_id"] for r in df.orderBy("draw_no").collect()]


def test_a_stopped_stream_goes_on(spark, events, tmp_path):
    """The first query fails after some micro-batches; a new driver object with the same folders gives the sample of the whole stream."""
    source = f"{tmp_path}/in"
    for k in range(6):
        events.where(f"{DAY} DIV 5 = {k}").coalesce(1).write.parquet(f"{source}/part={k}")
    rows = lambda: spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{source}/part=*")
    one = stream.StreamSampler(spark, Q.EVENTS, f"{tmp_path}/state")

    def until_lost(batch, number):
        one(batch, number)
        if number == 2:
            raise RuntimeError("lost")

    with pytest.raises(Exception, match="lost"):
        stream.drain(rows(), until_lost, f"{tmp_path}/state/checkpoint")
    assert one.inner.state.version == 2 and one.inner.state.n_seen < events.count()
    again = stream.StreamSampler(spark, Q.EVENTS, f"{tmp_path}/state")
    assert again.inner.state == one.inner.state
    assert ids(again.run(rows())) == ids(reservoir.sample_once(events, Q.EVENTS))
    assert again.inner.state.n_seen == events.where("value > 0").count()
    versions = again.inner.log.table().orderBy("version").collect()
    assert [r["version"] for r in versions] == list(range(6)) and versions[-1]["threshold"] == again.inner.state.threshold
    with pytest.raises(ValueError, match="another k"):
        reservoir.DecentralSampler(spark, Q.EVENTS.but(k=50), f"{tmp_path}/state")


def test_a_first_batch_is_capped(spark, events):
    capped, whole = (reservoir.DecentralSampler(spark, Q.EVENTS.but(k=20, cap=c)) for c in (True, False))
    for one in (capped, whole):
        r = one.process(events.repartition(4), 0)
        assert r.held_after == 20 and r.candidates == r.n_items and r.candidates_max_pe < r.n_items
    assert capped.reports.rows[0].stored <= 80 < whole.reports.rows[0].stored
    assert ids(capped.sample()) == ids(whole.sample()) == ids(reservoir.sample_once(events, Q.EVENTS.but(k=20)))


def test_report_counts(spark, events):
    one = W.run(spark, "tail", Q.EVENTS, replay(events, f"{DAY} DIV 10"))
    for r in one.reports.rows[1:]:
        t, day = r.threshold_before, r.batch_no
        rows = keyed(events.where(f"{DAY} DIV 10 = {day}"), Q.EVENTS).where(F.col("key") <= t)
        by = rows.groupBy(F.spark_partition_id()).count()
        assert (r.candidates, r.candidates_max_pe) == (rows.count(), by.agg(F.max("count")).first()[0])
        assert r.rows_examined == r.n_items and r.t_threshold > 0
    jumps = W.run(spark, "tail", Q.EVENTS.but(fill="jump", block=8), replay(events, f"{DAY} DIV 10"))
    assert all(0 < r.rows_examined < r.n_items and r.blocks_skipped > 0 for r in jumps.reports.rows[1:])


def test_staged_batches_are_the_batches(spark, events, tmp_path):
    plain, staged = (dict(replay(events, f"{DAY} DIV 7", None, p)) for p in (None, f"{tmp_path}/staged"))
    assert plain.keys() == staged.keys()
    for b in plain:
        assert plain[b].exceptAll(staged[b].select(plain[b].columns)).isEmpty() and plain[b].count() == staged[b].count()


def test_incremental_selection_moves_new_rows_only(spark, events):
    one = W.sampler(spark, "incremental", Q.EVENTS)
    for number, rows in replay(events, DAY):
        r = one.process(rows, number)
        if number:
            assert r.rows_moved >= r.stored and r.rounds <= 4
    assert ids(one.sample()) == ids(reservoir.sample_once(events, Q.EVENTS))


def test_files_draw_for_themselves(spark, tmp_path):
    """Equal files: a walk in one says nothing about the others."""
    for k in range(4):
        spark.range(400).select(F.lit(float(1)).alias("w"), F.col("id").alias("i")).coalesce(1).write.parquet(f"{tmp_path}/t/f={k}")
    path, spec = f"{tmp_path}/t", Q.EVENTS.but(id_cols=("f", "i"), weight="w")
    m = manifest.build(spark, path, spec, rows=100)
    places = {}
    for r in manifest.uniform_positions(m, 0.1, 7).collect():
        places.setdefault(r["file"], []).append((r["block"], r["place"]))
    assert len(places) == 4 and len({tuple(sorted(p)) for p in places.values()}) == 4
    got = {}
    for r in manifest.sample_from_manifest(spark, path, m, spec, 0.1, rows=100).collect():
        f, i = r["item_id"].split("|")
        got.setdefault(f, set()).add(i)
    assert len({frozenset(x) for x in got.values()}) == len(got) == 4
    few = manifest.what_is_read(m, spec, 1e-3).first()
    assert few["files"] == 4 and few["files_read"] < 4 and few["bytes_read"] < few["file_bytes"] and few["blocks"] == 16
    plan = manifest.sample_from_manifest(spark, path, m, spec, 1e-3, rows=100)
    assert plan.count() == 0 or len(plan.inputFiles()) == few["files_read"]


def test_partitions_draw_keys_for_themselves(spark):
    df = spark.createDataFrame([(1.0,)] * 4, "w double").repartitionById(4, F.monotonically_increasing_id().cast("int") % 4)
    df = spark.range(4, numPartitions=4).select(F.lit(1.0).alias("w"))
    keys = [r["key"] for r in df.mapInPandas(lambda b: sqlapi.batch_keys(b, 3), "w double, key double").collect()]
    assert len(set(keys)) == 4


def test_scaling_stages_items_once(spark, sf, monkeypatch):
    seen, real = [], W.spread_batches
    monkeypatch.setattr(W, "spread_batches", lambda *a: seen.append(1) or real(*a))
    df = W.lineitem(spark, sf)
    rows = W.scaling(spark, df, Q.LINES, [(1, 3), (2, 2), (2, 1)], (20, 300), ("pivot8", "gather"))
    assert len(seen) == 1 and rows.where("run = 'gather'").groupBy("p", "batches", "k").agg(F.sum("n_items").alias("n")).where(f"n <> {df.count()}").isEmpty()


def test_local_cap_sorts_no_partition(spark):
    rows = spark.range(0, 40_000, 1, 3).select(F.col("id").cast("string").alias("item_id"), F.lit(1.0).alias("w"), (F.xxhash64("id") % 500).cast("double").alias("key"), F.lit(0).cast("long").alias("batch_no"), F.spark_partition_id().alias("pe"))
    got = reservoir.local_cap(rows, 150)
    assert "Window" not in got._jdf.queryExecution().executedPlan().toString()
    want = localres.local_smallest(rows, 150).select(got.columns)
    assert got.count() == 450 and got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_rows_once_each_are_not_held_in_memory(spark, sf):
    got = Q.QUERIES["stream_once_each"](spark, sf)
    assert not spark.catalog.tableExists("events_once") and got.first()["n"] == spark.read.parquet(f"{sf}/events.parquet").count()
    assert "RocksDB" not in spark.conf.get("spark.sql.streaming.stateStore.providerClass")


def test_sessions_over_micro_batches(spark):
    """Out of order, over three micro-batches: the last one bridges two sessions; exactly the gap after an event a new session begins."""
    at = lambda minutes: f"2024-01-01 {minutes // 60:02d}:{minutes % 60:02d}:00"
    rows = lambda *minutes: spark.createDataFrame([(m, 1, at(m), 2.0) for m in minutes], "event_id long, u long, ts string, value double").withColumn("ts", F.col("ts").cast("timestamp"))
    store = stream.SessionStore(spark, Q.EVENTS.but(k=2), "u")
    parts = [(0, 10, 20, 130), (100, 60, 5), (40, 160, 110)]
    for number, part in enumerate(parts):
        store.add(rows(*part), number)
        store.add(rows(*part), number)
    got = sorted((r["session_start"], r["n"], [x["item_id"] for x in r["least"]]) for r in store.held().collect())
    keys = {int(r["item_id"]): r["key"] for r in keyed(rows(*sum(parts, ())), Q.EVENTS).collect()}
    want = [sorted(s, key=keys.get)[:2] for s in ((0, 5, 10, 20, 40, 60), (100, 110, 130), (160,))]
    assert [n for _, n, _ in got] == [6, 3, 1] and [x for _, _, x in got] == [[str(i) for i in w] for w in want]


def test_session_gaps_count_to_the_nearest_second(spark):
    times = ["2024-01-01 00:00:00.6", "2024-01-01 00:30:01.4", "2024-01-01 01:00:01.4", "2024-01-01 01:30:01.6"]
    df = spark.createDataFrame([(i, 1, t, 1.0) for i, t in enumerate(times)], "event_id long, u long, ts string, value double").withColumn("ts", F.col("ts").cast("timestamp"))
    got = stream.session_sample(df, Q.EVENTS.but(k=9), "u", 30).orderBy("item_id").collect()
    assert [r["session_no"] for r in got] == [1, 1, 1, 2]


def test_expected_insertions_at_the_ends(spark):
    grid = spark.createDataFrame([(1000, 10, 4, 250), (500, 10, 4, 250), (4000, 10, 4, 250)], "n long, k long, p long, b long")
    got = [r[0] for r in grid.orderBy("n").select(cost.columns_expected(*[F.col(c) for c in "nkpb"])).collect()]
    assert got == pytest.approx([cost.expected_insertions(n, 10, 4, 250) for n in (500, 1000, 4000)])
    assert cost.insert_probability(10, 5) == 1 and cost.insert_probability(10, 40) == 0.25
    assert relative_error(9.0, 10.0) == pytest.approx(0.1) and relative_error(2.0, 0.0) == 2


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    parts = ["2024-01-20 10:00:00", "2024-01-01 10:00:00", "2024-01-19 20:00:00"]
    for k, ts in enumerate(parts):
        spark.createDataFrame([(10 * k + i, ts, 1.0) for i in range(3)], "event_id long, ts string, value double").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(f"{tmp_path}/e/part={k}")
    schema = spark.read.parquet(f"{tmp_path}/e").drop("part").schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/e/part=*")
    store = stream.stream_windows(rows, Q.EVENTS.but(k=2), "1 day", "1 day")
    assert store.late == 3
    assert {r[0] for r in store.held().select(F.to_date("window_start").cast("string")).collect()} == {"2024-01-20", "2024-01-19"}
    assert store.held().count() == 4


def test_closed_windows_are_written_once(spark, tmp_path):
    for k in range(4):
        spark.createDataFrame([(10 * k + i, f"2024-01-{1 + 5 * k:02d} 10:00:00", 1.0) for i in range(3)], "event_id long, ts string, value double").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(f"{tmp_path}/e/part={k}")
    schema = spark.read.parquet(f"{tmp_path}/e").drop("part").schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/e/part=*")
    store = stream.stream_windows(rows, Q.EVENTS.but(k=2), "1 day", "1 day")
    assert store.late == 0 and len(store.closed) == 3 and store._read(store.open).select("window_start").distinct().count() == 1
    assert store.held().count() == 8


@pytest.mark.parametrize("batch", [1, 2, 7])
def test_batches_on_one_element_follow_the_definition(batch):
    """With one item a batch the batch method is the sequential sampler: both have the law of successive draws."""
    weights, k, trials, counts = np.arange(1.0, 8.0), 2, 5000, np.zeros(7)
    for seed in range(trials):
        at, keys = skips.batched(weights, k, batch, seed)
        assert len(at) == k and (np.diff(keys) >= 0).all()
        counts[at] += 1
    assert largest_z(counts, inclusion_law(weights, k), trials) < 4.5


def test_a_stream_in_parts_is_one_stream():
    weights, k, trials, counts = np.arange(1.0, 8.0), 2, 5000, np.zeros(7)
    for seed in range(trials):
        one = skips.Sequential(k, seed, True)
        for part in (weights[:1], weights[1:3], weights[3:3], weights[3:]):
            one.add(part)
        counts[one.sample()[0]] += 1
    assert largest_z(counts, inclusion_law(weights, k), trials) < 4.5
    flat = np.zeros(7)
    for seed in range(trials):
        one = skips.Sequential(k, seed, False)
        for n in (1, 2, 0, 4):
            one.add(np.ones(n))
        flat[one.sample()[0]] += 1
    assert largest_z(flat, np.full(7, 2 / 7), trials) < 4.5


def test_blocks_are_passed_over():
    rng, w = np.random.default_rng(5), np.ones(10_000)
    walk = skips.weighted_fill(w, 1e-3, rng, 100)
    assert walk.examined == 100 * len({p // 100 for p in walk.positions.tolist()}) and walk.skipped_blocks == 100 - walk.examined // 100
    assert skips.weighted_fill(w, 1e-3, np.random.default_rng(5), 1).examined == len(skips.weighted_fill(w, 1e-3, np.random.default_rng(5), 1).positions)


def test_inclusion_test_and_conditional_key_have_the_law_of_keys(spark):
    """As columns: of 40,000 items the test lets in a share of 1 - exp(-T w); keys of those are spread like keys below T."""
    spec = Q.EVENTS.but(id_cols=("id",), weight="w")
    rows = spark.range(40_000).select(F.col("id"), F.lit(2.0).alias("w"))
    t = 0.5
    got = np.sort([r["key"] for r in reservoir.candidates_by_test(valid(items(rows, spec)), spec, t).select("key").collect()])
    share = -np.expm1(-t * 2)
    assert abs(len(got) / 40_000 - share) < 5 * (share * (1 - share) / 40_000) ** 0.5 and got.min() > 0 and got.max() <= t
    assert np.max(np.abs(-np.expm1(-2 * got) / share - np.arange(len(got)) / len(got))) < 2 / len(got) ** 0.5
    u = spark.range(20_000).select(V.uniform_key_below(V.uniform_key(F.col("id").cast("string"), "x", 1), 0.2).alias("k")).agg(F.max("k"), F.avg("k")).first()
    assert u[0] <= 0.2 and abs(u[1] - 0.1) < 0.003


def test_scaling_reports(spark, sf):
    df = W.lineitem(spark, sf)
    rows = W.scaling(spark, df, Q.LINES, [(1, 2), (2, 1)], (50,), ("pivot1", "pivot8"))
    by = {(r["run"], r["p"]): r for r in W.scaling_summary(rows).collect()}
    assert set(by) == {(m, p) for m in ("pivot1", "pivot8") for p in (1, 2)} and by["pivot1", 1]["speedup"] == pytest.approx(1)
    for r in by.values():
        assert r["n_items"] == df.where("l_extendedprice > 0").count() and sum(r[f"{c}_share"] for c in ("insert", "select", "threshold", "gather")) == pytest.approx(1)
    assert by["pivot8", 1]["selection_saved"] is not None and by["pivot1", 1]["selection_saved"] is None


def test_cap_never_cuts_below_k():
    rng = np.random.default_rng(1)
    one, keys = localres.FirstBatch(100), rng.random(20_000)
    for a in range(0, 20_000, 700):
        one.add(keys[a : a + 700], np.arange(a, min(a + 700, 20_000)))
    assert 100 <= len(one.keys) <= localres.cap_limits(100)[1] and set(np.argsort(keys)[:100]) <= set(one.ids.tolist())
