"""Samplers on Spark: every way to run them gives the one-shot sample, and invariants hold after each batch."""

import pytest
from pyspark.sql import functions as F

from streamsample import queries as Q
from streamsample.operators import reservoir
from streamsample.operators import select as S
from streamsample.plans import workloads as W
from streamsample.plans.batches import DAY, keyed, replay


@pytest.fixture(scope="module")
def events(spark, sf):
    return spark.read.parquet(f"{sf}/events.parquet")


@pytest.fixture(scope="module")
def want(events):
    return [r["item_id"] for r in reservoir.sample_once(events, Q.EVENTS).orderBy("draw_no").collect()]


def test_fixed_sample(want):
    assert want[:3] == ["843", "984", "687"]


def test_power_keys_give_the_same_sample(events, want):
    assert [r["item_id"] for r in reservoir.sample_top_power(events, Q.EVENTS).orderBy("draw_no").collect()] == want


@pytest.mark.parametrize("method", ["pivot1", "pivot8", "two_pivot", "combined", "incremental", "unsorted", "sort", "tail", "gather", "auto"])
def test_every_method_gives_the_one_shot_sample(spark, events, want, method):
    one = W.run(spark, method, Q.EVENTS, replay(events, f"{DAY} DIV 6"))
    assert [r["item_id"] for r in one.sample().orderBy("draw_no").collect()] == want
    seen, last = 0, None
    for r in one.reports.rows:
        seen += r.n_items
        assert r.held_after == min(100, seen)
        assert last is None or r.threshold_after <= last
        last = r.threshold_after


def test_a_repeated_batch_changes_nothing(spark, events, want):
    one = W.sampler(spark, "tail", Q.EVENTS)
    for number, rows in replay(events, f"{DAY} DIV 10"):
        one.process(rows, number)
        one.process(rows, number)
    assert [r["item_id"] for r in one.sample().orderBy("draw_no").collect()] == want


@pytest.mark.parametrize("fill", ["test", "jump"])
@pytest.mark.parametrize("weight", ["value", None])
def test_drawn_keys_keep_the_invariants(spark, events, fill, weight):
    one = W.sampler(spark, "tail", Q.EVENTS.but(fill=fill, weight=weight))
    for number, rows in replay(events, f"{DAY} DIV 10"):
        one.process(rows, number)
    got = one.sample().collect()
    assert len(got) == len({r["item_id"] for r in got}) == 100
    assert max(r["key"] for r in got) <= one.state.threshold


def test_fewer_items_than_wanted(spark, sf):
    nation = spark.read.parquet(f"{sf}/nation.parquet")
    one = W.sampler(spark, "tail", Q.NATIONS)
    one.process(nation, 0)
    assert one.state.threshold is None and one.state.held == 25
    one.process(nation.limit(0), 1)
    assert one.state.held == 25 and one.sample().count() == 25


def test_bad_weights_are_rejected_and_counted(spark):
    df = spark.createDataFrame([(1, 1.0), (2, 0.0), (3, -1.0), (4, float("nan")), (5, float("inf")), (6, None)], "id long, w double")
    spec = Q.EVENTS.but(id_cols=("id",), weight="w", k=3)
    one = W.sampler(spark, "tail", spec)
    report = one.process(df, 0)
    assert report.n_rejected == 5 and [r["item_id"] for r in one.sample().collect()] == ["1"]


def test_lazy_sampler_selects_less_often(spark, events):
    runs = {m: W.run(spark, m, Q.EVENTS.but(k_max=200), replay(events, f"{DAY} DIV 3")) for m in ("lazy", "eager")}
    picks = {m: sum(r.rounds > 0 for r in x.reports.rows) for m, x in runs.items()}
    assert picks["lazy"] < picks["eager"]
    for x in runs.values():
        assert all(100 <= r.held_after <= 200 for r in x.reports.rows[1:] if r.threshold_after is not None)
        assert keyed(events, Q.EVENTS).where(F.col("key") <= x.state.threshold).count() == x.state.held


def test_selectors_at_the_ends_and_with_equal_keys(spark):
    runs = spark.range(500).select((F.col("id") % 7).cast("double").alias("key"), F.format_string("%04d", "id").alias("item_id")).persist()
    every = sorted((r["key"], r["item_id"]) for r in runs.collect())
    for rank in (1, 2, 250, 499, 500):
        for name in ("pivot", "two_pivot", "combined", "unsorted", "sort", "tail"):
            got = S.select(name, runs, rank, 500, finish=1)
            assert (got.key, got.item_id) == every[rank - 1], (name, rank)
    got = S.pivot_select(runs, 100, 200, 500, 4)
    assert 100 <= got.rank <= 200 and every[got.rank - 1] == (got.key, got.item_id)
    with pytest.raises(ValueError):
        S.sort_select(runs, 501, 500)


def test_eight_pivots_need_fewer_rounds(spark, sf):
    df = W.sliced(W.lineitem(spark, sf), W.LINE_ID, 6)
    depth = {d: rounds for d, rounds, _ in W.depth_by_pivots(spark, df, Q.LINES, "slice", (1, 8))}
    assert depth[8] < depth[1]


def test_the_fill_moves_no_rows_and_reads_two_columns(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet")
    plan = reservoir.candidates_by_key(keyed(events, Q.EVENTS).drop("key"), Q.EVENTS, 0.01)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "props" not in plan and "event_id" in plan
    top = reservoir.sample_once(events, Q.EVENTS)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in top
    group = reservoir.sample_by_group(events, Q.EVENTS, "event_type")._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in group


def test_synthetic_source(spark):
    from streamsample.sources.synthetic import WeightedItems

    spark.dataSource.register(WeightedItems)
    df = spark.read.format("weighted_items").option("n", 100).option("p", 3).option("batches", 2).load()
    assert df.count() == 600 and df.select("item_id").distinct().count() == 600
    assert df.where("w <= 0 OR w > 100").count() == 0


def test_sql_surface(spark, events, want):
    from streamsample.functions import sqlapi

    sqlapi.register(spark)
    events.createOrReplaceTempView("events_v")
    rows = spark.sql("SELECT id FROM (SELECT cast(event_id AS string) AS id, exp_key('events', 7, cast(event_id AS string), value) AS key FROM events_v WHERE value > 0) ORDER BY key LIMIT 100").collect()
    assert [r["id"] for r in rows] == want
    got = spark.sql("SELECT * FROM sample_weighted(TABLE(SELECT cast(event_id AS string), value FROM events_v) WITH SINGLE PARTITION, 20, 7)").collect()
    assert len(got) == 20 and all(r["w"] > 0 for r in got)


def test_manifest_reads_few_blocks(spark, sf):
    from streamsample.sources import manifest

    path = f"{sf}/events.parquet"
    m = manifest.build(spark, path, Q.EVENTS, rows=20).persist()
    t = 1e-5
    hits = manifest.hit_blocks(m, Q.EVENTS, t).count()
    got = manifest.sample_from_manifest(spark, path, m, Q.EVENTS, t, rows=20).collect()
    assert 0 < hits < m.count() / 2 and len(got) >= hits and all(r["key"] <= t for r in got)
