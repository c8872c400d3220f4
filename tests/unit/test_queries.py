"""Queries against their SQL, run by DuckDB on the same files."""

from pathlib import Path

import duckdb
import pytest

from streamsample.operators.reservoir import counts_of_small_batches
from streamsample.plans import workloads as W
from streamsample.plans.batches import DAY, replay
from streamsample import around  # noqa: F401  registers its queries
from streamsample.queries import EVENTS, ORACLES, QUERIES

#: Formulas over figures that the tables give.
MEASURES = ["collective_cost", "max_insertions_bound", "monitoring_messages", "predict_cost"]
NAMES = [
    "uniform_bottom_k",
    "weighted_bottom_k_exp",
    "sample_fewer_than_k",
    "negative_weight_rejected",
    "select_tail",
    "local_rank",
    "stratified_bottom_k",
    "merge_samples",
    "sliding_window_sample",
    "subset_sum_estimate",
    "expected_insertions",
    "sample_cube",
    "turnover_full_join",
    "drifting_weight_sample",
    "stream_tumbling_sample",
    "state_versions",
    "lopsided_batches",
    "first_batch_held",
    "manifest_reads",
    "manifest_sample",
    "skip_weighted",
    "drift_replay",
    "stream_late_rows",
    "stream_once_each",
    "jump_targets_range_join",
    "drawn_batch_keys",
    "benchmark_anti_join",
    *MEASURES,
]


def plain(value):
    return None if value is None or value != value else repr(float(value)) if isinstance(value, (int, float)) and not isinstance(value, bool) else str(value)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_sql(spark, sf, name):
    con = duckdb.connect()
    for file in Path(sf).glob("*.parquet"):
        con.execute(f"CREATE VIEW {file.stem} AS SELECT * FROM '{file}'")
    want, got = con.execute(ORACLES[name]).df(), QUERIES[name](spark, sf).toPandas()
    assert sorted(want.columns) == sorted(got.columns)
    cols = sorted(want.columns)
    rows = [sorted(([plain(v) for v in r] for r in x[cols].astype(object).values.tolist()), key=str) for x in (want, got)]
    assert rows[0] == rows[1]


@pytest.mark.parametrize("name", [*MEASURES, "expected_insertions"])
def test_measures_read_a_table(spark, sf, name, tmp_path):
    """Half the rows give other figures."""
    for table, key in (("lineitem", "l_orderkey"), ("events", "event_id")):
        spark.read.parquet(f"{sf}/{table}.parquet").where(f"{key} % 4 < 2").write.parquet(f"{tmp_path}/{table}.parquet")
    half, whole = (sorted(map(str, QUERIES[name](spark, d).collect())) for d in (str(tmp_path), sf))
    assert half != whole


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES) and len(QUERIES) > 80


@pytest.mark.parametrize("name", ["compare_methods", "variable_size_eager"])
def test_methods_get_every_batch(spark, sf, name, monkeypatch):
    seen = []

    class Spy:
        def process(self, rows, number):
            seen.append(number)

        def report(self):
            raise InterruptedError

    monkeypatch.setattr(W, "sampler", lambda *_: Spy())
    with pytest.raises(InterruptedError):
        QUERIES[name](spark, sf)
    ends = spark.read.parquet(f"{sf}/events.parquet").selectExpr(f"min({DAY})", f"max({DAY})").first()
    assert ends[1] > 9 and seen == list(range(ends[0], ends[1] + 1))


def test_counts_of_small_batches(spark, sf):
    events, spec = spark.read.parquet(f"{sf}/events.parquet"), EVENTS.but(k=5)
    got = {r["batch_no"]: tuple(r) for r in QUERIES["single_item_batches"](spark, sf).collect()}
    assert len(got) == events.selectExpr("event_id DIV 4").distinct().count() > 6
    first = W.run(spark, "gather", spec, replay(events.where("event_id < 32"), "event_id DIV 4")).report()
    want = [tuple(r) for r in first.select("batch_no", "n_items", "candidates", "held_after").collect()]
    assert [got[w[0]] for w in want] == want
    again = counts_of_small_batches(events, spec, "event_id DIV 4", group=100).collect()
    assert {r["batch_no"]: tuple(r) for r in again} == got
