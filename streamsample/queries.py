"""Queries over the given tables, one for each method, variant, baseline, measure and operator, with the SQL that checks them.

Every key is a function of the item, so both engines compute the same sample. Exponential keys leave as ``round(ln(key), 9)``.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import variates as V
from .model import SamplerSpec
from .operators import estimate, localres, reservoir
from .operators import select as S
from .plans import cost
from .plans import workloads as W
from .plans.batches import DAY, items, keyed, replay, valid
from .sources import manifest
from .streaming import stream, windows

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

EVENTS = SamplerSpec("events", ("event_id",), "value", 100)
EVENTS_U = EVENTS.but(weight=None)
LINES = SamplerSpec("lineitem", W.LINE_ID, "l_extendedprice", 1000)
ORDERS = SamplerSpec("orders", ("o_orderkey",), "o_totalprice", 100)
DOCS = SamplerSpec("documents", ("doc_id",), "n_chars", 50)
CUSTOMERS = SamplerSpec("customer", ("c_custkey",), "c_acctbal", 50)
NATIONS = SamplerSpec("nation", ("n_nationkey",), None, 100)
DISCOUNTS = LINES.but(weight="l_discount", k=100)

LINE_SQL = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, cast(round(l_extendedprice * 100) AS bigint))"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return W.lineitem(spark, sf_dir) if table == "lineitem" else spark.read.parquet(f"{sf_dir}/{table}.parquet")


def unit_sql(stream_id: str, item: str, purpose: str = "") -> str:
    head = f"{stream_id}:7:{purpose}{':' if purpose else ''}"
    return f"((('0x' || substr(md5('{head}' || {item}), 1, 13))::bigint + 1) / power(2::double, 52))"


def keyed_sql(table: str, item: str, weight: str | None, more: str = "", stream_id: str | None = None) -> str:
    """(item_id, w, key, more) of the valid rows of a table."""
    u, extra = unit_sql(stream_id or table, f"({item})::varchar"), f", {more}" if more else ""
    w = f"({weight})::double" if weight else "1.0::double"
    key = f"-ln({u}) / {w}" if weight else u
    test = f"{w} > 0 AND {w} < 'infinity'::double" if weight else "true"
    return f"SELECT ({item})::varchar AS item_id, {w} AS w, {key} AS key{extra} FROM {table} WHERE {test}"


EVENTS_SQL = keyed_sql("events", "event_id", "value", "datediff('day', DATE '2024-01-01', ts::date) AS batch_no, event_type, user_id, ts")
EVENTS_U_SQL = keyed_sql("events", "event_id", None, "datediff('day', DATE '2024-01-01', ts::date) AS batch_no")
LINES_SQL = keyed_sql("lineitem", LINE_SQL, "l_extendedprice", "l_orderkey, l_returnflag")


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def shown(rows: DataFrame, weighted: bool = True, *more: str) -> DataFrame:
    """Id, order of draw and key, as oracles have them."""
    key = F.round(F.log("key"), 9).alias("ln_key") if weighted else F.col("key")
    return rows.select(*more, "item_id", F.col("draw_no").cast("long").alias("draw_no"), key)


def bottom_sql(rows: str, k: int, weighted: bool = True, group: str = "") -> str:
    over = f"OVER ({f'PARTITION BY {group} ' if group else ''}ORDER BY key, item_id)"
    key = "round(ln(key), 9) AS ln_key" if weighted else "key"
    lead = f"{group}, " if group else ""
    return f"SELECT {lead}item_id, draw_no, {key} FROM (SELECT *, row_number() {over} AS draw_no FROM ({rows})) WHERE draw_no <= {k}"


# one-shot samples ------------------------------------------------------------------------------------------------------------------


def _one_shot(name: str, table: str, spec: SamplerSpec, item: str) -> None:
    weighted = spec.weight is not None
    QUERIES[name] = lambda s, d: shown(reservoir.sample_once(read(s, d, table), spec), weighted)
    ORACLES[name] = bottom_sql(keyed_sql(table, item, spec.weight), spec.k, weighted)


_one_shot("uniform_bottom_k", "events", EVENTS_U, "event_id")
_one_shot("weighted_bottom_k_exp", "events", EVENTS, "event_id")
_one_shot("weighted_lineitem_extprice", "lineitem", LINES, LINE_SQL)
_one_shot("weighted_lineitem_quantity", "lineitem", LINES.but(weight="l_quantity"), LINE_SQL)
_one_shot("weighted_documents_chars", "documents", DOCS, "doc_id")
_one_shot("weighted_orders_price", "orders", ORDERS, "o_orderkey")
_one_shot("weighted_part_near_uniform", "part", SamplerSpec("part", ("p_partkey",), "p_retailprice", 50), "p_partkey")
_one_shot("sample_fewer_than_k", "nation", NATIONS, "n_nationkey")
_one_shot("zero_weight_rejected", "lineitem", DISCOUNTS, LINE_SQL)
_one_shot("negative_weight_rejected", "customer", CUSTOMERS, "c_custkey")
_one_shot("uniform_embeddings", "embeddings", SamplerSpec("embeddings", ("vec_id",), None, 50), "vec_id")
_one_shot("weighted_conversations", "conversations", SamplerSpec("conversations", ("conv_id", "turn"), "length(text)", 50), "concat_ws('|', conv_id, turn)")
_one_shot("weighted_pages", "pages", SamplerSpec("pages", ("page_id",), "length(html)", 20), "page_id")
_one_shot("json_weight_sample", "events", EVENTS.but(weight="try_cast(get_json_object(props, '$.k') AS double)"), "event_id")
ORACLES["json_weight_sample"] = bottom_sql(keyed_sql("events", "event_id", "coalesce(try_cast(json_extract_string(props, '$.k') AS double), 0)"), 100)


@query("weighted_top_k_power", f"SELECT item_id, draw_no FROM ({bottom_sql(EVENTS_SQL, 100)})")
def _(s, d):
    return reservoir.sample_top_power(read(s, d, "events"), EVENTS).select("item_id", F.col("draw_no").cast("long").alias("draw_no"))


@query("deep_key_sample")
def _(s, d):
    return shown(reservoir.sample_once(read(s, d, "lineitem"), LINES.but(deep=True)))


# batches -----------------------------------------------------------------------------------------------------------------------------


def _replayed(name: str, method: str, spec: SamplerSpec, oracle: str | None) -> None:
    def f(s, d):
        return shown(W.run(s, method, spec, days(s, d)).sample(), spec.weight is not None)

    query(name, oracle)(f)


def days(s, d):
    """The events by day, staged once."""
    return replay(read(s, d, "events"), DAY, None, reservoir.storage(s))


def invariants(s, method: str, spec: SamplerSpec, d: str) -> DataFrame:
    """What holds for each batch of a sampler whose keys are drawn: n_items, the size, and whether the threshold fell and no key is above it."""
    one = W.run(s, method, spec, days(s, d))
    rows, last, out = one.reports.rows, None, []
    for r in rows:
        out.append((r.batch_no, r.n_items, r.held_after, last is None or r.threshold_after <= last))
        last = r.threshold_after
    most, n, ids = one.sample().agg(F.max("key"), F.count(F.lit(1)), F.count_distinct("item_id")).first()
    good = bool(n == ids == one.state.held and most <= one.state.threshold)
    return s.createDataFrame(out, "batch_no long, n_items long, held_after long, falls boolean").withColumn("sample_is_sound", F.lit(good))


def _invariants_sql(rows: str, k: int) -> str:
    return f"WITH e AS ({rows}), n AS (SELECT batch_no, count(*) AS n FROM e GROUP BY 1) SELECT batch_no, n AS n_items, least({k}, sum(n) OVER (ORDER BY batch_no))::bigint AS held_after, true AS falls, true AS sample_is_sound FROM n"


_replayed("decentral_weighted_replay", "tail", EVENTS, bottom_sql(EVENTS_SQL, 100))
_replayed("decentral_uniform_replay", "tail", EVENTS_U, bottom_sql(EVENTS_U_SQL, 100, False))
_replayed("decentral_pivot1_replay", "pivot1", EVENTS, bottom_sql(EVENTS_SQL, 100))
_replayed("decentral_pivot8_replay", "pivot8", EVENTS, bottom_sql(EVENTS_SQL, 100))
_replayed("decentral_two_pivot_replay", "two_pivot", EVENTS, bottom_sql(EVENTS_SQL, 100))
_replayed("decentral_combined_replay", "combined", EVENTS, bottom_sql(EVENTS_SQL, 100))
_replayed("gather_weighted_replay", "gather", EVENTS, bottom_sql(EVENTS_SQL, 100))
_replayed("gather_uniform_replay", "gather", EVENTS_U, bottom_sql(EVENTS_U_SQL, 100, False))
_replayed("decentral_incremental_replay", "incremental", EVENTS, bottom_sql(EVENTS_SQL, 100))

for _name, _spec, _sql in (
    ("decentral_test_fill", EVENTS.but(fill="test"), EVENTS_SQL),
    ("decentral_jump_fill", EVENTS.but(fill="jump"), EVENTS_SQL),
    ("decentral_test_uniform", EVENTS_U.but(fill="test"), EVENTS_U_SQL),
    ("decentral_jump_uniform", EVENTS_U.but(fill="jump"), EVENTS_U_SQL),
):
    query(_name, _invariants_sql(_sql, 100))(lambda s, d, spec=_spec: invariants(s, "tail", spec, d))

_THRESHOLDS = f"""
WITH e AS ({EVENTS_SQL}), d AS (SELECT DISTINCT batch_no AS day FROM e),
r AS (SELECT day, batch_no, key, row_number() OVER (PARTITION BY day ORDER BY key, item_id) AS place FROM d JOIN e ON batch_no <= day),
t AS (SELECT day, max(key) FILTER (WHERE place = 100) AS threshold FROM r GROUP BY day)
"""


@query("per_batch_thresholds", f"{_THRESHOLDS} SELECT day AS batch_no, round(ln(threshold), 9) AS ln_threshold FROM t")
def _(s, d):
    return W.run(s, "tail", EVENTS, days(s, d)).report().select("batch_no", F.round(F.log("threshold_after"), 9).alias("ln_threshold"))


@query(
    "per_batch_candidates",
    f"{_THRESHOLDS}, n AS (SELECT batch_no, count(*) AS n FROM e GROUP BY batch_no) "
    "SELECT n.batch_no, n.n AS n_items, (SELECT count(*) FROM e WHERE e.batch_no = n.batch_no AND key <= coalesce((SELECT threshold FROM t WHERE t.day = n.batch_no - 1), 1e300)) AS candidates FROM n",
)
def _(s, d):
    return W.run(s, "tail", EVENTS, days(s, d)).report().select("batch_no", "n_items", "candidates")


@query("variable_size_bounds", f"WITH e AS ({EVENTS_SQL}) SELECT DISTINCT batch_no, true AS in_range, true AS bottom_set FROM e")
def _(s, d):
    df = read(s, d, "events")
    one = W.run(s, "lazy", EVENTS.but(k_max=200), days(s, d))
    seen = keyed(df, EVENTS).where(F.col("key") <= one.state.threshold).agg(F.count(F.lit(1))).first()[0]
    kept = one.sample().count()
    rows = one.report().select("batch_no", F.col("held_after").between(100, 200).alias("in_range"))
    return rows.withColumn("bottom_set", F.lit(bool(seen == kept == one.state.held)))


_DAYS = f"WITH e AS ({EVENTS_SQL}), n AS (SELECT batch_no, count(*) AS n FROM e GROUP BY 1), c AS (SELECT batch_no, n, sum(n) OVER (ORDER BY batch_no) AS seen FROM n)"


@query("variable_size_eager", f"{_DAYS} SELECT batch_no, n AS n_items, seen >= 100 AS in_range, seen > 100 AS selected FROM c")
def _(s, d):
    """The sample is brought into 100..200 in every batch."""
    rows = W.run(s, "eager", EVENTS.but(k_max=200), days(s, d)).report()
    return rows.select("batch_no", "n_items", F.col("held_after").between(100, 200).alias("in_range"), (F.col("jobs") > 1).alias("selected"))


@query("variable_against_exact", "SELECT true AS fewer_selections, true AS exact_selects_always, true AS sizes_in_range")
def _(s, d):
    """A sample of 100 to 200 against one of exactly 100 over all days: how often a threshold is selected."""
    lazy, exact = (W.run(s, m, EVENTS.but(k_max=200) if m == "lazy" else EVENTS, days(s, d)).reports.rows for m in ("lazy", "pivot8"))
    often = [sum(r.rounds > 0 for r in rows) for rows in (lazy, exact)]
    busy = sum(r.held_before + r.stored > 100 for r in exact)
    return s.createDataFrame([(often[0] < often[1], often[1] == busy, all(100 <= r.held_after <= 200 for r in lazy))], "fewer_selections boolean, exact_selects_always boolean, sizes_in_range boolean")


# selection ---------------------------------------------------------------------------------------------------------------------------


def _runs(s, d) -> DataFrame:
    """lineitem's keys, cached: each selector passes over them several times."""
    return keyed(read(s, d, "lineitem"), LINES).select("item_id", "w", "key").withColumn("pe", F.pmod(F.xxhash64("item_id"), F.lit(8)).cast("int"))


def _selected(name: str, selector: str, **options) -> None:
    def f(s, d):
        runs = _runs(s, d).persist()
        n = runs.count()
        got = S.select(selector, runs, 1000, n, **options)
        runs.unpersist()
        return s.createDataFrame([(got.item_id, got.rank, got.key)], "item_id string, rank long, key double").select("item_id", "rank", F.round(F.log("key"), 9).alias("ln_key"))

    query(name, f"SELECT item_id, draw_no AS rank, ln_key FROM ({bottom_sql(LINES_SQL, 1000)}) WHERE draw_no = 1000")(f)


_selected("select_pivot1", "pivot", d=1, finish=1)
_selected("select_pivot8", "pivot", d=8, finish=1)
_selected("select_two_pivot", "two_pivot")
_selected("select_combined", "combined")
_selected("select_unsorted", "unsorted")
_selected("select_sort", "sort")
_selected("select_tail", "tail")


@query("select_range", "SELECT true AS in_range, true AS rank_is_right")
def _(s, d):
    runs = _runs(s, d).persist()
    got = S.pivot_select(runs, 1000, 2000, runs.count(), 1)
    true = runs.where(S.up_to((got.key, got.item_id))).count()
    runs.unpersist()
    return s.createDataFrame([(1000 <= got.rank <= 2000, got.rank == true)], "in_range boolean, rank_is_right boolean")


# local reservoirs --------------------------------------------------------------------------------------------------------------------

_PE = f"SELECT *, l_orderkey % 8 AS pe FROM ({LINES_SQL})"


def _by_pe(s, d) -> DataFrame:
    return keyed(read(s, d, "lineitem"), LINES, "l_orderkey").select("item_id", "w", "key", (F.col("l_orderkey") % 8).alias("pe"))


@query("local_rank", f"SELECT pe, count(*) FILTER (WHERE key < 1e-6) AS rank FROM ({_PE}) GROUP BY pe")
def _(s, d):
    return localres.local_rank(_by_pe(s, d), 1e-6)


@query("local_kth", f"SELECT pe, item_id FROM (SELECT *, row_number() OVER (PARTITION BY pe ORDER BY key, item_id) AS place FROM ({_PE})) WHERE place = 50")
def _(s, d):
    return localres.local_kth(_by_pe(s, d), 50).select("pe", "item_id")


@query("local_split", f"SELECT pe, key <= 1e-6 AS low, count(*) AS n FROM ({_PE}) GROUP BY ALL")
def _(s, d):
    return localres.local_split(_by_pe(s, d), F.lit(1e-6)).groupBy("pe", "low").agg(F.count(F.lit(1)).alias("n"))


@query("local_join", bottom_sql(LINES_SQL, 100))
def _(s, d):
    rows = _by_pe(s, d)
    low, high = (localres.local_smallest(rows.where(c), 100) for c in ("pe < 4", "pe >= 4"))
    return shown(reservoir.merge(low, high, 100))


@query(
    "local_neighbours",
    f"SELECT pe, item_id, lag(item_id) OVER w AS before, lead(item_id) OVER w AS after FROM ({_PE}) WHERE key < 1e-6 WINDOW w AS (PARTITION BY pe ORDER BY key, item_id)",
)
def _(s, d):
    return localres.local_neighbours(_by_pe(s, d).where("key < 1e-6")).select("pe", "item_id", "before", "after")


@query("first_batch_cap", f"SELECT pe, least(count(*), 100) AS held FROM ({_PE}) GROUP BY pe")
def _(s, d):
    return localres.local_smallest(_by_pe(s, d), 100).groupBy("pe").agg(F.count(F.lit(1)).alias("held"))


# samples of samples ------------------------------------------------------------------------------------------------------------------


@query("stratified_bottom_k", bottom_sql(EVENTS_SQL, 20, True, "event_type"))
def _(s, d):
    return shown(reservoir.sample_by_group(read(s, d, "events"), EVENTS.but(k=20), "event_type"), True, "event_type")


@query("stratified_documents", bottom_sql(keyed_sql("documents", "doc_id", "n_chars", "lang"), 10, True, "lang"))
def _(s, d):
    return shown(reservoir.sample_by_group(read(s, d, "documents"), DOCS.but(k=10), "lang"), True, "lang")


@query("merge_samples", bottom_sql(keyed_sql("orders", "o_orderkey", "o_totalprice"), 100))
def _(s, d):
    df = read(s, d, "orders")
    halves = [reservoir.sample_once(df.where(F.col("o_orderkey") % 2 == r), ORDERS) for r in (0, 1)]
    return shown(reservoir.merge(*halves, 100))


@query(
    "sliding_window_sample",
    f"WITH e AS ({EVENTS_SQL}), d AS (SELECT DISTINCT batch_no AS window_end FROM e) "
    "SELECT window_end, item_id, draw_no, round(ln(key), 9) AS ln_key FROM (SELECT window_end, item_id, key, row_number() OVER (PARTITION BY window_end ORDER BY key, item_id) AS draw_no "
    "FROM d JOIN e ON batch_no BETWEEN window_end - 6 AND window_end) WHERE draw_no <= 100",
)
def _(s, d):
    return shown(windows.sliding_sample(read(s, d, "events"), EVENTS, DAY, 7), True, "window_end")


@query("tumbling_window_sample", f"SELECT cast(ts::date AS varchar) AS day, * EXCLUDE (ts, w, key), round(ln(key), 9) AS ln_key FROM (SELECT ts, item_id, w, key, row_number() OVER (PARTITION BY ts::date ORDER BY key, item_id) AS draw_no FROM ({EVENTS_SQL})) WHERE draw_no <= 5")
def _(s, d):
    rows = windows.window_sample(read(s, d, "events"), EVENTS.but(k=5), "1 day")
    return shown(rows.withColumn("day", F.to_date("window_start").cast("string")), True, "day")


# estimates ---------------------------------------------------------------------------------------------------------------------------


@query("inclusion_feasibility", "WITH t AS (SELECT sum(o_totalprice) AS total, count(*) * 7 // 10 AS k FROM orders) SELECT o_orderkey::varchar AS item_id, round(o_totalprice * k / total, 6) AS share FROM orders, t WHERE o_totalprice * k > total")
def _(s, d):
    rows = valid(items(read(s, d, "orders"), ORDERS))
    return estimate.inclusion_feasibility(rows, rows.count() * 7 // 10).select("item_id", F.round("share", 6).alias("share"))


def _with_threshold(s, d, df: DataFrame, spec: SamplerSpec, *payload: str) -> tuple[DataFrame, float]:
    sample = reservoir.sample_once(df, spec, *payload).persist()
    return sample, sample.agg(F.max("key")).first()[0]


_LINE_SAMPLE = f"s AS (SELECT * FROM ({LINES_SQL}) ORDER BY key, item_id LIMIT 1000), t AS (SELECT max(key) AS t FROM s), a AS (SELECT *, w / (1 - exp(-t * w)) AS x FROM s, t WHERE key < t)"


@query("subset_sum_estimate", f"WITH {_LINE_SAMPLE} SELECT round(sum(x) / 1000, 3) AS thousands, count(*) AS rows_used FROM a WHERE l_returnflag = 'R'")
def _(s, d):
    sample, t = _with_threshold(s, d, read(s, d, "lineitem"), LINES, "l_returnflag")
    return estimate.subset_sum(sample, t, F.col("l_returnflag") == "R").select(F.round(F.col("estimate") / 1000, 3).alias("thousands"), "rows_used")


@query("heavy_hitters", f"WITH {_LINE_SAMPLE}, g AS (SELECT l_returnflag, sum(x) AS e FROM a GROUP BY 1) SELECT l_returnflag, round(e / (SELECT sum(e) FROM g), 9) AS share FROM g WHERE e >= 0.1 * (SELECT sum(e) FROM g)")
def _(s, d):
    sample, t = _with_threshold(s, d, read(s, d, "lineitem"), LINES, "l_returnflag")
    return estimate.heavy_hitters(sample, t, "l_returnflag", 0.1).select("l_returnflag", F.round("share", 9).alias("share"))


@query("count_track", f"WITH s AS (SELECT * FROM ({EVENTS_U_SQL}) ORDER BY key, item_id LIMIT 100) SELECT round(99 / max(key), 6) AS estimate FROM s")
def _(s, d):
    sample, t = _with_threshold(s, d, read(s, d, "events"), EVENTS_U)
    return estimate.count_track(sample, t).select(F.round("estimate", 6).alias("estimate"))


# cost measures over parameters --------------------------------------------------------------------------------------------------------

#: Streams: the items of lineitem by return flag, n of each; under several sample sizes (at most n), partitions and batches.
_CONFIGS = "(VALUES (1000, 8, 1000), (1000, 8, 100), (500, 4, 500), (2500, 4, 2500)) AS g(k, p, b)"
_GRID = f"(SELECT l_returnflag AS stream, n, least(k, n)::bigint AS k, p::bigint AS p, b::bigint AS b FROM (SELECT l_returnflag, count(*) AS n FROM ({LINES_SQL}) GROUP BY 1), {_CONFIGS})"


def _grid(s, d) -> DataFrame:
    by = valid(items(read(s, d, "lineitem"), LINES, "l_returnflag")).groupBy(F.col("l_returnflag").alias("stream")).agg(F.count(F.lit(1)).alias("n"))
    configs = s.sql(f"SELECT cast(k AS bigint) k, cast(p AS bigint) p, cast(b AS bigint) b FROM {_CONFIGS}")
    return by.crossJoin(F.broadcast(configs)).withColumn("k", F.least("k", "n"))


def _args() -> list:
    return [F.col(c) for c in "nkpb"]


@query(
    "expected_insertions",
    "SELECT stream, n, k, p, b, round(CASE WHEN n >= p * b THEN b ELSE 0 END + coalesce((SELECT sum(least(b::double, k::double / (i * p))) FROM generate_series(1, (n // (p * b) - 1)::bigint) AS s(i)), 0), 3) AS expected, "
    f"round(k / p * (1 + ln(n / k)), 6) AS shape FROM {_GRID}",
)
def _(s, d):
    return _grid(s, d).select("stream", "n", "k", "p", "b", F.round(cost.columns_expected(*_args()), 3).alias("expected"), F.round(cost.columns_shape(*_args()[:3]), 6).alias("shape"))


@query("max_insertions_bound", f"SELECT stream, n, k, p, round(m + sqrt(2 * m * ln(p)), 6) AS bound FROM (SELECT *, k / p * (1 + ln(n / k)) AS m FROM {_GRID})")
def _(s, d):
    return _grid(s, d).select("stream", "n", "k", "p", F.round(cost.columns_max(*_args()[:3]), 6).alias("bound"))


@query(
    "collective_cost",
    f"WITH n AS (SELECT batch_no, count(*) FILTER (WHERE key < 1e-3)::double AS words FROM ({EVENTS_SQL}) GROUP BY 1) "
    "SELECT batch_no, kind, words, p::bigint AS p, round(0.5 * words * CASE WHEN kind = 'gather' THEN p ELSE 1 END + 100 * log2(p), 6) AS cost "
    "FROM n, (VALUES ('broadcast'), ('reduce'), ('all_reduce'), ('gather')) AS a(kind), (VALUES (2), (16), (256)) AS c(p)",
)
def _(s, d):
    """What the candidates of each day would cost as one message, by kind of exchange and number of partitions."""
    rows = keyed(read(s, d, "events").withColumn("batch_no", F.expr(DAY).cast("long")), EVENTS, "batch_no")
    words = rows.groupBy("batch_no").agg(F.count_if(F.col("key") < 1e-3).cast("double").alias("words"))
    ways = words.select("*", F.explode(F.array(*map(F.lit, cost.COLLECTIVES))).alias("kind")).select("*", F.explode(F.array(*(F.lit(p).cast("long") for p in _PES))).alias("p"))
    return ways.select("batch_no", "kind", "words", "p", F.round(cost.columns_collective(F.col("kind"), F.col("words"), F.col("p"), 100.0, 0.5), 6).alias("cost"))


_PES = (2, 16, 256)


@query(
    "predict_cost",
    f"WITH e AS ({keyed_sql('lineitem', LINE_SQL, 'l_extendedprice', 'l_orderkey, l_linenumber')}), "
    "c AS (SELECT l_linenumber::bigint AS batch_no, p::bigint AS p, l_orderkey % p AS pe, count(*) AS n, count(*) FILTER (WHERE key <= 1e-7) AS c FROM e, (VALUES (2), (16), (256)) AS c(p) GROUP BY ALL), "
    "m AS (SELECT batch_no, p, max(n) AS b, max(c) AS b_star, log2(1000 + max(c)) AS lg FROM c GROUP BY ALL) "
    "SELECT batch_no, p, b, b_star, round(b + (b_star + 1) * lg + 8 * lg + 4 + 100 * log2(p), 6) AS pivot8, round(b + (b_star + 1) * lg + log2(1000 * p) * lg + 100 * pow(log2(1000 * p), 2), 6) AS general, "
    "round((b_star + 1) * lg + 8 * lg + 4 + 100 * log2(p), 6) AS uniform FROM m",
)
def _(s, d):
    """Predicted time of each batch, from the items and the candidates of its busiest partition. Batches are line numbers, partitions orders."""
    rows = keyed(read(s, d, "lineitem"), LINES, "l_orderkey", "l_linenumber")
    finest = rows.groupBy(F.col("l_linenumber").cast("long").alias("batch_no"), (F.col("l_orderkey") % max(_PES)).alias("pe")).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("key") <= 1e-7).alias("c"))
    each = finest.withColumn("p", F.explode(F.array(*(F.lit(p).cast("long") for p in _PES)))).groupBy("batch_no", "p", F.pmod("pe", "p").alias("pe")).agg(F.sum("n").alias("n"), F.sum("c").alias("c"))
    work = each.groupBy("batch_no", "p").agg(F.max("n").alias("b"), F.max("c").alias("b_star")).collect()  # a row for each batch and p
    more = {"k": 1000, "alpha": 100.0, "beta": 0.5}
    times = [tuple(round(cost.predict("pivot", b=r["b"], b_star=r["b_star"], p=r["p"], **more, **how), 6) for how in ({}, {"select": "pivot"}, {"weighted": False})) for r in work]
    return s.createDataFrame([(*r, *t) for r, t in zip(work, times, strict=True)], "batch_no long, p long, b long, b_star long, pivot8 double, general double, uniform double")


@query("compare_methods", f"{_DAYS} SELECT run, count(*) AS batches, sum(n)::bigint AS n_items, 100::bigint AS held, CASE WHEN run = 'gather' THEN 0 ELSE 1 END::bigint AS rows_stay FROM c, (VALUES ('pivot1'), ('pivot8'), ('gather')) AS m(run) GROUP BY run")
def _(s, d):
    rows = W.compare(s, read(s, d, "events"), EVENTS, DAY)
    return rows.groupBy("run").agg(F.count(F.lit(1)).alias("batches"), F.sum("n_items").alias("n_items"), F.max_by("held_after", "batch_no").alias("held"), (F.sum("rows_moved") <= F.count_if(F.col("rounds") > 0)).cast("long").alias("rows_stay"))


@query("compare_methods_times")
def _(s, d):
    return W.summary(W.compare(s, read(s, d, "events"), EVENTS, f"{DAY} DIV 5"))


def _scaling_sql(runs: list[tuple[int, int]], ks: tuple[int, ...]) -> str:
    cfg, k = ", ".join(f"({p}, {n})" for p, n in runs), ", ".join(f"({x})" for x in ks)
    return f"""WITH e AS (SELECT key, item_id, ub FROM ({keyed_sql('lineitem', LINE_SQL, 'l_extendedprice', unit_sql('lineitem', LINE_SQL, 'batch') + ' AS ub')})),
a AS (SELECT p, batches, least(floor(ub * batches), batches - 1)::bigint AS batch_no, key, item_id FROM e, (VALUES {cfg}) AS c(p, batches)),
n AS (SELECT p, batches, batch_no, count(*) AS n, sum(count(*)) OVER (PARTITION BY p, batches ORDER BY batch_no) AS seen FROM a GROUP BY p, batches, batch_no),
r AS (SELECT n.p, n.batches, n.batch_no, a.key, row_number() OVER (PARTITION BY n.p, n.batches, n.batch_no ORDER BY a.key, a.item_id) AS place
  FROM n JOIN a ON a.p = n.p AND a.batches = n.batches AND a.batch_no < n.batch_no),
t AS (SELECT p, batches, batch_no, place AS k, key AS threshold FROM r WHERE place IN ({', '.join(map(str, ks))})),
g AS (SELECT n.*, k, threshold FROM (SELECT n.*, k FROM n, (VALUES {k}) AS v(k)) n LEFT JOIN t USING (p, batches, batch_no, k)),
c AS (SELECT g.p, g.batches, g.batch_no, g.k, g.n, g.seen, count(*) AS candidates FROM g JOIN a ON a.p = g.p AND a.batches = g.batches AND a.batch_no = g.batch_no AND a.key <= coalesce(g.threshold, 1e300) GROUP BY ALL)
SELECT run, p::bigint AS p, k::bigint AS k, batch_no, n AS n_items, candidates, least(k, seen)::bigint AS held_after FROM c, (VALUES ('pivot1'), ('pivot8'), ('gather')) AS m(run)"""


_WEAK, _STRONG, _KS = [(1, 4), (2, 2), (4, 1)], [(1, 3), (4, 3)], (25, 2500)


def _scaled(s, d, runs, ks) -> DataFrame:
    rows = W.scaling(s, read(s, d, "lineitem"), LINES, runs, ks)
    return rows.select("run", F.col("p").cast("long").alias("p"), F.col("k").cast("long").alias("k"), "batch_no", "n_items", "candidates", "held_after")


@query("weak_scaling", _scaling_sql(_WEAK, _KS))
def _(s, d):
    """A batch grows with the partitions: 1, 2 and 4 of them, a quarter of the table for each."""
    return _scaled(s, d, _WEAK, _KS)


@query("strong_scaling", _scaling_sql(_STRONG, _KS))
def _(s, d):
    """Batches of a third of the table, on one and four partitions."""
    return _scaled(s, d, _STRONG, _KS)


@query("scaling_times")
def _(s, d):
    """Speedup over pivot1 on one partition, throughput, phases, and what eight pivots save, by method: the figures behind both scaling workloads."""
    return W.scaling_summary(W.scaling(s, read(s, d, "lineitem"), LINES, [(1, 4), (4, 1), (1, 2), (4, 2)], (2500,)))


@query("depth_by_pivots", f"SELECT pivots, round(ln(t), 9) AS ln_threshold, true AS more_pivots_fewer_rounds FROM (VALUES (1), (2), (4), (8), (16), (32)) AS v(pivots), (SELECT max(key) AS t FROM (SELECT key FROM ({LINES_SQL}) ORDER BY key, item_id LIMIT 1000))")
def _(s, d):
    got = _depths(s, d)
    deep = dict((p, r) for p, r, _ in got)
    return s.createDataFrame([(p, t, deep[32] <= deep[8] <= deep[1]) for p, _, t in got], "pivots int, t double, more_pivots_fewer_rounds boolean").select("pivots", F.round(F.log("t"), 9).alias("ln_threshold"), "more_pivots_fewer_rounds")


def _depths(s, d) -> list[tuple[int, float, float]]:
    return W.depth_by_pivots(s, W.sliced(read(s, d, "lineitem"), W.LINE_ID, 6), LINES, "slice")


@query("candidates_moved", f"{_THRESHOLDS}, n AS (SELECT batch_no, count(*) AS n FROM e GROUP BY batch_no), "
    "c AS (SELECT n.batch_no, (SELECT count(*) FROM e WHERE e.batch_no = n.batch_no AND key <= coalesce((SELECT threshold FROM t WHERE t.day = n.batch_no - 1), 1e300)) AS candidates FROM n) "
    "SELECT batch_no, candidates, true AS moves_new_ones_only FROM c")  # fmt: skip
def _(s, d):
    """The incremental combined selector: up to k new candidates, no rough step, and no other rows move but the sample of pivots and the few between them."""
    rows = W.run(s, "incremental", EVENTS, days(s, d)).report()
    small = (F.col("held_before") == 0) | (F.col("rows_moved") - F.col("stored") <= 2 * (F.col("held_before") + F.col("stored")))
    return rows.select("batch_no", "candidates", small.alias("moves_new_ones_only"))


@query("turnover_expected", f"{_DAYS} SELECT batch_no, n AS n_items, round(CASE WHEN seen - n < 100 THEN n ELSE n * 100.0 / (seen - n) END, 6) AS expected, true AS near FROM c")
def _(s, d):
    """Candidates of each day beside their expectation: every item enters with chance k over the items before."""
    rows = W.run(s, "tail", EVENTS, days(s, d)).reports.rows
    out, seen, total, real = [], 0, 0.0, 0
    for r in rows:
        expected = r.n_items * cost.insert_probability(100, seen)
        out.append((r.batch_no, r.n_items, round(expected, 6)))
        seen, total, real = seen + r.n_items, total + expected, real + r.candidates
    near = abs(real - total) < 6 * total**0.5 + 0.05 * total
    return s.createDataFrame(out, "batch_no long, n_items long, expected double").withColumn("near", F.lit(bool(near)))


# first batch, blocks, imbalance --------------------------------------------------------------------------------------------------------


@query("first_batch_held", "SELECT capped, count(*) AS n_items, true AS bounded, 100::bigint AS held FROM lineitem, (VALUES (true), (false)) AS v(capped) GROUP BY capped")
def _(s, d):
    """One batch far above k, with and without the local cap: rows written are at most k a partition with it."""
    df, out = read(s, d, "lineitem").repartition(6), []
    for cap in (True, False):
        one = W.run(s, "", LINES.but(k=100), [(0, df)], reservoir.DecentralSampler(s, LINES.but(k=100, cap=cap)))
        r = one.reports.rows[0]
        out.append((cap, r.n_items, r.stored <= 600 if cap else r.stored == r.n_items, r.held_after))
    return s.createDataFrame(out, "capped boolean, n_items long, bounded boolean, held long")


@query("block_sizes", "SELECT block, count(*) AS n_items, true AS larger_blocks_look_at_more, true AS uniform_looks_at_hits_only FROM lineitem, (VALUES (1), (32), (1024)) AS v(block) GROUP BY block")
def _(s, d):
    """Weights looked at one by one, and blocks passed over, by block size; a uniform sample looks at hits only."""
    got = _block_figures(s, d)
    weighted = {b: x for kind, b, _, x, _ in got if kind == "weighted"}
    ordered = weighted[1] <= weighted[32] <= weighted[1024]
    hits = all(x < n * 0.05 for kind, _, n, x, _ in got if kind == "uniform")
    return s.createDataFrame([(b, n, ordered, hits) for kind, b, n, _, _ in got if kind == "weighted"], "block int, n_items long, larger_blocks_look_at_more boolean, uniform_looks_at_hits_only boolean")


def _block_figures(s, d) -> list[tuple[str, int, int, int, int]]:
    """(kind, block, items, looked at, blocks passed over) of one fill under a threshold that lets about k items in."""
    df, out = read(s, d, "lineitem"), []
    for kind, spec, t in (("weighted", LINES, 1e-7), ("uniform", LINES.but(weight=None), 1e-2)):
        for block in (1, 32, 1024) if kind == "weighted" else (32,):
            rows = reservoir.candidates_by_jump(valid(items(df, spec)), spec.but(block=block), t, 1, counted=True)
            x, skipped = rows.agg(F.sum("examined"), F.sum("skipped")).first()
            out.append((kind, block, df.count(), x, skipped))
    return out


@query("block_figures")
def _(s, d):
    return s.createDataFrame(_block_figures(s, d), "kind string, block int, n_items long, rows_examined long, blocks_skipped long")


@query("uniform_against_weighted", f"{_DAYS} SELECT batch_no, n AS n_items, true AS uniform_examines_fewer FROM c")
def _(s, d):
    """Rows looked at by jumps over all days: the weighted sampler needs all weights, the uniform one its hits."""
    w, u = (W.run(s, "tail", spec.but(fill="jump"), days(s, d)).reports.rows for spec in (EVENTS, EVENTS_U))
    fewer = sum(r.rows_examined for r in u[1:]) < sum(r.n_items for r in w[1:]) / 2
    return s.createDataFrame([(r.batch_no, r.n_items, fewer) for r in w], "batch_no long, n_items long, uniform_examines_fewer boolean")


for _name, _shape in (
    ("lopsided_batches", lambda df: W.lopsided(df, 6)),
    ("sorted_batches", lambda df: df.repartitionByRange(6, "l_extendedprice").sortWithinPartitions("l_extendedprice")),
    ("falling_batches", lambda df: df.repartitionByRange(6, F.desc("l_extendedprice")).sortWithinPartitions(F.desc("l_extendedprice"))),
):

    def _f(s, d, shape=_shape):
        cut = replay(W.sliced(read(s, d, "lineitem"), W.LINE_ID, 3), "slice", None, reservoir.storage(s))
        return shown(W.run(s, "pivot8", LINES, ((b, shape(rows)) for b, rows in cut)).sample())

    query(_name, bottom_sql(LINES_SQL, 1000))(_f)


@query("busiest_partition", "SELECT true AS lopsided_is_busier, true AS within_total")
def _(s, d):
    """Candidates of the busiest partition, even and lopsided: only balance suffers."""
    df, most = read(s, d, "lineitem"), []
    for rows in (df.repartition(6), W.lopsided(df, 6)):
        one = W.run(s, "tail", LINES, ((b, x) for b, x in enumerate((rows, rows.withColumn("l_cents", F.col("l_cents") + 10**9)))))
        most.append(one.reports.rows[1])
    return s.createDataFrame([(most[1].candidates_max_pe > most[0].candidates_max_pe, all(r.candidates_max_pe <= r.candidates for r in most))], "lopsided_is_busier boolean, within_total boolean")


@query(
    "drift_replay",
    f"WITH i AS (SELECT {LINE_SQL} AS item_id, l_orderkey % 8 AS pe, l_linenumber AS b FROM lineitem), "
    f"w AS (SELECT item_id, greatest(0.01, b + pe + sqrt(-2 * ln({unit_sql('lineitem', 'item_id', 'n1')})) * cos(2 * pi() * {unit_sql('lineitem', 'item_id', 'n2')})) AS w FROM i), "
    f"k AS (SELECT item_id, -ln({unit_sql('lineitem', 'item_id')}) / w AS key FROM w) SELECT item_id FROM k ORDER BY key, item_id LIMIT 1000",
)
def _(s, d):
    """A sampler over batches whose weights grow with the batch and the partition."""
    df = read(s, d, "lineitem").withColumn("item_id", V.item_id(W.LINE_ID))
    df = df.withColumn("w_drift", W.drifting_weight("l_linenumber", "l_orderkey % 8", "lineitem", 7))
    cut = replay(df.select("item_id", "w_drift", "l_linenumber"), "l_linenumber", None, reservoir.storage(s))
    return W.run(s, "pivot8", LINES.but(id_cols=("item_id",), weight="w_drift"), cut).sample().select("item_id")


@query("state_goes_on", bottom_sql(EVENTS_SQL, 100))
def _(s, d):
    """The sampler is made anew from its files after each ten days."""
    path, one = reservoir.storage(s), None
    for number, rows in days(s, d):
        if one is None or number % 10 == 0:
            one = reservoir.DecentralSampler(s, EVENTS, path)
        one.process(rows, number)
    return shown(reservoir.DecentralSampler(s, EVENTS, path).sample())


@query("state_versions", f"{_THRESHOLDS}, c AS (SELECT batch_no, count(*) AS n, sum(count(*)) OVER (ORDER BY batch_no) AS seen FROM e GROUP BY 1) SELECT batch_no AS version, seen::bigint AS n_seen, least(100, seen)::bigint AS held, round(ln(threshold), 9) AS ln_threshold FROM c JOIN t ON t.day = c.batch_no")
def _(s, d):
    one = W.run(s, "tail", EVENTS, days(s, d))
    return one.log.table().select("version", "n_seen", "held", F.round(F.log("threshold"), 9).alias("ln_threshold"))


@query("subset_sum_error", f"WITH {_LINE_SAMPLE} SELECT l_returnflag, true AS near FROM a GROUP BY 1")
def _(s, d):
    """Estimated against true totals by return flag: within five standard errors, about 1 / sqrt(rows used)."""
    df = read(s, d, "lineitem")
    sample, t = _with_threshold(s, d, df, LINES, "l_returnflag")
    true = {r[0]: r[1] for r in df.where("l_extendedprice > 0").groupBy("l_returnflag").agg(F.sum("l_extendedprice")).collect()}
    out = []
    for flag, total in true.items():
        got = estimate.subset_sum(sample, t, F.col("l_returnflag") == flag).first()
        out.append((flag, bool(estimate.relative_error(got["estimate"], total) < 5 / max(1, got["rows_used"]) ** 0.5)))
    return s.createDataFrame(out, "l_returnflag string, near boolean")


# jumps -------------------------------------------------------------------------------------------------------------------------------


def _drawn(rows: DataFrame, real: DataFrame, threshold: float | None, expected: F.Column) -> DataFrame:
    """What holds for drawn samples: items of the table, each once, keys below the threshold, and about as many as expected (one row)."""
    known = rows.join(real.select("item_id").distinct(), "item_id", "left_semi").agg(F.count(F.lit(1)).alias("known"))
    below = F.max("key") <= threshold if threshold else F.max("key") > 0
    total = rows.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("item_id").alias("ids"), below.alias("keys_below"))
    law = real.agg(F.sum(expected).alias("expected"))
    near = F.abs(F.col("n") - F.col("expected")) <= 6 * F.sqrt("expected") + 1
    return total.crossJoin(F.broadcast(known)).crossJoin(F.broadcast(law)).select(((F.col("n") == F.col("ids")) & (F.col("n") == F.col("known"))).alias("once_each"), "keys_below", near.alias("as_many_as_expected"))


_SOUND = "SELECT true AS once_each, true AS keys_below, true AS as_many_as_expected"


for _name, _spec, _sql in (("sequential_weighted", EVENTS, EVENTS_SQL), ("sequential_uniform", EVENTS_U, EVENTS_U_SQL)):

    def _f(s, d, spec=_spec):
        df = read(s, d, "events")
        got = reservoir.sequential_sample(df, spec)
        return _drawn(got, valid(items(df, spec)), None, F.lit(0)).select("once_each", "keys_below").crossJoin(F.broadcast(got.agg(F.count(F.lit(1)).alias("n"))))

    query(_name, f"SELECT true AS once_each, true AS keys_below, least(100, count(*))::bigint AS n FROM ({_sql})")(_f)


@query("skip_weighted", _SOUND)
def _(s, d):
    real = valid(items(read(s, d, "lineitem"), LINES))
    return _drawn(reservoir.candidates_by_jump(real, LINES, 1e-6, 1), real, 1e-6, -F.expm1(-F.col("w") * 1e-6))


@query("skip_uniform", _SOUND)
def _(s, d):
    real = items(read(s, d, "events"), EVENTS_U)
    return _drawn(reservoir.candidates_by_jump(real, EVENTS_U, 0.01, 1), real, 0.01, F.lit(0.01))


@query("skip_weighted_rows")
def _(s, d):
    return reservoir.candidates_by_jump(valid(items(read(s, d, "lineitem"), LINES)), LINES, 1e-6, 1)


_PLAIN_LINES = LINES.but(id_cols=("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"))


@query("manifest_blocks", "SELECT count(*) AS n, round(sum(l_extendedprice) / 1000, 3) AS thousands, ceil(count(*) / 4096)::bigint AS blocks FROM lineitem WHERE l_extendedprice > 0")
def _(s, d):
    got = manifest.build(s, f"{d}/lineitem.parquet", _PLAIN_LINES)
    return got.agg(F.sum("n").alias("n"), F.round(F.sum("weight") / 1000, 3).alias("thousands"), F.count(F.lit(1)).alias("blocks"))


@query("manifest_sample", _SOUND.replace("once_each", "of_the_table").replace("true AS as_many_as_expected", "true AS as_many_as_expected"))
def _(s, d):
    """Items below the threshold from the blocks that the manifest's sums of weight pick."""
    path, t = f"{d}/lineitem.parquet", 1e-6
    real = valid(items(s.read.parquet(path), _PLAIN_LINES))
    got = manifest.sample_from_manifest(s, path, manifest.build(s, path, _PLAIN_LINES), _PLAIN_LINES, t).persist()
    known = got.join(real.select("item_id").distinct(), "item_id", "left_semi").count() == got.count()
    return _drawn(got, real, t, -F.expm1(-F.col("w") * t)).select(F.lit(known).alias("of_the_table"), "keys_below", "as_many_as_expected")


@query("manifest_sample_rows")
def _(s, d):
    path = f"{d}/lineitem.parquet"
    return manifest.sample_from_manifest(s, path, manifest.build(s, path, _PLAIN_LINES), _PLAIN_LINES, 1e-8)


@query("manifest_reads", "SELECT 30::bigint AS files, true AS reads_fewer, true AS bytes_are_fewer")
def _(s, d):
    """A table of 30 files, a small threshold: files and bytes that are read at all."""
    path = reservoir.storage(s)
    read(s, d, "lineitem").repartitionById(30, F.pmod(F.xxhash64("l_orderkey"), F.lit(30)).cast("int")).write.parquet(path)
    blocks = manifest.build(s, path, LINES)
    total = blocks.agg(F.sum("weight")).first()[0]
    got = manifest.what_is_read(blocks, LINES, 3 / total)
    return got.select("files", (F.col("files_read") < 15).alias("reads_fewer"), (F.col("bytes_read") < F.col("file_bytes") / 2).alias("bytes_are_fewer"))


@query("manifest_positions", "SELECT true AS places_in_blocks, true AS as_many_as_expected, true AS once_each")
def _(s, d):
    """Places of a uniform sample's rows, from row counts alone."""
    blocks = manifest.build(s, f"{d}/events.parquet", EVENTS_U)
    got = manifest.uniform_positions(blocks, 0.05, 7).persist()
    n = blocks.agg(F.sum("n")).first()[0]
    inside = got.join(blocks, ["file", "block"]).where("place < n").count()
    count = got.count()
    return s.createDataFrame([(inside == count, abs(count - 0.05 * n) <= 6 * (0.05 * n) ** 0.5 + 1, got.distinct().count() == count)], "places_in_blocks boolean, as_many_as_expected boolean, once_each boolean")


# around a sample ---------------------------------------------------------------------------------------------------------------------

_ORDER_SAMPLE = f"(SELECT * FROM ({keyed_sql('orders', 'o_orderkey', 'o_totalprice', 'o_orderkey')}) ORDER BY key, item_id LIMIT 100)"


def _orders(s, d) -> DataFrame:
    return reservoir.sample_once(read(s, d, "orders"), ORDERS, "o_orderkey")


@query("sample_payload_join", f"SELECT o.o_orderkey, o_orderpriority, c_mktsegment, n_name FROM orders o JOIN {_ORDER_SAMPLE} s USING (o_orderkey) JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey")
def _(s, d):
    full = read(s, d, "orders").join(F.broadcast(_orders(s, d).select("o_orderkey")), "o_orderkey")
    named = full.join(read(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return named.select("o_orderkey", "o_orderpriority", "c_mktsegment", "n_name")


@query("sample_semi_join", f"SELECT l_returnflag, count(*) AS n FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM {_ORDER_SAMPLE}) GROUP BY 1")
def _(s, d):
    lines = read(s, d, "lineitem").join(F.broadcast(_orders(s, d).select(F.col("o_orderkey").alias("l_orderkey"))), "l_orderkey", "left_semi")
    return lines.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@query("labelled_anti_join", bottom_sql("SELECT * FROM (" + keyed_sql("documents", "doc_id", "n_chars", "doc_id") + ") WHERE doc_id NOT IN (SELECT doc_id FROM labels)", 50))
def _(s, d):
    rest = read(s, d, "documents").join(read(s, d, "labels").select("doc_id"), "doc_id", "left_anti")
    return shown(reservoir.sample_once(rest, DOCS))


@query(
    "turnover_full_join",
    f"WITH e AS ({EVENTS_SQL}), a AS (SELECT item_id FROM e WHERE batch_no < 15 ORDER BY key, item_id LIMIT 100), b AS (SELECT item_id FROM e ORDER BY key, item_id LIMIT 100) "
    "SELECT coalesce(a.item_id, b.item_id) AS item_id, CASE WHEN a.item_id IS NULL THEN 'entered' WHEN b.item_id IS NULL THEN 'left' ELSE 'kept' END AS what FROM a FULL JOIN b ON a.item_id = b.item_id",
)
def _(s, d):
    df = read(s, d, "events")
    old, new = (reservoir.sample_once(x, EVENTS).select("item_id", F.lit(1).alias(n)) for x, n in ((df.where(f"{DAY} < 15"), "old"), (df, "new")))
    what = F.when(F.col("old").isNull(), "entered").when(F.col("new").isNull(), "left").otherwise("kept")
    return old.join(new, "item_id", "full").select("item_id", what.alias("what"))


def _event_sample(s, d, k: int = 100) -> DataFrame:
    return reservoir.sample_once(read(s, d, "events"), EVENTS.but(k=k), "event_type", "user_id", "ts").withColumn("day", F.to_date("ts").cast("string"))


_EVENT_SAMPLE = f"(SELECT *, cast(ts::date AS varchar) AS day FROM ({EVENTS_SQL}) ORDER BY key, item_id LIMIT 100)"


@query("sample_cube", f"SELECT event_type, day, count(*) AS n FROM {_EVENT_SAMPLE} GROUP BY CUBE (event_type, day)")
def _(s, d):
    return _event_sample(s, d).cube("event_type", "day").agg(F.count(F.lit(1)).alias("n"))


@query("sample_rollup", f"SELECT event_type, day, count(*) AS n FROM {_EVENT_SAMPLE} GROUP BY ROLLUP (event_type, day)")
def _(s, d):
    return _event_sample(s, d).rollup("event_type", "day").agg(F.count(F.lit(1)).alias("n"))


@query("sample_grouping_sets", f"SELECT event_type, day, count(*) AS n FROM {_EVENT_SAMPLE} GROUP BY GROUPING SETS ((event_type), (day))")
def _(s, d):
    return _event_sample(s, d).groupingSets([["event_type"], ["day"]], "event_type", "day").agg(F.count(F.lit(1)).alias("n"))


@query("sample_distinct_users", f"SELECT event_type, count(DISTINCT user_id) AS users FROM {_EVENT_SAMPLE} GROUP BY 1")
def _(s, d):
    return _event_sample(s, d).groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query("interval_join_after_sample", f"SELECT s.item_id, count(*) AS n FROM {_EVENT_SAMPLE} s JOIN events e ON e.user_id = s.user_id AND e.ts >= s.ts AND e.ts <= s.ts + INTERVAL 1 HOUR GROUP BY 1")
def _(s, d):
    one = _event_sample(s, d).select("item_id", F.col("user_id").alias("u"), F.col("ts").alias("t"))
    e = read(s, d, "events").select("user_id", "ts")
    near = e.join(F.broadcast(one), (F.col("user_id") == F.col("u")) & (F.col("ts") >= F.col("t")) & (F.col("ts") <= F.col("t") + F.expr("INTERVAL 1 HOUR")))
    return near.groupBy("item_id").agg(F.count(F.lit(1)).alias("n"))


@query("asof_threshold", f"{_THRESHOLDS} SELECT e.item_id, round(ln(t.threshold), 9) AS ln_threshold FROM e JOIN t ON t.day = e.batch_no - 1 WHERE e.key < 1e-3")
def _(s, d):
    """The threshold in force when an event came: the last report row before its day, by a window over both."""
    df = read(s, d, "events")
    steps = W.run(s, "tail", EVENTS, days(s, d)).report().select((F.col("batch_no") + 1).alias("day"), F.lit(0).alias("kind"), F.lit(None).cast("string").alias("item_id"), "threshold_after")
    rows = keyed(df.withColumn("day", F.expr(DAY).cast("long")), EVENTS, "day").where("key < 1e-3").select("day", F.lit(1).alias("kind"), "item_id", F.lit(None).cast("double").alias("threshold_after"))
    # the lookup is by day; a day's rows follow its one report row
    by_day = Window.partitionBy("day").orderBy("kind")
    joined = steps.unionByName(rows).withColumn("threshold", F.last("threshold_after", ignorenulls=True).over(by_day))
    return joined.where("kind = 1 AND threshold IS NOT NULL").select("item_id", F.round(F.log("threshold"), 9).alias("ln_threshold"))


@query("threshold_by_percentile")
def _(s, d):
    """An estimate of the threshold only, by the built-in sketch, beside the exact one."""
    rows = keyed(read(s, d, "lineitem"), LINES)
    n = rows.count()
    return rows.agg(F.percentile_approx("key", 1000 / n, 100_000).alias("sketched")).crossJoin(F.broadcast(reservoir.sample_once(read(s, d, "lineitem"), LINES).agg(F.max("key").alias("exact"))))


@query("builtin_bernoulli_sample")
def _(s, d):
    """The engine's own sampling, for contrast: neither weighted nor of fixed size."""
    return read(s, d, "events").sample(0.01, seed=7).select("event_id")


# streams -----------------------------------------------------------------------------------------------------------------------------


@query("stream_foreach_batch", bottom_sql(EVENTS_SQL, 100))
def _(s, d):
    return shown(stream.StreamSampler(s, EVENTS).run(stream.table_stream(s, d, "events")))


@query("stream_tumbling_sample", f"SELECT day, item_id, round(ln(key), 9) AS ln_key FROM (SELECT cast(ts::date AS varchar) AS day, item_id, key, row_number() OVER (PARTITION BY ts::date ORDER BY key, item_id) AS r FROM ({EVENTS_SQL})) WHERE r <= 5")
def _(s, d):
    rows = stream.stream_window_sample(stream.table_stream(s, d, "events"), EVENTS.but(k=5), "1 day")
    return rows.select(F.to_date("window_start").cast("string").alias("day"), "item_id", F.round(F.log("key"), 9).alias("ln_key"))


@query(
    "session_sample",
    f"WITH e AS ({EVENTS_SQL}), q AS (SELECT *, CASE WHEN epoch(ts)::bigint - epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, item_id))::bigint <= 1800 THEN 0 ELSE 1 END AS fresh FROM e), "
    "n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, item_id)::bigint AS session_no FROM q) "
    "SELECT user_id, session_no, item_id, draw_no FROM (SELECT *, row_number() OVER (PARTITION BY user_id, session_no ORDER BY key, item_id) AS draw_no FROM n) WHERE draw_no <= 2",
)
def _(s, d):
    return stream.session_sample(read(s, d, "events"), EVENTS.but(k=2), "user_id", 30).select("user_id", "session_no", "item_id", F.col("draw_no").cast("long").alias("draw_no"))


@query("stream_state_shards", f"SELECT item_id, round(ln(key), 9) AS ln_key FROM ({EVENTS_SQL}) ORDER BY key, item_id LIMIT 100")
def _(s, d):
    return stream.stream_shard_sample(stream.table_stream(s, d, "events"), EVENTS).select("item_id", F.round(F.log("key"), 9).alias("ln_key"))


# other weights ------------------------------------------------------------------------------------------------------------------------


def _weighted_by(df: DataFrame, spec: SamplerSpec, weight) -> DataFrame:
    """A sample whose weights are derived from the items."""
    rows = items(df, spec).withColumn("w", weight)
    u = V.uniform_key(F.col("item_id"), spec.stream_id, spec.seed)
    return reservoir.bottom_k(valid(rows).withColumn("key", V.exp_key(u, F.col("w"))), spec.k)


_U_LINE = unit_sql("lineitem", "item_id")


@query(
    "uniform_weight_sample",
    f"WITH i AS (SELECT {LINE_SQL} AS item_id FROM lineitem), k AS (SELECT item_id, -ln({_U_LINE}) / (100 * {unit_sql('lineitem', 'item_id', 'w')}) AS key FROM i) {bottom_sql('SELECT * FROM k', 1000)}",
)
def _(s, d):
    return shown(_weighted_by(read(s, d, "lineitem"), LINES, W.uniform_weight("lineitem", 7)))


@query(
    "drifting_weight_sample",
    f"WITH i AS (SELECT {LINE_SQL} AS item_id, l_orderkey % 8 AS pe, l_linenumber AS b FROM lineitem), "
    f"w AS (SELECT item_id, greatest(0.01, b + pe + sqrt(-2 * ln({unit_sql('lineitem', 'item_id', 'n1')})) * cos(2 * pi() * {unit_sql('lineitem', 'item_id', 'n2')})) AS w FROM i), "
    f"k AS (SELECT item_id, -ln({_U_LINE}) / w AS key FROM w) SELECT item_id FROM k ORDER BY key, item_id LIMIT 1000",
)
def _(s, d):
    df = read(s, d, "lineitem")
    rows = df.select(V.item_id(W.LINE_ID).alias("item_id"), W.drifting_weight("l_linenumber", "l_orderkey % 8", "lineitem", 7).alias("w"))
    u = V.uniform_key(F.col("item_id"), "lineitem", 7)
    return reservoir.bottom_k(rows.withColumn("key", V.exp_key(u, F.col("w"))), 1000).select("item_id")


# versions of a sample, and what surrounds them ----------------------------------------------------------------------------------------

_HALF = f"SELECT item_id FROM ({EVENTS_SQL}) WHERE batch_no < 15 ORDER BY key, item_id LIMIT 100"
_FULL = f"SELECT item_id FROM ({EVENTS_SQL}) ORDER BY key, item_id LIMIT 100"


def _versions(s, d) -> tuple[DataFrame, DataFrame]:
    df = read(s, d, "events")
    return tuple(reservoir.sample_once(x, EVENTS).select("item_id") for x in (df.where(f"{DAY} < 15"), df))


@query("versions_intersect", f"({_HALF}) INTERSECT ({_FULL})")
def _(s, d):
    old, new = _versions(s, d)
    return old.intersect(new)


@query("versions_except", f"({_FULL}) EXCEPT ({_HALF})")
def _(s, d):
    old, new = _versions(s, d)
    return new.exceptAll(old)


@query("sample_pivot", f"SELECT event_type, count(*) FILTER (WHERE day < '2024-01-16') AS early, count(*) FILTER (WHERE day >= '2024-01-16') AS late FROM {_EVENT_SAMPLE} GROUP BY 1")
def _(s, d):
    rows = _event_sample(s, d).withColumn("half", F.when(F.col("day") < "2024-01-16", "early").otherwise("late"))
    return rows.groupBy("event_type").pivot("half", ["early", "late"]).agg(F.count(F.lit(1))).na.fill(0)


@query("sample_unpivot", f"SELECT item_id, 'w' AS what, round(w, 6) AS amount FROM {_EVENT_SAMPLE} UNION ALL SELECT item_id, 'ln_key', round(ln(key), 6) FROM {_EVENT_SAMPLE}")
def _(s, d):
    rows = _event_sample(s, d).select("item_id", F.round("w", 6).alias("w"), F.round(F.log("key"), 6).alias("ln_key"))
    return rows.unpivot("item_id", ["w", "ln_key"], "what", "amount")


@query(
    "sample_ranks",
    f"SELECT item_id, dense_rank() OVER (PARTITION BY event_type ORDER BY key) AS place, ntile(4) OVER (PARTITION BY event_type ORDER BY key) AS quarter, "
    f"round(percent_rank() OVER (PARTITION BY event_type ORDER BY key), 9) AS share FROM {_EVENT_SAMPLE}",
)
def _(s, d):
    by = Window.partitionBy("event_type").orderBy("key")
    return _event_sample(s, d).select("item_id", F.dense_rank().over(by).cast("long").alias("place"), F.ntile(4).over(by).cast("long").alias("quarter"), F.round(F.percent_rank().over(by), 9).alias("share"))


@query(
    "candidates_moving_mean",
    f"WITH e AS ({EVENTS_SQL}), n AS (SELECT batch_no, count(*) FILTER (WHERE key < 1e-3) AS c FROM e GROUP BY 1) "
    "SELECT batch_no, round(avg(c) OVER (ORDER BY batch_no ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 9) AS mean FROM n",
)
def _(s, d):
    by_day = keyed(read(s, d, "events").withColumn("batch_no", F.expr(DAY).cast("long")), EVENTS, "batch_no").groupBy("batch_no").agg(F.count_if(F.col("key") < 1e-3).alias("c"))
    last = Window.partitionBy(F.lit(0)).orderBy("batch_no").rowsBetween(-2, 0)  # one row a batch
    return by_day.select("batch_no", F.round(F.avg("c").over(last), 9).alias("mean"))


@query("rank_counts_cross_join", f"SELECT p::double AS pivot, count(*) FILTER (WHERE key <= p) AS rank FROM ({LINES_SQL}), (VALUES (1e-7), (1e-6), (1e-5)) AS v(p) GROUP BY 1")
def _(s, d):
    pivots = s.createDataFrame([(1e-7,), (1e-6,), (1e-5,)], "pivot double")
    rows = keyed(read(s, d, "lineitem"), LINES).select("key").crossJoin(F.broadcast(pivots))
    return rows.groupBy("pivot").agg(F.count_if(F.col("key") <= F.col("pivot")).alias("rank"))


@query("wide_selection", f"SELECT item_id, draw_no AS rank FROM ({bottom_sql(LINES_SQL, 1000)}) WHERE draw_no = 1000")
def _(s, d):
    """32 pivots a round and the tail finished on the driver: few rounds where each is a job."""
    runs = _runs(s, d).persist()
    got = S.pivot_select(runs, 1000, 1000, runs.count(), 32, finish=256)
    runs.unpersist()
    return s.createDataFrame([(got.item_id, got.rank)], "item_id string, rank long")


@query("monitoring_messages", f"SELECT stream, n, k, p, round(k * (1 + ln(n / k)) * (1 + p), 6) AS messages FROM {_GRID}")
def _(s, d):
    return _grid(s, d).select("stream", "n", "k", "p", F.round(cost.columns_shape(F.col("n"), F.col("k"), F.lit(1)) * (1 + F.col("p")), 6).alias("messages"))


_SINGLE = f"""WITH e AS (SELECT item_id, key, item_id::bigint // 4 AS batch_no FROM ({EVENTS_SQL})), b AS (SELECT DISTINCT event_id // 4 AS batch_no FROM events),
c AS (SELECT b.batch_no, count(item_id) AS n FROM b LEFT JOIN e USING (batch_no) GROUP BY 1),
s AS (SELECT batch_no, n, coalesce(sum(n) OVER (ORDER BY batch_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS seen FROM c),
r AS (SELECT b.batch_no, e.key, row_number() OVER (PARTITION BY b.batch_no ORDER BY e.key, e.item_id) AS place FROM b JOIN e ON e.batch_no < b.batch_no),
t AS (SELECT batch_no, key AS threshold FROM r WHERE place = 5)
SELECT s.batch_no, s.n AS n_items, count(e.item_id) FILTER (WHERE e.key <= coalesce(t.threshold, 1e300)) AS candidates, least(5, s.seen + s.n)::bigint AS held_after
FROM s LEFT JOIN t USING (batch_no) LEFT JOIN e USING (batch_no) GROUP BY s.batch_no, s.n, s.seen"""


@query("single_item_batches", _SINGLE)
def _(s, d):
    """Batches of four items, one a partition: the continuous monitoring model as a special case. All events, without a job a batch."""
    return reservoir.counts_of_small_batches(read(s, d, "events"), EVENTS.but(k=5), "event_id DIV 4")
