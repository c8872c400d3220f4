"""Queries for the sources, sinks, joins, aggregates and functions around the samplers, with the SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .functions import sqlapi
from .operators import reservoir
from .plans.batches import items, keyed, valid
from .queries import EVENTS, EVENTS_SQL, LINES, LINES_SQL, ORDERS, _EVENT_SAMPLE, _ORDER_SAMPLE, _event_sample, _orders, bottom_sql, keyed_sql, query, read, shown, unit_sql
from .streaming import stream, windows

# sources and sinks ---------------------------------------------------------------------------------------------------------------------


@query("scan_formats", f"SELECT form, item_id, draw_no, ln_key FROM ({bottom_sql(EVENTS_SQL, 100)}), (VALUES ('csv'), ('json'), ('orc'), ('parquet')) AS f(form)")
def _(s, d):
    """The same sample from the events in four formats."""
    df, out = read(s, d, "events").select("event_id", "value"), None
    for form in ("csv", "json", "orc", "parquet"):
        path = reservoir.storage(s)
        df.write.format(form).option("header", "true").save(path)
        back = s.read.schema(df.schema).format(form).option("header", "true").load(path)
        rows = shown(reservoir.sample_once(back, EVENTS)).withColumn("form", F.lit(form))
        out = rows if out is None else out.unionByName(rows)
    return out


@query("sample_view", f"SELECT event_type, count(*) AS n FROM {_EVENT_SAMPLE} GROUP BY 1")
def _(s, d):
    """The sample as a view, asked by SQL."""
    read(s, d, "events").createOrReplaceTempView("all_events")
    sqlapi.sample_table(s, "all_events", EVENTS).createOrReplaceTempView("event_sample")
    return s.sql("SELECT event_type, count(*) AS n FROM event_sample JOIN all_events ON item_id = cast(event_id AS string) GROUP BY event_type")


@query("stream_memory_sink", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(s, d):
    """Rows of each type seen by a stream, in a table in memory."""
    counted = stream.table_stream(s, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return stream.to_memory(counted, "events_by_type", "complete").select("event_type", "n")


# filters and joins ---------------------------------------------------------------------------------------------------------------------

_TEST = "event_type IN ('click', 'view', 'purchase') OR event_type LIKE 's%' OR NOT (event_type LIKE '%a%') OR event_type IS NULL"


@query("filtered_sample", bottom_sql(f"SELECT * FROM ({EVENTS_SQL}) WHERE ({_TEST}) AND w BETWEEN 1 AND 200", 100))
def _(s, d):
    kind = F.col("event_type")
    test = kind.isin("click", "view", "purchase") | kind.like("s%") | ~kind.like("%a%") | kind.isNull()
    return shown(reservoir.sample_once(read(s, d, "events").where(test & F.col("value").between(1, 200)), EVENTS))


_ORDER_LINES = f"SELECT s.o_orderkey, count(*) AS n, round(sum(l_extendedprice) / 1000, 3) AS thousands FROM lineitem JOIN {_ORDER_SAMPLE} s ON l_orderkey = s.o_orderkey GROUP BY 1"


def _order_lines(s, d, hint: str) -> DataFrame:
    picked = _orders(s, d).select("o_orderkey").hint(hint)
    lines = read(s, d, "lineitem").join(picked, F.col("l_orderkey") == F.col("o_orderkey"))
    return lines.groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice") / 1000, 3).alias("thousands"))


@query("sample_merge_join", _ORDER_LINES)
def _(s, d):
    return _order_lines(s, d, "merge")


@query("sample_shuffle_hash_join", _ORDER_LINES)
def _(s, d):
    return _order_lines(s, d, "shuffle_hash")


@query(
    "sample_left_join",
    f"SELECT n_name, count(s.o_orderkey) AS n FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey LEFT JOIN orders o ON o_custkey = c_custkey LEFT JOIN {_ORDER_SAMPLE} s ON s.o_orderkey = o.o_orderkey GROUP BY 1",
)
def _(s, d):
    """Sampled orders by nation; nations without any stay."""
    found = read(s, d, "orders").join(F.broadcast(_orders(s, d).select("o_orderkey")), "o_orderkey").join(read(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    by = found.groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n"))
    return read(s, d, "nation").join(by, F.col("n_nationkey") == F.col("c_nationkey"), "left").select("n_name", F.coalesce("n", F.lit(0)).alias("n"))


@query(
    "benchmark_anti_join",
    "WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents), "
    "c AS (SELECT DISTINCT doc_id FROM l WHERE trim(line) IN (SELECT trim(text) FROM benchmark)) " + bottom_sql("SELECT * FROM (" + keyed_sql("documents", "doc_id", "n_chars", "doc_id") + ") WHERE doc_id NOT IN (SELECT doc_id FROM c)", 50),
)
def _(s, d):
    """A sample of documents none of whose lines is a text of the benchmark."""
    docs = read(s, d, "documents")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n", -1)).alias("line")).withColumn("line", F.trim("line"))
    hit = lines.join(read(s, d, "benchmark").select(F.trim("text").alias("line")).distinct(), "line", "left_semi").select("doc_id").distinct()
    from .queries import DOCS

    return shown(reservoir.sample_once(docs.join(hit, "doc_id", "left_anti"), DOCS))


_PRICE_STEPS = f"WITH o AS (SELECT item_id, w, sum(w) OVER (ORDER BY item_id ROWS UNBOUNDED PRECEDING) AS hi FROM ({keyed_sql('customer', 'c_custkey', 'c_acctbal')}))"


@query("jump_targets_range_join", f"{_PRICE_STEPS}, t AS (SELECT i, (i + 0.5) * (SELECT max(hi) FROM o) / 20 AS x FROM generate_series(0, 19) AS g(i)) SELECT i::bigint AS target, item_id FROM t JOIN o ON hi - w < x AND x <= hi")
def _(s, d):
    """The items that targets within the running total of weights fall on: a range join, with the targets broadcast."""
    from .queries import CUSTOMERS

    rows = valid(items(read(s, d, "customer"), CUSTOMERS))
    steps = rows.withColumn("hi", F.sum("w").over(Window.partitionBy(F.lit(0)).orderBy("item_id").rowsBetween(Window.unboundedPreceding, 0)))  # a small table
    top = steps.agg(F.max("hi").alias("top"))
    targets = s.range(20).select(F.col("id").alias("target")).crossJoin(F.broadcast(top)).select("target", ((F.col("target") + 0.5) * F.col("top") / 20).alias("x"))
    return steps.join(F.broadcast(targets), (F.col("hi") - F.col("w") < F.col("x")) & (F.col("x") <= F.col("hi"))).select("target", "item_id")


# aggregates, windows, functions ----------------------------------------------------------------------------------------------------------


@query(
    "sample_extremes",
    f"SELECT event_type, max_by(item_id, key) AS last_in, min_by(item_id, key) AS first_in, string_agg(item_id, ',' ORDER BY key, item_id) AS in_order FROM {_EVENT_SAMPLE} GROUP BY 1",
)
def _(s, d):
    listed = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("key", "item_id"))), lambda x: x["item_id"]), ",")
    return _event_sample(s, d).groupBy("event_type").agg(F.max_by("item_id", "key").alias("last_in"), F.min_by("item_id", "key").alias("first_in"), listed.alias("in_order"))


@query("approximate_against_exact", "SELECT true AS users_near, true AS kll_near, true AS percentile_near, true AS hll_near FROM (SELECT 1)")
def _(s, d):
    """Built-in sketches over the keys and users of all events, each within its error of the exact figure."""
    rows = keyed(read(s, d, "events"), EVENTS, "user_id")
    n = rows.count()
    cut, share = reservoir.sample_once(read(s, d, "events"), EVENTS).agg(F.max("key")).first()[0], 100 / n
    got = rows.agg(
        F.approx_count_distinct("user_id").alias("approx"),
        F.count_distinct("user_id").alias("users"),
        F.percentile_approx("key", share, 100_000).alias("cut"),
        F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll"),
        F.expr(f"kll_sketch_get_quantile_double(kll_sketch_agg_double(key), {min(0.5, 10 * share)}D)").alias("kll"),
        F.expr(f"percentile(key, {min(0.5, 10 * share)}D)").alias("tenfold"),
    ).first()
    near = lambda a, b, e: bool(abs(a - b) <= e * max(abs(b), 1e-300))
    return s.createDataFrame([(near(got["approx"], got["users"], 0.15), near(got["kll"], got["tenfold"], 0.7), near(got["cut"], cut, 0.1), near(got["hll"], got["users"], 0.1))], "users_near boolean, kll_near boolean, percentile_near boolean, hll_near boolean")


@query(
    "sample_analytics",
    f"SELECT item_id, round(sum(w) OVER (ORDER BY key, item_id ROWS UNBOUNDED PRECEDING), 6) AS so_far, first_value(item_id) OVER (ORDER BY key, item_id) AS first_in, "
    f"nth_value(item_id, 3) OVER (ORDER BY key, item_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS third, lead(item_id, 2) OVER (ORDER BY key, item_id) AS after_next FROM {_EVENT_SAMPLE}",
)
def _(s, d):
    by = Window.partitionBy(F.lit(0)).orderBy("key", "item_id")  # the sample: k rows
    whole = by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    run = by.rowsBetween(Window.unboundedPreceding, 0)
    return _event_sample(s, d).select(
        "item_id", F.round(F.sum("w").over(run), 6).alias("so_far"), F.first("item_id").over(by).alias("first_in"), F.nth_value("item_id", 3).over(whole).alias("third"), F.lead("item_id", 2).over(by).alias("after_next")
    )


@query("window_value_range", f"SELECT item_id, count(*) OVER (ORDER BY w RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS near FROM {_EVENT_SAMPLE}")
def _(s, d):
    return _event_sample(s, d).select("item_id", F.count(F.lit(1)).over(Window.partitionBy(F.lit(0)).orderBy("w").rangeBetween(-5, 5)).alias("near"))


@query("report_maps", f"SELECT event_type, count(*) AS n, max(round(w, 6)) AS largest FROM {_EVENT_SAMPLE} GROUP BY 1")
def _(s, d):
    """Counts and largest weights kept in maps, and taken out again."""
    by = _event_sample(s, d).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.max(F.round("w", 6)).alias("largest"))
    maps = by.agg(F.map_from_arrays(F.collect_list("event_type"), F.collect_list("n")).alias("n"), F.map_from_entries(F.collect_list(F.struct("event_type", "largest"))).alias("largest"))
    return maps.select(F.explode("n").alias("event_type", "n"), "largest").select("event_type", "n", F.element_at("largest", F.col("event_type")).alias("largest"))


@query("placement", "SELECT how, count(*) AS n, true AS as_many_places FROM lineitem, (VALUES ('range'), ('hash'), ('fewer')) AS v(how) GROUP BY how")
def _(s, d):
    """Items dealt to partitions by range, by hash, and to fewer ones without moving."""
    df, out = read(s, d, "lineitem").select("l_orderkey", "l_extendedprice"), None
    for how, rows, most in (("range", df.repartitionByRange(5, "l_extendedprice"), 5), ("hash", df.repartition(5, "l_orderkey"), 5), ("fewer", df.repartition(6).coalesce(2), 2)):
        by = rows.groupBy(F.spark_partition_id().alias("place")).agg(F.count(F.lit(1)).alias("n"))
        one = by.agg(F.sum("n").alias("n"), (F.count(F.lit(1)) <= most).alias("as_many_places")).withColumn("how", F.lit(how))
        out = one if out is None else out.unionByName(one)
    return out


@query("group_bottom_k_array", f"SELECT event_type, string_agg(item_id, ',' ORDER BY key, item_id) AS ids FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY key, item_id) AS r FROM ({EVENTS_SQL})) WHERE r <= 5 GROUP BY 1")
def _(s, d):
    by = keyed(read(s, d, "events"), EVENTS, "event_type").groupBy("event_type").agg(sqlapi.bottom_k_aggregate(5).alias("least"))
    return by.select("event_type", F.array_join(F.transform("least", lambda x: x["item_id"]), ",").alias("ids"))


@query("group_kth_udaf", f"SELECT event_type, round(ln(max(key)), 9) AS ln_key FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY key, item_id) AS r FROM ({EVENTS_SQL})) WHERE r <= 5 GROUP BY 1")
def _(s, d):
    by = keyed(read(s, d, "events"), EVENTS, "event_type").groupBy("event_type").agg(sqlapi.bottom_k_udaf(5)("key").alias("kth"))
    return by.select("event_type", F.round(F.log("kth"), 9).alias("ln_key"))


@query("arrow_udf_sample", bottom_sql(EVENTS_SQL, 100))
def _(s, d):
    """The sample by keys from a scalar Arrow function."""
    rows = valid(items(read(s, d, "events"), EVENTS)).withColumn("key", sqlapi.arrow_exp_key("events", 7)("item_id", "w"))
    return shown(reservoir.bottom_k(rows, 100))


@query("sql_function_sample", bottom_sql(EVENTS_SQL, 100))
def _(s, d):
    """The sample by SQL alone, with the registered key function."""
    sqlapi.register(s)
    read(s, d, "events").createOrReplaceTempView("all_events")
    small = s.sql("SELECT cast(event_id AS string) AS item_id, value AS w, exp_key('events', 7, cast(event_id AS string), value) AS key FROM all_events WHERE value > 0 ORDER BY key, item_id LIMIT 100")
    return shown(reservoir.bottom_k(small, 100))


@query("drawn_batch_keys", f"SELECT count(*) AS n, true AS all_keys_differ FROM ({LINES_SQL})")
def _(s, d):
    """Keys drawn by partition; no two partitions draw the same ones."""
    rows = valid(items(read(s, d, "lineitem"), LINES)).repartition(8).select(F.col("w"))
    keys = rows.mapInPandas(lambda b: sqlapi.batch_keys(b, 7), "w double, key double")
    return keys.agg(F.count(F.lit(1)).alias("n"), (F.count_distinct(F.col("key") * F.col("w")) == F.count(F.lit(1))).alias("all_keys_differ"))


@query("builtin_samples", "SELECT how, true AS near_expected FROM (VALUES ('sample'), ('sample_by'), ('tablesample'), ('random_split'), ('with_replacement')) AS v(how)")
def _(s, d):
    """The engine's own samples, for contrast: unweighted, and of a size that varies about its expectation."""
    df = read(s, d, "events")
    n = df.count()
    df.createOrReplaceTempView("all_events")
    kinds = [r[0] for r in df.select("event_type").distinct().collect()]
    sizes = {
        "sample": df.sample(0.1, seed=7).count(),
        "sample_by": df.sampleBy("event_type", dict.fromkeys(kinds, 0.1), seed=7).count(),
        "tablesample": s.sql("SELECT * FROM all_events TABLESAMPLE (10 PERCENT) REPEATABLE (7)").count(),
        "random_split": df.randomSplit([0.1, 0.9], seed=7)[0].count(),
        "with_replacement": df.sample(True, 0.1, seed=7).count(),
    }
    return s.createDataFrame([(how, abs(c - 0.1 * n) < 6 * (0.1 * n) ** 0.5) for how, c in sizes.items()], "how string, near_expected boolean")


# event time ----------------------------------------------------------------------------------------------------------------------------


@query(
    "hopping_window_sample",
    f"WITH e AS (SELECT * FROM ({EVENTS_SQL})), w AS (SELECT item_id, key, floor(epoch(ts))::bigint // 21600 * 21600 - i * 21600 AS start FROM e, generate_series(0, 3) AS g(i)) "
    "SELECT start::bigint AS start, item_id FROM (SELECT *, row_number() OVER (PARTITION BY start ORDER BY key, item_id) AS r FROM w) WHERE r <= 3",
)
def _(s, d):
    rows = windows.window_sample(read(s, d, "events"), EVENTS.but(k=3), "1 day", "6 hours")
    return rows.select(F.unix_timestamp("window_start").alias("start"), "item_id")


_SESSIONS = (
    f"WITH e AS (SELECT * FROM ({EVENTS_SQL})), q AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, item_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM e), "
    "n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, item_id) AS session_no FROM q), "
    "r AS (SELECT *, row_number() OVER (PARTITION BY user_id, session_no ORDER BY key, item_id) AS place FROM n)"
)


@query("stream_session_sample", f"{_SESSIONS} SELECT user_id, floor(epoch(min(ts)))::bigint AS start, count(*) AS n, string_agg(item_id, ',' ORDER BY key, item_id) FILTER (WHERE place <= 2) AS least FROM r GROUP BY user_id, session_no")
def _(s, d):
    """Sessions on a stream, each with its two smallest keys."""
    store = stream.SessionStore(s, EVENTS.but(k=2), "user_id")
    stream.drain(stream.table_stream(s, d, "events"), store.add)
    return store.held().select("user_id", F.unix_timestamp("session_start").alias("start"), "n", F.array_join(F.transform("least", lambda x: x["item_id"]), ",").alias("least"))


@query("stream_once_each", "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def _(s, d):
    """A stream that brings every event twice, without its repeats."""
    path = reservoir.storage(s)
    twice = read(s, d, "events").select("event_id", "ts")
    twice.union(twice).write.parquet(path)
    again = s.readStream.schema(twice.schema).parquet(path)
    rows = stream.to_files(stream.without_repeats(again, ["event_id"], "40 days"))
    return rows.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("event_id").alias("ids"))


@query("stream_static_join", bottom_sql("SELECT * FROM (" + keyed_sql("events", "event_id", "value", "user_id") + ") JOIN customer ON user_id = c_custkey", 100))
def _(s, d):
    """A sample of the events of known customers: a stream joined to a table, batch by batch."""
    known = read(s, d, "customer").select(F.col("c_custkey").alias("user_id"))
    joined = stream.table_stream(s, d, "events").join(known, "user_id")
    return shown(stream.StreamSampler(s, EVENTS).run(joined))


@query("stream_late_rows", "SELECT (SELECT count(*) FROM events) AS n_rows, sum((ts < TIMESTAMP '2024-01-05')::int)::bigint AS late, true AS others_held FROM events")
def _(s, d):
    """Days from the fifth on first, the first four days after them: windows that the watermark has passed take no more rows."""
    path, df = reservoir.storage(s), read(s, d, "events")
    first = df.where("ts >= TIMESTAMP_NTZ '2024-01-05'")
    for number, part in enumerate((first, df.where("ts < TIMESTAMP_NTZ '2024-01-05'"))):
        part.coalesce(1).write.parquet(f"{path}/part={number}")
    rows = s.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).option("pathGlobFilter", "*.parquet").parquet(f"{path}/part=*")
    store = stream.stream_windows(rows, EVENTS.but(k=5), "1 day", "1 day")
    want = windows.window_sample(first, EVENTS.but(k=5), "1 day").select("item_id")
    held = store.held().select("item_id")
    same = want.exceptAll(held).isEmpty() and held.exceptAll(want).isEmpty()
    bad = df.where("value IS NULL OR value <= 0").where("ts < TIMESTAMP_NTZ '2024-01-05'").count()
    return s.createDataFrame([(df.count(), store.late + bad, same)], "n_rows long, late long, others_held boolean")


@query("uniform_order_sample", f"SELECT item_id, key FROM ({keyed_sql('orders', 'o_orderkey', None)}) WHERE key <= 0.001")
def _(s, d):
    """All items under a given uniform threshold: a sample whose size varies."""
    rows = reservoir.candidates_by_key(items(read(s, d, "orders"), ORDERS.but(weight=None)), ORDERS.but(weight=None), 0.001)
    return rows.select("item_id", "key")


@query("conditional_keys", f"SELECT count(*) FILTER (WHERE {unit_sql('events', 'event_id::varchar', 'in')} < 1 - exp(-1e-3 * value)) AS n, true AS below, true AS positive FROM events WHERE value > 0")
def _(s, d):
    """Inclusion by a test, then keys given that they are below the threshold: as many items as the test lets in, all keys in range."""
    rows = reservoir.candidates_by_test(valid(items(read(s, d, "events"), EVENTS)), EVENTS, 1e-3)
    return rows.agg(F.count(F.lit(1)).alias("n"), (F.max("key") <= 1e-3).alias("below"), (F.min("key") > 0).alias("positive"))
