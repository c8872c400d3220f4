"""The experiments on tables: methods over batches, and what their reports show (rounds, rows moved, throughput, phases)."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import variates as V
from ..model import SamplerSpec
from ..operators.reservoir import DecentralSampler, GatherSampler, VariableSampler, auto_method, storage
from .batches import items, replay, variate_of

LINE_ID = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_cents")
METHODS = ("pivot1", "pivot8", "gather")


def lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with the price in cents, part of its five-column id."""
    return spark.read.parquet(f"{sf_dir}/lineitem.parquet").withColumn("l_cents", F.round(F.col("l_extendedprice") * 100).cast("long"))


def sampler(spark: SparkSession, method: str, spec: SamplerSpec):
    """pivot1, pivot8: decentralised with one and eight pivots a round and exact size; gather: the centralised way; others name a selector."""
    if method == "auto":
        method = auto_method(spec, spec.k)
        method = "tail" if method == "decentral" else method
    if method == "gather":
        return GatherSampler(spark, spec)
    if method in ("pivot1", "pivot8"):
        return DecentralSampler(spark, spec.but(selector="pivot", d=int(method[5:]), finish=1))
    if method == "incremental":
        return DecentralSampler(spark, spec.but(selector="combined", incremental=True))
    if method in ("lazy", "eager"):
        return VariableSampler(spark, spec.but(k_max=spec.k_max or 2 * spec.k, lazy=method == "lazy", finish=1))
    return DecentralSampler(spark, spec.but(selector=method))


def run(spark: SparkSession, method: str, spec: SamplerSpec, batches: Iterable[tuple[int, DataFrame]], one=None):
    """``one``: a sampler that goes on; a new one of the method without it."""
    one = one or sampler(spark, method, spec)
    for number, rows in batches:
        one.process(rows, number)
    return one


def sliced(df: DataFrame, item: tuple[str, ...], batches: int) -> DataFrame:
    """Equal batches by a hash of the item."""
    return df.withColumn("slice", F.pmod(F.xxhash64(V.item_id(item)), F.lit(batches)))


def compare(spark: SparkSession, df: DataFrame, spec: SamplerSpec, batch: str, methods: Iterable[str] = METHODS, last: int | None = None) -> DataFrame:
    """All methods over the same batches, staged once: their reports, one below the other, and the method's name as run."""
    out, path = None, storage(spark)
    for m in methods:
        rows = run(spark, m, spec, replay(df, batch, last, path)).report().withColumn("run", F.lit(m))
        out = rows if out is None else out.unionByName(rows)
    return out


def summary(reports: DataFrame) -> DataFrame:
    """By run: mean rounds, candidates, rows and bytes moved, seconds by phase, items a second."""
    seconds = F.sum(F.col("t_insert") + F.col("t_select") + F.col("t_threshold") + F.col("t_gather"))
    later = F.col("held_before") > 0
    return reports.groupBy("run").agg(
        F.count(F.lit(1)).alias("batches"),
        F.avg(F.when(F.col("rounds") > 0, F.col("rounds"))).alias("mean_rounds"),
        F.avg(F.when(later, F.col("candidates"))).alias("mean_candidates"),
        F.sum("rows_moved").alias("rows_moved"),
        F.sum("bytes_moved").alias("bytes_moved"),
        F.sum("jobs").alias("jobs"),
        (F.sum(F.col("t_insert") + F.col("t_gather")) / seconds).alias("insert_share"),
        (F.sum("t_select") / seconds).alias("select_share"),
        (F.sum("n_items") / seconds).alias("items_per_second"),
    )


def depth_by_pivots(spark: SparkSession, df: DataFrame, spec: SamplerSpec, batch: str, pivots: Iterable[int] = (1, 2, 4, 8, 16, 32), last: int | None = None) -> list[tuple[int, float, float]]:
    """(pivots, mean rounds a selection, last threshold) by number of pivots."""
    out, path = [], storage(spark)
    for d in pivots:
        one = run(spark, "", spec, replay(df, batch, last, path), DecentralSampler(spark, spec.but(selector="pivot", d=d, finish=1)))
        rounds = [r.rounds for r in one.reports.rows if r.rounds]
        out.append((d, sum(rounds) / max(1, len(rounds)), one.state.threshold))
    return out


def spread_batches(spark: SparkSession, df: DataFrame, spec: SamplerSpec, counts: Iterable[int]) -> DataFrame:
    """(item_id, w, variate, and of_n for each number of batches n), written once in folders by batch; batches are of about equal size, by a variate of the item, which
    other engines can compute, too. What a key is made of is drawn here, once for all runs over the same items."""
    cuts = {f"of_{n}": n for n in sorted(set(counts), reverse=True)}
    u = V.uniform_key(F.col("item_id"), spec.stream_id, spec.seed, "batch")
    rows = items(df, spec).withColumn("variate", variate_of(spec)).withColumn("u", u)
    rows = rows.select("item_id", "w", "variate", *[F.least(F.floor(F.col("u") * n), F.lit(n - 1)).cast("long").alias(c) for c, n in cuts.items()])
    path = storage(spark)
    rows.write.partitionBy(*cuts).parquet(path)
    return spark.read.schema(rows.schema).parquet(path)


def scaling(spark: SparkSession, df: DataFrame, spec: SamplerSpec, runs: Iterable[tuple[int, int]], ks: Iterable[int], methods: Iterable[str] = METHODS) -> DataFrame:
    """Reports of all methods with run, p, batches and k: for each (partitions, number of batches) of ``runs`` the whole table, cut into that many batches.

    Weak scaling: partitions times batches is constant, so that a batch grows with the partitions. Strong scaling: the number of batches is. Items and variates are staged
    once; the times are those of the samplers over them.
    """
    out, runs = None, list(runs)
    cut, drawn = spread_batches(spark, df, spec, [n for _, n in runs]), spec.but(id_cols=("item_id",), weight="w" if spec.weight else None, variate="variate")
    for p, batches in runs:
        of = F.col(f"of_{batches}")
        numbers = sorted(r[0] for r in cut.select(of).distinct().collect())
        for k in ks:
            for m in methods:
                steps = ((b, cut.where(of == b).coalesce(p)) for b in numbers)
                rows = run(spark, m, drawn.but(k=k), steps).report().select("*", *[F.lit(x).alias(n) for n, x in (("run", m), ("p", p), ("batches", batches), ("k", k))])
                out = rows if out is None else out.unionByName(rows)
    return out


def scaling_summary(reports: DataFrame) -> DataFrame:
    """By run, p, batches and k: seconds, items a second and partition, shares of the phases, rounds, rows moved, and the speedup over pivot1 on the fewest partitions with
    the same k; work is counted by items, so one formula serves weak and strong scaling."""
    parts = ["t_insert", "t_select", "t_threshold", "t_gather"]
    by = reports.groupBy("run", "p", "batches", "k").agg(
        F.sum("n_items").alias("n_items"),
        *[F.sum(c).alias(c) for c in parts],
        F.avg(F.when(F.col("rounds") > 0, F.col("rounds"))).alias("mean_rounds"),
        F.sum("rows_moved").alias("rows_moved"),
        F.sum("jobs").alias("jobs"),
    )
    by = by.withColumn("seconds", sum((F.col(c) for c in parts[1:]), F.col(parts[0]))).withColumn("items_per_second", F.col("n_items") / F.col("seconds"))
    base = by.where("run = 'pivot1'").groupBy("k").agg(F.min_by("items_per_second", "p").alias("base"))
    one = by.where("run = 'pivot1'").select("p", "batches", "k", F.col("t_select").alias("s1"), F.col("seconds").alias("all1"))
    joined = by.join(F.broadcast(base), "k").join(F.broadcast(one), ["p", "batches", "k"])
    shares = [(F.col(c) / F.col("seconds")).alias(c.replace("t_", "") + "_share") for c in parts]
    eight = F.col("run") == "pivot8"
    return joined.select(
        "run", "p", "batches", "k", "n_items", "seconds", (F.col("items_per_second") / F.col("p")).alias("items_per_second_and_pe"), (F.col("items_per_second") / F.col("base")).alias("speedup"),
        F.col("p").cast("double").alias("ideal"), *shares, "mean_rounds", "rows_moved", "jobs",
        F.when(eight, 1 - F.col("t_select") / F.col("s1")).alias("selection_saved"), F.when(eight, 1 - F.col("seconds") / F.col("all1")).alias("time_saved"),
    )


def lopsided(df: DataFrame, partitions: int, seed: int = 7) -> DataFrame:
    """Nine rows of ten on one partition, one partition without any."""
    u = F.pmod(F.xxhash64(*df.columns, F.lit(seed)), F.lit(100))
    place = F.when(u < 90, F.lit(0)).otherwise(1 + u % (partitions - 2))
    return df.withColumn("place", place.cast("int")).repartitionById(partitions, "place").drop("place")


def drifting_weight(batch: str, pe: str, stream: str, seed: int) -> F.Column:
    """Normal weights around batch plus partition, at least 0.01, from two variates of the item."""
    u = [V.uniform_key(F.col("item_id"), stream, seed, p) for p in ("n1", "n2")]
    z = F.sqrt(-2 * F.log(u[0])) * F.cos(2 * F.pi() * u[1])
    return F.greatest(F.lit(0.01), F.expr(batch) + F.expr(pe) + z)


def uniform_weight(stream: str, seed: int) -> F.Column:
    """Weights over 0 to 100."""
    return 100 * V.uniform_key(F.col("item_id"), stream, seed, "w")
