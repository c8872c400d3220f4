"""Samplers: one-shot, decentralised over batches, centralised gathering, sequential; samples that merge, by group, by window."""

from __future__ import annotations

import json
import tempfile
import time
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import skips
from ..functions import variates as V
from ..model import STATE_SCHEMA, Report, Reports, SamplerSpec, State
from ..plans.batches import items, key_of, keyed, valid, variate_of
from . import localres
from .select import Selected, incremental_select, local_kth, pivot_select, select, up_to

RUN = "item_id string, w double, key double, batch_no long, pe int"


def bottom_k(rows: DataFrame, k: int) -> DataFrame:
    """The k smallest keys with their place, by a top-k that keeps k rows a partition."""
    small = rows.orderBy("key", "item_id").limit(k)
    return small.withColumn("draw_no", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("key", "item_id")))


def sample_once(df: DataFrame, spec: SamplerSpec, *payload: str) -> DataFrame:
    """A sample of a finite table: (item_id, w, key, draw_no, payload)."""
    return bottom_k(keyed(df, spec, *payload), spec.k)


def sample_top_power(df: DataFrame, spec: SamplerSpec) -> DataFrame:
    """The same sample by power keys, the k largest."""
    u = V.uniform_key(F.col("item_id"), spec.stream_id, spec.seed)
    rows = valid(items(df, spec)).withColumn("u", u).withColumn("key", V.power_key(F.col("u"), F.col("w")))
    small = rows.orderBy(F.desc("key"), "item_id").limit(spec.k)
    return small.withColumn("draw_no", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("key"), "item_id")))


def sample_by_group(df: DataFrame, spec: SamplerSpec, group: str) -> DataFrame:
    """One reservoir a group; no group is gathered, each task keeps k rows of each at most."""
    rows = keyed(df, spec, group)
    place = F.row_number().over(Window.partitionBy(group).orderBy("key", "item_id"))
    return rows.withColumn("draw_no", place).where(F.col("draw_no") <= spec.k)


def merge(one: DataFrame, other: DataFrame, k: int) -> DataFrame:
    """The sample of two streams without common items, out of their samples."""
    cols = [c for c in one.columns if c in other.columns and c != "draw_no"]
    return bottom_k(one.select(cols).unionByName(other.select(cols)), k)


def candidates_by_key(rows: DataFrame, spec: SamplerSpec, threshold: float | None) -> DataFrame:
    """Each item draws its own key; with a threshold, as a test that needs no division for most items."""
    if threshold is None:
        return rows.withColumn("key", key_of(spec))
    if spec.weight and not spec.deep:
        # the cheap test is a hair wider than the exact one that follows
        wide = rows.withColumn("u", variate_of(spec)).where(-F.log("u") <= F.lit(threshold * (1 + 1e-12)) * F.col("w"))
        return wide.withColumn("key", V.exp_key(F.col("u"), F.col("w"))).where(F.col("key") <= threshold).drop("u")
    return rows.withColumn("key", key_of(spec)).where(F.col("key") <= threshold)


def candidates_by_test(rows: DataFrame, spec: SamplerSpec, threshold: float | None) -> DataFrame:
    """Inclusion is tested first; who is in draws a key below the threshold, from a second variate."""
    if threshold is None:
        return candidates_by_key(rows, spec, None)
    one, two = (V.uniform_key(F.col("item_id"), spec.stream_id, spec.seed, p) for p in ("in", "key"))
    if not spec.weight:
        return rows.where(one <= threshold).withColumn("key", V.uniform_key_below(two, threshold))
    return rows.where(V.included(one, F.col("w"), threshold)).withColumn("key", V.exp_key_below(two, F.col("w"), threshold))


def candidates_by_jump(rows: DataFrame, spec: SamplerSpec, threshold: float | None, batch_no: int, counted: bool = False) -> DataFrame:
    """Jumps, one walk a partition, seeded by (seed, batch, partition). The first batches cap each partition's run instead.

    counted: also rows without an item, which say how many weights were looked at one by one, and how many blocks were passed over.
    """
    seed, block, k, weighted = spec.seed, spec.block, spec.k, spec.weight is not None
    names = ["item_id", "w", "key", *(["examined", "skipped"] if counted else [])]

    def out(ids: pa.Array, w: np.ndarray, keys: np.ndarray, examined: int = 0, skipped: int = 0) -> pa.RecordBatch:
        cols = [ids, pa.array(w, pa.float64()), pa.array(keys, pa.float64())]
        if counted:
            n, none = len(ids), pa.nulls(1, pa.float64())
            cols = [pa.concat_arrays([ids, pa.nulls(1, pa.string())]), *(pa.concat_arrays([c, none]) for c in cols[1:])]
            cols += [pa.array([0] * n + [x], pa.int64()) for x in (examined, skipped)]
        return pa.RecordBatch.from_arrays(cols, names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng = np.random.default_rng([seed, batch_no + 1, TaskContext.get().partitionId()])
        capped, n_in = localres.FirstBatch(k), 0
        weights: dict[object, float] = {}
        for batch in batches:
            ids, w = batch.column(0), batch.column(1).to_numpy(zero_copy_only=False)
            if threshold is not None:
                walk = skips.weighted_fill(w, threshold, rng, block) if weighted else skips.uniform_fill(len(w), threshold, rng)
                yield out(ids.take(pa.array(walk.positions)), w[walk.positions], walk.keys, walk.examined, walk.skipped_blocks)
                continue
            u = 1 - rng.random(len(w))
            items_in, n_in = np.array(ids.to_pylist(), dtype=object), n_in + len(w)
            capped.add(-np.log(u) / w if weighted else u, items_in)
            weights.update(zip(items_in.tolist(), w.tolist(), strict=True))
            kept = set(capped.ids.tolist())
            weights = {i: x for i, x in weights.items() if i in kept}
        if threshold is None and n_in:
            yield out(pa.array(capped.ids.tolist(), pa.string()), np.array([weights[i] for i in capped.ids.tolist()]), capped.keys, n_in)

    return rows.select("item_id", "w").mapInArrow(run, "item_id string, w double, key double" + (", examined long, skipped long" if counted else ""))


def local_cap(found: DataFrame, k: int) -> DataFrame:
    """The k smallest of each partition, in one pass that holds little more than k rows: the rest is dropped before rows move, so a first batch is never written as a whole."""
    most = localres.cap_limits(k)[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n, limit = [], 0, np.inf
        for batch in batches:
            batch = batch.filter(pa.array(batch.column("key").to_numpy(zero_copy_only=False) <= limit))
            held, n = [*held, batch], n + batch.num_rows
            if n > most:
                rows = pa.Table.from_batches(held)
                keys = rows.column("key").to_numpy()
                limit = np.partition(keys, k - 1)[k - 1]
                held = rows.filter(pa.array(keys <= limit)).combine_chunks().to_batches()
                n = sum(b.num_rows for b in held)
        if n:
            yield from pa.Table.from_batches(held).sort_by([("key", "ascending"), ("item_id", "ascending")]).slice(0, k).combine_chunks().to_batches()

    return found.mapInArrow(run, found.schema)


def storage(spark: SparkSession) -> str:
    """A new folder for a sampler's runs, under the shared checkpoint folder. Where that is unset, a temporary one in local runs, and an error on a cluster."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
        root = f"file://{tempfile.mkdtemp(prefix='runs-')}"
    return f"{root.rstrip('/')}/sampler-{uuid.uuid4().hex}"


class StateLog:
    """One small file for each version of a sampler's state; the newest one that is whole counts. Files are written under another name and renamed."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, f"{path}/state"
        jvm = spark.sparkContext._jvm
        self.of = jvm.org.apache.hadoop.fs.Path
        self.fs = self.of(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def write(self, version: int, row: dict) -> None:
        name, part = self.of(f"{self.path}/v{version:012d}.json"), self.of(f"{self.path}/_v{version:012d}-{uuid.uuid4().hex}")
        out = self.fs.create(part, True)
        out.write(bytearray(json.dumps(row).encode()))
        out.close()
        if self.fs.exists(name):
            self.fs.delete(name, False)
        if not self.fs.rename(part, name):
            raise OSError(f"state {version} was not written")

    def newest(self) -> dict | None:
        folder = self.of(self.path)
        if not self.fs.exists(folder):
            return None
        names = sorted(f.getPath().getName() for f in self.fs.listStatus(folder) if f.getPath().getName().startswith("v"))
        if not names:
            return None
        stream = self.fs.open(self.of(f"{self.path}/{names[-1]}"))
        try:
            text = self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        return json.loads(text)

    def table(self) -> DataFrame:
        """All versions, as rows."""
        return self.spark.read.schema(STATE_SCHEMA).json(f"{self.path}/v*.json")


class DecentralSampler:
    """Batches fill runs where their items lie, under a fixed threshold; then the new threshold is selected, and runs are cut.

    Runs are files of candidates by batch; a cut is a filter by (key, item), applied when they are read, and once the
    files hold much more than the sample they are rewritten. Between batches the driver has the few numbers of ``State`` and the list of files only,
    and both are written after each batch: a sampler made anew with the same ``path`` goes on where the last one ended.
    """

    method = "decentral"

    def __init__(self, spark: SparkSession, spec: SamplerSpec, path: str | None = None):
        self.spark, self.spec, self.path = spark, spec, path or storage(spark)
        self.state, self.reports, self.stored, self.files = State(), Reports(), 0, []
        self.log, self.parts = StateLog(spark, self.path), spark.sparkContext.defaultParallelism
        if path is not None:
            self._restore()

    def _row(self) -> dict:
        s, spec = self.state, self.spec
        return {
            "stream_id": spec.stream_id, "version": s.version, "threshold": s.threshold, "threshold_id": s.threshold_id, "n_seen": s.n_seen, "w_seen": s.w_seen, "held": s.held, "k": spec.k, "k_max": spec.k_max,
            "seed": spec.seed, "method": f"{self.method}/{spec.fill}", "weight": spec.weight, "stored": self.stored, "files": self.files,
        }

    def _restore(self) -> None:
        row = self.log.newest()
        if row is None:
            return
        mine = self._row()
        other = [c for c in ("stream_id", "k", "k_max", "seed", "method", "weight") if row[c] != mine[c]]
        if other:
            raise ValueError(f"{self.path} holds the state of a sampler with another {other[0]}")
        self.state = State(row["threshold"], row["threshold_id"], row["version"], row["n_seen"], row["w_seen"], row["held"])
        self.stored, self.files = row["stored"], row["files"]

    def runs(self) -> DataFrame | None:
        """What is held."""
        if not self.files:
            return None
        rows = self.spark.read.schema(RUN).parquet(*self.files)
        t = self.state.threshold
        return rows if t is None else rows.where(up_to((t, self.state.threshold_id)))

    def sample(self) -> DataFrame:
        """The sample after the last batch, with the order of draws."""
        runs = self.runs()
        rows = runs if runs is not None else self.spark.createDataFrame([], RUN)
        return rows.withColumn("draw_no", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("key", "item_id")))

    def _fill(self, rows: DataFrame, batch_no: int, found: Observation) -> DataFrame:
        """The rows to write; ``found`` takes the number of candidates, the most of one partition, and what jumps looked at."""
        t, spec = self.state.threshold, self.spec
        jumps = spec.fill == "jump"
        if jumps:
            hits = candidates_by_jump(rows, spec, t, batch_no, counted=True)
        else:
            hits = (candidates_by_key if spec.fill == "key" else candidates_by_test)(rows, spec, t)
        looked = [F.col(c) if jumps else F.lit(0).cast("long").alias(c) for c in ("examined", "skipped")]
        # an id's low bits are the row's place in its partition
        place = (F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)) + 1).alias("place")
        hits = hits.select("item_id", "w", "key", F.lit(batch_no).cast("long").alias("batch_no"), F.spark_partition_id().alias("pe"), place, *looked)
        item = F.col("item_id").isNotNull()
        hits = hits.observe(found, F.count_if(item).alias("c"), F.max(F.when(item, F.col("place"))).alias("most"), F.sum("examined").alias("examined"), F.sum("skipped").alias("skipped"))
        hits = (hits.where(item) if jumps else hits).drop("place", "examined", "skipped")
        if t is None and spec.cap and not jumps:
            hits = local_cap(hits, max(spec.k, spec.k_max or 0))
        return hits.repartition(self.parts, F.xxhash64("item_id")) if spec.incremental else hits

    def _select(self, runs: DataFrame, held: int, new: int, report: Report) -> Selected | None:
        """None: the threshold stays as it is."""
        spec, seed = self.spec, self.spec.seed + report.batch_no
        if held <= spec.k or (spec.k_max is not None and spec.lazy and held <= spec.k_max):
            return None
        runs = runs.select("key", "item_id")
        if spec.k_max is None and spec.selector in ("tail", "sort"):
            return select(spec.selector, runs, spec.k, held)  # one pass: nothing to keep
        runs = runs.persist()
        try:
            if spec.k_max is not None:
                return pivot_select(runs, spec.k, min(spec.k_max, held), held, spec.d, seed, finish=1)
            if spec.selector == "combined" and spec.incremental:
                return incremental_select(runs, spec.k, held, new, self.parts, seed)
            return select(spec.selector, runs, spec.k, held, spec.d, self.parts, seed, spec.finish)
        finally:
            runs.unpersist()

    def process(self, batch: DataFrame, batch_no: int | None = None) -> Report:
        """Take in one batch. A number not above the last one taken is a repetition and changes nothing."""
        s, spec = self.state, self.spec
        batch_no = s.version + 1 if batch_no is None else batch_no
        if batch_no <= s.version:
            return self.reports.rows[-1] if self.reports.rows else Report(self.method, s.version, held_before=s.held, held_after=s.held, threshold_before=s.threshold, threshold_after=s.threshold)
        report = Report(self.method, batch_no, held_before=s.held, threshold_before=s.threshold)
        began, counts, found, written = time.perf_counter(), Observation(), Observation(), Observation()
        rows = items(batch, spec).withColumn("ok", V.valid_weight(F.col("w")))
        rows = rows.observe(counts, F.count_if("ok").alias("n"), F.sum(F.when(F.col("ok"), F.col("w"))).alias("w"), F.count_if(~F.col("ok")).alias("bad")).where("ok").drop("ok")
        path = f"{self.path}/batch-{batch_no}"
        self._fill(rows, batch_no, found).observe(written, F.count(F.lit(1)).alias("c")).write.mode("overwrite").parquet(path)
        got, seen, c = counts.get, found.get, written.get["c"] or 0
        report.n_items, report.w_items, report.n_rejected, report.stored, report.jobs = got["n"], got["w"] or 0.0, got["bad"], c, 1
        report.candidates, report.candidates_max_pe = seen["c"] or 0, seen["most"] or 0
        if spec.fill == "jump":
            report.rows_examined, report.blocks_skipped = seen["examined"] or 0, seen["skipped"] or 0
            if s.threshold is None:
                report.candidates = report.n_items
        else:
            report.rows_examined = report.n_items
        if c:
            self.files = [*self.files, path]
        self.stored += c
        held = s.held + c
        report.t_insert = time.perf_counter() - began
        began = time.perf_counter()
        chosen = self._select(self.runs(), held, c, report) if c or held > spec.k else None
        if spec.incremental:
            report.rows_moved += c
        if chosen is not None:
            s.threshold, s.threshold_id, held = chosen.key, chosen.item_id, chosen.rank
            report.rounds, report.pivots_drawn, report.rows_moved = chosen.rounds, chosen.pivots, report.rows_moved + chosen.rows_moved
            report.jobs += chosen.jobs
        elif held == spec.k and spec.k_max is None and c:
            last = self.runs().agg(F.max(F.struct("key", "item_id"))).first()[0]
            s.threshold, s.threshold_id, report.jobs = last["key"], last["item_id"], report.jobs + 1
        report.t_select = time.perf_counter() - began
        began = time.perf_counter()
        s.version, s.n_seen, s.w_seen, s.held = batch_no, s.n_seen + report.n_items, s.w_seen + report.w_items, held
        report.held_after, report.threshold_after = held, s.threshold
        if len(self.files) > 1 and self.stored > 4 * max(held, spec.k) or len(self.files) > 24:
            self._compact(batch_no)
            report.jobs += 1
        # the new threshold, and the files that it cuts, are what the next batch, or the next run, begins with
        self.log.write(batch_no, self._row())
        report.t_threshold = time.perf_counter() - began
        report.bytes_moved = 16 * report.rows_moved
        self.reports.rows.append(report)
        return report

    def _compact(self, batch_no: int) -> None:
        path = f"{self.path}/cut-{batch_no}"
        self.runs().write.mode("overwrite").parquet(path)
        self.files, self.stored = [path], self.state.held

    def report(self) -> DataFrame:
        return self.reports.table(self.spark)


class VariableSampler(DecentralSampler):
    """Keeps between k and k_max items: any threshold gives a sample, so it is only moved once the sample outgrows k_max (lazy), or, eagerly, in every batch."""

    method = "variable"

    def __init__(self, spark: SparkSession, spec: SamplerSpec, path: str | None = None):
        if spec.k_max is None:
            raise ValueError("k_max is needed")
        super().__init__(spark, spec, path)


def counts_of_small_batches(df: DataFrame, spec: SamplerSpec, batch: str, group: int = 4096) -> DataFrame:
    """(batch_no, n_items, candidates, held_after) of ``GatherSampler`` over batches of few items, for every batch with rows, in two passes.

    The first finds the k smallest keys of each ``group`` of successive batches; their running union, k numbers a group, tells what is held before a group.
    """
    k = spec.k
    rows = items(df, spec, F.expr(batch).cast("long").alias("batch_no"))
    rows = rows.select("batch_no", F.floor(F.col("batch_no") / group).alias("part"), F.when(V.valid_weight(F.col("w")), key_of(spec)).alias("key"))
    least = rows.groupBy("part").agg(F.slice(F.array_sort(F.collect_list("key")), 1, k).alias("least"))
    before, held = {}, []
    for r in least.orderBy("part").collect():
        before[r["part"]] = held
        held = sorted([*held, *r["least"]])[:k]

    def run(key: tuple, batches: pd.DataFrame) -> pd.DataFrame:
        held, out = before[key[0]], []
        for number, keys in batches.sort_values("batch_no").groupby("batch_no")["key"]:
            new = keys.dropna().tolist()
            found = [x for x in new if x <= held[-1]] if len(held) == k else new
            held = sorted([*held, *found])[:k]
            out.append((number, len(new), len(found), len(held)))
        return pd.DataFrame(out, columns=["batch_no", "n_items", "candidates", "held_after"])

    return rows.groupBy("part").applyInPandas(run, "batch_no long, n_items long, candidates long, held_after long")


class GatherSampler:
    """The centralised way: partitions discard by the threshold, at most k rows of each go to the driver, which selects and sends the threshold back.

    ``gather_bytes`` bounds what the driver takes; beyond it the batch is refused, and the decentralised sampler is the way to go.
    """

    method = "gather"

    def __init__(self, spark: SparkSession, spec: SamplerSpec):
        self.spark, self.spec, self.state, self.reports = spark, spec, State(), Reports()
        self.held = pd.DataFrame({"item_id": np.zeros(0, dtype=object), "w": np.zeros(0), "key": np.zeros(0), "batch_no": np.zeros(0, dtype=np.int64), "pe": np.zeros(0, dtype=np.int32)})

    def process(self, batch: DataFrame, batch_no: int | None = None) -> Report:
        s, spec = self.state, self.spec
        batch_no = s.version + 1 if batch_no is None else batch_no
        if batch_no <= s.version:
            return self.reports.rows[-1]
        report, counts, began = Report(self.method, batch_no, held_before=s.held, threshold_before=s.threshold), Observation(), time.perf_counter()
        rows = items(batch, spec).withColumn("ok", V.valid_weight(F.col("w")))
        rows = rows.observe(counts, F.count_if("ok").alias("n"), F.sum(F.when(F.col("ok"), F.col("w"))).alias("w"), F.count_if(~F.col("ok")).alias("bad")).where("ok").drop("ok")
        found = candidates_by_key(rows, spec, s.threshold) if spec.fill != "jump" else candidates_by_jump(rows, spec, s.threshold, batch_no)
        found = found.select("item_id", "w", "key", F.lit(batch_no).cast("long").alias("batch_no"), F.spark_partition_id().alias("pe"))
        if s.threshold is None and spec.fill != "jump":
            found = local_cap(found, spec.k)  # no place sends more than its k smallest
        limit = max(spec.k, spec.gather_bytes // 64)
        new = found.limit(limit + 1).toPandas()
        if len(new) > limit:
            raise MemoryError(f"more than {limit} candidates in one batch; use the decentralised sampler")
        report.t_gather = time.perf_counter() - began
        began = time.perf_counter()
        self.held = pd.concat([self.held, new], ignore_index=True)
        if len(self.held) >= spec.k:
            t = local_kth(self.held["key"].to_numpy(), self.held["item_id"].to_numpy(), spec.k)
            keep = (self.held["key"] < t[0]) | ((self.held["key"] == t[0]) & (self.held["item_id"] <= t[1]))
            self.held = self.held[keep].reset_index(drop=True)
            s.threshold, s.threshold_id = t
        report.t_select, got = time.perf_counter() - began, counts.get
        report.n_items, report.w_items, report.n_rejected, report.stored, report.jobs = got["n"], got["w"] or 0.0, got["bad"], len(new), 1
        report.candidates = got["n"] if report.threshold_before is None else len(new)
        report.candidates_max_pe = int(new["pe"].value_counts().max()) if len(new) else 0
        report.rows_moved, report.bytes_moved, report.held_after, report.threshold_after = len(new), int(new.memory_usage(deep=True).sum()), len(self.held), s.threshold
        s.version, s.n_seen, s.w_seen, s.held = batch_no, s.n_seen + report.n_items, s.w_seen + report.w_items, len(self.held)
        self.reports.rows.append(report)
        return report

    def sample(self) -> DataFrame:
        rows = self.held.sort_values(["key", "item_id"]).reset_index(drop=True)
        rows["draw_no"] = np.arange(1, len(rows) + 1)
        return self.spark.createDataFrame(rows, f"{RUN}, draw_no int")

    def report(self) -> DataFrame:
        return self.reports.table(self.spark)


def auto_method(spec: SamplerSpec, candidates: float, row_bytes: int = 64) -> str:
    """gather while the sample and a batch's candidates fit the driver's share, decentral beyond."""
    return "gather" if (spec.k + candidates) * row_bytes <= spec.gather_bytes else "decentral"


def _one_stream(k: int, seed: int, weighted: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one, held = skips.Sequential(k, seed, weighted), {}
        for b in batches:
            w, before = b.column(1).to_numpy(zero_copy_only=False), one.seen
            entered = len(one.log)
            one.add(w)
            for at in one.log[entered:]:
                held[at] = (b.column(0)[at - before].as_py(), float(w[at - before]))
            kept = {at for _, at in one.heap}
            held = {at: x for at, x in held.items() if at in kept}
        at, keys = one.sample()
        if len(at):
            ids, w = zip(*(held[i] for i in at.tolist()), strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.string()), pa.array(w, pa.float64()), pa.array(keys), pa.array(np.full(len(at), len(one.log)), pa.int64())], names=["item_id", "w", "key", "insertions"])

    return run


def sequential_sample(df: DataFrame, spec: SamplerSpec) -> DataFrame:
    """The sequential sampler, for one stream in item order: the reference that the others are held against. It is one task by its nature, and holds k items."""
    rows = valid(items(df, spec)).repartition(1).sortWithinPartitions("item_id")
    return rows.mapInArrow(_one_stream(spec.k, spec.seed, spec.weight is not None), "item_id string, w double, key double, insertions long")
