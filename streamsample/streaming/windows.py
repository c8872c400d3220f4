"""Samples over windows: of batches, of event time, of sessions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import SamplerSpec
from ..plans.batches import keyed


def per_batch_smallest(df: DataFrame, spec: SamplerSpec, batch: str) -> DataFrame:
    """Each batch's k smallest keys: any window of whole batches has its sample among them."""
    rows = keyed(df.withColumn("batch_no", F.expr(batch).cast("long")), spec, "batch_no")
    place = F.row_number().over(Window.partitionBy("batch_no").orderBy("key", "item_id"))
    return rows.withColumn("place", place).where(F.col("place") <= spec.k).drop("place")


def sliding_sample(df: DataFrame, spec: SamplerSpec, batch: str, length: int) -> DataFrame:
    """The sample of the last ``length`` batches at the end of each batch: (window_end, item_id, w, key, draw_no)."""
    small = per_batch_smallest(df, spec, batch)
    last = small.agg(F.max("batch_no").alias("last_batch"))
    ends = F.sequence(F.col("batch_no"), F.least(F.col("batch_no") + length - 1, F.col("last_batch")))
    seen = small.crossJoin(F.broadcast(last)).withColumn("window_end", F.explode(ends))
    place = F.row_number().over(Window.partitionBy("window_end").orderBy("key", "item_id"))
    return seen.withColumn("draw_no", place).where(F.col("draw_no") <= spec.k).select("window_end", "item_id", "w", "key", "draw_no")


def window_sample(df: DataFrame, spec: SamplerSpec, length: str, slide: str | None = None) -> DataFrame:
    """A sample of each window of event time (``ts``)."""
    timed = df.withColumn("ts", F.col("ts").cast("timestamp"))
    rows = keyed(timed, spec, "ts").withColumn("window", F.window("ts", length, slide) if slide else F.window("ts", length))
    place = F.row_number().over(Window.partitionBy("window").orderBy("key", "item_id"))
    return rows.withColumn("draw_no", place).where(F.col("draw_no") <= spec.k).select(F.col("window.start").alias("window_start"), "item_id", "w", "key", "draw_no")
