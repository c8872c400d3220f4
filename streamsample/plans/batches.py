"""Mini-batches out of tables: valid rows with item, weight and key, one batch number at a time."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import variates as V
from ..model import SamplerSpec

DAY = "datediff(cast(ts AS date), DATE '2024-01-01')"


def items(df: DataFrame, spec: SamplerSpec, *payload: str) -> DataFrame:
    """(item_id, w, payload...), only the columns needed, so that the scan reads no others. Uniform samples have weight 1."""
    w = F.expr(spec.weight).cast("double") if spec.weight else F.lit(1.0)
    drawn = [F.col(spec.variate).alias("variate")] if spec.variate else []
    return df.select(V.item_id(spec.id_cols).alias("item_id"), w.alias("w"), *drawn, *payload)


def valid(rows: DataFrame) -> DataFrame:
    return rows.where(V.valid_weight(F.col("w")))


def variate_of(spec: SamplerSpec) -> Column:
    return F.col("variate") if spec.variate else V.uniform_key(F.col("item_id"), spec.stream_id, spec.seed)


def key_of(spec: SamplerSpec) -> Column:
    item, w = F.col("item_id"), F.col("w")
    if spec.deep and spec.weight:
        return V.deep_exp_key(item, w, spec.stream_id, spec.seed)
    u = variate_of(spec)
    return V.exp_key(u, w) if spec.weight else u


def keyed(df: DataFrame, spec: SamplerSpec, *payload: str) -> DataFrame:
    """Valid items with their keys."""
    return valid(items(df, spec, *payload)).withColumn("key", key_of(spec))


def staged(df: DataFrame, batch: str, path: str) -> DataFrame:
    """The rows with batch_no, written once in folders by batch, so that reading a batch reads no other; about as many partitions as ``df`` has."""
    numbered = df.withColumn("batch_no", F.expr(batch).cast("long"))
    numbered.repartitionByRange("batch_no", F.spark_partition_id()).write.mode("overwrite").partitionBy("batch_no").parquet(path)
    return df.sparkSession.read.schema(numbered.schema).parquet(path)


def replay(df: DataFrame, batch: str, last: int | None = None, path: str | None = None) -> Iterator[tuple[int, DataFrame]]:
    """(number, rows) of each batch, in order; ``batch``: an SQL expression that gives the number. ``path``: where to stage the batches; each one is a scan of ``df`` without it."""
    numbered = df.withColumn("batch_no", F.expr(batch).cast("long")) if path is None else staged(df, batch, path)
    ends = numbered.agg(F.min("batch_no"), F.max("batch_no")).first()
    if ends[0] is None:
        return
    for b in range(ends[0], (ends[1] if last is None else min(last, ends[1])) + 1):
        yield b, numbered.where(F.col("batch_no") == b)
