"""Sampling that reads only the blocks it hits: sums of weight by block of a file, drawn against the threshold first.

A block of weight S has an item below threshold T with chance 1 - exp(-T S), blocks independently. In a hit block the first jump is
drawn given that it ends inside; later ones are plain. Exact, since walks may start anywhere. Files without a hit block are not opened; within the
others, rows of hit blocks go on. It pays where T times a file's weight is small.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import skips
from ..functions import variates as V
from ..model import SamplerSpec
from ..plans.batches import items

BLOCK_ROWS = 4096


def blocks(spark: SparkSession, path: str, rows: int = BLOCK_ROWS, files: list[str] | None = None) -> DataFrame:
    """The table, or some files of it, with the block each row lies in: the file's path, the file's size, and the block's number in it."""
    reader = spark.read
    if files:
        folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        if folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(folder).isDirectory():
            reader = reader.option("basePath", path)  # columns that folder names hold stay
    df = reader.parquet(*(files or [path]))
    return df.withColumn("file", F.col("_metadata.file_path")).withColumn("file_bytes", F.col("_metadata.file_size")).withColumn("block", F.floor(F.col("_metadata.row_index") / rows))


def block_rng(seed: int, file: str, block: int) -> np.random.Generator:
    """A generator of its own for each block of each file."""
    return np.random.default_rng([seed, int(block), int.from_bytes(hashlib.blake2b(file.encode(), digest_size=8).digest(), "little")])


def build(spark: SparkSession, path: str, spec: SamplerSpec, rows: int = BLOCK_ROWS) -> DataFrame:
    """The manifest: (file, file_bytes, block, n, weight). A row for each block; write it beside the table."""
    w = F.expr(spec.weight).cast("double") if spec.weight else F.lit(1.0)
    return blocks(spark, path, rows).select("file", "file_bytes", "block", w.alias("w")).where(V.valid_weight(F.col("w"))).groupBy("file", "file_bytes", "block").agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("weight"))


def hit_blocks(manifest: DataFrame, spec: SamplerSpec, threshold: float) -> DataFrame:
    """The blocks that are read at all."""
    draw = V.uniform_key(F.concat_ws("/", "file", F.col("block").cast("string")), spec.stream_id, spec.seed, "block")
    rate = F.lit(threshold) if spec.weight else F.lit(-np.log1p(-min(threshold, 1 - 1e-12)))
    return manifest.withColumn("draw", draw).where(F.col("draw") <= -F.expm1(-rate * F.col("weight")))


def _walk(threshold: float, seed: int, block: int, weighted: bool):
    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("item_id")
        w, rng = rows["w"].to_numpy(), block_rng(seed, key[0], key[1])
        if weighted:
            first = -np.log1p(skips.unit(rng) * np.expm1(-threshold * w.sum())) / threshold
            hit = skips.weighted_fill(w, threshold, rng, block, first=min(first, np.nextafter(w.sum(), 0)))
        else:
            hit = skips.uniform_fill(len(w), threshold, rng)
            while not len(hit.positions):
                hit = skips.uniform_fill(len(w), threshold, rng)
        out = rows.iloc[hit.positions].copy()
        out["key"] = hit.keys
        return out[["item_id", "w", "key"]]

    return run


def what_is_read(manifest: DataFrame, spec: SamplerSpec, threshold: float) -> DataFrame:
    """(files, files_read, file_bytes, bytes_read, blocks, blocks_hit) of a draw: one row."""
    hits = hit_blocks(manifest, spec, threshold).select("file", "block", F.lit(True).alias("hit"))
    per_file = manifest.join(hits, ["file", "block"], "left").groupBy("file", "file_bytes").agg(F.count(F.lit(1)).alias("blocks"), F.count("hit").alias("hits"))
    read = F.col("hits") > 0
    return per_file.agg(
        F.count(F.lit(1)).alias("files"),
        F.count_if(read).alias("files_read"),
        F.coalesce(F.sum("file_bytes"), F.lit(0)).alias("file_bytes"),
        F.coalesce(F.sum(F.when(read, F.col("file_bytes"))), F.lit(0)).alias("bytes_read"),
        F.coalesce(F.sum("blocks"), F.lit(0)).alias("blocks"),
        F.coalesce(F.sum("hits"), F.lit(0)).alias("blocks_hit"),
    )


def sample_from_manifest(spark: SparkSession, path: str, manifest: DataFrame, spec: SamplerSpec, threshold: float, rows: int = BLOCK_ROWS) -> DataFrame:
    """The items below the threshold, (item_id, w, key), from the hit files alone. A group is one block, so it is bounded.

    The paths of the hit files come to the driver, which lists the files of any table it scans.
    """
    hits = hit_blocks(manifest, spec, threshold).select("file", "block")
    files = [r["file"] for r in hits.select("file").distinct().collect()]
    if not files:
        return spark.createDataFrame([], "item_id string, w double, key double")
    picked = items(blocks(spark, path, rows, files), spec, "file", "block").where(V.valid_weight(F.col("w"))).join(hits, ["file", "block"], "left_semi")
    return picked.groupBy("file", "block").applyInPandas(_walk(threshold, spec.seed, spec.block, spec.weight is not None), "item_id string, w double, key double")


def uniform_positions(manifest: DataFrame, threshold: float, seed: int) -> DataFrame:
    """(file, block, place) of the rows that enter a uniform sample, from row counts alone; the data is not looked at."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for f, k, n in zip(b["file"], b["block"], b["n"], strict=True):
                at = skips.uniform_fill(int(n), threshold, block_rng(seed, f, k)).positions
                yield pd.DataFrame({"file": f, "block": k, "place": at})

    return manifest.mapInPandas(run, "file string, block long, place long")
