"""What several operators of this subpackage use: stored tables that cut lineage, and text columns."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The six characters that the contracts call white space. Fixed values.
WHITE = " \t\n\x0b\x0c\r"


def shared_root(spark: SparkSession) -> str:
    """The folder that all executors see: ``spark.checkpoint.dir``. Where it is unset, a temporary one in local runs, and an error on a cluster, whose machines share none."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            return held.get().rstrip("/")
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
        root = f"file://{tempfile.mkdtemp(prefix='shared-')}"
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


class Workspace:
    """Tables written once to the shared folder and read back, so that lost executors never force old stages to run again."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.base = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"

    def store(self, df: DataFrame, name: str, by: str | None = None, codec: str = "zstd", level: int = 3) -> DataFrame:
        """Write ``df`` and return the reread table. ``by``: a column to lay folders out by. ``level``: of zstd."""
        path, schema = f"{self.base}/{name}", df.schema
        writer = df.write.mode("overwrite").option("compression", codec).option("parquet.compression.codec.zstd.level", str(level))
        (writer.partitionBy(by) if by else writer).parquet(path)
        return self.spark.read.schema(schema).parquet(path)

    def drop(self, name: str = "") -> None:
        """Remove a table that no later stage reads; without a name, all of them, once results that read them are written."""
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.base}/{name}".rstrip("/"))
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def trim() -> None:
    """Give memory that a worker no longer uses back to the machine, where the C library can."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def ascii_lower(text: Column) -> Column:
    """A-Z to a-z and nothing else: texts of one byte a character take the fast built-in."""
    upper = "".join(map(chr, range(65, 91)))
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, upper, upper.lower()))


def without_white(text: Column) -> Column:
    """The text without its white space; one byte search for each of the six characters."""
    for ch in WHITE:
        text = F.replace(text, F.lit(ch), F.lit(""))
    return text


def raw_key(text: Column) -> Column:
    """Beside its id, tells a row from others that repeat the id with another text. A null text is empty."""
    return F.xxhash64(F.coalesce(text.cast("string"), F.lit("")))


def keep_rows(docs: DataFrame, verdicts: DataFrame, id_col: str, text_col: str, space: Workspace) -> DataFrame:
    """``docs``, all its columns, without the rows whose verdict is not to stay, and one of rows that repeat id and text.

    verdicts: (doc_id, raw_key, stays), a row for each row of ``docs``. Ids meet null-safely. Repeats, which are few as a rule, are
    taken from a second scan, whose rows are combined before they move.
    """
    once = verdicts.groupBy(F.col("doc_id").alias("__id"), F.col("raw_key").alias("__raw")).agg(F.max("stays").alias("stays"), F.count(F.lit(1)).alias("c"))
    once = space.store(once.where("NOT stays OR c > 1"), "verdicts")
    same = lambda: docs[id_col].cast("long").eqNullSafe(F.col("__id")) & (raw_key(docs[text_col]) == F.col("__raw"))
    kept = docs.join(once, same(), "left_anti")
    repeated = once.where("stays")
    if repeated.isEmpty():
        return kept
    again = docs.join(repeated, same(), "left_semi").withColumn("__id", docs[id_col].cast("long")).withColumn("__raw", raw_key(docs[text_col]))
    return kept.union(again.dropDuplicates(["__id", "__raw"]).drop("__id", "__raw"))


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")
