"""Exact duplicates by a tree of merged digest runs; DataFrame functions only.

Every document becomes one small row (digest, length, id). The input's partitions are the leaves: each holds a run. Runs are merged in
rounds of a binomial tree of ``fan`` branches: in round r the runs whose numbers differ in digit r only exchange their rows, so that each of them ends
with the rows of one part of the digests. Every round sorts what arrives and merges it in order: rows of one digest meet, the best one
stays, and sizes add up, so a digest that holds a third of all rows is one row a run after the first step and thins out by ``fan`` in every
round before it meets in one place. After log_fan(runs) rounds a run's number is a part of its digests, each different text has one row, and a
join on the digest, whose hot partitions adaptive execution splits, hands the outcome to all documents.

"Verified": rows meet only if SHA-256, the length in bytes and a second, independent 64-bit hash of the normalised text agree,
at every level of the tree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import Workspace, keep_rows, raw_key, read, without_white

KEY = ["digest", "n_bytes", "proof"]


def digest_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", runs: int = 64) -> DataFrame:
    """(doc_id, raw_key, n_points, digest, n_bytes, proof, run) for every row; run: the partition it is read in, of ``runs``."""
    raw = docs.select(F.col(id_col).cast("long").alias("doc_id"), raw_key(F.col(text_col)).alias("raw_key"), F.coalesce(F.col(text_col), F.lit("")).alias("raw"))
    plain = raw.select("doc_id", "raw_key", F.char_length("raw").alias("n_points"), without_white(F.col("raw")).alias("plain"))
    return plain.select(
        "doc_id",
        "raw_key",
        "n_points",
        F.unhex(F.sha2("plain", 256)).alias("digest"),
        F.octet_length("plain").alias("n_bytes"),
        F.xxhash64("plain").alias("proof"),
        F.pmod(F.spark_partition_id(), F.lit(runs)).cast("int").alias("run"),
    )


def partner(digits: int, place: int, fan: int) -> Column:
    """The run that takes a row in a round: its own number with one digit replaced by that of the row's digest."""
    unit = fan**place
    own = F.floor(F.col("run") / unit) % fan
    of_digest = F.floor(F.pmod(F.xxhash64("digest"), F.lit(fan**digits)) / unit) % fan
    return (F.col("run") + (of_digest - own) * unit).cast("int")


def merge_runs(rows: DataFrame, runs: int = 64, fan: int = 4) -> DataFrame:
    """One row for each different text: key, keep_id, keep_raw, group_size. ``rows`` as ``digest_rows`` returns them."""
    # the greatest (points, then smallest id): with all bits of an id turned one max serves both, for the least long too; a null id loses every tie
    best = F.struct("n_points", F.bitwise_not("doc_id").alias("turned"), "raw_key")
    level = rows.groupBy("run", *KEY).agg(F.max(best).alias("best"), F.count(F.lit(1)).alias("size"))
    digits = 0
    while fan**digits < runs:
        digits += 1
    for place in range(digits):
        arrived = level.withColumn("run", partner(digits, place, fan)).repartition("run", *KEY).sortWithinPartitions("run", *KEY)
        level = arrived.groupBy("run", *KEY).agg(F.max("best").alias("best"), F.sum("size").alias("size"))
    return level.select(*KEY, F.bitwise_not("best.turned").alias("keep_id"), F.col("best.raw_key").alias("keep_raw"), F.col("size").alias("group_size"))


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", runs: int = 64, fan: int = 4) -> DataFrame:
    """One row for each row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256, raw_key.

    Null texts count as empty, and empty texts equal each other. The row with the most code points in its original
    text stays, then the one with the smallest id; rows with a null id lose ties. Rows that repeat an id are told apart by their texts
    (raw_key); rows that repeat id and text share their verdict. Other columns of ``docs`` are not read. An empty table gives an empty result.
    """
    space = Workspace(docs.sparkSession, "exact")
    rows = space.store(digest_rows(docs, id_col, text_col, runs), "digests")
    best = merge_runs(rows, runs, fan)
    return rows.join(best, KEY).select(
        "doc_id",
        "keep_id",
        "group_size",
        (F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("raw_key") == F.col("keep_raw"))).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
        "raw_key",
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs``, all its columns, with one row of each group of equal texts. Of rows that repeat id and text, too, one stays."""
    verdicts = exact_groups(docs, id_col, text_col).select("doc_id", "raw_key", F.col("kept").alias("stays"))
    return keep_rows(docs, verdicts, id_col, text_col, Workspace(docs.sparkSession, "copies"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(read(spark, sf_dir, "documents")).drop("raw_key")


ORACLE = r"""
WITH d AS (
  SELECT doc_id, length(coalesce(text, '')) AS n_points,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
  FROM documents),
g AS (
  SELECT text_sha256, count(*) AS group_size, first(doc_id ORDER BY n_points DESC, doc_id) AS keep_id
  FROM d GROUP BY text_sha256)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM d JOIN g USING (text_sha256)
"""
