"""Lines that repeat across documents, counted in levelled sorted runs; DataFrame functions only.

Documents come in batches. A batch turns its lines into 128-bit keys and counts each key once a document. Keys that
have already reached the limit in earlier batches are settled: the batch is merge-anti-joined with them and adds only the
rest, as a new sorted run of level 0. When a level holds ``fan`` runs they are compacted into one run of the next level, where
keys that reach the limit move to the settled ones. At the end all runs are merged once more.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import WHITE, Workspace, ascii_lower, raw_key, read

KEY = ["h1", "h2"]


def line_key(line: Column) -> Column:
    return ascii_lower(F.btrim(line, F.lit(WHITE)))


def hashed_lines(docs: DataFrame, id_col: str, text_col: str, min_points: int, batches: int) -> DataFrame:
    """(doc_id, raw_key, pos, h1, h2, first, batch): the lines whose keys are long enough; ``first``: the key's first line in its document."""

    def hashed(line: Column, pos: Column) -> Column:
        key = line_key(line)
        return F.when(
            F.char_length(key) >= min_points,
            F.struct(F.xxhash64(key).alias("h1"), F.xxhash64(F.lit(7), F.reverse(key)).alias("h2"), pos.cast("int").alias("pos")),
        )

    lines = F.split(F.coalesce(F.col(text_col), F.lit("")), "\n", -1)
    found = F.array_sort(F.filter(F.transform(lines, hashed), lambda x: x.isNotNull()))
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), raw_key(F.col(text_col)).alias("raw_key"), found.alias("found"))
    before = lambda i: F.get(F.col("found"), i - 1)
    marked = F.transform(
        "found", lambda x, i: F.struct(x["h1"].alias("h1"), x["h2"].alias("h2"), x["pos"].alias("pos"), ((i == 0) | (x["h1"] != before(i)["h1"]) | (x["h2"] != before(i)["h2"])).alias("first"))
    )
    return base.select("doc_id", "raw_key", F.pmod(F.xxhash64("doc_id"), F.lit(batches)).cast("int").alias("batch"), F.inline(marked))


class LevelledRuns:
    """Sorted runs of (h1, h2, n) by level, and the settled keys."""

    def __init__(self, space: Workspace, limit: int, fan: int = 2):
        self.space, self.limit, self.fan = space, limit, fan
        self.levels: dict[int, list[DataFrame]] = {}
        self.settled: list[DataFrame] = []
        self.made = 0

    def _store(self, df: DataFrame) -> DataFrame:
        self.made += 1
        return self.space.store(df.sortWithinPartitions(*KEY), f"run{self.made}")

    def add(self, batch: DataFrame) -> None:
        """``batch``: a row (h1, h2) for each document and key in it."""
        new = batch.groupBy(*KEY).agg(F.count(F.lit(1)).alias("n"))
        for old in self.settled:
            new = new.join(old.hint("merge"), KEY, "left_anti")
        self._push(0, self._store(new))

    def _push(self, level: int, run: DataFrame) -> None:
        runs = self.levels.setdefault(level, [])
        runs.append(run)
        if len(runs) == self.fan:
            self.levels[level] = []
            merged = self._store(self._merge(runs))
            self.settled.append(merged.where(F.col("n") >= self.limit))
            self._push(level + 1, merged.where(F.col("n") < self.limit))

    @staticmethod
    def _merge(runs: list[DataFrame]) -> DataFrame:
        return reduce(DataFrame.union, runs).groupBy(*KEY).agg(F.sum("n").alias("n"))

    def frequent(self) -> DataFrame:
        """The keys with at least ``limit`` documents."""
        open_runs = [run for runs in self.levels.values() for run in runs]
        parts = [*self.settled, *([self._merge(open_runs).where(F.col("n") >= self.limit)] if open_runs else [])]
        return reduce(DataFrame.union, parts).select(*KEY)


def drop_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_points: int = 1, min_docs: int = 10, batches: int = 4) -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept_text) for each row of ``docs``.

    A null or empty text is one empty line. A key is a line without white space at its ends and with A-Z lower-cased; keys
    shorter than ``min_points`` never go. Every row is a document of its own in the counts, rows that share an id, or have a null one, too; each
    loses its own lines only. Other columns are not read. An empty table gives an empty result.
    """
    space = Workspace(docs.sparkSession, "lines")
    lines = space.store(hashed_lines(docs, id_col, text_col, min_points, batches), "lines", by="batch")
    store = LevelledRuns(space, min_docs)
    for b in range(batches):
        store.add(lines.where((F.col("batch") == b) & F.col("first")).select(*KEY))
    gone = lines.join(store.frequent(), KEY, "left_semi").groupBy(F.col("doc_id").alias("gone_id"), F.col("raw_key").alias("gone_raw")).agg(F.collect_set("pos").alias("gone"))
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), raw_key(F.col(text_col)).alias("raw_key"), F.coalesce(F.col(text_col), F.lit("")).alias("raw"))
    none = F.array().cast("array<int>")
    same = F.col("doc_id").eqNullSafe(F.col("gone_id")) & (F.col("raw_key") == F.col("gone_raw"))
    marked = base.join(gone, same, "left").select("doc_id", F.split("raw", "\n", -1).alias("lines"), F.coalesce("gone", none).alias("gone"))
    stay = F.array_except(F.sequence(F.lit(0), F.size("lines") - 1), F.col("gone"))
    kept = F.array_join(F.transform(stay, lambda i: F.get(F.col("lines"), i)), "\n")
    return marked.select("doc_id", F.size("lines").cast("long").alias("n_lines"), F.size("gone").cast("long").alias("n_dropped"), kept.alias("kept_text"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = drop_lines(read(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


ORACLE = r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
k AS (
  SELECT doc_id, line, pos,
         translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM l),
f AS (SELECT key FROM k WHERE length(key) >= 1 GROUP BY key HAVING count(DISTINCT doc_id) >= 10),
m AS (SELECT k.*, f.key IS NOT NULL AS gone FROM k LEFT JOIN f ON k.key = f.key)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
