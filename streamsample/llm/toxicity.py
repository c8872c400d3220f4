"""Toxicity of whole texts by a small recurrent network over overlapping windows of words.

The network (``gru``) is trained on the driver on a bounded sample of labelled rows and sent to the tasks. A text's score is that of
its strongest window; windows of 32 words start every 16 words, so every word but those at the ends lies in two. A run of more than 62 bytes without blanks
counts as several words: its parts between joining marks, or sub-words that overlap by half. Only the text enters a score.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .gru import DIMS, Words, embedded, sigmoid, tables_of, text_logits, train, word_inputs, words_of
from .shared import read, trim
from .tokens import text_parts

#: Labelled rows that training takes at most, of label 0 and label 1, and the longest text among them.
SAMPLE, LONGEST = (3000, 1500), 20_000
#: Distinct words that a task remembers at most.
REMEMBERED = 200_000
OUT = "doc_id long, held_out boolean, score double, predicted int, n_windows long"


def fold(id_col: str) -> F.Column:
    """crc32 of the id as text, mod 5; null for a null id."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 5


def sample(docs: DataFrame, labels: DataFrame, size: tuple[int, int] = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> list[tuple[int, str, int, int]]:
    """At most ``size`` rows (id, text, label, fold) of either label, none of fold 0, by the order of a hash of the id."""
    marked = labels.select(F.col("doc_id").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id IS NOT NULL AND toxic IN (0, 1)")
    marked = marked.groupBy("doc_id").agg(F.max("toxic").alias("toxic"), F.first(fold("doc_id")).alias("fold")).where("fold <> 0")
    some = [marked.where(F.col("toxic") == k).orderBy(F.xxhash64("doc_id"), "doc_id").limit(size[k]) for k in (0, 1)]
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    rows = text.join(F.broadcast(some[0].union(some[1])), "doc_id").where(F.char_length("text") <= LONGEST).dropDuplicates(["doc_id"])
    return sorted((r["doc_id"], r["text"], r["toxic"], r["fold"]) for r in rows.collect())


class Scorer:
    """Scores texts; remembers what the network makes of words, up to a bound."""

    def __init__(self, p: dict[str, np.ndarray] | None):
        self.p = p
        self._forget()

    def _forget(self) -> None:
        self.words, self.done = Words(), 0
        self.tables = {d: np.zeros((0, 0), dtype=np.float32) for d in "fb"}

    def _learn(self) -> None:
        new = self.words.texts[self.done :]
        parts = [embedded(self.p, *word_inputs(new[k : k + 20_000])) for k in range(0, len(new), 20_000)]
        x = np.concatenate(parts) if parts else np.zeros((0, DIMS), dtype=np.float32)
        if not self.done:
            x[0] = 0
        more = tables_of(self.p, x)
        self.tables = {d: np.concatenate([t, more[d]]) if self.done else more[d] for d, t in self.tables.items()}
        self.done = len(self.words.texts)

    def logits(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(logit, number of windows) of each text."""
        if len(self.words.texts) > REMEMBERED:
            self._forget()
        docs = [self.words.ids(words_of(t)) for t in texts]
        self._learn()
        n = np.array([max(1, -(-(len(x) - 16) // 16)) for x in docs])
        return text_logits(self.p, self.tables, docs)[0], n


def _score(p: dict[str, np.ndarray] | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trim()  # what earlier tasks of this worker held
        scorer = Scorer(p)
        for batch in batches:
            for a, b, texts in text_parts(batch.column(2)):
                if p is None:
                    s, n = np.zeros(b - a), np.zeros(b - a, dtype=np.int64)
                else:
                    logit, n = scorer.logits(texts)
                    s = sigmoid(logit.astype(np.float64))
                cols = [batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), pa.array(s), pa.array((s >= 0.5).astype(np.int32)), pa.array(n.astype(np.int64))]
                yield pa.RecordBatch.from_arrays(cols, names=[c.split()[0] for c in OUT.split(", ")])
        del scorer
        trim()

    return run


def fitted(docs: DataFrame, labels: DataFrame, size: tuple[int, int] = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> dict[str, np.ndarray] | None:
    """The network; what the driver took up for the sample and the training is given back to the machine."""
    rows = sample(docs, labels, size, id_col, text_col)
    p = train([r[1] for r in rows], [r[2] for r in rows], [r[3] == 1 for r in rows])
    del rows
    trim()
    return p


def score(docs: DataFrame, labels: DataFrame, size: tuple[int, int] = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted, n_windows) for each row of ``docs``; ``labels``: doc_id, toxic 0/1.

    Null and empty texts have one window without words. Each row stands alone; a null id is not held out. If the labels don't hold both
    classes among the texts, no network can be trained: all scores are 0 and n_windows is 0. Other columns are not read.
    """
    p = fitted(docs, labels, size, id_col, text_col)
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(fold(id_col) == 0, F.lit(False)).alias("held_out"), F.col(text_col).cast("string").alias("text"))
    return base.mapInArrow(_score(p), OUT)


def drop_toxic(docs: DataFrame, labels: DataFrame, size: tuple[int, int] = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs``, all its columns, without the rows whose text scores 0.5 or more. Repeated and null ids do no harm."""
    scorer = fitted(docs, labels, size, id_col, text_col)
    names, spot = docs.columns, docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trim()  # what earlier tasks of this worker held
        tool = Scorer(scorer)
        for batch in batches:
            for a, b, texts in text_parts(batch.column(spot)):
                keep = tool.logits(texts)[0] < 0 if scorer is not None else np.ones(b - a, dtype=bool)
                yield batch.slice(a, b - a).filter(pa.array(keep))
        del tool
        trim()

    return docs.select(names).mapInArrow(run, docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))
