"""Token sequences of several context sizes, packed tier by tier without gaps.

A document's ids, with an end id, are cut into full windows of the largest size; what is left goes to the smallest tier that holds it.
Tiers are packed from the largest down: each rest opens a window of its tier, and its gap is filled with the longest rests of shorter tiers
that fit, the last of them cut to size. So every window is full, and its size a power of two. Windows that shorter tiers could not fill wait
for the next documents; at a task's end what waits is laid end to end and cut into powers of two. Each task packs its own
documents, no texts move, and memory holds one slice of documents.

Sequences of one tier go to step groups. Tasks note how many tokens of a tier each sequence has before it; from the tasks' totals its place in
the whole table follows, and the tier's tokens are dealt evenly to as few groups as can hold them. What is shorter than the smallest tier, some
sequences a task, forms groups of its own, dealt in the same way.
"""

from __future__ import annotations

import zlib
from bisect import bisect_right, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shared import Workspace, read, trim
from .tokens import encoder, text_parts, vocabulary

TIERS = (256, 512, 1024, 2048)
STEP_TOKENS = 32768
OUT = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, tier int"
PACKED = f"{OUT}, level int, part long, before long"


class Packer:
    """Full windows of pieces. A piece: (document's number, start, length); ``done`` takes a window's pieces."""

    def __init__(self, tiers: tuple[int, ...]):
        self.tiers = tuple(sorted(tiers))
        self.waiting: list[tuple[int, int, int]] = []
        self.done: list[tuple[int, list[tuple[int, int, int]]]] = []

    def add(self, pieces: list[tuple[int, int, int]]) -> None:
        """Pack the documents (number, 0, length) and what waits."""
        top, rests = self.tiers[-1], []
        for doc, start, n in [*self.waiting, *pieces]:
            while n >= top:
                self.done.append((top, [(doc, start, top)]))
                start, n = start + top, n - top
            if n:
                rests.append((n, doc, start))
        rests.sort()
        self.waiting = []
        for k in range(len(self.tiers) - 1, -1, -1):
            size, floor = self.tiers[k], self.tiers[k - 1] if k else 0
            at = bisect_right(rests, (floor, float("inf")))
            own, rests = rests[at:], rests[:at]
            if not k:
                rests, own = own, []
                while rests:
                    n, doc, start = rests.pop()
                    self._fill(size, [(doc, start, n)], rests)
            for n, doc, start in reversed(own):
                self._fill(size, [(doc, start, n)], rests)

    def _fill(self, size: int, window: list[tuple[int, int, int]], rests: list[tuple[int, int, int]]) -> None:
        gap = size - window[0][2]
        while gap and rests:
            at = bisect_right(rests, (gap, float("inf")))
            n, doc, start = rests.pop(max(at - 1, 0))
            take = min(n, gap)
            window.append((doc, start, take))
            if n > take:
                insort(rests, (n - take, doc, start + take))
            gap -= take
        if gap:
            self.waiting += window
        else:
            self.done.append((size, window))

    def finish(self) -> None:
        """Lay what waits end to end; each sequence is the largest power of two that is left, up to the largest tier."""
        left = sum(n for _, _, n in self.waiting)
        queue = self.waiting[::-1]
        while left:
            size = min(self.tiers[-1], 1 << left.bit_length() - 1)
            window, gap = [], size
            while gap:
                doc, start, n = queue.pop()
                take = min(n, gap)
                window.append((doc, start, take))
                if n > take:
                    queue.append((doc, start + take, n - take))
                gap -= take
            self.done.append((size, window))
            left -= size
        self.waiting = []


def _pack(path: str, end_id: int, tiers: tuple[int, ...]):
    tail = np.array([end_id], dtype="<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number_of_task, tool, packer = TaskContext.get().partitionId(), encoder(path), Packer(tiers)
        part = number_of_task << 32
        held: dict[int, tuple[int | None, bytes]] = {}
        number = sequences = 0
        before = dict.fromkeys((0, *tiers), 0)

        def flush() -> pa.RecordBatch:
            nonlocal sequences
            rows = []
            for size, window in packer.done:
                level = size if size in before else 0
                offset = 0
                for doc, start, n in window:
                    doc_id, ids = held[doc]
                    rows.append((doc_id, start, n, zlib.crc32(ids[4 * start : 4 * (start + n)]), len(ids) // 4, part | sequences, offset, size, level, number_of_task, before[level]))
                    offset += n
                sequences += 1
                before[level] += size
            packer.done = []
            keep = {doc for doc, _, _ in packer.waiting}
            for doc in [d for d in held if d not in keep]:
                del held[doc]
            cols = list(zip(*rows, strict=True)) or [[]] * 11
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int32() if k in (7, 8) else pa.int64()) for k, c in enumerate(cols)], names=[c.split()[0] for c in PACKED.split(", ")])

        trim()  # what earlier tasks of this worker held
        for batch in batches:
            for a, b, texts in text_parts(batch.column(1)):
                new = []
                for doc_id, ids in zip(batch.column(0).slice(a, b - a).to_pylist(), tool.encode(texts), strict=True):
                    held[number] = (doc_id, ids + tail)
                    new.append((number, 0, len(ids) // 4 + 1))
                    number += 1
                packer.add(new)
                yield flush()
        packer.finish()
        if packer.done:
            yield flush()
        tool.forget()
        trim()

    return run


def grouped(packed: DataFrame, step_tokens: int) -> DataFrame:
    """``packed`` with step_group: a level's sequences, in the order of their tasks, are dealt to groups of as equal tokens as whole sequences allow.

    The running totals are over one row for each task and level.
    """
    sizes = packed.where("offset = 0").groupBy("level", "part").agg(F.sum("tier").alias("tokens"))
    so_far = F.sum("tokens").over(Window.partitionBy("level").orderBy("part"))
    spots = sizes.select("level", "part", (so_far - F.col("tokens")).alias("ahead"), F.sum("tokens").over(Window.partitionBy("level")).alias("total"))
    n_groups = F.ceil(F.col("total") / step_tokens)
    number = F.floor((F.col("ahead") + F.col("before")).cast("double") / F.col("total") * n_groups).cast("long")
    joined = packed.join(spots, ["level", "part"])
    return joined.select(*[c.split()[0] for c in OUT.split(", ")], (F.col("level").cast("long") * (1 << 44) + number).alias("step_group"))


def pack(docs: DataFrame, path: str, end_id: int = 1, tiers: tuple[int, ...] = TIERS, step_tokens: int = STEP_TOKENS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, tier, step_group.

    ``tiers``: powers of two. Null and empty texts are the end id alone. Each row is a document of its own, repeated or null
    ids included. Every sequence is full, so none needs padding. Other columns are not read. An empty table gives no pieces.
    """
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    packed = Workspace(docs.sparkSession, "packing").store(base.mapInArrow(_pack(path, end_id, tuple(tiers)), PACKED), "pieces")
    return grouped(packed, step_tokens)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(read(spark, sf_dir, "documents"), vocabulary())
