"""A content-addressed store of token ids: chunks cut by a rolling hash, unique chunks once, recipes, and a Merkle manifest.

Three tables make a store. ``chunks``: (hash, body), one row for each different chunk, named by the hash of its ids. ``recipes``: one row
for each document, in ascending id order with the number of ids before it, listing its chunks. ``manifest``: hash-tree nodes
over the recipes in that order, up to one root. Where a chunk ends depends on the 16 ids before the cut only, so equal
passages make equal chunks wherever they stand.

Writing takes one pass over the texts: each task writes the chunks it meets first and the recipes; chunks that several tasks have written
are found by their hashes, and a rewrite keeps the first task's copy. Reading back, each chunk's body is checked against its name
and gives its length and CRC; a document's CRC is put together from those of its chunks, so bodies never move.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import Workspace, read, trim
from .shingles import mixed
from .tokens import encoder, text_parts, vocabulary

WINDOW, BITS, LEAST, MOST, FAN = 16, 8, 64, 2048, 1024
#: Bytes of the table of repeated chunks up to which it is broadcast.
SMALL = 32 << 20


def marks(ids: np.ndarray) -> np.ndarray:
    """Places after which a chunk may end, over texts laid end to end: the rolling hash of the last 16 ids has 8 zero bits.

    Within 16 ids of a text's start the hash reaches into the text before it, but no chunk ends there: the shortest has 64 ids.
    """
    rolled = mixed(ids.astype(np.uint64) + np.uint64(0x632BE5AB))
    for k in (1, 2, 4, 8):  # sums over 2, 4, 8, 16 ids
        rolled[k:] = rolled[k:] + (rolled[:-k] << np.uint64(k))
    return np.flatnonzero((rolled >> np.uint64(64 - BITS)) == 0) + 1


def cuts(n: int, marked: list[int]) -> list[int]:
    """Ends of a text's chunks: marked places, 64 to 2048 ids apart."""
    ends, at = [], 0
    for e in [*marked, n]:
        while e - at > MOST:
            at += MOST
            ends.append(at)
        if e - at >= LEAST:
            ends.append(e)
            at = e
    return ends + [n] * (at < n)


def name_of(ids: bytes) -> bytes:
    return hashlib.blake2b(ids, digest_size=16).digest()


FIRST = "kind int, pack int, uid long, doc_id long, n_tokens long, hashes array<binary>, lengths array<int>, leaf binary, hash binary, body binary"


def _first_pass(path: str, end_id: int):
    tail = np.array([end_id], dtype="<u4").tobytes()
    schema = pa.schema([("kind", pa.int32()), ("pack", pa.int32()), ("uid", pa.int64()), ("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("hashes", pa.list_(pa.binary())), ("lengths", pa.list_(pa.int32())), ("leaf", pa.binary()), ("hash", pa.binary()), ("body", pa.binary())])

    def filled(n: int, **columns: pa.Array) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([columns[f.name] if f.name in columns else pa.nulls(n, f.type) for f in schema], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack, tool, seen, row = TaskContext.get().partitionId(), encoder(path), set(), 0
        same = lambda n, v, t: pa.array(np.full(n, v), t)
        for batch in batches:
            for a, b, texts in text_parts(batch.column(1), 1 << 21):
                found = [ids + tail for ids in tool.encode(texts)]
                sizes = np.array([len(x) // 4 for x in found])
                offsets = np.concatenate([[0], np.cumsum(sizes)])
                flat = np.frombuffer(b"".join(found), dtype="<u4")
                at = marks(flat)
                spots = np.searchsorted(at, offsets, side="right").tolist()
                short = flat.astype("<u2") if flat.max() < 65536 else None
                names, lengths, leaves, parts, first, bodies = [], [], [], [0], [], []
                for k, (ids, n, start) in enumerate(zip(found, sizes.tolist(), offsets.tolist(), strict=False)):
                    before, own = 0, []
                    for end in cuts(n, [e - start for e in at[spots[k] : spots[k + 1]].tolist()]):
                        h = name_of(ids[4 * before : 4 * end])
                        own.append(h)
                        lengths.append(end - before)
                        if h not in seen:
                            seen.add(h)
                            first.append(h)
                            bodies.append(short[start + before : start + end].tobytes() if short is not None else b"\0" + ids[4 * before : 4 * end])
                        before = end
                    names += own
                    leaves.append(name_of(b"".join(own)))
                    parts.append(len(names))
                n, spans = b - a, pa.array(parts, pa.int32())
                hashes, sizes_of = pa.ListArray.from_arrays(spans, pa.array(names, pa.binary())), pa.ListArray.from_arrays(spans, pa.array(lengths, pa.int32()))
                uids = pa.array((pack << 40) + np.arange(row, row + n), pa.int64())
                yield filled(n, kind=same(n, 0, pa.int32()), pack=same(n, pack, pa.int32()), uid=uids, doc_id=batch.column(0).slice(a, n), n_tokens=pa.array(sizes, pa.int64()), hashes=hashes, lengths=sizes_of, leaf=pa.array(leaves, pa.binary()))
                row += n
                if first:
                    m = len(first)
                    yield filled(m, kind=same(m, 1, pa.int32()), pack=same(m, pack, pa.int32()), hash=pa.array(first, pa.binary()), body=pa.array(bodies, pa.binary()))
        trim()

    return run


def _running(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Place and ids before it within the partition, for each recipe."""
    part, place, before = TaskContext.get().partitionId(), 0, 0
    for batch in batches:
        n = batch.column(2).to_numpy(zero_copy_only=False)
        total = np.cumsum(n)
        cols = [batch.column(0), batch.column(1), batch.column(2), batch.column(3), pa.array(np.full(len(n), part), pa.int64()), pa.array(np.arange(place, place + len(n)), pa.int64()), pa.array(before + total - n, pa.int64())]
        yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "uid", "n_tokens", "leaf", "part", "place", "before"])
        place, before = place + len(n), before + int(total[-1]) if len(n) else before


def write_store(docs: DataFrame, path: str, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> dict[str, DataFrame]:
    """The tables chunks, recipes and manifest of ``docs``; ``path``: the tokenizer's file on every machine.

    Null and empty texts are the end id alone. Repeated ids follow one another; null ids come first. Other columns are not read.
    """
    spark = docs.sparkSession
    space = Workspace(spark, "store")
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    first = space.store(base.mapInArrow(_first_pass(path, end_id), FIRST), "first", by="kind", codec="snappy")
    written, made = first.where("kind = 1").select("pack", "hash", "body"), first.where("kind = 0").drop("kind", "hash", "body", "pack")

    again = space.store(written.groupBy("hash").agg(F.min("pack").alias("owner"), F.count(F.lit(1)).alias("c")).where("c > 1").select("hash", "owner"), "repeated")
    n_again = again.count()
    side = F.broadcast(again) if n_again * 64 <= SMALL else again.hint("merge")
    kept = written.join(side, "hash", "left").where("owner IS NULL OR owner = pack")
    chunks = space.store(kept.select("hash", "body"), "chunks")

    order = made.select("doc_id", "uid", "n_tokens", "leaf").repartitionByRange("doc_id", "uid").sortWithinPartitions("doc_id", "uid")
    placed = space.store(order.mapInArrow(_running, "doc_id long, uid long, n_tokens long, leaf binary, part long, place long, before long"), "placed")
    totals = placed.groupBy("part").agg(F.sum("n_tokens").alias("n"), F.count(F.lit(1)).alias("rows")).orderBy("part").collect()  # a row for each partition
    offsets, at = [], 0
    for t in totals:
        offsets.append((t["part"], at))
        at += t["n"]
    shift = spark.createDataFrame(offsets, "part long, offset long")
    recipes = space.store(placed.join(F.broadcast(shift), "part").select("doc_id", "uid", (F.col("before") + F.col("offset")).alias("start"), "n_tokens", "leaf", "part", "place").join(made.select("uid", "hashes", "lengths"), "uid"), "recipes")
    return {"chunks": chunks, "recipes": recipes, "manifest": space.store(manifest(recipes), "manifest")}


def manifest(recipes: DataFrame, longest: int | None = None) -> DataFrame:
    """(level, part, place, node): hash-tree nodes over the recipes' leaves, 1024 to a node, the root last. No node gathers more than that."""
    level = recipes.select("part", "place", F.hex("leaf").alias("node"))
    longest = recipes.agg(F.max("place")).first()[0] if longest is None else longest
    out, depth = [], 0
    join_up = F.sha2(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("at", "node"))), lambda x: x["node"]), ""), 256).alias("node")
    while longest is not None and (longest > 0 or depth == 0):
        longest, depth = longest // FAN, depth + 1
        level = level.withColumn("at", F.col("place")).withColumn("place", F.floor(F.col("place") / FAN)).groupBy("part", "place").agg(join_up)
        out.append(level.select(F.lit(depth).alias("level"), "part", "place", "node"))
    parts = level.select(F.col("part").alias("at"), "node", F.floor(F.col("part") / FAN).alias("place"))
    out.append(parts.groupBy("place").agg(join_up).select(F.lit(depth + 1).alias("level"), F.lit(-1).cast("long").alias("part"), "place", "node"))
    total = out[0]
    for x in out[1:]:
        total = total.union(x)
    return total


@lru_cache(1)
def _zero_byte_maps() -> np.ndarray:
    """For k: tables that take a CRC to that of the same bytes with 2**k zero bytes after them."""
    one = np.zeros(32, dtype=np.uint32)  # the columns of the map of one zero bit
    one[0], one[1:] = 0xEDB88320, 1 << np.arange(31, dtype=np.uint32)

    def apply(m: np.ndarray, v: np.ndarray) -> np.ndarray:
        out = np.zeros_like(v)
        for bit in range(32):
            out ^= np.where(v >> np.uint32(bit) & 1, m[bit], 0).astype(np.uint32)
        return out

    for _ in range(3):
        one = apply(one, one)
    maps = []
    for _ in range(48):
        maps.append([apply(one, np.arange(256, dtype=np.uint32) << np.uint32(8 * b)) for b in range(4)])
        one = apply(one, one)
    return np.array(maps)


def crc_before(crc: np.ndarray, after: np.ndarray) -> np.ndarray:
    """What a part's CRC adds to that of a whole in which ``after`` bytes follow it; the sum is bitwise exclusive or."""
    crc, after = crc.astype(np.uint32), after.astype(np.int64)
    for k, (t0, t1, t2, t3) in enumerate(_zero_byte_maps()):
        on = (after >> k & 1).astype(bool)
        if on.any():
            c = crc[on]
            crc[on] = t0[c & 255] ^ t1[c >> 8 & 255] ^ t2[c >> 16 & 255] ^ t3[c >> 24]
    return crc


def ids_of(bodies: list[bytes]) -> list[memoryview]:
    """Stored chunks' ids, 4 bytes each. A body of odd length begins with a mark and has 4 bytes an id, others have 2."""
    short = [b for b in bodies if not len(b) % 2]
    wide = memoryview(np.frombuffer(b"".join(short), dtype="<u2").astype("<u4").tobytes())
    out, at = [], 0
    for b in bodies:
        if len(b) % 2:
            out.append(memoryview(b)[1:])
        else:
            out.append(wide[at : at + 2 * len(b)])
            at += 2 * len(b)
    return out


def _checked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = ids_of(batch.column(1).to_pylist())
        for h, part in zip(batch.column(0).to_pylist(), ids, strict=True):
            if name_of(part) != h:
                raise ValueError(f"chunk {h.hex()} does not match its name")
        cols = [batch.column(0), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(list(map(zlib.crc32, ids)), pa.int64())]
        yield pa.RecordBatch.from_arrays(cols, names=["hash", "n", "crc"])


@F.pandas_udf(T.LongType())
def _placed_crc(crc: pd.Series, after: pd.Series) -> pd.Series:
    return pd.Series(crc_before(crc.to_numpy(), after.to_numpy()).astype(np.int64))


def read_store(store: dict[str, DataFrame]) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) from a store's files. A missing, changed or misplaced chunk, a recipe unlike its leaf and leaves unlike the manifest are errors."""
    check_manifest(store)
    chunks = store["chunks"].mapInArrow(_checked, "hash binary, n long, crc long")
    total = F.col("n_tokens")
    sized = store["recipes"].select("uid", "n_tokens", F.posexplode(F.arrays_zip("hashes", "lengths")).alias("k", "c"), "lengths")
    after = 4 * (total - F.aggregate(F.slice("lengths", 1, F.col("k") + 1), F.lit(0).cast("long"), lambda s, x: s + x))
    refs = sized.select("uid", F.col("c.hashes").alias("hash"), after.alias("after"))
    sums = refs.join(chunks, "hash").groupBy("uid").agg(F.sum("n").alias("n_read"), F.bit_xor(_placed_crc("crc", "after")).alias("ids_crc32"))
    back = store["recipes"].select("doc_id", "uid", "start", "n_tokens").join(sums, "uid", "left")
    n = F.when(F.col("n_read") == total, total).otherwise(F.raise_error(F.lit("chunks are missing or of other lengths")).cast("long"))
    return back.select("doc_id", "start", n.alias("n_tokens"), "ids_crc32")


def _leaf_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The leaf made anew from each recipe's hashes; another one stored is an error."""
    for batch in batches:
        lists = batch.column(1)
        if lists.null_count or not batch.num_rows:
            ends, names = [0] * (batch.num_rows + 1), b""
        else:
            ends, names = [16 * (x - lists.offsets[0].as_py()) for x in lists.offsets.to_pylist()], b"".join(lists.flatten().to_pylist())
        for uid, a, b, leaf in zip(batch.column(0).to_pylist(), ends[:-1], ends[1:], batch.column(2).to_pylist(), strict=True):
            if a == b or name_of(names[a:b]) != leaf:
                raise ValueError(f"recipe {uid} does not match its leaf")
        yield pa.RecordBatch.from_arrays([batch.column(k) for k in (2, 3, 4)], names=["leaf", "part", "place"])


def check_manifest(store: dict[str, DataFrame]) -> None:
    """An error unless each leaf is that of its recipe's hashes and the manifest, from its first level to the root, is that of the leaves."""
    leaves = store["recipes"].select("uid", "hashes", "leaf", "part", "place").mapInArrow(_leaf_of, "leaf binary, part long, place long")
    again = manifest(leaves, store["recipes"].agg(F.max("place")).first()[0])
    kept = store["manifest"].select("level", "part", "place", F.col("node").alias("kept"))
    same = again.join(kept, ["level", "part", "place"], "full").where(~F.col("node").eqNullSafe(F.col("kept")))
    if same.limit(1).count():
        raise ValueError("the manifest is not that of the recipes")


def verify(store: dict[str, DataFrame]) -> bool:
    """Whether ``check_manifest`` finds nothing wrong."""
    try:
        check_manifest(store)
    except Exception as e:
        if "does not match its leaf" in str(e) or "is not that of the recipes" in str(e):
            return False
        raise
    return True


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_store(write_store(read(spark, sf_dir, "documents"), vocabulary()))
