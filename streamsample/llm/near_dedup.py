"""Near duplicates by MinHash with tensored banding, every link confirmed on full shingle sets.

A document gets two collections of ``tables`` half keys, each made of ``half`` minhashes. A table key is a pair, one half key from
either collection, so ``tables``**2 tables of 2 * ``half`` minhashes each need no more than 2 * ``tables`` * ``half`` minhashes.
A pair of similarity s shares a table with probability (1 - (1 - s**half)**tables)**2: with 16 and 4 it is missed at
s = 0.85 with probability 1.5e-5, and at 0.5 it is a candidate with probability 0.41, in few tables.

Half keys that only one document has can be in no shared table, so only the others are paired; most documents drop out there.

Groups are linked without writing out all their pairs. Equal shingle sets are one class, a numbered node, with its smallest id as representative. In each
bucket all members are first compared with its first one, the hub. Components of the confirmed links follow. Where the members
around a hub still lie in several components, those outside the largest one are compared with all of them, in blocks of bounded
size, and only links leave a block. So no rows of pairs are made but those with hubs and those of links.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import components
from .shared import Workspace, keep_rows, raw_key, read, trim
from .shingles import mixed, raw_texts, shingle_sets, slices

WIDTH, TABLES, HALF, PERCENT = 5, 16, 4, 85


def _functions(tables: int, half: int) -> tuple[np.ndarray, np.ndarray]:
    k = np.arange(2 * tables * half, dtype=np.uint64)
    return mixed(k * np.uint64(2) + np.uint64(0x51ED)), mixed(k * np.uint64(2) + np.uint64(0xC0DE1)) | np.uint64(1)


def half_keys(shingles: np.ndarray, tables: int, half: int) -> np.ndarray:
    """2 * tables keys of a nonempty set."""
    flip, times = _functions(tables, half)
    low = np.full(len(flip), np.iinfo(np.uint64).max, dtype=np.uint64)
    for at in range(0, len(shingles), 2048):
        np.minimum(low, ((shingles[at : at + 2048, None] ^ flip) * times).min(axis=0), out=low)
    rows = mixed(low).reshape(2 * tables, half)
    key = np.zeros(2 * tables, dtype=np.uint64)
    for k in range(half):
        key = mixed(key + rows[:, k])
    return key.view(np.int64)


def _each_set(batches: Iterator[pa.RecordBatch], width: int):
    for batch in batches:
        data, offsets = raw_texts(batch.column(batch.num_columns - 1))
        for a, b in slices(offsets):
            yield [c.slice(a, b - a) for c in batch.columns[:-1]], shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], width)


SKETCH = "doc_id long, raw_key long, n_shingles long, set_key binary, half_keys array<long>"


def _sketches(width: int, tables: int, half: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, sets in _each_set(batches, width):
            keys = [half_keys(s, tables, half) if len(s) else None for s in sets]
            marks = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
            yield pa.RecordBatch.from_arrays(
                [*ids, pa.array([len(s) for s in sets], pa.int64()), pa.array(marks, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], names=[c.split()[0] for c in SKETCH.split(", ")]
            )
        trim()

    return run


def _sets(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, sets in _each_set(batches, width):
            offs = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
            flat = np.concatenate(sets).view(np.int64) if sets else np.zeros(0, dtype=np.int64)
            yield pa.RecordBatch.from_arrays([*ids, pa.ListArray.from_arrays(pa.array(offs), pa.array(flat))], names=["node", "shingles"])
        trim()

    return run


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) that are linked, on full sets."""
    side = lambda x: sets.select(F.col("node").alias(x), F.col("shingles").alias(f"s{x}"))
    both = F.size(F.array_intersect("sa", "sb"))
    linked = pairs.join(side("a"), "a").join(side("b"), "b")
    return linked.where(both * 100 >= percent * (F.size("sa") + F.size("sb") - both)).select("a", "b")


def _blocks(percent: int):
    """Links of some outsiders with some members of a hub's group: overlaps of all of them at once, by products of 0/1 matrices over shared shingles."""
    ends = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def side(table: pa.Table):
        sets = table.column("shingles").combine_chunks()
        sizes = np.diff(sets.offsets.to_numpy())
        return table.column("node").to_numpy(), table.column("component").to_numpy(), sizes, np.repeat(np.arange(len(sizes)), sizes), sets.flatten().to_numpy()

    def run(rows: pa.Table) -> pa.Table:
        asks = rows.column("asks")
        outsiders, members = rows.filter(asks), rows.filter(pc.invert(asks))
        if not outsiders.num_rows or not members.num_rows:
            return pa.table({"a": [], "b": []}, schema=ends)
        (xn, xc, xs, xi, xf), (yn, yc, ys, yi, yf) = side(outsiders), side(members)
        shared = np.intersect1d(xf, yf)
        both = np.zeros((len(xn), len(yn)), dtype=np.float32)
        for at in range(0, len(shared), 1024):
            part = shared[at : at + 1024]
            flags = []
            for n, rows, flat in ((len(xn), xi, xf), (len(yn), yi, yf)):
                spot = np.searchsorted(part, flat).clip(max=len(part) - 1)
                hit = part[spot] == flat
                one = np.zeros((n, len(part)), dtype=np.float32)
                one[rows[hit], spot[hit]] = 1
                flags.append(one)
            both += flags[0] @ flags[1].T
        inter = both.astype(np.int64)
        linked = (100 * inter >= percent * (xs[:, None] + ys[None, :] - inter)) & (xc[:, None] != yc[None, :])
        x, y = np.nonzero(linked)
        _, first = np.unique(np.stack([x, yc[y]]), axis=1, return_index=True)  # one link to each component does
        return pa.table({"a": xn[x[first]], "b": yn[y[first]]}, schema=ends)

    return run


def _links_of_the_rest(rest: DataFrame, sets: DataFrame, percent: int, budget: int = 400_000, most_rows: int = 2048) -> DataFrame:
    """Links between components of one hub's group: members outside its largest component against all, in blocks of bounded size.

    rest: (hub, node, component, most). A side's rows are dealt to blocks of about ``budget`` shingles and ``most_rows`` rows; each pair of blocks is one
    task's group, so it needs memory for most_rows ** 2 overlaps at most. The pairs of blocks of one hub grow with the product of its outsiders and members. Only links come out.
    """
    full = rest.join(sets, "node").withColumn("n", F.size("shingles").cast("long")).withColumn("out", F.col("component") != F.col("most"))
    sums = [F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)) for c in (F.col("out"), F.lit(True))]
    rows = [F.count_if(c) for c in (F.col("out"), F.lit(True))]
    blocks = [F.ceil(F.greatest(s / budget, r / most_rows)).cast("int").alias(name) for s, r, name in zip(sums, rows, ("nx", "ny"), strict=True)]
    counts = full.select("hub", "n", "out").groupBy("hub").agg(*blocks)
    dealt = full.join(counts, "hub")
    own = lambda n: F.pmod(F.xxhash64("node"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    cols = ["hub", "node", "component", "shingles"]
    x = dealt.where("out").select(*cols, F.lit(True).alias("asks"), own("nx").alias("i"), every("ny").alias("j"))
    y = dealt.select(*cols, F.lit(False).alias("asks"), every("nx").alias("i"), own("ny").alias("j"))
    return x.union(y).groupBy("hub", "i", "j").applyInArrow(_blocks(percent), "a long, b long").distinct()


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, percent: int = PERCENT, tables: int = TABLES, half: int = HALF) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row of ``docs``.

    Texts are lower-cased (A-Z) and split at white space; a text of fewer than ``width`` words is one shingle; null and
    empty texts have none and are linked with nothing. Rows with a null id are linked with nothing, have a null component and are kept.
    Rows that repeat an id are told apart by their texts (raw_key): each has its own set and links. Other columns are not read.
    """
    space = Workspace(docs.sparkSession, "near")
    found = _grouped(docs, space, id_col, text_col, width, percent, tables, half)
    kept = F.col("doc_id").eqNullSafe(F.col("component_id")) & F.coalesce(F.col("raw_key") == F.col("keep_raw"), F.lit(True))
    return found.withColumn("kept", kept).drop("keep_raw", "raw_key")


def _grouped(docs: DataFrame, space: Workspace, id_col: str, text_col: str, width: int, percent: int, tables: int, half: int) -> DataFrame:
    """(doc_id, raw_key, n_shingles, component_id, keep_raw): keep_raw tells the row that stays from others with its id; null where a row is linked with nothing."""
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), raw_key(F.col(text_col)).alias("raw_key"), F.col(text_col).cast("string").alias("text"))
    rows = space.store(base.mapInArrow(_sketches(width, tables, half), SKETCH), "sketches")
    full = rows.where("n_shingles > 0 AND doc_id IS NOT NULL")
    # equal sets are a class; its number is the node, its representative the row with the smallest id
    classes = full.groupBy("set_key").agg(F.min(F.struct("doc_id", "raw_key")).alias("rep")).select("set_key", "rep.doc_id", "rep.raw_key")
    classes = space.store(classes.withColumn("node", F.monotonically_increasing_id()), "classes")
    reps = full.join(classes.select("doc_id", "raw_key", "node"), ["doc_id", "raw_key"]).groupBy("node").agg(F.first("half_keys").alias("half_keys"))

    # half keys that at least two representatives have
    parts = reps.select("node", F.posexplode("half_keys").alias("pos", "v"))
    shared = parts.groupBy("pos", "v").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo < hi").select("pos", "v")
    own = parts.join(shared, ["pos", "v"], "left_semi").groupBy("node").agg(F.collect_list(F.struct("pos", "v")).alias("own"))
    sides = own.select("node", F.filter("own", lambda x: x["pos"] < tables).alias("left"), F.filter("own", lambda x: x["pos"] >= tables).alias("right"))
    sides = space.store(sides.where((F.size("left") > 0) & (F.size("right") > 0)), "sides")
    keys = F.flatten(
        F.transform("left", lambda x: F.transform("right", lambda y: F.xxhash64(x["pos"], x["v"], y["pos"], y["v"])))
    )
    tensored = sides.select("node", F.explode(keys).alias("key"))
    hubs = tensored.groupBy("key").agg(F.min("node").alias("hub"), F.max("node").alias("top")).where("hub < top").select("key", "hub")
    members = space.store(tensored.join(hubs, "key"), "members")

    involved = classes.join(members.select("node").distinct(), "node", "left_semi").select("doc_id", "raw_key", "node")
    texts = base.join(involved, ["doc_id", "raw_key"]).select("node", "text").dropDuplicates(["node"])
    sets = space.store(texts.mapInArrow(_sets(width), "node long, shingles array<long>"), "sets")

    # every member against the smallest of its bucket
    first = space.store(_confirmed(members.where("node <> hub").select(F.col("hub").alias("a"), F.col("node").alias("b")).distinct(), sets, percent), "links0")
    label = space.store(components(first, space, "stars"), "label0")

    # what is still apart, by hub
    around = members.select("hub", "node").union(members.select("hub", F.col("hub").alias("node"))).distinct()
    now = around.join(label, "node", "left").select("hub", "node", F.coalesce("component", "node").alias("component"))
    apart = now.groupBy("hub", "component").agg(F.count(F.lit(1)).alias("c")).groupBy("hub").agg(F.max(F.struct("c", "component")).alias("most"), F.count(F.lit(1)).alias("parts")).where("parts > 1")
    rest = space.store(now.join(apart.select("hub", F.col("most.component").alias("most")), "hub"), "rest")
    second = space.store(_links_of_the_rest(rest, sets, percent), "links1")
    stars = label.where("node <> component").select(F.col("node").alias("a"), F.col("component").alias("b"))
    final = components(stars.union(second), space, "all")

    labelled = space.store(classes.join(final, "node", "left").withColumn("component", F.coalesce("component", "node")), "labelled")
    least = labelled.groupBy("component").agg(F.min(F.struct("doc_id", "raw_key")).alias("least"))
    of_class = labelled.join(least, "component").select("set_key", F.col("least.doc_id").alias("component_id"), F.col("least.raw_key").alias("keep_raw"))
    linked = full.join(of_class, "set_key").select("doc_id", "raw_key", "n_shingles", "component_id", "keep_raw")
    alone = rows.where("n_shingles = 0 OR doc_id IS NULL").select("doc_id", "raw_key", "n_shingles", F.col("doc_id").alias("component_id"), F.lit(None).cast("long").alias("keep_raw"))
    return linked.union(alone)


def drop_near(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, percent: int = PERCENT, tables: int = TABLES, half: int = HALF
) -> DataFrame:
    """``docs``, all its columns, with one row of each group; rows that are linked with nothing stay, but one of those that repeat id and text."""
    space = Workspace(docs.sparkSession, "near")
    found = _grouped(docs, space, id_col, text_col, width, percent, tables, half)
    stays = F.col("keep_raw").isNull() | ((F.col("doc_id") == F.col("component_id")) & (F.col("raw_key") == F.col("keep_raw")))
    return keep_rows(docs, found.select("doc_id", "raw_key", stays.alias("stays")), id_col, text_col, space)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_groups(read(spark, sf_dir, "documents"))
