"""SentencePiece encoding and decoding over a relational lattice.

Texts are normalised and cut into words, which no piece crosses, and words into atoms wherever no piece holds the two neighbouring
characters. A first pass turns documents into numbers of their parcel's distinct atoms; parcels make buckets of bounded size. Only
distinct atoms are encoded: their substrings of bounded length are exploded and joined to the piece table, whose size is that of the
vocabulary, so it may be broadcast; edges are grouped by atom; and a fold over an atom's edges, sorted by end, keeps the best scores of
the last positions and a back pointer for each (Viterbi). Decoding is a join too: ids are exploded, joined to the pieces' bytes and
put together again in order. Encodings then meet the documents of their bucket, where arrays of numbers are looked up, not strings.

The segmentation is the one of greatest total score, ties to the longest last piece: SentencePiece's unigram reading of the piece table.
Characters in no piece cost the least score less 10 and become byte pieces.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import read, trim
from .shingles import distinct_pieces, piece_hashes, ragged
from .tokens import vocabulary

SPACE = "▁"
#: Characters of text in a parcel and bytes in a bucket, about; characters of an atom in one row of the lattice, and of the pieces that the table of heads tells apart.
PARCEL, BUCKET, BLOCK, HEAD = 8 << 20, 64 << 20, 64, 4
#: Characters that one numpy pass takes, longer single texts aside.
SLICE = 1 << 18
#: Edges of the lattice, and characters of an atom, in one step of the folds.
STEP = 512
_WORD = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+")


@dataclass
class Vocabulary:
    """The normal pieces with scores, byte pieces, and the neighbours that occur in pieces."""

    path: str

    def __post_init__(self) -> None:
        from sentencepiece import SentencePieceProcessor

        self.tool = sp = SentencePieceProcessor(model_file=self.path)
        self.size = sp.get_piece_size()
        texts = [sp.id_to_piece(i) for i in range(self.size)]
        odd = [sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i) for i in range(self.size)]
        self.pieces = [(t, i, float(sp.get_score(i))) for i, t in enumerate(texts) if not odd[i]]
        self.bytes = {int(t[3:5], 16): i for i, t in enumerate(texts) if sp.is_byte(i)}
        self.longest = max(len(t) for t, _, _ in self.pieces)
        self.unknown = min(s for _, _, s in self.pieces) - 10
        self.neighbours = {(t[k], t[k + 1]) for t, _, _ in self.pieces for k in range(len(t) - 1)}
        marks = sorted({c for pair in self.neighbours for c in pair})
        self.kinds = np.zeros(0x110000, dtype=np.int16)
        self.kinds[[ord(c) for c in marks]] = np.arange(1, len(marks) + 1)
        self.near = np.zeros((len(marks) + 1, len(marks) + 1), dtype=bool)
        for x, y in self.neighbours:
            self.near[self.kinds[ord(x)], self.kinds[ord(y)]] = True
        self.plain = {i: t.replace(SPACE, " ").encode() for t, i, _ in self.pieces} | {i: bytes([b]) for b, i in self.bytes.items()}

    def words(self, text: str) -> list[str]:
        """Pieces never cross from one of these to the next."""
        return _WORD.findall(self.tool.normalize(text))

    def atoms(self, word: str) -> list[str]:
        near = self.neighbours
        cuts = [k for k, pair in enumerate(zip(word, word[1:], strict=False), 1) if pair not in near]
        return [word[a:b] for a, b in zip([0, *cuts], [*cuts, len(word)], strict=True)]

    def ids_of(self, code: int) -> list[int]:
        """An edge's ids: its piece, or the bytes of its character."""
        return [code] if code < self.size else [self.bytes[b] for b in chr(code - self.size).encode("utf-8", "replace")]

    def decode(self, ids: list[int]) -> str:
        """The text of ids; the blank that encoding puts first is taken off."""
        raw = b"".join(self.plain.get(i, b"") for i in ids).decode("utf-8", "replace")
        return raw[1:] if raw.startswith(" ") else raw


_OPEN: dict[str, Vocabulary] = {}


def opened(path: str) -> Vocabulary:
    """One for each file and Python process."""
    if path not in _OPEN:
        _OPEN[path] = Vocabulary(path)
    return _OPEN[path]


def name_of(atom: str) -> str:
    """A short name: the atom, or a digest of a long one. No short atom looks like that, since the vocabulary has no piece with the first character."""
    return atom if len(atom) <= BLOCK else "\0" + hashlib.md5(atom.encode("utf-8", "replace")).hexdigest()


def _named(atom: Column) -> Column:
    return F.when(F.char_length(atom) <= BLOCK, atom).otherwise(F.concat(F.lit("\0"), F.md5(atom)))


def _cut(voc: Vocabulary, code: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Where the atoms of normalised texts, laid end to end as code points, begin, and the end: as ``atoms`` of ``words`` of each text. edges: where texts begin and end."""
    kind = voc.kinds[code]
    cut = np.ones(len(code) + 1, dtype=bool)
    if len(code):
        mark = code == ord(SPACE)
        cut[1:-1] = ~voc.near[kind[:-1], kind[1:]] | (mark[1:] & ~mark[:-1])
    cut[edges] = True
    return np.flatnonzero(cut)


class Parcel:
    """Some documents as numbers of the parcel's own distinct atoms."""

    def __init__(self, voc: Vocabulary):
        self.voc, self.held = voc, 0
        self.ids: list[int | None] = []
        self.lossless: list[bool] = []
        self.sizes: list[np.ndarray] = []
        #: For each slice of texts: numbers of its atoms; and of its distinct ones two hashes, counts, characters, bytes, and all their text.
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []

    def add(self, ids: list[int | None], texts: list[str]) -> None:
        normal = [self.voc.tool.normalize(t) for t in texts]
        whole = "".join(normal)
        code = np.frombuffer(whole.encode("utf-32-le"), dtype=np.uint32)
        edges = np.concatenate([[0], np.cumsum([len(t) for t in normal])]).astype(np.int64)
        spots = _cut(self.voc, code, edges)
        one, two = piece_hashes(code, spots)
        for k in np.flatnonzero(np.diff(spots) > 8 * BLOCK).tolist():  # sums of powers are for short pieces
            one[k], two[k] = np.frombuffer(hashlib.blake2b(whole[spots[k] : spots[k + 1]].encode(), digest_size=16).digest(), dtype=np.uint64)
        first, numbers, counts = distinct_pieces(one, two)
        width = np.zeros(len(code) + 1, dtype=np.int32)
        width[1:] = 1
        for least in (0x80, 0x800, 0x10000):
            width[1:] += code >= least
        at = np.cumsum(width, dtype=np.int64)[spots]
        begins, sizes = at[:-1][first], np.diff(at)[first]
        text = np.frombuffer(whole.encode(), dtype=np.uint8)[ragged(begins, sizes)]
        self.parts.append((numbers, one[first], two[first], counts, np.diff(spots)[first].astype(np.int32), sizes, text))
        self.ids += ids
        self.sizes.append(np.diff(np.searchsorted(spots, edges)))
        plain = [n.replace(SPACE, " ") for n in normal]
        self.lossless += [(n[1:] if n.startswith(" ") else n) == t for n, t in zip(plain, texts, strict=True)]
        self.held += sum(map(len, texts)) + 64 * len(texts)

    def distinct(self) -> tuple[pa.Array, np.ndarray, np.ndarray]:
        """(distinct atoms, frequent ones first; how many characters each has; the atoms of all documents as numbers of these)."""
        one, two, counts, chars, sizes, text = (np.concatenate([p[k] for p in self.parts]) for k in range(1, 7))
        first, numbers, _ = distinct_pieces(one, two)
        total = np.bincount(numbers, counts, len(first))
        order = np.argsort(-total, kind="stable")
        place = np.empty(len(order), dtype=np.uint32)
        place[order] = np.arange(len(order), dtype=np.uint32)
        of = place[numbers]
        shift = np.cumsum([0, *(len(p[1]) for p in self.parts)])
        every = np.concatenate([of[a + p[0].astype(np.int64)] for a, p in zip(shift, self.parts, strict=False)])
        begins, kept = np.cumsum(sizes) - sizes, first[order]
        offsets = np.concatenate([[0], np.cumsum(sizes[kept])]).astype(np.int32)
        return pa.StringArray.from_buffers(len(order), pa.py_buffer(offsets), pa.py_buffer(text[ragged(begins[kept], sizes[kept])])), chars[kept], every

    def row(self, bucket: int, number: int) -> pa.RecordBatch:
        names, sizes, numbers = self.distinct()
        long = [(k, names[k].as_py()) for k in np.flatnonzero(sizes > BLOCK).tolist()]
        parts = [(name_of(a), len(a), at, a[at : at + BLOCK + self.voc.longest - 1]) for _, a in long for at in range(0, len(a), BLOCK)]
        if long:
            texts = names.to_pylist()
            for k, a in long:
                texts[k] = name_of(a)
            names = pa.array(texts, pa.string())
        # frequent atoms have small numbers, whose upper bytes pack away
        planes = b"".join((numbers >> np.uint32(8 * k)).astype(np.uint8).tobytes() for k in range(4))
        tables = (
            pa.table({"doc_id": pa.array(self.ids, pa.int64()), "lossless": self.lossless, "size": pa.array(np.concatenate(self.sizes))}),
            pa.table({"name": names}),
            pa.table([pa.array(c, t) for c, t in zip(zip(*parts, strict=True) if parts else [[]] * 4, (pa.string(), pa.int32(), pa.int32(), pa.string()), strict=True)], names=["name", "n", "at", "chunk"]),
        )
        cols = [pa.array([bucket], pa.int64()), pa.array([number], pa.int64()), pa.array([len(numbers)], pa.int64()), pa.array([pa.compress(planes, "zstd", asbytes=True)], pa.binary())]
        return pa.RecordBatch.from_arrays([*cols, *(pa.array([_packed(t)], pa.binary()) for t in tables)], names=[c.split()[0] for c in PARCELS.split(", ")])


def _packed(table: pa.Table) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def _unpacked(raw: bytes) -> pa.Table:
    return pa.ipc.open_stream(raw).read_all()


PARCELS = "bucket long, parcel long, n long, numbers binary, docs binary, names binary, long binary"


def _parcelled(path: str, buckets: int, limit: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, k, voc = TaskContext.get().partitionId() << 32, 0, opened(path)
        now = Parcel(voc)
        for batch in batches:
            at = 0
            while at < batch.num_rows:  # some texts at a time
                texts, size = [], 0
                while at + len(texts) < batch.num_rows and size < SLICE:
                    texts.append(batch.column(1)[at + len(texts)].as_py() or "")
                    size += len(texts[-1])
                now.add(batch.column(0).slice(at, len(texts)).to_pylist(), texts)
                at += len(texts)
                if now.held >= limit:
                    out, now = now.row(zlib.crc32(str(part + k).encode()) % buckets, part + k), Parcel(voc)
                    k += 1
                    trim()
                    yield out
        if now.ids:
            yield now.row(zlib.crc32(str(part + k).encode()) % buckets, part + k)
        trim()

    return run


def _numbered(parcels: pa.Table) -> tuple[pa.Table, pa.Array, list[np.ndarray]]:
    """(the parcels in order, the distinct names of their bucket, each parcel's names as numbers of these)."""
    parcels = parcels.sort_by("parcel")
    names = pa.chunked_array([_unpacked(raw.as_py()).column(0).combine_chunks() for raw in parcels.column("names")], pa.string())
    coded = names.combine_chunks().dictionary_encode()
    ends = np.cumsum([len(c) for c in names.chunks])[:-1]
    return parcels, coded.dictionary, np.split(coded.indices.to_numpy(), ends)


#: Atoms of a bucket that a place can number.
MOST = 1 << 26
ATOMS = "place long, name string, n int, at int, chunk string"


def _listed(parcels: pa.Table) -> pa.Table:
    """A row for each distinct atom of a bucket, and rows without a place for the parts of long ones."""
    bucket = parcels.column("bucket")[0].as_py()
    parcels, names, _ = _numbered(parcels)
    n, fields = len(names), [pa.field(f.split()[0], t) for f, t in zip(ATOMS.split(", "), (pa.int64(), pa.string(), pa.int32(), pa.int32(), pa.string()), strict=True)]
    order = pc.sort_indices(names)  # neighbours that look alike pack better when they move
    rows = pa.table([pa.array(bucket * MOST + order.to_numpy().astype(np.int64)), names.take(order), pa.nulls(n, pa.int32()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.string())], schema=pa.schema(fields))
    long = pa.concat_tables([_unpacked(raw.as_py()) for raw in parcels.column("long")])
    more = pa.table([pa.nulls(len(long), pa.int64()), *long.columns], schema=pa.schema(fields))
    return pa.concat_tables([rows, more])


def piece_table(spark: SparkSession, voc: Vocabulary) -> DataFrame:
    return spark.createDataFrame(pa.table({"piece": [t for t, _, _ in voc.pieces], "id": pa.array([i for _, i, _ in voc.pieces], pa.int32()), "score": [s for _, _, s in voc.pieces]}))


def byte_table(spark: SparkSession, voc: Vocabulary) -> DataFrame:
    """(id, bytes in hex) of all pieces that stand for text."""
    return spark.createDataFrame(pa.table({"id": pa.array(list(voc.plain), pa.int32()), "hex": [b.hex() for b in voc.plain.values()]}))


def edges_of(atoms: DataFrame, voc: Vocabulary, pieces: DataFrame | None = None) -> DataFrame:
    """(name, n, spot) for each edge of the lattices of ``atoms`` (name, n, at, chunk); spot: end, length and code in one number.

    From each start substrings are exploded up to the longest piece that begins with the same four characters, then joined to the pieces.
    """
    pieces = piece_table(atoms.sparkSession, voc) if pieces is None else pieces
    heads = pieces.where(F.char_length("piece") >= HEAD).groupBy(F.substring("piece", 1, HEAD).alias("head")).agg(F.max(F.char_length("piece")).alias("reach"))
    starts = atoms.select("name", "n", "at", "chunk", F.explode(F.sequence(F.lit(1), F.least(F.lit(BLOCK), F.col("n") - F.col("at")))).alias("i"))
    starts = starts.select("name", "n", (F.col("at") + F.col("i") - 1).cast("long").alias("start"), F.substring("chunk", F.col("i"), F.lit(voc.longest)).alias("ahead"))
    known = starts.join(F.broadcast(heads), F.substring("ahead", 1, HEAD) == F.col("head"), "left")
    reach = F.least(F.char_length("ahead"), F.coalesce("reach", F.lit(HEAD - 1)))
    subs = known.select("name", "n", "start", "ahead", F.explode(F.sequence(F.lit(1), reach)).alias("len"))
    subs = subs.select("name", "n", "start", "len", F.substring("ahead", F.lit(1), F.col("len")).alias("piece"))
    hits = subs.join(F.broadcast(pieces.select("piece", "id")), "piece", "left").where("id IS NOT NULL OR len = 1")
    code = F.coalesce(F.col("id"), F.lit(voc.size) + F.ascii("piece")).cast("long")
    return hits.select("name", "n", ((F.col("start") + F.col("len")) * (1 << 27) + F.col("len").cast("long") * (1 << 22) + code).alias("spot"))


def encode_atoms(atoms: DataFrame, voc: Vocabulary, pieces: DataFrame | None = None) -> DataFrame:
    """(name, ids) for distinct atoms, given as rows (name, n, at, chunk): explode, join, group, fold.

    Both folds go in steps of bounded size, each of which makes one short array, so the work grows with an atom's length and not with its square.
    An atom's edges, about three a character and 8 bytes each, lie in one row.
    """
    most, by_id = voc.longest, {i: x for _, i, x in voc.pieces}
    # scores by id as one constant, which the optimiser folds
    scores = "cast(split('" + ",".join(repr(by_id.get(i, voc.unknown)) for i in range(voc.size)) + "', ',') AS array<double>)"
    edges = edges_of(atoms, voc, pieces).withColumn("h", F.xxhash64("name"))
    grouped = edges.groupBy("h", "name", "n").agg(F.sort_array(F.collect_list("spot")).alias("edges"))
    code, span = f"cast(e & {(1 << 22) - 1} AS int)", "cast(shiftright(e, 22) & 31 AS int)"
    gain = f"if({code} < {voc.size}, {scores}[{code}], {float(voc.unknown)!r}D)"
    # win: best scores of the positions before ``cur``, the nearest first; best, enc: score and last edge of ``cur`` so far; back: last edges of the positions before it
    step = f"""(s, e) -> if(shiftright(e, 27) > s.cur,
        named_struct('win', slice(concat(array(s.best), s.win), 1, {most}), 'cur', shiftright(e, 27), 'best', if({span} = 1, s.best, s.win[{span} - 2]) + {gain}, 'enc', e & {(1 << 27) - 1}, 'back', concat(s.back, array(s.enc))),
        if(s.win[{span} - 1] + {gain} < s.best, s, named_struct('win', s.win, 'cur', s.cur, 'best', s.win[{span} - 1] + {gain}, 'enc', e & {(1 << 27) - 1}, 'back', s.back)))"""
    nothing = "cast(array() AS array<bigint>)"
    start = f"named_struct('win', cast(array() AS array<double>), 'cur', 0L, 'best', 0D, 'enc', -1L, 'back', {nothing})"
    long = f"""aggregate(sequence(1, size(edges), {STEP}), named_struct('s', {start}, 'done', cast(array() AS array<array<bigint>>)),
        (o, k) -> transform(array(aggregate(slice(edges, k, {STEP}), o.s, {step})), s -> named_struct(
            's', named_struct('win', s.win, 'cur', s.cur, 'best', s.best, 'enc', s.enc, 'back', {nothing}), 'done', concat(o.done, array(s.back))))[0],
        o -> concat(flatten(o.done), array(o.s.enc)))"""
    # the first entry is that of position 0, before the atom
    last = grouped.select("name", "n", F.expr(f"slice({long}, 2, n)").alias("back"))
    # from the end: skip as many positions as the last edge is long
    take = f"""(s, x) -> if(s.skip > 0, named_struct('skip', s.skip - 1, 'codes', s.codes),
        named_struct('skip', (shiftright(x, 22) & 31) - 1, 'codes', concat(s.codes, array(cast(x & {(1 << 22) - 1} AS int)))))"""
    none = "cast(array() AS array<int>)"
    one = f"reverse(aggregate(reverse(back), named_struct('skip', 0L, 'codes', {none}), {take}, s -> s.codes))"
    many = f"""reverse(aggregate(sequence(1, n, {STEP}), named_struct('skip', 0L, 'done', cast(array() AS array<array<int>>)),
        (o, k) -> transform(array(aggregate(slice(turned[0], k, {STEP}), named_struct('skip', o.skip, 'codes', {none}), {take})),
            s -> named_struct('skip', s.skip, 'done', concat(o.done, array(s.codes))))[0], o -> flatten(o.done)))"""
    many = f"flatten(transform(array(array(reverse(back))), turned -> {many}))"
    codes = last.select("name", F.expr(f"if(n <= {STEP}, {one}, {many})").alias("codes"))
    byte_ids = "array(" + ",".join(str(voc.bytes.get(b, 0)) for b in range(256)) + ")"
    char = f"hex(encode(decode(unhex(lpad(hex(c - {voc.size}), 8, '0')), 'UTF-32'), 'UTF-8'))"
    spread = f"flatten(transform(codes, c -> if(c < {voc.size}, array(c), transform(sequence(1, length({char}), 2), k -> {byte_ids}[cast(conv(substring({char}, k, 2), 16, 10) AS int)]))))"
    return codes.select("name", F.expr(f"if(exists(codes, c -> c >= {voc.size}), {spread}, codes)").alias("ids"))


def decode(rows: DataFrame, path: str, key: str = "doc_id", ids_col: str = "ids", first_blank: bool = False) -> DataFrame:
    """(key, text, ids) for rows of (key, ids), by a join of the exploded ids with the pieces' bytes.

    Keys are distinct and not null. Ids that stand for no text add nothing; null and empty lists give an empty text. Bytes that are no UTF-8
    become the replacement character. The blank that encoding puts first is taken off unless ``first_blank``.
    """
    voc = opened(path)
    parts = rows.select(F.col(key), F.posexplode_outer(ids_col).alias("at", "id"))
    bytes_of = F.broadcast(byte_table(rows.sparkSession, voc))
    said = parts.join(bytes_of, "id", "left").groupBy(key).agg(F.sort_array(F.collect_list(F.struct("at", "id", "hex"))).alias("parts"))
    text = F.make_valid_utf8(F.unhex(F.array_join(F.col("parts.hex"), "")).cast("string"))
    return said.select(key, (text if first_blank else F.regexp_replace(text, r"\A ", "")).alias("text"), F.array_compact(F.col("parts.id")).alias("ids"))


OUT = "doc_id long, n_pieces long, ids_crc32 long, round_trip boolean"


def _assembled(with_ids: bool):
    """A bucket's documents with the ids of their atoms: a look-up of ragged rows."""
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.bool_(), *([pa.list_(pa.int32())] if with_ids else [])]
    schema = pa.schema(list(zip([*(c.split()[0] for c in OUT.split(", ")), "ids"], kinds, strict=False)))

    def run(parcels: pa.Table, found: pa.Table) -> pa.Table:
        trim()
        return _put_together(parcels, found, schema)

    return run


def _put_together(parcels: pa.Table, found: pa.Table, schema: pa.Schema) -> pa.Table:
    out, order = [], np.argsort(found.column("place").to_numpy())
    lists = found.column("ids").combine_chunks()
    ends, flat = lists.offsets.to_numpy().astype(np.int64), lists.values.to_numpy()
    sizes, at, wrong = np.diff(ends)[order], ends[:-1][order], ~found.column("exact").to_numpy(zero_copy_only=False)[order]
    parcels, _, maps = _numbered(parcels)
    for k, own in enumerate(maps):
        row = {c: parcels.column(c)[k].as_py() for c in ("n", "numbers", "docs")}
        planes = np.frombuffer(pa.decompress(row["numbers"], 4 * row["n"], "zstd"), dtype=np.uint8).reshape(4, -1)
        docs, start = _unpacked(row["docs"]).combine_chunks(), 0
        spots = np.concatenate([[0], np.cumsum(docs.column("size").to_numpy())])
        doc_ids, lossless = docs.column("doc_id").combine_chunks(), docs.column("lossless").to_numpy(zero_copy_only=False)
        while start < len(docs):  # some documents at a time
            stop = max(start + 1, int(np.searchsorted(spots, spots[start] + (1 << 19), side="right")) - 1)
            some = planes[:, spots[start] : spots[stop]].astype(np.uint32)
            atoms = own[some[0] | some[1] << 8 | some[2] << 16 | some[3] << 24]
            total, cuts = np.concatenate([[0], np.cumsum(sizes[atoms])]), spots[start : stop + 1] - spots[start]
            ids, to = flat[ragged(at[atoms], sizes[atoms])].astype("<i4"), total[cuts]
            faults = np.diff(np.concatenate([[0], np.cumsum(wrong[atoms])])[cuts])
            crc = [zlib.crc32(ids[x:y]) for x, y in zip(to[:-1].tolist(), to[1:].tolist(), strict=True)]
            cols = [doc_ids.slice(start, stop - start), pa.array(np.diff(to)), pa.array(crc, pa.int64()), pa.array(lossless[start:stop] & (faults == 0)), pa.ListArray.from_arrays(pa.array(to.astype(np.int32)), pa.array(ids))]
            out.append(pa.RecordBatch.from_arrays(cols[: len(schema)], schema=schema))
            start = stop
    return pa.Table.from_batches(out, schema=schema)


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", parcel: int = PARCEL, bucket: int = BUCKET, with_ids: bool = True) -> DataFrame:
    """(doc_id, n_pieces, ids_crc32, round_trip, and ids unless left out) for each row of ``docs``; ``path``: the model's file on every machine.

    round_trip: whether decoding gives the text again; it does unless the text holds the mark that stands for a blank. Null and empty texts have
    no pieces. Each row stands alone, repeated and null ids included. Other columns are not read.
    """
    voc = opened(path)
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    total = base.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = min(8192, max(docs.sparkSession.sparkContext.defaultParallelism, -(-total // (8 << 20))))
    buckets = max(1, -(-total // bucket))
    parcels = base.mapInArrow(_parcelled(path, buckets, parcel), PARCELS)
    parcels = parcels.repartition(buckets, "bucket")
    listed = parcels.groupBy("bucket").applyInArrow(_listed, ATOMS)
    distinct = listed.select("name", "n", "at", "chunk").repartition(parts, "name").dropDuplicates(["name", "at"])
    # a short atom is its own name, and one part; of a long one the row with its place has no part
    rows = distinct.where((F.substring("name", 1, 1) != "\0") | (F.col("name") == "\0") | F.col("at").isNotNull())
    rows = rows.select("name", F.coalesce("n", F.char_length("name")).alias("n"), F.coalesce("at", F.lit(0)).alias("at"), F.coalesce("chunk", "name").alias("chunk"))
    back = decode(encode_atoms(rows, voc), path, "name", first_blank=True)
    coded = back.select("name", "ids", (_named(F.replace("text", F.lit(" "), F.lit(SPACE))) == F.col("name")).alias("exact"))
    if voc.size < 1 << 15:  # shorter rows to move
        coded = coded.withColumn("ids", F.col("ids").cast("array<smallint>"))
    placed = listed.where("place IS NOT NULL").select("place", "name").repartition(parts, "name").join(coded, "name")
    by_bucket = placed.select(F.floor(F.col("place") / MOST).alias("bucket"), "place", "ids", "exact")
    return parcels.groupBy("bucket").cogroup(by_bucket.groupBy("bucket")).applyInArrow(_assembled(with_ids), OUT + (", ids array<int>" if with_ids else ""))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(read(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"), with_ids=False)
