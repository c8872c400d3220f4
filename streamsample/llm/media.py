"""Telephony audio in binary columns: mu-law, A-law and ADPCM to PCM, resampled; numpy over many rows at once.

Payloads are kept as RIFF files with 8-bit samples (mu-law or A-law) or 4-bit ADPCM blocks. The two companding laws expand by
tables of 256 entries made from their rule. ADPCM predicts each sample from the one before it, so a block is a chain, but blocks
don't depend on each other: the decoder walks along the samples of a block and handles all blocks of all rows in each step.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import Workspace, read
from .shingles import raw_texts, slices

RATE, UNIT = 8000, 64
#: Of the rate at which sound is stored to that of the files: 16 kHz.
RATIO = (2, 1)
#: Format tags of RIFF audio.
PCM, A_LAW, MU_LAW, ADPCM = 1, 6, 7, 0x11


def mu_law_table() -> np.ndarray:
    """16-bit sample of each mu-law code."""
    code = ~np.arange(256) & 0xFF
    size = (((code & 15) << 3) + 132 << (code >> 4 & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


def a_law_table() -> np.ndarray:
    """16-bit sample of each A-law code."""
    code = np.arange(256) ^ 0x55
    part, low = code >> 4 & 7, (code & 15) << 4
    size = np.where(part == 0, low + 8, low + 264 << np.maximum(part - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


def step_table() -> np.ndarray:
    """The 89 ADPCM step sizes, each about a tenth larger than the one before it."""
    #: Fixed values.
    steps = [
        7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494,
        544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487,
        12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767,
    ]
    return np.array(steps, dtype=np.int32)


MU, A, STEPS = mu_law_table(), a_law_table(), step_table()
#: How a code's three low bits move the step index.
MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8] * 2, dtype=np.int32)


def decode_adpcm(blocks: np.ndarray) -> np.ndarray:
    """(n, size) bytes of mono blocks to (n, 1 + 2 * (size - 4)) samples. A block: first sample, step index (clipped to the table), unused, codes."""
    n, size = blocks.shape
    now = blocks[:, 0].astype(np.int32) | blocks[:, 1].astype(np.int32) << 8
    now = np.where(now > 32767, now - 65536, now)
    index = np.minimum(blocks[:, 2].astype(np.int32), len(STEPS) - 1)
    codes = np.empty((2 * (size - 4), n), dtype=np.uint8)
    codes[0::2], codes[1::2] = blocks[:, 4:].T & 15, blocks[:, 4:].T >> 4
    out = np.empty((len(codes) + 1, n), dtype=np.int16)
    out[0] = now
    for k, code in enumerate(codes):
        step = STEPS[index]
        diff = (step >> 3) + (step >> 2) * (code & 1) + (step >> 1) * (code >> 1 & 1) + step * (code >> 2 & 1)
        now = np.clip(now + np.where(code & 8, -diff, diff), -32768, 32767)
        index = np.clip(index + MOVES[code], 0, len(STEPS) - 1)
        out[k + 1] = now
    return out.T


def encode_adpcm(samples: np.ndarray, size: int = 256) -> np.ndarray:
    """(n, 1 + 2 * (size - 4)) samples to (n, size) bytes of blocks; the decoder's own predictions steer it."""
    now, index = samples[:, 0].astype(np.int32), np.zeros(len(samples), dtype=np.int32)
    out = np.zeros((len(samples), size), dtype=np.uint8)
    out[:, 0], out[:, 1] = now & 255, now >> 8 & 255
    for k in range(1, samples.shape[1]):
        step = STEPS[index]
        gap = samples[:, k].astype(np.int32) - now
        code, left, diff = np.where(gap < 0, 8, 0), np.abs(gap), step >> 3
        for bit, part in ((4, step), (2, step >> 1), (1, step >> 2)):
            on = left >= part
            code, left, diff = code | bit * on, left - part * on, diff + part * on
        now = np.clip(now + np.where(code & 8, -diff, diff), -32768, 32767)
        index = np.clip(index + MOVES[code], 0, len(STEPS) - 1)
        out[:, 4 + (k - 1) // 2] |= (code << 4 * ((k - 1) % 2)).astype(np.uint8)
    return out


def resample(pcm: np.ndarray, ends: np.ndarray, up: int, down: int) -> tuple[np.ndarray, np.ndarray]:
    """(signals at up / down of their rate, by linear interpolation rounded down; where they end). pcm: signals laid end to end; ``ends``: where each ends. The last sample is held."""
    sizes = np.diff(ends, prepend=0)
    made = -(-sizes * up // down)
    out_ends = np.cumsum(made)
    place = (np.arange(out_ends[-1] if len(ends) else 0) - np.repeat(out_ends - made, made)) * down
    at = np.repeat(ends - sizes, made) + place // up
    after = np.minimum(at + 1, np.repeat(ends, made) - 1)
    now, part = pcm[at].astype(np.int32), (place % up).astype(np.int32)
    return (now + (pcm[after].astype(np.int32) - now) * part // up).astype(np.int16), out_ends


def riff(payload: bytes, tag: int = MU_LAW, rate: int = RATE, block: int = 1, bits: int = 8, per_block: int = 1) -> bytes:
    """A mono RIFF file. A payload of odd length gets the format's pad byte."""
    extra = struct.pack("<HH", 2, per_block) if tag == ADPCM else struct.pack("<H", 0)
    fmt = struct.pack("<HHIIHH", tag, 1, rate, rate * block // per_block, block, bits) + extra
    units = len(payload) // block * per_block
    body = b"WAVE" + b"fmt " + struct.pack("<I", len(fmt)) + fmt + b"fact" + struct.pack("<II", 4, units) + b"data" + struct.pack("<I", len(payload)) + payload + b"\0" * (len(payload) % 2)
    return b"RIFF" + struct.pack("<I", len(body)) + body


def parts(media: bytes) -> tuple[tuple[int, int, int], memoryview]:
    """((format tag, rate, block size), payload) of a RIFF file; ValueError if it is none."""
    view = memoryview(media)
    if len(view) < 12 or view[:4] != b"RIFF" or view[8:12] != b"WAVE":
        raise ValueError("not a RIFF audio file")
    at, fmt = 12, None
    while at + 8 <= len(view):
        name, size = bytes(view[at : at + 4]), int.from_bytes(view[at + 4 : at + 8], "little")
        body = view[at + 8 : at + 8 + size]
        if name == b"fmt ":
            if len(body) < 14:
                raise ValueError("format chunk cut short")
            tag, _, rate, _, block = struct.unpack("<HHIIH", body[:14])
            fmt = (tag, rate, block)
        elif name == b"data":
            if fmt is None or len(body) < size:
                raise ValueError("no format before the data, or data cut short")
            return fmt, body
        at += 8 + size + size % 2
    raise ValueError("no data")


def whole(tag: int, size: int, block: int) -> int:
    """Bytes of a payload that hold whole samples or blocks; ValueError if the format is unknown or its blocks can't be."""
    if tag == ADPCM:
        if block <= 4:
            raise ValueError(f"blocks of {block} bytes hold no samples")
        return size // block * block
    if tag not in (PCM, MU_LAW, A_LAW):
        raise ValueError(f"format {tag} is unknown")
    return size // 2 * 2 if tag == PCM else size


def expand(tag: int, payload: np.ndarray, block: int) -> np.ndarray:
    """PCM of a payload of any of the formats; of several ones laid end to end, too, if each is of whole samples or blocks."""
    payload = payload[: whole(tag, len(payload), block)]
    if tag == PCM:
        return payload.view("<i2")
    return decode_adpcm(payload.reshape(-1, block)).reshape(-1) if tag == ADPCM else (MU if tag == MU_LAW else A)[payload]


def pcm_files(files: list[bytes | None], ratio: tuple[int, int] = RATIO) -> tuple[list[bytes | None], list[str | None]]:
    """(16-bit PCM files at ``ratio`` of the rate, or nulls; why there is none). Files of one format are expanded and resampled together."""
    out: list[bytes | None] = [None] * len(files)
    faults: list[str | None] = [None] * len(files)
    groups: dict[tuple[int, int, int], list[tuple[int, memoryview]]] = {}
    for k, media in enumerate(files):
        try:
            form, load = parts(media or b"")
            load = load[: whole(form[0], len(load), form[2])]
            groups.setdefault(form, []).append((k, load))
        except ValueError as e:
            faults[k] = str(e)
    for (tag, rate, block), some in groups.items():
        pcm = expand(tag, np.frombuffer(b"".join(load for _, load in some), dtype=np.uint8), block)
        per = {PCM: (1, 2), ADPCM: (2 * block - 7, block)}.get(tag, (1, 1))
        ends = np.cumsum([len(load) // per[1] * per[0] for _, load in some])
        made, ends = resample(pcm, ends, *ratio)
        raw = made.astype("<i2").view(np.uint8)
        for (k, _), a, b in zip(some, [0, *ends[:-1].tolist()], ends.tolist(), strict=True):
            out[k] = riff(raw[2 * a : 2 * b].tobytes(), PCM, rate * ratio[0] // ratio[1], 2, 16)
    return out, faults


def _between(even: np.ndarray, n: int) -> np.ndarray:
    """The means, rounded down, of the first n of these samples and the ones after them; the last one is held."""
    after = np.append(even[1:], even[-1:])[:n]
    return even[:n].astype(np.int32) + after >> 1


def pack(file: bytes) -> bytes:
    """A file of 16-bit PCM without loss: its head, every other sample, and by how much those between differ from the means of their neighbours."""
    at = len(file) - len(parts(file)[1])
    pcm = np.frombuffer(file, dtype="<i2", offset=at)
    even, odd = pcm[0::2], pcm[1::2]
    return file[:at] + even.tobytes() + (odd - _between(even, len(odd))).astype("<i2").tobytes()


def unpack(packed: bytes) -> bytes:
    """The file that ``pack`` was given."""
    at = len(packed) - len(parts(packed)[1])
    load = np.frombuffer(packed, dtype="<i2", offset=at)
    pcm, n = np.empty_like(load), len(load) // 2
    pcm[0::2] = load[: len(load) - n]
    pcm[1::2] = (_between(pcm[0::2], n) + load[len(load) - n :]).astype("<i2")
    return packed[:at] + pcm.tobytes()


def _store(batches: Iterator[pa.RecordBatch], packed: bool = False) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, offsets = raw_texts(batch.column(1))
        for a, b in slices(offsets):
            raw = [data[offsets[k] : offsets[k + 1]].tobytes() for k in range(a, b)]
            media = [riff(x + b"\0" * (max(UNIT, -(-len(x) // UNIT) * UNIT) - len(x))) for x in raw]
            sound = pcm_files(media)[0]
            sound = [pack(x) for x in sound] if packed else sound
            cols = [batch.column(0).slice(a, b - a), pa.array([len(x) for x in raw], pa.int64()), pa.array(media, pa.binary()), pa.array(sound, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "n_bytes", "media", "pcm"])


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", packed: bool = False) -> DataFrame:
    """(doc_id, n_bytes, media, pcm): each text's bytes, filled with 0 to a positive multiple of 64, as mu-law samples in a RIFF file, and that file's
    sound as 16-bit PCM at 16 kHz, in a RIFF file too; ``packed``: by ``pack``, for stores whose codec then finds little in what was interpolated.

    Null and empty texts become 64 zero bytes. Each row stands alone. Other columns are not read.
    """
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(partial(_store, packed=packed), "doc_id long, n_bytes long, media binary, pcm binary")


def _resampled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        _, offsets = raw_texts_of_binary(batch.column(1))
        for a, b in slices(offsets):
            out, faults = pcm_files(batch.column(1).slice(a, b - a).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(out, pa.binary()), pa.array(faults, pa.string())], names=["doc_id", "pcm", "fault"])


def to_pcm(media: DataFrame, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """(doc_id, pcm, fault): telephony files as RIFF files of 16-bit PCM at twice their rate. Nulls and files that can't be read get a null and the reason."""
    return media.select(F.col(id_col).cast("long").alias("doc_id"), F.col(media_col).alias("media")).mapInArrow(_resampled, "doc_id long, pcm binary, fault string")


READ = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _features(batches: Iterator[pa.RecordBatch], packed: bool = False) -> Iterator[pa.RecordBatch]:
    """Several files a pass: their payloads, all of whole units, are laid end to end."""
    for batch in batches:
        data, offsets = raw_texts_of_binary(batch.column(2))
        for a, b in slices(offsets):
            files = [data[offsets[k] : offsets[k + 1]].tobytes() for k in range(a, b)]
            loads = [parts(x)[1] for x in files]
            sizes = np.array([len(x) for x in loads])
            ends = np.cumsum(sizes)
            flat = np.frombuffer(b"".join(loads), dtype=np.uint8)
            mu, al = MU[flat], A[flat]
            stored = batch.column(3).slice(a, b - a).to_pylist()
            sound = [parts(unpack(x) if packed else x)[1] for x in stored]
            coded = decode_adpcm(flat.reshape(-1, UNIT))
            at, per = ends - sizes, (ends - sizes) // UNIT
            power = lambda x, where: np.add.reduceat(x.astype(np.int64) ** 2, where)
            mu2, al2 = power(mu, at), power(al, at)
            ad2 = np.add.reduceat((coded.astype(np.int64) ** 2).sum(axis=1), per)
            turns = np.append((mu[1:] < 0) != (mu[:-1] < 0), False)
            turns[ends - 1] = False
            zero = np.add.reduceat(turns.astype(np.int64), at)
            peak = np.maximum.reduceat(np.abs(mu.astype(np.int32)), at)
            feature = [
                f"mu_ms={mu2[k] // sizes[k]};a_ms={al2[k] // sizes[k]};adpcm_ms={ad2[k] // (sizes[k] // UNIT * coded.shape[1])};peak={peak[k]};turns={zero[k]};pcm={len(sound[k]) // 2}:{zlib.crc32(sound[k]):08x}"
                for k in range(b - a)
            ]
            cols = [
                batch.column(0).slice(a, b - a),
                batch.column(1).slice(a, b - a),
                pa.array(sizes, pa.int64()),
                pa.array([hashlib.sha256(x).hexdigest() for x in loads]),
                pa.array([zlib.crc32(x[-UNIT:]) for x in loads], pa.int64()),
                pa.array([len(x) for x in files], pa.int64()),
                pa.array([hashlib.sha256(x).hexdigest() for x in files]),
                pa.array(feature),
            ]
            yield pa.RecordBatch.from_arrays(cols, names=[c.split()[0] for c in READ.split(", ")])


def raw_texts_of_binary(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """As ``raw_texts``, of a column of files."""
    arr = column.cast(pa.large_binary())
    _, offsets, data = arr.buffers()
    offs = np.frombuffer(offsets, dtype=np.int64)[arr.offset : arr.offset + len(arr) + 1]
    flat = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)
    return flat[offs[0] : offs[-1]], offs - offs[0]


def read_back(media: DataFrame, packed: bool = False) -> DataFrame:
    """Sums and features of stored texts (doc_id, n_bytes, media, pcm), from the stored bytes of both files. All figures are whole numbers."""
    return media.select("doc_id", "n_bytes", "media", "pcm").mapInArrow(partial(_features, packed=packed), READ)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    space = Workspace(spark, "media")
    return read_back(space.store(store_texts(read(spark, sf_dir, "documents"), packed=True), "files", level=12), packed=True)
