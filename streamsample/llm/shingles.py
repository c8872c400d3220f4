"""Word shingles of whole texts as 64-bit hashes, in numpy over the bytes of many texts at once."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text that one numpy pass takes, longer single texts aside.
CHUNK = 1 << 21
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_WHITE = np.zeros(256, dtype=bool)
_WHITE[[9, 10, 11, 12, 13, 32]] = True
#: Odd bases of rolling sums, each with its inverse.
_BASES = [(np.uint64(b), np.uint64(pow(b, -1, 1 << 64))) for b in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)]
_POWERS: list[list[np.ndarray]] = [[], []]
_PLACES = np.array([pow(0xD6E8FEB86659FD93, k + 1, 1 << 64) for k in range(64)], dtype=np.uint64)


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words whose every output bit depends on every input bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def powers(n: int, which: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of a base, and of its inverse."""
    held = _POWERS[which]
    if not held or len(held[0]) < n:
        size = max(1 << 18, 1 << (n - 1).bit_length() if n else 1)
        held[:] = [np.cumprod(np.full(size, b, dtype=np.uint64), dtype=np.uint64) for b in _BASES[which]]
    return held[0][:n], held[1][:n]


def raw_texts(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of all texts, offsets); a null is empty."""
    arr = pc.fill_null(column, "").cast(pa.large_binary())
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    _, offsets, data = arr.buffers()
    offs = np.frombuffer(offsets, dtype=np.int64)[arr.offset : arr.offset + len(arr) + 1]
    flat = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)
    return flat[offs[0] : offs[-1]], offs - offs[0]


def slices(offsets: np.ndarray, limit: int = CHUNK):
    """Ranges of texts of about ``limit`` bytes together."""
    at, n = 0, len(offsets) - 1
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1)
        yield at, min(to, n)
        at = min(to, n)


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, words before each text). Words are runs of other than white space; A-Z are lower-cased."""
    n = len(data)
    if not n:
        return np.zeros(0, dtype=np.uint64), np.zeros(len(offsets), dtype=np.int64)
    low = _LOWER[data]
    white = _WHITE[low]
    edge = np.zeros(n + 1, dtype=bool)
    edge[offsets] = True
    before, after = edge[:-1].copy(), edge[1:].copy()
    before[1:] |= white[:-1]
    after[:-1] |= white[1:]
    starts, ends = np.flatnonzero(~white & before), np.flatnonzero(~white & after) + 1
    up, down = powers(n)
    total = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum((low.astype(np.uint64) + np.uint64(1)) * up, out=total[1:])
    own = (total[ends] - total[starts]) * down[starts]
    words = mixed(own + (ends - starts).astype(np.uint64) * np.uint64(0xA0761D6478BD642F))
    return words, np.searchsorted(starts, offsets)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int = 5) -> list[np.ndarray]:
    """For each text the sorted distinct hashes of its shingles of ``width`` words; of its whole sequence if it has fewer."""
    words, at = word_hashes(data, offsets)
    n = max(0, len(words) - width + 1)
    rolled = np.zeros(n, dtype=np.uint64)
    for k in range(width):
        rolled += words[k : n + k] * _PLACES[k]
    rolled = mixed(rolled)
    out = []
    for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        if b - a >= width:
            out.append(np.unique(rolled[a : b - width + 1]))
        elif b > a:
            whole = (words[a:b] * _PLACES[: b - a]).sum(dtype=np.uint64) + np.uint64(b - a)
            out.append(mixed(np.array([whole], dtype=np.uint64)))
        else:
            out.append(np.zeros(0, dtype=np.uint64))
    return out


def piece_hashes(code: np.ndarray, spots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two hashes of each piece of a text given as code points; ``spots``: where pieces begin, and the end. Sums of mixed code points times powers of two bases; meant for pieces of up to some hundred characters."""
    values, starts, sizes = mixed(code.astype(np.uint64) + np.uint64(1)), spots[:-1], np.diff(spots).astype(np.uint64)
    out, total = [], np.zeros(len(code) + 1, dtype=np.uint64)
    for which in (0, 1):
        up, down = powers(len(code), which)
        np.cumsum(values * up, out=total[1:])
        at = total[spots]
        out.append((at[1:] - at[:-1]) * down[starts])
    return mixed(out[0]) + sizes, out[1]


def distinct_pieces(one: np.ndarray, two: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(the first place of each distinct hash, in the order of places; all as numbers of these; how often each occurs). The second hash must agree."""
    _, first, numbers, counts = np.unique(one, return_index=True, return_inverse=True, return_counts=True)
    if (two[first[numbers]] != two).any():
        raise ValueError("two pieces have one hash")
    order = np.argsort(first)
    place = np.empty(len(order), dtype=np.uint32)
    place[order] = np.arange(len(order), dtype=np.uint32)
    return first[order], place[numbers], counts[order]


def ragged(at: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Indices at[0], at[0]+1, ... of each run, one run after the other."""
    return np.repeat(at - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
