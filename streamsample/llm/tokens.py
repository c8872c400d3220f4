"""Token ids of whole texts by the tokenizers library, each distinct piece of text encoded once while it stays in a bounded memory.

The byte-level vocabulary cuts a text before it merges: runs of letters, of digits and of other signs, each with a blank before it, and white space.
No token crosses such a cut, so the ids of a text are those of its pieces, one after the other. Texts of Latin characters are cut by
numpy, many at once, and their pieces told apart by hashes (``Pieces``). Other texts are cut before every blank that a non-blank follows; runs of three
white spaces, or of two at the end, are the exception: such texts are encoded whole.
"""

from __future__ import annotations

import os
import re
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .shingles import piece_hashes, ragged

#: Pieces remembered: by hash, and by text in each of two generations.
REMEMBERED, REMEMBERED_TEXTS = 1_500_000, 300_000
_ODD_SPACE = re.compile(r"\s\s\s|\s\s\Z")
#: A word of Latin letters, perhaps with a mark, perhaps with a line's end and another such word.
_LATIN = "[A-Za-zÀ-ÖØ-öø-ɏ]+"
_PLAIN = re.compile(f"({_LATIN})([.,]?)(?:(\n)({_LATIN})([.,]?))?")
#: The byte-level alphabet: printable bytes stand for themselves, the others for the characters from U+0100 on.
_SHOWN = [b for b in range(256) if 33 <= b < 127 or 161 <= b < 173 or 174 <= b]
_ALPHABET = {b: chr(b) for b in _SHOWN} | {b: chr(256 + k) for k, b in enumerate(sorted(set(range(256)) - set(_SHOWN)))}
_ENCODERS: dict[str, PieceEncoder] = {}


#: Code points below which texts are cut by numpy; kinds of characters: blank, other white space, letter, digit, other sign.
LATIN = 0x250
BLANK, WHITE, LETTER, DIGIT, SIGN = range(5)
KINDS = np.array([BLANK if c == 32 else WHITE if 9 <= c <= 13 else LETTER if chr(c).isalpha() else DIGIT if chr(c).isnumeric() else SIGN for c in range(LATIN)], dtype=np.uint8)
#: Pieces of so many characters at most are told apart by hashes.
LONGEST = 512
#: Characters whose texts are not cut by numpy: others than Latin ones, and separators that libraries may take differently.
_OTHER = re.compile("[^\x00-\x1b\x20-\x84\x86-\x9f\xa1-\u024f]")


def cut_pieces(code: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Where the pieces of texts of Latin characters, laid end to end, begin, and the end. edges: where texts begin and end.

    Of a run of white space that something follows, the last character stands by itself, or, if a blank, with what follows. A word with an apostrophe stays whole.
    """
    n = len(code)
    cut = np.ones(n + 1, dtype=bool)
    if n:
        kind = KINDS[code]
        white = kind <= WHITE
        ends = np.zeros(n + 1, dtype=bool)
        ends[edges] = True
        open_after = np.append(~white[1:], False) & ~ends[1:]  # a character that is no white space follows in the same text
        a, b = slice(None, -1), slice(1, None)
        words = np.cumsum(np.append(True, white[b] | white[a] | ends[1:-1]))
        whole = np.zeros(words[-1] + 1, dtype=bool)
        whole[words[code == 39]] = True
        inside = ~white[a] & ~white[b]
        cut[1:-1] = np.where(inside, (kind[a] != kind[b]) & ~whole[words[b]], np.where(white[a] & white[b], open_after[b], white[b] | (kind[a] == WHITE)))
        cut[edges] = True
    return np.flatnonzero(cut)


class Pieces:
    """Ids of pieces that were met, by hash, up to a bound: sorted runs, of which younger ones are merged before they are half as long as the one before."""

    def __init__(self, encode) -> None:
        self.encode = encode
        self._forget()

    def _forget(self) -> None:
        #: Each run: hashes in order, second hashes, where ids begin in ``flat``, and their number.
        self.runs: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        self.flat, self.held = np.zeros(1 << 16, dtype=np.uint32), 0

    def _keep(self, one: np.ndarray, two: np.ndarray, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Have the ids of new pieces, given in the order of their hashes."""
        at, sizes, flat = self.encode(pieces)
        at += self.held
        if self.held + len(flat) > len(self.flat):
            self.flat = np.concatenate([self.flat[: self.held], np.zeros(self.held + 2 * len(flat), dtype=np.uint32)])
        self.flat[self.held : self.held + len(flat)] = flat
        self.held += len(flat)
        self.runs.append((one, two, at, sizes))
        while len(self.runs) > 1 and 2 * len(self.runs[-1][0]) > len(self.runs[-2][0]):
            young, old = self.runs.pop(), self.runs.pop()
            order = np.argsort(np.concatenate([old[0], young[0]]), kind="stable")
            self.runs.append(tuple(np.concatenate([x, y])[order] for x, y in zip(old, young, strict=True)))
        return at, sizes

    def ids(self, texts: list[str]) -> list[bytes] | None:
        """The ids of each text; None if a piece is too long for a hash, or two pieces have the same one."""
        if sum(len(r[0]) for r in self.runs) > REMEMBERED:
            self._forget()
        whole = "".join(texts)
        code = np.frombuffer(whole.encode("utf-32-le"), dtype=np.uint32)
        edges = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
        spots = cut_pieces(code, edges)
        if len(code) and np.diff(spots).max() > LONGEST:
            return None
        one, two = piece_hashes(code, spots)
        sought, first, numbers = np.unique(one, return_index=True, return_inverse=True)
        second = two[first]
        if (second[numbers] != two).any():
            return None
        at, sizes, new = np.zeros(len(sought), dtype=np.int64), np.zeros(len(sought), dtype=np.int64), np.arange(len(sought))
        for run in self.runs:
            spot = np.minimum(np.searchsorted(run[0], sought[new]), len(run[0]) - 1)
            known = run[0][spot] == sought[new]
            hits, spot = new[known], spot[known]
            if (run[1][spot] != second[hits]).any():
                return None
            at[hits], sizes[hits], new = run[2][spot], run[3][spot], new[~known]
        if len(new):
            begins, ends = spots[first[new]].tolist(), spots[first[new] + 1].tolist()
            at[new], sizes[new] = self._keep(sought[new], second[new], [whole[a:b] for a, b in zip(begins, ends, strict=True)])
        sizes = sizes[numbers]
        raw = self.flat[ragged(at[numbers], sizes)].tobytes()
        total = 4 * np.concatenate([[0], np.cumsum(sizes)])[np.searchsorted(spots, edges)]
        return [raw[a:b] for a, b in zip(total[:-1].tolist(), total[1:].tolist(), strict=True)]


class PieceEncoder:
    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # such strings in a text are ordinary text
        self.model = self.tokenizer.model
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.pieces = Pieces(self._encoded_pieces)

    def forget(self) -> None:
        """Drop what is remembered, for a worker that goes on to other work."""
        self.pieces._forget()
        self.young, self.old = {}, {}

    def _encoded_pieces(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(where each piece's ids begin, their number, all ids)."""
        first, sizes, flat, tokenize, blank = [0] * len(pieces), [0] * len(pieces), [], self.model.tokenize, _ALPHABET[32]
        rest = []
        for k, p in enumerate(pieces):
            if (p[1:] if p[0] == " " else p).isalpha():  # one run of letters is one token before merging, so the library's model may be asked at once
                found = tokenize(p.replace(" ", blank) if p.isascii() else p.encode().decode("latin-1").translate(_ALPHABET))
                first[k], sizes[k] = len(flat), len(found)
                flat += [t.id for t in found]
            else:
                rest.append(k)
        for k, e in zip(rest, self.tokenizer.encode_batch_fast([pieces[k] for k in rest], add_special_tokens=False), strict=True):
            first[k], sizes[k] = len(flat), len(e.ids)
            flat += e.ids
        return np.array(first, dtype=np.int64), np.array(sizes, dtype=np.int64), np.array(flat, dtype=np.uint32)

    def _encoded(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, dtype="<u4").tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _encoded_words(self, words: list[str], lead: str = _ALPHABET[32]) -> list[bytes]:
        """The same for words of Latin letters with a blank before each: one token run by itself, so the library's model may be asked at once."""
        out, tokenize = [], self.model.tokenize
        for w in words:
            shown = lead + (w if w.isascii() else w.encode().decode("latin-1").translate(_ALPHABET))
            out.append(array("I", [t.id for t in tokenize(shown)]).tobytes())
        return out

    def _learn(self, pieces: set[str]) -> None:
        """Have every one of ``pieces`` in the young generation, under its text with the blank before it."""
        if len(self.young) > REMEMBERED_TEXTS:
            self.old, self.young = self.young, {}
        young, old = self.young, self.old
        new, split = set(), []
        for p in pieces.difference(young):
            if p in old:
                young[p] = old[p]
            elif m := _PLAIN.fullmatch(p):  # letters, a mark and a line's end are never in one token
                if m.end(1) < len(p):
                    split.append((p, *m.groups("")))
                if m.group(1) not in young:
                    new.add(m.group(1))
            else:
                new.add(p)
        words = [p for p in new if p.isalpha() and max(p) < "\u0250"]
        young.update(zip(words, self._encoded_words(words), strict=True))
        rest = list(new.difference(words))
        young.update(zip(rest, self._encoded([f" {p}" for p in rest]), strict=True))
        if split:
            mark = {"": b""} | dict(zip(".,\n", self._encoded([".", ",", "\n"]), strict=True))
            heads = self._encoded_words([s[4] for s in split if s[3]], "")
            at = iter(heads)
            for p, word, one, line, _, two in split:
                young[p] = young[word] + mark[one] + (mark[line] + next(at) + mark[two] if line else b"")

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text, 4 bytes each, little-endian."""
        latin = [not _OTHER.search(t) for t in texts]
        out: list[bytes | None] = [None] * len(texts)
        fast = [k for k, x in enumerate(latin) if x]
        for a, b in text_slices([texts[k] for k in fast], 1 << 18):
            found = self.pieces.ids([texts[k] for k in fast[a:b]])
            for k, ids in zip(fast[a:b], found if found is not None else self._by_blanks([texts[k] for k in fast[a:b]]), strict=True):
                out[k] = ids
        other = [k for k, x in enumerate(latin) if not x]
        for k, ids in zip(other, self._by_blanks([texts[k] for k in other]), strict=True):
            out[k] = ids
        return out

    def _by_blanks(self, texts: list[str]) -> list[bytes]:
        out: list[bytes | None] = [None] * len(texts)
        cut = [None if _ODD_SPACE.search(t) else t.split(" ") for t in texts]
        whole = [k for k, c in enumerate(cut) if c is None]
        if whole:
            for k, ids in zip(whole, self._encoded([texts[k] for k in whole]), strict=True):
                out[k] = ids
        rest = [k for k, c in enumerate(cut) if c is not None]
        heads = self._encoded([cut[k].pop(0) for k in rest])
        self._learn(set().union(*(cut[k] for k in rest)))
        find = self.young.__getitem__
        for k, head in zip(rest, heads, strict=True):
            out[k] = head + b"".join(map(find, cut[k]))
        return out


def encoder(path: str) -> PieceEncoder:
    """One for each vocabulary and Python process."""
    if path not in _ENCODERS:
        _ENCODERS[path] = PieceEncoder(path)
    return _ENCODERS[path]


def text_slices(texts: list[str], limit: int = 1 << 21):
    """Ranges of texts of about ``limit`` characters together."""
    at, held = 0, 0
    for k, t in enumerate(texts):
        if held and held + len(t) > limit:
            yield at, k
            at, held = k, 0
        held += len(t)
    if at < len(texts):
        yield at, len(texts)


def text_parts(column: pa.Array, limit: int = 1 << 20):
    """(from, to, texts) for ranges of a column of about ``limit`` bytes together, a null text empty: only one range at a time is held as Python strings."""
    if not len(column):
        return
    ends = np.cumsum(pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < len(column):
        before = int(ends[at - 1]) if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + limit, side="right")))
        yield at, to, [t or "" for t in column.slice(at, to - at).to_pylist()]
        at = to


def vocabulary(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
