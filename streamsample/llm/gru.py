"""A bidirectional gated recurrent network with attention pooling, over word and character inputs; numpy, forwards and backwards."""

from __future__ import annotations

import re
import zlib

import numpy as np

from .shingles import ragged

BUCKETS = 1 << 15
DIMS, STATE, LOOK = 12, 8, 8
SPAN, STRIDE = 32, 16
_EDGES = ".,;:!?\"'()[]{}<>«»¿¡…-_*~"
#: Bytes of a word up to which it is one input, and bytes of each of the overlapping sub-words that a longer part is cut into.
WHOLE, PART = 62, 16
_JOINS = r"!-/:-@\[-`{-~\u00ad\u200b-\u200d\u2010-\u2015\u2060\u3001\u3002\uff01\uff0c\uff1a\uff1b\uff1f\ufeff"
_JOINED = re.compile(f"[^{_JOINS}]+[{_JOINS}]*|[{_JOINS}]+")


def core(word: str) -> bytes:
    return (word.strip(_EDGES) or word).encode("utf-8", "replace")


def _width(word: str) -> int:
    return len(word.encode("utf-8", "replace"))


def sub_words(word: str) -> list[str]:
    """The word, or, if it is longer than ``WHOLE`` bytes, its parts between joining marks; parts that are still longer are cut into
    sub-words of about ``PART`` bytes, each of which overlaps the next by half. Every character is in one of them."""
    if len(word) * 4 <= WHOLE or _width(word) <= WHOLE:
        return [word]
    out = []
    for part in _JOINED.findall(word):
        if _width(part) <= WHOLE:
            out.append(part)
            continue
        n = PART // max(map(_width, set(part))) // 2 * 2
        out += [part[k : k + n] for k in range(0, max(1, len(part) - n // 2), n // 2)]
    return out


def words_of(text: str) -> list[str]:
    """A text's words in lower case, long ones as sub-words."""
    words = text.lower().split()
    if max(map(len, words), default=0) * 4 <= WHOLE:
        return words
    return [p for w in words for p in sub_words(w)]


def word_inputs(words: list[str], sizes: tuple[int, ...] = (3, 4, 5)) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(each word's bucket in the word table; its byte n-grams' buckets in the character table, word by word; how many those are)."""
    cores = [core(w) for w in words]
    own = np.array([zlib.crc32(c) % BUCKETS for c in cores], dtype=np.int64)
    marked = [b"^" + c + b"$" for c in cores]
    flat = np.frombuffer(b"".join(marked), dtype=np.uint8).astype(np.uint32)
    of = np.repeat(np.arange(len(words), dtype=np.int32), [len(m) for m in marked])
    grams, where = [], []
    for n in sizes:
        h = np.full(max(0, len(flat) - n + 1), n, dtype=np.uint32)
        for k in range(n):
            h = (h ^ flat[k : len(h) + k]) * np.uint32(0x01000193)
        h = (h ^ h >> np.uint32(15)) * np.uint32(0x2C1B3C6D)
        inside = of[: len(h)] == of[n - 1 :][: len(h)]
        grams.append((h[inside] >> np.uint32(17)).astype(np.int32))
        where.append(of[: len(h)][inside])
    where = np.concatenate(where)
    order = np.argsort(where, kind="stable")
    return own, np.concatenate(grams)[order], np.bincount(where, minlength=len(words))


def starts(n_words: int) -> list[int]:
    """Where the windows of a text of so many words begin; they overlap by half, and together cover it all."""
    return list(range(0, max(1, n_words - STRIDE), STRIDE))


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def new_parameters(seed: int = 5) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    p = {"words": rng.normal(0, 0.05, (BUCKETS, DIMS)), "chars": rng.normal(0, 0.05, (BUCKETS, DIMS))}
    for d in "fb":
        p[f"w{d}"], p[f"u{d}"], p[f"c{d}"] = rng.normal(0, 0.4, (DIMS, 3 * STATE)), rng.normal(0, 0.3, (STATE, 3 * STATE)), np.zeros(3 * STATE)
    p |= {"look": rng.normal(0, 0.4, (2 * STATE, LOOK)), "look0": np.zeros(LOOK), "pick": rng.normal(0, 0.4, LOOK), "out": rng.normal(0, 0.4, 2 * STATE), "out0": np.zeros(1)}
    return {k: v.astype(np.float32) for k, v in p.items()}


class Words:
    """Distinct words in the order met; word 0 is the blank that fills windows."""

    def __init__(self) -> None:
        self.index: dict[str, int] = {}
        self.texts = [""]

    def ids(self, words: list[str]) -> np.ndarray:
        index = self.index
        for w in dict.fromkeys(words):
            if w not in index:
                index[w] = len(self.texts)
                self.texts.append(w)
        return np.fromiter(map(index.__getitem__, words), dtype=np.int64, count=len(words))


def summed(rows: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Row k: the sum of the values whose row is k."""
    return np.stack([np.bincount(rows, v, n) for v in values.T], axis=1).astype(np.float32)


def embedded(p: dict[str, np.ndarray], own: np.ndarray, flat: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Input vectors: a word's row plus the mean of its n-grams' rows."""
    x = p["words"][own].copy()
    has = sizes > 0
    if len(flat):
        at = (np.cumsum(sizes) - sizes)[has]
        x[has] += np.add.reduceat(p["chars"][flat], at) / sizes[has, None]
    return x


def all_inputs(words: list[str], block: int = 20_000) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``word_inputs`` in blocks of words, so that only the buckets of all of them are held at once."""
    parts = [word_inputs(words[k : k + block]) for k in range(0, len(words), block)]
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def embedded_all(p: dict[str, np.ndarray], own: np.ndarray, flat: np.ndarray, sizes: np.ndarray, block: int = 20_000) -> np.ndarray:
    """The same in blocks of words, word 0 blank."""
    ends = np.cumsum(sizes)
    parts = [embedded(p, own[k : k + block], flat[ends[k] - sizes[k] : ends[min(k + block, len(own)) - 1]], sizes[k : k + block]) for k in range(0, len(own), block)]
    x = np.concatenate(parts)
    x[0] = 0
    return x


def forward(p: dict[str, np.ndarray], tables: dict[str, np.ndarray], ids: np.ndarray, mask: np.ndarray, keep: bool = False):
    """Logits of windows. ids, mask: (n, SPAN). tables: for each direction the input part of all gates by word. keep: also what the way back needs."""
    n = len(ids)
    hidden, trace = np.zeros((SPAN, n, 2 * STATE), dtype=np.float32), {"f": [], "b": []}
    for d, order, side in (("f", range(SPAN), slice(0, STATE)), ("b", range(SPAN - 1, -1, -1), slice(STATE, None))):
        h, u, table = np.zeros((n, STATE), dtype=np.float32), p[f"u{d}"], tables[d]
        for t in order:
            g = table[ids[:, t]]
            zr = sigmoid(g[:, : 2 * STATE] + h @ u[:, : 2 * STATE])
            z, r = zr[:, :STATE], zr[:, STATE:]
            c = np.tanh(g[:, 2 * STATE :] + (r * h) @ u[:, 2 * STATE :])
            m = mask[:, t, None]
            if keep:
                trace[d].append((t, h, z, r, c, m))
            h = h + m * (1 - z) * (c - h)
            hidden[t, :, side] = h
    seen = np.tanh(hidden @ p["look"] + p["look0"])
    e = seen @ p["pick"] + np.where(mask.T > 0, 0, -1e4).astype(np.float32)
    e = np.exp(e - e.max(axis=0)) * (mask.T > 0)
    a = e / np.maximum(e.sum(axis=0), 1e-9)
    pooled = (a[:, :, None] * hidden).sum(axis=0)
    logit = pooled @ p["out"] + p["out0"]
    return (logit, (hidden, trace, seen, a, pooled)) if keep else logit


def backward(p: dict[str, np.ndarray], ids: np.ndarray, x: np.ndarray, kept, d_logit: np.ndarray) -> tuple[dict[str, np.ndarray], np.ndarray]:
    """Gradients of the parameters but the tables, and of the inputs by word (``x``: the words' vectors)."""
    hidden, trace, seen, a, pooled = kept
    g = {"out": pooled.T @ d_logit, "out0": d_logit.sum(keepdims=True)}
    d_pool = d_logit[:, None] * p["out"]
    d_hidden = a[:, :, None] * d_pool
    d_a = (hidden * d_pool).sum(axis=2)
    d_e = a * (d_a - (a * d_a).sum(axis=0))
    g["pick"] = np.einsum("tn,tnk->k", d_e, seen)
    d_seen = d_e[:, :, None] * p["pick"] * (1 - seen**2)
    g["look"], g["look0"] = np.einsum("tns,tnk->sk", hidden, d_seen), d_seen.sum(axis=(0, 1))
    d_hidden += d_seen @ p["look"].T
    parts: dict[int, np.ndarray] = {}
    for d, side in (("f", slice(0, STATE)), ("b", slice(STATE, None))):
        u, w = p[f"u{d}"], p[f"w{d}"]
        gu, gw, gc = np.zeros_like(u), np.zeros_like(w), np.zeros(3 * STATE, dtype=np.float32)
        carry = np.zeros((len(ids), STATE), dtype=np.float32)
        for t, h, z, r, c, m in reversed(trace[d]):
            dh = d_hidden[t, :, side] + carry
            dc = dh * m * (1 - z) * (1 - c**2)
            dz = dh * m * (h - c) * z * (1 - z)
            d_rh = dc @ u[:, 2 * STATE :].T
            dr = d_rh * h * r * (1 - r)
            dg = np.concatenate([dz, dr, dc], axis=1)
            carry = dh * (1 - m * (1 - z)) + d_rh * r + dg[:, : 2 * STATE] @ u[:, : 2 * STATE].T
            gu[:, : 2 * STATE] += h.T @ dg[:, : 2 * STATE]
            gu[:, 2 * STATE :] += (r * h).T @ dc
            gw += x[ids[:, t]].T @ dg
            gc += dg.sum(axis=0)
            parts[t] = parts.get(t, 0) + dg @ w.T
        g[f"u{d}"], g[f"w{d}"], g[f"c{d}"] = gu, gw, gc
    dx = summed(ids.T.ravel(), np.concatenate([parts[t] for t in range(SPAN)]), len(x))
    dx[0] = 0
    return g, dx


class Adam:
    def __init__(self, p: dict[str, np.ndarray], rate: float):
        self.p, self.rate, self.k = p, rate, 0
        self.m, self.v = ({n: np.zeros_like(a) for n, a in p.items()} for _ in range(2))

    def step(self, g: dict[str, np.ndarray]) -> None:
        self.k += 1
        for n, d in g.items():
            m, v = self.m[n], self.v[n]
            m += 0.1 * (d - m)
            v += 0.01 * (d * d - v)
            self.p[n] -= self.rate * (m / (1 - 0.9**self.k)) / (np.sqrt(v / (1 - 0.99**self.k)) + 1e-6)


def tables_of(p: dict[str, np.ndarray], x: np.ndarray) -> dict[str, np.ndarray]:
    out = {d: x @ p[f"w{d}"] + p[f"c{d}"] for d in "fb"}
    return {d: t.astype(np.float32) for d, t in out.items()}


def windows(doc_ids: list[np.ndarray], block: int = 4096) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, mask, document number) of all windows of some texts. Places are worked out for ``block`` windows at a time."""
    flat = np.concatenate([*doc_ids, np.zeros(1, dtype=np.int64)], dtype=np.int32, casting="same_kind")
    sizes = np.array([len(x) for x in doc_ids])
    begins = [starts(n) for n in sizes.tolist()]
    doc = np.repeat(np.arange(len(doc_ids)), [len(b) for b in begins])
    begin, before = np.concatenate(begins).astype(np.int64), np.cumsum(sizes) - sizes
    ids, mask = np.zeros((len(doc), SPAN), dtype=np.int32), np.zeros((len(doc), SPAN), dtype=np.float32)
    for k in range(0, len(doc), block):
        of = doc[k : k + block]
        within = begin[k : k + block, None] + np.arange(SPAN)
        inside = within < sizes[of][:, None]
        at = before[of][:, None] + within
        ids[k : k + block] = np.where(inside, flat[np.minimum(at, len(flat) - 1)], 0)
        mask[k : k + block] = inside
    return ids, mask, doc


def window_logits(p: dict[str, np.ndarray], tables: dict[str, np.ndarray], ids: np.ndarray, mask: np.ndarray, block: int = 4096) -> np.ndarray:
    return np.concatenate([forward(p, tables, ids[k : k + block], mask[k : k + block]) for k in range(0, len(ids), block)])


def text_logits(p: dict[str, np.ndarray], tables: dict[str, np.ndarray], doc_ids: list[np.ndarray], block: int = 4096) -> tuple[np.ndarray, np.ndarray]:
    """(largest logit of each text's windows, logits of all windows)."""
    ids, mask, doc = windows(doc_ids)
    logit = window_logits(p, tables, ids, mask, block)
    first = np.searchsorted(doc, np.arange(len(doc_ids)))
    return np.maximum.reduceat(logit, first), logit


def train(texts: list[str], labels: list[int], check: list[bool], seed: int = 5, rounds: int = 4, steps: int = 60, batch: int = 256) -> dict[str, np.ndarray] | None:
    """Parameters fitted to whole texts with one label each: of a text marked 1 the strongest window is held to 1, of one marked 0 the
    strongest two and a random one to 0; which these are is found anew in each round. ``check`` marks texts kept from fitting, on which the
    final shift is set. None unless both labels occur among the others."""
    y, aside, rng, words = np.array(labels), np.array(check, dtype=bool), np.random.default_rng(seed), Words()
    if len(set(y[~aside].tolist())) < 2:
        return None
    docs = [words.ids(words_of(t)) for t in texts]
    own, flat, sizes = all_inputs(words.texts)
    at = np.cumsum(sizes) - sizes
    p = new_parameters(seed)

    # the first input dimension starts as the log odds of label 1 by bucket
    fit = np.flatnonzero(~aside)
    seen = {n: np.zeros((2, BUCKETS)) for n in ("words", "chars")}
    for k in fit.tolist():
        u = np.unique(docs[k])
        if len(u):
            np.add.at(seen["words"][y[k]], np.unique(own[u]), 1)
            np.add.at(seen["chars"][y[k]], np.unique(flat[ragged(at[u], sizes[u])]), 1)
    n1 = max(1, int(y[fit].sum()))
    n0 = max(1, len(fit) - n1)
    for n, (c0, c1) in seen.items():
        odds = np.log((c1 + 0.5) / (n1 + 1)) - np.log((c0 + 0.5) / (n0 + 1))
        p[n][:, 0] = np.where(c0 + c1 > 2, np.clip(odds, -3, 5) / 2, 0)

    ids, mask, doc = windows([docs[k] for k in fit.tolist()])
    first = np.searchsorted(doc, np.arange(len(fit)))
    last = np.append(first[1:], len(doc))
    tool = Adam(p, 0.01)
    score = embedded_all(p, own, flat, sizes)[:, 0][ids].max(axis=1) + 0.01 * rng.random(len(ids))
    for k in range(rounds):
        chosen = []
        for a, b, label in zip(first.tolist(), last.tolist(), y[fit].tolist(), strict=True):
            best = a + np.argsort(-score[a:b], kind="stable")[: 2 - label]
            chosen += [*best.tolist(), *([] if label else [int(rng.integers(a, b))])]
        chosen = np.array(chosen)
        target = y[fit][doc[chosen]]
        weight = np.where(target == 1, 0.5 / max(1, target.sum()), 0.5 / max(1, (1 - target).sum())) * len(chosen)
        for _ in range(steps):
            take = rng.integers(0, len(chosen), min(batch, len(chosen)))
            w = chosen[take]
            u, inverse = np.unique(np.append(0, ids[w].ravel()), return_inverse=True)
            local = inverse[1:].reshape(len(w), SPAN)
            pieces = flat[ragged(at[u], sizes[u])]
            x = embedded(p, own[u], pieces, sizes[u])
            x[0] = 0
            logit, kept = forward(p, tables_of(p, x), local, mask[w], keep=True)
            d = ((sigmoid(logit) - target[take]) * weight[take] / len(take)).astype(np.float32)
            g, dx = backward(p, local, x, kept, d)
            g["words"] = summed(own[u], dx, BUCKETS)
            g["chars"] = summed(pieces, np.repeat(dx / np.maximum(sizes[u], 1)[:, None], sizes[u], axis=0), BUCKETS)
            tool.step(g)
        x = embedded_all(p, own, flat, sizes)
        score = window_logits(p, tables_of(p, x), ids, mask)

    # the shift: the cut with the fewest faults on the texts kept aside, nearer to label 1, of which fewer are rare
    held = np.flatnonzero(aside) if len(set(y[aside].tolist())) == 2 else fit
    most, _ = text_logits(p, tables_of(p, x), [docs[k] for k in held.tolist()])
    order = np.argsort(most)
    edges = np.concatenate([[most.min() - 1], (np.sort(most)[1:] + np.sort(most)[:-1]) / 2, [most.max() + 1]])
    missed = np.concatenate([[0], np.cumsum(y[held][order] == 1)])
    false = np.concatenate([[(y[held] == 0).sum()], (y[held] == 0).sum() - np.cumsum(y[held][order] == 0)])
    good = np.flatnonzero(missed + false == (missed + false).min())
    p["out0"] -= np.float32(0.25 * edges[good].min() + 0.75 * edges[good].max())
    return p
