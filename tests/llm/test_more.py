"""Cases beyond the first tests: repeated ids, long and broken inputs, decoding, gradients, held-out accuracy, SQL on the given tables."""

import random
import time
import zlib
from collections import Counter, defaultdict
from pathlib import Path

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from streamsample.llm import exact_dedup, gru, license_scan, line_dedup, media, near_dedup, packing, pii, piece_lattice, registry, tokens, toxicity

DOCS = "doc_id long, text string, digest string"


def pairs(df):
    return Counter((r["doc_id"], r["text"]) for r in df.collect())


def test_exact_copies_with_repeated_ids(spark):
    least = -(1 << 63)
    rows = [(0, "dup", "x"), (1, "unique", "x"), (1, "dup", "x"), (2, "same", "x"), (2, "same", "y"), (least, "low", "x"), (5, "low", "x"), (None, "dup", "x"), (None, "alone", "x"), (7, "a b", "x"), (7, "a  b", "x")]
    df = spark.createDataFrame(rows, DOCS)
    assert pairs(exact_dedup.drop_copies(df)) == Counter([(0, "dup"), (1, "unique"), (2, "same"), (least, "low"), (None, "alone"), (7, "a  b")])
    assert exact_dedup.drop_copies(df).columns == df.columns
    assert exact_dedup.drop_copies(df.limit(0)).count() == 0


@pytest.mark.parametrize("runs, fan", [(1, 4), (5, 2), (64, 4), (64, 8)])
def test_merged_runs_of_any_tree(spark, runs, fan):
    rng = random.Random(runs)
    rows = [(k, rng.choice(["hot", f"t{rng.randrange(40)}", f" t {rng.randrange(40)}"]), "x") for k in range(500)]
    groups = defaultdict(list)
    for i, t, _ in rows:
        groups[t.replace(" ", "")].append((-len(t), i))
    got = exact_dedup.exact_groups(spark.createDataFrame(rows, DOCS).repartition(7), runs=runs, fan=fan).collect()
    assert {(r["doc_id"], r["keep_id"], r["group_size"]) for r in got} == {(i, min(g)[1], len(g)) for g in groups.values() for _, i in g}


def test_lines_with_repeated_ids(spark):
    rows = [(k, "hot", "x") for k in range(20)] + [(50, "hot\nmine", "x"), (50, "own\nhot", "x"), (None, "hot\nleft", "x"), (51, "hot\nhot\nx", "x"), (51, "hot\nhot\nx", "x")]
    got = line_dedup.drop_lines(spark.createDataFrame(rows, DOCS)).collect()
    assert sorted((r["n_dropped"], r["kept_text"]) for r in got if r["doc_id"] not in range(20)) == [(1, "left"), (1, "mine"), (1, "own"), (2, "x"), (2, "x")]


def test_near_copies_with_repeated_ids(spark):
    rng = random.Random(9)
    words = [[f"w{rng.randrange(10**6)}" for _ in range(120)] for _ in range(4)]
    text = [" ".join(w) for w in words]
    near = [" ".join(w[:-1]) for w in words]
    rows = [(1, text[0], "x"), (1, text[1], "x"), (2, near[0], "x"), (3, near[1], "x"), (4, text[2], "x"), (4, text[2], "x"), (None, text[3], "x"), (5, near[3], "x"), (6, "", "x"), (6, None, "x")]
    got = near_dedup.near_groups(spark.createDataFrame(rows, DOCS)).collect()
    assert Counter((r["doc_id"], r["component_id"], r["kept"]) for r in got) == Counter(
        [(1, 1, True), (1, 1, True), (2, 1, False), (3, 1, False), (4, 4, True), (4, 4, True), (None, None, True), (5, 5, True), (6, 6, True), (6, 6, True)]
    )
    left = pairs(near_dedup.drop_near(spark.createDataFrame(rows, DOCS)))
    assert left[(1, text[0])] == left[(1, text[1])] == left[(4, text[2])] == left[(5, near[3])] == left[(None, text[3])] == 1
    assert sum(left.values()) == 6 and not {(2, near[0]), (3, near[1])} & set(left)


def test_near_blocks_are_bounded_in_rows(spark):
    """Many short texts that share all but their first word are linked with none, and block sizes don't depend on how short they are."""
    rows = [(k, f"a{k} b c d e f g h i", "x") for k in range(300)] + [(1000 + k, f"z{k} b c d e f g h i j k l m n o p q r s t u v w x y z", "x") for k in range(40)]
    got = {r["doc_id"]: r["component_id"] for r in near_dedup.near_groups(spark.createDataFrame(rows, DOCS)).collect()}
    assert all(got[k] == k for k in range(300)) and {got[1000 + k] for k in range(40)} == {1000}
    sets = spark.createDataFrame([(k, [1, 2, 3, 4, 5, 6, 7, 8, 9, 10 + k % 2]) for k in range(50)], "node long, shingles array<long>")
    rest = spark.createDataFrame([(0, k, k, 0) for k in range(50)], "hub long, node long, component long, most long")
    links = {(min(r), max(r)) for r in near_dedup._links_of_the_rest(rest, sets, 90, most_rows=7).collect()}
    assert links == {(a, b) for a in range(50) for b in range(a + 1, 50) if a % 2 == b % 2}


def test_long_numbers_and_blanks_are_no_trouble():
    assert pii.all_spans("0" * 5000 + ".1.1.1")[0] == [(0, 1, 5006)] and pii.all_spans("1" * 5000 + ".1.1.1") == ([], [])
    began = time.perf_counter()
    text = "x(at)" + " " * 1_000_000 + "example.com"
    assert pii.all_spans(text)[1] == [(0, 0, len(text))]
    base, every = pii.all_spans("a@b.co c (at) d.org " * 8000)
    assert (len(base), len(every)) == (8000, 16000)
    assert time.perf_counter() - began < 20


def test_broken_files_are_faults(spark):
    good = media.riff(bytes(range(64)), media.MU_LAW)
    short = b"RIFF\0\0\0\0WAVEfmt \4\0\0\0\1\0\1\0" + b"data\0\0\0\0"
    flat = media.riff(b"x" * 64, media.ADPCM, block=1)
    zero = flat.replace(b"\x01\x00\x04\x00", b"\x00\x00\x04\x00", 1)
    files = [good, None, b"", b"RIFF", short, flat, zero, media.riff(b"", media.A_LAW), media.riff(b"abc", media.PCM), media.riff(b"x" * 64, 99), media.riff(b"y" * 600, media.ADPCM, block=256, bits=4, per_block=505)]
    out, faults = media.pcm_files(files)
    assert [f is None for f in faults] == [True, False, False, False, False, False, False, True, True, False, True]
    assert all((o is None) == (f is not None) for o, f in zip(out, faults, strict=True))
    assert len(media.parts(out[0])[1]) == 4 * 64 and len(media.parts(out[7])[1]) == 0 and len(media.parts(out[8])[1]) == 4 and len(media.parts(out[10])[1]) == 2 * 4 * 505
    got = media.to_pcm(spark.createDataFrame([(k, bytearray(f) if f is not None else None) for k, f in enumerate(files)], "doc_id long, media binary")).collect()
    assert [r["pcm"] and bytes(r["pcm"]) for r in got] == out and [r["fault"] for r in got] == faults


def test_stored_sound_is_that_of_the_text(odd):
    rows = media.store_texts(odd).collect()
    for r, f in zip(rows, media.read_back(media.store_texts(odd)).collect(), strict=True):
        codes = np.frombuffer(media.parts(bytes(r["media"]))[1], dtype=np.uint8)
        pcm = media.MU[codes].astype(np.int64)
        want = np.empty(2 * len(pcm), dtype=np.int64)
        want[0::2], want[1:-1:2], want[-1] = pcm, (pcm[1:] + pcm[:-1]) >> 1, pcm[-1]
        (tag, rate, _), load = media.parts(bytes(r["pcm"]))
        assert (tag, rate) == (media.PCM, 16000) and np.array_equal(np.frombuffer(load, dtype="<i2"), want)
        assert f["feature"].endswith(f"pcm={len(want)}:{zlib.crc32(want.astype('<i2').tobytes()):08x}")
        assert f"mu_ms={int((pcm**2).sum()) // len(pcm)};" in f["feature"] and f"peak={abs(pcm).max()};" in f["feature"]


def test_any_ratio_of_rates():
    pcm, ends = np.array([0, 30, 60, 90, -3000, 3001, 7], dtype=np.int16), np.array([4, 4, 6, 7])
    for up, down in ((3, 2), (2, 1), (1, 2), (1, 1), (441, 320)):
        got, to = media.resample(pcm, ends, up, down)
        want = []
        for a, b in zip([0, 4, 4, 6], [4, 4, 6, 7], strict=True):
            x = pcm[a:b].astype(int).tolist()
            want += [x[k * down // up] + (x[min(k * down // up + 1, len(x) - 1)] - x[k * down // up]) * (k * down % up) // up for k in range(-(-len(x) * up // down))]
        assert got.tolist() == want and to[-1] == len(want)


def test_gradients_equal_finite_differences():
    rng = np.random.default_rng(3)
    p = {k: v.astype(np.float64) for k, v in gru.new_parameters(4).items()}
    x = rng.normal(size=(30, gru.DIMS))
    x[0] = 0
    ids = rng.integers(1, 30, (5, gru.SPAN))
    mask = np.ones((5, gru.SPAN), dtype=np.float32)
    mask[1, 7:] = mask[4, 1:] = 0
    ids[mask == 0] = 0
    target = rng.normal(size=5)

    def loss():
        tables = {d: x @ p[f"w{d}"] + p[f"c{d}"] for d in "fb"}
        return float(gru.forward(p, tables, ids, mask) @ target)

    tables = {d: x @ p[f"w{d}"] + p[f"c{d}"] for d in "fb"}
    _, kept = gru.forward(p, tables, ids, mask, keep=True)
    g, dx = gru.backward(p, ids, x, kept, target)
    for name, grad in [*g.items(), ("x", dx)]:
        where = x if name == "x" else p[name]
        for _ in range(6):
            at = tuple(rng.integers(1 if name == "x" and k == 0 else 0, n) for k, n in enumerate(where.shape))
            old, step = where[at], 1e-3
            where[at] = old + step
            up = loss()
            where[at] = old - step
            down = loss()
            where[at] = old
            assert abs((up - down) / (2 * step) - grad[at]) < 2e-3 * max(1, abs(grad[at])), (name, at)


def test_forward_equals_a_plain_loop():
    rng = np.random.default_rng(6)
    p = {k: v.astype(np.float64) for k, v in gru.new_parameters(8).items()}
    x = rng.normal(size=(12, gru.DIMS))
    n_words = [1, 5, gru.SPAN]
    ids, mask = np.zeros((3, gru.SPAN), dtype=int), np.zeros((3, gru.SPAN))
    for k, n in enumerate(n_words):
        ids[k, :n], mask[k, :n] = rng.integers(1, 12, n), 1
    got = gru.forward(p, {d: x @ p[f"w{d}"] + p[f"c{d}"] for d in "fb"}, ids, mask)
    sig = lambda v: 1 / (1 + np.exp(-v))
    s = gru.STATE
    for k, n in enumerate(n_words):
        states = {}
        for d, order in (("f", range(n)), ("b", range(n - 1, -1, -1))):
            h = np.zeros(s)
            for t in order:
                a, u = x[ids[k, t]] @ p[f"w{d}"] + p[f"c{d}"], p[f"u{d}"]
                z, r = sig(a[:s] + h @ u[:, :s]), sig(a[s : 2 * s] + h @ u[:, s : 2 * s])
                c = np.tanh(a[2 * s :] + (r * h) @ u[:, 2 * s :])
                h = z * h + (1 - z) * c
                states[d, t] = h
        both = np.array([np.concatenate([states["f", t], states["b", t]]) for t in range(n)])
        e = np.tanh(both @ p["look"] + p["look0"]) @ p["pick"]
        a = np.exp(e - e.max()) / np.exp(e - e.max()).sum()
        assert abs(float(a @ both @ p["out"] + p["out0"][0]) - got[k]) < 1e-4


def test_toxicity_on_the_given_tables(spark):
    base = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{base}/{t}.parquet") for t in ("documents", "labels"))
    rows = toxicity.score(docs, labels).join(labels.select("doc_id", "toxic"), "doc_id").where("held_out").collect()
    score, y = np.array([r["score"] for r in rows]), np.array([r["toxic"] for r in rows])
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in rows)
    if 0 < y.sum() < len(y):
        above = (score[y == 1][:, None] > score[y == 0][None, :]).mean() + 0.5 * (score[y == 1][:, None] == score[y == 0][None, :]).mean()
        assert above > 0.9, above


def test_decoding_is_a_join(spark, odd):
    path = tokens.vocabulary("piece_bpe_32k.model")
    voc = piece_lattice.opened(path)
    coded = piece_lattice.encode(odd, path)
    numbered = coded.withColumn("key", F.monotonically_increasing_id()).collect()
    again = spark.createDataFrame([(r["key"], r["ids"]) for r in numbered], "key long, ids array<int>")
    got = {r["key"]: r["text"] for r in piece_lattice.decode(again, path, "key").collect()}
    assert Counter((r["doc_id"], got[r["key"]]) for r in numbered) == Counter((r["doc_id"], r["text"] or "") for r in odd.collect())
    rng = random.Random(4)
    rows = [(k, [rng.randrange(voc.size) for _ in range(rng.randrange(9))]) for k in range(200)] + [(900, []), (901, None)]
    got = {r["key"]: r["text"] for r in piece_lattice.decode(spark.createDataFrame(rows, "key long, ids array<int>"), path, "key").collect()}
    assert got == {k: voc.decode(ids or []) for k, ids in rows}


def test_atoms_at_once_equal_atoms_of_words():
    voc, rng = piece_lattice.opened(tokens.vocabulary("piece_bpe_32k.model")), random.Random(3)
    bits = [" ", "  ", "a", "the", "ing", "é", "日", "\n", "▁", "\0", "x1", ".", "😀"]
    for _ in range(2000):
        texts = ["".join(rng.choice(bits) for _ in range(rng.randint(0, 12))) for _ in range(3)]
        one = piece_lattice.Parcel(voc)
        one.add([1, 2], texts[:2])
        one.add([3], texts[2:])
        names, sizes, numbers = one.distinct()
        names = names.to_pylist()
        assert sizes.tolist() == list(map(len, names))
        at = np.concatenate([[0], np.cumsum(np.concatenate(one.sizes))])
        assert [[names[n] for n in numbers[a:b]] for a, b in zip(at[:-1], at[1:], strict=True)] == [[x for w in voc.words(t) for x in voc.atoms(w)] for t in texts]
        assert len(set(names)) == len(names)


def test_long_runs_of_letters(spark):
    path, rng = tokens.vocabulary("piece_bpe_32k.model"), random.Random(6)
    voc = piece_lattice.opened(path)
    text = "".join(rng.choice("etaoinshrdlu") for _ in range(30_000))
    score, code = {t: s for t, _, s in voc.pieces}, {t: i for t, i, _ in voc.pieces}
    whole = "▁" + text
    top, back = [0.0] + [-1e300] * len(whole), [0] * (len(whole) + 1)
    for e in range(1, len(whole) + 1):
        for s in range(max(0, e - voc.longest), e):
            v = top[s] + score.get(whole[s:e], voc.unknown if e - s == 1 else -1e300)
            if v > top[e]:
                top[e], back[e] = v, s
    ids, e = [], len(whole)
    while e:
        ids.append(code[whole[back[e] : e]])
        e = back[e]
    row = piece_lattice.encode(spark.createDataFrame([(1, text)], "doc_id long, text string"), path).first()
    assert row["ids"] == ids[::-1] and row["round_trip"]


def test_step_groups_are_level(spark):
    rng = random.Random(2)
    rows = [(k, " ".join(rng.choice(["alpha", "beta", "the", "x"]) for _ in range(rng.choice([3, 50, 400, 1500])))) for k in range(400)]
    got = packing.pack(spark.createDataFrame(rows, "doc_id long, text string").repartition(6), tokens.vocabulary(), step_tokens=8192).collect()
    tier = {r["sequence_id"]: (r["tier"], r["step_group"]) for r in got}
    assert all(len({x["step_group"] for x in got if x["sequence_id"] == s}) == 1 for s in list(tier)[:20])
    tokens_of = defaultdict(int)
    kinds = defaultdict(set)
    for size, group in tier.values():
        tokens_of[group] += size
        kinds[group].add(size if size in packing.TIERS else 0)
    assert all(len(k) == 1 for k in kinds.values())
    by = defaultdict(list)
    for group, n in tokens_of.items():
        by[next(iter(kinds[group]))].append(n)
    for size, sums in by.items():
        assert max(sums) <= 8192 + max(size, packing.TIERS[0]) and len(sums) == -(-sum(sums) // 8192), (size, sums)
        assert max(sums) - min(sums) <= 2 * (size or packing.TIERS[0])


def test_rules_take_the_longest_match(spark):
    known = license_scan.SENTENCES
    said = lambda *keys: "\n".join(known[k] for k in keys)
    bsd = ("bsd-redistribution", "bsd-source", "bsd-binary")
    rows = {
        "BSD-3-Clause=1": said(*bsd, "bsd-endorse"),
        "BSD-2-Clause=1": said(*bsd),
        "BSD-4-Clause=1": said(*bsd, "bsd-advertising", "bsd-endorse"),
        "BSD-2-Clause=1,BSD-3-Clause=1": said(*bsd, "bsd-endorse", *bsd),
        "MIT=1": said("mit-title", "mit-grant", "mit-condition", "mit-as-is"),
        "GPL-2.0-or-later=1": said("gpl-program", "gpl-terms", "gpl-version-2"),
        "LGPL-2.1-or-later=1": said("lgpl-library", "lgpl-terms", "gpl-version-2.1"),
        "ISC=1": said("isc-grant", "isc-as-is"),
        "All-Rights-Reserved=1,BSD-2-Clause=1": said("bsd-redistribution", "reserved", "bsd-source", "bsd-binary"),
        "": said("bsd-redistribution", "mit-condition", "bsd-source", "bsd-binary"),
        "Apache-2.0=1,Zlib=1": "// SPDX-License-Identifier: Apache-2.0\n" + said("zlib-as-is", "zlib-altered"),
    }
    df = spark.createDataFrame([(k, t) for k, t in enumerate(rows.values())], "doc_id long, text string")
    got = {r["doc_id"]: ",".join(f"{m['licence']}={m['matches']}" for m in r["matches"]) for r in license_scan.scan(df).collect()}
    assert [got[k] for k in range(len(rows))] == list(rows)
    con = duckdb.connect()
    con.register("documents", df.toPandas())
    want = dict(con.execute(f"SELECT doc_id, licences FROM ({license_scan.oracle()})").fetchall())
    assert want == got


@pytest.mark.parametrize("name", ["op2_exact_dedup", "op6_line_dedup", "op7_license_scan"])
def test_queries_equal_their_sql(spark, sf, name):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{Path(sf) / 'documents.parquet'}'")
    want = con.execute(registry.oracle_sql()[name]).df()
    got = registry.queries()[name](spark, sf).toPandas()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns)
    assert Counter(map(tuple, want[cols].astype(str).values.tolist())) == Counter(map(tuple, got[cols].astype(str).values.tolist()))


def test_latin_pieces_equal_the_library(monkeypatch):
    rng, tool = random.Random(15), tokens.PieceEncoder(tokens.vocabulary())
    bits = ["a", "The", " ", "  ", "\n", ".", ",", "é", "'s", "'", "1", "23", "\t", "\r\n", "ª", "x\n", "<|endoftext|>", "!", "_", "ŉ", "²", "½", "ß", "'ll", "...", " '", "\xa0", "日", "x" * 600]
    made = ["".join(rng.choice(bits[: rng.choice([26, 26, 26, 29])]) for _ in range(rng.randint(0, 25))) for _ in range(6000)]
    want = [np.array(e.ids, "<u4").tobytes() for e in tool.tokenizer.encode_batch(made, add_special_tokens=False)]
    assert tool.encode(made) == want
    monkeypatch.setattr(tokens, "REMEMBERED", 50)
    assert [x for k in range(0, 600, 20) for x in tool.encode(made[k : k + 20])] == want[:600]
    assert tool.encode([]) == [] and tool.encode(["", " ", "\n"]) == [np.array(e.ids, "<u4").tobytes() for e in tool.tokenizer.encode_batch(["", " ", "\n"], add_special_tokens=False)]


def test_packed_sound_comes_back(spark):
    """Any PCM comes back byte by byte; of interpolated sound, what lies between packs to zeros; figures are those of plain files."""
    rng = np.random.default_rng(3)
    for n in (0, 1, 2, 3, 64, 1001):
        file = media.riff(rng.integers(-32768, 32768, n).astype("<i2").tobytes(), media.PCM, 16000, 2, 16)
        assert media.unpack(media.pack(file)) == file
    sound = media.pcm_files([media.riff(rng.bytes(640))])[0][0]
    assert media.pack(sound)[-1280:] == bytes(1280) and media.unpack(media.pack(sound)) == sound
    docs = spark.createDataFrame([(1, "some text " * 40), (2, ""), (3, None), (4, "\u00e9t\u00e9")], "doc_id long, text string")
    plain, packed = (sorted(map(tuple, media.read_back(media.store_texts(docs, packed=p), packed=p).collect())) for p in (False, True))
    assert plain == packed


def test_training_takes_little_of_the_driver(monkeypatch):
    """Windows and word inputs are worked out in blocks, equal to what one pass gives; after training the driver gives memory back."""
    import tracemalloc

    rng = np.random.default_rng(8)
    docs = [rng.integers(1, 9000, n) for n in (0, 1, 33, *rng.integers(400, 900, 2500).tolist())]
    tracemalloc.start()
    ids, mask, doc = gru.windows(docs)
    held, most = tracemalloc.get_traced_memory()
    tracemalloc.stop()
    assert len(ids) > 50_000 and most < 2 * held
    for k in (0, 1, 2, 300, len(docs) - 1):
        for row, inside, a in zip(ids[doc == k], mask[doc == k], gru.starts(len(docs[k])), strict=True):
            own = docs[k][a : a + gru.SPAN]
            assert row.tolist() == own.tolist() + [0] * (gru.SPAN - len(own)) and inside.sum() == len(own)
    words = ["", *(f"w{k}-{k * k}é" for k in range(500))]
    assert all((a == b).all() and a.dtype == b.dtype for a, b in zip(gru.word_inputs(words), gru.all_inputs(words, 7), strict=True))

    calls = []
    rows = [(k, "bad thing here" if k % 2 else "good thing there", k % 2, 1 + k % 4) for k in range(40)]
    monkeypatch.setattr(toxicity, "sample", lambda *a: rows)
    monkeypatch.setattr(toxicity, "train", lambda *a: calls.append("train"))
    monkeypatch.setattr(toxicity, "trim", lambda: calls.append("trim"))
    assert toxicity.fitted(None, None) is None and calls == ["train", "trim"]
