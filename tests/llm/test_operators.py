"""Each operator against a brute-force version, and on odd rows."""

import hashlib
import random
import re
import textwrap
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from streamsample.llm import components, exact_dedup, gru, license_scan, line_dedup, media, near_dedup, packing, pii, piece_lattice, token_store, tokens, toxicity
from streamsample.llm.shared import Workspace

WHITE = re.compile(r"[\x20\x09-\x0D]")


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").limit(200).persist()


def texts(df):
    return [(r["doc_id"], r["text"] or "") for r in df.select("doc_id", "text").collect()]


def test_exact_groups(odd, none):
    rows = texts(odd)
    groups = defaultdict(list)
    for i, t in rows:
        groups[WHITE.sub("", t)].append((-len(t), float("inf") if i is None else i, i))
    want = sorted((i is None, i or 0, min(groups[k := WHITE.sub("", t)])[2], len(groups[k]), hashlib.sha256(k.encode()).hexdigest()) for i, t in rows)
    got = exact_dedup.exact_groups(odd, runs=8, fan=2).collect()
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0, r["keep_id"], r["group_size"], r["text_sha256"]) for r in got) == want
    assert all(r["kept"] == (r["doc_id"] == r["keep_id"]) for r in got)
    assert exact_dedup.exact_groups(none).count() == 0
    assert exact_dedup.drop_copies(odd).columns == odd.columns


def test_lines(spark, odd, none):
    rows = [(k, f"Shared line\n own {k}\n\n  shared LINE ") for k in range(12)] + [(20, None), (21, ""), (22, "Shared line")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r for r in line_dedup.drop_lines(df, batches=4).collect()}
    seen = Counter(k for _, t in rows for k in {x.strip(" \t\n\v\f\r").lower() for x in (t or "").split("\n")} if k)
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if seen[x.strip().lower()] < 10]
        assert (got[i]["n_lines"], got[i]["n_dropped"], got[i]["kept_text"]) == (len(lines), len(lines) - len(kept), "\n".join(kept))
    assert line_dedup.drop_lines(odd).count() == odd.count() and line_dedup.drop_lines(none).count() == 0


def test_line_keys_lower_ascii_only(spark):
    rows = [(k, "ÉTÉ Grand" if k % 2 else "ÉTé GRAND") for k in range(10)]
    got = line_dedup.drop_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert all(r["n_dropped"] == 0 for r in got)  # É and é stay apart: two keys of five documents each
    same = line_dedup.drop_lines(spark.createDataFrame([(k, "ÉTé Grand" if k % 2 else "Été GRAND") for k in range(10)], "doc_id long, text string")).collect()
    assert all(r["n_dropped"] == 1 for r in same)


def test_licences(spark, odd, none):
    bsd = license_scan.SENTENCES
    rows = [
        (1, "text. Licensed under the Apache License, Version 2.0.\nmore"),
        (2, "\n".join(bsd[k] for k in ("bsd-redistribution", "bsd-source", "reserved", "bsd-binary"))),
        (3, "\n".join(bsd[k] for k in ("bsd-source", "bsd-redistribution", "bsd-binary"))),
        (4, "ALL  rights, reserved! All rights reserved."),
        (5, None),
    ]
    got = {r["doc_id"]: {m["licence"]: m["matches"] for m in r["matches"]} for r in license_scan.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: {"Apache-2.0": 1}, 2: {"All-Rights-Reserved": 1, "BSD-2-Clause": 1}, 3: {}, 4: {"All-Rights-Reserved": 2}, 5: {}}
    assert license_scan.scan(none).count() == 0 and license_scan.scan(odd).count() >= odd.count()


def test_wrapped_licences(spark):
    known = license_scan.SENTENCES

    def wrapped(keys, width, mark="", bullets=False):
        parts = [textwrap.fill(("* " if bullets and k != keys[0] else "") + known[k], width) for k in keys]
        return "\n".join(mark + x for x in "\n".join(parts).split("\n"))

    bsd = ("bsd-redistribution", "bsd-source", "bsd-binary", "bsd-endorse")
    texts_of = {
        "MIT": lambda w, m: "The MIT License (MIT)\n\nCopyright\n\n" + wrapped(("mit-condition", "mit-as-is"), w, m),
        "GPL-3.0-or-later": lambda w, m: wrapped(("gpl-free", "gpl-hope"), w, m) + " without even",
        "BSD-3-Clause": lambda w, m: wrapped(bsd, w, m, True),
        "BSD-2-Clause": lambda w, m: wrapped(bsd[:3], w, m, True),
        "MPL-2.0": lambda w, m: wrapped(("mpl-notice",), w, m) + " 2.0.",
        "Apache-2.0": lambda w, m: wrapped(("apache-notice-long", "apache-use"), w, m),
    }
    rows = [(name, f"Intro\n\n{make(w, m)}\n\nend", w, m) for name, make in texts_of.items() for w in (30, 72, 80, 1000) for m in ("", " * ", "# ", "// ", ";; ", "! ")]
    df = spark.createDataFrame([(k, r[1]) for k, r in enumerate(rows)], "doc_id long, text string")
    for r in license_scan.scan(df).collect():
        name, text, *how = rows[r["doc_id"]]
        got = {m["licence"]: m["matches"] for m in r["matches"]}
        assert got.pop(name, 0) == 1, (name, how, text, r)
        assert set(got) <= {"BSD-2-Clause"}, (name, how, got)


def test_companding_and_adpcm():
    assert media.MU[0xFF] == 0 and media.MU[0] == -32124 and media.MU[0x80] == 32124
    assert media.A[0xD5] == 8 and media.A[0x55] == -8 and int(media.A.max()) == 32256
    t = np.arange(505)
    wave = (8000 * np.sin(t / 9)).astype(np.int16)[None, :].repeat(3, axis=0)
    back = media.decode_adpcm(media.encode_adpcm(wave, 256))
    assert back.shape == wave.shape and np.sqrt(((back.astype(float) - wave) ** 2).mean()) < 600
    tag, load = media.parts(media.riff(b"abc", media.MU_LAW))
    assert tag[0] == media.MU_LAW and bytes(load) == b"abc"
    with pytest.raises(ValueError):
        media.parts(b"RIFFxxxx")


def test_media_payloads(odd, none):
    files = media.store_texts(odd)
    for r, (i, t) in zip(media.read_back(files).collect(), texts(odd), strict=True):
        raw = t.encode()
        load = raw + b"\0" * (max(64, -(-len(raw) // 64) * 64) - len(raw))
        assert (r["doc_id"], r["n_bytes"], r["payload_bytes"]) == (i, len(raw), len(load))
        assert r["payload_sha256"] == hashlib.sha256(load).hexdigest() and r["tail_crc32"] == zlib.crc32(load[-64:])
    assert all(r["fault"] is None and r["pcm"][:4] == b"RIFF" for r in media.to_pcm(files).collect())
    assert media.read_back(media.store_texts(none)).count() == 0


def test_toxicity(spark, odd, none):
    rng = random.Random(1)
    words = [f"word{k}" for k in range(300)]
    rows, labels = [], []
    for k in range(400):
        body = rng.choices(words, k=rng.randint(5, 120))
        bad = k % 4 == 0
        if bad:
            body[rng.randrange(len(body))] = rng.choice(["nastyone", "nastytwo", "nastythree"])
        rows.append((k, " ".join(body)))
        labels.append((k, int(bad)))
    df, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    got = {r["doc_id"]: r for r in toxicity.score(df, marks).collect()}
    held = [k for k, _ in rows if zlib.crc32(str(k).encode()) % 5 == 0]
    assert all(got[k]["held_out"] == (k in held) for k, _ in rows)
    assert sum(got[k]["predicted"] == dict(labels)[k] for k in held) / len(held) > 0.95
    kept = toxicity.drop_toxic(df, marks)
    assert kept.columns == df.columns and 250 < kept.count() < 350
    assert all(r["score"] == 0 for r in toxicity.score(odd, marks.limit(0)).collect())
    assert toxicity.score(none, marks).count() == 0


def test_texts_without_blanks_are_read_whole():
    for w in ("x" * 63, "".join(chr(0x4E00 + k) for k in range(10_000)), "-" * 200, "a_b/" * 100, "é😀" * 90):
        parts = gru.sub_words(w)
        assert len(parts) > 1 and set("".join(parts)) == set(w) and sum(map(len, parts)) >= len(w)
        assert all(len(p.encode()) <= gru.WHOLE and p in w for p in parts) and w.startswith(parts[0]) and w.endswith(parts[-1])
    assert gru.sub_words("x" * 62) == ["x" * 62]

    rng, latin, han = random.Random(2), [f"word{k}" for k in range(300)], [chr(0x4E00 + k) for k in range(300)]
    for words, bad_ones, blank, joints in (
        (latin, ["nastyone", "nastytwo", "nastythree"], " ", ("_", "/", "-", "\u200b")),
        (han, ["毒害品", "恶骂语"], "", ("",)),
    ):
        rows = [(rng.choices(words, k=rng.randint(5, 120)), k % 4 == 0) for k in range(1000)]
        for body, bad in rows:
            if bad:
                body[rng.randrange(len(body))] = rng.choice(bad_ones)
        p = gru.train([blank.join(b) for b, _ in rows], [int(bad) for _, bad in rows], [k % 5 == 1 for k in range(1000)])
        for joint in joints:
            clean = [rng.choices(words, k=400) for _ in range(20)]
            dirty = [[*c[:300], bad_ones[0], *c[300:]] for c in clean]
            tool = toxicity.Scorer(p)
            (a, n), (b, _) = (tool.logits([joint.join(x) for x in some]) for some in (clean, dirty))
            assert n.min() > 10 and (b > a).all() and (b > 0).mean() > 0.8 and (a < 0).mean() > 0.8, (joint, a, b)


def test_token_store(odd, none, docs):
    tool = tokens.encoder(tokens.vocabulary()).tokenizer
    for df in (odd.where("doc_id IS NOT NULL").dropDuplicates(["doc_id"]), docs):
        store = token_store.write_store(df, tokens.vocabulary())
        got, at = {r["doc_id"]: r for r in token_store.read_store(store).collect()}, 0
        for i, t in sorted(texts(df)):
            ids = [*tool.encode(t, add_special_tokens=False).ids, 0]
            assert (got[i]["start"], got[i]["n_tokens"], got[i]["ids_crc32"]) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
            at += len(ids)
        assert token_store.verify(store)
        names = [bytes(r["hash"]) for r in store["chunks"].collect()]
        assert len(names) == len(set(names))
    assert token_store.read_store(token_store.write_store(none, tokens.vocabulary())).count() == 0


def test_changed_recipes_and_manifests_are_errors(spark):
    rng = random.Random(8)
    rows = [(k, " ".join(f"{rng.randrange(10**6)}" for _ in range(1500))) for k in range(3)]
    store = token_store.write_store(spark.createDataFrame(rows, "doc_id long, text string"), tokens.vocabulary())
    assert token_store.verify(store) and token_store.read_store(store).count() == 3
    recipes, nodes = store["recipes"], store["manifest"]
    assert recipes.selectExpr("min(size(hashes))").first()[0] > 1
    swapped = recipes.withColumn("hashes", F.reverse("hashes")).withColumn("lengths", F.reverse("lengths"))
    other_leaf = swapped.withColumn("leaf", F.unhex(F.lit("00" * 16)))
    top = nodes.selectExpr("max(level)").first()[0]
    for bad in (
        store | {"recipes": swapped},
        store | {"recipes": other_leaf},
        store | {"recipes": recipes.where("doc_id <> 1")},
        store | {"manifest": nodes.withColumn("node", F.when(F.col("level") == top, "0").otherwise(F.col("node")))},
        store | {"manifest": nodes.where(F.col("level") < top)},
    ):
        assert not token_store.verify(bad)
        with pytest.raises(Exception, match="does not match its leaf|is not that of the recipes"):
            token_store.read_store(bad).collect()


def test_crc_of_joined_parts():
    parts = [b"abc", b"", b"x" * 1000, b"\0" * 77]
    whole, after, total = b"".join(parts), 0, 0
    for p in reversed(parts):
        total ^= int(token_store.crc_before(np.array([zlib.crc32(p)]), np.array([after]))[0])
        after += len(p)
    assert total == zlib.crc32(whole)


def test_piecewise_tokens_equal_the_library():
    rng, tool = random.Random(5), tokens.encoder(tokens.vocabulary())
    bits = ["a", "The", " ", "  ", "\n", ".", ",", "é", "'s", "1", "23", "日本", "\t", "\r\n", "ǅ", "ª", " ", "x\n", "<|endoftext|>", "!", "_", "ŉ"]
    made = ["".join(rng.choice(bits) for _ in range(rng.randint(0, 25))) for _ in range(3000)]
    want = [np.array(e.ids, "<u4").tobytes() for e in tool.tokenizer.encode_batch(made, add_special_tokens=False)]
    assert tool.encode(made) == want


def test_packing(odd, none, docs):
    tool = tokens.encoder(tokens.vocabulary()).tokenizer
    rows = packing.pack(docs, tokens.vocabulary()).collect()
    by, sequences = defaultdict(list), defaultdict(list)
    for r in rows:
        by[r["doc_id"]].append(r)
        sequences[r["sequence_id"]].append(r)
    for i, t in texts(docs):
        ids, at = [*tool.encode(t, add_special_tokens=False).ids, 1], 0
        for r in sorted(by[i], key=lambda r: r["start"]):
            assert r["start"] == at and r["doc_tokens"] == len(ids)
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[at : at + r["length"]], "<u4").tobytes())
            at += r["length"]
        assert at == len(ids)
    for s in sequences.values():
        at = 0
        for r in sorted(s, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048 and at & (at - 1) == 0
    assert sum(r["length"] for r in packing.pack(odd, tokens.vocabulary()).collect()) > 0 and packing.pack(none, tokens.vocabulary()).count() == 0


def plain(t):
    out = [(m.start(), 0, m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[ -]", "", m.group())
        total = sum(int(c) if k % 2 == 0 else sum(map(int, str(2 * int(c)))) for k, c in enumerate(d[::-1]))
        if 12 <= len(d) <= 19 and total % 10 == 0:
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m.group())) <= 15]
    return sorted(out)


def test_plain_spans_equal_the_patterns():
    rng = random.Random(2)
    for _ in range(20000):
        t = "".join(rng.choice("a1.@+- 4(2)é") for _ in range(rng.randint(0, 40)))
        assert pii.plain_spans(t) == plain(t), t


@pytest.mark.parametrize(
    "text, found",
    [
        ("write to john dot smith at mail dot example dot com now", "john dot smith at mail dot example dot com"),
        ("a.b (at) c [dot] org", "a.b (at) c [dot] org"),
        ("jоhn@exаmple.com x", "jоhn@exаmple.com"),
        ("call plus four one five five five five one two three four now", "plus four one five five five five one two three four"),
        ("four one one one 1111 one one one one 1111", "four one one one 1111 one one one one 1111"),
        ("host one nine two dot one six eight dot one dot two up", "one nine two dot one six eight dot one dot two"),
        ("４１１１ 1111 1111 1111", "４１１１ 1111 1111 1111"),
        ("jo​hn@example.com", "jo​hn@example.com"),
    ],
)
def test_disguises_map_back(text, found):
    base, every = pii.all_spans(text)
    added = [text[a:b] for a, k, b in every if (a, k, b) not in base]
    assert added == [found] and base == plain(text)


@pytest.mark.parametrize(
    "text, found",
    [
        ("host 192 dot 168 dot 1 dot 20 up", "192 dot 168 dot 1 dot 20"),
        ("host 192 dot 168 dot one dot 20 up", "192 dot 168 dot one dot 20"),
        ("call +1 415 555 01 two three now", "+1 415 555 01 two three"),
        ("write to john at example.com now", "john at example.com"),
        ("from a dot b dot c dot d dot e dot f at example dot com on", "a dot b dot c dot d dot e dot f at example dot com"),
        ("to user@example { dot } com now", "user@example { dot } com"),
        ("to user@example < dot > com now", "user@example < dot > com"),
        ("to user@example ( . ) com now", "user@example ( . ) com"),
        ("to user {  at  } example.com now", "user {  at  } example.com"),
        ("to user [\tat ] example (  dot ) com now", "user [\tat ] example (  dot ) com"),
        ("host 10(dot)0(dot)zero(dot)one up", "10(dot)0(dot)zero(dot)one"),
    ],
)
def test_disguises_with_few_signs(text, found):
    base, every = pii.all_spans(text)
    assert [text[a:b] for a, k, b in every if (a, k, b) not in base] == [found]


def test_spoken_at_before_a_number_stays():
    for t in ("sold at 3.50 each", "at 10.30 or at 11.45", "dot " * 5000, "a dot " * 5000 + "at"):
        assert pii.all_spans(t) == ([], [])


def test_clean_texts_stay(odd, none):
    for t in ("the thing at the. Foo dot bar", "look at that dot", "un deux trois", "one or two at a time. Three"):
        assert pii.all_spans(t) == ([], [])
    assert pii.find(odd).count() == odd.count() and pii.find(none).count() == 0
    assert pii.redact(odd).columns == odd.columns


def brute_components(rows, percent, width=5):
    lower = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = {}
    for i, t in rows:
        w = [x for x in WHITE.split(t.translate(lower)) if x]
        sets[i] = frozenset() if not w else frozenset([tuple(w)]) if len(w) < width else frozenset(tuple(w[k : k + width]) for k in range(len(w) - width + 1))
    comp = {i: i for i in sets}
    ids = sorted(sets)
    for x in ids:
        for y in ids:
            both = len(sets[x] & sets[y])
            if x < y and both and 100 * both >= percent * (len(sets[x]) + len(sets[y]) - both):
                a, b = comp[x], comp[y]
                comp = {i: min(a, b) if c in (a, b) else c for i, c in comp.items()}
    return {i: (len(sets[i]), comp[i]) for i in ids}


def test_near_groups(spark, odd, none):
    rng, rows = random.Random(3), []
    for g in range(12):
        base = [f"t{rng.randrange(500)}" for _ in range(rng.randint(60, 200))]
        for _ in range(12):
            words = base[:]
            for _ in range(rng.randint(0, 4)):
                words[rng.randrange(len(words))] = f"u{rng.randrange(500)}"
            rows.append((len(rows), " ".join(words)))
    rows += [(900, ""), (901, None), (902, "Two words"), (903, "two WORDS"), (904, "a b c d")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r for r in near_dedup.near_groups(df).collect()}
    want = brute_components([(i, t or "") for i, t in rows], 85)
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == want
    assert all(r["kept"] == (i == r["component_id"]) for i, r in got.items())
    assert near_dedup.near_groups(odd).count() == odd.count() and near_dedup.near_groups(none).count() == 0


def test_components(spark):
    chain = [(k, k + 1) for k in range(40)] + [(100, 102), (101, 102), (7, 7), (None, 3)]
    got = components.components(spark.createDataFrame(chain, "a long, b long"), Workspace(spark, "t"), "c").collect()
    assert {r["node"]: r["component"] for r in got} == {**dict.fromkeys(range(41), 0), 100: 100, 101: 100, 102: 100}


def test_pieces(spark, odd, none, docs):
    path = tokens.vocabulary("piece_bpe_32k.model")
    voc = piece_lattice.opened(path)
    score, code = {t: s for t, _, s in voc.pieces}, {t: i for t, i, _ in voc.pieces}

    def best(w):
        top, back = [0.0] + [-1e300] * len(w), [0] * (len(w) + 1)
        for e in range(1, len(w) + 1):
            for s in range(max(0, e - voc.longest), e):
                v = top[s] + score.get(w[s:e], voc.unknown if e - s == 1 else -1e300)
                if v > top[e]:
                    top[e], back[e] = v, s
        out, e = [], len(w)
        while e:
            out = [*voc.ids_of(code.get(w[back[e] : e], voc.size + ord(w[back[e]]))), *out]
            e = back[e]
        return out

    for df in (odd, docs.limit(40)):
        got = piece_lattice.encode(df, path).collect()
        want = Counter()
        for i, t in texts(df):
            ids = [x for w in voc.words(t) for x in best(w)]
            assert voc.decode(ids) == t
            want[(i, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))] += 1
        assert Counter((r["doc_id"], r["n_pieces"], r["ids_crc32"]) for r in got) == want and all(r["round_trip"] for r in got)
    assert piece_lattice.encode(none, path).count() == 0
