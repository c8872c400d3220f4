"""The pipeline's stages against what they promise, on a small table with planted cases."""

import random

import corpus_pipeline
from streamsample.llm import pii


def test_stages(spark, tmp_path):
    rng, rows, labels = random.Random(4), [], []
    for k in range(300):
        body = [f"word{rng.randrange(900)}" for _ in range(rng.randint(20, 80))]
        if k % 4 == 0:
            body[3] = rng.choice(["nastyone", "nastytwo"])
        rows.append((k, " ".join(body), "en", "s", 0))
        labels.append((k, 1, int(k % 4 == 0)))
    clean = [r for r in rows if r[0] % 4]
    near = max(clean, key=lambda r: len(r[1]))
    words = near[1].split()
    rows += [(1000, clean[1][1].replace(" ", "  "), "en", "s", 0), (1001, " ".join(words[:-1]), "en", "s", 0), (1002, "mail jo@example.com and four words more here", "en", "s", 0), (1003, None, None, None, None)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs, kept = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before, docs = docs, stage(spark, docs, str(tmp_path))
        docs.write.parquet(f"{tmp_path}/{name}")
        docs = spark.read.parquet(f"{tmp_path}/{name}")
        if name != "packing":
            assert docs.columns == columns
            kept[name] = {r["doc_id"]: r["text"] for r in docs.collect()}
            assert set(kept[name]) <= {r["doc_id"] for r in before.collect()}
    toxic = {k for k, _, y in labels if y}
    assert len(toxic & set(kept["toxicity"])) <= 3 and len({r[0] for r in clean} - set(kept["toxicity"])) <= 3
    assert len({clean[1][0], 1000} & set(kept["exact_dedup"])) == 1
    left = set(kept["near_dedup"])
    assert len({near[0], 1001} & left) == 1
    assert kept["pii"][1002] == "mail [EMAIL] and four words more here"
    assert all(not pii.all_spans(t or "")[0] for t in kept["pii"].values())
    assert {r["doc_id"] for r in docs.collect()} == set(kept["pii"])
