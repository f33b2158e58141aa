"""The pipeline's stages against brute force on a small corpus."""

import re

import numpy as np

import corpus_pipeline
from proxrec.llm import bpe


def test_pipeline(spark, tmp_path):
    rng = np.random.default_rng(8)
    word = lambda: "".join(rng.choice(list("abcdefgh"), 6))
    texts = [" ".join(word() for _ in range(60)) for _ in range(120)]
    for i in range(0, 60, 2):
        texts[i] += " vile slur vile"
    texts[71] = texts[70]
    texts[73] = texts[72] + " tail"
    item = " ".join(texts[80].split()[5:20])
    texts[91] += ' token = "0123456789abcdef0123456789abcdef01234567"'
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(i, 1, int(i < 60 and i % 2 == 0)) for i in range(120)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    gone = {*range(0, 60, 2), 71, 73, 80}
    rows = {r["doc_id"]: r for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert set(rows) == set(range(120)) - gone
    vocabulary = bpe.public_vocabulary()
    for i, r in rows.items():
        want = re.sub(r'token = "[0-9a-f]+', "[SECRET]", texts[i])
        assert b"".join(vocabulary.decoder[x] for x in r["ids"]).decode() == want and r["n_tokens"] == len(r["ids"])
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, str(tmp_path)).columns == docs.columns
        assert stage(spark, docs.where("false"), str(tmp_path)).count() == 0


def test_near_copies_between_80_and_85_percent_go(spark, tmp_path):
    """Scattered word edits in 200 words: each takes 5 of 196 shingles, so 4 leave 176/216 = 0.815 and 5 leave 171/221 = 0.774."""
    texts = []
    for k in range(12):
        words = [f"w{k}_{i}" for i in range(200)]
        texts.append((2 * k, " ".join(words)))
        for i in range(20, 20 + 30 * (4 if k < 8 else 5), 30):
            words[i] = f"x{k}_{i}"
        texts.append((2 * k + 1, " ".join(words)))
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in texts], "doc_id long, text string, lang string, source string, n_chars long")
    left = {r["doc_id"] for r in corpus_pipeline.drop_near_duplicates(spark, docs, str(tmp_path)).collect()}
    assert left == set(range(24)) - {2 * k + 1 for k in range(8)}


def test_pipeline_on_odd_rows(spark, tmp_path):
    """Null, empty and very long texts, repeated rows, a null id, and columns that the stages' results are named like."""
    rng = np.random.default_rng(9)
    long = " ".join("".join(rng.choice(list("abcdefgh"), 6)) for _ in range(40_000))
    texts = [(1, None), (2, ""), (3, long), (4, "one two three four five six"), (4, "one two three four five six"), (5, "a b c d e f g"), (None, "p q r s t u v"), (6, long + " end")]
    extra = {"secrets": "string", "n_hit": "int", "toxic": "string", "P_toxic": "double", "kept": "boolean", "component_id": "long", "decoded": "string", "hit_items": "string"}
    rows = [(i, t, "en", "s", "own", 7, "t", 0.5, False, 99, "d", "h") for i, t in texts]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, " + ", ".join(f"{k} {v}" for k, v in extra.items())).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(None, None), (1, "")], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    done = corpus_pipeline.run(spark, str(tmp_path))
    got = done.collect()
    assert sorted((r["doc_id"] if r["doc_id"] is not None else -1) for r in got) == [-1, 1, 2, 3, 4, 4, 5]
    assert all((r["secrets"], r["n_hit"], r["toxic"], r["P_toxic"], r["kept"], r["component_id"], r["decoded"], r["hit_items"]) == ("own", 7, "t", 0.5, False, 99, "d", "h") for r in got)
    assert "n_chars" not in done.columns and {r["doc_id"]: r["n_tokens"] for r in got}[1] == 0
