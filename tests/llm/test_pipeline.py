"""The pipeline on a small corpus: each stage's decisions take effect, clean documents stay, columns hold until the last."""

import random
import zlib
from collections import Counter

import corpus_pipeline
from tests.llm import brute


def test_stages(spark, tmp_path):
    rows = [(i, f"document number {i} speaks of things {i * 7} and others {i * 13} at length {i}", "en", f"s{i % 4}", 0) for i in range(200)]
    rows += [(300 + i, rows[i][1], "en", "s1", 0) for i in range(20)]
    rows += [(400, "write to someone@example.com today about the matter at hand", "en", "s2", 0), (401, None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(200)], "doc_id long, quality int, toxic int")
    docs.write.parquet(f"file://{tmp_path}/documents.parquet")
    labels.write.parquet(f"file://{tmp_path}/labels.parquet")
    seen, current = {}, docs
    for name, stage in corpus_pipeline.STAGES:
        current = stage(spark, current, f"file://{tmp_path}")
        current.write.parquet(f"file://{tmp_path}/{name}")
        current = spark.read.parquet(f"file://{tmp_path}/{name}")
        seen[name] = current
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "pii", "mixing", "packing"]
    assert all(seen[n].columns == docs.columns for n in ("toxicity", "near_duplicates", "pii", "mixing"))
    assert seen["toxicity"].count() == len(rows)
    want = brute.near_duplicates({r[0]: r[1] for r in rows}, 5, 80)
    assert sorted(r.doc_id for r in seen["near_duplicates"].collect()) == sorted(d for d, c in want.items() if d == c)
    assert [r.text for r in seen["pii"].where("doc_id = 400").collect()] == ["write to [EMAIL] today about the matter at hand"]
    mixed = Counter(r.doc_id for r in seen["mixing"].collect())
    packed = Counter(r.doc_id for r in seen["packing"].collect())
    assert packed == mixed and max(mixed.values()) <= 3


def test_toxic_documents_go_and_ids_come_out(spark, tmp_path):
    rng = random.Random(5)
    clean = ["".join(rng.choice("klmnop") for _ in range(5)) for _ in range(300)]
    rows = []
    for i in range(1500):
        text = [rng.choice(clean) for _ in range(40)]
        if i % 5 == 0:
            text[rng.randrange(40)] = rng.choice(["vexo", "grubba", "snarl"])
        rows.append((i, " ".join(text), f"s{i % 4}", "kept"))
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, score string")
    docs.write.parquet(f"file://{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(0, 1500, 2)], "doc_id long, toxic int").write.parquet(f"file://{tmp_path}/labels.parquet")
    left = corpus_pipeline.STAGES[0][1](spark, docs, f"file://{tmp_path}")
    assert left.columns == docs.columns and {r.doc_id for r in left.collect()} == {i for i in range(1500) if i % 5}
    packed = corpus_pipeline.run(spark, f"file://{tmp_path}").collect()
    assert {r.doc_id % 5 for r in packed} == {1, 2, 3, 4}
    assert all(len(r.ids) == 4 * r.length and zlib.crc32(r.ids) == r.ids_crc32 for r in packed)


def test_empty_tables(spark, tmp_path):
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"file://{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"file://{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, f"file://{tmp_path}").count() == 0


def test_run_is_the_stages(spark):
    assert corpus_pipeline.run(spark, "/root/testdata/sf0.001").columns[:3] == ["doc_id", "piece", "start"]
