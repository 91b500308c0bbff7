"""The stages in order, on a small corpus with planted cases."""

import numpy as np
import pytest

pipeline = pytest.importorskip("corpus_pipeline")


def test_stages(spark, tmp_path):
    rng = np.random.default_rng(8)
    words, junk = [f"w{i}" for i in range(200)], [f"X{i}###" for i in range(50)]
    rows = [(i, " ".join(rng.choice(words, 60)), "en", "a" if i < 150 else "b", 0) for i in range(200)]
    rows += [(1000 + i, " ".join(rng.choice(junk, 60)), "en", "a", 0) for i in range(100)]
    copies = [(2000 + i, rows[i][1], "en", "b", 0) for i in range(5)]
    near = [(3000 + i, rows[i][1] + " more", "en", "b", 0) for i in range(5, 10)]
    rows += copies + near + [(4000, rows[20][1], "en", "a", 0), (20, rows[20][1], "en", "a", 0)]
    sf = str(tmp_path / "sf")
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(rows, schema).write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(200)] + [(1000 + i, 0, 0) for i in range(100)], "doc_id long, quality int, toxic int").write.parquet(f"{sf}/labels.parquet")
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns
        out.write.parquet(f"{sf}/{name}")
        docs = spark.read.parquet(f"{sf}/{name}")
        ids = sorted(r.doc_id for r in docs.select("doc_id").collect())
        if name == "quality":
            assert set(range(200)) <= set(ids) and not any(1000 <= i < 1100 for i in ids)
        elif name == "near_duplicates":
            assert ids == list(range(200))
        else:
            assert set(ids) == set(range(200)) and max(map(ids.count, set(ids))) <= 2
    assert [n for n, _ in pipeline.STAGES] == ["quality", "near_duplicates", "mixing", "packing"]
    packed = pipeline.run(spark, sf)
    assert {r.doc_id for r in packed.select("doc_id").distinct().collect()} == set(range(200))


def test_other_texts_of_an_identifier_stay(spark):
    a, b = " ".join(f"a{i}" for i in range(40)), " ".join(f"b{i}" for i in range(40))
    docs = spark.createDataFrame([(3, b, 1), (5, a, 2), (5, b, 3), (None, b, 4), (6, None, 5), (6, None, 6)], "doc_id long, text string, _gone long")
    got = pipeline.near_duplicate_removal(spark, docs, "")
    assert got.columns == docs.columns
    rows = sorted((r.doc_id or 0, r.text or "") for r in got.collect())
    assert rows == [(0, b), (3, b), (5, a), (6, "")]


def test_empty_corpus(spark, tmp_path):
    sf = str(tmp_path / "sf")
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{sf}/labels.parquet")
    assert pipeline.run(spark, sf).count() == 0
