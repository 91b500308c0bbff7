"""The registry, and that the rest works without the training-data operators."""

import os
import random
import shutil
import subprocess
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parent.parent


def test_sql_twins_belong_to_queries():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries()) and len(e.queries()) > 100


@pytest.mark.parametrize("pipeline_stays", [True, False])
def test_imports_without_the_llm_parts(tmp_path, pipeline_stays):
    """The whole tree less both folders, with nothing of this tree on the path."""
    gone = shutil.ignore_patterns("llm", "__pycache__", ".git", *([] if pipeline_stays else ["corpus_pipeline.py"]))
    tree = tmp_path / "tree"
    shutil.copytree(ROOT, tree, ignore=gone)
    code = "import __spark_entry__ as e; q = e.queries(); assert q and not any(n.startswith('op') or n == 'pipeline' for n in q); assert set(e.oracle_sql()) <= set(q); import bench"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    subprocess.run([sys.executable, "-c", code], cwd=tree, env=env, check=True, timeout=120)
    # and with the other tree still on the path, as a driver may have it
    subprocess.run([sys.executable, "-c", code], cwd=tree, env=env | {"PYTHONPATH": f"{tree}:{ROOT}"}, check=True, timeout=120)


def test_entry_runs(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 25


def test_corpus_fill_takes_every_document(spark, tmp_path):
    from patchspace.plans import load

    rng = random.Random(3)
    rows = [(i, "".join(rng.choice("abcdef ") for _ in range(n))) for i, n in ((1, 1100), (20, 2048), (33, 1500))]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.image_id for r in load()[0]["corpus_fill"](spark, str(tmp_path)).collect()}
    assert got == {1, 20, 33}


def test_corpus_fill_keeps_an_image_in_a_row(spark, tmp_path):
    """The figures of images as rows of cells, without a join or a row a cell; a text too short for a hole has none."""
    from patchspace.operators import fill, metrics
    from patchspace.plans import load
    from patchspace.sources import masks, rasters

    rng = random.Random(4)
    rows = [(i, "".join(rng.choice("abc \u00e9\u4e2d\U0001f600") for _ in range(n))) for i, n in ((1, 700), (2, 1041), (3, 40), (5, 320))]
    spark.createDataFrame([*rows, (7, ""), (8, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    r = rasters.document_corpus(spark, str(tmp_path))
    m = masks.hole_mask(r, 8)
    want = metrics.fill_quality(fill.inpaint(masks.damage(r, m), "zcurve", k=7, order="onion"), r, m)
    got = load()[0]["corpus_fill"](spark, str(tmp_path))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Generate" not in plan and got.columns == want.columns
    assert {tuple(x) for x in got.collect()} == {tuple(x) for x in want.collect()} and got.count() >= 2
