"""Queries that made their data up before work on the given tables: same rows as their SQL, also on odd rows."""

import collections

import duckdb
import numpy as np
import pytest

NAMES = ["fill_stripes", "footprint_cover", "footprint_except", "footprint_intersect", "footprint_union", "hilbert_neighbours", "index_choice", "params_map", "sql_box_dist2", "sql_z_decode", "sql_z_encode", "sql_z_less"]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    at = tmp_path_factory.mktemp("given")
    rng = np.random.default_rng(2)
    rows = [(i * 10, [float(x) for x in v]) for i, v in enumerate([np.full(64, -1.0), np.full(64, 1.0), *rng.uniform(-1, 1, (58, 64))])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(3).write.parquet(f"{at}/embeddings.parquet")
    items = [(float(q), 10.25 * q, 0.01 * (q % 11), 0.02) for q in range(1, 51)]
    spark.createDataFrame(items, "l_quantity double, l_extendedprice double, l_discount double, l_tax double").write.parquet(f"{at}/lineitem.parquet")
    return at


@pytest.mark.parametrize("name", NAMES)
def test_same_rows_as_sql(spark, folder, name):
    from patchspace.plans import load

    plans, sql = load()
    db = duckdb.connect()
    for t in ("embeddings", "lineitem"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{folder}/{t}.parquet/*.parquet')")
    want = db.execute(sql[name])
    columns = [c[0] for c in want.description]
    found = plans[name](spark, str(folder))
    assert any("embeddings.parquet" in f or "lineitem.parquet" in f for f in found.inputFiles())  # a table is read
    assert collections.Counter(map(tuple, found.select(*columns).collect())) == collections.Counter(want.fetchall())


def test_the_union_takes_every_patch(spark, folder):
    """Not only the patches of the stated queries, in code and SQL; each of their 64 samples is under a footprint."""
    from patchspace.plans import load

    plans, sql = load()
    ids = sorted(r.vec_id for r in spark.read.parquet(f"{folder}/embeddings.parquet").select("vec_id").collect())
    assert any(i % 20 for i in ids)
    db = duckdb.connect()
    db.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{folder}/embeddings.parquet/*.parquet')")
    want = sorted((i, pos) for i in ids for pos in range(64))
    assert sorted(plans["footprint_union"](spark, str(folder)).select("patch_id", "pos").toLocalIterator()) == want
    assert sorted(db.execute(f"SELECT patch_id, pos FROM ({sql['footprint_union']})").fetchall()) == want
