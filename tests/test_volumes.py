"""Volumes cut into boxes give the cubes, sums and answers of the whole volume."""

import numpy as np
import pytest

from patchspace.operators import kernels, volumes
from patchspace.plans import experiments
from patchspace.sources import rasters


def test_boxes_hold_every_cube_once(spark, monkeypatch):
    monkeypatch.setattr(volumes, "CUBES", 7)
    rng = np.random.default_rng(4)
    vol = rng.integers(0, 256, (5, 6, 4)).astype(np.int16)
    vol[:, 2:] = 0  # boxes without a cell
    b = volumes.Boxes(vol.shape, 3)
    p, centres = kernels.cubes(vol, np.ones(vol.shape, bool), 3)
    cells = spark.createDataFrame([(int(z), int(y), int(x), int(vol[z, y, x])) for z, y, x in np.argwhere(vol)], "z int, y int, x int, v smallint")
    boxes = volumes.boxed(cells, b, np.array([0, 11, 23])).cache()
    assert b.n > 3 and boxes.count() == b.n and b.cubes == len(p) == 24
    parts = [b.cut(r.box, np.frombuffer(r.samples, np.int16)) for r in boxes.select("box", "samples").collect()]
    order = np.argsort(np.concatenate([n for _, _, n in parts]))
    assert (np.concatenate([x for x, _, _ in parts])[order] == p).all() and (np.concatenate([c for _, c, _ in parts])[order] == centres).all()
    n, s, prod = volumes.fit_sums(boxes)
    x = p.astype(np.int64)
    assert n == 24 and (s == x.sum(0)).all() and (prod == x.T @ x).all()
    asked = volumes.asked_of(boxes, 3)
    assert sorted(asked) == [0, 11, 23] and all((v == p[i]).all() for i, v in asked.items())
    assert (b.centres(np.array([0, 11, 23])) == centres[[0, 11, 23]]).all()


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    at, rng = tmp_path_factory.mktemp("volumes"), np.random.default_rng(7)
    events = [(int(u), f"2024-01-{d:02d} {h:02d}:30:00", "a", float(v)) for u, d, h, v in zip(rng.integers(0, 25, 4000), rng.integers(1, 10, 4000), rng.integers(0, 24, 4000), rng.uniform(0, 99, 4000).round(2), strict=True)]
    events += [(3, "2023-12-31 20:00:00", "a", 5000.0)]  # before the first slot: no cell, nor the largest sum
    spark.createDataFrame(events, "user_id long, ts string, event_type string, value double").selectExpr("user_id", "timestamp(ts) ts", "event_type", "value").write.parquet(f"{at}/events.parquet")
    items = [(f"1995-01-{2 + int(d):02d}", float(q), float(p), 0.01 * int(s)) for d, q, p, s in zip(rng.integers(0, 29, 3000), rng.integers(1, 51, 3000), rng.uniform(1, 99, 3000).round(2), rng.integers(0, 11, 3000), strict=True)]
    spark.createDataFrame(items, "d string, l_quantity double, l_extendedprice double, l_discount double").selectExpr("timestamp(d) l_shipdate", "l_quantity", "l_extendedprice", "l_discount").write.parquet(f"{at}/lineitem.parquet")
    return str(at)


def test_a_volume_needs_no_task_that_holds_it(spark, folder, monkeypatch):
    """However many boxes, errors are those of one index over the whole; sizes have no limit."""
    cells = rasters.scaled_volume(rasters.activity_volume(spark, folder)).selectExpr("z", "y", "x", "pix[0] v").toPandas()
    vol = np.zeros(cells[["z", "y", "x"]].max().to_numpy() + 1, np.int16)
    vol[cells.z, cells.y, cells.x] = cells.v
    p, centres = kernels.cubes(vol, np.ones(vol.shape, bool), 3)
    s, mask, errors = kernels.ZCurve(p, centres, 3, 1, None, ndim=3, dims=10, knn=20, mu=256), np.arange(27) < 18, []
    for r in np.linspace(0, len(p) - 1, 9).astype(int):
        own, q = np.abs(centres - centres[r]).max(1) >= 3, np.where(mask, p[r], 0)
        near = s.candidates(q, mask, None)
        if own[near].any():
            errors.append(np.sqrt(s.costs(near[own[near]], q, mask).min() / s.costs(None, q, mask)[own].min()) - 1)
    monkeypatch.setattr(experiments, "MOST_CELLS", 10)
    for most in (volumes.CUBES, 40):
        monkeypatch.setattr(volumes, "CUBES", most)
        got = {(r.params["side"], r.method, r.metric): r for r in experiments.w18_volume(spark, folder, 9, 20).collect()}
        assert len(got) == 12 and got[3, "zcurve", "queries"].params["cubes"] == len(p)
        assert got[3, "zcurve", "queries"].value == len(errors) and got[3, "zcurve", "ae_mean"].value == pytest.approx(np.mean(errors))
        assert 0 < got[3, "zcurve", "work_distances"].value <= 9 * len(p)


def test_a_volume_without_cubes(spark, folder, tmp_path):
    """Fewer layers than a cube has: no queries, not a failure."""
    spark.read.parquet(f"{folder}/events.parquet").where("user_id < 2").write.parquet(f"{tmp_path}/events.parquet")
    spark.read.parquet(f"{folder}/lineitem.parquet").limit(0).write.parquet(f"{tmp_path}/lineitem.parquet")
    got = experiments.w18_volume(spark, str(tmp_path)).collect()
    assert {r.value for r in got if r.metric == "queries"} == {0.0} and len(got) == 12
