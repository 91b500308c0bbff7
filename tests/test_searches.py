"""Registered searches answer as their scans do, and no row stands for a query and a block or an entry."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from patchspace.functions import costs
from patchspace.operators import footprints as fpx
from patchspace.operators import knn, patches, zindex
from patchspace.plans import core, load
from patchspace.streaming import queries as st


@pytest.mark.parametrize("name", ["frequency_exact", "index_increment", "w14_reusable_dictionary", "zcurve_search_exact_l1"])
def test_a_registered_search_pairs_blocks(spark, name):
    at = "/root/testdata/sf0.001"
    d = core.dictionary(spark, at)
    found = load()[0][name](spark, at)
    assert "e_block" not in found._jdf.queryExecution().optimizedPlan().toString()
    got = {r.query_id: r.cost for r in found.collect()}
    if name == "w14_reusable_dictionary":  # approximate: every odd patch has an answer among the even, none below the scan's
        q = patches.half_patches(d.where("patch_id % 2 = 1"), core.K, 5)
        scan = {r.query_id: r.cost for r in knn.full_scan(q, d.where("patch_id % 2 = 0"), costs.l2(), 1).collect()}
        assert got.keys() == scan.keys() and all(got[i] >= scan[i] for i in scan)
        return
    q = core.queries_of(d, core.K) if name == "frequency_exact" else core.queries_of(d)
    scan = knn.full_scan(q, d, costs.l1() if name.endswith("l1") else costs.l2(), 1, 1)
    assert got == {r.query_id: r.cost for r in scan.select("query_id", F.col("cost")).collect()}


def test_the_catalogue_of_an_increment_is_written_once(spark, tmp_path):
    """whoever asks for a grown index's blocks reads rows of blocks, and does not add up the entries again."""
    d = core.dictionary(spark, "/root/testdata/sf0.001")
    index = zindex.build_index(d.where("patch_id % 2 = 0"), core.FPS, core.K, 10, core.MU)
    grown = st.add_to_index(index, d.where("patch_id % 2 = 1"), f"file://{tmp_path}/delta")
    assert "Aggregate" not in grown.catalog._jdf.queryExecution().optimizedPlan().toString()
    assert grown.catalog.agg(F.sum("n")).first()[0] == grown.entries.count() == 8 * d.count()
    again = zindex.block_catalog(grown.entries, 10).select(grown.catalog.columns)
    assert again.exceptAll(grown.catalog).count() == grown.catalog.exceptAll(again).count() == 0


def test_the_driver_gets_the_blocks_of_the_chosen_indices_alone(spark):
    """of eight indices' catalogues, only those that queries have chosen are collected and sent."""
    d = core.dictionary(spark, "/root/testdata/sf0.001")
    index = zindex.build_index(d, core.FPS, core.K, 14, core.MU)
    own = knn.chosen(fpx.select_index(core.queries_of(d), core.FPS))
    assert len(own) == 1
    (i, tree), = knn._boxes(index, own).items()
    rows = sorted(index.catalog.where(F.col("index_id") == i).collect(), key=lambda r: (bytes(r.z_lo), r.block_id))
    assert [i, *tree.ids] == [own[0], *(r.block_id for r in rows)] and [*tree.n] == [r.n for r in rows]
    assert tree.keys == [bytes(r.z_lo) for r in rows] and tree.levels[0][1].tolist() == [list(r.box_hi) for r in rows]
    assert knn._boxes(index, []) == {}


def test_l1_of_queries_that_know_the_same():
    rng = np.random.default_rng(21)
    q, p, known = rng.integers(0, 256, (70, 64)).astype(float), rng.integers(0, 256, (50, 64)).astype(float), np.tile(np.arange(64) < 40, (70, 1))
    want = (np.abs(q[:, None] - p) * known[:, None]).sum(2)
    assert (costs.l1().block(q, p, known) == want).all()
    known[3, :9] = False
    assert (costs.l1().block(q, p, known) == (np.abs(q[:, None] - p) * known[:, None]).sum(2)).all()
    assert (costs.l1().block(q[:2], p, known[:2] & False) == 0).all()
