"""Invariants of the curve, the index, the searches and the fills."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from patchspace.functions import costs, zcurve
from patchspace.operators import fill, footprints, kernels, knn, metrics, patches, reduce, zindex
from patchspace.sources import masks, rasters


# curve


def test_worked_example_of_a_split():
    (lo, litmax), (bigmin, hi), dim, cut = zcurve.split((2, 0), (3, 7))
    assert (litmax, bigmin, dim, cut) == ([3, 3], [2, 4], 1, 3)
    keys = [zcurve.encode_int(p, 3) for p in (lo, litmax, bigmin, hi)]
    assert keys == [8, 15, 24, 31]
    q = np.array((4, 6))
    gap = lambda a, b: float(np.sqrt((np.maximum(0, np.maximum(np.array(a) - q, q - np.array(b))) ** 2).sum()))
    assert gap(bigmin, hi) == 1 and gap(lo, litmax) == pytest.approx(10**0.5)


@pytest.mark.parametrize("side,dims,bits", [(8, 2, 3), (4, 3, 2)])
def test_curve_invariants(side, dims, bits):
    points = list(itertools.product(range(side), repeat=dims))
    keys = {p: zcurve.encode_int(p, bits) for p in points}
    assert sorted(keys.values()) == list(range(side**dims))
    assert all(zcurve.decode_int(k, dims, bits) == list(p) for p, k in keys.items())
    raw = {p: zcurve.encode(np.array(p), bits)[0].tobytes() for p in points}
    assert sorted(points, key=keys.get) == sorted(points, key=raw.get)
    spans = [(a, b) for a in range(side) for b in range(a, side)]
    for box in itertools.product(spans, repeat=dims):
        lo, hi = [a for a, _ in box], [b for _, b in box]
        inside = {p for p in points if all(a <= x <= b for x, (a, b) in zip(p, box, strict=True))}
        assert all(keys[tuple(lo)] <= keys[p] <= keys[tuple(hi)] for p in inside)
        found = zcurve.split(lo, hi)
        assert (found is None) == (len(inside) == 1)
        if found:
            (a, litmax), (bigmin, b), *_ = found
            assert keys[tuple(litmax)] < keys[tuple(bigmin)] and (a, b) == (lo, hi)
        cover = zcurve.ranges(lo, hi, bits, 64)
        assert sorted(k for a, b in cover for k in range(a, b + 1)) == sorted(keys[p] for p in inside)
    assert sorted(zcurve.hilbert(np.array(points), bits).tolist()) == list(range(side**dims))


def test_footprints():
    fps = footprints.footprints(9, 0.6)
    assert len(fps) == 8 and all(len(f.pos) == 49 and len(set(f.pos)) == 49 for f in fps)
    assert [f.kind for f in fps] == ["edge"] * 4 + ["corner"] * 4
    assert len(footprints.footprints(9, 0.6, 3)[0].pos) == 147 and len(footprints.footprints(3, 0.6, 1, 3)) == 26


def test_components_basis_contracts_distances():
    rng = np.random.default_rng(0)
    x = rng.integers(0, 256, (200, 25))
    fp = footprints.footprints(5, 0.6)[2]
    b = reduce.pca_of(len(x), x.sum(0), x.T @ x, fp, 6)
    assert np.allclose(b.loadings @ b.loadings.T, np.eye(6))
    full = ((x[:, None, :] - x[None]) ** 2)[..., b.pos].sum(-1)
    c = b.project(x.astype(float))
    assert (((c[:, None] - c[None]) ** 2).sum(-1) <= full + 1e-6).all()
    assert 0 < b.explained <= 1


# costs


def test_costs_match_their_local_form(spark):
    rng = np.random.default_rng(1)
    q, p = rng.integers(0, 256, (20, 9)), rng.integers(0, 256, (20, 9))
    known = rng.random((20, 9)) < 0.7
    known[0] = False
    df = spark.createDataFrame([(i, q[i].tolist(), p[i].tolist(), known[i].tolist()) for i in range(20)], "i int, q array<smallint>, p array<smallint>, k array<boolean>")
    for cost in (costs.l2(), costs.l1(), costs.lp(3, 9), costs.weighted_l2(costs.centre_weights(3)), costs.hellinger_l2(), costs.ssim()):
        got = {r.i: r.c for r in df.select("i", cost.column(F.col("q"), F.col("p"), F.col("k")).cast("double").alias("c")).collect()}
        for i in range(20):
            want = float(np.atleast_1d(cost.local(q[i], p[i : i + 1], known[i]))[0])
            assert got[i] == pytest.approx(want, rel=1e-9, abs=1e-9), cost.name
    w = costs.blend_weights(q[0], p[:4], np.ones(9))
    assert w.sum() == pytest.approx(1)


# search


def small(spark, h=16, w=18, seed=0, values=40):
    rng = np.random.default_rng(seed)
    img = rng.integers(0, values, (h, w))
    cells = [(0, y, x, [int(img[y, x])], True) for y in range(h) for x in range(w)]
    return spark.createDataFrame(cells, fill.CELLS)


def local_knn(points, q, k):
    d = ((points - q) ** 2).sum(1)
    return np.lexsort((np.arange(len(d)), d))[:k]


@pytest.mark.parametrize("mu", [4, 64])
def test_batch_search_equals_a_sorted_scan(spark, mu):
    r = small(spark)
    d = patches.build_dictionary(r, 5).cache()
    index = zindex.build_index(d, footprints.footprints(5, 0.6), 5, 4, mu)
    q = patches.half_patches(d.where("patch_id % 7 = 0"), 5, 4)
    chosen = footprints.select_index(q, index.footprints)
    got = knn.zcurve_knn(chosen, index, 6).toPandas()
    rows = d.orderBy("patch_id").toPandas()
    x = np.stack(rows.vals)
    for qid, part in got.groupby("query_id"):
        i = chosen.where(F.col("query_id") == int(qid)).first().index_id
        c = index.basis(i).project(x.astype(float)).astype(np.float32).astype(float)
        own = index.basis(i).project(x[rows.patch_id == qid][0].astype(float))
        dist = ((c - own) ** 2).sum(1)
        assert np.allclose(np.sort(part.dist2), np.sort(dist)[:6], atol=1e-4)
    exact = knn.search(q, index, d, 3, costs.l2(), exact=True, exclude_radius=2).select("query_id", "cost").toPandas().set_index("query_id").cost
    scan = knn.full_scan(q, d, costs.l2(), 1, 2).toPandas().set_index("query_id").cost
    assert exact.sort_index().equals(scan.sort_index())


def test_search_edge_cases(spark):
    flat = spark.createDataFrame([(0, y, x, [7], True) for y in range(7) for x in range(7)], fill.CELLS)
    d = patches.build_dictionary(flat, 5)
    index = zindex.build_index(d, footprints.footprints(5, 0.6), 5, 4, 4)  # constant: no variance
    q = patches.half_patches(d, 5, 4)
    out = knn.search(q, index, d, 1000, costs.l2(), exact=True).collect()  # k > n, all tied
    assert {(r.cost, r.patch_id) for r in out} == {(0, min(r.patch_id for r in d.collect()))}
    none = patches.half_patches(d, 5, 1)  # no footprint is known wholly
    assert knn.search(none, index, d, 5).where("cost = 0").count() == d.count()
    assert footprints.select_index(none, index.footprints, "defer").count() == 0
    assert patches.build_dictionary(flat, 9).count() == 0  # smaller than a patch
    with pytest.raises(ValueError):
        knn.search(q, index, d, 5, costs.ssim(), exact=True)


def test_index_survives_saving(spark):
    d = patches.build_dictionary(small(spark), 5)
    from patchspace.shared import new_path

    path = new_path(spark, "test-index")
    a = zindex.build_index(d, footprints.footprints(5, 0.6), 5, 4, 16, path=path)
    b = zindex.load_index(spark, path)
    assert b.entries.count() == 8 * d.count() == a.catalog.agg(F.sum("n")).first()[0]
    assert b.catalog.agg(F.max("n")).first()[0] <= 16 and np.allclose(a.bases[3].loadings, b.bases[3].loadings)


# kernels


def image(seed=0, h=40, w=50):
    rng = np.random.default_rng(seed)
    a = kernels.box_mean(rng.normal(size=(h, w)), 5)
    img = ((a - a.min()) / (a.max() - a.min()) * 255).astype(np.int16)[..., None]
    known = np.ones((h, w), bool)
    for _ in range(4):
        y, x = rng.integers(6, h - 12), rng.integers(6, w - 14)
        known[y : y + 5, x : x + 8] = False
    return img, known


@pytest.mark.parametrize("method", sorted(kernels.SELECTORS))
def test_fills_end_and_keep_known_cells(method):
    img, known = image()
    out, trace, _ = kernels.fill(np.where(known[..., None], img, 0), known, method, 7, measure=True)
    assert (out[known] == img[known]).all() and sum(t["filled"] for t in trace) == (~known).sum()
    e = kernels.errors(trace)
    assert (e[~np.isnan(e)] >= -1e-12).all()
    if method in ("scan", "naive", "early_stop"):
        assert (e == 0).all()


def test_descent_equals_blocks_for_any_threshold():
    img, known = image(3)
    p, c = kernels.windows(img, known, 7)
    queries = [(p[i], np.repeat(np.arange(7) < 5, 7)) for i in range(0, len(p), 97)]
    answers = []
    for cls, mu in ((kernels.ZCurve, 8), (kernels.ZCurve, 300), (kernels.OutsideIn, 8), (kernels.OutsideIn, 100), (kernels.IDistance, 0), (kernels.PackedBoxes, 32)):
        s = cls(p, c, 7, 1, dims=6, knn=12, mu=mu or 64)
        answers.append([sorted(s.candidates(q, m, None).tolist()) for q, m in queries])
    assert all(a == answers[0] for a in answers[1:])


def test_more_candidates_never_hurt_and_all_are_exact():
    img, known = image(4)
    from patchspace.plans.experiments import grid, targets_of

    rows = grid(img, known, "zcurve", 6, (1, 5, 20, 100_000), 7, queries=targets_of(img, known, 7, 20))
    ae = [v for _, _, m, v in rows if m == "ae"]
    assert all(b <= a + 1e-12 for a, b in zip(ae, ae[1:])) and ae[-1] == pytest.approx(0, abs=1e-12)


def test_fill_edge_cases():
    img, known = image()
    with pytest.raises(ValueError):
        kernels.fill(img, np.zeros_like(known))
    same, trace, _ = kernels.fill(img, np.ones_like(known))
    assert (same == img).all() and trace == []
    with pytest.raises(ValueError):
        kernels.fill(img[:5, :5], np.eye(5, dtype=bool), k=9)


@pytest.mark.parametrize("order", ["structure", "salient", "sparsity", "levels", "value", "onion", "raster", "user"])
def test_orders_give_front_cells(order):
    img, known = image()
    value = kernels.Order(order, 7)(img, known, known.astype(float))
    on = np.isfinite(value)
    assert on.any() and (on <= (known & kernels.neighbours(~known))).all()


def test_level_lines_that_meet_come_first():
    img = np.full((21, 21, 1), 20, np.int16)
    img[10:] = 220
    known = np.ones((21, 21), bool)
    known[6:15, 6:15] = False
    order, flat = kernels.Order("levels", 5), known.astype(float)
    value = order(img, known, flat)
    y, x = np.unravel_index(int(np.argmax(value)), value.shape)
    assert y in (9, 10) and x in (5, 15)  # an end of the edge, whose other end is right across
    ends = order.joints(img, known, np.isfinite(value))
    assert np.allclose(ends, ends[:, ::-1])
    assert (ends[np.isfinite(value)] > 1e-3).sum() == 4
    img[:, 15:] = 240 - img[:, 15:]  # the other side is brighter there, so these ends do not match
    turned = order.joints(img, known, np.isfinite(value))
    assert (turned[9:11, 5] < (ends[9:11, 5] + 1e-3) / 2).all()
    assert (order.joints(np.full_like(img, 7), known, np.isfinite(value)) == 1e-3).all()


def test_slopes_use_known_neighbours_only():
    rng = np.random.default_rng(3)
    a, known = rng.integers(0, 255, (6, 7)).astype(float), rng.random((6, 7)) < 0.6
    down, right = kernels.slopes(a, known)
    for y in range(6):
        for x in range(7):
            for got, dy, dx in ((down, 1, 0), (right, 0, 1)):
                steps = [s * (a[y + s * dy, x + s * dx] - a[y, x]) for s in (-1, 1) if 0 <= y + s * dy < 6 and 0 <= x + s * dx < 7 and known[y, x] and known[y + s * dy, x + s * dx]]
                assert got[y, x] == pytest.approx(np.mean(steps) if steps else 0)


# plans over rasters


def test_patches_front_and_paste(spark):
    r = small(spark, 9, 10)
    m = masks.hole_mask(r, 3)
    broken = masks.damage(r, m)
    img, known, _, _ = fill.to_arrays(broken.toPandas())
    front = {(c.y, c.x) for c in patches.fill_front(broken).collect()}
    assert front == set(zip(*(a.tolist() for a in np.nonzero(known & kernels.neighbours(~known))), strict=True))
    want, centres = kernels.windows(img, known, 3)
    got = {(p.cy, p.cx): p.vals for p in patches.build_dictionary(broken, 3).collect()}
    assert got == {tuple(c): v for c, v in zip(centres.tolist(), want.tolist(), strict=True)}
    out, _, _, _ = fill.to_arrays(fill.inpaint(broken, "scan", k=3).toPandas())
    assert (out[known] == img[known]).all()
    assert fill.step(broken, 3).where(~F.col("known")).count() < broken.where(~F.col("known")).count()


def test_texts_masks_cover_a_fifth(spark):
    r = small(spark, 30, 40)
    (c,) = masks.coverage(masks.exact_hash_mask(r, 0.2)).collect()
    assert c.unknown == 240
    (q,) = metrics.fill_quality(r, r, masks.exact_hash_mask(r, 0.2)).collect()
    assert (q.cells, q.mse, q.psnr) == (240, 0.0, None)


def test_fill_of_two_channels_of_images(spark):
    a = rasters.stripes(spark, 20, 20)
    two = a.unionByName(a.withColumn("image_id", F.lit(5).cast("long"))).withColumn("pix", F.concat("pix", "pix", "pix"))
    out = fill.inpaint(masks.damage(two, masks.hole_mask(two, 5)), "scan", k=5).collect()
    truth = {(c.image_id, c.y, c.x): c.pix for c in two.collect()}
    assert all(c.pix == truth[c.image_id, c.y, c.x] for c in out) and len(out) == 800


@pytest.mark.parametrize("method", ["scan", "zcurve", "outside_in"])
def test_volume_fill(method):
    z, y, x = np.mgrid[:9, :10, :11]
    vol = ((x + 2 * y + 3 * z) % 6 * 40).astype(np.int16)
    known = np.ones(vol.shape, bool)
    known[3:5, 4:6, 4:7] = False
    out, trace = kernels.fill_volume(np.where(known, vol, 0), known, method, 3, dims=6, knn=10_000)
    assert (out[known] == vol[known]).all() and sum(t["filled"] for t in trace) == 12
    if method == "scan":
        assert (out == vol).all()
    assert kernels.fill_volume(vol, np.ones_like(known))[1] == []


def test_the_seed_round_is_linear_in_the_queries(spark, monkeypatch):
    """Round one pairs a query with the blocks that hold k entries and one more, whatever the index holds."""
    from patchspace.plans import core

    sf = "/root/testdata/sf0.001"
    d = core.dictionary(spark, sf)
    fps, bases = core.whole_basis(10)
    index = zindex.build_index(d, fps, 8, 10, 8, bases)
    q = core.queries_of(d, 8).withColumn("index_id", F.lit(0))
    coords = knn.query_coords(q, index)
    n, blocks, k = q.count(), index.catalog.count(), 20
    assert blocks > 40 and knn.near_blocks(coords, index, k).count() <= n * (-(-k // 8) + 2)
    want = [tuple(r) for r in knn.zcurve_knn(q, index, k, 1).orderBy("query_id", "rank").collect()]
    monkeypatch.setattr(zindex, "UNITS", 4)  # a catalogue too large to send: groups first, then their blocks
    large = zindex.ZIndex(index.entries, index.catalog, index.bases, index.footprints, 8, 10, 8)
    assert large.grouped
    assert [tuple(r) for r in knn.zcurve_knn(q, large, k, 1).orderBy("query_id", "rank").collect()] == want


def test_candidates_are_cut_from_strips(spark, monkeypatch):
    monkeypatch.setattr(patches, "STRIP", 7)
    r = rasters.stripes(spark, 20, 23)
    holed = masks.damage(r, masks.hole_mask(r))
    whole = {x.patch_id: list(x.vals) for x in patches.build_dictionary(holed, 5).collect()}
    ids = [*whole][::3] + [patches.STEP * 10 + 10, patches.STEP * 500 + 2]  # in the hole; off the raster
    got = patches.RasterPatches(holed, 5).cut(spark.createDataFrame([(i,) for i in ids], "patch_id long"))
    assert {x.patch_id: list(x.vals) for x in got.collect()} == {i: whole[i] for i in ids if i in whole}


def test_images_that_cannot_be_filled_come_back(spark):
    r = rasters.stripes(spark, 16, 16)
    images = [r.withColumn("image_id", F.lit(i).cast("long")) for i in range(4)]
    hole = ~((F.col("y").between(6, 8)) & (F.col("x").between(6, 8)))
    good = images[0].withColumn("known", hole)
    dark = images[1].withColumn("known", F.lit(False))
    tiny = images[2].where("y < 3 AND x < 3").withColumn("known", F.col("x") > 0)
    whole = images[3]
    df = good.unionByName(dark).unionByName(tiny).unionByName(whole)
    df = df.withColumn("pix", F.when(F.col("known"), F.col("pix")))
    got = fill.inpaint(df, "scan", k=5)
    counts = {x.image_id: (x.n, x.k) for x in got.groupBy("image_id").agg(F.count("*").alias("n"), F.count(F.when(F.col("known"), 1)).alias("k")).collect()}
    assert counts == {0: (256, 256), 1: (256, 0), 2: (9, 6), 3: (256, 256)}
    assert got.where("NOT known AND pix IS NOT NULL").count() == 0
    assert fill.inpaint_trace(df, "scan", k=5).select("image_id").distinct().collect()[0].image_id == 0
    empty = df.limit(0)
    assert fill.inpaint(empty, "scan", k=5).count() == 0 and fill.wave_fill(empty, 5)[0].count() == 0
    assert fill.wave_fill(dark.withColumn("pix", F.lit(None).cast("array<smallint>")), 5)[0].where("known").count() == 0


def test_baselines_on_empty_tables(spark):
    from patchspace.operators.baselines import plans as base

    points = spark.createDataFrame([], "patch_id long, coord array<double>")
    q = spark.createDataFrame([(1, [0.0, 1.0])], "query_id long, coord array<double>")
    keyed, centres = base.idistance_build(points)
    assert base.idistance_knn(q, keyed, centres, 3, 1.0).count() == 0
    assert base.tsvq_knn(q, points).count() == 0 and base.lsh_knn(q, points, 3, 1.0).count() == 0


def test_dictionaries_are_saved_in_curve_order(spark, tmp_path):
    from patchspace.plans import core

    d = core.dictionary(spark, "/root/testdata/sf0.001")
    index = zindex.build_index(d, core.FPS[:2], 8, 6, 32)
    patches.save_dictionary(d, str(tmp_path / "d"), index)
    rows = spark.read.parquet(str(tmp_path / "d")).where("index_id = 0").select(F.hex("zkey").alias("z")).collect()
    assert len(rows) == d.count() and sorted((tmp_path / "d").glob("index_id=*")) != []
    back = patches.load_dictionary(spark, str(tmp_path / "d"))
    assert {(r.patch_id, tuple(r.vals)) for r in back.collect()} == {(r.patch_id, tuple(r.vals)) for r in d.collect()}


def test_regions_side_by_side_do_not_change_the_answer():
    rng = np.random.default_rng(1)
    p = rng.integers(0, 256, (3000, 25)).astype(np.int16)
    centres = np.stack([np.arange(3000), np.zeros(3000, int)], 1)
    mask = np.ones(25, bool)
    one = kernels.ZCurve(p, centres, 5, 1, None, dims=6, knn=40, mu=16)
    many = kernels.ZCurve(p, centres, 5, 1, None, dims=6, knn=40, mu=16, nu=32, threads=4)
    for i in range(0, 3000, 300):
        assert (one.candidates(p[i], mask, None) == many.candidates(p[i], mask, None)).all()
    assert many.work["regions"] > one.work["queries"]


def test_fills_follow_a_guide():
    guide = costs.guided(3, None, lambda q, p: np.abs(p[..., 0] - 7).astype(np.int64))
    p = np.array([[7, 1], [9, 1]], np.int16)
    assert guide.local(np.array([0, 1]), p, np.array([False, True])).tolist() == [0, 6]
    with pytest.raises(ValueError):
        costs.guided(3, None).local(np.array([0, 1]), p, np.array([False, True]))


def test_activity_rasters_hold_the_whole_table(spark):
    sf = "/root/testdata/sf0.01"
    total = spark.read.parquet(f"{sf}/events.parquet").agg(F.sum(F.round(F.col("value") * 100).cast("long"))).first()[0]
    assert rasters.activity_field(spark, sf).agg(F.sum("v")).first()[0] == total
    assert rasters.activity_volume(spark, sf).agg(F.sum("v")).first()[0] == total
    price = spark.read.parquet(f"{sf}/lineitem.parquet").agg(F.sum(F.round(F.col("l_extendedprice") * 100).cast("long"))).first()[0]
    assert rasters.sales_volume(spark, sf).agg(F.sum("v")).first()[0] == price
    assert rasters.market_sums(spark, sf, "S", rasters.LEVELS).agg(F.sum("v")).first()[0] == price
