"""Scans on matrices against the column forms of the costs, and that they emit no row a pair."""

import time
from types import SimpleNamespace

import numpy as np
import pytest
from pyspark.sql import functions as F

from patchspace.functions import costs
from patchspace.operators import knn, pairs, patches
from patchspace.operators.baselines import plans as base

GUIDE = lambda q, p: F.aggregate(F.zip_with(q, p, lambda a, b: F.abs(a.cast("long") - b)), F.lit(0).cast("long"), lambda s, x: s + x)
COSTS = {
    "l2": costs.l2,
    "l1": costs.l1,
    "weighted": lambda: costs.weighted_l2(costs.centre_weights(4)),
    "l3": lambda: costs.lp(3, 16),
    "hellinger": lambda: costs.hellinger_l2(8),
    "ssim": costs.ssim,
    "guided": lambda: costs.guided(2, GUIDE, lambda q, p: np.abs(p - q).sum(1)),
}


@pytest.fixture(scope="module")
def table(spark):
    rng = np.random.default_rng(5)
    rows = [(i, 0, 0, i, [int(x) for x in rng.integers(0, 256, 16)]) for i in range(60)]
    rows += [(60 + i, 0, 0, 60 + i, rows[i % 4][4]) for i in range(40)]  # groups of copies
    d = spark.createDataFrame(rows, "patch_id long, image_id long, cy int, cx int, vals array<smallint>")
    return d, patches.half_patches(d.where("patch_id % 5 = 0"), 4, 3)


@pytest.mark.parametrize("name", COSTS)
def test_matrices_say_what_the_columns_say(table, name):
    (d, q), cost = table, COSTS[name]()
    found = knn.full_scan(q, d, cost, 7, 1)
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "zip_with" not in plan and "MapInArrow" in plan
    p = d.select("patch_id", F.col("vals").alias("p"))
    every = p.join(q, F.col("patch_id") != F.col("query_id")).select("query_id", "patch_id", cost.column(F.col("vals"), F.col("p"), F.col("known")).alias("cost")).toPandas()
    want = every.sort_values(["query_id", "cost", "patch_id"]).groupby("query_id").head(7)
    got = found.toPandas().sort_values(["query_id", "rank"])
    assert got.cost.to_numpy() == pytest.approx(want.cost.to_numpy(), rel=1e-12)
    assert got.patch_id.tolist() == want.patch_id.tolist() and got["rank"].tolist() == [1, 2, 3, 4, 5, 6, 7] * 20


def test_early_stop_on_matrices(table):
    d, q = table
    got = {(r.query_id, r.patch_id, r.cost) for r in base.early_stop_scan(q, d).collect()}
    assert got == {(r.query_id, r.patch_id, r.cost) for r in knn.full_scan(q, d, costs.l2(), 1, 1).collect()}


def test_least_breaks_ties_by_id():
    rows, ids, cost = pairs.least(np.array([[2.0, 1, 1, np.inf], [3, 3, 3, 3]]), np.array([7, 9, 4, 1]), 2)
    assert list(zip(rows, ids, cost, strict=True)) == [(0, 4, 1), (0, 9, 1), (1, 1, 3), (1, 4, 3)]


def test_hashing_meets_a_pair_once(spark):
    """In wide buckets every table joins every pair; none comes twice, and no shuffle looks for repeats."""
    points = spark.range(40).select(F.col("id").alias("patch_id"), F.array(*[(F.col("id") * i % 7).cast("double") for i in (1, 2, 3)]).alias("coord"))
    q = points.where("patch_id % 8 = 0").select(F.col("patch_id").alias("query_id"), "coord")
    found = base.lsh_knn(q, points, 1000, 1e9)
    assert "Aggregate" not in found._jdf.queryExecution().optimizedPlan().toString()
    got = [(r.query_id, r.patch_id) for r in found.collect()]
    assert len(got) == len(set(got)) == 5 * 39


@pytest.mark.parametrize(("width", "few"), [(1e9, 100_000), (40.0, 100_000), (40.0, 0), (0.5, 100_000)])
def test_hashing_writes_no_row_a_pair(spark, monkeypatch, width, few):
    """Packed buckets give the pairs that share one, whether queries are sent to all tasks or dealt, also where an
    identifier comes twice or is null; with one wide bucket a pair of blocks is met in the first table alone."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    monkeypatch.setattr(pairs, "FEW", few)
    rng = np.random.default_rng(8)
    coord = rng.normal(0, 30, (2500, 4))
    coord[1::50] = coord[::50]  # copies
    ids = [*range(2490), *range(9), None]
    points = spark.createDataFrame([(i, c.tolist()) for i, c in zip(ids, coord, strict=True)], "patch_id long, coord array<double>").repartition(3)
    q = points.where("patch_id % 20 = 0").select(F.col("patch_id").alias("query_id"), "coord").dropDuplicates(["query_id"])
    found = base.lsh_knn(q, points, 7, width, 3)
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "zip_with" not in plan and plan.count("MapInArrow") == 3
    got = sorted((r.query_id, r["rank"], r.patch_id, r.dist2) for r in found.collect())

    features = points.withColumn("features", array_to_vector("coord"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=width, numHashTables=3, seed=4).fit(features)
    rows = [(r.patch_id, np.array(r.coord), [h[0] for h in r.hashes]) for r in model.transform(features).collect() if r.patch_id is not None]
    c, h, of = np.array([r[1] for r in rows]), np.array([r[2] for r in rows]), np.array([r[0] for r in rows])
    asked = {r.query_id: np.array(r.coord) for r in q.collect()}
    want = []
    for i, x in asked.items():
        own = h[[j for j, r in enumerate(rows) if r[0] == i and (r[1] == x).all()][0]]
        near = np.flatnonzero((h == own).any(1) & (of != i))
        dist2 = sum((x[d] - c[near, d]) ** 2 for d in range(4))
        order = np.lexsort((of[near], dist2))[:7]
        want += [(i, n + 1, int(of[near[j]]), float(dist2[j])) for n, j in enumerate(order)]
    assert got == sorted(want)
    assert base.lsh_knn(q.limit(0), points, 7, width, 3).count() == 0


def test_blocks_that_met_before_are_not_paired(spark):
    """All rows in one bucket of each of two tables: only the pairs of blocks of the first table are there."""
    rows = spark.range(3000).select(F.col("id").alias("patch_id"), F.array(F.lit(0.0)).alias("vals"), *[F.lit(5).cast("long").alias(h) for h in ("h0", "h1")], F.explode(F.array(F.lit(0), F.lit(1))).alias("turn"), F.lit(5).alias("bucket"))
    q = rows.where("patch_id < 40").withColumnRenamed("patch_id", "query_id")
    met = (F.col("turn") > 0) & (F.col("q_h0_all") == F.col("p_h0_all"))
    both = pairs.paired(q, rows, (), ("query_id", "h0", "h1"), ("patch_id", "h0", "h1"), by=("turn", "bucket"), alike=("h0", "h1"), met=met)
    got = both.select("turn", (F.col("q_n").cast("long") * F.col("p_n")).alias("n")).groupBy("turn").agg(F.sum("n").alias("n")).collect()
    assert [(r.turn, r.n) for r in got] == [(0, 40 * 3000)]


def test_ratios_of_all_pairs(table):
    """As from the pairs written out, without a row a pair."""
    d, q = table
    square = lambda q, p, k: np.sqrt(costs.l2().block(q.vals, p.vals, k(q)))
    got = pairs.ratios(q, d, lambda a, b: square(a, b, lambda x: x.known), lambda a, b: square(a, b, lambda x: np.ones_like(x.known)), 1).first()
    v = {r.patch_id: np.array(r.vals, float) for r in d.collect()}
    known = np.arange(16) < 12
    want = [np.sqrt((x * x * known).sum() / (x * x).sum()) for i in v if i % 5 == 0 for j in v if j != i for x in [v[i] - v[j]] if x.any()]
    assert got.pairs == len(want) and got.ratio_mean == pytest.approx(np.mean(want)) and got.ratio_stddev == pytest.approx(np.std(want, ddof=1))


def test_a_search_writes_no_row_a_query_and_block(spark, table, monkeypatch):
    """Both rounds' answers are the sorted scan's, whichever side is sent to the tasks and whichever indices
    the queries choose, and no row stands for a query and a block that is within its radius."""
    from patchspace.operators import footprints, zindex

    d, q = table
    fps = footprints.footprints(4, 0.6)
    index = zindex.build_index(d, fps, 4, 6, 4)
    left = F.array(*[F.lit(i % 4 < 3) for i in range(16)])
    q = q.withColumn("known", F.when(F.col("query_id") % 2 == 0, F.col("known")).otherwise(left))
    chosen = footprints.select_index(q, fps).cache()
    assert chosen.select("index_id").distinct().count() == 2
    e = index.entries.toPandas()
    coords = {r.query_id: np.array(r.coord) for r in knn.query_coords(chosen, index).collect()}
    want = []
    for r in chosen.orderBy("query_id").collect():
        own = e[(e.index_id == r.index_id) & (e.patch_id != r.query_id)]
        dist = sum((coords[r.query_id][i] - own.coord.map(lambda c, i=i: float(c[i])).to_numpy()) ** 2 for i in range(6))
        order = np.lexsort((own.patch_id, dist))[:9]
        want += list(zip([r.query_id] * 9, own.patch_id.to_numpy()[order], strict=True))
    scan = sorted(tuple(r) for r in knn.full_scan(q, d, costs.l2(), 1, 1).select("query_id", "patch_id", "cost").collect())
    for sent in (knn.SENT, 0):
        monkeypatch.setattr(knn, "SENT", sent)
        near = knn.zcurve_knn(chosen, index, 9, 1)
        assert "e_block" not in near._jdf.queryExecution().optimizedPlan().toString()
        assert [(r.query_id, r.patch_id) for r in near.orderBy("query_id", "rank").collect()] == want
        best = knn.search(q, index, d, 9, costs.l2(), exact=True, exclude_radius=1)
        assert "e_block" not in best._jdf.queryExecution().optimizedPlan().toString()
        assert sorted((r.query_id, r.patch_id, r.cost) for r in best.collect()) == scan
        assert best.agg(F.min("refined")).first()[0] >= 1


def test_a_batch_of_a_stream_is_read_once(spark, table, tmp_path, monkeypatch):
    """A search reads its queries more than once, so it gets them written, outside the stream's plan."""
    from patchspace.streaming import queries as st

    _, q = table
    q.withColumn("ts", F.timestamp_seconds(F.col("query_id"))).coalesce(1).write.parquet(f"{tmp_path}/in")
    seen = []

    def search(queries, *_, **__):
        seen.append(queries.inputFiles())
        return queries.select("query_id", F.col("query_id").alias("patch_id"), F.lit(0).cast("long").alias("cost"))

    monkeypatch.setattr(knn, "search", search)
    stream = spark.readStream.schema(spark.read.parquet(f"{tmp_path}/in").schema).parquet(f"{tmp_path}/in")
    assert st.serve(stream, None, None).count() == q.count()
    assert all("/asked/" in f for files in seen for f in files) and all(seen)


def test_the_filter_of_blocks_is_a_product_of_matrices():
    """It gives the distances of all pairs within the radius, and takes less time than the differences of all pairs."""
    rng, dims, n = np.random.default_rng(6), 12, 1024
    q, p = SimpleNamespace(n=n), SimpleNamespace(n=n)
    q.vals, p.vals = rng.normal(size=(n, dims)), rng.normal(size=(n, dims)).astype(np.float32).astype(float)
    q.query_id, q.image_id, q.cy, q.cx, q.index_id = np.arange(n), np.arange(n) % 2, np.zeros(n, int), np.arange(n), np.zeros(n, int)
    p.patch_id, p.image_id, p.block_id, p.index_id = rng.permutation(n), np.arange(n) % 2, np.arange(n) // 32, np.zeros(n, int)
    dense = lambda: sum((q.vals[:, i, None] - p.vals[:, i]) ** 2 for i in range(dims))
    want = dense()
    q.radius2 = np.sort(want, axis=1)[:, 20].copy()  # a pair lies at exactly the radius
    q.radius2[:9] = np.inf
    want[want > q.radius2[:, None]] = np.inf
    found = knn.within(dims, None)(q, p)
    assert (found == want).all() and np.isfinite(found[9:]).sum() == 21 * (n - 9)
    apart = (q.image_id[:, None] == p.image_id) & (np.abs(p.patch_id - q.cx[:, None]) < 3)
    assert (knn.within(dims, 3)(q, p) == np.where(apart, np.inf, want)).all()

    def least_time(f):
        took = []
        for _ in range(7):
            began = time.perf_counter()
            f()
            took.append(time.perf_counter() - began)
        return min(took)

    assert least_time(lambda: knn.within(dims, 1)(q, p)) < least_time(dense)


def test_the_radius_shrinks_to_the_kth_best_of_the_task(spark):
    """a query that has k pairs looks no farther than the k-th; answers and ties stay."""
    at = F.array(*[F.pmod(F.col("id") * m, F.lit(n)).cast("double") for m, n in ((7, 40), (11, 30))])
    rows = spark.range(3000).select(F.col("id").alias("patch_id"), F.lit(0).cast("long").alias("image_id"), F.lit(0).alias("index_id"), F.expr("id div 32").alias("block_id"), at.alias("vals"))
    q = rows.where("patch_id % 20 = 0").select(F.col("patch_id").alias("query_id"), "image_id", F.lit(0).alias("cy"), F.col("patch_id").cast("int").alias("cx"), "index_id", "vals", F.lit(float("inf")).alias("radius2"))

    def strict():
        seen, near = set(), knn.within(2, 1)

        def cost(qb, pb):
            assert qb.query_id.tobytes() not in seen or np.isfinite(qb.radius2).all()
            seen.add(qb.query_id.tobytes())
            return near(qb, pb)

        return cost

    data = np.array(rows.select("vals").toPandas().vals.to_list())
    for by_query in (True, False):
        found = pairs.best_pairs(q, rows.coalesce(1), strict(), 5, ("radius2",), knn.ASKED, knn.ENTRY, by_query=by_query, shrink=True)
        got = [(r.query_id, r.patch_id) for r in knn.first_k(found.withColumnRenamed("cost", "dist2"), 5).orderBy("query_id", "rank").collect()]
        want = []
        for i in range(0, 3000, 20):
            dist = ((data - data[i]) ** 2).sum(1)
            dist[i] = np.inf
            want += [(i, int(j)) for j in np.lexsort((np.arange(3000), dist))[:5]]
        assert got == want


def test_the_least_of_rows_of_any_width():
    rng = np.random.default_rng(4)
    for width in (1, 3, 8, 60):
        cost, ids = rng.integers(0, 5, (40, width)).astype(float), rng.permutation(width)
        cost[rng.random(cost.shape) < 0.4] = np.inf
        cost[5] = np.inf
        for k in (1, 2, 8, 40):
            want = [(r, int(ids[c]), cost[r, c]) for r in range(40) for c in np.lexsort((ids, cost[r]))[:k] if np.isfinite(cost[r, c])]
            assert list(zip(*(x.tolist() for x in pairs.least(cost, ids, k)), strict=True)) == want
