"""The index and its parts on embedding patches: the smallest full slice of the method."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.functions import costs, zcurve
from patchspace.operators import footprints as fpx
from patchspace.operators import knn, metrics, patches, reduce, zindex
from patchspace.plans import sql
from patchspace.plans.registry import query
from patchspace.sources import rasters

K, N_KNOWN = 8, 8 * sql.ROWS_KNOWN
FPS = sql.FP8


def dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rasters.embedding_patches(spark, sf_dir)


def queries_of(d: DataFrame, rows_known: int = sql.ROWS_KNOWN) -> DataFrame:
    """The stated query set: every 20th patch, of which the first rows are known."""
    return patches.half_patches(d.where(F.col("patch_id") % sql.EVERY == 0), K, rows_known)


def whole_basis(dims: int) -> tuple[list, list]:
    """One footprint of all pixels with an integer Walsh basis, orthonormal after scaling."""
    fp = fpx.Footprint(0, "all", tuple(range(K * K)))
    rows = reduce.frequencies(K, dims, "hadamard") / K
    return [fp], [reduce.Basis(0, np.arange(K * K), np.zeros(K * K), rows, np.ones(K * K), -1024.0, 8.0)]


@query("patch_fullscan_l2", f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l2('q.vals', 'p.vals', N_KNOWN), 1)}")
def patch_fullscan_l2(spark, sf_dir):
    d = dictionary(spark, sf_dir)
    return knn.full_scan(queries_of(d), d, costs.l2(), 1, 1)


@query("patch_fullscan_l1", f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l1('q.vals', 'p.vals', N_KNOWN), 1)}")
def patch_fullscan_l1(spark, sf_dir):
    d = dictionary(spark, sf_dir)
    return knn.full_scan(queries_of(d), d, costs.l1(), 1, 1)


@query("patch_topk", f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l2('q.vals', 'p.vals', N_KNOWN), 10)}")
def patch_topk(spark, sf_dir):
    d = dictionary(spark, sf_dir)
    return knn.full_scan(queries_of(d), d, costs.l2(), 10, 1)


WEIGHTS = costs.centre_weights(K)
NEAR_CENTRE = "(1 + 8 - greatest(abs((i - 1) // 8 - 4), abs((i - 1) % 8 - 4)))"


@query("patch_fullscan_weighted", f"WITH {sql.PATCHES}, " + sql.ranked_scan(f"list_sum([(q.vals[i] - p.vals[i]) * (q.vals[i] - p.vals[i]) * {NEAR_CENTRE} for i in range(1, {N_KNOWN + 1})])::BIGINT", 1))
def patch_fullscan_weighted(spark, sf_dir):
    d = dictionary(spark, sf_dir)
    return knn.full_scan(queries_of(d), d, costs.weighted_l2(WEIGHTS), 1, 1)


@query("patch_fullscan_l3", f"WITH {sql.PATCHES}, s AS (SELECT q.patch_id AS query_id, p.patch_id AS patch_id, list_sum([abs(q.vals[i] - p.vals[i])**3 for i in range(1, {N_KNOWN + 1})]) AS c FROM emb q JOIN emb p ON p.patch_id <> q.patch_id WHERE q.patch_id % {sql.EVERY} = 0) SELECT query_id, arg_min(patch_id, (c, patch_id)) AS patch_id, round(min(c) ** (1.0 / 3), 6) AS cost FROM s GROUP BY query_id")
def patch_fullscan_l3(spark, sf_dir):
    d = dictionary(spark, sf_dir)
    return knn.full_scan(queries_of(d), d, costs.lp(3, K * K), 1, 1).select("query_id", "patch_id", F.round("cost", 6).alias("cost"))


MASKED = "m AS (SELECT patch_id, vals[1] % 8 + 1 AS a, vals[2] % 8 + 1 AS b FROM emb)"


def masked(spark, sf_dir) -> DataFrame:
    """Patches with numbers of known rows and columns, from 1 to 8, that their first samples give."""
    of = lambda i: (F.col("vals")[i] % 8 + 1).cast("int")
    return dictionary(spark, sf_dir).select("patch_id", of(0).alias("rows_known"), of(1).alias("cols_known"))


@query("footprint_cover", f"WITH {sql.PATCHES}, {sql.footprint_rows()}, {MASKED} SELECT patch_id, a::INTEGER AS rows_known, index_id, kind, len([i for i in pos if i < 8 * a])::INTEGER AS cover, len([i for i in pos if i < 8 * a]) = len(pos) AS whole FROM m, fp")
def footprint_cover(spark, sf_dir):
    masks = masked(spark, sf_dir).withColumn("known", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: i < F.col("rows_known") * 8))
    return fpx.cover(masks, FPS).select("patch_id", "rows_known", "index_id", "kind", "cover", "whole")


@query("index_choice", f"""WITH {sql.PATCHES}, {sql.footprint_rows()}, {MASKED}, ab AS (SELECT DISTINCT a, b FROM m),
c AS (SELECT a, b, index_id, len(pos) AS size, len([i for i in pos if i // 8 < a and i % 8 < b]) AS cover FROM ab, fp),
best AS (SELECT a, b, arg_max(index_id, (cover, -index_id)) AS index_id FROM c WHERE cover = size GROUP BY a, b)
SELECT patch_id, a::INTEGER AS rows_known, b::INTEGER AS cols_known, coalesce(index_id, -1)::INTEGER AS index_id FROM m LEFT JOIN best USING (a, b)""")
def index_choice(spark, sf_dir):
    masks = masked(spark, sf_dir).withColumn("known", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: (F.floor(i / 8) < F.col("rows_known")) & (i % 8 < F.col("cols_known"))))
    return fpx.select_index(masks, FPS).select("patch_id", "rows_known", "cols_known", F.coalesce("index_id", F.lit(-1)).alias("index_id"))


SCATTER = f"WITH {sql.PATCHES} SELECT (i - 1)::INTEGER AS i, (j - 1)::INTEGER AS j, count(*) AS n, sum(vals[i] * vals[j])::BIGINT AS sum_products FROM emb, (SELECT unnest(range(1, 65)) AS i), (SELECT unnest(range(1, 65)) AS j) WHERE i <= j GROUP BY ALL"


@query("scatter_matrix", SCATTER)
def scatter_matrix(spark, sf_dir):
    n, _, p = reduce.scatter(dictionary(spark, sf_dir))
    rows = [(i, j, n, int(p[i, j])) for i in range(len(p)) for j in range(i, len(p))]
    return spark.createDataFrame(rows, "i int, j int, n long, sum_products long")


@query("scatter_matrix_sql", SCATTER)
def scatter_matrix_sql(spark, sf_dir):
    return reduce.scatter_table(dictionary(spark, sf_dir))


@query("pca_trace", f"WITH {sql.PATCHES}, {sql.footprint_rows()}, m AS (SELECT i, avg(vals[i + 1]) AS a, avg(vals[i + 1] * vals[i + 1]) AS s FROM emb, (SELECT unnest(range(0, 64)) AS i) GROUP BY i) SELECT index_id::INTEGER AS index_id, round(sum(s - a * a), 4) AS total_variance FROM (SELECT index_id, unnest(pos) AS i FROM fp) JOIN m USING (i) GROUP BY index_id")
def pca_trace(spark, sf_dir):
    bases = reduce.fit_pca(dictionary(spark, sf_dir), FPS, 10)
    return spark.createDataFrame([(b.index_id, float(round(b.eigen.sum(), 4))) for b in bases], "index_id int, total_variance double")


@query("explained_variance")
def explained_variance(spark, sf_dir):
    bases = reduce.fit_pca(dictionary(spark, sf_dir), FPS, 10)
    return spark.createDataFrame(reduce.explained_variance(bases), "index_id int, explained double")


@query("patch_fullscan_hellinger", f"""WITH {sql.PATCHES}, h AS (SELECT patch_id, vals, [len([v for v in vals[1:{N_KNOWN}] if v * 8 // 256 = b]) for b in range(0, 8)] AS hist FROM emb),
s AS (SELECT q.patch_id AS query_id, p.patch_id, round(sqrt({sql.l2('q.vals', 'p.vals', N_KNOWN)}) * sqrt(greatest(0, 1 - list_sum([sqrt(q.hist[b] * p.hist[b]) / {N_KNOWN}.0 for b in range(1, 9)]))), 4) AS cost
  FROM h q JOIN h p ON p.patch_id <> q.patch_id WHERE q.patch_id % {sql.EVERY} = 0)
SELECT query_id, round(min(cost), 4)::DOUBLE AS cost FROM s GROUP BY query_id""")
def patch_fullscan_hellinger(spark, sf_dir):
    """The least cost of each query; rounded, as roots differ in the last digit."""
    d = dictionary(spark, sf_dir)
    return knn.full_scan(queries_of(d), d, costs.hellinger_l2(8), 1, 1).select("query_id", F.round("cost", 4).alias("cost"))


SSIM = """1 - (2 * q.m * p.m + 6.5025) * (2 * (list_inner_product(q.k, p.k) / {n} - q.m * p.m) + 58.5225) / ((q.m * q.m + p.m * p.m + 6.5025) * (q.v + p.v + 58.5225))""".replace("{n}", f"{N_KNOWN}.0")


@query("patch_fullscan_ssim", f"""WITH {sql.PATCHES}, k AS (SELECT patch_id, vals[1:{N_KNOWN}]::DOUBLE[] AS k FROM emb),
h AS (SELECT patch_id, k, list_avg(k) AS m, list_avg([x * x for x in k]) - list_avg(k) * list_avg(k) AS v FROM k),
s AS (SELECT q.patch_id AS query_id, {SSIM} AS cost FROM h q JOIN h p ON p.patch_id <> q.patch_id WHERE q.patch_id % {sql.EVERY} = 0)
SELECT query_id, round(min(cost), 6) AS cost FROM s GROUP BY query_id""")
def patch_fullscan_ssim(spark, sf_dir):
    d = dictionary(spark, sf_dir)
    return knn.full_scan(queries_of(d), d, costs.ssim(), 1, 1).select("query_id", F.round("cost", 6).alias("cost"))


@query("patch_fullscan_guided", f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l2('q.vals', 'p.vals', N_KNOWN)[:-8] + f' + 2 * list_sum([abs(q.vals[i] - p.vals[i]) for i in range({N_KNOWN + 1}, 65)]))::BIGINT', 1)}".replace("list_sum([(q", "(list_sum([(q", 1))
def patch_fullscan_guided(spark, sf_dir):
    """The unknown rows of the query stand for a guide raster's patch."""
    d = dictionary(spark, sf_dir)
    guide = lambda q, p: F.aggregate(F.zip_with(F.slice(q, N_KNOWN + 1, 64), F.slice(p, N_KNOWN + 1, 64), lambda a, b: F.abs(a.cast("long") - b)), F.lit(0).cast("long"), lambda s, x: s + x)
    local = lambda q, p: np.abs(p[:, N_KNOWN:] - q[N_KNOWN:]).sum(1)
    return knn.full_scan(queries_of(d), d, costs.guided(2, guide, local), 1, 1)


Z_DIMS, Z_BITS = 7, 8
H7 = sql.hadamard("vals", Z_DIMS)
BYTES = ", ".join(f"{sql.hadamard_byte(f'h{i}', i == 0)} AS b{i}" for i in range(Z_DIMS))
KEYED = f"""{sql.PATCHES}, h AS (SELECT patch_id, {', '.join(f'{e} AS h{i}' for i, e in enumerate(H7))} FROM emb),
b AS (SELECT patch_id, {BYTES} FROM h), keyed AS (SELECT *, ({sql.z_key([f'b{i}' for i in range(Z_DIMS)], Z_BITS)})::BIGINT AS zkey FROM b)"""


def keyed_patches(spark, sf_dir) -> DataFrame:
    d = dictionary(spark, sf_dir)
    coords = reduce.hadamard_coords(F.col("vals"), K, Z_DIMS)
    d = d.select("patch_id", *[reduce.hadamard_byte(c, K, i == 0).alias(f"b{i}") for i, c in enumerate(coords)])
    return d.withColumn("zkey", zcurve.z_key([F.col(f"b{i}") for i in range(Z_DIMS)], Z_BITS))


@query("zkey_hadamard", f"WITH {KEYED} SELECT patch_id, zkey, b0, b6 FROM keyed")
def zkey_hadamard(spark, sf_dir):
    return keyed_patches(spark, sf_dir).select("patch_id", "zkey", "b0", "b6")


@query("zkey_hex", f"WITH {KEYED} SELECT patch_id, lpad(upper(to_hex(zkey)), 14, '0') AS zkey FROM keyed")
def zkey_hex(spark, sf_dir):
    return keyed_patches(spark, sf_dir).select("patch_id", zcurve.z_key_hex(F.array(*[f"b{i}" for i in range(Z_DIMS)]), Z_DIMS).alias("zkey"))


@query("zdecode_roundtrip", f"WITH {KEYED} SELECT patch_id, b0, b1, b2, b3, b4, b5, b6 FROM keyed")
def zdecode_roundtrip(spark, sf_dir):
    c = zcurve.z_coords(F.col("zkey"), Z_DIMS)
    return keyed_patches(spark, sf_dir).select("patch_id", *[c[i].alias(f"b{i}") for i in range(Z_DIMS)])


GRID = "g AS (SELECT unnest(range(0, 8)) AS a), z AS (SELECT x.a AS x, y.a AS y, ({key})::BIGINT AS k FROM g x, g y)".format(key=sql.z_key(["x.a", "y.a"], 3))


@query("zless_grid", f"WITH {GRID} SELECT (p.x * 8 + p.y)::INTEGER AS p, (q.x * 8 + q.y)::INTEGER AS q, p.k < q.k AS less FROM z p, z q")
def zless_grid(spark, sf_dir):
    """The comparison without keys, on all pairs of an 8x8 grid."""
    p = spark.range(64).select(F.col("id").cast("int").alias("p"))
    at = lambda c: F.array(F.expr(f"{c} div 8"), F.col(c) % 8)
    pairs = p.withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(63))))
    return pairs.select("p", "q", zcurve.z_less(at("p"), at("q")).alias("less"))


def _boxes(spark) -> DataFrame:
    at = F.explode(F.sequence(F.lit(0), F.lit(7)))
    b = spark.range(8).select(F.col("id").cast("int").alias("x0")).withColumn("x1", at).withColumn("y0", at).withColumn("y1", at)
    return b.where("x0 <= x1 AND y0 <= y1")


KEY2 = lambda x, y: sql.z_key([x, y], 3)


@query("zinterval_containment", f"""WITH g AS (SELECT unnest(range(0, 8)) AS v),
b AS (SELECT a.v AS x0, c.v AS x1, d.v AS y0, e.v AS y1 FROM g a, g c, g d, g e WHERE a.v <= c.v AND d.v <= e.v),
p AS (SELECT a.v AS x, c.v AS y, ({KEY2('a.v', 'c.v')})::BIGINT AS k FROM g a, g c)
SELECT x0::INTEGER AS x0, x1::INTEGER AS x1, y0::INTEGER AS y0, y1::INTEGER AS y1, count(*) AS in_interval,
  count(CASE WHEN x BETWEEN x0 AND x1 AND y BETWEEN y0 AND y1 THEN 1 END) AS in_box
FROM b JOIN p ON k BETWEEN ({KEY2('x0', 'y0')}) AND ({KEY2('x1', 'y1')}) GROUP BY ALL""")
def zinterval_containment(spark, sf_dir):
    """Points in a box's key interval, and how many of them lie in the box (all of the box's)."""
    b = _boxes(spark).withColumn("lo", zcurve.z_key([F.col("x0"), F.col("y0")], 3)).withColumn("hi", zcurve.z_key([F.col("x1"), F.col("y1")], 3))
    points = b.withColumn("k", F.explode(F.sequence("lo", "hi"))).withColumn("c", zcurve.z_coords(F.col("k"), 2, 3))
    inside = F.col("c")[0].between(F.col("x0"), F.col("x1")) & F.col("c")[1].between(F.col("y0"), F.col("y1"))
    return points.groupBy("x0", "x1", "y0", "y1").agg(F.count("*").alias("in_interval"), F.count(F.when(inside, 1)).alias("in_box"))


@query("zsplit_grid", """WITH g AS (SELECT unnest(range(0, 8)) AS v),
b AS (SELECT a.v AS x0, c.v AS x1, d.v AS y0, e.v AS y1, xor(a.v, c.v) AS dx, xor(d.v, e.v) AS dy FROM g a, g c, g d, g e WHERE a.v <= c.v AND d.v <= e.v),
s AS (SELECT *, CASE WHEN dx >= 4 THEN 4 WHEN dx >= 2 THEN 2 ELSE dx END AS bx, CASE WHEN dy >= 4 THEN 4 WHEN dy >= 2 THEN 2 ELSE dy END AS ty FROM b WHERE dx + dy > 0)
SELECT x0::INTEGER AS x0, x1::INTEGER AS x1, y0::INTEGER AS y0, y1::INTEGER AS y1, CASE WHEN bx >= ty THEN 0 ELSE 1 END::INTEGER AS dim,
  (CASE WHEN bx >= ty THEN (x1 // bx) * bx ELSE (y1 // ty) * ty END - 1)::INTEGER AS cut FROM s""")
def zsplit_grid(spark, sf_dir):
    split = zcurve.z_split(F.array("x0", "y0"), F.array("x1", "y1"))
    return _boxes(spark).withColumn("s", split).where("s IS NOT NULL").select("x0", "x1", "y0", "y1", "s.dim", "s.cut")


LAST = {2: [0, 7], 3: [0, 0, 7], 4: [0, 0, 0, 7]}  # where the curve ends on a grid of side 8


@query("hilbert_neighbours", f"WITH {sql.PATCHES}, s AS (SELECT unnest([{', '.join(f'[{d}, CASE WHEN ' + ' AND '.join(f'vals[{i + 1}] // 32 = {v}' for i, v in enumerate(e)) + ' THEN 0 ELSE 1 END]' for d, e in LAST.items())}]) AS s FROM emb) SELECT s[1]::INTEGER AS dims, sum(s[2])::BIGINT AS steps, sum(s[2])::BIGINT AS unit_steps FROM s GROUP BY s[1]")
def hilbert_neighbours(spark, sf_dir):
    """On a Hilbert curve every step goes to a neighbouring cell: from each patch's first samples, as a cell of
    a grid of side 8 in 2, 3 and 4 dimensions, to the next cell of the whole curve."""
    out = None
    for dims in (2, 3, 4):
        cells = spark.range(8**dims).select(F.array(*[F.shiftright("id", 3 * i).bitwiseAND(F.lit(7)) for i in range(dims)]).alias("q"))
        after = cells.select((zcurve.h_key(F.col("q"), dims, 3) - 1).alias("at"), "q")
        own = dictionary(spark, sf_dir).select(F.array(*[F.expr(f"vals[{i}] div 32").cast("long") for i in range(dims)]).alias("p"))
        keyed = own.withColumn("at", zcurve.h_key(F.col("p"), dims, 3))
        step = F.aggregate(F.zip_with("p", "q", lambda a, b: F.abs(a - b)), F.lit(0).cast("long"), lambda s, x: s + x)
        row = keyed.join(after, "at").agg(F.lit(dims).alias("dims"), F.count("*").alias("steps"), F.count(F.when(step == 1, 1)).alias("unit_steps"))
        out = row if out is None else out.unionByName(row)
    return out


MU = 32


@query("block_catalog_hadamard", f"""WITH {KEYED}, n AS (SELECT *, ((row_number() OVER (ORDER BY zkey, patch_id) - 1) // {MU})::BIGINT AS block FROM keyed)
SELECT block, count(*) AS n, min(zkey)::BIGINT AS z_lo, max(zkey)::BIGINT AS z_hi, min(b0) AS lo0, max(b0) AS hi0, min(b1) AS lo1, max(b1) AS hi1 FROM n GROUP BY block""")
def block_catalog_hadamard(spark, sf_dir):
    """Blocks of one curve order; two-level numbering, so no window holds the whole dictionary."""
    keyed = keyed_patches(spark, sf_dir).withColumn("range", F.shiftright("zkey", 46))
    sizes = keyed.groupBy("range").agg(F.count("*").alias("m"))
    ahead = sizes.select("range", F.coalesce(F.sum("m").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("ahead"))  # 1024 key ranges at most
    order = Window.partitionBy("range").orderBy("zkey", "patch_id")
    numbered = keyed.withColumn("at", F.row_number().over(order) - 1).join(F.broadcast(ahead), "range")
    block = F.floor((F.col("at") + F.col("ahead")) / MU).cast("long")
    return numbered.groupBy(block.alias("block")).agg(F.count("*").alias("n"), F.min("zkey").alias("z_lo"), F.max("zkey").alias("z_hi"), *[f(f"b{i}").alias(f"{n}{i}") for i in (0, 1) for n, f in (("lo", F.min), ("hi", F.max))])


H10 = sql.hadamard("vals", 10)
KNN_SQL = f"""WITH {sql.PATCHES}, h AS (SELECT patch_id, [{', '.join(H10)}] AS c FROM emb),
s AS (SELECT q.patch_id AS query_id, p.patch_id AS patch_id, list_sum([(q.c[i] - p.c[i]) * (q.c[i] - p.c[i]) for i in range(1, 11)]) / 64.0 AS dist2
  FROM h q JOIN h p ON p.patch_id <> q.patch_id WHERE q.patch_id % {sql.EVERY} = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist2, patch_id)::INTEGER AS rank FROM s)"""


def hadamard_index(spark, sf_dir, mu: int = MU):
    d = dictionary(spark, sf_dir)
    fps, bases = whole_basis(10)
    return d, queries_of(d, K).withColumn("index_id", F.lit(0)), zindex.build_index(d, fps, K, 10, mu, bases)


@query("zcurve_knn_hadamard", f"{KNN_SQL} SELECT query_id, rank, patch_id, round(dist2::DOUBLE, 6) AS dist2 FROM r WHERE rank <= 10")
def zcurve_knn_hadamard(spark, sf_dir):
    _, q, index = hadamard_index(spark, sf_dir)
    return knn.zcurve_knn(q, index, 10, 1).select("query_id", "rank", "patch_id", F.round("dist2", 6).alias("dist2"))


AE_SQL = f"""{KNN_SQL}, t AS (SELECT q.patch_id AS query_id, p.patch_id AS patch_id, {sql.l2('q.vals', 'p.vals', 64)} AS cost
  FROM emb q JOIN emb p ON p.patch_id <> q.patch_id WHERE q.patch_id % {sql.EVERY} = 0),
e AS (SELECT query_id, min(cost) AS exact FROM t GROUP BY query_id),
k AS (SELECT unnest([1, 5, 10, 20]) AS k),
a AS (SELECT k, r.query_id, min(t.cost) AS approx FROM k JOIN r ON r.rank <= k JOIN t USING (query_id, patch_id) GROUP BY ALL),
x AS (SELECT k, query_id, sqrt(approx) / sqrt(exact) - 1 AS ae FROM a JOIN e USING (query_id))"""


@query("acceleration_error_hadamard", f"{AE_SQL} SELECT k::INTEGER AS k, count(*) AS n, round(avg(ae), 6) AS ae_mean, round(max(ae), 6) AS ae_max FROM x GROUP BY k")
def acceleration_error_hadamard(spark, sf_dir):
    d, q, index = hadamard_index(spark, sf_dir)
    near = knn.zcurve_knn(q, index, 20, 1)
    exact = knn.full_scan(q, d, costs.l2(), 1, 1)
    return metrics.error_by_k(near, q, d, exact, (1, 5, 10, 20)).groupBy("k").agg(F.count("*").alias("n"), F.round(F.avg("ae"), 6).alias("ae_mean"), F.round(F.max("ae"), 6).alias("ae_max"))


@query("ae_cube", f"{AE_SQL}, c AS (SELECT k, (query_id // {sql.EVERY}) % 2 AS half, ae FROM x) SELECT k::INTEGER AS k, half::BIGINT AS half, count(*) AS n, round(avg(ae), 6) AS ae_mean FROM c GROUP BY CUBE (k, half)")
def ae_cube(spark, sf_dir):
    d, q, index = hadamard_index(spark, sf_dir)
    near = knn.zcurve_knn(q, index, 20, 1)
    e = metrics.error_by_k(near, q, d, knn.full_scan(q, d, costs.l2(), 1, 1), (1, 5, 10, 20))
    e = e.withColumn("half", F.expr(f"query_id div {sql.EVERY} % 2"))
    return e.cube("k", "half").agg(F.count("*").alias("n"), F.round(F.avg("ae"), 6).alias("ae_mean"))


@query("recall_at_k", f"""{KNN_SQL}, t AS (SELECT q.patch_id AS query_id, p.patch_id AS patch_id, row_number() OVER (PARTITION BY q.patch_id ORDER BY {sql.l2('q.vals', 'p.vals', 64)}, p.patch_id) AS true_rank
  FROM emb q JOIN emb p ON p.patch_id <> q.patch_id WHERE q.patch_id % {sql.EVERY} = 0)
SELECT t.query_id, count(r.patch_id) AS found, round(count(r.patch_id) / 10.0, 6)::DOUBLE AS recall FROM t LEFT JOIN (SELECT * FROM r WHERE rank <= 20) r USING (query_id, patch_id) WHERE true_rank <= 10 GROUP BY t.query_id""")
def recall_at_k(spark, sf_dir):
    d, q, index = hadamard_index(spark, sf_dir)
    return metrics.recall(knn.zcurve_knn(q, index, 20, 1), knn.full_scan(q, d, costs.l2(), 10, 1), 10)


SQL_SCAN = f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l2('q.vals', 'p.vals', N_KNOWN), 1).replace('SELECT query_id, rank, patch_id', 'SELECT query_id, patch_id')}"


@query("zcurve_search_exact", f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l2('q.vals', 'p.vals', N_KNOWN), 1).replace('SELECT query_id, rank, patch_id', 'SELECT query_id, patch_id')}")
def zcurve_search_exact(spark, sf_dir):
    """Principal components, curve, blocks and exact refinement; the answer is the full scan's."""
    d = dictionary(spark, sf_dir)
    index = zindex.build_index(d, FPS, K, 10, MU)
    return knn.search(queries_of(d), index, d, 10, costs.l2(), exact=True, exclude_radius=1).select("query_id", "patch_id", "cost")


@query("zcurve_search_exact_l1", f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l1('q.vals', 'p.vals', N_KNOWN), 1).replace('SELECT query_id, rank, patch_id', 'SELECT query_id, patch_id')}")
def zcurve_search_exact_l1(spark, sf_dir):
    d = dictionary(spark, sf_dir)
    index = zindex.build_index(d, FPS, K, 14, MU)
    return knn.search(queries_of(d), index, d, 20, costs.l1(), exact=True, exclude_radius=1).select("query_id", "patch_id", "cost")


@query("zcurve_search")
def zcurve_search(spark, sf_dir):
    """The approximate method as published: k candidates, best by true cost."""
    d = dictionary(spark, sf_dir)
    index = zindex.build_index(d, FPS, K, 10, MU)
    return knn.search(queries_of(d), index, d, 80, costs.l2(), exclude_radius=1)


@query("search_counters")
def search_counters(spark, sf_dir):
    d = dictionary(spark, sf_dir)
    index = zindex.build_index(d, FPS, K, 10, MU)
    chosen = fpx.select_index(queries_of(d), FPS)
    return knn.zcurve_knn(chosen, index, 10, 1, counters=True)
