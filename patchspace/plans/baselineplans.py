"""Baselines as registered queries."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from patchspace.functions import costs
from patchspace.functions.portable import portable_hash, portable_hash_sql
from patchspace.operators import knn, pairs, patches
from patchspace.operators.baselines import plans as base
from patchspace.plans import core, sql
from patchspace.plans.rasterplans import DAMAGED, FRONT, WINDOWS, K, damaged
from patchspace.plans.registry import query
from patchspace.shared import staged

SCAN1 = f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l2('q.vals', 'p.vals', core.N_KNOWN), 1).replace('SELECT query_id, rank, patch_id', 'SELECT query_id, patch_id')}"


def coords(spark, sf_dir):
    """(points, queries) in the integer Walsh space."""
    from patchspace.operators import reduce

    d = core.dictionary(spark, sf_dir)
    c = reduce.hadamard_coords(F.col("vals"), core.K, 10)
    p = d.select("patch_id", F.array(*[x.cast("double") / 8 for x in c]).alias("coord"))
    return p, p.where(F.col("patch_id") % sql.EVERY == 0).select(F.col("patch_id").alias("query_id"), "coord")


KNN10 = f"{core.KNN_SQL} SELECT query_id, rank, patch_id, round(dist2::DOUBLE, 6) AS dist2 FROM r WHERE rank <= 10"


@query("idistance_knn_exact", KNN10)
def idistance_knn_exact(spark, sf_dir):
    p, q = coords(spark, sf_dir)
    keyed, centres = base.idistance_build(p, 8)
    return base.idistance_knn(q, keyed, centres, 10, 64.0).select("query_id", "rank", "patch_id", F.round("dist2", 6).alias("dist2"))


@query("early_stop_exact", SCAN1)
def early_stop_exact(spark, sf_dir):
    d = core.dictionary(spark, sf_dir)
    return base.early_stop_scan(core.queries_of(d), d)


@query("frequency_exact", f"WITH {sql.PATCHES}, {sql.ranked_scan(sql.l2('q.vals', 'p.vals', 64), 1).replace('SELECT query_id, rank, patch_id', 'SELECT query_id, patch_id')}")
def frequency_exact(spark, sf_dir):
    """Few low-frequency coefficients as filter, refined until nothing nearer can remain."""
    from patchspace.operators import zindex

    d = core.dictionary(spark, sf_dir)
    fps, bases = core.whole_basis(12)
    index = zindex.build_index(d, fps, core.K, 12, core.MU, bases)
    return knn.search(core.queries_of(d, core.K), index, d, 10, costs.l2(), exact=True, exclude_radius=1).select("query_id", "patch_id", "cost")


TARGETS = f"{DAMAGED}, {FRONT}, {WINDOWS}, q AS (SELECT p.* FROM patches p JOIN front f ON f.image_id = p.image_id AND f.y = cy AND f.x = cx)"
COST = "list_sum([CASE WHEN q.known[i] THEN (q.vals[i] - d.vals[i]) * (q.vals[i] - d.vals[i]) ELSE 0 END for i in range(1, 26)])::BIGINT"


def targets(spark, sf_dir):
    r = staged(damaged(spark, sf_dir), "targets-raster")
    return staged(patches.active_patches(patches.fill_front(r), r, K), "targets"), staged(patches.build_dictionary(r, K), "targets-patches")


@query("window_knn", f"{TARGETS}, s AS (SELECT q.patch_id AS query_id, d.patch_id, {COST} AS cost FROM q JOIN patches d ON d.image_id = q.image_id AND d.n_known = 25 AND abs(d.cy - q.cy) <= 12 AND abs(d.cx - q.cx) <= 12) SELECT query_id, 1::INTEGER AS rank, patch_id, cost FROM s QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cost, patch_id) = 1")
def window_knn(spark, sf_dir):
    q, d = targets(spark, sf_dir)
    return base.window_knn(q, d, 12)


@query("local_diameter_knn", f"""{TARGETS}, u AS (SELECT *, [v for v in vals if v IS NOT NULL] AS own FROM q), r AS (SELECT *, least(24, greatest(6, floor(sqrt(greatest(0, list_sum([v * v for v in own])::DOUBLE / len(own) - (list_sum(own)::DOUBLE / len(own)) * (list_sum(own)::DOUBLE / len(own)))) * 24 / 64))) AS reach FROM u),
s AS (SELECT q.patch_id AS query_id, d.patch_id, {COST} AS cost FROM r q JOIN patches d ON d.image_id = q.image_id AND d.n_known = 25 AND abs(d.cy - q.cy) <= reach AND abs(d.cx - q.cx) <= reach)
SELECT query_id, 1::INTEGER AS rank, patch_id, cost FROM s QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cost, patch_id) = 1""")
def local_diameter_knn(spark, sf_dir):
    q, d = targets(spark, sf_dir)
    return base.local_diameter_knn(q, d, 24)


SIDE, TOP, BINS = 16, 3, 8


def _bin(v: str) -> str:
    return f"least(floor({v} * {BINS} / 256), {BINS - 1})"


CONTEXT = f"""{TARGETS}, h AS (SELECT image_id, cy // {SIDE} AS gy, cx // {SIDE} AS gx, {", ".join(f"count(*) FILTER (WHERE {_bin('vals[13]')} = {i})::DOUBLE / count(*) AS h{i}" for i in range(BINS))}
  FROM patches WHERE n_known = 25 GROUP BY ALL),
u AS (SELECT *, [v for v in vals if v IS NOT NULL] AS own FROM q),
c AS (SELECT *, {", ".join(f"len([v for v in own if {_bin('v')} = {i}])::DOUBLE / greatest(len(own), 1) AS c{i}" for i in range(BINS))} FROM u),
best AS (SELECT c.*, gy, gx FROM c JOIN h USING (image_id)
  QUALIFY row_number() OVER (PARTITION BY patch_id ORDER BY {" + ".join(f"sqrt(c{i} * h{i})" for i in range(BINS))} DESC, gy, gx) <= {TOP}),
s AS (SELECT q.patch_id AS query_id, d.patch_id, {COST} AS cost FROM best q JOIN patches d ON d.image_id = q.image_id AND d.n_known = 25 AND d.cy // {SIDE} = gy AND d.cx // {SIDE} = gx)
SELECT query_id, patch_id, cost FROM s QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cost, patch_id) = 1"""


@query("block_context_knn", CONTEXT)
def block_context_knn(spark, sf_dir):
    q, d = targets(spark, sf_dir)
    return base.block_context_knn(q, d, SIDE, TOP, BINS)


MATCHES = f"{TARGETS}, s AS (SELECT q.patch_id AS query_id, d.patch_id, d.cy - q.cy AS dy, d.cx - q.cx AS dx, {COST} AS cost FROM q JOIN patches d ON d.n_known = 25), b AS (SELECT * FROM s QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cost, patch_id) = 1)"


@query("offset_histogram", f"{MATCHES} SELECT dy::BIGINT AS dy, dx::BIGINT AS dx, count(*) AS n FROM b GROUP BY ALL")
def offset_histogram(spark, sf_dir):
    q, d = targets(spark, sf_dir)
    return base.offset_histogram(knn.full_scan(q, d))


FEW = portable_hash_sql("patch_id") + f" < {(1 << 31) // 32}"


@query("offset_stats_knn", f"""{TARGETS}, f AS (SELECT * FROM patches WHERE n_known = 25 AND {FEW}),
m AS (SELECT q.patch_id AS query_id, d.cy - q.cy AS dy, d.cx - q.cx AS dx, d.patch_id, list_sum([(q.vals[i] - d.vals[i]) * (q.vals[i] - d.vals[i]) for i in range(1, 26)]) AS cost FROM f q JOIN patches d ON d.n_known = 25 AND (abs(d.cy - q.cy) >= {K} OR abs(d.cx - q.cx) >= {K})),
b AS (SELECT * FROM m QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cost, patch_id) = 1),
top AS (SELECT dy, dx, count(*) AS n FROM b GROUP BY ALL ORDER BY n DESC, dy, dx LIMIT 20),
s AS (SELECT q.patch_id AS query_id, d.patch_id, {COST} AS cost FROM q JOIN top ON true JOIN patches d ON d.n_known = 25 AND d.cy = q.cy + top.dy AND d.cx = q.cx + top.dx)
SELECT query_id, patch_id, cost FROM s QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cost, patch_id) = 1""")
def offset_stats_knn(spark, sf_dir):
    """Offsets come from known patches matched among themselves: a hash share of them, against all."""
    q, d = targets(spark, sf_dir)
    few = d.where(portable_hash(F.col("patch_id")) < (1 << 31) // 32)
    whole = few.select(F.col("patch_id").alias("query_id"), "image_id", "cy", "cx", "vals", F.transform("vals", lambda _: F.lit(True)).alias("known"))
    return base.offset_stats_knn(q, d, base.offset_histogram(knn.full_scan(whole, d, exclude_radius=K)), 20)


@query("tsvq_knn")
def tsvq_knn(spark, sf_dir):
    p, q = coords(spark, sf_dir)
    return base.tsvq_knn(q, p)


@query("lsh_knn")
def lsh_knn(spark, sf_dir):
    p, q = coords(spark, sf_dir)
    return base.lsh_knn(q, p, 10, 120.0)


@query("propagation_nnf")
def propagation_nnf(spark, sf_dir):
    _, d = targets(spark, sf_dir)
    return base.propagation_field(d, K, 2)


@query("diffuse_step", f"""{DAMAGED}, n AS (SELECT a.image_id, a.y, a.x, avg(b.pix) AS m FROM damaged a JOIN damaged b ON a.image_id = b.image_id AND abs(a.y - b.y) + abs(a.x - b.x) = 1 AND a.y BETWEEN b.y - 1 AND b.y + 1 WHERE b.pix IS NOT NULL GROUP BY ALL)
SELECT d.image_id, d.y, d.x, coalesce(CASE WHEN d.known THEN d.pix ELSE round(m) END, -1)::BIGINT AS pix FROM damaged d LEFT JOIN n USING (image_id, y, x)""")
def diffuse_step(spark, sf_dir):
    out = base.diffuse_step(damaged(spark, sf_dir))
    return out.select("image_id", "y", "x", F.coalesce(F.col("pix")[0], F.lit(-1)).cast("long").alias("pix"))


@query("set_candidates", f"""{core.KNN_SQL}, t AS (SELECT q.patch_id AS query_id, p.patch_id, row_number() OVER (PARTITION BY q.patch_id ORDER BY {sql.l2('q.vals', 'p.vals', 64)}, p.patch_id) AS k FROM emb q JOIN emb p ON p.patch_id <> q.patch_id WHERE q.patch_id % {sql.EVERY} = 0),
a AS (SELECT query_id, patch_id FROM r WHERE rank <= 10), b AS (SELECT query_id, patch_id FROM t WHERE k <= 10)
SELECT 'both' AS part, count(*) AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'filter only', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)
UNION ALL SELECT 'either', count(*) FROM (SELECT * FROM a UNION SELECT * FROM b)""")
def set_candidates(spark, sf_dir):
    d, q, index = core.hadamard_index(spark, sf_dir)
    a = knn.zcurve_knn(q, index, 10, 1).select("query_id", "patch_id")
    b = knn.full_scan(q, d, costs.l2(), 10, 1).select("query_id", "patch_id")
    count = lambda df, name: df.agg(F.lit(name).alias("part"), F.count("*").alias("n"))
    return count(a.intersect(b), "both").unionByName(count(a.exceptAll(b), "filter only")).unionByName(count(a.union(b).distinct(), "either"))


@query("random_projection_preservation")
def random_projection_preservation(spark, sf_dir):
    """Reduced over true distance, for components and for random signs: all pairs, none written out."""
    from patchspace.operators import footprints, reduce

    d = core.dictionary(spark, sf_dir)
    q = core.queries_of(d, core.K)
    fp = [footprints.Footprint(0, "all", tuple(range(64)))]
    square, out = costs.l2().block, None
    for name, fit in (("components", reduce.fit_pca), ("random", reduce.fit_random)):
        rows = fit(d, fp, 10)[0].loadings

        def reduced(q, p, rows=rows):
            a, b = q.vals @ rows.T, p.vals @ rows.T
            return np.sqrt(sum((a[:, i, None] - b[None, :, i]) ** 2 for i in range(len(rows))))

        row = pairs.ratios(q, d, reduced, lambda q, p: np.sqrt(square(q.vals, p.vals, q.known)), 1).withColumn("basis", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@query("lda_basis")
def lda_basis(spark, sf_dir):
    from patchspace.operators import reduce
    from patchspace.shared import table

    labels = table(sf_dir, "embeddings", spark).select(F.col("vec_id").alias("patch_id"), "label")
    bases = reduce.fit_lda(core.dictionary(spark, sf_dir), labels, core.FPS[:1], 9)
    return spark.createDataFrame([(b.index_id, len(b.loadings), float(b.explained)) for b in bases], "index_id int, dims int, explained double")
