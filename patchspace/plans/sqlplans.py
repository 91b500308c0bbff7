"""Queries written in SQL over the registered functions."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.functions import zcurve
from patchspace.functions.register import register
from patchspace.plans import core, sql
from patchspace.plans.registry import query


@query("sql_udf_masked_l2", f"WITH {sql.PATCHES} SELECT q.patch_id AS query_id, min({sql.l2('q.vals', 'p.vals', core.N_KNOWN)})::BIGINT AS cost FROM emb q JOIN emb p ON p.patch_id <> q.patch_id WHERE q.patch_id % {sql.EVERY} = 0 GROUP BY q.patch_id")
def sql_udf_masked_l2(spark, sf_dir):
    register(spark)
    d = core.dictionary(spark, sf_dir)
    q = core.queries_of(d).select("query_id", F.col("vals").alias("q_vals"), "known")
    pairs = d.join(q, F.col("patch_id") != F.col("query_id"))
    return pairs.groupBy("query_id").agg(F.min(F.expr("masked_l2(q_vals, vals, known)")).alias("cost"))


BITS = 8
AT = f"SELECT patch_id, vals[1] AS x, vals[2] AS y, ({sql.z_key(['vals[1]', 'vals[2]'], BITS)})::BIGINT AS k, ({sql.z_key(['vals[3]', 'vals[4]'], BITS)})::BIGINT AS next FROM emb"
POINT = "array(CAST(vals[0] AS INT), CAST(vals[1] AS INT))"  # a patch's first two samples


def points(spark, sf_dir):
    register(spark)
    return core.dictionary(spark, sf_dir)


@query("sql_z_encode", f"WITH {sql.PATCHES} SELECT patch_id, k FROM ({AT})")
def sql_z_encode(spark, sf_dir):
    return points(spark, sf_dir).select("patch_id", F.expr(f"z_encode({POINT}, {BITS})").alias("k"))


@query("udtf_zranges", f"""WITH {core.GRID}, k AS (SELECT k, k - row_number() OVER (ORDER BY k) AS g FROM z WHERE x BETWEEN 1 AND 4 AND y BETWEEN 2 AND 5)
SELECT min(k)::BIGINT AS z_lo, max(k)::BIGINT AS z_hi FROM k GROUP BY g""")
def udtf_zranges(spark, sf_dir):
    """With enough ranges the cover of a box is exact."""
    register(spark)
    return spark.sql("SELECT * FROM z_ranges(array(1, 2), array(4, 5), 3, 64)")


@query("udaf_topk_merge", "SELECT user_id, string_agg(event_id::VARCHAR, ',' ORDER BY value DESC, event_id) AS best FROM (SELECT * FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) <= 4) GROUP BY user_id")
def udaf_topk_merge(spark, sf_dir):
    """The first four of each task's rows of a key, merged by sort and slice: a list never holds more
    than four rows of a task."""
    from patchspace.shared import table

    t = table(sf_dir, "events", spark).withColumn("p", F.spark_partition_id())
    order = Window.partitionBy("user_id", "p").orderBy(F.desc("value"), "event_id")
    few = t.withColumn("r", F.row_number().over(order)).where("r <= 4")
    key = F.struct((-F.col("value")).alias("v"), "event_id")
    best = few.groupBy("user_id").agg(F.slice(F.array_sort(F.collect_list(key)), 1, 4).alias("top"))
    return best.select("user_id", F.array_join(F.transform("top", lambda s: s["event_id"].cast("string")), ",").alias("best"))


@query("sql_box_dist2", f"""WITH {sql.PATCHES} SELECT patch_id,
  (greatest(64 - x, x - 96, 0) ** 2 + greatest(96 - y, y - 160, 0) ** 2)::DOUBLE AS d FROM ({AT})""")
def sql_box_dist2(spark, sf_dir):
    return points(spark, sf_dir).select("patch_id", F.expr("box_dist2(array(double(vals[0]), double(vals[1])), array(64D, 96D), array(96D, 160D))").alias("d"))


@query("sql_z_decode", f"WITH {sql.PATCHES} SELECT patch_id, k, x::INTEGER AS x, y::INTEGER AS y FROM ({AT})")
def sql_z_decode(spark, sf_dir):
    k = zcurve.z_key([F.col("vals")[0], F.col("vals")[1]], BITS)
    p = points(spark, sf_dir).select("patch_id", k.alias("k")).withColumn("p", F.expr(f"z_decode(k, 2, {BITS})"))
    return p.select("patch_id", "k", F.col("p")[0].alias("x"), F.col("p")[1].alias("y"))


@query("sql_z_less", f"WITH {sql.PATCHES} SELECT patch_id, k < next AS less FROM ({AT})")
def sql_z_less(spark, sf_dir):
    """A patch's first two samples before its next two on the curve."""
    after = "array(CAST(vals[2] AS INT), CAST(vals[3] AS INT))"
    return points(spark, sf_dir).select("patch_id", F.expr(f"z_less({POINT}, {after})").alias("less"))
