"""Relational operators a user needs around the methods, each with a SQL twin."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.functions.portable import cents
from patchspace.plans import core, sql
from patchspace.plans.rasterplans import DAMAGED, FRONT, MARKET, damaged, flat, market
from patchspace.plans.registry import query
from patchspace.shared import new_path, table
from patchspace.sources.rasters import week_of


@query("cells_scan_pruned", "SELECT l_quantity::INTEGER AS quantity, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS v FROM lineitem WHERE l_discount >= 0.05 AND l_quantity < 25 GROUP BY ALL")
def cells_scan_pruned(spark, sf_dir):
    """Three columns are read, both filters reach the scan."""
    t = table(sf_dir, "lineitem", spark).where((F.col("l_discount") >= 0.05) & (F.col("l_quantity") < 25))
    return t.groupBy(F.col("l_quantity").cast("int").alias("quantity")).agg(F.sum(cents(F.col("l_extendedprice"))).alias("v"))


@query("cells_box_filter", f"WITH {MARKET} SELECT image_id, y, x, pix::BIGINT AS pix FROM raster WHERE y BETWEEN 10 AND 20 AND x BETWEEN 30 AND 50")
def cells_box_filter(spark, sf_dir):
    return flat(market(spark, sf_dir)).where(F.col("y").between(10, 20) & F.col("x").between(30, 50))


@query("front_semi_join", f"{DAMAGED}, {FRONT} SELECT d.image_id, d.y, d.x, d.pix::BIGINT AS pix FROM damaged d SEMI JOIN front f ON d.image_id = f.image_id AND d.y = f.y AND d.x = f.x")
def front_semi_join(spark, sf_dir):
    from patchspace.operators.patches import fill_front

    r = damaged(spark, sf_dir)
    return flat(r.join(fill_front(r), ["image_id", "y", "x"], "left_semi"))


SLOT = "(datediff('day', DATE '2024-01-01', ts::DATE) * 4 + hour(ts) // 6)::INTEGER"


def slots(spark, sf_dir):
    ts = F.col("ts")
    return table(sf_dir, "events", spark).select("user_id", (F.datediff(ts, F.lit("2024-01-01")) * 4 + F.floor(F.hour(ts) / 6)).cast("int").alias("slot"), "ts", "event_id", "value", "event_type", "props")


@query("gap_anti_join", f"SELECT u.user_id, s.slot::INTEGER AS slot FROM (SELECT DISTINCT user_id FROM events WHERE user_id < 20) u, (SELECT unnest(range(0, 120)) AS slot) s ANTI JOIN (SELECT DISTINCT user_id, {SLOT} AS slot FROM events) e USING (user_id, slot)".replace("u, (SELECT unnest", "u CROSS JOIN (SELECT unnest"))
def gap_anti_join(spark, sf_dir):
    e = slots(spark, sf_dir).select("user_id", "slot").distinct()
    full = e.where("user_id < 20").select("user_id").distinct().withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(119))))
    return full.join(e, ["user_id", "slot"], "left_anti")


@query("grid_full_outer", f"WITH a AS (SELECT user_id, count(*) AS early FROM events WHERE {SLOT} < 60 GROUP BY user_id), b AS (SELECT user_id, count(*) AS late FROM events WHERE {SLOT} >= 60 GROUP BY user_id) SELECT user_id, coalesce(early, 0) AS early, coalesce(late, 0) AS late FROM a FULL JOIN b USING (user_id)")
def grid_full_outer(spark, sf_dir):
    s = slots(spark, sf_dir)
    a = s.where("slot < 60").groupBy("user_id").agg(F.count("*").alias("early"))
    b = s.where("slot >= 60").groupBy("user_id").agg(F.count("*").alias("late"))
    return a.join(b, "user_id", "full").select("user_id", F.coalesce("early", F.lit(0)).alias("early"), F.coalesce("late", F.lit(0)).alias("late"))


@query("cover_broadcast_join", f"WITH {sql.footprint_rows()} SELECT kind, count(*) AS n, sum(len(pos))::BIGINT AS cells FROM fp, (SELECT vec_id FROM embeddings WHERE vec_id % 20 = 0) GROUP BY kind")
def cover_broadcast_join(spark, sf_dir):
    from patchspace.operators.footprints import footprint_table

    q = core.dictionary(spark, sf_dir).where(F.col("patch_id") % sql.EVERY == 0).select("patch_id")
    return q.join(F.broadcast(footprint_table(spark, sql.FP8)), F.lit(True)).groupBy("kind").agg(F.count("*").alias("n"), F.sum(F.size("pos")).alias("cells"))


@query("refine_merge_join", f"WITH {sql.PATCHES} SELECT e.patch_id, list_sum(e.vals)::BIGINT AS total, l.label FROM emb e JOIN embeddings l ON l.vec_id = e.patch_id")
def refine_merge_join(spark, sf_dir):
    d = core.dictionary(spark, sf_dir).select("patch_id", F.aggregate("vals", F.lit(0).cast("long"), lambda s, v: s + v).alias("total"))
    labels = table(sf_dir, "embeddings", spark).select(F.col("vec_id").alias("patch_id"), "label")
    return d.join(labels.hint("merge"), "patch_id")


@query("zrange_block_join", f"""WITH {core.KEYED}, q AS (SELECT patch_id AS query_id, zkey AS k FROM keyed WHERE patch_id % 25 = 0)
SELECT query_id, count(*) AS n, min(patch_id) AS least FROM q JOIN keyed ON zkey BETWEEN k - 70368744177664 AND k + 70368744177664 GROUP BY query_id""")
def zrange_block_join(spark, sf_dir):
    """A range join on curve keys, rewritten to an equi-join on key blocks of the range's width."""
    width = 1 << 46
    keyed = core.keyed_patches(spark, sf_dir).select("patch_id", "zkey").withColumn("block", F.shiftright("zkey", 46))
    q = keyed.where("patch_id % 25 = 0").select(F.col("patch_id").alias("query_id"), F.col("zkey").alias("k"), F.explode(F.array(*[F.col("block") + i for i in (-1, 0, 1)])).alias("block"))
    near = q.join(keyed, "block").where(F.abs(F.col("zkey") - F.col("k")) <= width)
    return near.groupBy("query_id").agg(F.count("*").alias("n"), F.min("patch_id").alias("least"))


WORK = f"SELECT l_linenumber::INTEGER AS line, {sql.WEEK} % 4 AS phase, round(l_extendedprice * 100)::BIGINT AS v FROM lineitem"


def work(spark, sf_dir):
    return table(sf_dir, "lineitem", spark).select(F.col("l_linenumber").cast("int").alias("line"), F.pmod(week_of(F.col("l_shipdate")), F.lit(4)).alias("phase"), cents(F.col("l_extendedprice")).alias("v"))


@query("work_rollup", f"SELECT coalesce(line, -1)::INTEGER AS line, coalesce(phase, -1)::INTEGER AS phase, count(*) AS n, sum(v)::BIGINT AS v FROM ({WORK}) GROUP BY ROLLUP (line, phase)")
def work_rollup(spark, sf_dir):
    g = work(spark, sf_dir).rollup("line", "phase").agg(F.count("*").alias("n"), F.sum("v").alias("v"))
    return g.select(F.coalesce("line", F.lit(-1)).alias("line"), F.coalesce("phase", F.lit(-1)).alias("phase"), "n", "v")


@query("work_grouping_sets", f"SELECT coalesce(line, -1)::INTEGER AS line, coalesce(phase, -1)::INTEGER AS phase, count(*) AS n FROM ({WORK}) GROUP BY GROUPING SETS ((line), (phase), ())")
def work_grouping_sets(spark, sf_dir):
    g = work(spark, sf_dir).groupingSets([["line"], ["phase"], []], "line", "phase").agg(F.count("*").alias("n"))
    return g.select(F.coalesce("line", F.lit(-1)).alias("line"), F.coalesce("phase", F.lit(-1)).alias("phase"), "n")


@query("approx_distinct_zkeys")
def approx_distinct_zkeys(spark, sf_dir):
    return core.keyed_patches(spark, sf_dir).agg(F.approx_count_distinct("zkey").alias("approx"), F.countDistinct("zkey").alias("exact"))


@query("cost_quantiles", "SELECT l_linenumber::INTEGER AS line, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY l_linenumber")
def cost_quantiles(spark, sf_dir):
    t = table(sf_dir, "lineitem", spark)
    return t.groupBy(F.col("l_linenumber").cast("int").alias("line")).agg(F.round(F.percentile("l_extendedprice", 0.5), 4).alias("median"), F.round(F.percentile("l_extendedprice", 0.9), 4).alias("p90"))


@query("gradient_window", f"WITH {MARKET} SELECT image_id, y, x, (coalesce(lead(pix) OVER r, pix) - coalesce(lag(pix) OVER r, pix))::BIGINT AS gx, (coalesce(lead(pix) OVER c, pix) - coalesce(lag(pix) OVER c, pix))::BIGINT AS gy FROM raster WINDOW r AS (PARTITION BY image_id, y ORDER BY x), c AS (PARTITION BY image_id, x ORDER BY y)")
def gradient_window(spark, sf_dir):
    r, c = Window.partitionBy("image_id", "y").orderBy("x"), Window.partitionBy("image_id", "x").orderBy("y")
    d = lambda w: (F.coalesce(F.lead("pix").over(w), F.col("pix")) - F.coalesce(F.lag("pix").over(w), F.col("pix"))).cast("long")
    return flat(market(spark, sf_dir)).select("image_id", "y", "x", d(r).alias("gx"), d(c).alias("gy"))


@query("topk_per_query", "SELECT user_id, rank::INTEGER AS rank, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS rank FROM events) WHERE rank <= 3")
def topk_per_query(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    return table(sf_dir, "events", spark).select("user_id", "event_id", F.row_number().over(w).alias("rank")).where("rank <= 3")


@query("zorder_top_n", f"WITH {core.KEYED} SELECT patch_id, zkey FROM keyed ORDER BY zkey DESC, patch_id LIMIT 25")
def zorder_top_n(spark, sf_dir):
    return core.keyed_patches(spark, sf_dir).select("patch_id", "zkey").orderBy(F.desc("zkey"), "patch_id").limit(25)


def parts(d):
    """Samples of the patches ``d`` under the edge footprints, and under those of corners."""
    from patchspace.operators.footprints import footprint_table

    t = F.broadcast(footprint_table(d.sparkSession, sql.FP8).select("kind", F.explode("pos").alias("pos")))  # 8 footprints
    t = d.join(t, F.lit(True)).select("patch_id", "kind", "pos", F.element_at("vals", F.col("pos") + 1).cast("long").alias("v"))
    return t.where("kind = 'edge'").drop("kind"), t.where("kind = 'corner'").drop("kind")


def stated(spark, sf_dir):
    """The patches of the stated queries."""
    return core.dictionary(spark, sf_dir).where(F.col("patch_id") % sql.EVERY == 0)


def ec(where: str) -> str:
    return f"WITH {sql.PATCHES}, {sql.footprint_rows()}, t AS (SELECT kind, unnest(pos)::INTEGER AS pos FROM fp), u AS (SELECT patch_id, kind, pos, vals[pos + 1] AS v FROM emb, t{where}), e AS (SELECT patch_id, pos, v FROM u WHERE kind = 'edge'), c AS (SELECT patch_id, pos, v FROM u WHERE kind = 'corner')"


EC = ec(f" WHERE patch_id % {sql.EVERY} = 0")


@query("footprint_union", f"{ec('')} SELECT * FROM e UNION SELECT * FROM c")
def footprint_union(spark, sf_dir):
    """Of every patch of the table."""
    e, c = parts(core.dictionary(spark, sf_dir))
    return e.union(c).distinct()


@query("footprint_intersect", f"{EC} SELECT * FROM e INTERSECT SELECT * FROM c")
def footprint_intersect(spark, sf_dir):
    e, c = parts(stated(spark, sf_dir))
    return e.intersect(c)


@query("footprint_except", f"{EC} SELECT * FROM e EXCEPT ALL SELECT * FROM c")
def footprint_except(spark, sf_dir):
    e, c = parts(stated(spark, sf_dir))
    return e.exceptAll(c)


@query("grid_pivot", f"SELECT line, sum(CASE WHEN phase = 0 THEN v END)::BIGINT AS p0, sum(CASE WHEN phase = 1 THEN v END)::BIGINT AS p1, sum(CASE WHEN phase = 2 THEN v END)::BIGINT AS p2, sum(CASE WHEN phase = 3 THEN v END)::BIGINT AS p3 FROM ({WORK}) GROUP BY line")
def grid_pivot(spark, sf_dir):
    p = work(spark, sf_dir).groupBy("line").pivot("phase", [0, 1, 2, 3]).agg(F.sum("v"))
    return p.select("line", *[F.col(str(i)).alias(f"p{i}") for i in range(4)])


@query("grid_unpivot", f"SELECT line, 'p' || phase AS phase, sum(v)::BIGINT AS v FROM ({WORK}) GROUP BY ALL")
def grid_unpivot(spark, sf_dir):
    return grid_pivot(spark, sf_dir).unpivot("line", ["p0", "p1", "p2", "p3"], "phase", "v")


@query("asof_fill", "SELECT event_id, coalesce(last_value(CASE WHEN event_type = 'purchase' THEN round(value * 100)::BIGINT END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), -1)::BIGINT AS v FROM events")
def asof_fill(spark, sf_dir):
    """The last known value before a gap, per user."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    v = F.when(F.col("event_type") == "purchase", cents(F.col("value")))
    return slots(spark, sf_dir).select("event_id", F.coalesce(F.last(v, ignorenulls=True).over(w), F.lit(-1)).cast("long").alias("v"))


@query("glyph_strings", "SELECT doc_id, length(text) AS n, unicode(substr(text, 1, 1))::INTEGER AS first, length(regexp_replace(text, '[aeiou]', '', 'g')) AS consonants FROM documents WHERE length(text) > 0")
def glyph_strings(spark, sf_dir):
    t = table(sf_dir, "documents", spark).where(F.length("text") > 0)
    return t.select("doc_id", F.length("text").cast("long").alias("n"), F.ascii(F.substring("text", 1, 1)).alias("first"), F.length(F.regexp_replace("text", "[aeiou]", "")).cast("long").alias("consonants"))


@query("date_axis", f"SELECT {sql.WEEK} AS week, count(*) AS n, min(l_shipdate)::DATE::VARCHAR AS first FROM lineitem GROUP BY ALL")
def date_axis(spark, sf_dir):
    return table(sf_dir, "lineitem", spark).groupBy(week_of(F.col("l_shipdate")).alias("week")).agg(F.count("*").alias("n"), F.min("l_shipdate").cast("date").cast("string").alias("first"))


RATES = ("discount", "extendedprice", "quantity", "tax")


@query("params_map", "SELECT k, count(*) AS n, sum(v)::BIGINT AS v FROM (SELECT unnest([" + ", ".join(f"'{r}'" for r in RATES) + "]) AS k, unnest([" + ", ".join(sql.CENTS.format(f"l_{r}") for r in RATES) + "]) AS v FROM lineitem) GROUP BY k")
def params_map(spark, sf_dir):
    """A row's amounts as a map, and the map's entries as rows."""
    m = F.map_from_arrays(F.array(*[F.lit(r) for r in RATES]), F.array(*[cents(F.col(f"l_{r}")) for r in RATES]))
    return table(sf_dir, "lineitem", spark).select(F.explode(m).alias("k", "v")).groupBy("k").agg(F.count("*").alias("n"), F.sum("v").alias("v"))


@query("index_roundtrip_parquet", f"WITH {core.KEYED} SELECT patch_id, zkey FROM keyed WHERE zkey >= 36028797018963968")
def index_roundtrip_parquet(spark, sf_dir):
    """Written in key order and read back with a key filter that reaches the files' statistics."""
    path = new_path(spark, "roundtrip")
    core.keyed_patches(spark, sf_dir).select("patch_id", "zkey").repartitionByRange(8, "zkey").sortWithinPartitions("zkey").write.parquet(path)
    return spark.read.parquet(path).where(F.col("zkey") >= 1 << 55)


@query("formats_roundtrip", "SELECT p_partkey, round(p_retailprice * 100)::BIGINT AS v FROM part")
def formats_roundtrip(spark, sf_dir):
    """CSV, JSON and ORC in turn, with given schemas."""
    df = table(sf_dir, "part", spark).select("p_partkey", cents(F.col("p_retailprice")).alias("v"))
    for kind in ("csv", "json", "orc"):
        path = new_path(spark, kind)
        df.write.format(kind).save(path)
        df = spark.read.schema("p_partkey long, v long").format(kind).load(path)
    return df


@query("props_json_channel", "SELECT event_id, coalesce(json_extract_string(props, '$.page'), '') AS page FROM events")
def props_json_channel(spark, sf_dir):
    return table(sf_dir, "events", spark).select("event_id", F.coalesce(F.get_json_object("props", "$.page"), F.lit("")).alias("page"))


@query("sampling_hash", "SELECT count(*) AS n, sum(vec_id)::BIGINT AS ids FROM (SELECT vec_id, " + sql.portable_hash_sql("vec_id") + " AS h FROM embeddings) WHERE h < 536870912")
def sampling_hash(spark, sf_dir):
    from patchspace.functions.portable import portable_hash

    return table(sf_dir, "embeddings", spark).where(portable_hash(F.col("vec_id")) < 1 << 29).agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))
