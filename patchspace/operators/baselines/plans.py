"""Baselines as DataFrame plans, for dictionaries of any size."""

from __future__ import annotations

from functools import reduce
from operator import or_

import numpy as np
from pyspark.ml.clustering import BisectingKMeans, KMeans
from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.functions.costs import Cost, l2
from patchspace.functions.portable import portable_hash
from patchspace.functions.zcurve import l2_squared
from patchspace.operators import knn, pairs
from patchspace.operators.patches import STEP
from patchspace.shared import staged

DENSE = 0.2  # share of pairs left above which a stage takes them all

def idistance_build(points: DataFrame, refs: int = 16, seed: int = 5, sample: int = 20_000) -> tuple[DataFrame, list[list[float]]]:
    """(points with ``ref`` and ``r``, the reference points): the distance key of every point.

    ``points``: patch_id, coord. References are means fitted on a bounded sample in hash order.
    """
    if points.isEmpty():
        return points.select("patch_id", "coord", F.lit(0).alias("ref"), F.lit(0.0).alias("r")), []
    few = points.orderBy(portable_hash(F.col("patch_id")), "patch_id").limit(sample)
    model = KMeans(k=refs, seed=seed, maxIter=5, featuresCol="features").fit(few.select(array_to_vector("coord").alias("features")))
    centres = [[float(v) for v in c] for c in model.clusterCenters()]
    table = F.array(*[F.array(*[F.lit(v) for v in c]) for c in centres])
    each = F.transform(table, lambda c, i: F.struct(l2_squared(F.col("coord"), c).alias("d2"), i.alias("ref")))
    near = F.array_min(each)
    return points.withColumn("_n", near).select("patch_id", "coord", F.col("_n.ref").alias("ref"), F.sqrt("_n.d2").alias("r")), centres


def idistance_knn(queries: DataFrame, keyed: DataFrame, centres: list[list[float]], k: int, width: float, max_rounds: int = 64) -> DataFrame:
    """Exact k nearest by annuli of growing radius: query_id, rank, patch_id, dist2.

    Keys are cut into rings of ``width``; a round joins the rings that the radius reaches, and a
    query ends when its k-th distance is within the radius: nothing outside can be nearer.
    """
    if not centres:
        return queries.select("query_id", F.lit(0).alias("rank"), F.lit(None).cast("long").alias("patch_id"), F.lit(0.0).alias("dist2")).limit(0)
    rings = keyed.withColumn("ring", F.floor(F.col("r") / width))
    table = F.array(*[F.array(*[F.lit(v) for v in c]) for c in centres])
    to = F.transform(table, lambda c, i: F.struct(i.alias("ref"), F.sqrt(l2_squared(F.col("coord"), c)).alias("d")))
    open_q = staged(queries.select("query_id", "coord", F.posexplode(to).alias("_i", "t")).select("query_id", "coord", F.col("t.ref").alias("ref"), "t.d"), "idistance-open")
    far = keyed.agg(F.max("r").alias("m")).first().m or 0.0
    found, done = None, None
    for turn in range(max_rounds):
        radius = width * 2**turn
        lo, hi = F.floor(F.greatest(F.col("d") - radius, F.lit(0.0)) / width), F.floor((F.col("d") + radius) / width)
        want = open_q.withColumn("ring", F.explode(F.sequence(lo, F.greatest(lo, F.least(hi, F.lit(int(far / width) + 1))))))
        near = want.join(rings.select(F.col("ref"), F.col("ring"), "patch_id", F.col("coord").alias("p")), ["ref", "ring"]).where(F.col("query_id") != F.col("patch_id"))
        near = near.select("query_id", "patch_id", l2_squared(F.col("coord"), F.col("p")).alias("dist2"))
        best = staged(knn.first_k(near, k), "idistance-round")
        settled = best.groupBy("query_id").agg(F.max("dist2").alias("worst"), F.count("*").alias("n")).where((F.col("n") == k) & (F.sqrt("worst") <= radius))
        if radius > 2 * far + width * 4 and turn > 0:
            settled = best.select("query_id").distinct()
        part = best.join(settled.select("query_id"), "query_id", "left_semi").select("query_id", "rank", "patch_id", "dist2")
        found = part if found is None else found.unionByName(part)
        done = settled.select("query_id")
        open_q = staged(open_q.join(done, "query_id", "left_anti"), "idistance-open")
        if open_q.isEmpty():
            return found
    raise RuntimeError("queries are left without k neighbours")


def early_stop_scan(queries: DataFrame, dictionary: DataFrame, chunks: int = 4) -> DataFrame:
    """Exact L2 scan by staged sums: each stage drops pairs above the best bound known so far.

    The bound is the least complete cost among a small hash share of the patches.
    """
    # a first bound from the patches of one hash share, completely compared; then one pass over all
    few = dictionary.where(portable_hash(F.col("patch_id")) < (1 << 31) // 64)
    whole = l2().block
    other = lambda q, p, c: np.where(q.query_id[:, None] == p.patch_id, np.inf, c)
    first = pairs.best_pairs(queries, few, lambda q, p: other(q, p, whole(q.vals, p.vals, q.known)), 1)
    bounded = staged(queries.join(first.groupBy("query_id").agg(F.min("cost").alias("bound")), "query_id", "left"), "early-stop-queries")

    def stages(q, p):
        bound = np.nan_to_num(q.bound, nan=np.inf)[:, None]
        step = -(-q.vals.shape[1] // chunks)
        sofar, alive = np.zeros((q.n, p.n)), q.query_id[:, None] != p.patch_id
        for at in range(0, q.vals.shape[1], step):
            part = slice(at, at + step)
            if alive.mean() > DENSE:
                sofar += whole(q.vals[:, part], p.vals[:, part], q.known[:, part])
            else:
                i, j = np.nonzero(alive)
                sofar[i, j] += ((q.vals[i, part] - p.vals[j, part]) ** 2 * q.known[i, part]).sum(1)
            alive &= sofar <= bound
        return np.where(alive, sofar, np.inf)

    best = pairs.best_pairs(bounded, dictionary, stages, 1, ("bound",)).groupBy("query_id").agg(F.min(F.struct("cost", "patch_id")).alias("b"))
    return best.select("query_id", F.col("b.patch_id").alias("patch_id"), F.col("b.cost").cast("long").alias("cost"))


def window_knn(queries: DataFrame, dictionary: DataFrame, radius: int, k: int = 1, cost: Cost | None = None, radius_of: Column | None = None) -> DataFrame:
    """Patches within ``radius`` of the target, by an equi-join on tiles instead of a range join."""
    cost = cost or l2()
    tile = radius
    near = F.array(*[F.lit(i) for i in (-1, 0, 1)])
    q = queries.withColumn("reach", radius_of if radius_of is not None else F.lit(radius))
    q = q.select("*", F.explode(near).alias("dy")).withColumn("dx", F.explode(near))
    q = q.select("query_id", "image_id", "cy", "cx", "vals", "known", "reach", (F.expr(f"cy div {tile}") + F.col("dy")).alias("ty"), (F.expr(f"cx div {tile}") + F.col("dx")).alias("tx"))
    d = dictionary.select("patch_id", F.col("image_id"), F.col("cy").alias("py"), F.col("cx").alias("px"), F.col("vals").alias("p"), F.expr(f"cy div {tile}").alias("ty"), F.expr(f"cx div {tile}").alias("tx"))
    pairs = q.join(d, ["image_id", "ty", "tx"]).where((F.abs(F.col("py") - F.col("cy")) <= F.col("reach")) & (F.abs(F.col("px") - F.col("cx")) <= F.col("reach")))
    found = pairs.select("query_id", "patch_id", cost.column(F.col("vals"), F.col("p"), F.col("known")).alias("cost"))
    order = Window.partitionBy("query_id").orderBy("cost", "patch_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def local_diameter_knn(queries: DataFrame, dictionary: DataFrame, most: int, k: int = 1) -> DataFrame:
    """The radius follows the spread of the known samples: flat targets look near, busy ones far."""
    own = F.filter(F.zip_with("vals", "known", lambda v, m: F.when(m, v.cast("double"))), lambda v: v.isNotNull())
    n = F.greatest(F.size(own), F.lit(1))
    mean = F.aggregate(own, F.lit(0.0), lambda s, v: s + v) / n
    spread = F.sqrt(F.greatest(F.lit(0.0), F.aggregate(own, F.lit(0.0), lambda s, v: s + v * v) / n - mean * mean))
    reach = F.least(F.lit(most), F.greatest(F.lit(most // 4), (spread * most / 64).cast("int")))
    return window_knn(queries, dictionary, most, k, radius_of=reach)


def block_context_knn(queries: DataFrame, dictionary: DataFrame, side: int = 16, top: int = 3, bins: int = 8) -> DataFrame:
    """Non-overlapping blocks compared by histograms; only patches of the best blocks are scanned."""
    bin_of = lambda v: F.least(F.floor(v * bins / 256), F.lit(bins - 1)).cast("int")
    blocks = dictionary.withColumn("by", F.expr(f"cy div {side}")).withColumn("bx", F.expr(f"cx div {side}"))
    b = blocks.groupBy("image_id", "by", "bx").agg(F.count("*").alias("n"), *[F.count(F.when(bin_of(F.element_at("vals", F.expr("CAST(size(vals) div 2 + 1 AS INT)"))) == i, 1)).alias(f"h{i}") for i in range(bins)])
    b = b.select("image_id", "by", "bx", F.array(*[F.col(f"h{i}") / F.col("n") for i in range(bins)]).alias("hist"))
    known = F.filter(F.zip_with("vals", "known", lambda v, m: F.when(m, bin_of(v))), lambda v: v.isNotNull())
    own = F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda i: F.size(F.filter(known, lambda x: x == i)) / F.greatest(F.size(known), F.lit(1)))
    q = queries.withColumn("own", own)
    score = F.aggregate(F.zip_with("own", "hist", lambda a, c: F.sqrt(a * c)), F.lit(0.0), lambda s, x: s + x)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "by", "bx")
    best = q.join(b, "image_id").withColumn("score", score).withColumn("r", F.row_number().over(order)).where(F.col("r") <= top)
    pairs = best.select("query_id", "image_id", "by", "bx", F.col("vals").alias("q"), "known").join(blocks.select("image_id", "by", "bx", "patch_id", F.col("vals").alias("p")), ["image_id", "by", "bx"])
    found = pairs.select("query_id", "patch_id", l2().column(F.col("q"), F.col("p"), F.col("known")).alias("cost"))
    win = found.groupBy("query_id").agg(F.min(F.struct("cost", "patch_id")).alias("b"))
    return win.select("query_id", F.col("b.patch_id").alias("patch_id"), F.col("b.cost").alias("cost"))


def offset_histogram(matches: DataFrame) -> DataFrame:
    """How often each offset occurs between patches and their matches: dy, dx, n."""
    y = lambda c: F.pmod(F.shiftright(c, 20), F.lit(STEP))
    x = lambda c: F.pmod(c, F.lit(STEP))
    o = matches.select((y(F.col("patch_id")) - y(F.col("query_id"))).alias("dy"), (x(F.col("patch_id")) - x(F.col("query_id"))).alias("dx"))
    return o.groupBy("dy", "dx").agg(F.count("*").alias("n"))


def offset_stats_knn(queries: DataFrame, dictionary: DataFrame, offsets: DataFrame, top: int = 60) -> DataFrame:
    """Only places at the most frequent offsets are compared."""
    o = F.broadcast(offsets.orderBy(F.desc("n"), "dy", "dx").limit(top))
    at = queries.join(o, F.lit(True)).select("query_id", "image_id", "vals", "known", (F.col("cy") + F.col("dy")).cast("int").alias("cy"), (F.col("cx") + F.col("dx")).cast("int").alias("cx"))
    pairs = at.join(dictionary.select("patch_id", "image_id", "cy", "cx", F.col("vals").alias("p")), ["image_id", "cy", "cx"])
    win = pairs.select("query_id", "patch_id", l2().column(F.col("vals"), F.col("p"), F.col("known")).alias("cost")).groupBy("query_id").agg(F.min(F.struct("cost", "patch_id")).alias("b"))
    return win.select("query_id", F.col("b.patch_id").alias("patch_id"), F.col("b.cost").alias("cost"))


def tsvq_knn(queries: DataFrame, points: DataFrame, leaves: int = 16, seed: int = 4) -> DataFrame:
    """Tree-structured vector quantisation: the query's leaf is scanned. queries/points: id, coord."""
    if points.isEmpty():
        return queries.select("query_id", F.lit(None).cast("long").alias("patch_id"), F.lit(0.0).alias("dist2"), F.lit(0).alias("rank")).limit(0)
    model = BisectingKMeans(k=leaves, seed=seed, featuresCol="features", predictionCol="leaf").fit(points.select(array_to_vector("coord").alias("features")))
    p = model.transform(points.select("patch_id", "coord", array_to_vector("coord").alias("features"))).select("patch_id", F.col("coord").alias("p"), "leaf")
    q = model.transform(queries.select("query_id", "coord", array_to_vector("coord").alias("features"))).select("query_id", "coord", "leaf")
    near = q.join(p, "leaf").where(F.col("query_id") != F.col("patch_id")).select("query_id", "patch_id", l2_squared(F.col("coord"), F.col("p")).alias("dist2"))
    return knn.first_k(near, 1)


def lsh_knn(queries: DataFrame, points: DataFrame, k: int, width: float, tables: int = 6, seed: int = 4) -> DataFrame:
    """Locality-preserving hashing: candidates share a bucket in one of the tables.

    The rows of a bucket are packed, so its candidates are compared as matrices and no row stands for a pair.
    """
    if points.isEmpty():
        return queries.select("query_id", F.lit(None).cast("long").alias("patch_id"), F.lit(0.0).alias("dist2"), F.lit(0).alias("rank")).limit(0)
    hashing = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=width, numHashTables=tables, seed=seed)
    model = hashing.fit(points.select(array_to_vector("coord").alias("features")))
    names = [f"h{i}" for i in range(tables)]

    def keyed(df: DataFrame, id_: str) -> DataFrame:
        hashed = model.transform(df.where(F.col(id_).isNotNull()).select(id_, "coord", array_to_vector("coord").alias("features")))
        hashed = hashed.select(id_, F.col("coord").alias("vals"), F.transform("hashes", lambda h: F.hash(h.cast("string"))).alias("all"))
        return staged(hashed, "lsh-keyed").select(id_, "vals", *[F.col("all")[i].cast("long").alias(h) for i, h in enumerate(names)], F.posexplode("all").alias("turn", "bucket"))

    def near(q, p):
        # a pair counts in the first table where it meets: no shuffle of all pairs to find it again
        before = [(getattr(q, h), getattr(p, h)) for h in names[: q.turn]] + [(q.query_id, p.patch_id)]
        out, size, dims = np.full((q.n, p.n), np.inf), (p.vals**2).sum(1), range(p.vals.shape[1])
        for at in range(0, q.n, knn.TILE):
            rows = slice(at, at + knn.TILE)
            own, radius2 = q.vals[rows], q.radius2[rows, None]
            # a product of matrices decides all but the pairs that its rounding leaves open
            whole = (own**2).sum(1)[:, None] + size
            close = whole - 2 * own @ p.vals.T <= radius2 + whole * knn.ROUNDING
            if close.mean() > DENSE:
                for x, y in before:
                    close &= x[rows, None] != y
            if close.mean() > DENSE:
                dist2 = sum((own[:, d, None] - p.vals[:, d]) ** 2 for d in dims)
                out[rows] = np.where(close, dist2, np.inf)
                continue
            i, j = np.nonzero(close)
            for x, y in before:
                new = x[rows][i] != y[j]
                i, j = i[new], j[new]
            out[at + i, j] = sum((own[i, d] - p.vals[j, d]) ** 2 for d in dims)
        return out

    # blocks whose rows have all met before are not paired
    met = reduce(or_, [(F.col("turn") > i) & (F.col(f"q_{h}_all") == F.col(f"p_{h}_all")) for i, h in enumerate(names)])
    asked = keyed(queries, "query_id").withColumn("radius2", F.lit(float("inf")))
    found = pairs.best_pairs(asked, keyed(points, "patch_id"), near, k, ("radius2",), ("query_id", *names), ("patch_id", *names), shrink=True, by=("turn", "bucket"), alike=tuple(names), met=met)
    return knn.first_k(found.withColumnRenamed("cost", "dist2"), k)


def propagation_field(dictionary: DataFrame, k: int, rounds: int = 4, seed: int = 7) -> DataFrame:
    """A nearest-neighbour field by propagation over all patches, in its fixed-order form.

    image_id, y, x, sy, sx, cost. Each round offers to every place its four neighbours' matches,
    shifted, and hashed samples around its own match at shrinking distance; joins are equi-joins
    on places, and the field is written to the shared folder between rounds.
    """
    d = staged(dictionary.select("image_id", F.col("cy").alias("y"), F.col("cx").alias("x"), "vals"), "field-patches")
    ends = d.groupBy("image_id").agg(F.min("y").alias("y0"), F.max("y").alias("y1"), F.min("x").alias("x0"), F.max("x").alias("x1"))
    ends = staged(ends, "field-ends")  # a row per image

    def jump(y, x, salt, span):
        h = portable_hash((F.col("y") * 4099 + F.col("x") * 8191 + salt * 131 + seed).cast("long"))
        return (y + F.pmod(h, 2 * span + 1) - span).cast("int"), (x + F.pmod(F.expr("1") * F.shiftright(h, 11), 2 * span + 1) - span).cast("int")

    def measured(cand: DataFrame) -> DataFrame:
        src = d.select("image_id", F.col("y").alias("sy"), F.col("x").alias("sx"), F.col("vals").alias("s"))
        far = (F.abs(F.col("sy") - F.col("y")) >= k) | (F.abs(F.col("sx") - F.col("x")) >= k)
        pairs = cand.where(far).join(src, ["image_id", "sy", "sx"]).join(d, ["image_id", "y", "x"])
        whole = F.transform("vals", lambda _: F.lit(True))
        cost = pairs.select("image_id", "y", "x", "sy", "sx", l2().column(F.col("vals"), F.col("s"), whole).alias("cost"))
        best = cost.groupBy("image_id", "y", "x").agg(F.min(F.struct("cost", "sy", "sx")).alias("b"))
        return best.select("image_id", "y", "x", F.col("b.sy").alias("sy"), F.col("b.sx").alias("sx"), F.col("b.cost").alias("cost"))

    first = d.select("image_id", "y", "x").join(ends, "image_id")
    span_y, span_x = F.col("y1") - F.col("y0") + 1, F.col("x1") - F.col("x0") + 1
    tries = first.withColumn("t", F.explode(F.sequence(F.lit(1), F.lit(4))))
    h = portable_hash((F.col("y") * 4099 + F.col("x") * 8191 + F.col("t") * 17 + seed).cast("long"))
    start = tries.select("image_id", "y", "x", (F.col("y0") + F.pmod(h, span_y)).cast("int").alias("sy"), (F.col("x0") + F.pmod(F.shiftright(h, 12), span_x)).cast("int").alias("sx"))
    now = staged(measured(start), "field")
    for turn in range(rounds):
        offers = now.select("image_id", "y", "x", "sy", "sx")
        for dy, dx in ((0, 1), (1, 0), (0, -1), (-1, 0)):
            offers = offers.unionByName(now.select("image_id", (F.col("y") + dy).alias("y"), (F.col("x") + dx).alias("x"), (F.col("sy") + dy).alias("sy"), (F.col("sx") + dx).alias("sx")))
        for i, span in enumerate((32, 8, 2)):
            a, b = jump(F.col("sy"), F.col("sx"), turn * 8 + i, F.lit(span))
            offers = offers.unionByName(now.select("image_id", "y", "x", a.alias("sy"), b.alias("sx")))
        now = staged(measured(offers.distinct()), "field")
    return now


def diffuse_step(raster: DataFrame) -> DataFrame:
    """One round of neighbour means for unknown cells, as joins: a floor for fill quality."""
    steps = F.array(*[F.struct(F.lit(dy).alias("dy"), F.lit(dx).alias("dx")) for dy, dx in ((-1, 0), (1, 0), (0, -1), (0, 1))])
    given = raster.where("pix IS NOT NULL").select("image_id", F.explode(steps).alias("s"), "y", "x", F.col("pix")[0].cast("double").alias("v"))
    mean = given.groupBy("image_id", (F.col("y") + F.col("s.dy")).alias("y"), (F.col("x") + F.col("s.dx")).alias("x")).agg(F.avg("v").alias("mean"))
    out = raster.join(mean, ["image_id", "y", "x"], "left")
    new = F.when(F.col("known"), F.col("pix")).when(F.col("mean").isNotNull(), F.array(F.round("mean").cast("smallint"))).otherwise(F.col("pix"))
    return out.select("image_id", "y", "x", new.alias("pix"), "known")
