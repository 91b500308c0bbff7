"""Accuracy and work measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patchspace.functions.costs import Cost, l2
from patchspace.operators import knn


def ratio_error(approx: Column, exact: Column) -> Column:
    """Norm ratio less one; 0/0 is 0, and x/0 is null (counted as undefined)."""
    return F.when(exact > 0, approx / F.when(exact > 0, exact) - 1).when(approx == 0, 0.0)


def acceleration_error(approx: DataFrame, exact: DataFrame, cost: Cost | None = None) -> DataFrame:
    """Per query: the norm of the approximate winner over the full scan's, less one."""
    cost = cost or l2()
    e = exact.select("query_id", F.col("cost").alias("exact_cost"))
    joined = approx.join(e, "query_id")
    return joined.select("query_id", "cost", "exact_cost", ratio_error(cost.report(F.col("cost").cast("double")), cost.report(F.col("exact_cost").cast("double"))).alias("ae"))


def summary(errors: DataFrame, *by: str) -> DataFrame:
    return errors.groupBy(*by).agg(F.count("*").alias("n"), F.avg("ae").alias("mean"), F.stddev_samp("ae").alias("stddev"), F.max("ae").alias("max"), F.count(F.when(F.col("ae").isNull(), 1)).alias("undefined"))


def error_by_k(near: DataFrame, queries: DataFrame, dictionary: DataFrame, exact: DataFrame, ks: tuple[int, ...], cost: Cost | None = None) -> DataFrame:
    """k, query_id, ae from one ranked candidate list: candidate sets are nested in k."""
    cost = cost or l2()
    all_costs = knn.refine(near, queries, dictionary, cost, k=max(ks) + 1).drop("rank")
    ranked = near.select("query_id", "patch_id", "rank").join(all_costs, ["query_id", "patch_id"])
    ranked = ranked.withColumn("k", F.explode(F.filter(F.array(*[F.lit(k) for k in ks]), lambda k: k >= F.col("rank"))))
    best = ranked.groupBy("k", "query_id").agg(F.min("cost").alias("cost"))
    return best.join(acceleration_input(exact), "query_id").select("k", "query_id", ratio_error(cost.report(F.col("cost").cast("double")), cost.report(F.col("exact_cost").cast("double"))).alias("ae"))


def acceleration_input(exact: DataFrame) -> DataFrame:
    return exact.select("query_id", F.col("cost").alias("exact_cost"))


def recall(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Share of the true k best among the found candidates, per query."""
    t = truth.where(F.col("rank") <= k).select("query_id", "patch_id")
    hits = t.join(found.select("query_id", "patch_id", F.lit(1).alias("hit")), ["query_id", "patch_id"], "left")
    return hits.groupBy("query_id").agg(F.count("hit").alias("found"), F.round(F.count("hit") / F.lit(float(k)), 6).alias("recall"))


def distance_preservation(reduced: DataFrame, true: DataFrame) -> DataFrame:
    """Mean and deviation of reduced over true distance for pairs (query_id, patch_id)."""
    r = reduced.select("query_id", "patch_id", F.sqrt("dist2").alias("reduced"))
    t = true.select("query_id", "patch_id", F.sqrt(F.col("cost").cast("double")).alias("true")).where(F.col("true") > 0)
    return r.join(t, ["query_id", "patch_id"]).agg(F.count("*").alias("pairs"), F.avg(F.col("reduced") / F.col("true")).alias("ratio_mean"), F.stddev_samp(F.col("reduced") / F.col("true")).alias("ratio_stddev"))


def fill_quality(filled: DataFrame, truth: DataFrame, mask: DataFrame) -> DataFrame:
    """MSE, MAE and PSNR over the cells that were unknown, per image."""
    m = mask.where(~F.col("known")).select("image_id", "y", "x")
    pair = m.join(filled.select("image_id", "y", "x", F.col("pix").alias("a")), ["image_id", "y", "x"]).join(truth.select("image_id", "y", "x", F.col("pix").alias("b")), ["image_id", "y", "x"])
    d = pair.select("image_id", F.explode(F.zip_with("a", "b", lambda a, b: a.cast("long") - b)).alias("d"))
    q = d.groupBy("image_id").agg(F.count("*").alias("cells"), F.avg(F.col("d") * F.col("d")).alias("mse"), F.avg(F.abs("d")).alias("mae"))
    return q.withColumn("psnr", F.when(F.col("mse") > 0, 10 * F.log10(F.lit(65025.0) / F.col("mse"))))


def pick_parameters(grid: DataFrame, limit: float = 0.01) -> DataFrame:
    """Of the (dims, k) with error below the limit, that with the least work."""
    ok = grid.where(F.col("ae") < limit)
    return ok.agg(F.min_by(F.struct("dims", "k", "ae", "seconds"), F.struct("seconds", "dims", "k")).alias("best")).select("best.*")


def scaling(points: DataFrame, size: str = "n", work: str = "work") -> DataFrame:
    """Work regressed on log2(n) squared, and the power of n it grows with."""
    sq = F.pow(F.log2(F.col(size).cast("double")), 2)
    return points.agg(F.regr_slope(F.col(work).cast("double"), sq).alias("slope"), F.regr_r2(F.col(work).cast("double"), sq).alias("r2"), F.regr_slope(F.ln(F.col(work).cast("double")), F.ln(F.col(size).cast("double"))).alias("power"))


def speedup(seconds: DataFrame, base: str, method: str) -> DataFrame:
    """Ratio of mean seconds of two methods: rows (method, size, seconds)."""
    m = seconds.groupBy("size").pivot("method", [base, method]).agg(F.avg("seconds"))
    return m.select("size", (F.col(base) / F.col(method)).alias("speedup"))


def timed(run: Callable[[], object]) -> tuple[object, float]:
    start = time.perf_counter()
    out = run()
    return out, time.perf_counter() - start
