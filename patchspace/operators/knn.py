"""Nearest neighbours on the z-curve for a batch of queries, and filter-and-refine search.

A recursion that prunes region by region becomes two rounds that all queries share. Round one
finds each query's place among the sorted blocks by bisection, as its key is made like theirs, and scans the
blocks around it that hold k entries: that gives the query a radius. Round two pairs packed entries and
packed queries as matrices: within them a query meets the blocks whose box is not farther
than the radius, and a task keeps k rows a query, not a row a pair. The result is that of the recursion: bounds
only leave out what cannot be among the k nearest.

Ties go to the smaller patch_id everywhere, so a box at exactly the radius is still scanned.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.functions.costs import Cost, l2
from patchspace.functions.zcurve import box_distance2, encode, l2_squared
from patchspace.operators import pairs as pairs_
from patchspace.operators.footprints import select_index
from patchspace.operators.patches import RasterPatches
from patchspace.operators.reduce import matrix
from patchspace.operators.zindex import ZIndex
from patchspace.shared import ship, staged

FAN = 32  # children of a node of the box tree
MOST = 1000  # neighbours a query that a task keeps of its blocks
HANDED = 20_000  # pairs of a query and a block that a task hands on at once
SENT = 64 << 20  # bytes of entries that may go to every task
MARGIN = 1e-4  # relative, for coordinates stored as floats
ROUNDING = 1e-12  # relative, of a product of matrices of doubles
TILE = 128  # queries of a product, so that what it needs stays in a cache


def query_coords(queries: DataFrame, index: ZIndex) -> DataFrame:
    """Queries (with index_id) with their coordinates ``coord`` (doubles) in that index's space.

    Where a query does not know a footprint position, the index mean stands in for it.
    """
    ship(queries.sparkSession)
    by_id, dims = {b.index_id: b for b in index.bases}, index.dims
    names = ["query_id", "image_id", "cy", "cx", "index_id"]

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            vals = matrix(batch.column("vals"))
            known = matrix(batch.column("known")).astype(bool)
            own = batch.column("index_id").to_numpy()
            x = np.nan_to_num(vals.astype(float))
            out = np.zeros((len(own), dims))
            for i, b in by_id.items():
                rows = np.flatnonzero(own == i)
                if len(rows):
                    diff = np.where(known[rows][:, b.pos], x[rows][:, b.pos] - b.mean, 0.0)
                    out[rows] = diff @ b.loadings.T
            arr = pa.ListArray.from_arrays(pa.array(np.arange(0, out.size + 1, dims, dtype=np.int32)), pa.array(out.ravel()))
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in names], arr], names=[*names, "coord"])

    rows = queries.where(F.col("index_id").isNotNull()).select(*names, "vals", "known")
    return rows.mapInArrow(run, "query_id long, image_id long, cy int, cx int, index_id int, coord array<double>")


class Boxes:
    """The units of an index (blocks, or groups of them) in curve order, under a tree of boxes."""

    def __init__(self, keys: list[bytes], ids: np.ndarray, n: np.ndarray, lo: np.ndarray, hi: np.ndarray):
        self.keys, self.ids, self.n = keys, ids, n
        self.levels = [(lo, hi)]
        while len(self.levels[-1][0]) > FAN:
            lo, hi = self.levels[-1]
            cut = np.arange(0, len(lo), FAN)
            self.levels.append((np.minimum.reduceat(lo, cut), np.maximum.reduceat(hi, cut)))

    def around(self, key: bytes, wanted: int) -> np.ndarray:
        """Units on both sides of a key's place, until they hold ``wanted`` entries."""
        at = max(0, bisect_right(self.keys, key) - 1)
        left, right, have = at, at, int(self.n[at]) if len(self.n) else 0
        while have < wanted and (left > 0 or right + 1 < len(self.n)):
            if right + 1 < len(self.n):
                right += 1
                have += int(self.n[right])
            if left > 0 and have < wanted:
                left -= 1
                have += int(self.n[left])
        return np.arange(left, right + 1) if len(self.n) else np.empty(0, np.int64)

    def within(self, point: np.ndarray, radius2: float) -> np.ndarray:
        """Units whose box is within the radius, found from the root down."""
        at = np.arange(len(self.levels[-1][0]))
        for depth in range(len(self.levels) - 1, -1, -1):
            lo, hi = self.levels[depth]
            at = at[at < len(lo)]
            gap = np.maximum(0.0, np.maximum(lo[at] - point, point - hi[at]))
            at = at[(gap**2).sum(1) <= radius2]
            if depth:
                at = (at[:, None] * FAN + np.arange(FAN)[None, :]).ravel()
        return at


def chosen(q: DataFrame) -> list[int]:
    """The indices that queries have chosen; their number is that of the footprints."""
    return sorted(r.index_id for r in q.select("index_id").where(F.col("index_id").isNotNull()).distinct().collect())


def _boxes(index: ZIndex, asked: list[int]) -> dict[int, Boxes]:
    """A tree for each of the indices asked for of its units; their number is checked where they are chosen."""
    out = {}
    for i in asked:  # an index at a time, and in Arrow's form: UNITS rows at most of all
        own = index.units().where(F.col("index_id") == i).toArrow().sort_by([("z_lo", "ascending"), ("unit", "ascending")])
        if own.num_rows:
            lo, hi = (matrix(own.column(c).combine_chunks()).astype(float) for c in ("box_lo", "box_hi"))
            out[i] = Boxes(own.column("z_lo").to_pylist(), own.column("unit").to_numpy().astype(np.int64), own.column("n").to_numpy().astype(np.int64), lo, hi)
    return out


QUERY = "query_id long, image_id long, cy int, cx int, index_id int, coord array<double>"


def near_blocks(q: DataFrame, index: ZIndex, wanted: int, radius: bool = False) -> DataFrame:
    """Pairs of ``q`` (with ``radius2``, if ``radius``) and blocks: those around a query's place, or,
    with a radius, those within it that the first kind (of ``wanted`` entries) leaves out."""
    spark = q.sparkSession
    ship(spark)
    sent, bases = spark.sparkContext.broadcast(_boxes(index, chosen(q))), {b.index_id: b for b in index.bases}
    bits, grouped = index.bits, index.grouped

    def pair(batches):
        trees = sent.value
        for batch in batches:
            if not batch.num_rows:
                continue
            points = matrix(batch.column("coord")).astype(float)
            found, rows, have = [], [], 0
            for row, (i, point) in enumerate(zip(batch.column("index_id").to_pylist(), points, strict=True)):
                tree = trees.get(i)
                if tree is None:
                    continue
                key = encode(bases[i].quantise(point[None, :], bits), bits).tobytes()
                units = tree.around(key, 1 if grouped else wanted) if wanted else np.empty(0, np.int64)
                if radius:
                    inside = tree.within(point, batch.column("radius2")[row].as_py())
                    units = inside if grouped else np.setdiff1d(inside, units)
                found.append(tree.ids[units])
                rows.append(np.full(len(units), row))
                have += len(units)
                if have >= HANDED:
                    yield rows_of(batch, rows, found)
                    found, rows, have = [], [], 0
            if rows:
                yield rows_of(batch, rows, found)

    def rows_of(batch, rows, found):
        out = batch.take(pa.array(np.concatenate(rows)))
        return pa.RecordBatch.from_arrays([*out.columns, pa.array(np.concatenate(found))], names=[*out.schema.names, "unit"])

    columns = ["query_id", "image_id", "cy", "cx", "index_id", "coord", *(["radius2"] if radius else [])]
    pairs = q.select(*columns).mapInArrow(pair, QUERY + (", radius2 double" if radius else "") + ", unit long")
    if not grouped:
        return pairs.withColumnRenamed("unit", "block_id")
    # a large catalogue: units are groups, so the blocks of the few groups of a query are met next
    blocks = index.catalog.select(F.col("index_id").alias("c_index"), "block_id", index.unit_of(F.col("block_id")).alias("c_unit"), "n", "box_lo", "box_hi")
    met = pairs.join(blocks, [F.col("index_id") == F.col("c_index"), F.col("unit") == F.col("c_unit")])
    met = met.withColumn("d", box_distance2(F.col("coord"), F.col("box_lo"), F.col("box_hi"))).drop("c_index", "c_unit", "unit", "box_lo", "box_hi")
    if radius:
        return met.where(F.col("d") <= F.col("radius2")).drop("d", "n")
    ahead = F.sum("n").over(Window.partitionBy("query_id").orderBy("d", "block_id").rowsBetween(Window.unboundedPreceding, -1))
    return met.withColumn("ahead", F.coalesce(ahead, F.lit(0))).where(F.col("ahead") < wanted).drop("ahead", "d", "n")


def scan_blocks(pairs: DataFrame, entries: DataFrame, k: int | None, exclude_radius: int | None) -> DataFrame:
    """Entries of the paired blocks by (dist2, patch_id), the first k of each query."""
    e = entries.select(F.col("index_id").alias("e_index"), F.col("block_id").alias("e_block"), F.col("coord").alias("e_coord"), "patch_id", F.col("image_id").alias("e_image"))
    found = pairs.hint("merge").join(e.hint("merge"), [F.col("index_id") == F.col("e_index"), F.col("block_id") == F.col("e_block")])  # what Python gives is larger than Spark's estimate
    if exclude_radius is not None:
        found = found.where(~overlaps(F.col("e_image"), F.col("patch_id"), exclude_radius))
    found = found.select("query_id", "patch_id", l2_squared(F.col("coord"), F.col("e_coord")).alias("dist2"))
    return found if k is None else first_k(found, k)


def overlaps(image: Column, patch: Column, radius: int) -> Column:
    """Whether a raster patch lies within ``radius`` of the query's own centre."""
    y, x = F.pmod(F.shiftright(patch, 20), F.lit(1 << 20)), F.pmod(patch, F.lit(1 << 20))
    return (image == F.col("image_id")) & (F.abs(y - F.col("cy")) < radius) & (F.abs(x - F.col("cx")) < radius)


def first_k(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy("dist2", "patch_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


ENTRY, ASKED = ("patch_id", "image_id", "index_id", "block_id"), (*pairs_.QUERY, "index_id")


def within(dims: int, exclude_radius: int | None, cost: Cost | None = None) -> Callable[[pairs_.Block, pairs_.Block], np.ndarray]:
    """A matrix of queries and entries, infinite where an entry is not within the query's ``radius2`` or of another
    index: the squared distances of the first ``dims`` values, or of what follows them the ``cost``.

    Entries of a block of the index are met by those queries alone that its box is near enough to.
    """

    def run(q, p):
        out = np.full((q.n, p.n), np.inf)
        points, entries = q.vals[:, :dims], p.vals[:, :dims]
        starts = np.flatnonzero(np.concatenate([[True], (p.block_id[1:] != p.block_id[:-1]) | (p.index_id[1:] != p.index_id[:-1])]))
        lo, hi = np.minimum.reduceat(entries, starts), np.maximum.reduceat(entries, starts)
        gaps = sum(np.maximum(0.0, np.maximum(lo[:, i] - points[:, i, None], points[:, i, None] - hi[:, i])) ** 2 for i in range(dims))
        near = (gaps <= q.radius2[:, None]) & (q.index_id[:, None] == p.index_id[starts])
        ends, size = np.diff([*starts, p.n]), (entries**2).sum(1)
        apart = None if exclude_radius is None else ~pairs_.near_centre(q, p, exclude_radius)
        asking = np.flatnonzero(near.any(1))
        for rows in np.split(asking, range(TILE, len(asking), TILE)):
            # a product of matrices decides all but the pairs that its rounding leaves open
            own, radius2 = points[rows], q.radius2[rows, None]
            open_ = (own**2).sum(1)[:, None] + size
            about = open_ - 2 * own @ entries.T
            open_ *= ROUNDING
            met = (about <= radius2 + open_) & np.repeat(near[rows], ends, axis=1)
            if apart is not None:
                met &= apart[rows]
            at, to = np.nonzero(met) if cost is None else np.nonzero(met & (about > radius2 - open_))
            dist2 = sum((own[at, i] - entries[to, i]) ** 2 for i in range(dims))
            if cost is None:
                kept = dist2 <= radius2[at, 0]
                out[rows[at[kept]], to[kept]] = dist2[kept]
                continue
            met[at, to] = dist2 <= radius2[at, 0]
            to = np.flatnonzero(met.any(0))
            if len(to):
                out[np.ix_(rows, to)] = np.where(met[:, to], cost.block(q.vals[rows, dims:], p.vals[to, dims:], q.known[rows]), np.inf)
        return out

    return run


def asked(q: DataFrame, index: ZIndex) -> tuple[DataFrame, int]:
    """The entries of those indices that queries have chosen, and how many."""
    own = chosen(q)
    n = index.catalog.where(F.col("index_id").isin(own)).agg(F.sum("n")).first()[0]
    return index.entries.where(F.col("index_id").isin(own)), int(n or 0)


def zcurve_knn(queries: DataFrame, index: ZIndex, k: int, exclude_radius: int | None = None, counters: bool = False) -> DataFrame:
    """query_id, rank, patch_id, dist2 of the k nearest entries in principal space.

    ``counters``: also blocks visited, blocks in the index, and distances computed per query.
    """
    q = staged(query_coords(queries, index), "knn-queries")
    wanted = k if exclude_radius is None else k + (2 * exclude_radius - 1) ** 2  # room for what is excluded
    seeds = near_blocks(q, index, wanted)
    first = scan_blocks(seeds, index.entries, k, exclude_radius)
    worst = first.groupBy("query_id").agg(F.max("dist2").alias("worst"), F.count("*").alias("got"))
    radius = worst.select(F.col("query_id").alias("r_id"), F.when(F.col("got") >= k, F.col("worst") * (1 + MARGIN)).otherwise(F.lit(float("inf"))).alias("radius2"))
    q2 = q.join(radius, F.col("query_id") == F.col("r_id"), "left").withColumn("radius2", F.coalesce("radius2", F.lit(float("inf")))).drop("r_id")
    q2 = staged(q2, "knn-radius")
    if not counters:
        entries, n = asked(q, index)
        entries = entries.withColumn("vals", F.col("coord").cast("array<double>"))
        if k <= MOST:
            found = pairs_.best_pairs(q2.withColumn("vals", F.col("coord")), entries, within(index.dims, exclude_radius), k, ("radius2",), ASKED, ENTRY, by_query=n * 8 * (index.dims + len(ENTRY)) <= SENT, shrink=True)
            return first_k(found.withColumnRenamed("cost", "dist2"), k)
        return first_k(scan_blocks(near_blocks(q2, index, 0, radius=True), index.entries, None, exclude_radius), k)
    rest = near_blocks(q2, index, wanted, radius=True)
    if index.grouped:  # a seed is met again with its group
        rest = rest.join(seeds.select("query_id", "block_id"), ["query_id", "block_id"], "left_anti")
    sizes = index.catalog.select(F.col("index_id").alias("c_index"), F.col("block_id").alias("c_block"), "n")
    visits = seeds.select("query_id", "index_id", "block_id").unionByName(rest.select("query_id", "index_id", "block_id"))
    visits = visits.join(sizes, [F.col("index_id") == F.col("c_index"), F.col("block_id") == F.col("c_block")])
    visits = visits.groupBy("query_id", "index_id").agg(F.count("*").alias("blocks"), F.sum("n").alias("distances"))
    all_of = index.catalog.groupBy(F.col("index_id").alias("s_index")).agg(F.count("*").alias("all_blocks"), F.sum("n").alias("entries"))
    return visits.join(F.broadcast(all_of), F.col("index_id") == F.col("s_index")).select("query_id", "index_id", "blocks", "all_blocks", "distances", "entries")  # a row per index


def refine(candidates: DataFrame, queries: DataFrame, dictionary: DataFrame | RasterPatches, cost: Cost, k: int = 1) -> DataFrame:
    """True costs of candidates over the whole search area; the k best of each query.

    Candidates of a raster's patches are sent to the strips they are cut from; a dictionary that is a
    table is joined by patch_id. Neither join broadcasts candidates, which are larger than Spark's estimate.
    """
    wanted = candidates.select("query_id", "patch_id")
    patches = dictionary.cut(wanted.select("patch_id").distinct()) if isinstance(dictionary, RasterPatches) else dictionary
    pairs = wanted.hint("merge").join(patches.select("patch_id", F.col("vals").alias("p_vals")), "patch_id")
    found = pairs.hint("merge").join(queries.select("query_id", "vals", "known"), "query_id").select("query_id", "patch_id", cost.column(F.col("vals"), F.col("p_vals"), F.col("known")).alias("cost"))
    if k == 1:
        best = found.groupBy("query_id").agg(F.min(F.struct("cost", "patch_id")).alias("b"), F.count("*").alias("refined"))
        return best.select("query_id", F.col("b.patch_id").alias("patch_id"), F.col("b.cost").alias("cost"), "refined")
    order = Window.partitionBy("query_id").orderBy("cost", "patch_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def full_scan(queries: DataFrame, dictionary: DataFrame | RasterPatches, cost: Cost | None = None, k: int = 1, exclude_radius: int | None = None) -> DataFrame:
    """The declared baseline: every query against every patch. query_id, rank, patch_id, cost.

    The stated queries go to the tasks that hold patches, as long as they are few; beyond that
    Spark pairs partitions of both. A cost with a block form is worked out on matrices.
    """
    cost = cost or l2()
    dictionary = dictionary.frame if isinstance(dictionary, RasterPatches) else dictionary
    order = Window.partitionBy("query_id").orderBy("cost", "patch_id")
    if cost.block and k <= MOST:
        near = pairs_.best_pairs(queries, dictionary, pairs_.cost_matrix(cost, exclude_radius), k)
        near = near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
        return near.withColumn("cost", F.col("cost").cast("long")) if cost.integer else near
    q = queries.select("query_id", "image_id", "cy", "cx", "vals", "known")
    if q.count() <= 10_000:
        q = F.broadcast(q)
    d = dictionary.select("patch_id", F.col("image_id").alias("p_image"), F.col("vals").alias("p_vals"))
    pairs = d.join(q, F.lit(True))
    if exclude_radius is not None:
        pairs = pairs.where(~overlaps(F.col("p_image"), F.col("patch_id"), exclude_radius))
    found = pairs.select("query_id", "patch_id", cost.column(F.col("vals"), F.col("p_vals"), F.col("known")).alias("cost"))
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def search(queries: DataFrame, index: ZIndex, dictionary: DataFrame | RasterPatches, k: int = 80, cost: Cost | None = None, exact: bool = False, exclude_radius: int | None = None, on_uncovered: str = "scan") -> DataFrame:
    """Filter with the index, refine with the true cost: query_id, patch_id, cost, refined.

    ``exact``: an orthonormal projection of some known positions never exceeds the L2 cost, so
    after the first answer (cost C) all entries within C of the query are refined as well. Costs
    that declare no bound are refused, as is the ``mean`` policy.
    """
    cost = cost or l2()
    if exact and (cost.filter_scale is None or on_uncovered == "mean"):
        raise ValueError("exact search needs a cost with a bound, and queries that know their footprint")
    chosen = staged(select_index(queries, index.footprints, on_uncovered), "search-queries")
    candidates = zcurve_knn(chosen, index, k, exclude_radius)
    best = refine(candidates, chosen, dictionary, cost)
    if exact:
        best = staged(best, "search-first")
        norm = F.sqrt(F.col("cost").cast("double")) if cost.root == 2 else F.col("cost").cast("double")
        radius = best.select(F.col("query_id").alias("r_id"), F.pow(norm / cost.filter_scale * (1 + MARGIN) + MARGIN, 2).alias("radius2"))
        q = query_coords(chosen, index).join(radius, F.col("query_id") == F.col("r_id"), "left").withColumn("radius2", F.coalesce("radius2", F.lit(float("inf")))).drop("r_id")
        if cost.block:
            # entries beside their patches and coordinates beside samples, so that one task filters and refines
            whole = (dictionary.frame if isinstance(dictionary, RasterPatches) else dictionary).select("patch_id", F.col("vals").cast("array<double>").alias("p_vals"))
            entries = asked(q, index)[0].hint("merge").join(whole, "patch_id").withColumn("vals", F.concat(F.col("coord").cast("array<double>"), "p_vals"))
            entries = entries.repartitionByRange("index_id", "block_id").sortWithinPartitions("index_id", "block_id")  # blocks stay together
            q = q.hint("merge").join(chosen.select("query_id", F.col("vals").cast("array<double>").alias("q_vals"), "known"), "query_id").withColumn("vals", F.concat("coord", "q_vals"))
            found = pairs_.best_pairs(q, entries, within(index.dims, exclude_radius, cost), 1, ("radius2",), ASKED, ENTRY, counted=True)
            best = found.groupBy("query_id").agg(F.min(F.struct("cost", "patch_id")).alias("b"), F.sum("met").alias("refined"))
            best = best.select("query_id", F.col("b.patch_id").alias("patch_id"), F.col("b.cost").cast("long" if cost.integer else "double").alias("cost"), "refined")
        else:
            met = scan_blocks(near_blocks(q, index, 0, radius=True), index.entries, None, exclude_radius).join(radius.withColumnRenamed("r_id", "query_id"), "query_id", "left").where(F.col("dist2") <= F.coalesce("radius2", F.lit(float("inf"))))
            best = refine(met, chosen, dictionary, cost)
    if on_uncovered == "scan" and not (left := chosen.where("index_id IS NULL")).isEmpty():
        scanned = full_scan(left, dictionary, cost, 1, exclude_radius).select("query_id", "patch_id", "cost", F.lit(None).cast("long").alias("refined"))
        best = best.unionByName(scanned)
    return best
