"""Queries against patches in blocks: rows are packed, blocks are paired, and a task works on matrices.

A packed row holds up to ``ROWS`` patches (or queries) as bytes. Patch blocks are dealt evenly over the
tasks and meet every query block; of each query a task keeps its k best so far, so what leaves a task
is k rows a query and not a row a pair. Nothing passes through the driver but the query blocks that
Spark broadcasts while they are few.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patchspace.functions.costs import Cost
from patchspace.operators.reduce import matrix
from patchspace.shared import ship

ROWS = 1024  # of a block
FEW = 100_000  # queries whose blocks are broadcast
HELD = 4_000_000  # best pairs that a task holds before it hands them on
STEP = 1 << 20  # as in a patch_id
PATCH, QUERY = ("patch_id", "image_id"), ("query_id", "image_id", "cy", "cx")


def samples(column: pa.Array) -> np.ndarray:
    """An array column as a matrix; what is null in it is 0."""
    x = matrix(column)
    return np.nan_to_num(x) if x.dtype.kind == "f" else x


def _bytes(x: np.ndarray) -> tuple[bytes, str]:
    """A matrix as bytes, in two bytes a sample where they hold it."""
    if x.size and x.dtype.kind == "f" and (x == np.rint(x)).all() and np.abs(x).max() < 1 << 31:
        x = x.astype(np.int64)
    kind = "<i2" if x.dtype.kind in "iu" and (not x.size or np.abs(x).max() < 1 << 15) else "<f8"
    return x.astype(kind).tobytes(), kind


def _runs(batch: pa.RecordBatch, by: tuple[str, ...]) -> list[int]:
    """Where runs of rows that are equal in ``by`` start, and the number of rows."""
    new = np.zeros(max(batch.num_rows - 1, 0), bool)
    for c in by:
        x = np.asarray(batch.column(c))
        new |= x[1:] != x[:-1]
    return [0, *(np.flatnonzero(new) + 1).tolist(), batch.num_rows]


def pack(rows: DataFrame, ids: tuple[str, ...], more: tuple[str, ...] = (), size: int = ROWS, by: tuple[str, ...] = (), alike: tuple[str, ...] = ()) -> DataFrame:
    """Blocks of ``size`` ``rows``: their long columns ``ids``, their double columns ``more``, ``vals`` and, if there, ``known``.

    A block ends where an int column of ``by`` changes, and has these columns as they are. Where all its rows have
    one value of a long column c of ``alike``, it is in ``c_all`` (else null).
    """
    ship(rows.sparkSession)
    given = [c for c in ("known",) if c in rows.columns]

    def run(batches):
        for batch in batches:
            ends = _runs(batch, by)
            for at, end in ((at, min(at + size, end)) for start, end in zip(ends, ends[1:], strict=False) for at in range(start, end, size)):
                b = batch.slice(at, end - at)
                vals, kind = _bytes(samples(b.column("vals")))
                out = {"n": pa.array([b.num_rows], pa.int32()), "kind": pa.array([kind]), "vals": pa.array([vals], pa.binary())}
                out |= {c: pa.array([np.asarray(b.column(c)).astype(np.int64).tobytes()], pa.binary()) for c in ids}
                out |= {c: pa.array([np.asarray(b.column(c).fill_null(np.nan)).astype(np.float64).tobytes()], pa.binary()) for c in more}
                out |= {c: pa.array([matrix(b.column(c)).astype(bool).tobytes()], pa.binary()) for c in given}
                out |= {c: b.column(c).slice(0, 1) for c in by}
                out |= {f"{c}_all": pa.array([x[0] if (x == x[0]).all() else None], pa.int64()) for c in alike for x in [np.asarray(b.column(c))]}
                yield pa.RecordBatch.from_arrays(list(out.values()), names=list(out))

    ddl = ", ".join(["n int", "kind string", "vals binary", *[f"{c} binary" for c in (*ids, *more, *given)], *[f"{c} int" for c in by], *[f"{c}_all long" for c in alike]])
    return rows.select(*ids, *[F.col(c).cast("double").alias(c) for c in more], "vals", *given, *by).mapInArrow(run, ddl)


class Block:
    """A packed row of a batch, its columns named with ``prefix``."""

    def __init__(self, batch: pa.RecordBatch, row: int, prefix: str, ids: tuple[str, ...], more: tuple[str, ...] = (), known: bool = False):
        cell = lambda c: batch.column(f"{prefix}{c}")[row].as_py()
        n = cell("n")
        for c in ids:
            setattr(self, c, np.frombuffer(cell(c), np.int64))
        for c in more:
            setattr(self, c, np.frombuffer(cell(c), np.float64))
        self.vals = np.frombuffer(cell("vals"), cell("kind")).reshape(n, -1).astype(np.float64)
        if known:
            self.known = np.frombuffer(cell("known"), bool).reshape(n, -1)
        self.n = n


def near_centre(q: Block, p: Block, radius: int) -> np.ndarray:
    """Which patches of a raster lie within ``radius`` of a query's own centre."""
    y, x = (p.patch_id >> 20) % STEP, p.patch_id % STEP
    order = np.argsort(x, kind="stable")
    first, n = np.searchsorted(x[order], q.cx - radius, "right"), np.searchsorted(x[order], q.cx + radius, "left")
    n = np.maximum(n - first, 0)
    rows = np.repeat(np.arange(q.n), n)
    cols = order[np.arange(len(rows)) + np.repeat(first - np.cumsum(n) + n, n)]
    out = np.zeros((q.n, p.n), bool)
    out[rows, cols] = (q.image_id[rows] == p.image_id[cols]) & (np.abs(y[cols] - q.cy[rows]) < radius)
    return out


def least(cost: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, id, cost) of the k least of each row by (cost, id); infinite costs do not count.

    ``ids``: of the columns, or of every cell.
    """
    if k == 1 and ids.ndim == 1:
        best = cost.min(1)
        rows, cols = np.nonzero((cost == best[:, None]) & np.isfinite(best)[:, None])
        rows, first = np.unique(rows, return_index=True)
        return rows, np.minimum.reduceat(ids[cols], first) if len(rows) else ids[:0], best[rows]
    many = np.isfinite(cost).sum(1) > k
    top = np.full(len(cost), np.inf)
    if many.any():
        top[many] = np.partition(cost[many], k - 1, axis=1)[:, k - 1]
    rows, cols = np.nonzero((cost <= top[:, None]) & np.isfinite(cost))
    found, c = ids[cols] if ids.ndim == 1 else ids[rows, cols], cost[rows, cols]
    order = np.lexsort((found, c, rows))
    rows, found, c = rows[order], found[order], c[order]
    first = np.arange(len(rows)) - np.searchsorted(rows, rows) < k
    return rows[first], found[first], c[first]


class Best:
    """The k best pairs of each query that a task has met so far, and how many it has met."""

    def __init__(self, k: int):
        self.k, self.by, self.size = k, {}, 0

    def add(self, queries: np.ndarray, matrix_: np.ndarray, patches: np.ndarray) -> None:
        rows, ids, cost = least(matrix_, patches, self.k)
        met = np.isfinite(matrix_).sum(1)
        key = queries.tobytes()
        if key in self.by:
            _, r, i, c, m = self.by[key]
            self.size -= len(r)
            rows, ids, cost = np.concatenate([r, rows]), np.concatenate([i, ids]), np.concatenate([c, cost])
            order = np.lexsort((ids, cost, rows))
            rows, ids, cost = rows[order], ids[order], cost[order]
            first = np.arange(len(rows)) - np.searchsorted(rows, rows) < self.k
            rows, ids, cost, met = rows[first], ids[first], cost[first], met + m
        self.by[key] = queries, rows, ids, cost, met
        self.size += len(rows)

    def bounds(self, queries: np.ndarray) -> np.ndarray:
        """The cost of each query's k-th best pair so far, infinite where it has fewer."""
        out = np.full(len(queries), np.inf)
        if (held := self.by.get(queries.tobytes())) is not None:
            _, rows, _, cost, _ = held
            last = np.arange(len(rows)) - np.searchsorted(rows, rows) == self.k - 1
            out[rows[last]] = cost[last]
        return out

    def take(self) -> Iterator[pa.RecordBatch]:
        for queries, rows, ids, cost, met in self.by.values():
            if len(rows):
                first = np.concatenate([[True], rows[1:] != rows[:-1]])
                yield pa.RecordBatch.from_arrays([pa.array(queries[rows]), pa.array(ids), pa.array(cost.astype(np.float64)), pa.array(np.where(first, met[rows], 0))], names=["query_id", "patch_id", "cost", "met"])
        self.by, self.size = {}, 0


def paired(queries: DataFrame, patches: DataFrame, more: tuple[str, ...] = (), q_ids: tuple[str, ...] = QUERY, p_ids: tuple[str, ...] = PATCH, by_query: bool = False, by: tuple[str, ...] = (), alike: tuple[str, ...] = (), met: Column | None = None) -> DataFrame:
    """Every patch block beside every query block: columns p_* and q_*.

    ``by_query``: query blocks are dealt over the tasks and patch blocks sent to each, for a caller that knows
    that the patches are few; a query is then answered in one task.
    ``by``: rows meet only where these int columns are equal. Rows are dealt in their order, so a value that many
    rows share is cut over several tasks; within it they are in the order of the long columns ``alike``. Blocks do
    not meet where ``met`` holds, a condition on ``by`` and on the p_*_all and q_*_all of ``alike``.
    """
    tasks, n = 4 * queries.sparkSession.sparkContext.defaultParallelism, queries.count()
    if by:
        order = lambda ids: (*by, *alike, ids[0])
        q = queries.repartitionByRange(max(1, min(tasks, n // (4 * ROWS))), *order(q_ids)).sortWithinPartitions(*order(q_ids))
        p = patches.repartitionByRange(tasks, *order(p_ids)).sortWithinPartitions(*order(p_ids))
        q, p = pack(q, q_ids, more, by=by, alike=alike), pack(p, p_ids, by=by, alike=alike)
        q, p = (rows.select(*by, *[F.col(c).alias(f"{side}_{c}") for c in rows.columns if c not in by]) for rows, side in ((q, "q"), (p, "p")))
        both = p.join(F.broadcast(q) if n <= FEW else q, list(by))
        return both if met is None else both.where(~F.coalesce(met, F.lit(False)))
    if by_query:
        q, p = pack(queries, q_ids, more, min(ROWS, n // tasks + 1)).repartition(tasks), F.broadcast(pack(patches, p_ids))
    else:
        q, p = pack(queries, q_ids, more), pack(patches, p_ids).repartition(tasks)
        if n <= FEW:
            q = F.broadcast(q)
    q, p = q.select(*[F.col(c).alias(f"q_{c}") for c in q.columns]), p.select(*[F.col(c).alias(f"p_{c}") for c in p.columns])
    return q.join(p, F.lit(True)) if by_query else p.join(q, F.lit(True))


def best_pairs(queries: DataFrame, patches: DataFrame, cost: Callable[[Block, Block], np.ndarray], k: int, more: tuple[str, ...] = (), q_ids: tuple[str, ...] = QUERY, p_ids: tuple[str, ...] = PATCH, by_query: bool = False, counted: bool = False, shrink: bool = False, by: tuple[str, ...] = (), alike: tuple[str, ...] = (), met: Column | None = None) -> DataFrame:
    """query_id, patch_id, cost (double) of the k best pairs of each query in each task; ``counted``: also ``met``,
    in the row of a query's least pair the number of its pairs that count there (else 0).

    ``cost(q, p)``: the matrix of a query block and a patch block, infinite where a pair does not count.
    ``shrink``: costs are squared distances and a query has a ``radius2``, which becomes that of its k-th best
    pair in the task as soon as that is less.
    ``by``, ``alike``, ``met``: as in ``paired``; a query block has the values of ``by``.
    """

    def run(batches):
        best = Best(k)
        for batch in batches:
            for row in range(batch.num_rows):
                qb = Block(batch, row, "q_", q_ids, more, known="q_known" in batch.schema.names)
                pb = Block(batch, row, "p_", p_ids)
                for c in by:
                    setattr(qb, c, batch.column(c)[row].as_py())
                if shrink:
                    qb.radius2 = np.minimum(qb.radius2, best.bounds(qb.query_id))
                best.add(qb.query_id, cost(qb, pb), pb.patch_id)
                if best.size > HELD:
                    yield from best.take()
        yield from best.take()

    found = paired(queries, patches, more, q_ids, p_ids, by_query, by, alike, met).mapInArrow(run, "query_id long, patch_id long, cost double, met long")
    return found if counted else found.drop("met")


def ratios(queries: DataFrame, patches: DataFrame, above: Callable[[Block, Block], np.ndarray], below: Callable[[Block, Block], np.ndarray], exclude_radius: int | None) -> DataFrame:
    """pairs, ratio_mean, ratio_stddev of ``above`` over ``below`` for all pairs where ``below`` is positive:
    a task sends a row of sums for each pair of blocks."""

    def run(batches):
        for batch in batches:
            for row in range(batch.num_rows):
                q, p = Block(batch, row, "q_", QUERY, known=True), Block(batch, row, "p_", PATCH)
                under = below(q, p)
                kept = under > 0
                if exclude_radius is not None:
                    kept &= ~near_centre(q, p, exclude_radius)
                r = above(q, p)[kept] / under[kept]
                yield pa.RecordBatch.from_arrays([pa.array([r.size]), pa.array([r.sum()]), pa.array([(r * r).sum()])], names=["n", "s", "ss"])

    sums = paired(queries, patches).mapInArrow(run, "n long, s double, ss double").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("ss").alias("ss"))
    n, mean = F.col("n"), F.when(F.col("n") > 0, F.col("s") / F.col("n"))
    spread = F.when(n > 1, F.sqrt(F.greatest(F.lit(0.0), F.col("ss") - F.col("s") * mean) / (n - 1)))
    return sums.select(F.coalesce(n, F.lit(0)).alias("pairs"), mean.alias("ratio_mean"), spread.alias("ratio_stddev"))


def cost_matrix(cost: Cost, exclude_radius: int | None) -> Callable[[Block, Block], np.ndarray]:
    block = cost.block

    def run(q, p):
        out = block(q.vals, p.vals, q.known)
        return out if exclude_radius is None else np.where(near_centre(q, p, exclude_radius), np.inf, out)

    return run
