"""Exact top-k inner products over a pivot-distance index.

Vectors become integers ``floor(scale * x)``. One more coordinate, ``sqrt(M^2 - |v|^2)`` with M
the largest norm, gives all vectors one length, and 0 for queries: then the largest inner
products are the smallest distances, ``d^2 = |q|^2 + M^2 - 2 q.v``, and the triangle inequality
bounds them exactly.

Index: pivots are vectors of a bounded sample (in the order of a hash); their number grows with
the square root of the table up to ``MAX_PIVOTS``. Every vector is keyed by its nearest pivot and
the distance to it, rows are range-partitioned by that key, and cut into blocks of ``block_rows``:
sorted annuli around pivots. A block row holds the pivot, the inner and outer radius,
identifiers and vectors. Neighbouring blocks of one pivot make a group of bounded size, as do neighbouring queries.

Search: each query first sees the block it lies in itself, which bounds its k-th score and so
its reach. By the triangle inequality the vectors within reach of a query lie, around each pivot, in
the annulus of its own distance plus and minus the reach. A group of queries asks for the union of
those annuli, a row for each pivot, and only the groups of blocks that they overlap are
paired with it and shuffled to it. In a pair, each query opens its nearest block first; then the blocks are opened
by rising lower bound, and a query takes no part as soon as the bound exceeds its k-th best
distance. The last step keeps k per query over the pairs. Nothing is capped: what the bounds do
not exclude is compared.

Vectors null, or with a null or non-finite component, take no part; vectors of unequal lengths
are padded with zeros. Ties go to the smaller identifier. A repeated identifier is a row of its
own; a query skips all rows with its own identifier. Scores are exact while they stay below 2^53.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.shared import ship, staged

BLOCK = "kind string, grp long, pivot int, r_lo double, r_hi double, n int, ids binary, vecs binary, bound binary, lows array<double>, highs array<double>"
FIELDS = pa.schema([("kind", pa.string()), ("grp", pa.int64()), ("pivot", pa.int32()), ("r_lo", pa.float64()), ("r_hi", pa.float64()), ("n", pa.int32()), ("ids", pa.binary()), ("vecs", pa.binary()), ("bound", pa.binary()), ("lows", pa.list_(pa.float64())), ("highs", pa.list_(pa.float64()))])
SLACK = 1e-6  # relative, for rounding of distances
MIN_PIVOTS, MAX_PIVOTS = 16, 1024
GROUP_QUERIES, GROUP_ROWS = 4096, 1 << 15


def integers(df: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 64) -> DataFrame:
    """vec_id, v (array of long), n2 (its squared norm) of the vectors that take part."""
    v = F.transform(F.col(vector_col), lambda x: F.floor(x.cast("double") * scale).cast("double"))
    ok = F.col(vector_col).isNotNull() & ~F.exists(F.col(vector_col), lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = df.where(F.coalesce(ok, F.lit(False))).select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v"))
    return rows.withColumn("n2", F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat, off = np.asarray(column.flatten(), float), np.asarray(column.offsets, np.int64)
    off = off - off[0]
    n = np.diff(off)
    if len(n) and (n == dim).all():
        return flat.reshape(-1, dim)
    out = np.zeros((len(n), dim))
    for i, (a, k) in enumerate(zip(off[:-1], n, strict=True)):
        out[i, :k] = flat[a : a + k]
    return out


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best of a row by (score falling, id rising)."""
    if len(scores) > k:
        floor_ = np.partition(scores, len(scores) - k)[len(scores) - k]
        keep = scores >= floor_
        scores, ids = scores[keep], ids[keep]
    order = np.lexsort((ids, -scores))[:k]
    return scores[order], ids[order]


def _to_pivots(x: np.ndarray, pivots: np.ndarray, x2: np.ndarray, tail: np.ndarray | None = None) -> np.ndarray:
    """Distances of vectors to the pivots; ``tail`` is the vectors' added coordinate (0 for queries)."""
    dim = x.shape[1]
    dot = x @ pivots[:, :dim].T
    if tail is not None:
        dot = dot + tail[:, None] * pivots[None, :, dim]
        x2 = x2 + tail**2
    return np.sqrt(np.maximum(0.0, x2[:, None] + (pivots**2).sum(1)[None, :] - 2 * dot))


def _reach(x2: np.ndarray, m2: float, bound: np.ndarray) -> np.ndarray:
    """How far from a query a vector can be that still scores ``bound``."""
    return np.sqrt(np.maximum(0.0, x2 + m2 - 2 * np.where(np.isfinite(bound), bound, -1e300)))


def build_index(rows: DataFrame, k: int, is_query, n_pivots: int | None = None, block_rows: int = 2048, group_queries: int = GROUP_QUERIES, group_rows: int = GROUP_ROWS) -> tuple[DataFrame, dict]:
    """(block rows and query rows, facts of the index)."""
    spark = rows.sparkSession
    ship(spark)
    facts = rows.agg(F.count("*").alias("n"), F.max("n2").alias("m2"), F.max(F.size("v")).alias("dim")).first()
    dim, m2 = int(facts.dim or 0), float(facts.m2 or 0.0)
    if n_pivots is None:
        n_pivots = min(MAX_PIVOTS, max(MIN_PIVOTS, math.isqrt(facts.n or 0) // 4))
    sample = [r.v for r in rows.orderBy(F.xxhash64("vec_id"), "vec_id").select("v").limit(n_pivots).collect()]
    pivots = np.zeros((len(sample), dim + 1))
    for i, v in enumerate(sample):
        pivots[i, : len(v)] = v
        pivots[i, dim] = np.sqrt(max(0.0, m2 - float(np.dot(v, v))))

    def key(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            x = _matrix(batch.column("v"), dim)
            x2 = (x**2).sum(1)
            d = _to_pivots(x, pivots, x2, np.sqrt(np.maximum(0.0, m2 - x2)))
            near = d.argmin(1)
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("v"), pa.array(near.astype(np.int32)), pa.array(d[np.arange(len(x)), near]), batch.column("own")], names=["vec_id", "v", "pivot", "r", "own"])

    keyed = rows.select("vec_id", "v", is_query.alias("own")).mapInArrow(key, "vec_id long, v array<double>, pivot int, r double, own boolean")
    dealt = staged(keyed, "annuli-keys").repartitionByRange("pivot", "r", "vec_id").sortWithinPartitions("pivot", "r", "vec_id")

    def cut(batches):
        base = TaskContext.get().partitionId() << 32
        group, last, room = -1, None, 0  # of blocks: of one pivot, and of bounded size
        q_group, q_room = 0, group_queries
        blob = lambda a, t: np.ascontiguousarray(a, t).tobytes()

        def emit(pivots_, r, ids, x, own):
            nonlocal group, last, room, q_group, q_room
            pivot, n = int(pivots_[0]), len(ids)
            if pivot != last or room < n:
                group, last, room = group + 1, pivot, max(n, group_rows)
            room -= n
            out = [("block", base | group, pivot, float(r[0]), float(r[-1]), n, blob(ids, "<i8"), blob(x, "<f8"), None, None, None)]
            q = np.flatnonzero(own)
            if len(q):
                if q_room < len(q):
                    q_group, q_room = q_group + 1, max(len(q), group_queries)
                q_room -= len(q)
                scores = x[q] @ x.T
                bound = np.full(len(q), -np.inf)
                for j, i in enumerate(q):
                    s = scores[j][ids != ids[i]]
                    if len(s) >= k:
                        bound[j] = np.partition(s, len(s) - k)[len(s) - k]
                x2 = (x[q] ** 2).sum(1)
                d, far = _to_pivots(x[q], pivots, x2), _reach(x2, m2, bound) * (1 + SLACK) + SLACK
                lows, highs = (d - far[:, None]).min(0) * (1 - SLACK) - SLACK, (d + far[:, None]).max(0) * (1 + SLACK) + SLACK
                out.append(("query", base | q_group, pivot, float(r[0]), float(r[-1]), len(q), blob(ids[q], "<i8"), blob(x[q], "<f8"), blob(bound, "<f8"), lows.tolist(), highs.tolist()))
            return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*out, strict=True), FIELDS.types, strict=True)], schema=FIELDS)

        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            own = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("pivot", "r", "vec_id")] + [_matrix(batch.column("v"), dim), batch.column("own").to_numpy(zero_copy_only=False).astype(bool)]
            held = own if held is None else [np.concatenate(p) for p in zip(held, own, strict=True)]
            while held is not None:  # a block ends with its pivot, or when it is full
                n = int(np.searchsorted(held[0], held[0][0], "right"))
                if n < block_rows and n == len(held[0]):
                    break
                n = min(n, block_rows)
                yield emit(*(a[:n] for a in held))
                held = [a[n:] for a in held] if n < len(held[0]) else None
        if held is not None:
            yield emit(*held)

    index = staged(dealt.mapInArrow(cut, BLOCK), "annuli")
    return index, {"n": facts.n, "dim": dim, "m2": m2, "pivots": pivots}


def pairs(index: DataFrame) -> DataFrame:
    """g, h: the groups of queries and of blocks that the annuli within reach connect."""
    asked = index.where("kind = 'query'").select("grp", F.posexplode(F.arrays_zip("lows", "highs")).alias("pivot", "ring"))
    asked = asked.groupBy(F.col("grp").alias("g"), "pivot").agg(F.min("ring.lows").alias("low"), F.max("ring.highs").alias("high")).where("high >= 0")
    rings = index.where("kind = 'block'").groupBy(F.col("grp").alias("h"), F.col("pivot").alias("p")).agg(F.min("r_lo").alias("r_lo"), F.max("r_hi").alias("r_hi"))
    return asked.join(rings, (F.col("pivot") == F.col("p")) & (F.col("r_lo") <= F.col("high")) & (F.col("r_hi") >= F.col("low"))).select("g", "h")


def search(index: DataFrame, facts: dict, k: int) -> DataFrame:
    """query_id, rank, vec_id, score, opened (blocks compared for the query)."""
    dim, m2, pivots = facts["dim"], facts["m2"], facts["pivots"]
    met = staged(pairs(index), "annuli-pairs")  # a block group has one pivot, so a pair occurs once
    left = index.where("kind = 'query'").join(met, F.col("grp") == F.col("g")).select("g", "h", "ids", "vecs", "bound")
    # new names: both sides come from one table, and a cogroup tells columns apart by origin
    to = met.select(F.col("g").alias("b_g"), F.col("h").alias("b_h"))
    right = index.where("kind = 'block'").join(to, F.col("grp") == F.col("b_h")).select("b_g", "b_h", *[F.col(c).alias(f"b_{c}") for c in ("pivot", "r_lo", "r_hi", "ids", "vecs")])
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64()), ("opened", pa.int64())])

    def meet(q: pa.Table, b: pa.Table) -> pa.Table:
        if not q.num_rows or not b.num_rows:
            return schema.empty_table()
        join = lambda t, c, kind: np.frombuffer(b"".join(t.column(c).to_pylist()), kind)
        qid, x, bound = join(q, "ids", "<i8"), join(q, "vecs", "<f8").reshape(-1, dim), join(q, "bound", "<f8").copy()
        q2 = (x**2).sum(1)
        to_pivot = _to_pivots(x, pivots, q2)
        lo, hi, piv = b.column("b_r_lo").to_numpy(), b.column("b_r_hi").to_numpy(), b.column("b_pivot").to_numpy()
        low = np.maximum(0.0, np.maximum(to_pivot[:, piv] - hi[None, :], lo[None, :] - to_pivot[:, piv])) * (1 - SLACK) - SLACK
        opened = np.zeros(len(qid), np.int64)
        best: list = [(np.empty(0), np.empty(0, np.int64))] * len(qid)
        ids_of, vecs_of = b.column("b_ids").to_pylist(), b.column("b_vecs").to_pylist()

        def open_block(j: int, near: np.ndarray) -> None:
            near = near[low[near, j] <= _reach(q2[near], m2, bound[near])]
            if not len(near):
                return
            ids, v = np.frombuffer(ids_of[j], "<i8"), np.frombuffer(vecs_of[j], "<f8").reshape(-1, dim)
            scores = x[near] @ v.T
            opened[near] += 1
            for row, i in zip(scores, near, strict=True):
                hit = row >= bound[i]
                if not hit.any():
                    continue
                hit &= ids != qid[i]
                s, w = best[i]
                s, w = _best(np.concatenate([s, row[hit]]), np.concatenate([w, ids[hit]]), k)
                best[i] = (s, w)
                if len(s) == k:
                    bound[i] = max(bound[i], s[-1])

        nearest = low.argmin(1)
        for j in np.unique(nearest):
            open_block(j, np.flatnonzero(nearest == j))
        for j in np.argsort(low.min(0), kind="stable"):
            open_block(j, np.flatnonzero(nearest != j))
        n = np.array([len(s) for s, _ in best])
        cols = [np.repeat(qid, n), np.concatenate([w for _, w in best]), np.concatenate([s for s, _ in best]).astype(np.int64), np.repeat(opened, n)]
        return pa.Table.from_arrays([pa.array(c) for c in cols], schema=schema)

    found = left.groupBy("g", "h").cogroup(right.groupBy("b_g", "b_h")).applyInArrow(meet, "query_id long, vec_id long, score long, opened long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", "opened")


def top_k(df: DataFrame, is_query, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 64, n_pivots: int | None = None, block_rows: int = 2048, group_queries: int = GROUP_QUERIES, group_rows: int = GROUP_ROWS) -> DataFrame:
    """Exact k largest integer inner products for each row that ``is_query`` (on vec_id) marks."""
    rows = integers(df, id_col, vector_col, scale)
    index, facts = build_index(rows, k, is_query, n_pivots, block_rows, group_queries, group_rows)
    return search(index, facts, k)


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.col("vec_id") % 20 == 0)
    return found.select("query_id", "rank", "vec_id", "score")
