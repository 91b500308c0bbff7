"""From patches to few coordinates: principal components per footprint, and other bases.

The scatter matrix of whole patches is summed once, in integers, over the dictionary; every
footprint's matrix is a part of it. Only these sums (the square of a patch's size, whatever the dictionary)
reach the driver, for the eigenvectors.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patchspace.functions.zcurve import encode
from patchspace.operators.footprints import Footprint
from patchspace.shared import ship


@dataclass
class Basis:
    index_id: int
    pos: np.ndarray
    mean: np.ndarray
    loadings: np.ndarray  # one row per kept component, orthonormal
    eigen: np.ndarray  # all variances, falling
    low: float  # value of quantised 0, one for all axes
    step: float  # one for all axes, so that norms keep their meaning

    def project(self, vals: np.ndarray) -> np.ndarray:
        return (vals[..., self.pos] - self.mean) @ self.loadings.T

    def quantise(self, coords: np.ndarray, bits: int = 8) -> np.ndarray:
        return np.clip(np.rint((coords - self.low) / self.step), 0, (1 << bits) - 1).astype(np.int64)

    def keys(self, coords: np.ndarray, bits: int = 8) -> np.ndarray:
        return encode(self.quantise(coords, bits), bits)

    @property
    def explained(self) -> float:
        total = float(self.eigen.sum())
        return float(self.eigen[: len(self.loadings)].sum() / total) if total > 0 else 1.0


def matrix(column: pa.Array) -> np.ndarray:
    """A batch's array column, all of one length, as a matrix."""
    flat = np.asarray(column.flatten())
    return flat.reshape(len(column), -1) if len(column) else np.empty((0, 0), flat.dtype)


def scatter(patches: DataFrame) -> tuple[int, np.ndarray, np.ndarray]:
    """(n, sums, sums of products) of the patch vectors, exact."""
    ship(patches.sparkSession)

    def sums(batches):
        n, first, second = 0, None, None
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column(0)).astype(np.float64)  # products of bytes: exact below 2^53
                part = (x.T @ x).astype(np.int64)
                first = x.sum(0).astype(np.int64) if first is None else first + x.sum(0).astype(np.int64)
                second = part if second is None else second + part
                n += len(x)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId() % 16], pa.int32()), pa.array([n]), pa.array([first.tobytes()], pa.binary()), pa.array([second.tobytes()], pa.binary())], names=["salt", "n", "s", "p"])

    return summed(patches.select("vals").mapInArrow(sums, SUMS))


SUMS = "salt int, n long, s binary, p binary"


def summed(parts: DataFrame) -> tuple[int, np.ndarray, np.ndarray]:
    """The total of such sums; ``salt`` (0 to 15) names the task that adds them first."""

    def add(batches):
        total = None
        for batch in batches:
            for n, s, p in zip(*(batch.column(c).to_pylist() for c in ("n", "s", "p")), strict=True):
                own = [n, np.frombuffer(s, np.int64), np.frombuffer(p, np.int64)]
                total = own if total is None else [a + b for a, b in zip(total, own, strict=True)]
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([total[0]]), pa.array([total[1].tobytes()], pa.binary()), pa.array([total[2].tobytes()], pa.binary())], names=["salt", "n", "s", "p"])

    rows = parts.repartition(16, "salt").mapInArrow(add, SUMS).collect()  # 16 rows at most
    if not rows:
        return 0, np.zeros(0, np.int64), np.zeros((0, 0), np.int64)
    s = sum(np.frombuffer(r.s, np.int64) for r in rows)
    return sum(r.n for r in rows), s, sum(np.frombuffer(r.p, np.int64) for r in rows).reshape(len(s), len(s))


def scatter_table(patches: DataFrame) -> DataFrame:
    """The same sums as rows i <= j, in SQL functions alone."""
    one = patches.select("vals", F.posexplode("vals").alias("i", "a"))
    pair = one.select("i", "a", F.posexplode("vals").alias("j", "b")).where("i <= j")
    return pair.groupBy("i", "j").agg(F.count("*").alias("n"), F.sum(F.col("a").cast("long") * F.col("b")).alias("sum_products"))


def _finish(fp: Footprint, mean: np.ndarray, loadings: np.ndarray, eigen: np.ndarray, spread: float) -> Basis:
    sigma = float(np.sqrt(max(spread, 0.0)))
    reach = 4 * sigma if sigma > 0 else 1.0
    return Basis(fp.index_id, np.asarray(fp.pos), mean, loadings, eigen, -reach, 2 * reach / 255)


def pca_of(n: int, s: np.ndarray, p: np.ndarray, fp: Footprint, dims: int) -> Basis:
    """The leading components of a footprint's part of the scatter matrix."""
    pos = np.asarray(fp.pos)
    mean = s[pos] / max(1, n)
    cov = p[np.ix_(pos, pos)] / max(1, n) - np.outer(mean, mean)
    values, vectors = np.linalg.eigh(cov)
    order = np.argsort(-values, kind="stable")
    values, vectors = np.maximum(values[order], 0), vectors[:, order[: min(dims, len(pos))]].T
    largest = np.abs(vectors).argmax(1)
    signs = np.sign(vectors[np.arange(len(vectors)), largest])
    return _finish(fp, mean, vectors * np.where(signs == 0, 1, signs)[:, None], values, values[0])


def fit_pca(patches: DataFrame, fps: list[Footprint], dims: int) -> list[Basis]:
    n, s, p = scatter(patches)
    if not n:
        return [_finish(fp, np.zeros(len(fp.pos)), np.eye(min(dims, len(fp.pos)), len(fp.pos)), np.zeros(len(fp.pos)), 0.0) for fp in fps]
    return [pca_of(n, s, p, fp, dims) for fp in fps]


def fit_random(patches: DataFrame, fps: list[Footprint], dims: int, seed: int = 1) -> list[Basis]:
    """Random signs, scaled so that lengths are kept on average; found worse than components.

    Rows are not orthonormal, so this basis gives no lower bound: approximate search only.
    """
    n, s, p = scatter(patches)
    out = []
    for fp in fps:
        pos, rng = np.asarray(fp.pos), np.random.default_rng(seed + fp.index_id)
        rows = (rng.integers(0, 2, (min(dims, len(pos)), len(pos))) * 2 - 1) / np.sqrt(min(dims, len(pos)))
        mean = s[pos] / max(1, n)
        cov = p[np.ix_(pos, pos)] / max(1, n) - np.outer(mean, mean)
        spread = np.maximum(np.einsum("ij,jk,ik->i", rows, cov, rows), 0)
        out.append(_finish(fp, mean, rows, np.sort(np.diag(cov))[::-1], float(spread.max())))
    return out


def fit_lda(patches: DataFrame, labels: DataFrame, fps: list[Footprint], dims: int, ridge: float = 1e-3) -> list[Basis]:
    """Directions that part classes (labels: patch_id, label), orthonormalised."""
    rows = patches.join(labels, "patch_id").where(F.col("label").isNotNull())
    classes = [r.label for r in rows.select("label").distinct().orderBy("label").collect()]  # class names
    if not classes:
        return fit_pca(rows, fps, dims)
    parts = [scatter(rows.where(F.col("label") == c)) for c in classes]
    n, s, p = (sum(x[i] for x in parts) for i in range(3))
    out = []
    for fp in fps:
        pos = np.asarray(fp.pos)
        mean = s[pos] / n
        between = sum(m * np.outer(a[pos] / m - mean, a[pos] / m - mean) for m, a, _ in parts) / n
        total = p[np.ix_(pos, pos)] / n - np.outer(mean, mean)
        within = total - between + np.eye(len(pos)) * ridge * np.trace(total) / len(pos)
        values, vectors = np.linalg.eig(np.linalg.solve(within, between))
        order = np.argsort(-values.real, kind="stable")[: min(dims, len(pos))]
        q, _ = np.linalg.qr(vectors[:, order].real)
        out.append(_finish(fp, mean, q.T, np.sort(np.linalg.eigvalsh(total))[::-1], float(np.einsum("ij,jk,ik->i", q.T, total, q.T).max())))
    return out


def dct_rows(size: int) -> np.ndarray:
    k, x = np.arange(size)[:, None], np.arange(size)[None, :]
    m = np.cos(np.pi * (2 * x + 1) * k / (2 * size)) * np.sqrt(2 / size)
    m[0] /= np.sqrt(2)
    return m


def hadamard_rows(size: int) -> np.ndarray:
    """Walsh functions by number of sign changes, entries +-1; size is a power of two."""
    m = np.ones((1, 1), int)
    while len(m) < size:
        m = np.block([[m, m], [m, -m]])
    changes = (m[:, 1:] != m[:, :-1]).sum(1)
    return m[np.argsort(changes, kind="stable")]


def frequencies(k: int, dims: int, kind: str = "dct") -> np.ndarray:
    """The lowest two-dimensional frequencies of a k x k patch, flattened, by (sum, row)."""
    one = dct_rows(k) if kind == "dct" else hadamard_rows(k)
    order = sorted(((u, v) for u in range(k) for v in range(k)), key=lambda p: (p[0] + p[1], p[0]))[:dims]
    return np.array([np.outer(one[u], one[v]).ravel() for u, v in order])


def hadamard_coords(vals: Column, k: int, dims: int) -> list[Column]:
    """Integer Walsh coefficients of a patch column: exact in any engine."""
    out = []
    for row in frequencies(k, dims, "hadamard"):
        plus = F.array(*[F.lit(int(x)) for x in row])
        out.append(F.aggregate(F.zip_with(vals, plus, lambda a, s: a.cast("long") * s), F.lit(0).cast("long"), lambda t, x: t + x))
    return out


def hadamard_byte(coord: Column, k: int, leading: bool = False) -> Column:
    """A coefficient as a byte: one step for all axes, the mean shifted to be signed like the rest."""
    size = k * k
    shifted = coord - F.lit(size * 128) if leading else coord
    return F.greatest(F.lit(0), F.least(F.lit(255), F.floor((shifted + size * 128) / size))).cast("long")


def explained_variance(bases: list[Basis]) -> list[tuple[int, float]]:
    return [(b.index_id, b.explained) for b in bases]
