"""Patch costs as columns of (query values, patch values, known positions).

Unknown positions contribute nothing. A cost declares whether it is a norm, and a factor ``s``
with ``s * (L2 distance on a subset of the known positions) <= cost``; exact search needs one.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Cost:
    """``column`` orders patches; ``root`` turns it to the reported norm (2: square root)."""

    name: str
    column: Callable[[Column, Column, Column], Column]
    local: Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]
    is_norm: bool
    filter_scale: float | None
    root: int = 1
    block: Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray] | None = None  # rows of queries, of patches, of known: a matrix, as ``column`` gives it
    integer: bool = False

    def report(self, c: Column) -> Column:
        return F.sqrt(c) if self.root == 2 else c


def _sum(values: Column, zero) -> Column:
    start = F.lit(zero).cast("long") if isinstance(zero, int) else F.lit(zero)
    return F.aggregate(values, start, lambda s, x: s + x)


def _masked(q: Column, p: Column, known: Column, term: Callable[[Column], Column], zero) -> Column:
    diff = F.zip_with(q, p, lambda a, b: a.cast("long") - b.cast("long"))
    return _sum(F.zip_with(diff, known, lambda d, k: F.when(k, term(d)).otherwise(F.lit(zero))), zero)


def _squares(q: np.ndarray, p: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Weighted squared differences of all pairs; integers of this size stay exact in doubles."""
    return (q * q * w).sum(1)[:, None] - 2 * ((q * w) @ p.T) + w @ (p * p).T


def _row_wise(term: Callable[[np.ndarray], np.ndarray]) -> Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]:
    """Sums of ``term`` of the absolute differences."""

    def block(q, p, known):
        if len(known) and (known == known[0]).all():
            return _same(q[:, known[0]], np.ascontiguousarray(p[:, known[0]].T))
        out = np.empty((len(q), len(p)))
        for i, own in enumerate(known):
            out[i] = term(np.abs(p[:, own] - q[i, own])) @ np.ones(int(own.sum()))
        return out

    def _same(q, p):
        """All queries know the same positions: a position at a time, few queries at once."""
        out = np.zeros((len(q), p.shape[1]))
        for at in range(0, len(q), 32):
            own = out[at : at + 32]
            diff = np.empty_like(own)
            for i, row in enumerate(p):
                np.subtract(q[at : at + 32, i, None], row, out=diff)
                own += term(np.abs(diff, out=diff))
        return out

    return block


def l2() -> Cost:
    """Squared, as an exact integer."""
    column = lambda q, p, k: _masked(q, p, k, lambda d: d * d, 0).cast("long")
    return Cost("l2", column, lambda q, p, k: (((p - q).astype(np.int64) ** 2) * k).sum(-1), True, 1.0, 2, lambda q, p, k: _squares(q, p, k.astype(np.float64)), True)


def l1() -> Cost:
    column = lambda q, p, k: _masked(q, p, k, lambda d: F.abs(d), 0).cast("long")
    return Cost("l1", column, lambda q, p, k: (np.abs((p - q).astype(np.int64)) * k).sum(-1), True, 1.0, 1, _row_wise(lambda d: d), True)


def lp(p_: float, size: int) -> Cost:
    """The p-norm; ``size`` bounds the number of known positions (for the filter factor)."""
    column = lambda q, p, k: F.pow(_masked(q, p, k, lambda d: F.pow(F.abs(d).cast("double"), F.lit(float(p_))), 0.0), F.lit(1.0 / p_))
    scale = 1.0 if p_ <= 2 else float(size) ** (1 / p_ - 0.5)
    sums = _row_wise((lambda d: d * d * d) if p_ == 3 else (lambda d: d**p_))
    return Cost(f"l{p_:g}", column, lambda q, p, k: ((np.abs((p - q).astype(float)) ** p_) * k).sum(-1) ** (1 / p_), p_ >= 1, scale, 1, lambda q, p, k: sums(q, p, k) ** (1 / p_))


def weighted_l2(weights: list[int]) -> Cost:
    """Squared differences times integer weights (for example heavier towards the centre)."""
    w = F.array(*[F.lit(int(x)) for x in weights])

    def column(q, p, k):
        diff = F.zip_with(q, p, lambda a, b: (a.cast("long") - b.cast("long")) * (a.cast("long") - b.cast("long")))
        return _sum(F.zip_with(F.zip_with(diff, w, lambda d, x: d * x.cast("long")), k, lambda d, z: F.when(z, d).otherwise(F.lit(0))), 0).cast("long")

    a = np.array(weights, np.int64)
    return Cost("weighted_l2", column, lambda q, p, k: (((p - q).astype(np.int64) ** 2) * k * a).sum(-1), True, float(min(weights)) ** 0.5, 2, lambda q, p, k: _squares(q, p, k * a.astype(np.float64)), True)


def centre_weights(k: int, channels: int = 1) -> list[int]:
    mid = k // 2
    return [1 + k - max(abs(y - mid), abs(x - mid)) for y in range(k) for x in range(k) for _ in range(channels)]


def hellinger_l2(bins: int = 8) -> Cost:
    """L2 times the Hellinger distance of the two patches' histograms on the known positions."""

    def histogram(v: Column, known: Column) -> Column:
        own = F.zip_with(v, known, lambda a, k: F.when(k, F.floor(a * bins / 256).cast("int")).otherwise(F.lit(-1)))
        return F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda b: F.size(F.filter(own, lambda x: x == b)).cast("double"))

    def column(q, p, k):
        n = F.greatest(F.size(F.filter(k, lambda x: x)).cast("double"), F.lit(1.0))
        overlap = _sum(F.zip_with(histogram(q, k), histogram(p, k), lambda a, b: F.sqrt(a * b) / n), 0.0)
        h = F.sqrt(F.greatest(F.lit(0.0), 1 - overlap))
        return F.sqrt(_masked(q, p, k, lambda d: d * d, 0).cast("double")) * h

    def local(q, p, k):
        p = np.atleast_2d(p)
        m = np.broadcast_to(k.astype(bool), p.shape)
        n = max(1, int(k.sum()))
        hist = lambda v: np.stack([((v * bins // 256 == b) & m).sum(-1) for b in range(bins)], -1)
        overlap = np.sqrt(hist(np.broadcast_to(q, p.shape)) * hist(p)).sum(-1) / n
        return np.sqrt((((p - q).astype(np.int64) ** 2) * k).sum(-1)) * np.sqrt(np.maximum(0, 1 - overlap))

    def block(q, p, known):
        n = np.maximum(known.sum(1).astype(np.float64), 1.0)[:, None]
        l2_, overlap = _squares(q, p, known.astype(np.float64)), np.zeros((len(q), len(p)))
        for b in range(bins):  # in the order of the column, so that sums are the same to the last digit
            own = (np.floor(q * bins / 256) == b) & known
            overlap += np.sqrt(own.sum(1).astype(np.float64)[:, None] * (known.astype(np.float64) @ (np.floor(p * bins / 256) == b).astype(np.float64).T)) / n
        return np.sqrt(l2_) * np.sqrt(np.maximum(0.0, 1 - overlap))

    return Cost("hellinger_l2", column, local, False, None, 1, block)


SSIM_C1, SSIM_C2 = (0.01 * 255) ** 2, (0.03 * 255) ** 2


def ssim() -> Cost:
    """1 - structural similarity over the known positions; not a norm."""

    def column(q, p, k):
        zero = F.struct(*[F.lit(0.0).alias(c) for c in ("n", "a", "b", "aa", "bb", "ab")])

        def add(s, v):
            a, b = v["0"].cast("double"), v["1"].cast("double")
            one = F.when(v["2"], 1.0).otherwise(0.0)
            return F.struct((s.n + one).alias("n"), (s.a + one * a).alias("a"), (s.b + one * b).alias("b"), (s.aa + one * a * a).alias("aa"), (s.bb + one * b * b).alias("bb"), (s.ab + one * a * b).alias("ab"))

        def close(s):
            n = F.greatest(s.n, F.lit(1.0))
            ma, mb = s.a / n, s.b / n
            va, vb, cov = s.aa / n - ma * ma, s.bb / n - mb * mb, s.ab / n - ma * mb
            return 1 - (2 * ma * mb + SSIM_C1) * (2 * cov + SSIM_C2) / ((ma * ma + mb * mb + SSIM_C1) * (va + vb + SSIM_C2))

        both = F.zip_with(F.zip_with(q, p, lambda a, b: F.struct(a.alias("0"), b.alias("1"))), k, lambda v, z: F.struct(v["0"].alias("0"), v["1"].alias("1"), z.alias("2")))
        return F.aggregate(both, zero, add, close)

    def local(q, p, k):
        p = np.atleast_2d(p).astype(float)
        q, n = q.astype(float), max(1, k.sum())
        ma, mb = (q * k).sum() / n, (p * k).sum(-1) / n
        va, vb, cov = (q * q * k).sum() / n - ma * ma, (p * p * k).sum(-1) / n - mb * mb, (q * p * k).sum(-1) / n - ma * mb
        return 1 - (2 * ma * mb + SSIM_C1) * (2 * cov + SSIM_C2) / ((ma * ma + mb * mb + SSIM_C1) * (va + vb + SSIM_C2))

    def block(q, p, known):
        k = known.astype(np.float64)
        n = np.maximum(k.sum(1), 1.0)[:, None]
        ma, mb = (q * k).sum(1)[:, None] / n, (k @ p.T) / n
        va, vb, cov = (q * q * k).sum(1)[:, None] / n - ma * ma, (k @ (p * p).T) / n - mb * mb, ((q * k) @ p.T) / n - ma * mb
        return 1 - (2 * ma * mb + SSIM_C1) * (2 * cov + SSIM_C2) / ((ma * ma + mb * mb + SSIM_C1) * (va + vb + SSIM_C2))

    return Cost("ssim", column, local, False, None, 1, block)


def guided(weight: int, guide: Callable[[Column, Column], Column], guide_local: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> Cost:
    """Squared L2 plus a weighted non-negative distance to a guide raster's patch.

    ``guide`` gives that distance for columns, ``guide_local`` for a query and rows of patches in
    numpy, as integers; fills need the second, and scans are faster with it.
    """
    base = l2()

    def local(q, p, k):
        if guide_local is None:
            raise ValueError("this guide has no numpy form, which a fill needs")
        return base.local(q, p, k) + weight * guide_local(q, p)

    def block(q, p, known):
        return base.block(q, p, known) + weight * np.stack([guide_local(x, p) for x in q])

    return Cost("guided", lambda q, p, k: base.column(q, p, k) + weight * guide(q, p), local, True, 1.0, 2, block if guide_local else None, guide_local is not None)


def blend_weights(query: np.ndarray, patches: np.ndarray, known: np.ndarray, ridge: float = 1e-3) -> np.ndarray:
    """Coefficients with sum 1 of the combination of patches closest to the query where known."""
    e = ((patches - query) * known).astype(float)
    gram = e @ e.T
    gram += np.eye(len(gram)) * (ridge * max(1.0, np.trace(gram)))
    w = np.linalg.solve(gram, np.ones(len(gram)))
    return w / w.sum()
