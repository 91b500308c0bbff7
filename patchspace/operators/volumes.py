"""Volumes in boxes: each task holds the cubes of one box, whatever the size of the volume.

A box has some layers and rows of a volume and all its columns, and as many cells more as its cubes
reach over. Cells that hold 0 need no row.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patchspace.operators import kernels
from patchspace.operators.reduce import summed
from patchspace.shared import ship

CUBES, SAMPLES = 200_000, 16_000_000  # of a box at most
CHUNK = 4_000_000  # samples that are doubles at once
BOX = "box int, samples binary, salt int, n long, s binary, p binary, asked binary, vals binary"


@dataclass(frozen=True)
class Boxes:
    """How a volume of ``shape`` (layers, rows, columns) is cut for cubes of side ``k``."""

    shape: tuple[int, int, int]
    k: int
    most: int = field(default_factory=lambda: CUBES)  # cubes of a box

    @property
    def counts(self) -> tuple[int, int, int]:
        """Cubes along each axis."""
        return tuple(max(0, n - self.k + 1) for n in self.shape)

    @property
    def cubes(self) -> int:
        z, y, x = self.counts
        return z * y * x

    @property
    def step(self) -> tuple[int, int]:
        """Cubes of a box along layers and rows."""
        z, y, x = self.counts
        most = min(self.most, SAMPLES // self.k**3)
        rows = min(y, max(1, most // x))
        return min(z, max(1, most // (x * rows))), rows

    @property
    def across(self) -> int:
        return -(-self.counts[1] // self.step[1])

    @property
    def n(self) -> int:
        return -(-self.counts[0] // self.step[0]) * self.across

    def at(self, box: int) -> tuple[tuple[int, int], tuple[int, int, int]]:
        """First layer and row of a box, and its cells along each axis."""
        z, y = box // self.across * self.step[0], box % self.across * self.step[1]
        return (z, y), (min(self.step[0], self.counts[0] - z) + self.k - 1, min(self.step[1], self.counts[1] - y) + self.k - 1, self.shape[2])

    def cut(self, box: int, samples: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """A box's cubes as rows of samples, their centres in the volume and their numbers in it, by layer, row, column."""
        (z, y), size = self.at(box)
        vol = samples.reshape(size)
        p, centres = kernels.cubes(vol, np.ones(size, bool), self.k)
        centres = centres + [z, y, 0]
        first = centres - self.k // 2
        return p, centres, (first[:, 0] * self.counts[1] + first[:, 1]) * self.counts[2] + first[:, 2]

    def centres(self, numbers: np.ndarray) -> np.ndarray:
        return np.stack(np.unravel_index(numbers, self.counts), 1) + self.k // 2


def boxed(cells: DataFrame, b: Boxes, asked: np.ndarray) -> DataFrame:
    """A row per box from the cells (z, y, x, v) of a volume: its samples, the sums and products of its cubes for
    ``fit_sums``, and the samples of those of its cubes whose numbers are ``asked`` for."""
    spark = cells.sparkSession
    ship(spark)

    def met(axis: str, n: int, step: int):
        first, last = F.greatest(F.col(axis) - (b.k - 1), F.lit(0)), F.least(F.col(axis), F.lit(n - 1))
        return F.explode(F.sequence(F.floor(first / step), F.floor(last / step)))

    dealt = cells.withColumn("bz", met("z", b.counts[0], b.step[0])).withColumn("by", met("y", b.counts[1], b.step[1]))
    dealt = dealt.select((F.col("bz") * b.across + F.col("by")).cast("int").alias("box"), *[F.col(c).cast("int").alias(c) for c in "zyxv"])
    every = spark.range(b.n).select(F.col("id").cast("int").alias("box"), *[F.lit(None).cast("int").alias(c) for c in "zyxv"])  # boxes of zeros too

    def build(key, rows):
        box = int(key[0])
        (z, y), size = b.at(box)
        rows = rows[rows.z.notna()].astype(np.int64)
        vol = np.zeros(size, np.int16)
        vol[rows.z - z, rows.y - y, rows.x] = rows.v
        p, _, numbers = b.cut(box, vol)
        s, prod = np.zeros(b.k**3, np.int64), np.zeros((b.k**3, b.k**3), np.int64)
        for at in range(0, len(p), max(1, CHUNK // b.k**3)):
            x = p[at : at + max(1, CHUNK // b.k**3)].astype(np.float64)  # products of bytes: exact below 2^53
            s, prod = s + x.sum(0).astype(np.int64), prod + (x.T @ x).astype(np.int64)
        own = np.flatnonzero(np.isin(numbers, asked))
        return pd.DataFrame([(box, vol.tobytes(), box % 16, len(p), s.tobytes(), prod.tobytes(), numbers[own].astype(np.int64).tobytes(), p[own].tobytes())], columns=["box", "samples", "salt", "n", "s", "p", "asked", "vals"])

    return every.unionByName(dealt).groupBy("box").applyInPandas(build, BOX)


def fit_sums(boxes: DataFrame) -> tuple[int, np.ndarray, np.ndarray]:
    """(n, sums, sums of products) of all cubes."""
    return summed(boxes.select("salt", "n", "s", "p"))


def asked_of(boxes: DataFrame, k: int) -> dict[int, np.ndarray]:
    """Number -> samples of the cubes asked for (they are the caller's few)."""
    out = {}
    for r in boxes.where("length(asked) > 0").select("asked", "vals").collect():
        out |= dict(zip(np.frombuffer(r.asked, np.int64).tolist(), np.frombuffer(r.vals, np.int16).reshape(-1, k**3), strict=True))
    return out
