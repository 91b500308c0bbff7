"""The index: entries on the z-curve in blocks, and a catalogue of the blocks.

Entries are ``index_id, block_id, zkey, coord, patch_id, image_id``; patches themselves are not stored.
They are range-partitioned by (index_id, zkey) and cut into blocks of ``mu`` within each
partition, so no task sorts more than its share and no row counts are gathered. The catalogue has a row per
block: key range, number of entries, and the tight box of real-valued coordinates, which is what
prunes; quantisation only orders, so clamped values lose nothing.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.operators.footprints import Footprint
from patchspace.operators.reduce import Basis, fit_pca, matrix
from patchspace.shared import new_path, ship

UNITS = 200_000  # blocks, or groups of them, that may go to every task
ENTRY = "index_id int, zkey binary, coord array<float>, patch_id long, image_id long"
BLOCKED = "index_id int, block_id long, zkey binary, coord array<float>, patch_id long, image_id long"


@dataclass
class ZIndex:
    entries: DataFrame
    catalog: DataFrame
    bases: list[Basis]
    footprints: list[Footprint]
    k: int
    dims: int
    mu: int
    bits: int = 8

    def basis(self, index_id: int) -> Basis:
        return next(b for b in self.bases if b.index_id == index_id)

    @cached_property
    def shift(self) -> int:
        """Units are blocks as long as the catalogue has at most UNITS rows; beyond, neighbouring blocks
        share a unit, in powers of two, until there are no more units than that."""
        n, shift = self.catalog.count(), 0
        while n >> shift > UNITS:
            shift += 4
        return shift

    @property
    def grouped(self) -> bool:
        return self.shift > 0

    def unit_of(self, block_id: Column) -> Column:
        return F.shiftright(block_id, self.shift)

    def units(self) -> DataFrame:
        """index_id, unit, n, z_lo, box_lo, box_hi: what every task may know of the catalogue."""
        if not self.grouped:
            return self.catalog.select("index_id", F.col("block_id").alias("unit"), "n", "z_lo", "box_lo", "box_hi")
        axis = lambda f, c: F.array(*[f(F.col(c)[i]) for i in range(self.dims)])
        grouped = self.catalog.groupBy("index_id", self.unit_of(F.col("block_id")).alias("unit"))
        return grouped.agg(F.sum("n").alias("n"), F.min("z_lo").alias("z_lo"), axis(F.min, "box_lo").alias("box_lo"), axis(F.max, "box_hi").alias("box_hi"))


def project(dictionary: DataFrame, bases: list[Basis], bits: int = 8, order: list[int] | None = None) -> DataFrame:
    """Entries of all indices in one pass over the patches."""
    ship(dictionary.sparkSession)

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            x = matrix(batch.column("vals")).astype(np.float64)
            for b in bases:
                coords = b.project(x)
                cols = b.quantise(coords, bits)
                keyed = cols if order is None else cols[:, [i for i in order if i < cols.shape[1]]]
                from patchspace.functions.zcurve import encode

                keys = encode(keyed, bits)
                flat = pa.array(coords.astype(np.float32).ravel())
                arr = pa.ListArray.from_arrays(pa.array(np.arange(0, coords.size + 1, coords.shape[1], dtype=np.int32)), flat)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), b.index_id, np.int32)), pa.array([k.tobytes() for k in keys], pa.binary()), arr, batch.column("patch_id"), batch.column("image_id")], names=["index_id", "zkey", "coord", "patch_id", "image_id"])

    return dictionary.select("patch_id", "image_id", "vals").mapInArrow(run, ENTRY)


def cut_blocks(entries: DataFrame, mu: int, partitions: int | None = None) -> DataFrame:
    """Entries sorted along the curve and numbered in blocks of ``mu``; a block has one index."""
    key = ["index_id", "zkey", "patch_id"]
    dealt = entries.repartitionByRange(*([partitions] if partitions else []), *key).sortWithinPartitions(*key)

    def number(batches):
        base, block, now, room = TaskContext.get().partitionId() << 32, -1, None, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            ids = np.empty(batch.num_rows, np.int64)
            index = batch.column("index_id").to_numpy()
            at = 0
            while at < len(ids):
                if now != index[at] or not room:
                    now, room, block = index[at], mu, block + 1
                end = min(at + room, int(np.searchsorted(index[at:], now, "right")) + at)
                ids[at:end] = base | block
                room -= end - at
                at = end
            yield pa.RecordBatch.from_arrays([batch.column("index_id"), pa.array(ids), *[batch.column(c) for c in ("zkey", "coord", "patch_id", "image_id")]], names=["index_id", "block_id", "zkey", "coord", "patch_id", "image_id"])

    return dealt.mapInArrow(number, BLOCKED)


def block_catalog(blocked: DataFrame, dims: int) -> DataFrame:
    """One row per block. Blocks lie within partitions, and sums combine before the shuffle."""
    axis = lambda f: F.array(*[f(F.col("coord")[i]) for i in range(dims)])
    return blocked.groupBy("index_id", "block_id").agg(F.count("*").alias("n"), F.min("zkey").alias("z_lo"), F.max("zkey").alias("z_hi"), axis(F.min).alias("box_lo"), axis(F.max).alias("box_hi"))


def build_index(dictionary: DataFrame, fps: list[Footprint], k: int, dims: int = 10, mu: int = 256, bases: list[Basis] | None = None, bits: int = 8, path: str | None = None, order: list[int] | None = None) -> ZIndex:
    """Fit, project, sort, cut, and persist below ``path`` (by default the shared folder).

    ``order`` permutes the dimensions before keys are made; the default is falling variance.
    """
    spark = dictionary.sparkSession
    bases = fit_pca(dictionary, fps, dims) if bases is None else bases
    used = len(bases[0].loadings)
    path = path or new_path(spark, "zindex")
    cut_blocks(project(dictionary, bases, bits, order), mu).write.partitionBy("index_id").parquet(f"{path}/entries")
    entries = spark.read.schema(BLOCKED).parquet(f"{path}/entries")
    block_catalog(entries, used).write.parquet(f"{path}/catalog")
    meta = {"k": k, "dims": used, "mu": mu, "bits": bits, "footprints": [asdict(f) for f in fps], "bases": [{"index_id": b.index_id, "pos": b.pos.tolist(), "mean": b.mean.tolist(), "loadings": b.loadings.tolist(), "eigen": b.eigen.tolist(), "low": b.low, "step": b.step} for b in bases]}
    spark.createDataFrame([(json.dumps(meta),)], "meta string").coalesce(1).write.parquet(f"{path}/meta")
    return load_index(spark, path)


def load_index(spark: SparkSession, path: str) -> ZIndex:
    meta = json.loads(spark.read.parquet(f"{path}/meta").first().meta)
    fps = [Footprint(f["index_id"], f["kind"], tuple(f["pos"])) for f in meta["footprints"]]
    bases = [Basis(b["index_id"], np.array(b["pos"]), np.array(b["mean"]), np.array(b["loadings"]).reshape(-1, len(b["pos"])), np.array(b["eigen"]), b["low"], b["step"]) for b in meta["bases"]]
    return ZIndex(spark.read.schema(BLOCKED).parquet(f"{path}/entries"), spark.read.parquet(f"{path}/catalog"), bases, fps, meta["k"], meta["dims"], meta["mu"], meta["bits"])
