"""Patches, dictionaries, the fill front, active patches and pasting, over rows of cells."""

from __future__ import annotations

from typing import TYPE_CHECKING

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.functions.portable import portable_hash
from patchspace.shared import staged

if TYPE_CHECKING:
    from patchspace.operators.zindex import ZIndex

STEP = 1 << 20  # cells per side of the largest raster a patch_id can address


def patch_id(image: Column, y: Column, x: Column) -> Column:
    """Unique over images: image, row and column of the centre, 20 bits for each of the latter."""
    return (image * STEP + y) * STEP + x


def gather(raster: DataFrame, k: int, ndim: int = 2) -> DataFrame:
    """Every k-wide window that lies on the raster: image_id, cy, cx (and cz), cells.

    Rows of a window come from ordered windows over cell rows (a shuffle by image and row), then
    columns of such rows (a shuffle by image and column): k arrays of k cells instead of k*k
    copies of every cell.
    """
    axes = ["z", "y", "x"][3 - ndim :]
    cell = F.struct(F.col("pix").alias("pix"), F.col("known").alias("known"))
    rows = raster.withColumn("_w", F.array(cell)).withColumn("_at", F.array(F.col(axes[-1])))
    for axis in reversed(axes):
        others = [a for a in axes if a != axis]
        frame = Window.partitionBy("image_id", *others).orderBy(axis).rowsBetween(0, k - 1)
        first, last = F.first(axis).over(frame), F.last(axis).over(frame)
        many = F.collect_list("_w").over(frame)
        rows = rows.withColumn("_n", F.size(many)).withColumn("_span", last - first).withColumn("_w", F.flatten(many)).where((F.col("_n") == k) & (F.col("_span") == k - 1)).drop("_n", "_span")
    half = k // 2
    centre = [(F.col(a) + half).cast("int").alias(f"c{a}") for a in axes]
    return rows.select("image_id", *centre, F.col("_w").alias("cells"))


def extract_patches(raster: DataFrame, k: int, stride: int = 1, ndim: int = 2) -> DataFrame:
    """patch_id, image_id, cy, cx, vals, known: one patch per centre, in (row, column, channel)
    order; unknown samples are null in ``vals``."""
    found = gather(raster, k, ndim)
    if stride > 1:
        for a in ("cz", "cy", "cx")[3 - ndim :]:
            found = found.where(F.pmod(F.col(a) - k // 2, F.lit(stride)) == 0)
    channels = F.coalesce(F.array_max(F.transform("cells", lambda c: F.size(c["pix"]))), F.lit(1))
    hole = F.transform(F.sequence(F.lit(1), F.greatest(channels, F.lit(1))), lambda _: F.lit(None).cast("smallint"))
    vals = F.flatten(F.transform("cells", lambda c: F.coalesce(c["pix"], hole)))
    known = F.flatten(F.transform("cells", lambda c: F.transform(F.sequence(F.lit(1), F.greatest(channels, F.lit(1))), lambda _: c["known"])))
    pid = patch_id(F.col("image_id"), F.col("cy"), F.col("cx"))
    if ndim == 3:  # 16 bits per axis
        pid = ((F.col("image_id") * 65536 + F.col("cz")) * 65536 + F.col("cy")) * 65536 + F.col("cx")
    return found.select(pid.alias("patch_id"), "image_id", *[c for c in ("cz", "cy", "cx")[3 - ndim :]], vals.alias("vals"), known.alias("known"))


def build_dictionary(raster: DataFrame, k: int, stride: int = 1, sample: float | None = None, distinct: bool = False, ndim: int = 2) -> DataFrame:
    """The wholly known patches. ``sample`` keeps a hash share, ``distinct`` one of equal patches."""
    out = extract_patches(raster, k, stride, ndim).where(F.forall("known", lambda x: x)).drop("known")
    if sample is not None:
        out = out.where(portable_hash(F.col("patch_id")) < int(sample * (1 << 31)))
    if distinct:
        keep = [c for c in out.columns if c not in ("vals",)]
        out = out.groupBy("vals").agg(F.min(F.struct(*keep)).alias("one")).select("one.*", "vals").select(out.columns)
    return out


STRIP = 256  # cells of a strip, a piece of a raster's row


class RasterPatches:
    """The dictionary of a raster that is never written out: patches are cut where they are asked for."""

    def __init__(self, raster: DataFrame, k: int):
        self.raster, self.k = raster, k
        self._strips: DataFrame | None = None

    @property
    def frame(self) -> DataFrame:
        """All wholly known patches, as a table."""
        return build_dictionary(self.raster, self.k)

    @property
    def strips(self) -> DataFrame:
        """image_id, y, strip, x0, cells: known cells of a piece of a row, written once, in order of x."""
        if self._strips is None:
            cells = self.raster.where("known").groupBy("image_id", "y", F.expr(f"x div {STRIP}").alias("strip"))
            strips = cells.agg(F.array_sort(F.collect_list(F.struct("x", "pix"))).alias("cells"))
            self._strips = staged(strips, "strips")
        return self._strips

    def cut(self, ids: DataFrame) -> DataFrame:
        """patch_id, vals of the patches with these identifiers: k rows of each, from the strips they cross.

        A patch that is not wholly known, or not on the raster, has no row.
        """
        half, k = self.k // 2, self.k
        at = ids.select("patch_id", F.shiftright("patch_id", 40).alias("image_id"), F.pmod(F.shiftright("patch_id", 20), F.lit(STEP)).cast("int").alias("cy"), F.pmod("patch_id", F.lit(STEP)).cast("int").alias("cx"))
        rows = at.select("patch_id", "image_id", "cx", F.explode(F.sequence(F.col("cy") - half, F.col("cy") - half + (k - 1))).alias("y"))
        first, last = F.expr(f"(cx - {half}) div {STRIP}"), F.expr(f"(cx - {half} + {k - 1}) div {STRIP}")
        rows = rows.select("patch_id", "image_id", "cx", "y", F.explode(F.sequence(first, last)).alias("strip"))
        part = rows.join(self.strips, ["image_id", "y", "strip"])
        part = part.select("patch_id", "y", "strip", F.filter("cells", lambda c: c["x"].between(F.col("cx") - half, F.col("cx") - half + (k - 1))).alias("cells"))
        whole = part.groupBy("patch_id").agg(F.array_sort(F.collect_list(F.struct("y", "strip", "cells"))).alias("parts"))
        cells = F.flatten(F.transform("parts", lambda p: p["cells"]))
        return whole.select("patch_id", cells.alias("cells")).where(F.size("cells") == k * k).select("patch_id", F.flatten(F.transform("cells", lambda c: c["pix"])).alias("vals"))


def save_dictionary(dictionary: DataFrame, path: str, index: ZIndex | None = None) -> None:
    """Write a dictionary; with an index, in curve order, a folder for each of its indices."""
    if index is None:
        dictionary.write.mode("errorifexists").parquet(path)
        return
    keys = index.entries.select("index_id", "zkey", "patch_id")
    rows = keys.join(dictionary, "patch_id").repartitionByRange("index_id", "zkey", "patch_id").sortWithinPartitions("index_id", "zkey", "patch_id")
    rows.write.mode("errorifexists").partitionBy("index_id").parquet(path)


def load_dictionary(spark: SparkSession, path: str) -> DataFrame:
    """A saved dictionary, with the columns that ``build_dictionary`` gives."""
    found = spark.read.parquet(path)
    if {"index_id", "zkey"} <= set(found.columns):  # saved in curve order: a patch stands once in each index
        found = found.where(F.col("index_id") == found.agg(F.min("index_id")).first()[0]).drop("index_id", "zkey")
    missing = {"patch_id", "image_id", "vals"} - set(found.columns)
    if missing:
        raise ValueError(f"not a dictionary: no {sorted(missing)}")
    return found


def fill_front(raster: DataFrame) -> DataFrame:
    """Known cells with an unknown cell beside them (four neighbours)."""
    steps = F.array(*[F.struct(F.lit(dy).alias("dy"), F.lit(dx).alias("dx")) for dy, dx in ((-1, 0), (1, 0), (0, -1), (0, 1))])
    beside = raster.where(~F.col("known")).select("image_id", "y", "x", F.explode(steps).alias("s")).select("image_id", (F.col("y") + F.col("s.dy")).alias("y"), (F.col("x") + F.col("s.dx")).alias("x"))
    return raster.where("known").select("image_id", "y", "x").join(beside, ["image_id", "y", "x"], "left_semi")


def active_patches(front: DataFrame, raster: DataFrame, k: int) -> DataFrame:
    """Queries around front cells: query_id, image_id, cy, cx, vals, known."""
    at = front.select("image_id", F.col("y").alias("cy"), F.col("x").alias("cx"))
    found = extract_patches(raster, k).join(at, ["image_id", "cy", "cx"], "left_semi")
    return found.select(F.col("patch_id").alias("query_id"), "image_id", "cy", "cx", "vals", "known")


def paste(raster: DataFrame, winners: DataFrame, k: int) -> DataFrame:
    """Write the winning patches' samples into unknown cells only.

    ``winners``: image_id, cy, cx, vals. Where two overlap, the smaller centre writes.
    """
    channels = F.expr(f"size(vals) div {k * k}").cast("int")
    half = k // 2
    cells = winners.withColumn("c", channels).select("image_id", "cy", "cx", "vals", "c", F.explode(F.sequence(F.lit(0), F.lit(k * k - 1))).alias("i"))
    cells = cells.select("image_id", (F.col("cy") - half + F.expr(f"i div {k}")).cast("int").alias("y"), (F.col("cx") - half + F.col("i") % k).cast("int").alias("x"), F.slice("vals", F.col("i") * F.col("c") + 1, F.col("c")).alias("new"), "cy", "cx")
    best = cells.groupBy("image_id", "y", "x").agg(F.min_by("new", F.struct("cy", "cx")).alias("new"))
    joined = raster.join(best, ["image_id", "y", "x"], "left")
    return joined.select("image_id", "y", "x", F.when(F.col("known"), F.col("pix")).otherwise(F.col("new")).alias("pix"), (F.col("known") | F.col("new").isNotNull()).alias("known"))


def half_patches(patches: DataFrame, k: int, rows_known: int, channels: int = 1) -> DataFrame:
    """Patches as queries of which only the first rows are known."""
    n = k * k * channels
    known = F.array(*[F.lit(i < rows_known * k * channels) for i in range(n)])
    return patches.select(F.col("patch_id").alias("query_id"), "image_id", "cy", "cx", "vals", known.alias("known"))
