"""Which cells are unknown. A mask is ``image_id, y, x, known``; ``damage`` applies it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.functions.portable import MODULUS, portable_hash
from patchspace.shared import table

IMAGE_STEP = 1000003


def _shape(raster: DataFrame) -> DataFrame:
    return raster.groupBy("image_id").agg((F.max("y") + 1).alias("h"), (F.max("x") + 1).alias("w"))


def cell_hash(raster: DataFrame) -> DataFrame:
    """The raster's cells with a portable hash of (image, cell)."""
    cells = raster.select("image_id", "y", "x").join(_shape(raster), "image_id")
    return cells.withColumn("hash", portable_hash(F.col("y").cast("long") * F.col("w") + F.col("x") + F.col("image_id") * IMAGE_STEP))


def hash_mask(raster: DataFrame, p: float) -> DataFrame:
    """Unknown where the hash is below p: sparse acquisition."""
    return cell_hash(raster).select("image_id", "y", "x", (F.col("hash") >= int(p * MODULUS)).alias("known"))


def _first(cells: DataFrame, bucket: Column, order: list, p: float) -> DataFrame:
    """The mask whose unknown cells are the first floor(p * cells) of each image by (bucket, *order).

    Buckets are counted first and only ranked within, so no task holds an image; a row per
    bucket and image carries the number of cells ahead of it.
    """
    cells = cells.withColumn("bucket", bucket)
    sizes = cells.groupBy("image_id", "bucket").agg(F.count("*").alias("m"))
    before = Window.partitionBy("image_id").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select("image_id", "bucket", F.coalesce(F.sum("m").over(before), F.lit(0)).alias("ahead"))
    ranked = cells.withColumn("rank", F.row_number().over(Window.partitionBy("image_id", "bucket").orderBy(*order)))
    ranked = ranked.join(sizes, ["image_id", "bucket"])
    return ranked.select("image_id", "y", "x", (F.col("rank") + F.col("ahead") > F.floor(F.col("h") * F.col("w") * p)).alias("known"))


def exact_hash_mask(raster: DataFrame, p: float) -> DataFrame:
    """As ``hash_mask``, with exactly floor(p * cells) unknown cells in every image."""
    return _first(cell_hash(raster), F.shiftright("hash", 19), ["hash", "y", "x"], p)


def hole_mask(raster: DataFrame, part: int = 4) -> DataFrame:
    """One centred rectangle of a ``part``-th of each side: a deleted object."""
    cells = raster.select("image_id", "y", "x").join(_shape(raster), "image_id")
    inside = lambda c, n: F.col(c).between(F.expr(f"({n} - {n} div {part}) div 2"), F.expr(f"({n} - {n} div {part}) div 2 + {n} div {part} - 1"))
    return cells.select("image_id", "y", "x", (~(inside("y", "h") & inside("x", "w"))).alias("known"))


def margin_mask(raster: DataFrame, margin: int) -> DataFrame:
    cells = raster.select("image_id", "y", "x").join(_shape(raster), "image_id")
    known = F.col("y").between(margin, F.col("h") - margin - 1) & F.col("x").between(margin, F.col("w") - margin - 1)
    return cells.select("image_id", "y", "x", known.alias("known"))


def lattice_mask(raster: DataFrame, factor: int = 2) -> DataFrame:
    return raster.select("image_id", "y", "x", ((F.col("y") % factor == 0) & (F.col("x") % factor == 0)).alias("known"))


def text_mask(spark: SparkSession, sf_dir: str, raster: DataFrame, p: float = 0.2) -> DataFrame:
    """Bits of benchmark characters drawn as columns of 7, up to p of the cells.

    Characters of all items are laid out in item order, a line of them seven cells high with one free
    row after it. The cells of the glyphs come first, in layout order, then others in hash order, so that
    exactly floor(p * cells) cells of each image are unknown.
    """
    items = table(sf_dir, "benchmark", spark).where(F.length("text") > 0).select("item_id", "text", F.length("text").alias("length"))
    before = Window.orderBy("item_id").rowsBetween(Window.unboundedPreceding, -1)  # a row per item
    starts = items.select(F.col("item_id").alias("s_id"), F.coalesce(F.sum("length").over(before), F.lit(0)).alias("start"))
    chars = items.join(starts, F.col("item_id") == F.col("s_id")).select("start", F.posexplode(F.split("text", "")).alias("at", "c")).where("c <> ''")
    chars = chars.select((F.col("start") + F.col("at")).alias("turn"), F.ascii("c").cast("long").alias("code"))
    cells = cell_hash(raster).withColumn("bit", F.col("y") % 8).withColumn("place", F.when((F.col("bit") < 7) & (F.expr("y div 8") < F.expr("h div 8")), F.expr("y div 8") * F.col("w") + F.col("x")))
    cells = cells.join(chars, F.col("place") == F.col("turn"), "left")
    on = F.coalesce(F.getbit("code", "bit") == 1, F.lit(False))
    cells = cells.withColumn("turn", F.when(on, F.col("turn")))
    bucket = F.when(on, F.expr("turn div 512")).otherwise(F.shiftright("hash", 19) + (1 << 40))
    return _first(cells, bucket, [F.col("turn").asc_nulls_last(), "hash", "y", "x"], p)


def damage(raster: DataFrame, mask: DataFrame) -> DataFrame:
    """The raster with unknown cells where the mask has them."""
    m = mask.withColumnRenamed("known", "_known")
    known = F.col("known") & F.coalesce("_known", F.lit(True))
    return raster.join(m, ["image_id", "y", "x"], "left").select("image_id", "y", "x", F.when(known, F.col("pix")).alias("pix"), known.alias("known"))


def coverage(mask: DataFrame) -> DataFrame:
    """Unknown cells, cells and their ratio per image."""
    n = mask.groupBy("image_id").agg(F.count("*").alias("cells"), F.count(F.when(~F.col("known"), 1)).alias("unknown"))
    return n.withColumn("coverage", F.round(F.col("unknown") / F.col("cells"), 6))
