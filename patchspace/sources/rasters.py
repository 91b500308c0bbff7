"""Rasters and volumes made from the given tables, as rows of cells.

A raster is ``image_id, y, x, v`` before scaling and ``image_id, y, x, pix, known`` after: ``pix``
an array of channel samples, null exactly where ``known`` is false. Amounts are summed in cents,
and scaling divides integers, so every engine gets the same samples.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.functions.portable import cents
from patchspace.shared import ship, table

DAY0 = "1995-01-02"
QUANTITIES = 50
LEVELS = tuple(range(11))  # discounts in percent
# Width and height of the paper's four resolutions, an eighth per side.
SIZES = {"S": (100, 75), "M": (200, 150), "L": (256, 192), "XL": (320, 240)}


def grid(spark: SparkSession, height: int, width: int, images: Column) -> DataFrame:
    """All cells of images of one shape; ``images`` is an array column of ids."""
    ys = spark.range(height).select(F.col("id").cast("int").alias("y"))
    return ys.select(F.explode(images.cast("array<bigint>")).alias("image_id"), "y").withColumn("x", F.explode(F.sequence(F.lit(0), F.lit(width - 1))))


def on_grid(spark: SparkSession, sums: DataFrame, height: int, width: int, images: Column, value: str = "v") -> DataFrame:
    """Sums put on the full grid; cells without rows are 0, as a sum over nothing."""
    return grid(spark, height, width, images).join(sums, ["image_id", "y", "x"], "left").select("image_id", "y", "x", F.coalesce(value, F.lit(0)).cast("long").alias("v"))


def box_sum(cells: DataFrame, size: int) -> DataFrame:
    """Sums over size x size neighbours, clipped at the border: rows first, then columns."""
    r = size // 2
    rows = Window.partitionBy("image_id", "y").orderBy("x").rowsBetween(-r, r)
    cols = Window.partitionBy("image_id", "x").orderBy("y").rowsBetween(-r, r)
    return cells.withColumn("v", F.sum("v").over(rows)).withColumn("v", F.sum("v").over(cols))


def running_surface(cells: DataFrame) -> DataFrame:
    """Two-dimensional running sums."""
    rows = Window.partitionBy("image_id", "y").orderBy("x").rowsBetween(Window.unboundedPreceding, 0)
    cols = Window.partitionBy("image_id", "x").orderBy("y").rowsBetween(Window.unboundedPreceding, 0)
    return cells.withColumn("v", F.sum("v").over(rows)).withColumn("v", F.sum("v").over(cols))


def scaled(cells: DataFrame) -> DataFrame:
    """Samples 0..255 per image by integer min-max division; a constant image is 0.

    One small row per image carries the extremes, so no window holds a whole image.
    """
    ends = cells.groupBy("image_id").agg(F.min("v").alias("lo"), F.max("v").alias("hi"))
    pix = F.expr("CASE WHEN hi > lo THEN ((v - lo) * 255) div (hi - lo) ELSE 0 END").cast("smallint")
    return cells.join(ends, "image_id").select("image_id", "y", "x", F.array(pix).alias("pix"), F.lit(True).alias("known"))


def week_of(day: Column) -> Column:
    return F.floor(F.datediff(day, F.lit(DAY0)) / 7).cast("int")


def extent(cells: DataFrame, axis: str = "y") -> int:
    """Length of an axis that begins at 0: one number reaches the driver."""
    last = cells.agg(F.max(axis)).first()[0]
    return 0 if last is None else int(last) + 1


def weeks_of(lineitem: DataFrame) -> int:
    return extent(lineitem.select(week_of(F.col("l_shipdate")).alias("y")))


def sales_field(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Week of shipping x quantity, extended price in cents; as many weeks as the table has."""
    t = table(sf_dir, "lineitem", spark)
    sums = t.groupBy(week_of(F.col("l_shipdate")).alias("y"), (F.col("l_quantity").cast("int") - 1).alias("x")).agg(F.sum(cents(F.col("l_extendedprice"))).alias("v"))
    return on_grid(spark, sums.withColumn("image_id", F.lit(0).cast("long")), weeks_of(t), QUANTITIES, F.array(F.lit(0)))


def sales_smooth(spark: SparkSession, sf_dir: str, size: int = 5) -> DataFrame:
    return scaled(box_sum(sales_field(spark, sf_dir), size))


def sales_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scaled(running_surface(sales_field(spark, sf_dir)))


def market_sums(spark: SparkSession, sf_dir: str, size: str, levels: tuple[int, ...]) -> DataFrame:
    """Part ranges x week ranges, an image per discount level, extended price in cents: every row of a
    level falls in a cell of its image, whatever the size."""
    w, h = SIZES[size]
    weeks = max(1, weeks_of(table(sf_dir, "lineitem", spark)))
    parts = table(sf_dir, "part", spark).agg(F.max("p_partkey").alias("parts"))
    t = table(sf_dir, "lineitem", spark).withColumn("image_id", F.round(F.col("l_discount") * 100).cast("long")).where(F.col("image_id").isin(*levels))
    y = F.least(F.expr(f"l_partkey * {h} div (parts + 1)"), F.lit(h - 1)).cast("int")
    x = F.least(F.expr(f"week * {w} div {weeks}"), F.lit(w - 1)).cast("int")
    t = t.withColumn("week", week_of(F.col("l_shipdate")))
    sums = t.crossJoin(F.broadcast(parts)).groupBy("image_id", y.alias("y"), x.alias("x")).agg(F.sum(cents(F.col("l_extendedprice"))).alias("v"))  # one row of parts
    return on_grid(spark, sums, h, w, F.array(*[F.lit(i) for i in levels]))


def market_smooth(spark: SparkSession, sf_dir: str, size: str = "S", levels: tuple[int, ...] = LEVELS, window: int = 5) -> DataFrame:
    """The photo-like ladder: ``market_sums`` smoothed and scaled."""
    return scaled(box_sum(market_sums(spark, sf_dir, size, levels), window))


def activity_sums(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User x six-hour slot: count, sum of cents, number of types."""
    t = table(sf_dir, "events", spark)
    slot = (F.datediff("ts", F.lit("2024-01-01")) * 4 + F.floor(F.hour("ts") / 6)).cast("int")
    return t.groupBy(F.col("user_id").cast("int").alias("y"), slot.alias("x")).agg(F.count("*").alias("n"), F.sum(cents(F.col("value"))).alias("v"), F.countDistinct("event_type").alias("kinds"))


def activity_field(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All users and slots of the table."""
    sums = activity_sums(spark, sf_dir).withColumn("image_id", F.lit(0).cast("long"))
    return on_grid(spark, sums, extent(sums), extent(sums, "x"), F.array(F.lit(0)))


def activity_rgb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three channels, each scaled on its own."""
    sums = activity_sums(spark, sf_dir).withColumn("image_id", F.lit(0).cast("long"))
    full = grid(spark, extent(sums), extent(sums, "x"), F.array(F.lit(0))).join(sums, ["image_id", "y", "x"], "left").na.fill(0, ["n", "v", "kinds"])
    ends = full.groupBy("image_id").agg(*[f(c).alias(f"{c}_{k}") for c in ("n", "v", "kinds") for k, f in (("lo", F.min), ("hi", F.max))])
    one = lambda c: F.expr(f"CASE WHEN {c}_hi > {c}_lo THEN (({c} - {c}_lo) * 255) div ({c}_hi - {c}_lo) ELSE 0 END").cast("smallint")
    return full.join(ends, "image_id").select("image_id", "y", "x", F.array(one("n"), one("v"), one("kinds")).alias("pix"), F.lit(True).alias("known"))


def activity_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User x day x six-hour slot: z, y, x, v of those that have rows."""
    return activity_sums(spark, sf_dir).select(F.col("y").alias("z"), F.expr("x div 4").cast("int").alias("y"), (F.col("x") % 4).cast("int").alias("x"), "v")


def activity_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User x day x six-hour slot: image_id, z, y, x, v."""
    sums = activity_cells(spark, sf_dir)
    full = grid(spark, extent(sums), 4, F.array(F.lit(0))).withColumn("z", F.explode(F.sequence(F.lit(0), F.lit(max(0, extent(sums, "z") - 1)))))
    return full.join(sums, ["z", "y", "x"], "left").select("image_id", "z", "y", "x", F.coalesce("v", F.lit(0)).cast("long").alias("v"))


def part_surface(spark: SparkSession, sf_dir: str, width: int = 50) -> DataFrame:
    t = table(sf_dir, "part", spark)
    at = F.col("p_partkey")  # keys are dense from 0
    cells = t.select(F.lit(0).cast("long").alias("image_id"), F.floor(at / width).cast("int").alias("y"), F.pmod(at, F.lit(width)).cast("int").alias("x"), cents(F.col("p_retailprice")).alias("v"))
    return scaled(cells)


def document_corpus(spark: SparkSession, sf_dir: str, width: int = 32, least: int = 1) -> DataFrame:
    """An image per document of ``least`` characters at least: the whole text, wrapped at ``width``, the
    last row filled up with blanks."""
    t = table(sf_dir, "documents", spark).where(F.length("text") >= least)
    rows = F.ceil(F.length("text") / width).cast("int")
    line = lambda y: F.rpad(F.substring(F.col("text"), (y * width + 1).cast("int"), F.lit(width)), width, " ")
    at = t.select(F.col("doc_id").alias("image_id"), F.posexplode(F.transform(F.sequence(F.lit(0), rows - 1), line)).alias("y", "line"))
    cells = at.select("image_id", "y", F.posexplode(F.split("line", "")).alias("x", "c")).where(F.col("x") < width)
    return cells.select("image_id", "y", "x", F.array(F.least(F.ascii("c"), F.lit(255)).cast("smallint")).alias("pix"), F.lit(True).alias("known"))


def document_images(spark: SparkSession, sf_dir: str, width: int = 32, least: int = 1) -> DataFrame:
    """The images of ``document_corpus`` in a row each: image_id, width, samples (a byte a cell, row by row)."""
    ship(spark)
    t = table(sf_dir, "documents", spark).where(F.length("text") >= least).select("doc_id", "text")
    t = t.repartition(4 * spark.sparkContext.defaultParallelism)  # few files may hold many documents

    def run(batches):
        for batch in batches:
            cells = [np.minimum(np.frombuffer(x.encode("utf-32-le"), "<u4"), 255).astype(np.uint8).tobytes() for x in batch.column("text").to_pylist()]
            cells = [x + b" " * (-len(x) % width) for x in cells]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.full(len(cells), width, np.int32)), pa.array(cells, pa.binary())], names=["image_id", "width", "samples"])

    return t.mapInArrow(run, "image_id long, width int, samples binary")


def sales_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Discount level x week x quantity: z, y, x, v of those that have rows."""
    keys = [F.round(F.col("l_discount") * 100).cast("int").alias("z"), week_of(F.col("l_shipdate")).alias("y"), (F.col("l_quantity").cast("int") - 1).alias("x")]
    return table(sf_dir, "lineitem", spark).groupBy(*keys).agg(F.sum(cents(F.col("l_extendedprice"))).alias("v"))


def sales_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Week x quantity x discount level, all of the table: image_id, z, y, x, v."""
    sums = sales_cells(spark, sf_dir)
    full = grid(spark, weeks_of(table(sf_dir, "lineitem", spark)), QUANTITIES, F.array(F.lit(0))).withColumn("z", F.explode(F.sequence(F.lit(0), F.lit(10))))
    return full.join(sums, ["z", "y", "x"], "left").select("image_id", "z", "y", "x", F.coalesce("v", F.lit(0)).cast("long").alias("v"))


def scaled_volume(cells: DataFrame) -> DataFrame:
    """Samples 0..255 by the largest sum: image_id, z, y, x, pix, known."""
    ends = cells.groupBy("image_id").agg(F.max("v").alias("hi"))
    pix = F.expr("CASE WHEN hi > 0 THEN (v * 255) div hi ELSE 0 END").cast("smallint")
    return cells.join(ends, "image_id").select("image_id", "z", "y", "x", F.array(pix).alias("pix"), F.lit(True).alias("known"))


def stripes(spark: SparkSession, height: int = 64, width: int = 64, period: int = 8) -> DataFrame:
    """A periodic texture that a fill must recover exactly."""
    cells = grid(spark, height, width, F.array(F.lit(0)))
    v = (F.pmod(F.col("x") + F.col("y") * 3, F.lit(period)) * 28 + F.pmod(F.col("y"), F.lit(period // 2)) * 5).cast("smallint")
    return cells.select("image_id", "y", "x", F.array(v).alias("pix"), F.lit(True).alias("known"))


def tiled(spark: SparkSession, sf_dir: str, height: int = 64, width: int = 64, side: int = 8) -> DataFrame:
    """A periodic texture: the sums of all embedding patches, place by place, repeated over the image."""
    each = embedding_patches(spark, sf_dir).select(F.posexplode("vals").alias("at", "s"))
    sums = each.groupBy("at").agg(F.sum("s").alias("v"))
    at = (F.pmod("y", F.lit(side)) * side + F.pmod("x", F.lit(side))).alias("at")
    return scaled(grid(spark, height, width, F.array(F.lit(0))).select("image_id", "y", "x", at).join(sums, "at").drop("at"))


def embedding_patches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each embedding as an 8x8 grey patch: patch_id, image_id, cy, cx, vals.

    Vectors that are null, of another length, or hold a null or NaN are no patches; ``rejected``
    counts them.
    """
    t = table(sf_dir, "embeddings", spark).where(usable_vector(F.col("embedding")))
    vals = F.transform("embedding", lambda v: F.floor((v.cast("double") + 1) * 127.5).cast("smallint"))
    return t.select(F.col("vec_id").alias("patch_id"), F.lit(0).cast("long").alias("image_id"), F.lit(0).alias("cy"), F.col("vec_id").cast("int").alias("cx"), vals.alias("vals"))


def usable_vector(v: Column, size: int = 64) -> Column:
    return F.coalesce((F.size(v) == size) & ~F.exists(v, lambda e: e.isNull() | F.isnan(e)), F.lit(False))
