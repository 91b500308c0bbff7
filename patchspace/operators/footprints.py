"""Pixel subsets of a patch, one per index, and the choice among them.

A footprint holds the share ``c`` of a patch's pixels that lie nearest the middle of an edge or
a corner (in three dimensions: of a face, an edge or a corner). Size: floor(c * pixels + 1/2).
Order: squared distance to the anchor, then axis by axis; ties therefore have one answer.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Footprint:
    index_id: int
    kind: str
    pos: tuple[int, ...]


def footprints(k: int, c: float = 0.6, channels: int = 1, ndim: int = 2) -> list[Footprint]:
    """8 subsets in two dimensions, 26 in three: those touching the fewest sides come first."""
    anchors = [a for a in product((-1, 0, 1), repeat=ndim) if any(a)]
    anchors.sort(key=lambda a: (sum(map(abs, a)), a))
    kinds = {1: "edge" if ndim == 2 else "face", 2: "corner" if ndim == 2 else "edge", 3: "corner"}
    size = int(c * k**ndim + 0.5)
    out = []
    for i, a in enumerate(anchors):
        # doubled coordinates keep the middle of an even side an integer
        at = [(s + 1) * (k - 1) for s in a]
        cells = sorted(product(range(k), repeat=ndim), key=lambda p: (sum((2 * x - y) ** 2 for x, y in zip(p, at, strict=True)), p))[:size]
        flat = []
        for p in cells:
            n = 0
            for x in p:
                n = n * k + x
            flat += [n * channels + ch for ch in range(channels)]
        out.append(Footprint(i, kinds[sum(map(abs, a))], tuple(flat)))
    return out


def footprint_table(spark: SparkSession, fps: list[Footprint]) -> DataFrame:
    return spark.createDataFrame([(f.index_id, f.kind, list(f.pos)) for f in fps], "index_id int, kind string, pos array<int>")


def cover(queries: DataFrame, fps: list[Footprint]) -> DataFrame:
    """How many positions of each footprint a query knows, and whether it knows all."""
    table = F.broadcast(footprint_table(queries.sparkSession, fps))  # 8 or 26 rows
    known = F.size(F.filter("pos", lambda i: F.element_at(F.col("known"), i + 1)))
    return queries.join(table, F.lit(True)).withColumn("cover", known).withColumn("whole", F.col("cover") == F.size("pos"))


def select_index(queries: DataFrame, fps: list[Footprint], on_uncovered: str = "scan") -> DataFrame:
    """Each query with ``index_id``: of the footprints it knows wholly the largest, else by policy.

    ``scan``: null, the query is left to a full scan. ``mean``: the footprint with most known
    positions; unknown ones then take the index mean. ``defer``: the query is dropped for now.
    """
    if on_uncovered not in ("scan", "mean", "defer"):
        raise ValueError(f"unknown policy {on_uncovered!r}")
    cases = [F.struct(F.aggregate(F.array(*[F.lit(p + 1) for p in f.pos]), F.lit(0), lambda s, i: s + F.when(F.element_at("known", i), 1).otherwise(0)).alias("cover"), F.lit(-f.index_id).alias("rank"), F.lit(len(f.pos)).alias("size")) for f in fps]
    best = F.array_max(F.array(*cases) if on_uncovered == "mean" else F.filter(F.array(*cases), lambda s: s["cover"] == s["size"]))
    out = queries.withColumn("index_id", (-best["rank"]).cast("int"))
    return out.where(F.col("index_id").isNotNull()) if on_uncovered == "defer" else out
