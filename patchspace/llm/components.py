"""Connected components of an edge table by joins, without gathering edges anywhere."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patchspace.llm.spread import spread_join
from patchspace.shared import staged


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges(a, b)`` of longs -> ``(node, component)``, the smallest node of each component.

    Rounds of star contraction: every node hangs its larger neighbours below its smallest one,
    then its smaller ones too, until no edge changes. A round halves the paths at least; a node
    with many edges costs a row per edge, minima combine before the shuffle, and a hub's edges are
    dealt over many tasks.
    """
    now = staged(_distinct(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))), "cc")
    state = _fingerprint(now)
    for _ in range(max_rounds):
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), F.count("*").alias("n"))
        large = spread_join(both, low, "a", 2 * state[0], F.col("b")).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = staged(_distinct(large.where("a <> b")), "cc-large")
        least = staged(large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")), "cc-least")
        small = spread_join(large, least, "a", 2 * state[0], F.col("b"))
        small = small.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        now = staged(_distinct(small.where("a <> b")), "cc")
        fresh = _fingerprint(now)
        if fresh == state:
            break
        state = fresh
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def _distinct(edges: DataFrame) -> DataFrame:
    return edges.distinct()


def _fingerprint(edges: DataFrame) -> tuple:
    h = F.xxhash64("a", "b")
    row = edges.agg(F.count("*"), F.sum(F.shiftrightunsigned(h, 24)), F.bit_xor(h)).first()
    return tuple(row)
