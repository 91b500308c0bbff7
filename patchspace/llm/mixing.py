"""Temperature mixing of sources, in DataFrame functions only.

Weights are source token shares raised to an exponent and normalised. Exponent 1 keeps the
shares, 0 makes all sources equal. The exponent is bisected: the largest that reaches the
target entropy, or, if that repeats some source more often than allowed, the smallest that
keeps the repetition limit. The budget is given in tokens, or (``budget=None``) is the smallest
for which no source is cut, so that every document occurs at least once.

A source's stream is its documents in a seeded order, once for each epoch, each epoch in an
order of its own, up to the source's part of the budget. The stream is cut into blocks: block b
takes from each source the same share of ``block_tokens``, and is then permuted as a whole.
Positions are prefix sums of two levels (within hash ranges of a source, then over the ranges'
sums), so a source of any size is spread over as many tasks as it has ranges.

Null text counts no tokens; null sources form one source of their own; repeated rows are mixed
row by row; a table without tokens keeps every row once, and the documents of a source without
tokens are dealt evenly over the blocks. Other columns may have any name.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from patchspace.shared import staged

MAX_REPEATS, ENTROPY_SHARE, BLOCK_TOKENS, SEED = 2.0, 1.0, 1 << 20, 7
STEPS, HALVINGS = 48, 8  # of the bisection in all, and in one pass over the sources
NO_SOURCE = "\x00"


def token_count(text: Column) -> Column:
    """Words between ASCII white space; null has none."""
    words = F.filter(F.split(text, r"[ \t\n\x0B\f\r]+"), lambda w: w != "")
    return F.when(text.isNull(), 0).otherwise(F.size(words)).cast("long")


def _unit(*cols: Column) -> Column:
    """A seeded position in [0, 1) from columns."""
    return F.pmod(F.xxhash64(*cols), F.lit(1 << 52)) / F.lit(float(1 << 52))


def solve_exponent(by: DataFrame, all_tokens: float, target_entropy: float, limit: float) -> float:
    """The exponent for the sources of ``by`` (column tokens, positive), by bisection.

    Entropy falls and repeats fall as the exponent rises, so both conditions are bisected on
    [0, 1], ``HALVINGS`` halvings in one pass over the sources: a pass evaluates all the
    midpoints that these halvings could ask for, as sums that combine before the shuffle. Sources
    are never gathered, however many there are.
    """
    share = F.col("tokens") / F.lit(all_tokens)

    def bisect(high_enough) -> float:
        """The least exponent that ``high_enough`` holds for, within 2 ** -STEPS."""
        lo, hi = 0.0, 1.0
        for _ in range(STEPS // HALVINGS):
            n = 1 << HALVINGS
            mids = [lo + (hi - lo) * i / n for i in range(1, n)]
            power = F.pow("p", "a")
            at = by.select(share.alias("p"), F.explode(F.array(*[F.lit(a) for a in mids])).alias("a"))
            sums = at.groupBy("a").agg(F.sum(power).alias("z"), F.sum(F.when(power > 0, power * F.ln(power)).otherwise(0.0)).alias("t"), F.max(F.pow("p", F.col("a") - 1)).alias("most"), F.min(F.pow("p", F.col("a") - 1)).alias("least"))
            ok = {r.a: high_enough(r) for r in sums.collect()}  # a row per midpoint
            first = next((i for i, a in enumerate(mids) if ok[a]), n - 1)
            lo, hi = lo + (hi - lo) * first / n, lo + (hi - lo) * (first + 1) / n
        return hi

    ends = by.select(F.max(share).alias("most"), F.min(share).alias("least")).first()
    by_entropy = bisect(lambda r: math.log(r.z) - r.t / r.z < target_entropy)
    by_repeats = 0.0 if ends.most / ends.least <= limit else bisect(lambda r: r.most / r.least <= limit)
    return max(0.0 if by_entropy <= 2.0 ** (2 - STEPS) else by_entropy, by_repeats)


def weights(rows: DataFrame, entropy_share: float = ENTROPY_SHARE, max_repeats: float = MAX_REPEATS, budget: float | None = None) -> DataFrame:
    """One row per source: source_key, tokens, docs, exponent, weight, target_tokens, rate, budget.

    ``entropy_share``: target entropy as a part of the largest possible, ln of the number of
    sources. ``rate`` is the number of passes over the source.
    """
    by = staged(rows.groupBy("source_key").agg(F.sum("n_tokens").alias("tokens"), F.count("*").alias("docs")), "mix-sources")
    some = by.where("tokens > 0")
    facts = some.agg(F.coalesce(F.sum("tokens"), F.lit(0)).alias("all"), F.count("*").alias("n")).first()
    exponent = solve_exponent(some, float(facts["all"]), math.log(max(1, facts.n)) * entropy_share - 1e-12, float(max_repeats)) if facts.n else 1.0
    share = F.col("tokens") / F.lit(float(max(1, facts["all"])))
    powers = some.agg(F.sum(F.pow(share, F.lit(exponent))).alias("norm"), F.max(F.pow(share, F.lit(1.0 - exponent))).alias("most")).first()
    norm = powers.norm or 1.0
    full = float(budget) if budget is not None else facts["all"] * (powers.most or 0.0) * norm
    weight = F.when(F.col("tokens") > 0, F.pow(share, F.lit(exponent)) / norm).otherwise(0.0)
    out = by.withColumn("exponent", F.lit(exponent)).withColumn("weight", weight).withColumn("target_tokens", F.col("weight") * full)
    rate = F.when(F.col("tokens") > 0, F.col("target_tokens") / F.col("tokens")).otherwise(1.0)
    out = out.withColumn("rate", rate).withColumn("full_epochs", F.floor(F.col("rate") + 1e-9).cast("int"))
    return out.withColumn("budget", F.lit(full))


def _lean(docs: DataFrame, id_col: str, source_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), F.coalesce(F.col(source_col).cast("string"), F.lit(NO_SOURCE)).alias("source_key"), token_count(F.col(text_col)).alias("n_tokens"))


def plan_mix(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", entropy_share: float = ENTROPY_SHARE, max_repeats: float = MAX_REPEATS, budget: float | None = None, block_tokens: int = BLOCK_TOKENS, seed: int = SEED) -> tuple[DataFrame, DataFrame]:
    """(occurrences, weights): every occurrence of a document with its block and position."""
    rows = staged(_lean(docs, id_col, source_col, text_col), "mix-rows")
    w = staged(weights(rows, entropy_share, max_repeats, budget), "mix-weights")
    occ = _streams(rows, w, seed)
    block = F.floor(F.col("start_token") / F.greatest(F.col("weight") * block_tokens, F.lit(1.0)))
    # a source without tokens has no share of a block: its documents are dealt evenly over all blocks
    n_blocks = F.greatest(F.ceil(F.col("budget") / block_tokens), F.ceil(F.col("docs") / block_tokens), F.lit(1))
    block = F.when(F.col("tokens") > 0, block).otherwise(F.floor(F.col("place") * n_blocks)).cast("long")
    occ = occ.select("doc_id", "source", "n_tokens", "epoch", "start_token", "place", block.alias("block"))
    order = Window.partitionBy("block").orderBy(F.xxhash64(F.lit(seed), F.lit("block"), "doc_id", "epoch"), "doc_id", "epoch", "place")
    occ = occ.withColumn("position", F.row_number().over(order) - 1)
    return occ.select("doc_id", "source", "n_tokens", "epoch", F.col("start_token").alias("source_offset"), "block", "position"), w


def _streams(rows: DataFrame, w: DataFrame, seed: int) -> DataFrame:
    """Each document once per epoch in which its source's budget reaches it."""
    n = rows.count()
    ranges = max(1, math.isqrt(n))  # as many ranges as rows in a range: both levels stay small
    joined = rows.join(w.select("source_key", "weight", "tokens", "docs", "budget", "target_tokens", "full_epochs"), "source_key")
    epochs = joined.withColumn("epoch", F.explode(F.sequence(F.lit(0), F.col("full_epochs"))))
    epochs = epochs.withColumn("place", _unit(F.lit(seed), F.col("epoch"), F.col("doc_id"), F.col("source_key")))
    epochs = epochs.withColumn("range", F.floor(F.col("place") * ranges).cast("int"))
    sums = epochs.groupBy("source_key", "epoch", "range").agg(F.sum("n_tokens").alias("in_range"))
    before = Window.partitionBy("source_key", "epoch").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select("source_key", "epoch", "range", F.coalesce(F.sum("in_range").over(before), F.lit(0)).alias("before"))
    inner = Window.partitionBy("source_key", "epoch", "range").orderBy("place", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)
    placed = epochs.withColumn("ahead", F.coalesce(F.sum("n_tokens").over(inner), F.lit(0)))
    placed = placed.join(sums, ["source_key", "epoch", "range"])
    placed = placed.withColumn("start_token", F.col("epoch") * F.col("tokens") + F.col("before") + F.col("ahead"))
    return placed.where((F.col("epoch") < F.col("full_epochs")) | (F.col("start_token") < F.col("target_tokens") - 1e-6))


def apply_mix(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", entropy_share: float = ENTROPY_SHARE, max_repeats: float = MAX_REPEATS, budget: float | None = None, seed: int = SEED) -> DataFrame:
    """The documents with all their columns, each as often as it occurs in the mix.

    The last, partial epoch of a source ends at one place of its seeded order; so a row per
    source decides all copies, and the texts are never shuffled.
    """
    rows = staged(_lean(docs, id_col, source_col, text_col), "mix-rows")
    w = staged(weights(rows, entropy_share, max_repeats, budget), "mix-weights")
    last = _streams(rows, w, seed).where(F.col("epoch") == F.col("full_epochs"))
    ends = last.groupBy("source_key").agg(F.max("place").alias("until"))
    cut = staged(w.select("source_key", "full_epochs").join(ends, "source_key", "left"), "mix-cut")
    key = F.coalesce(F.col(source_col).cast("string"), F.lit(NO_SOURCE))
    # the row travels as one struct, so that its columns may have any name
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), key.alias("source_key"), F.col(id_col).alias("id"))
    joined = packed.join(cut, "source_key")
    place = _unit(F.lit(seed), F.col("full_epochs"), F.col("id"), F.col("source_key"))
    copies = F.col("full_epochs") + F.when(place <= F.col("until"), 1).otherwise(0)
    return joined.where(copies > 0).select("row", F.explode(F.sequence(F.lit(1), copies)).alias("copy")).select("row.*")


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return plan_mix(spark.read.parquet(f"{sf_dir}/documents.parquet"))[0]
