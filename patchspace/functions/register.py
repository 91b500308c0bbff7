"""Functions that can be called from SQL, registered as SQL functions where SQL can say them."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from patchspace.functions import zcurve
from patchspace.shared import ship

# name, parameters, result, body
SQL_FUNCTIONS = (
    ("masked_l2", "q ARRAY<SMALLINT>, p ARRAY<SMALLINT>, known ARRAY<BOOLEAN>", "BIGINT", "aggregate(zip_with(zip_with(q, p, (a, b) -> CAST(a AS BIGINT) - b), known, (d, k) -> CASE WHEN k THEN d * d ELSE 0L END), 0L, (s, x) -> s + x)"),
    ("masked_l1", "q ARRAY<SMALLINT>, p ARRAY<SMALLINT>, known ARRAY<BOOLEAN>", "BIGINT", "aggregate(zip_with(zip_with(q, p, (a, b) -> CAST(a AS BIGINT) - b), known, (d, k) -> CASE WHEN k THEN abs(d) ELSE 0L END), 0L, (s, x) -> s + x)"),
    ("box_dist2", "q ARRAY<DOUBLE>, lo ARRAY<DOUBLE>, hi ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(zip_with(lo, q, (a, v) -> greatest(a - v, 0D)), zip_with(hi, q, (b, v) -> greatest(v - b, 0D)), (a, b) -> a + b), 0D, (s, x) -> s + x * x)"),
    ("z_decode", "k BIGINT, dims INT, bits INT", "ARRAY<INT>", "transform(sequence(0, dims - 1), i -> CAST(aggregate(sequence(bits - 1, 0, -1), 0L, (s, b) -> s * 2 + getbit(k, b * dims + dims - 1 - i)) AS INT))"),
    ("z_less", "a ARRAY<INT>, b ARRAY<INT>", "BOOLEAN", "element_at(zip_with(a, b, (x, y) -> x < y), 1 - array_max(transform(zip_with(a, b, (x, y) -> x ^ y), (d, i) -> struct(CASE WHEN d = 0 THEN -1 ELSE CAST(floor(log2(d)) AS INT) END AS bit, -i AS first))).first)"),
    ("z_encode", "p ARRAY<INT>, bits INT", "BIGINT", "aggregate(flatten(transform(sequence(bits - 1, 0, -1), b -> transform(p, v -> CAST(getbit(CAST(v AS BIGINT), b) AS BIGINT)))), 0L, (s, x) -> s * 2 + x)"),
)


def register(spark: SparkSession) -> list[str]:
    """Temporary SQL functions, and a table function ``z_ranges(lo, hi, bits, most)``."""
    ship(spark)
    for name, params, kind, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {kind} RETURN {body}")

    @F.udtf(returnType="z_lo: long, z_hi: long")
    class ZRanges:
        def eval(self, lo, hi, bits: int, most: int):
            yield from zcurve.ranges(list(lo), list(hi), bits, most)

    spark.udtf.register("z_ranges", ZRanges)
    return [f[0] for f in SQL_FUNCTIONS] + ["z_ranges"]
