"""Pieces of SQL that several query twins share."""

from __future__ import annotations

from patchspace.functions.portable import portable_hash_sql
from patchspace.operators.footprints import footprints
from patchspace.operators.reduce import frequencies
from patchspace.sources.rasters import DAY0, SIZES

CENTS = "round({0} * 100)::BIGINT"

PATCHES = """emb AS (
  SELECT vec_id AS patch_id, [floor((v::DOUBLE + 1) * 127.5)::BIGINT for v in embedding] AS vals FROM embeddings)"""

EVERY = 20  # queries are the patches whose identifier is divisible by this
ROWS_KNOWN = 5


def l2(q: str, p: str, n: int) -> str:
    return f"list_sum([({q}[i] - {p}[i]) * ({q}[i] - {p}[i]) for i in range(1, {n + 1})])::BIGINT"


def l1(q: str, p: str, n: int) -> str:
    return f"list_sum([abs({q}[i] - {p}[i]) for i in range(1, {n + 1})])::BIGINT"


def ranked_scan(cost: str, k: int) -> str:
    return f"""s AS (
  SELECT q.patch_id AS query_id, p.patch_id AS patch_id, {cost} AS cost
  FROM emb q JOIN emb p ON p.patch_id <> q.patch_id WHERE q.patch_id % {EVERY} = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY cost, patch_id)::INTEGER AS rank FROM s)
SELECT query_id, rank, patch_id, cost FROM r WHERE rank <= {k}"""


def hadamard(vals: str, dims: int, k: int = 8) -> list[str]:
    return [f"list_sum([{vals}[i + 1] * ([{', '.join(str(int(x)) for x in row)}])[i + 1] for i in range(0, {k * k})])::BIGINT" for row in frequencies(k, dims, "hadamard")]


def hadamard_byte(c: str, leading: bool, k: int = 8) -> str:
    size = k * k
    shifted = f"({c} - {size * 128})" if leading else c
    return f"greatest(0, least(255, floor(({shifted} + {size * 128}) / {size})))::BIGINT"


def z_key(coords: list[str], bits: int) -> str:
    d = len(coords)
    parts = [f"(((({c}) >> {b}) & 1) << {b * d + d - 1 - i})" for i, c in enumerate(coords) for b in range(bits)]
    return " + ".join(parts)


def grid(h: int | str, w: int | str, images: str = "0") -> str:
    return f"grid AS (SELECT image_id::BIGINT AS image_id, y::INTEGER AS y, x::INTEGER AS x FROM (SELECT unnest([{images}]) AS image_id), (SELECT unnest(range(0, {h})) AS y), (SELECT unnest(range(0, {w})) AS x))"


WEEK = f"floor(datediff('day', DATE '{DAY0}', l_shipdate::DATE) / 7)::INTEGER"


WEEKS = f"(SELECT max({WEEK}) + 1 FROM lineitem)"


def sales_field() -> str:
    return f"""{grid(WEEKS, 50)},
sums AS (SELECT {WEEK} AS y, l_quantity::INTEGER - 1 AS x, sum({CENTS.format('l_extendedprice')})::BIGINT AS v FROM lineitem GROUP BY ALL),
field AS (SELECT g.image_id, g.y, g.x, coalesce(s.v, 0)::BIGINT AS v FROM grid g LEFT JOIN sums s USING (y, x))"""


def market_sums(size: str, levels: str) -> str:
    w, h = SIZES[size]
    return f"""{grid(h, w, levels)},
sums AS (SELECT round(l_discount * 100)::BIGINT AS image_id, least(l_partkey * {h} // ((SELECT max(p_partkey) FROM part) + 1), {h - 1})::INTEGER AS y, least({WEEK} * {w} // {WEEKS}, {w - 1})::INTEGER AS x,
  sum({CENTS.format('l_extendedprice')})::BIGINT AS v FROM lineitem GROUP BY ALL),
field AS (SELECT g.image_id, g.y, g.x, coalesce(s.v, 0)::BIGINT AS v FROM grid g LEFT JOIN sums s USING (image_id, y, x))"""


def box_sum(size: int, source: str = "field", name: str = "boxed") -> str:
    r = size // 2
    return f"""{name}_r AS (SELECT image_id, y, x, sum(v) OVER (PARTITION BY image_id, y ORDER BY x ROWS BETWEEN {r} PRECEDING AND {r} FOLLOWING)::BIGINT AS v FROM {source}),
{name} AS (SELECT image_id, y, x, sum(v) OVER (PARTITION BY image_id, x ORDER BY y ROWS BETWEEN {r} PRECEDING AND {r} FOLLOWING)::BIGINT AS v FROM {name}_r)"""


def running(source: str = "field", name: str = "surface") -> str:
    return f"""{name}_r AS (SELECT image_id, y, x, sum(v) OVER (PARTITION BY image_id, y ORDER BY x ROWS UNBOUNDED PRECEDING)::BIGINT AS v FROM {source}),
{name} AS (SELECT image_id, y, x, sum(v) OVER (PARTITION BY image_id, x ORDER BY y ROWS UNBOUNDED PRECEDING)::BIGINT AS v FROM {name}_r)"""


def scaled(source: str, name: str = "raster") -> str:
    return f"""{name} AS (SELECT c.image_id, c.y, c.x, CASE WHEN hi > lo THEN ((v - lo) * 255) // (hi - lo) ELSE 0 END AS pix
  FROM {source} c JOIN (SELECT image_id, min(v) AS lo, max(v) AS hi FROM {source} GROUP BY image_id) USING (image_id))"""


def hashed(source: str = "raster", name: str = "hashed") -> str:
    h = portable_hash_sql("y::BIGINT * w + x + image_id * 1000003")
    return f"""{name} AS (SELECT image_id, y, x, h, w, {h} AS hash FROM {source} JOIN (SELECT image_id, max(y) + 1 AS h, max(x) + 1 AS w FROM {source} GROUP BY image_id) USING (image_id))"""


def footprint_rows(k: int = 8, c: float = 0.6) -> str:
    """fp(index_id, kind, pos): the cells nearest the middle of an edge or a corner, by the rule."""
    return f"""fp_a AS (SELECT a, b, abs(a) + abs(b) AS sides FROM (SELECT unnest(range(-1, 2)) AS a), (SELECT unnest(range(-1, 2)) AS b) WHERE a <> 0 OR b <> 0),
fp_i AS (SELECT *, row_number() OVER (ORDER BY sides, a, b) - 1 AS index_id FROM fp_a),
fp_d AS (SELECT index_id, sides, y * {k} + x AS cell, row_number() OVER (PARTITION BY index_id ORDER BY (2 * y - (a + 1) * {k - 1}) ** 2 + (2 * x - (b + 1) * {k - 1}) ** 2, y, x) AS near
  FROM fp_i, (SELECT unnest(range(0, {k})) AS y), (SELECT unnest(range(0, {k})) AS x)),
fp AS (SELECT index_id::INTEGER AS index_id, CASE sides WHEN 1 THEN 'edge' ELSE 'corner' END AS kind, list(cell ORDER BY near) AS pos FROM fp_d WHERE near <= floor({c} * {k * k} + 0.5) GROUP BY index_id, sides)"""


FP8 = footprints(8, 0.6)
