"""The z-curve: keys of quantised points, comparisons, boxes and their splits.

A key takes the highest bit of every dimension, dimension 0 first, then the next bits. Column
builders serve plans; the functions on integers and arrays serve kernels and tests.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


def z_key(coords: list[Column], bits: int = 8) -> Column:
    """The key as a long; ``len(coords) * bits`` may be 63 at most."""
    if len(coords) * bits > 63:
        raise ValueError("use z_key_hex for keys above 63 bits")
    d, out = len(coords), F.lit(0).cast("long")
    for i, c in enumerate(coords):
        for b in range(bits):
            bit = F.shiftright(c.cast("long"), b).bitwiseAND(F.lit(1))
            out = out.bitwiseOR(F.shiftleft(bit, b * d + d - 1 - i))
    return out


def z_key_hex(coords: Column, dims: int, bits: int = 8) -> Column:
    """The key of an array column as upper-case hex text; its order is the curve order."""
    planes = F.transform(F.sequence(F.lit(bits - 1), F.lit(0), F.lit(-1)), lambda b: F.array_join(F.transform(coords, lambda v: F.getbit(v.cast("long"), b.cast("int")).cast("string")), ""))
    text = F.array_join(planes, "")
    width = -(-dims * bits // 4) * 4
    whole = F.lpad(text, width, "0")
    return F.array_join(F.transform(F.sequence(F.lit(1), F.lit(width), F.lit(4)), lambda at: F.conv(F.substring(whole, at, F.lit(4)), 2, 16)), "")


def z_coords(key: Column, dims: int, bits: int = 8) -> Column:
    """The point of a long key."""
    axes = []
    for i in range(dims):
        v = F.lit(0).cast("long")
        for b in range(bits):
            v = v.bitwiseOR(F.shiftleft(F.shiftright(key, b * dims + dims - 1 - i).bitwiseAND(F.lit(1)), b))
        axes.append(v)
    return F.array(*axes)


def z_less(a: Column, b: Column) -> Column:
    """Curve order of two points from the dimension of their highest differing bit alone."""
    diff = F.zip_with(a, b, lambda x, y: x.cast("long").bitwiseXOR(y.cast("long")))
    ranked = F.transform(diff, lambda d, i: F.struct(F.when(d == 0, -1).otherwise(F.floor(F.log2(d.cast("double")))).cast("int").alias("bit"), (-i).alias("dim"), i.alias("i")))
    at = F.array_max(ranked).i + 1
    return F.element_at(a, at) < F.element_at(b, at)


def box_distance2(q: Column, lo: Column, hi: Column) -> Column:
    """Squared distance of a point to a box; 0 inside."""
    low = F.zip_with(lo, q, lambda e, v: F.greatest(e.cast("double") - v.cast("double"), F.lit(0.0)))
    high = F.zip_with(hi, q, lambda e, v: F.greatest(v.cast("double") - e.cast("double"), F.lit(0.0)))
    return F.aggregate(F.zip_with(low, high, lambda a, b: a + b), F.lit(0.0), lambda s, x: s + x * x)


def l2_squared(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, d: s + d)


def encode(points: np.ndarray, bits: int = 8) -> np.ndarray:
    """Keys as fixed-width byte strings (rows), for points of any number of dimensions."""
    points = np.atleast_2d(points).astype(np.int64)
    planes = (points[:, None, :] >> np.arange(bits - 1, -1, -1)[None, :, None]) & 1
    return np.packbits(planes.reshape(len(points), -1).astype(np.uint8), axis=1)


def encode_int(point, bits: int = 8) -> int:
    key = 0
    for b in range(bits - 1, -1, -1):
        for v in point:
            key = key << 1 | (int(v) >> b & 1)
    return key


def decode_int(key: int, dims: int, bits: int = 8) -> list[int]:
    out = [0] * dims
    for at in range(dims * bits):
        if key >> (dims * bits - 1 - at) & 1:
            out[at % dims] |= 1 << (bits - 1 - at // dims)
    return out


def split_at(lo, hi) -> tuple[int, int] | None:
    """(dimension, last value of the lower half) of the best cut of a box, None for one point."""
    best, dim = 0, -1
    for i, (a, b) in enumerate(zip(lo, hi, strict=True)):
        bit = (int(a) ^ int(b)).bit_length()
        if bit > best:
            best, dim = bit, i
    if dim < 0:
        return None
    return dim, (int(hi[dim]) >> (best - 1) << (best - 1)) - 1


def split(lo, hi):
    """Both halves of a box: ((lo, litmax), (bigmin, hi), dimension, cut)."""
    found = split_at(lo, hi)
    if found is None:
        return None
    dim, cut = found
    litmax, bigmin = list(hi), list(lo)
    litmax[dim], bigmin[dim] = cut, cut + 1
    return (list(lo), litmax), (bigmin, list(hi)), dim, cut


def ranges(lo, hi, bits: int = 8, most: int = 16) -> list[tuple[int, int]]:
    """At most ``most`` key intervals that cover a box, by splitting the widest one first."""
    import heapq

    key = lambda p: encode_int(p, bits)
    heap = [(-(key(hi) - key(lo)), list(lo), list(hi))]
    done = []
    while heap and len(heap) + len(done) < most:
        width, a, b = heapq.heappop(heap)
        size = 1
        for x, y in zip(a, b, strict=True):
            size *= int(y) - int(x) + 1
        halves = split(a, b)
        if halves is None or -width + 1 == size:  # the interval holds nothing else
            done.append((a, b))
            continue
        for p, q in halves[:2]:
            heapq.heappush(heap, (-(key(q) - key(p)), p, q))
    boxes = done + [(a, b) for _, a, b in heap]
    out: list[list[int]] = []
    for a, b in sorted((key(p), key(q)) for p, q in boxes):
        if out and a <= out[-1][1] + 1:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [tuple(x) for x in out]


def hilbert(points: np.ndarray, bits: int = 8) -> np.ndarray:
    """Places of points (rows) on the Hilbert curve, as Python integers in an object array where needed.

    From the highest bit down, the bits of a point name one of the 2^D sub-boxes. The curve visits
    sub-boxes in Gray-code order after the box's own reflection (``flip``) and rotation of axes
    (``turn``); both follow from the sub-box that was entered.
    """
    points = np.atleast_2d(points).astype(np.int64)
    n, dims = points.shape
    full = (1 << dims) - 1
    flip, turn = np.zeros(n, np.int64), np.zeros(n, np.int64)
    out = np.zeros(n, np.int64 if dims * bits < 63 else object)
    rotate = lambda x, r: ((x >> r) | (x << (dims - r))) & full
    for b in range(bits - 1, -1, -1):
        box = np.zeros(n, np.int64)
        for i in range(dims):
            box |= (points[:, i] >> b & 1) << i
        local = rotate(box ^ flip, turn)
        place, shifted = local.copy(), local >> 1
        while shifted.any():  # the inverse of the Gray code: prefix parities of the bits
            place ^= shifted
            shifted >>= 1
        out = (out << dims) | place
        # where the curve enters the sub-box, and along which axis it leaves it
        even = np.maximum(0, 2 * ((place - 1) // 2))
        entry = np.where(place == 0, 0, even ^ (even >> 1))
        ones = np.where(place % 2 == 0, place - 1, place)
        axis = np.zeros(n, np.int64)
        run = np.where(place == 0, 0, ones)
        while (run & 1).any():  # trailing ones
            axis += run & 1
            run = np.where(run & 1, run >> 1, 0)
        axis = np.where(place == 0, 0, axis) % dims
        flip = flip ^ rotate(entry, (dims - turn) % dims)
        turn = (turn + axis + 1) % dims
    return out


def h_key(coords: Column, dims: int, bits: int = 8) -> Column:
    """The Hilbert place of an array column as a long; ``dims * bits`` is 62 at most."""
    if dims * bits > 62:
        raise ValueError("a Hilbert key has 62 bits at most")

    @F.pandas_udf("long")
    def place(p: pd.Series) -> pd.Series:
        return pd.Series(hilbert(np.stack(p.to_numpy()), bits).astype(np.int64) if len(p) else np.empty(0, np.int64))

    return place(coords)


def z_split(lo: Column, hi: Column) -> Column:
    """struct(dim, cut): where a box is cut, at the highest bit in which its corners differ (of several
    dimensions the first); null for a single point. ``cut`` is the last value of the lower half."""
    diff = F.zip_with(lo, hi, lambda a, b: a.cast("long").bitwiseXOR(b.cast("long")))
    ranked = F.transform(diff, lambda d, i: F.struct(F.when(d > 0, F.floor(F.log2(d.cast("double")))).otherwise(-1).cast("int").alias("bit"), (-i).alias("first")))
    best = F.array_max(ranked)
    top = F.element_at(hi, 1 - best["first"]).cast("long")
    size = F.call_function("shiftleft", F.lit(1).cast("long"), best["bit"])
    return F.when(best["bit"] >= 0, F.struct((-best["first"]).cast("int").alias("dim"), (top - F.pmod(top, size) - 1).cast("int").alias("cut")))
