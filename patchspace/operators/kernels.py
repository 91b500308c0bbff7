"""The strictly sequential part of a fill: one image in one task, in numpy.

A selector holds an image's dictionary and answers "which patch is cheapest on the known pixels".
All selectors share costs, pasting and order, so that only the search differs between methods.
Ties go to the smaller patch number (row-major order of centres).
"""

from __future__ import annotations

import heapq
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import cached_property

import numpy as np

from patchspace.functions import zcurve
from patchspace.functions.costs import Cost, blend_weights, l2
from patchspace.operators.footprints import Footprint, footprints
from patchspace.operators.reduce import Basis, frequencies, pca_of


class NoPatches(ValueError):
    """An image that cannot be filled: wholly unknown, or without a wholly known patch."""


def windows(img: np.ndarray, known: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(wholly known patches as rows of (row, column, channel) values, their centres)."""
    h, w, c = img.shape
    if h < k or w < k:
        return np.empty((0, k * k * c), np.int16), np.empty((0, 2), np.int64)
    view = np.lib.stride_tricks.sliding_window_view(known, (k, k))
    ys, xs = np.nonzero(view.all((2, 3)))
    cells = np.lib.stride_tricks.sliding_window_view(img, (k, k), (0, 1))[ys, xs]
    return cells.transpose(0, 2, 3, 1).reshape(len(ys), k * k * c).astype(np.int16), np.stack([ys + k // 2, xs + k // 2], 1)


class Selector:
    """Full scan as masked matrix products: all patches at once."""

    name = "scan"

    def __init__(self, patches: np.ndarray, centres: np.ndarray, k: int, channels: int, cost: Cost | None = None, **params):
        self.p, self.centres, self.k, self.channels = patches, centres, k, channels
        self.cost, self.params = cost or l2(), params
        self.work = {"distances": 0, "refined": 0, "queries": 0, "blocks": 0, "regions": 0}
        self.build()

    @cached_property
    def f(self) -> np.ndarray:
        return self.p.astype(np.float64)

    @cached_property
    def f2(self) -> np.ndarray:
        return self.f**2

    def build(self) -> None:
        pass

    def costs(self, rows, q: np.ndarray, known: np.ndarray) -> np.ndarray:
        self.work["refined"] += len(self.p) if rows is None else len(rows)
        if self.cost.name == "l2" and (rows is None or len(rows) > 4096):
            f, f2 = (self.f, self.f2) if rows is None else (self.f[rows], self.f2[rows])
            m = known.astype(float)
            return np.rint(f2 @ m - 2 * (f @ (q * m)) + (q.astype(float) ** 2 * m).sum()).astype(np.int64)
        return self.cost.local(q, self.p if rows is None else self.p[rows], known)

    def best_of(self, rows: np.ndarray | None, q, known) -> tuple[int, float]:
        c = self.costs(rows, q, known)
        i = int(np.argmin(c)) if rows is None else int(np.lexsort((rows, c))[0])
        return (i if rows is None else int(rows[i])), float(c[i])

    def find(self, q, known, centre) -> tuple[int, float]:
        self.work["queries"] += 1
        rows = self.candidates(q, known, centre)
        if rows is not None and not len(rows):
            rows = None
        return self.best_of(rows, q, known)

    def candidates(self, q, known, centre) -> np.ndarray | None:
        return None

    def pasted(self, y: int, x: int, winner: int) -> None:
        """Told of every paste; selectors that carry a field update it."""


class NaiveScan(Selector):
    """The original: one patch after another."""

    name = "naive"

    def find(self, q, known, centre):
        self.work["queries"] += 1
        best, at = None, 0
        for i in range(len(self.p)):
            c = float(self.cost.local(q, self.p[i], known)) if self.cost.name != "ssim" else float(self.cost.local(q, self.p[i : i + 1], known)[0])
            if best is None or c < best:
                best, at = c, i
        self.work["refined"] += len(self.p)
        return at, best


class EarlyStop(Selector):
    """Partial sums in chunks of pixels; patches above the best complete cost leave early."""

    name = "early_stop"

    def find(self, q, known, centre):
        self.work["queries"] += 1
        pos = np.flatnonzero(known)
        parts = np.array_split(pos, max(1, min(self.params.get("chunks", 4), len(pos))))
        rows, total = np.arange(len(self.p)), np.zeros(len(self.p), np.int64)
        for j, part in enumerate(parts):
            total = total + ((self.p[np.ix_(rows, part)].astype(np.int64) - q[part]) ** 2).sum(1)
            self.work["distances"] += len(rows) * len(part)
            if j + 1 < len(parts) and len(rows) > 1:
                lead = rows[int(np.argmin(total))]
                bound = int(((self.p[lead][pos].astype(np.int64) - q[pos]) ** 2).sum())
                keep = total <= bound
                rows, total = rows[keep], total[keep]
        i = int(np.lexsort((rows, total))[0])
        return int(rows[i]), float(total[i])


def best_covered(bases: list[Basis], known: np.ndarray) -> int:
    """The footprint with most known positions, of several the first."""
    return int(np.argmax([int(known[b.pos].sum()) for b in bases]))


class Reduced(Selector):
    """Common part of filter-and-refine: footprints, bases, coordinates of all patches.

    ``fitted``: bases that are given. ``kept``: the footprints whose index stays in memory when all are built.
    """

    def bases(self) -> list[Basis]:
        x = self.p.astype(np.float64)
        n, s, prod = len(x), x.sum(0).astype(np.int64), (x.T @ x).astype(np.int64)
        return [pca_of(n, s, prod, fp, self.params.get("dims", 10)) for fp in self.fps]

    def build(self) -> None:
        self.fps: list[Footprint] = footprints(self.k, self.params.get("c", 0.6), self.channels, self.params.get("ndim", 2))
        self.basis = self.params.get("fitted") or (self.bases() if len(self.p) else [])
        self.points, self.index = [], []
        for i, b in enumerate(self.basis):
            points = b.project(self.p.astype(np.float64))
            index, stays = self.make(b, points), i in self.params.get("kept", range(len(self.basis)))
            self.points.append(points if stays else None)
            self.index.append(index if stays else None)

    def make(self, basis: Basis, points: np.ndarray):
        return None

    def choose(self, known: np.ndarray) -> int | None:
        """The footprint with most known positions; None if the policy wants it whole and it is not.

        A front cell's patch often knows little more than half its pixels, so by default the index
        mean stands in for the unknown part of the best footprint (policy ``mean``); ``scan``
        leaves such targets to the full scan.
        """
        i = best_covered(self.basis, known)
        if known[self.basis[i].pos].all() or self.params.get("on_uncovered", "mean") == "mean":
            return i
        return None

    def candidates(self, q, known, centre):
        i = self.choose(known)
        if i is None:
            return None
        b = self.basis[i]
        diff = np.where(known[b.pos], q[b.pos] - b.mean, 0.0)
        return self.nearest(i, b.loadings @ diff, min(self.params.get("knn", 80), len(self.p)))

    def nearest(self, i: int, point: np.ndarray, k: int) -> np.ndarray:
        raise NotImplementedError


class ZCurve(Reduced):
    """Blocks of the z-ordered patches, opened nearest box first until the k-th is nearer."""

    name = "zcurve"

    def make(self, basis, points):
        bits = self.params.get("bits", 8)
        cols = basis.quantise(points, bits)
        order = self.params.get("order")
        if order == "reversed":
            cols = cols[:, ::-1]
        elif order == "random":
            cols = cols[:, np.random.default_rng(0).permutation(cols.shape[1])]
        keys = zcurve.encode(cols, bits)
        rank = np.lexsort((np.arange(len(keys)), *keys.T[::-1]))
        x, mu = points[rank], self.params.get("mu", 256)
        start = np.arange(0, len(x), mu)
        return rank, x, start, np.minimum.reduceat(x, start), np.maximum.reduceat(x, start), mu

    def nearest(self, i, point, k):
        rank, x, start, lo, hi, mu = self.index[i]
        gap = (np.maximum(0, np.maximum(lo - point, point - hi)) ** 2).sum(1)
        order = np.argsort(gap, kind="stable")
        need, rows, dist, bound, at = max(1, -(-k // mu)), [], [], np.inf, 0
        while at < len(order) and gap[order[at]] <= bound:
            # while neither half of what is open holds more than nu entries, blocks are scanned one by one;
            # else all that the bound leaves open is cut into regions of nu entries, which scan side by side
            left = order[at:][gap[order[at:]] <= bound]
            regions = self.regions(left, mu, len(x)) if len(dist) else []
            take = left if regions else left[:need]
            for part in self.scan_regions(regions, x, point, start, mu) if regions else [self.scan(take, x, point, start, mu)]:
                rows.append(rank[part[0]])
                dist.append(part[1])
            self.work["blocks"] += len(take)
            self.work["regions"] += max(1, len(regions))
            self.work["distances"] += int(np.minimum(start[take] + mu, len(x)).sum() - start[take].sum())
            at += len(take)
            d = np.concatenate(dist)
            if len(d) >= k:
                bound = np.partition(d, k - 1)[k - 1]
                keep = d <= bound
                rows, dist = [np.concatenate(rows)[keep]], [d[keep]]
        r, d = np.concatenate(rows), np.concatenate(dist)
        return r[np.lexsort((r, d))[:k]]

    def regions(self, blocks: np.ndarray, mu: int, n: int) -> list[np.ndarray]:
        """Blocks in order of distance, in regions of at least nu entries; none where there are not two."""
        threads, nu = self.params.get("threads", 1), self.params.get("nu", 2048)
        count = min(threads, len(blocks) * mu // max(1, nu))
        return np.array_split(blocks, count) if threads > 1 and count > 1 else []

    def scan(self, blocks, x, point, start, mu) -> tuple[np.ndarray, np.ndarray]:
        at = np.concatenate([np.arange(start[b], min(start[b] + mu, len(x))) for b in blocks])
        return at, ((x[at] - point) ** 2).sum(1)

    def scan_regions(self, regions, x, point, start, mu):
        if not hasattr(self, "pool"):
            self.pool = ThreadPoolExecutor(self.params["threads"])
        return list(self.pool.map(lambda r: self.scan(r, x, point, start, mu), regions))


class OutsideIn(ZCurve):
    """The same search as a descent: regions are cut at the highest differing bit, the nearer half
    first, and a half is left out when it is farther than the k-th best. A heap of regions by
    distance stands for the order of visits."""

    name = "outside_in"

    def make(self, basis, points):
        rank, x, *_ = super().make(basis, points)
        bits = self.params.get("bits", 8)
        q = basis.quantise(x, bits)
        return rank, x, q, zcurve.encode(q, bits).view(f"S{basis.loadings.shape[0]}").ravel(), basis

    def nearest(self, i, point, k):
        rank, x, q, keys, basis = self.index[i]
        bits, mu = self.params.get("bits", 8), self.params.get("mu", 256)
        top, width = (1 << bits) - 1, f"S{q.shape[1]}"
        key = lambda p: zcurve.encode(np.array(p), bits).view(width).ravel()[0]

        def gap(lo, hi):  # cells of the outermost values reach without end: they hold clamped points
            low = np.where(np.array(lo) == 0, -np.inf, basis.low + (np.array(lo) - 0.5) * basis.step)
            high = np.where(np.array(hi) == top, np.inf, basis.low + (np.array(hi) + 0.5) * basis.step)
            return float((np.maximum(0, np.maximum(low - point, point - high)) ** 2).sum())

        lo, hi = [0] * q.shape[1], [top] * q.shape[1]
        heap, turn = [(0.0, 0, lo, hi, 0, len(x))], 0
        best: list[tuple[float, int]] = []  # (-distance, -row): the worst on top
        while heap:
            d, _, lo, hi, a, b = heapq.heappop(heap)
            if len(best) == k and d > -best[0][0]:
                break
            if b - a <= mu or (halves := zcurve.split(lo, hi)) is None:
                self.work["blocks"] += 1
                self.work["distances"] += b - a
                inside = ((q[a:b] >= lo) & (q[a:b] <= hi)).all(1)
                for row, e in zip(rank[a:b][inside].tolist(), ((x[a:b][inside] - point) ** 2).sum(1).tolist(), strict=True):
                    if len(best) < k:
                        heapq.heappush(best, (-e, -row))
                    elif (-e, -row) > best[0]:
                        heapq.heapreplace(best, (-e, -row))
                continue
            for p, r in halves[:2]:  # ends are sought inside the parent's interval only
                s = a + int(np.searchsorted(keys[a:b], key(p), "left"))
                e = a + int(np.searchsorted(keys[a:b], key(r), "right"))
                if s < e:
                    turn += 1
                    heapq.heappush(heap, (gap(p, r), turn, p, r, s, e))
        return np.array([-r for _, r in sorted(best, reverse=True)], np.int64)


class RandomProjection(ZCurve):
    name = "random_projection"

    def bases(self):
        out = super().bases()
        for b in out:
            rng = np.random.default_rng(b.index_id)
            b.loadings = (rng.integers(0, 2, b.loadings.shape) * 2 - 1) / np.sqrt(len(b.loadings))
        return out


class Frequency(ZCurve):
    """The lowest cosine frequencies of the footprint's pixels, others set to the mean."""

    name = "frequency"

    def bases(self):
        rows = frequencies(self.k, self.params.get("dims", 10))
        out = super().bases()
        for b in out:
            own = np.repeat(rows, self.channels, axis=1)[:, b.pos]
            qr, _ = np.linalg.qr(own.T)
            b.loadings = qr.T
        return out


class IDistance(Reduced):
    """Distances to the nearest of some reference points, sorted; annuli grow around the query."""

    name = "idistance"

    def make(self, basis, points):
        m = min(self.params.get("refs", 16), len(points))
        refs = points[np.linspace(0, len(points) - 1, m).astype(int)]
        for _ in range(5):  # a few rounds of means
            near = ((points[:, None] - refs[None]) ** 2).sum(2).argmin(1)
            refs = np.stack([points[near == j].mean(0) if (near == j).any() else refs[j] for j in range(m)])
        near = ((points[:, None] - refs[None]) ** 2).sum(2).argmin(1)
        r = np.sqrt(((points - refs[near]) ** 2).sum(1))
        order = np.lexsort((r, near))
        cut = np.searchsorted(near[order], np.arange(m + 1))
        return refs, order, r[order], cut

    def nearest(self, i, point, k):
        refs, order, r, cut = self.index[i]
        to = np.sqrt(((refs - point) ** 2).sum(1))
        x, m = self.points[i], len(refs)
        lo = np.array([cut[j] + np.searchsorted(r[cut[j] : cut[j + 1]], to[j]) for j in range(m)])
        hi = lo.copy()
        step = radius = max(1e-9, float(r.max()) / 20)
        rows, dist = [], []
        while True:
            for j in range(m):
                a = cut[j] + np.searchsorted(r[cut[j] : cut[j + 1]], to[j] - radius)
                b = cut[j] + np.searchsorted(r[cut[j] : cut[j + 1]], to[j] + radius, "right")
                for s, e in ((a, lo[j]), (hi[j], b)):
                    if e > s:
                        rows.append(order[s:e])
                        dist.append(((x[order[s:e]] - point) ** 2).sum(1))
                        self.work["distances"] += int(e - s)
                lo[j], hi[j] = min(a, lo[j]), max(b, hi[j])
            self.work["blocks"] += m
            n = sum(map(len, rows))
            if n >= k:
                d = np.concatenate(dist)
                if np.sqrt(np.partition(d, k - 1)[k - 1]) <= radius or n == len(order):
                    own = np.concatenate(rows)
                    return own[np.lexsort((own, d))[:k]]
            radius += step
            if n == len(order):
                own, d = np.concatenate(rows), np.concatenate(dist)
                return own[np.lexsort((own, d))[:k]]


class Hashing(Reduced):
    """Locality-preserving hashing: several tables of quantised random projections."""

    name = "hashing"

    def make(self, basis, points):
        rng = np.random.default_rng(1)
        tables = []
        for _ in range(self.params.get("tables", 8)):
            a = rng.normal(size=(points.shape[1], 3))
            width = 1.5 * float((points @ a).std()) + 1e-9
            keys = np.floor(points @ a / width).astype(int)
            table: dict[tuple, list[int]] = {}
            for row, key in enumerate(map(tuple, keys.tolist())):
                table.setdefault(key, []).append(row)
            tables.append((a, width, table))
        return tables

    def nearest(self, i, point, k):
        rows = {r for a, width, t in self.index[i] for r in t.get(tuple(np.floor(point @ a / width).astype(int).tolist()), ())}
        if len(rows) < 1:
            return np.arange(len(self.p))
        own = np.fromiter(rows, np.int64)
        self.work["distances"] += len(own)
        d = ((self.points[i][own] - point) ** 2).sum(1)
        return own[np.lexsort((own, d))[:k]]


class PackedBoxes(ZCurve):
    """Tree-style boxes instead of a curve: sort-tile packing on the first two components."""

    name = "packed_boxes"

    def make(self, basis, points):
        mu = self.params.get("mu", 256)
        strips = max(1, int(np.sqrt(-(-len(points) // mu))))
        strip = np.argsort(np.argsort(points[:, 0], kind="stable"), kind="stable") * strips // max(1, len(points))
        second = points[:, 1] if points.shape[1] > 1 else np.zeros(len(points))
        rank = np.lexsort((np.arange(len(points)), second, strip))
        x = points[rank]
        start = np.arange(0, len(x), mu)
        return rank, x, start, np.minimum.reduceat(x, start), np.maximum.reduceat(x, start), mu


class VectorTree(Reduced):
    """Tree-structured vector quantisation: two means per node, greedy descent."""

    name = "vector_tree"

    def make(self, basis, points):
        def grow(rows, depth):
            if len(rows) <= self.params.get("leaf", 64) or depth > 20:
                return rows
            x = points[rows]
            a, b = x[0], x[int(((x - x[0]) ** 2).sum(1).argmax())]
            for _ in range(4):
                left = ((x - a) ** 2).sum(1) <= ((x - b) ** 2).sum(1)
                if left.all() or not left.any():
                    return rows
                a, b = x[left].mean(0), x[~left].mean(0)
            return a, b, grow(rows[left], depth + 1), grow(rows[~left], depth + 1)

        return grow(np.arange(len(points)), 0)

    def nearest(self, i, point, k):
        node = self.index[i]
        while isinstance(node, tuple):
            a, b, left, right = node
            self.work["distances"] += 2
            node = left if ((point - a) ** 2).sum() <= ((point - b) ** 2).sum() else right
        self.work["distances"] += len(node)
        return node


class Window(Selector):
    """Only patches whose centre lies within a radius of the target."""

    name = "window"

    def radius(self, q, known) -> int:
        return self.params.get("radius", 3 * self.k)

    def candidates(self, q, known, centre):
        return np.flatnonzero((np.abs(self.centres - np.asarray(centre)) <= self.radius(q, known)).all(1))


class LocalDiameter(Window):
    """The radius depends on the target: busier patches look farther."""

    name = "local_diameter"

    def radius(self, q, known):
        spread = float(np.std(q[known])) if known.any() else 0.0
        return int(self.k * (1.5 + min(4.0, spread / 16)))


class BlockContext(Selector):
    """Non-overlapping blocks compared by histograms first; patches of the best blocks only."""

    name = "block_context"

    def build(self):
        side, bins = self.params.get("side", 4 * self.k), 16
        cell = self.centres // side if len(self.centres) else np.empty((0, 2), int)
        _, self.block = np.unique(cell, axis=0, return_inverse=True)
        mid = (self.k * self.k // 2) * self.channels
        self.bins = bins
        n = int(self.block.max()) + 1 if len(self.block) else 0
        hist = np.zeros((n, bins))
        np.add.at(hist, (self.block, self.p[:, mid] * bins // 256), 1)
        self.hist = np.sqrt(hist / np.maximum(1, hist.sum(1, keepdims=True)))

    def candidates(self, q, known, centre):
        own = np.bincount(q[known] * self.bins // 256, minlength=self.bins).astype(float)
        score = self.hist @ np.sqrt(own / max(1, own.sum()))
        top = np.argsort(-score, kind="stable")[: self.params.get("blocks", 4)]
        return np.flatnonzero(np.isin(self.block, top))


class OffsetStats(Selector):
    """Most frequent offsets between similar known patches give the places to look at."""

    name = "offset_stats"

    def build(self):
        self.at = {tuple(c): i for i, c in enumerate(self.centres.tolist())}
        rng = np.random.default_rng(2)
        rows = rng.choice(len(self.p), min(400, len(self.p)), replace=False) if len(self.p) else []
        counts: dict[tuple[int, int], int] = {}
        whole = np.ones(self.p.shape[1], bool)
        for i in rows:
            c = self.cost.local(self.p[i], self.p, whole)
            c = np.where((np.abs(self.centres - self.centres[i]) < self.k).all(1), np.inf, c)
            if np.isfinite(c).any():
                o = tuple((self.centres[int(np.argmin(c))] - self.centres[i]).tolist())
                counts[o] = counts.get(o, 0) + 1
        self.offsets = sorted(counts, key=lambda o: (-counts[o], o))[: self.params.get("top", 60)]

    def candidates(self, q, known, centre):
        y, x = centre
        return np.array(sorted({self.at[y + dy, x + dx] for dy, dx in self.offsets if (y + dy, x + dx) in self.at}), np.int64)


class Propagation(Selector):
    """A field of matches: neighbours' matches, shifted, and shrinking random samples around them.

    The field of known cells is set up beforehand; pasted cells take over the winner's offset.
    Own choices where the published description is not at hand: rounds and update on paste.
    """

    name = "propagation"

    def build(self):
        self.at = {tuple(c): i for i, c in enumerate(self.centres.tolist())}
        self.rng = np.random.default_rng(self.params.get("seed", 3))
        n, self.field = len(self.p), {}
        if not n:
            return
        extent = self.centres.max(0) - self.centres.min(0) + 1
        self.scales = []
        while extent.max() >= 1:
            self.scales.append(extent.copy())
            extent = extent // 2
        grid = np.full(self.centres.max(0) + 2, -1, np.int64)
        grid[tuple(self.centres.T)] = np.arange(n)
        self.grid, self.ring = grid, np.array([(dy, dx) for dy in range(-2, 3) for dx in range(-2, 3)])
        match = self.rng.integers(0, n, n)
        x = self.p.astype(np.int32)
        far = lambda a: (np.abs(self.centres[a] - self.centres) >= self.k).any(1)
        measure = lambda a: np.where(far(a), ((x - x[a]) ** 2).sum(1), np.iinfo(np.int64).max)
        cost = measure(match)
        hi = np.array(grid.shape) - 1
        for turn in range(self.params.get("rounds", 5)):
            for dy, dx in ((0, 1), (1, 0), (0, -1), (-1, 0)):
                side = self.centres - (dy, dx)
                near = np.where((side >= 0).all(1), grid[tuple(np.clip(side, 0, hi).T)], -1)
                shifted = self.centres[match[np.maximum(near, 0)]] + (dy, dx)
                cand = np.where((near >= 0) & (shifted <= hi).all(1) & (shifted >= 0).all(1), grid[tuple(np.clip(shifted, 0, hi).T)], -1)
                self._better(match, cost, cand, measure)
            for s in self.scales[turn % 2 :: 2]:
                jump = self.centres[match] + np.rint((self.rng.random((n, 2)) * 2 - 1) * s).astype(int)
                cand = np.where((jump >= 0).all(1) & (jump <= hi).all(1), grid[tuple(np.clip(jump, 0, hi).T)], -1)
                self._better(match, cost, cand, measure)
            self.work["distances"] += n * (4 + len(self.scales))
        self.field = {tuple(c): tuple(self.centres[m] - c) for c, m in zip(self.centres, match, strict=True)}

    def _better(self, match, cost, cand, measure):
        own = np.where(cand >= 0, cand, match)
        c = measure(own)
        win = c < cost
        match[win], cost[win] = own[win], c[win]

    def candidates(self, q, known, centre):
        y, x = (int(v) for v in centre)
        near = set()
        for dy in range(-2, 3):
            for dx in range(-2, 3):
                o = self.field.get((y + dy, x + dx))
                if o is not None:
                    i = self.at.get((y + int(o[0]), x + int(o[1])))
                    if i is not None:
                        near.add(i)
        rounds = self.params.get("tries", 10)
        spread = self.rng.integers(0, len(self.p), 48)
        rows = np.unique(np.concatenate([np.fromiter(near, np.int64, len(near)), spread]))
        for _ in range(rounds):
            # around the best matches so far: shrinking random samples, and the places beside them
            lead = rows[np.lexsort((rows, self.costs(rows, q, known)))[: self.params.get("leads", 6)]]
            base = self.centres[lead]
            jumps = [base + np.rint((self.rng.random((len(base), 2)) * 2 - 1) * s).astype(int) for s in self.scales for _ in range(self.params.get("samples", 3))]
            beside = (base[:, None, :] + self.ring[None, :, :]).reshape(-1, 2)
            more = self.rows_at(np.concatenate([*jumps, beside]))
            fresh = np.union1d(rows, more)
            if len(fresh) == len(rows):
                break
            rows = fresh
        self.work["distances"] += len(rows)
        return rows

    def rows_at(self, places: np.ndarray) -> np.ndarray:
        """Patches centred at these places, where there are any."""
        ok = ((places >= 0) & (places < np.array(self.grid.shape))).all(1)
        found = self.grid[tuple(places[ok].T)]
        return found[found >= 0]

    def pasted(self, y, x, winner):
        o = tuple(self.centres[winner] - (y, x))
        half = self.k // 2
        for dy in range(-half, half + 1):
            for dx in range(-half, half + 1):
                self.field.setdefault((y + dy, x + dx), o)


SELECTORS: dict[str, type[Selector]] = {s.name: s for s in (Selector, NaiveScan, EarlyStop, ZCurve, OutsideIn, RandomProjection, Frequency, IDistance, Hashing, PackedBoxes, VectorTree, Window, LocalDiameter, BlockContext, OffsetStats, Propagation)}


def neighbours(a: np.ndarray) -> np.ndarray:
    """Whether one of the four neighbours is set."""
    out = np.zeros_like(a)
    out[1:] |= a[:-1]
    out[:-1] |= a[1:]
    out[:, 1:] |= a[:, :-1]
    out[:, :-1] |= a[:, 1:]
    return out


def box_mean(a: np.ndarray, k: int) -> np.ndarray:
    """Mean over k x k windows; windows are cut at the border."""
    pad = np.zeros((a.shape[0] + 1, a.shape[1] + 1))
    pad[1:, 1:] = a.cumsum(0).cumsum(1)
    h, r = k // 2, np.arange(a.shape[0])
    c = np.arange(a.shape[1])
    y0, y1 = np.maximum(r - h, 0), np.minimum(r + h + 1, a.shape[0])
    x0, x1 = np.maximum(c - h, 0), np.minimum(c + h + 1, a.shape[1])
    s = pad[np.ix_(y1, x1)] - pad[np.ix_(y0, x1)] - pad[np.ix_(y1, x0)] + pad[np.ix_(y0, x0)]
    return s / np.outer(y1 - y0, x1 - x0)


def slopes(a: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Mean differences to the known neighbours of known cells, down and right; 0 without any."""

    def down(v, m):
        ok = np.pad(m[1:] & m[:-1], ((1, 1), (0, 0)))
        step = np.where(ok, np.pad(np.diff(v, axis=0), ((1, 1), (0, 0))), 0.0)
        return (step[1:] + step[:-1]) / np.maximum(1, ok[1:].astype(int) + ok[:-1])

    return down(a, known), down(a.T, known.T).T


class Order:
    """Priorities of front cells; the front is known cells beside unknown ones."""

    def __init__(self, kind: str = "structure", k: int = 9, user: np.ndarray | None = None):
        self.kind, self.k, self.user = kind, k, user

    def __call__(self, img: np.ndarray, known: np.ndarray, confidence: np.ndarray) -> np.ndarray:
        """A priority for every cell, -inf off the front."""
        front = known & neighbours(~known)
        if self.kind == "onion":
            value = box_mean(known.astype(float), self.k)
        elif self.kind == "raster":
            value = -np.arange(known.size, dtype=float).reshape(known.shape)
        elif self.kind == "value":
            value = img.mean(2)
        elif self.kind == "user":
            value = box_mean(confidence, self.k) + (1e3 * self.user if self.user is not None else 0)
        elif self.kind == "sparsity":
            value = box_mean(confidence, self.k) * self.sparsity(img, known, front)
        elif self.kind == "levels":
            value = box_mean(confidence, self.k) * self.joints(img, known, front)
        else:
            grey = np.where(known, img.mean(2), np.nan)
            gy, gx = np.gradient(grey)
            gy, gx = np.nan_to_num(gy), np.nan_to_num(gx)
            ny, nx = np.gradient(known.astype(float))
            size = np.sqrt(ny**2 + nx**2) + 1e-9
            data = np.abs(-gx * ny + gy * nx) / size / 255 + 1e-3
            if self.kind == "salient":
                norm = np.sqrt(gx**2 + gy**2) + 1e-9
                curve = np.abs(np.gradient(gy / norm, axis=0) + np.gradient(gx / norm, axis=1))
                data = data * (1 + norm / 255) / (1 + curve)
            value = box_mean(confidence, self.k) * data
        return np.where(front, value, -np.inf)

    def joints(self, img, known, front):
        """How well the level line that ends at a front cell goes on to another one across the hole.

        Lines are joined by spirals, whose curvature changes evenly along them: with the angles a and b
        of the ends to the chord, bending times length is 4 (a^2 + a b + b^2) for small angles. Ends match
        if their values are alike, the same side is brighter and the middle of the chord is unknown.
        """
        out = np.full(known.shape, 1e-3)
        grey = img.mean(2)
        gy, gx = slopes(grey, known)
        y, x = np.nonzero(front & ((gy != 0) | (gx != 0)))
        hole_y, hole_x = slopes((~known).astype(float), np.ones_like(known))
        rise, inward = (right[y, x] + 1j * down[y, x] for down, right in ((gy, gx), (hole_y, hole_x)))
        side = np.where((1j * rise * inward.conj()).real < 0, -1, 1)  # a complex number is a direction
        line, place, level = side * 1j * rise, x + 1j * y, grey[y, x]
        for at in range(0, len(y), 256):
            i = slice(at, at + 256)
            chord = place[None] - place[i, None]
            far = np.abs(chord)
            middle = (place[None] + place[i, None]) / 2
            ok = (far > 0) & (side[i, None] != side[None])
            ok &= ~known[np.rint(middle.imag).astype(int), np.rint(middle.real).astype(int)]
            a, b = np.angle(line[i, None] * chord.conj()), np.angle(-line[None] * chord.conj())
            bend, step = 4 * (a**2 + a * b + b**2), level[i, None] - level[None]
            joint = np.where(ok, np.exp(-bend - step**2 / 625) / (1 + far / self.k), 0.0).max(1)
            out[y[i], x[i]] += joint * np.abs(rise[i]) / 255
        return out

    def sparsity(self, img, known, front):
        """How concentrated the similarities of a front cell's patch to its neighbours are."""
        h, out = self.k // 2, np.ones(known.shape)
        grey = np.where(known, img.mean(2), 0.0)
        for y, x in zip(*np.nonzero(front), strict=True):
            y0, x0 = max(h, min(y, known.shape[0] - h - 1)), max(h, min(x, known.shape[1] - h - 1))
            own, m = grey[y0 - h : y0 + h + 1, x0 - h : x0 + h + 1], known[y0 - h : y0 + h + 1, x0 - h : x0 + h + 1]
            w = []
            for dy, dx in ((-h, -h), (-h, 0), (-h, h), (0, -h), (0, h), (h, -h), (h, 0), (h, h)):
                a, b = y0 + dy - h, x0 + dx - h
                if a < 0 or b < 0 or a + self.k > known.shape[0] or b + self.k > known.shape[1]:
                    continue
                both = m & known[a : a + self.k, b : b + self.k]
                if both.any():
                    w.append(np.exp(-((own - grey[a : a + self.k, b : b + self.k])[both] ** 2).mean() / 625))
            if w and sum(w) > 0:
                s = np.array(w) / sum(w)
                out[y, x] = np.sqrt((s**2).sum() * len(w) / 8)
        return out


def diffuse(img: np.ndarray, known: np.ndarray, rounds: int = 200) -> np.ndarray:
    """Neighbour means spread into the unknown cells: a floor for quality, not a patch search."""
    out = np.where(known[..., None], img, img[known].mean(0) if known.any() else 0).astype(float)
    for _ in range(rounds):
        p = np.pad(out, ((1, 1), (1, 1), (0, 0)), mode="edge")
        mean = (p[:-2, 1:-1] + p[2:, 1:-1] + p[1:-1, :-2] + p[1:-1, 2:]) / 4
        out = np.where(known[..., None], out, mean)
    return np.rint(out).astype(np.int16)


def fill(img: np.ndarray, known: np.ndarray, method: str = "zcurve", k: int = 9, order: str = "structure", cost: Cost | None = None, measure: bool = False, user: np.ndarray | None = None, dictionary: np.ndarray | None = None, blend: int = 1, on_step: Callable | None = None, **params) -> tuple[np.ndarray, list[dict], Selector]:
    """Complete one image: (image, trace of targets and winners, selector).

    Strict order, one target per step, a static dictionary of the patches known at the start (or
    the given one, rows of patch values). ``measure`` also asks the full scan for the same target.
    A whole unknown image, or one without any patch, is an error; nothing unknown is no work.
    """
    img, known = img.astype(np.int16).copy(), known.copy()
    if known.all():
        return img, [], None
    if not known.any():
        raise NoPatches("the whole image is unknown")
    h, w, c = img.shape
    if method == "diffuse":
        return diffuse(img, known), [], None
    patches, centres = windows(img, known, k) if dictionary is None else (dictionary.astype(np.int16), np.zeros((len(dictionary), 2), np.int64))
    if not len(patches) or h < k or w < k:
        raise NoPatches("no wholly known patch to fill from")
    selector = SELECTORS[method](patches, centres, k, c, cost, **params)
    scan = Selector(patches, centres, k, c, cost) if measure else None
    rank, half, confidence, trace = Order(order, k, user), k // 2, known.astype(float), []
    while not known.all():
        value = rank(img, known, confidence)
        y, x = np.unravel_index(int(np.argmax(value)), value.shape)
        cy, cx = min(max(int(y), half), h - half - 1), min(max(int(x), half), w - half - 1)
        at = (slice(cy - half, cy + half + 1), slice(cx - half, cx + half + 1))
        m = known[at]
        mask = np.repeat(m.ravel(), c)
        q = np.where(mask, img[at].reshape(-1), 0)
        i, best = selector.find(q, mask, (cy, cx))
        new = patches[i]
        if blend > 1:
            near = np.argsort(selector.cost.local(q, patches, mask), kind="stable")[:blend]
            new = np.clip(np.rint(blend_weights(q, patches[near], mask) @ patches[near]), 0, 255).astype(np.int16)
        hole = ~m
        if not hole.any():  # the window was moved off the hole at a border: cannot happen for front cells
            raise RuntimeError("a target without unknown cells")
        block = img[at]
        block[hole] = new.reshape(k, k, c)[hole]
        conf = confidence[at]
        conf[hole] = float((conf * m).sum() / m.size)
        known[at] = True
        selector.pasted(cy, cx, i)
        step = {"step": len(trace), "y": cy, "x": cx, "sy": int(centres[i][0]), "sx": int(centres[i][1]), "patch": i, "cost": best, "filled": int(hole.sum())}
        if scan is not None:
            step["exact"] = scan.find(q, mask, (cy, cx))[1]
        trace.append(step)
    return img, trace, selector


def errors(trace: list[dict], root: bool = True) -> np.ndarray:
    """Acceleration error of each measured step; 0/0 is 0, x/0 is nan."""
    a, e = (np.array([t[c] for t in trace], float) for c in ("cost", "exact"))
    if root:
        a, e = np.sqrt(np.maximum(0, a)), np.sqrt(np.maximum(0, e))
    return np.where(e > 0, a / np.where(e > 0, e, 1) - 1, np.where(a == 0, 0.0, np.nan))


def cubes(vol: np.ndarray, known: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(wholly known cubes as rows of (layer, row, column) values, their centres)."""
    if min(vol.shape) < k:
        return np.empty((0, k**3), np.int16), np.empty((0, 3), np.int64)
    at = np.argwhere(np.lib.stride_tricks.sliding_window_view(known, (k, k, k)).all((3, 4, 5)))
    cells = np.lib.stride_tricks.sliding_window_view(vol, (k, k, k))[tuple(at.T)]
    return cells.reshape(len(at), k**3).astype(np.int16), at + k // 2


def window_counts(a: np.ndarray, k: int) -> np.ndarray:
    """Sums over k-wide windows around each cell, cut at the border, along every axis in turn."""
    out = a.astype(np.int64)
    for axis in range(a.ndim):
        c = np.concatenate([np.zeros_like(out.take([0], axis)), out.cumsum(axis)], axis)
        i = np.arange(a.shape[axis])
        out = c.take(np.minimum(i + k // 2 + 1, a.shape[axis]), axis) - c.take(np.maximum(i - k // 2, 0), axis)
    return out


def fill_volume(vol: np.ndarray, known: np.ndarray, method: str = "zcurve", k: int = 3, **params) -> tuple[np.ndarray, list[dict]]:
    """Complete one volume of single samples: cubic patches, the unknown cell with most known
    cells around it first (ties in layer, row, column order)."""
    vol, known = vol.astype(np.int16).copy(), known.copy()
    if known.all():
        return vol, []
    patches, centres = cubes(vol, known, k)
    if not len(patches):
        raise NoPatches("no wholly known cube to fill from")
    selector, half, trace = SELECTORS[method](patches, centres, k, 1, None, ndim=3, **params), k // 2, []
    while not known.all():
        z, y, x = np.unravel_index(int(np.argmax(np.where(known, -1, window_counts(known, k)))), known.shape)
        c = [min(max(int(v), half), n - half - 1) for v, n in zip((z, y, x), known.shape, strict=True)]
        at = tuple(slice(v - half, v + half + 1) for v in c)
        m = known[at].copy()
        q = np.where(m, vol[at], 0).ravel()
        i, cost = selector.find(q, m.ravel(), c)
        vol[at] = np.where(m, vol[at], patches[i].reshape(k, k, k))
        known[at] = True
        trace.append({"step": len(trace), "z": c[0], "y": c[1], "x": c[2], "patch": i, "cost": cost, "filled": int((~m).sum())})
    return vol, trace
