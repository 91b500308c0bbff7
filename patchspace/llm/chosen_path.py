"""Near-duplicate groups by a chosen-path set similarity join.

Every text is a set of word shingles. Equal sets are one class, found by a 128-bit fingerprint;
the rest works on one representative (the smallest identifier) of each class.

1. A representative carries a sketch: ``COORDINATES`` minwise values, a byte of each.
2. ``trees`` independent trees. The root of a tree branches by the full minwise token of its own
   coordinate; a node of more than ``leaf_rows`` rows branches again, by a coordinate drawn for
   that node, and so on. Two sets of similarity s stay together with probability s per level, so
   a pair in a leaf of depth d is missed by all trees with probability (1 - s^d)^trees.
3. Leaves are compared exhaustively on sketches. The threshold lies ``SIGMAS`` standard
   deviations below the target similarity, and only pairs of fitting sizes count. Before a
   large node branches, its smallest row is compared with all others, so that large groups of
   alike texts are linked by a number of pairs that is linear in their size.
4. Candidate pairs are joined to loose groups (connected components). A group's full sets meet
   in one task, if they are fewer than ``group_rows`` and ``group_shingles`` together; else the
   leaves of trees grown over that group's rows link most of it, and step 5 the rest. In either, links
   are confirmed on full sets, in integers, by prefix filtering; pairs that are connected already
   are skipped, as they cannot change the result.
5. Rows of larger groups are met exactly, and so is a row whose leaves lie so deep that 1 - (the
   product of 1 - s^depth over its trees) is below ``recall`` at the target similarity: such rows are
   joined on the rare end of their full sets (``exact_links``), between components that are not
   linked yet.
6. Components of the confirmed links give the classes; a class is named by its smallest
   identifier.

Null and empty texts have an empty set and are linked with nothing. Null identifiers are kept
as rows of their own with a null component. Repeated rows have equal sets, so share a class. Texts
that share an identifier are nodes of their own, so they link nothing but what they are alike to.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.shared import ship, staged
from patchspace.llm.components import components
from patchspace.llm.shingles import M1, M2, mix, shingle_hashes, shingle_sets
from patchspace.llm.tokens import slices

COORDINATES, TREES, SIGMAS = 128, 12, 4.75
LEAF_ROWS, GROUP_ROWS, GROUP_SHINGLES, MAX_DEPTH = 2048, 8192, 4_000_000, 64
RECALL, BUCKET_BITS, CELL_ROWS = 0.99, 20, 512


def sketches(docs: DataFrame, words: int, trees: int = TREES, id_col: str = "doc_id", text_col: str = "text", seed: int = 1) -> DataFrame:
    """doc_id, text_key, n_shingles, f1, f2 (fingerprint), roots (full minwise tokens), sketch (bytes)."""
    ship(docs.sparkSession)
    odd = np.random.default_rng(seed).integers(1 << 62, size=COORDINATES, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)
    names = ["doc_id", "text_key", "n_shingles", "f1", "f2", "roots", "sketch"]

    def make(batches):
        for batch in batches:
            for part in slices(batch):
                h, at = shingle_hashes(part.column("text"), words)
                rows = part.num_rows
                n = np.zeros(rows, np.int64)
                f = np.zeros((2, rows), np.uint64)
                mins = np.zeros((rows, COORDINATES), np.uint64)
                with np.errstate(over="ignore"):
                    for i in range(rows):
                        own = np.unique(h[at[i] : at[i + 1]])
                        n[i] = len(own)
                        f[0, i], f[1, i] = own.sum(), mix(own + M1).sum()
                    full = np.flatnonzero(np.diff(at) > 0)
                    starts = at[:-1][full]
                    for c in range(COORDINATES if len(full) else 0):
                        mins[full, c] = np.minimum.reduceat(mix((h * odd[c]) ^ M2) if c < trees else h * odd[c], starts)
                    sketch = (mix(mins) >> np.uint64(56)).astype(np.uint8)
                roots = pa.FixedSizeListArray.from_arrays(pa.array(mins[:, :trees].astype(np.int64).ravel()), trees).cast(pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_key"), pa.array(n), pa.array(f[0].view(np.int64)), pa.array(f[1].view(np.int64)), roots, pa.array([x.tobytes() for x in sketch], pa.binary())], names=names)

    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text).alias("text_key"), text.alias("text"))
    return rows.mapInArrow(make, "doc_id long, text_key long, n_shingles long, f1 long, f2 long, roots array<long>, sketch binary")


def grow(reps: DataFrame, trees: int = TREES, leaf_rows: int = LEAF_ROWS) -> tuple[list[DataFrame], list[DataFrame]]:
    """(leaf rows by depth from 1, star pairs of the nodes that branched): trees over doc_id, n_shingles, roots, sketch."""
    rows = reps.select("doc_id", "n_shingles", "sketch", F.posexplode("roots").alias("tree", "token"))
    rows = rows.select(F.xxhash64("tree", "token").alias("node"), "doc_id", "n_shingles", "sketch")
    leaves, stars = [], []
    depth = 1
    while True:
        counts = rows.groupBy("node").agg(F.count("*").alias("size"), F.min("doc_id").alias("hub")).where(f"size > {leaf_rows}")
        counts = staged(counts, "path-nodes")  # at most one row per leaf_rows rows
        big = counts.agg(F.count("*"), F.max("size")).first()
        if not big[0] or depth >= MAX_DEPTH:
            leaves.append(rows)
            break
        marked = rows.join(counts.select(F.col("node").alias("big"), "hub"), F.col("node") == F.col("big"), "left")
        leaves.append(marked.where("big IS NULL").select(rows.columns))
        inner = staged(marked.where("big IS NOT NULL"), "path-inner")
        hubs = inner.where("doc_id = hub").select(F.col("node").alias("at"), F.col("sketch").alias("hub_sketch"), F.col("n_shingles").alias("hub_n")).dropDuplicates(["at"])
        stars.append(inner.join(hubs, F.col("node") == F.col("at")).select("doc_id", "n_shingles", "sketch", "hub", "hub_n", "hub_sketch"))
        coordinate = F.pmod(F.xxhash64("node", F.lit(depth)), F.lit(COORDINATES)).cast("int") + 1
        value = F.substring("sketch", coordinate, F.lit(1))
        rows = inner.select(F.xxhash64("node", F.lit(depth), value).alias("node"), "doc_id", "n_shingles", "sketch")
        depth += 1
    return leaves, stars


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for more in frames[1:]:
        out = out.unionByName(more)
    return out


def deep_rows(leaves: list[DataFrame], percent: int, trees: int, recall: float) -> DataFrame | None:
    """doc_id of the rows whose leaves miss ``recall`` at the target similarity; None if no leaf can."""
    s = percent / 100
    enough = 0  # the depth down to which ``trees`` trees suffice
    while enough < len(leaves) and 1 - (1 - s ** (enough + 1)) ** trees >= recall:
        enough += 1
    if enough == len(leaves):
        return None
    # a tree with a higher leaf counts as one of depth ``enough``, so too many rows rather than too few are deep
    high = math.log1p(-(s**enough)) if 0 < enough else -math.inf
    below = _union([f.select("doc_id", F.lit(math.log1p(-(s ** (enough + 1 + k)))).alias("miss")) for k, f in enumerate(leaves[enough:])])
    sums = below.groupBy("doc_id").agg(F.sum("miss").alias("miss"), F.count("*").alias("n"))
    if enough:
        sums = sums.withColumn("miss", F.col("miss") + F.lit(high) * (F.lit(trees) - F.col("n")))
    return sums.where(F.col("miss") > math.log1p(-recall) if recall < 1 else F.lit(True)).select("doc_id")


def _runs(batches, key: str):
    """Tables of whole runs of equal keys, in order, a run never split; rows come sorted."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        k = batch.column(key).to_numpy()
        change = np.flatnonzero(k[1:] != k[:-1])
        first = held[-1].column(key)[-1].as_py() if held else None
        if held and k[0] != first:
            yield pa.Table.from_batches(held).combine_chunks()
            held = []
        if len(change):
            cut = int(change[-1]) + 1
            yield pa.Table.from_batches([*held, batch.slice(0, cut)]).combine_chunks()
            held = [batch.slice(cut)]
        else:
            held.append(batch)
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _limit(percent: int) -> float:
    p = percent / 100
    return COORDINATES * p - SIGMAS * (COORDINATES * p * (1 - p)) ** 0.5


def _pairs_schema() -> pa.Schema:
    return pa.schema([("a", pa.int64()), ("b", pa.int64())])


def compare_leaves(leaves: DataFrame, percent: int) -> DataFrame:
    """Candidate pairs (a, b) of leaves; a large leaf gives the star of each loose group in it."""
    limit = _limit(percent)

    def compare(batches):
        for t in _runs(batches, "node"):
            node, doc, n = (t.column(c).to_numpy() for c in ("node", "doc_id", "n_shingles"))
            x = np.frombuffer(b"".join(t.column("sketch").to_pylist()), np.uint8).reshape(-1, COORDINATES)
            start = np.flatnonzero(np.concatenate(([True], node[1:] != node[:-1])))
            size = np.diff(np.append(start, len(node)))
            run = np.repeat(np.arange(len(start)), size)
            small = size[run] <= 24
            out_a, out_b = [], []
            for k in range(1, int(min(24, size.max()))):
                i = np.flatnonzero((run[k:] == run[:-k]) & small[k:])
                i = i[(100 * np.minimum(n[i], n[i + k]) >= percent * np.maximum(n[i], n[i + k])) & (doc[i] != doc[i + k])]
                for at in range(0, len(i), 1 << 15):
                    j = i[at : at + (1 << 15)]
                    j = j[(x[j] == x[j + k]).sum(1) >= limit]
                    out_a.append(doc[j])
                    out_b.append(doc[j + k])
            for s, m in zip(start[size > 24], size[size > 24], strict=True):
                a, b = _stars(doc[s : s + m], n[s : s + m], x[s : s + m], percent, limit)
                out_a.append(a)
                out_b.append(b)
            a = np.concatenate(out_a) if out_a else np.empty(0, np.int64)
            b = np.concatenate(out_b) if out_b else np.empty(0, np.int64)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(np.maximum(a, b)), pa.array(np.minimum(a, b))], schema=_pairs_schema())

    dealt = leaves.repartition("node").sortWithinPartitions("node", "doc_id")
    return dealt.mapInArrow(compare, "a long, b long")


def _stars(doc, n, x, percent, limit):
    """Loose groups of one leaf: each row's first match joins groups until all are settled."""
    m = len(doc)
    up = np.arange(m)

    def find(i):
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    order = np.argsort(n, kind="stable")
    xs, ns = x[order], n[order]
    for i in range(m):
        # sizes ascend, so what fits row i begins where the smaller set is large enough
        lo = int(np.searchsorted(100 * ns[:i], percent * ns[i]))
        if lo >= i:
            continue
        hit = np.flatnonzero((xs[lo:i] == xs[i]).sum(1) >= limit) + lo
        root = find(i)
        for r in set(up[hit].tolist()):
            r = find(r)
            if r != root:
                up[max(r, root)] = min(r, root)
                root = min(r, root)
    group = np.array([find(i) for i in range(m)])
    least = np.full(m, np.iinfo(np.int64).max)
    np.minimum.at(least, group, doc[order])
    a, b = doc[order], least[group]
    return a[a != b], b[a != b]


def compare_stars(stars: DataFrame, percent: int) -> DataFrame:
    """Candidate pairs of branching nodes' hubs with their rows."""
    limit = _limit(percent)

    def compare(batches):
        for t in batches:
            if not t.num_rows:
                continue
            one = lambda c: np.frombuffer(b"".join(t.column(c).to_pylist()), np.uint8).reshape(-1, COORDINATES)  # noqa: B023, E731
            n, m, doc, hub = (t.column(c).to_numpy() for c in ("n_shingles", "hub_n", "doc_id", "hub"))
            ok = ((one("sketch") == one("hub_sketch")).sum(1) >= limit) & (100 * np.minimum(n, m) >= percent * np.maximum(n, m)) & (doc != hub)
            yield pa.RecordBatch.from_arrays([pa.array(doc[ok]), pa.array(hub[ok])], schema=_pairs_schema())

    return stars.mapInArrow(compare, "a long, b long")


def links_of_group(doc: list[int], sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """A spanning set of the links among the sets of a group, each confirmed in integers."""
    order = sorted(range(len(doc)), key=lambda i: (len(sets[i]), doc[i]))
    up = list(range(len(doc)))

    def find(i):
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    found: list[tuple[int, int]] = []
    full = [None] * len(doc)
    if len(doc) > 32:  # prefix filtering: rare shingles first
        values, codes = np.unique(np.concatenate(sets), return_inverse=True)
        often = np.bincount(codes)
        rank = np.empty(len(values), np.int64)
        rank[np.argsort(often, kind="stable")] = np.arange(len(values))
        ends = np.cumsum([len(s) for s in sets])
        ranked = [np.sort(rank[codes[e - len(s) : e]]) for s, e in zip(sets, ends, strict=True)]
        index: dict[int, list[int]] = {}
    for place, i in enumerate(order):
        if len(doc) > 32:
            n = len(sets[i])
            prefix = ranked[i][: n - (percent * n + 99) // 100 + 1].tolist()
            near: set[int] = set()
            for v in prefix:
                near.update(index.get(v, ()))
                index.setdefault(v, []).append(i)
        else:
            near = order[:place]
        for j in near:
            if find(i) == find(j):
                continue
            a, b = len(sets[i]), len(sets[j])
            if 100 * b < percent * a:
                continue
            for q in (i, j):
                if full[q] is None:
                    full[q] = set(sets[q].tolist())
            both = len(full[i] & full[j])
            if 100 * both >= percent * (a + b - both):
                found.append((max(doc[i], doc[j]), min(doc[i], doc[j])))
                up[find(i)] = find(j)
    return found


def keyed_texts(docs: DataFrame, id_col: str, text_col: str, repeated: DataFrame | None) -> DataFrame:
    """_id, text. Where texts share an identifier (a row of ``repeated``), each has a key of its own."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("_id"), text.alias("text"))
    if repeated is None:
        return rows
    marked = rows.join(repeated.select(F.col("doc_id").alias("_again")), F.col("_id") == F.col("_again"), "left")
    return marked.select(F.when(F.col("_again").isNotNull(), F.xxhash64("_id", F.xxhash64("text"))).otherwise(F.col("_id")).alias("_id"), "text")


def confirm(texts: DataFrame, groups: DataFrame, words: int, percent: int) -> DataFrame:
    """Confirmed links (a, b) within groups(group, doc_id), read from whole texts(_id, text)."""

    def check(batches):
        for t in _runs(batches, "group"):
            group = t.column("group").to_numpy()
            start = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1])))
            bounds = np.append(start, len(group))
            at = 0
            while at < len(start):  # some whole groups at a time
                end = at + 1
                while end < len(start) and bounds[end + 1] - bounds[at] <= 4096:
                    end += 1
                rows = t.slice(int(bounds[at]), int(bounds[end] - bounds[at])).combine_chunks()
                doc = rows.column("doc_id").to_pylist()
                sets = []
                for b in rows.to_batches():
                    for part in slices(b):
                        sets += shingle_sets(part.column("text"), words)
                pairs = []
                for g in range(at, end):
                    lo, hi = int(bounds[g] - bounds[at]), int(bounds[g + 1] - bounds[at])
                    pairs += links_of_group(doc[lo:hi], sets[lo:hi], percent)
                if pairs:
                    a, b = zip(*pairs, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], schema=_pairs_schema())
                at = end

    rows = groups.join(texts, F.col("doc_id") == F.col("_id")).select("group", "doc_id", "text")
    dealt = rows.repartition("group").sortWithinPartitions("group", "doc_id")
    return dealt.mapInArrow(check, "a long, b long")


def exact_links(texts: DataFrame, rows: DataFrame, words: int, percent: int) -> DataFrame:
    """Confirmed links (a, b) among rows(doc_id, component) of different components, none missed.

    A prefix join: shingles have one global order, rarest first, and the first common shingle of
    a pair at the limit lies in the first n - ceil(limit * n) + 1 of either set. What the places leave
    room for below that shingle bounds the common part. A shingle of many rows is dealt over cells,
    a cell being a pair of blocks of its rows, so no key has to fit in one task.
    """
    rows = staged(rows, "path-exact-rows")  # of known size, so that texts are only shuffled for many rows
    rows = staged(rows.join(texts, F.col("doc_id") == F.col("_id")).select("doc_id", "component", "text"), "path-exact")
    shift = np.uint64(64 - BUCKET_BITS)

    def count(batches):
        sums = np.zeros(1 << BUCKET_BITS, np.int64)
        for batch in batches:
            for part in slices(batch):
                own = np.concatenate(shingle_sets(part.column("text"), words))
                sums += np.bincount((own >> shift).astype(np.int64), minlength=len(sums))
        at = np.flatnonzero(sums)
        for lo in range(0, len(at), 1 << 16):
            yield pa.RecordBatch.from_arrays([pa.array(at[lo : lo + (1 << 16)]), pa.array(sums[at[lo : lo + (1 << 16)]])], names=["bucket", "n"])

    found = rows.select("text").mapInArrow(count, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    often = np.zeros(1 << BUCKET_BITS, np.uint8)  # eighths of powers of two; any order is right, a good one is quick
    often[found.column("bucket").to_numpy()] = np.minimum(255, 8 * np.log2(found.column("n").to_numpy() + 1.0)).astype(np.uint8)

    def prefixes(batches):
        for batch in batches:
            for part in slices(batch):
                keys, places, lengths = [], [], []
                for own in shingle_sets(part.column("text"), words):
                    keep = len(own) - (percent * len(own) + 99) // 100 + 1 if len(own) else 0
                    keys.append(own[np.lexsort((own, often[(own >> shift).astype(np.int64)]))[:keep]])
                    places.append(np.arange(keep))
                    lengths.append((len(own), keep))
                n, kept = np.array(lengths).T
                key = np.concatenate(keys).view(np.int64)
                doc, component = (np.repeat(part.column(c).to_numpy(), kept) for c in ("doc_id", "component"))
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (key, np.concatenate(places), doc, component, np.repeat(n, kept))], names=["key", "place", "doc_id", "component", "n_shingles"])

    def meet(batches):
        for t in _runs(batches, "cell"):
            cell, own, place, doc, component, n = (t.column(c).to_numpy() for c in ("cell", "own", "place", "doc_id", "component", "n_shingles"))
            diagonal = t.column("diagonal").to_numpy(zero_copy_only=False)
            i, k = np.arange(len(cell)), 1
            while len(i := i[i + k < len(cell)]) and len(i := i[cell[i] == cell[i + k]]):
                for at in range(0, len(i), 1 << 16):
                    x = i[at : at + (1 << 16)]
                    y = x + k
                    ok = (component[x] != component[y]) & (diagonal[x] | (own[x] != own[y]))
                    ok &= 100 * np.minimum(n[x], n[y]) >= percent * np.maximum(n[x], n[y])
                    ok &= (100 + percent) * np.minimum(n[x] - place[x], n[y] - place[y]) >= percent * (n[x] + n[y])
                    x, y = doc[x[ok]], doc[y[ok]]
                    if len(x):
                        yield pa.RecordBatch.from_arrays([pa.array(np.maximum(x, y)), pa.array(np.minimum(x, y))], schema=_pairs_schema())
                k += 1

    keyed = staged(rows.mapInArrow(prefixes, "key long, place long, doc_id long, component long, n_shingles long"), "path-prefix")
    shared = keyed.groupBy("key").agg(F.count("*").alias("rows"), F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi")
    shared = shared.select(F.col("key").alias("_key"), F.expr(f"cast(ceil(rows / {CELL_ROWS}) AS int)").alias("blocks"))
    met = keyed.join(shared, F.col("key") == F.col("_key")).withColumn("own", F.pmod(F.xxhash64("doc_id"), "blocks").cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    cell = F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other")).alias("cell")
    met = met.select(cell, "own", (F.col("own") == F.col("other")).alias("diagonal"), "place", "doc_id", "component", "n_shingles")
    pairs = staged(met.repartition("cell").sortWithinPartitions("cell").mapInArrow(meet, "a long, b long").distinct(), "path-met")
    pair_rows = pairs.select(F.xxhash64("a", "b").alias("group"), F.explode(F.array("a", "b")).alias("doc_id"))
    return confirm(texts, pair_rows, words, percent)


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, trees: int = TREES, leaf_rows: int = LEAF_ROWS, id_col: str = "doc_id", text_col: str = "text", group_rows: int = GROUP_ROWS, group_shingles: int = GROUP_SHINGLES, recall: float = RECALL) -> DataFrame:
    """doc_id, n_shingles, component_id, kept, text_key, first: a row per row of ``docs``.

    ``text_key`` is xxhash64 of the text. ``first`` marks one text of each component (the texts with the
    smallest identifier and, of several under it, one): it differs from ``kept`` only where an
    identifier has several texts, which then are documents of their own.
    """
    all_rows = staged(sketches(docs, words, trees, id_col, text_col), "path-sketches")
    repeated = staged(all_rows.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("text_key").alias("lo"), F.max("text_key").alias("hi")).where("lo <> hi").select("doc_id"), "path-repeated")
    if repeated.isEmpty():
        repeated = None
        all_rows = all_rows.withColumn("node", F.col("doc_id"))
    else:
        again = repeated.select(F.col("doc_id").alias("_again"))
        own_key = F.when(F.col("_again").isNotNull(), F.xxhash64("doc_id", "text_key")).otherwise(F.col("doc_id"))
        all_rows = staged(all_rows.join(again, F.col("doc_id") == F.col("_again"), "left").withColumn("node", own_key).drop("_again"), "path-nodes")
    texts = keyed_texts(docs, id_col, text_col, repeated)
    some = all_rows.where("n_shingles > 0 AND doc_id IS NOT NULL")
    classes = staged(some.groupBy("n_shingles", "f1", "f2").agg(F.min(F.struct("doc_id", "node")).alias("r")).select("n_shingles", "f1", "f2", F.col("r.doc_id").alias("rep_id"), F.col("r.node").alias("rep")), "path-classes")
    own = classes.select(F.col("rep").alias("_rep"), F.col("f1").alias("_f1"), F.col("f2").alias("_f2"))
    reps = some.join(own, (F.col("node") == F.col("_rep")) & (F.col("f1") == F.col("_f1")) & (F.col("f2") == F.col("_f2")), "left_semi")
    reps = staged(reps.dropDuplicates(["node"]).select(F.col("node").alias("doc_id"), "n_shingles", "roots", "sketch"), "path-reps")
    leaves, stars = grow(reps, trees, leaf_rows)
    exact = deep_rows(leaves, percent, trees, recall)
    pairs = compare_leaves(_union(leaves), percent)
    for s in stars:
        pairs = pairs.unionByName(compare_stars(s, percent))
    loose = staged(components(pairs), "path-loose")
    sizes = loose.join(reps.select("doc_id", "n_shingles"), F.col("node") == F.col("doc_id"))
    sizes = sizes.groupBy("component").agg(F.count("*").alias("rows"), F.sum("n_shingles").alias("total"))
    big = staged(sizes.where(f"rows > {group_rows} OR total > {group_shingles}").select("component"), "path-big")
    groups = loose.join(big, "component", "left_anti").select(F.col("component").alias("group"), F.col("node").alias("doc_id"))
    links = confirm(texts, groups, words, percent)
    if not big.isEmpty():
        # leaves of trees over a large group link most of it cheaply; the exact join below links the rest
        rest = reps.join(loose.join(big, "component", "left_semi").select(F.col("node").alias("_n")), F.col("doc_id") == F.col("_n"), "left_semi")
        own_leaves, _ = grow(rest, trees, max(2, leaf_rows // 4))
        links = links.unionByName(confirm(texts, _union(own_leaves).select(F.col("node").alias("group"), "doc_id"), words, percent))
        exact = rest.select("doc_id") if exact is None else exact.unionByName(rest.select("doc_id"))
    if exact is not None:
        links = staged(links, "path-links")
        known = staged(components(links), "path-known")
        rows = exact.distinct().join(known, F.col("doc_id") == F.col("node"), "left").select("doc_id", F.coalesce("component", "doc_id").alias("component"))
        links = links.unionByName(staged(exact_links(texts, rows, words, percent), "path-exact-links"))
    linked = staged(components(links), "path-linked")
    named = classes.join(linked, F.col("rep") == F.col("node"), "left").select("n_shingles", "f1", "f2", "rep_id", "rep", F.coalesce("component", "rep").alias("component"))
    if repeated is None:
        named = named.withColumn("component_id", F.col("component")).withColumn("first_node", F.col("component"))
    else:
        least = named.groupBy("component").agg(F.min(F.struct("rep_id", "rep")).alias("l")).select("component", F.col("l.rep_id").alias("component_id"), F.col("l.rep").alias("first_node"))
        named = named.join(least, "component")
    named = staged(named.select("n_shingles", "f1", "f2", "component_id", "first_node"), "path-named")
    out = all_rows.select("doc_id", "node", "text_key", "n_shingles", "f1", "f2").join(named, ["n_shingles", "f1", "f2"], "left")
    component = F.when(F.col("doc_id").isNull(), F.lit(None)).otherwise(F.coalesce("component_id", "doc_id")).cast("long")
    out = out.select("doc_id", "n_shingles", component.alias("component_id"), "text_key", F.coalesce(F.col("node") == F.col("first_node"), F.lit(True)).alias("first"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True))).select("doc_id", "n_shingles", "component_id", "kept", "text_key", "first")


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"), words=3, percent=85).select("doc_id", "n_shingles", "component_id", "kept")
