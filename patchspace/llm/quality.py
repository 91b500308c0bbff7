"""Quality scores: random-indexing word vectors, pooled, and a two-layer network in numpy.

Words. A word is split into its core (lower case, without marks at its ends) and its mark (the
case of its letters and the signs around it). Both are hashed into ``BUCKETS`` terms. Every term
has a fixed sparse random index vector; its word vector is the sum of the index vectors of what
stands beside it, over all documents. The sums are taken over the whole corpus, in blocks of
terms, and have a fixed size (``BUCKETS`` x ``DIM``) whatever the corpus.

Documents. Pooled features: mean vectors of cores and of marks, spread of the core vectors, the
concentration of index vectors, how alike neighbours are, and the length.

Classifier. It learns from at most ``max_train`` labelled rows (those with the smallest hash of
their identifier), never from held-out rows; a fifth of them sets the temperature that
calibrates the probabilities. Labels, lang, source and identifiers are never inputs of a score.

Null text is an empty text, scored like any other. Null and repeated identifiers are scored row
by row. Without labelled rows, or with one class only, all scores are the smoothed share of
label 1. Other columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.shared import ship
from patchspace.llm.tokens import slices

BUCKETS, DIM, BLOCK = 1 << 14, 32, 1 << 10
NONZERO = 6
MAX_TRAIN = 20_000
THRESHOLD = 0.3
FEATURES = 3 * DIM + 4
PARTS = re.compile(r"([^\w]*)(.*?)([^\w]*)", re.S)


def index_vectors() -> np.ndarray:
    """Sparse ternary vectors, a row per term; fixed by their seed."""
    rng = np.random.default_rng(20)
    out = np.zeros((BUCKETS, DIM), np.int8)
    rows = np.repeat(np.arange(BUCKETS), NONZERO)
    cols = np.argsort(rng.random((BUCKETS, DIM)), axis=1)[:, :NONZERO].ravel()
    out[rows, cols] = rng.integers(0, 2, len(rows)) * 2 - 1
    return out


def terms(word: str) -> tuple[int, int]:
    """(core term, mark term) of a word."""
    before, core, after = PARTS.fullmatch(word).groups()
    low = core.lower()
    case = "l" if core == low else "U" if core == core.upper() and len(core) > 1 else "T" if core[:1] != low[:1] and core[1:] == low[1:] else "m"
    kind = case if low.isalpha() else "d" if low.isdigit() else "-" if not low else "x"
    return xxhash.xxh32_intdigest(low) % BUCKETS, xxhash.xxh32_intdigest(f"{kind} {before[:3]} {after[:3]}") % BUCKETS


_known: dict[str, tuple[int, int]] = {}
KNOWN_WORDS = 100_000  # a bound on a worker's memory; terms do not depend on it


def _terms_of(words: list[str]) -> np.ndarray:
    if len(_known) > KNOWN_WORDS:
        _known.clear()
    known = _known
    for w in words:
        if w not in known:
            known[w] = terms(w)
    return np.array([known[w] for w in words], np.int64).reshape(-1, 2)


def word_terms(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(core terms, mark terms, offsets of the texts)."""
    texts = pc.fill_null(texts, "").cast(pa.large_string())
    split = pc.ascii_split_whitespace(texts)
    at = np.asarray(split.offsets, dtype=np.int64)
    at = at - at[0]
    coded = pc.dictionary_encode(split.flatten())
    words = coded.dictionary.to_pylist()
    table = _terms_of(words)
    index = np.asarray(coded.indices, dtype=np.int64)
    empty = np.fromiter((not w for w in words), bool, len(words))
    if empty.any():
        keep = ~empty[index]
        at = np.concatenate(([0], np.cumsum(keep)))[at]
        index = index[keep]
    return table[index, 0], table[index, 1], at


def _add_contexts(sums: np.ndarray, core: np.ndarray, mark: np.ndarray, at: np.ndarray, index: np.ndarray, part: int = 1 << 18) -> None:
    """Add to each term the index vectors of the words beside its occurrences."""
    first = np.zeros(len(core), bool)
    first[at[:-1][np.diff(at) > 0]] = True
    for a in range(0, len(core), part):
        b = min(a + part, len(core))
        lo, hi = max(a - 1, 0), min(b + 1, len(core))
        v = index[core[lo:hi]] + index[mark[lo:hi]]
        beside = np.zeros((b - a, DIM), np.int8)
        left = ~first[a:b]  # not the first word of its text
        left[0] &= a > 0
        rows = np.flatnonzero(left)
        beside[rows] += v[rows + a - lo - 1]
        nxt = np.append(first[a + 1 : b], True if b == len(core) else first[b])
        rows = np.flatnonzero(~nxt)
        beside[rows] += v[rows + a - lo + 1]
        for term in (core, mark):
            own = term[a:b].astype(np.uint16)
            order = np.argsort(own, kind="stable")
            ranked = own[order]
            start = np.flatnonzero(np.concatenate(([True], ranked[1:] != ranked[:-1])))
            sums[ranked[start]] += np.add.reduceat(beside[order], start, axis=0, dtype=np.int64)


def word_vectors(docs: DataFrame, text_col: str = "text") -> np.ndarray:
    """The BUCKETS x DIM word vectors of the whole corpus, rows of unit length.

    A task sends a block of sums for the terms it has seen; blocks are added up by key in two
    steps. What reaches the driver is the fixed-size matrix.
    """
    ship(docs.sparkSession)
    ddl = "block int, salt int, sums binary"
    names = ["block", "salt", "sums"]

    def pack(block: int, salt: int, sums: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([salt], pa.int32()), pa.array([sums.astype("<i8").tobytes()], pa.binary())], names=names)

    def gather(batches):
        from pyspark import TaskContext

        index, sums = index_vectors(), np.zeros((BUCKETS, DIM), np.int64)
        for batch in batches:
            for part in slices(batch):
                _add_contexts(sums, *word_terms(part.column("text")), index)
        for b in range(0, BUCKETS, BLOCK):
            if sums[b : b + BLOCK].any():
                yield pack(b // BLOCK, TaskContext.get().partitionId() % 32, sums[b : b + BLOCK])

    def add(batches):
        held: dict[int, np.ndarray] = {}
        for batch in batches:
            for block, raw in zip(batch.column("block").to_pylist(), batch.column("sums").to_pylist(), strict=True):
                x = np.frombuffer(raw, "<i8").reshape(BLOCK, DIM)
                held[block] = held[block] + x if block in held else x
        for block, x in held.items():
            yield pack(block, 0, x)

    rows = docs.select(F.coalesce(F.col(text_col), F.lit("")).alias("text")).mapInArrow(gather, ddl)
    once = rows.repartition("block", "salt").mapInArrow(add, ddl)
    out = np.zeros((BUCKETS, DIM))
    for r in once.repartition(8, "block").mapInArrow(add, ddl).collect():  # BUCKETS / BLOCK rows
        out[r.block * BLOCK : (r.block + 1) * BLOCK] += np.frombuffer(r.sums, "<i8").reshape(BLOCK, DIM)
    return (out / np.maximum(1e-9, np.sqrt((out**2).sum(1, keepdims=True)))).astype(np.float32)


def features(texts: pa.Array, vectors: np.ndarray, index: np.ndarray) -> np.ndarray:
    """Pooled features, a row per text; ``index`` as floats."""
    core, mark, at = word_terms(texts)
    n = np.diff(at)
    out = np.zeros((len(n), FEATURES), np.float32)
    for i in np.flatnonzero(n):
        c = core[at[i] : at[i + 1]]
        m, row = float(n[i]), out[i]
        own = vectors[c]
        mean = own.sum(0) / m
        centre = index[c].sum(0) / m
        row[:DIM] = mean
        row[DIM : 2 * DIM] = vectors[mark[at[i] : at[i + 1]]].sum(0) / m
        row[2 * DIM : 3 * DIM] = np.sqrt(np.maximum(0, np.einsum("ij,ij->j", own, own) / m - mean * mean))
        row[3 * DIM] = centre @ centre / NONZERO
        row[3 * DIM + 1] = np.count_nonzero(c[1:] == c[:-1]) / m
        row[3 * DIM + 2] = np.vdot(own[1:], own[:-1]) / m
        row[3 * DIM + 3] = np.log1p(m)
    return out


@dataclass
class Model:
    vectors: np.ndarray
    centre: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        h = np.tanh((x - self.centre) / self.scale @ self.w1 + self.b1)
        return h @ self.w2 + self.b2

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x) / self.temperature, -60, 60)))


def train(x: np.ndarray, y: np.ndarray, vectors: np.ndarray, hidden: int = 32, epochs: int = 60, seed: int = 3) -> Model:
    """Fit by Adam on four fifths of the rows, calibrate on the rest."""
    width = x.shape[1]
    prior = (y.sum() + 1) / (len(y) + 2)
    if len(y) < 20 or y.min() == y.max():
        return Model(vectors, np.zeros(width), np.ones(width), np.zeros((width, hidden)), np.zeros(hidden), np.zeros(hidden), float(np.log(prior / (1 - prior))), 1.0)
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(y))
    cut = len(y) // 5
    held, fit = order[:cut], order[cut:]
    centre, scale = x[fit].mean(0), x[fit].std(0) + 1e-3
    z = (x - centre) / scale
    p = [rng.normal(0, width**-0.5, (width, hidden)), np.zeros(hidden), rng.normal(0, hidden**-0.5, hidden), np.array(np.log(prior / (1 - prior)))]
    mom, var, step = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p], 0
    for epoch in range(epochs):
        rate = 3e-3 * (1 - epoch / epochs) + 1e-4
        for part in np.array_split(rng.permutation(fit), max(1, len(fit) // 128)):
            h = np.tanh(z[part] @ p[0] + p[1])
            e = (1 / (1 + np.exp(-np.clip(h @ p[2] + p[3], -60, 60))) - y[part]) / len(part)
            back = np.outer(e, p[2]) * (1 - h**2)
            grads = [z[part].T @ back + 1e-4 * p[0], back.sum(0), h.T @ e + 1e-4 * p[2], e.sum()]
            step += 1
            for i, g in enumerate(grads):
                mom[i] = 0.9 * mom[i] + 0.1 * g
                var[i] = 0.999 * var[i] + 0.001 * g * g
                p[i] = p[i] - rate * (mom[i] / (1 - 0.9**step)) / (np.sqrt(var[i] / (1 - 0.999**step)) + 1e-8)
    model = Model(vectors, centre, scale, *p[:3], float(p[3]), 1.0)
    logits = model.logits(x[held])
    grid = np.exp(np.linspace(np.log(0.25), np.log(8), 141))
    loss = [np.mean(np.logaddexp(0, -np.where(y[held] == 1, logits, -logits) / t)) for t in grid]
    model.temperature = float(grid[int(np.argmin(loss))])
    return model


def held_out(id_col: Column, modulus: int = 5) -> Column:
    return F.pmod(F.crc32(id_col.cast("string").cast("binary")), F.lit(modulus)) == 0


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text", max_train: int = MAX_TRAIN) -> Model:
    """Word vectors from all documents, the network from a bounded labelled sample."""
    vectors = word_vectors(docs, text_col)
    usable = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull() & ~held_out(F.col(id_col)))
    own = usable.groupBy(F.col(id_col).cast("long").alias("c_id")).agg(F.max(label_col).cast("int").alias("y"))
    chosen = own.orderBy(F.xxhash64("c_id"), "c_id").limit(max_train)  # at most max_train small rows
    lean = docs.select(F.col(id_col).cast("long").alias("i"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    rows = lean.join(F.broadcast(chosen), F.col("i") == F.col("c_id")).select("i", "y", F.xxhash64("text").alias("k"), "text")

    def pool(batches):
        index = index_vectors().astype(np.float32)
        for batch in batches:
            for part in slices(batch):
                x = features(part.column("text"), vectors, index)
                yield pa.RecordBatch.from_arrays([part.column("i"), part.column("y"), part.column("k"), pa.array([r.tobytes() for r in x], pa.binary())], names=["i", "y", "k", "x"])

    # of several texts of an identifier, the one of the least hash, so that the model depends on no row order
    one = rows.mapInArrow(pool, "i long, y int, k long, x binary").groupBy("i").agg(F.min(F.struct("k", "y", "x")).alias("r"))
    got = one.select("i", "r.y", "r.x").collect()  # at most max_train rows
    got.sort(key=lambda r: r.i)
    x = np.frombuffer(b"".join(r.x for r in got), np.float32).reshape(-1, FEATURES).astype(float)
    return train(x, np.array([r.y for r in got], float), vectors)


_index: list[np.ndarray] = []


def _float_index() -> np.ndarray:
    if not _index:
        _index.append(index_vectors().astype(np.float32))
    return _index[0]


def scorer(model: Model):
    """A function of a text column: the calibrated probability of label 1."""
    spark = SparkSession.active()
    sent = spark.sparkContext.broadcast(model)  # fixed size: word vectors and two small layers

    @F.arrow_udf("double")
    def score(text: pa.Array) -> pa.Array:
        rows = pa.RecordBatch.from_arrays([text], names=["text"])
        got = [sent.value.probability(features(p.column("text"), sent.value.vectors, _float_index())) for p in slices(rows)]
        return pa.array(np.concatenate(got) if got else np.empty(0), pa.float64())

    return lambda text: score(F.coalesce(text, F.lit("")))


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    score = scorer(model)(F.col("text"))
    scored = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), score.alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))
