"""Katz backoff language model over the whole corpus, of any order (3), scored text by text.

Counts. Words are lower-cased (A-Z) runs between ASCII white space; a text ends with an end
token, and one start mark stands before its first word. N-grams of the training rows are counted
over the whole corpus; Good-Turing discounts apply to counts up to ``K``, order by order.

Model, evaluated recursively for a word w after a history h of n - 1 words, c being counts and h'
the history without its first word::

    P(w | h) = d(c(h,w)) c(h,w) / c(h)       if c(h,w) > 0
             = a(h) P(w | h')                if c(h) > 0
             = P(w | h')                     otherwise
    P(w)     = d(c(w)) c(w) / N              if c(w) > 0
             = what is left of 1             for the unknown word, one type

    a(h) = (1 - sum of P(w|h) over seen w) / (1 - sum of P(w|h') over seen w)

so that every distribution sums to 1 over the V training types and the unknown word. Where all
counts after h are above K nothing would be left: there h counts one more occurrence, unseen.
A history reaches back to the start mark at most: the first words of a text have shorter ones.

Execution. Texts become blocks of word hashes and local word numbers, staged once. Level by level
a block asks for its distinct n-grams: a message for each (block, bucket) that has any, so never more
than there are keys. A bucket merges messages to its part of the count table and answers each in
the order of its keys. Words, and then n-grams, are named by dense numbers of the level below,
so keys stay some bytes short and are never cut or merged. An n-gram that no other block asked for is local: what
follows it, or ends in it, is counted within the block, and of that only sums for shared histories are
sent. So the higher levels exchange only what several blocks may have in common.

N-grams are dealt by history; a history with more than half a bucket's share of all tokens is dealt
over as many parts as it has such shares, and its sums, additive, are collected: at most
two rows per bucket. Answers hold sufficient statistics (counts of counts after h), so discounts can
come last. Blocks and answers meet in one exchange by block, and levels below are worked out
again from the answers rather than stored. The count tables are kept by bucket (rows of kind 0 in
the folders), n-grams of one block with the block.

Null text is an empty text: its only token is the end. Null identifiers are training rows (they
have no remainder). Repeated rows are counted and scored one by one. With no training rows all
tokens are the unknown word, of probability 1. Other columns are ignored.
"""

from __future__ import annotations

import gc
import struct
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.shared import drop_path, ship, staged_at, trim
from patchspace.llm.shingles import mix, word_hashes
from patchspace.llm.tokens import slices

K, ORDER = 5, 3
START = 0  # the number of the start mark; words have theirs from 1
END = np.uint64(0x454E44)
BLOCK_TOKENS, BUCKET_KEYS, BLOCKS_A_TASK = 1_000_000, 2_000_000, 4
TABLE, ANSWER, TOTALS = 0, 1, 2
BASE, WORDS = 0, 1
MOVED = "bucket int, block long, kind int, body binary"
MOVED_SCHEMA = pa.schema([("bucket", pa.int32()), ("block", pa.int64()), ("kind", pa.int32()), ("body", pa.binary())])


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays as zstd over their byte planes; integers, never negative, in as few bytes as the largest needs."""
    head, body = [struct.pack("<B", len(arrays))], []
    for a in arrays:
        if a.dtype == bool:
            kind, planes = 0, np.packbits(a)
        elif a.dtype.kind == "f":
            kind, planes = 9, np.ascontiguousarray(a, "<f8").view(np.uint8).reshape(-1, 8).T
        else:
            most = int(a.max()) if len(a) else 0
            kind = max(1, -(-most.bit_length() // 8))
            planes = np.ascontiguousarray(a, "<u8").view(np.uint8).reshape(-1, 8)[:, :kind].T
        head.append(struct.pack("<BQ", kind, len(a)))
        body.append(np.ascontiguousarray(planes).tobytes())
    return zstandard.ZstdCompressor(level=1).compress(b"".join(head + body))


def unpack(raw: bytes) -> list[np.ndarray]:
    """The arrays of ``pack``: booleans, int64 or doubles."""
    data = zstandard.ZstdDecompressor().decompress(raw)
    at, out = 1 + 9 * data[0], []
    for i in range(data[0]):
        kind, n = struct.unpack_from("<BQ", data, 1 + 9 * i)
        size = (n + 7) // 8 if kind == 0 else n * (8 if kind == 9 else kind)
        part = np.frombuffer(data, np.uint8, size, at)
        at += size
        if kind == 0:
            out.append(np.unpackbits(part, count=n).astype(bool))
        elif kind == 9:
            out.append(np.ascontiguousarray(part.reshape(8, n).T).view("<f8").ravel())
        else:
            wide = np.zeros((n, 8), np.uint8)
            wide[:, :kind] = part.reshape(kind, n).T
            out.append(wide.view("<i8").ravel())
    return out


def steps(a: np.ndarray) -> np.ndarray:
    """Differences of a rising array; ``np.cumsum`` gives it back."""
    return np.diff(a, prepend=0)


def good_turing(n: np.ndarray, k: int = K) -> np.ndarray:
    """Discounts d[0..k] from counts of counts n[1..k+1]: between 0 and 1, and no smaller for a
    larger count. Where the counts of counts as they are do not give that (few n-grams, or
    many texts that occur just so often), a line through their logarithms stands for them; where
    that does not either, half a count is taken off."""
    r = np.arange(1, k + 2, dtype=float)
    own = n[1 : k + 2].astype(float)
    some = own > 0
    tries = [own]
    if some.sum() > 1:
        slope, level = np.polyfit(np.log(r[some]), np.log(own[some]), 1)
        tries.append(np.exp(level) * r**slope)
    for c in tries:
        if c.all() and (k + 1) * c[k] < c[0]:
            tail = (k + 1) * c[k] / c[0]
            d = (r[1:] * c[1:] / (r[:-1] * c[:-1]) - tail) / (1 - tail)
            if (d > 0).all() and (d < 1).all() and (np.diff(d) >= 0).all():
                return np.append(1.0, d)
    return np.append(1.0, (r[:-1] - 0.5) / r[:-1])


@dataclass
class Unigrams:
    """What is known of all training tokens; the size does not depend on the corpus."""

    n: int
    types: int
    discounts: np.ndarray
    scale: float = 1.0  # below 1 where one more, unknown, occurrence is counted

    def probability(self, c: np.ndarray, unknown: float) -> np.ndarray:
        d = np.where(c <= K, self.discounts[np.minimum(c, K)], 1.0)
        return np.where(c > 0, d * c * self.scale / max(1, self.n), unknown)


def training(id_col: Column, modulus: int = 7, out: int = 2) -> Column:
    return F.coalesce(F.pmod(F.crc32(id_col.cast("string").cast("binary")), F.lit(modulus)) != out, F.lit(True))


STAGE = pa.schema([("block", pa.int64()), ("kind", pa.int32()), ("tokens", pa.int64()), ("texts", pa.int64()), ("words", pa.int64()), ("body", pa.binary())])
STAGE_DDL = "block long, kind int, tokens long, texts long, words long, body binary"


def stage_blocks(docs: DataFrame, id_col: str, text_col: str, is_train: Column, block_tokens: int) -> tuple[DataFrame, str]:
    """Two rows for each block: its texts as local word numbers (by rising hash), and what the numbers
    stand for, hashes and training counts."""

    def make(batches):
        task, number = TaskContext.get().partitionId(), 0
        held: list = []
        size = 0

        def emit():
            nonlocal number, held, size
            ids = np.array([i or 0 for p in held for i in p[0]], np.int64)
            nulls = np.array([i is None for p in held for i in p[0]], bool)
            train = np.concatenate([p[1] for p in held]).astype(bool)
            w, sizes = np.concatenate([p[2] for p in held]), np.concatenate([p[3] for p in held])
            hashes, local = np.unique(np.append(w, END), return_inverse=True)
            trained = np.bincount(local[:-1], weights=np.repeat(train, sizes), minlength=len(hashes)).astype(np.int64)
            trained[local[-1]] += train.sum()
            block = task << 32 | number
            rows = [
                (block, BASE, len(w) + len(ids), int(train.sum()), len(hashes), pack(ids.view(np.uint64), nulls, sizes, train, local, np.array([len(hashes)]))),
                (block, WORDS, 0, 0, 0, pack_words(hashes, trained)),
            ]
            number, held, size = number + 1, [], 0
            return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows, strict=True), STAGE.types, strict=True)], schema=STAGE)

        for batch in batches:
            for part in slices(batch, max_bytes=2 << 20):
                w, at = word_hashes(part.column("text"))
                held.append((part.column("doc_id").to_pylist(), np.asarray(part.column("train")), w, np.diff(at)))
                size += len(w) + part.num_rows
                if size >= block_tokens:
                    yield emit()
                    trim()
        if held:
            yield emit()

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), is_train.cast("int").alias("train"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return staged_at(rows.mapInArrow(make, STAGE_DDL), "katz-blocks", ["kind"])


def pack_words(hashes: np.ndarray, trained: np.ndarray) -> bytes:
    return len(hashes).to_bytes(8, "little") + hashes.astype("<u8").tobytes() + pack(trained)


def unpack_words(body: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = int.from_bytes(body[:8], "little")
    return np.frombuffer(body, "<u8", n, 8), unpack(body[8 + 8 * n :])[0]


class Block:
    """A staged block: its texts, and a token's word and place in its text."""

    def __init__(self, body: bytes):
        self.ids, self.nulls, self.sizes, self.train, local, n = unpack(body)
        self.words = int(n[0])
        docs = len(self.sizes)
        ends = np.cumsum(self.sizes + 1)
        self.start = ends - self.sizes - 1
        self.word = np.full(len(local) - 1 + docs, local[-1])  # the words, and an end for each text
        inner = np.ones(len(self.word), bool)
        inner[ends - 1] = False
        self.word[inner] = local[:-1]
        self.doc = np.repeat(np.arange(docs), self.sizes + 1)
        self.at = np.arange(len(self.word)) - self.start[self.doc]
        self.trained = self.train[self.doc]


class Level:
    """What a block knows of its distinct n-grams of one length; ``place`` is each token's (-1: none).

    ``c`` counts, ``shared`` whether other blocks have it too, ``number`` its number if shared and
    seen, ``p`` its probability if seen; ``low`` are the integers that ``p`` follows from.
    """

    place: np.ndarray
    c: np.ndarray
    shared: np.ndarray
    number: np.ndarray
    p: np.ndarray
    low: list[np.ndarray]


@dataclass
class Facts:
    """What all blocks need to know of a level that is done; the size grows with the buckets only."""

    buckets: int
    hot_from: float
    offsets: np.ndarray | None = None
    discounts: np.ndarray | None = None
    uni: Unigrams | None = None
    unknown: float = 1.0
    texts: int = 0
    hot: tuple | None = None  # numbers of split histories, rising; few, many, mass

    def probability(self, low: list[np.ndarray]) -> np.ndarray:
        """The probability of seen n-grams from the integers that go along with them."""
        if self.uni is not None:
            return self.uni.probability(low[0], 0.0)
        return np.where(low[0] <= K, self.discounts[np.minimum(low[0], K)], 1.0) * low[0] / np.maximum(1, low[1])


def distinct(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(a place of each distinct key, by rising key; which of them each key is)."""
    order = np.argsort(keys)
    own = keys[order]
    first = np.ones(len(own), bool)
    first[1:] = own[1:] != own[:-1]
    inverse = np.empty(len(own), np.int64)
    inverse[order] = np.cumsum(first) - 1
    return order[first], inverse


def spans(values: np.ndarray):
    """(value, from, to) of the runs of a sorted array."""
    if len(values):
        cut = np.concatenate(([0], np.flatnonzero(values[1:] != values[:-1]) + 1, [len(values)]))
        for lo, hi in zip(cut[:-1], cut[1:], strict=True):
            yield int(values[lo]), lo, hi


def level_one(block: Block, answers: list[tuple[int, bytes]], facts: Facts) -> Level:
    """Words; the start mark comes after them, as a history only. Buckets are ranges of hashes, so
    their answers, one after the other, are in the order of the local numbers."""
    counts, shared, numbers = [], [], []
    for bucket, body in answers:
        c, both, rank = unpack(body)
        own = np.full(len(c), -1)
        own[both & (c > 0)] = np.cumsum(rank) + facts.offsets[bucket]
        counts.append(c)
        shared.append(both)
        numbers.append(own)
    got = Level()
    got.c = np.append(np.concatenate(counts), facts.texts)
    got.shared = np.append(np.concatenate(shared), True)
    got.number = block.numbers = np.append(np.concatenate(numbers), START)
    got.place = block.word
    got.low = [got.c]
    got.p = facts.uni.probability(got.c, facts.unknown)
    return got


def climb(body: bytes, answers: list[list[tuple[int, bytes]]], done: tuple[Facts, ...], order: int) -> tuple[Block, Level, Level, np.ndarray]:
    """A block with its first and its last answered level, and the probability of each token by then."""
    block = Block(body)
    first = level = level_one(block, answers[0], done[0])
    p = level.p[block.word]
    for n, facts in enumerate(done[1:], 2):
        level, p = Plan(block, level, n, facts).settle(answers[n - 1], facts, p, n == order)
    return block, first, level, p


class Plan:
    """The distinct n-grams of length ``n`` of a block, and what of them it asks whom for."""

    def __init__(self, block: Block, below: Level, n: int, facts: Facts):
        size = len(below.c)
        tokens = np.flatnonzero(block.at >= n - 2)
        if n == 2:
            history = np.where(block.at[tokens] > 0, block.word[tokens - 1], size - 1)
        else:
            history = below.place[tokens - 1]
        one, inverse = distinct(history * block.words + block.word[tokens])
        self.h = history[one]
        one = tokens[one]
        self.s = below.place[one]  # the n-gram without its first word
        self.trained = np.bincount(inverse, weights=block.trained[tokens], minlength=len(one)).astype(np.int64)
        self.place = np.full(len(block.word), -1)
        self.place[tokens] = inverse
        self.history = np.full(len(block.word), -1)
        self.history[tokens] = history
        del inverse
        alive = below.c[self.h] > 0
        common, ends_seen = below.shared[self.h], below.c[self.s] > 0
        ends_common = below.shared[self.s]
        self.local = alive & (~common | ends_seen & ~ends_common)
        self.ask = np.flatnonzero(alive & common & ends_seen & ends_common)
        self.below, self.size = below, size
        # histories that other blocks have too, by number, each with its home bucket
        self.known = np.zeros(size, bool)
        self.known[self.h[alive & common]] = True
        self.hists = np.flatnonzero(self.known)
        self.hists = self.hists[np.argsort(below.number[self.hists])]
        number = below.number[self.hists].astype(np.uint64)
        rank = np.full(size, -1)
        rank[self.hists] = np.arange(len(self.hists))
        home = mix(number + np.uint64(1))
        self.parts = np.maximum(1, np.ceil(below.c[self.hists] / max(1.0, facts.hot_from))).astype(np.int64)
        # keys: (bucket, history) pairs are entries; a split history has one in each of its parts' buckets
        r = rank[self.h[self.ask]]
        word = block.numbers[block.word[one[self.ask]]]
        bucket = home[r]
        split = self.parts[r] > 1
        if split.any():
            bucket[split] = mix(bucket[split] + np.uint64(1) + mix(word[split].astype(np.uint64)) % self.parts[r[split]].astype(np.uint64))
        width, buckets = max(1, len(self.hists)), np.uint64(facts.buckets)
        own = (bucket % buckets).astype(np.int64) * width + r
        self.homes = (home % buckets).astype(np.int64) * width + np.arange(len(self.hists))
        self.entries = np.sort(self.homes) if not split.any() else np.unique(np.concatenate([self.homes, own[split]]))
        # the n-grams of a history lie together, their words by rising number; so only runs change places
        opens = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1]))) if len(own) else np.empty(0, np.int64)
        length = np.diff(np.append(opens, len(own)))
        entry = np.searchsorted(self.entries, own[opens])
        turn = np.argsort(entry, kind="stable")
        ends = np.cumsum(length[turn])
        order = np.repeat(opens[turn] - (ends - length[turn]), length[turn]) + np.arange(len(own))
        self.ask, self.words = self.ask[order], word[order]
        self.run = np.bincount(entry, weights=length, minlength=len(self.entries)).astype(np.int64)
        self.entry_hist = self.entries % width
        self.entry_bucket = self.entries // width
        self.is_home = np.zeros(len(self.entries), bool)
        self.is_home[np.searchsorted(self.entries, self.homes)] = True
        # only a text that the counts leave out can have an n-gram that they do not know
        self.open = np.zeros(size, bool)
        self.open[self.history[(self.place >= 0) & ~block.trained]] = True
        self.need = self.is_home & self.open[self.hists[self.entry_hist]]

    def sums(self, of: np.ndarray, c: np.ndarray, p: np.ndarray, size: int):
        """(few, many, mass): the statistics of histories ``of`` over n-grams of counts c."""
        few = np.stack([np.bincount(of[c == r], minlength=size) for r in range(1, K + 1)])
        return few, np.bincount(of, weights=np.where(c > K, c, 0), minlength=size).astype(np.int64), np.bincount(of, weights=p, minlength=size).astype(float)

    def messages(self):
        """(bucket, body): entries, then keys; and the block's own counts of counts."""
        seen = np.flatnonzero(self.local & (self.trained > 0) & self.below.shared[self.h])
        rank = np.full(self.size, -1)
        rank[self.hists] = np.arange(len(self.hists))
        few, many, mass = self.sums(rank[self.h[seen]], self.trained[seen], self.below.p[self.s[seen]], len(self.hists))
        some = (few.sum(0) > 0) | (many > 0)
        starts = np.concatenate(([0], np.cumsum(self.run)))
        low = [x[self.s[self.ask]] for x in self.below.low]
        numbers = self.below.number[self.hists]
        for bucket, lo, hi in spans(self.entry_bucket):
            e = self.entry_hist[lo:hi]
            with_sums = self.is_home[lo:hi] & some[e]
            keys = slice(starts[lo], starts[hi])
            own = e[with_sums]
            trained = self.trained[self.ask[keys]]
            yield bucket, pack(steps(numbers[e]), self.run[lo:hi], self.need[lo:hi], self.parts[e] > 1, with_sums, *few[:, own], many[own], mass[own], self.words[keys], trained, *[x[keys][trained > 0] for x in low])

    def cofc(self) -> np.ndarray:
        return _counts_of_counts(self.trained[self.local])

    def settle(self, answers: list[tuple[int, bytes]], facts: Facts, before: np.ndarray, last: bool) -> tuple[Level, np.ndarray]:
        """The level, and the probability of each token after it."""
        below, size = self.below, self.size
        got = Level()
        got.place = self.place
        got.c = np.where(self.local, self.trained, 0)
        got.shared, got.number = np.zeros(len(self.h), bool), np.full(len(self.h), -1)
        # statistics of histories: of local ones from here, of others from the answers
        seen = np.flatnonzero(self.local & (self.trained > 0) & ~below.shared[self.h])
        full = below.c > 0
        full[self.h[seen[self.trained[seen] <= K]]] = False
        seen = seen[self.open[self.h[seen]]]
        few, many, mass = self.sums(self.h[seen], self.trained[seen], below.p[self.s[seen]], size)
        told = dict(answers)
        starts = np.concatenate(([0], np.cumsum(self.run)))
        for bucket, lo, hi in spans(self.entry_bucket):
            c, both, rank, none_left, *stats = unpack(told[bucket])
            own = self.ask[starts[lo] : starts[hi]]
            got.c[own] = c
            got.shared[own] = both
            if not last:
                numbers = np.full(len(c), -1)
                numbers[both & (c > 0)] = np.cumsum(rank) + facts.offsets[bucket]
                got.number[own] = numbers
            hist = self.hists[self.entry_hist[lo:hi]]
            full[hist] = none_left
            hist = hist[self.need[lo:hi]]
            few[:, hist], many[hist], mass[hist] = np.stack(stats[:K]), stats[K], stats[K + 1]
        split = np.flatnonzero(self.parts > 1)
        if len(split):
            i = np.searchsorted(facts.hot[0], below.number[self.hists[split]])
            hist = self.hists[split]
            few[:, hist], many[hist], mass[hist] = facts.hot[1][:, i], facts.hot[2][i], facts.hot[3][i]
            full[hist] = (facts.hot[1][:, i].sum(0) == 0) & (facts.hot[2][i] > 0)
        whole = below.c + full  # what the counts after a history are divided by
        got.low = [got.c, whole[self.h]]
        got.p = np.where(got.c > 0, facts.probability(got.low), 0.0)
        now = before.copy()
        t = np.flatnonzero(self.place >= 0)
        p = got.p[self.place[t]]
        hit = p > 0
        now[t[hit]] = p[hit]
        t = t[~hit]
        hist = self.history[t]
        t, hist = t[below.c[hist] > 0], hist[below.c[hist] > 0]
        kept = sum(facts.discounts[r] * r * few[r - 1, hist] for r in range(1, K + 1)) + many[hist]
        now[t] *= (1 - kept / whole[hist]) / np.maximum(1e-300, 1 - mass[hist])
        return got, now


def _counts_of_counts(c: np.ndarray) -> np.ndarray:
    return np.bincount(np.minimum(c[c > 0], K + 2), minlength=K + 3)[: K + 2].astype(np.int64)


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows, strict=True), MOVED_SCHEMA.types, strict=True)], schema=MOVED_SCHEMA)


def _by_bucket(asked: DataFrame, buckets: int, merge) -> DataFrame:
    """Whole buckets to ``merge(bucket, messages, blocks' totals)``; a bucket's messages come together."""

    def run(batches):
        now, messages, totals = None, [], []
        for batch in batches:
            for row in batch.to_pylist():
                if now is not None and row["bucket"] != now:
                    yield from merge(now, messages, totals)
                    messages, totals = [], []
                    trim()
                now = row["bucket"]
                (totals if row["kind"] == TOTALS else messages).append((row["block"], row["body"]))
        if now is not None:
            yield from merge(now, messages, totals)
            trim()

    return asked.repartition(buckets, "bucket").sortWithinPartitions("bucket", "block").mapInArrow(run, MOVED)


def _merge_words(bucket: int, messages: list, totals: list):
    parts = [unpack_words(body) for _, body in messages]
    values, inverse, asked = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True, return_counts=True)
    c = np.bincount(inverse, weights=np.concatenate([p[1] for p in parts]), minlength=len(values)).astype(np.int64)
    both, seen = asked > 1, c > 0
    numbered = both & seen
    rank = np.cumsum(numbered) - 1
    yield _rows([(bucket, -1, TABLE, pack_words(values[seen], c[seen])), (bucket, -1, TOTALS, pack(np.array([c.sum(), seen.sum(), numbered.sum()]), _counts_of_counts(c)))])
    at = 0
    for (block, _), (own, _) in zip(messages, parts, strict=True):
        i = inverse[at : at + len(own)]
        at += len(own)
        yield _rows([(bucket, block, ANSWER, pack(c[i], both[i], steps(rank[i[numbered[i]]])))])


def _merge_grams(below: Facts, last: bool):
    lows = 1 if below.uni is not None else 2

    def merge(bucket: int, messages: list, totals: list):
        cofc = sum((unpack(body)[0] for _, body in totals), np.zeros(K + 2, np.int64))
        told = [unpack(body) for _, body in messages]
        cat = lambda j: np.concatenate([m[j] for m in told]) if told else np.empty(0, np.int64)
        entry = np.concatenate([np.cumsum(m[0]) for m in told]) if told else np.empty(0, np.int64)
        hists, inv = np.unique(entry, return_inverse=True)
        size = len(hists)
        word, trained = cat(K + 7), cat(K + 8)
        h = np.repeat(inv, cat(1))
        order = np.argsort(h * (int(word.max()) + 1 if len(word) else 1) + word)
        first = np.ones(len(order), bool)
        first[1:] = (h[order[1:]] != h[order[:-1]]) | (word[order[1:]] != word[order[:-1]])
        start = np.flatnonzero(first)
        place = np.empty(len(order), np.int64)
        place[order] = np.cumsum(first) - 1
        c = np.add.reduceat(trained[order], start) if len(start) else np.empty(0, np.int64)
        both = np.diff(np.append(start, len(order))) > 1
        of, one = h[order[start]], order[start]
        seen = c > 0
        low = np.zeros((lows, len(order)), np.int64)
        low[:, trained > 0] = [cat(K + 9 + j) for j in range(lows)]  # blocks send it with what they count
        low = np.maximum.reduceat(low[:, order], start, axis=1) if len(start) else low
        p = np.where(seen, below.probability(list(low)), 0.0)
        few = np.stack([np.bincount(of[c == r], minlength=size) for r in range(1, K + 1)])
        many = np.bincount(of, weights=np.where(c > K, c, 0), minlength=size).astype(np.int64)
        mass = np.bincount(of, weights=p, minlength=size).astype(float)
        summed = inv[cat(4).astype(bool)]  # what the blocks add of their own n-grams
        add = lambda j: np.bincount(summed, weights=cat(j), minlength=size)
        few += np.stack([add(5 + r) for r in range(K)]).astype(np.int64)
        many += add(5 + K).astype(np.int64)
        mass = mass + add(6 + K)
        cofc = cofc + _counts_of_counts(c)
        none_left = (few.sum(0) == 0) & (many > 0)
        hot = np.unique(inv[cat(3).astype(bool)])
        numbered = both & seen
        rank = np.cumsum(numbered) - 1
        kept = np.flatnonzero(numbered)  # n-grams of one block are counted there
        table = pack(steps(hists), np.bincount(of[kept], minlength=size), word[one[kept]], c[kept])
        yield _rows([(bucket, -1, TABLE, table), (bucket, -1, TOTALS, pack(np.array([0, 0, numbered.sum()]), cofc, hists[hot], *few[:, hot], many[hot], mass[hot]))])
        at = at_entry = 0
        for (block, _), m in zip(messages, told, strict=True):
            i, e = place[at : at + len(m[K + 7])], inv[at_entry : at_entry + len(m[0])]
            at, at_entry = at + len(i), at_entry + len(e)
            need = e[m[2]]
            ranks = steps(rank[i[numbered[i]]]) if not last else np.empty(0, np.int64)
            yield _rows([(bucket, block, ANSWER, pack(c[i], both[i], ranks, none_left[e], *few[:, need], many[need], mass[need]))])

    return merge


def _with_answers(base: DataFrame, told: list[DataFrame], n_blocks: int, work, ddl: str) -> DataFrame:
    """``work(body of a block, [answers of each level])`` for every block, in one exchange."""
    rows = base.select("block", F.lit(0).alias("level"), F.lit(-1).alias("bucket"), "body")
    for level, t in enumerate(told, 1):
        rows = rows.unionByName(t.where(f"kind = {ANSWER}").select("block", F.lit(level).alias("level"), "bucket", "body"))
    dealt = rows.repartition(max(1, -(-n_blocks // BLOCKS_A_TASK)), "block").sortWithinPartitions("block", "level", "bucket")
    levels = len(told)

    def run(batches):
        now, body, answers = None, None, []
        for batch in batches:
            for i in range(batch.num_rows):
                block, level, bucket, part = (batch.column(c)[i].as_py() for c in range(4))
                if level == 0:
                    if body is not None:
                        yield from work(now, body, answers)
                        trim()
                    now, body, answers = block, part, [[] for _ in range(levels)]
                else:
                    answers[level - 1].append((bucket, part))
        if body is not None:
            yield from work(now, body, answers)
            trim()

    return dealt.mapInArrow(run, ddl)


def _release(spark: SparkSession) -> None:
    """Let Spark's cleaner drop the shuffle files of finished jobs; only disk depends on it."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", modulus: int = 7, out: int = 2, order: int = ORDER, block_tokens: int = BLOCK_TOKENS, bucket_keys: int = BUCKET_KEYS) -> tuple[DataFrame, dict[str, str]]:
    """(scores, folders of the count tables). One row per row of ``docs``: doc_id, held_out,
    n_tokens, n_known, train_tokens, base_score, score. ``order`` is the longest n-gram, 1 at least."""
    if order < 1:
        raise ValueError("a model has order 1 at least")
    spark = docs.sparkSession
    ship(spark)
    rows, rows_path = stage_blocks(docs, id_col, text_col, training(F.col(id_col), modulus, out), block_tokens)
    base = rows.where(f"kind = {BASE}")
    facts = base.agg(F.sum("tokens"), F.sum("words"), F.count("*"), F.sum("texts")).first()
    total, words, n_blocks = facts[0] or 0, facts[1] or 0, facts[2]
    done: list[Facts] = []
    told: list[DataFrame] = []
    paths = {"blocks": rows_path}

    def totals(df: DataFrame) -> list:
        return sorted((r.bucket, unpack(r.body)) for r in df.where(f"kind = {TOTALS}").select("bucket", "body").collect())  # a row per bucket

    def offsets(parts: list, buckets: int, first: int) -> np.ndarray:
        counts = np.zeros(buckets + 1, np.int64)
        for bucket, body in parts:
            counts[bucket + 1] = body[0][2]
        return np.cumsum(counts) + first

    def ask_words(batches):
        for batch in batches:
            for block, body in zip(batch.column("block").to_pylist(), batch.column("body"), strict=True):
                hashes, trained = unpack_words(body.as_py())
                for bucket, lo, hi in spans((hashes >> np.uint64(32)) * np.uint64(one.buckets) >> np.uint64(32)):
                    yield _rows([(bucket, block, ANSWER, pack_words(hashes[lo:hi], trained[lo:hi]))])

    one = Facts(max(1, -(-words // (2 * bucket_keys))), float("inf"), texts=facts[3] or 0)
    asked = rows.where(f"kind = {WORDS}").select("block", "body").mapInArrow(ask_words, MOVED)
    answered, paths["1"] = staged_at(_by_bucket(asked, one.buckets, _merge_words), "katz-1")
    parts = totals(answered)
    n, types = (sum(int(body[0][j]) for _, body in parts) for j in range(2))
    cofc = sum((body[1] for _, body in parts), np.zeros(K + 2, np.int64))
    one.offsets = offsets(parts, one.buckets, START + 1)
    one.uni = uni = Unigrams(n, types, good_turing(cofc))
    few = sum(uni.discounts[r] * r * int(cofc[r]) for r in range(1, K + 1))
    many = n - sum(r * int(cofc[r]) for r in range(1, K + 1))
    one.unknown = 1 - (few + many) / n if n else 1.0
    if n and one.unknown <= 1e-12:  # no count up to K: one more occurrence, of the unknown word
        one.unknown, uni.scale = 1 / (n + 1), n / (n + 1)
    done.append(one)
    told.append(answered)
    drop_path(spark, f"{rows_path}/kind={WORDS}")
    _release(spark)

    for level in range(2, order + 1):
        buckets = max(1, -(-total // bucket_keys))
        now = Facts(buckets, n / (2 * buckets))
        below = tuple(done)

        def ask(block, body, answers, level=level, now=now, below=below):
            own, _, last, _ = climb(body, answers, below, order)
            plan = Plan(own, last, level, now)
            yield _rows([(block % now.buckets, block, TOTALS, pack(plan.cofc()))])
            for bucket, message in plan.messages():
                yield _rows([(bucket, block, ANSWER, message)])

        asked = _with_answers(base, told, n_blocks, ask, MOVED)
        answered, paths[str(level)] = staged_at(_by_bucket(asked, buckets, _merge_grams(below[-1], level == order)), f"katz-{level}")
        parts = totals(answered)
        now.discounts = good_turing(sum((body[1] for _, body in parts), np.zeros(K + 2, np.int64)))
        now.offsets = offsets(parts, buckets, 1)
        now.hot = _hot(parts)
        done.append(now)
        told.append(answered)
        _release(spark)

    fields = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])
    finished = tuple(done)

    def evaluate(_, body, answers):
        block, words, _, p = climb(body, answers, finished, order)
        add = lambda x: np.add.reduceat(x, block.start)
        c = words.c[block.word]
        base_score = add(np.log10((c + 1) / (n + types + 1)))
        ids = pa.array(block.ids, mask=block.nulls)
        yield pa.RecordBatch.from_arrays([ids, pa.array(~block.train), pa.array(block.sizes + 1), pa.array(add((c > 0).astype(np.int64))), pa.array(np.full(len(block.ids), n)), pa.array(base_score), pa.array(add(np.log10(p)))], schema=fields)

    ddl = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    return _with_answers(base, told, n_blocks, evaluate, ddl), paths


def _hot(parts: list) -> tuple:
    """The summed statistics of split histories, by number; at most two per bucket."""
    cat = lambda j: np.concatenate([body[j] for _, body in parts]) if parts else np.empty(0, np.int64)
    names, inv = np.unique(cat(2), return_inverse=True)
    add = lambda j: np.bincount(inv, weights=cat(j), minlength=len(names))
    return names, np.stack([add(3 + r) for r in range(K)]).astype(np.int64), add(3 + K).astype(np.int64), add(4 + K)


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(spark.read.parquet(f"{sf_dir}/documents.parquet"))[0]
