"""Bounded-space online packing of token sequences into windows of a fixed capacity.

Each task keeps at most ``open_windows`` windows. A document longer than the capacity gives
full windows of its own; what remains goes to the open window it fits best. When none fits, the
fullest window is emitted: filled up with the head of the piece if more than ``max_slack``
tokens would stay unused, else as it is. The windows that a task leaves open are merged in
rounds of ``fan`` tasks, cutting pieces so that each group leaves one window at most, until one
group is left; rounds shrink the leftovers by ``fan`` and no task sees more than ``fan`` times
``open_windows`` windows.

Null text is an empty text: its only token is the end id. Null and repeated identifiers are
packed row by row like any other. An empty table gives no row. Other columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.shared import ship, staged
from patchspace.llm.tokens import default_tokenizer, encoder, slices

CAPACITY, END_ID = 4096, 2
FIELDS = [("done", pa.bool_()), ("task", pa.int64()), ("sequence_id", pa.int64()), ("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("offset", pa.int64()), ("sequence_tokens", pa.int64()), ("ids", pa.binary())]
DDL = "done boolean, task long, sequence_id long, doc_id long, start long, length long, ids_crc32 long, doc_tokens long, offset long, sequence_tokens long, ids binary"


class Packer:
    """Windows are lists of pieces (doc_id, start, ids, doc_tokens)."""

    def __init__(self, capacity: int = CAPACITY, open_windows: int | None = 64, max_slack: int = 32):
        self.capacity, self.open_windows, self.max_slack = capacity, open_windows, max_slack
        self.slack: list[tuple[int, int]] = []  # (free tokens, window number), ascending
        self.windows: dict[int, list] = {}
        self.closed: list[list] = []
        self.number = 0

    def add(self, doc_id, start: int, ids: np.ndarray, doc_tokens: int) -> None:
        whole = len(ids) - len(ids) % self.capacity
        for a in range(0, whole, self.capacity):
            self.closed.append([(doc_id, start + a, ids[a : a + self.capacity], doc_tokens)])
        if whole < len(ids):
            self._place(doc_id, start + whole, ids[whole:], doc_tokens)

    def _place(self, doc_id, start, ids, doc_tokens) -> None:
        i = bisect_left(self.slack, (len(ids), -1))
        if i < len(self.slack):
            free, w = self.slack.pop(i)
        elif self.open_windows is None or len(self.slack) < self.open_windows:
            free, w = self.capacity, self.number
            self.windows[w] = []
            self.number += 1
        else:
            free, w = self.slack.pop(0)  # the fullest
            window = self.windows.pop(w)
            if free > self.max_slack:
                window.append((doc_id, start, ids[:free], doc_tokens))
                start, ids = start + free, ids[free:]
            self.closed.append(window)
            self._place(doc_id, start, ids, doc_tokens)
            return
        self.windows[w].append((doc_id, start, ids, doc_tokens))
        if free == len(ids):
            self.closed.append(self.windows.pop(w))
        else:
            insort(self.slack, (free - len(ids), w))

    def take(self) -> list[list]:
        out, self.closed = self.closed, []
        return out

    def rest(self) -> list[list]:
        return [self.windows[w] for _, w in self.slack]


def _batch(windows: list[list], done: bool, task: int, first: int, keep_ids: bool) -> pa.RecordBatch:
    cols: list[list] = [[] for _ in FIELDS]
    for k, window in enumerate(windows):
        total, at = sum(len(p[2]) for p in window), 0
        for doc_id, start, ids, doc_tokens in window:
            raw = ids.astype("<u4").tobytes()
            for c, v in zip(cols, (done, task, first + k, doc_id, start, len(ids), zlib.crc32(raw), doc_tokens, at, total, raw if keep_ids else None), strict=True):
                c.append(v)
            at += len(ids)
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(cols, FIELDS, strict=True)], names=[n for n, _ in FIELDS])


def merge_windows(windows: list[list], capacity: int, max_slack: int, last: bool) -> tuple[list[list], list[list]]:
    """(emitted, left): best fit by falling size, then cuts; one window is left at most."""
    packer = Packer(capacity, None, max_slack)
    pieces = sorted((p for w in windows for p in w), key=lambda p: (-len(p[2]), p[0] is None, p[0] or 0, p[1]))
    for p in pieces:
        packer.add(*p)
    emitted, part = packer.take(), []
    used = 0
    for w in packer.rest():
        n = sum(len(p[2]) for p in w)
        if capacity - n <= max_slack:
            emitted.append(w)
            continue
        for doc_id, start, ids, doc_tokens in w:
            while len(ids):
                head = ids[: capacity - used]
                part.append((doc_id, start, head, doc_tokens))
                used += len(head)
                start, ids = start + len(head), ids[len(head) :]
                if used == capacity:
                    emitted.append(part)
                    part, used = [], 0
    left = [part] if part else []
    return (emitted + left, []) if last else (emitted, left)


def _merger(turn: int, last: bool, fan: int, capacity: int, max_slack: int):
    """The function of one merging round over the open windows of a group of tasks."""

    def merge(table: pa.Table) -> pa.Table:
        names = ("task", "sequence_id", "doc_id", "start", "ids", "doc_tokens", "offset")
        rows = zip(*(table.column(c).to_pylist() for c in names), strict=True)
        windows: dict[tuple, list] = {}
        for t, s, d, a, raw, n, _ in sorted(rows, key=lambda r: (r[0], r[1], r[6])):
            windows.setdefault((t, s), []).append((d, a, np.frombuffer(raw, "<u4"), n))
        group = min(windows)[0] // fan
        base = 1 << 62 | turn << 56 | group << 32
        emitted, rest = merge_windows(list(windows.values()), capacity, max_slack, last)
        return pa.Table.from_batches([_batch(emitted, True, group, base, False), _batch(rest, False, group, base + len(emitted), True)])

    return merge


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None, end_id: int = END_ID, capacity: int = CAPACITY, open_windows: int = 64, max_slack: int = 32, fan: int = 32) -> DataFrame:
    """One row per piece: where it lies in its document and in its sequence.

    ``padded_length`` is what the sequence takes: its own length if that is a power of two
    (no padding then), else the capacity.
    """
    spark = docs.sparkSession
    ship(spark)
    path = tokenizer or default_tokenizer()

    def first(batches):
        enc, task = encoder(path), TaskContext.get().partitionId()
        packer, n = Packer(capacity, open_windows, max_slack), task << 32
        for batch in batches:
            for part in slices(batch):
                ids, at = enc.batch(part.column("text"))
                for i, key in enumerate(part.column("doc_id").to_pylist()):
                    own = np.append(ids[at[i] : at[i + 1]], np.uint32(end_id))
                    packer.add(key, 0, own, len(own))
                windows = packer.take()
                if windows:
                    yield _batch(windows, True, task, n, False)
                    n += len(windows)
        left = packer.rest()
        if left:
            yield _batch(left, False, task, n, True)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    now = staged(rows.mapInArrow(first, DDL), "packed")
    found = [now.where("done")]
    left = now.where("NOT done")
    tasks = (left.agg(F.max("task")).first()[0] or 0) + 1
    turn = 0
    while True:
        turn += 1
        last = tasks <= fan

        merged = left.withColumn("group", F.expr(f"task div {fan}")).groupBy("group").applyInArrow(_merger(turn, last, fan, capacity, max_slack), DDL)
        now = staged(merged, "packed-merge")
        found.append(now.where("done"))
        if last:
            break
        left, tasks = now.where("NOT done"), (tasks + fan - 1) // fan
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    power = F.expr("bit_count(sequence_tokens) = 1")
    return out.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "sequence_tokens", F.when(power, F.col("sequence_tokens")).otherwise(F.lit(capacity).cast("long")).alias("padded_length"))


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
