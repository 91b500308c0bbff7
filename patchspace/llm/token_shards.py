"""Token-ID output: documents as sorted-string-table shards, and reading them back.

``write_shards`` deals documents by ranges of their identifier, so shard order is identifier
order; each task encodes its texts and streams them into one file of the shared folder. What a
task wrote counts only through its row in the returned manifest, so a task that is run again
leaves at most an unused file. ``read_shards`` returns one row per document from the files.

Null text is an empty text (its ids are the end id alone). Null identifiers are kept, before
all others. Equal identifiers are kept as separate entries, ordered by a hash of their text.
An empty table gives no shard and no row. Other columns are ignored, whatever their names.
"""

from __future__ import annotations

import uuid
import zlib
from bisect import bisect_left
from collections import OrderedDict

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.shared import new_path, open_fs, ship, staged
from patchspace.llm.sstable import Reader, Writer, encode_key
from patchspace.llm.tokens import default_tokenizer, encoder, slices

END_ID = 1
MANIFEST = "shard int, path string, n_docs long, n_tokens long, min_id long, max_id long, bytes long"


def write_shards(docs: DataFrame, folder: str, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None, end_id: int = END_ID, block_bytes: int = 1 << 16) -> DataFrame:
    """Write the shards below ``folder``; returns the manifest (one small row per shard)."""
    ship(docs.sparkSession)
    path = tokenizer or default_tokenizer()

    def write(batches):
        enc, shard = encoder(path), TaskContext.get().partitionId()
        writer = sink = None
        n_tokens, low, high = 0, None, None
        for batch in batches:
            for part in slices(batch, max_bytes=8 << 20):
                ids, at = enc.batch(part.column("text"))
                for i, key in enumerate(part.column("doc_id").to_pylist()):
                    if writer is None:
                        fs, root = open_fs(folder)
                        fs.create_dir(root, recursive=True)
                        name = f"shard-{shard:06d}-{uuid.uuid4().hex[:8]}.sst"
                        sink = fs.open_output_stream(f"{root}/{name}")
                        writer = Writer(sink, block_bytes)
                        low = key
                    own = np.append(ids[at[i] : at[i + 1]], np.uint32(end_id))
                    writer.add(encode_key(key), own)
                    n_tokens += len(own)
                    high = key
        if writer is not None:
            size = writer.finish()
            sink.close()
            yield pa.RecordBatch.from_pylist([{"shard": shard, "path": f"{folder}/{name}", "n_docs": writer.n, "n_tokens": n_tokens, "min_id": low, "max_id": high, "bytes": size}], schema=_manifest_schema())

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    order = ["doc_id", F.xxhash64("text")]
    dealt = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    return staged(dealt.mapInArrow(write, MANIFEST), "shard-manifest")


def _manifest_schema() -> pa.Schema:
    return pa.schema([("shard", pa.int32()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("min_id", pa.int64()), ("max_id", pa.int64()), ("bytes", pa.int64())])


def _by_shard(spark: SparkSession, manifest: DataFrame) -> DataFrame:
    """The manifest with each shard's first token position, dealt one shard to a task.

    Collects one row per shard file, so what reaches the driver is the list of files.
    """
    rows = sorted(manifest.collect(), key=lambda r: r.shard)
    out, start = [], 0
    for r in rows:
        out.append((r.path, start))
        start += r.n_tokens
    schema = "path string, first long"
    if not out:
        return spark.createDataFrame([], schema)
    return spark.createDataFrame(spark.sparkContext.parallelize(out, len(out)), schema)


def read_shards(manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids (uint32 little-endian bytes), ids_crc32, read from the files."""
    return _scan(manifest, True)


def _scan(manifest: DataFrame, with_ids: bool) -> DataFrame:
    spark = manifest.sparkSession
    ship(spark)

    def read(batches):
        for batch in batches:
            for path, start in zip(batch.column("path").to_pylist(), batch.column("first").to_pylist(), strict=True):
                fs, name = open_fs(path)
                rows, size = [], 0
                with fs.open_input_file(name) as f:
                    for key, ids in Reader(f).scan():
                        raw = ids.astype("<u4").tobytes()
                        row = {"doc_id": key, "start": start, "n_tokens": len(ids), "ids_crc32": zlib.crc32(raw)}
                        if with_ids:
                            row["ids"] = raw
                            size += len(raw)
                        rows.append(row)
                        start += len(ids)
                        if len(rows) >= 4096 or size > 4 << 20:
                            yield pa.RecordBatch.from_pylist(rows, schema=arrow)
                            rows, size = [], 0
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=arrow)

    fields = [("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())]
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long"
    if with_ids:
        fields.append(("ids", pa.binary()))
        schema += ", ids binary"
    arrow = pa.schema(fields)
    return _by_shard(spark, manifest).mapInArrow(read, schema)


def lookup(manifest: DataFrame, wanted: DataFrame, id_col: str = "doc_id", open_shards: int = 8) -> DataFrame:
    """The ids of wanted identifiers: shards by bisection over key ranges, then filter, index and blocks.

    The range list of the shards is small (a row per file) and goes along as an expression.
    Requests are dealt and sorted by range, so a task needs neighbouring shards and keeps at most
    ``open_shards`` of them open.
    """
    spark = manifest.sparkSession
    ship(spark)
    rows = sorted(manifest.collect(), key=lambda r: r.shard)
    nulls = [r.path for r in rows if r.min_id is None]
    keyed = [(-(1 << 63) if r.min_id is None else r.min_id, r.max_id, r.path) for r in rows if r.max_id is not None]
    highs = [r[1] for r in keyed]

    def paths(x):
        if x is None:
            yield from nulls
            return
        at = bisect_left(highs, x)  # equal identifiers may lie in neighbouring shards
        while at < len(keyed) and keyed[at][0] <= x:
            yield keyed[at][2]
            at += 1

    def find(batches):
        opened: OrderedDict[str, tuple] = OrderedDict()
        for batch in batches:
            out = []
            for x in batch.column(0).to_pylist():
                for path in paths(x):
                    if path not in opened:
                        if len(opened) >= open_shards:
                            opened.popitem(last=False)[1][0].close()
                        fs, name = open_fs(path)
                        f = fs.open_input_file(name)
                        opened[path] = (f, Reader(f))
                    opened.move_to_end(path)
                    out += [{"doc_id": x, "ids": v.astype("<u4").tobytes(), "n_tokens": len(v)} for v in opened[path][1].get_all(x)]
            yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("doc_id", pa.int64()), ("ids", pa.binary()), ("n_tokens", pa.int64())]))
        for f, _ in opened.values():
            f.close()

    keys = wanted.select(F.col(id_col).cast("long").alias("doc_id")).distinct()
    return keys.repartitionByRange("doc_id").sortWithinPartitions("doc_id").mapInArrow(find, "doc_id long, ids binary, n_tokens long")


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    manifest = write_shards(docs, new_path(spark, "token-shards"))
    return _scan(manifest, False).select("doc_id", "start", "n_tokens", "ids_crc32")
