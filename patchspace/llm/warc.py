"""WARC archives from a chunked record table, and back.

Writing: a row per page becomes one record. A record's payload is written in chunks of
``chunk_bytes`` into a gzip member of its own; memory holds one chunk, not the record's
archive form. Equal payloads of at least ``min_revisit`` bytes are written once: the page with
the smallest identifier is the response, the others are revisit records that name it.

Reading: archives are streamed; an inflating window of ``chunk_bytes`` turns each payload into
rows ``(record_id, chunk_no, n_chunk, data, sha256_so_far, total)``. The digest of a row covers
all chunks up to it, so the last row's is the payload's, and each record is checked against its
declared length and digest as it passes.

Files count only through the manifest (one row per file), so repeated tasks leave at most an
unused file. Null HTML is an empty payload; null urls give an empty target; null identifiers
stay responses; rows that repeat both identifier and payload are all responses or all revisits.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.llm.spread import spread_join
from patchspace.shared import new_path, open_fs, ship, staged

MIN_REVISIT, CHUNK = 100, 1 << 20
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2000-01-01T00:00:00Z"
MANIFEST = "path string, n_records long, bytes long"
CHUNKS = "page_id long, record_type string, refers_to long, declared_bytes long, declared_digest string, chunk_no int, n_chunk long, data binary, sha256_so_far string, total long"


def decide(pages: DataFrame, id_col: str = "page_id", payload_col: str = "html", min_revisit: int = MIN_REVISIT) -> DataFrame:
    """The pages as page_id, url, payload, digest, refers_to (null for a response).

    Grouping moves digests and identifiers only. Digests that occur once cannot be revisited, so
    the rest make a table (a row per repeated payload) that is joined on: while it is small Spark
    broadcasts it; beyond that payloads are shuffled once, and those of a frequent digest are dealt
    over many tasks.
    """
    payload = F.encode(F.coalesce(F.col(payload_col), F.lit("")), "UTF-8")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.coalesce(F.col("url"), F.lit("")).alias("url"), payload.alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    small = rows.where(F.octet_length("payload") >= min_revisit).select("page_id", "digest")
    firsts = staged(small.groupBy("digest").agg(F.min("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1"), "warc-firsts")
    total = firsts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    return spread_join(rows, firsts, "digest", total, F.xxhash64("page_id", "url"), "left").withColumn("refers_to", F.when(F.col("page_id") != F.col("refers_to"), F.col("refers_to")))


def _head(row: dict, n: int) -> bytes:
    kind = "revisit" if row["refers_to"] is not None else "response"
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'null' if row['page_id'] is None else row['page_id']}>", f"WARC-Target-URI: {row['url'].replace(chr(13), ' ').replace(chr(10), ' ')}", f"WARC-Date: {DATE}", f"WARC-Payload-Digest: sha256:{row['digest']}", f"X-Payload-Length: {n}"]
    if kind == "revisit":
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{row['refers_to']}>"]
    lines += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {0 if kind == 'revisit' else n}"]
    return ("\r\n".join(lines) + "\r\n\r\n").encode()


def write_warc(decided: DataFrame, folder: str, chunk_bytes: int = CHUNK, level: int = 4) -> DataFrame:
    """Write the archives below ``folder``, a file per task; returns the manifest."""
    ship(decided.sparkSession)

    def write(batches):
        sink, n, size = None, 0, 0
        for batch in batches:
            payloads = batch.column("payload")
            for i, row in enumerate(batch.drop_columns(["payload"]).to_pylist()):
                if sink is None:
                    fs, root = open_fs(folder)
                    fs.create_dir(root, recursive=True)
                    name = f"part-{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex[:8]}.warc.gz"
                    sink = fs.open_output_stream(f"{root}/{name}", compression=None)
                payload = payloads[i].as_buffer()
                pack = zlib.compressobj(level, zlib.DEFLATED, 31)
                parts = [pack.compress(_head(row, payload.size))]
                for a in range(0, payload.size if row["refers_to"] is None else 0, chunk_bytes):
                    parts.append(pack.compress(payload.slice(a, min(chunk_bytes, payload.size - a))))
                    if len(parts) > 4:
                        size += sum(sink.write(p) or len(p) for p in parts)
                        parts = []
                parts += [pack.compress(b"\r\n\r\n"), pack.flush()]
                for p in parts:
                    sink.write(p)
                    size += len(p)
                n += 1
        if sink is not None:
            sink.close()
            yield pa.RecordBatch.from_pylist([{"path": f"{folder}/{name}", "n_records": n, "bytes": size}], schema=pa.schema([("path", pa.string()), ("n_records", pa.int64()), ("bytes", pa.int64())]))

    rows = decided.select("page_id", "url", "payload", "digest", "refers_to")
    return staged(rows.mapInArrow(write, MANIFEST), "warc-manifest")


class Stream:
    """Bytes of a file of gzip members, inflated as they are asked for."""

    def __init__(self, source, window: int):
        self.source, self.window = source, window
        self.pending, self.ready, self.unpack = b"", bytearray(), zlib.decompressobj(31)

    def fill(self) -> bool:
        """Inflate some more; False at the end of the file."""
        if not self.pending:
            self.pending = self.source.read(1 << 18)
            if not self.pending:
                return False
        if self.unpack.eof:
            self.unpack = zlib.decompressobj(31)
        self.ready += self.unpack.decompress(self.pending, self.window)
        self.pending = self.unpack.unused_data if self.unpack.eof else self.unpack.unconsumed_tail
        return True

    def take(self, n: int) -> bytes:
        """Between 1 and n bytes, or none at the end."""
        while not self.ready and self.fill():
            pass
        out = bytes(self.ready[:n])
        del self.ready[:n]
        return out

    def exactly(self, n: int) -> bytes:
        while len(self.ready) < n and self.fill():
            pass
        if len(self.ready) < n:
            raise ValueError("the archive ends within a record")
        return self.take(n) if n else b""

    def header(self) -> dict[str, str] | None:
        while (end := self.ready.find(b"\r\n\r\n")) < 0:
            if not self.fill():
                if self.ready:
                    raise ValueError("the archive ends within a header")
                return None
        lines = bytes(self.ready[:end]).decode().split("\r\n")
        del self.ready[: end + 4]
        if not lines[0].startswith("WARC/"):
            raise ValueError("no record starts here")
        return {k.lower(): v for k, _, v in (x.partition(": ") for x in lines[1:])}


def read_records(source, chunk_bytes: int = CHUNK) -> Iterator[dict]:
    """Chunk rows of one archive; a record without content gives one row with empty data."""
    s = Stream(source, chunk_bytes)
    number = lambda x: None if x.endswith(":null>") else int(x.rpartition(":")[2][:-1])
    while (h := s.header()) is not None:
        left, sha, k, total = int(h["content-length"]), hashlib.sha256(), 0, 0
        declared = h["warc-payload-digest"].partition(":")[2]
        head = {"page_id": number(h["warc-record-id"]), "record_type": h["warc-type"], "refers_to": number(h["warc-refers-to"]) if "warc-refers-to" in h else None, "declared_bytes": int(h["x-payload-length"]), "declared_digest": declared}
        while True:
            data = s.exactly(min(chunk_bytes, left))
            left -= len(data)
            sha.update(data)
            total += len(data)
            yield head | {"chunk_no": k, "n_chunk": len(data), "data": data, "sha256_so_far": sha.hexdigest(), "total": total}
            k += 1
            if not left:
                break
        if s.exactly(4) != b"\r\n\r\n":
            raise ValueError("no end of the record")
        if h["warc-type"] == "response" and (sha.hexdigest() != declared or total != head["declared_bytes"]):
            raise ValueError("a payload differs from its digest")


def read_warc(manifest: DataFrame, chunk_bytes: int = CHUNK, with_data: bool = True) -> DataFrame:
    """The chunked record table of the archives, a task per file."""
    spark = manifest.sparkSession
    ship(spark)
    fields = [("page_id", pa.int64()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("declared_bytes", pa.int64()), ("declared_digest", pa.string()), ("chunk_no", pa.int32()), ("n_chunk", pa.int64()), ("data", pa.binary()), ("sha256_so_far", pa.string()), ("total", pa.int64())]
    schema = pa.schema(fields)

    def read(batches):
        for batch in batches:
            for path in batch.column("path").to_pylist():
                fs, name = open_fs(path)
                rows, size = [], 0
                with fs.open_input_stream(name, compression=None) as source:
                    for row in read_records(source, chunk_bytes):
                        size += row["n_chunk"]
                        if not with_data:
                            row["data"] = None
                        rows.append(row)
                        if size > 4 << 20 or len(rows) > 4096:
                            yield pa.RecordBatch.from_pylist(rows, schema=schema)
                            rows, size = [], 0
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=schema)

    files = [(r.path,) for r in manifest.select("path").collect()]  # a row per archive
    if not files:
        return spark.createDataFrame([], CHUNKS)
    return spark.createDataFrame(spark.sparkContext.parallelize(files, len(files)), "path string").mapInArrow(read, CHUNKS)


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    decided = decide(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    chunks = read_warc(write_warc(decided, new_path(spark, "warc")), with_data=False)
    last = chunks.where((F.col("record_type") == "revisit") | (F.col("total") == F.col("declared_bytes")))
    digest = F.when(F.col("record_type") == "response", F.col("sha256_so_far")).otherwise(F.col("declared_digest"))
    return last.select("page_id", F.col("declared_bytes").alias("payload_bytes"), digest.alias("payload_digest"), "record_type", "refers_to")
