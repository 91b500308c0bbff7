"""Media columns: interleaved document sequences with payloads resolved by digest.

A page is parsed to an ordered array of items, each either a text block or a reference to a
medium: ``struct<position, kind, text, digest, caption>``. A figure's caption belongs to the media
directly in that figure, before or after it; media without one keep their own description; a
caption outside figures is a text block. What scripts, styles and inert templates hold is no item. Payloads live in a media table of
their own, a row per stored form, found by the digest of the payload. ``interleave`` parses,
``resolve`` joins by digest; position and caption come from the page, bytes from the store, so
they stay aligned whatever the join does to row order.

Stored form: an 8-bit grey PNG of width 64, one sample per payload byte, rows unfiltered. The
payload is the UTF-8 text, padded with zero bytes to a positive multiple of 64. It is lossless,
and equal payloads have equal stored forms.

Null text is an empty text (64 zero bytes). Null identifiers and repeated rows are kept. A
reference whose digest is not in the store keeps its position with null bytes. The store may
hold a digest more than once (each task drops only its own repeats); readers take one.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from patchspace.llm.spread import spread_join
from patchspace.shared import ship, staged

WIDTH = 64
PNG = b"\x89PNG\r\n\x1a\n"
ITEM = "struct<position:int,kind:string,text:string,digest:string,caption:string>"
SCHEME = "sha256:"


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def encode_png(payload: bytes, part: int = 1 << 20) -> bytes:
    """Grey PNG of width 64; the payload's length is a multiple of 64."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    out = [PNG, _chunk(b"IHDR", struct.pack(">IIBBBBB", WIDTH, len(rows), 8, 0, 0, 0, 0))]
    pack, step = zlib.compressobj(3), part // WIDTH
    for a in range(0, len(rows), step):
        block = rows[a : a + step]
        lines = np.zeros((len(block), WIDTH + 1), np.uint8)  # each line: filter type 0, samples
        lines[:, 1:] = block
        data = pack.compress(lines.tobytes())
        if data:
            out.append(_chunk(b"IDAT", data))
    out += [_chunk(b"IDAT", pack.flush()), _chunk(b"IEND", b"")]
    return b"".join(out)


def decode_png(png: bytes) -> bytes:
    """The samples of such a PNG; checks signature, sizes and chunk checksums."""
    if png[:8] != PNG:
        raise ValueError("not a PNG")
    at, height, data, unpack = 8, None, [], zlib.decompressobj()
    while at < len(png):
        n = struct.unpack_from(">I", png, at)[0]
        kind, body = png[at + 4 : at + 8], png[at + 8 : at + 8 + n]
        if struct.unpack_from(">I", png, at + 8 + n)[0] != zlib.crc32(kind + body):
            raise ValueError("a damaged chunk")
        if kind == b"IHDR":
            width, height, depth, colour = struct.unpack_from(">IIBB", body)
            if (width, depth, colour) != (WIDTH, 8, 0):
                raise ValueError("another kind of PNG")
        elif kind == b"IDAT":
            data.append(unpack.decompress(body))
        at += 12 + n
    lines = np.frombuffer(b"".join(data), np.uint8).reshape(height, WIDTH + 1)
    if lines[:, 0].any():
        raise ValueError("a filtered line")
    return lines[:, 1:].tobytes()


def feature(payload: bytes) -> str:
    """A picture's signature: mean, deviation, and which of 8x8 cells are above the mean."""
    x = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    edges = np.linspace(0, len(x), 9).astype(int)
    columns = x.reshape(len(x), 8, 8).sum(2, dtype=np.int64)
    cells = np.array([columns[a : max(b, a + 1)].mean(0) if a < len(x) else columns[-1] for a, b in zip(edges[:-1], edges[1:], strict=True)])
    bits = np.packbits((cells > cells.mean()).ravel()).tobytes().hex()
    return f"h={len(x)};mean={x.mean():.4f};std={x.std():.4f};grid={bits}"


def payload_of(text: Column) -> Column:
    """UTF-8 bytes padded with zero bytes to a positive multiple of 64; null is empty."""
    t = F.coalesce(text, F.lit(""))
    n = F.octet_length(t)
    pad = F.when(n == 0, WIDTH).otherwise(F.pmod(-n, F.lit(WIDTH)))
    return F.concat(F.encode(t, "UTF-8"), F.unhex(F.repeat(F.lit("00"), pad)))


def store_media(payloads: DataFrame, payload_col: str = "payload") -> DataFrame:
    """Write the stored forms: digest, media. Repeats within a task are dropped."""
    ship(payloads.sparkSession)
    schema = pa.schema([("digest", pa.string()), ("media", pa.binary())])

    def write(batches):
        seen: set[bytes] = set()
        for batch in batches:
            out, size = [], 0
            for payload in batch.column(0):
                raw = payload.as_py()
                own = hashlib.sha256(raw).digest()
                if own in seen:
                    continue
                if len(seen) < 1 << 20:  # a bound on memory; more repeats only take room
                    seen.add(own)
                out.append({"digest": own.hex(), "media": encode_png(raw)})
                size += len(out[-1]["media"])
                if size > 4 << 20:
                    yield pa.RecordBatch.from_pylist(out, schema=schema)
                    out, size = [], 0
            if out:
                yield pa.RecordBatch.from_pylist(out, schema=schema)

    return staged(payloads.select(payload_col).mapInArrow(write, "digest string, media binary"), "media-store")


def media_features(store: DataFrame) -> DataFrame:
    """Features of the stored bytes, read back and decoded; one small row per digest."""
    fields = [("digest", pa.string()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())]

    def read(batches):
        for batch in batches:
            out = []
            for digest, media in zip(batch.column("digest").to_pylist(), batch.column("media"), strict=True):
                raw = media.as_py()
                p = decode_png(raw)
                out.append((digest, len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-WIDTH:]), len(raw), hashlib.sha256(raw).hexdigest(), feature(p)))
            cols = list(zip(*out, strict=True)) or [[] for _ in fields]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, (_, t) in zip(cols, fields, strict=True)], names=[n for n, _ in fields])

    ddl = "digest string, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    rows = store.select("digest", "media").mapInArrow(read, ddl)
    return rows.groupBy("digest").agg(*[F.min(n).alias(n) for n, _ in fields[1:]])


class _Items(HTMLParser):
    BLOCK = set("p div section article li ul ol table tr td th h1 h2 h3 h4 h5 h6 blockquote pre figure figcaption header footer br hr".split())
    MEDIA = {"img": "src", "video": "src", "audio": "src", "source": "src", "object": "data", "embed": "src"}
    HIDDEN = {"script", "style", "template"}

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.items: list[dict] = []
        self.text: list[str] = []
        self.hidden = 0
        self.figures: list[dict] = []  # open figures: places of the media directly in them, caption
        self.captions: list[tuple[dict, list[str]]] = []  # open captions, each of a figure

    def flush(self) -> None:
        words = re.sub(r"\s+", " ", "".join(self.text)).strip()
        self.text = []
        if words:
            self.items.append({"position": len(self.items), "kind": "text", "text": words, "digest": None, "caption": None})

    def end_caption(self) -> None:
        figure, parts = self.captions.pop()
        figure["caption"] = figure["caption"] or re.sub(r"\s+", " ", "".join(parts)).strip()

    def end_figure(self) -> None:
        figure = self.figures.pop()
        while self.captions and self.captions[-1][0] is figure:
            self.end_caption()
        for place in figure["media"] if figure["caption"] else ():
            self.items[place]["caption"] = figure["caption"]

    def handle_starttag(self, tag, attrs):
        if tag in self.HIDDEN:
            self.hidden += 1
        if self.hidden:
            return
        if tag in self.BLOCK or tag in self.MEDIA:
            self.flush()
        if tag == "figure":
            self.figures.append({"media": [], "caption": None})
        elif tag == "figcaption" and self.figures:
            self.captions.append((self.figures[-1], []))
        elif tag in self.MEDIA:
            own = dict(attrs)
            ref = own.get(self.MEDIA[tag])
            if ref:
                digest = ref[len(SCHEME) :] if ref.startswith(SCHEME) else None
                if self.figures:
                    self.figures[-1]["media"].append(len(self.items))
                self.items.append({"position": len(self.items), "kind": "media", "text": None if digest else ref, "digest": digest, "caption": own.get("alt") or None})

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag in self.HIDDEN:
            self.hidden -= 1

    def handle_endtag(self, tag):
        if tag in self.HIDDEN:
            self.hidden = max(0, self.hidden - 1)
        if self.hidden:
            return
        if tag in self.BLOCK:
            self.flush()
        if tag == "figcaption" and self.captions:
            self.end_caption()
        elif tag == "figure" and self.figures:
            self.end_figure()

    def handle_data(self, data):
        if not self.hidden:
            (self.captions[-1][1] if self.captions else self.text).append(data)

    def finish(self) -> list[dict]:
        self.close()
        self.flush()
        while self.figures:
            self.end_figure()
        return self.items


def parse_items(html: str | None) -> list[dict]:
    p = _Items()
    p.feed(html or "")
    return p.finish()


def interleave(pages: DataFrame, html_col: str = "html") -> DataFrame:
    """The pages with a column ``items``: ordered text and media-reference structs.

    Null or empty HTML gives an empty array; markup errors never fail a row.
    """
    ship(pages.sparkSession)

    @F.pandas_udf(f"array<{ITEM}>")
    def items(html):
        return html.map(parse_items)

    return pages.withColumn("items", items(F.coalesce(F.col(html_col), F.lit(""))))


def resolve(pages: DataFrame, media: DataFrame, key: list[str]) -> DataFrame:
    """One row per item, with the media row of its digest joined on; ``key`` and position tell the order.

    ``media`` holds one row per digest, whatever its columns: stored bytes, features. References to
    a popular digest are counted first and dealt over many tasks.
    """
    flat = pages.select(*key, F.explode("items").alias("item")).select(*key, "item.*")
    uses = flat.where("digest IS NOT NULL").groupBy("digest").agg(F.count("*").alias("n"))
    uses = staged(uses, "media-uses")
    total = uses.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    found = media.join(uses, "digest")  # a medium that nothing refers to takes no part
    return spread_join(flat, found, "digest", total, F.xxhash64(*key, "position"), "left")


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    payload = payload_of(F.col("text"))
    media = staged(media_features(store_media(docs.select(payload.alias("payload")))), "media-features")
    page = F.format_string('<article><p>Document %s</p><figure><img src="sha256:%s" alt="text"><figcaption>Text of document %s</figcaption></figure></article>', F.col("doc_id"), F.sha2(payload, 256), F.col("doc_id"))
    pages = docs.select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"), page.alias("html"))
    found = resolve(interleave(pages), media, ["doc_id", "n_bytes"]).where("kind = 'media'")
    return found.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "position", "caption")
