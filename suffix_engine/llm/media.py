"""Interleaved document sequences: ordered text and media references from HTML, and a media store joined by digest."""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from suffix_engine.session import written

#: Samples in a row of a stored image; payloads are filled up to whole rows.
WIDTH = 64
SEQUENCE = "array<struct<pos:int,kind:string,text:string,digest:string,caption:string>>"
_MEDIA = {"img": "image", "video": "video", "audio": "audio", "source": "source"}
_HIDDEN = {"script", "style", "template", "noscript"}
_BLOCKS = {"p", "div", "li", "h1", "h2", "h3", "h4", "h5", "h6", "tr", "br", "section", "article", "ul", "ol", "table", "figure", "nav", "header", "footer", "title", "body", "blockquote", "pre"}
_SIGNATURE = b"\x89PNG\r\n\x1a\n"


class _Reader(HTMLParser):
    """Blocks of text and media references in document order. A figure's caption goes with its media, wherever it stands in the figure."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.items: list[dict] = []
        self.text: list[str] = []
        self.caption: list[str] | None = None
        self.hidden, self.figures = 0, []

    def _flush(self) -> None:
        words = " ".join("".join(self.text).split())
        self.text = []
        if words:
            self.items.append({"kind": "text", "text": words, "digest": None, "caption": None})

    def handle_starttag(self, tag, attrs):
        given = dict(attrs)
        if tag in _HIDDEN:
            self.hidden += 1
        elif tag == "figure":
            self._flush()
            self.figures.append([])
        elif tag == "figcaption":
            self._flush()
            self.caption = []
        elif tag in _MEDIA and (given.get("src") or given.get("data-digest")):
            if self.caption is None:
                self._flush()
            source = given.get("data-digest") or given["src"]
            self.items.append({"kind": _MEDIA[tag], "text": None, "digest": source.removeprefix("sha256:"), "caption": given.get("alt") or None})
            if self.figures:
                self.figures[-1].append(self.items[-1])
        elif tag in _BLOCKS and self.caption is None:
            self._flush()

    def handle_endtag(self, tag):
        if tag in _HIDDEN:
            self.hidden = max(0, self.hidden - 1)
        elif tag == "figcaption" and self.caption is not None:
            words, self.caption = " ".join("".join(self.caption).split()), None
            if self.figures:
                self.figures[-1].append(words)
            elif words:
                self.items.append({"kind": "text", "text": words, "digest": None, "caption": None})
        elif tag == "figure" and self.figures:
            self._flush()
            own = self.figures.pop()
            words = " ".join(x for x in own if isinstance(x, str) and x)
            media = [x for x in own if not isinstance(x, str)]
            for x in media:
                x["caption"] = words or x["caption"]
            if words and not media:
                self.items.append({"kind": "text", "text": words, "digest": None, "caption": None})
        elif tag in _BLOCKS and self.caption is None:
            self._flush()

    def handle_data(self, data):
        if not self.hidden:
            (self.text if self.caption is None else self.caption).append(data)


def read_html(html: str | None) -> list[dict]:
    reader = _Reader()
    reader.feed(html or "")
    reader.close()
    if reader.caption is not None:
        reader.handle_endtag("figcaption")
    while reader.figures:
        reader.handle_endtag("figure")
    reader._flush()
    return [{"pos": i} | x for i, x in enumerate(reader.items)]


def sequences(df: DataFrame, key: str, html: str) -> DataFrame:
    """key and the sequence of its HTML; null and empty HTML have an empty sequence. All rows stay; other columns aren't read."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("pos", pa.int32()), ("kind", pa.string()), ("text", pa.string()), ("digest", pa.string()), ("caption", pa.string())]))
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch["key"], pa.array([read_html(x.as_py()) for x in batch["html"]], kind)], ["key", "sequence"])

    return df.select(F.col(key).cast("long").alias("key"), F.col(html).alias("html")).mapInArrow(run, f"key long, sequence {SEQUENCE}").withColumnRenamed("key", key)


def _chunk(name: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + name + data + struct.pack(">I", zlib.crc32(name + data))


def encode_image(payload: bytes) -> bytes:
    """A lossless image of 8-bit grey samples, WIDTH to a row; the payload has whole rows."""
    rows = np.zeros((len(payload) // WIDTH, WIDTH + 1), np.uint8)
    rows[:, 1:] = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    head = struct.pack(">IIBBBBB", WIDTH, len(rows), 8, 0, 0, 0, 0)
    return _SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(rows.tobytes(), 1)) + _chunk(b"IEND", b"")


def decode_image(media: bytes) -> bytes:
    """The samples; raises if the form, a checksum or the size is wrong."""
    if media[:8] != _SIGNATURE:
        raise ValueError("not an image")
    at, data, size = 8, b"", None
    while at < len(media):
        (n,) = struct.unpack_from(">I", media, at)
        name, body = media[at + 4 : at + 8], media[at + 8 : at + 8 + n]
        if zlib.crc32(name + body) != struct.unpack_from(">I", media, at + 8 + n)[0]:
            raise ValueError("damaged image")
        size = struct.unpack(">II", body[:8]) if name == b"IHDR" else size
        data += body if name == b"IDAT" else b""
        at += n + 12
    rows = np.frombuffer(zlib.decompress(data), np.uint8).reshape(size[1], size[0] + 1)
    if rows[:, 0].any():
        raise ValueError("a filter that isn't written here")
    return rows[:, 1:].tobytes()


def feature(payload: bytes) -> str:
    """Which of the image's 64 columns are brighter than their median, as hexadecimal digits, the mean sample and the entropy."""
    x = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    columns = x.sum(axis=0, dtype=np.int64)
    bits = np.packbits(columns > np.median(columns)).tobytes().hex()
    p = np.bincount(x.ravel(), minlength=256) / x.size
    p = p[p > 0]
    return f"{bits}:{x.mean():.4f}:{abs(float(-(p * np.log2(p)).sum())):.4f}"


def padded(text: Column) -> Column:
    """UTF-8 with bytes 0 up to a positive multiple of WIDTH."""
    raw = F.encode(F.coalesce(text, F.lit("")), "UTF-8")
    n = F.octet_length(raw)
    short = F.when(n == 0, F.lit(WIDTH)).otherwise(F.pmod(-n, F.lit(WIDTH))).cast("int")
    return F.concat(raw, F.unhex(F.repeat(F.lit("00"), short)))


def store(payloads: DataFrame) -> DataFrame:
    """Writes the media of (digest, payload) to a table in the shared folder: digest, media. Equal payloads of a task are stored once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[str] = set()
        for batch in batches:
            names = batch["digest"].to_pylist()
            new = [i for i, x in enumerate(names) if x not in seen and not seen.add(x)]
            yield pa.RecordBatch.from_arrays([pa.array([names[i] for i in new], pa.string()), pa.array([encode_image(batch["payload"][i].as_py()) for i in new], pa.binary())], ["digest", "media"])

    return written(payloads.mapInArrow(run, "digest string, media binary"), "media")


def inspected(media: DataFrame) -> DataFrame:
    """One row for each digest, all figures from the bytes read back from the store."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for digest, stored in zip(batch["digest"].to_pylist(), batch["media"], strict=True):
                stored = stored.as_py()
                payload = decode_image(stored)
                rows.append({"digest": digest, "payload_bytes": len(payload), "payload_sha256": hashlib.sha256(payload).hexdigest(), "tail_crc32": zlib.crc32(payload[-WIDTH:]), "media_bytes": len(stored), "media_sha256": hashlib.sha256(stored).hexdigest(), "feature": feature(payload)})
            kind = pa.schema([("digest", pa.string()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())])
            yield pa.RecordBatch.from_pylist(rows, kind)

    return media.mapInArrow(run, "digest string, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string").dropDuplicates(["digest"])


def resolve(sequence: DataFrame, key: str, media: DataFrame) -> DataFrame:
    """Each item of the sequences (key, pos, kind, text, digest, caption) with the columns of its media, null for text and for
    digests that the store lacks. media has one row for each digest; a digest that many items share is dealt out by adaptive execution."""
    items = sequence.select(key, F.inline("sequence"))
    found = media.withColumnRenamed("digest", "_digest")
    return items.join(found, items["digest"] == found["_digest"], "left").drop("_digest")


def as_page(digest: Column, caption: Column) -> Column:
    return F.concat(F.lit('<article><figure><img src="sha256:'), digest, F.lit('"><figcaption>'), caption.cast("string"), F.lit("</figcaption></figure></article>"))


def document_media(docs: DataFrame) -> DataFrame:
    """Each text as a stored image, referred to by a page of its own, resolved by digest, with the features of what was read back.

    Null and empty texts are one row of bytes 0. All rows stay, repeated ones too. The caption carries the number of bytes, so it must stay aligned.
    """
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    paid = own.withColumn("payload", padded(F.col("text"))).withColumn("digest", F.sha2("payload", 256))
    pages = paid.select("doc_id", as_page(F.col("digest"), F.octet_length(F.coalesce("text", F.lit("")))).alias("html"))
    # written, so that both sides of the join are plain exchanges, which adaptive execution can split at a digest of many documents
    found = written(inspected(store(paid.select("digest", "payload"))), "inspected")
    out = resolve(sequences(pages, "doc_id", "html"), "doc_id", found)
    return out.select("doc_id", F.col("caption").cast("long").alias("n_bytes"), "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")
