"""Media columns: interleaved sequences of text and media, resolved by digest.

HTML is parsed into an ordered array of structs, text blocks and media references alternating as they stand in the
page; a reference names its payload by SHA-256 and carries its caption. Payloads lie in a content-addressed table as
grey PNG images of 64 samples a row, 8 bits a sample, so any bytes whose length is a multiple of 64 are stored
without loss. Resolving explodes the sequences with their positions, joins the digests against what was read back from
the store, and keeps text, positions and captions where they were.

Results for odd input: null html or text is empty; references without a digest, or with one that the store lacks,
stay in the sequence with null payload columns; equal payloads may be stored more than once but resolve to one row;
repeated rows are parsed each; an empty table gives no rows; further columns are left alone.
"""

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

from .common import written

WIDTH = 64
_SIGNATURE = b"\x89PNG\r\n\x1a\n"
#: Digests that one task remembers so as not to store a payload again.
REMEMBERED = 200_000
SEQUENCE = "array<struct<position:int,kind:string,text:string,digest:string,caption:string>>"
_BLOCKS = {"p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "div", "section", "article", "td", "th", "blockquote", "pre", "br", "tr", "table", "ul", "ol", "nav", "header", "footer"}
_MEDIA = {"img", "audio", "video", "source"}


def padded(text: Column) -> Column:
    """UTF-8 bytes of ``text`` with zero bytes up to a positive multiple of 64."""
    data = F.encode(F.coalesce(text, F.lit("")), "utf-8")
    return F.rpad(data, F.greatest(F.lit(WIDTH), F.ceil(F.octet_length(data) / WIDTH) * WIDTH).cast("int"), F.lit(b"\x00"))


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def to_png(payload: bytes) -> bytes:
    """An 8-bit grey PNG, 64 wide, rows unfiltered; the same bytes for the same payload."""
    rows = np.zeros((len(payload) // WIDTH, WIDTH + 1), np.uint8)
    rows[:, 1:] = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    head = struct.pack(">IIBBBBB", WIDTH, len(rows), 8, 0, 0, 0, 0)
    return _SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(rows.tobytes(), 1)) + _chunk(b"IEND", b"")


def from_png(media: bytes) -> bytes:
    """The samples of a grey PNG as ``to_png`` writes it; refuses damaged files and other kinds."""
    if not media.startswith(_SIGNATURE):
        raise ValueError("not a PNG file")
    at, head, data = len(_SIGNATURE), None, []
    while at < len(media):
        size, kind = struct.unpack_from(">I4s", media, at)
        body = media[at + 8 : at + 8 + size]
        if zlib.crc32(kind + body) != struct.unpack_from(">I", media, at + 8 + size)[0]:
            raise ValueError("a chunk's checksum is wrong")
        if kind == b"IHDR":
            head = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            data.append(body)
        at += size + 12
    if head is None or head[2:] != (8, 0, 0, 0, 0):
        raise ValueError("only 8-bit grey images without interlacing are read")
    rows = np.frombuffer(zlib.decompress(b"".join(data)), np.uint8).reshape(head[1], head[0] + 1)
    if rows[:, 0].any():
        raise ValueError("only unfiltered rows are read")
    return rows[:, 1:].tobytes()


def feature_of(samples: bytes) -> str:
    """Rows, mean, deviation and entropy of the samples."""
    counts = np.bincount(np.frombuffer(samples, np.uint8), minlength=256)
    share = counts / counts.sum()
    mean = float(share @ np.arange(256))
    spread = float(share @ (np.arange(256) - mean) ** 2) ** 0.5
    some = share[share > 0]
    return f"{len(samples) // WIDTH}x{WIDTH} mean={mean:.4f} sd={spread:.4f} bits={float(-(some * np.log2(some)).sum()):.4f}"


def store(payloads: DataFrame) -> DataFrame:
    """The written table (digest, media) for ``payloads`` (digest, payload); one task stores a digest once."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[str] = set()
        for batch in batches:
            digests, media = [], []
            for digest, payload in zip(batch.column("digest").to_pylist(), batch.column("payload"), strict=True):
                if digest in seen:
                    continue
                if len(seen) >= REMEMBERED:
                    seen.clear()
                seen.add(digest)
                digests.append(digest)
                media.append(to_png(payload.as_py()))
            yield pa.RecordBatch.from_arrays([pa.array(digests, pa.string()), pa.array(media, pa.binary())], names=["digest", "media"])

    return written(payloads.select("digest", "payload").mapInArrow(work, "digest string, media binary"), "media")


_READ = {"payload_bytes": pa.int64(), "payload_sha256": pa.string(), "tail_crc32": pa.int64(), "media_bytes": pa.int64(), "media_sha256": pa.string(), "feature": pa.string()}


def read_back(media: DataFrame) -> DataFrame:
    """digest and what the stored bytes hold: sizes, digests, the last 64 bytes' checksum, feature; one row a digest."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for x in batch.column("media"):
                stored = x.as_py()
                payload = from_png(stored)
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-WIDTH:]), len(stored), hashlib.sha256(stored).hexdigest(), feature_of(payload)))
            columns = zip(*rows, strict=True) if rows else [[]] * len(_READ)
            yield pa.RecordBatch.from_arrays([batch.column("digest"), *[pa.array(c, t) for c, t in zip(columns, _READ.values(), strict=True)]], names=["digest", *_READ])

    kinds = {pa.int64(): "long", pa.string(): "string"}
    return media.mapInArrow(work, "digest string, " + ", ".join(f"{c} {kinds[t]}" for c, t in _READ.items())).dropDuplicates(["digest"])


class _Sequence(HTMLParser):
    """Collects text blocks and media references in document order."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.out: list[dict] = []
        self.text: list[str] = []
        self.figure: list[dict] | None = None
        self.caption: list[str] | None = None
        self.hidden = 0

    def flush(self) -> None:
        said = " ".join("".join(self.text).split())
        self.text = []
        if said:
            self.out.append({"kind": "text", "text": said, "digest": None, "caption": None})

    def handle_starttag(self, tag: str, attrs: list) -> None:
        if tag in ("script", "style", "template"):
            self.hidden += 1
        elif tag == "figure":
            self.flush()
            self.figure = []
        elif tag == "figcaption":
            self.flush()
            self.caption = []
        elif tag in _MEDIA:
            self.flush()
            has = dict(attrs)
            src = has.get("src") or ""
            digest = has.get("data-sha256") or (src[7:] if src.startswith("sha256:") else None)
            ref = {"kind": "media", "text": src or None, "digest": digest, "caption": has.get("alt")}
            self.out.append(ref)
            if self.figure is not None:
                self.figure.append(ref)
        elif tag in _BLOCKS:
            self.flush()

    def handle_endtag(self, tag: str) -> None:
        if tag in ("script", "style", "template"):
            self.hidden = max(0, self.hidden - 1)
        elif tag == "figcaption" and self.caption is not None:
            said = " ".join("".join(self.caption).split())
            for ref in self.figure or ():
                ref["caption"] = said
            if not self.figure and said:  # no reference to belong to: it stays as text
                self.out.append({"kind": "text", "text": said, "digest": None, "caption": None})
            self.caption = None
        elif tag == "figure":
            self.flush()
            self.figure = None
        elif tag in _BLOCKS:
            self.flush()

    def handle_data(self, data: str) -> None:
        if not self.hidden:
            (self.text if self.caption is None else self.caption).append(data)


def sequence_of(html: str) -> list[dict]:
    """Ordered structs of one page."""
    parser = _Sequence()
    parser.feed(html)
    parser.close()
    parser.flush()
    return [{"position": i, **x} for i, x in enumerate(parser.out)]


def sequences(pages: DataFrame, *carried: str) -> DataFrame:
    """``carried`` columns and ``sequence`` for each row of ``pages`` (html)."""
    kind = pa.list_(pa.struct([("position", pa.int32()), *[(c, pa.string()) for c in ("kind", "text", "digest", "caption")]]))
    fields = [f"`{c}` {pages.schema[c].dataType.simpleString()}" for c in carried]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [sequence_of(x or "") for x in batch.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in carried), pa.array(found, kind)], names=[*carried, "sequence"])

    return pages.select(*carried, "html").mapInArrow(work, ", ".join([*fields, f"sequence {SEQUENCE}"]))


def resolve(sequenced: DataFrame, held: DataFrame, *carried: str) -> DataFrame:
    """One row per element: ``carried``, its place in the sequence, and the payload columns of media (else null)."""
    rows = sequenced.select(*carried, F.inline("sequence"))
    return rows.join(held, "digest", "left").select(*carried, "position", "kind", "text", "digest", "caption", *_READ)


def documents_as_media(docs: DataFrame) -> DataFrame:
    """Each document's text as the one figure of a small page: stored, referred to, resolved and read back."""
    payload = padded(F.col("text"))
    base = docs.select("doc_id", F.octet_length(F.encode(F.coalesce("text", F.lit("")), "utf-8")).cast("long").alias("n_bytes"), payload.alias("payload"))
    base = base.withColumn("digest", F.sha2("payload", 256))
    held = read_back(store(base))
    html = F.concat(F.lit("<article><h1>Document "), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit('</h1><figure><img src="sha256:'), F.col("digest"), F.lit('"><figcaption>'), F.col("n_bytes").cast("string"), F.lit(" bytes</figcaption></figure></article>"))
    paged = base.select("doc_id", "n_bytes", html.alias("html"))
    return resolve(sequences(paged, "doc_id", "n_bytes"), held, "doc_id", "n_bytes")
