"""WARC archives and the external merge of their capture index.

Pages are written as WARC 1.1 records by Spark's text writer (records end in two line breaks, which is the writer's line
separator), one gzip file a task. Of equal payloads of ``REVISIT_BYTES`` or more, the record of the largest page_id
is a response and the others are revisits of it. Reading parses each file as a stream by its Content-Length headers,
so payloads may hold anything, and gives one capture run a file, sorted by URL key and time. Runs are dealt out by
range, as many as bound a range's size, and each range is merged from its runs by a loser tree.

Results for odd input: null html is an empty payload; a null url is an empty target; control characters in a url are
escaped in the header; rows that repeat a page_id get a record each; rows without page_id are never responses to others and
refer to the largest page_id; ties in URL key and time go by page_id; an empty table gives no rows; further columns are left alone.
"""

from __future__ import annotations

import gzip
import hashlib
import io
import math
import re
from collections.abc import Callable, Iterator
from itertools import groupby, islice

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import scratch_path, written

REVISIT_BYTES = 1000
#: Bytes of index rows that one range holds, about.
RANGE_BYTES = 64 << 20
_EOL = "\r\n"
_FIELDS = [("urlkey", pa.string()), ("captured", pa.string()), ("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("archive", pa.string()), ("at", pa.int64())]
_SCHEMA = pa.schema(_FIELDS)
_DDL = "urlkey string, captured string, page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, archive string, at long"


def typed(pages: DataFrame, least: int = REVISIT_BYTES) -> DataFrame:
    """page_id, url, html with payload_bytes, digest, record_type and refers_to."""
    html = F.coalesce("html", F.lit(""))
    base = pages.select("page_id", F.coalesce("url", F.lit("")).alias("url"), html.alias("html"))
    base = base.withColumn("payload_bytes", F.octet_length("html").cast("long")).withColumn("digest", F.sha1(F.encode("html", "utf-8")))
    first = base.filter(F.col("payload_bytes") >= least).groupBy("digest").agg(F.max("page_id").alias("first"), F.count(F.lit(1)).alias("size")).filter("size > 1 and first is not null").drop("size")
    out = base.join(first, "digest", "left")
    again = F.col("first").isNotNull() & ~F.coalesce(F.col("page_id") == F.col("first"), F.lit(False))
    return out.select("page_id", "url", "html", "payload_bytes", "digest", F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("first")).alias("refers_to"))


def records(pages: DataFrame) -> DataFrame:
    """One column ``value``: each page's WARC record without its closing line breaks."""
    seconds = F.pmod(F.coalesce("page_id", F.lit(0)), F.lit(10**9)).cast("long")
    two = lambda c: F.lpad(F.floor(c).cast("string"), 2, "0")
    date = F.concat(
        F.date_add(F.lit("2024-01-01").cast("date"), F.floor(seconds / 86400).cast("int")).cast("string"),
        F.lit("T"), two(seconds % 86400 / 3600), F.lit(":"), two(seconds % 3600 / 60), F.lit(":"), two(seconds % 60), F.lit("Z"),
    )
    target = F.regexp_replace(F.regexp_replace("url", "\r", "%0D"), "\n", "%0A")
    revisit = F.col("record_type") == "revisit"
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{_EOL}Content-Type: text/html; charset=utf-8{_EOL}Content-Length: "), F.col("payload_bytes").cast("string"), F.lit(_EOL * 2))
    block = F.when(revisit, http).otherwise(F.concat(http, "html"))
    name = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(F.col(c).cast("string"), F.lit("none")), F.lit(">"))
    line = lambda k, v: F.concat(F.lit(f"{k}: "), v, F.lit(_EOL))
    head = F.concat(
        F.lit(f"WARC/1.1{_EOL}"),
        line("WARC-Type", F.col("record_type")),
        line("WARC-Record-ID", name("page_id")),
        line("WARC-Date", date),
        line("WARC-Target-URI", target),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), "digest")),
        F.when(revisit, F.concat(line("WARC-Refers-To", name("refers_to")), F.lit(f"WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest{_EOL}"))).otherwise(""),
        F.lit(f"Content-Type: application/http;msgtype=response{_EOL}"),
        line("Content-Length", F.octet_length(block).cast("string")),
        F.lit(_EOL),
    )
    return pages.select(F.concat(head, block).alias("value"))


def write(pages: DataFrame, folder: str) -> None:
    """Archive files of ``pages`` (page_id, url, html) in ``folder``, on any file system Spark can write."""
    records(typed(pages)).write.option("lineSep", _EOL * 2).option("compression", "gzip").text(folder)


def url_key(url: str) -> str:
    """Host labels reversed and joined by commas, then path and query, in lower case."""
    rest = url.partition("://")[2] if "://" in url else url
    host, path = re.match(r"([^/?#]*)(.*)", rest, re.S).groups()
    return (",".join(reversed(host.lower().split("."))) + ")" + path.partition("#")[0]).lower()


def parse(archive: io.BufferedIOBase) -> Iterator[tuple[dict[str, str], bytes, int]]:
    """Headers, block and offset of every record of an open, uncompressed archive."""
    while True:
        at = archive.tell()
        line = archive.readline()
        if not line:
            return
        if line == b"\r\n":
            continue
        if not line.startswith(b"WARC/1."):
            raise ValueError(f"no record begins at {at}")
        head = {}
        while (line := archive.readline()) not in (b"\r\n", b""):
            k, _, v = line.decode("utf-8").rstrip("\r\n").partition(": ")
            head[k] = v
        block = archive.read(int(head["Content-Length"]))
        if len(block) != int(head["Content-Length"]) or archive.read(4) != b"\r\n\r\n":
            raise ValueError(f"the record at {at} is cut off")
        yield head, block, at


def _page(name: str | None) -> int | None:
    found = re.fullmatch(r"<urn:page:(-?\d+)>", name or "")
    return int(found[1]) if found else None


def capture(head: dict[str, str], block: bytes, archive: str, at: int) -> tuple:
    """One index row; a response's size and digest come from its payload, a revisit's from its headers."""
    http, _, payload = block.partition(b"\r\n\r\n")
    if head["WARC-Type"] == "response":
        size, digest = len(payload), hashlib.sha1(payload).hexdigest()
        if head["WARC-Payload-Digest"] != f"sha1:{digest}":
            raise ValueError(f"the payload at {at} of {archive} has another digest")
    else:
        size, digest = int(re.search(rb"Content-Length: (\d+)", http)[1]), head["WARC-Payload-Digest"].removeprefix("sha1:")
    return (url_key(head["WARC-Target-URI"]), head["WARC-Date"], _page(head["WARC-Record-ID"]), size, digest, head["WARC-Type"], _page(head.get("WARC-Refers-To")), archive, at)


def _key(row: tuple) -> tuple:
    return row[0], row[1], row[2] is not None, row[2] or 0


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else [[]] * len(_FIELDS)
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(columns, _FIELDS, strict=True)], schema=_SCHEMA)


def runs(spark, folder: str) -> DataFrame:
    """Index rows of every archive of ``folder``; those of one file are one sorted run."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, content in zip(batch.column("path").to_pylist(), batch.column("content"), strict=True):
                name = path.rpartition("/")[2]
                with gzip.GzipFile(fileobj=io.BytesIO(content.as_py())) as archive:
                    rows = sorted((capture(*x[:2], name, x[2]) for x in parse(archive)), key=_key)
                for lo in range(0, len(rows), 10_000):
                    yield _batch(rows[lo : lo + 10_000])

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(folder)
    return files.select("path", "content").mapInArrow(work, _DDL)


class LoserTree:
    """Merges sorted iterators: inner nodes hold the losers of their matches, and each step replays one path."""

    def __init__(self, sources: list[Iterator[tuple]], key: Callable[[tuple], tuple]) -> None:
        self.sources, self.key = sources, key
        self.heads: list = [None] * len(sources)
        self.keys: list = [None] * len(sources)
        for i in range(len(sources)):
            self._next(i)
        self.losers = [-1] * max(1, len(sources))
        self.winner = self._build(1) if sources else -1

    def _next(self, i: int) -> None:
        self.heads[i] = next(self.sources[i], None)
        self.keys[i] = None if self.heads[i] is None else self.key(self.heads[i])

    def _beats(self, i: int, j: int) -> bool:
        if self.keys[i] is None or self.keys[j] is None:
            return self.keys[j] is None and (self.keys[i] is not None or i < j)
        return (self.keys[i], i) < (self.keys[j], j)

    def _build(self, node: int) -> int:
        if node >= len(self.sources):
            return node - len(self.sources)
        a, b = self._build(2 * node), self._build(2 * node + 1)
        win, lose = (a, b) if self._beats(a, b) else (b, a)
        self.losers[node] = lose
        return win

    def __iter__(self) -> Iterator[tuple]:
        while self.winner >= 0 and self.keys[self.winner] is not None:
            yield self.heads[self.winner]
            win = self.winner
            self._next(win)
            node = (win + len(self.sources)) // 2
            while node:
                if self._beats(self.losers[node], win):
                    self.losers[node], win = win, self.losers[node]
                node //= 2
            self.winner = win


def _rows(run: list[pa.RecordBatch]) -> Iterator[tuple]:
    for batch in run:
        for lo in range(0, batch.num_rows, 1000):
            yield from zip(*(c.to_pylist() for c in batch.slice(lo, 1000).columns), strict=True)


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One range's rows, which arrive archive by archive and in order within each, merged to one run."""
    found: dict[str | None, list[pa.RecordBatch]] = {}
    for batch in batches:
        lo = 0
        for name, same in groupby(batch.column("archive").to_pylist()):
            n = sum(1 for _ in same)
            found.setdefault(name, []).append(batch.slice(lo, n))
            lo += n
    rows = iter(LoserTree([_rows(run) for run in found.values()], _key))
    while some := list(islice(rows, 10_000)):
        yield _batch(some)


def merged(index: DataFrame, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """Capture histories: ``index`` ordered by URL key, time and page_id over all partitions and within each.

    There are as many ranges as keep each near ``range_bytes``. Runs arrive sorted by Spark's own sort, which spills
    where it must, so that a task holds its range and one row of each run and keeps no files.
    """
    keys = ("urlkey", "captured", "page_id")
    size = index.agg(F.sum(F.octet_length("urlkey") + 200)).first()[0] or 0
    ranges = max(int(index.sparkSession.conf.get("spark.sql.shuffle.partitions")), math.ceil(size / range_bytes))
    return index.repartitionByRange(ranges, *keys).sortWithinPartitions("archive", *keys).mapInArrow(_merge, _DDL)


def round_trip(pages: DataFrame) -> DataFrame:
    """Writes the archives of ``pages`` to the shared folder, reads them back and merges their captures."""
    folder = scratch_path(pages.sparkSession, "warc")
    write(pages, folder)
    return merged(written(runs(pages.sparkSession, folder), "captures"))
