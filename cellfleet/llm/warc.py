"""WARC archives of pages, and their capture index merged from locally sorted runs.

Pages are written as WARC/1.1 files through Spark's text sink (any store Spark can write to), a gzip member per record, so
that an index row's offset and length in the file are enough to read its record. The sink ends every row with a zero byte,
which is the last byte of the member: the high byte of its length, or, from 16 MB on, the end of an empty member after it.
Of records with equal payloads the one with the smallest page_id is a response, all others are revisits that refer to it and
carry no payload. Files are read back as binaries, member by member, parsed by their lengths and checked against their
digests; each file gives one run of its captures sorted by URL key and time. The runs are dealt by ranges of that key, as
many as their rows ask for, and sorted by run in Spark's external sort; each range merges its share of every run with a loser
tree, a few rows of a run at a time, so that the ranges one after another are the globally ordered capture history.

A null html is an empty payload, a null url is written as an empty one. A null page_id is larger than any other. Of repeated
rows of the smallest page_id one is the response. The capture time is a bounded function of the page_id, or a given column.
An empty table gives an empty result. A single payload must fit memory, an archive file holds ``FILE_BYTES`` and one payload more.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import re
import zlib
from collections.abc import Callable, Iterator, Sequence
from urllib.parse import urlsplit

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellfleet.llm.common import HEAVY, cut, onto, scratch, table

EPOCH, CAPTURE_SECONDS = "2024-01-01 00:00:00", 100_000_000
#: Captures of a range of the merge, about, and rows of a run that its reader holds.
RANGE_ROWS, READ_ROWS = 100_000, 64
#: Payload of an archive file, about, and the most records it has.
FILE_BYTES, FILE_RECORDS = 16 << 20, 20_000
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
INDEX = "page_id bigint, url string, url_key string, captured string, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, file string, offset bigint, length bigint"


def digest(payload: Column) -> Column:
    """SHA-1 in upper-case base32: five hexadecimal digits are four characters."""
    h = F.sha1(payload)
    out = []
    for i in range(8):
        n = F.conv(F.substring(h, 5 * i + 1, 5), 16, 10).cast("int")
        for shift in (15, 10, 5, 0):
            out.append(F.substring(F.lit(BASE32), F.shiftright(n, shift).bitwiseAND(F.lit(31)) + 1, F.lit(1)))
    return F.concat(*out)


def typed(pages: DataFrame, captured: str | None = None, least: int = HEAVY) -> tuple[DataFrame, int]:
    """(page_id, url, w_html, w_digest, w_type, w_first, w_when) and the bytes of all payloads: only ids, urls and digests are
    compared and shuffled. Rows that repeat in all of these stay one row with their number until the last step, so that a
    group of them is no task's burden, and only its first row keeps the html."""
    when_ = F.timestamp_seconds(F.unix_timestamp(F.lit(EPOCH)) + F.pmod(F.coalesce("page_id", F.lit(0)), F.lit(CAPTURE_SECONDS)))
    when_ = when_ if captured is None else F.coalesce(F.col(captured).cast("timestamp"), when_)
    d = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("w_html"), when_.alias("w_when")).withColumn("w_digest", digest(F.col("w_html").cast("binary")))
    same = ["page_id", "url", "w_digest", "w_when"]
    small = cut(d.groupBy(*same).agg(F.count("*").alias("w_n"), F.max(F.octet_length("w_html")).alias("w_bytes")))
    order_ = F.struct(F.col("page_id").isNull().alias("lost"), "page_id", "url", "w_when")
    first = cut(small.groupBy("w_digest").agg(F.min(order_).alias("w_least"), F.count("*").alias("w_rows"), F.max("w_n").alias("w_most")))
    hot = cut(first.where(F.col("w_rows") > least).select("w_digest"), 1)
    known = onto(small, first.select("w_digest", "w_least"), "w_digest", None if hot.isEmpty() else hot)
    known = known.withColumn("w_is_first", order_ == F.col("w_least")).withColumn("w_first", F.col("w_least.page_id"))
    known = known.select(*[F.col(c).alias(f"k_{c}") for c in same], "w_n", "w_is_first", "w_first")
    meets = [F.col(c).eqNullSafe(F.col(f"k_{c}")) for c in same]
    if first.where("w_most > 1").isEmpty():
        out = d.join(known, meets).withColumn("w_again", ~F.col("w_is_first"))
    else:
        whole = d.groupBy(*same).agg(F.first("w_html").alias("w_html")).join(known, meets)
        out = whole.withColumn("w_i", F.explode(F.sequence(F.lit(1).cast("long"), F.col("w_n")))).withColumn("w_again", ~F.col("w_is_first") | (F.col("w_i") > 1))
    total = small.agg(F.sum(F.col("w_bytes") * F.col("w_n")).alias("n")).first()["n"] or 0
    return out.withColumn("w_type", F.when(F.col("w_again"), "revisit").otherwise("response")), total


def record(crlf: str = "\r\n") -> Column:
    """The record of a row of ``typed``, with the two line ends that close it."""
    ident = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("null")), F.lit(">"))
    n = F.octet_length("w_html").cast("string")
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{crlf}Content-Type: text/html; charset=utf-8{crlf}Content-Length: "), n, F.lit(crlf * 2))
    again = F.col("w_type") == "revisit"
    block = F.concat(http, F.when(again, "").otherwise(F.col("w_html")))
    when_ = F.date_format("w_when", "yyyy-MM-dd'T'HH:mm:ss'Z'")
    lines = [
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), F.col("w_type")),
        F.concat(F.lit("WARC-Record-ID: "), ident(F.col("page_id"))),
        F.concat(F.lit("WARC-Date: "), when_),
        F.concat(F.lit("WARC-Target-URI: "), F.regexp_replace(F.coalesce("url", F.lit("")), r"[\r\n]", "")),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("w_digest")),
        F.when(again, F.concat(F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest" + crlf + "WARC-Refers-To: "), ident(F.col("w_first")))),
        F.lit("Content-Type: application/http; msgtype=response"),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    ]
    return F.concat(F.concat_ws(crlf, *lines), F.lit(crlf * 2), block, F.lit(crlf * 2))


#: An empty gzip member, which ends in a zero byte.
NOTHING = gzip.compress(b"", 1, mtime=0)


def member(record_: bytes, level: int = 1) -> bytes:
    """A gzip member of the record, without the zero byte that it ends in."""
    out = gzip.compress(record_, level, mtime=0)
    return (out if out[-1] == 0 else out + NOTHING)[:-1]


def compressed(records: DataFrame, level: int = 1) -> DataFrame:
    """``records(value)`` as members, in text rows that hold their bytes as they are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([member(x.as_buffer(), level) for x in b.column(0)], pa.binary())], names=["value"])

    return records.mapInArrow(run, "value binary").select(F.col("value").cast("string").alias("value"))


def members(data: bytes) -> Iterator[tuple[int, int, bytes]]:
    """(offset, length, content) of the records of an archive, one unpacked at a time; an empty member belongs to the one before it."""
    view, at = memoryview(data).cast("B"), 0
    while at < len(view):
        begin, parts = at, []
        while at < len(view) and (not parts or view[at : at + len(NOTHING)] == NOTHING):
            one = zlib.decompressobj(wbits=31)
            # as much as the record needs: what follows it is handed in piece by piece
            piece = 1 << 16
            while not one.eof:
                if at >= len(view):
                    raise ValueError(f"no whole member at byte {begin}")
                parts.append(one.decompress(view[at : at + piece]))
                at += min(piece, len(view) - at) - len(one.unused_data)
        yield begin, at - begin, b"".join(parts)


def write(pages: DataFrame, path: str, file_bytes: int = FILE_BYTES, file_records: int = FILE_RECORDS, captured: str | None = None) -> None:
    out, payload = typed(pages, captured)
    out = out.select(record().alias("value")).coalesce(max(1, -(-payload // file_bytes)))
    compressed(out.select(F.col("value").cast("binary").alias("value"))).write.option("lineSep", "\0").option("compression", "none").option("maxRecordsPerFile", file_records).text(path)


def url_key(url: str) -> str:
    """Host labels in reverse, then path and query, all in lower case; scheme, port, www and fragment don't count."""
    try:
        u = urlsplit(url.strip())
        host = (u.hostname or "").removeprefix("www.")
    except ValueError:
        return url.lower()
    return ",".join(reversed(host.split("."))) + ")" + (u.path or "/").lower() + (f"?{u.query.lower()}" if u.query else "")


def page(ident: str) -> int | None:
    number = re.fullmatch(r"<urn:page:(-?\d+|null)>", ident)[1]
    return None if number == "null" else int(number)


def parse(data: bytes, file: str) -> Iterator[tuple]:
    """Index rows of the records of an archive; raises if a length or digest doesn't hold."""
    for at, length, record_ in members(data):
        head = record_.index(b"\r\n\r\n")
        lines = record_[:head].decode("utf-8", "replace").split("\r\n")
        fields = dict(x.split(": ", 1) for x in lines[1:])
        start, n = head + 4, int(fields["Content-Length"])
        end = start + n
        if lines[0] != "WARC/1.1" or record_[end:] != b"\r\n\r\n":
            raise ValueError(f"no whole record at byte {at} of {file}")
        body = record_.index(b"\r\n\r\n", start) + 4
        size = int(re.search(rb"\r\nContent-Length: (\d+)", record_[start:body])[1])
        told, again = fields["WARC-Payload-Digest"].removeprefix("sha1:"), fields["WARC-Type"] == "revisit"
        if not again and (end - body != size or base64.b32encode(hashlib.sha1(memoryview(record_)[body:end]).digest()).decode() != told):
            raise ValueError(f"digest of the record at byte {at} of {file} doesn't hold")
        url, refers = fields["WARC-Target-URI"], page(fields["WARC-Refers-To"]) if again else None
        yield page(fields["WARC-Record-ID"]), url, url_key(url), fields["WARC-Date"], size, told, fields["WARC-Type"], refers, file, at, length


def order(row: Sequence) -> tuple:
    return row[2], row[3], row[0] is None, row[0] or 0, row[8], row[9]


NAMES = [x.split()[0] for x in INDEX.split(", ")]
ARROW = pa.schema([(n, pa.int64() if t == "bigint" else pa.string()) for n, t in (x.split() for x in INDEX.split(", "))])


def batch(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [[] for _ in NAMES]
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, ARROW, strict=True)], schema=ARROW)


def runs(spark: SparkSession, path: str) -> DataFrame:
    """One sorted run of index rows per archive file."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for name, content in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                yield batch(sorted(parse(content.as_buffer(), name.rpartition("/")[2]), key=order))

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path)
    return files.select("path", "content").mapInArrow(read, INDEX)


class LoserTree:
    """Merges sorted runs: inner nodes keep the loser of their match, so that each next row costs one path to the root."""

    def __init__(self, sorted_runs: Sequence[Sequence], key: Callable):
        self.runs, self.key = [iter(r) for r in sorted_runs], key
        self.k = len(self.runs)
        self.heads = [next(r, None) for r in self.runs]
        self.keys = [None if h is None else key(h) for h in self.heads]
        self.tree = [-1] * max(1, self.k)
        for i in range(self.k):
            self._play(i)

    def _loses(self, a: int, b: int) -> bool:
        """Whether run a loses against run b: it has ended, or its head is later; ties go to the earlier run."""
        x, y = self.keys[a], self.keys[b]
        return x is None or y is not None and (y, b) < (x, a)

    def _play(self, i: int) -> None:
        winner, node = i, (i + self.k) // 2
        while node > 0:
            other = self.tree[node]
            if other < 0:  # still being built: wait here for the other side
                self.tree[node] = winner
                return
            if self._loses(winner, other):
                self.tree[node], winner = winner, other
            node //= 2
        self.tree[0] = winner

    def __iter__(self) -> Iterator:
        while self.k and self.keys[w := self.tree[0]] is not None:
            yield self.heads[w]
            self.heads[w] = next(self.runs[w], None)
            self.keys[w] = None if self.heads[w] is None else self.key(self.heads[w])
            self._play(w)


def reader(share: pa.Table, rows: int = READ_ROWS) -> Iterator[tuple]:
    """The rows of a sorted run, a few at a time."""
    for at in range(0, share.num_rows, rows):
        yield from zip(*(c.to_pylist() for c in share.slice(at, rows).columns), strict=True)


def merge(index: DataFrame, rows: int | None = None, range_rows: int = RANGE_ROWS) -> DataFrame:
    """The capture history: ranges of (url_key, captured), each merged from its shares of the runs. ``rows``: of the index."""
    rows = index.count() if rows is None else rows

    def one(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = pa.Table.from_batches(batches, ARROW)
        files = whole.column("file").combine_chunks().dictionary_encode()
        number = files.indices.to_numpy(zero_copy_only=False)
        starts = [0, *(np.flatnonzero(np.diff(number)) + 1).tolist(), len(number)] if len(number) else [0]
        out: list[tuple] = []
        for row in LoserTree([reader(whole.slice(a, b - a)) for a, b in zip(starts, starts[1:], strict=False)], order):
            out.append(row)
            if len(out) == 4096:
                yield batch(out)
                out = []
        yield batch(out)

    keys = ["url_key", "captured", F.col("page_id").asc_nulls_last(), "file", "offset"]
    dealt = index.repartitionByRange(max(1, -(-rows // range_rows)), *keys)
    return dealt.sortWithinPartitions("file", *keys).mapInArrow(one, INDEX)


def archive(pages: DataFrame, path: str, captured: str | None = None) -> DataFrame:
    """Writes the archives to ``path`` and returns their merged index, read back from them."""
    write(pages, path, captured=captured)
    return merge(cut(runs(pages.sparkSession, path)))


def op10_warc_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = archive(table(spark, sf_dir, "pages"), scratch(spark, "warc"))
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


_CHARS = " || ".join(
    f"substr('{BASE32}', (((('0x' || substr(sha, {5 * i + 1}, 5))::bigint >> {shift}) & 31) + 1)::bigint, 1)" for i in range(8) for shift in (15, 10, 5, 0)
)
ORACLE_SQL = f"""
with p as (select page_id, coalesce(html, '') as html from pages), h as (select page_id, octet_length(encode(html))::bigint as n, sha1(html) as sha from p),
f as (select page_id, n, {_CHARS} as digest, min(page_id) over (partition by sha) as first, row_number() over (partition by sha order by page_id nulls last) as place from h)
select page_id, n as payload_bytes, digest as payload_digest, case when place = 1 then 'response' else 'revisit' end as record_type,
 case when place > 1 then first end as refers_to from f
"""
