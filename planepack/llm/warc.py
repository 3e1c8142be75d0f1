"""WARC archives with a two-level capture index.

Writing: a record per page, as text in the exact WARC/1.1 form, by Spark's own text writer (its line separator is the record's closing
CRLF CRLF), so the commit protocol makes the files survive lost tasks and any file system Spark knows will do.  The block is
an HTTP response whose payload is the html.  Of records with equal payloads of at least ``min_revisit_bytes`` the one with the largest page_id is a
``response``; the others are ``revisit`` records that hold the HTTP header only and refer to it.

Index: every archive is read as a stream, record by record, each payload's digest is taken anew, and its capture entry keyed by the reversed-host URL
form.  Entries are range-sorted by key and packed into compressed blocks (level two); a sparse directory has first and last key of each
block (level one).

Lookup, for a whole table of URLs at once: tasks binary-search the directory, each block that is hit is opened once and binary-searched for all its
keys, and the records are read by byte ranges, those of an archive in order.  ``CaptureIndex`` does the same for one URL.  Archives are opened through
Arrow's file systems (``planepack.datasource.opened``).

Defined results: null html is an empty payload; null URLs are written as an empty target; a null page_id keeps a record without a number
and is reported as null; rows that repeat the largest page_id of a payload are all responses; an empty table gives an empty index.
"""

from __future__ import annotations

import base64
import bisect
import hashlib
import json
import re
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from planepack.datasource import opened
from planepack.storage import fresh

from . import common as C

CRLF = "\r\n"
ENTRIES_PER_BLOCK, RECORDS_PER_FILE = 1000, 2000
#: Base32 of a digest is read off the 32-digit numerals of its 40-bit pieces.  Fixed values.
DIGITS, BASE32 = "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def base32_sha1(payload):
    """Upper-case base32 of the SHA-1 of a string column, JVM-side."""
    h = F.sha1(payload)
    return F.concat(*(F.translate(F.lpad(F.conv(F.substring(h, 10 * i + 1, 10), 16, 32), 8, "0"), DIGITS, BASE32) for i in range(4)))


def described(pages: DataFrame, min_revisit_bytes: int = 0) -> DataFrame:
    """__id, __url, __html, __digest, __refers (null for responses)."""
    html = F.coalesce(F.col("html").cast("string"), F.lit(""))
    keys = pages.select(F.col("page_id").cast("long").alias("__id"), base32_sha1(html).alias("__digest"), F.octet_length(html).alias("__size"))
    repeated = keys.filter(F.col("__size") >= min_revisit_bytes).groupBy("__digest").agg(F.max("__id").alias("__last"), F.count(F.lit(1)).alias("__c")).filter("__c > 1").select(F.col("__digest").alias("__d"), "__last")
    repeated = C.written(repeated, "repeated")
    rows = pages.select(F.col("page_id").cast("long").alias("__id"), F.coalesce(F.col("url").cast("string"), F.lit("")).alias("__url"), html.alias("__html"), base32_sha1(html).alias("__digest"))
    joined = rows.join(C.small(repeated, repeated.count()), F.col("__digest") == F.col("__d"), "left")
    return joined.withColumn("__refers", F.when(F.col("__last") > F.coalesce("__id", F.lit(-(1 << 63))), F.col("__last"))).drop("__d", "__last")


def records(rows: DataFrame, date: str = "2024-01-01T00:00:00Z") -> DataFrame:
    """One text column: the record without its closing CRLF CRLF."""
    name = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("null")), F.lit(">"))
    length = F.octet_length("__html").cast("string")
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), length, F.lit(CRLF + CRLF))
    block = F.when(F.col("__refers").isNull(), F.concat(http, "__html")).otherwise(http)
    url = F.regexp_replace(F.regexp_replace("__url", "\r", "%0D"), "\n", "%0A")
    again = F.concat(F.lit(f"{CRLF}WARC-Refers-To: "), name(F.col("__refers")), F.lit(f"{CRLF}WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"))
    head = F.concat(
        F.lit(f"WARC/1.1{CRLF}WARC-Type: "), F.when(F.col("__refers").isNull(), F.lit("response")).otherwise(F.lit("revisit")),
        F.lit(f"{CRLF}WARC-Record-ID: "), name(F.col("__id")), F.lit(f"{CRLF}WARC-Date: {date}{CRLF}WARC-Target-URI: "), url,
        F.lit(f"{CRLF}WARC-Payload-Digest: sha1:"), F.col("__digest"), F.coalesce(again, F.lit("")),
        F.lit(f"{CRLF}Content-Type: application/http; msgtype=response{CRLF}Content-Length: "), F.octet_length("__block").cast("string"), F.lit(CRLF + CRLF),
    )
    return rows.withColumn("__block", block).select(F.concat(head, F.col("__block")).alias("value"))


def write_archives(pages: DataFrame, path: str, min_revisit_bytes: int = 0, records_per_file: int = RECORDS_PER_FILE) -> None:
    """Write ``page_id, url, html`` rows as WARC files under ``path``."""
    records(described(pages, min_revisit_bytes)).write.option("lineSep", CRLF + CRLF).option("maxRecordsPerFile", records_per_file).text(path)


def surt(url: str) -> str:
    """Reversed-host form of a URL: ``org,example,www)/path?query``."""
    m = re.match(r"(?s)[^:/?#]*://([^/?#]*)([^#]*)", url)
    if not m:
        return f"){url}"
    host, _, port = m[1].rpartition("@")[2].lower().partition(":")
    return ",".join(reversed(host.split("."))) + (f":{port}" if port else "") + ")" + (m[2] or "/")


def parse_records(data: bytes, base: int = 0):
    """(offset, length, headers, block) of the records in ``data``."""
    at = 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        lines = data[at:end].decode("utf-8").split(CRLF)
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no record at {base + at}")
        headers = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])
        stop = end + 4 + int(headers["Content-Length"])
        if data[stop : stop + 4] != b"\r\n\r\n":
            raise ValueError(f"the record at {base + at} does not end where it says")
        yield base + at, stop + 4 - at, headers, data[end + 4 : stop]
        at = stop + 4


def payload_of(block: bytes) -> tuple[dict, bytes]:
    end = block.index(b"\r\n\r\n")
    return dict(x.split(": ", 1) for x in block[:end].decode().split(CRLF)[1:]), block[end + 4 :]


def _number(name: str | None):
    m = re.fullmatch(r"<urn:page:(-?\d+)>", name or "")
    return int(m[1]) if m else None


_ENTRY = pa.schema([("key", pa.string()), ("entry", pa.string())])


def stream_records(f, chunk: int = 1 << 20):
    """The same from an open file; no more than a record and a chunk is held."""
    buf, at, base = b"", 0, 0  # the next record begins at buf[at], which is byte base + at of the file

    def more(n: int) -> bool:
        nonlocal buf, at, base
        got = f.read(max(chunk, n))
        buf, base, at = buf[at:] + got, base + at, 0
        return bool(got)

    while True:
        while (end := buf.find(b"\r\n\r\n", at)) < 0:
            if not more(0):
                if at < len(buf):
                    raise ValueError(f"the file ends inside the record at {base + at}")
                return
        lines = buf[at:end].decode("utf-8").split(CRLF)
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no record at {base + at}")
        headers = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])
        head = end + 4 - at
        length = head + int(headers["Content-Length"]) + 4
        while len(buf) - at < length:
            if not more(length - (len(buf) - at)):
                raise ValueError(f"the file ends inside the record at {base + at}")
        if buf[at + length - 4 : at + length] != b"\r\n\r\n":
            raise ValueError(f"the record at {base + at} does not end where it says")
        yield base + at, length, headers, buf[at + head : at + length - 4]
        at += length


def described_record(headers: dict, block: bytes) -> tuple:
    """(page_id, payload bytes, digest, type, refers to); a response's payload is held against what its headers say."""
    http, payload = payload_of(block)
    kind = headers["WARC-Type"]
    if kind == "response":
        digest, size = base64.b32encode(hashlib.sha1(payload).digest()).decode(), len(payload)
        if headers["WARC-Payload-Digest"] != f"sha1:{digest}" or int(http["Content-Length"]) != size:
            raise ValueError(f"the payload of {headers['WARC-Record-ID']} is damaged")
    else:
        digest, size = headers["WARC-Payload-Digest"].removeprefix("sha1:"), int(http["Content-Length"])
    return _number(headers["WARC-Record-ID"]), size, digest, kind, _number(headers.get("WARC-Refers-To"))


def _captures(batches):
    """Capture entries of whole archives: (key, [page, size, digest, type, refers to, archive, offset, length])."""
    for r in batches:
        for path in r.column(0).to_pylist():
            keys, entries = [], []
            store, at = opened(path)
            with store.open_input_stream(at) as f:
                for offset, length, h, block in stream_records(f):
                    keys.append(surt(h["WARC-Target-URI"]))
                    entries.append(json.dumps([*described_record(h, block), path, offset, length], separators=(",", ":")))
                    if len(keys) >= 4096:
                        yield C.batch(_ENTRY, keys, entries)
                        keys, entries = [], []
            if keys:
                yield C.batch(_ENTRY, keys, entries)


_BLOCK = pa.schema([("first_key", pa.string()), ("last_key", pa.string()), ("n", pa.int32()), ("data", pa.binary())])


def _blocks(batches, per_block):
    keys, entries = [], []

    def packed():
        return C.batch(_BLOCK, [keys[0]], [keys[-1]], [len(keys)], [zlib.compress("\n".join(f"{json.dumps(k)} {e}" for k, e in zip(keys, entries, strict=True)).encode(), 6)])

    for r in batches:
        for k, e in zip(r.column(0).to_pylist(), r.column(1).to_pylist(), strict=True):
            keys.append(k)
            entries.append(e)
            if len(keys) >= per_block:
                yield packed()
                keys, entries = [], []
    if keys:
        yield packed()


def unpack(data: bytes) -> list[tuple[str, list]]:
    out = []
    for line in zlib.decompress(data).decode().split("\n"):
        key, at = json.JSONDecoder().raw_decode(line)
        out.append((key, json.loads(line[at + 1 :])))
    return out


#: Blocks of the directory that the driver and the tasks hold at once.
DIRECTORY_ROWS = 200_000


def build_index(spark, archives: str, index: str, per_block: int = ENTRIES_PER_BLOCK) -> None:
    """Blocks of sorted captures under ``index/blocks`` and their sparse directory under ``index/directory``; ``block`` numbers ascend with the keys."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(archives).select("path")
    entries = C.written(files.transform(C.arrow, _captures, "key string, entry string"), "captures")
    order = entries.repartitionByRange("key", F.xxhash64("entry")).sortWithinPartitions("key", "entry")
    packed = order.transform(C.arrow, lambda b: _blocks(b, per_block), "first_key string, last_key string, n int, data binary")
    packed.withColumn("block", F.monotonically_increasing_id()).write.option("compression", "uncompressed").parquet(f"{index}/blocks")
    spark.read.parquet(f"{index}/blocks").select("block", "first_key", "last_key", "n").write.parquet(f"{index}/directory")
    C.forget(entries)


class Directory:
    """Sorted first and last keys of blocks."""

    def __init__(self, rows):
        self.rows = sorted((r.first_key, r.last_key, r.block) for r in rows)
        self.first, self.last = [r[0] for r in self.rows], [r[1] for r in self.rows]

    def blocks(self, key: str) -> list[int]:
        """Blocks that may hold the key; more than one only if its captures cross blocks."""
        hi = bisect.bisect_right(self.first, key)
        lo = bisect.bisect_left(self.last, key, 0, hi)
        return [b for _, _, b in self.rows[lo:hi]]


def matches(data: bytes, key: str, held: list | None = None) -> list[list]:
    """Entries of a key in a block."""
    rows = unpack(data) if held is None else held
    return [e for _, e in rows[bisect.bisect_left(rows, key, key=lambda x: x[0]) : bisect.bisect_right(rows, key, key=lambda x: x[0])]]


class CaptureIndex:
    """Lookups of single URLs: directory in memory behind a check of its size, one block per lookup, one byte range per record."""

    def __init__(self, spark, index: str):
        self.spark, self.index = spark, index
        rows = spark.read.parquet(f"{index}/directory")
        if (n := rows.count()) > DIRECTORY_ROWS:
            raise ValueError(f"the directory has {n} blocks: look up a table of URLs with lookup()")
        self.directory = Directory(rows.collect())

    def lookup(self, url: str) -> list[list]:
        key, found = surt(url), []
        for b in self.directory.blocks(key):
            for r in self.spark.read.parquet(f"{self.index}/blocks").filter(F.col("block") == b).select("data").collect():
                found += matches(bytes(r.data), key)
        return found

    def fetch(self, entry: list) -> tuple[dict, bytes]:
        """Headers and payload of a capture, by one range read."""
        _, _, headers, block = read_record(*entry[5:8])
        return headers, payload_of(block)[1]


def read_record(path: str, offset: int, length: int):
    store, at = opened(path)
    with store.open_input_file(at) as f:
        f.seek(offset)
        return next(parse_records(f.read(length), offset))


_PLACE = pa.schema([("archive", pa.string()), ("offset", pa.int64()), ("length", pa.int64())])


def lookup(spark, index: str, urls: DataFrame, directory_rows: int = DIRECTORY_ROWS) -> DataFrame:
    """(archive, offset, length) of every capture of the URLs in the one column of ``urls``; null URLs are empty targets, repeated ones are looked up once.

    A directory beyond ``directory_rows`` blocks is searched part by part.
    """

    def keyed(batches):
        schema = pa.schema([("key", pa.string())])
        for r in batches:
            yield C.batch(schema, [surt(u) for u in r.column(0).to_pylist()])

    target = F.regexp_replace(F.regexp_replace(F.coalesce(F.col(urls.columns[0]).cast("string"), F.lit("")), "\r", "%0D"), "\n", "%0A")
    keys = urls.select(target.alias("url")).distinct().transform(C.arrow, keyed, "key string").distinct()
    sparse = spark.read.parquet(f"{index}/directory").select("block", "first_key", "last_key")
    parts = max(1, -(-sparse.count() // directory_rows))
    keys = C.written(keys, "keys") if parts > 1 else keys
    hit = None
    for p in range(parts):
        held = spark.sparkContext.broadcast(Directory(sparse.filter(F.pmod(F.xxhash64("block"), F.lit(parts)) == p).collect()))

        def search(batches, held=held):
            schema = pa.schema([("block", pa.int64()), ("key", pa.string())])
            for r in batches:
                found = [(b, k) for k in r.column(0).to_pylist() for b in held.value.blocks(k)]
                if found:
                    yield C.batch(schema, *map(list, zip(*found, strict=True)))

        got = keys.transform(C.arrow, search, "block long, key string")
        hit = got if hit is None else hit.unionByName(got)

    def opened_blocks(batches):
        for r in batches:
            for data, wanted in zip(r.column(0).to_pylist(), r.column(1).to_pylist(), strict=True):
                held = unpack(data)
                found = [e[5:8] for k in wanted for e in matches(data, k, held)]
                if found:
                    yield C.batch(_PLACE, *map(list, zip(*found, strict=True)))

    per_block = hit.groupBy("block").agg(F.collect_list("key").alias("keys"))  # distinct keys of one block's range
    blocks = spark.read.parquet(f"{index}/blocks").select("block", "data")
    return blocks.join(per_block, "block").select("data", "keys").transform(C.arrow, opened_blocks, "archive string, offset long, length long")


_PAGE = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("archive", pa.string()), ("offset", pa.int64())])
PAGE_DDL = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, archive string, offset long"


def read_pages(places: DataFrame) -> DataFrame:
    """What the records at (archive, offset, length) hold, by range reads; the ranges of an archive are read in order by one task, one record at a time."""

    def run(batches):
        path = f = None
        try:
            for r in batches:
                rows = []
                for archive, offset, length in zip(*(c.to_pylist() for c in r.columns), strict=True):
                    if archive != path:
                        if f is not None:
                            f.close()
                        store, at = opened(archive)
                        path, f = archive, store.open_input_file(at)
                    f.seek(offset)
                    _, _, headers, block = next(parse_records(f.read(length), offset))
                    rows.append((*described_record(headers, block), archive, offset))
                if rows:
                    yield C.batch(_PAGE, *map(list, zip(*rows, strict=True)))
        finally:
            if f is not None:
                f.close()

    return places.repartition("archive").sortWithinPartitions("archive", "offset").transform(C.arrow, run, PAGE_DDL)


def read_captures(spark, index: str) -> DataFrame:
    """All captures of an index as rows, from the entries alone."""

    def run(batches):
        for r in batches:
            for data in r.column(0).to_pylist():
                rows = [e[:7] for _, e in unpack(data)]
                yield C.batch(_PAGE, *(list(x) for x in zip(*rows, strict=True)))

    return spark.read.parquet(f"{index}/blocks").select("data").transform(C.arrow, run, PAGE_DDL)


def op4(spark, sf_dir):
    """Write, index, and read every page's record back through the index: directory, block, byte range."""
    pages = C.table(spark, sf_dir, "pages", "page_id", "url", "html")
    where = fresh(spark, "warc")
    write_archives(pages, f"{where}/archives")
    build_index(spark, f"{where}/archives", f"{where}/index")
    return read_pages(lookup(spark, f"{where}/index", pages.select("url"))).drop("archive", "offset")


OP4_SQL = """
with p as (select page_id, coalesce(html, '') as h, max(page_id) over (partition by coalesce(html, '')) as last from pages),
x as (select *, unhex(sha1(h)) as d from p),
b as (select *, rpad(replace(bit_string, ' ', ''), 160, '0') as bits from (select *, cast(cast(d as bit) as varchar) as bit_string from x))
select cast(page_id as bigint) as page_id, cast(strlen(h) as bigint) as payload_bytes,
  array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', cast(list_reduce(list_transform(range(1, 6), lambda j: cast(substr(bits, i * 5 + j, 1) as integer)), lambda a, v: a * 2 + v) as integer) + 1, 1)), '') as payload_digest,
  case when page_id = last then 'response' else 'revisit' end as record_type, case when page_id = last then null else cast(last as bigint) end as refers_to from b
"""
