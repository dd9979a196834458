"""WARC archives with a two-level capture index (operator 10).

``write_archives`` writes one record per page through Spark's own text writer: the row
is the whole record and the line separator is the blank lines that end a record, so the
files are plain WARC 1.1 and reach any store Spark can write to.  Of records with equal
payloads the one with the smallest page_id is a response, the others are revisits that
name it.

``read_archives`` parses whole files (bounded bytes each: large payloads are written apart,
fewer to a file), with the byte offset and length of every record, and takes the digest of
every payload anew.  ``check_revisits`` holds every revisit against the response it names.

``build_index`` sorts capture lines by reversed-host key, packs them into compressed
blocks and keeps a sparse directory of (first key, last key, block); both are tables in
the shared folder.  ``lookup`` searches the directory by bisection, reads only the blocks
that can hold the key, bisects inside them and reads the record's bytes by range.

Defined results for odd rows: null and empty html are empty payloads (one equal group);
a null url is the empty key; line breaks and per cent signs of a url are written per cent
encoded and decoded again; repeated page rows are records of their own, every row with
the smallest page_id of its payload being a response; a null page_id is written as such,
and is a response only if its payload has no other page_id; an empty table gives empty
archives.  Extra columns are ignored.
"""

from __future__ import annotations

import base64
import bisect
import hashlib
import json
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, shared_dir, ship

#: (bytes of payload up to which, records in a file): a file stays below 64 MB or is one record.
TIERS = ((32 << 10, 2_000), (512 << 10, 120), (8 << 20, 7), (1 << 62, 1))
#: Capture lines in a block, bytes of revisit table that may be broadcast.
LINES, BROADCAST = 3_000, 16 << 20
CAPTURE = "key string, page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, file string, offset long, length long"
EMPTY = "unset"


def base32_of_hex(digest: Column) -> Column:
    """Bare upper-case base32 of a 40-digit hexadecimal string, in built-in functions."""
    bits = F.concat(*[F.lpad(F.conv(F.substring(digest, 1 + 10 * i, 10), 16, 2), 40, "0") for i in range(4)])
    letters = [F.substring(F.lit("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"), F.conv(F.substring(bits, 1 + 5 * i, 5), 2, 10).cast("int") + 1, F.lit(1)) for i in range(32)]
    return F.concat(*letters)


def host_key(url: Column) -> Column:
    """Sort key: the host's labels reversed, then path and query, e.g. ``org,example)/a?b``."""
    rest = F.regexp_replace(F.coalesce(url, F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?", "")
    host = F.lower(F.regexp_extract(rest, r"^([^/?#:]*)", 1))
    path = F.regexp_replace(F.regexp_replace(rest, r"^[^/?#]*", ""), r"#.*$", "")
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.")), ","), F.lit(")"), path)


def _records(pages: DataFrame) -> DataFrame:
    """Pages with their payload digest and what they are: response, or revisit of an id."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    rows = rows.withColumn("sha", F.sha1(F.col("html").cast("binary")))
    # only payloads that occur more than once need a word with each other
    groups = materialise(rows.groupBy("sha").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"))
    small = groups.count() * 64 <= BROADCAST
    rows = rows.join(F.broadcast(groups) if small else groups, "sha", "left")
    return rows.withColumn("refers_to", F.when(F.col("page_id").isNull() | (F.col("page_id") != F.col("first")), F.col("first")))


def quoted(url: Column) -> Column:
    """The URL on one line: per cent signs and line breaks become per cent codes."""
    for mark, code in (("%", "%25"), ("\r", "%0D"), ("\n", "%0A")):
        url = F.replace(url, F.lit(mark), F.lit(code))
    return url


def record_text(row: DataFrame) -> DataFrame:
    """The column ``value``: a whole record without the blank lines that end it."""
    end = "\r\n"
    size = F.octet_length("html")
    revisit = F.col("refers_to").isNotNull()
    name = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(F.col(c).cast("string"), F.lit(EMPTY)), F.lit(">"))
    head = F.concat_ws(
        end,
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), F.when(revisit, "revisit").otherwise("response")),
        F.concat(F.lit("WARC-Record-ID: "), name("page_id")),
        F.lit("WARC-Date: 1970-01-01T00:00:00Z"),
        F.concat(F.lit("WARC-Target-URI: "), quoted(F.coalesce("url", F.lit("")))),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), base32_of_hex(F.col("sha"))),
        F.concat(F.lit("WARC-Payload-Bytes: "), size.cast("string")),
        F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), name("refers_to"))),
        F.when(revisit, F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        F.lit("Content-Type: text/html; charset=utf-8"),
        F.concat(F.lit("Content-Length: "), F.when(revisit, F.lit(0)).otherwise(size).cast("string")),
    )
    return row.select(F.concat(head, F.lit(end + end), F.when(revisit, "").otherwise(F.col("html"))).alias("value"))


def write_archives(pages: DataFrame, path: str) -> None:
    """Files below ``path``, one folder for each size of payload that occurs."""
    rows = _records(pages)
    size = F.when(F.col("refers_to").isNotNull(), 0).otherwise(F.octet_length("html"))
    least, most = rows.agg(F.coalesce(F.min(size), F.lit(0)), F.coalesce(F.max(size), F.lit(0))).first()
    low = -1
    for k, (high, records) in enumerate(TIERS):
        if (most > low and least <= high) or not k:
            own = rows if low < least and most <= high else rows.where((size > low) & (size <= high))
            record_text(own).write.option("lineSep", "\r\n\r\n").option("maxRecordsPerFile", records).text(f"{path}/size{k}")
        low = high


def parse(data: bytes) -> Iterator[tuple[int, int, dict[str, str], bytes]]:
    """(offset, length, headers, block) of each record of an archive."""
    at = 0
    while at < len(data):
        head = data.index(b"\r\n\r\n", at)
        lines = data[at:head].decode("utf-8").split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no record at byte {at}")
        fields = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines[1:])
        end = head + 4 + int(fields["Content-Length"])
        yield at, end - at, fields, data[head + 4 : end]
        at = end + 4


def _number(name: str | None) -> int | None:
    word = name[len("<urn:page:") : -1] if name else EMPTY
    return None if word == EMPTY else int(word)


def _capture_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", "file", "offset", "length"]
    kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64()]
    for batch in batches:
        for file, data in zip(batch.column(0), batch.column(1), strict=True):
            rows = []
            for offset, length, head, block in parse(data.as_py()):
                digest, size = head["WARC-Payload-Digest"].removeprefix("sha1:"), int(head["WARC-Payload-Bytes"])
                if head["WARC-Type"] == "response":
                    digest, size = base64.b32encode(hashlib.sha1(block).digest()).decode(), len(block)
                    if digest != head["WARC-Payload-Digest"].removeprefix("sha1:"):
                        raise ValueError(f"payload of {head['WARC-Record-ID']} does not have its digest")
                url = head["WARC-Target-URI"].replace("%0A", "\n").replace("%0D", "\r").replace("%25", "%")
                rows.append((_number(head["WARC-Record-ID"]), url, head["WARC-Type"], _number(head.get("WARC-Refers-To")), size, digest, file.as_py(), offset, length))
            columns = list(zip(*rows, strict=True)) or [[] for _ in names]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """One capture per record, read back from the files."""
    files = spark.read.format("binaryFile").load(f"{path}/size*").where("length > 0").select("path", "content")
    plain = CAPTURE.removeprefix("key string, ")
    rows = files.mapInArrow(_capture_batches, plain)
    return rows.select(host_key(F.col("url")).alias("key"), "*")


def _block_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    waiting: list[tuple[str, str]] = []

    def pack(lines: list[tuple[str, str]]) -> pa.RecordBatch:
        packed = zlib.compress("\n".join(line for _, line in lines).encode())
        return pa.RecordBatch.from_arrays([pa.array([lines[0][0]]), pa.array([lines[-1][0]]), pa.array([len(lines)], pa.int64()), pa.array([packed], pa.binary())], names=["first", "last", "n", "block"])

    for batch in batches:
        waiting += zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)
        while len(waiting) >= LINES:
            yield pack(waiting[:LINES])
            waiting = waiting[LINES:]
    if waiting:
        yield pack(waiting)


def build_index(captures: DataFrame) -> DataFrame:
    """Blocks (first, last, n, block) of capture lines in key order, in the shared folder.

    Ordering by key and page_id together splits a host that holds a third of all rows.
    """
    lines = captures.select("key", "page_id", F.to_json(F.struct(*[c for c in captures.columns])).alias("line"))
    ordered = lines.orderBy("key", "page_id").select("key", "line")
    return materialise(ordered.mapInArrow(_block_batches, "first string, last string, n long, block binary"))


def _unpack_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for block in batch.column(0).to_pylist():
            yield pa.RecordBatch.from_arrays([pa.array(zlib.decompress(block).decode().split("\n"), pa.string())], names=["line"])


def read_index(index: DataFrame) -> DataFrame:
    """All captures that an index holds."""
    lines = index.select("block").mapInArrow(_unpack_batches, "line string")
    return lines.select(F.from_json("line", CAPTURE).alias("c")).select("c.*")


def directory(index: DataFrame) -> list[tuple[str, str]]:
    """The sparse upper level: (first, last) key of each block, one row for LINES captures."""
    return sorted((r["first"], r["last"]) for r in index.select("first", "last").collect())


def lookup(index: DataFrame, url: str, upper: list[tuple[str, str]] | None = None) -> list[dict]:
    """Captures of a URL (absent keys are null): bisect the directory, read the blocks that can hold it, bisect inside."""
    spark = index.sparkSession
    key = spark.range(1).select(host_key(F.lit(url))).first()[0]
    upper = directory(index) if upper is None else upper
    end = bisect.bisect_right([first for first, _ in upper], key)
    hits = []
    for first, last in sorted({b for b in upper[:end] if b[1] >= key}):
        for row in index.where((F.col("first") == first) & (F.col("last") == last)).select("block").collect():
            lines = [json.loads(x) for x in zlib.decompress(row.block).decode().split("\n")]
            low, high = (side(lines, key, key=lambda x: x["key"]) for side in (bisect.bisect_left, bisect.bisect_right))
            hits += lines[low:high]
    return hits


def read_record(spark: SparkSession, file: str, offset: int, length: int) -> tuple[dict[str, str], bytes]:
    """Headers and payload of one record, by a range read through the store's own client."""
    jvm = spark._jvm
    path = jvm.org.apache.hadoop.fs.Path(file)
    stream = path.getFileSystem(spark._jsc.hadoopConfiguration()).open(path)
    try:
        stream.seek(offset)
        data = bytes(jvm.org.apache.commons.io.IOUtils.toByteArray(stream, length))
    finally:
        stream.close()
    _, _, head, block = next(parse(data))
    return head, block


def check_revisits(captures: DataFrame) -> None:
    """Raises if a revisit does not have the digest and size of the response that it names."""
    payload = ["payload_digest", "payload_bytes"]
    said = captures.where("record_type = 'revisit'").select("refers_to", *payload).distinct()
    held = captures.where("record_type = 'response'").select(F.col("page_id").alias("refers_to"), *payload)
    lost = said.join(held, ["refers_to", *payload], "left_anti").limit(1).collect()
    if lost:
        raise ValueError(f"the payload of a revisit of page {lost[0].refers_to} is not there")


def archive_round_trip(pages: DataFrame) -> DataFrame:
    """Write, read back, check, index, and return the captures out of the index."""
    path = shared_dir(pages.sparkSession)
    write_archives(pages, path)
    captures = materialise(read_archives(pages.sparkSession, path))
    check_revisits(captures)
    return read_index(build_index(captures))


ORACLE = None  # base32 of a SHA-1 has no counterpart in DuckDB; tests compare with hashlib

ship(__name__)
