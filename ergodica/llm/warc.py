"""A content-addressed WARC archive of pages.

``write`` decides by a strong digest (SHA-256 of the payload) which record of a group of equal payloads keeps the bytes: the
largest page_id is the response, the others are revisits of it. Only digests and ids are grouped and joined; payloads meet the decision by
page, so one that a third of all pages share is never gathered. The archives are gzip files of WARC/1.0 records, written by Spark's own text
writer (the records' closing line ends are its line separator; a file is one gzip member), so they can lie in any store that Spark reaches and
a file appears only when its task is done. Pages are dealt by payload size into classes whose files hold 64 MB of payloads at most.

``read`` parses the archives as a stream by their Content-Length, whatever bytes the payloads hold, and verifies the SHA-256 and the SHA-1 of every payload;
``store`` splits what was read into payloads (once each, under the verified SHA-256) and exact headers; ``originals`` joins them
again, payloads of hot digests repeated for a bounded number of salts.

Defined results. Null html: the empty payload. Null url: no target header. Null page_id: never chosen as response while its
group has a row with an id; a group without ids is all responses. Repeated rows: each has its record; rows that repeat a page and its payload are one
record to the archive and share its identifier; rows that repeat the largest page_id are all
responses. Payloads below ``least`` bytes are all responses. A payload above 1 MB shares its file with three others at most. Empty table: no records. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
from collections.abc import Iterator
from datetime import datetime, timezone

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import give_back, slim, work_path, written

END = "\r\n\r\n"
CLASSES = ((64 << 10, 1024), (1 << 20, 64), (None, 4))  # (payload bytes at most, records of a file): 64 MB of payloads a file, or four larger ones
# Fixed value: the profile the WARC standard names for revisits of equal payloads.
PROFILE = "http://netpreserve.org/warc/1.0/revisit/identical-payload-digest"
_HEX32, _BASE32 = "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def base32_sha1(c: Column) -> Column:
    """Upper-case base32 of the SHA-1 of a binary or string column, made of eight groups of 20 bits."""
    digest = F.sha1(c)
    groups = [F.lpad(F.conv(F.substring(digest, 5 * i + 1, 5), 16, 32), 4, "0") for i in range(8)]
    return F.translate(F.concat(*groups), _HEX32, _BASE32)


def _strong(html: Column) -> Column:
    return F.sha2(F.encode(html, "UTF-8"), 256)


def _hot(keys: DataFrame, name: str) -> DataFrame:
    """strong, salts of the digests that more rows of ``keys`` have than an even share of a partition: fewer than there are partitions."""
    parts = int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    counts = written(keys.groupBy("strong").agg(F.count("*").alias("n")).where("n > 1"), name)
    share = max(1, (counts.agg(F.sum("n")).first()[0] or 0) // parts)
    return counts.where(F.col("n") > share).select("strong", F.ceil(F.col("n") / share).cast("int").alias("salts"))


def revisits(digests: DataFrame, least: int = 0) -> DataFrame:
    """page_id, strong, response_id of the pages that are revisits; ``digests``: page_id, strong, payload_bytes. Ids and digests are all that moves."""
    some = digests.where(F.col("payload_bytes") >= least).select("page_id", "strong")
    groups = some.groupBy("strong").agg(F.max("page_id").alias("response_id"), F.count("*").alias("n")).where("n > 1 and response_id is not null").drop("n")
    hot = F.broadcast(_hot(some, "copies").select("strong"))
    named = some.join(hot, "strong").join(F.broadcast(groups.join(hot, "strong")), "strong")  # hot groups: fewer than partitions
    rest = some.join(hot, "strong", "left_anti").join(groups, "strong")
    return named.unionByName(rest).where(~F.col("page_id").eqNullSafe(F.col("response_id"))).select("page_id", "strong", "response_id").distinct()


def write(pages: DataFrame, path: str, least: int = 0, date: str | None = None) -> None:
    """One WARC record per row of ``pages`` into gzip archives under ``path``; ``date``: of all records (ISO 8601; now)."""
    base = slim(pages, "page_id", "url", "html").withColumn("html", F.coalesce("html", F.lit("")))
    full = base.withColumns({"payload_bytes": F.octet_length("html").cast("long"), "strong": _strong(F.col("html"))})
    digests = written(full.select("page_id", "strong", "payload_bytes"), "digests")
    of = written(revisits(digests, least), "revisits").select(F.col("page_id").alias("__page"), F.col("strong").alias("__strong"), "response_id", F.lit(True).alias("revisit"))
    d = full.join(of, full["page_id"].eqNullSafe(F.col("__page")) & (F.col("strong") == F.col("__strong")), "left")
    revisit = F.coalesce("revisit", F.lit(False))
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit("\r\n"))
    ident = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("")), F.lit(":"), F.col("strong"), F.lit(">"))
    header = F.concat(
        F.lit("WARC/1.0\r\n"),
        line("WARC-Type", F.when(revisit, "revisit").otherwise("response")),
        line("WARC-Record-ID", ident(F.col("page_id"))),
        line("WARC-Date", F.lit(date or datetime.now(timezone.utc).strftime("%Y-%m-%dT%H:%M:%SZ"))),
        F.coalesce(line("WARC-Target-URI", F.regexp_replace("url", r"[\r\n]", "%0A")), F.lit("")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), base32_sha1(F.encode("html", "UTF-8")))),
        F.when(revisit, F.concat(line("WARC-Refers-To", ident(F.col("response_id"))), line("WARC-Profile", F.lit(PROFILE)))).otherwise(line("WARC-Block-Digest", F.concat(F.lit("sha256:"), "strong"))),
        line("Content-Type", F.lit("text/html; charset=utf-8")),
        line("Content-Length", F.when(revisit, F.lit(0)).otherwise(F.col("payload_bytes")).cast("string")),
        F.lit("\r\n"),
    )
    record = F.concat(header, F.when(revisit, F.lit("")).otherwise(F.col("html")))
    largest, above = digests.agg(F.max("payload_bytes")).first()[0] or 0, -1
    for most, records in CLASSES:
        if above < largest:
            sized = d.where((F.col("payload_bytes") > above) & (F.col("payload_bytes") <= (most or largest)))
            sized.select(record.alias("value")).write.mode("append").option("lineSep", END).option("compression", "gzip").option("maxRecordsPerFile", records).text(path)
            above = most or largest


def parse(data: io.BufferedIOBase) -> Iterator[tuple[int, bytes, bytes]]:
    """(place, exact header, payload) of each record of an archive, read one after the other; raises on a broken one."""
    at = 0
    while line := data.readline():
        header = [line]
        while line not in (b"\r\n", b""):
            line = data.readline()
            header.append(line)
        whole = b"".join(header)
        length = int(whole.rpartition(b"Content-Length: ")[2].split(b"\r\n")[0])
        payload = data.read(length)
        if len(payload) != length or data.read(4) != END.encode():
            raise ValueError("a record's length does not fit")
        yield at, whole, payload
        at += len(whole) + length + 4


def field(header: bytes, name: bytes) -> str | None:
    _, found, rest = header.partition(b"\r\n" + name + b": ")
    return rest.split(b"\r\n", 1)[0].decode() if found else None


def _page(ident: str | None) -> int | None:
    return int(x) if ident and (x := ident.split(":")[2]) else None


RECORD = "page_id long, record_type string, refers_to long, strong string, place long, header binary, payload binary"
_KINDS = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.binary(), pa.binary()]
BATCH_BYTES = 4 << 20


def read(spark: SparkSession, path: str) -> DataFrame:
    """The archives' records: page_id, record_type, refers_to, strong (SHA-256 of the payload), place (in the file), header, payload (null for revisits).

    A response's SHA-256 and SHA-1 are made anew from its bytes and must equal its header's.
    """

    def record(place: int, header: bytes, payload: bytes) -> tuple:
        ident, target, kind = field(header, b"WARC-Record-ID"), field(header, b"WARC-Refers-To"), field(header, b"WARC-Type")
        strong = ident.rstrip(">").rsplit(":", 1)[1]
        if kind != "response":
            return _page(ident), kind, _page(target), strong, place, header, None
        if hashlib.sha256(payload).hexdigest() != strong or field(header, b"WARC-Block-Digest") != f"sha256:{strong}":
            raise ValueError(f"the payload of {ident} does not have its SHA-256")
        if base64.b32encode(hashlib.sha1(payload).digest()).decode() != field(header, b"WARC-Payload-Digest").removeprefix("sha1:"):
            raise ValueError(f"the payload of {ident} does not have its SHA-1")
        return _page(ident), kind, None, strong, place, header, payload

    def batch(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), _KINDS, strict=True)], names=[x.split()[0] for x in RECORD.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for files in batches:
            for content in files.column(0):
                rows, size = [], 0
                with gzip.open(io.BytesIO(content.as_buffer()), "rb") as data:
                    for place, header, payload in parse(data):
                        rows.append(record(place, header, payload))
                        size += len(header) + len(payload)
                        if size > BATCH_BYTES:
                            yield batch(rows)
                            rows, size = [], 0
                if rows:
                    yield batch(rows)
        give_back()

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").option("recursiveFileLookup", "true").load(path)
    return files.select("content").mapInArrow(run, RECORD)


def store(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(payloads: strong, payload, one row for each digest; headers: page_id, record_type, refers_to, strong, place, header), from a written table of records."""
    records = written(read(spark, path), "warc", "zstd")
    payloads = records.where("record_type = 'response'").groupBy("strong").agg(F.first("payload").alias("payload"))
    return payloads, records.drop("payload")


def originals(payloads: DataFrame, headers: DataFrame) -> DataFrame:
    """The headers' columns and the payload of every record, revisits with the payload of their response.

    Records of hot digests (more rows than an even share) meet copies of their payload under as many salts as they have shares.
    """
    hot = written(_hot(headers.select("strong"), "records"), "hot")
    rest = headers.join(F.broadcast(hot), "strong", "left_anti").join(payloads, "strong")
    salted = headers.join(F.broadcast(hot), "strong").withColumn("salt", F.pmod(F.xxhash64("page_id", "place"), F.col("salts")).cast("int")).drop("salts")
    copies = payloads.join(F.broadcast(hot), "strong").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("salts")
    return rest.unionByName(salted.join(copies, ["strong", "salt"]).drop("salt"))


def archive(pages: DataFrame, least: int = 0) -> DataFrame:
    """Write, read back, store and rebuild: page_id, payload_bytes, payload_digest, record_type, refers_to, of the rebuilt records."""
    spark = pages.sparkSession
    path = work_path(spark, "warc")
    write(pages, path, least)
    whole = originals(*store(spark, path))
    return whole.select("page_id", F.octet_length("payload").cast("long").alias("payload_bytes"), base32_sha1(F.col("payload")).alias("payload_digest"), "record_type", "refers_to")
