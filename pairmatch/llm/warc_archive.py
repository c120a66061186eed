"""WARC archives: written with Spark's text writer, read back, captures assembled.

A capture is a request, a response or revisit, and a metadata record; the last two
name the first's sibling through WARC-Concurrent-To. Reading parses records by their
declared lengths (a torn record raises an error), and assembly joins the three kinds into one nested row a capture.
Payloads are the UTF-8 bytes of the html; a payload already held by the page with the
smallest id is written as a revisit of it.

Defined results: null html is the empty payload; rows without a page_id cannot be
named and take no part; repeated rows (same id and payload) are one capture; two
payloads under one id are two captures, told apart by their digest; null urls are
written as empty; an empty table gives an empty archive.
"""

from __future__ import annotations

import re
import uuid

from pyspark.sql import Column, DataFrame, functions as F

from pairmatch.llm.common import checkpoint_root

# The base-32 alphabets of the number conversion and of RFC 4648.
DIGITS, BASE32 = "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
DATE = "2024-01-01T00:00:00Z"
RECORDS_PER_FILE = 3000


def base32_sha1(data: Column) -> Column:
    """Bare upper-case base32 of the SHA-1: ten hex digits are eight base32 ones."""
    h = F.sha1(data)
    parts = [F.lpad(F.conv(F.substring(h, 1 + 10 * i, 10), 16, 32), 8, "0") for i in range(4)]
    return F.translate(F.upper(F.concat(*parts)), DIGITS, BASE32)


def decide(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """page_id, payload_digest and refers_to (null: a response) of each capture."""
    payload = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    seen = pages.where(F.col("page_id").isNotNull()).select(
        F.col("page_id").cast("long"), base32_sha1(payload).alias("payload_digest"), F.octet_length(payload).cast("long").alias("payload_bytes")
    ).distinct()
    first = seen.groupBy("payload_digest", "payload_bytes").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    held = seen.join(first, ["payload_digest", "payload_bytes"], "left")
    revisit = (F.col("first") < F.col("page_id")) & (F.col("payload_bytes") >= least_bytes)
    return held.select("page_id", "payload_digest", F.when(revisit, F.col("first")).alias("refers_to"))


def _id(kind: str, page: Column, digest: Column) -> Column:
    return F.concat(F.lit(f"<urn:capture:{kind}:"), page.cast("string"), F.lit(":"), digest, F.lit(">"))


def _record(head: list[tuple[str, Column]], body: Column) -> Column:
    """One record as text, without headers of null value; the writer's line separator is the last line end."""
    lines = [F.concat(F.lit(f"{k}: "), v, F.lit("\r\n")) for k, v in head] + [F.concat(F.lit("Content-Length: "), F.octet_length(body).cast("string"), F.lit("\r\n"))]
    return F.concat(F.lit("WARC/1.1\r\n"), *[F.coalesce(x, F.lit("")) for x in lines], F.lit("\r\n"), body, F.lit("\r\n"))


def records(pages: DataFrame, decisions: DataFrame) -> DataFrame:
    """One row a record: kind and the record's text."""
    body = F.coalesce("html", F.lit(""))
    rows = pages.where(F.col("page_id").isNotNull()).select(
        F.col("page_id").cast("long"), F.regexp_replace(F.coalesce("url", F.lit("")), r"[\r\n]", "").alias("url"), body.alias("body"), base32_sha1(F.encode(body, "UTF-8")).alias("payload_digest")
    ).join(decisions, ["page_id", "payload_digest"]).dropDuplicates(["page_id", "payload_digest"])
    page, digest, uri = F.col("page_id"), F.col("payload_digest"), F.col("url")
    hit = F.col("refers_to").isNotNull()
    main = _id("main", page, digest)
    shared = [("WARC-Target-URI", uri), ("WARC-Date", F.lit(DATE))]
    held = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"), F.when(hit, "").otherwise(F.col("body")))
    of = [("WARC-Refers-To", F.when(hit, _id("main", F.col("refers_to"), digest))), ("WARC-Profile", F.when(hit, F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")))]
    response = _record(
        [("WARC-Type", F.when(hit, "revisit").otherwise("response")), ("WARC-Record-ID", main), *shared, ("WARC-Payload-Digest", F.concat(F.lit("sha1:"), digest)), *of, ("Content-Type", F.lit("application/http; msgtype=response"))], held
    )
    request = _record([("WARC-Type", F.lit("request")), ("WARC-Record-ID", _id("request", page, digest)), ("WARC-Concurrent-To", main), *shared, ("Content-Type", F.lit("application/http; msgtype=request"))], F.concat(F.lit("GET "), uri, F.lit(" HTTP/1.1\r\n\r\n")))
    metadata = _record(
        [("WARC-Type", F.lit("metadata")), ("WARC-Record-ID", _id("metadata", page, digest)), ("WARC-Concurrent-To", main), *shared, ("Content-Type", F.lit("application/warc-fields"))],
        F.concat(F.lit("page-id: "), page.cast("string"), F.lit("\r\npayload-length: "), F.octet_length(F.col("body")).cast("string"), F.lit("\r\n")),
    )
    return rows.select(F.explode(F.array(request, response, metadata)).alias("value"))


def write_archives(pages: DataFrame, path: str, least_bytes: int = 0) -> str:
    """Writes gzipped WARC files of a bounded number of records under path."""
    out = records(pages, decide(pages, least_bytes))
    out.write.option("lineSep", "\r\n").option("compression", "gzip").option("maxRecordsPerFile", RECORDS_PER_FILE).mode("overwrite").text(path)
    return path


def parse(data: bytes, strict: bool = False):
    """(headers, block) of each record of an archive; a torn record ends it, or raises where strict."""
    at = data.find(b"WARC/1.")
    while 0 <= at < len(data):
        end = data.find(b"\r\n\r\n", at)
        head = {}
        for line in data[at : max(end, at)].split(b"\r\n")[1:]:
            name, _, value = line.partition(b":")
            head[name.strip().lower().decode("ascii", "replace")] = value.strip().decode("utf-8", "replace")
        size = int(head.get("content-length") or 0)
        block = data[end + 4 : end + 4 + size]
        if end < 0 or len(block) < size:
            if strict:
                raise ValueError(f"torn record at byte {at}: {head.get('warc-record-id')}")
            return
        yield head, block
        at = data.find(b"WARC/1.", end + 4 + size)


def read_records(spark, path: str) -> DataFrame:
    """record_id, record_type, concurrent_to, refers_to, uri, digest and the block of each record under path."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.gz").load(path).select("content")
    schema = "record_id string, record_type string, concurrent_to string, refers_to string, uri string, digest string, block binary"
    names = ("warc-record-id", "warc-type", "warc-concurrent-to", "warc-refers-to", "warc-target-uri", "warc-payload-digest")

    def run(batches):
        import zlib

        import pyarrow as pa

        types = [pa.string()] * 6 + [pa.binary()]
        labels = [x.split()[0] for x in schema.split(", ")]
        for batch in batches:
            for cell in batch.column(0):
                data, rest = b"", cell.as_buffer().to_pybytes()
                while rest:  # members of a multi-member file in turn
                    d = zlib.decompressobj(47)
                    data += d.decompress(rest) + d.flush()
                    rest = d.unused_data
                rows = []
                for head, block in parse(data, strict=True):
                    rows.append((*(head.get(n) for n in names), block))
                    if len(rows) == 500:
                        yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=labels)
                        rows = []
                if rows:
                    yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=labels)

    return files.mapInArrow(run, schema)


def assemble(recs: DataFrame) -> DataFrame:
    """One nested row a capture: the main record with its request and metadata."""
    http = lambda b: F.expr(f"substring({b}, instr(cast({b} as string), '\r\n\r\n') + 4)")
    main = recs.where(F.col("record_type").isin("response", "revisit")).select(
        F.col("record_id"), F.struct("record_type", "uri", "digest", "refers_to", http("block").alias("payload")).alias("response")
    )
    side = recs.where(F.col("record_type").isin("request", "metadata") & F.col("concurrent_to").isNotNull()).select(
        F.col("concurrent_to").alias("record_id"), "record_type", F.struct(F.col("record_id").alias("id"), F.col("block")).alias("rec")
    )
    sides = side.groupBy("record_id").agg(
        F.min(F.when(F.col("record_type") == "request", F.col("rec"))).alias("request"), F.min(F.when(F.col("record_type") == "metadata", F.col("rec"))).alias("metadata")
    )
    return main.join(sides, "record_id", "left").select("record_id", "request", "response", "metadata")


def captures(pages: DataFrame, path: str | None = None, least_bytes: int = 0) -> DataFrame:
    """Writes the archives and gives the captures read back from them."""
    spark = pages.sparkSession
    path = path or f"{checkpoint_root(spark).rstrip('/')}/warc-{uuid.uuid4().hex}"
    return assemble(read_records(spark, write_archives(pages, path, least_bytes)))


def capture_digest(found: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of each capture."""
    part = lambda c: F.regexp_extract(c, re.escape("<urn:capture:main:") + r"(-?\d+):", 1).cast("long")
    kind = F.col("response.record_type")
    length = F.regexp_extract(F.col("metadata.block").cast("string"), r"payload-length: (\d+)", 1).cast("long")
    own = F.octet_length("response.payload").cast("long")
    return found.select(
        part(F.col("record_id")).alias("page_id"), F.when(kind == "revisit", length).otherwise(own).alias("payload_bytes"),
        F.when(kind == "revisit", F.substring_index("response.digest", ":", -1)).otherwise(base32_sha1(F.col("response.payload"))).alias("payload_digest"),
        kind.alias("record_type"), F.when(kind == "revisit", part(F.col("response.refers_to"))).alias("refers_to"),
    )
