"""WARC archives: writing pages as transactions, and assembling transactions from archives."""

from __future__ import annotations

import gzip
import hashlib
import io
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from navgraph.session import scratch_path, ship, written

#: Payloads of at least so many bytes are kept once; equal ones refer to the first.
LEAST_SHARED = 100
#: Captures per archive file at most, and about the bytes of pages in one, which bound what one reading task holds.
PER_FILE, FILE_BYTES = 4000, 64 << 20
END = "\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _urn(*parts: Column) -> Column:
    h = F.md5(F.concat_ws("|", *(F.coalesce(p.cast("string"), F.lit("null")) for p in parts)))
    return F.concat(F.lit("urn:uuid:"), *(x for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12)) for x in (*([F.lit("-")] if a > 1 else []), F.substring(h, a, n))))


def _record(kind: str | Column, record_id: Column, block: Column, *headers: tuple[str, Column]) -> Column:
    lines = [F.concat(F.lit("WARC/1.1\r\nWARC-Type: "), kind if isinstance(kind, Column) else F.lit(kind), F.lit("\r\nWARC-Record-ID: <"), record_id, F.lit(">\r\n"))]
    lines += [F.coalesce(F.concat(F.lit(f"{name}: "), value, F.lit("\r\n")), F.lit("")) for name, value in headers]
    return F.concat(*lines, F.lit("Content-Length: "), F.octet_length(block).cast("string"), F.lit(END), block)


def transactions(pages: DataFrame, least_shared: int = LEAST_SHARED) -> DataFrame:
    """One column `value` per page: its response or revisit, request and metadata records.

    Which record refers to which is found on digests alone; page bodies are dealt out once, by page and digest, so that a
    payload shared by any number of pages gathers nowhere.
    """
    p = pages.select("page_id", F.regexp_replace("url", r"[\r\n\s]", "%20").alias("url"), F.coalesce(F.col("html"), F.lit("")).alias("html")).withColumn("digest", F.sha2("html", 256))
    p = p.withColumn("rid", _urn(F.lit("response"), F.col("page_id"), F.col("url"), F.col("digest")))
    large = p.filter(F.octet_length("html") >= least_shared).select("page_id", "digest", "rid")
    first = large.groupBy("digest").agg(F.min(F.struct("page_id", "rid")).alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1").select(F.col("digest").alias("d"), "first")
    later = large.join(first, F.col("digest") == F.col("d")).filter(~F.col("page_id").eqNullSafe(F.col("first.page_id")))
    later = later.select(F.col("page_id").alias("later_page"), F.col("digest").alias("later_digest"), F.col("first.rid").alias("refers")).distinct()
    p = p.join(later, F.col("page_id").eqNullSafe(F.col("later_page")) & (F.col("digest") == F.col("later_digest")), "left")
    revisit, date = F.col("refers").isNotNull(), F.lit("2024-01-01T00:00:00Z")
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.octet_length("html").cast("string"), F.lit(END))
    bracket = lambda c: F.concat(F.lit("<"), c, F.lit(">"))
    common = (("WARC-Date", date), ("WARC-Target-URI", F.col("url")))
    response = _record(
        F.when(revisit, "revisit").otherwise("response"), F.col("rid"), F.when(revisit, http).otherwise(F.concat(http, F.col("html"))), *common,
        ("Content-Type", F.lit("application/http; msgtype=response")), ("WARC-Payload-Digest", F.concat(F.lit("sha256:"), F.col("digest"))),
        ("WARC-Refers-To", bracket(F.col("refers"))), ("WARC-Profile", F.when(revisit, F.lit(PROFILE))),
    )
    request = _record("request", _urn(F.lit("request"), F.col("rid")), F.concat(F.lit("GET "), F.coalesce("url", F.lit("/")), F.lit(" HTTP/1.1"), F.lit(END)), *common, ("Content-Type", F.lit("application/http; msgtype=request")), ("WARC-Concurrent-To", bracket(F.col("rid"))))
    page = F.coalesce(F.concat(F.lit("page-id: "), F.col("page_id").cast("string"), F.lit("\r\n")), F.lit(""))
    metadata = _record("metadata", _urn(F.lit("metadata"), F.col("rid")), F.concat(page, F.lit("fetched-by: navgraph\r\n")), *common, ("Content-Type", F.lit("application/warc-fields")), ("WARC-Concurrent-To", bracket(F.col("rid"))))
    return p.select(F.concat(response, F.lit(END), request, F.lit(END), metadata).alias("value"))


def write(pages: DataFrame, path: str, least_shared: int = LEAST_SHARED) -> None:
    """Writes page_id, url, html as compressed WARC files below `path`, through Spark's own writer (any file system). Files hold
    as many captures as pages of the mean length fill FILE_BYTES."""
    n, size = pages.agg(F.count(F.lit(1)), F.sum(F.octet_length("html"))).first()
    per_file = max(1, min(PER_FILE, FILE_BYTES * n // max(size or 0, 1))) if n else PER_FILE
    transactions(pages, least_shared).write.option("lineSep", END).option("compression", "gzip").option("maxRecordsPerFile", per_file).text(path)


def records(stream: io.BufferedIOBase) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers (names in lower case; repeated ones joined by a blank) and block of each record, by its Content-Length."""
    while line := stream.readline():
        if not line.strip():
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError(f"no record starts with {line[:40]!r}")
        headers: dict[str, str] = {}
        while (line := stream.readline()).strip():
            name, _, value = line.decode("utf-8", "replace").partition(":")
            name, value = name.strip().lower(), value.strip()
            headers[name] = f"{headers[name]} {value}" if name in headers else value
        block = stream.read(size := int(headers.get("content-length", 0)))
        if len(block) < size:
            raise ValueError("the archive ends within a record")
        yield headers, block


SCHEMA = "record_id string, type string, concurrent_to array<string>, refers_to string, uri string, payload_bytes long, payload_digest string, intact boolean, fields map<string,string>, http string, payload binary"


def read(spark: SparkSession, path: str, content: bool = True) -> DataFrame:
    """One row per record of the archives below `path` (plain or gzip). payload_* are of what was read; for a revisit, the
    digest is the one it states. intact: the payload has the digest that its header states. With content, http has the head of a
    request, response or revisit and payload the body of a response; without, both are null and no body travels."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    ship(spark)
    schema = _parse_datatype_string(SCHEMA)
    ids = re.compile(r"<([^>]*)>")

    def run(batches):
        target = to_arrow_schema(schema)
        for batch in batches:
            for archive in batch.column(0):
                raw = pa.BufferReader(archive.as_buffer())
                zipped = raw.read(2) == b"\x1f\x8b"
                raw.seek(0)
                rows, held = [], 0
                for h, block in records(io.BufferedReader(gzip.GzipFile(fileobj=raw), 1 << 20) if zipped else io.BufferedReader(raw)):
                    kind = h.get("warc-type")
                    head, gap, payload = block.partition(b"\r\n\r\n") if "http" in h.get("content-type", "") else (b"", b"", block)
                    stated = h.get("warc-payload-digest", "").removeprefix("sha256:") or None
                    found = hashlib.sha256(payload).hexdigest() if kind == "response" else None
                    rows.append({
                        "record_id": "".join(ids.findall(h.get("warc-record-id", ""))), "type": kind, "concurrent_to": ids.findall(h.get("warc-concurrent-to", "")), "refers_to": next(iter(ids.findall(h.get("warc-refers-to", ""))), None), "uri": h.get("warc-target-uri"),
                        "payload_bytes": len(payload) if kind != "revisit" else None, "payload_digest": found or stated, "intact": found == stated if found and stated else None,
                        "fields": [tuple(x.strip() for x in y.split(":", 1)) for y in block.decode("utf-8", "replace").split("\r\n") if ":" in y] if kind == "metadata" else None,
                        "http": head.decode("utf-8", "replace") if content and gap else None, "payload": payload if content and kind == "response" else None,
                    })
                    held += len(block)
                    if len(rows) >= 5000 or held > 32 << 20:
                        yield pa.RecordBatch.from_pylist(rows, target)
                        rows, held = [], 0
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, target)

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).filter(~F.col("path").rlike(r"/[._][^/]*$") & (F.col("length") > 0)).select("content")
    return files.mapInArrow(run, schema)


def assemble(found: DataFrame) -> DataFrame:
    """One nested row per capture: response (or revisit) with the request and metadata that are concurrent to it.

    A link may be stated on either side. Of several requests or metadata records of one capture the one with the smallest id
    stays; a capture without any has null there. A revisit gets payload size and digest of the response it refers to; if that
    isn't in the archives, size is null and the digest the stated one. Repeated records give repeated rows. http and payload are the
    capture's own (a revisit's text is its response's: join on refers_id); rows whose metadata names no page have a null page_id,
    and pages written with a null id come back so; two rows written with one page_id and one payload are both responses.
    """
    own = F.struct("record_id", "uri", "fields", "http")
    stated = found.select("record_id", "type", own.alias("own"), F.explode("concurrent_to").alias("to"))
    back = found.filter(F.col("type").isin("response", "revisit")).select(F.col("record_id").alias("center"), F.explode("concurrent_to").alias("other"))
    others = found.filter(F.col("type").isin("request", "metadata"))
    links = stated.filter(F.col("type").isin("request", "metadata")).select(F.col("to").alias("center"), "type", "own")
    links = links.unionByName(back.join(others, F.col("other") == F.col("record_id")).select("center", "type", own.alias("own")))
    least = lambda kind: F.min_by(F.when(F.col("type") == kind, F.col("own")), F.when(F.col("type") == kind, F.col("own.record_id")))
    sides = links.groupBy("center").agg(least("request").alias("request"), least("metadata").alias("metadata"))
    captures = found.filter(F.col("type").isin("response", "revisit")).join(sides, F.col("record_id") == F.col("center"), "left")
    captures = captures.select("record_id", "type", "refers_to", "uri", "payload_bytes", "payload_digest", "intact", "request", "metadata", "http", "payload", F.try_element_at("metadata.fields", F.lit("page-id")).cast("long").alias("page_id"))
    response = captures.filter("type = 'response'").dropDuplicates(["record_id"]).select(F.col("record_id").alias("first_id"), F.struct("page_id", "payload_bytes", "payload_digest").alias("first"))
    # Responses refer to nothing; in the join they would all meet under null.
    own = captures.filter("type = 'response'").withColumns({"first_id": F.lit(None).cast("string"), "first": F.lit(None).cast("struct<page_id:long,payload_bytes:long,payload_digest:string>")})
    joined = captures.filter("type = 'revisit'").join(response, F.col("refers_to") == F.col("first_id"), "left").unionByName(own)
    return joined.select(
        "page_id", "record_id", F.col("type").alias("record_type"), "uri", "intact", "request", "metadata", "http", "payload", F.col("refers_to").alias("refers_id"),
        F.coalesce("payload_bytes", "first.payload_bytes").alias("payload_bytes"), F.coalesce("first.payload_digest", "payload_digest").alias("payload_digest"), F.col("first.page_id").alias("refers_to"),
    )


def op6_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch_path(spark, "warc")
    write(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html"), path)
    found = written(read(spark, path, content=False), "warc-records")
    return assemble(found).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


SQL = """
WITH p AS (SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first FROM p)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 100 AND page_id > first THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 100 AND page_id > first THEN first END AS refers_to
FROM f
"""
