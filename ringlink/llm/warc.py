"""WARC archives: write captures, read them back, assemble each capture's transaction."""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringlink.llm.common import hot_join, remove, settle, shared_dir, stored

RECORD = "record_id string, kind string, concurrent_to string, refers_to string, page_id long, payload_bytes long, payload_digest string, payload binary"
_CRLF = "\r\n"
#: Payload bytes beyond which pages go to archives of their own, and bytes that one archive may hold.
LONG, ARCHIVE = 1 << 19, 1 << 30


def _urn(h: Column) -> Column:
    """A record id from 32 hex digits."""
    part = lambda a, n: F.substring(h, a, n)
    return F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", part(1, 8), part(9, 4), part(13, 4), part(17, 4), part(21, 12)), F.lit(">"))


def _response_id() -> Column:
    """One response per payload, so its digest names it, and every revisit knows the name."""
    return _urn(F.md5(F.concat(F.lit("response|"), F.col("sha"))))


def _base32(hexed: str) -> Column:
    """Bare upper-case base 32 of 40 hex digits: each five digits are four letters."""
    letters = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'"
    bits = ", ".join(f"substring({letters}, (shiftright(n, {s}) & 31) + 1, 1)" for s in (15, 10, 5, 0))
    return F.expr(f"concat_ws('', transform(transform(sequence(0, 7), i -> int(conv(substring({hexed}, i * 5 + 1, 5), 16, 10))), n -> concat({bits})))")


def _record(kind: str, own: Column, block: Column, *headers: tuple[str, Column]) -> Column:
    parts = [F.lit("WARC/1.1" + _CRLF + f"WARC-Type: {kind}{_CRLF}WARC-Record-ID: "), own, F.lit(_CRLF + "WARC-Date: 2020-01-01T00:00:00Z" + _CRLF)]
    for name, value in headers:
        parts += [F.lit(f"{name}: "), value, F.lit(_CRLF)]
    return F.concat(*parts, F.lit("Content-Length: "), F.octet_length(block).cast("string"), F.lit(_CRLF + _CRLF), block)


def _texts() -> list[Column]:
    """The records of one page, from page_id, url, html, sha, bytes, own (its capture's id) and again (a revisit)."""
    head = F.lit(f"HTTP/1.1 200 OK{_CRLF}Content-Type: text/html; charset=utf-8{_CRLF}{_CRLF}")
    about = [("WARC-Target-URI", F.col("url")), ("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest")))]
    response = _record("response", F.col("own"), F.concat(head, F.col("html")), *about)
    revisit = _record("revisit", F.col("own"), head, *about, ("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")), ("WARC-Refers-To", _response_id()))
    other = lambda kind: _urn(F.md5(F.concat(F.lit(kind + "|"), F.col("own"))))
    request = _record("request", other("request"), F.concat(F.lit("GET "), F.col("url"), F.lit(f" HTTP/1.1{_CRLF}{_CRLF}")), ("WARC-Concurrent-To", F.col("own")))
    notes = F.concat(F.lit("page-id: "), F.coalesce(F.col("page_id").cast("string"), F.lit("")), F.lit(_CRLF + "payload-bytes: "), F.col("bytes").cast("string"), F.lit(_CRLF))
    return [F.when(F.col("again"), revisit).otherwise(response), request, _record("metadata", other("metadata"), notes, ("WARC-Concurrent-To", F.col("own")))]


def write(pages: DataFrame, folder: str, least: int = 0, per_file: int = 2000) -> None:
    """Archives of pages (page_id, url, html): a response or revisit, a request and a metadata record for each row.

    Of equal payloads of `least` bytes or more the smallest page_id (null last) is the response; of repeated rows of
    it one is. Null html is an empty payload, a null url an empty target; other columns are left out. Only digests are
    shuffled: groups of equal payloads are met by a broadcast where they are few, and a payload moves only where they
    are many or its first page stands there more than once. Records end in two line breaks, so Spark's text writer
    writes the archive, gzipped; files hold `per_file` pages or ARCHIVE bytes of long ones at most.
    """
    spark = pages.sparkSession
    text = F.coalesce("html", F.lit(""))
    p = pages.select(F.col("page_id").cast("long").alias("page_id"), F.regexp_replace(F.coalesce("url", F.lit("")), r"[\r\n]", "").alias("url"), text.alias("html"), F.sha1(text.cast("binary")).alias("sha"), F.octet_length(text).cast("long").alias("bytes"))
    each = p.where(F.col("bytes") >= least).groupBy("sha", "page_id").agg(F.count("*").alias("n"))
    first = F.min(F.struct(F.col("page_id").isNull().alias("missing"), "page_id", "n")).alias("first")
    groups = each.groupBy("sha").agg(first, F.sum("n").alias("n")).where("n > 1").select(F.col("sha").alias("g"), "first.page_id", (F.col("first.n") > 1).alias("twice")).withColumnRenamed("page_id", "first_id")
    groups = stored(groups, f"{folder}-groups")
    longest = p.agg(F.max("bytes")).first()[0] or 0
    p = hot_join(p, groups, "sha", "g")
    at_first = F.col("page_id").eqNullSafe(F.col("first_id"))
    tied = F.coalesce(F.col("twice") & at_first, F.lit(False))
    single = p.where(~tied).withColumn("again", F.col("g").isNotNull() & ~at_first)
    parts = [single]
    if not groups.where("twice").isEmpty():  # rows of one page and payload are counted, then told apart by their numbers
        keys = ["sha", "page_id", "url", "bytes"]
        same = p.where(tied).groupBy(*keys).agg(F.count("*").alias("n"), F.any_value("html").alias("html"))
        low = p.where(tied).groupBy(F.col("sha").alias("l")).agg(F.min("url").alias("low"))
        same = same.join(low, F.col("sha") == F.col("l")).select(*keys, "html", "low", F.explode(F.sequence(F.lit(1).cast("long"), F.col("n"))).alias("i"))
        parts.append(same.withColumn("again", (F.col("url") != F.col("low")) | (F.col("i") > 1)))
    cols = ["page_id", "url", "html", "sha", "bytes", "again"]
    rows = parts[0].select(*cols) if len(parts) == 1 else parts[0].select(*cols).unionByName(parts[1].select(*cols))
    rows = rows.withColumn("digest", _base32("sha")).withColumn("own", F.when(F.col("again"), F.concat(F.lit("<urn:uuid:"), F.uuid(), F.lit(">"))).otherwise(_response_id()))
    if least > 0:  # short payloads are responses each, whatever they equal
        rows = rows.withColumn("own", F.when(F.col("bytes") < least, F.concat(F.lit("<urn:uuid:"), F.uuid(), F.lit(">"))).otherwise(F.col("own")))
    sizes = [(F.col("bytes") <= LONG, per_file)] + ([(F.col("bytes") > LONG, max(1, ARCHIVE // (longest + 4096)))] if longest > LONG else [])
    for i, (where, pages_) in enumerate(sizes):
        lines = rows.where(where).select(F.explode(F.array(*_texts())).alias("value"))
        lines.write.option("lineSep", _CRLF * 2).option("compression", "gzip").option("maxRecordsPerFile", 3 * pages_).text(f"{folder}/{i}")
    remove(spark, f"{folder}-groups")


def parse(raw: bytes):
    """The records of one archive, by their content lengths, one in memory at a time; a payload's digest is checked."""
    source = gzip.GzipFile(fileobj=io.BytesIO(raw)) if raw[:2] == b"\x1f\x8b" else io.BytesIO(raw)
    source = io.BufferedReader(source, 1 << 20)
    while True:
        line = source.readline()
        if not line:
            return
        head = {}
        while (line := source.readline()) != b"\r\n":
            if not line:
                raise ValueError("an archive ends inside a record")
            name, _, value = line.decode("utf-8").rstrip("\r\n").partition(":")
            head[name] = value.strip(" ")
        block = source.read(int(head["Content-Length"]))
        if source.read(4) != b"\r\n\r\n":
            raise ValueError(f"{head['WARC-Record-ID']} does not end where its length says")
        kind, page, size, payload = head["WARC-Type"], None, None, None
        digest = head.get("WARC-Payload-Digest", "")[5:] or None
        if kind == "response":
            payload = block.split(b"\r\n\r\n", 1)[1]
            size = len(payload)
            if base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest:
                raise ValueError(f"payload of {head['WARC-Record-ID']} does not meet its digest")
        elif kind == "metadata":
            notes = dict(x.split(": ", 1) for x in block.decode().split(_CRLF) if ": " in x)
            page, size = int(p) if (p := notes.get("page-id", "")) else None, int(notes["payload-bytes"])
        yield head["WARC-Record-ID"], kind, head.get("WARC-Concurrent-To"), head.get("WARC-Refers-To"), page, size, digest, payload


def read(spark, folder: str, payloads: bool = True) -> DataFrame:
    """One row per record of the archives; files hold a bounded number of bytes."""
    names = ["record_id", "kind", "concurrent_to", "refers_to", "page_id", "payload_bytes", "payload_digest", "payload"]
    types = [pa.string(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary()]

    def batch(rows: list) -> pa.RecordBatch:
        cols = list(zip(*rows, strict=True)) or [[]] * len(names)
        return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types, strict=True)], names=names)

    def run(batches):
        for held in batches:
            for raw in held.column("content"):
                rows, size = [], 0
                for r in parse(raw.as_py()):
                    rows.append(r if payloads else (*r[:-1], None))
                    size += len(r[-1] or b"") if payloads else 0
                    if len(rows) >= 10_000 or size > 1 << 26:
                        yield batch(rows)
                        rows, size = [], 0
                yield batch(rows)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").option("recursiveFileLookup", True).load(folder)
    return files.select("content").mapInArrow(run, RECORD)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row per capture: its response or revisit, request and metadata, met through concurrent-to.

    One pass and one grouping by the capture's id; the records of a capture mostly stand together and meet before the
    shuffle. A capture without a request or metadata record has null there; notes on no capture are left out.
    """
    rows = records.withColumn("capture", F.coalesce("concurrent_to", "record_id"))
    of = lambda kinds, *cols: F.first(F.when(F.col("kind").isin(*kinds), F.struct(*cols)), True)
    met = rows.groupBy("capture").agg(
        of(["response", "revisit"], "kind", "refers_to", "payload_bytes", "payload_digest", "payload").alias("response"),
        of(["request"], "record_id").alias("request"),
        of(["metadata"], "record_id", "page_id", "payload_bytes").alias("metadata"),
    )
    return met.where("response is not null")


def digest(pages: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to: one row per row of pages, as its archive says.

    Null html counts as empty; of repeated rows of the first page one is the response. An empty table gives no rows.
    The archives are removed once the result is settled.
    """
    spark = pages.sparkSession
    folder = f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}"
    write(pages, folder)
    met = assemble(read(spark, folder, payloads=False))
    rows = settle(met.select("capture", "metadata.page_id", "metadata.payload_bytes", "response.payload_digest", F.col("response.kind").alias("record_type"), F.col("response.refers_to").alias("to")))
    named = rows.where("to is not null").select("to").distinct().join(rows.select("capture", F.col("page_id").alias("refers_to")), F.col("to") == F.col("capture")).select(F.col("to").alias("r"), "refers_to")
    named = stored(named, f"{folder}-named")
    out = settle(hot_join(rows, named, "to", "r").select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"))
    remove(spark, folder, f"{folder}-named")
    return out
