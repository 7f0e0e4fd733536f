"""WARC archives: written per capture, read back, and assembled into one nested row per capture.

A capture is three records: a request, a response or revisit, and a metadata record; the request and
the metadata name the response in WARC-Concurrent-To. Records are lines of Spark's text writer with
the blank lines that end a record as separator, so archives are gzip files written and committed by
tasks on any file system. Files hold a bounded number of records, are read whole by name and parsed
as streams, by Content-Length. Assembly meets the three records of a capture on the identifier that
WARC-Concurrent-To gives, in one grouping rather than two joins, and carries no payload unless asked.

Payloads of ``least_revisit`` bytes or more that are equal (SHA-1 and length) are stored once, by the
row with the largest page id; the others revisit it. The holders come from narrow rows, collapsed before
they are shuffled. A payload of more than one in ``HOT`` of all rows is hot: there are fewer than ``HOT``
such, so their holders are broadcast, and their rows are dealt by themselves instead of by their digest.

Defined cases: null html is empty; equal rows (same id and payload) are all responses if they hold
the largest id; a null id never holds a payload that another row can hold; line breaks in a url are
deleted; an empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dnfblock.storage import materialize, new_path

END = "\r\n\r\n"
LEAST_REVISIT = 1000
HOT = 2048
FILE_BYTES = 32 << 20
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def holders(pages: DataFrame, id_col: str, body_col: str, least: int = LEAST_REVISIT) -> DataFrame:
    """``h_digest, h_bytes, h_id, h_row, h_rows``: for payloads with copies, the row that stores them, and how many have them."""
    rows = pages.select(
        F.sha1(F.coalesce(body_col, F.lit(""))).alias("h_digest"),
        F.octet_length(F.coalesce(body_col, F.lit(""))).alias("h_bytes"),
        F.struct(F.col(id_col).isNotNull().alias("named"), F.col(id_col).alias("id"), F.monotonically_increasing_id().alias("row")).alias("one"),
    )
    rows = rows.where(F.col("h_bytes") >= least).groupBy("h_digest", "h_bytes")
    rows = rows.agg(F.max("one").alias("one"), F.count("*").alias("n")).where("n > 1")
    return rows.select("h_digest", "h_bytes", F.col("one.id").alias("h_id"), F.col("one.row").alias("h_row"), F.col("n").alias("h_rows"))


def with_holders(rows: DataFrame, held: DataFrame, hot: int) -> DataFrame:
    """``rows`` (``digest, n, row, …``) and ``h_digest, h_id, h_row`` of their holder, null where a payload has no copy.

    Payloads of more than ``hot`` rows are looked up in a broadcast table; their rows meet nothing in the join
    that follows, and go to the tasks that a hash of the row itself gives.
    """
    few = held.where(F.col("h_rows") > hot).select(*(F.col(f"h_{c}").alias(f"b_{c}") for c in ("digest", "bytes", "id", "row")))
    rows = rows.join(F.broadcast(few), (rows["digest"] == few["b_digest"]) & (rows["n"] == few["b_bytes"]), "left")
    own = F.when(F.col("b_digest").isNull(), F.col("digest")).otherwise(F.concat(F.lit("row "), F.col("row").cast("string")))
    rest = held.where(F.col("h_rows") <= hot).drop("h_rows")
    rows = rows.withColumn("__key", own).join(rest, (F.col("__key") == rest["h_digest"]) & (F.col("n") == rest["h_bytes"]), "left")
    found = {f"h_{c}": F.coalesce(f"b_{c}", f"h_{c}") for c in ("digest", "id", "row")}
    return rows.withColumns(found).drop("__key", "h_bytes", "b_digest", "b_bytes", "b_id", "b_row")


def _record(kind: str | Column, identifier: Column, block: Column, content: str, *fields: Column) -> Column:
    kind = F.lit(kind) if isinstance(kind, str) else kind
    head = [F.lit("WARC/1.1"), F.concat(F.lit("WARC-Type: "), kind), F.concat(F.lit("WARC-Record-ID: "), identifier)]
    head += [F.lit(f"WARC-Date: {DATE}"), *fields, F.lit(f"Content-Type: {content}")]
    head.append(F.concat(F.lit("Content-Length: "), F.octet_length(block)))
    return F.concat(F.concat_ws("\r\n", *head), F.lit(END), block)


def write_archives(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", body_col: str = "html", least: int = LEAST_REVISIT) -> None:
    """Write the records of every row of ``pages`` to gzip files below ``path``."""
    held = materialize(holders(pages, id_col, body_col, least), "holders")
    size = pages.agg(F.count("*"), F.coalesce(F.sum(F.octet_length(body_col)), F.lit(0))).first()
    mean = 1500 + (size[1] / size[0] if size[0] else 0)
    rows = pages.select(
        pages[id_col].alias("id"),
        F.regexp_replace(F.coalesce(pages[url_col], F.lit("")), "[\\x00-\\x20]", "").alias("url"),
        F.coalesce(pages[body_col], F.lit("")).alias("body"),
        F.monotonically_increasing_id().alias("row"),
    ).withColumns({"digest": F.sha1("body"), "n": F.octet_length("body")})
    rows = with_holders(rows, held, size[0] // HOT)
    revisit = F.col("h_digest").isNotNull() & ~F.col("id").eqNullSafe(F.col("h_id"))
    name = lambda i, r, kind: F.concat(
        F.lit("<urn:capture:"), F.coalesce(i.cast("string"), F.lit("none")), F.lit(":"), r, F.lit(f":{kind}>")
    )
    own = lambda kind: name(F.col("id"), F.col("row"), kind)
    uri = F.concat(F.lit("WARC-Target-URI: "), "url")
    together = F.concat(F.lit("WARC-Concurrent-To: "), own("response"))
    digest = F.concat(F.lit("WARC-Payload-Digest: sha1:"), "digest")
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), "n", F.lit(END))
    refers = F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), name(F.col("h_id"), F.col("h_row"), "response")))
    profile = F.when(revisit, F.lit(f"WARC-Profile: {PROFILE}"))
    host = F.regexp_extract("url", "^[a-zA-Z]+://([^/?#]*)", 1)
    place = F.regexp_extract("url", "^[a-zA-Z]+://[^/?#]*([^#]*)", 1)
    asked = F.concat(F.lit("GET "), F.when(place == "", F.lit("/")).otherwise(place), F.lit(" HTTP/1.1\r\nHost: "), host, F.lit(END))
    about = F.concat(F.lit("pageId: "), F.coalesce(F.col("id").cast("string"), F.lit("")), F.lit("\r\npayloadLength: "), "n", F.lit("\r\n"))
    answer = F.when(revisit, http).otherwise(F.concat(http, "body"))
    records = F.concat_ws(
        END,
        _record("request", own("request"), asked, "application/http; msgtype=request", uri, together),
        _record(
            F.when(revisit, F.lit("revisit")).otherwise(F.lit("response")),
            own("response"), answer, "application/http; msgtype=response", uri, digest, refers, profile,
        ),
        _record("metadata", own("metadata"), about, "application/warc-fields", uri, together),
    )
    rows.select(records.alias("value")).write.option("lineSep", END).option("compression", "gzip").option(
        "maxRecordsPerFile", int(max(16, min(4096, FILE_BYTES // mean)))
    ).text(path)


def parse(pieces: Iterator[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers (names in lower case) and block of every record of a decompressed stream."""
    held, ended = bytearray(), False

    def more() -> bool:
        nonlocal ended
        part = next(pieces, None)
        ended = part is None
        held.extend(part or b"")
        return not ended

    while True:
        while (at := held.find(b"\r\n\r\n")) < 0 and more():
            pass
        if at < 0:
            if held.strip():
                raise ValueError("the archive ends inside a record's headers")
            return
        lines = held[:at].decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no record begins with {lines[0][:40]!r}")
        head = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        size = int(head["content-length"])
        while len(held) < at + 8 + size and more():
            pass
        if len(held) < at + 8 + size:
            raise ValueError("the archive ends inside a record")
        yield head, bytes(held[at + 4 : at + 4 + size])
        del held[: at + 8 + size]


def inflated(data: memoryview, step: int = 1 << 16) -> Iterator[bytes]:
    """Pieces of a gzip file of one or more members."""
    at, unzip = 0, zlib.decompressobj(31)
    while at < len(data) or unzip.unconsumed_tail:
        part = unzip.unconsumed_tail or bytes(data[at : (at := at + step)])
        yield unzip.decompress(part, 16 * step)
        if unzip.eof and (unzip.unused_data or at < len(data)):
            rest, unzip = unzip.unused_data, zlib.decompressobj(31)
            at -= len(rest)


RECORD = (
    "capture string, record_id string, type string, uri string, refers_to string, digest string, "
    "block_bytes long, payload_bytes long, payload_digest string, fields map<string,string>"
)


def read_records(spark: SparkSession, path: str, payloads: bool = False) -> DataFrame:
    """One row per record below ``path``: capture identifier, headers, payload length and SHA-1."""
    names = [x.split()[0] for x in RECORD.split(", ")] + ["payload"] * payloads
    kinds = [pa.string()] * 6 + [pa.int64(), pa.int64(), pa.string(), pa.map_(pa.string(), pa.string())] + [pa.binary()] * payloads

    def batch_of(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file in batch.column(0):
                rows, held = [], 0
                for head, block in parse(inflated(memoryview(file.as_buffer()))):
                    kind, fields, payload = head["warc-type"], {}, None
                    if kind == "metadata":
                        fields = {k.strip(): v.strip() for k, _, v in (x.partition(":") for x in block.decode().split("\r\n") if x)}
                    elif kind in ("response", "revisit"):
                        payload = block.partition(b"\r\n\r\n")[2]
                    row = (
                        head.get("warc-concurrent-to", head["warc-record-id"]), head["warc-record-id"], kind,
                        head.get("warc-target-uri"), head.get("warc-refers-to"), head.get("warc-payload-digest", "").removeprefix("sha1:"),
                        len(block), None if payload is None else len(payload),
                        None if payload is None else hashlib.sha1(payload).hexdigest(), list(fields.items()),
                    )
                    rows.append((*row, payload) if payloads else row)
                    held += len(block) if payloads else 500
                    if held > 4 << 20:
                        yield batch_of(rows)
                        rows, held = [], 0
                if rows:
                    yield batch_of(rows)

    files = spark.read.format("binaryFile").load(path).select("content")
    return files.mapInArrow(run, RECORD + ", payload binary" * payloads)


def assemble(records: DataFrame) -> DataFrame:
    """``capture, request, response, metadata``: one nested row per capture, of records in any order.

    Parts that a capture lacks are null. A revisit stores no payload: its length is the one that the
    metadata has, its digest the one that its header has.
    """
    of = lambda *kinds: F.col("type").isin(*kinds)
    body = ["record_id", "type", "uri", "refers_to", "digest", "payload_bytes", "payload_digest"]
    body += ["payload"] * ("payload" in records.columns)
    return records.groupBy("capture").agg(
        F.first(F.when(of("request"), F.struct("record_id", "uri", "block_bytes")), ignorenulls=True).alias("request"),
        F.first(F.when(of("response", "revisit"), F.struct(*body)), ignorenulls=True).alias("response"),
        F.first(F.when(of("metadata"), F.struct("record_id", "fields")), ignorenulls=True).alias("metadata"),
    )


def captures(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", body_col: str = "html", least: int = LEAST_REVISIT) -> DataFrame:
    """Archive every row of ``pages``, read the archives back, and digest the assembled captures."""
    spark = pages.sparkSession
    path = new_path(spark, "warc")
    write_archives(pages, path, id_col, url_col, body_col, least)
    rows = assemble(read_records(spark, path))
    revisit = F.col("response.type") == "revisit"
    field = lambda name: F.col("metadata.fields")[name]
    return rows.select(
        F.expr("try_cast(metadata.fields['pageId'] AS long)").alias("page_id"),
        F.when(revisit, field("payloadLength").cast("long")).otherwise(F.col("response.payload_bytes")).alias("payload_bytes"),
        F.when(revisit, F.col("response.digest")).otherwise(F.col("response.payload_digest")).alias("payload_digest"),
        F.col("response.type").alias("record_type"),
        F.expr("try_cast(regexp_extract(response.refers_to, '^<urn:capture:(-?[0-9]+):', 1) AS long)").alias("refers_to"),
    )
