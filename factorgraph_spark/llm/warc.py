"""WARC archives with revisit records for repeated payloads.

Only headers are shuffled by payload digest: of each digest one record stays the response and the others become revisits that name it. The
headers then meet their payloads by id, each record is laid out with fresh headers, and Spark's text writer stores the records, with the
two line ends that close a WARC record as its line separator. So archives are committed by Spark's output committer, on any file system
that Spark writes to, and survive lost executors. Reading takes whole files, each of a bounded size, and walks the records by their
Content-Length; nothing in a payload can end a record early.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, fresh_path

VERSION = "WARC/1.1"
END = "\r\n"
#: Payloads with at least so many bytes can be revisited.
LEAST_BYTES = 0
#: Payload bytes of an archive at most, for payloads of average size.
FILE_BYTES = 16_000_000
#: Revisits up to which they are broadcast to the payloads; beyond, payloads are shuffled by id.
BROADCAST_ROWS = 1_000_000


def digest(payload: Column) -> Column:
    """SHA-1 in upper-case base32, without a prefix: five hex digits are four base32 digits."""
    hexed = F.sha1(payload)
    four = [F.lpad(F.conv(F.substring(hexed, 1 + 5 * k, 5), 16, 32), 4, "0") for k in range(8)]
    return F.translate(F.concat(*four), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def resolve(headers: DataFrame, least: int = LEAST_BYTES) -> DataFrame:
    """headers (id, digest, bytes, ...) with record_type and refers_to.

    The largest id of a digest is the response. Hot digests are summed before they are shuffled, and the join back is one that Spark splits
    where a key is skewed.
    """
    first = headers.where(F.col("bytes") >= least).groupBy("digest").agg(F.max("id").alias("response"), F.count(F.lit(1)).alias("n"))
    repeated = first.where("n > 1 and response is not null").select(F.col("digest").alias("d"), "response")
    joined = headers.join(repeated, (F.col("d") == F.col("digest")) & (F.col("bytes") >= least), "left")
    again = F.col("response").isNotNull() & ~F.col("response").eqNullSafe(F.col("id"))
    return joined.withColumn("record_type", F.when(again, "revisit").otherwise("response")).withColumn("refers_to", F.when(again, F.col("response"))).drop("d", "response")


def _record(uri: Column, name: Column, kind: Column, refers: Column, digest_: Column, size: Column, payload: Column) -> Column:
    """One record but for its closing line ends."""
    line = lambda key, value: F.concat(F.lit(f"{key}: "), value, F.lit(END))
    revisit = kind == "revisit"
    urn = lambda ident: F.concat(F.lit("<urn:page:"), F.coalesce(ident.cast("string"), F.lit("null")), F.lit(">"))
    clean = F.regexp_replace(F.coalesce(uri, F.lit("")), r"[\r\n]+", " ")
    return F.concat(
        F.lit(VERSION + END),
        line("WARC-Type", kind),
        line("WARC-Record-ID", urn(name)),
        line("WARC-Date", F.lit("1970-01-01T00:00:00Z")),
        line("WARC-Target-URI", clean),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), digest_)),
        F.when(revisit, line("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"))).otherwise(""),
        F.when(revisit, line("WARC-Refers-To", urn(refers))).otherwise(""),
        line("X-Payload-Bytes", size.cast("string")),
        line("Content-Type", F.lit("text/html; charset=utf-8")),
        line("Content-Length", F.when(revisit, F.lit("0")).otherwise(size.cast("string"))),
        F.lit(END),
        F.when(revisit, F.lit("")).otherwise(payload),
    )


def write(pages: DataFrame, path: str, *, page_id: str = "page_id", url: str = "url", html: str = "html", least: int = LEAST_BYTES) -> None:
    """Writes a record for every row of pages: a response with its payload, or a revisit without.

    Null payloads and URLs are empty. Rows that share an id are a record each and agree in their kind; rows with a null id are responses or
    revisits like others, but none refers to them. An empty table makes an empty archive.
    """
    rows = pages.select(F.col(page_id).alias("id"), F.col(url).alias("u"), F.coalesce(F.col(html), F.lit("")).alias("p"))
    heads = rows.select("id", digest(F.encode("p", "UTF-8")).alias("digest"), F.octet_length("p").cast("long").alias("bytes"))
    heads = cut(heads)
    links = resolve(heads, least).where("record_type = 'revisit'").select(F.col("id").alias("i"), F.col("digest").alias("d"), "refers_to").distinct()
    links = cut(links)
    total, n = heads.agg(F.sum("bytes"), F.count(F.lit(1))).first()
    rows = rows.withColumn("digest", digest(F.encode("p", "UTF-8"))).withColumn("bytes", F.octet_length("p").cast("long"))
    few = links.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    joined = rows.join(F.broadcast(links) if few else links, F.col("id").eqNullSafe(F.col("i")) & (F.col("digest") == F.col("d")), "left")
    kind = F.when(F.col("refers_to").isNotNull(), "revisit").otherwise("response")
    value = _record(F.col("u"), F.col("id"), kind, F.col("refers_to"), F.col("digest"), F.col("bytes"), F.col("p"))
    each = max(1, FILE_BYTES * n // max(1, total or 0))
    joined.select(value.alias("value")).write.option("lineSep", END + END).option("compression", "none").option("maxRecordsPerFile", each).text(path)


def _records(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    at = 0
    while at < len(data):
        stop = data.index(b"\r\n\r\n", at)
        lines = data[at:stop].decode("utf-8", "replace").split(END)
        if lines[0] != VERSION:
            raise ValueError(f"no {VERSION} record at byte {at}")
        fields = dict(line.split(": ", 1) for line in lines[1:])
        size = int(fields["Content-Length"])
        yield fields, data[stop + 4 : stop + 4 + size]
        at = stop + 4 + size + 4


def read(spark: SparkSession, path: str) -> DataFrame:
    """A row per record of the archives: page_id, url, payload_bytes, payload_digest, record_type, refers_to and the block.

    The digest of a response is computed from its block; a mismatch with the header raises an error.
    """

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = lambda urn: None if urn is None or urn == "<urn:page:null>" else int(urn[len("<urn:page:") : -1])
        for batch in batches:
            for k in range(batch.num_rows):
                out = {c: [] for c in ("page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "block")}
                for fields, block in _records(batch.column("content")[k].as_py()):
                    stated, kind = fields["WARC-Payload-Digest"].removeprefix("sha1:"), fields["WARC-Type"]
                    if kind == "response":
                        own = base64.b32encode(hashlib.sha1(block, usedforsecurity=False).digest()).decode()
                        if own != stated:
                            raise ValueError(f"digest of {fields['WARC-Record-ID']}")
                    row = (number(fields["WARC-Record-ID"]), fields["WARC-Target-URI"], int(fields["X-Payload-Bytes"]), stated, kind, number(fields.get("WARC-Refers-To")), block)
                    for c, v in zip(out, row):
                        out[c].append(v)
                kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out.values(), kinds)], list(out))

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return files.mapInArrow(parse, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, block binary")


def op8(pages: DataFrame) -> DataFrame:
    spark = pages.sparkSession
    path = fresh_path(spark, "warc")
    write(pages, path)
    return read(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
