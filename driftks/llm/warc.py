"""WARC archives with resolved revisits.

Only headers (id, payload digest, payload size) are shuffled to find equal payloads: the largest
id of each payload of ``least`` bytes or more stays a response, the others become revisits that
refer to it. The maximum is pre-aggregated, and a payload that very many rows share gets its
original by broadcast. Revisits are then counted: up to ``FEW`` of their headers go to the payloads by
broadcast, so no payload moves; only beyond does a shuffle by (id, digest) bring both together. The
archives are written with fresh headers, responses with their payload and
revisits without, by Spark's text writer: a record is one row, and the row separator is the
CRLF CRLF that ends a WARC record, so each part file is a valid archive (gzip, one member), is committed
like any Spark output, and may live in any store that Spark writes.

Part files are bounded in bytes: payloads above ``LARGE`` bytes go to files of their own, so many to
a file as fit ``PART`` bytes (one at least); of others, ``per_file`` records make a file. Reading inflates a part
as a stream and holds one record, walks the records by their Content-Length, recomputes the
digest of every payload that is there and joins the revisit headers, by payload digest, to the
original responses they need.

Edge cases: a null payload is an empty one; a null URL gives no target URI; a null id never
replaces another as the response, and its record is told apart by its random record id only;
rows that repeat an id get a record each, and if they also share the payload whose largest id
they carry, all of them are responses; an empty table gives archives without records; other
columns are ignored.
"""

from __future__ import annotations

import gzip
import hashlib
import io

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftks.llm.tables import joined_unique, remove, settled, shared_folder, table, whole_text

CRLF = "\r\n"
#: Payloads below this many bytes are never replaced by a revisit.
LEAST = 1000
#: Revisit headers (some 80 bytes each) that are broadcast at most; bytes of a large payload, and of a part before compression.
FEW, LARGE, PART = 200_000, 1 << 17, 1 << 28
# Fixed value: the profile URI that the WARC 1.1 standard gives revisits with identical payloads.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP = CRLF.join(["HTTP/1.1 200 OK", "Content-Type: text/html; charset=utf-8", "", ""])

HEADERS = "page_id long, record_type string, record_id string, refers_to_id long, stated_digest string, stated_bytes long, payload_digest string, payload_bytes long, url string, file string"


def resolve(pages: DataFrame, key: str = "page_id", url: str = "url", body: str = "html", least: int = LEAST) -> DataFrame:
    """Headers of all pages: ``key``, ``digest``, ``bytes`` and ``refers_to`` (null for responses).

    The decision needs no payload: rows of some 60 bytes are grouped by payload digest.
    """
    payload = whole_text(body)
    heads = settled(pages.select(F.col(key), F.sha1(F.encode(payload, "UTF-8")).alias("digest"), F.octet_length(payload).cast("long").alias("bytes")))
    kept = heads.where(F.col("bytes") >= least).groupBy("digest", "bytes").agg(F.max(key).alias("original"))
    joined = joined_unique(heads, kept, ["digest", "bytes"])
    return joined.select(key, "digest", "bytes", F.when(F.col("original") != F.col(key), F.col("original")).alias("refers_to"))


def _record(key: Column, url: Column, payload: Column, digest: Column, size: Column, refers: Column) -> Column:
    """The text of one record without the CRLF CRLF that ends it."""
    name = F.concat(F.lit("<urn:page:"), F.coalesce(key.cast("string"), F.uuid()), F.lit(">"))
    line = lambda label, value: F.concat(F.lit(f"{label}: "), value, F.lit(CRLF))
    revisit = refers.isNotNull()
    http = F.lit(HTTP)
    block = F.when(revisit, http).otherwise(F.concat(http, payload))
    length = F.lit(len(HTTP)) + F.when(revisit, F.lit(0)).otherwise(size)
    head = F.concat(
        F.lit(f"WARC/1.1{CRLF}"),
        line("WARC-Type", F.when(revisit, F.lit("revisit")).otherwise(F.lit("response"))),
        line("WARC-Record-ID", name),
        line("WARC-Date", F.date_format(F.current_timestamp(), "yyyy-MM-dd'T'HH:mm:ss'Z'")),
        F.coalesce(line("WARC-Target-URI", F.regexp_replace(url, r"[\r\n]", "%0A")), F.lit("")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), digest)),
        line("X-Payload-Length", size.cast("string")),
        F.when(revisit, F.concat(line("WARC-Refers-To", F.concat(F.lit("<urn:page:"), refers.cast("string"), F.lit(">"))), line("WARC-Profile", F.lit(PROFILE)))).otherwise(F.lit("")),
        line("Content-Type", F.lit("application/http; msgtype=response")),
        line("Content-Length", length.cast("string")),
        F.lit(CRLF),
    )
    return F.concat(head, block)


def write(pages: DataFrame, folder: str, key: str = "page_id", url: str = "url", body: str = "html", least: int = LEAST, per_file: int = 2000, few: int = FEW, large: int = LARGE) -> None:
    """Write the deduplicated archives of ``pages`` below ``folder`` (part files, gzip)."""
    rows = pages.select(F.col(key).alias("k"), F.col(url).alias("u"), F.col(body).alias("b"))
    heads = settled(resolve(rows, "k", "u", "b", least))
    revisits = heads.where("refers_to is not null").select(F.col("k").alias("rk"), F.col("digest").alias("rd"), "refers_to").distinct()
    count, most = revisits.count(), heads.agg(F.max("bytes")).first()[0] or 0
    payload = whole_text("b")
    own = rows.withColumn("digest", F.sha1(F.encode(payload, "UTF-8"))).withColumn("bytes", F.octet_length(payload).cast("long"))
    # equal pages with one id have one response among them
    joined = own.join(F.broadcast(revisits) if count <= few else revisits, (F.col("k") == F.col("rk")) & (F.col("digest") == F.col("rd")), "left")
    record = _record(F.col("k"), F.col("u"), payload, F.col("digest"), F.col("bytes"), F.col("refers_to"))

    def put(some: DataFrame, name: str, records: int) -> None:
        some.select(record.alias("value")).write.option("lineSep", CRLF * 2).option("compression", "gzip").option("maxRecordsPerFile", records).text(f"{folder}/{name}")

    put(joined.where(F.col("bytes") <= large), "pages", per_file)
    if most > large:
        put(joined.where(F.col("bytes") > large), "large-pages", max(1, PART // most))


def records(archive):
    """Header dictionary and block of each record of an uncompressed archive, a binary stream; one record is in memory."""
    while first := archive.readline():
        if not first.startswith(b"WARC/"):
            raise ValueError(f"no record begins with {first[:40]!r}")
        head = {}
        while (line := archive.readline()) not in (b"\r\n", b""):
            name, _, value = line.decode().rstrip(CRLF).partition(": ")
            head[name] = value
        block = archive.read(int(head["Content-Length"]))
        if archive.read(4) != b"\r\n\r\n":
            raise ValueError(f"record {head.get('WARC-Record-ID')} does not end where it says")
        yield head, block


def _page(name: str | None) -> int | None:
    text = (name or "").removeprefix("<urn:page:").removesuffix(">")
    return int(text) if text.lstrip("-").isdigit() else None


def read_headers(spark: SparkSession, folder: str) -> DataFrame:
    """One row a record of the archives below ``folder``; digests and sizes of payloads that are there are recomputed."""
    names = [c.split()[0] for c in HEADERS.split(", ")]

    def run(batches):
        for batch in batches:
            for path, content in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                rows = []
                for head, block in records(io.BufferedReader(gzip.GzipFile(fileobj=pa.BufferReader(content.as_buffer())))):
                    body = block[block.index(b"\r\n\r\n") + 4 :]
                    there = head["WARC-Type"] == "response"
                    rows.append((
                        _page(head["WARC-Record-ID"]), head["WARC-Type"], head["WARC-Record-ID"], _page(head.get("WARC-Refers-To")), head["WARC-Payload-Digest"].removeprefix("sha1:"), int(head["X-Payload-Length"]),
                        hashlib.sha1(body).hexdigest() if there else None, len(body) if there else None, head.get("WARC-Target-URI"), path,
                    ))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if k in (0, 3, 5, 7) else pa.string()) for k, c in enumerate(zip(*rows, strict=True))], names=names)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").option("recursiveFileLookup", True).load(folder).select("path", "content")
    return files.mapInArrow(run, HEADERS)


def resolved(headers: DataFrame) -> DataFrame:
    """Join revisit headers to the original responses; every record with digest and size of its full payload.

    A record whose stated digest and size are not those of its payload is told by ``intact`` = false.
    """
    originals = headers.where("record_type = 'response'").groupBy(F.col("payload_digest").alias("stated_digest"), F.col("page_id").alias("refers_to_id")).agg(F.max("payload_bytes").alias("n"))
    responses = headers.where("refers_to_id is null").withColumn("n", F.lit(None).cast("long"))
    revisits = settled(headers.where("refers_to_id is not null"))
    out = joined_unique(revisits, originals, ["stated_digest", "refers_to_id"]).unionByName(responses)
    digest = F.coalesce("payload_digest", F.when(F.col("n").isNotNull(), F.col("stated_digest")))
    size = F.coalesce("payload_bytes", "n")
    return out.select("page_id", size.alias("payload_bytes"), digest.alias("payload_digest"), "record_type", F.col("refers_to_id").alias("refers_to"), "url", "file", F.coalesce((digest == F.col("stated_digest")) & (size == F.col("stated_bytes")), F.lit(False)).alias("intact"))


def op5_warc_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages written to deduplicated archives and read back."""
    folder = shared_folder(spark, "warc")
    write(table(spark, sf_dir, "pages"), folder)
    headers = settled(read_headers(spark, folder))
    remove(spark, folder)  # what is asked for is in the headers
    return resolved(headers).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "intact")


OP5_SQL = f"""
with p as (
  select page_id, strlen(coalesce(html, '')) as payload_bytes, sha1(coalesce(html, '')) as payload_digest from pages
), o as (
  select payload_digest, max(page_id) as original from p where payload_bytes >= {LEAST} group by payload_digest
)
select page_id, payload_bytes, p.payload_digest,
       case when original is not null and original <> page_id then 'revisit' else 'response' end as record_type,
       case when original <> page_id then original end as refers_to, true as intact
from p left join o on p.payload_digest = o.payload_digest and payload_bytes >= {LEAST}
"""
