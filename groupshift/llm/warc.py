"""A content-addressed WARC archive: payload bytes once each, exact record headers apart, records rebuilt by joins.

The archive is two tables. ``payloads`` has each distinct payload once under a strong digest (SHA-256, with its
length); ``headers`` has for every record its exact header bytes and the digest of its payload. All of it runs
inside the JVM.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import salted_join, shared_folder, work_table

#: Most repeated pages whose ids go to every executor; about 100 bytes each.
BROADCAST_ROWS = 500_000
#: The digits that conv() writes for base 32, and the alphabet of base 32 that WARC digests use.
CONV_DIGITS = "0123456789ABCDEFGHIJKLMNOPQRSTUV"
BASE32_DIGITS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
END = "\r\n\r\n"


@dataclass(frozen=True)
class Archive:
    payloads: DataFrame
    headers: DataFrame


def base32_sha1(payload: Column) -> Column:
    """SHA-1 in upper-case base 32. 160 bits are 4 times 40; 40 bits are 10 hexadecimal or 8 base-32 digits."""
    digest = F.sha1(payload)
    part = [F.lpad(F.conv(F.substring(digest, 1 + 10 * i, 10), 16, 32), 8, "0") for i in range(4)]
    return F.translate(F.concat(*part), CONV_DIGITS, BASE32_DIGITS)


def _header(kind: Column) -> Column:
    """The header block of a record, to the blank line; every value on it is that of the row."""
    uri = F.coalesce(F.col("url"), F.lit(""))
    safe = F.regexp_replace(uri, r"[\r\n]", "%0A")
    name = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("null")), F.lit(">"))
    revisit = kind == "revisit"
    return F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: "), kind,
        F.lit("\r\nWARC-Record-ID: "), name(F.col("page_id")),
        F.lit("\r\nWARC-Target-URI: "), safe,
        F.when(revisit, F.concat(
            F.lit("\r\nWARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest\r\nWARC-Refers-To: "),
            name(F.col("first_id")),
        )).otherwise(F.lit("")),
        F.lit("\r\nWARC-Payload-Digest: sha1:"), F.col("sha1"),
        F.lit("\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "),
        F.when(revisit, F.lit("0")).otherwise(F.col("payload_bytes").cast("string")),
        F.lit(END),
    )


def write_archive(
    pages: DataFrame, folder: str | None = None, min_revisit_bytes: int = 0, broadcast_rows: int = BROADCAST_ROWS
) -> Archive:
    """Writes a record for every row of pages (page_id, url, html); returns the archive as written.

    Of records with equal payloads of at least min_revisit_bytes bytes, that with the smallest page_id is a
    response and the others are revisits of it; records with smaller payloads are all responses. A null html is
    an empty payload, a null page_id comes last, a null url is written empty. Rows that repeat page_id and payload
    have the same type. An empty table gives an empty archive. Other columns are ignored.
    """
    spark = pages.sparkSession
    folder = folder or f"{shared_folder(spark)}/archive-{uuid.uuid4().hex}"
    rows = pages.select("page_id", "url", F.coalesce(F.col("html"), F.lit("")).cast("binary").alias("payload"))
    digests = work_table(
        rows.select(
            "page_id", "url", F.sha2("payload", 256).alias("sha256"), base32_sha1(F.col("payload")).alias("sha1"),
            F.octet_length("payload").cast("long").alias("payload_bytes"),
        ),
        "digests",
    )
    # One row for each digest, summed before the exchange: a payload that a third of all pages share is one key.
    firsts = digests.groupBy(F.col("sha256").alias("sha"), F.col("payload_bytes").alias("len")).agg(
        F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n")
    )
    repeats = work_table(firsts.where("n > 1").select("sha", "len", "first_id"), "repeats")
    n_repeats = repeats.count()
    small = F.broadcast(repeats) if n_repeats <= broadcast_rows else repeats
    same = (digests["sha256"] == small["sha"]) & (digests["payload_bytes"] == small["len"])
    typed = digests.join(small, same, "left").withColumn(
        "record_type",
        F.when(
            F.col("sha").isNull() | F.col("page_id").eqNullSafe(F.col("first_id")) | (F.col("payload_bytes") < min_revisit_bytes),
            "response",
        ).otherwise("revisit"),
    )
    typed.select(
        "page_id", "url", "sha256", _header(F.col("record_type")).cast("binary").alias("header")
    ).write.parquet(f"{folder}/headers")
    # Payloads: pages whose digest occurs once are written where they are read; only those that repeat move.
    own = rows.withColumn("sha256", F.sha2("payload", 256))
    once = own.join(small.select("sha"), own["sha256"] == F.col("sha"), "left_anti")
    several = own.join(small.select("sha"), own["sha256"] == F.col("sha"), "left_semi")
    firsts_only = several.join(
        small.select("sha", "first_id"), (F.col("sha256") == F.col("sha")) & F.col("page_id").eqNullSafe(F.col("first_id")), "left_semi"
    ).dropDuplicates(["sha256"])
    columns = ("sha256", F.octet_length("payload").cast("long").alias("payload_bytes"), "payload")
    once.select(*columns).unionByName(firsts_only.select(*columns)).write.parquet(f"{folder}/payloads")
    return read_archive(spark, folder)


def read_archive(spark: SparkSession, folder: str) -> Archive:
    return Archive(
        spark.read.schema("sha256 string, payload_bytes long, payload binary").parquet(f"{folder}/payloads"),
        spark.read.schema("page_id long, url string, sha256 string, header binary").parquet(f"{folder}/headers"),
    )


def _field(name: str) -> Column:
    return F.regexp_extract(F.col("header").cast("string"), rf"\r\n{name}: ([^\r\n]*)\r\n", 1)


def verified(archive: Archive) -> DataFrame:
    """The payload table with digests taken anew from the stored bytes; bytes that don't match their key raise an error."""
    found = archive.payloads.withColumn("again", F.sha2("payload", 256))
    broken = F.raise_error(F.concat(F.lit("stored payload differs from its digest "), F.col("sha256")))
    sound = (F.col("again") == F.col("sha256")) & (F.octet_length("payload") == F.col("payload_bytes"))
    return found.select(F.when(sound, F.col("sha256")).otherwise(broken).alias("sha256"), "payload", "payload_bytes")


def records(archive: Archive, *payload_columns: Column) -> DataFrame:
    """Every record read back: its header fields, joined with what payload_columns make of its payload.

    With no payload_columns the payload itself is joined. Naming small ones keeps payloads out of the exchange.
    """
    content = verified(archive).select("sha256", "payload_bytes", *(payload_columns or (F.col("payload"),)))
    heads = archive.headers.select(
        "page_id", "url", "header", "sha256", F.regexp_extract(F.col("header").cast("string"), r"WARC-Type: (\w+)", 1).alias("record_type"),
        F.regexp_extract(_field("WARC-Payload-Digest"), "sha1:(.*)", 1).alias("header_digest"),
        F.regexp_extract(_field("WARC-Refers-To"), r"<urn:page:(-?\d+)>", 1).try_cast("long").alias("refers_to"),
    )
    # Records of a payload that very many share are split, and the payload repeated for each part.
    uses = work_table(archive.headers.groupBy("sha256").agg(F.count(F.lit(1)).alias("uses")).where("uses > 1"), "uses")
    if uses.isEmpty():
        return heads.join(content, "sha256")
    content = content.join(uses, "sha256", "left").withColumn("uses", F.coalesce("uses", F.lit(1).cast("long")))
    return salted_join(heads, content, ["sha256"], "uses", archive.headers.count()).drop("uses")


def original_records(archive: Archive) -> DataFrame:
    """page_id and the record's bytes as a WARC file holds them: header, block, two line ends. A revisit has no block."""
    empty = F.lit("").cast("binary")
    block = F.when(F.col("record_type") == "response", F.col("payload")).otherwise(empty)
    return records(archive).select("page_id", F.concat(F.col("header"), block, F.lit(END).cast("binary")).alias("record"))


def export_warc(archive: Archive, path: str, records_per_file: int = 1000) -> None:
    """Writes the records as plain WARC files, by Spark's own text writer with a record's end as line end.

    Payloads are UTF-8, so a record is a string; response records come before revisits nowhere in particular.
    """
    text = original_records(archive).select(F.expr("decode(substr(record, 1, octet_length(record) - 4), 'UTF-8')").alias("value"))
    text.write.option("lineSep", END).option("maxRecordsPerFile", records_per_file).text(path)


def import_warc(spark: SparkSession, path: str) -> DataFrame:
    """page_id, record_type, payload of every record in WARC files under path; revisits have a null payload.

    Files are cut by Content-Length, as a payload may hold anything. Each file is one task's memory.
    """

    def cut(batches):
        import pyarrow as pa

        for batch in batches:
            for content in batch.column("content"):
                data, at, out = content.as_py(), 0, {"page_id": [], "record_type": [], "payload": []}
                while at < len(data):
                    end = data.index(b"\r\n\r\n", at)
                    fields = dict(line.split(b": ", 1) for line in data[at:end].split(b"\r\n")[1:])
                    size = int(fields[b"Content-Length"])
                    name = fields[b"WARC-Record-ID"][len(b"<urn:page:") : -1]
                    out["page_id"].append(None if name == b"null" else int(name))
                    out["record_type"].append(fields[b"WARC-Type"].decode())
                    out["payload"].append(None if fields[b"WARC-Type"] == b"revisit" else data[end + 4 : end + 4 + size])
                    at = end + 4 + size + 4
                yield pa.RecordBatch.from_pydict(
                    out, pa.schema([("page_id", pa.int64()), ("record_type", pa.string()), ("payload", pa.binary())])
                )

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return files.mapInArrow(cut, "page_id long, record_type string, payload binary")
