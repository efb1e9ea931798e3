"""Content-addressed WARC archive.

Payload bytes are stored once per digest; the exact header block of every
record is stored separately with the payload's digest; original records are
rebuilt by joining the two, byte by byte, and parsed from those bytes.  The
digest that addresses a payload is SHA-256, verified on writing (every row of a
digest must have one length and one SHA-1) and on reading (the block cut out of
a rebuilt record by its Content-Length is hashed again and must have the digest
that its header names).  ``export`` writes the rebuilt records as plain WARC
files; ``read_files`` reads such files in splits, as any text.

Defined results: a null payload is empty; among records with equal payloads of
at least ``min_revisit_bytes`` bytes the smallest page_id is the response and
the others are revisits that refer to it, smaller payloads are all responses; a
null page_id sorts last; repeated page_ids with equal payloads beyond the
smallest record stay one response per row; line breaks in a url become spaces;
an empty table writes an empty archive.  Extra columns of the input are not
stored.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

MIN_REVISIT_BYTES = 0
# Fixed: the base32 alphabet, and the date written to every record.
_B32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
DATE = "2024-01-01T00:00:00Z"
#: Stands for a null page_id inside the archive, so that it sorts last.
_NO_ID = (1 << 63) - 1


def base32(hex40: Column) -> Column:
    """Bare upper-case base32 of a 160-bit hex digest: 5 hex digits are 4 letters."""
    value = lambda i: F.conv(F.substring(hex40, 5 * i + 1, 5), 16, 10).cast("int")
    letter = lambda v, s: F.substring(F.lit(_B32), F.shiftright(v, s).bitwiseAND(F.lit(31)) + F.lit(1), F.lit(1))
    return F.concat(*[letter(value(i), s) for i in range(8) for s in (15, 10, 5, 0)])


def record_id(page_id: Column) -> Column:
    return F.concat(F.lit("<urn:page:"), F.coalesce(page_id.cast("string"), F.lit("none")), F.lit(">"))


def _start(archive: str) -> str:
    return f"WARC/1.1\r\nX-Archive-ID: {archive}\r\n"


def headers(archive: str, kind: Column, url: Column, page_id: Column, refers: Column, digest: Column, size: Column) -> Column:
    """A record's header block with the empty line that ends it.  Its second line,
    random for each archive, tells record starts from payloads that hold WARC."""
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit("\r\n"))
    clean = F.regexp_replace(F.coalesce(url, F.lit("")), r"[\r\n]+", " ")
    return F.concat(
        F.lit(f"{_start(archive)}"),
        line("WARC-Type", kind),
        line("WARC-Record-ID", record_id(page_id)),
        line("WARC-Date", F.lit(DATE)),
        line("WARC-Target-URI", clean),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), digest)),
        F.when(kind == "revisit", F.concat(
            line("WARC-Refers-To", record_id(refers)),
            line("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        )).otherwise(F.lit("")),
        F.lit("Content-Type: text/html; charset=utf-8\r\n"),
        line("Content-Length", F.when(kind == "revisit", F.lit("0")).otherwise(size.cast("string"))),
        F.lit("\r\n"),
    )


def write(pages: DataFrame, root: str, min_revisit_bytes: int = MIN_REVISIT_BYTES) -> None:
    """Write ``root/payloads`` (one row per payload) and ``root/records``."""
    # a column of its own in the input is never mixed up: everything is renamed here
    payload = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    keyed = pages.select(
        F.coalesce(F.col("page_id").cast("long"), F.lit(_NO_ID)).alias("page_id"), F.col("url").cast("string").alias("url"), payload.alias("payload")
    ).withColumn(
        "address", F.unhex(F.sha2("payload", 256))
    )
    facts = keyed.select(
        "page_id", "url", "address", F.octet_length("payload").cast("long").alias("size"), base32(F.sha1("payload")).alias("digest")
    )
    # one pass over the pages; from here on the payload itself is not needed
    facts.write.parquet(f"{root}/facts")
    facts = pages.sparkSession.read.schema(facts.schema).parquet(f"{root}/facts")
    first = facts.groupBy("address").agg(
        F.min("page_id").alias("first_id"),
        F.min("size").alias("size"),
        F.min("digest").alias("digest"),
        ((F.min("size") == F.max("size")) & (F.min("digest") == F.max("digest"))).alias("verified"),
    )
    # written, so that the rows of a payload that most pages share can be split in the joins
    first.write.parquet(f"{root}/first")
    first = pages.sparkSession.read.schema(first.schema).parquet(f"{root}/first")
    # payload bytes: the first row of each digest; rows repeated whole are one.
    # Join and duplicate removal share their keys, so payloads move once.
    stored = (
        keyed.select("address", "page_id", "payload")
        .join(first.select("address", F.col("first_id").alias("page_id"), "size", "digest", "verified"), ["address", "page_id"])
        .dropDuplicates(["address", "page_id"])
        .select(
            "address",
            F.when(F.col("verified"), F.col("payload")).otherwise(F.raise_error("two payloads share a digest")).alias("payload"),
            "size",
            "digest",
        )
    )
    stored.write.parquet(f"{root}/payloads")
    kind = F.when(
        (F.col("size") >= min_revisit_bytes) & (F.col("page_id") != F.col("first_id")), "revisit"
    ).otherwise("response")
    records = (
        facts.select("page_id", "url", "address")
        .join(first, "address")
        .withColumn("kind", kind)
        .withColumn("refers_to", F.when(F.col("kind") == "revisit", F.col("first_id")))
        .withColumn("page_id", F.when(F.col("page_id") != _NO_ID, F.col("page_id")))
        .select(
            "page_id",
            "refers_to",
            "kind",
            "address",
            F.encode(headers(uuid.uuid4().hex, F.col("kind"), F.col("url"), F.col("page_id"), F.col("refers_to"), F.col("digest"), F.col("size")), "UTF-8").alias("header"),
        )
    )
    records.write.parquet(f"{root}/records")


_BREAK = "\r\n\r\n"


def read_records(spark: SparkSession, root: str, kind: str | None = None) -> DataFrame:
    """Original records: header block, payload and the record's bytes.

    A revisit gets the payload it refers to in ``payload``; ``record`` holds
    the bytes as archived (a revisit's block is empty)."""
    payloads = spark.read.parquet(f"{root}/payloads").select("address", "payload")
    records = spark.read.parquet(f"{root}/records")
    if kind:
        records = records.filter(F.col("kind") == kind)
    block = F.when(F.col("kind") == "response", F.col("payload")).otherwise(F.encode(F.lit(""), "UTF-8"))
    return records.join(payloads, "address").withColumn("record", F.concat("header", block, F.encode(F.lit(_BREAK), "UTF-8")))


def parsed(records: DataFrame, record: str = "record") -> DataFrame:
    """``records`` with what the bytes of each say: page_id, record_type,
    refers_to, named (the digest), block, whole (lengths and ends agree)."""
    text = F.col(record).cast("string")
    head = F.concat(F.substring_index(text, _BREAK, 1), F.lit("\r\n"))
    field = lambda name: F.regexp_extract("_head", rf"(?m)^{name}: ([^\r]*)\r", 1)
    page = lambda name: F.regexp_extract(field(name), r"^<urn:page:(-?\d+)>$", 1).try_cast("long")
    size, start = field("Content-Length").try_cast("int"), F.octet_length("_head") + 2
    return (
        records.withColumn("_head", head)
        .withColumn("page_id", page("WARC-Record-ID"))
        .withColumn("record_type", field("WARC-Type"))
        .withColumn("refers_to", page("WARC-Refers-To"))
        .withColumn("named", field("WARC-Payload-Digest"))
        .withColumn("block", F.substring(F.col(record), start + 1, size))
        .withColumn("whole", (F.octet_length(record) == start + size + 4) & (F.substring(F.col(record), -4, 4) == F.encode(F.lit(_BREAK), "UTF-8")))
        .drop("_head")
    )


def read_index(spark: SparkSession, root: str) -> DataFrame:
    """Per record its id, type and payload facts, all read from the rebuilt
    records: responses with their payload, then revisits, which must name the
    digest and the id of the response that they are joined with."""
    got = parsed(read_records(spark, root, "response").select("address", "record"))
    digest = base32(F.sha1("block"))
    good = F.col("whole") & (F.col("record_type") == "response") & (F.col("named") == F.concat(F.lit("sha1:"), digest))
    responses = got.select(
        "address",
        "page_id",
        F.octet_length("block").cast("long").alias("payload_bytes"),
        F.when(good & (F.unhex(F.sha2("block", 256)) == F.col("address")), digest)
        .otherwise(F.raise_error("a record does not match its digest"))
        .alias("payload_digest"),
        "record_type",
        "refers_to",
    )
    responses.write.parquet(f"{root}/read")
    responses = spark.read.schema(responses.schema).parquet(f"{root}/read")
    empty = F.concat("header", F.encode(F.lit(_BREAK), "UTF-8"))
    revisits = parsed(spark.read.parquet(f"{root}/records").filter("kind = 'revisit'").select("address", empty.alias("record")))
    seen = responses.select("address", F.col("page_id").alias("seen_id"), "payload_bytes", "payload_digest")
    right = F.col("whole") & (F.col("named") == F.concat(F.lit("sha1:"), F.col("payload_digest"))) & F.col("refers_to").eqNullSafe(F.col("seen_id"))
    joined = revisits.join(seen, "address", "left").select(
        "page_id",
        "payload_bytes",
        F.when(right, F.col("payload_digest")).otherwise(F.raise_error("a revisit does not match its response")).alias("payload_digest"),
        "record_type",
        "refers_to",
    )
    return responses.drop("address").unionByName(joined)


def archive(pages: DataFrame, min_revisit_bytes: int = MIN_REVISIT_BYTES) -> DataFrame:
    """Write the archive to the shared folder, then read it back."""
    spark = pages.sparkSession
    root = common.shared_dir(spark, "warc")
    write(pages, root, min_revisit_bytes)
    return read_index(spark, root)


def export(spark: SparkSession, root: str, path: str) -> None:
    """Write the archive's records as plain WARC files, one for each task."""
    value = F.expr("substring(record, 1, octet_length(record) - 4)").cast("string").alias("value")
    read_records(spark, root).select(value).write.option("lineSep", _BREAK).text(path)  # the writer ends each record


def read_files(spark: SparkSession, path: str) -> DataFrame:
    """The records of exported WARC files as ``record`` and what ``parsed`` adds."""
    first = spark.read.text(path).limit(2).collect()
    if not first:
        return parsed(spark.createDataFrame([], "record binary"))
    start = _start(first[1][0].removesuffix("\r").split(": ", 1)[1])
    # what stands between separators lacks its start, but for the first of a file, and
    # its end, but for the last of a file, as its length tells
    value = F.when(F.startswith("value", F.lit(start)), F.col("value")).otherwise(F.concat(F.lit(start), F.col("value")))
    rows = parsed(spark.read.option("lineSep", _BREAK + start).text(path).select(F.encode(value, "UTF-8").alias("part")), "part")
    over = F.octet_length("part") - F.octet_length(F.substring_index(F.col("part").cast("string"), _BREAK, 1)) - 4 - F.octet_length("block")
    record = F.when((over == 4) & F.col("whole"), F.col("part")).otherwise(F.concat("part", F.encode(F.lit(_BREAK), "UTF-8")))
    return parsed(rows.select(record.alias("record")))


ORACLE = """
WITH p AS (
  SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
h AS (
  SELECT page_id, octet_length(b) AS n, sha1(b) AS x, min(page_id) OVER (PARTITION BY b) AS f FROM p)
SELECT page_id, n::BIGINT AS payload_bytes,
  array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    1 + ((('0x' || substr(x, 5 * (i // 4)::INT + 1, 5))::INT >> (15 - 5 * (i % 4)::INT)) & 31), 1)), '') AS payload_digest,
  CASE WHEN page_id = f THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = f THEN NULL ELSE f END AS refers_to
FROM h
"""
