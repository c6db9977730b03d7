"""Writing and reading web archives, with boundary-chain verification.

Writing: each page becomes one record; of pages with equal payloads the one with the smallest id is the
response and the others revisit it. Records are lines of Spark's text sink whose line separator is the
record's own terminator, so archives are written in parallel to any store Spark knows, one file per task.

Reading: the text source cuts archives at the magic of a record, splitting large files between tasks. Each
task emits the candidates it meets, with their offsets relative to its split and the offset at which the next
record must begin by the declared length. Offsets become absolute by a running sum over the splits of a file.
Candidates whose successor is the very next candidate are chained inside a split; then pointer jumping from
the start of every file marks the reachable chains in a logarithmic number of rounds. What is not reachable is
magic inside a payload, and goes back into the payload that holds it.

Defined cases: null html is an empty payload; empty payloads can be equal like others (`min_bytes`: smaller
payloads are never revisits); null ids sort after all others and are written as a record id without a page, null
urls as no target; ids and urls are percent-encoded, so any text comes back; several rows with one id are several records; a page in a group refers to the smallest id; an empty table gives no records.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialize, scratch, small_side

MAGIC = "WARC/1.1\r\n"
END = "\r\n\r\n"
# The format's field texts.
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP_HEAD = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def base32(hexadecimal: Column) -> Column:
    """Base 32 of a 160 bit digest given in hexadecimal, five digits to four letters at a time."""
    letters = []
    for g in range(8):
        value = F.conv(F.substring(hexadecimal, 5 * g + 1, 5), 16, 10).cast("int")
        for shift in (15, 10, 5, 0):
            letters.append(F.substring(F.lit(ALPHABET), F.shiftright(value, shift).bitwiseAND(31) + 1, F.lit(1)))
    return F.concat(*letters)


def _one_line(value: Column) -> Column:
    """value on one line: what is no visible ASCII character, and the escape's own sign, in percent notation."""
    return F.regexp_replace(F.url_encode(value.cast("string")), r"\+", "%20")


def describe(pages: DataFrame, id_col: str = "page_id", html_col: str = "html", min_bytes: int = 0) -> DataFrame:
    """Groups of equal payloads: sum (SHA-256), first (smallest id), of groups with several rows only."""
    payload = F.coalesce(F.col(html_col), F.lit(""))
    rows = pages.select(F.col(id_col).alias("id"), F.sha2(payload, 256).alias("sum"), F.octet_length(payload).alias("n")).filter(F.col("n") >= min_bytes)
    return rows.groupBy("sum").agg(F.min("id").alias("first"), F.count("*").alias("rows")).filter("rows > 1").select("sum", "first")


def write_archives(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", min_bytes: int = 0, date: str = "2020-01-01T00:00:00Z") -> None:
    """Write all pages as records below path."""
    payload = F.coalesce(F.col(html_col), F.lit(""))
    groups = materialize(describe(pages, id_col, html_col, min_bytes), "warc-groups")
    rows = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), payload.alias("payload"), F.sha2(payload, 256).alias("sum"), F.octet_length(payload).alias("n")).join(small_side(groups), "sum", "left")
    revisit = F.col("first").isNotNull() & (F.col("n") >= min_bytes) & ~F.coalesce(F.col("id") == F.col("first"), F.lit(False))
    block = F.concat(F.lit(HTTP_HEAD), F.when(revisit, F.lit("")).otherwise(F.col("payload")))
    uri = lambda c: F.coalesce(F.concat(F.lit("<urn:page:"), _one_line(c), F.lit(">")), F.lit("<urn:page>"))
    fields = [
        (F.lit("WARC-Type"), F.when(revisit, F.lit("revisit")).otherwise(F.lit("response"))),
        (F.lit("WARC-Record-ID"), uri(F.col("id"))),
        (F.lit("WARC-Date"), F.lit(date)),
        (F.lit("WARC-Target-URI"), F.coalesce(_one_line(F.col("url")), F.lit(""))),
        (F.lit("WARC-Payload-Digest"), F.concat(F.lit("sha1:"), base32(F.sha1(F.col("payload"))))),
        (F.lit("X-Payload-Length"), F.col("n").cast("string")),
        (F.lit("Content-Type"), F.lit("application/http; msgtype=response")),
        (F.lit("Content-Length"), F.octet_length(block).cast("string")),
    ]
    more = F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), uri(F.col("first")), F.lit(f"\r\nWARC-Profile: {REVISIT_PROFILE}\r\n"))).otherwise(F.lit(""))
    head = F.concat(*[x for name, value in fields for x in (name, F.lit(": "), value, F.lit("\r\n"))], more)
    rows.select(F.concat(F.lit(MAGIC), head, F.lit("\r\n"), block).alias("value")).write.option("lineSep", END).text(path)


PIECE = "file string, split long, seq long, start long, size long, need long, head binary, sha1 string, payload_bytes long"


def _pieces(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Candidates of each split in order. start: offset in the split of what follows the magic; need: bytes up
    to the next record's magic by the declared length, -1 if the head is no record's."""
    at: dict[tuple[str, int], list[int]] = {}
    for pdf in batches:
        out = []
        for file, split, value in zip(pdf["file"], pdf["split"], pdf["value"], strict=True):
            place = at.setdefault((file, split), [0, 0])
            value = bytes(value)
            cut = value.find(b"\r\n\r\n")
            head = value[: cut + 2] if cut >= 0 else b""
            length = re.search(rb"(?:^|\r\n)Content-Length: *(\d{1,18})\r\n", head, re.I)
            need = cut + 4 + int(length[1]) + len(END) if length else -1
            sha1, n = None, None
            if length and need <= len(value) + len(END):
                block = value[cut + 4 : cut + 4 + int(length[1])]
                body = block[block.find(b"\r\n\r\n") + 4 :] if b"\r\n\r\n" in block else b""
                sha1, n = base64.b32encode(hashlib.sha1(body).digest()).decode(), len(body)
            out.append((file, split, place[1], place[0], len(value), need, head if length else b"", sha1, n))
            place[0] += len(value) + len(MAGIC)
            place[1] += 1
        yield pd.DataFrame(out, columns=["file", "split", "seq", "start", "size", "need", "head", "sha1", "payload_bytes"]).astype({"payload_bytes": "Int64"})


def read_pieces(spark: SparkSession, path: str) -> DataFrame:
    """One row per candidate of all archives below path, without payloads."""
    raw = spark.read.option("lineSep", MAGIC).text(path)
    raw = raw.select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("split"), F.col("value").cast("binary").alias("value"))
    return raw.mapInPandas(_pieces, PIECE)


def reachable(pieces: DataFrame) -> DataFrame:
    """The pieces that a chain from the start of their file reaches, with offset and successor."""
    spans = pieces.groupBy("file", "split").agg(F.sum(F.col("size") + len(MAGIC)).alias("span"))
    running = Window.partitionBy("file").orderBy("split").rowsBetween(Window.unboundedPreceding, -1)
    spans = materialize(spans.withColumn("base", F.coalesce(F.sum("span").over(running), F.lit(0))).drop("span"), "warc-splits")
    placed = pieces.join(small_side(spans), ["file", "split"]).withColumn("offset", F.col("base") + F.col("start"))
    # what stands before a file's first magic is no candidate; offsets are those after the magic
    found = placed.filter("need >= 0").withColumn("succ", F.col("offset") + F.col("need") + len(MAGIC))
    found = found.withColumn("following", F.lead("offset").over(Window.partitionBy("file", "split").orderBy("offset")))
    found = materialize(found, "warc-candidates")
    jumps = materialize(found.filter("following is null or following <> succ").select("file", F.col("succ").alias("offset"), F.lit(True).alias("landing")).distinct(), "warc-jumps")
    before = Window.partitionBy("file", "split").orderBy("offset")
    marked = found.join(small_side(jumps), ["file", "offset"], "left")
    marked = marked.withColumn("new", F.when(F.col("landing") | F.coalesce(F.lag("succ").over(before) != F.col("offset"), F.lit(True)), F.col("offset")))
    chained = materialize(marked.withColumn("chain", F.last("new", ignorenulls=True).over(before)).drop("new", "landing"), "warc-chained")
    # one node per chain: from its first offset to where its last record points
    nodes = chained.groupBy("file", "chain").agg(F.max("succ").alias("to"))
    step = materialize(nodes.select("file", F.col("chain").alias("at"), "to"), "warc-step")
    live = materialize(step.filter(F.col("at") == len(MAGIC)).select("file", "at"), "warc-live")
    while True:  # the live set doubles its depth in each round
        ahead = live.join(step, ["file", "at"]).select("file", F.col("to").alias("at")).join(step.select("file", "at"), ["file", "at"], "left_semi")
        grown = materialize(live.unionByName(ahead).distinct(), "warc-live")
        if grown.count() == live.count():
            break
        live = grown
        step = materialize(step.join(step.select("file", F.col("at").alias("to"), F.col("to").alias("then")), ["file", "to"], "left").select("file", "at", F.coalesce("then", "to").alias("to")), "warc-step")
    return chained.join(small_side(live.withColumnRenamed("at", "chain")), ["file", "chain"], "left_semi")


def _rejoin(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
    """Digest and length of one payload that magic had cut into pieces."""
    pdf = pdf.sort_values("offset")
    whole = MAGIC.encode().join(map(bytes, pdf["value"]))
    cut = whole.find(b"\r\n\r\n") + 4
    block = whole[cut : int(pdf["need"].max()) - len(END)]
    body = block[block.find(b"\r\n\r\n") + 4 :] if b"\r\n\r\n" in block else b""
    return pd.DataFrame({"file": [key[0]], "offset": [key[1]], "sha1": [base64.b32encode(hashlib.sha1(body).digest()).decode()], "payload_bytes": [len(body)]})


def _values(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    at: dict[tuple[str, int], int] = {}
    for pdf in batches:
        starts = []
        for file, split, value in zip(pdf["file"], pdf["split"], pdf["value"], strict=True):
            starts.append(at.get((file, split), 0))
            at[file, split] = starts[-1] + len(value) + len(MAGIC)
        yield pdf.assign(start=starts)


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """id (as text), record_type, refers_to (as text), payload_digest, payload_bytes, verified of every record.

    Digest and length are computed from the payload read back; for revisits they are the declared ones.
    """
    live = materialize(reachable(materialize(read_pieces(spark, path), "warc-pieces")), "warc-records")
    cut = live.filter("sha1 is null").select("file", F.col("offset").alias("owner"), "need")
    whole = live.filter("sha1 is not null").select("file", "offset", "head", "sha1", "payload_bytes")
    if not cut.isEmpty():  # payloads with magic inside: read their pieces again and join them
        bases = live.groupBy("file", "split").agg(F.max("base").alias("base"))
        raw = spark.read.option("lineSep", MAGIC).text(path).select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("split"), F.col("value").cast("binary").alias("value"))
        raw = raw.mapInPandas(_values, "file string, split long, value binary, start long").join(F.broadcast(cut.select("file").distinct()), "file").join(small_side(bases), ["file", "split"]).withColumn("offset", F.col("base") + F.col("start"))
        inside = raw.join(small_side(cut), "file").filter((F.col("offset") >= F.col("owner")) & (F.col("offset") < F.col("owner") + F.col("need")))
        mended = inside.groupBy("file", "owner").applyInPandas(_rejoin, "file string, offset long, sha1 string, payload_bytes long")
        whole = whole.unionByName(live.select("file", "offset", "head").join(mended, ["file", "offset"]))
    head = F.col("head").cast("string")
    field = lambda name: F.regexp_extract(head, rf"(?:^|\r\n){name}: ([^\r\n]*)\r\n", 1)
    page = lambda name: F.when(field(name).startswith("<urn:page:"), F.url_decode(F.regexp_extract(field(name), "^<urn:page:(.*)>$", 1)))
    revisit = field("WARC-Type") == "revisit"
    declared = F.regexp_replace(field("WARC-Payload-Digest"), "^sha1:", "")
    return whole.select(
        page("WARC-Record-ID").alias("id"),
        field("WARC-Type").alias("record_type"),
        F.when(revisit, page("WARC-Refers-To")).alias("refers_to"),
        F.when(revisit, declared).otherwise(F.col("sha1")).alias("payload_digest"),
        F.when(revisit, field("X-Payload-Length").cast("long")).otherwise(F.col("payload_bytes")).alias("payload_bytes"),
        (revisit | (declared == F.col("sha1"))).alias("verified"),
    )


def archive_round_trip(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", min_bytes: int = 0) -> DataFrame:
    """Write pages as archives in the shared folder and read them back."""
    spark = pages.sparkSession
    path = scratch(spark, "warc")
    write_archives(pages, path, id_col, url_col, html_col, min_bytes)
    kind = pages.schema[id_col].dataType
    return read_archives(spark, path).select(F.col("id").try_cast(kind).alias(id_col), "payload_bytes", "payload_digest", "record_type", F.col("refers_to").try_cast(kind).alias("refers_to"), "verified")
