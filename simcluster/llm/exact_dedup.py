"""Exact deduplication over a log-structured merge index, in DataFrame expressions only.

Memtables (the rows of one task) are flushed as a run of (digest, id, rows) sorted by digest: a narrow pass, no
shuffle. When a level holds `FANOUT` runs, they are merged into one run of the next level: equal digests are
combined inside every task first, so that a hot digest is no hot task, and the identifier that stays is kept.
Every run has a filter of its digests (bitmaps of `PAGE_BITS` bits, sized by the run's entries): `lookup` asks each
run's filter before it reads the run. `compact` merges all levels and gives the entries with several rows; a filter
over these lets all other texts skip the byte verification. Texts of hits meet the text of the row that stays, and
only rows whose bytes are equal count as its copies. Rows that share a digest but no bytes are grouped by their
bytes instead. A filter is broadcast up to `MOST_PAGES` pages; beyond, runs are joined without one.

A merge is an aggregation by digest over the runs, since Spark reads sorted files in no given order; what the levels
save is that a batch is merged with few others before the large runs.

Joins of rows to entries are plain equi-joins of two exchanges, which adaptive execution splits where a digest
is hot.

Defined cases: null texts count as empty texts; a null id never stays while another row of its group has an
id; in a group without any id every row counts as kept; several rows with the same text and the same, staying id
are all kept (`drop_copies` leaves one of them); an empty table gives an empty result.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import keep_rows, materialize, scratch, small_side

FANOUT = 4
PAGE_BITS = 1 << 15  # bits of one bitmap of bitmap_construct_agg
MOST_PAGES = 4096  # 16 MB
BITS_PER_ENTRY = 16


def _bit(digest: Column, pages: int) -> Column:
    """A filter position from a hexadecimal digest; the built-in bitmap functions count from 1."""
    return F.pmod(F.xxhash64(digest), F.lit(pages * PAGE_BITS)) + 1


@dataclass
class Run:
    """A sorted run of (digest, keep_id, rows) and, once asked for, its filter."""

    entries: DataFrame
    pages: int
    filter: DataFrame | None = None

    def has(self, rows: DataFrame) -> DataFrame:
        """Rows (with a digest) that the run's filter cannot rule out."""
        if self.pages > MOST_PAGES:
            return rows
        if self.filter is None:
            self.filter = materialize(filter_pages(self.entries, self.pages), "digest-filter")
        return maybe_in(rows, self.filter, self.pages)


def pages_of(entries: DataFrame) -> int:
    return max(1, math.ceil(entries.count() * BITS_PER_ENTRY / PAGE_BITS))


class DigestLog:
    """Levels of sorted runs of (digest, keep_id, rows) below the shared folder."""

    def __init__(self, spark: SparkSession, largest: bool = True):
        self.spark, self.largest, self.levels = spark, largest, [[]]

    def add(self, rows: DataFrame, id_col: str, text_col: str) -> DataFrame:
        """Flush one batch as a run, every task its rows in order; full levels are merged. Gives the batch's (digest, id)."""
        text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
        path = scratch(self.spark, "digest-run")
        rows.select(F.sha2(text, 256).alias("digest"), F.col(id_col).alias("id")).sortWithinPartitions("digest", "id").write.parquet(path)
        flushed = self.spark.read.parquet(path)
        entries = flushed.select("digest", F.col("id").alias("keep_id"), F.lit(1).cast("long").alias("rows"))
        self.levels[0].append(Run(entries, pages_of(entries)))
        level = 0
        while len(self.levels[level]) >= FANOUT:
            merged, self.levels[level] = self._merge(self.levels[level]), []
            if level + 1 == len(self.levels):
                self.levels.append([])
            self.levels[level + 1].append(merged)
            level += 1
        return flushed

    def _merge(self, runs: list[Run]) -> Run:
        entries = materialize(self._combined(runs).sortWithinPartitions("digest"), "digest-level")
        return Run(entries, pages_of(entries))

    def _combined(self, runs: list[Run]) -> DataFrame:
        keep = F.max("keep_id") if self.largest else F.min("keep_id")
        return reduce(DataFrame.unionByName, [r.entries for r in runs]).groupBy("digest").agg(keep.alias("keep_id"), F.sum("rows").alias("rows"))

    def runs(self) -> list[Run]:
        return [r for level in self.levels for r in level]

    def lookup(self, digests: DataFrame) -> DataFrame:
        """digest, keep_id and rows of the given digests (one column) that the index holds, run by run through the filters."""
        digests = digests.distinct()
        hits = [Run(r.has(digests).join(r.entries, "digest"), r.pages) for r in self.runs()]
        return self._combined(hits)

    def compact(self) -> DataFrame:
        """All levels as one run; its entries (digest, keep_id, group_size) with several rows."""
        bottom = self.runs()
        if len(bottom) > 1:
            bottom = [self._merge(bottom)]
            self.levels = [[] for _ in self.levels[:-1]] + [bottom]
        keep = self._combined(bottom).filter("rows > 1").withColumnRenamed("rows", "group_size")
        return materialize(keep.sortWithinPartitions("digest"), "digest-several")


def filter_pages(entries: DataFrame, pages: int) -> DataFrame:
    """Bitmaps over digests: at most so many rows of PAGE_BITS / 8 bytes."""
    at = _bit(F.col("digest"), pages)
    return entries.groupBy(F.bitmap_bucket_number(at).alias("page")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits"))


def maybe_in(rows: DataFrame, bitmaps: DataFrame, pages: int) -> DataFrame:
    """Rows (with a digest) that the bitmaps cannot rule out."""
    place = _bit(F.col("digest"), pages)
    at = F.bitmap_bit_position(place)
    byte = F.conv(F.hex(F.substring(F.col("bits"), (at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    hit = F.getbit(byte, (at % 8).cast("int")) == 1
    return rows.withColumn("page", F.bitmap_bucket_number(place)).join(F.broadcast(bitmaps), "page").filter(hit).drop("page", "bits")


def verify(docs: DataFrame, level: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """digest, id and same (bytes equal to those of the row that stays) of rows with an entry."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    hits = Run(level, pages_of(level)).has(docs.select(F.col(id_col).alias("id"), text.alias("text"), F.sha2(text, 256).alias("digest")))
    stays = level.select(F.col("digest").alias("of"), F.col("keep_id"))
    keepers = hits.join(stays, (F.col("digest") == F.col("of")) & F.col("id").eqNullSafe(F.col("keep_id"))).select("digest", F.col("text").alias("kept_text")).dropDuplicates(["digest"])
    keepers = materialize(keepers, "digest-keepers")
    return hits.select("digest", "id", "text").join(keepers, "digest").select("digest", "id", (F.col("text") == F.col("kept_text")).alias("same"), F.when(F.col("text") != F.col("kept_text"), F.col("text")).alias("other"))


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", largest: bool = True) -> DataFrame:
    """id, keep_id, group_size, kept and text_sha256 of every row."""
    log = DigestLog(docs.sparkSession, largest)
    rows = log.add(docs, id_col, text_col)
    level = log.compact()
    checked = materialize(verify(docs, level, id_col, text_col).filter("not same"), "digest-unequal")
    if not checked.isEmpty():  # two texts share a digest: group these rows by their bytes
        keep = F.max("id") if largest else F.min("id")
        apart = checked.groupBy("digest", "other").agg(keep.alias("keep_id"), F.count("*").alias("group_size"))
        parted = checked.join(apart, ["digest", "other"]).select("digest", "id", F.col("keep_id").alias("own_keep"), F.col("group_size").alias("own_size"))
        fewer = checked.groupBy("digest").agg(F.count("*").alias("gone"))
        level = level.join(fewer, "digest", "left").select("digest", "keep_id", (F.col("group_size") - F.coalesce("gone", F.lit(0))).alias("group_size"))
        out = rows.join(level, "digest", "left").join(parted.distinct(), ["digest", "id"], "left").withColumns({"keep_id": F.coalesce("own_keep", "keep_id"), "group_size": F.coalesce("own_size", "group_size")})
    else:
        out = rows.join(level, "digest", "left")
    keep_id = F.when(F.col("group_size").isNull(), F.col("id")).otherwise(F.col("keep_id"))
    return out.select(F.col("id").alias(id_col), keep_id.alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"), F.col("id").eqNullSafe(keep_id).alias("kept"), F.col("digest").alias("text_sha256"))


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", largest: bool = True) -> DataFrame:
    """Rows of docs, all columns, one of each group of equal texts.

    Rows are told by id and text, so a repeated or null id costs no other text its row.
    """
    copies = exact_groups(docs, id_col, text_col, largest).filter("group_size > 1")
    marks = materialize(copies.groupBy(F.col(id_col).alias("id"), F.col("text_sha256").alias("mark")).agg(F.max("kept").alias("stays"), F.count("*").alias("rows")), "copies")
    return keep_rows(docs, id_col, F.sha2(F.coalesce(F.col(text_col).cast("string"), F.lit("")), 256), marks)
