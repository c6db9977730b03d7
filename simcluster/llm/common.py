"""What the corpus operators share: scratch folders, size-checked broadcasts and small expressions."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a side of a join may be broadcast; callers keep rows under 100 bytes.
BROADCAST_ROWS = 200_000

#: Characters that part words in the contracts of the mixing and n-gram operators.
WORD = r"[^\x20\x09-\x0D]+"


def scratch_root(spark: SparkSession) -> str:
    """The shared folder named by spark.checkpoint.dir; where unset, a temporary folder under a local master only."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if root:
        return root
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    root = tempfile.mkdtemp(prefix="simcluster-")
    atexit.register(shutil.rmtree, root, True)
    root = f"file://{root}"
    spark.conf.set("spark.checkpoint.dir", root)
    return root


def scratch(spark: SparkSession, name: str) -> str:
    """A new path below the shared folder."""
    return f"{scratch_root(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: cuts the lineage, and survives the loss of executors."""
    spark = df.sparkSession
    path = scratch(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def release(*stages: DataFrame) -> None:
    """Delete stages of `materialize` that no later plan reads, and let Spark drop the shuffles behind them."""
    for df in stages:
        jvm = df.sparkSession._jvm
        path = jvm.org.apache.hadoop.fs.Path(df._scratch_path)
        path.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)
    if stages:
        drop_shuffles(stages[0].sparkSession)


def drop_shuffles(spark: SparkSession) -> None:
    """Shuffle files go when the driver's collector finds their plans unused; it is asked to look now."""
    gc.collect()  # Python's hold on plans first
    spark._jvm.System.gc()


def narrow(df: DataFrame, name: str) -> DataFrame:
    """materialize for tables of a few numbers a row: four files per core, or a sixteenth of the shuffle partitions if more, without a shuffle."""
    spark = df.sparkSession
    return materialize(df.coalesce(max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")) // 16)), name)


def small_side(df: DataFrame, max_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint if a count proves that df is small; else df as it is, for a shuffled join."""
    return F.broadcast(df) if df.limit(max_rows + 1).count() <= max_rows else df


def maybe_among(rows: DataFrame, col: str, keys: DataFrame, most_pages: int = 4096) -> DataFrame:
    """Rows whose value (null included) may be among the keys (one column): all that are, and few or some others.

    Up to BROADCAST_ROWS keys are broadcast; more go into bitmaps of 4 KB, most_pages at most, which are.
    """
    keys = keys.toDF("k").distinct()
    count = keys.count()
    if count <= BROADCAST_ROWS:
        return rows.join(F.broadcast(keys), F.col(col).eqNullSafe(F.col("k")), "left_semi")
    pages = min(most_pages, -(-16 * count // (1 << 15)))
    at = lambda c: F.pmod(F.xxhash64(c), F.lit(pages << 15)) + 1
    bitmaps = keys.groupBy(F.bitmap_bucket_number(at("k")).alias("page")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at("k"))).alias("bits"))
    place = F.bitmap_bit_position(at(col))
    byte = F.conv(F.hex(F.substring("bits", (place / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    met = rows.join(F.broadcast(bitmaps), F.bitmap_bucket_number(at(col)) == F.col("page"))
    return met.filter(F.getbit(byte, (place % 8).cast("int")) == 1).drop("page", "bits")


def free_name(df: DataFrame, name: str) -> str:
    """name, with underscores before it until df has no such column."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def keep_rows(docs: DataFrame, id_col: str, mark: Column, marks: DataFrame) -> DataFrame:
    """Rows of docs but those whose id and mark stand in marks (id, mark, stays, rows) without staying.

    Of rows that stay and agree in id and mark, one is kept. Only ids and marks of rows in groups are joined.
    """
    a, b, m = (free_name(docs, x) for x in ("gone_id", "gone_mark", "row_mark"))
    named = lambda x: small_side(x.select(F.col("id").alias(a), F.col("mark").alias(b)))
    gone, many = marks.filter("not stays"), marks.filter("stays and rows > 1")
    with_mark = docs.withColumn(m, mark)
    same = with_mark[id_col].eqNullSafe(F.col(a)) & (F.col(m) == F.col(b))
    kept = with_mark.join(named(gone), same, "left_anti")
    if many.isEmpty():
        return kept.drop(m)
    once = kept.join(named(many), same, "left_semi").dropDuplicates([id_col, m])
    return kept.join(named(many), same, "left_anti").unionByName(once).drop(m)


def crc_mod4(id_col: str) -> Column:
    """crc32 of the id as text, modulo 4; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % 4


def unit_hash(col: str | Column, seed: int) -> Column:
    """A number in [0, 1) that depends on the value and the seed only."""
    return F.pmod(F.xxhash64(F.lit(seed), col), F.lit(1 << 30)) / float(1 << 30)
