"""Mixing sources to target weights by capped water-filling.

Every source gets a share of the mix in proportion to its weight, but no more than `max_epochs` times its
own size; what a clamped source leaves over goes to the others in proportion to their weights until no
source is above its limit. With sources sorted by limit per weight, the level of the water is found in one
running sum, which gives the same targets as clamping and sharing out again and again.

A target of e times the source's size takes every document floor(e) times whole, and the documents that come
first in a seeded order once more, the last of them in part, so that the words taken meet the target.

Plan: one narrow pass over the texts writes (id, source, size, order key); sizes are summed by source and by
4096 slices of the key before any shuffle, so a hot source is no hot task; running sums run over slices, and
over rows only inside the one slice of each source in which the extra repetition ends.

Defined cases: null texts have size 0; a null source is a source of its own, ordered last; sources without
words get target 0; an empty table gives an empty mix; rows that repeat count as rows of their own and share
their place in the order, ties going by size.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, materialize, small_side

SHARE = 1.5
WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 2
SEED = 17
SLICE_DIGITS = 3  # hexadecimal digits of the key: 4096 slices


def sized(docs: DataFrame, id_col: str, text_col: str, source_col: str, seed: int, whole_rows: bool = False) -> DataFrame:
    """id, source, size in words, skey (source, nulls last), the seeded order key of every row and, if asked for, the row."""
    source = F.col(source_col).cast("string")
    return docs.select(
        F.col(id_col).alias("id"),
        source.alias("source"),
        F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
        F.when(source.isNull(), "1").otherwise(F.concat(F.lit("0"), source)).alias("skey"),
        F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(id_col).cast("string"), F.lit("null")))).alias("key"),
        *([F.struct(*docs.columns).alias("row")] if whole_rows else []),
    )


def targets(by_source: DataFrame, share: float = SHARE, weights: tuple[int, ...] = WEIGHTS, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """skey, source_size and target from skey and source_size: one row per source, in one small window."""
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    ranked = by_source.withColumn("weight", cycle[(F.row_number().over(Window.orderBy("skey")) - 1) % len(weights)]).withColumn("cap", F.lit(float(max_epochs)) * F.col("source_size"))
    order = Window.orderBy(F.col("cap") / F.col("weight"), "skey")
    levels = ranked.select("*", F.lit(share) * F.sum("source_size").over(Window.partitionBy()), F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("filled"), F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)).alias("open"))
    levels = levels.toDF(*by_source.columns, "weight", "cap", "budget", "filled", "open").withColumn("level", (F.col("budget") - F.col("filled")) / F.col("open"))
    free = F.min(F.when(F.col("cap") / F.col("weight") >= F.col("level"), F.struct(F.col("cap") / F.col("weight"), "skey", "level"))).over(Window.partitionBy())
    return levels.withColumn("water", free["level"]).select("skey", "source_size", F.when(F.col("water").isNull(), F.col("cap")).otherwise(F.least("cap", F.col("water") * F.col("weight"))).alias("target"))


def mix_sources(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", share: float = SHARE, weights: tuple[int, ...] = WEIGHTS, max_epochs: float = MAX_EPOCHS, seed: int = SEED, whole_rows: bool = False) -> DataFrame:
    """id, source, size, source_size, target and taken (words, repeats counted) of every row; whole_rows adds it as a struct."""
    rows = materialize(sized(docs, id_col, text_col, source_col, seed, whole_rows), "mix-sizes")
    slices = rows.groupBy("skey", F.substring("key", 1, SLICE_DIGITS).alias("slice")).agg(F.sum("size").alias("words"))
    slices = materialize(slices, "mix-slices")
    plan = targets(slices.groupBy("skey").agg(F.sum("words").alias("source_size")), share, weights, max_epochs)
    plan = plan.withColumn("goal", F.round("target").cast("long")).withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("goal") / F.col("source_size"))).otherwise(0).cast("long"))
    plan = plan.withColumn("more", F.col("goal") - F.col("whole") * F.col("source_size"))
    running = Window.partitionBy("skey").orderBy("slice")
    before = slices.withColumn("before", F.sum("words").over(running) - F.col("words"))
    edge = before.join(F.broadcast(plan), "skey").filter(F.col("before") <= F.col("more")).groupBy("skey").agg(F.max(F.struct("slice", "before")).alias("edge"))
    plan = materialize(plan.join(edge, "skey", "left").select("skey", "source_size", "target", "whole", "more", F.col("edge.slice").alias("edge_slice"), F.col("edge.before").alias("edge_before")), "mix-plan")
    joined = rows.join(small_side(plan), "skey").withColumn("slice", F.substring("key", 1, SLICE_DIGITS))
    plain = joined.filter(F.col("slice") != F.col("edge_slice")).withColumn("extra_words", F.when(F.col("slice") < F.col("edge_slice"), F.col("size")).otherwise(F.lit(0)))
    inner = Window.partitionBy("skey").orderBy("key", "id", "size").rowsBetween(Window.unboundedPreceding, -1)
    at_edge = joined.filter(F.col("slice") == F.col("edge_slice")).withColumn("left", F.col("more") - F.col("edge_before") - F.coalesce(F.sum("size").over(inner), F.lit(0)))
    at_edge = at_edge.withColumn("extra_words", F.greatest(F.lit(0), F.least("size", "left"))).drop("left")
    both = plain.unionByName(at_edge)
    return both.select(F.col("id").alias(id_col), "source", "size", "source_size", "target", (F.col("whole") * F.col("size") + F.col("extra_words")).cast("long").alias("taken"), *(["row"] if whole_rows else []))
