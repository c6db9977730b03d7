"""Places of regular expression matches in DataFrame expressions only.

A text cut at its matches and the list of these matches give every match's start as a running sum of lengths
in code points. The sum runs over chunks of matches, so that a text with very many stays cheap. Patterns must
be safe on very long texts: repeated groups are possessive, which Java's engine walks in a loop, and
open-ended runs are tried at their first character only.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = "array<struct<a:bigint,b:bigint,m:string,left:string>>"
SPAN_ACROSS = "array<struct<a:bigint,b:bigint,m:string,left:string,right:string>>"
CHUNK = 64
CONTEXT = 160


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body of a value that is evaluated once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _running(items: Column, width: Callable[[Column], Column], made: Callable[[Column, Column], Column], kind: str, first: Column) -> Column:
    """made(item, sum of the widths before it) of every item."""
    return F.aggregate(
        items,
        F.struct(first.cast("bigint").alias("at"), F.array().cast(kind).alias("out")),
        lambda acc, x: F.struct((acc["at"] + width(x)).cast("bigint").alias("at"), F.concat(acc["out"], F.array(made(x, acc["at"]))).alias("out")),
        lambda acc: acc["out"],
    )


def match_spans(text: Column, pattern: str, across: bool = False) -> Column:
    """array<struct<a, b, m, left>>: start, end (exclusive), text and left context of every leftmost match.

    The left context ends at the previous match. With across it reaches over the two matches before, and right is the
    context after the match that reaches over the two matches after.
    """
    kind = SPAN_ACROSS if across else SPAN

    def span(x: Column, at: Column) -> Column:
        more = [x["right"].alias("right")] if across else []
        return F.struct((at + x["gap"]).cast("bigint").alias("a"), (at + x["gap"] + F.length(x["m"])).cast("bigint").alias("b"), x["m"].alias("m"), x["left"].alias("left"), *more)

    def placed(items: Column) -> Column:
        chunks = F.transform(F.sequence(F.lit(0), F.floor((F.size(items) - 1) / CHUNK).cast("int")), lambda c: F.slice(items, c * CHUNK + 1, F.lit(CHUNK)))
        wide = F.transform(chunks, lambda c: F.struct(c.alias("c"), F.aggregate(c, F.lit(0).cast("bigint"), lambda acc, x: acc + x["gap"] + F.length(x["m"])).alias("w")))
        return let(wide, lambda cs: F.flatten(F.zip_with(cs, _running(cs, lambda c: c["w"], lambda c, at: at, "array<bigint>", F.lit(0)), lambda c, at: _running(c["c"], lambda x: x["gap"] + F.length(x["m"]), span, kind, at))))

    def reaching(xs: Column) -> Column:
        before = lambda i, n: F.when(i >= n, let(F.get(xs, i - n), lambda p: F.concat(p["left"], F.right(p["m"], F.lit(CONTEXT))))).otherwise("")
        after = lambda i, n: F.when(i + n < F.size(xs), let(F.get(xs, i + n), lambda p: F.concat(F.left(p["m"], F.lit(CONTEXT)), p["right"]))).otherwise("")
        return F.transform(xs, lambda x, i: F.struct(x["m"].alias("m"), x["gap"].alias("gap"), F.right(F.concat(before(i, 2), before(i, 1), x["left"]), F.lit(CONTEXT)).alias("left"), F.left(F.concat(x["right"], after(i, 1), after(i, 2)), F.lit(CONTEXT)).alias("right")))

    both = F.struct(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("m"), F.split(text, pattern, -1).alias("g"))
    if across:
        items = let(both, lambda s: F.transform(s["m"], lambda m, i: F.struct(m.alias("m"), F.length(F.get(s["g"], i)).cast("bigint").alias("gap"), F.right(F.get(s["g"], i), F.lit(CONTEXT)).alias("left"), F.left(F.get(s["g"], i + 1), F.lit(CONTEXT)).alias("right"))))
        items = let(items, reaching)
    else:
        items = let(both, lambda s: F.zip_with(s["m"], F.slice(s["g"], F.lit(1), F.size(s["m"])), lambda m, g: F.struct(m.alias("m"), F.length(g).cast("bigint").alias("gap"), F.right(g, F.lit(CONTEXT)).alias("left"))))
    return F.when(F.regexp_like(text, F.lit(pattern)), let(items, placed)).otherwise(F.array().cast(kind))


def labelled(spans: Column, kind: str, rank: int) -> Column:
    """The spans as structs of rank, start and their text kind:start:end."""
    return F.transform(spans, lambda s: F.struct(F.lit(rank).alias("k"), s["a"].alias("a"), s["b"].alias("b"), F.concat_ws(":", F.lit(kind), s["a"].cast("string"), s["b"].cast("string")).alias("t")))


def joined(spans: Column) -> Column:
    """The texts of labelled spans in their order, with commas between."""
    return F.concat_ws(",", F.transform(F.array_sort(spans), lambda s: s["t"]))
