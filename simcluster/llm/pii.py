"""Personal data by patterns of form, widened by bootstrapped contextual extraction; DataFrame expressions only.

Emails, addresses of hosts, payment cards and phone numbers that match the base expressions are the seed
entities. Their left and right contexts (two words each, or a line's only one) are lexical patterns; every
identifier-like token or run of digit groups that no base span covers is an instance of unknown kind in some context.
The graph of patterns and instances is scored in rounds: a pattern is as reliable for a kind as the share of its instances that are known of that kind, and
counts from `MIN_SEEDS` different known instances on; an instance that reliable patterns extract becomes
known, if its form is not at odds with the kind, and supports further patterns. Base spans always stay.

Plan: one narrow pass writes spans and contexts without the texts; rounds aggregate the small edge table by
pattern (combined before the shuffle) and join pattern scores back, one row per pattern.

Defined cases: null texts count as empty; failing matches are dropped, not tried again; repeated rows are
handled each by itself; an empty table gives none.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .spans import joined, labelled, match_spans

# The contract's expressions; runs are tried at their first character, repeated groups possessive.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
KINDS = tuple(PATTERNS)
#: Runs of digit groups that a space, parenthesis, dot or hyphen joins, and other tokens with a digit or an at sign.
_GROUP = r"[0-9]++(?=[\x20().-]|[,;:!?\"'\]]*+(?!\S))"
TOKEN = rf"(?<!\S)(?:[+(]*+{_GROUP}(?:(?:\)[\x20.-]?+|[\x20.-])\(?+{_GROUP})*+(?=[).,;:!?\"'\]-]*+(?!\S))|[^\s0-9@]*+[0-9@]\S*+)"
ROUNDS = 3
MIN_SEEDS = 4
MIN_CONFIDENCE = 0.8
MIN_SCORE = 0.8


def luhn(digits: Column) -> Column:
    """Whether the check digit of a text of digits fits."""
    reverse = F.split(F.reverse(digits), "")
    total = F.aggregate(
        F.transform(reverse, lambda x, i: F.when(i % 2 == 0, x.cast("int")).otherwise(x.cast("int") * 2 - F.when(x.cast("int") > 4, 9).otherwise(0))),
        F.lit(0),
        lambda acc, x: acc + F.coalesce(x, F.lit(0)),
    )
    return total % 10 == 0


def _valid(kind: str, m: Column) -> Column:
    digits = F.regexp_replace(m, r"[^0-9]", "")
    if kind == "ip":
        return F.forall(F.split(m, r"\."), lambda p: F.regexp_like(p, F.lit("^0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])$")))
    if kind == "card":
        return F.when(F.length(digits).between(13, 19), luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(digits).between(9, 15)
    return F.lit(True)


def base_spans(text: Column, kind: str) -> Column:
    spans = match_spans(text, PATTERNS[kind], across=True)
    return spans if kind == "email" else F.filter(spans, lambda s: _valid(kind, s["m"]))


def context_of(left: Column) -> Column:
    """The last two words before an entity, in lower case, digits as 0.

    A line's only word before it stands alone, after a mark; where its line has none, the words of the lines before count.
    """
    found = lambda pattern: F.nullif(F.regexp_extract(left, pattern, 1), F.lit(""))
    label = F.concat(F.lit("^ "), found(r"(?:^|\n)[^\S\n]*(\S+)[^\S\n]+$"))
    words = F.coalesce(found(r"(\S+[^\S\n]+\S+)[^\S\n]+$"), label, found(r"(\S+\s+\S+)\s+$"), F.lit(""))
    return F.regexp_replace(F.lower(words), r"[0-9]", "0")


def context_after(right: Column) -> Column:
    """The first two words after an entity and its punctuation, in the form of context_of; marked as those of the right."""
    found = lambda pattern: F.nullif(F.regexp_extract(right, pattern, 1), F.lit(""))
    label = F.concat(found(r"^[^\w\s]{0,4}[^\S\n]+(\S+)[^\S\n]*+(?:$|\n)"), F.lit(" $"))
    words = F.coalesce(found(r"^[^\w\s]{0,4}[^\S\n]+(\S+[^\S\n]+\S+)"), label, found(r"^[^\w\s]{0,4}\s+(\S+\s+\S+)"), F.lit(""))
    return F.when(words == "", "").otherwise(F.concat(F.lit("> "), F.regexp_replace(F.lower(words), r"[0-9]", "0")))


def _shape_fits(kind: Column, token: Column) -> Column:
    n = F.length(F.regexp_replace(token, r"[^0-9]", ""))
    return F.when(kind == "email", F.contains(token, F.lit("@"))).when(kind == "card", n.between(13, 19)).when(kind == "phone", n.between(9, 15)).when(kind == "ip", n.between(4, 12) & F.contains(token, F.lit("."))).otherwise(False)


def bootstrap(edges: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """inst and kind of newly known instances, from edges (pattern, inst, kind or null)."""
    links = materialize(edges.filter("pattern <> ''").groupBy("pattern", "inst").agg(F.max("kind").alias("seed")), "pii-links")
    known = links.filter("seed is not null").select("inst", F.col("seed").alias("kind")).distinct()
    new = None
    for _ in range(rounds):
        marked = links.join(known, "inst", "left")
        totals = marked.groupBy("pattern").agg(F.count_distinct("inst").alias("total"), *[F.count_distinct(F.when(F.col("kind") == k, F.col("inst"))).alias(k) for k in KINDS])
        best = totals.select("pattern", "total", F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), F.col(k).alias("hits")) for k in KINDS])).alias("x")).select("pattern", F.col("x.kind").alias("kind"), "total", F.col("x.hits").alias("hits"))
        reliable = best.filter((F.col("hits") >= MIN_SEEDS) & (F.col("hits") >= MIN_CONFIDENCE * F.col("total"))).withColumn("miss", F.log(1.0001 - F.col("hits") / F.col("total")))
        found = links.filter("seed is null").join(reliable, "pattern").filter(_shape_fits(F.col("kind"), F.col("inst"))).groupBy("inst", "kind").agg((1 - F.exp(F.sum("miss"))).alias("score"))
        new = materialize(found.filter(F.col("score") >= MIN_SCORE).groupBy("inst").agg(F.max_by("kind", F.struct("score", "kind")).alias("kind")), "pii-found")
        known = links.filter("seed is not null").select("inst", F.col("seed").alias("kind")).distinct().unionByName(new)
    return new


def find_personal_data(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """row, id, the base spans of every kind, and the added ones (kind, a, b)."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    spans = docs.select(F.col(id_col).alias("id"), *[base_spans(text, k).alias(k) for k in KINDS], match_spans(text, TOKEN, across=True).alias("tokens"))
    covered = lambda s: F.exists(F.concat(*KINDS), lambda x: (x["a"] < s["b"]) & (s["a"] < x["b"]))
    looks = lambda s: F.contains(s["m"], F.lit("@")) | (F.length(F.regexp_replace(s["m"], r"[^0-9]", "")) >= 6)
    edge = lambda s, kind: F.struct(kind.cast("string").alias("kind"), s["a"].alias("a"), s["b"].alias("b"), F.lower(s["m"]).alias("inst"), context_of(s["left"]).alias("pattern"), context_after(s["right"]).alias("after"))
    trimmed = lambda s: F.struct(s["a"].alias("a"), s["b"].alias("b"))
    seeds = lambda k: F.transform(k, lambda s: edge(s, F.lit(k)))
    edges = F.concat(*map(seeds, KINDS), F.transform(F.filter(F.filter("tokens", looks), lambda s: ~covered(s)), lambda s: edge(s, F.lit(None))))
    rows = materialize(spans.select(F.monotonically_increasing_id().alias("row"), "id", *[F.transform(k, trimmed).alias(k) for k in KINDS], edges.alias("edges")), "pii-spans")
    flat = rows.select("row", F.explode("edges").alias("e")).select("row", "e.*")
    new = bootstrap(flat.select(F.explode(F.array("pattern", "after")).alias("pattern"), "inst", "kind"))
    added = flat.filter("kind is null").drop("kind").join(new, "inst").groupBy("row").agg(F.collect_list(F.struct("kind", "a", "b")).alias("added"))
    return rows.drop("edges").join(added, "row", "left").withColumnRenamed("id", id_col)


def report(found: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Counts and digest of base spans, and all spans as text, in order of kind, then start."""
    base = F.concat(*[labelled(F.col(k), k, i) for i, k in enumerate(KINDS)])
    rank = F.create_map(*[x for i, k in enumerate(KINDS) for x in (F.lit(k), F.lit(i))])
    added = F.transform(F.coalesce("added", F.array().cast("array<struct<kind:string,a:bigint,b:bigint>>")), lambda s: F.struct(rank[s["kind"]].alias("k"), s["a"].alias("a"), s["b"].alias("b"), F.concat_ws(":", s["kind"], s["a"].cast("string"), s["b"].cast("string")).alias("t")))
    return found.select(F.col(id_col), *[F.size(k).cast("long").alias(f"n_{k}") for k in KINDS], F.sha2(joined(base), 256).alias("base_sha256"), joined(F.concat(base, added)).alias("spans"))
