"""Secret scanning over a trigram inverted index, in DataFrame expressions only.

Every rule's regular expression is compiled into a Boolean trigram query: the literal texts that any match
must hold, as alternatives of sets of trigrams. One pass over the texts posts (trigram, document) for the
trigrams that some rule needs; postings are intersected per alternative by counting, and only candidate
documents of a rule are verified with its expression. Rules without mandatory trigrams are scanned fully.

Postings are combined per document inside a task before they are shuffled, no key is hotter than one document
has trigrams, and texts are never shuffled: up to `BROADCAST_ROWS` candidates are broadcast with the rules they are
candidates of; more go into bitmaps of their ids (`CANDIDATE_PAGES` pages of 4 KB at most), whose hits are verified by
every rule. A candidate too many costs time, never a span.

Defined cases: null texts count as empty; rows with a null id have no postings and are verified by every
rule; several rows with one id share candidates and are verified each by itself; an empty table gives none.
"""

from __future__ import annotations

from dataclasses import dataclass
from re import _parser  # the standard library's parser of expressions

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common
from .common import materialize
from .spans import joined, labelled, match_spans

MOST_LITERALS = 64
CANDIDATE_PAGES = 4096


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    #: Least code points of a group (0: the match); shorter matches are dropped.
    group: int = 0
    least: int = 1


# The contract's expressions, with runs tried at their first character and possessive.
BASE_RULES = (
    Rule("assign", r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*+[:=]\x20*+["']?([A-Za-z0-9+/_.=-]++)""", 2, 8),
    Rule("access", r"AKIA[A-Z0-9]++", 0, 16),
    Rule("hex", r"(?<![0-9a-f])[0-9a-f]{32,}+", 0, 32),
)
# Further public token formats; their spans are added to the base ones.
MORE_RULES = (
    Rule("pem", r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----"),
    Rule("ghtoken", r"gh[pousr]_[A-Za-z0-9]{36,}+"),
    Rule("slack", r"xox[abprs]-[A-Za-z0-9-]{20,}+"),
    Rule("webtoken", r"eyJ[A-Za-z0-9_-]{10,}+\.eyJ[A-Za-z0-9_-]{10,}+\.[A-Za-z0-9_-]{10,}+"),
)
RULES = BASE_RULES + MORE_RULES


def _literals(tree) -> list[set[str] | None]:
    """Runs of alternative literals that a match holds in this order; None where anything may stand between."""
    runs: list[set[str] | None] = [{""}]

    def add(options: set[str] | None) -> None:
        last = runs[-1]
        if options is None:
            runs.extend((None, {""}))
        elif len(options) * len(last) > MOST_LITERALS:
            runs.extend((None, options))
        else:
            runs[-1] = {a + b for a in last for b in options}

    def exact(own: list) -> set[str] | None:
        return own[0] if len(own) == 1 else None

    for op, arg in tree:
        name = str(op)
        if name == "LITERAL":
            add({chr(arg).lower()})
        elif name == "SUBPATTERN":
            for i, part in enumerate(inner := _literals(arg[3])):
                if part is not None:
                    add(part)
                elif i < len(inner):
                    runs.extend((None, {""}))
        elif name == "ATOMIC_GROUP":
            for part in _literals(arg):
                runs.extend((None, {""})) if part is None else add(part)
        elif name == "BRANCH":
            options = [exact(_literals(x)) for x in arg[1]]
            add(set().union(*options) if all(x is not None for x in options) else None)
        elif name == "IN":
            chars = {chr(x).lower() for kind, x in arg if str(kind) == "LITERAL"}
            add(chars if len(chars) <= 8 and all(str(kind) == "LITERAL" for kind, _ in arg) else None)
        elif name in ("MAX_REPEAT", "MIN_REPEAT", "POSSESSIVE_REPEAT"):
            low, high, body = arg
            own = exact(_literals(body))
            if own is not None and high == 1:
                add(own | {""} if low == 0 else own)
            else:
                for _ in range(min(low, 8) if own is not None else 0):
                    add(own)
                if own is None and low:
                    for part in _literals(body):
                        runs.extend((None, {""})) if part is None else add(part)
                if high != low or own is None or low > 8:
                    runs.extend((None, {""}))
        elif name not in ("AT", "ASSERT", "ASSERT_NOT"):
            add(None)
    return runs


def trigram_query(pattern: str) -> list[frozenset[str]] | None:
    """Alternatives of trigram sets, in lower case, one of which every match holds; None: the rule has none."""
    runs = [x for x in _literals(_parser.parse(pattern)) if x and all(len(y) >= 3 for y in x)]
    if not runs:
        return None
    best = max(runs, key=lambda x: (min(map(len, x)), -len(x)))
    options = {frozenset(y[i : i + 3] for i in range(len(y) - 2)) for y in best}
    return sorted((x for x in options if not any(y < x for y in options)), key=sorted)


def build_index(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Postings (tri, id) of all trigrams that the rules need, written to the shared folder in order of tri."""
    needed = sorted({t for r in rules for alternative in trigram_query(r.pattern) or () for t in alternative})
    low = F.lower(F.col(text_col))
    present = F.array_compact(F.array(*[F.when(F.contains(low, F.lit(t)), F.lit(t)) for t in needed])) if needed else F.array().cast("array<string>")
    postings = docs.filter(F.col(id_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), F.explode(present).alias("tri"))
    return materialize(postings.sortWithinPartitions("tri"), "trigram-index")


def candidates(index: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """id and the kinds of rules whose trigram query the document meets."""
    spark = index.sparkSession
    clauses = [(r.kind, n, t, len(alternative)) for r in rules for n, alternative in enumerate(trigram_query(r.pattern) or ()) for t in sorted(alternative)]
    table = spark.createDataFrame(clauses, "kind string, clause int, tri string, need int")
    met = index.join(F.broadcast(table), "tri").groupBy("id", "kind", "clause", "need").agg(F.count_distinct("tri").alias("n")).filter("n = need")
    return met.groupBy("id").agg(F.collect_set("kind").alias("kinds"))


def rule_spans(text: Column, rule: Rule) -> Column:
    spans = match_spans(text, rule.pattern)
    measured = (lambda m: m) if not rule.group else (lambda m: F.regexp_extract(m, rule.pattern, rule.group))
    return F.filter(spans, lambda s: F.length(measured(s["m"])) >= rule.least) if rule.least > 1 else spans


def with_candidates(rows: DataFrame, found: DataFrame, rules: tuple[Rule, ...]) -> DataFrame:
    """rows with the kinds that each is a candidate of, or null."""
    count = found.count()
    if count <= common.BROADCAST_ROWS:
        return rows.join(F.broadcast(found), "id", "left")
    pages = min(CANDIDATE_PAGES, -(-16 * count // (1 << 15)))
    at = lambda c: F.pmod(F.xxhash64(c), F.lit(pages << 15)) + 1
    bitmaps = found.groupBy(F.bitmap_bucket_number(at("id")).alias("page")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at("id"))).alias("bits"))
    place = F.bitmap_bit_position(at("id"))
    byte = F.conv(F.hex(F.substring("bits", (place / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    maybe = rows.withColumn("page", F.bitmap_bucket_number(at("id"))).join(F.broadcast(bitmaps), "page", "left")
    every = F.array(*[F.lit(r.kind) for r in rules])
    return maybe.select("id", "text", F.when(F.getbit(byte, (place % 8).cast("int")) == 1, every).alias("kinds"))


def find_secrets(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and one array of spans (a, b, m, left) for every rule, under the rule's kind."""
    found = materialize(candidates(build_index(docs, rules, id_col, text_col), rules), "secret-candidates")
    rows = with_candidates(docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")), found, rules)
    none = F.array().cast("array<struct<a:bigint,b:bigint,m:string,left:string>>")
    columns = []
    for r in rules:
        spans = rule_spans(F.col("text"), r)
        if trigram_query(r.pattern) is not None:
            spans = F.when(F.col("id").isNull() | F.coalesce(F.array_contains("kinds", r.kind), F.lit(False)), spans).otherwise(none)
        columns.append(spans.alias(r.kind))
    return rows.select(F.col("id").alias(id_col), *columns)


def report(found: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id") -> DataFrame:
    """Counts and digest of the base kinds, and all spans as text, in order of start, then kind."""
    order = lambda s: F.transform(s, lambda x: F.struct(x["a"].alias("a"), x["k"].alias("k"), x["b"].alias("b"), x["t"].alias("t")))
    each = {r.kind: order(labelled(F.col(r.kind), r.kind, i)) for i, r in enumerate(rules)}
    base = F.concat(*[each[r.kind] for r in BASE_RULES])
    return found.select(F.col(id_col), *[F.size(r.kind).cast("long").alias(f"n_{r.kind}") for r in BASE_RULES], F.sha2(joined(base), 256).alias("base_sha256"), joined(F.concat(*each.values())).alias("spans"))
