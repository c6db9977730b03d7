"""Benchmark decontamination with one Aho-Corasick automaton.

All windows of `WINDOW` consecutive words of every benchmark item go into one automaton (an item of fewer
words is one window), each framed by single spaces. A document is normalised to its words joined by single
spaces and scanned once; every match ends at a known place of the normalised text, which maps back to word
numbers and, for documents with hits, to code point offsets in the original text.

The pass over documents is narrow: no shuffle. Benchmarks of up to `MAX_WINDOWS` windows are held by every worker as one
automaton. Larger ones are dealt into automata of that size, by whole items; each scans all texts in a pass of its
own whose hits are written, and a last pass merges the hits, so a worker never holds more than one automaton.

Defined cases: null or wordless texts have no words and no hits; null or wordless items have no window;
an item without an id has windows that hit, but is not listed; several rows with one item_id count as one item; equal windows of several items hit all of these items.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, materialize

WINDOW = 10
MAX_WINDOWS = 500_000

#: Words of a text in UTF-8 whose ASCII letters are lower-cased.
WORD_BYTES = re.compile(rb"[0-9a-z\x80-\xff]+")
WORD_CHARS = re.compile("[0-9A-Za-z\x80-\U0010ffff]+")


def words_of(text: str | None) -> list[bytes]:
    return WORD_BYTES.findall(text.encode("utf-8", "surrogatepass").lower()) if text else []


def windows_of(items: list[tuple[str, str | None]], window: int = WINDOW) -> dict[str, tuple[int, list[str]]]:
    """Framed window -> (words in it, ids of the items that hold it)."""
    found: dict[str, tuple[int, list[str]]] = {}
    for item, text in items:
        words = words_of(text)
        n = min(window, len(words))
        for i in range(len(words) - n + 1 if n else 0):
            key = " " + b" ".join(words[i : i + n]).decode("latin-1") + " "
            ids = found.setdefault(key, (n, []))[1]
            if item is not None and item not in ids:
                ids.append(item)
    return found


def build(windows: dict[str, tuple[int, list[str]]]) -> ahocorasick.Automaton:
    automaton = ahocorasick.Automaton()
    for key, value in windows.items():
        automaton.add_word(key, value)
    automaton.make_automaton()
    return automaton


def scan_text(text: str | None, automaton: ahocorasick.Automaton) -> tuple[int, int, list[str], list[tuple[int, int]]]:
    """Words, hit words, sorted ids of items that occur, and the hit stretches as code point offsets."""
    words = words_of(text)
    if not words:
        return 0, 0, [], []
    line = " " + b" ".join(words).decode("latin-1") + " "
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)  # place of the space after each word
    cover, items = np.zeros(len(words) + 1, np.int64), set()
    for at, (n, ids) in automaton.iter(line) if len(automaton) else ():
        last = int(np.searchsorted(ends, at))
        cover[last - n + 1] += 1
        cover[last + 1] -= 1
        items.update(ids)
    hit = np.cumsum(cover[:-1]) > 0
    spans: list[tuple[int, int]] = []
    if hit.any():
        places = [m.span() for m in WORD_CHARS.finditer(text)]
        edges = np.flatnonzero(np.diff(np.r_[0, hit.astype(np.int8), 0]))
        spans = [(places[a][0], places[b - 1][1]) for a, b in zip(edges[::2], edges[1::2], strict=True)]
    return len(words), int(hit.sum()), sorted(items), spans


_automata: dict[str, ahocorasick.Automaton] = {}


def held_parts(docs: DataFrame, benchmark: DataFrame, item_col: str = "item_id", item_text: str = "text", window: int = WINDOW) -> list:
    """Broadcasts of the benchmark's windows, MAX_WINDOWS at most in each but for items that are longer alone; one at least.

    The benchmark comes to the driver item by item.
    """
    rows = benchmark.select(F.col(item_col).cast("string").alias("i"), F.col(item_text).alias("t")).orderBy("i", "t")
    parts, items, words = [], [], 0
    for r in rows.toLocalIterator():
        items.append((r["i"], r["t"]))
        words += len(words_of(r["t"]))
        if words >= MAX_WINDOWS:
            parts.append(docs.sparkSession.sparkContext.broadcast(windows_of(items, window)))
            items, words = [], 0
    if items or not parts:
        parts.append(docs.sparkSession.sparkContext.broadcast(windows_of(items, window)))
    return parts


def scanner(held):
    """A column function from text to struct<n_words, n_hit, items, starts, ends> over the windows of one broadcast."""
    key = uuid.uuid4().hex  # workers are used again: the automaton they hold may be another one's

    @F.pandas_udf("n_words long, n_hit long, items array<string>, starts array<long>, ends array<long>")
    def scan(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        if key not in _automata:
            _automata.clear()
            _automata[key] = build(held.value)
        automaton = _automata[key]
        for texts in batches:
            got = [scan_text(x if isinstance(x, str) else None, automaton) for x in texts]
            yield pd.DataFrame({"n_words": [g[0] for g in got], "n_hit": [g[1] for g in got], "items": [g[2] for g in got], "starts": [[a for a, _ in g[3]] for g in got], "ends": [[b for _, b in g[3]] for g in got]}, columns=["n_words", "n_hit", "items", "starts", "ends"]).astype({"n_words": "int64", "n_hit": "int64"})

    return scan.asNondeterministic()


def merge_hits(text: Column, parts: list[Column]) -> Column:
    """The hits of several scans of one text as one: stretches joined, hit words counted again."""

    @F.pandas_udf("n_words long, n_hit long, items array<string>, starts array<long>, ends array<long>")
    def merge(texts: pd.Series, hits: pd.Series) -> pd.DataFrame:
        out = []
        for own, parts in zip(texts, hits, strict=True):
            marks = [m.span() for m in WORD_CHARS.finditer(own)] if isinstance(own, str) else []
            cover = np.zeros(len(marks) + 1, np.int64)
            begins, ends = np.array([a for a, _ in marks]), np.array([b for _, b in marks])
            for part in parts:
                for a, b in zip(part["starts"], part["ends"], strict=True):
                    cover[np.searchsorted(begins, a)] += 1
                    cover[np.searchsorted(ends, b) + 1] -= 1
            hit = np.cumsum(cover[:-1]) > 0
            edges = np.flatnonzero(np.diff(np.r_[0, hit.astype(np.int8), 0]))
            stretches = [(marks[a][0], marks[b - 1][1]) for a, b in zip(edges[::2], edges[1::2], strict=True)]
            out.append((len(marks), int(hit.sum()), sorted({x for part in parts for x in part["items"]}), [a for a, _ in stretches], [b for _, b in stretches]))
        return pd.DataFrame(out, columns=["n_words", "n_hit", "items", "starts", "ends"]).astype({"n_words": "int64", "n_hit": "int64"})

    return merge(text, F.array(*parts))


def find_contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: id, n_words, n_hit, items, starts and ends of hit stretches."""
    parts = held_parts(docs, benchmark)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    if len(parts) == 1:
        return rows.select("id", scanner(parts[0])("text").alias("r")).select(F.col("id").alias(id_col), "r.*")
    for i, part in enumerate(parts):
        rows = materialize(rows.withColumn(f"r{i}", scanner(part)("text")), "benchmark-hits")
    merged = merge_hits(F.col("text"), [F.col(f"r{i}") for i in range(len(parts))])
    return rows.select("id", merged.alias("r")).select(F.col("id").alias(id_col), "r.*")


def items_digest(items: Column) -> Column:
    return F.sha2(F.concat_ws(",", F.array_sort(items)), 256)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, text_col: str = "text") -> DataFrame:
    """Rows of docs, all columns, in which no benchmark window occurs."""
    for part in held_parts(docs, benchmark):
        name = free_name(docs, "hits_of_row")
        docs = docs.withColumn(name, scanner(part)(F.col(text_col))).filter(F.col(f"{name}.n_hit") == 0).drop(name)
    return docs


def digest_of(items: list[str]) -> str:
    """What items_digest gives, for tests."""
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
