"""Operator 7: benchmark decontamination by pigeonhole edit matching.

An item of n characters may differ from a stretch of a document by k = budget *
n edits.  Cut into k + 1 pieces, at least one piece of a matching item is in
the document unchanged, so an Aho-Corasick automaton over all pieces finds
every candidate place; there Myers' bit-parallel recurrence gives the least
edit distance of the whole item to any stretch of the text around it, and
places within k are hits.

Both sides are compared in lower case with every run of characters that are
neither letters nor digits made one blank.  Spans are given in the original
text.  Documents are read once for every `block_chars` characters of benchmark
text, so the automaton has a bound whatever the benchmark's size; documents are
never shuffled or compared with each other.

Null and empty documents match nothing.  Items that are null or hold no letter
or digit are skipped.  An item of fewer than `least_words` words and fewer than
5 * `least_words` characters may not differ at all and must stand on word
borders, since little remains of so short a text after edits; beside a character
of a script without blanks no border is asked for.  Repeated items give a row each.  One row per (document row, item) that
match: the place of least distance (leftmost on ties), and the number of places.
A very long text is searched whole, in memory of a few times its size.  Empty
tables of either kind give no rows, and all documents are clean.  `find_items`
reads no other columns, whatever their names; `is_clean` keeps them and
replaces a column of its output's name.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from runstore.llm import base

_WORD = re.compile(r"[^\W_]+")
#: Characters of scripts that put no blanks between words.
_UNSPACED = re.compile("[\u0e00-\u109f\u1780-\u17ff\u2e80-\u9fff\uf900-\ufaff\U00020000-\U0003ffff]")
BUDGET, LEAST_WORDS, BLOCK_CHARS = 0.08, 5, 8_000_000


def normal(text: str) -> str:
    return " ".join(_WORD.findall(text.lower()))


def distance_in(pattern: str, text: str, most: int) -> tuple[int, int] | None:
    """(least edit distance of pattern to a stretch of text, that stretch's end), leftmost; None above most."""
    m = len(pattern)
    where: dict[str, int] = {}
    for i, c in enumerate(pattern):
        where[c] = where.get(c, 0) | 1 << i
    full, top = (1 << m) - 1, 1 << (m - 1)
    plus, minus, score, best = full, 0, m, (most + 1, -1)
    for j, c in enumerate(text):
        eq = where.get(c, 0)
        cross = eq | minus
        eq = (((eq & plus) + plus) ^ plus) | eq
        up = minus | (full & ~(eq | plus))
        down = plus & eq
        if up & top:
            score += 1
        elif down & top:
            score -= 1
            if score < best[0]:
                best = (score, j + 1)
        up, down = up << 1, down << 1
        plus = (down | ~(cross | up)) & full
        minus = up & cross & full
    return best if best[0] <= most else None


def is_short(item: str, least_words: int) -> bool:
    """Whether a normalised item is only looked for as it stands."""
    return item.count(" ") + 1 < least_words and len(item) < 5 * least_words


def on_borders(text: str, start: int, end: int) -> bool:
    """Whether no word runs across either end of text[start:end]."""
    return all(k in (0, len(text)) or " " in text[k - 1 : k + 1] or _UNSPACED.search(text[k - 1 : k + 1]) for k in (start, end))


class Matcher:
    """Finds a block of items in documents."""

    def __init__(self, items: list[tuple[int | None, str]], budget: float, least_words: int = LEAST_WORDS):
        import ahocorasick

        self.items = items
        self.short = [is_short(text, least_words) for _, text in items]
        self.errors = [0 if short else int(budget * len(text)) for short, (_, text) in zip(self.short, items)]
        pieces: dict[str, list[tuple[int, int]]] = {}
        for i, (_, text) in enumerate(items):
            k = self.errors[i]
            cuts = [len(text) * j // (k + 1) for j in range(k + 2)]
            for a, b in zip(cuts, cuts[1:]):
                pieces.setdefault(text[a:b], []).append((i, a))
        self.automaton = ahocorasick.Automaton()
        for p, uses in pieces.items():
            self.automaton.add_word(p, (len(p), uses))
        self.automaton.make_automaton()

    def find(self, text: str) -> list[tuple[int, int, int, int, int]]:
        """(item index, distance, start, end, places) in a normalised text."""
        if not text:
            return []
        starts: dict[int, list[int]] = {}
        for end, (size, uses) in self.automaton.iter(text):
            for i, at in uses:
                starts.setdefault(i, []).append(end + 1 - size - at)
        out = []
        for i, at in starts.items():
            item, k = self.items[i][1], self.errors[i]
            at.sort()
            if self.short[i]:
                at = [a for a in at if on_borders(text, a, a + len(item))]
            best, places, j = None, 0, 0
            while j < len(at):  # candidates closer than 2k share a window
                last = j
                while last + 1 < len(at) and at[last + 1] - at[last] <= 2 * k + 1:
                    last += 1
                left = max(0, at[j] - k)
                window = text[left : at[last] + len(item) + k]
                exact = window.find(item)
                got = (0, exact + len(item)) if exact >= 0 else k and distance_in(item, window, k)
                if got:
                    places += 1
                    if best is None or got[0] < best[0]:
                        back = distance_in(item[::-1], window[: got[1]][::-1][: len(item) + k], k) if got[0] else (0, len(item))
                        best = (got[0], left + got[1] - back[1], left + got[1])
                j = last + 1
            if best:
                out.append((i, *best, places))
        return out


def raw_span(text: str, start: int, end: int) -> tuple[int, int]:
    """Where characters start..end of normal(text) are in text, widened to whole words."""
    at, first, last, low = 0, None, 0, text.lower()
    for m in _WORD.finditer(low):
        size = m.end() - m.start()
        if first is None and at + size > start:
            first = m.start()
        if at >= end:
            break
        last = m.end()
        at += size + 1
    first = first or 0
    if len(low) == len(text):
        return first, last
    ends = list(accumulate(len(c.lower()) for c in text))  # some letters are longer in lower case
    return bisect_right(ends, first), min(len(text), bisect_left(ends, last) + 1)


def _blocks(benchmark: DataFrame, item_col: str, text_col: str, block_chars: int) -> Iterator[list]:
    """Items (id, normalised text), in blocks whose size is counted before they reach the driver."""
    items = benchmark.select(F.col(item_col).cast("long").alias("i"), F.col(text_col).alias("t")).where("t is not null")
    total = items.agg(F.sum(F.length("t"))).first()[0] or 0
    n = -(-total // block_chars)
    for b in range(n):
        part = items if n == 1 else items.where(F.pmod(F.xxhash64("i", "t"), F.lit(n)) == b)
        rows = sorted(((r["i"], normal(r["t"])) for r in part.collect()), key=lambda r: (r[0] is None, r[0] or 0, r[1]))
        yield [r for r in rows if r[1]]


def find_items(docs: DataFrame, benchmark: DataFrame, budget: float = BUDGET, least_words: int = LEAST_WORDS, block_chars: int = BLOCK_CHARS, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """Rows (doc_id, item_id, distance, span_start, span_end, places) of contaminated documents."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("t")).where("t is not null")
    schema = "doc_id long, item_id long, distance int, span_start long, span_end long, places int"
    out = None
    for number, items in enumerate(_blocks(benchmark, item_col, item_text_col, block_chars)):
        if not items:
            continue
        found = rows.mapInArrow(_search(items, budget, least_words, number), schema)
        out = found if out is None else out.union(found)
    return spark.createDataFrame([], schema) if out is None else out


def _matcher(items: list, budget: float, least_words: int, number: int):
    """A function that gives this worker's automaton for a block of items."""
    key = ("matcher", number, len(items), hash(tuple(items)), budget, least_words)

    return lambda: base.held(key, lambda: Matcher(items, budget, least_words))


def _search(items: list, budget: float, least_words: int, number: int):
    matcher = _matcher(items, budget, least_words, number)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find = matcher().find
        for batch in batches:
            found: list[list] = [[] for _ in range(6)]
            for doc, text in zip(batch.column(0), batch.column(1)):
                text = text.as_py()
                for i, d, a, b, places in find(normal(text)):
                    for column, v in zip(found, (doc.as_py(), items[i][0], d, *raw_span(text, a, b), places)):
                        column.append(v)
            types = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(found, types)], names=["doc_id", "item_id", "distance", "span_start", "span_end", "places"])

    return run


def is_clean(docs: DataFrame, benchmark: DataFrame, out: str, budget: float = BUDGET, least_words: int = LEAST_WORDS, block_chars: int = BLOCK_CHARS, text_col: str = "text") -> DataFrame:
    """docs with a new boolean column that is false where any item matches; no shuffle, no join."""
    docs = docs.withColumn(out, F.lit(True))
    for number, items in enumerate(_blocks(benchmark, "item_id", "text", block_chars)):
        if items:
            rows = docs.select("*", F.col(f"`{text_col}`").alias("__text"))
            docs = rows.mapInArrow(_flag(items, budget, least_words, number, docs.columns.index(out)), docs.schema)
    return docs


def _flag(items: list, budget: float, least_words: int, number: int, at: int):
    matcher = _matcher(items, budget, least_words, number)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find = matcher().find
        for batch in batches:
            texts, was = batch.column(batch.num_columns - 1), batch.column(at).to_pylist()
            columns = list(batch.columns[:-1])
            columns[at] = pa.array([w and not find(normal(t.as_py() or "")) for w, t in zip(was, texts)], pa.bool_())
            yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names[:-1])

    return run


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_items(base.table(spark, sf_dir, "documents"), base.table(spark, sf_dir, "benchmark"))
