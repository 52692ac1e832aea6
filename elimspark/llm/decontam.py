"""Benchmark decontamination: approximate search for test items by pigeonhole pieces.

Texts and items are compared in lower case with every run of other signs than letters
and digits as one space. An item of m signs may be changed by a budget of
``RATE`` * m edits (at least one). Cut into budget + 1 pieces, at least one piece of any
such occurrence is unchanged: all pieces of all items are searched at once by an
Aho-Corasick automaton, and around each hit Myers' bit-parallel distance verifies the item.

The automaton travels with the tasks, so its size is checked: items beyond
``PIECE_LIMIT`` signs are searched in further passes over the documents.

Items of fewer than ``SHORT`` signs would match anything within an edit of one: they have
budget 0 and count between word borders only.

Edge cases: null and empty texts hold nothing; items without a letter or digit and null
items are nothing to look for; a null doc_id gives a
row with null doc_id; equal items each give a row; rows of one doc_id are merged, the
least distance stays.
"""

from __future__ import annotations

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import keep_where

RATE, SHORT, PIECE_LIMIT = 0.06, 24, 8_000_000


def plain(column: Column) -> Column:
    """Lower case, other signs than letters and digits as single spaces."""
    return F.trim(F.regexp_replace(F.lower(column.cast("string")), r"[^\p{L}\p{N}]+", " "))


def budget(length: int, rate: float = RATE) -> int:
    return max(1, int(rate * length)) if length >= SHORT else 0


def myers(pattern: str, text: str, most: int) -> int | None:
    """Least edit distance of the pattern to any part of the text, if at most ``most``.

    One machine word per text sign however long the pattern is: Python's integers hold
    the vertical differences of a whole column.
    """
    m = len(pattern)
    masks: dict[str, int] = {}
    for k, sign in enumerate(pattern):
        masks[sign] = masks.get(sign, 0) | 1 << k
    full, top = (1 << m) - 1, 1 << (m - 1)
    up, down, score, best = full, 0, m, m
    for sign in text:
        match = masks.get(sign, 0)
        diagonal = (((match & up) + up) ^ up) | match | down
        rise = down | ~(diagonal | up) & full
        fall = up & diagonal
        if rise & top:
            score += 1
        elif fall & top:
            score -= 1
            if score < best:
                best = score
                if not best:
                    break
        rise, fall = rise << 1 & full, fall << 1 & full
        up = fall | ~(diagonal | rise) & full
        down = rise & diagonal
    return best if best <= most else None


class Pieces:
    """Automaton over the pieces of a set of items."""

    def __init__(self, items: list[tuple[int, str]], rate: float = RATE):
        self.items = [(i, t, budget(len(t), rate)) for i, t in items]
        where: dict[str, list[tuple[int, int]]] = {}
        for k, (_, text, edits) in enumerate(self.items):
            cuts = [round(j * len(text) / (edits + 1)) for j in range(edits + 2)]
            for a, b in zip(cuts, cuts[1:]):
                where.setdefault(text[a:b], []).append((k, a))
        self.automaton = ahocorasick.Automaton()
        for piece, places in where.items():
            if piece:
                self.automaton.add_word(piece, (len(piece), places))
        self.empty = not len(self.automaton)
        if not self.empty:
            self.automaton.make_automaton()

    def search(self, text: str) -> list[tuple[int, int]]:
        """(item_id, least distance) of the items that occur in the text."""
        if self.empty or not text:
            return []
        spans: dict[int, list[tuple[int, int]]] = {}
        whole: dict[int, int] = {}
        for end, (length, places) in self.automaton.iter(text):
            for k, offset in places:
                _, item, edits = self.items[k]
                start = end - length + 1 - offset
                if len(item) < SHORT:
                    if (start == 0 or text[start - 1] == " ") and (end + 1 == len(text) or text[end + 1] == " "):
                        whole[k] = 0
                    continue
                spans.setdefault(k, []).append((start - edits, start + len(item) + edits))
        found = [(self.items[k][0], edits) for k, edits in whole.items()]
        for k, windows in spans.items():
            ident, item, edits = self.items[k]
            windows.sort()
            best, low, high = None, *windows[0]
            for a, b in [*windows[1:], (None, None)]:
                if a is not None and a <= low + edits + 1:
                    high = max(high, b)
                    continue
                part = text[max(0, low) : max(0, high)]
                got = 0 if item in part else myers(item, part, edits)
                if got is not None and (best is None or got < best):
                    best = got
                if best == 0 or a is None:
                    break
                low, high = a, b
            if best is not None:
                found.append((ident, best))
        return found


def item_slices(benchmark: DataFrame, limit: int = PIECE_LIMIT) -> list[list[tuple[int, str]]]:
    """The items in plain form, in slices of at most ``limit`` signs (or one item)."""
    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), plain(F.col("text")).alias("text")).where("text <> ''").orderBy("item_id", "text").toLocalIterator()
    slices: list[list[tuple[int, str]]] = [[]]
    size = 0
    for row in rows:
        if size + len(row.text) > limit and slices[-1]:
            slices.append([])
            size = 0
        slices[-1].append((row.item_id, row.text))
        size += len(row.text)
    return slices


def leaks(documents: DataFrame, benchmark: DataFrame, rate: float = RATE, limit: int = PIECE_LIMIT) -> DataFrame:
    """(doc_id, item_id, edits): the test items that each document holds, with the least distance."""
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), plain(F.col("text")).alias("text")).where("text <> ''")

    def searcher(items):
        def run(batches):
            pieces = Pieces(items, rate)
            for batch in batches:
                docs, idents, edits = [], [], []
                for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
                    for ident, distance in pieces.search(text):
                        docs.append(doc)
                        idents.append(ident)
                        edits.append(distance)
                yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(idents, pa.int64()), pa.array(edits, pa.int64())], ["doc_id", "item_id", "edits"])

        return run

    found = None
    for items in item_slices(benchmark, limit):
        part = texts.mapInArrow(searcher(items), "doc_id long, item_id long, edits long")
        found = part if found is None else found.unionByName(part)
    return found.groupBy("doc_id", "item_id").agg(F.min("edits").alias("edits"))


def semi_global(pattern: str, text: str) -> int:
    """Plain dynamic programme for the same distance, for tests."""
    row = np.arange(len(pattern) + 1)
    best = row[-1]
    for sign in text:
        new = np.empty_like(row)
        new[0] = 0
        for k in range(1, len(row)):
            new[k] = min(row[k - 1] + (pattern[k - 1] != sign), row[k] + 1, new[k - 1] + 1)
        row = new
        best = min(best, row[-1])
    return int(best)


def without_leaks(documents: DataFrame, benchmark: DataFrame, rate: float = RATE, limit: int = PIECE_LIMIT) -> DataFrame:
    """The rows that hold no test item, all columns unchanged; a filter per slice of items, no join."""

    def clean(items):
        def judge_of():
            pieces = Pieces(items, rate)
            return lambda text: not pieces.search(text)

        return judge_of

    kept = documents
    for items in item_slices(benchmark, limit):
        kept = keep_where(kept, plain(F.col("text")), clean(items))
    return kept
