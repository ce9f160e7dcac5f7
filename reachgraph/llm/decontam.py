"""Benchmark decontamination by counted word pairs and local alignment.

A document holds an item if a Smith-Waterman alignment over words, 1 for a match
and -1 for a mismatch or a gap, scores at least a share of the item's words, so
that edited and paraphrased copies score by how much of the item they keep, in
order. Where no two matches follow each other directly, each match but one costs
a penalty; an alignment of score s thus has at least s - 1 pairs of neighbouring
words that stand in the item too, and it spans a bounded stretch of the document.
Stretches with so many pairs of an item are aligned with it and no others need
be: no item and no pair is left out for being frequent or rare.

Items come in blocks of a fixed number, so what the executors hold does not
grow; the documents are read once per block and never shuffled.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.llm.common import bound_batches
from reachgraph.llm.near_dup import Shingler

#: ASCII punctuation and control characters become blanks.
_PLAIN = bytes(c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


class Words:
    """Texts as arrays of word hashes and of word n-gram hashes."""

    def __init__(self) -> None:
        self.hash = Shingler(1)

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").lower().encode("utf-8", "surrogatepass").translate(_PLAIN).split()
        return np.fromiter(map(self.hash._word, words), dtype=np.uint64, count=len(words))

    @staticmethod
    def grams(words: np.ndarray, width: int) -> np.ndarray:
        out = np.zeros(max(0, len(words) - width + 1), dtype=np.uint64)
        for i in range(width):
            out = (out ^ (out >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15) + words[i : len(words) - width + 1 + i]
        return out


def align(item: np.ndarray, passage: np.ndarray) -> tuple[int, int]:
    """Best local alignment score and its end in the passage: 1 for a match, -1 for a mismatch or a gap."""
    steps = np.arange(len(passage) + 1)
    above = np.zeros(len(passage) + 1, dtype=np.int64)
    best, end = 0, 0
    for word in item:
        row = np.maximum(above - 1, 0)
        row[1:] = np.maximum(row[1:], above[:-1] + np.where(passage == word, 1, -1))
        row = np.maximum.accumulate(row + steps) - steps
        top = int(row.argmax())
        if row[top] > best:
            best, end = int(row[top]), top
        above = row
    return best, end


class Finder:
    """Finds the stretches of a document that an item can be aligned with."""

    #: Words of a document looked at in one go, at least, so that memory is bounded by the items and not by the text.
    SLICE = 1024

    def __init__(self, items: list[np.ndarray], width: int, least: float) -> None:
        sizes = np.array([len(w) for w in items], dtype=np.int64)
        goal = np.array([max(1, math.ceil(least * n)) for n in sizes.tolist()], dtype=np.int64)
        whole = sizes < width
        self.gram = np.where(whole, sizes, np.where(goal > 1, 2, 1))
        self.need = np.where(whole | (goal < 2), 1, goal - 1)
        # an alignment of score goal has at most so many words of the document
        self.span = np.maximum(2 * sizes - goal, self.gram)
        self.lists = []
        for gram in sorted(set(self.gram.tolist())):
            own = [(i, np.unique(Words.grams(items[i], gram))) for i in np.flatnonzero(self.gram == gram).tolist()]
            values, owners = np.concatenate([g for _, g in own]), np.repeat([i for i, _ in own], [len(g) for _, g in own])
            by = np.argsort(values, kind="stable")
            known, start, count = np.unique(values[by], return_index=True, return_counts=True)
            self.lists.append((gram, known, start, count, owners[by]))

    def __call__(self, words: np.ndarray) -> dict[int, list[tuple[int, int]]]:
        """By number of the item, the stretches [start, end), in order and apart."""
        found: dict[int, list[tuple[int, int]]] = {}
        for gram, known, start, count, owners in self.lists:
            overlap = int(self.span[self.gram == gram].max()) + gram
            size = max(2 * overlap, self.SLICE)
            grams = Words.grams(words, gram)
            where, at = _among(grams, known)
            for lo in range(0, len(grams), size - overlap):
                a, b = np.searchsorted(where, (lo, lo + size))
                if a < b:
                    self._slice(where[a:b], start[at[a:b]], count[at[a:b]], owners, len(words), found)
        return {item: _joined(some) for item, some in sorted(found.items())}

    def _slice(self, where: np.ndarray, start: np.ndarray, count: np.ndarray, owners: np.ndarray, n: int, found: dict) -> None:
        """Adds the stretches around as many hits of an item as it needs, within its span."""
        steps = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        item, pos = owners[np.repeat(start, count) + steps], np.repeat(where, count)
        enough = np.bincount(item, minlength=len(self.need)) >= self.need
        item, pos = item[enough[item]], pos[enough[item]]
        by = np.argsort(item, kind="stable")
        item, pos = item[by], pos[by]
        last = np.arange(len(item)) + self.need[item] - 1
        first = np.flatnonzero(last < len(item))
        last = last[first]
        gram, span = self.gram[item[first]], self.span[item[first]]
        # what holds all these hits and is no longer than the span
        lo, hi = (pos[last] + gram - span).clip(0), (pos[first] + span).clip(max=n)
        near = (item[first] == item[last]) & (pos[last] - pos[first] + gram <= span)
        for i, a, b in zip(item[first][near].tolist(), lo[near].tolist(), hi[near].tolist(), strict=True):
            found.setdefault(i, []).append((a, b))


def _joined(stretches: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Stretches that overlap or touch as one."""
    out: list[tuple[int, int]] = []
    for lo, hi in sorted(stretches):
        if out and lo <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], hi))
        else:
            out.append((lo, hi))
    return out


def _among(values: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of those that are in the sorted array ``known``, and their places there."""
    if not len(values) or not len(known):
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
    at = np.searchsorted(known, values)
    at[at == len(known)] = 0
    where = np.flatnonzero(known[at] == values)
    return where, at[where]


def _matches(items: list[tuple[int, np.ndarray]], width: int, least: float):
    schema = pa.schema([("doc_id", pa.int64()), ("tie", pa.int64()), ("item_id", pa.int64()), ("score", pa.float64()), ("at_word", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = Words()
        finder = Finder([w for _, w in items], width, least)
        bags = [Counter(w.tolist()) for _, w in items]
        for batch in batches:
            out: list[tuple] = []
            for doc, tie, text in zip(batch.column("doc_id").to_pylist(), batch.column("tie").to_pylist(), batch.column("text"), strict=True):
                w = words(text.as_py())
                for item, stretches in finder(w).items():
                    item_id, text_words = items[item]
                    size = len(text_words)
                    best = (0, 0)
                    for lo, hi in stretches:
                        passage = w[lo:hi]
                        # no alignment scores more than the words that both have
                        if (Counter(passage.tolist()) & bags[item]).total() < least * size:
                            continue
                        score, end = align(text_words, passage)
                        best = max(best, (score, lo + end), key=lambda b: b[0])
                    if best[0] >= least * size:
                        out.append((doc, tie, item_id, round(best[0] / size, 6), best[1]))
            columns = list(zip(*out, strict=True)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)

    return run


def contaminated(
    docs: DataFrame,
    benchmark: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    width: int = 3,
    least: float = 0.5,
    item_block: int = 2000,
) -> DataFrame:
    """doc_id, tie, item_id, score, at_word: one row per document row and item that it holds.

    ``score`` is the alignment score over the item's number of words, 1 for a
    whole copy, and at least ``least``; ``at_word`` is where the alignment ends.
    Every alignment
    of that score counts, however its edits lie. Case and punctuation do not
    count. Items without words match nothing; those shorter than ``width`` words
    match where they stand whole. Null texts are empty; null ids
    stay null; repeated rows give repeated results; other columns are not read.
    """
    spark = docs.sparkSession
    bound_batches(spark)
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0).cast("long")).alias("tie"),
        F.col(text_col).cast("string").alias("text"),
    )
    items = benchmark.select(F.col(item_col).cast("long").alias("item_id"), F.col(item_text_col).cast("string").alias("text")).where("text is not null")
    blocks = max(1, -(-items.count() // item_block))
    result = None
    words = Words()
    for b in range(blocks):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b)
        block = [(i, w) for i, w in sorted(((r.item_id, words(r.text)) for r in part.collect()), key=lambda x: (x[0] is None, x[0] or 0, x[1].tolist())) if len(w)]
        if not block:
            continue
        found = rows.mapInArrow(_matches(block, width, least), "doc_id long, tie long, item_id long, score double, at_word long")
        result = found if result is None else result.unionByName(found)
    return result if result is not None else spark.createDataFrame([], "doc_id long, tie long, item_id long, score double, at_word long")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, **options: object) -> DataFrame:
    """The documents that hold no benchmark item, with all their columns."""
    id_col, text_col = str(options.get("id_col", "doc_id")), str(options.get("text_col", "text"))
    bad = contaminated(docs, benchmark, **options).select(F.col("doc_id").alias("_id"), F.col("tie").alias("_tie")).distinct()
    tie = F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0).cast("long"))
    return docs.join(bad.hint("shuffle_hash"), docs[id_col].cast("long").eqNullSafe(bad["_id"]) & (tie == bad["_tie"]), "left_anti")
