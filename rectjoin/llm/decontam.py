"""Benchmark decontamination by greedy string tiling.

Words are runs of letters and digits, lower-cased. A run of ``least`` words (a seed) that a text shares with a
benchmark item makes the two a candidate. For candidates the longest matching run of unmarked words is marked
again and again, found by running Karp-Rabin over windows that shrink from long to ``least``, until nothing is
left to mark. The share of the item's words under tiles is its coverage, whatever the order of the passages.

The benchmark is the smaller side by its nature. Its words, seeds and items are broadcast in blocks of at most
``BLOCK_CHARS`` characters of text; a larger benchmark means more blocks, each held against all texts. Texts
are read whole, never shuffled and never grouped.

Defined results: a null text, or an item without words, matches nothing. An item shorter than ``least`` words
matches where all its words stand in a row. Rows that repeat are reported as often as they come. Items with
the same text are reported each. Only the named columns are read.
"""

from __future__ import annotations

import re
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import kept_texts, sliced, written

LEAST = 5
COVERAGE = 0.5
#: Characters of a block. Its arrays take about 24 bytes a word, its vocabulary about 120 bytes a distinct word: at the
#: very most some 200 MB in a worker, 40 MB for common prose.
BLOCK_CHARS = 8_000_000
WORD = re.compile(r"[^\W_]+")
_BASE = np.uint64(0x9E3779B97F4A7C15)


def rolling(ids: np.ndarray, width: int) -> np.ndarray:
    """Karp-Rabin hashes of all windows, modulo 2**64."""
    n = len(ids) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    h = np.zeros(n, np.uint64)
    mixed = ids.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
    mixed ^= mixed >> np.uint64(32)
    for j in range(width):
        h = h * _BASE + mixed[j : j + n]
    return h


def tiles(item: list[int] | np.ndarray, text: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """(place in the item, place in the text, length) of the tiles; ids below 0 in the text match nothing."""
    n, free_item, free_text, out = len(item), np.ones(len(item), bool), np.ones(len(text), bool), []
    pattern = np.array(item, np.int64)
    width = n
    while width >= least:
        # Windows of unmarked words only, on both sides.
        open_item = np.flatnonzero(rolling_sum(free_item, width) == width)
        open_text = np.flatnonzero(rolling_sum(free_text, width) == width)
        if len(open_item) and len(open_text):
            at: dict[int, list[int]] = {}
            for p, h in zip(open_item.tolist(), rolling(pattern, width)[open_item].tolist()):
                at.setdefault(h, []).append(p)
            hashes = rolling(text, width)[open_text]
            hit = np.isin(hashes, np.fromiter(at, np.uint64, len(at)))
            for t, h in zip(open_text[hit].tolist(), hashes[hit].tolist()):
                if not at[h] or not free_text[t : t + width].all():
                    continue
                at[h] = [p for p in at[h] if free_item[p : p + width].all()]
                # Windows are tried from long to short, so each match is as long as the window.
                p = next((p for p in at[h] if (pattern[p : p + width] == text[t : t + width]).all()), None)
                if p is not None:
                    free_item[p : p + width] = free_text[t : t + width] = False
                    out.append((p, t, width))
        if not free_item.any():
            break
        width = min(width - 1, longest_open(pattern, text, free_item, free_text, width - 1, least))
    return out


def rolling_sum(flags: np.ndarray, width: int) -> np.ndarray:
    total = np.concatenate(([0], np.cumsum(flags)))
    return total[width:] - total[:-width] if len(total) > width else np.empty(0, np.int64)


def longest_open(item: np.ndarray, text: np.ndarray, free_item: np.ndarray, free_text: np.ndarray, most: int, least: int) -> int:
    """The greatest width up to ``most`` at which windows of unmarked words agree, by halving; 0 if none does."""

    def some(width: int) -> bool:
        a = rolling(item, width)[rolling_sum(free_item, width) == width]
        b = rolling(text, width)[rolling_sum(free_text, width) == width]
        return bool(len(a) and len(b) and np.isin(a, b).any())

    if most < least or not some(least):
        return 0
    low, high = least, most
    while low < high:
        middle = (low + high + 1) // 2
        low, high = (middle, high) if some(middle) else (low, middle - 1)
    return low


class Benchmark:
    """Words, seeds and items of one block of the benchmark, as arrays; only the words themselves are Python objects."""

    def __init__(self, items: list[tuple[int, str]], least: int):
        self.least, self.vocabulary, self.item_ids = least, {}, []
        own, hashes = [], []
        for item_id, text in items:
            ids = np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in WORD.findall((text or "").lower())], np.int32)
            if len(ids):
                self.item_ids.append(item_id)
                own.append(ids)
                hashes.append(rolling(ids, min(least, len(ids))))
        self.words = np.concatenate(own) if own else np.empty(0, np.int32)
        self.sizes = np.fromiter(map(len, own), np.int64, len(own))
        self.first = np.cumsum(self.sizes) - self.sizes
        self.widths = np.unique(np.minimum(self.sizes, least)).tolist()
        h = np.concatenate(hashes) if own else np.empty(0, np.uint64)
        item = np.repeat(np.arange(len(own), dtype=np.int32), [len(x) for x in hashes])
        order = np.lexsort((item, h))
        h, item = h[order], item[order]
        # One entry a seed and item, with the number of windows of the item that are this seed.
        new = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (item[1:] != item[:-1]))[: len(h)])
        self.item, self.windows = item[new], np.diff(np.append(new, len(h))).astype(np.int32)
        self.keys, start = np.unique(h[new], return_index=True)
        self.start = np.append(start, len(new))

    def matches(self, text: str | None, coverage: float) -> list[tuple[int, int, int, int]]:
        """(item, tiles, words covered, words) of the items that a text covers to the given share."""
        words = WORD.findall((text or "").lower())
        ids = np.fromiter(map(self.vocabulary.get, words, repeat(0)), np.int64, len(words))
        known = ids > 0
        seen, places = [], np.zeros(len(ids) + 1, np.int64)
        for k in self.widths:
            at = np.flatnonzero(rolling_sum(known, k) == k)
            if not len(at):
                continue
            h = np.zeros(len(at), np.uint64)
            for j in range(k):
                mixed = ids[at + j].astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
                h = h * _BASE + (mixed ^ (mixed >> np.uint64(32)))
            slot = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
            hit = self.keys[slot] == h
            places[at[hit]] += 1
            places[at[hit] + k] -= 1
            seen.append(slot[hit])
        if not any(map(len, seen)):
            return []
        slots = np.unique(np.concatenate(seen))
        begin, n = self.start[slots], self.start[slots + 1] - self.start[slots]
        entries = np.repeat(begin - np.cumsum(n) + n, n) + np.arange(n.sum())
        near, place = np.unique(self.item[entries], return_inverse=True)
        windows = np.bincount(place, self.windows[entries])  # windows of an item that the text has too
        near = near[windows * np.minimum(self.sizes[near], self.least) >= coverage * self.sizes[near]]  # else the seeds can't cover enough
        # Words that no seed touches can't be in a tile; one blank stands for each run of them.
        inside = np.cumsum(places[:-1]) > 0
        keep = inside | np.append(False, inside[:-1])
        short = np.where(inside, ids, -1)[keep]
        out = []
        for item in near.tolist():
            own = self.words[self.first[item] : self.first[item] + self.sizes[item]]
            found = tiles(own, short, min(self.least, len(own)))
            if (covered := sum(x[2] for x in found)) >= coverage * len(own):
                out.append((self.item_ids[item], len(found), covered, len(own)))
        return out


def _blocks(benchmark: DataFrame, id_col: str, text_col: str, least: int):
    rows = benchmark.select(F.col(id_col).cast("long").alias("item_id"), F.col(text_col).alias("text")).where(F.col("text").isNotNull())
    chars = rows.agg(F.sum(F.length("text"))).first()[0] or 0
    n = -(-chars // BLOCK_CHARS) or 1
    for k in range(n):
        yield Benchmark([tuple(x) for x in (rows if n == 1 else rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k)).collect()], least)


def contaminated(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, least: int = LEAST) -> DataFrame:
    """doc_id, item_id, tiles, covered, item_words of every document and item it covers."""
    out = None
    for block in _blocks(benchmark, "item_id", "text", least):
        shared = docs.sparkSession.sparkContext.broadcast(block)

        def run(batches, shared=shared):
            held = shared.value
            for batch in sliced(batches):
                rows = [(doc, *m) for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()) for m in held.matches(text, coverage)]
                columns = list(zip(*rows)) or [()] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["doc_id", "item_id", "tiles", "covered", "item_words"])

        found = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, item_id long, tiles long, covered long, item_words long")
        out = found if out is None else out.unionByName(found)
    return out


def clean_rows(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, least: int = LEAST) -> DataFrame:
    """The rows of ``docs`` that cover no item to the given share, as they are."""
    blocks, more = _blocks(benchmark, "item_id", "text", least), False
    for block in blocks:
        shared = docs.sparkSession.sparkContext.broadcast(block)
        docs = written(docs, "clean-of-a-block") if more else docs  # so that a task holds one block
        docs, more = kept_texts(docs, "text", lambda texts, shared=shared: [not shared.value.matches(t, coverage) for t in texts]), True
    return docs
