"""Token ids as files: Simple-8b words in blocks, read back by vectorised decoding.

A word has 64 bits: a selector in the top 4 bits, below it as many ids of one width as the selector says,
the first in the lowest bits. A value that doesn't fit 60 bits (or is the escape itself) is the escape word
followed by one raw word. Blocks of ``BLOCK`` ids start on a word of their own; the table of their first words
lets any block be decoded alone. A *segment* is a run of whole documents:

    magic, n_docs, n_ids, n_words, n_blocks | doc ids | first id of each document | first word of each block | words

The file is a Parquet table with a segment a row: (part, base, n_ids, payload), so that Spark's commit protocol
makes a partly written or repeated task harmless and any store will do. Parts are ranges of ascending ids; base
is the number of ids before a segment in its part. Only the totals of the parts reach the driver.

Defined results: a null or empty text is its end id alone; null ids come first; rows that repeat are written
as often as they come; an empty table gives none. Only the id and the text column are read.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import scratch, sliced
from .tokens import encoder as kept_encoder
from .tokens import tokenizer_path

#: Ids a word and bits an id, by selector.
COUNTS = (240, 120, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1)
WIDTHS = (0, 0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60)
BLOCK = 4096
SEGMENT_IDS = 1 << 18
MAGIC = 0x5338424C
ESCAPE = np.uint64(0xFFFFFFFFFFFFFFFF)
NULL_ID = -(1 << 63)
_LIMITS = np.array([0] + [(1 << w) - 1 for w in range(1, 60)] + [(1 << 60) - 2], np.uint64)


_SMALL_BITS = np.searchsorted(_LIMITS, np.arange(1 << 16, dtype=np.uint64)).astype(np.uint8)


def _bits(values: np.ndarray) -> np.ndarray:
    """Bits that each value needs; 61: the escape."""
    bits = _SMALL_BITS[values & np.uint64(0xFFFF)]
    wide = np.flatnonzero(values > np.uint64(0xFFFF))
    if len(wide):
        bits[wide] = np.searchsorted(_LIMITS, values[wide])
    return bits


def encode(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The words of unsigned values, and the first word of each block."""
    n = len(values)
    if not n:
        return np.empty(0, np.uint64), np.empty(0, np.uint32)
    padded = np.zeros(n + COUNTS[0], np.uint64)
    padded[:n] = values
    bits = _bits(padded)
    # The greatest width among the next c values, for each c; a longer run that fits takes the place of a shorter.
    selector, widest, have = np.full(n, 15, np.uint8), bits, 1
    for k in range(14, -1, -1):
        c, w = COUNTS[k], WIDTHS[k]
        while have < c:
            step = min(have, c - have)
            widest = np.maximum(widest[: len(bits) - have - step + 1], widest[step : len(bits) - have + 1])
            have += step
        fits = widest[:n] <= w
        if not fits.any():
            break  # a longer run has this one in it and less room
        selector[fits] = k
    step = np.array(COUNTS)[selector].tolist()
    starts, firsts = [], []
    for block in range(0, n, BLOCK):
        firsts.append(len(starts))
        i, end = block, min(block + BLOCK, n)
        while i < end:
            starts.append(i)
            i += step[i]
    at = np.array(starts)
    end = np.minimum((at // BLOCK + 1) * BLOCK, n)
    chosen = selector[at]
    words = np.zeros(len(at), np.uint64)
    for k in np.unique(chosen):
        own = np.flatnonzero(chosen == k)
        word = np.full(len(own), np.uint64(int(k) << 60))
        first, c = at[own], COUNTS[k]
        over = np.flatnonzero(first + c > end[own])  # words that end with their block hold fewer ids
        for j in range(c if WIDTHS[k] else 0):
            ids = padded[first + j]
            if len(over):
                ids[over[first[over] + j >= end[own[over]]]] = 0
            word |= ids << np.uint64(j * WIDTHS[k])
        words[own] = word
    big = bits[at] == 61
    if big.any():
        words[big] = ESCAPE
        moved = np.arange(len(at)) + np.cumsum(big) - big
        out = np.empty(len(at) + int(big.sum()), np.uint64)
        out[moved] = words
        out[moved[big] + 1] = padded[at[big]]
        return out, moved[firsts].astype(np.uint32)
    return words, np.array(firsts, np.uint32)


def decode(words: np.ndarray, n: int, firsts: np.ndarray) -> np.ndarray:
    """The ``n`` values of a run of blocks that starts at ``words[firsts[0]]``."""
    if not n:
        return np.empty(0, np.uint64)
    raw = np.zeros(len(words), bool)
    last = -2
    for i in np.flatnonzero(words == ESCAPE).tolist():
        if i != last + 1:
            last = i
            raw[i + 1] = True
    live = np.flatnonzero(~raw)
    chosen = (words[live] >> np.uint64(60)).astype(np.int64)
    held = np.array(COUNTS)[chosen]
    block = np.searchsorted(firsts, live, side="right") - 1
    before = np.cumsum(held) - held
    first_live = np.searchsorted(live, firsts)
    at = before - before[first_live][block] + block * BLOCK
    end = np.minimum((block + 1) * BLOCK, n)
    out = np.zeros(n, np.uint64)
    for k in np.unique(chosen):
        own = np.flatnonzero(chosen == k)
        if not WIDTHS[k]:
            continue
        mask = np.uint64((1 << WIDTHS[k]) - 1)
        first, word, c = at[own], words[live[own]], COUNTS[k]
        whole = first + c <= end[own]
        rest, part = first[~whole], word[~whole]
        last = end[own][~whole]
        first, word = first[whole], word[whole]
        for j in range(c):
            out[first + j] = (word >> np.uint64(j * WIDTHS[k])) & mask
            ok = rest + j < last
            out[rest[ok] + j] = (part[ok] >> np.uint64(j * WIDTHS[k])) & mask
    if raw.any():
        out[at[np.searchsorted(live, np.flatnonzero(raw) - 1)]] = words[raw]
    return out


def segment(ids: list[int | None], lists: list[bytes]) -> bytes:
    """A segment of whole documents; ``lists`` has their ids as little-endian unsigned 32-bit bytes."""
    values = np.frombuffer(b"".join(lists), "<u4")
    starts = np.cumsum([0, *(len(x) // 4 for x in lists)])[:-1]
    words, firsts = encode(values)
    head = np.array([MAGIC, len(ids), len(values), len(words), len(firsts)], "<u8")
    docs = np.array([NULL_ID if x is None else x for x in ids], "<i8")
    return b"".join(x.tobytes() for x in (head, docs, starts.astype("<u8"), firsts.astype("<u4"), words.astype("<u8")))


def documents_of(payload: bytes) -> tuple[list[int | None], np.ndarray, np.ndarray]:
    """Document ids, the first id of each, and all ids of a segment."""
    magic, n_docs, n_ids, n_words, n_blocks = np.frombuffer(payload, "<u8", 5).tolist()
    if magic != MAGIC:
        raise ValueError("not a segment")
    docs = np.frombuffer(payload, "<i8", n_docs, 40)
    starts = np.frombuffer(payload, "<u8", n_docs, 40 + 8 * n_docs)
    firsts = np.frombuffer(payload, "<u4", n_blocks, 40 + 16 * n_docs)
    words = np.frombuffer(payload, "<u8", n_words, 40 + 16 * n_docs + 4 * n_blocks)
    return [None if x == NULL_ID else x for x in docs.tolist()], starts.astype(np.int64), decode(words, n_ids, firsts).astype("<u4")


def write(docs: DataFrame, to: str, path: str | None = None, end: int = 0, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encode every text and write the segments, in ascending order of ids."""
    path, end_id = path or tokenizer_path(), np.uint32(end).tobytes()
    rows = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_text")).repartitionByRange("_id").sortWithinPartitions("_id")

    def run(batches):
        from pyspark import TaskContext

        encoder, part, base, ids, lists, n = kept_encoder(path), TaskContext.get().partitionId(), 0, [], [], 0

        def row():
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([base], pa.int64()), pa.array([n], pa.int64()), pa.array([segment(ids, lists)], pa.binary())], ["part", "base", "n_ids", "payload"])

        for batch in sliced(batches, 2000, keep_encoder=True):
            known: dict[str | None, bytes] = {}  # copies in one batch
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids.append(doc)
                if text not in known:
                    known[text] = encoder.encode(text) + end_id
                lists.append(known[text])
                n += len(lists[-1]) // 4
                if n >= SEGMENT_IDS:
                    yield row()
                    base, ids, lists, n = base + n, [], [], 0
        if ids:
            yield row()

    rows.mapInArrow(run, "part int, base long, n_ids long, payload binary").write.parquet(to)


def read(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document of the files at ``path``."""
    table = spark.read.schema("part int, base long, n_ids long, payload binary").parquet(path)
    totals = dict(table.groupBy("part").agg(F.sum("n_ids")).toArrow().to_pandas().itertuples(index=False))  # a number for each part
    before, n = {}, 0
    for part in sorted(totals):
        before[part], n = n, n + int(totals[part])

    def run(batches):
        for batch in batches:
            for part, base, payload in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                docs, starts, ids = documents_of(payload.as_buffer())
                ends = [*starts[1:].tolist(), len(ids)]
                yield pa.RecordBatch.from_arrays([
                    pa.array(docs, pa.int64()), pa.array(starts + before[part] + base, pa.int64()), pa.array(np.array(ends) - starts, pa.int64()),
                    pa.array([zlib.crc32(ids[a:b]) for a, b in zip(starts.tolist(), ends)], pa.int64()),
                ], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return table.select("part", "base", "payload").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, path: str | None = None) -> DataFrame:
    """Write ``docs`` to a new place in the shared folder and read the files back."""
    to = scratch(docs.sparkSession, "simple8b")
    write(docs, to, path)
    return read(docs.sparkSession, to)
