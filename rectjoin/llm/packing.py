"""Sum-of-squares packing of token sequences.

A document is its ids and an end id. One longer than a sequence is cut so that only its first piece may be
shorter than a sequence; full pieces need no partner. Every other piece goes where the sum of squares of the
counts of open bins per residual gap becomes smallest (ties: the tightest bin). A new bin is opened only where no
open one has room: the sum alone would open more, and few sequences are what packing is for. The longest come first.

A last step takes sequences away: the least filled ones are emptied, one after another, and their pieces are placed
again by the same rule. A piece that finds no room takes the place of a shorter one, which is placed in its stead,
until the last one fits; if it can't, the sequence stays. It ends where the tokens need every sequence there is.

The pieces are dealt evenly over shards of at most ``SHARD`` pieces, which are packed apart: a shard needs
memory for its lengths only, no key decides where a piece goes, and what a shard wastes at its end is a few
sequences. Texts are read once and never shuffled.

Defined results: a null or empty text is its end id alone. Ids may be null or repeat; each row is packed on its
own. An empty table gives none. Only the id and the text column are read.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import sliced, written
from .tokens import encoder as kept_encoder
from .tokens import tokenizer_path

SIZE = 2048
SHARD = 200_000
END = b"\0\0\0\0"


def pieces(docs: DataFrame, size: int = SIZE, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32."""
    path = path or tokenizer_path()

    def run(batches):
        encoder = kept_encoder(path)
        for batch in sliced(batches, 2000, keep_encoder=True):
            known, out = {}, ([], [], [], [], [])
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if (cut := known.get(text)) is None:
                    ids = encoder.encode(text) + END
                    n = len(ids) // 4
                    ends = range(n % size or size, n + 1, size) if n > size else (n,)
                    cut = known[text] = [(k, max(0, e - size) if k else 0, e - (max(0, e - size) if k else 0)) for k, e in enumerate(ends)]
                    cut = known[text] = [(*c, zlib.crc32(ids[4 * c[1] : 4 * (c[1] + c[2])])) for c in cut]
                for row in cut:
                    for column, value in zip(out, (doc, *row)):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int32() if i == 1 else pa.int64()) for i, x in enumerate(out)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(docs[id_col].cast("long"), docs[text_col]).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def sum_of_squares(lengths: np.ndarray, size: int = SIZE) -> tuple[np.ndarray, np.ndarray]:
    """For pieces of 1 to ``size`` tokens, in the order given: the bin and the offset of each."""
    counts = np.zeros(size + 1, np.int64)  # of open bins by gap; gaps 0 and ``size`` don't count
    bins: list[list[int]] = [[] for _ in range(size + 1)]
    where, offset, made = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64), 0
    for i, s in enumerate(lengths.tolist()):
        gap = size
        if s < size:
            # The change of the sum, halved: from gap g to g - s, for g = s ... size - 1.
            change = np.where(counts[s:size] > 0, counts[: size - s] - counts[s:size] + 1.0, np.inf)
            if counts[s]:
                change[0] = 0.5 - counts[s]
            k = int(change.argmin())
            if change[k] < np.inf:
                gap = s + k
        if gap == size:
            b, made = made, made + 1
        else:
            b = bins[gap].pop()
            counts[gap] -= 1
        where[i], offset[i] = b, size - gap
        if left := gap - s:
            bins[left].append(b)
            counts[left] += 1
    return where, offset


#: Sequences that are tried, of the least filled, before the last step ends.
EMPTIED = 16


def emptied(lengths: np.ndarray, where: np.ndarray, size: int = SIZE) -> np.ndarray:
    """The bins of the pieces once as many as can go are gone. Bins are numbered anew."""
    fill = np.bincount(where, lengths).astype(np.int64) if len(where) else np.empty(0, np.int64)
    least, alive = -(-int(lengths.sum()) // size), int((fill > 0).sum())
    while alive > least:
        for gone in np.argsort(np.where(fill > 0, fill, size + 1), kind="stable")[: min(EMPTIED, alive)].tolist():
            if (moved := _without(lengths, where, fill, gone, size)) is not None:
                where, fill = moved
                alive -= 1
                break
        else:
            break
    return np.unique(where, return_inverse=True)[1]


def _without(lengths: np.ndarray, where: np.ndarray, fill: np.ndarray, gone: int, size: int) -> tuple[np.ndarray, np.ndarray] | None:
    """Bins and fills after one bin is emptied, or None."""
    loose = sorted(np.flatnonzero(where == gone).tolist(), key=lambda i: lengths[i])
    where, gap = where.copy(), size - fill
    gap[(fill == 0) | (np.arange(len(fill)) == gone)] = 0  # takes nothing
    open_ = np.flatnonzero(gap[where] > 0)  # pieces in bins with room
    while loose:
        i = loose.pop()
        s = lengths[i]
        room = np.flatnonzero(gap >= s)
        if len(room):
            counts = np.bincount(gap, minlength=size + 1)
            counts[0] = counts[size] = 0
            change = np.where(gap[room] == s, 0.5 - counts[gap[room]], counts[gap[room] - s] - counts[gap[room]] + 1.0)
            b = room[np.lexsort((gap[room], change))[0]]
            gap[b] -= s
        else:  # the shortest piece whose place is enough; every step takes a shorter one out
            own = lengths[open_]
            can = np.flatnonzero((own < s) & (own + gap[where[open_]] >= s) & (where[open_] != gone))
            if not len(can):
                return None
            j = open_[can[own[can].argmin()]]
            b = where[j]
            gap[b] -= s - lengths[j]
            where[j] = gone
            loose.append(int(j))
        where[i] = b
        open_ = np.append(open_, i)
    return where, np.bincount(where, lengths, len(fill)).astype(np.int64)


def offsets(lengths: np.ndarray, where: np.ndarray) -> np.ndarray:
    """The place of each piece in its bin, in the order given."""
    order = np.argsort(where, kind="stable")
    before = np.cumsum(lengths[order]) - lengths[order]
    first = np.append(True, np.diff(where[order]) != 0)[: len(order)]
    out = np.empty(len(order), np.int64)
    out[order] = before - np.maximum.accumulate(np.where(first, before, 0))
    return out


def arrival(lengths: np.ndarray) -> np.ndarray:
    """The order in which pieces are placed: the longest first."""
    return np.argsort(-lengths, kind="stable")


def pack(docs: DataFrame, size: int = SIZE, path: str | None = None, shard: int = SHARD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    made = written(pieces(docs, size, path, id_col, text_col), "pieces")
    dealt = made.repartition(max(1, -(-made.count() // shard)))

    def run(batches):
        from pyspark import TaskContext

        batches = [b for b in batches if b.num_rows]
        if batches:
            rows = pa.Table.from_batches(batches).combine_chunks()
            length = rows.column("length").to_numpy()
            order = arrival(length)
            where = np.empty_like(order)
            where[order] = sum_of_squares(length[order], size)[0]
            where = emptied(length, where, size)
            offset = offsets(length, where)
            rows = rows.append_column("sequence_id", pa.array(where + (TaskContext.get().partitionId() << 40))).append_column("offset", pa.array(offset))
            yield from rows.to_batches(max_chunksize=50_000)

    return dealt.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
