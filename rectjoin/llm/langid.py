"""Language identification: multinomial naive Bayes over hashed character 1- to 3-grams.

The model is one matrix of log probabilities, ``2**bits`` buckets by learned languages, which is broadcast:
its size is fixed by the parameters. Whole batches of texts are scored in numpy: all grams of a batch are
hashed at once, their rows of the matrix are gathered and summed per document.

Defined results: a null text, or one without any letter, is ``und`` with score 0. Texts are scored whole, in
pieces of at most ``PIECE`` code points so that memory is bounded; grams across a piece's end don't count.
Ties go to the language that sorts first. With no labelled row every document is ``und``. Repeated rows and
rows with a null id are scored like any other; only the id and the text column are read.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import kept_texts, sliced

BITS = 16
PIECE = 1_000_000
#: Bound of the training sample in documents (expected number; rows are chosen by a hash of their id).
TRAIN_DOCS = 20_000
#: More classes than this are refused, as the matrix is broadcast.
MAX_LANGS = 512
_MIX = (0x9E3779B1, 0x85EBCA6B, 0xC2B2AE35)


@functools.lru_cache(1)
def _letters() -> np.ndarray:
    """Which code points are letters; numbers that look like some (Ⅷ, ½, ①) aren't."""
    return np.fromiter(map(str.isalpha, map(chr, range(0x110000))), bool, 0x110000)


def has_letter(text: str | None) -> bool:
    return any(map(str.isalpha, text or ""))


class Grams:
    """Hashed grams of many texts at once."""

    def __init__(self, bits: int):
        self.shift, self.letter = np.uint32(32 - bits), _letters()

    def __call__(self, texts: list[str]) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
        """Where each text starts, and for each gram length the bucket at every place and whether a gram counts there.

        Letters are lower-cased, everything else is a blank. A gram counts if it has a letter (3: in its middle).
        """
        joined = "  " + "  ".join(x.lower() for x in texts) + "  "
        code = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        is_letter = self.letter[code]
        code = np.where(is_letter, code, np.uint32(32))
        lens = np.fromiter((len(x.lower()) + 2 for x in texts), np.int64, len(texts))
        starts = np.cumsum(lens) - lens + 1  # the blank before a text belongs to its first gram
        one = code * np.uint32(_MIX[0])
        two = np.empty_like(one)
        two[:-1] = (one[:-1] ^ (one[:-1] >> np.uint32(15))) * np.uint32(_MIX[1]) + code[1:] + np.uint32(1)
        two[-1] = 0
        three = np.empty_like(one)
        three[1:-1] = (two[:-2] ^ (two[:-2] >> np.uint32(13))) * np.uint32(_MIX[2]) + code[2:] + np.uint32(2)
        three[0] = three[-1] = 0
        next_letter = np.append(is_letter[1:], False)
        out = []
        for h, counts in ((one, is_letter), (two, is_letter | next_letter), (three, is_letter)):
            h = (h ^ (h >> np.uint32(16))) * np.uint32(_MIX[2])
            out.append(((h >> self.shift).astype(np.int32), counts))
        return starts, out


def pieces(texts: list[str | None], most: int) -> Iterator[tuple[list[int], list[str]]]:
    """Lists of texts (with the index of each one's document) that have about ``most`` code points together."""
    at, held, n = [], [], 0
    for i, text in enumerate(texts):
        for k in range(0, len(text or ""), PIECE):
            part = text[k : k + PIECE]
            if n and n + len(part) > most:
                yield at, held
                at, held, n = [], [], 0
            at.append(i)
            held.append(part)
            n += len(part) + 2
    if at:
        yield at, held


def gram_counts(labelled: DataFrame, bits: int = BITS) -> DataFrame:
    """Rows (lang, bucket, n) over (text, lang); bucket -1 counts documents. At most languages * (2**bits + 1) rows."""

    def count(batches):
        grams, totals, size = Grams(bits), {}, 1 << bits
        for batch in sliced(batches):
            langs, texts = batch.column("lang").to_pylist(), batch.column("text").to_pylist()
            for lang in set(langs):
                own = [t for t, x in zip(texts, langs) if x == lang]
                held = totals.setdefault(lang, np.zeros(size + 1, np.int64))
                held[size] += len(own)
                for _, part in pieces(own, PIECE):
                    for bucket, counts in grams(part)[1]:
                        held[:size] += np.bincount(bucket[counts], minlength=size)
        for lang, held in totals.items():
            at = np.flatnonzero(held)
            bucket = np.where(at == size, -1, at)
            yield pa.RecordBatch.from_pydict({"lang": pa.array([lang] * len(at), pa.string()), "bucket": pa.array(bucket, pa.int32()), "n": pa.array(held[at], pa.int64())})

    return labelled.select("text", "lang").mapInArrow(count, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))


class Model:
    def __init__(self, langs: list[str], log_prob: np.ndarray, log_prior: np.ndarray, bits: int):
        self.langs, self.log_prob, self.log_prior, self.bits = langs, log_prob, log_prior, bits

    def scores(self, texts: list[str | None], grams: Grams) -> np.ndarray:
        """Log joint of every text and language."""
        out = np.tile(self.log_prior, (len(texts), 1))
        for at, part in pieces(texts, max(10_000, 4 * PIECE // (4 + len(self.langs)))):
            starts, found = grams(part)
            total = 0
            for bucket, counts in found:
                total = total + self.log_prob[np.where(counts, bucket, 1 << self.bits)]
            np.add.at(out, at, np.add.reduceat(total, starts, axis=0, dtype=np.float64))
        return out

    def predict(self, texts: list[str | None], grams: Grams) -> tuple[list[str], np.ndarray]:
        if not self.langs or not texts:
            return ["und"] * len(texts), np.zeros(len(texts))
        known = np.fromiter(map(has_letter, texts), bool, len(texts))
        joint = self.scores([t if k else None for t, k in zip(texts, known)], grams)
        best = joint.argmax(axis=1)
        share = 1 / np.exp(joint - joint.max(axis=1, keepdims=True)).sum(axis=1)
        return [self.langs[b] if k else "und" for b, k in zip(best, known)], np.where(known, share, 0.0)


def train(labelled: DataFrame, bits: int = BITS, smoothing: float = 0.5) -> Model:
    """A model from (text, lang). Rows with a null text or lang teach nothing."""
    counts = gram_counts(labelled.where(F.col("text").isNotNull() & F.col("lang").isNotNull()), bits)
    n_langs = labelled.select("lang").where(F.col("lang").isNotNull()).distinct().limit(MAX_LANGS + 1).count()
    if n_langs > MAX_LANGS:
        raise ValueError(f"more than {MAX_LANGS} languages")
    table = counts.toArrow()
    langs = sorted(set(table.column("lang").to_pylist()))
    size, index = 1 << bits, {x: i for i, x in enumerate(langs)}
    held = np.zeros((size + 1, len(langs)))
    held[table.column("bucket").to_numpy(), [index[x] for x in table.column("lang").to_pylist()]] = table.column("n").to_numpy()
    docs, held = held[size].copy(), held[:size] + smoothing
    log_prob = np.zeros((size + 1, len(langs)), np.float32)  # the last row stands for places without a gram
    log_prob[:size] = np.log(held / held.sum(axis=0))
    return Model(langs, log_prob, np.log(docs / docs.sum()) if langs else docs, bits)


def held_out(id_col: str = "doc_id"):
    """Every fifth document by the checksum of its id, which training leaves out."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(5)) == 0, F.lit(False))


def training_rows(docs: DataFrame, most: int = TRAIN_DOCS, id_col: str = "doc_id") -> DataFrame:
    """A sample of about ``most`` labelled rows at any size of the input; all of them where there are fewer."""
    own = docs.where(~held_out(id_col) & F.col("lang").isNotNull() & F.col("text").isNotNull())
    n = own.count()
    return own if n <= most else own.where(F.pmod(F.xxhash64(F.col(id_col), F.lit(17)), F.lit(1 << 30)) < int(most / n * (1 << 30)))


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, lang_pred, score."""
    shared = docs.sparkSession.sparkContext.broadcast((model.langs, model.log_prob, model.log_prior, model.bits))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out(id_col).alias("held_out"), F.col(text_col).alias("_text"))

    def score(batches):
        own = Model(*shared.value)
        grams = Grams(own.bits)
        for batch in sliced(batches):
            langs, scores = own.predict(batch.column(2).to_pylist(), grams)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    return rows.mapInArrow(score, "doc_id long, held_out boolean, lang_pred string, score double")


def identify(docs: DataFrame, most: int = TRAIN_DOCS) -> DataFrame:
    """Train on the labelled rows of ``docs`` that aren't held out, then predict every row."""
    return predict(docs, train(training_rows(docs, most)))


def identified_rows(docs: DataFrame, least_score: float = 0.5, most: int = TRAIN_DOCS) -> DataFrame:
    """The rows with a language, as they are: ``und`` and predictions below ``least_score`` go."""
    model = train(training_rows(docs, most))
    shared = docs.sparkSession.sparkContext.broadcast((model.langs, model.log_prob, model.log_prior, model.bits))

    def keep(texts: list[str | None]) -> list[bool]:
        own, grams = _own(shared)
        langs, scores = own.predict(texts, grams)
        return [x != "und" and s >= least_score for x, s in zip(langs, scores)]

    return kept_texts(docs, "text", keep)


def _own(shared) -> tuple[Model, Grams]:
    own = Model(*shared.value)
    return own, Grams(own.bits)
