"""Token totals by source, language and tokenizer version, kept by deltas.

Every change is signed: an insert counts +1 and its tokens, a delete -1 and minus its tokens, a revision takes
the old count off and puts the new one on. A batch of changes is summed by key before it is stored, so a batch
is as small as its keys; sums have map-side combining, and no key is ever gathered. Totals are the sum of the
committed batches; :meth:`Rollup.compact` folds batches into one.

A batch's sums are written to a folder of their own, which nobody reads until a *commit file* names it. That
file appears by one rename that fails if its name is taken, so of several drivers that send one batch, at once or
again, exactly one counts; what a lost driver left without a commit file is never read. A compaction is the
commit of the next generation: it lists all batches that it stands for, of two at once only one succeeds, and
batches committed meanwhile stay beside it.

Tokenizer versions are files of the ``tokenizers`` library. A version is the file's name, so a new file is a new
version with totals of its own.

Defined results: a null source, language or text is kept as the key null or the count 0; null ids and rows
that repeat count like any other; keys whose totals are all zero are left out; no batch gives no row. Extra
columns are not read.
"""

from __future__ import annotations

import functools
import json
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import rows_with, scratch, written
from .tokens import encoder as kept_encoder
from .tokens import tokenizer_path

#: The versions that the query keeps.
TOKENIZERS = ("byte_bpe_50k", "word_bpe_49k")
KEYS = ["source", "lang", "tokenizer"]
SCHEMA = "source string, lang string, tokenizer string, docs long, tokens long"


def token_count(text: Column, version: str, path: str | None = None) -> Column:
    """The number of a text's ids, no end id."""
    path = path or tokenizer_path(f"{version}.json")

    @F.arrow_udf("long")
    def count(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        encoder = kept_encoder(path)
        for texts in arrays:
            yield pa.array([len(encoder.encode(t)) // 4 for at in range(0, len(texts), 1000) for t in texts.slice(at, 1000).to_pylist()], pa.int64())

    return count(text)


def per_document(docs: DataFrame, tokenizers: tuple[str, ...] = TOKENIZERS, text: Column | str = "text") -> DataFrame:
    """(doc_id, source, lang, counts): what each tokenizer version makes of a text. Deletes and revisions need the
    old counts, so this small table is kept."""
    text = F.col(text) if isinstance(text, str) else text
    rows = docs.select("doc_id", "source", "lang", *(token_count(text, v).alias(f"_n{i}") for i, v in enumerate(tokenizers)))
    each = F.array(*(F.struct(F.lit(v).alias("tokenizer"), F.col(f"_n{i}").alias("tokens")) for i, v in enumerate(tokenizers)))
    return rows.select("doc_id", "source", "lang", each.alias("counts"))


def counted(docs: DataFrame, tokenizers: tuple[str, ...] = TOKENIZERS) -> DataFrame:
    """The table of :func:`per_document`, written in a pass for each version, so that a worker holds one tokenizer."""
    return functools.reduce(DataFrame.unionByName, [written(per_document(docs, (v,)), f"counts-{v}") for v in tokenizers])


def changes(counts: DataFrame, sign: int = 1) -> DataFrame:
    """Signed changes (source, lang, tokenizer, docs, tokens) of counted documents."""
    rows = counts.select("source", "lang", F.lit(sign).cast("long").alias("docs"), F.inline("counts"))
    return rows.select(*KEYS, "docs", (F.col("tokens") * sign).alias("tokens"))


def revised(before: DataFrame, after: DataFrame) -> DataFrame:
    """Changes that replace the counts ``before`` by those ``after`` (both as inserts)."""
    return after.unionByName(before.withColumns({"docs": -F.col("docs"), "tokens": -F.col("tokens")}))


class Rollup:
    """path/data has a folder of sums for each batch sent, path/commits a file for each one that counts."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path, self._jvm = spark, path.rstrip("/"), spark.sparkContext._jvm

    def _files(self):
        path = self._jvm.org.apache.hadoop.fs.Path(f"{self.path}/commits")
        return path, self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(path.toUri(), self.spark.sparkContext._jsc.hadoopConfiguration())

    def _commits(self) -> dict[str, dict]:
        """What counts: the batches of the last compaction on, by name."""
        root, files = self._files()
        if not files.util().exists(root):
            return {}
        names = [x.getPath().getName() for x in files.util().listStatus(root)]
        folds = [int(m[1]) for n in names if (m := re.fullmatch(r"fold-(\d+)", n))]
        last = f"fold-{max(folds)}" if folds else None
        held = {last: self._read(last)} if last else {}
        folded = set(held[last]["folded"]) if last else set()
        return held | {n: self._read(n) for n in sorted(names) if n.startswith("batch=") and n not in folded}

    def _read(self, name: str) -> dict:
        root, files = self._files()
        stream = files.open(self._jvm.org.apache.hadoop.fs.Path(root, name))
        try:
            return json.loads(bytes(stream.readAllBytes()))
        finally:
            stream.close()

    def _done(self, name: str) -> bool:
        root, files = self._files()
        return files.util().exists(self._jvm.org.apache.hadoop.fs.Path(root, name))

    def _commit(self, name: str, content: dict) -> bool:
        """The commit file appears whole, or not at all where its name is taken."""
        root, files = self._files()
        fs = self._jvm.org.apache.hadoop.fs
        gateway = self.spark.sparkContext._gateway
        here, there = fs.Path(root, f".{uuid.uuid4().hex}"), fs.Path(root, name)
        flags = self._jvm.java.util.EnumSet.of(fs.CreateFlag.CREATE)
        parents = gateway.new_array(gateway.jvm.org.apache.hadoop.fs.Options.CreateOpts, 1)
        parents[0] = getattr(self._jvm, "org.apache.hadoop.fs.Options$CreateOpts").createParent()
        stream = files.create(here, flags, parents)
        stream.write(json.dumps(content).encode())
        stream.close()
        if self._done(name):
            files.delete(here, False)
            return False
        rename = getattr(gateway.jvm, "org.apache.hadoop.fs.Options$Rename")
        options = gateway.new_array(rename, 1)
        options[0] = rename.NONE
        try:
            files.rename(here, there, options)
        except Exception as e:
            files.delete(here, False)
            if "FileAlreadyExistsException" in str(e):
                return False
            raise
        return True

    def _stored(self, rows: DataFrame, name: str) -> str:
        folder = f"{name}-{uuid.uuid4().hex}"
        rows.groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens")).write.parquet(f"{self.path}/data/{folder}")
        return folder

    def apply(self, batch_id: str, rows: DataFrame) -> bool:
        """Commit a batch. False, and nothing done, if that id is committed already."""
        if not re.fullmatch(r"[\w.-]+", batch_id):
            raise ValueError(f"a batch id is a word: {batch_id!r}")
        name = f"batch={batch_id}"
        return not self._done(name) and self._commit(name, {"data": self._stored(rows, name)})

    def compact(self) -> bool:
        """Fold what is committed into one folder. False if another compaction came first. Folded ids stay known, so
        that a repeat is still refused."""
        held = self._commits()
        fold = next((n for n in held if n.startswith("fold-")), None)
        name = f"fold-{int(fold[5:]) + 1 if fold else 0}"
        folded = sorted({n for n in held if n.startswith("batch=")} | set(held[fold]["folded"] if fold else ()))
        return self._commit(name, {"data": self._stored(self._sum(held), name), "folded": folded})

    def _sum(self, held: dict[str, dict]) -> DataFrame:
        if not held:
            return self.spark.createDataFrame([], SCHEMA)
        rows = self.spark.read.schema(SCHEMA).parquet(*(f"{self.path}/data/{x['data']}" for x in held.values()))
        return rows.groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))

    def totals(self) -> DataFrame:
        return self._sum(self._commits()).where("docs != 0 OR tokens != 0")


#: Words of digits alone, which a revision takes out of a text.
DIGITS = r"(?<![^\x20\x09-\x0D])[0-9]+(?![^\x20\x09-\x0D])"


def maintained(docs: DataFrame, labels: DataFrame, tokenizers: tuple[str, ...] = TOKENIZERS) -> DataFrame:
    """Load all documents; take toxic ones back; revise those of low quality, whose texts lose their words of digits
    and are counted anew by every tokenizer.

    Each batch is sent twice, as after a lost acknowledgement; the second sending changes nothing. A compaction
    comes between the batches.
    """
    held = Rollup(docs.sparkSession, scratch(docs.sparkSession, "rollup"))
    toxic = labels.where("toxic = 1").select("doc_id").distinct()
    poor = labels.where("quality = 0 AND coalesce(toxic, 0) != 1").select("doc_id").distinct().join(toxic, "doc_id", "left_anti")
    counts = counted(docs, tokenizers)
    # Texts aren't shuffled: some others are counted too, and left out afterwards.
    after = counted(rows_with(docs.select("doc_id", "source", "lang", "text"), poor, "doc_id").withColumn("text", F.regexp_replace("text", DIGITS, "")), tokenizers).join(poor, "doc_id", "left_semi")
    before = counts.join(poor, "doc_id", "left_semi")
    batches = {"load": changes(counts), "takedown": changes(counts.join(toxic, "doc_id", "left_semi"), -1), "revision": revised(changes(before), changes(after))}
    for batch, rows in batches.items():
        held.apply(batch, rows)
        held.apply(batch, rows)
        held.compact()
    return held.totals()
