"""Exact deduplication by skew-safe combining, with DataFrame functions only.

Rows are first combined inside each task (the partial aggregate), then in salted groups of (digest, whole
text, salt), then the winners of all salts meet by (digest, whole text). The whole text is part of the key in
every one of these stages, so a clash of digests never merges different texts. A group that holds a third of all
rows reaches a reduce task as at most one row per map task and salt, and one row per salt after that.

:func:`combine` also tells every row which one stays. That look-up is by SHA-256 and the row's salt, and carries no
text: groups are dealt by digest alone and counted for each, and two texts under one digest, if there ever were
such, end the job with an error instead of a wrong row. A hot group's rows are spread over its salts.

Defined results: a null text counts as empty. A null id loses against any id. Rows that repeat both id and
text are one document delivered twice: :func:`combine` flags them alike, :func:`kept_rows` keeps one, the greatest
by its other columns. Columns beyond id and text are carried by :func:`kept_rows` and may have any name and type.
An empty table gives none.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

SALTS = 16


def _keyed(docs: DataFrame, id_col: str, text_col: str, salts: int, *more) -> DataFrame:
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(F.col(id_col).alias("_id"), text.alias("_text"), F.sha2(text, 256).alias("_sha"), F.pmod(F.xxhash64(F.col(id_col)), F.lit(salts)).cast("int").alias("_salt"), *more)


def combine(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    rows = _keyed(docs, id_col, text_col, salts)
    salted = rows.groupBy("_sha", "_text", "_salt").agg(F.max("_id").alias("_keep"), F.count(F.lit(1)).alias("_size"))
    groups = salted.repartition("_sha").groupBy("_sha", "_text").agg(F.max("_keep").alias("_keep"), F.sum("_size").alias("_size"))
    texts = F.count(F.lit(1)).over(Window.partitionBy("_sha"))
    sure = F.when(texts > 1, F.raise_error(F.concat(F.lit("different texts under the digest "), "_sha")).cast("long")).otherwise(F.col("_size"))
    shared = groups.select("_sha", "_keep", sure.alias("_size")).where("_size > 1").withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    found = rows.select("_id", "_sha", "_salt").join(shared, ["_sha", "_salt"], "left")
    alone = F.col("_size").isNull()
    keep = F.when(alone, F.col("_id")).otherwise(F.col("_keep"))
    return found.select(
        F.col("_id").alias("doc_id"), keep.alias("keep_id"), F.coalesce("_size", F.lit(1)).cast("long").alias("group_size"),
        F.col("_id").eqNullSafe(keep).alias("kept"), F.col("_sha").alias("text_sha256"),
    )


def _ordered(column: Column, kind: T.DataType) -> Column:
    """The column, or its JSON where its type has no order."""
    return column if not any(x in kind.simpleString() for x in ("map<", "variant")) else F.to_json(F.struct(column.alias("v")))


def kept_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """The rows that stay, with all their columns. The whole row travels with its group, so no join is needed."""
    others = [(f"c{i}", f.name, f.dataType) for i, f in enumerate(docs.schema.fields) if f.name != text_col]
    quoted = lambda c: F.col(f"`{c.replace('`', '``')}`")
    none = quoted(text_col).isNull().alias("none")
    row = F.struct(none, *(quoted(c).alias(k) for k, c, _ in others))
    odd = [_ordered(quoted(c), kind) for _, c, kind in others if any(x in kind.simpleString() for x in ("map<", "variant"))]
    plain = [quoted(c) for _, c, kind in others if not any(x in kind.simpleString() for x in ("map<", "variant"))]
    # Where every type has an order the row itself is what is compared.
    rows = _keyed(docs, id_col, text_col, salts, F.struct(quoted(id_col).alias("k"), *([row.alias("row")] if not odd else [F.struct(*plain, *odd, none).alias("by")])).alias("_by"), *([row.alias("_row")] if odd else []))
    best = (lambda df: df.agg(F.max_by("_row", "_by").alias("_row"), F.max("_by").alias("_by"))) if odd else (lambda df: df.agg(F.max("_by").alias("_by")))
    found = best(best(rows.groupBy("_sha", "_text", "_salt")).groupBy("_sha", "_text"))
    kept = F.col("_row") if odd else F.col("_by.row")
    text = F.when(~kept["none"], F.col("_text"))
    at = {c: k for k, c, _ in others}
    return found.select(*(text.alias(c) if c == text_col else kept[at[c]].alias(c) for c in docs.columns))
