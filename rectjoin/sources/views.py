"""Rectangle views of the given tables, in Spark SQL and, for checks, in DuckDB's."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class SparkDialect:
    @staticmethod
    def day(c: str) -> str:
        return f"CAST(unix_date(CAST({c} AS DATE)) AS DOUBLE)"

    @staticmethod
    def sec(c: str) -> str:
        return f"(timestampdiff(MICROSECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', {c}) / 1e6D)"

    @staticmethod
    def num(v: str) -> str:
        return f"{v}D"

    @staticmethod
    def json_k(c: str) -> str:
        return f"CAST(get_json_object({c}, '$.k') AS DOUBLE)"

    @staticmethod
    def item(c: str, i: int) -> str:
        return f"CAST({c}[{i}] AS DOUBLE)"


class DuckDialect:
    @staticmethod
    def day(c: str) -> str:
        return f"CAST(date_diff('day', TIMESTAMP '1970-01-01', {c}) AS DOUBLE)"

    @staticmethod
    def sec(c: str) -> str:
        return f"(CAST(epoch_us({c}) - 1704067200000000 AS DOUBLE) / 1e6)"

    @staticmethod
    def num(v: str) -> str:
        return f"CAST({v} AS DOUBLE)"

    @staticmethod
    def json_k(c: str) -> str:
        return f"CAST(json_extract_string({c}, '$.k') AS DOUBLE)"

    @staticmethod
    def item(c: str, i: int) -> str:
        return f"CAST({c}[{i + 1}] AS DOUBLE)"


@dataclass(frozen=True)
class View:
    table: str
    ids: tuple[str, ...]
    #: xl, yl, xu, yu for a dialect
    rect: object
    payload: tuple[str, ...] = ()
    grouped: bool = False

    def sql(self, d, where: str = "") -> str:
        xl, yl, xu, yu = self.rect(d)
        tail = (f" WHERE {where}" if where else "") + (f" GROUP BY {', '.join(self.ids)}" if self.grouped else "")
        return f"SELECT {', '.join(self.ids)}, {xl} AS xl, {yl} AS yl, {xu} AS xu, {yu} AS yu{''.join(', ' + p for p in self.payload)} FROM {self.table}{tail}"


def _ship(d):
    x = d.day("l_shipdate")
    return x, "l_extendedprice", f"{x} + l_quantity / {d.num('25')}", f"l_extendedprice + {d.num('20')} * l_quantity"


def _sale(d):
    x = d.day("o_orderdate")
    return x, f"{d.num('0.2')} * o_totalprice", f"{x} + {d.num('1')} + CAST(o_custkey % 3 AS DOUBLE)", f"{d.num('0.21')} * o_totalprice"


def _visit(d):
    x, u = d.sec("ts"), "CAST(user_id AS DOUBLE)"
    return x, u, f"{x} + {d.num('60')} * value", f"{u} + {d.json_k('props')} / {d.num('50')}"


def _by_nation(nation: str, balance: str):
    return lambda d: (f"CAST({nation} AS DOUBLE)", balance, f"CAST({nation} AS DOUBLE) + {d.num('0.5')}", f"{balance} + {d.num('50')}")


def _prod(d):
    return "CAST(p_size AS DOUBLE)", "p_retailprice", f"CAST(p_size AS DOUBLE) + {d.num('1')}", f"p_retailprice + {d.num('0.5')}"


def _docbox(d):
    x, y = "CAST(n_chars AS DOUBLE)", "CAST(length(text) - length(replace(text, ' ', '')) AS DOUBLE)"
    return x, y, f"{x} * {d.num('1.02')}", f"{y} * {d.num('1.02')}"


def _ordbox(d):
    x = d.day("l_shipdate")
    return f"min({x})", "min(l_extendedprice)", f"max({x})", "max(l_extendedprice)"


def _pt(d):
    x, y = d.item("embedding", 0), d.item("embedding", 1)
    return x, y, x, y


VIEWS = {
    "ship": View("lineitem", ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"), _ship),
    "sale": View("orders", ("o_orderkey",), _sale),
    "visit": View("events", ("event_id",), _visit),
    "account": View("customer", ("c_custkey",), _by_nation("c_nationkey", "c_acctbal"), ("c_nationkey",)),
    "vendor": View("supplier", ("s_suppkey",), _by_nation("s_nationkey", "s_acctbal"), ("s_nationkey",)),
    "prod": View("part", ("p_partkey",), _prod),
    "docbox": View("documents", ("doc_id",), _docbox),
    "ordbox": View("lineitem", ("l_orderkey",), _ordbox, grouped=True),
    "pt": View("embeddings", ("vec_id",), _pt),
}


def rect_view(spark: SparkSession, sf_dir: str, name: str, where: str = "", payload: tuple[str, ...] = ()) -> DataFrame:
    """A view as rectangles; ``where`` is a condition on the table's columns, which reaches the scan."""
    view = VIEWS[name]
    table = spark.read.parquet(f"{sf_dir}/{view.table}.parquet")
    xl, yl, xu, yu = view.rect(SparkDialect)
    exprs = [F.expr(e).alias(c) for c, e in zip(("xl", "yl", "xu", "yu"), (xl, yl, xu, yu))]
    table = table.where(where) if where else table
    rid = F.col(view.ids[0]) if len(view.ids) == 1 else F.struct(*view.ids)
    if view.grouped:
        return table.groupBy(*view.ids).agg(*exprs).select(rid.alias("rid"), "xl", "yl", "xu", "yu")
    return table.select(rid.alias("rid"), *exprs, *(*view.payload, *payload))


def duck_view(name: str, where: str = "") -> str:
    return VIEWS[name].sql(DuckDialect, where)
