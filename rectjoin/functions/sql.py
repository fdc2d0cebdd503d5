"""The same for SQL users: functions that the analyzer inlines, and a table function for the cells of a rectangle."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

FUNCTIONS = {
    "rect_intersects": ("rxl DOUBLE, ryl DOUBLE, rxu DOUBLE, ryu DOUBLE, sxl DOUBLE, syl DOUBLE, sxu DOUBLE, syu DOUBLE", "BOOLEAN", "rxl <= sxu AND sxl <= rxu AND ryl <= syu AND syl <= ryu"),
    "cell_of": ("v DOUBLE, lo DOUBLE, hi DOUBLE, k INT", "INT", "CASE WHEN k <= 1 OR hi <= lo THEN 0 ELSE CAST(least(greatest(floor((v - lo) / (hi - lo) * k), 0), k - 1) AS INT) END"),
    "shared_area": ("rxl DOUBLE, ryl DOUBLE, rxu DOUBLE, ryu DOUBLE, sxl DOUBLE, syl DOUBLE, sxu DOUBLE, syu DOUBLE", "DOUBLE", "greatest(0D, least(rxu, sxu) - greatest(rxl, sxl)) * greatest(0D, least(ryu, syu) - greatest(ryl, syl))"),
}


class RectCells:
    """The cells of a kx by ky grid over the unit square that a rectangle touches."""

    def eval(self, xl: float, yl: float, xu: float, yu: float, kx: int, ky: int):
        def cell(v: float, k: int) -> int:
            return min(max(int(v * k // 1), 0), k - 1)

        for x in range(cell(xl, kx), cell(xu, kx) + 1):
            for y in range(cell(yl, ky), cell(yu, ky) + 1):
                yield x, y


def register(spark: SparkSession) -> None:
    for name, (arguments, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("rect_cells", udtf(RectCells, returnType="tx int, ty int"))
