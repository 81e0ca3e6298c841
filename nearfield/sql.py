"""SQL surface: functions, table functions and parameterised statements."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .functions.elements import SPECIES, ElementModel


def _overlap(a: pd.Series, b: pd.Series, r: pd.Series) -> pd.Series:
    """Overlap of two species' functions at a distance, whole batches at a time."""
    model, out = ElementModel(), pd.Series(0.0, index=r.index)
    for p in a.unique():
        for q in b.unique():
            here = (a == p) & (b == q)
            if here.any() and p in SPECIES and q in SPECIES:
                out[here] = model.overlap(p, q)(r[here].to_numpy())
    return out


def _trace(row: pd.Series, col: pd.Series, val: pd.Series) -> float:
    """Trace of a group's entries."""
    return float(val[row == col].sum())


class CellNeighbours:
    """The bins around a position: (t, bx, by, bz, sx, sy, sz), with the image shift of each."""

    def eval(self, x: float, y: float, z: float, lx: float, ly: float, lz: float, width: float) -> Iterator[tuple]:
        n = [max(1, int(e // width)) for e in (lx, ly, lz)]
        at = [int(p % e // (e / k)) for p, e, k in zip((x, y, z), (lx, ly, lz), n, strict=True)]
        number = 0
        for i in (-1, 0, 1):
            for j in (-1, 0, 1):
                for k in (-1, 0, 1):
                    to = [a + d for a, d in zip(at, (i, j, k), strict=True)]
                    shift = [-(t // m) * e for t, m, e in zip(to, n, (lx, ly, lz), strict=True)]
                    yield (number, *[t % m for t, m in zip(to, n, strict=True)], *shift)
                    number += 1


def register(spark: SparkSession) -> None:
    """overlap_of(a, b, r), dense_trace(row, col, val) and the table function pattern_cells(x, y, z, lx, ly, lz, width)."""
    spark.udf.register("overlap_of", F.pandas_udf(_overlap, "double"))
    spark.udf.register("dense_trace", _grouped())
    cells = F.udtf(CellNeighbours, returnType="t int, bx int, by int, bz int, sx double, sy double, sz double")
    spark.udtf.register("pattern_cells", cells)


def _grouped():
    def trace(row: pd.Series, col: pd.Series, val: pd.Series) -> float:
        return _trace(row, col, val)

    trace.__annotations__ = {"row": pd.Series, "col": pd.Series, "val": pd.Series, "return": float}
    return F.pandas_udf(trace, "double")


def run(spark: SparkSession, statement: str, **values) -> DataFrame:
    """A statement with {name} for values or DataFrames, which are bound and never pasted into the text."""
    return spark.sql(statement, **values)


def top_per_group(df: DataFrame, group: str, by: str, k: int) -> DataFrame:
    """The k rows of each group with the largest value; ties by the other columns."""
    rest = [c for c in df.columns if c not in (group, by)]
    w = W.partitionBy(group).orderBy(F.desc(by), *rest)
    return df.withColumn("_k", F.row_number().over(w)).where(F.col("_k") <= k).drop("_k")


def lateral_top(spark: SparkSession, view: str, k: int) -> DataFrame:
    """The same for a matrix view (row, col, val) by column, as a lateral join."""
    return spark.sql(f"SELECT c.col, t.row, t.val FROM (SELECT DISTINCT col FROM {view}) c, LATERAL (SELECT m.row, m.val FROM {view} m WHERE m.col = c.col ORDER BY m.val DESC, m.row LIMIT {int(k)}) t")
