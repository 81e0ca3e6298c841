"""Sparse matrices as rows (row, col, val): building, checking, algebra, norms, comparison.

A product joins on the inner index and adds by (row, col): two shuffles. It exists for the global baselines and for
checks; the submatrix methods never multiply globally.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import settle, squeeze, unsqueeze

MAT = "row long, col long, val double"


class MatrixError(ValueError):
    """A table does not meet the contract of a matrix."""


def from_coo(df: DataFrame, duplicates: str = "sum") -> DataFrame:
    """Rows of a table with row, col and val; repeated places are summed, or an error."""
    m = df.select(F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), F.col("val").cast("double").alias("val"))
    if duplicates == "sum":
        return m.groupBy("row", "col").agg(F.sum("val").alias("val"))
    return m


def validate(m: DataFrame, symmetry: str = "check") -> DataFrame:
    """The matrix if it keeps its contract: unique places, no null or NaN, the diagonal there, symmetric.

    ``symmetry``: "check" raises for unlike mirror images; "union" adds the missing mirror places with zeros; "any"
    looks at nothing of the kind. Repeated places, nulls and NaN always raise.
    """
    bad = m.agg(
        F.count(F.when(F.col("row").isNull() | F.col("col").isNull() | F.col("val").isNull() | F.isnan("val"), 1)).alias("nulls"),
        F.count(F.lit(1)).alias("n"),
    ).first()
    if bad.nulls:
        raise MatrixError(f"{bad.nulls} rows hold null or NaN")
    if m.groupBy("row", "col").count().where("count > 1").limit(1).count():
        raise MatrixError("a place occurs twice")
    if symmetry == "check" and max_asymmetry(m) > 1e-9:
        raise MatrixError("not symmetric; symmetry='union' takes the union of the pattern and its transpose")
    if symmetry == "union":
        t = m.select(F.col("col").alias("row"), F.col("row").alias("col"), F.lit(0.0).alias("val"))
        return m.union(t).groupBy("row", "col").agg(F.sum("val").alias("val"))
    return m


def with_diagonal(m: DataFrame) -> DataFrame:
    """The matrix with a zero for every missing diagonal place of its rows and columns."""
    ids = m.select(F.explode(F.array("row", "col")).alias("row")).distinct()
    return m.unionByName(ids.select("row", F.col("row").alias("col"), F.lit(0.0).alias("val"))).groupBy("row", "col").agg(F.sum("val").alias("val"))


def transpose(m: DataFrame) -> DataFrame:
    return m.select(F.col("col").alias("row"), F.col("row").alias("col"), *[c for c in m.columns if c not in ("row", "col")])


def scale(m: DataFrame, by: float) -> DataFrame:
    return m.withColumn("val", F.col("val") * by)


def axpy(a: float, x: DataFrame, b: float, y: DataFrame) -> DataFrame:
    """a X + b Y, by one aggregation of both tables."""
    both = x.select("row", "col", (F.col("val") * a).alias("val")).unionByName(y.select("row", "col", (F.col("val") * b).alias("val")))
    return both.groupBy("row", "col").agg(F.sum("val").alias("val"))


def threshold(m: DataFrame, tol: float) -> DataFrame:
    """Without off-diagonal entries of at most ``tol``."""
    return m.where((F.abs("val") > tol) | (F.col("row") == F.col("col")))


def hadamard(x: DataFrame, y: DataFrame) -> DataFrame:
    return x.join(y.withColumnRenamed("val", "val2"), ["row", "col"]).select("row", "col", (F.col("val") * F.col("val2")).alias("val"))


def mask(m: DataFrame, pattern: DataFrame) -> DataFrame:
    """Only the places of a pattern (row, col)."""
    return m.join(pattern.select("row", "col").distinct(), ["row", "col"], "left_semi")


def identity_of(m: DataFrame) -> DataFrame:
    ids = m.select(F.explode(F.array("row", "col")).alias("row")).distinct()
    return ids.select("row", F.col("row").alias("col"), F.lit(1.0).alias("val"))


def multiply(a: DataFrame, b: DataFrame, tol: float | None = None) -> DataFrame:
    """A B: join on the inner index, sum by place; ``tol`` drops small off-diagonal results."""
    left = a.select(F.col("row"), F.col("col").alias("k"), F.col("val").alias("x"))
    right = b.select(F.col("row").alias("k"), F.col("col"), F.col("val").alias("y"))
    out = left.join(right, "k").groupBy("row", "col").agg(F.sum(F.col("x") * F.col("y")).alias("val"))
    return out if tol is None else threshold(out, tol)


#: Entries that a task packs into parts of blocks at a time, and blocks that it fills at a time.
PACKED, FILLED = 1 << 18, 1 << 12


def blocks_of(m: DataFrame, size: int) -> DataFrame:
    """Block rows (bi, bj, v): dense row-major blocks of ``size`` from a matrix of entries.

    Entries go through the shuffle as parts of blocks, a row for each block that a task meets.
    """

    def pack(row, col, val):
        bi, bj, place = row // size, col // size, (row % size * size + col % size).astype(np.int32)
        order = np.lexsort((bj, bi))
        bi, bj = bi[order], bj[order]
        first = np.flatnonzero(np.concatenate([[True], (bi[1:] != bi[:-1]) | (bj[1:] != bj[:-1])]))
        ends = pa.array(np.append(first, len(bi)).astype(np.int32))
        lists = [pa.ListArray.from_arrays(ends, pa.array(x[order])) for x in (place, val)]
        return pa.RecordBatch.from_arrays([pa.array(bi[first]), pa.array(bj[first]), *lists], ["bi", "bj", "place", "val"])

    def run(batches):
        held, n = [], 0
        for b in batches:
            held.append([c.to_numpy() for c in b.columns])
            n += b.num_rows
            if n >= PACKED:
                yield pack(*map(np.concatenate, zip(*held, strict=True)))
                held, n = [], 0
        if n:
            yield pack(*map(np.concatenate, zip(*held, strict=True)))

    def dense(batches):
        for x in batches:
            for b in (x.slice(k, FILLED) for k in range(0, x.num_rows, FILLED)):
                block = np.repeat(np.arange(b.num_rows), b.column("place").value_lengths().to_numpy())
                v = np.zeros(b.num_rows * size * size)
                np.add.at(v, block * size * size + b.column("place").flatten().to_numpy(), b.column("val").flatten().to_numpy())
                ends = pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * size * size)
                yield pa.RecordBatch.from_arrays([b.column("bi"), b.column("bj"), pa.ListArray.from_arrays(ends, pa.array(v))], ["bi", "bj", "v"])

    whole = m.where("row is not null and col is not null and val is not null")
    parts = whole.select(*[F.col(c).cast(kind).alias(c) for c, kind in (("row", "long"), ("col", "long"), ("val", "double"))])
    parts = parts.mapInArrow(run, "bi long, bj long, place array<int>, val array<double>")
    lists = parts.groupBy("bi", "bj").agg(*[F.flatten(F.collect_list(c)).alias(c) for c in ("place", "val")])
    return lists.mapInArrow(dense, "bi long, bj long, v array<double>")


#: Rows and columns of a tile of a product of blocks, about.
TILE = 1024


def multiply_blocks(a: DataFrame, b: DataFrame, size: int) -> DataFrame:
    """A B of block rows: tiles of blocks meet by row, inner and column tile as one dense product; partial tiles are summed.

    A task holds a tile of each factor and of the product. Blocks are repeated for each tile that they meet, and what is
    summed comes once for each inner tile, not for each pair of blocks. Blocks travel as compressed parts of tiles.
    """
    tile = max(1, TILE // size)
    of = lambda c: F.floor(F.col(c) / tile).cast("long")

    def packed(batches):
        for x in batches:
            ti, tj = (x.column(c).to_numpy() // tile for c in ("bi", "bj"))
            order = np.lexsort((tj, ti))
            ti, tj, x = ti[order], tj[order], x.take(pa.array(order))
            first = np.flatnonzero(np.concatenate([[True], (ti[1:] != ti[:-1]) | (tj[1:] != tj[:-1])])) if len(ti) else np.zeros(0, np.int64)
            ends = np.append(first, len(ti))
            data = pa.array([squeeze(x.slice(a, b - a)) for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(ti[first]), pa.array(tj[first]), data], ["ti", "tj", "data"])

    def parts_of(m: DataFrame, row: str, col: str) -> DataFrame:
        blocks = m.select(F.col("bi").cast("long").alias("bi"), F.col("bj").cast("long").alias("bj"), "v")
        return blocks.mapInArrow(packed, "ti long, tj long, data binary").toDF(row, col, "data")

    met = a.select(of("bi").alias("ti"), of("bj").alias("tk")).distinct().join(b.select(of("bi").alias("tk"), of("bj").alias("tj")).distinct(), "tk")
    met = settle(met)
    key = ["ti", "tk", "tj"]
    left = parts_of(a, "ti", "tk").join(met, ["ti", "tk"]).select(*key, "data")
    right = parts_of(b, "tk", "tj").join(met, ["tk", "tj"]).select(*key, "data")

    def blocks(t: pa.Table) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        parts = [unsqueeze(x) for x in t.column("data").to_pylist()]
        return [(x.column("bi").to_numpy(), x.column("bj").to_numpy(), x.column("v").combine_chunks().flatten().to_numpy().reshape(-1, size, size)) for x in parts]

    def dense(parts: list, rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
        out = np.zeros((len(rows), size, len(cols), size))
        for bi, bj, v in parts:
            i, j = np.searchsorted(rows, bi), np.searchsorted(cols, bj)
            if len(np.unique(i * len(cols) + j)) == len(i):
                out[i, :, j] += v
            else:
                np.add.at(out, (i, slice(None), j), v)
        return out.reshape(len(rows) * size, len(cols) * size)

    ids = lambda *found: np.unique(np.concatenate(found))
    summed = pa.schema([("ti", pa.int64()), ("tj", pa.int64()), ("data", pa.binary())])

    def meet(x: pa.Table, y: pa.Table) -> pa.Table:
        if not x.num_rows or not y.num_rows:
            return summed.empty_table()
        ti, tj, x, y = x.column("ti")[0].as_py(), y.column("tj")[0].as_py(), blocks(x), blocks(y)
        rows, cols, inner = ids(*(p[0] for p in x)), ids(*(p[1] for p in y)), ids(*(p[1] for p in x), *(p[0] for p in y))
        out = (dense(x, rows, inner) @ dense(y, inner, cols)).reshape(len(rows), size, len(cols), size).transpose(0, 2, 1, 3).reshape(-1, size * size)
        full = out.any(axis=1)
        i, j = np.repeat(rows, len(cols))[full], np.tile(cols, len(rows))[full]
        v = pa.ListArray.from_arrays(pa.array(np.arange(len(i) + 1, dtype=np.int32) * size * size), pa.array(out[full].ravel()))
        return pa.table([[ti], [tj], [squeeze(pa.table({"bi": i, "bj": j, "v": v}))]], summed)

    def total(t: pa.Table) -> pa.Table:
        parts = blocks(t)
        rows, cols = ids(*(p[0] for p in parts)), ids(*(p[1] for p in parts))
        out = dense(parts, rows, cols)
        i, j = np.nonzero(out)
        at = lambda known, k: known[k // size] * size + k % size
        return pa.table({"row": at(rows, i), "col": at(cols, j), "val": out[i, j]})

    parts = left.groupBy(*key).cogroup(right.groupBy(*key)).applyInArrow(meet, "ti long, tj long, data binary")
    return parts.groupBy("ti", "tj").applyInArrow(total, MAT)


def trace(m: DataFrame) -> float:
    return m.where("row = col").agg(F.coalesce(F.sum("val"), F.lit(0.0))).first()[0]


def trace_of_product(a: DataFrame, b: DataFrame) -> float:
    """tr(A B) as a sum over matching places; no product is formed."""
    t = transpose(b).withColumnRenamed("val", "val2")
    return a.join(t, ["row", "col"]).agg(F.coalesce(F.sum(F.col("val") * F.col("val2")), F.lit(0.0))).first()[0]


def norms(m: DataFrame) -> dict[str, float]:
    """Norms 1, inf, Frobenius and max."""
    one = m.groupBy("col").agg(F.sum(F.abs("val")).alias("v")).agg(F.max("v")).first()[0]
    inf = m.groupBy("row").agg(F.sum(F.abs("val")).alias("v")).agg(F.max("v")).first()[0]
    fro, most = m.agg(F.sqrt(F.sum(F.col("val") * F.col("val"))), F.max(F.abs("val"))).first()
    return {"one": one or 0.0, "inf": inf or 0.0, "fro": fro or 0.0, "max": most or 0.0}


def max_asymmetry(m: DataFrame) -> float:
    """Largest difference of mirror entries; a missing one is zero."""
    d = m.unionByName(transpose(m).withColumn("val", -F.col("val"))).groupBy("row", "col").agg(F.abs(F.sum("val")).alias("d"))
    return d.agg(F.coalesce(F.max("d"), F.lit(0.0))).first()[0]


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: max_abs and rms over a's places, off_pattern (root of squares of b's other entries), places."""
    both = a.select("row", "col", F.col("val").alias("x")).join(b.select("row", "col", F.col("val").alias("y")), ["row", "col"], "full_outer")
    d = F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))
    on = F.col("x").isNotNull()
    return both.agg(
        F.max(F.when(on, F.abs(d))).alias("max_abs"),
        F.sqrt(F.avg(F.when(on, d * d))).alias("rms"),
        F.sqrt(F.coalesce(F.sum(F.when(~on, F.col("y") * F.col("y"))), F.lit(0.0))).alias("off_pattern"),
        F.count(F.when(on, 1)).alias("places"),
    )


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda x, y: x.unionByName(y), frames)
