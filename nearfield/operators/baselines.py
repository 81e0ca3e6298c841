"""What the submatrix methods are compared with: dense solvers and global sparse iterations."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import MatFn, Purification, purify, sign_exact
from ..sources.tables import cut, settle
from . import matrix
from .patterns import components
from .submatrix import submatrix_apply


def dense(m: DataFrame, max_dim: int = 5000, value: str = "val") -> tuple[np.ndarray, np.ndarray]:
    """(ids, dense matrix) on the driver; refuses more than ``max_dim`` rows."""
    ids = m.select(F.explode(F.array("row", "col")).alias("id")).distinct()
    n = ids.limit(max_dim + 1).count()
    if n > max_dim:
        raise matrix.MatrixError(f"over {max_dim} rows: a dense reference is for small systems")
    known = np.array(sorted(r.id for r in ids.collect()), np.int64)
    out = np.zeros((n, n))
    rows = m.select("row", "col", value).toPandas()
    out[np.searchsorted(known, rows["row"]), np.searchsorted(known, rows["col"])] = rows[value]
    return known, out


def from_dense(spark, ids: np.ndarray, a: np.ndarray) -> DataFrame:
    """Rows (row, col, val) of a driver-side matrix."""
    import pandas as pd

    i, j = np.nonzero(np.ones_like(a))
    return spark.createDataFrame(pd.DataFrame({"row": ids[i], "col": ids[j], "val": a[i, j]}))


def dense_reference(m: DataFrame, fn: MatFn, max_dim: int = 5000) -> DataFrame:
    """f of the whole matrix, a connected component in one executor task: exact, cubic.

    Components share no entry, so f of the matrix is f of each and zero between them; those zeros have no row. A
    component of more than ``max_dim`` rows is refused.
    """
    one = m.select(F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col"), F.col("val").cast("double").alias("val"))
    parts = cut(components(one))
    if (parts.groupBy("component").count().agg(F.max("count")).first()[0] or 0) > max_dim:
        raise matrix.MatrixError(f"over {max_dim} connected rows: a dense reference is for small systems")

    def solve(table: pa.Table) -> pa.Table:
        row, col = table.column("row").to_numpy(), table.column("col").to_numpy()
        known = np.unique(np.concatenate([row, col]))
        a = np.zeros((len(known), len(known)))
        a[np.searchsorted(known, row), np.searchsorted(known, col)] = table.column("val").to_numpy()
        out, n = fn(a), len(known)
        return pa.table({"row": np.repeat(known, n), "col": np.tile(known, n), "val": out.ravel()})

    return one.join(parts, F.col("row") == F.col("node")).select("component", "row", "col", "val").groupBy("component").applyInArrow(solve, "row long, col long, val double")


def dense_density(pair: DataFrame, mu: float, max_dim: int = 5000) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, D, W) of the whole pair by the generalised eigenproblem."""
    ids, h = dense(pair, max_dim, "h")
    _, s = dense(pair, max_dim, "s")
    d, w, _ = purify(h, s, Purification(mu=mu, solver="eigen"))
    return ids, d, w


def global_inverse(s: DataFrame, steps: int = 12, tol: float = 1e-10) -> DataFrame:
    """S^-1 by the coupled root iteration on sparse matrices: three global products a step."""
    c = matrix.norms(s)["inf"]
    y, eye = settle(matrix.scale(s, 1 / c)), settle(matrix.identity_of(s))
    z = eye
    for _ in range(steps):
        t = settle(matrix.axpy(1.5, eye, -0.5, matrix.multiply(z, y, tol)))
        y, z = settle(matrix.multiply(y, t, tol)), settle(matrix.multiply(t, z, tol))
    return matrix.scale(matrix.multiply(z, z, tol), 1 / c)


def global_sign(a: DataFrame, steps: int = 20, tol: float = 1e-10) -> DataFrame:
    """sign(A) by the cubic iteration on a sparse matrix: two global products a step, small entries dropped."""
    n = matrix.norms(a)
    x, eye = settle(matrix.scale(a, 1 / (np.sqrt(n["one"] * n["inf"]) or 1.0))), settle(matrix.identity_of(a))
    for _ in range(steps):
        poly = matrix.axpy(1.5, eye, -0.5, matrix.multiply(x, x, tol))
        x = settle(matrix.multiply(x, poly, tol))
    return x


def global_density(h: DataFrame, s: DataFrame, mu: float, k_inverse: int = 12, k_sign: int = 20, tol: float = 1e-10) -> DataFrame:
    """D by global products only: the conventional linear-scaling scheme."""
    inv = cut(global_inverse(s, k_inverse, tol))
    eye = matrix.identity_of(s)
    a = cut(matrix.axpy(1.0, matrix.multiply(inv, h, tol), -mu, eye))
    x = global_sign(a, k_sign, tol)
    return matrix.multiply(matrix.axpy(0.5, eye, -0.5, x), inv, tol)


def orthogonalised_density(h: DataFrame, s: DataFrame, mu: float, groups: DataFrame | None = None, k_inverse: int = 12, tol: float = 1e-10) -> DataFrame:
    """D by the single-matrix method: S^-1 and S^-1 H formed globally, the sign of their submatrices, times S^-1."""
    inv = cut(global_inverse(s, k_inverse, tol))
    eye = matrix.identity_of(s)
    a = cut(matrix.axpy(1.0, matrix.multiply(inv, h, tol), -mu, eye))
    x = submatrix_apply(a, MatFn("sign", lambda m: sign_exact(m, symmetric=False)), groups)
    return matrix.multiply(matrix.axpy(0.5, eye, -0.5, x), inv, tol)
