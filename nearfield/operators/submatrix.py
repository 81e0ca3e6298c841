"""The submatrix method: cut one dense principal submatrix out per column group, apply a function, keep owned columns.

One exchange brings each part of groups the matrix columns that its lists name ("halo"), or each group the entries of
its own submatrix ("gather"). After the dense stage nothing is shuffled: results are written where they are made.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import PLAIN, MatFn, Plain, Purification, Twins, purify, spectral_weights
from ..plans.balance import balance, parts_for
from ..sources.tables import cut, settle_packed
from .patterns import group_pattern, places, single_groups

METRICS = "n long, k_inv int, k_sign int, resid double, gemms int, secs double"


class Columns:
    """A part's matrix entries by column, and dense submatrices cut from them."""

    def __init__(self, row: np.ndarray, col: np.ndarray, values: list[np.ndarray]):
        order = np.lexsort((row, col))
        self.row, self.values = row[order], [v[order] for v in values]
        self.cols, first = np.unique(col[order], return_index=True)
        self.first = np.append(first, len(row))

    def cut(self, idx: np.ndarray, out: list[np.ndarray] | None = None) -> tuple[list[np.ndarray], np.ndarray]:
        """(dense matrices on the index list, mask of the places that are stored); ``out``: zeroed matrices to fill."""
        n = len(idx)
        at = np.searchsorted(self.cols, idx)
        at[at == len(self.cols)] = 0
        known = self.cols[at] == idx if len(self.cols) else np.zeros(n, bool)
        start, length = self.first[at], np.where(known, self.first[at + 1] - self.first[at], 0) if len(self.cols) else np.zeros(n, np.int64)
        total = int(length.sum())
        spots = np.arange(total) - np.repeat(np.cumsum(length) - length - start, length) if total else np.zeros(0, np.int64)
        j = np.repeat(np.arange(n), length)
        r = self.row[spots]
        i = np.searchsorted(idx, r)
        i[i == n] = 0
        inside = idx[i] == r if total else np.zeros(0, bool)
        i, j, spots = i[inside], j[inside], spots[inside]
        mask = np.zeros((n, n), bool)
        mask[i, j] = True
        out = out if out is not None else [np.zeros((n, n)) for _ in self.values]
        for m, v in zip(out, self.values, strict=True):
            m[i, j] = v[spots]
        return out, mask


class Buffers:
    """Work arrays that a task uses again for group after group; they grow to the largest stack."""

    def __init__(self, kinds: int):
        self.flat = [np.zeros(0) for _ in range(kinds)]

    def zeros(self, shape: tuple[int, int, int]) -> list[np.ndarray]:
        size = shape[0] * shape[1] * shape[2]
        for k, held in enumerate(self.flat):
            if held.size < size:
                self.flat[k] = np.zeros(size)
            else:
                held[:size] = 0.0
        return [held[:size].reshape(shape) for held in self.flat]


#: Values of a stack of equal-sized submatrices that a kernel gets at a time, at most (one submatrix may have more).
STACK = 1 << 18


def lists_of(column) -> list[np.ndarray]:
    """Arrays of a list column, without Python numbers."""
    parts = []
    for chunk in column.chunks if isinstance(column, pa.ChunkedArray) else [column]:
        ends, flat = chunk.offsets.to_numpy(), chunk.values.to_numpy(zero_copy_only=False).astype(np.int64)
        parts += [flat[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
    return parts


def stacks_of(lists: list[np.ndarray], together: bool) -> Iterator[np.ndarray]:
    """Numbers of the lists in stacks of equal length."""
    n = np.array([len(x) for x in lists], np.int64)
    order = np.argsort(n, kind="stable")
    for own in np.split(order, np.flatnonzero(np.diff(n[order])) + 1) if len(order) else []:
        size = int(n[own[0]])
        step = max(1, STACK // max(1, size * size)) if together else 1
        for at in range(0, len(own), step):
            yield own[at : at + step]


#: Entries that a task packs into parts of columns at a time.
PACKED = 1 << 18


def column_parts(m: DataFrame, values: list[str], drop_tol: float = 0.0) -> DataFrame:
    """(col, rows, values...): the entries of ``places`` as parts of columns, a row for each column that a task meets.

    Zeros on the diagonal are not made; an id that no column part names has a part without rows. So each id of the matrix
    is a col, and the places are those of the parts and the diagonal.
    """

    def pack(row, col, kept, *found):
        ids = np.unique(np.concatenate([row, col]))
        order = np.lexsort((row, col))
        order = order[kept[order]]
        row, col = row[order], col[order]
        cols, many = np.unique(col, return_counts=True)
        alone = np.setdiff1d(ids, cols, assume_unique=True)
        ends = pa.array(np.concatenate([[0], np.cumsum(many), np.full(len(alone), len(col))]).astype(np.int32))
        lists = [pa.ListArray.from_arrays(ends, pa.array(v)) for v in (row, *(v[order] for v in found))]
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([cols, alone])), *lists], ["col", "rows", *values])

    def run(batches):
        held, n = [], 0
        for b in batches:
            held.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
            n += b.num_rows
            if n >= PACKED:
                yield pack(*map(np.concatenate, zip(*held, strict=True)))
                held, n = [], 0
        if n:
            yield pack(*map(np.concatenate, zip(*held, strict=True)))

    long = [F.col(c).cast("long").alias(c) for c in ("row", "col")]
    kept = F.coalesce(F.abs("val") > drop_tol, F.lit(False)) | (F.col("row") == F.col("col"))
    real = [F.coalesce(F.col(v).cast("double"), F.lit(0.0)).alias(v) for v in values]
    m = m.where("row is not null and col is not null")
    return m.select(*long, kept.alias("kept"), *real).mapInArrow(run, "col long, rows array<long>" + "".join(f", {v} array<double>" for v in values))


Kernel = Callable[[list[np.ndarray]], tuple[list[np.ndarray], dict]]


def run_groups(groups: DataFrame, entries: DataFrame, values: list[str], results: list[str], kernel: Kernel, result_pattern: str, strategy: str = "halo", together: bool = False, parts: int | None = None, diagonal: bool = False, measured: bool = True) -> DataFrame:
    """The dense stage: (group_id, row, col, results..., metrics...), where a group's metrics are a row without place.

    ``groups``: group_id, idx, own, n, part_id. ``kernel(dense)`` gets one stack of dense matrices (a single matrix,
    unless ``together``) for each of the value columns and returns as many as ``results`` and a dict of metrics.
    ``parts``: that many tasks, which adaptive execution does not join by their bytes: parts are dealt by work.
    ``together``: submatrices of equal size go to the kernel in stacks. ``result_pattern``: "input" keeps owned
    entries where the matrix stores one, "merged" all rows of the owned columns. ``diagonal``: the matrix stores all of
    it, as zeros where ``entries`` has none. Not ``measured``: only row, col and the results, without metrics.
    Entries may be rows, or for the halo parts of columns (see ``column_parts``).
    """
    row = "rows" if "rows" in entries.columns else "row"
    kind = "array<double>" if row == "rows" else "double"
    lists = groups.select("part_id", F.explode("idx").alias("c"), "group_id")
    if strategy == "gather":
        cells = lists.select("part_id", "group_id", F.col("c"))
        e = cells.join(entries, F.col("c") == F.col("col")).select("part_id", "group_id", "row", "col", *values)
        inside = cells.select(F.col("group_id").alias("g2"), F.col("c").alias("r2"))
        e = e.join(inside, (F.col("group_id") == F.col("g2")) & (F.col("row") == F.col("r2")), "left_semi")
        e = e.drop("group_id").distinct()
    else:
        wanted = lists.select("part_id", "c").distinct()
        e = wanted.join(entries, F.col("c") == F.col("col")).select("part_id", row, "col", *values)
    e = e.select(F.col("part_id").alias("part"), F.col(row).alias("e_row"), F.col("col").alias("e_col"), *[F.col(v).cast(kind).alias(f"e_{v}") for v in values])
    merged = result_pattern == "merged"

    def work(left, right):
        if row == "rows":
            of = lambda name: right.column(name).combine_chunks().flatten().to_numpy()
            long = right.column("e_row").combine_chunks().value_lengths().to_numpy()
            c = Columns(of("e_row"), np.repeat(right.column("e_col").to_numpy(), long), [of(f"e_{v}") for v in values])
        else:
            c = Columns(right.column("e_row").to_numpy(), right.column("e_col").to_numpy(), [right.column(f"e_{v}").to_numpy() for v in values])
        ids, idx_of, own_of = left.column("group_id").to_pylist(), lists_of(left.column("idx")), lists_of(left.column("own"))
        places_of, metrics, held = [], [], Buffers(len(values))
        bare = pa.schema([("row", pa.int64()), ("col", pa.int64()), *((r, pa.float64()) for r in results)])
        for stack in stacks_of(idx_of, together):
            began = time.perf_counter()
            n = len(idx_of[stack[0]])
            dense = held.zeros((len(stack), n, n))
            masks = [c.cut(idx_of[g], [d[k] for d in dense])[1] for k, g in enumerate(stack)]
            found, done = kernel(dense if together else [d[0] for d in dense])
            found = found if together else [f[None] for f in found]
            miss, size = (np.broadcast_to(done.get(k, v), len(stack)) for k, v in (("residual", 0.0), ("n", n)))
            took = (time.perf_counter() - began) / len(stack)
            for k, g in enumerate(stack):
                idx, own = idx_of[g], own_of[g]
                at = np.searchsorted(idx, own)
                keep = np.ones((n, len(own)), bool) if merged else masks[k][:, at]
                if diagonal:
                    keep[at, np.arange(len(own))] = True
                i, j = np.nonzero(keep)
                place = (ids[g], idx[i], own[j], [f[k][:, at][i, j] for f in found])
                places_of.append(place if measured else pa.record_batch([place[1], place[2], *place[3]], bare))
                metrics.append((ids[g], int(size[k]), done.get("k_inverse", 0), done.get("k_sign", 0), float(miss[k]), done.get("gemms", 0), took))
        return _table(places_of, metrics, results) if measured else pa.Table.from_batches(places_of, bare)

    found = "row long, col long" + "".join(f", {r} double" for r in results)
    schema = f"group_id long, {found}, {METRICS}" if measured else found
    left = groups.select("part_id", "group_id", "idx", "own")
    if parts is not None:
        left, e = left.repartition(parts, "part_id"), e.repartition(parts, "part")
    return left.groupBy("part_id").cogroup(e.groupBy("part")).applyInArrow(work, schema)


def _table(found: list, metrics: list, results: list[str]) -> pa.Table:
    n, m = sum(len(f[1]) for f in found), len(metrics)
    cat = lambda parts, kind: np.concatenate(parts).astype(kind) if parts else np.zeros(0, kind)
    nulls = lambda k: pa.nulls(k)
    cols = {
        "group_id": pa.array(np.concatenate([np.repeat(np.array([f[0] for f in found], np.int64), [len(f[1]) for f in found]), np.array([x[0] for x in metrics], np.int64)])),
        "row": pa.concat_arrays([pa.array(cat([f[1] for f in found], np.int64)), nulls(m).cast(pa.int64())]),
        "col": pa.concat_arrays([pa.array(cat([f[2] for f in found], np.int64)), nulls(m).cast(pa.int64())]),
    }
    for k, r in enumerate(results):
        cols[r] = pa.concat_arrays([pa.array(cat([f[3][k] for f in found], np.float64)), nulls(m).cast(pa.float64())])
    kinds = {"n": pa.int64(), "k_inv": pa.int32(), "k_sign": pa.int32(), "resid": pa.float64(), "gemms": pa.int32(), "secs": pa.float64()}
    for k, (name, kind) in enumerate(kinds.items(), 1):
        cols[name] = pa.concat_arrays([nulls(n).cast(kind), pa.array([x[k] for x in metrics], kind)])
    return pa.table(cols)


def entries_of(out: DataFrame, value: str) -> DataFrame:
    """(row, col, val) of one result of the dense stage."""
    return out.where(F.col("row").isNotNull()).select("row", "col", F.col(value).alias("val"))


def metrics_of(out: DataFrame) -> DataFrame:
    """(group_id, n, k_inv, k_sign, resid, gemms, flops, secs): a row for each submatrix."""
    flops = (F.lit(2) * F.col("gemms") * F.pow(F.col("n").cast("double"), 3)).cast("decimal(38,0)")
    return out.where(F.col("row").isNull()).select("group_id", "n", "k_inv", "k_sign", "resid", "gemms", flops.alias("flops"), "secs")


def space_of(dense: list[np.ndarray], values: list[str]) -> Plain:
    """What the dense matrices stand for: themselves, or larger ones if one of the value columns is ``twins``."""
    return Twins.of(dense[values.index("twins")]) if "twins" in values else PLAIN


def submatrix_apply(
    m: DataFrame,
    fn: MatFn,
    groups: DataFrame | None = None,
    drop_tol: float = 0.0,
    result_pattern: str = "input",
    strategy: str = "halo",
    parts: int | None = None,
    with_metrics: bool = False,
) -> DataFrame:
    """f(A) by the submatrix method: (row, col, val) on the pattern of A, or of the groups' lists.

    ``groups`` (group_id, member) share one submatrix each; by default every column has its own. With
    ``with_metrics`` the dense stage's table is returned; see ``entries_of`` and ``metrics_of``. A matrix with a column
    ``twins`` is a reduced one (see ``twins.py``), and so is the result.
    """
    values = ["val", *(["twins"] if "twins" in m.columns else [])]
    e = settle_packed(column_parts(m, values, drop_tol))
    p = e.select("col", F.concat("rows", F.array("col")).alias("rows"))
    gp = cut(group_pattern(p, groups if groups is not None else single_groups(p)))
    parts = parts or parts_for(gp)
    gp = balance(gp, parts)
    if strategy == "gather":
        pairs = F.explode(F.arrays_zip("rows", *values)).alias("e")
        e = e.select("col", pairs).select(F.col("e.rows").alias("row"), "col", *[f"e.{v}" for v in values])

    def kernel(dense):
        space = space_of(dense, values)
        return [fn(dense[0], space)], {"n": space.size(dense[0])}

    out = run_groups(gp, e, values, ["val"], kernel, result_pattern, strategy, fn.stacks, parts, diagonal=True, measured=with_metrics)
    return out if with_metrics else entries_of(out, "val")


def locality_report(m: DataFrame, fn: MatFn, share: float = 0.05, seed: int = 1) -> DataFrame:
    """(col, leak): on a hash sample of columns, how far one- and two-step submatrices' columns differ (max abs).

    A small leak says that the function keeps the pattern well enough for the method.
    """
    p = places(m)
    near = p.where(F.pmod(F.xxhash64("col", F.lit(seed)), F.lit(10_000)) < int(10_000 * share))
    far = near.join(p.select(F.col("row").alias("r2"), F.col("col").alias("mid")), F.col("row") == F.col("mid")).select(F.col("r2").alias("row"), "col").distinct()
    found = []
    for lists in (near, far):
        gp = cut(group_pattern(lists, single_groups(near)))
        parts = parts_for(gp)
        out = run_groups(balance(gp, parts), m.select("row", "col", "val"), ["val"], ["val"], lambda dense: ([fn(dense[0])], {}), "input", together=fn.stacks, parts=parts)
        found.append(entries_of(out, "val"))
    both = found[0].join(found[1].withColumnRenamed("val", "val2"), ["row", "col"])
    return both.groupBy("col").agg(F.max(F.abs(F.col("val") - F.col("val2"))).alias("leak"))


# ---- the pair


def paired_purify(
    pair: DataFrame,
    how: Purification,
    groups: DataFrame | None = None,
    with_w: bool = True,
    result_pattern: str = "input",
    strategy: str = "halo",
    parts: int | None = None,
    max_n: int | None = None,
) -> DataFrame:
    """The paired method: D (and W = D H D) from (row, col, h, s), cut on the union of both patterns.

    Returns the dense stage's table with columns d and w; ``entries_of(out, "d")`` and ``metrics_of(out)`` split it.
    ``max_n`` refuses a group whose submatrix is larger. A pair with a column ``twins`` is a reduced one (see
    ``twins.py``), and so is the result; its metrics have the size and products of the full submatrices.
    """
    from ..plans.balance import explain

    values = ["h", "s", *(["twins"] if "twins" in pair.columns else [])]
    both = pair.select("row", "col", (F.abs("h") + F.abs("s")).alias("val"))
    p = places(both)
    gp = cut(group_pattern(p, groups if groups is not None else single_groups(p)))
    if max_n is not None:
        explain(gp, most_n=max_n)
    parts = parts or parts_for(gp)
    gp = balance(gp, parts)

    def kernel(dense):
        space = space_of(dense, values)
        d, w, done = purify(dense[0], dense[1], how, with_w, space)
        return [d, w if w is not None else np.zeros_like(d)], done | {"n": space.size(d)}

    return run_groups(gp, pair, values, ["d", "w"], kernel, result_pattern, strategy, how.stacks, parts)


def level_weights(pair: DataFrame, groups: DataFrame, parts: int | None = None) -> DataFrame:
    """(group_id, level, weight): each submatrix's levels with the weight of the functions it owns, computed once.

    The electron count at any potential is then an aggregate of this table. A pair with a column ``twins`` is a reduced
    one: its levels count as often as the full pair has them.
    """
    values = ["h", "s", *(["twins"] if "twins" in pair.columns else [])]
    p = places(pair.select("row", "col", (F.abs("h") + F.abs("s")).alias("val")))
    gp = cut(group_pattern(p, groups))
    parts = parts or parts_for(gp)
    gp = balance(gp, parts)
    lists = gp.select("part_id", F.explode("idx").alias("c")).distinct()
    e = lists.join(pair, F.col("c") == F.col("col")).select(F.col("part_id").alias("part"), F.col("row").alias("e_row"), F.col("col").alias("e_col"), *[F.col(v).cast("double").alias(f"e_{v}") for v in values])

    def meet(left, right):
        c = Columns(*(right.column(k).to_numpy() for k in ("e_row", "e_col")), [right.column(f"e_{v}").to_numpy() for v in values])
        g, level, weight = [], [], []
        for group, idx, own in zip(left.column("group_id").to_pylist(), lists_of(left.column("idx")), lists_of(left.column("own")), strict=True):
            (h, s, *twins), _ = c.cut(idx)
            e_, w_ = spectral_weights(h, s, np.searchsorted(idx, own), np.diagonal(twins[0]) if twins else None)
            g += [group] * len(e_)
            level += e_.tolist()
            weight += w_.tolist()
        return pa.table({"group_id": pa.array(g, pa.int64()), "level": pa.array(level, pa.float64()), "weight": pa.array(weight, pa.float64())})

    left = gp.select("part_id", "group_id", "idx", "own").repartition(parts, "part_id")
    return left.groupBy("part_id").cogroup(e.repartition(parts, "part").groupBy("part")).applyInArrow(meet, "group_id long, level double, weight double")
