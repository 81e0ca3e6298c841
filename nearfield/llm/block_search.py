"""Exact nearest neighbours by a blocked matrix join of queries and candidates.

Queries and candidates are dealt into blocks of bounded size; every (query block, candidate block) pair meets in one
task. There an int8 product tile gives each distance up to a proven quantisation error; only the pairs that may be
among a query's nearest are computed anew from the original vectors. Heaps merge the tiles' nearest.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLOCK = 8192
_HIT = "query_id long, part long, vec_id long, score double"


def usable(column: str) -> Column:
    """A vector that is not null, not zero, and has only finite components."""
    v = F.col(column)
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return F.coalesce(v.isNotNull() & finite & F.exists(v, lambda x: x != 0), F.lit(False))


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """int8 codes, the scale of each row, the norm of what the codes stand for, and of what they miss."""
    scale = np.maximum(np.abs(x).max(axis=1) / 127.0, 1e-300)
    codes = np.rint(x / scale[:, None]).astype(np.int8)
    stands = codes * scale[:, None]
    return codes, scale, np.sqrt((stands**2).sum(axis=1)), np.sqrt(((x - stands) ** 2).sum(axis=1))


def distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Euclidean distance of each row pair, in double precision, components added in order.

    Rows whose squares leave the range of doubles are scaled by a power of two, which is exact; a distance above the
    largest double is infinite.
    """
    with np.errstate(over="ignore", under="ignore", invalid="ignore"):
        total = np.zeros(len(x))
        for i in range(x.shape[1]):
            d = x[:, i] - y[:, i]
            total += d * d
        out = np.sqrt(total)
        odd = np.flatnonzero(~(total < 1e300) | (total < 1e-280))
        if len(odd):
            a, b = x[odd] * 0.25, y[odd] * 0.25  # so that a difference stays finite
            d = a - b
            e = np.frexp(np.abs(d).max(axis=1))[1]
            d = np.ldexp(d, -e[:, None])
            total = np.zeros(len(odd))
            for i in range(d.shape[1]):
                total += d[:, i] * d[:, i]
            out[odd] = np.ldexp(np.sqrt(total), e + 2)
    return out


def tile(queries: np.ndarray, q_ids: np.ndarray, rows: np.ndarray, r_ids: np.ndarray, k: int) -> list[tuple[int, int, float]]:
    """(query id, row id, distance) of each query's k nearest rows of other ids; ties to the smaller id.

    Integer products are exact in the float type that multiplies them; with the codes' errors, a distance's square
    lies within ``slack`` of its estimate, so a row whose lower bound exceeds the k-th least upper bound is out. Vectors
    whose squares would leave the range of doubles are scaled for the estimate, all by one power of two; what then
    vanishes is within the bound, and the distances returned are those of the vectors given.
    """
    kind = np.float32 if 127 * 127 * rows.shape[1] < 1 << 24 else np.float64
    given_queries, given_rows = queries, rows
    most = max(np.abs(queries).max(), np.abs(rows).max())
    if not 1e-100 < most < 1e100:
        shift = -int(np.frexp(most)[1])
        queries, rows = np.ldexp(queries, shift), np.ldexp(rows, shift)
    q8, qs, qn, qe = quantise(queries)
    r8, rs, rn, re = quantise(rows)
    q2, r2 = (queries**2).sum(axis=1), (rows**2).sum(axis=1)
    r8t = r8.astype(kind).T
    out = []
    step = max(1, (1 << 21) // max(1, len(rows)))
    for at in range(0, len(queries), step):
        s = slice(at, at + step)
        estimate = q2[s, None] + r2 - 2 * (qs[s, None] * rs) * (q8[s].astype(kind) @ r8t)
        slack = 2 * (qn[s, None] * re + qe[s, None] * (rn + re)) + 1e-12 * (q2[s, None] + r2) + 1e-290
        own = q_ids[s, None] == r_ids
        estimate[own] = np.inf
        upper = estimate + slack
        if upper.shape[1] > k:
            most = np.partition(upper, k - 1, axis=1)[:, k - 1]
            left = (estimate - slack <= most[:, None]) & ~own
        else:
            left = ~own
        i, j = np.nonzero(left)
        score = np.concatenate([distances(given_queries[s][i[a : a + 65536]], given_rows[j[a : a + 65536]]) for a in range(0, len(i), 65536)] or [np.zeros(0)])
        ends = np.searchsorted(i, np.arange(len(estimate) + 1))
        for q, (a, b) in enumerate(zip(ends[:-1], ends[1:], strict=True)):
            best = heapq.nsmallest(k, zip(score[a:b].tolist(), r_ids[j[a:b]].tolist(), strict=True))
            out.extend((int(q_ids[at + q]), r, d) for d, r in best)
    return out


def _block(table: pa.Table, prefix: str) -> tuple[np.ndarray, np.ndarray]:
    """(vectors in double precision, ids), by id; of rows that share an id, the first by components."""
    ids = table.column(f"{prefix}_id").to_numpy()
    flat = table.column(f"{prefix}_v").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    x = flat.reshape(len(ids), -1)
    order = np.lexsort((*x.T[::-1], ids))
    x, ids = x[order], ids[order]
    first = np.ones(len(ids), bool)
    first[1:] = ids[1:] != ids[:-1]
    return x[first], ids[first]


def nearest(vectors: DataFrame, is_query: Column, k: int = 10, column: str = "embedding", block: int = BLOCK) -> DataFrame:
    """Each query's k nearest other rows: query_id, rank (from 1), vec_id, score (Euclidean distance).

    Rows whose vector is null, zero or not finite everywhere, and rows without vec_id, take no part; rows that share
    a vec_id are one (the first by components). Vectors of unlike length never meet. With fewer candidates than k all
    are returned. Other columns are ignored. Work is queries times rows by its nature; a task holds one block of each.
    """
    v = vectors.where(F.col("vec_id").isNotNull() & usable(column)).select("vec_id", F.col(column).alias("v"), F.size(column).alias("dim"), is_query.alias("asks"))
    n, asking = v.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.col("asks").cast("long")), F.lit(0))).first()
    parts, sides = max(1, math.ceil(n / block)), max(1, math.ceil(asking / block))
    part, side = F.pmod(F.xxhash64("vec_id"), F.lit(parts)), F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(sides))
    everywhere = lambda m: F.explode(F.sequence(F.lit(0), F.lit(m - 1)).cast("array<long>"))
    rows = v.select(F.col("vec_id").alias("r_id"), F.col("v").alias("r_v"), F.col("dim").alias("r_dim"), everywhere(sides).alias("r_side"), part.alias("r_part"))
    queries = v.where("asks").select(F.col("vec_id").alias("q_id"), F.col("v").alias("q_v"), F.col("dim").alias("q_dim"), side.alias("q_side"), everywhere(parts).alias("q_part"))

    def meet(key, left, right):
        hits = []
        if left.num_rows and right.num_rows:
            (q, q_ids), (r, r_ids) = _block(left, "q"), _block(right, "r")
            hits = tile(q, q_ids, r, r_ids, k)
        q, r, d = zip(*hits, strict=True) if hits else ((), (), ())
        return pa.table({"query_id": pa.array(q, pa.int64()), "part": pa.array([key[2].as_py()] * len(q), pa.int64()), "vec_id": pa.array(r, pa.int64()), "score": pa.array(d, pa.float64())})

    def merge(table: pa.Table) -> list[tuple[float, int]]:
        return heapq.nsmallest(k, zip(table.column("score").to_pylist(), table.column("vec_id").to_pylist(), strict=True))

    def partly(key, table):
        best = merge(table)
        return pa.table({"query_id": [key[0].as_py()] * len(best), "part": [key[1].as_py()] * len(best), "vec_id": [b for _, b in best], "score": [a for a, _ in best]})

    def ranked(key, table):
        best = merge(table)
        return pa.table({"query_id": [key[0].as_py()] * len(best), "rank": pa.array(range(1, len(best) + 1), pa.int32()), "vec_id": [b for _, b in best], "score": [a for a, _ in best]})

    hits = queries.groupBy("q_dim", "q_side", "q_part").cogroup(rows.groupBy("r_dim", "r_side", "r_part")).applyInArrow(meet, _HIT)
    if parts > 64:  # two rounds, so that no merge grows with the number of blocks
        hits = hits.withColumn("part", F.col("part") % math.isqrt(parts)).groupBy("query_id", "part").applyInArrow(partly, _HIT)
    return hits.groupBy("query_id").applyInArrow(ranked, "query_id long, rank int, vec_id long, score double")
