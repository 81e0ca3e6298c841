"""Sparsity patterns, column groups and their index lists."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import settle

def places(m: DataFrame, drop_tol: float = 0.0, value: str = "val") -> DataFrame:
    """(row, col) where the entry exceeds ``drop_tol``, and the diagonal of every row and column named."""
    p = m.where(F.abs(value) > drop_tol).select("row", "col")
    ids = m.select(F.explode(F.array("row", "col")).alias("row"))
    return p.unionByName(ids.select("row", F.col("row").alias("col"))).distinct()


def as_lists(p: DataFrame) -> DataFrame:
    """(col, rows): the sorted row list of each column."""
    return p.groupBy("col").agg(F.array_sort(F.collect_set("row")).alias("rows"))


def pattern(m: DataFrame, drop_tol: float = 0.0) -> DataFrame:
    """(col, rows): rows where a column is nonzero; the diagonal always belongs to it."""
    return as_lists(places(m, drop_tol))


def merged_places(h: DataFrame, s: DataFrame, drop_tol: float = 0.0) -> DataFrame:
    """(row, col) where either matrix is nonzero; one exchange for both."""
    both = h.select("row", "col", "val").unionByName(s.select("row", "col", "val"))
    return places(both, drop_tol)


def merge_patterns(h: DataFrame, s: DataFrame, drop_tol: float = 0.0) -> DataFrame:
    """(col, rows): a row belongs to a column's list if either matrix is nonzero there."""
    return as_lists(merged_places(h, s, drop_tol))


def pair_rows(h: DataFrame, s: DataFrame) -> DataFrame:
    """Two matrices as one table (row, col, h, s) on the union of their patterns: later steps scan and shuffle once."""
    zero = F.lit(0.0)
    both = h.select("row", "col", F.col("val").alias("h"), zero.alias("s")).unionByName(s.select("row", "col", zero.alias("h"), F.col("val").alias("s")))
    return both.groupBy("row", "col").agg(F.sum("h").alias("h"), F.sum("s").alias("s"))


def single_groups(p: DataFrame) -> DataFrame:
    """(group_id, member): every column its own group."""
    return p.select(F.col("col").alias("group_id"), F.col("col").alias("member")).distinct()


def one_group(p: DataFrame) -> DataFrame:
    """(group_id, member): all columns in one group, which makes the method exact."""
    return p.select(F.col("col").alias("member")).distinct().select(F.lit(0).cast("long").alias("group_id"), "member")


#: Places that a task joins together at a time.
JOINED = 1 << 18


def _hung(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, the least node that places (a, b) connect each with)."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y, label = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while True:
        lx, ly = label[x], label[y]
        apart = lx != ly
        if not apart.any():
            return nodes, nodes[label]
        x, y, lx, ly = x[apart], y[apart], lx[apart], ly[apart]
        np.minimum.at(label, np.maximum(lx, ly), np.minimum(lx, ly))
        while (label[label] != label).any():
            label = label[label]


def contracted(e: DataFrame) -> DataFrame:
    """(a, b): for each partition of places (a, b) its nodes, each with the least node that the partition connects it with.

    Components stay the same, and so do the nodes; what is left is a row a node and partition, however many places there are.
    """

    def run(batches):
        a = b = np.zeros(0, np.int64)
        held, n, kind = [], 0, pa.int64()
        for x in batches:
            held.append(tuple(c.to_numpy().astype(np.int64) for c in x.columns))
            n, kind = n + x.num_rows, x.schema.field(0).type
            if n >= JOINED:
                a, b = _hung(*(np.concatenate([star, *c]) for star, c in zip((a, b), zip(*held, strict=True), strict=True)))
                held, n = [], 0
        if n:
            a, b = _hung(*(np.concatenate([star, *c]) for star, c in zip((a, b), zip(*held, strict=True), strict=True)))
        yield pa.RecordBatch.from_arrays([pa.array(a).cast(kind), pa.array(b).cast(kind)], ["a", "b"])

    return e.mapInArrow(run, e.schema)


def components(p: DataFrame) -> DataFrame:
    """(node, component) of places (row, col): the least id that entries connect a row or column with.

    Each round hangs every component below its least neighbour, follows these links to their ends and joins the places
    with the ends; places within one component drop out. Before, each task joins what its own places connect.
    """
    e = p.select(F.col("row").cast("long").alias("a"), F.col("col").cast("long").alias("b")).where("a is not null and b is not null")
    e = settle(contracted(e))
    labels = settle(e.select(F.explode(F.array("a", "b")).alias("node")).distinct().withColumn("component", F.col("node")))
    e = e.where("a <> b")
    while True:
        both = e.select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("e")).select("e.a", "e.b")
        up = settle(both.groupBy("a").agg(F.min("b").alias("_m")).select("a", F.least("a", "_m").alias("up")))
        if up.isEmpty():
            return labels
        while True:
            higher = up.select(F.col("a").alias("_a"), F.col("up").alias("_up"))
            up = settle(up.join(higher, F.col("up") == F.col("_a")).select("a", F.col("_up").alias("up"), (F.col("up") > F.col("_up")).alias("_moved")))
            if up.where("_moved").isEmpty():
                break
        up = up.select("a", "up")
        labels = settle(labels.join(up, F.col("component") == F.col("a"), "left").select("node", F.coalesce("up", "component").alias("component")))
        e = e.join(up, "a").select(F.col("up").alias("a"), "b").distinct()
        e = settle(e.join(up.withColumnRenamed("a", "b"), "b").where("a <> up").select("a", F.col("up").alias("b")).distinct())


def component_groups(p: DataFrame) -> DataFrame:
    """(group_id, member): the columns of each connected component in one group, which makes the method exact."""
    return components(p).select(F.col("component").alias("group_id"), F.col("node").alias("member"))


def group_pattern(p: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, idx, own, n): the union of the members' row lists, the members, and the dimension.

    ``p`` holds places (row, col), or parts of columns (col, rows). Columns that no group names are left out.
    """
    rows = F.explode("rows").alias("row") if "rows" in p.columns else "row"
    joined = groups.join(p, F.col("member") == F.col("col")).select("group_id", rows, "member")
    g = joined.groupBy("group_id").agg(F.array_sort(F.collect_set("row")).alias("idx"), F.array_sort(F.collect_set("member")).alias("own"))
    return g.withColumn("n", F.size("idx").cast("long"))


def coarse(p: DataFrame, groups: DataFrame) -> DataFrame:
    """(row, col) between groups: the pattern of blocks, such as of atoms."""
    a = groups.select(F.col("member").alias("row"), F.col("group_id").alias("ri"))
    b = groups.select(F.col("member").alias("col"), F.col("group_id").alias("ci"))
    return p.join(a, "row").join(b, "col").select(F.col("ri").alias("row"), F.col("ci").alias("col")).distinct()


def hub_report(gp: DataFrame, top: int = 10) -> tuple[DataFrame, DataFrame]:
    """(quantiles of n, the ``top`` largest groups): columns whose submatrix grows with the system show here."""
    quantiles = gp.agg(F.count(F.lit(1)).alias("groups"), *[F.percentile_approx("n", q).alias(f"p{int(q * 100)}") for q in (0.5, 0.9, 0.99)], F.max("n").alias("largest"))
    return quantiles, gp.select("group_id", "n").orderBy(F.desc("n"), "group_id").limit(top)


def weighted_size(gp: DataFrame, weights: DataFrame) -> DataFrame:
    """``gp`` with n as the sum of the listed members' weights (member, weight), such as functions of atoms."""
    long = gp.select("group_id", F.explode("idx").alias("member")).join(weights, "member")
    n = long.groupBy("group_id").agg(F.sum("weight").cast("long").alias("n"))
    return gp.drop("n").join(n, "group_id")
