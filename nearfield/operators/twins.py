"""Block-diagonal matrices of cliques of like rows, kept as two numbers a clique instead of an entry a pair of rows.

On a clique of m rows a matrix with ``on`` on the diagonal and ``off`` elsewhere acts on the normed sum of the rows as
on + (m - 1) off and on their m - 1 differences as on - off. The submatrix method runs on these (``kernels.Twins``), and
``expand`` makes the entries of the result from members: no entry of the full matrix is shuffled or stored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Columns of a clique that its rows meet at a time, and entries that a task makes, about.
COLUMNS_A_PIECE, ENTRIES_A_PART = 1024, 20_000_000


def reduced(cliques: DataFrame, **values: tuple[Column, Column]) -> DataFrame:
    """(row, col, values..., twins) from (clique, m) and (on, off) of each value; twins: how many functions a place stands for.

    Place 2 * clique is that of the sum, 2 * clique + 1 that of the differences (of none, if m is 1).
    """
    m = F.col("m").cast("double")
    both = [(F.lit(0), m - 1, F.lit(1.0)), (F.lit(1), F.lit(-1.0), m - 1)]
    kinds = F.explode(F.array(*[F.struct((2 * F.col("clique") + k).alias("row"), *[(on + many * off).cast("double").alias(v) for v, (on, off) in values.items()], twins.alias("twins")) for k, many, twins in both])).alias("e")
    return cliques.select(kinds).select("e.row", F.col("e.row").alias("col"), *[f"e.{v}" for v in values], "e.twins")


def reduced_groups(cliques: DataFrame) -> DataFrame:
    """(group_id, member): a clique a group."""
    return cliques.select(F.col("clique").alias("group_id"), F.explode(F.array(2 * F.col("clique"), 2 * F.col("clique") + 1)).alias("member"))


def expand(m: DataFrame, members: DataFrame, digits: int | None = None) -> DataFrame:
    """(row, col, val) of every pair of a clique's members from the reduced (row, col, val); ``members``: member, clique, m.

    With ``digits`` values are rounded, once a clique. Each row meets its clique's columns in pieces. No column is nullable
    (but ``row``, if a member is null), so that Parquet's writer makes no level of nulls for an entry.
    """
    cliques = members.select("clique", "m").distinct()
    at = m.groupBy(F.shiftright("row", 1).alias("clique")).agg(*[F.max(F.when(F.col("row") % 2 == k, F.col("val"))).alias(name) for k, name in ((0, "_sum"), (1, "_apart"))])
    off = (F.col("_sum") - F.col("_apart")) / F.col("m")
    of = [(off + F.col("_apart")).alias("on"), off.alias("off")]
    at = at.join(cliques, "clique").select("clique", *of)
    if digits is not None:
        at = at.select("clique", *[(F.round(c, digits) + F.lit(0.0)).alias(c) for c in ("on", "off")])
    entries, unknown = members.agg(F.coalesce(F.sum(F.col("m").cast("double")), F.lit(0.0)), F.count_if(F.col("member").isNull())).first()
    parts = int(max(3 * m.sparkSession.sparkContext.defaultParallelism, entries // ENTRIES_A_PART))
    pieces = F.ceil(F.col("m") / COLUMNS_A_PIECE)
    member = F.col("member") if unknown else F.coalesce("member", F.lit(0).cast(members.schema["member"].dataType))
    row = [member.alias("row"), F.col("clique").alias("_c"), *[F.coalesce(c, F.lit(float("nan"))).alias(c) for c in ("on", "off")]]
    left = members.join(at, "clique").select(*row, F.explode(F.sequence(F.lit(0).cast("long"), pieces - 1)).alias("_p"))
    right = members.groupBy(F.col("clique").alias("_c"), F.pmod(F.xxhash64("member"), pieces).alias("_p")).agg(F.collect_list("member").alias("_cols"))
    left, right = (x.repartition(parts, "_c", "_p") for x in (left, right))
    pairs = left.join(right.hint("shuffle_hash"), ["_c", "_p"]).select("row", F.explode("_cols").alias("col"), "on", "off")
    return pairs.select("row", "col", F.when(F.col("row") == F.col("col"), F.col("on")).otherwise(F.col("off")).alias("val"))
