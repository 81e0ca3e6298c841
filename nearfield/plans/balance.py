"""Placing submatrices on tasks by their cost, and what a run will cost before it runs.

Adaptive execution balances bytes; the work of a submatrix is n^3, so parts are cut by cumulative cost instead.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def size_class(n):
    """Sizes within a factor of 2^(1/4) of one another share a class."""
    return F.floor(F.log2(F.greatest(n, F.lit(1)).cast("double")) * 4).cast("int")


def balance(gp: DataFrame, parts: int, locality: str | None = None) -> DataFrame:
    """``gp`` with part_id from 0 to about ``parts`` - 1, each of about equal sum of n^3.

    Costs are added by (locality, size class), prefix sums run over that small table only, and within a class a hash
    spreads the groups over the parts that the class covers; no window sees all groups. A class's largest group can
    exceed an even share; it then has a part of its own.
    """
    key = F.col(locality) if locality else F.lit(0)
    g = gp.withColumns({"_class": size_class(F.col("n")), "_place": key, "_cost": F.pow(F.col("n").cast("double"), 3)})
    by = g.groupBy("_place", "_class").agg(F.sum("_cost").alias("_sum"))
    order = W.orderBy("_place", "_class").rowsBetween(W.unboundedPreceding, -1)
    by = by.withColumns({"_before": F.coalesce(F.sum("_sum").over(order), F.lit(0.0)), "_total": F.sum("_sum").over(W.partitionBy())})
    by = by.select(F.col("_place").alias("_p"), F.col("_class").alias("_c"), "_sum", "_before", "_total")
    g = g.join(by, (F.col("_place") == F.col("_p")) & (F.col("_class") == F.col("_c")))
    within = F.pmod(F.xxhash64("group_id"), F.lit(1 << 20)) / float(1 << 20)
    at = (F.col("_before") + within * F.col("_sum")) / F.greatest("_total", F.lit(1.0))
    return g.select(*gp.columns, F.least(F.floor(at * parts), F.lit(parts - 1)).cast("int").alias("part_id"))


@dataclass
class Explanation:
    """Counts known before the dense work starts."""

    groups: int
    largest: int
    sum_n3: float
    flops: float
    listed: int
    bytes_largest: int
    sum_n2: float = 0.0

    def __str__(self) -> str:
        return f"{self.groups} submatrices, largest {self.largest}; sum n^3 {self.sum_n3:.3g}, {self.flops:.3g} flops; {self.listed} list entries to exchange; largest needs {self.bytes_largest / 1e6:.1f} MB"


class TooExpensive(RuntimeError):
    """The plan exceeds its budget."""


def explain(gp: DataFrame, gemms: int = 40, budget_flops: float | None = None, most_n: int | None = None) -> Explanation:
    """The cost of a run with so many products a submatrix; raises if over the budget or a submatrix is too large."""
    n = F.col("n").cast("double")
    r = gp.agg(F.count(F.lit(1)), F.coalesce(F.max("n"), F.lit(0)), F.coalesce(F.sum(n * n * n), F.lit(0.0)), F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum(n * n), F.lit(0.0))).first()
    e = Explanation(r[0], r[1], r[2], 2 * gemms * r[2], r[3], 6 * 8 * r[1] * r[1], r[4])
    if budget_flops is not None and e.flops > budget_flops:
        raise TooExpensive(f"over {budget_flops:.3g} flops: {e}")
    if most_n is not None and e.largest > most_n:
        raise TooExpensive(f"a submatrix over {most_n}: {e}")
    return e


#: List entries, and values of all submatrices together, that a part holds at most, about.
PART_LISTED, PART_VALUES = 500_000, 40_000_000


def parts_for(gp: DataFrame, least: int | None = None, flops_a_part: float = 2e11, gemms: int = 40) -> int:
    """Number of parts: enough for the cluster's tasks, and more where the work, the lists or the values are large."""
    spark = gp.sparkSession
    least = least or max(2, 3 * spark.sparkContext.defaultParallelism)
    e = explain(gp, gemms)
    return int(max(least, min(2_000_000, max(e.flops // flops_a_part, e.listed // PART_LISTED, e.sum_n2 // PART_VALUES))))
