"""Connected components of an edge table, by rounds of joins: nothing is gathered on the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import settle


#: Parts that the neighbours of a node are dealt in at least, and neighbours in a part of the largest hubs, about.
PARTS, PART_EDGES = 16, 100_000


def _beside_least(rows: DataFrame, n: int) -> DataFrame:
    """``rows`` (u, v), of which there are at most ``n``, with the least v of each u as m.

    The neighbours of each node are gathered in parts, dealt by node and part, so a hub's are spread; what meets by the
    node alone are its parts: one row for many neighbours, few rows however many neighbours a hub has.
    """
    part = F.pmod(F.xxhash64("v"), F.lit(max(PARTS, -(-n // PART_EDGES))))
    lists = rows.groupBy("u", part.alias("p")).agg(F.collect_list("v").alias("vs"))
    least = lists.groupBy(F.col("u").alias("k")).agg(F.min(F.array_min("vs")).alias("m"))
    return lists.join(least, F.col("u") == F.col("k")).select("u", F.explode("vs").alias("v"), "m")


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): component is the least node reachable; only nodes that an edge names.

    Alternates two steps until nothing changes: every node's larger neighbours are linked to its least neighbour,
    then every node and its smaller neighbours to the least of them. The number of rounds grows with the logarithm
    of the longest path. A node of very many edges is no hot group: see ``_beside_least``. Null ends and loops are
    left out.
    """
    e = edges.select(F.least(a, b).alias("v"), F.greatest(a, b).alias("u")).where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
    e = settle(e.distinct())
    seen, n = None, e.count()
    while n:
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _beside_least(both, 2 * n).where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.least("u", "m").alias("v"))
        large = large.distinct()
        small = _beside_least(large, n)  # no more rows than edges
        e = small.select(F.col("m").alias("v"), "u").union(small.where("v <> m").select(F.col("m").alias("v"), F.col("v").alias("u"))).where("u <> v").distinct()
        e = settle(e)
        now = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen, n = now, now[0]
    nodes = e.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.union(e.select(F.col("v"), F.col("v")).distinct())
