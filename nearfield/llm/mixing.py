"""Mixing sources to target weights: Sainte-Lague apportionment of equal-token blocks. DataFrame functions only.

Sources get integer quotas of equal-token blocks by highest quotients, then each source's quota is apportioned in the
same way to its shards of documents. Within a shard the documents lie in a seeded order; whole passes come first, then
one run of blocks from a seeded place on. No window holds more than one shard, so a hot source is split.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .shared import cut, word_count

#: Words in a block.
BLOCK = 32
#: Words in a shard, about; sources over MOST_SHARDS of them have larger shards.
SHARD_WORDS = 1 << 18
MOST_SHARDS = 8192


def seeded(*of: Column | str) -> Column:
    """Seeded order and draws: 32 hex digits that DuckDB computes alike."""
    return F.md5(F.concat_ws("|", *[F.coalesce(c.cast("string") if isinstance(c, Column) else F.lit(c), F.lit("null")) for c in of]))


def draw(digits: Column, below: Column) -> Column:
    """A number from 0 to below - 1, by the first 12 of the hex digits."""
    return F.pmod(F.conv(F.substring(digits, 1, 12), 16, 10).cast("long"), F.greatest(below, F.lit(1)))


def apportion(parties: DataFrame, group: list[str], key: list[str], votes: str, seats: str) -> DataFrame:
    """Add ``quota``: each group's ``seats`` dealt to its parties by the highest quotients votes / 1, / 3, / 5...

    Starts from rounded shares, then hands out or takes back the few seats that those miss, by quotient (ties: by
    key). A party can be off by its share of the missing seats and of one seat a party at most, which bounds the
    quotients looked at: about three a party, never one for every seat. Groups without votes get no seats.
    """
    whole = W.partitionBy(*group)
    total = F.sum(votes).over(whole)
    share = F.when(F.col("_total") > 0, F.col(votes) * F.col(seats) / F.col("_total")).otherwise(0.0)
    a = parties.withColumns({"_total": total, "_parties": F.count(F.lit(1)).over(whole)})
    a = a.withColumn("_start", F.floor(share + 0.5))
    a = a.withColumn("_off", F.when(F.col("_total") > 0, F.col(seats) - F.sum("_start").over(whole)).otherwise(F.lit(0)).cast("long"))
    some = F.abs("_off")
    reach = F.least(some, F.ceil((some + F.col("_parties")) * F.col(votes) / F.greatest("_total", F.lit(1e-9))) + 1)
    more = F.expr("sequence(_start, _start + _reach - 1)")
    less = F.expr("sequence(greatest(0L, _start - _reach), _start - 1)")
    steps = F.when(F.col("_off") > 0, more).when((F.col("_off") < 0) & (F.col("_start") > 0), less)
    a = a.withColumn("_reach", reach.cast("long"))
    a = a.withColumn("_step", F.explode_outer(F.when((F.col("_reach") > 0) & (F.col(votes) > 0), steps)))
    sign = F.signum("_off").cast("long")
    rank = F.row_number().over(whole.orderBy((-sign * F.col(votes) / (2 * F.col("_step") + 1)).asc_nulls_last(), *[F.col(k).asc_nulls_last() for k in key], "_step"))
    a = a.withColumn("_won", F.when(F.col("_step").isNotNull() & (rank <= some), sign).otherwise(F.lit(0)))
    names = parties.columns
    out = a.groupBy(*names).agg((F.first("_start") + F.sum("_won")).cast("long").alias("quota"))
    return out


def source_targets(sizes: DataFrame, weights: tuple[float, ...], share: float, most: float) -> DataFrame:
    """(source, source_size, target) from (source, size): ``share`` of all sizes by weight, none over ``most`` times its size.

    Sources in code-point order, null last, take the weights in turn. What a source cannot take is shared anew by
    weight among the others until none is above: the level that all unfilled sources reach, found by one sort.
    """
    by = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    turn = (F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (turn + 1).cast("int"))
    by = by.withColumns({"_weight": weight, "_cap": F.col("source_size") * most})
    order = W.orderBy(F.col("_cap") / F.col("_weight"), F.col("source").asc_nulls_last())
    filled = F.coalesce(F.sum("_cap").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0))
    left = F.sum("_weight").over(order.rowsBetween(0, W.unboundedFollowing))
    by = by.withColumn("_level", (F.sum("source_size").over(W.partitionBy()) * share - filled) / left)
    level = F.max("_level").over(W.partitionBy())  # rises until the sources before it are those filled, then falls
    return by.select("source", "source_size", F.least("_cap", F.col("_weight") * level).alias("target"))


def mix(docs: DataFrame, weights=(3, 1, 2), share: float = 1.5, most: int = 2, block: int = BLOCK, shard_words: int = SHARD_WORDS, seed: str = "mix") -> DataFrame:
    """Per row of ``docs``: doc_id, size, source, source_size, target, taken (words the mix takes, repeats counted).

    Null text has size 0 and is never taken; a null source is a source. Rows that share a doc_id are taken each on
    their own. No row is taken over ``most`` times. Other columns are ignored; reruns agree.
    """
    place = seeded(F.lit(seed), F.col("doc_id"))
    sizes = cut(docs.select("doc_id", "source", word_count("text").alias("size")).withColumn("_place", place))
    targets = source_targets(sizes, tuple(weights), share, most)
    seats = F.round(F.sum("target").over(W.partitionBy()) / block).cast("long")
    quotas = apportion(targets.withColumns({"_all": F.lit(0), "_seats": seats}), ["_all"], ["source"], "target", "_seats")
    shards = F.greatest(F.lit(1), F.least(F.lit(MOST_SHARDS), F.ceil(F.col("source_size") / shard_words))).cast("long")
    quotas = cut(quotas.select(F.col("source").alias("_source"), "source_size", "target", "quota", shards.alias("_shards")))
    rows = sizes.join(quotas, F.col("source").eqNullSafe(F.col("_source")), "inner")
    rows = rows.withColumn("_shard", draw(F.reverse("_place"), F.col("_shards"))).drop("_source", "_shards")
    held = rows.groupBy("source", "_shard").agg(F.sum("size").alias("_held"), F.first("quota").alias("_seats"))
    held = apportion(held, ["source"], ["_shard"], "_held", "_seats")
    want = F.least(F.col("quota") * block, F.col("_held") * most)
    held = held.select(F.col("source").alias("_source"), F.col("_shard").alias("_part"), "_held", want.alias("_want"))
    held = held.withColumn("_passes", F.when(F.col("_held") > 0, F.floor(F.col("_want") / F.col("_held"))).otherwise(F.lit(0)))
    held = held.withColumn("_rest", F.col("_want") - F.col("_passes") * F.col("_held"))
    blocks = F.ceil(F.col("_held") / block)
    held = held.withColumn("_from", draw(seeded(F.lit(seed), F.col("_source"), F.col("_part")), blocks) * block)
    order = W.partitionBy("source", "_shard").orderBy("_place", F.col("doc_id").asc_nulls_last(), "size")
    rows = rows.withColumn("_end", F.sum("size").over(order.rowsBetween(W.unboundedPreceding, 0)))
    both = rows.join(held, F.col("source").eqNullSafe(F.col("_source")) & (F.col("_shard") == F.col("_part")), "inner")
    start, end, run = F.col("_end") - F.col("size"), F.col("_end"), F.col("_from") + F.col("_rest")
    inside = [F.greatest(F.lit(0), F.least(end + k, run) - F.greatest(start + k, F.col("_from"))) for k in (F.lit(0), F.col("_held"))]
    taken = F.col("_passes") * F.col("size") + reduce(lambda x, y: x + y, inside)
    return both.select("doc_id", "size", "source", "source_size", "target", taken.cast("long").alias("taken"))


def copies(size: str = "size", taken: str = "taken") -> Column:
    """How often a mix that deals whole documents repeats one: its share taken, rounded half up."""
    return F.when(F.col(size) > 0, F.floor(F.col(taken) / F.col(size) + 0.5)).otherwise(F.lit(0)).cast("int")
