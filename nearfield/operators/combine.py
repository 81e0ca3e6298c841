"""Combining submatrices: merge two groups if and only if the cube of their union is below the sum of their cubes.

``combine`` runs rounds of conflict-free merges as DataFrame steps; ``combine_subcells`` merges greedily within
spatial or graph cells in one shuffle, which is the form for very large systems; ``combine_kmeans`` is the earlier
spatial approach, kept to compare with.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..sources.tables import cut, settle

def gain(n_i: Column, n_j: Column, common: Column) -> Column:
    """Cubes saved by merging groups of n_i and n_j rows of which ``common`` are shared; merge if above zero."""
    cube = lambda c: c.cast("double") * c * c
    return cube(n_i) + cube(n_j) - cube(n_i + n_j - common)


def _entries(gp: DataFrame, weights: DataFrame | None) -> DataFrame:
    """(group_id, member, weight) of every list entry."""
    long = gp.select("group_id", F.explode("idx").alias("member"))
    return long.join(weights, "member") if weights is not None else long.withColumn("weight", F.lit(1).cast("long"))


def merge_candidates(gp: DataFrame, weights: DataFrame | None = None, touched: DataFrame | None = None) -> DataFrame:
    """(i, j, n_i, n_j, common, added, gain), i < j: groups of which one's list names a member of the other.

    ``gp``: group_id, idx, own. With ``weights`` (member, weight) sizes are sums of weights, else counts. Shared rows
    are counted by joining list entries of the candidate pairs, so no list is compared twice. ``touched`` (group_id):
    only pairs with one of these groups.
    """
    long = _entries(gp, weights)
    sizes = long.groupBy("group_id").agg(F.sum("weight").cast("long").alias("n"))
    owner = gp.select(F.col("group_id").alias("other"), F.explode("own").alias("member"))
    if touched is None:
        pairs = long.join(owner, "member")
    else:
        mine = touched.select(F.col("group_id").alias("_t"))
        pairs = long.join(mine, F.col("group_id") == F.col("_t"), "left_semi").join(owner, "member")
        pairs = pairs.unionByName(long.join(owner.join(mine, F.col("other") == F.col("_t"), "left_semi"), "member"))
    pairs = pairs.where("group_id <> other")
    pairs = pairs.select(F.least("group_id", "other").alias("i"), F.greatest("group_id", "other").alias("j")).distinct()
    return _counted(pairs, long, sizes)


def _counted(pairs: DataFrame, long: DataFrame, sizes: DataFrame) -> DataFrame:
    """``merge_candidates`` of the pairs (i, j) from list entries and sizes."""
    a = long.select(F.col("group_id").alias("i"), "member", "weight")
    b = long.select(F.col("group_id").alias("j"), "member")
    common = pairs.join(a, "i").join(b, ["j", "member"]).groupBy("i", "j").agg(F.sum("weight").cast("long").alias("common"))
    c = common.join(sizes.select(F.col("group_id").alias("i"), F.col("n").alias("n_i")), "i")
    c = c.join(sizes.select(F.col("group_id").alias("j"), F.col("n").alias("n_j")), "j")
    # the smaller group's new rows decide the order
    added = F.least("n_i", "n_j") - F.col("common")
    return c.select("i", "j", "n_i", "n_j", "common", added.alias("added"), gain(F.col("n_i"), F.col("n_j"), F.col("common")).alias("gain"))


#: Ids whose groups are looked at together, bits of a list's mark, and pairs of marks compared at once.
BLOCK, BITS, COMPARED = 1 << 15, 512, 1 << 16


def _marks(lists: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """A row of bits for each list, set at its members' hashes: a bit that another list's lacks stands for a row it lacks."""
    h = lists.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    bit, out = (h >> np.uint64(64 - (BITS - 1).bit_length())).astype(np.int64), []
    ends = np.concatenate([[0], np.cumsum(sizes)])
    for at in range(0, len(sizes), 4096):
        some = sizes[at : at + 4096]
        on = np.zeros((len(some), BITS), bool)
        on[np.repeat(np.arange(len(some)), some), bit[ends[at] : ends[at + len(some)]]] = True
        out.append(np.packbits(on, axis=1).view(np.uint64))
    return np.concatenate(out) if out else np.zeros((0, BITS // 64), np.uint64)


def _lists(column) -> tuple[np.ndarray, np.ndarray]:
    """(all values, how many each row has) of a column of lists."""
    x = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return x.flatten().to_numpy(), x.value_lengths().to_numpy().astype(np.int64)


def may_pay(gp: DataFrame) -> DataFrame:
    """(i, j), i < j: all pairs of ``merge_candidates`` with a gain, and few others; sizes are counts.

    Lists go once to the block of their ids; what comes there of the groups that own their members is a mark of fixed size.
    Rows that two lists share are at most those of one without what the other's mark lacks, and a pair that would not
    pay with so many is left out; no list is joined with another.
    """
    spark = gp.sparkSession

    def marked(batches):
        for b in batches:
            values, sizes = _lists(b.column("idx"))
            marks = _marks(values, sizes)
            yield pa.RecordBatch.from_arrays([b.column("group_id"), b.column("own"), pa.array(sizes), pa.array([m.tobytes() for m in marks], pa.binary())], ["other", "own", "size", "mark"])

    marks = gp.select("group_id", "own", "idx").mapInArrow(marked, "other long, own array<long>, size long, mark binary")
    marks = marks.select(F.explode("own").alias("member"), "other", "size", "mark")
    parts = max(3 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = gp.select(F.floor(F.col("group_id") / BLOCK).alias("block"), "group_id", "idx").repartition(parts, "block")
    wanted = dealt.select(F.col("block").alias("_block"), F.explode("idx").alias("member")).distinct().join(marks, "member")

    def work(table, sides):
        member, other, size = (sides.column(c).to_numpy() for c in ("member", "other", "size"))
        mark = np.frombuffer(b"".join(sides.column("mark").to_pylist()), np.uint64).reshape(-1, BITS // 64)
        order = np.argsort(member, kind="stable")
        member, other, size, mark = member[order], other[order], size[order], mark[order]
        group = table.column("group_id").to_numpy()
        values, sizes = _lists(table.column("idx"))
        own, at = _marks(values, sizes), np.repeat(np.arange(len(group)), sizes)
        found = [np.zeros((0, 2), np.int64)]
        for k in range(0, len(values), COMPARED):
            x, a = values[k : k + COMPARED], at[k : k + COMPARED]
            # members may have several owners, or none
            first, last = np.searchsorted(member, x), np.searchsorted(member, x, "right")
            many = last - first
            a, b = np.repeat(a, many), np.repeat(first - np.cumsum(many) + many, many) + np.arange(many.sum())
            keep = group[a] != other[b]
            a, b = a[keep], b[keep]
            n, m = sizes[a].astype(float), size[b].astype(float)
            both = np.bitwise_count(own[a] & mark[b]).sum(axis=1)
            lacks = [np.bitwise_count(y).sum(axis=1) - both for y in (own[a], mark[b])]
            common = np.minimum(n - lacks[0], m - lacks[1])
            pays = n**3 + m**3 > (n + m - common) ** 3
            i, j = group[a[pays]], other[b[pays]]
            found.append(np.stack([np.minimum(i, j), np.maximum(i, j)], axis=1))
        pairs = np.unique(np.concatenate(found), axis=0)
        return pa.table({"i": pairs[:, 0], "j": pairs[:, 1]})

    return dealt.groupBy("block").cogroup(wanted.groupBy("_block")).applyInArrow(work, "i long, j long").distinct()


def paying(gp: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """``merge_candidates`` with a gain; where sizes are counts, only pairs that may pay are counted out."""
    if weights is not None:
        return merge_candidates(gp, weights).where("gain > 0")
    pairs = settle(may_pay(gp))
    if pairs.isEmpty():
        return pairs.select("i", "j", *[F.lit(0).cast(kind).alias(name) for name, kind in (("n_i", "long"), ("n_j", "long"), ("common", "long"), ("added", "long"), ("gain", "double"))])
    named = pairs.select(F.explode(F.array("i", "j")).alias("_g")).distinct()
    long = _entries(gp.join(named, F.col("group_id") == F.col("_g"), "left_semi"), None)
    return _counted(pairs, long, long.groupBy("group_id").agg(F.sum("weight").cast("long").alias("n"))).where("gain > 0")


def match(candidates: DataFrame, ties: str = "ids") -> DataFrame:
    """(i, j): pairs that are each other's best by (added, gain, ties), so that no group merges twice in a round.

    ``ties``: "ids" takes the least ids; "hash" a hash of them first, with which a lattice of equal groups, where ids
    would let few pairs agree, needs few rounds.
    """
    order = [F.col("added"), F.desc("gain"), *([F.xxhash64("i", "j")] if ties == "hash" else []), F.col("i"), F.col("j")]
    both = candidates.select("*", F.col("i").alias("end")).union(candidates.select("*", F.col("j").alias("end")))
    best = both.withColumn("_k", F.row_number().over(W.partitionBy("end").orderBy(*order))).where("_k = 1")
    return best.groupBy("i", "j").agg(F.count(F.lit(1)).alias("_both")).where("_both = 2").select("i", "j")


def with_sizes(gp: DataFrame, weights: DataFrame | None) -> DataFrame:
    """(group_id, idx, own, n), n the number of rows or the sum of their weights.

    Lists are not broadcast: Spark's estimate takes lists that were exploded from a small table for as small as that.
    """
    plain = gp.select("group_id", "idx", "own")
    if weights is None:
        return plain.withColumn("n", F.size("idx").cast("long"))
    n = _entries(plain, weights).groupBy(F.col("group_id").alias("_g")).agg(F.sum("weight").cast("long").alias("n"))
    return plain.hint("merge").join(n, F.col("group_id") == F.col("_g")).drop("_g")


def apply_merges(gp: DataFrame, pairs: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """``gp`` with each pair as one group of the smaller id, by the exact union of rows."""
    to = pairs.select(F.col("j").alias("_from"), F.col("i").alias("_to"))
    moved = gp.join(to, F.col("group_id") == F.col("_from"), "left").withColumn("group_id", F.coalesce("_to", "group_id"))
    g = moved.groupBy("group_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("idx")))).alias("idx"), F.array_sort(F.flatten(F.collect_list("own"))).alias("own"))
    return with_sizes(g, weights)


def join_equal(gp: DataFrame, *keys: str) -> tuple[DataFrame, int]:
    """((keys..., group_id, idx, own), merges): groups of equal lists as one of the smallest id, within equal ``keys``.

    Such a merge adds no row and always pays. Lists are known by a hash of 128 bits, so that what is shuffled is a row for
    each group and, from each task, one of each different list; where no list is there twice ``gp`` stays as it is. Groups
    that own a row outside their list are no candidates of their likes, and stay too.
    """
    inside = F.when(F.size("own") == 1, F.array_contains("idx", F.get("own", F.lit(0)))).otherwise(F.size(F.array_except("own", "idx")) == 0)
    alone = F.when(~inside, F.col("group_id"))
    hashed = [F.coalesce(alone, F.xxhash64("idx")).alias("_a"), F.coalesce(alone, F.xxhash64(F.lit("second"), "idx")).alias("_b"), inside.alias("_in")]
    key = [*keys, "_a", "_b", "_in"]
    own = F.array_sort(F.flatten(F.collect_list("own"))).alias("own")
    alike = settle(gp.select(*keys, "group_id", "own", *hashed).groupBy(*key).agg(F.min("group_id").alias("group_id"), own, F.count(F.lit(1)).alias("_n")))
    merges = alike.agg(F.coalesce(F.sum(F.col("_n") - 1), F.lit(0))).first()[0]
    joined = gp.select(*keys, *hashed, "idx").distinct().hint("merge").join(alike, key) if merges else gp
    return joined.select(*keys, "group_id", "idx", "own"), merges


def combine(gp: DataFrame, weights: DataFrame | None = None, growth: float = 1.6, most_rounds: int | None = None) -> tuple[DataFrame, list[tuple[int, int]]]:
    """(combined gp, [(bound, merges) of each round]): rounds over a rising bound on the rows that a merge may add.

    Groups of equal lists are joined in a round before the others, all at once; only different lists are stored or
    exploded. ``gp`` is read up to three times: one that is dear to make is to be cut before.
    Within a bound rounds repeat until no merge is left; the bound then grows by ``growth`` to the next at which one
    is. Ends when no pair of groups has a gain: there is no target number of clusters. Every round merges at least
    the best pair, so it ends; ``most_rounds`` raises beyond so many. Only pairs with a group that a round merged are
    looked at again. Ties are broken by ids, so the result does not depend on the partitioning. With ``weights``
    sizes, and n of the result, are sums of weights. Each round is cut from its lineage.
    """
    joined, merges = join_equal(gp)
    done: list[tuple[int, int]] = [(0, merges)] if merges else []
    bound = 0
    gp = settle(with_sizes(settle(joined) if merges else gp, weights))
    c = settle(paying(gp, weights))
    while (least := c.agg(F.min("added")).first()[0]) is not None:
        if most_rounds is not None and len(done) >= most_rounds:
            raise RuntimeError(f"{most_rounds} rounds did not end the merging")
        while bound < least:
            bound = int(bound * growth) + 1
        pairs = settle(match(c.where(F.col("added") <= bound), "hash"))
        done.append((bound, pairs.count()))
        gp = settle(apply_merges(gp, pairs, weights))
        gone = pairs.select(F.explode(F.array("i", "j")).alias("_e"))
        left = c.join(gone, F.col("i") == F.col("_e"), "left_anti").join(gone, F.col("j") == F.col("_e"), "left_anti")
        anew = merge_candidates(gp, weights, pairs.select(F.col("i").alias("group_id"))).where("gain > 0")
        c = settle(left.unionByName(anew))
    return gp, done


def groups_of(gp: DataFrame) -> DataFrame:
    """(group_id, member) of a group pattern."""
    return gp.select("group_id", F.explode("own").alias("member"))


# ---- greedy within cells


def greedy(lists: dict[int, set[int]], own: dict[int, list[int]], weight=None, fixed: frozenset[int] = frozenset()) -> dict[int, list[int]]:
    """group id -> merged groups' ids, by plain greedy: least added rows first, then largest gain, then ids.

    Candidates of a group are the groups that own a row of its list. ``fixed`` groups merge with none. A heap holds
    candidate merges; stale ones are recomputed when they come up.
    """
    size = (lambda s: sum(weight[x] for x in s)) if weight else len
    lists = {g: set(s) for g, s in lists.items()}
    owner = {m: g for g, ms in own.items() for m in ms}
    members = {g: [g] for g in lists}
    n = {g: size(s) for g, s in lists.items()}
    stamp = dict.fromkeys(lists, 0)
    heap: list[tuple] = []

    def push(i: int, j: int) -> None:
        i, j = min(i, j), max(i, j)
        common = size(lists[i] & lists[j])
        won = n[i] ** 3 + n[j] ** 3 - (n[i] + n[j] - common) ** 3
        if won > 0:
            heapq.heappush(heap, (min(n[i], n[j]) - common, -won, i, j, stamp[i], stamp[j]))

    def near(i: int) -> set[int]:
        return {g for x in lists[i] if (g := owner.get(x)) is not None and g != i and g not in fixed}

    for i in sorted(lists):
        if i not in fixed:
            for j in near(i):
                if i < j or i not in near(j):
                    push(i, j)
    while heap:
        _, _, i, j, a, b = heapq.heappop(heap)
        if stamp.get(i) != a or stamp.get(j) != b:
            continue
        lists[i] |= lists.pop(j)
        members[i] += members.pop(j)
        n[i] = size(lists[i])
        del n[j], stamp[j]
        for m in own[j]:
            owner[m] = i
        own[i] = own[i] + own.pop(j)
        stamp[i] += 1
        for k in near(i):
            push(i, k)
    return members


def combine_subcells(gp: DataFrame, cells: DataFrame | Column, weights: DataFrame | None = None, border: str = "second_pass") -> DataFrame:
    """Combined gp: greedy within each cell (group_id, cell), one task a cell at most, one shuffle of different lists.

    ``cells`` may be a column of ``gp`` instead, which spares a join. Equal lists of a cell come to its task once.
    With ``weights`` (member, weight) sizes, and n of the result, are sums of weights.

    ``border``: "ignore" leaves it there; "second_pass" then merges again among clusters of whose lists a row is
    owned in another cell, with all others unchanged, in cells made of neighbouring cells.
    """
    placed = gp.withColumn("cell", cells) if isinstance(cells, Column) else gp.join(cells, "group_id")
    owner = placed.select(F.explode("own").alias("member"), F.col("cell").alias("owner_cell"))
    first = cut(_greedy_by(placed, weights))
    if border == "ignore":
        return first.drop("cell")
    reach = first.select("group_id", "cell", F.explode("idx").alias("member")).join(owner, "member")
    touching = reach.where("cell <> owner_cell").groupBy("group_id").agg(F.min(F.least("cell", "owner_cell")).alias("_to")).withColumnRenamed("group_id", "_id")
    marked = first.join(touching, F.col("group_id") == F.col("_id"), "left")
    marked = cut(marked)
    inner = marked.where(F.col("_to").isNull()).select("group_id", "idx", "own", "n")
    outer = marked.where(F.col("_to").isNotNull()).select("group_id", "idx", "own", "n", F.col("_to").alias("cell"))
    return inner.unionByName(_greedy_by(outer, weights).drop("cell"))


def _greedy_by(gp: DataFrame, weights: DataFrame | None) -> DataFrame:
    rows = settle(join_equal(gp.withColumn("cell", F.col("cell").cast("long")), "cell")[0])

    def run(table, weight):
        lists = dict(zip(table.column("group_id").to_pylist(), map(set, table.column("idx").to_pylist()), strict=True))
        own = dict(zip(table.column("group_id").to_pylist(), table.column("own").to_pylist(), strict=True))
        done = greedy(lists, dict(own), weight)
        cell = table.column("cell")[0].as_py()
        out = [(g, cell, sorted(set().union(*(lists[m] for m in ms))), sorted(x for m in ms for x in own[m])) for g, ms in sorted(done.items())]
        g, c, i, o = zip(*out, strict=True)
        long = pa.list_(pa.int64())
        return pa.table({"group_id": pa.array(g, pa.int64()), "cell": pa.array(c, pa.int64()), "idx": pa.array(i, long), "own": pa.array(o, long), "n": pa.array([sum(weight[m] for m in x) if weight else len(x) for x in i], pa.int64())})

    def counted(table):
        return run(table, None)

    def weighed(table, w):
        return run(table, dict(zip(w.column("member").to_pylist(), w.column("weight").to_pylist(), strict=True))) if table.num_rows else none

    out = "group_id long, cell long, idx array<long>, own array<long>, n long"
    if weights is None:
        return rows.groupBy("cell").applyInArrow(counted, out)
    long = pa.list_(pa.int64())
    none = pa.schema([("group_id", pa.int64()), ("cell", pa.int64()), ("idx", long), ("own", long), ("n", pa.int64())]).empty_table()
    # a weight comes to a cell once, however many of its lists name the member
    of = rows.select(F.col("cell").alias("_cell"), F.explode("idx").alias("member")).distinct().join(weights.select("member", F.col("weight").cast("long").alias("weight")), "member")
    return rows.groupBy("cell").cogroup(of.groupBy("_cell")).applyInArrow(weighed, out)


def nearest_centre(a: DataFrame, centres: DataFrame, width: float) -> DataFrame:
    """``a`` (x, y, z, ...) with c, the nearest of ``centres`` (c, cx, cy, cz); ties to the smaller c.

    Centres lie in bins of ``width`` and are joined with the atoms of the 27 bins around: a centre nearer than the width
    is among them. Atoms without one so near are looked at again with bins twice as wide.
    """
    names, left, found = a.columns, a, []
    spots = centres.agg(*[f(c) for c in ("cx", "cy", "cz") for f in (F.min, F.max)]).first()
    while True:
        bins = [F.floor(F.col(f"c{c}") / width).cast("long") for c in "xyz"]
        near = centres
        for axis, at in zip("xyz", bins, strict=True):
            near = near.withColumn(f"b{axis}", F.explode(F.sequence(at - 1, at + 1)))
        own = left.withColumns({f"a{c}": F.floor(F.col(c) / width).cast("long") for c in "xyz"})
        both = own.join(near, [F.col(f"a{c}") == F.col(f"b{c}") for c in "xyz"], "left")
        d = F.round(F.pow(F.col("cx") - F.col("x"), 2) + F.pow(F.col("cy") - F.col("y"), 2) + F.pow(F.col("cz") - F.col("z"), 2), 9)
        best = both.groupBy(*names).agg(F.min(F.when(F.col("c").isNotNull(), F.struct(d.alias("d"), F.col("c").alias("c")))).alias("_best"))
        best = settle(best)
        sure = F.coalesce(F.col("_best.d") < width * width, F.lit(False))
        found.append(best.where(sure).select(*names, F.col("_best.c").alias("c")))
        left = best.where(~sure).select(*names)
        if left.isEmpty():
            break
        extent = left.agg(*[f(c) for c in "xyz" for f in (F.min, F.max)]).first()
        span = max(max(extent[i + 1], spots[i + 1]) - min(extent[i], spots[i]) for i in (0, 2, 4))
        if width > 2 * span + 1:
            raise ValueError("a position is not a number")
        width *= 2
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return out


def combine_kmeans(atoms: DataFrame, k: int, iterations: int = 10) -> DataFrame:
    """(group_id, member) by k-means of positions: the spatial clustering that merging replaces.

    Centres start at every (count / k)-th atom in id order. They are a table like the atoms: nothing is gathered.
    """
    a = atoms.select("atom_id", "x", "y", "z")
    n, *ends = a.agg(F.count(F.lit(1)), *[f(c) for c in "xyz" for f in (F.min, F.max)]).first()
    step = max(1, n // k)
    volume = (ends[1] - ends[0] + 1) * (ends[3] - ends[2] + 1) * (ends[5] - ends[4] + 1)
    width = 1.5 * (volume / k) ** (1 / 3)
    start = a.where((F.col("atom_id") % step == 0) & (F.col("atom_id") < step * k))
    centres = start.select((F.col("atom_id") / step + 1).cast("long").alias("c"), F.col("x").alias("cx"), F.col("y").alias("cy"), F.col("z").alias("cz"))
    for turn in range(iterations):
        own = nearest_centre(a, settle(centres), width)
        if turn < iterations - 1:
            centres = own.groupBy("c").agg(F.avg("x").alias("cx"), F.avg("y").alias("cy"), F.avg("z").alias("cz"))
    least = own.groupBy("c").agg(F.min("atom_id").alias("group_id"))
    return own.join(least, "c").select("group_id", F.col("atom_id").alias("member"))


# ---- keeping a merge over time


def still_valid(gp: DataFrame, p: DataFrame) -> DataFrame:
    """Groups of ``gp`` with ``covers``: whether its list still holds all rows of the pattern (row, col) of its columns."""
    have = gp.select("group_id", F.explode("own").alias("col"), "idx").join(p, "col")
    missed = have.groupBy("group_id").agg(F.max((~F.array_contains("idx", F.col("row"))).cast("int")).alias("_missed"))
    return gp.join(missed, "group_id", "left").withColumn("covers", F.coalesce("_missed", F.lit(0)) == 0).drop("_missed")


def write_groups(gp: DataFrame, path: str, step: int) -> None:
    """Keep a merge as a table with the step that made it, for many steps of dynamics."""
    gp.select("group_id", "idx", "own", "n", F.lit(step).cast("long").alias("step_made")).write.mode("overwrite").parquet(path)


def read_groups(spark, path: str) -> DataFrame:
    """A kept merge: group_id, idx, own, n, step_made."""
    return spark.read.schema("group_id long, idx array<long>, own array<long>, n long, step_made long").parquet(path)


def refresh(gp: DataFrame, p: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """A group pattern for a changed pattern: groups that no longer cover it fall into their columns and are combined anew.

    Groups that still cover theirs keep their members; their lists are kept too. With ``weights`` n is a sum of weights.
    """
    from .patterns import group_pattern

    marked = cut(still_valid(gp, p))
    kept = with_sizes(marked.where("covers"), weights)
    loose = marked.where(~F.col("covers")).select(F.explode("own").alias("member")).select(F.col("member").alias("group_id"), "member")
    anew, _ = combine(settle(group_pattern(p, loose)), weights)
    return kept.unionByName(anew.select("group_id", "idx", "own", "n"))
