"""The paired method with elements generated where they are used: only atoms move, in one exchange.

Atoms are dealt to supercells together with a halo of those within reach of the supercell. A worker finds each
group's list, generates its two submatrices from species and positions, purifies, and emits owned columns.
"""

from __future__ import annotations

import math
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.elements import ElementModel
from ..functions.kernels import Purification, purify
from ..plans.balance import balance, parts_for
from .lattice import Box
from .submatrix import _table

SCHEMA = "group_id long, row long, col long, d double, w double, h double, s double, n long, k_inv int, k_sign int, resid double, gemms int, secs double"


def supercells(a: DataFrame, box: Box, width: float, halo: float) -> DataFrame:
    """(cell, owned, atom_id, species, x, y, z, bf0, group_id): every atom in its supercell and in those it is near to.

    Positions are those of the image that is near. Supercells are at least ``width`` wide where the box allows.
    """
    n = [max(1, int(e // width)) for e in box.edges]
    w = [e / k for e, k in zip(box.edges, n, strict=True)]
    out, far = a, F.lit(0.0)
    cell, own = F.lit(0).cast("long"), F.lit(True)
    for axis, k, size in zip("xyz", n, w, strict=True):
        inside = F.pmod(F.col(axis), F.lit(k * size))
        span = max(1, math.ceil(halo / size))
        out = out.withColumn(axis, inside).withColumn(f"_b{axis}", F.least(F.floor(inside / size), F.lit(k - 1)).cast("long"))
        out = out.withColumn(f"_d{axis}", F.explode(F.sequence(F.lit(-span), F.lit(span))))
        to = F.col(f"_b{axis}") + F.col(f"_d{axis}")
        home = F.pmod(to, F.lit(k)).cast("long")
        place = F.col(axis) - F.floor(to / k) * F.lit(k * size)
        gap = F.greatest(home * size - place, place - (home + 1) * size, F.lit(0.0))
        out = out.withColumns({f"_t{axis}": home, f"_p{axis}": place, f"_g{axis}": gap}).where(F.col(f"_g{axis}") <= halo)
        cell = cell * k + F.col(f"_t{axis}")
        own = own & (F.col(f"_d{axis}") == 0)
        far = far + F.col(f"_g{axis}") * F.col(f"_g{axis}")
    out = out.where(far <= halo * halo)
    return out.select(cell.alias("cell"), own.alias("owned"), "atom_id", "species", *[F.col(f"_p{c}").alias(c) for c in "xyz"], "bf0", "group_id")


#: Cost that a task takes at most of a supercell, in submatrices of an ordinary atom; costlier cells are split.
TASK_COST = 200.0


def split_costly(rows: DataFrame, model: ElementModel, present, task_cost: float = TASK_COST) -> DataFrame:
    """``rows`` with turn, the task of a cell, and leads: whether the row's group is done there.

    An atom's submatrix grows with the cube of its reach and its cost with the cube of that, so a cell of far-reaching
    atoms costs many times an ordinary one. Such cells are done in several turns: each has all atoms of the cell, and
    the groups are dealt to the turns by a hash.
    """
    least = min(model.cutoff(s, s) for s in present)
    reach = F.lit(least)
    for s in present:
        reach = F.when(F.col("species") == s, F.lit(model.cutoff(s, s))).otherwise(reach)
    lead = F.col("owned") & (F.col("atom_id") == F.col("group_id"))
    cost = rows.where("owned").groupBy(F.col("cell").alias("_cell")).agg(F.sum(F.pow(reach / least, 9)).alias("_cost"))
    turns = cost.select("_cell", F.ceil(F.col("_cost") / task_cost).cast("int").alias("_turns")).where("_turns > 1")
    dealt = rows.join(turns, F.col("cell") == F.col("_cell"), "left").withColumn("_turns", F.coalesce("_turns", F.lit(1)))
    dealt = dealt.withColumn("turn", F.explode(F.sequence(F.lit(0), F.col("_turns") - 1)))
    leads = lead & (F.pmod(F.xxhash64("group_id"), F.col("_turns")) == F.col("turn"))
    return dealt.select(*rows.columns, "turn", leads.alias("leads"))


def _purified(g, ids, species, xyz, bf0, mine, model, nbf_of, edges, how, dtype) -> tuple[tuple, tuple]:
    """(entries of the owned columns, metrics) of one group from its sites, of which it owns those that are ``mine``."""
    h, s, at = model.pair(list(species), xyz, edges, dtype)
    functions = np.concatenate([first + np.arange(nbf_of[x]) for first, x in zip(bf0, species, strict=True)])
    own = np.concatenate([np.arange(at[k], at[k + 1]) for k in np.flatnonzero(mine)])
    d, w, done = purify(h, s, how)
    i, j = np.nonzero((h[:, own] != 0) | (s[:, own] != 0))
    entries = (g, functions[i], functions[own][j], [x[:, own][i, j] for x in (d, w, h, s)])
    return entries, (int(g), len(h), done["k_inverse"], done["k_sign"], float(done["residual"]), done["gemms"])


def generate_density(a: DataFrame, box: Box, model: ElementModel, how: Purification, present=("H", "O"), groups: DataFrame | None = None, width: float | None = None, element_dtype: str = "float64") -> DataFrame:
    """The dense stage's table with columns d, w, h, s over basis functions of owned atoms.

    ``groups`` (group_id, member) of atoms share a submatrix; by default each atom has its own. A group belongs to
    the supercell of its least member, so halos are twice as deep then. Atom rows are shuffled, and the cells' costs
    beside them; nothing after it.
    """
    reach = model.longest(present)
    if groups is None:
        rows, halo = a.withColumn("group_id", F.col("atom_id")), reach
    else:
        rows, halo = a.join(groups, F.col("atom_id") == F.col("member")), 2 * reach
    rows = supercells(rows.select("atom_id", "species", "x", "y", "z", "bf0", "group_id"), box, width or 2 * reach, halo)
    rows = split_costly(rows, model, present)
    # tasks are of like work, not of like bytes, so their number is not left to adaptive execution
    cells = math.prod(max(1, int(e // (width or 2 * reach))) for e in box.edges)
    rows = rows.repartition(int(max(4 * a.sparkSession.sparkContext.defaultParallelism, min(2 * cells, 100_000))), "cell", "turn")
    edges = np.array(box.edges)
    nbf_of = {s: v["nbf"] for s, v in model.species.items()}
    dtype = np.dtype(element_dtype)

    def work(table):
        ids, group = table.column("atom_id").to_numpy(), table.column("group_id").to_numpy()
        leads = table.column("leads").to_numpy(zero_copy_only=False).astype(bool)
        species = np.array(table.column("species").to_pylist(), object)
        xyz = np.stack([table.column(c).to_numpy() for c in "xyz"], axis=1)
        bf0 = table.column("bf0").to_numpy()
        reach_of = np.array([model.cutoff(s, s) for s in species])
        found, metrics = [], []
        # a group is done where its least member is owned; its other members may be halo atoms
        order_by, all_groups = np.argsort(group, kind="stable"), np.sort(group)
        for lead in sorted(np.flatnonzero(leads).tolist(), key=lambda r: group[r]):
            began = time.perf_counter()
            g = group[lead]
            members = order_by[np.searchsorted(all_groups, g) : np.searchsorted(all_groups, g, "right")]
            if len(members) > 1:  # of several images of a member, the one nearest to the lead
                order = members[np.argsort(((xyz[members] - xyz[lead]) ** 2).sum(axis=1), kind="stable")]
                members = order[np.unique(ids[order], return_index=True)[1]]
            near = np.zeros(len(ids), bool)
            for m in members:
                r2 = ((xyz - xyz[m]) ** 2).sum(axis=1)
                near |= r2 < np.maximum(reach_of, reach_of[m]) ** 2
            near[members] = True
            take = np.flatnonzero(near)
            take = take[np.unique(ids[take], return_index=True)[1]]
            entries, did = _purified(g, ids[take], species[take], xyz[take], bf0[take], np.isin(ids[take], ids[members]), model, nbf_of, edges, how, dtype)
            found.append(entries)
            metrics.append((*did, time.perf_counter() - began))
        return _table(found, metrics, ["d", "w", "h", "s"]) if metrics else _table([], [], ["d", "w", "h", "s"]).cast(_EMPTY)

    return rows.groupBy("cell", "turn").applyInArrow(work, SCHEMA)


def generate_listed(a: DataFrame, box: Box, model: ElementModel, how: Purification, gp: DataFrame, element_dtype: str = "float64") -> DataFrame:
    """``generate_density`` where the lists of the groups are known: ``gp`` (group_id, idx, own, n) of atoms, n in functions.

    An atom goes to the groups that list it and to no halo, so a row is shuffled for each list entry; parts are of like cost.
    """
    parts = parts_for(gp)
    listed = balance(gp, parts).select("part_id", "group_id", "own", F.explode("idx").alias("_atom"))
    listed = listed.select("part_id", "group_id", "_atom", F.array_contains("own", F.col("_atom")).alias("mine"))
    sites = a.select("atom_id", "species", "x", "y", "z", "bf0")
    rows = listed.join(sites, F.col("_atom") == F.col("atom_id")).drop("_atom").repartition(parts, "part_id")
    edges = np.array(box.edges)
    nbf_of = {s: v["nbf"] for s, v in model.species.items()}
    dtype = np.dtype(element_dtype)

    def work(table):
        table = table.sort_by([("group_id", "ascending"), ("atom_id", "ascending")])
        group, ids, bf0 = (table.column(c).to_numpy() for c in ("group_id", "atom_id", "bf0"))
        mine = table.column("mine").to_numpy(zero_copy_only=False).astype(bool)
        species = np.array(table.column("species").to_pylist(), object)
        xyz = np.stack([table.column(c).to_numpy() for c in "xyz"], axis=1)
        found, metrics = [], []
        for at in np.split(np.arange(len(group)), np.flatnonzero(np.diff(group)) + 1):
            began = time.perf_counter()
            entries, did = _purified(group[at[0]], ids[at], species[at], xyz[at], bf0[at], mine[at], model, nbf_of, edges, how, dtype)
            found.append(entries)
            metrics.append((*did, time.perf_counter() - began))
        return _table(found, metrics, ["d", "w", "h", "s"])

    return rows.groupBy("part_id").applyInArrow(work, SCHEMA)


def atom_lists(a: DataFrame, box: Box, model: ElementModel, present) -> DataFrame:
    """(group_id, idx, own, n): each atom with the atoms within the pair's cutoff and itself, n in basis functions.

    The lists are made where atoms and their halo meet, so no pair of atoms is shuffled.
    """
    reach = model.longest(present)
    rows = supercells(a.select("atom_id", "species", "x", "y", "z", "bf0", F.col("atom_id").alias("group_id")), box, 2 * reach, reach)
    cells = math.prod(max(1, int(e // (2 * reach))) for e in box.edges)
    rows = rows.repartition(int(max(4 * a.sparkSession.sparkContext.defaultParallelism, min(cells, 100_000) // 8)), "cell")
    nbf_of = {s: v["nbf"] for s, v in model.species.items()}

    def work(table):
        ids, owned = table.column("atom_id").to_numpy(), table.column("owned").to_numpy(zero_copy_only=False).astype(bool)
        xyz = np.stack([table.column(c).to_numpy() for c in "xyz"], axis=1)
        species = table.column("species").to_pylist()
        nbf, reach_of = np.array([nbf_of[s] for s in species]), np.array([model.cutoff(s, s) for s in species])
        _, first, one = np.unique(ids, return_index=True, return_inverse=True)
        who, lists = np.flatnonzero(owned), []
        for at in range(0, len(who), 256):
            some = who[at : at + 256]
            r = np.sqrt(((xyz[some, None] - xyz[None]) ** 2).sum(axis=2))
            near = r < np.maximum(reach_of[some, None], reach_of[None])
            near[np.arange(len(some)), some] = True
            lists += [first[np.unique(one[n])] for n in near]  # images of an atom are one
        sizes = [len(x) for x in lists]
        idx = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(ids[np.concatenate([*lists, np.zeros(0, int)]).astype(int)], pa.int64()))
        own = pa.ListArray.from_arrays(pa.array(np.arange(len(who) + 1), pa.int32()), pa.array(ids[who], pa.int64()))
        return pa.table({"group_id": pa.array(ids[who], pa.int64()), "idx": idx, "own": own, "n": pa.array([int(nbf[x].sum()) for x in lists], pa.int64())})

    return rows.select("cell", "owned", "atom_id", "species", "x", "y", "z").groupBy("cell").applyInArrow(work, "group_id long, idx array<long>, own array<long>, n long")


_EMPTY = pa.schema(
    [(c, pa.int64()) for c in ("group_id", "row", "col")] + [(c, pa.float64()) for c in ("d", "w", "h", "s")] + [("n", pa.int64()), ("k_inv", pa.int32()), ("k_sign", pa.int32()), ("resid", pa.float64()), ("gemms", pa.int32()), ("secs", pa.float64())]
)


def energies(out: DataFrame) -> DataFrame:
    """One row (energy, electrons), unscaled: every entry has its elements beside it, so nothing is joined."""
    return out.where(F.col("row").isNotNull()).agg(F.sum(F.col("d") * F.col("h")).alias("energy"), F.sum(F.col("d") * F.col("s")).alias("electrons"))
