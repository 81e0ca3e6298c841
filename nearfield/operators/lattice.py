"""Atoms from the part table, neighbour search by cells, and the pair of matrices as rows."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.elements import COUPLING, EDGE, SPECIES_SCHEMA, ElementModel, species_rows, unit_cell

SITES = 96


@dataclass(frozen=True)
class Box:
    """Whole cells along x, y and z of a periodic lattice."""

    nx: int
    ny: int
    nz: int

    @classmethod
    def of_cells(cls, cells: int) -> Box:
        """As near a cube as a number of cells allows; the surplus is left out."""
        n = max(1, math.floor(round(cells ** (1 / 3), 9)))
        return cls(n, n, max(1, cells // (n * n)))

    @property
    def cells(self) -> int:
        return self.nx * self.ny * self.nz

    @property
    def edges(self) -> tuple[float, float, float]:
        return self.nx * EDGE, self.ny * EDGE, self.nz * EDGE

    def repeated(self, times: int) -> Box:
        return Box(self.nx, self.ny, self.nz * times)


def box_of(part: DataFrame) -> Box:
    """The box that the whole cells of the part table fill."""
    n = part.agg((F.max("p_partkey") + 1).alias("n")).first().n or 0
    return Box.of_cells(max(1, n // SITES))


def _slots(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i, *row) for i, row in enumerate(unit_cell())], "slot int, base string, ux double, uy double, uz double")


def species(spark: SparkSession) -> DataFrame:
    """The table of species; a handful of rows."""
    return spark.createDataFrame(species_rows(), SPECIES_SCHEMA)


def atoms(part: DataFrame, box: Box | None = None, kind: str = "water", times: int = 1) -> DataFrame:
    """(atom_id, species, x, y, z, mass, nbf, bf0, cell_id): part keys laid out on whole cells, ``times`` along z.

    ``kind``: "water", or "mixed", where p_size = 50 makes a far-reaching site X and, in the lower half in z, O sites
    become C for two part types and S for one brand. bf0 numbers the basis functions by atom: cells are equally long
    in water, and in the mixed lattice the offset comes from counts by cell, so no window holds all atoms.
    """
    spark = part.sparkSession
    box = box or box_of(part)
    cell, slot = F.floor(F.col("p_partkey") / SITES).cast("long"), (F.col("p_partkey") % SITES).cast("int")
    a = part.select(cell.alias("cell"), slot.alias("slot"), "p_size", "p_type", "p_brand").where(F.col("cell") < box.cells)
    a = a.join(F.broadcast(_slots(spark)), "slot")
    ix, iy, iz = F.col("cell") % box.nx, F.floor(F.col("cell") / box.nx) % box.ny, F.floor(F.col("cell") / (box.nx * box.ny))
    who: Column = F.col("base")
    if kind == "mixed":
        low = iz * 2 < box.nz
        who = F.when(F.col("p_size") == 50, F.lit("X")).when(low & (who == "O") & F.col("p_type").isin("PROMO", "LARGE"), F.lit("C")).when(low & (who == "O") & (F.col("p_brand") == "Brand#7"), F.lit("S")).otherwise(who)
    copies = F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("copy")
    a = a.select("cell", "slot", who.alias("species"), (F.col("ux") + ix * EDGE).alias("x"), (F.col("uy") + iy * EDGE).alias("y"), (F.col("uz") + iz * EDGE).alias("z"), copies)
    a = a.select((F.col("cell") + F.col("copy") * box.cells).alias("cell_id"), "slot", "species", "x", "y", (F.col("z") + F.col("copy") * box.edges[2]).alias("z"))
    a = a.join(F.broadcast(species(spark).select("species", "nbf", "mass")), "species")
    return number(a.withColumn("atom_id", F.col("cell_id") * SITES + F.col("slot")))


def number(a: DataFrame) -> DataFrame:
    """Add bf0: running number of basis functions by atom_id, from sums by cell and one small running sum over cells."""
    from pyspark.sql import Window as W

    by = a.groupBy("cell_id").agg(F.sum("nbf").alias("n"))
    coarse = F.floor(F.col("cell_id") / 1024)
    blocks = by.groupBy(coarse.alias("block")).agg(F.sum("n").alias("n"))
    blocks = blocks.select("block", F.coalesce(F.sum("n").over(W.orderBy("block").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    by = by.withColumn("block", coarse).join(blocks, "block")
    by = by.select("cell_id", (F.col("before") + F.coalesce(F.sum("n").over(W.partitionBy("block").orderBy("cell_id").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).alias("first"))
    inside = F.coalesce(F.sum("nbf").over(W.partitionBy("cell_id").orderBy("slot").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return a.join(by, "cell_id").select("atom_id", "species", "x", "y", "z", "mass", "nbf", (F.col("first") + inside).cast("long").alias("bf0"), "cell_id")


def spread(a: DataFrame, box: Box, reach: float, keep: list[str]) -> DataFrame:
    """Each atom in every bin of its 3 x 3 x 3 neighbourhood, with the image shift of each: the halo of an equi-join.

    Bins are at least ``reach`` wide; where the box holds fewer than three along an axis, every needed image is made.
    """
    n = [max(1, int(e // reach)) for e in box.edges]
    width = [e / k for e, k in zip(box.edges, n, strict=True)]
    out = a
    for axis, k, w in zip("xyz", n, width, strict=True):
        out = out.withColumn(f"b{axis}", F.floor(F.pmod(F.col(axis), F.lit(k * w)) / w).cast("long"))
        span = max(1, math.ceil(reach / w))
        steps = F.explode(F.sequence(F.lit(-span), F.lit(span)))
        out = out.withColumn("_d", steps)
        to = F.col(f"b{axis}") + F.col("_d")
        out = out.withColumns({f"s{axis}": -F.floor(to / k) * F.lit(k * w), f"t{axis}": F.pmod(to, F.lit(k)).cast("long")}).drop("_d")
    bins = F.array("tx", "ty", "tz")
    shifted = [(F.pmod(F.col(c), F.lit(k * w)) + F.col(f"s{c}")).alias(c) for c, k, w in zip("xyz", n, width, strict=True)]
    return out.select(*keep, *shifted, bins.alias("bin"))


def binned(a: DataFrame, box: Box, reach: float, keep: list[str]) -> DataFrame:
    """Each atom in its own bin; see ``spread``."""
    n = [max(1, int(e // reach)) for e in box.edges]
    inside = [F.pmod(F.col(c), F.lit(e)) for c, e in zip("xyz", box.edges, strict=True)]
    bins = F.array(*[F.floor(p / (e / k)).cast("long") for p, e, k in zip(inside, box.edges, n, strict=True)])
    return a.select(*keep, *[p.alias(c) for p, c in zip(inside, "xyz", strict=True)], bins.alias("bin"))


def neighbours(a: DataFrame, box: Box, reach: float) -> DataFrame:
    """(i, j, dx, dy, dz, r): all ordered pairs nearer than ``reach``, one row for each periodic image; no self pairs.

    An equi-join on bins with the halo on one side: work follows the number of pairs.
    """
    left = binned(a.select(F.col("atom_id").alias("i"), "x", "y", "z"), box, reach, ["i"])
    right = spread(a.select(F.col("atom_id").alias("j"), "x", "y", "z"), box, reach, ["j"])
    right = right.withColumnsRenamed({"x": "x2", "y": "y2", "z": "z2", "bin": "bin2"})
    d = left.join(right, F.col("bin") == F.col("bin2")).select("i", "j", (F.col("x2") - F.col("x")).alias("dx"), (F.col("y2") - F.col("y")).alias("dy"), (F.col("z2") - F.col("z")).alias("dz"))
    r = F.sqrt(F.col("dx") * F.col("dx") + F.col("dy") * F.col("dy") + F.col("dz") * F.col("dz"))
    return d.withColumn("r", r).where((F.col("r") < reach) & (F.col("r") > 1e-9))


def neighbours_nested(a: DataFrame, box: Box, reach: float) -> DataFrame:
    """(i, j, r) by comparing all atoms: the plain form that tests hold ``neighbours`` against."""
    span = [math.ceil(reach / e) + 1 for e in box.edges]
    shift = a.sparkSession.createDataFrame([(i * box.edges[0], j * box.edges[1], k * box.edges[2]) for i in range(-span[0], span[0] + 1) for j in range(-span[1], span[1] + 1) for k in range(-span[2], span[2] + 1)], "sx double, sy double, sz double")
    b = a.select(F.col("atom_id").alias("j"), F.col("x").alias("x2"), F.col("y").alias("y2"), F.col("z").alias("z2")).crossJoin(F.broadcast(shift))
    d = a.select(F.col("atom_id").alias("i"), "x", "y", "z").crossJoin(b)
    r = F.sqrt(F.pow(F.col("x2") + F.col("sx") - F.col("x"), 2) + F.pow(F.col("y2") + F.col("sy") - F.col("y"), 2) + F.pow(F.col("z2") + F.col("sz") - F.col("z"), 2))
    return d.select("i", "j", r.alias("r")).where((F.col("r") < reach) & (F.col("r") > 1e-9))


def site_overlaps(a: DataFrame, box: Box, model: ElementModel, present: list[str]) -> DataFrame:
    """(i, j, v, vh): overlap of two sites summed over images, and the part of it within the Hamiltonian's cutoff."""
    pairs = neighbours(a, box, model.longest(present))
    kind = a.select("atom_id", "species")
    pairs = pairs.join(kind.withColumnsRenamed({"atom_id": "i", "species": "si"}), "i").join(kind.withColumnsRenamed({"atom_id": "j", "species": "sj"}), "j")
    value = F.lit(0.0)
    for p in present:
        for q in present:
            value = F.when((F.col("si") == p) & (F.col("sj") == q), F.expr(model.overlap_sql(p, q))).otherwise(value)
    pairs = pairs.withColumn("v", value).where("v > 0")
    in_h = F.when(F.col("r") < F.lit(model.h_rcut if model.h_rcut is not None else 1e9), F.col("v")).otherwise(0.0)
    return pairs.withColumn("vh", in_h).groupBy("i", "j").agg(F.sum("v").alias("v"), F.sum("vh").alias("vh"))


def matrix_from_atoms(a: DataFrame, box: Box, model: ElementModel, present: list[str] = ("H", "O")) -> DataFrame:
    """The pair as rows (row, col, h, s) over basis functions: on-site levels and identity, couplings from overlaps."""
    present = list(present)
    sp = F.broadcast(species(a.sparkSession).select("species", "level"))
    f = a.select("atom_id", "species", "bf0").join(sp, "species").select("atom_id", "bf0", F.posexplode("level").alias("k", "e"))
    f = f.select("atom_id", (F.col("bf0") + F.col("k")).alias("f"), "k", "e")
    same = f.join(f.withColumnsRenamed({"f": "g", "k": "m", "e": "e2"}), "atom_id")
    on = (F.col("k") == F.col("m")).cast("double")
    # images of a site couple its own functions too
    both = site_overlaps(a, box, model, present)
    self_v = both.where("i = j").select(F.col("i").alias("atom_id"), "v", "vh")
    mean = COUPLING * (F.col("e") + F.col("e2")) / 2
    diag = same.join(self_v, "atom_id", "left").select(F.col("f").alias("row"), F.col("g").alias("col"), (on * F.col("e") + mean * F.coalesce("vh", F.lit(0.0))).alias("h"), (on + F.coalesce("v", F.lit(0.0))).alias("s"))
    off = both.where("i <> j").join(f.withColumnsRenamed({"atom_id": "i", "f": "row"}), "i")
    off = off.join(f.withColumnsRenamed({"atom_id": "j", "f": "col", "k": "m", "e": "e2"}), "j").select("row", "col", (mean * F.col("vh")).alias("h"), F.col("v").alias("s"))
    return diag.where((F.col("h") != 0) | (F.col("s") != 0)).unionByName(off)


def atom_groups(a: DataFrame) -> DataFrame:
    """(group_id, member): the basis functions of each atom as one group."""
    return a.select(F.col("atom_id").alias("group_id"), F.explode(F.expr("sequence(bf0, bf0 + nbf - 1)")).alias("member"))


def neutralise(a: DataFrame, charge: int, ion: str = "X", seed: int = 1) -> DataFrame:
    """Replace so many molecules (three atoms in a row) by an ion at their first atom, in the order of a seeded hash."""
    molecule = F.floor(F.col("atom_id") / 3)
    water = a.where(F.col("species").isin("O", "H")).groupBy(molecule.alias("molecule")).agg(F.count(F.lit(1)).alias("n")).where("n = 3")
    chosen = water.orderBy(F.md5(F.concat_ws("|", F.col("molecule").cast("string"), F.lit(str(seed)))), "molecule").limit(max(0, charge)).select(F.col("molecule").alias("_m"))
    marked = a.withColumn("molecule", molecule).join(chosen, F.col("molecule") == F.col("_m"), "left")
    kept = marked.where(F.col("_m").isNull() | (F.col("atom_id") % 3 == 0))
    kept = kept.withColumn("species", F.when(F.col("_m").isNotNull(), F.lit(ion)).otherwise(F.col("species")))
    sp = F.broadcast(species(a.sparkSession).select("species", F.col("nbf").alias("_nbf"), F.col("mass").alias("_mass")))
    kept = kept.join(sp, "species").select("atom_id", "species", "x", "y", "z", F.col("_mass").alias("mass"), F.col("_nbf").alias("nbf"), "cell_id")
    return number(kept.withColumn("slot", (F.col("atom_id") % SITES).cast("int")))
