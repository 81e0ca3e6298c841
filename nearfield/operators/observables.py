"""Energies, electron counts, residuals; work, size and rate measures."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import matrix

# ---- energies and counts


def electronic_energy(d: DataFrame, h: DataFrame) -> float:
    """tr(D H) as a sum over H's entries; D's other entries never matter."""
    return matrix.trace_of_product(d, h)


def electron_count(d: DataFrame, s: DataFrame, occupancy: float = 2.0) -> float:
    return occupancy * matrix.trace_of_product(d, s)


def neutrality_gap(d: DataFrame, s: DataFrame, nuclear_charge: float, occupancy: float = 2.0) -> float:
    """Electrons beyond the nuclei's charge."""
    return electron_count(d, s, occupancy) - nuclear_charge


def sums_by(out: DataFrame, pair: DataFrame) -> DataFrame:
    """One row (energy, electrons), unscaled, from the dense stage's table and the pair (or reduced pair), in one join."""
    times = F.col("twins") if "twins" in pair.columns else F.lit(1.0)
    d = out.where(F.col("row").isNotNull()).select(F.col("col").alias("row"), F.col("row").alias("col"), "d")
    both = d.join(pair, ["row", "col"])
    return both.agg(F.sum(F.col("d") * F.col("h") * times).alias("energy"), F.sum(F.col("d") * F.col("s") * times).alias("electrons"))


def total_energy(electronic: float, double_counting: float = 0.0, ions: float = 0.0, dispersion: float = 0.0) -> dict[str, float]:
    """The parts and their sum; double counting is zero in the stand-in model."""
    return {"electronic": electronic, "double_counting": double_counting, "ions": ions, "dispersion": dispersion, "total": electronic + double_counting + ions + dispersion}


def residuals(d: DataFrame, s: DataFrame, h: DataFrame, tol: float | None = None) -> dict[str, float]:
    """How far D is from D S D = D, from commuting (H D S = S D H), and from being symmetric; and tr(D S).

    Global products: a check for small systems.
    """
    ds = matrix.multiply(d, s, tol)
    idempotency = matrix.norms(matrix.axpy(1.0, matrix.multiply(ds, d, tol), -1.0, d))["max"]
    hds = matrix.multiply(h, ds, tol)
    commutator = matrix.norms(matrix.axpy(1.0, hds, -1.0, matrix.transpose(hds).select("row", "col", "val")))["max"]
    return {"idempotency": idempotency, "commutator": commutator, "asymmetry": matrix.max_asymmetry(d), "trace": matrix.trace(ds)}


def symmetrised(m: DataFrame) -> DataFrame:
    """Half the matrix plus half its transpose."""
    return matrix.axpy(0.5, m, 0.5, matrix.transpose(m).select("row", "col", "val"))


# ---- work


def gemms(k_inverse: int, k_sign: int, with_w: bool = True, iterations_only: bool = False) -> int:
    """Products of one purification: three and two a step of the iterations, and those around them."""
    n = 3 * k_inverse + 2 * k_sign
    return n if iterations_only else n + 3 + 2 * with_w


def flops(gp: DataFrame, k_inverse: int, k_sign: int, with_w: bool = True) -> DataFrame:
    """One row (groups, iteration_flops, all_flops): 2 n^3 for each product; element generation is not counted."""
    cube = F.col("n").cast("decimal(12,0)")
    cube = (cube * cube).cast("decimal(24,0)") * cube
    total = F.sum(cube.cast("decimal(36,0)"))
    of = lambda g: (total.cast("decimal(30,0)") * F.lit(2 * g).cast("decimal(8,0)")).cast("decimal(38,0)")
    return gp.agg(F.count(F.lit(1)).alias("groups"), of(gemms(k_inverse, k_sign, with_w, True)).alias("iteration_flops"), of(gemms(k_inverse, k_sign, with_w)).alias("all_flops"))


def work_metric(gp: DataFrame, power: int) -> float:
    """Sum of n^power over the submatrices."""
    return float(gp.agg(F.coalesce(F.sum(F.pow(F.col("n").cast("double"), power)), F.lit(0.0))).first()[0])


def reduction(before: DataFrame, after: DataFrame) -> dict[str, float]:
    """Factors by which combining lowers the cubic and the quadratic work, and the number of submatrices."""
    return {"cubic": work_metric(before, 3) / work_metric(after, 3), "quadratic": work_metric(before, 2) / work_metric(after, 2), "count": before.count() / max(1, after.count())}


def size_histogram(gp: DataFrame, width: int = 400, by: list[str] | None = None) -> DataFrame:
    """(bin, groups, mean_n) for bins of ``width`` in n, and by other columns."""
    keys = [F.floor(F.col("n") / width).alias("bin"), *(by or [])]
    return gp.groupBy(*keys).agg(F.count(F.lit(1)).alias("groups"), F.avg("n").alias("mean_n"))


def histogram_pivot(before: DataFrame, after: DataFrame, width: int = 400) -> DataFrame:
    """(bin, before, after): numbers of submatrices by size before and after combining."""
    both = before.select("n", F.lit("before").alias("when")).unionByName(after.select("n", F.lit("after").alias("when")))
    return both.groupBy(F.floor(F.col("n") / width).alias("bin")).pivot("when", ["before", "after"]).agg(F.count(F.lit(1))).na.fill(0)


def size_summary(gp: DataFrame) -> DataFrame:
    """One row: groups, mean_n, median_n, largest, distinct sizes (approximate)."""
    return gp.agg(F.count(F.lit(1)).alias("groups"), F.avg("n").alias("mean_n"), F.percentile("n", 0.5).alias("median_n"), F.max("n").alias("largest"), F.approx_count_distinct("n").alias("sizes"))


def rollup_sizes(gp: DataFrame, species_of: DataFrame, width: int = 400, cube: bool = False) -> DataFrame:
    """Numbers and cubic work by species of the group's first member and size bin, with subtotals."""
    g = gp.join(species_of, "group_id").select("species", F.floor(F.col("n") / width).alias("bin"), F.pow(F.col("n").cast("double"), 3).alias("n3"))
    by = g.cube("species", "bin") if cube else g.rollup("species", "bin")
    return by.agg(F.count(F.lit(1)).alias("groups"), F.sum("n3").alias("sum_n3"))


def exponentials(gp: DataFrame, kinds: DataFrame, cost: Column) -> DataFrame:
    """(group_id, exponentials): sum over ordered site pairs of a list of a cost of species columns ``a`` and ``b``.

    Counts of species are taken first, so the pairs of a list are never made.
    """
    long = gp.select("group_id", F.explode("idx").alias("member")).join(kinds.select(F.col("member"), "species"), "member")
    counts = long.groupBy("group_id", "species").agg(F.count(F.lit(1)).alias("m"))
    both = counts.select("group_id", F.col("species").alias("a"), F.col("m").alias("ma")).join(counts.select("group_id", F.col("species").alias("b"), F.col("m").alias("mb")), "group_id")
    return both.groupBy("group_id").agg(F.sum(F.col("ma") * F.col("mb") * cost).alias("exponentials"))


# ---- rates


@dataclass
class StageTimer:
    """Wall-clock seconds of named stages; ``mean`` over repeats."""

    seconds: dict[str, list[float]] = field(default_factory=dict)

    def time(self, name: str, action):
        began = time.perf_counter()
        out = action()
        self.seconds.setdefault(name, []).append(time.perf_counter() - began)
        return out

    def mean(self, name: str, least: int = 1) -> float:
        if len(self.seconds.get(name, [])) < least:
            raise ValueError(f"{name} ran fewer than {least} times")
        return sum(self.seconds[name]) / len(self.seconds[name])


def sustained(total_flops: float, seconds: float) -> float:
    """Floating-point operations a second."""
    return total_flops / seconds


def measured_peak(n: int = 1024, repeats: int = 3) -> float:
    """Operations a second of one large double product on one core's worth of threads here: the peak to compare with."""
    import numpy as np

    a = np.random.default_rng(0).normal(size=(n, n))
    best = float("inf")
    for _ in range(repeats):
        began = time.perf_counter()
        a @ a
        best = min(best, time.perf_counter() - began)
    return 2 * n**3 / best


def peak_fraction(rate: float, peak: float) -> float:
    return rate / peak


def efficiency(runs: DataFrame, mode: str = "strong") -> DataFrame:
    """``runs`` (series, workers, seconds) with parallel efficiency against the fewest workers of a series.

    Strong: first seconds * first workers / (workers * seconds); weak (work grows with workers): first seconds / seconds.
    """
    w = W.partitionBy("series").orderBy("workers")
    first = F.first("seconds").over(w)
    share = F.first("workers").over(w) / F.col("workers") if mode == "strong" else F.lit(1.0)
    return runs.withColumn("efficiency", first * share / F.col("seconds"))


def throughput(atoms: int, columns: int, seconds: float, workers: int = 1) -> dict[str, float]:
    """Atoms and columns a second, and atoms a second for each worker."""
    return {"atoms_per_s": atoms / seconds, "columns_per_s": columns / seconds, "atoms_per_s_worker": atoms / seconds / workers}


def energy_error(energy: float, reference: float, atoms: int) -> dict[str, float]:
    return {"relative": abs(energy - reference) / abs(reference), "per_atom": abs(energy - reference) / atoms}
