"""Noise-compensated dynamics: forces, noise statistics, the friction they imply, thermostat and steps."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.elements import COUPLING, ElementModel
from ..functions.kernels import Purification
from ..sources.tables import cut, settle
from .generate import energies, generate_density
from .lattice import Box, neighbours, species

# ---- forces


def forces(density: DataFrame, a: DataFrame, box: Box, model: ElementModel, present=("H", "O"), charges: float = 0.0) -> DataFrame:
    """(atom_id, fx, fy, fz) from D and W rows (row, col, d, w): minus the derivative of tr(D H), basis moving with atoms.

    Blocks of D and W are contracted to one number for each atom pair; each image of the pair then pulls along its
    distance. ``charges`` scales a Coulomb-like pair repulsion of nuclei, screened like the overlaps.
    """
    sp = F.broadcast(species(a.sparkSession).select("species", "level", "charge"))
    fn = a.select("atom_id", "species", "bf0").join(sp, "species").select("atom_id", "bf0", F.posexplode("level").alias("k", "e"))
    fn = fn.select((F.col("bf0") + F.col("k")).alias("f"), "atom_id", "e")
    rows = density.where(F.col("row").isNotNull()).select("row", "col", "d", "w")
    rows = rows.join(fn.withColumnsRenamed({"f": "row", "atom_id": "i", "e": "ei"}), "row").join(fn.withColumnsRenamed({"f": "col", "atom_id": "j", "e": "ej"}), "col")
    pull = F.col("d") * COUPLING * (F.col("ei") + F.col("ej")) / 2 - F.col("w")
    g = rows.where("i <> j").groupBy("i", "j").agg(F.sum(pull).alias("g"))
    pairs = neighbours(a, box, model.longest(present)).join(g, ["i", "j"])
    kind = a.select("atom_id", "species").join(sp.select("species", "charge"), "species")
    pairs = pairs.join(kind.withColumnsRenamed({"atom_id": "i", "species": "si", "charge": "qi"}), "i").join(kind.withColumnsRenamed({"atom_id": "j", "species": "sj", "charge": "qj"}), "j")
    slope: Column = F.lit(0.0)
    for p in present:
        for q in present:
            amp, width, rc = model.shape(p, q)
            u = 1 - F.pow(F.col("r") / rc, 2)
            v = F.when(F.col("r") < rc, amp * F.exp(-F.pow(F.col("r") / width, 2)) * u * (-2 * F.col("r") / width**2 * u - 4 * F.col("r") / rc**2)).otherwise(0.0)
            slope = F.when((F.col("si") == p) & (F.col("sj") == q), v).otherwise(slope)
    # ordered pairs: each end sees half of the pair's two mirror blocks, so i feels twice its own row's share
    strength = 2 * F.col("g") * slope - charges * F.col("qi") * F.col("qj") * F.exp(-F.col("r")) * (1 + F.col("r")) / F.pow(F.col("r"), 2)
    out = pairs.groupBy(F.col("i").alias("atom_id")).agg(*[F.sum(strength * F.col(f"d{c}") / F.col("r")).alias(f"f{c}") for c in "xyz"])
    return a.select(F.col("atom_id").alias("_a")).join(out, F.col("_a") == F.col("atom_id"), "left").select(F.col("_a").alias("atom_id"), *[F.coalesce(f"f{c}", F.lit(0.0)).alias(f"f{c}") for c in "xyz"])


def ion_energy(a: DataFrame, box: Box, reach: float, charges: float) -> float:
    """Screened pair repulsion of the nuclei, charges * q q exp(-r) / r, each pair once."""
    kind = a.select("atom_id", "species").join(F.broadcast(species(a.sparkSession).select("species", "charge")), "species")
    p = neighbours(a, box, reach).join(kind.withColumnsRenamed({"atom_id": "i", "charge": "qi"}).drop("species"), "i").join(kind.withColumnsRenamed({"atom_id": "j", "charge": "qj"}).drop("species"), "j")
    return p.agg(F.coalesce(F.sum(F.col("qi") * F.col("qj") * F.exp(-F.col("r")) / F.col("r")), F.lit(0.0))).first()[0] * charges / 2


#: Waves of a direct sum at most, layers of waves that a task has, and complex values of its sums along y at a time.
MOST_WAVES, LAYERS, LINE_VALUES = 1_000_000_000, 4, 2_000_000


def ewald_energy(charged: DataFrame, box: Box, alpha: float = 0.6, reach: float | None = None, kmax: int | None = 6) -> float:
    """Coulomb energy of (atom_id, x, y, z, q) in a periodic neutral box: direct real-space pairs, structure factors, self term.

    With ``kmax`` None the waves are all those of a weight above 1e-9, whose number grows with the box: a reference for
    ``mesh_ewald_energy``. A task has some layers of waves along z and all charges. It sums along z for charges of equal x
    and y, then along y for those of equal x, then along x, so a lattice costs far less than waves times charges; no list
    of waves is made. Over ``MOST_WAVES`` it refuses.
    """
    most = [kmax if kmax is not None else math.ceil(9 * alpha * e / (2 * math.pi)) for e in box.edges]
    if math.prod(2 * m + 1 for m in most) > MOST_WAVES:
        raise ValueError("too many waves for the direct sum: use the mesh")
    least, (mx, my, mz) = 1e-12 if kmax is not None else 1e-9, most
    gx, gy, gz = (2 * math.pi / e * np.arange(-m, m + 1) for e, m in zip(box.edges, most, strict=True))

    def layers(t: pa.Table) -> pa.Table:
        first = t.column("layer")[0].as_py() * LAYERS
        k = np.arange(first, min(first + LAYERS, mz + 1))  # of k and -k one is enough
        x, y, z, q = (t.column(c).to_numpy() for c in "xyzq")
        order = np.lexsort((y, x))
        x, y, z, q = x[order], y[order], z[order], q[order]
        spot = np.flatnonzero(np.append(True, (x[1:] != x[:-1]) | (y[1:] != y[:-1])))
        along_z = np.concatenate([np.add.reduceat(q * np.exp(1j * g * z), spot)[:, None] for g in gz[mz + k]], axis=1)
        x, y = x[spot], y[spot]
        line = np.flatnonzero(np.append(True, x[1:] != x[:-1]))
        ends = np.append(line[1:], len(x))
        sums, step = np.zeros((len(gx), len(gy) * len(k)), complex), max(1, LINE_VALUES // (len(gy) * len(k)))
        for at in range(0, len(line), step):
            pairs = list(zip(line[at : at + step], ends[at : at + step], strict=True))
            along_y = np.stack([(np.exp(1j * np.outer(gy, y[a:b])) @ along_z[a:b]).ravel() for a, b in pairs])
            sums += np.exp(1j * np.outer(gx, x[line[at : at + step]])) @ along_y
        k2 = (gx * gx)[:, None, None] + (gy * gy)[:, None] + gz[mz + k] ** 2
        weight = np.exp(-k2 / (4 * alpha * alpha)) / np.where(k2 > 0, k2, np.inf)
        weight[weight <= least] = 0.0
        weight = weight * np.where(k == 0, 0.5, 1.0)
        return pa.table({"e": [float((weight * np.abs(sums.reshape(k2.shape)) ** 2).sum())]})

    dealt = charged.select(*[F.col(c).cast("double").alias(c) for c in "xyzq"], F.explode(F.sequence(F.lit(0), F.lit(mz // LAYERS))).alias("layer"))
    tasks = mz // LAYERS + 1
    found = dealt.repartition(tasks, "layer").groupBy("layer").applyInArrow(layers, "e double").agg(F.coalesce(F.sum("e"), F.lit(0.0))).first()[0]
    waves_e = found * 4 * math.pi / math.prod(box.edges)
    return waves_e + _ewald_near(charged, box, alpha, reach or 3.6 / alpha)


def _ewald_near(charged: DataFrame, box: Box, alpha: float, reach: float) -> float:
    """The real-space pairs less what each charge does to itself."""
    q = charged.select("atom_id", "q")
    p = neighbours(charged, box, reach).join(q.withColumnsRenamed({"atom_id": "i", "q": "qi"}), "i").join(q.withColumnsRenamed({"atom_id": "j", "q": "qj"}), "j")
    # erfc by a rational form good to 1.2e-7 (a published approximation)
    x = F.col("r") * alpha
    t = 1 / (1 + 0.5 * x)
    poly = F.lit(0.17087277)
    for c in (-0.82215223, 1.48851587, -1.13520398, 0.27886807, -0.18628806, 0.09678418, 0.37409196, 1.00002368, -1.26551223):
        poly = poly * t + c
    erfc = t * F.exp(-x * x + poly)
    real = p.agg(F.coalesce(F.sum(F.col("qi") * F.col("qj") * erfc / F.col("r")), F.lit(0.0))).first()[0] / 2
    return real - charged.agg(F.coalesce(F.sum(F.col("q") * F.col("q")), F.lit(0.0))).first()[0] * alpha / math.sqrt(math.pi)


def _spline(u: Column) -> Column:
    """The cardinal spline of fifth order, by truncated powers; zero outside 0 to 5."""
    out = F.lit(0.0)
    for k in range(5):
        out = out + (-1) ** k * math.comb(5, k) * F.pow(F.greatest(u - k, F.lit(0.0)), 4) / 24
    return out


def _spline_factor(n: int) -> np.ndarray:
    """What the splines take from each wave along an axis of n points: one over the squared size of their transform."""
    at = [sum((-1) ** j * math.comb(5, j) * max(k - j, 0) ** 4 for j in range(5)) / 24 for k in range(1, 5)]
    waves = np.arange(n)
    total = sum(v * np.exp(2j * np.pi * waves * k / n) for k, v in enumerate(at))
    return 1 / np.abs(total) ** 2


def mesh_ewald_energy(charged: DataFrame, box: Box, alpha: float = 0.6, reach: float | None = None, spacing: float = 0.5) -> float:
    """``ewald_energy`` with its waves on a mesh: charges spread by splines of fifth order, then Fourier transforms.

    Charges of a mesh point are summed before they are shuffled. The transform runs over slabs: one task holds a plane
    of the mesh (first y and z, then x), never all of it. Axes have odd numbers of points at most ``spacing`` apart.
    """
    edges = box.edges
    points = [int(math.ceil(e / spacing)) | 1 for e in edges]
    nx, ny, nz = points
    spots = charged.select("q", *[(F.pmod(F.col(c), F.lit(e)) / e * n).alias(f"u{c}") for c, e, n in zip("xyz", edges, points, strict=True)])
    for c, n in zip("xyz", points, strict=True):
        spots = spots.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(4))))
        whole = F.floor(f"u{c}")
        spots = spots.withColumns({f"g{c}": F.pmod(whole - F.col("j"), F.lit(n)).cast("long"), "q": F.col("q") * _spline(F.col(f"u{c}") - whole + F.col("j"))}).drop("j")
    mesh = spots.groupBy("gx", "gy", "gz").agg(F.sum("q").alias("q"))

    def plane(t: pa.Table) -> pa.Table:
        a = np.zeros((ny, nz))
        a[t.column("gy").to_numpy(), t.column("gz").to_numpy()] = t.column("q").to_numpy()
        f = np.fft.fft2(a)
        y, z = np.divmod(np.arange(ny * nz), nz)
        return pa.table({"gx": np.full(ny * nz, t.column("gx")[0].as_py()), "ky": y, "kz": z, "re": f.real.ravel(), "im": f.imag.ravel()})

    factors = [_spline_factor(n) for n in points]
    waves = [2 * np.pi * np.where(np.arange(n) <= n // 2, np.arange(n), np.arange(n) - n) / e for n, e in zip(points, edges, strict=True)]

    def across(t: pa.Table) -> pa.Table:
        a, ky = np.zeros((nx, nz), complex), t.column("ky")[0].as_py()
        a[t.column("gx").to_numpy(), t.column("kz").to_numpy()] = t.column("re").to_numpy() + 1j * t.column("im").to_numpy()
        f = np.abs(np.fft.fft(a, axis=0)) ** 2
        k2 = waves[0][:, None] ** 2 + waves[1][ky] ** 2 + waves[2][None] ** 2
        weight = np.where(k2 > 0, np.exp(-k2 / (4 * alpha * alpha)) / np.where(k2 > 0, k2, 1), 0)
        return pa.table({"e": [float((f * weight * factors[0][:, None] * factors[1][ky] * factors[2][None]).sum())]})

    half = mesh.groupBy("gx").applyInArrow(plane, "gx long, ky long, kz long, re double, im double")
    found = half.groupBy("ky").applyInArrow(across, "e double").agg(F.coalesce(F.sum("e"), F.lit(0.0))).first()[0]
    return _ewald_near(charged, box, alpha, reach or 3.6 / alpha) + found * 2 * math.pi / math.prod(edges)


def pair_forces(a: DataFrame, box: Box, reach: float, repulsion: float = 1.0, attraction: float = 8.0, least: float = 0.0) -> DataFrame:
    """(atom_id, fx, fy, fz) of a classical force field: repulsion / r^12 - attraction / r^6 between bodies from ``least`` to ``reach``.

    A shorter reach, a coarser format or a larger time step makes a noise of these forces, which the same friction
    compensates as that of electronic forces.
    """
    p = neighbours(a, box, reach).where(F.col("r") > least)
    slope = -12 * repulsion / F.pow("r", 13) + 6 * attraction / F.pow("r", 7)
    out = p.groupBy(F.col("i").alias("_i")).agg(*[F.sum(slope * F.col(f"d{c}") / F.col("r")).alias(f"f{c}") for c in "xyz"])
    return a.select("atom_id").join(out, F.col("atom_id") == F.col("_i"), "left").select("atom_id", *[F.coalesce(f"f{c}", F.lit(0.0)).alias(f"f{c}") for c in "xyz"])


def dispersion(a: DataFrame, box: Box, reach: float, c6: float = 1.0, r0: float = 2.5) -> float:
    """Rationally damped pair attraction: sum of -c6 / (r^6 + r0^6), each pair once."""
    p = neighbours(a, box, reach)
    return p.agg(F.coalesce(F.sum(-c6 / (F.pow("r", 6) + r0**6)), F.lit(0.0))).first()[0] / 2


# ---- noise


def force_noise(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    """(step, atom_id, nx, ny, nz): what an approximation adds to each force."""
    b = exact.select("step", "atom_id", *[F.col(f"f{c}").alias(f"e{c}") for c in "xyz"])
    return approximate.join(b, ["step", "atom_id"]).select("step", "atom_id", *[(F.col(f"f{c}") - F.col(f"e{c}")).alias(f"n{c}") for c in "xyz"])


def centred(series: DataFrame) -> DataFrame:
    """(id, t, v) with each id's mean taken off."""
    return series.select("id", "t", (F.col("v") - F.avg("v").over(W.partitionBy("id"))).alias("v"))


def noise_report(series: DataFrame, max_lag: int = 5) -> DataFrame:
    """(lag, cov, corr, n, z) of series (id, t, v), t ordering each id: white noise has |z| small at every lag above 0.

    All lags come from one window pass over each id. z is corr times the root of n; ``mean`` of the series is in lag 0.
    """
    order = W.partitionBy("id").orderBy("t")
    lags = [F.struct(F.lit(k).alias("lag"), (F.col("v") * (F.lag("v", k).over(order) if k else F.col("v"))).alias("p")) for k in range(max_lag + 1)]
    each = series.select(F.array(*lags).alias("lags"), "v")
    long = each.select(F.explode("lags").alias("x"), "v").select("x.lag", "x.p", "v").where("p is not null")
    c = long.groupBy("lag").agg(F.avg("p").alias("cov"), F.count(F.lit(1)).alias("n"), F.avg("v").alias("mean"))
    zero = F.max(F.when(F.col("lag") == 0, F.col("cov"))).over(W.partitionBy())
    corr = F.col("cov") / zero
    return c.select("lag", "cov", corr.alias("corr"), "n", (corr * F.sqrt("n")).alias("z"), "mean")


def is_white(report: DataFrame, bound: float = 4.0) -> bool:
    """No lag above 0 is over ``bound`` standard errors."""
    return report.where((F.col("lag") > 0) & (F.abs("z") > bound)).count() == 0


def gamma_from_noise(report: DataFrame, mass: float, temperature: float, dt: float) -> DataFrame:
    """One row (gamma): the friction that the noise's strength implies, of one component: the integral of its
    autocovariance over all lags is 2 gamma M kB T (kB = 1)."""
    total = F.sum(F.when(F.col("lag") == 0, F.col("cov")).otherwise(2 * F.col("cov")))
    return report.agg((total * dt / (2 * mass * temperature)).alias("gamma"))


# ---- thermostat and integration


def kinetic_temperature(traj: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(step, temperature) by equipartition: sum of M v^2 over three degrees of freedom an atom (kB = 1)."""
    v2 = F.col("vx") * F.col("vx") + F.col("vy") * F.col("vy") + F.col("vz") * F.col("vz")
    return traj.groupBy(*(by or ["step"])).agg((F.sum(F.col("mass") * v2) / (3 * F.count(F.lit(1)))).alias("temperature"))


def damp_and_kick(v: Column, f: Column, mass: Column, gamma: float, dt: float, first: bool) -> Column:
    """Half a step of friction and force: friction acts before the kick in the first half and after it in the second."""
    fade = math.exp(-gamma * dt / 2)
    return v * fade + f / mass * (dt / 2) if first else (v + f / mass * (dt / 2)) * fade


def langevin_step(state: DataFrame, force_of: Callable[[DataFrame], DataFrame], gamma: float, dt: float, scheme: str = "splitting") -> DataFrame:
    """state (atom_id, mass, x.., v.., f..) one step later. Friction only is added: the noise is in the forces.

    "splitting" fades velocities exactly around the force; "second_order" expands friction to the second order in dt.
    No random number is drawn and, after the forces have come, nothing is shuffled but their join.
    """
    axes = "xyz"
    if scheme == "splitting":
        half = {f"v{c}": damp_and_kick(F.col(f"v{c}"), F.col(f"f{c}"), F.col("mass"), gamma, dt, True) for c in axes}
        moved = state.withColumns(half)
        moved = moved.withColumns({c: F.col(c) + F.col(f"v{c}") * dt for c in axes})
    elif scheme == "second_order":
        a = lambda c: F.col(f"f{c}") / F.col("mass") - gamma * F.col(f"v{c}")
        place = {c: F.col(c) + F.col(f"v{c}") * dt + a(c) * (dt * dt / 2) for c in axes}
        half = {f"v{c}": F.col(f"v{c}") + a(c) * (dt / 2) - gamma * a(c) * (dt * dt / 8) for c in axes}
        moved = state.withColumns({**place, **half})
    else:
        raise ValueError(f"no such scheme: {scheme}")
    moved = moved.drop(*[f"f{c}" for c in axes])
    new = force_of(moved)
    rest = moved.join(new.withColumnRenamed("atom_id", "_a"), F.col("atom_id") == F.col("_a")).drop("_a")
    if scheme == "splitting":
        end = {f"v{c}": damp_and_kick(F.col(f"v{c}"), F.col(f"f{c}"), F.col("mass"), gamma, dt, False) for c in axes}
    else:
        k = gamma * dt / 2
        end = {f"v{c}": (F.col(f"v{c}") + F.col(f"f{c}") / F.col("mass") * (dt / 2)) / (1 + k) for c in axes}
    return rest.withColumns(end)


def next_gamma(gamma: float, temperature: float, target: float, dt: float, tau: float, g0: float) -> float:
    """Relaxation of the friction towards the temperature sought: raised while too hot, lowered while too cold, at least 0."""
    return max(0.0, gamma + dt / tau * g0 * (temperature / target - 1))


def calibrate_gamma(state: DataFrame, force_of: Callable[[DataFrame, int], DataFrame], target: float, dt: float, steps: int, tau: float, gamma: float = 0.0, g0: float = 1.0) -> tuple[float, list[tuple[int, float, float]]]:
    """(mean friction of the last half, [(step, temperature, gamma)]) of a short run on a small system.

    ``force_of(state, step)`` gives the noisy forces. Each step's state is cut from its lineage.
    """
    trace = []
    for step in range(1, steps + 1):
        state = settle(langevin_step(state, lambda s, n=step: force_of(s, n), gamma, dt))
        t = kinetic_temperature(state.withColumn("step", F.lit(step))).first().temperature
        trace.append((step, t, gamma))
        gamma = next_gamma(gamma, t, target, dt, tau, g0)
    late = [g for _, _, g in trace[len(trace) // 2 :]]
    return sum(late) / len(late), trace


def ensemble_average(traj: DataFrame, column: str, blocks: int = 10, order: str = "step") -> DataFrame:
    """One row (mean, error, blocks): the error from averages over ``blocks`` stretches of the ordered series.

    Block bounds come from the order's range, so no window holds the whole series.
    """
    lo, hi = traj.agg(F.min(order), F.max(order)).first()
    lo, hi = lo or 0, hi or 0
    block = F.least(F.floor((F.col(order) - lo) * blocks / max(1, hi - lo + 1)), F.lit(blocks - 1))
    means = traj.groupBy(block.alias("b")).agg(F.avg(column).alias("m"))
    return means.agg(F.avg("m").alias("mean"), (F.stddev_samp("m") / F.sqrt(F.count(F.lit(1)))).alias("error"), F.count(F.lit(1)).alias("blocks"))


# ---- steps of electronic-structure dynamics


@dataclass(frozen=True)
class StepConfig:
    """One step: the element model, purification, friction, time step, and nuclei's repulsion."""

    box: Box
    model: ElementModel
    how: Purification
    gamma: float = 0.0
    dt: float = 0.5
    present: tuple[str, ...] = ("H", "O")
    charges: float = 0.0
    scheme: str = "splitting"


def density_forces(a: DataFrame, cfg: StepConfig, groups: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(forces, the dense stage's table) of atoms at their positions."""
    out = cut(generate_density(a, cfg.box, cfg.model, cfg.how, cfg.present, groups))
    return forces(out, a, cfg.box, cfg.model, cfg.present, cfg.charges), out


def md_step(state: DataFrame, cfg: StepConfig, groups: DataFrame | None = None) -> tuple[DataFrame, dict]:
    """(the next state, observables): pattern, D and W, energy, forces, integration; the state is cut once a step.

    ``state``: the columns of atoms and vx, vy, vz, fx, fy, fz. Merged groups are used again and again.
    """
    seen: dict = {}

    def force_of(moved: DataFrame) -> DataFrame:
        f, out = density_forces(cut(moved), cfg, groups)
        e = energies(out).first()
        seen.update(energy=e.energy, electrons=e.electrons)
        return f

    after = settle(langevin_step(state, force_of, cfg.gamma, cfg.dt, cfg.scheme))
    v2 = F.col("vx") * F.col("vx") + F.col("vy") * F.col("vy") + F.col("vz") * F.col("vz")
    kinetic, n = after.agg(F.sum(F.col("mass") * v2) / 2, F.count(F.lit(1))).first()
    seen |= {"kinetic": kinetic, "temperature": 2 * kinetic / (3 * n)}
    if cfg.charges:
        seen["ions"] = ion_energy(after, cfg.box, cfg.model.longest(cfg.present), cfg.charges)
    return after, seen


def start_state(a: DataFrame, cfg: StepConfig, groups: DataFrame | None = None, speed: float = 0.0) -> DataFrame:
    """Atoms with table-driven velocities (a hash of the id, no random number) and their first forces."""
    axis = lambda k: (F.pmod(F.xxhash64("atom_id", F.lit(k)), F.lit(2001)) - 1000) / 1000.0 * speed
    s = a.withColumns({"vx": axis(1), "vy": axis(2), "vz": axis(3)})
    f, _ = density_forces(a, cfg, groups)
    return cut(s.join(f.withColumnRenamed("atom_id", "_a"), F.col("atom_id") == F.col("_a")).drop("_a"))


def simulate(state: DataFrame, cfg: StepConfig, steps: int, groups: DataFrame | None = None, anneal: float = 1.0) -> tuple[DataFrame, list[dict]]:
    """Several steps; velocities are scaled by ``anneal`` after each."""
    seen = []
    for _ in range(steps):
        state, o = md_step(state, cfg, groups)
        if anneal != 1.0:
            state = state.withColumns({f"v{c}": F.col(f"v{c}") * anneal for c in "xyz"})
        seen.append(o)
    return state, seen


# ---- self-consistency and propagation


def scf(h_of_d: Callable[[DataFrame | None], DataFrame], density_of: Callable[[DataFrame], DataFrame], mixing: float = 0.5, tol: float = 1e-6, most: int = 40) -> tuple[DataFrame, list[float]]:
    """(D, [change of each pass]): D from H(D), mixed linearly, until the largest change of an entry is below ``tol``."""
    from .matrix import axpy, norms

    d = cut(density_of(h_of_d(None)))
    changes = []
    for _ in range(most):
        new = density_of(h_of_d(d))
        step = settle(axpy(1.0, new, -1.0, d))
        changes.append(norms(step)["max"])
        d = settle(axpy(1.0, d, mixing, step))
        if changes[-1] < tol:
            break
    return d, changes


def propagate(history: list[DataFrame]) -> DataFrame:
    """The next D from past ones, newest last: alternating binomial weights, the always stable predictor of its order.

    With K past matrices the weight of the m-th newest is (-1)^(m+1) m C(2K, K-m) / C(2K-2, K-1).
    """
    k = len(history)
    weights = [(-1) ** (m + 1) * m * math.comb(2 * k, k - m) / math.comb(2 * k - 2, k - 1) for m in range(1, k + 1)]
    parts = [d.select("row", "col", (F.col("val") * w).alias("val")) for w, d in zip(weights, reversed(history), strict=True)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("row", "col").agg(F.sum("val").alias("val"))
