"""The chemical potential that makes a system neutral: an outer bisection around purification, or one on levels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import Purification
from ..sources.tables import cut
from .observables import sums_by
from .submatrix import level_weights, paired_purify


class NotBracketed(ValueError):
    """The bracket does not hold the electron number sought."""


def electrons_at(levels: DataFrame, mus: list[float], occupancy: float = 2.0) -> list[float]:
    """Electron numbers at several potentials, in one aggregation of the level table."""
    row = levels.agg(*[F.coalesce(F.sum(F.when(F.col("level") < mu, F.col("weight"))), F.lit(0.0)).alias(f"n{i}") for i, mu in enumerate(mus)]).first()
    return [occupancy * v for v in row]


def find_mu_spectral(pair: DataFrame, groups: DataFrame, electrons: float, lo: float, hi: float, tol: float = 1e-3, occupancy: float = 2.0, probes: int = 15, rounds: int = 20) -> dict:
    """The potential by levels computed once: each round probes many potentials in one pass and keeps a bracket.

    The count is a step function, nearly monotone; the middle of the widest plateau found within ``tol`` of the
    number is returned, else the nearest bracket's middle. Returns mu, electrons, residual, rounds.
    """
    levels = cut(level_weights(pair, groups))
    done = 0
    for done in range(1, rounds + 1):
        mus = [lo + (hi - lo) * i / (probes - 1) for i in range(probes)]
        counts = electrons_at(levels, mus, occupancy)
        if done == 1 and not (counts[0] - tol <= electrons <= counts[-1] + tol):
            raise NotBracketed(f"{electrons} electrons are not between {counts[0]} at {lo} and {counts[-1]} at {hi}")
        good = [i for i, c in enumerate(counts) if abs(c - electrons) <= tol]
        if good:
            mu = (mus[good[0]] + mus[good[-1]]) / 2
            return {"mu": mu, "electrons": (c := electrons_at(levels, [mu], occupancy)[0]), "residual": c - electrons, "rounds": done}
        above = next((i for i, c in enumerate(counts) if c > electrons), probes - 1)
        lo, hi = mus[max(0, above - 1)], mus[above]
        if hi - lo < 1e-12:
            break
    mu = (lo + hi) / 2
    c = electrons_at(levels, [mu], occupancy)[0]
    return {"mu": mu, "electrons": c, "residual": c - electrons, "rounds": done}


def find_mu_rerun(pair: DataFrame, groups: DataFrame, electrons: float, lo: float, hi: float, tol: float = 1e-3, occupancy: float = 2.0, rounds: int = 25, how: Purification | None = None) -> dict:
    """The potential by bisection with a full purification for each probe."""
    base = how or Purification(solver="eigen")

    def count(mu: float) -> float:
        out = paired_purify(pair, Purification(**{**base.__dict__, "mu": mu}), groups, with_w=False)
        return occupancy * (sums_by(out, pair).first().electrons or 0.0)

    low, high = count(lo), count(hi)
    if not (low - tol <= electrons <= high + tol):
        raise NotBracketed(f"{electrons} electrons are not between {low} and {high}")
    mid, c, done = (lo + hi) / 2, low, 0
    for done in range(1, rounds + 1):
        mid = (lo + hi) / 2
        c = count(mid)
        if abs(c - electrons) <= tol:
            break
        lo, hi = (mid, hi) if c < electrons else (lo, mid)
    return {"mu": mid, "electrons": c, "residual": c - electrons, "rounds": done}
