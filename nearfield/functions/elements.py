"""Species, the unit cell, and matrix elements generated for each pair of species.

One specification of a pair's elements gives both a vectorised numpy closure (used where elements are generated in a
worker) and a SQL expression of the distance (used where they are made as a relational matrix). All figures here are
a stand-in that is local, positive definite and gapped; they carry no chemistry.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np

# Functions a species has (two for H, nine for S, four for others), electrons, mass, levels, cutoff in A.
SPECIES: dict[str, dict] = {
    "H": {"nbf": 2, "charge": 1, "mass": 1.008, "level": (-0.05, 0.35), "rcut": 4.5, "amp": 0.12, "width": 1.3, "exponentials": 1},
    "O": {"nbf": 4, "charge": 6, "mass": 15.999, "level": (-0.9, -0.55, -0.52, -0.50), "rcut": 4.5, "amp": 0.12, "width": 1.3, "exponentials": 2},
    "C": {"nbf": 4, "charge": 4, "mass": 12.011, "level": (-0.7, -0.5, 0.2, 0.3), "rcut": 4.5, "amp": 0.12, "width": 1.3, "exponentials": 2},
    "S": {"nbf": 9, "charge": 6, "mass": 32.06, "level": (-0.8, -0.6, -0.55, 0.2, 0.25, 0.3, 0.35, 0.4, 0.45), "rcut": 4.5, "amp": 0.12, "width": 1.3, "exponentials": 6.3},
    "X": {"nbf": 4, "charge": 2, "mass": 22.99, "level": (-0.8, 0.3, 0.4, 0.45), "rcut": 7.5, "amp": 0.02, "width": 2.6, "exponentials": 2},
}
#: Edge of the cell in A, bond length in A, bond angle in degrees, factor of the off-site elements.
EDGE, BOND, ANGLE, COUPLING = 9.8, 0.96, 104.5, 1.75


@lru_cache(maxsize=1)
def unit_cell() -> tuple[tuple[str, float, float, float], ...]:
    """32 three-site molecules on a 4 x 4 x 2 grid: (species, x, y, z) of slots 0 to 95, to 4 decimals."""
    out = []
    for k in range(32):
        a, b, c = k // 8, k // 2 % 4, k % 2
        x, y, z = (a + 0.5) * EDGE / 4, (b + 0.5) * EDGE / 4, (c + 0.5) * EDGE / 2
        turn = 2 * math.pi * (7 * k % 32) / 32
        out.append(("O", round(x, 4), round(y, 4), round(z, 4)))
        for side in (1, -1):
            t = turn + side * math.radians(ANGLE / 2)
            out.append(("H", round(x + BOND * math.cos(t), 4), round(y + BOND * math.sin(t), 4), round(z, 4)))
    return tuple(out)


@dataclass(frozen=True)
class ElementModel:
    """Overlap and Hamiltonian elements between functions of two sites at a distance r below the pair's cutoff.

    S = amp exp(-(r / width)^2) (1 - (r / rc)^2)^2 between sites and the identity on one; H = COUPLING times the mean
    of the two levels times S between sites, the levels on one. ``h_rcut`` may cut H shorter than S.
    """

    rcut: float | None = None
    h_rcut: float | None = None
    species: dict = field(default_factory=lambda: SPECIES, hash=False, compare=False)

    def cutoff(self, a: str, b: str) -> float:
        """The larger of the two species' cutoffs."""
        own = [self.rcut if self.rcut is not None and s != "X" else self.species[s]["rcut"] for s in (a, b)]
        return max(own)

    def longest(self, present) -> float:
        return max(self.cutoff(a, a) for a in present)

    def shape(self, a: str, b: str) -> tuple[float, float, float]:
        """(amplitude, width, cutoff): those of the species with the longer reach."""
        far = max((self.species[s] for s in (a, b)), key=lambda s: s["rcut"])
        return far["amp"], far["width"], self.cutoff(a, b)

    def overlap(self, a: str, b: str) -> Callable[[np.ndarray], np.ndarray]:
        """Generated closure: overlap of a pair of functions from the distance."""
        amp, width, rc = self.shape(a, b)
        return lambda r: np.where(r < rc, amp * np.exp(-((r / width) ** 2)) * (1 - (r / rc) ** 2) ** 2, 0.0)

    def overlap_slope(self, a: str, b: str) -> Callable[[np.ndarray], np.ndarray]:
        """Generated closure: its derivative by the distance."""
        amp, width, rc = self.shape(a, b)

        def slope(r):
            u = 1 - (r / rc) ** 2
            return np.where(r < rc, amp * np.exp(-((r / width) ** 2)) * u * (-2 * r / width**2 * u - 4 * r / rc**2), 0.0)

        return slope

    def overlap_sql(self, a: str, b: str, r: str = "r") -> str:
        """The same as a SQL expression of the distance."""
        amp, width, rc = self.shape(a, b)
        return f"CASE WHEN {r} < {rc!r} THEN {amp!r} * exp(-power({r} / {width!r}, 2)) * power(1 - power({r} / {rc!r}, 2), 2) ELSE 0.0 END"

    def levels(self, a: str) -> np.ndarray:
        return np.array(self.species[a]["level"])

    def h_factor(self, a: str, b: str) -> np.ndarray:
        """Matrix that an overlap is multiplied with to give the Hamiltonian block of two sites."""
        return COUPLING * (self.levels(a)[:, None] + self.levels(b)[None, :]) / 2

    def cost(self, a: str, b: str) -> float:
        """Exponentials that a block of this pair takes; about ten times as many for S-S as for O-O."""
        return self.species[a]["exponentials"] * self.species[b]["exponentials"]

    def pair(self, species: list[str], xyz: np.ndarray, box: np.ndarray, dtype=np.float64) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(H, S, first function of each site) for sites in a periodic box, all image shifts within the cutoff summed.

        Elements are evaluated in ``dtype`` and returned in double precision.
        """
        names, kind = np.unique(np.array(species), return_inverse=True)
        nbf = np.array([self.species[s]["nbf"] for s in names])[kind]
        at = np.concatenate([[0], np.cumsum(nbf)])
        n = int(at[-1])
        h, s = np.zeros((n, n)), np.eye(n)
        h[range(n), range(n)] = np.concatenate([self.levels(x) for x in species]) if n else []
        if n == 0:
            return h, s, at
        site = np.zeros((len(species), len(species)))
        site_h = np.zeros_like(site)
        reach = self.longest(names)
        # beyond twice the reach only the nearest image counts
        images = [range(-int(math.ceil(reach / b)), int(math.ceil(reach / b)) + 1) if b < 2 * reach else range(1) for b in box]
        d0 = xyz[:, None, :] - xyz[None, :, :]
        wrap = np.where(np.isfinite(box), box, 1.0)
        d0 = np.where(np.isfinite(box), d0 - wrap * np.rint(d0 / wrap), d0)
        for i in images[0]:
            for j in images[1]:
                for k in images[2]:
                    shift = np.array([i, j, k]) * wrap
                    r = np.sqrt(((d0 + shift) ** 2).sum(axis=2)).astype(dtype)
                    if not (r < reach).any():
                        continue
                    for a in range(len(names)):
                        for b in range(len(names)):
                            rows, cols = np.flatnonzero(kind == a), np.flatnonzero(kind == b)
                            rr = r[np.ix_(rows, cols)]
                            v = np.where(rr > 1e-9, self.overlap(names[a], names[b])(rr), 0.0)
                            site[np.ix_(rows, cols)] += v
                            if self.h_rcut is not None:
                                v = np.where(rr < self.h_rcut, v, 0.0)
                            site_h[np.ix_(rows, cols)] += v
        who = np.repeat(np.arange(len(species)), nbf)
        s += site[np.ix_(who, who)]
        level = h.diagonal().copy()
        h += COUPLING * (level[:, None] + level[None, :]) / 2 * site_h[np.ix_(who, who)]
        return h, s, at


def species_rows() -> list[tuple]:
    """(species, nbf, charge, mass, level, rcut, exponentials) of every species."""
    return [(k, v["nbf"], v["charge"], v["mass"], list(v["level"]), v["rcut"], float(v["exponentials"])) for k, v in SPECIES.items()]


SPECIES_SCHEMA = "species string, nbf int, charge int, mass double, level array<double>, rcut double, exponentials double"
