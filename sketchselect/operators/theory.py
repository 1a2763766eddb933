"""Sizes and bounds from the theory of the sketched method, with small checks."""

from __future__ import annotations

import math

import numpy as np

from sketchselect.functions.hashing import SketchSpec, np_places


def topk_cells(p: int, k: int, tail: float, zeta: float, eps: float, delta: float) -> float:
    """Order of cells for recovering the k largest of p within eps: log(p/delta) (k + tail/(eps zeta)^2).

    ``tail`` is the squared norm outside the k largest.
    """
    return math.log(p / delta) * (k + tail / (eps * zeta) ** 2)


def convergence_size(eps: float, delta: float) -> tuple[float, float]:
    """Orders of buckets and rows for convergence in the sketched domain."""
    return math.log(1 / delta) / eps**2, math.log(1 / delta) / eps


def corollary_size(p: int, k: int, tail: float, zeta: float, eps: float, delta: float) -> float:
    """The larger of both sizes, each at half the failure probability."""
    return max(topk_cells(p, k, tail, zeta, eps, delta / 2), convergence_size(eps, delta / 2)[0])


def projection(p: int, spec: SketchSpec) -> np.ndarray:
    """S (p x cells) with entries +-1/sqrt(rows)."""
    buckets, signs = np_places(np.arange(p), spec)
    s = np.zeros((p, spec.cells))
    for j in range(spec.rows):
        s[np.arange(p), j * spec.buckets + buckets[j]] = signs[j] / math.sqrt(spec.rows)
    return s


def gram_of_projection(p: int, spec: SketchSpec) -> np.ndarray:
    """S'S scaled by m/p; its mean over seeds is the identity."""
    s = projection(p, spec)
    return s.T @ s * (spec.cells / p)


def tail_probability(p: int, m: int, eps: float) -> float:
    """Matrix tail bound that S'S leaves (1 +- eps) p/m, capped at 1."""
    t, v = eps * p / m, p * (m - 1) / m**2
    return min(1.0, 2 * m * math.exp(-(t**2) / 2 / (v + t / 3)))


def hessian_range(hessian: np.ndarray, spec: SketchSpec) -> tuple[float, float, float, float]:
    """Extreme eigenvalues of the Hessian and of S'HS."""
    s = projection(len(hessian), spec)
    own, cut = np.linalg.eigvalsh(hessian), np.linalg.eigvalsh(s.T @ hessian @ s)
    return own[0], own[-1], cut[0], cut[-1]


def gradient_bounds(p: int, m: int, largest: float, eps: float, bound: float) -> tuple[float, float]:
    """The squared projected gradient's bound without and with the curvature factor.

    Projection alone gives the first; the second also carries the largest curvature.
    """
    base = p / m * (1 + eps) * bound**2
    return base, base * largest


def rate_constant(eta0: float, t0: float, m1: float, big_c: float, second: float, gap: float) -> float:
    """Constant of the O(1/t) rate for steps eta0/(t + t0); raises where the conditions fail.

    ``m1`` bounds the inverse-curvature matrix below, ``big_c`` is the decay condition's constant,
    ``second`` bounds the noise term, ``gap`` is the first objective gap.
    """
    room = 2 * m1 * eta0 * t0 - big_c
    if room <= 0:
        raise ValueError("the step condition needs 2 m1 eta0 t0 > C")
    return max(eta0**2 * t0**2 * second / (2 * room), t0 * gap)
