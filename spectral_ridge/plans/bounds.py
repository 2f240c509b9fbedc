"""Guarantees as plain functions: rows, penalties and errors that follow from the tail energy."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np


def tail_energy(sigma_sq: np.ndarray) -> np.ndarray:
    """tail[k]: squared norm beyond the first k directions, k = 0 .. number of values."""
    s = np.sort(np.asarray(sigma_sq, dtype=np.float64))[::-1]
    return np.concatenate([np.cumsum(s[::-1])[::-1], [0.0]])


def _half(robust: bool) -> float:
    return 2.0 if robust else 1.0


def required_rows(tail: np.ndarray, gamma: float, eps: float, robust: bool = False) -> tuple[int, int]:
    """(sketch rows, best k) with which the coefficient error is at most ``eps``; no more than the
    rank is ever needed."""
    k = np.arange(len(tail))
    need = k + tail / (gamma * eps * _half(robust))
    best = int(np.argmin(need))
    rows = max(math.ceil(need[best] - 1e-12), best + 1)
    whole = tail[-1] <= 0  # else these are bounds from a sketch, which say nothing about the rank
    return (min(rows, max(int(np.count_nonzero(np.asarray(tail) > 0)), 1)) if whole else rows), best


def required_gamma(tail: np.ndarray, ell: int, eps: float, robust: bool = False) -> float:
    """The smallest penalty with which ``ell`` rows guarantee ``eps``."""
    k = np.arange(min(ell, len(tail)))
    return float(np.min(tail[k] / (eps * (ell - k) * _half(robust))))


def guaranteed_eps(tail: np.ndarray, ell: int, gamma: float, robust: bool = False) -> float:
    """The error that ``ell`` rows guarantee at a penalty."""
    return cov_bound(tail, ell, robust) / gamma


def cov_bound(tail: np.ndarray, ell: int, robust: bool = False) -> float:
    """A-priori bound of the spectral covariance error, the best over k."""
    k = np.arange(min(ell, len(tail)))
    return float(np.min(tail[k] / ((ell - k) * _half(robust))))


def regime(tail: np.ndarray, gamma: float, max_k: int = 10) -> int | None:
    """The smallest k up to ``max_k`` whose tail the penalty exceeds; None: outside the regime."""
    hits = [k for k in range(min(max_k + 1, len(tail))) if gamma >= tail[k]]
    return hits[0] if hits else None


def coefficient_bound(cov_err: float, lam_min: float, gamma: float) -> float:
    """Bound of the relative coefficient error for any approximation of the Gram matrix."""
    if lam_min + gamma <= 0:
        raise ValueError("smallest eigenvalue plus penalty must be positive")
    return cov_err / (lam_min + gamma)


def prediction_gap_bound(eps: float, x_norm: float, a_norm: float) -> float:
    """Bound of a prediction's change: a point's norm, or the spectral norm of a block of points."""
    return eps * x_norm * a_norm


def random_rows_for(eps: float) -> int:
    """Rows of the order that random transforms need for the same error."""
    return math.ceil(1 / eps**2)


def per_row_penalty(gamma: float, n: int) -> float:
    """The penalty of the objective with n * gamma as one of the objective with gamma."""
    return gamma * n


def tail_upper_bound(frob_sq: float, sigma: np.ndarray) -> np.ndarray:
    """Upper bounds of the tails from a sketch alone: exact norm minus the kept directions."""
    kept = np.concatenate([[0.0], np.cumsum(np.asarray(sigma) ** 2)])
    return np.maximum(frob_sq - kept, 0.0)


@dataclass
class TightExample:
    gram: np.ndarray
    approx: np.ndarray
    error: float


def tightness_example(d: int, alpha: float, beta: float, gamma: float) -> TightExample:
    """Gram matrices for which the coefficient bound is an equality: alpha >= 0, beta + gamma > 0."""
    if alpha < 0 or beta + gamma <= 0:
        raise ValueError("alpha >= 0 and beta + gamma > 0 are needed")
    return TightExample((alpha + beta) * np.eye(d), beta * np.eye(d), alpha / (beta + gamma))
