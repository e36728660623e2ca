"""Spectra, rank choice and leading vectors; everything here is as small as one mode."""

from __future__ import annotations

import warnings
from dataclasses import dataclass

import numpy as np

#: Mode length up to which the driver solves without complaint, and the least safe tolerance of the Gram route.
SOFT_LIMIT = 2000
GRAM_FLOOR = float(np.sqrt(np.finfo(float).eps))


@dataclass(frozen=True)
class Spectrum:
    """Squared singular values of an unfolding, falling; tails[r] is what rank r leaves out."""

    values: np.ndarray
    vectors: np.ndarray

    @property
    def tails(self) -> np.ndarray:
        return np.append(np.cumsum(self.values[::-1])[::-1], 0.0)

    def degenerate(self, rank: int) -> bool:
        v = self.values
        return 0 < rank < len(v) and v[rank - 1] - v[rank] <= 1e-10 * v[0]


def canonical(vectors: np.ndarray) -> np.ndarray:
    """Signs such that each column's largest entry (the first of equals) is positive."""
    if not vectors.size:
        return vectors
    size = np.abs(vectors)
    at = np.argmax(size >= size.max(axis=0) * (1 - 1e-12), axis=0)
    sign = np.where(vectors[at, np.arange(vectors.shape[1])] < 0, -1.0, 1.0)
    return vectors * sign


def from_gram(s: np.ndarray) -> Spectrum:
    values, vectors = np.linalg.eigh((s + s.T) / 2)
    return Spectrum(np.maximum(values[::-1], 0.0), canonical(vectors[:, ::-1]))


def from_triangle(r: np.ndarray, length: int) -> Spectrum:
    """From R of the transposed unfolding: its right singular vectors."""
    _, sigma, vt = np.linalg.svd(r, full_matrices=True)
    values = np.zeros(length)
    values[: len(sigma)] = sigma**2
    return Spectrum(values, canonical(vt.T))


def from_unfolding(matrix: np.ndarray) -> Spectrum:
    u, sigma, _ = np.linalg.svd(matrix, full_matrices=True)
    values = np.zeros(len(matrix))
    values[: len(sigma)] = sigma**2
    return Spectrum(values, canonical(u))


def rank_for_budget(values: np.ndarray, budget_sq: float, most: int | None = None) -> int:
    """The least rank (one at least) whose tail is within the budget; equality keeps the smaller."""
    tails = np.append(np.cumsum(values[::-1])[::-1], 0.0)
    rank = max(1, int(np.argmax(tails <= budget_sq)))
    return min(rank, most or len(values))


def numerical_rank(values: np.ndarray, tol: float = 1e-12) -> int:
    return int((values > tol * max(values[0], 1e-300)).sum()) if len(values) else 0


def choose_spectral_method(eps: float | None, length: int, limit: int = 8000) -> str:
    """'gram' where it is safe, else 'tsqr', which never squares the condition.

    Not safe: tolerances at or below GRAM_FLOOR, and modes whose Gram matrix (longer than
    `limit`) may not go to the driver. Beyond SOFT_LIMIT the driver's step is slow, and says so.
    """
    if length > SOFT_LIMIT:
        warnings.warn(f"a mode of length {length} is beyond {SOFT_LIMIT}: its spectrum is found by one process", stacklevel=2)
    return "tsqr" if length > limit or eps is not None and eps <= GRAM_FLOOR else "gram"


def leading_eigenvectors(s: np.ndarray, rank: int | None = None, budget_sq: float | None = None) -> tuple[np.ndarray, Spectrum]:
    found = from_gram(s)
    r = rank if rank is not None else rank_for_budget(found.values, budget_sq if budget_sq is not None else 0.0)
    return found.vectors[:, :r], found


def row_subset(vectors: np.ndarray, block: int, index: int) -> np.ndarray:
    """The rows of a factor that go with one block of its mode."""
    return vectors[index * block : (index + 1) * block]


def orthonormality(u: np.ndarray) -> float:
    return float(np.abs(u.T @ u - np.eye(u.shape[1])).max()) if u.size else 0.0
