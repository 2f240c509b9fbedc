"""Two-level sketch: a shrinking top level, and a sampled level for what shrinking removes."""

from __future__ import annotations

import numpy as np

from .base import SketchRow, hash_uniform
from .spectral import SpectralSketcher, factor


class TwoLevelSketcher(SpectralSketcher):
    """Top level of at most 3k directions; each direction loses min(squared value, delta), and
    ``ell - 3k`` independent slots each hold one lost direction, drawn in proportion to its lost
    mass. Slots scaled by the mean mass stand for the lost part without bias.

    A factorisation takes in as many new rows as the top level holds, so that a row costs d * k
    operations however many slots there are.
    """

    def setup(self, k: int | None = None, **options) -> None:
        self.k = int(k if k is not None else max(1, self.ell // 4))
        self.cap = min(3 * self.k, self.ell)
        super().setup(**{"batch_rows": self.cap} | {n: v for n, v in options.items() if v is not None})
        self.first_id: int | None = None
        self.slots = max(1, self.ell - self.cap)
        self.sample = np.zeros((self.slots, self.d))
        self.mass = 0.0
        self.draws = 0

    def absorb(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray) -> None:
        if self.first_id is None and len(ids):
            self.first_id = int(ids[0])
        super().absorb(x, y, ids)

    def offer(self, vectors: np.ndarray, weights: np.ndarray) -> None:
        """Unit vectors with lost mass, for the slots."""
        live = weights > 0
        vectors, weights = vectors[live], weights[live]
        fresh = float(weights.sum())
        if fresh <= 0:
            return
        self.mass += fresh
        self.draws += 1
        tag = np.array([self.part_tag() * 1_000_003 + self.draws], dtype=np.int64)
        u = hash_uniform(tag, 2 * self.slots, self.seed)[0]
        enter = u[: self.slots] < fresh / self.mass
        pick = np.minimum(np.searchsorted(np.cumsum(weights) / fresh, u[self.slots :]), len(weights) - 1)
        self.sample[enter] = vectors[pick[enter]]

    def part_tag(self) -> int:
        """A number of this sketch's own, from its first row's id: slots of different parts differ."""
        return (self.first_id or 0) % 1_000_000_007

    def compress(self, rows: np.ndarray) -> None:
        sigma, basis = factor(np.concatenate([self.sigma[:, None] * self.basis, rows]), self.svd)
        self.n_svd += 1
        square = sigma**2
        delta = float(square[self.cap]) if len(square) > self.cap else 0.0
        self.shrink_total += delta
        lost = np.minimum(square, delta) if delta else np.zeros(len(square))
        self.offer(basis, lost)
        left = np.maximum(square[: self.cap] - delta, 0.0)
        live = left > 0
        self.sigma, self.basis = np.sqrt(left[live]), basis[: self.cap][live]

    def absorb_sketches(self, rows: list[SketchRow]) -> None:
        for r in rows:
            if r.residual_mass > 0:
                self.mass += r.residual_mass
                self.draws += 1
                tag = np.array([(r.part_id + 1) * 1_000_003 + self.draws], dtype=np.int64)
                enter = hash_uniform(tag, self.slots, self.seed + 1)[0] < r.residual_mass / self.mass
                self.sample[enter] = r.payload.reshape(-1, self.d)[: self.slots][enter]
        super().absorb_sketches(rows)

    def fill(self, row: SketchRow) -> None:
        super().fill(row)
        row.payload, row.residual_mass = self.sample, self.mass


def residual_rows(row: SketchRow) -> np.ndarray:
    """The sampled level's rows, scaled."""
    sample = row.payload.reshape(-1, row.n_features)
    if row.residual_mass <= 0 or not len(sample):
        return np.zeros((0, row.n_features))
    norms = np.linalg.norm(sample, axis=1)
    live = norms > 0
    return sample[live] / norms[live, None] * np.sqrt(row.residual_mass / len(sample))
