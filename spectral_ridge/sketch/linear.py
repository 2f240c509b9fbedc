"""Additive summaries: the exact Gram matrix and three random linear transforms of the rows."""

from __future__ import annotations

import numpy as np

from .base import SketchRow, Sketcher, hash_words


class ExactSketcher(Sketcher):
    """The Gram matrix itself, as an upper triangle."""

    def setup(self) -> None:
        self.gram = np.zeros((self.d, self.d))

    def absorb(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray) -> None:
        self.gram += x.T @ x

    def absorb_sketches(self, rows: list[SketchRow]) -> None:
        for r in rows:
            self.gram += full_gram(r)

    def fill(self, row: SketchRow) -> None:
        row.payload, row.rank = self.gram[np.triu_indices(self.d)], self.d


def full_gram(row: SketchRow) -> np.ndarray:
    out = np.zeros((row.n_features, row.n_features))
    out[np.triu_indices(row.n_features)] = row.payload
    return out + np.triu(out, 1).T


class ProjectionSketcher(Sketcher):
    """C = sum of S x and v = sum of S y, S drawn for each row from its hash: a retried task, or
    another partitioning, draws the same."""

    def setup(self) -> None:
        self.projected = np.zeros((self.ell, self.d))
        self.proj_target = np.zeros((self.ell, self.t))

    def absorb_sketches(self, rows: list[SketchRow]) -> None:
        for r in rows:
            self.projected += r.payload.reshape(self.ell, self.d)
            self.proj_target += r.proj_target.reshape(self.ell, self.t)

    def fill(self, row: SketchRow) -> None:
        row.payload, row.proj_target, row.rank = self.projected, self.proj_target, min(self.ell, self.d)


class SignSketcher(ProjectionSketcher):
    """Dense random signs. ``scale``: "unbiased" is 1/sqrt(ell); "printed" is sqrt(ell), kept for
    the test that shows what it does to the Gram matrix."""

    def setup(self, scale: str = "unbiased") -> None:
        super().setup()
        self.scale = {"unbiased": self.ell**-0.5, "printed": self.ell**0.5}[scale]

    def absorb(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray) -> None:
        for at in range(0, len(x), 4096):
            words = hash_words(ids[at : at + 4096], -(-self.ell // 64), self.seed)
            bits = np.unpackbits(words.view(np.uint8), axis=1)[:, : self.ell]
            signs = (bits.astype(np.float64) * 2 - 1) * self.scale
            self.projected += signs.T @ x[at : at + 4096]
            self.proj_target += signs.T @ y[at : at + 4096]


class CountSketcher(ProjectionSketcher):
    """One random bucket and sign for each row."""

    def absorb(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray) -> None:
        words = hash_words(ids, 1, self.seed)[:, 0]
        bucket = ((words >> np.uint64(1)) % np.uint64(self.ell)).astype(np.int64)
        sign = np.where(words & np.uint64(1), 1.0, -1.0)[:, None]
        order = np.argsort(bucket, kind="stable")
        bucket = bucket[order]
        at = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
        self.projected[bucket[at]] += np.add.reduceat((sign * x)[order], at, axis=0)
        self.proj_target[bucket[at]] += np.add.reduceat((sign * y)[order], at, axis=0)


class StructuredSketcher(ProjectionSketcher):
    """Subsampled randomised Hadamard transform over blocks of rows: signs from the row hash, a
    Hadamard transform down the block, and ``ell`` of its rows, scaled."""

    def setup(self, block: int = 1024) -> None:
        super().setup()
        self.block = 1 << max(int(block) - 1, self.ell - 1, 1).bit_length()

    def absorb(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray) -> None:
        for at in range(0, len(x), self.block):
            rows = np.concatenate([x[at : at + self.block], y[at : at + self.block]], axis=1)
            keys = ids[at : at + self.block]
            n = 1 << max(len(rows) - 1, self.ell - 1, 1).bit_length()
            padded = np.zeros((n, rows.shape[1]))
            padded[: len(rows)] = rows * np.where(hash_words(keys, 1, self.seed) & np.uint64(1), 1.0, -1.0)
            step = 1
            while step < n:
                pair = padded.reshape(n // (2 * step), 2, step, -1)
                padded = np.concatenate([(pair[:, 0] + pair[:, 1])[:, None], (pair[:, 0] - pair[:, 1])[:, None]], axis=1).reshape(n, -1)
                step *= 2
            words = hash_words(np.arange(n) ^ int(keys[0] & 0x7FFFFFFF), 1, self.seed + 1)[:, 0]
            chosen = np.argsort(words, kind="stable")[: self.ell]
            sign = np.where(words[chosen] & np.uint64(1), 1.0, -1.0)[:, None]
            part = padded[chosen] * sign / np.sqrt(self.ell)
            self.projected += part[:, : self.d]
            self.proj_target += part[:, self.d :]
