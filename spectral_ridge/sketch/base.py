"""The sketch row, and what every sketcher does."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, fields

import numpy as np

VERSION = 1


@dataclass
class SketchRow:
    """One (partial or final) sketch. Matrices are row-major float64, so that they cross the
    boundary to the JVM as plain bytes."""

    method: str
    ell: int
    n_features: int
    n_targets: int = 1
    version: int = VERSION
    n_rows: int = 0
    n_skipped: int = 0
    frob_sq: float = 0.0
    target_sq: float = 0.0
    shrink_total: float = 0.0
    dropped_total: float = 0.0
    n_svd: int = 0
    rank: int = 0
    sigma: np.ndarray = field(default_factory=lambda: np.zeros(0))
    basis: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))
    cross: np.ndarray = field(default_factory=lambda: np.zeros(0))
    payload: np.ndarray = field(default_factory=lambda: np.zeros(0))
    proj_target: np.ndarray = field(default_factory=lambda: np.zeros(0))
    residual_mass: float = 0.0
    seed: int = 0
    part_id: int = 0
    train_ns: int = 0

    def to_dict(self) -> dict:
        out = {f.name: getattr(self, f.name) for f in fields(self)}
        for name in ("basis", "payload"):
            out[name] = np.ascontiguousarray(out[name], dtype=np.float64).tobytes()
        for name in ("sigma", "cross", "proj_target"):
            out[name] = np.asarray(out[name], dtype=np.float64).reshape(-1).tolist()
        return out

    @classmethod
    def from_dict(cls, row: dict) -> SketchRow:
        known = {f.name for f in fields(cls)}
        row = {k: v for k, v in row.items() if k in known}
        d, t = row["n_features"], row["n_targets"]
        row["sigma"] = np.asarray(row["sigma"], dtype=np.float64)
        row["basis"] = np.frombuffer(row["basis"], np.float64).reshape(-1, d)
        row["payload"] = np.frombuffer(row["payload"], np.float64)
        row["cross"] = np.asarray(row["cross"], dtype=np.float64).reshape(d, t)
        row["proj_target"] = np.asarray(row["proj_target"], dtype=np.float64)
        return cls(**row)


class Sketcher:
    """Folds batches of rows into a sketch, and merges sketches of the same kind.

    Sums (rows, squared norms, the exact feature-target moments) are kept here; subclasses keep
    what stands for the Gram matrix.
    """

    def __init__(self, method: str, ell: int, n_features: int, n_targets: int = 1, seed: int = 0, **options):
        if ell < 1:
            raise ValueError("ell must be at least 1")
        self.method, self.ell, self.d, self.t, self.seed = method, int(ell), int(n_features), int(n_targets), int(seed)
        self.cross = np.zeros((self.d, self.t))
        self.n_rows = self.n_skipped = 0
        self.frob_sq = self.target_sq = 0.0
        self.train_ns = 0
        self.setup(**options)

    def setup(self) -> None:
        """Options of the subclass."""

    def update(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray | None = None) -> None:
        """Fold rows in. ``ids``: 64-bit row hashes, for methods whose randomness hangs on the row."""
        began = time.perf_counter_ns()
        x = np.ascontiguousarray(x, dtype=np.float64)
        y = np.asarray(y, dtype=np.float64).reshape(len(x), self.t)
        if x.shape[1] != self.d:
            raise ValueError(f"rows have {x.shape[1]} features; {self.d} expected")
        self.cross += x.T @ y
        self.frob_sq += float(np.vdot(x, x))
        self.target_sq += float(np.vdot(y, y))
        first = self.n_rows
        self.n_rows += len(x)
        self.absorb(x, y, ids if ids is not None else np.arange(first, first + len(x), dtype=np.int64))
        self.train_ns += time.perf_counter_ns() - began

    def absorb(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray) -> None:
        raise NotImplementedError

    def merge(self, rows: list[SketchRow]) -> None:
        """Take in sketches of the same method and shape."""
        began = time.perf_counter_ns()
        rows = [r for r in rows if r.n_rows or r.n_skipped]
        for r in rows:
            if (r.method, r.n_features, r.n_targets) != (self.method, self.d, self.t):
                raise ValueError(f"cannot merge {r.method} of {r.n_features} features into {self.method} of {self.d}")
            self.cross += r.cross
            self.n_rows += r.n_rows
            self.n_skipped += r.n_skipped
            self.frob_sq += r.frob_sq
            self.target_sq += r.target_sq
            self.train_ns += r.train_ns
        self.absorb_sketches([r for r in rows if r.n_rows])
        self.train_ns += time.perf_counter_ns() - began

    def absorb_sketches(self, rows: list[SketchRow]) -> None:
        raise NotImplementedError

    def finish(self, part_id: int = 0) -> SketchRow:
        began = time.perf_counter_ns()
        row = SketchRow(self.method, self.ell, self.d, self.t, n_rows=self.n_rows, n_skipped=self.n_skipped, frob_sq=self.frob_sq, target_sq=self.target_sq, cross=self.cross, basis=np.zeros((0, self.d)), seed=self.seed, part_id=part_id)
        self.fill(row)
        row.train_ns = self.train_ns + time.perf_counter_ns() - began
        return row

    def fill(self, row: SketchRow) -> None:
        raise NotImplementedError


def hash_words(ids: np.ndarray, count: int, seed: int) -> np.ndarray:
    """(rows x count) pseudo-random 64-bit words, a pure function of row hash, column and seed."""
    with np.errstate(over="ignore"):
        lane = np.arange(1, count + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        z = ids.astype(np.int64).view(np.uint64)[:, None] * np.uint64(0xD1342543DE82EF95) + lane[None, :] + np.uint64(seed % (1 << 63)) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return z ^ (z >> np.uint64(31))


def hash_uniform(ids: np.ndarray, count: int, seed: int) -> np.ndarray:
    """Uniform numbers in (0, 1) from :func:`hash_words`."""
    return ((hash_words(ids, count, seed) >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)
