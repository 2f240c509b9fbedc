"""Shrinking spectral sketches: plain, robust and truncated, over dense or sparse rows."""

from __future__ import annotations

import numpy as np

from .base import SketchRow, Sketcher, hash_words


def factor(stack: np.ndarray, how: str = "direct") -> tuple[np.ndarray, np.ndarray]:
    """Singular values (descending) and right vectors as rows. ``row_gram`` goes through the
    small Gram matrix of the rows: faster for wide rows, half the digits."""
    if how == "direct" or len(stack) > stack.shape[1]:
        _, s, v = np.linalg.svd(stack, full_matrices=False)
    elif how == "row_gram":
        lam, u = np.linalg.eigh(stack @ stack.T)
        lam, u = lam[::-1], u[:, ::-1]
        keep = lam > np.finfo(float).eps * max(float(lam[0]) if len(lam) else 0.0, 1e-300) * len(stack)
        s = np.sqrt(lam[keep])
        v = (u[:, keep] / s).T @ stack
        if len(v) and np.abs(v @ v.T - np.eye(len(v))).max() > 1e-8:
            q, r = np.linalg.qr(v.T)
            v = (q * np.sign(np.diag(r))).T
    else:
        raise ValueError("svd must be 'direct' or 'row_gram'")
    live = s > 1e-14 * (s[0] if len(s) else 1.0)
    return s[live], v[live]


class SpectralSketcher(Sketcher):
    """Keeps at most ``ell`` directions: stack kept spectrum and new rows, factor, lower all
    squared singular values by the first one beyond the kept ones.

    ``shrink_at``: "ell_plus_1" keeps ``ell`` directions and removes the next squared value;
    "ell" removes the last kept one and so keeps ``ell`` - 1. ``batch_rows``: new rows per
    factorisation (default ``ell``). The truncated method lowers nothing. The removed amount is
    ``shrink_total``; the robust method adds half of it to the penalty when solving, so its sketch
    equals the plain one.
    """

    def setup(self, batch_rows: int | None = None, shrink_at: str = "ell_plus_1", svd: str = "direct") -> None:
        if shrink_at not in ("ell_plus_1", "ell"):
            raise ValueError("shrink_at must be 'ell_plus_1' or 'ell'")
        self.batch_rows, self.shrink_at, self.svd = int(batch_rows or self.ell), shrink_at, svd
        self.shrinks = self.method != "truncated_svd_ridge"
        self.sigma, self.basis = np.zeros(0), np.zeros((0, self.d))
        self.pending: list[np.ndarray] = []
        self.held = 0
        self.shrink_total = self.dropped_total = 0.0
        self.n_svd = 0

    def absorb(self, x: np.ndarray, y: np.ndarray, ids: np.ndarray) -> None:
        at = 0
        while at < len(x):
            take = min(self.batch_rows - self.held, len(x) - at)
            self.pending.append(x[at : at + take])
            self.held, at = self.held + take, at + take
            if self.held >= self.batch_rows:
                self.flush()

    def flush(self) -> None:
        if self.held:
            rows = np.concatenate(self.pending)
            self.pending, self.held = [], 0
            self.compress(rows)

    def compress(self, rows: np.ndarray) -> None:
        sigma, basis = factor(np.concatenate([self.sigma[:, None] * self.basis, rows]), self.svd)
        self.n_svd += 1
        square, ell = sigma**2, self.ell
        if not self.shrinks:
            self.dropped_total += float(square[ell]) if len(square) > ell else 0.0
            self.sigma, self.basis = sigma[:ell], basis[:ell]
            return
        at = ell if self.shrink_at == "ell_plus_1" else ell - 1
        delta = float(square[at]) if len(square) > at else 0.0
        self.shrink_total += delta
        left = np.maximum(square[:ell] - delta, 0.0)
        live = left > 0
        self.sigma, self.basis = np.sqrt(left[live]), basis[:ell][live]

    def absorb_sketches(self, rows: list[SketchRow]) -> None:
        self.flush()
        for r in rows:
            self.shrink_total += r.shrink_total
            self.dropped_total += r.dropped_total
            self.n_svd += r.n_svd
        stacks = [r.sigma[:, None] * r.basis for r in rows if len(r.sigma)]
        if stacks:
            self.compress(np.concatenate(stacks))  # one shrink for the whole merge

    def fill(self, row: SketchRow) -> None:
        self.flush()
        row.sigma, row.basis, row.rank = self.sigma, self.basis, len(self.sigma)
        row.shrink_total, row.dropped_total, row.n_svd = self.shrink_total, self.dropped_total, self.n_svd


class SparseRows:
    """Rows as parallel arrays of (row, column, value), sorted by row."""

    def __init__(self, indptr: np.ndarray, columns: np.ndarray, values: np.ndarray, width: int):
        self.indptr, self.columns, self.values, self.width = indptr, columns, values, width
        self.rows = np.repeat(np.arange(len(indptr) - 1), np.diff(indptr))
        self.by_column = np.argsort(columns, kind="stable")

    def __len__(self) -> int:
        return len(self.indptr) - 1

    @staticmethod
    def _sum_by(key: np.ndarray, parts: np.ndarray, size: int) -> np.ndarray:
        out = np.zeros((size, parts.shape[1]))
        if len(key):
            at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            out[key[at]] = np.add.reduceat(parts, at, axis=0)
        return out

    def times(self, right: np.ndarray) -> np.ndarray:
        """This matrix times a dense (width x k) one."""
        return self._sum_by(self.rows, self.values[:, None] * right[self.columns], len(self))

    def transposed_times(self, right: np.ndarray) -> np.ndarray:
        """This matrix's transpose times a dense (rows x k) one."""
        o = self.by_column
        return self._sum_by(self.columns[o], self.values[o, None] * right[self.rows[o]], self.width)


class SparseSpectralSketcher(SpectralSketcher):
    """The plain sketch over sparse rows, in time that follows the non-zeros.

    Rows wait until they hold ``ell * n_features`` non-zeros (or ``max_rows`` rows); a few block
    power steps from a hashed start then find their leading directions, and their projection is
    folded in like dense rows. What the projection leaves out is bounded by its squared norm,
    which goes to ``dropped_total``, so the certificate stays valid.
    """

    def setup(self, power_steps: int = 4, max_rows: int = 20_000, **options) -> None:
        super().setup(**options)
        self.power_steps, self.max_rows = power_steps, max_rows
        self.waiting: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.waiting_rows = self.waiting_values = 0

    def update_sparse(self, lengths: np.ndarray, columns: np.ndarray, values: np.ndarray, y: np.ndarray) -> None:
        """Fold sparse rows in: entries of each row, their columns and values, and the targets.
        Entries of one row and column add up."""
        owner = np.repeat(np.arange(len(lengths)), lengths)
        place, at = np.unique(owner * self.d + np.asarray(columns, dtype=np.int64), return_inverse=True)
        values = np.bincount(at, weights=np.asarray(values, dtype=np.float64), minlength=len(place))
        place, values = place[values != 0], values[values != 0]
        lengths, columns = np.bincount(place // self.d, minlength=len(lengths)), place % self.d
        y = np.asarray(y, dtype=np.float64).reshape(len(lengths), self.t)
        rows = SparseRows(np.concatenate([[0], np.cumsum(lengths)]), columns.astype(np.int64), values.astype(np.float64), self.d)
        self.cross += rows.transposed_times(y)
        self.frob_sq += float(np.vdot(rows.values, rows.values))
        self.target_sq += float(np.vdot(y, y))
        self.n_rows += len(lengths)
        self.waiting.append((np.asarray(lengths), rows.columns, rows.values))
        self.waiting_rows += len(lengths)
        self.waiting_values += len(values)
        if self.waiting_values >= self.ell * self.d or self.waiting_rows >= self.max_rows:
            self.flush_sparse()

    def flush_sparse(self) -> None:
        if not self.waiting_rows:
            return
        lengths, columns, values = (np.concatenate(x) for x in zip(*self.waiting, strict=True))
        self.waiting, self.waiting_rows, self.waiting_values = [], 0, 0
        rows = SparseRows(np.concatenate([[0], np.cumsum(lengths)]), columns, values, self.d)
        width = min(self.ell + 8, self.d)
        start = np.where(hash_words(np.arange(self.d), width, self.seed + self.n_svd) & np.uint64(1), 1.0, -1.0)
        start[:, : min(len(self.basis), width)] = self.basis[:width].T
        q = np.linalg.qr(start)[0]
        for _ in range(self.power_steps):
            q = np.linalg.qr(rows.transposed_times(rows.times(q)))[0]
        z = np.linalg.qr(rows.times(q))[0]  # left directions
        projected = rows.transposed_times(z).T
        self.dropped_total += max(0.0, float(np.vdot(values, values)) - float(np.vdot(projected, projected)))
        self.compress(projected)

    def fill(self, row: SketchRow) -> None:
        self.flush_sparse()
        super().fill(row)

    def absorb_sketches(self, rows: list[SketchRow]) -> None:
        self.flush_sparse()
        super().absorb_sketches(rows)
