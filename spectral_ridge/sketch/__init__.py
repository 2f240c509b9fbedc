"""NumPy kernels of the sketches; no Spark here."""

from .base import SketchRow, Sketcher
from .linear import CountSketcher, ExactSketcher, SignSketcher, StructuredSketcher
from .spectral import SpectralSketcher
from .two_level import TwoLevelSketcher

SPECTRAL = ("fd_ridge", "robust_fd_ridge", "truncated_svd_ridge")
ADDITIVE = ("exact_ridge", "sign_projection_ridge", "count_sketch_ridge", "srht_ridge")
METHODS = (*SPECTRAL, "two_level_ridge", *ADDITIVE)


def make_sketcher(method: str, ell: int, n_features: int, n_targets: int = 1, seed: int = 0, **options) -> Sketcher:
    """The sketcher of a method id; unknown names are an error that lists the known ones."""
    kinds = {
        "fd_ridge": SpectralSketcher, "robust_fd_ridge": SpectralSketcher, "truncated_svd_ridge": SpectralSketcher, "two_level_ridge": TwoLevelSketcher, "exact_ridge": ExactSketcher, "sign_projection_ridge": SignSketcher, "count_sketch_ridge": CountSketcher, "srht_ridge": StructuredSketcher,
    }
    if method not in kinds:
        raise ValueError(f"unknown method {method!r}; known: {', '.join(METHODS)}")
    return kinds[method](method, ell, n_features, n_targets, seed, **options)


__all__ = ["ADDITIVE", "METHODS", "SPECTRAL", "SketchRow", "Sketcher", "make_sketcher"]
