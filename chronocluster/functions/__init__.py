"""Scalar relations of the detectability and spectral theory, and Arrow-batched functions."""

from .scalars import affinity_lambda, affinity_rates, cheeger_bounds, detectability, register
from .udf import WindowsOf, adjacency_spectrum, cosine, register_windows, slice_spectra

__all__ = ["WindowsOf", "adjacency_spectrum", "affinity_lambda", "affinity_rates", "cheeger_bounds", "cosine", "detectability", "register", "register_windows", "slice_spectra"]
