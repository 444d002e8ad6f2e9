"""The methods: Leiden and its kin, spectral clustering, windows and sweeps."""

from .leiden import baseline_multislice_sequential, coupling_profile, independent_snapshots, leiden, louvain, resolution_profile, windowed
from .spectral import estimate_k, fiedler_split, modularity_bisect, spectral_clustering

__all__ = [
    "baseline_multislice_sequential",
    "coupling_profile",
    "estimate_k",
    "fiedler_split",
    "independent_snapshots",
    "leiden",
    "louvain",
    "modularity_bisect",
    "resolution_profile",
    "spectral_clustering",
    "windowed",
]
