"""Tables, edge lists and label sinks."""

from .edges import from_frames, read_edges, read_snapshots, to_triplets, write_edges, write_labels, write_supra
from .tables import load, register_views

__all__ = ["from_frames", "load", "read_edges", "read_snapshots", "register_views", "to_triplets", "write_edges", "write_labels", "write_supra"]
