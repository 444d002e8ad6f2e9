"""Snapshots from a stream of events."""

from .build import dedup, events_stream, run_counted, run_to_table, running_degrees, session_contacts, sliding_counts, stream_contacts, tumbling_edges, warm_communities

__all__ = ["dedup", "events_stream", "run_counted", "run_to_table", "running_degrees", "session_contacts", "sliding_counts", "stream_contacts", "tumbling_edges", "warm_communities"]
