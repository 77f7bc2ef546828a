"""Table readers and the shared working folder."""

from reportgraph.sources.io import checkpointed, read_table, shared_dir

__all__ = ["checkpointed", "read_table", "shared_dir"]
