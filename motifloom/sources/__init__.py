"""Sources of data graphs."""

from motifloom.sources.builders import BUILDERS, Builder, table
from motifloom.sources.readers import read_edges, write_adjacency, write_matches
from motifloom.sources.synthetic import synthetic

__all__ = ["BUILDERS", "Builder", "read_edges", "synthetic", "table", "write_adjacency", "write_matches"]
