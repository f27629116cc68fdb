"""Where graphs come from: the given tables, edge-list files and synthetic families."""
