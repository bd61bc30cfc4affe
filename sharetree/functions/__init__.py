"""Part of the path query engine."""
