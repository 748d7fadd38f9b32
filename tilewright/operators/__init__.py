"""Routing of boxes to tiles, tile-parallel joins and queries on staged tiles."""
