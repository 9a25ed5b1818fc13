"""Approximate neighbourhood analytics on large graphs: one mergeable sketch of the neighbours of each vertex."""

__version__ = "0.1.0"
