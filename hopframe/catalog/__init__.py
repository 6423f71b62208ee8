"""The graph mapping: where labels and relationship types live in existing tables."""

from hopframe.catalog.model import EdgeMap, End, GraphMap, NodeMap

__all__ = ["EdgeMap", "End", "GraphMap", "NodeMap"]
