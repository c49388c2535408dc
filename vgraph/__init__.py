"""vgraph: proximity-graph indexes built, pruned, merged, searched and measured with Spark."""

from .facade import Index, build_index, compare, knn_graph, prune

__all__ = ["Index", "build_index", "compare", "knn_graph", "prune"]
