"""The applications as vertex programs."""

from .components import ConnectedComponents, component_sizes, connected_components, min_reaching_id
from .pagerank import PageRank, pagerank, pagerank_converged, top_ranked
from .paths import UNREACHED, ShortestPaths, sssp

__all__ = [
    "UNREACHED",
    "ConnectedComponents",
    "PageRank",
    "ShortestPaths",
    "component_sizes",
    "connected_components",
    "min_reaching_id",
    "pagerank",
    "pagerank_converged",
    "sssp",
    "top_ranked",
]
