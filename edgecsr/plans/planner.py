"""Choice of the conversion method from degree statistics."""

from __future__ import annotations

from pyspark.sql import functions as F

from edgecsr.operators.degrees import degrees
from edgecsr.schema import Graph

#: Below this average degree one stage is the better build; measured with bench/workloads at sf0.1.
LOW_AVERAGE = 8.0
#: From this many edges on one exchange of the edges counts for more than anything else.
LARGE = 200_000_000
#: A vertex with this share of all edges makes one task slow unless its edges are split.
HOT_SHARE = 0.02


def choose_method(graph: Graph, avg_degree_threshold: float = LOW_AVERAGE, large: int = LARGE, hot_share: float = HOT_SHARE) -> str:
    """single for low degrees without hubs, sorted for very many edges, staged for the rest."""
    row = degrees(graph.edges).agg(F.sum("degree"), F.count("*"), F.max("degree")).first()
    n, v, top = row[0] or 0, row[1] or 1, row[2] or 0
    if n >= large:
        return "sorted"
    if n / max(v, 1) < avg_degree_threshold and top < max(1, hot_share * n):
        return "single"
    return "staged"
