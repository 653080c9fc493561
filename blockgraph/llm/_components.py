"""Connected components by alternating large-star and small-star, its rounds in the scratch folder of this package."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..plans import stars
from ._common import forget, materialise


def components(edges: DataFrame, label: str = "components", rounds: int = 200) -> DataFrame:
    """node, root for each node of edges(a, b), long ids; root is the smallest id reachable. Self-loops are ignored."""
    return stars.components(edges, label, rounds, materialise, forget)
