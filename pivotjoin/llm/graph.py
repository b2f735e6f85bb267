"""Connected components of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.tables import connected_components


def components(edges: DataFrame, most_links: int | None = None) -> DataFrame:
    """(u, v) long -> (node, root): root is the smallest node of its component; nodes without edges are absent. most_links: a bound of the number of edges, if known."""
    found = connected_components(edges.select(F.col("u").alias("id_x"), F.col("v").alias("id_y")), most_links=most_links)
    return found.select(F.col("id").alias("node"), F.col("component").alias("root"))
