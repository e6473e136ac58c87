"""Connected components by repeated contraction.

Each round every node points to the neighbour of smallest hashed name, if that is smaller than its
own, and the edges are rewritten by these pointers. Hashed names make the shrinking geometric whatever
the shape of the graph. Rounds are stored tables; nothing is gathered on the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frsketch.llm.shared import drop_stored, stored


def roots(nodes: DataFrame, edges: DataFrame, node: str = "node") -> DataFrame:
    """nodes (``node``) with ``root``, the same for all nodes of a component. edges: (u, v), any
    direction, repeats and loops allowed; null ends are no edges."""
    edges = stored(edges.where("u is not null and v is not null and u <> v").select("u", "v"), "edges")
    maps = []
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        best = both.groupBy("u").agg(F.min(F.struct(F.xxhash64("v").alias("h"), F.col("v").alias("to"))).alias("m"))
        step = stored(best.where(F.struct(F.xxhash64("u").alias("h"), F.col("u").alias("to")) > F.col("m")).select(F.col("u").alias("from"), F.col("m.to").alias("to")), "pointers")
        maps.append(step)
        left = edges.join(step.withColumnsRenamed({"from": "u", "to": "u2"}), "u", "left")
        left = left.join(step.withColumnsRenamed({"from": "v", "to": "v2"}), "v", "left")
        left = left.select(F.coalesce("u2", "u").alias("u"), F.coalesce("v2", "v").alias("v")).where("u <> v")
        left = left.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()
        fresh = stored(left, "edges")
        drop_stored(edges)
        edges = fresh
    drop_stored(edges)
    out = nodes.select(node, F.col(node).alias("root"))
    for step in maps:
        out = out.join(step.withColumnsRenamed({"from": "root", "to": "_to"}), "root", "left").select(node, F.coalesce("_to", "root").alias("root"))
    return out
