"""Containment of a small pattern as a chain of equi-joins on the graph id."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Graph


def embeddings(vertices: DataFrame, edges: DataFrame, pattern: Graph) -> DataFrame:
    """``(g, v0, v1, ...)``: every embedding of a connected pattern with one to four edges.

    One join per edge; labels are filtered before. Edges bucketed or partitioned by graph need no further exchange.
    """
    own = pattern.edges()
    if not 1 <= len(own) <= 4:
        raise ValueError("patterns of one to four edges")
    lab = vertices.select("g", "v", F.col("l").alias("vl"))
    arcs = edges.select("g", F.col("a").alias("x"), F.col("b").alias("y"), "l").unionByName(edges.select("g", F.col("b").alias("x"), F.col("a").alias("y"), "l"))
    arcs = arcs.join(lab.select("g", F.col("v").alias("x"), F.col("vl").alias("lx")), ["g", "x"]).join(lab.select("g", F.col("v").alias("y"), F.col("vl").alias("ly")), ["g", "y"])
    bound, out, left = set(), None, list(own)
    while left:
        edge = next((e for e in left if not bound or e[0] in bound or e[1] in bound), None)
        if edge is None:
            raise ValueError("the pattern is not connected")
        left.remove(edge)
        u, w, label = edge
        if bound and u not in bound:
            u, w = w, u
        step = arcs.where((F.col("l") == label) & (F.col("lx") == pattern.labels[u]) & (F.col("ly") == pattern.labels[w])).select("g", F.col("x").alias(f"v{u}"), F.col("y").alias(f"v{w}"))
        if out is None:
            out = step
        elif w in bound:
            out = out.join(step, ["g", f"v{u}", f"v{w}"])
        else:
            out = out.join(step, ["g", f"v{u}"])
            for t in bound - {u}:
                out = out.where(F.col(f"v{t}") != F.col(f"v{w}"))
        bound |= {u, w}
    return out.select("g", *[f"v{i}" for i in range(len(pattern.labels))])


def match(vertices: DataFrame, edges: DataFrame, pattern: Graph) -> DataFrame:
    """``(g)`` of the graphs that contain the pattern."""
    return embeddings(vertices, edges, pattern).select("g").distinct()
