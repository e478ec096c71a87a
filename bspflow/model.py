"""Relations of the engine: vertices, edges, messages and mutations, and the schemas they have.

Two layouts: SPLIT keeps the state (vid, halt, value, degree) apart from an immutable topology (src, dst, weight), so a
superstep rewrites state only and a hub is many rows; NESTED keeps a vertex's edges inside its row, for programs that
change their edges.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Graph:
    """``vertices``(vid long, ...) and directed ``edges``(src long, dst long, weight long)."""

    vertices: DataFrame
    edges: DataFrame

    @staticmethod
    def of(edges: DataFrame, symmetric: bool = False, vertices: DataFrame | None = None, complete: bool = True) -> Graph:
        """A graph from listed pairs; ``symmetric`` adds the reverse of each, ``complete`` adds endpoints as vertices."""
        if symmetric:
            edges = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")).distinct()
        ends = edges.select(F.col("src").alias("vid")).union(edges.select(F.col("dst").alias("vid")))
        if vertices is None:
            vertices = ends.distinct() if complete else edges.select(F.col("src").alias("vid")).distinct()
        elif complete:
            vertices = vertices.select("vid").union(ends).distinct()
        return Graph(vertices, edges)

    @property
    def spark(self):
        return self.vertices.sparkSession


def vertex_schema(value: str, edge: str = "long") -> str:
    """The nested vertex relation."""
    return f"vid long, halt boolean, value {value}, edges array<struct<dst:long,value:{edge}>>"


def msg_schema(payload: str) -> str:
    """Combined messages, one row a destination."""
    return f"vid long, payload {payload}"


def mutation_schema(value: str, edge: str = "long") -> str:
    """Insertions ('I') and deletions ('D') of vertices."""
    return f"vid long, op string, vertex struct<value:{value},edges:array<struct<dst:long,value:{edge}>>>"
