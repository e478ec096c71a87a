"""How an executor's memory is split, and an estimate of a graph's state."""

from __future__ import annotations

from dataclasses import dataclass

from ..model import Graph


@dataclass(frozen=True)
class MemoryProfile:
    """Shares of an executor's memory: a quarter caches tables by default, the rest is for joins and group-bys."""

    cache_share: float = 0.25
    execution_share: float = 0.35

    def to_conf(self) -> dict[str, str]:
        whole = self.cache_share + self.execution_share
        return {"spark.memory.fraction": f"{whole:.2f}", "spark.memory.storageFraction": f"{self.cache_share / whole:.2f}"}


def state_bytes(graph: Graph, per_vertex: int = 40, per_edge: int = 24) -> int:
    """Bytes of state and topology."""
    return graph.vertices.count() * per_vertex + graph.edges.count() * per_edge
