"""Vertex stores: whole snapshots, or a base with a log of changed rows that is merged now and then."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .hints import PlanHints, Store


class VertexStore:
    """The current state of all vertices, partitioned by vid.

    DELTA_LOG keeps the rows that a superstep changed as a layer of its own.  Layers are merged among themselves when
    there are ``fold_every`` of them, and into the base when they hold half as many rows as it does; so a superstep
    costs what it changes, and the base is rewritten a few times in a run.
    """

    def __init__(self, state: DataFrame, hints: PlanHints, pin):
        self.hints, self.pin, self.columns, self.held = hints, pin, state.columns, None
        self.replace(state)

    def _numbered(self, rows: DataFrame) -> DataFrame:
        return rows.selectExpr(*self.columns, f"{len(self.deltas)} AS version")

    def _newest(self, rows: DataFrame, *more: str) -> DataFrame:
        """Of rows of several layers the last one of each vertex; ``more`` are equal for all rows of a vertex."""
        cols = ", ".join([*[c for c in self.columns if c != "vid"], *more])
        return rows.groupBy("vid").agg(F.expr(f"max_by(struct({cols}), version) AS row")).selectExpr("vid", "row.*")

    def read(self) -> DataFrame:
        """Newest row of every vertex."""
        return self._newest(self.layers) if self.deltas else self.base

    def probe(self, active: DataFrame) -> DataFrame:
        """Newest rows of the vertices in ``active``(vid, payload), with their payload.

        The active set is the build side of a hash join that streams each layer, so nothing of the size of all
        vertices is sorted, grouped or exchanged; only what was found is folded.
        """
        if not self.held:  # layers are looked through again and again
            self.held = self.base.persist()
        asked = active.select("vid", "payload").hint("shuffle_hash")
        if not self.deltas:
            return self.base.join(asked, "vid")
        return self._newest(self.layers.join(asked, "vid"), "payload")

    def release(self) -> None:
        if self.held:
            self.held.unpersist()
        self.held = None

    def replace(self, state: DataFrame) -> None:
        self.release()
        self.base, self.deltas, self.delta_rows = state, [], 0
        #: all rows with the number of their layer; a union keeps the partitioning, so nothing is exchanged
        self.layers = self._numbered(state)

    def _append(self, changed: DataFrame) -> None:
        self.deltas.append(changed)
        self.layers = self.layers.unionByName(self._numbered(changed))

    def upsert(self, changed: DataFrame, n_changed: int, n_vertices: int) -> None:
        """Add the ``n_changed`` rows that are new or changed; ``n_vertices`` is how many vertices there are."""
        if not n_changed:
            return
        if self.hints.store is not Store.DELTA_LOG:
            kept = self.base.join(changed.select("vid").hint("shuffle_hash"), "vid", "left_anti")
            self.replace(self.pin(kept.unionByName(changed.select(*self.columns))))
            return
        self._append(changed)
        self.delta_rows += n_changed
        if 2 * self.delta_rows >= n_vertices:
            self.replace(self.pin(self.read().select(*self.columns)))
        elif len(self.deltas) >= self.hints.fold_every:
            merged = self.pin(self._newest(self.layers.where("version > 0")).select(*self.columns))
            self.deltas = []
            self.layers = self._numbered(self.base)
            self._append(merged)
