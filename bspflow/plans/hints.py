"""The physical choices of a job: 2 stores x 2 joins x 4 message group-bys."""

from __future__ import annotations

from dataclasses import dataclass
from enum import Enum
from itertools import product


class Join(Enum):
    FULL = "full"  # merge messages with all vertices
    LEFT = "left"  # probe vertices for messages and live vertices only
    AUTO = "auto"  # FULL or LEFT by the share of active vertices of the step before


class GroupBy(Enum):
    SORT = "sort"
    HASH = "hash"


class Connector(Enum):
    PLAIN = "plain"  # partition; the receiver groups again
    MERGE = "merge"  # partition and sort; the receiver groups in one pass


class Store(Enum):
    SNAPSHOT = "snapshot"  # every step writes the whole state
    DELTA_LOG = "delta_log"  # every step adds the changed rows; folded now and then


@dataclass(frozen=True)
class PlanHints:
    join: Join = Join.FULL
    groupby: GroupBy = GroupBy.SORT
    connector: Connector = Connector.PLAIN
    store: Store = Store.SNAPSHOT
    partitions: int | None = None
    #: AUTO takes LEFT while (live + receivers) / vertices is below this
    sparse_below: float = 0.1
    #: layers of changed rows kept before they are merged
    fold_every: int = 8


def all_plans() -> list[PlanHints]:
    """The 16 plans that users choose from."""
    return [PlanHints(j, g, c, s) for s, j, g, c in product(Store, (Join.FULL, Join.LEFT), GroupBy, Connector)]
