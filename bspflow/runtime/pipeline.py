"""Chains of jobs over one vertex schema, recovery, and several jobs at once."""

from __future__ import annotations

import threading
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from ..model import Graph
from ..plans.hints import PlanHints
from ..program import Program
from .checkpoint import Checkpointer
from .failure import FailurePolicy
from .loop import Result, run
from .session import shared_folder


@dataclass
class Job:
    program: Program
    hints: PlanHints = PlanHints()
    max_supersteps: int | None = None


def pipeline(graph: Graph, jobs: list[Job], pipelined: bool = True) -> Result:
    """Run jobs one after another on the same vertices.

    Pipelined, a job's final state is the next one's start, with all vertices active and no messages; otherwise the
    state goes through files between jobs, which a failure can go back to.  Jobs must agree on the vertex value.
    """
    kinds = {j.program.value_type for j in jobs}
    if len(kinds) > 1:
        raise ValueError(f"jobs of one pipeline need one vertex schema, not {sorted(kinds)}")
    spark, state, result = graph.spark, None, None
    for number, job in enumerate(jobs):
        result = run(graph, job.program, job.hints, job.max_supersteps, start=state)
        state = result.vertices.select("vid", "value", "degree")
        if not pipelined and number < len(jobs) - 1:
            path = f"{shared_folder(spark)}/pipeline-{id(jobs)}-{number}"
            state.write.mode("overwrite").parquet(path)
            state = spark.read.parquet(path)
    return result


def run_recoverable(graph: Graph, program: Program, path: str, hints: PlanHints = PlanHints(), every: int = 3, max_supersteps: int | None = None, policy: FailurePolicy | None = None, interrupt: Callable[[int], None] | None = None, stop_after: int | None = None) -> Result:
    """Run with a durable checkpoint every ``every`` supersteps; a recoverable failure resumes from the newest one.

    ``interrupt`` is called with the attempt number before each attempt; ``stop_after`` ends the first attempt early.
    """
    keeper, tries = Checkpointer(graph.spark, path), {"n": 0}

    def attempt() -> Result:
        tries["n"] += 1
        if interrupt:
            interrupt(tries["n"])
        early = stop_after if tries["n"] == 1 else None
        result = run(graph, program, hints, max_supersteps, checkpoint=keeper, checkpoint_when=every, resume=True, stop_after=early)
        if early and result.supersteps >= early:
            raise InterruptedError(f"stopped after superstep {early}")
        return result

    return (policy or FailurePolicy()).run(attempt)


class Admission:
    """Lets jobs in while they are few enough and their estimated state fits the budget."""

    def __init__(self, max_jobs: int, budget: int):
        self.max_jobs, self.budget, self.jobs, self.used = max_jobs, budget, 0, 0
        self.changed = threading.Condition()

    def run(self, need: int, job: Callable[[], object]):
        if need > self.budget:
            raise ValueError(f"a job of {need} bytes never fits a budget of {self.budget}")
        with self.changed:
            self.changed.wait_for(lambda: self.jobs < self.max_jobs and self.used + need <= self.budget)
            self.jobs, self.used = self.jobs + 1, self.used + need
        try:
            return job()
        finally:
            with self.changed:
                self.jobs, self.used = self.jobs - 1, self.used - need
                self.changed.notify_all()


def run_concurrent(jobs: list[Callable[[], object]], at_once: int) -> list:
    """Results of jobs run ``at_once`` at a time in one session."""
    with ThreadPoolExecutor(at_once) as pool:
        return list(pool.map(lambda j: j(), jobs))
