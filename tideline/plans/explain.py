"""The physical plan of one round under a schedule, without running it."""

from __future__ import annotations

import io
from contextlib import redirect_stdout

from tideline.operators.engine import BucketQueue, initial_state, lazy_round, steady
from tideline.plans.rules import OrderedProgram
from tideline.plans.schedule import Schedule, validate
from tideline.sources.graphs import Graph
from tideline.sources.tables import cut


def explain_schedule(program: OrderedProgram, graph: Graph, schedule: Schedule, start: dict[int, int], frontier: int = 1) -> str:
    """Spark's plan text of a lazy round from ``start``; ``frontier`` is the size that the planner is told."""
    validate(program, schedule)
    with steady(graph.spark, graph.P):
        state = cut(initial_state(program, graph, start, None).repartition(graph.P, "id"))
        q = BucketQueue(program, schedule, state)
        q.cur = 0
        new = lazy_round(q, graph, frontier, schedule.direction == "pull", None)
        told = io.StringIO()
        with redirect_stdout(told):
            new.explain()
        return told.getvalue()
