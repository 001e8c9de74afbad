"""What an ordered algorithm declares: its priority, its edge rule, when it stops; and what can be read off that."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column


@dataclass(frozen=True)
class PrioritySpec:
    """``order``: low or high priorities first. ``coarsen``: whether buckets may span more than one priority.

    The priority of a vertex is its value plus ``h``, which the run may give for each vertex (0 otherwise): the start values and
    ``h`` come with the run, so one specification serves all starts.
    """

    order: str = "low"
    coarsen: bool = True


@dataclass(frozen=True)
class EdgeRule:
    """What an edge out of the bucket does to its target: ``lower`` or ``raise`` to a value, or ``add`` to it.

    ``new``: from the source's value and the edge's weight (columns) to the offered value. ``delta``: what ``add`` adds,
    a number or a Column of the edge, whose ``sign`` (1 or -1) must then be told; ``floor``: the least result of an addition, a number
    or ``current``. The kind ``hook`` sends nothing along edges: the program's hooks say what becomes of the bucket.
    """

    kind: str
    new: Callable[[Column, Column], Column] | None = None
    delta: int | Callable[[Column], Column] | None = None
    floor: int | str | None = None
    sign: int = 0

    @staticmethod
    def lower(new: Callable[[Column, Column], Column]) -> EdgeRule:
        return EdgeRule("lower", new)

    @staticmethod
    def raise_(new: Callable[[Column, Column], Column]) -> EdgeRule:
        return EdgeRule("raise", new)

    @staticmethod
    def add(delta: int | Callable[[Column], Column], floor: int | str | None = None, sign: int = 0) -> EdgeRule:
        return EdgeRule("add", None, delta, floor, (delta > 0) - (delta < 0) if isinstance(delta, int) else sign)


@dataclass(frozen=True)
class OrderedProgram:
    """An algorithm without a word on how it runs.

    ``hooks``: outside code that looks at the bucket. A round calls each with the bucket's rows (``[id, value]``), its number and the
    number of the round; it returns ``[id, new, keep]``: the value that each of these vertices has now, and whether it stays active.
    """

    name: str
    spec: PrioritySpec
    rule: EdgeRule
    family: str = "sssp"
    hooks: tuple = ()
    labels: dict = field(default_factory=dict)

    def label(self, name: str, schedule) -> OrderedProgram:
        """The same program with a schedule remembered under a name."""
        return OrderedProgram(self.name, self.spec, self.rule, self.family, self.hooks, self.labels | {name: schedule})


@dataclass(frozen=True)
class Verdict:
    ok: bool
    reason: str = ""


@dataclass(frozen=True)
class ConstSum:
    """An addition whose amount and floor are the same for all edges."""

    delta: int
    floor: int | str | None


def constant_sum(rule: EdgeRule) -> ConstSum | None:
    """Whether updates can travel as counts: one ``add`` of a literal amount."""
    return ConstSum(rule.delta, rule.floor) if rule.kind == "add" and isinstance(rule.delta, int) and rule.delta else None


def eager_legal(program: OrderedProgram) -> Verdict:
    """Eager bins need the plain pop, apply, done loop: nothing else may look at the bucket."""
    return Verdict(False, "the bucket is used outside the edge rule") if program.hooks else Verdict(True)


def conflicts(direction: str) -> bool:
    """Whether targets are written from several partitions, so that messages need an exchange."""
    return direction != "pull"


def check_monotone(spec: PrioritySpec, rule: EdgeRule) -> Verdict:
    """Priorities may only move one way; which way a rule moves them must fit what is taken first."""
    if rule.kind == "lower" and spec.order != "low" or rule.kind == "raise" and spec.order != "high":
        return Verdict(False, f"rule {rule.kind} under order {spec.order}")
    if rule.kind == "add" and not rule.sign:
        return Verdict(False, "an addition of nothing, or of a sign that isn't told")
    if rule.kind == "add" and spec.order == "low" and rule.sign < 0 and rule.floor != "current":
        return Verdict(False, "priorities may fall below the bucket in hand: the floor must be the current one")
    if rule.kind == "add" and spec.order == "high" and rule.sign > 0:
        return Verdict(False, "priorities may rise above the bucket in hand")
    return Verdict(True)
