"""How an ordered program runs, apart from what it computes."""

from __future__ import annotations

from dataclasses import dataclass, fields, replace

from tideline.plans.rules import OrderedProgram, check_monotone, constant_sum, eager_legal

UPDATES = ("lazy", "lazy_count", "eager", "eager_fused")
DIRECTIONS = ("push", "pull", "auto")
UNBOUNDED = 1 << 62


@dataclass(frozen=True)
class Schedule:
    """``update``: how buckets are kept. ``delta``: priorities a bucket spans. ``fuse_limit``: the largest local bucket that
    is worked off without a barrier. ``direction``: push, pull, or by the frontier's out-degree each round.
    ``open_buckets``: buckets kept at hand, later ones wait in an overflow (0: all). ``width``: buckets taken in one round
    (1: exact order). ``plan_hops``: hops of one bucket in one plan. ``callback``: bucket ids by a Python function.
    ``blocks``/``layout``: how eager runs cut the graph (0: by its edges). ``balance``: vertex, edge or salted frontiers."""

    update: str = "lazy"
    delta: int = 1
    fuse_limit: int = UNBOUNDED
    direction: str = "push"
    open_buckets: int = 0
    width: int = 1
    plan_hops: int = 1
    callback: bool = False
    blocks: int = 0
    layout: str = "range"
    balance: str = "vertex"
    auto_ratio: float = 0.05

    def with_(self, **changes) -> Schedule:
        return replace(self, **changes)

    @staticmethod
    def parse(text: str) -> Schedule:
        """From ``key=value`` words, for example ``update=eager_fused delta=4096``."""
        kinds = {f.name: type(f.default) for f in fields(Schedule)}
        out = {}
        for word in text.replace(",", " ").split():
            key, sep, value = word.partition("=")
            if not sep or key not in kinds:
                raise ValueError(f"unknown option {word!r}")
            out[key] = value.lower() in ("1", "true", "yes") if kinds[key] is bool else kinds[key](value)
        return Schedule(**out)

    def text(self) -> str:
        """Only what differs from the defaults."""
        return " ".join(f"{f.name}={getattr(self, f.name)}" for f in fields(self) if getattr(self, f.name) != f.default) or "default"


PRESETS = {
    "lazy": Schedule(),
    "lazy_count": Schedule(update="lazy_count"),
    "eager_plain": Schedule(update="eager", fuse_limit=0),
    "eager_fused": Schedule(update="eager_fused"),
    "lazy_callback": Schedule(callback=True, direction="auto"),
    "relaxed": Schedule(width=4),
    "unordered_push": Schedule(delta=UNBOUNDED),
    "unordered_switching": Schedule(delta=UNBOUNDED, direction="auto"),
}


def validate(program: OrderedProgram, s: Schedule) -> None:
    """Raises ValueError where the schedule isn't legal for the program."""

    def need(ok: bool, why: str) -> None:
        if not ok:
            raise ValueError(f"{program.name}: {why}")

    need(s.update in UPDATES, f"unknown update {s.update}")
    need(s.direction in DIRECTIONS, f"unknown direction {s.direction}")
    need(s.balance in ("vertex", "edge", "salted"), f"unknown balance {s.balance}")
    need(s.delta >= 1 and s.width >= 1 and s.plan_hops >= 1 and s.open_buckets >= 0 and s.blocks >= 0 and s.fuse_limit >= 0, "numbers must not be below their least value")
    mono = check_monotone(program.spec, program.rule)
    need(mono.ok, mono.reason)
    eager = s.update in ("eager", "eager_fused")
    need(bool(program.hooks) == (program.rule.kind == "hook"), "hooks and the rule of that kind belong together")
    need(not (program.hooks and (s.update != "lazy" or s.callback or s.plan_hops > 1 or s.open_buckets)), "hooks run in plain lazy rounds")
    need(not (eager and s.direction != "push"), "eager updates only push")
    need(not (s.update == "lazy_count" and not constant_sum(program.rule)), "updates aren't a constant sum")
    need(program.spec.coarsen or s.delta == 1, "its order must be strict, so delta is 1")
    need(program.spec.coarsen or s.width == 1 or bool(program.hooks), "its order must be strict, so width is 1")
    if eager:
        verdict = eager_legal(program)
        need(verdict.ok, verdict.reason)
    need(not (s.update == "eager_fused" and program.rule.kind == "add"), "fusion needs a rule that sets priorities")
    need(not (eager and program.rule.kind == "raise"), "eager bins are kept for lower and add rules")
    need(not (s.plan_hops > 1 and (eager or program.rule.kind == "add")), "chained hops are for lazy rules that set priorities")
    need(not (s.open_buckets and (eager or program.rule.kind == "add" or s.plan_hops > 1)), "an overflow is for lazy rules that set priorities")
