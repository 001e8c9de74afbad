"""A search for a good schedule: an ensemble of techniques, each credited with its recent successes."""

from __future__ import annotations

import random
import time
from collections.abc import Callable
from dataclasses import dataclass, field

from tideline.operators.engine import OrderedResult
from tideline.plans.rules import OrderedProgram
from tideline.plans.schedule import Schedule, validate

SPACE: dict[str, list] = {
    "update": ["lazy", "lazy_count", "eager", "eager_fused"],
    "delta": [1 << k for k in range(18)],
    "fuse_limit": [0, 64, 1024, 1 << 62],
    "direction": ["push", "pull", "auto"],
    "blocks": [1, 4, 8, 32],
    "layout": ["range", "hash"],
    "balance": ["vertex", "salted"],
    "plan_hops": [1, 2, 4],
}


@dataclass
class TuneReport:
    best: Schedule
    best_seconds: float
    seconds: float
    trials: list[tuple[Schedule, float]] = field(default_factory=list)

    def gap(self, hand_tuned_seconds: float) -> float:
        """How much slower than a schedule chosen by hand, as a share."""
        return self.best_seconds / hand_tuned_seconds - 1


def legal(program: OrderedProgram, s: Schedule) -> bool:
    try:
        validate(program, s)
        return True
    except ValueError:
        return False


def autotune(program: OrderedProgram, run: Callable[[Schedule], OrderedResult], limit_s: float = 300, max_trials: int = 40, seed: int = 1, space: dict[str, list] | None = None) -> TuneReport:
    """Tries schedules of ``space`` that are legal for the program until the time or the trials are used up.

    The techniques: a random schedule, one option of the best one changed, the best two crossed, the best one's bucket
    width doubled or halved. A technique is chosen by its share of recent improvements, every fourth time at random.
    """
    rng, space, began = random.Random(seed), space or SPACE, time.monotonic()
    seen: dict[Schedule, float] = {}
    credit = {k: [1] for k in ("random", "mutate", "cross", "climb")}

    def draw(kind: str) -> Schedule:
        best = sorted(seen, key=seen.get)[:2]
        if kind == "random" or not best:
            return Schedule(**{k: rng.choice(v) for k, v in space.items()})
        if kind == "mutate" or kind == "cross" and len(best) < 2:
            k = rng.choice(list(space))
            return best[0].with_(**{k: rng.choice(space[k])})
        if kind == "cross":
            return best[0].with_(**{k: getattr(rng.choice(best), k) for k in space})
        return best[0].with_(delta=max(1, best[0].delta * 2 if rng.random() < 0.5 else best[0].delta // 2))

    start = Schedule()
    while len(seen) < max_trials and time.monotonic() - began < limit_s:
        kind = rng.choice(list(credit)) if rng.random() < 0.25 else max(credit, key=lambda k: sum(credit[k][-5:]) / len(credit[k][-5:]) + 0.01 * rng.random())
        s = start if not seen else next((x for x in (draw(kind if i < 50 else "random") for i in range(500)) if x not in seen and legal(program, x)), None)
        if s is None:
            break
        t = time.monotonic()
        run(s)
        took = time.monotonic() - t
        credit[kind].append(int(not seen or took < min(seen.values())))
        seen[s] = took
    best = min(seen, key=seen.get)
    return TuneReport(best, seen[best], time.monotonic() - began, list(seen.items()))
