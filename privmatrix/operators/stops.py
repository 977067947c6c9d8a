"""Stop conditions of trees: predicates on released or public values of a node, never on its true count."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

ALLOWED = frozenset({"ncount", "depth", "width", "m", "eps_left", "eps_k"})


@dataclass(frozen=True)
class Stop:
    """A SQL predicate over ncount, depth, width (of the next axis), m, eps_k (spent on this level) and eps_left."""

    text: str

    def __post_init__(self) -> None:
        import re

        names = set(re.findall(r"[a-z_][a-z0-9_]*", re.sub(r"'[^']*'", "", self.text.lower()))) - {"and", "or", "not", "true", "false", "sqrt", "pow", "is", "null"}
        if names - ALLOWED:
            raise ValueError(f"a stop condition may not read {sorted(names - ALLOWED)}")

    def column(self) -> Column:
        return F.expr(self.text)


def below(threshold: float) -> Stop:
    """The noisy count is below a threshold."""
    return Stop(f"ncount < {threshold!r}")


def below_noise(times: float = 1.0) -> Stop:
    """The noisy count is below some standard deviations of its own noise."""
    return Stop(f"ncount < {times!r} * sqrt(2.0) / eps_k")


def max_depth(k: int) -> Stop:
    return Stop(f"depth >= {k}")


def min_width(w: int) -> Stop:
    """The next axis is already narrower than w entries."""
    return Stop(f"width < {w}")


def noise_dominated(c: float = 1.0) -> Stop:
    """A child would hold fewer records than c standard deviations of the noise that all remaining budget buys."""
    return Stop(f"ncount / m < {c!r} * sqrt(2.0) / eps_left")


def never() -> Stop:
    return Stop("false")


def any_of(*stops: Stop) -> Stop:
    return Stop(reduce(lambda a, b: f"{a} OR ({b})", [s.text for s in stops[1:]], f"({stops[0].text})"))
