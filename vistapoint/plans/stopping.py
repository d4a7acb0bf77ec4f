"""When clustered sampling stops: measures of change and rules, in one place for all its modes, open to additions.

Both are plain formulas in operators that columns and numbers share, so a rule is written once and runs in a plan, in a task
and on the driver alike.
"""

from __future__ import annotations

from collections.abc import Callable
from typing import Any

from ..functions.intention import FIXED

#: (largest sum now, before, share seen now, before, absolute value, larger of two) -> how far the maximum moved.
MEASURES: dict[str, Callable[..., Any]] = {
    "raw": lambda now, before, p, q, size, larger: size(now - before) / FIXED,
    "relative": lambda now, before, p, q, size, larger: size(now - before) / larger(now, 1),
    "rescaled": lambda now, before, p, q, size, larger: size(now / p - before / q) / FIXED,
    "rescaled_relative": lambda now, before, p, q, size, larger: size(now / p - before / q) / larger(now / p, 1.0),
}

#: (options, change of the maximum, movement of the list in metres) -> whether to stop.
RULES: dict[str, Callable[..., Any]] = {
    "max_change": lambda o, d_max, d_topk: d_max < o.threshold,
    "topk_shift": lambda o, d_max, d_topk: d_topk < o.shift_threshold_m,
    "any_of": lambda o, d_max, d_topk: (d_max < o.threshold) | (d_topk < o.shift_threshold_m),
    "all_of": lambda o, d_max, d_topk: (d_max < o.threshold) & (d_topk < o.shift_threshold_m),
    "none": lambda o, d_max, d_topk: d_max < 0,
}


def add_rule(name: str, rule: Callable[..., Any]) -> None:
    """A rule of the caller's own; it must be written in operators that both columns and numbers have."""
    RULES[name] = rule


def add_measure(name: str, measure: Callable[..., Any]) -> None:
    MEASURES[name] = measure
