"""Seconds per stage and case, and the ratio to dynamic checking."""

from __future__ import annotations

import time
from contextlib import contextmanager


class StageTimer:
    """Wall-clock seconds by stage; ``per_case`` divides by the number of cases."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def stage(self, name: str):
        began = time.monotonic()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.monotonic() - began

    def per_case(self, cases: int) -> dict[str, float]:
        return {k: v / max(cases, 1) for k, v in self.seconds.items()}


def time_ratio(static_seconds_per_case: float, cases: int, dynamic_hours_per_case: float) -> float:
    """How many times longer dynamic checking takes than the static method, over a data set."""
    return dynamic_hours_per_case * 3600 * cases / (static_seconds_per_case * cases)
