"""Limits of a baseline run, reported instead of hidden."""

from __future__ import annotations

import time

#: Bytes that a baseline may hold on the driver.
MEMORY = 1 << 30


class Limits:
    """``status`` is 'ok', 'time' or 'memory'; a run that meets a limit returns what it has."""

    def __init__(self, seconds: float | None = None, memory: int = MEMORY):
        self.began, self.seconds, self.memory, self.status = time.monotonic(), seconds, memory, "ok"

    def spent(self) -> float:
        return time.monotonic() - self.began

    def over_time(self) -> bool:
        if self.seconds is not None and self.spent() > self.seconds:
            self.status = "time"
        return self.status == "time"

    def over_memory(self, needed: int) -> bool:
        if needed > self.memory:
            self.status = "memory"
        return self.status == "memory"
