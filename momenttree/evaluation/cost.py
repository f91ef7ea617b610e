"""What a construction costs: scans, non-zeros, bytes, seconds."""

from __future__ import annotations

import time
from dataclasses import dataclass, field


@dataclass
class Ledger:
    """Counters of one construction; bytes are those of the largest array of each kind."""

    scans: int = 0
    nonzeros: int = 0
    seconds: dict[str, float] = field(default_factory=dict)

    def bytes_of(self, v: int, k: int) -> dict[str, int]:
        return {"m2": 8 * v**2, "m3": 8 * v**3, "core": 8 * k**3, "whitener": 8 * v * k}

    def timed(self, name: str):
        ledger = self

        class Span:
            def __enter__(self):
                self.began = time.perf_counter()

            def __exit__(self, *_):
                ledger.seconds[name] = ledger.seconds.get(name, 0.0) + time.perf_counter() - self.began

        return Span()
