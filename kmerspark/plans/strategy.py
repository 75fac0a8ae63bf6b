"""Which way a probe goes: broadcast counters, a join by counter, or keys routed to partitioned counters."""

from __future__ import annotations

from dataclasses import dataclass

from ..operators.sketch import BROADCAST_BYTES, SketchSpec

#: Keys up to which a join by counter (a row per key and table) is worth it.
JOIN_KEYS = 1_000_000


@dataclass(frozen=True)
class Choice:
    strategy: str
    reason: str


def choose(spec: SketchSpec, n_queries: int | None = None, limit: int = BROADCAST_BYTES) -> Choice:
    size = spec.memory_bytes()
    if spec.layout == "single":
        return Choice("cells", "hashed positions are computed by the engine only")
    if size <= limit:
        return Choice("broadcast", f"{size} bytes of counters fit the bound of {limit}")
    if n_queries is not None and n_queries <= JOIN_KEYS:
        return Choice("cells", f"{n_queries} keys are few; counters of {size} bytes stay where they are")
    return Choice("sharded", f"counters of {size} bytes are partitioned by key")
