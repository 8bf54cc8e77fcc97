"""Several continuous joins over shared sources: a registry of specifications, one query each."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from winjoin.operators.window_join import window_join
from winjoin.plans.model import JoinSpec
from winjoin.streaming.join import collect, partitioned


@dataclass(frozen=True)
class Registered:
    name: str
    left: str
    right: str
    join: JoinSpec


class JoinService:
    """Registered joins over named streams. Bounded sources are answered by the batch join over one cached scan each."""

    def __init__(self):
        self.queries: dict[str, Registered] = {}

    def register(self, name: str, left: str, right: str, join: JoinSpec) -> None:
        if name in self.queries:
            raise ValueError(f"{name} is registered")
        self.queries[name] = Registered(name, left, right, join)

    def answer(self, sources: dict[str, DataFrame]) -> dict[str, DataFrame]:
        held = {k: v.cache() for k, v in sources.items()}
        return {q.name: window_join(held[q.left], held[q.right], q.join.w1_us, q.join.w2_us) for q in self.queries.values()}

    def start(self, merged_of, path: str, checkpoint: str, available_now: bool = True) -> list:
        """``merged_of(left, right)`` gives the merged live stream of two names."""
        return [collect(partitioned(merged_of(q.left, q.right), q.join.w1_us, q.join.w2_us, q.join.n_part, q.join.block_tuples), q.name, path, f"{checkpoint}/{q.name}", available_now) for q in self.queries.values()]
