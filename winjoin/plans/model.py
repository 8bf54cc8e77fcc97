"""Arguments that the operators, plans and experiments share, checked once here."""

from __future__ import annotations

from dataclasses import dataclass, replace

SECOND = 1_000_000
MINUTE = 60 * SECOND
HOUR = 60 * MINUTE
DAY = 24 * HOUR

#: Bytes of a tuple; block and threshold sizes in bytes convert to tuples by it.
TUPLE_BYTES = 64


def tuples_in(size_bytes: int, tuple_bytes: int = TUPLE_BYTES) -> int:
    return size_bytes // tuple_bytes


@dataclass(frozen=True)
class JoinSpec:
    """How a window join is partitioned and tuned; window lengths in microseconds, sizes in tuples."""

    w1_us: int = 10 * MINUTE
    w2_us: int = 10 * MINUTE
    n_part: int = 60
    block_tuples: int = 64
    theta_tuples: int = 24576
    tuned: bool = True
    max_depth: int = 12

    def __post_init__(self):
        if self.w1_us < 0 or self.w2_us < 0:
            raise ValueError("windows are not negative")
        if self.n_part < 1 or self.block_tuples < 1:
            raise ValueError("n_part and block_tuples are at least 1")
        if self.theta_tuples < self.block_tuples:
            raise ValueError("theta holds at least one block")
        if not 0 <= self.max_depth <= 16:
            raise ValueError("max_depth is between 0 and 16")


@dataclass(frozen=True)
class ClusterSpec:
    """Logical nodes and the master's clock; epochs in microseconds."""

    n_nodes: int = 4
    td_us: int = 2 * SECOND
    tr_us: int | None = 20 * SECOND
    buffer_bytes: int = 1 << 20
    th_con: float = 0.01
    th_sup: float = 0.5
    beta: float = 0.5
    n_groups: int = 1
    adaptive: bool = True
    initial_nodes: int | None = None
    cooldown_epochs: int = 0
    background_us: int = 0
    order: str = "fixed"
    seed: int = 42

    def __post_init__(self):
        if not 0 <= self.th_con < self.th_sup < 1:
            raise ValueError("0 <= th_con < th_sup < 1")
        if not 0 < self.beta < 1:
            raise ValueError("0 < beta < 1")
        if self.td_us < 1 or self.tr_us is not None and self.tr_us < self.td_us:
            raise ValueError("tr is at least td")
        if not 1 <= self.n_groups <= self.n_nodes:
            raise ValueError("1 <= n_groups <= n_nodes")
        if self.initial_nodes is not None and not 1 <= self.initial_nodes <= self.n_nodes:
            raise ValueError("1 <= initial_nodes <= n_nodes")
        if self.order not in ("fixed", "blocking"):
            raise ValueError("order is 'fixed' or 'blocking'")


@dataclass(frozen=True)
class CostSpec:
    """Prices of the modelled clock, in whole nanoseconds so that sums are exact everywhere."""

    ns_per_compare: int = 20
    ns_per_tuple: int = 2_000
    ns_per_message: int = 500_000
    ns_per_byte: int = 8
    tuple_bytes: int = TUPLE_BYTES


__all__ = ["DAY", "HOUR", "MINUTE", "SECOND", "TUPLE_BYTES", "ClusterSpec", "CostSpec", "JoinSpec", "replace", "tuples_in"]
