"""What a summary is to be: policy, size and the parameters of its policy."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

#: How a full table makes room, by name. Reducing policies subtract from all counters, replacing ones hand the least counter on.
REDUCING = ("rank", "sample_quantile", "global_min", "unit_decrement", "unit_expand_decrement")
REPLACING = ("space_saving_heap", "space_saving_list", "unit_expand_replace")
POLICIES = REDUCING + REPLACING
#: Policies that take weights of 1 only, and those that take a weight apart into ones.
UNIT_ONLY = ("unit_decrement", "space_saving_list")
EXPANDING = ("unit_expand_decrement", "unit_expand_replace")

#: The sample that the published failure bound holds for, and its constant.
SAMPLE_SIZE, SAFE_SHARE = 1024, 0.33


@dataclass(frozen=True)
class SummarySpec:
    """Parameters of a summary of at most k counters.

    k_star: the rank whose counter the rank policy subtracts (default k / 2). q: the quantile, from 0 for the
    smallest, that the sampling policy subtracts. clamp: never subtract more than the newcomer weighs
    (always so for global_min). engine: 'block' adds up a block of updates before the table sees them
    (reducing policies only), 'row' takes updates one by one in their order.
    """

    policy: str = "sample_quantile"
    k: int = 384
    k_star: int | None = None
    q: float = 0.5
    sample_size: int = SAMPLE_SIZE
    seed: int = 1
    clamp: bool = False
    with_replacement: bool = False
    engine: str = "block"
    block_rows: int = 65_536

    def __post_init__(self):
        if self.policy not in POLICIES:
            raise ValueError(f"unknown policy {self.policy!r}; there are {', '.join(POLICIES)}")
        if self.k < 1 or self.sample_size < 1 or self.block_rows < 1:
            raise ValueError("k, sample_size and block_rows must be at least 1")
        if self.k_star is not None and not 1 <= self.k_star <= self.k:
            raise ValueError("k_star must be between 1 and k")
        if not 0 <= self.q < 1:
            raise ValueError("q must be at least 0 and below 1")
        if self.engine not in ("block", "row"):
            raise ValueError("engine is 'block' or 'row'")

    @property
    def rank(self) -> int:
        """How many counters are at least as large as what a reduce subtracts: the error bound's denominator."""
        if self.policy == "rank":
            return self.k_star or max(1, self.k // 2)
        if self.policy == "sample_quantile":
            return max(1, self.k - min(int(self.q * self.k), self.k - 1))
        return self.k

    @property
    def blockwise(self) -> bool:
        return self.engine == "block" and self.policy in ("rank", "sample_quantile", "global_min")

    @property
    def rank_param(self) -> float:
        return float(self.rank) if self.policy == "rank" else self.q if self.policy == "sample_quantile" else 0.0

    def with_(self, **changes) -> SummarySpec:
        return replace(self, **changes)


def k_for(eps: float, share: float = SAFE_SHARE) -> int:
    """The smallest k of the form 0.75 * 2^b, so that tables of 4k/3 cells are powers of two, whose error is at most eps * N."""
    if not 0 < eps < 1:
        raise ValueError("eps must be between 0 and 1")
    return int(0.75 * 2 ** max(2, math.ceil(math.log2(1 / (share * eps) / 0.75))))


def recommend_quantile(priority: str = "balanced") -> float:
    """A quantile inside the useful band: below 0.1 many reduces can be forced, above 0.7 errors climb."""
    return {"accuracy": 0.1, "balanced": 0.5, "speed": 0.7}[priority]


def space_bytes(policy: str, k: int, distinct: int | None = None) -> int:
    """Bytes of a summary by the published layout: 8 + 8 + 2 for each cell of a table of the next power of two from 4k/3.

    The heap needs 8 bytes for the key and 8 for its place beside each counter; an exact table is laid out alike over all items.
    """
    def cells(n: int) -> int:
        return 1 << max(0, (-(-4 * n // 3) - 1).bit_length())

    if policy == "exact":
        return 18 * cells(distinct or 0)
    return 18 * cells(k) + (16 * k if policy in REPLACING else 0)
