"""Kernels by policy and engine."""

from __future__ import annotations

from ..spec import SummarySpec
from .base import Kernel
from .block import BlockReduce
from .reducing import GlobalMinReduce, RankReduce, SampleQuantileReduce, UnitDecrement, UnitExpandDecrement
from .replacing import HeapReplace, ListReplace, UnitExpandReplace

_BY_POLICY = {
    "rank": RankReduce,
    "sample_quantile": SampleQuantileReduce,
    "global_min": GlobalMinReduce,
    "unit_decrement": UnitDecrement,
    "unit_expand_decrement": UnitExpandDecrement,
    "space_saving_heap": HeapReplace,
    "space_saving_list": ListReplace,
    "unit_expand_replace": UnitExpandReplace,
}


def make_kernel(spec: SummarySpec, salt: int = 0) -> Kernel:
    return BlockReduce(spec, salt) if spec.blockwise else _BY_POLICY[spec.policy](spec, salt)


def merge_spec(spec: SummarySpec) -> SummarySpec:
    """How summaries of this spec are merged: policies for weights of 1 hand their counters to the weighted form of themselves."""
    return spec.with_(policy={"unit_decrement": "global_min", "unit_expand_decrement": "global_min", "space_saving_list": "space_saving_heap", "unit_expand_replace": "space_saving_heap"}.get(spec.policy, spec.policy))
