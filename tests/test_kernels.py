"""Kernels against a plain fold, their promises, and the table layout."""

from __future__ import annotations

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from freqspark.kernels import ProbingTable, make_kernel
from freqspark.kernels.factory import merge_spec
from freqspark.spec import POLICIES, REPLACING, SummarySpec, k_for, recommend_quantile, space_bytes
from reference_fold import fold

STREAM = st.lists(st.tuples(st.integers(0, 12), st.integers(1, 40)), max_size=120)
FOLDED = {"rank": ("rank", {}), "min": ("global_min", {}), "quantile": ("sample_quantile", {"q": 0.3}), "heap": ("space_saving_heap", {})}


def fed(spec, stream, salt=0):
    kernel = make_kernel(spec, salt)
    if stream:
        kernel.feed(*map(list, zip(*stream, strict=True)))
    kernel.finish()
    return kernel


@pytest.mark.parametrize("name", FOLDED)
@settings(max_examples=60, deadline=None)
@given(stream=STREAM, k=st.integers(1, 8))
def test_row_kernels_fold(name, stream, k):
    policy, extra = FOLDED[name]
    kernel = fed(SummarySpec(policy, k, engine="row", **extra), stream)
    table, offset = fold(stream, name, k, **extra)
    assert dict(kernel.counters()) == table and kernel.head.offset == offset
    assert kernel.head.n_updates == len(stream) and kernel.head.total_weight == sum(w for _, w in stream)


@settings(max_examples=60, deadline=None)
@given(stream=STREAM, k=st.integers(1, 8), policy=st.sampled_from(["rank", "sample_quantile", "global_min", "space_saving_heap"]), engine=st.sampled_from(["row", "block"]), block=st.integers(1, 50))
def test_bounds_hold_after_any_merge(stream, k, policy, engine, block):
    spec = SummarySpec(policy, k, engine=engine, block_rows=block, seed=5)
    third = len(stream) // 3
    parts = [fed(spec, stream[:third], 1), fed(spec, stream[third : 2 * third], 2), fed(spec, stream[2 * third :], 3)]
    target = parts[0]
    for other in parts[1:]:
        other.finish()
        target.absorb(other.counters(), other.head)
    target.finish()
    truth = {}
    for i, w in stream:
        truth[i] = truth.get(i, 0) + w
    held, offset = dict(target.counters()), target.head.offset
    assert len(held) <= k and target.head.total_weight == sum(truth.values())
    for i, f in truth.items():
        if policy in REPLACING:
            assert f <= held.get(i, offset)
        else:
            assert held.get(i, 0) <= f <= held.get(i, 0) + offset
    if policy not in REPLACING:
        missing = sum(truth.values()) - sum(held.values())
        assert offset * (1 if policy == "global_min" and engine == "row" else spec.rank if policy != "global_min" else 1) <= max(missing, 0) or k <= 2


def test_replacement_and_minimum_are_isomorphic():
    rnd = random.Random(3)
    stream = [(rnd.randrange(60), rnd.randint(1, 50)) for _ in range(4000)]
    heap = fed(SummarySpec("space_saving_heap", 13), stream)
    least = fed(SummarySpec("global_min", 12, engine="row"), stream)
    assert heap.head.offset == least.head.offset
    assert {i: c - heap.head.offset for i, c in heap.counters() if c > heap.head.offset} == dict(least.counters())


def test_unit_forms_agree():
    rnd = random.Random(4)
    ones = [(rnd.randrange(40), 1) for _ in range(3000)]
    assert dict(fed(SummarySpec("unit_decrement", 9), ones).counters()) == dict(fed(SummarySpec("global_min", 9, engine="row"), ones).counters())
    heap, linked = fed(SummarySpec("space_saving_heap", 9), ones), fed(SummarySpec("space_saving_list", 9), ones)
    assert dict(heap.counters()) == dict(linked.counters()) and heap.head.offset == linked.head.offset
    weighted = [(rnd.randrange(20), rnd.randint(1, 6)) for _ in range(800)]
    assert dict(fed(SummarySpec("unit_expand_decrement", 7), weighted).counters()) == dict(fed(SummarySpec("global_min", 7, engine="row"), weighted).counters())
    assert fed(SummarySpec("unit_expand_replace", 7), weighted).head.total_weight == sum(w for _, w in weighted)
    for policy in ("unit_decrement", "space_saving_list"):
        with pytest.raises(ValueError):
            fed(SummarySpec(policy, 3), [(1, 2)])


def test_reduces_are_rare_and_fall_with_the_quantile():
    rnd = random.Random(5)
    stream = [(rnd.randrange(5000), rnd.randint(1, 1000)) for _ in range(20_000)]
    reduces = [fed(SummarySpec("sample_quantile", 96, q=q, engine="row"), stream).head.n_reduces for q in (0.0, 0.1, 0.5, 0.9)]
    assert reduces == sorted(reduces, reverse=True) and reduces[2] * 96 / 3 <= len(stream)
    rank = fed(SummarySpec("rank", 96, engine="row"), stream)
    assert rank.head.n_reduces * (96 - 48 + 1) <= len(stream)
    # A table no larger than the sample makes the sampled median the rank's.
    assert dict(rank.counters()) == dict(fed(SummarySpec("sample_quantile", 96, engine="row"), stream).counters())


def test_sampled_subset_meets_the_practical_bound():
    rng = np.random.default_rng(6)
    items = rng.zipf(1.2, 30_000) % 20_000
    truth = np.bincount(items)
    for seed in range(3):
        kernel = fed(SummarySpec("sample_quantile", 384, sample_size=128, seed=seed, engine="row"), [(int(i), 1) for i in items])
        held = dict(kernel.counters())
        worst = max(int(f) - held.get(i, 0) for i, f in enumerate(truth))
        assert worst <= len(items) / (0.33 * 384)


def test_real_weights_and_empty_streams():
    kernel = fed(SummarySpec("sample_quantile", 3), [("a", 0.5), ("b", 1.5), ("c", 0.25), ("d", 2.0), ("a", 1.0)])
    assert kernel.head.total_weight == pytest.approx(5.25) and len(kernel.counters()) <= 3
    for policy in POLICIES:
        kernel = fed(SummarySpec(policy, 2), [])
        assert kernel.counters() == [] and kernel.head.n_updates == 0


def test_retry_gives_the_same_rows():
    stream = [(i % 500, 1 + i % 7) for i in range(9000)]
    spec = SummarySpec("sample_quantile", 64, sample_size=16, engine="row", seed=9)
    assert fed(spec, stream, 4).counters() == fed(spec, stream, 4).counters()


def test_specs():
    for bad in ({"policy": "x"}, {"k": 0}, {"k": 4, "k_star": 5}, {"q": 1.0}, {"engine": "c"}):
        with pytest.raises(ValueError):
            SummarySpec(**bad)
    assert SummarySpec("rank", 8).rank == 4 and SummarySpec("rank", 1).rank == 1 and SummarySpec("sample_quantile", 8, q=0.98).rank == 1
    assert k_for(0.01) == 384 and 1 / (0.33 * k_for(1e-3)) <= 1e-3 and 0.1 <= recommend_quantile("accuracy") <= recommend_quantile("speed") <= 0.7
    assert space_bytes("sample_quantile", 24_576) == 24 * 24_576 and space_bytes("exact", 0, 1_750_000) > 70 * space_bytes("sample_quantile", 24_576) * 0.9
    assert merge_spec(SummarySpec("space_saving_list", 3)).policy == "space_saving_heap"


@settings(max_examples=80, deadline=None)
@given(st.lists(st.one_of(st.tuples(st.integers(-5, 40), st.integers(1, 9)), st.integers(1, 6)), max_size=150), st.integers(1, 24))
def test_probing_table(steps, k):
    """Additions and subtractions against a dict."""
    table, plain = ProbingTable(k, seed=1), {}
    for step in steps:
        if isinstance(step, int):
            table.subtract(step)
            plain = {i: c - step for i, c in plain.items() if c > step}
        elif step[0] in plain or len(plain) < k:
            assert table.add(*step)
            plain[step[0]] = plain.get(step[0], 0) + step[1]
        else:
            assert not table.add(*step)
        assert table.items() == plain and table.size == len(plain)
        assert all(table.get(i) == c for i, c in plain.items())
    assert ProbingTable(24).bytes == 18 * 32


def test_an_item_that_one_part_lost_keeps_its_upper_bound():
    """z and a are in both parts, but the second one's table has no room for a: its weight there is at most the offset."""
    spec = SummarySpec("space_saving_heap", 3)
    one, two = fed(spec, [("z", 200), ("a", 100), ("b", 5), ("b", 4)], 1), fed(spec, [("z", 200), ("a", 3), ("c", 5), ("d", 5)], 2)
    two.finish()
    one.absorb(two.counters(), two.head)
    one.finish()
    held, offset = dict(one.counters()), one.head.offset
    assert held["z"] >= 400 and held["a"] >= 103 and offset >= 9


@pytest.mark.parametrize("q", [0.1, 0.5, 0.9])
def test_blocks_keep_heavy_items_among_very_many_light_ones(q):
    """One block of a hundred heavy items and 20,000 light ones, whatever the seed: each reduce leaves what its rank promises."""
    items = list(range(20_100))
    weights = [1_000_000 if i < 100 else 1 for i in items]
    for seed in range(200):
        kernel = fed(SummarySpec("sample_quantile", 384, q=q, seed=seed), list(zip(items, weights)), seed)
        held, rank = dict(kernel.counters()), kernel.spec.rank
        lost = sum(weights) - sum(held.values())
        worst = max(w - held.get(i, 0) for i, w in zip(items, weights))
        assert worst * rank <= lost
        if rank > 100:
            assert all(i in held for i in range(100))


def test_replay_orders_hold_the_bound():
    """Storage, random and seeded hash order replay the same counters; the drop stays within (N - C) / rank."""
    spec = SummarySpec("rank", 16, engine="row")
    stream = [(i * 7919 % 61, 1 + i * 31 % 17) for i in range(900)]
    truth = {}
    for i, w in stream:
        truth[i] = truth.get(i, 0) + w
    tables = {}
    for order in ("storage", "random", "hash_seed"):
        a, b = make_kernel(spec, 0), make_kernel(spec, 1)
        a.feed(*zip(*stream[:450], strict=True))
        b.feed(*zip(*stream[450:], strict=True))
        a.absorb(b.counters(), b.head, order)
        held = dict(a.counters())
        drop = (a.head.total_weight - sum(held.values())) / spec.rank
        assert all(0 <= f - held.get(i, 0) <= min(drop, a.head.offset) for i, f in truth.items())
        tables[order] = held
    assert len(tables) == 3


@pytest.mark.parametrize("spec", [SummarySpec("global_min", 7, engine="row"), SummarySpec("sample_quantile", 7, q=0.0, engine="row"), SummarySpec("sample_quantile", 7, q=0.0, clamp=True, engine="row")])
def test_least_counter_is_found_without_a_scan(spec):
    """The fed batches leave the counters, order and costs that one update after the other leaves, and a reduce scans no table."""
    rnd = random.Random(3)
    items, weights = [rnd.randrange(40) for _ in range(3_000)], [rnd.randint(1, 9) for _ in range(3_000)]
    fed, put = make_kernel(spec), make_kernel(spec)
    for lo in range(0, 3_000, 700):
        fed.feed(items[lo : lo + 700], weights[lo : lo + 700])
    for item, weight in zip(items, weights, strict=True):
        put.put(item, weight)
    assert list(fed.counters()) == list(put.counters())
    assert (fed.head.offset, fed.head.n_reduces, fed.head.counters_touched) == (put.head.offset, put.head.n_reduces, put.head.counters_touched)
    assert fed.head.n_reduces > 100 and fed.head.total_weight == sum(weights)
    seen = make_kernel(spec)
    type(seen).subtract, kept = (lambda self, cut: pytest.fail("a reduce went over the whole table")), type(seen).subtract
    try:
        seen.feed(items, weights)
    finally:
        type(seen).subtract = kept
