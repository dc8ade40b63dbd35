"""Restoring disguised spans: against every path of short lattices, and in linear time on long texts."""

from __future__ import annotations

import itertools
import time

import numpy as np

from freqspark.llm import toxicity


def restorer(seed: int = 3) -> toxicity.Restorer:
    n = toxicity.SYMBOLS
    return toxicity.Restorer(np.random.default_rng(seed).gamma(2.0, 1.0, (n, n, n)).astype(np.float32))


def best(r: toxicity.Restorer, span: str) -> float:
    """The least cost of all paths through the lattice, tried one by one."""
    costs = []
    for path in itertools.product(*r.lattice(span)):
        total, p, q = 0.0, 0, 0
        for reading, own in [*path, (" ", 0.0)]:
            total += own
            for s in r._symbols(reading):
                total += float(r.costs[p, q, s])
                p, q = q, s
        costs.append((total, "".join(x for x, _ in path)))
    return min(costs)


def test_viterbi_finds_the_best_of_all_paths():
    r = restorer()
    for span in ["h3ll0", "s t u p i d", "st00pid", "looooser", "1d1ot", "a-b-c-d", "b4aaad"]:
        assert r.read(span) == best(r, span)[1].rstrip(" ")


def test_spans_are_whole_words():
    r = restorer()
    r.read = lambda span: f"<{span}>"
    assert r.restore("so looong a word, baaad") == "so <looong> a word, <baaad>"


def test_long_words_take_linear_time():
    r = restorer()
    for text in ["ab" * 500_000, "a" * 1_000_000, "ab" * 20_000 + "ccc" + "de" * 20_000, "a b " * 20_000]:
        start = time.time()
        r.restore(text)
        assert time.time() - start < 20
