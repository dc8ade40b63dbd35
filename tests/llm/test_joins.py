"""Decontamination, near-duplicate join, exact top-k, graph helper and the pipeline, against plain versions."""

from __future__ import annotations

import hashlib
import random
import re
import sys

import numpy as np
import pytest

import corpus_pipeline
from freqspark.llm import _graph, bpe, decontaminate, line_dedup, ngram_join, topk, toxicity

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
TOKEN = re.compile(r"[^\x20\x09-\x0D]+")


def lower(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")


# ---- decontamination ------------------------------------------------------------------------------


def plain_report(docs, items):
    windows = {}
    for item, text in items:
        ws = WORD.findall(lower(text))
        for s in range(max(1, len(ws) - 9) if ws else 0):
            windows.setdefault(tuple(ws[s : s + 10]), set()).add(str(item))
    out = []
    for key, text in docs:
        ws = WORD.findall(lower(text))
        hit, owners = set(), set()
        for n in {len(w) for w in windows}:
            for s in range(len(ws) - n + 1):
                if (own := windows.get(tuple(ws[s : s + n]))) is not None:
                    hit.update(range(s, s + n))
                    owners |= own
        out.append((key, len(ws), len(hit), len(owners), hashlib.sha256(",".join(sorted(owners)).encode()).hexdigest(), bool(hit)))
    return out


def leak_corpus():
    rnd = random.Random(4)
    vocabulary = [f"w{i}" for i in range(40)] + ["Éa", "ÑU", "ab1"]
    items = [(i, " ".join(rnd.choice(vocabulary) for _ in range(rnd.choice([3, 7, 10, 14, 25])))) for i in range(12)] + [(90, None), (91, "!!"), (92, "w1"), (3, "w1 w2 w3 w4 w5 w6 w7 w8 w9 w10 w11")]
    docs = []
    for i in range(60):
        words = [rnd.choice(vocabulary) for _ in range(rnd.randint(0, 60))]
        if i % 3 == 0:
            words[5:5] = items[rnd.randrange(12)][1].upper().split() * rnd.randint(1, 3)
        docs.append((i, rnd.choice(["", " ", "("]) + rnd.choice([" ", ", "]).join(words) + rnd.choice(["", ".", " "])))
    return docs + [(100, None), (101, ""), (102, "..."), (None, items[0][1]), (0, docs[0][1]), (0, items[1][1])], items


@pytest.mark.parametrize("most", [100_000, 7])
def test_decontamination(spark, most):
    """Also where the windows go through the join in several parts."""
    docs, items = leak_corpus()
    got = decontaminate.report(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), most=most).collect()
    order = lambda r: (r[0] is None, r[0] or 0, *map(str, r[1:]))
    assert sorted((tuple(r) for r in got), key=order) == sorted(plain_report(docs, items), key=order)


def test_decontamination_keeps_clean_rows(spark):
    docs, items = leak_corpus()
    frame = spark.createDataFrame([(*d, "x") for d in docs], "doc_id long, text string, n_hit string")
    kept = decontaminate.keep_clean(frame, spark.createDataFrame(items, "item_id long, text string"))
    clean = [r for r, d in zip(plain_report(docs, items), docs, strict=True) if not r[5]]
    assert kept.columns == frame.columns and kept.count() == len(clean)
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.keep_clean(frame, none).count() == len(docs) and decontaminate.report(frame.limit(0), none).collect() == []


# ---- near-duplicates --------------------------------------------------------------------------------


def shingles(text, width=5):
    ws = TOKEN.findall(lower(text))
    return {tuple(ws[i : i + width]) for i in range(len(ws) - width + 1)} if len(ws) >= width else {tuple(ws)} if ws else set()


def plain_groups(docs, percent=75):
    sets = [shingles(t) for _, t in docs]
    parent = list(range(len(docs)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(docs)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * len(sets[i] | sets[j]):
                parent[find(i)] = find(j)
    least = {}
    for i, (key, _) in enumerate(docs):
        if key is not None:
            least[find(i)] = min(least.get(find(i), key), key)
    return [(key, len(sets[i]), least.get(find(i)) if sets[i] else key) for i, (key, _) in enumerate(docs)]


def near_corpus(seed, n, rate):
    rnd = random.Random(seed)
    vocabulary = [f"v{i}" for i in range(200)]
    bases = [[rnd.choice(vocabulary) for _ in range(rnd.choice([3, 6, 20, 60, 150]))] for _ in range(8)]
    passage = [rnd.choice(vocabulary) for _ in range(40)]
    docs = []
    for i in range(n):
        words = list(rnd.choice(bases))
        for p in range(len(words)):
            if rnd.random() < rate:
                words[p] = rnd.choice(vocabulary)
        if rnd.random() < 0.3:
            words += passage
        docs.append((i, rnd.choice([" ", "  ", "\n"]).join(w.upper() if rnd.random() < 0.1 else w for w in words)))
    rnd.shuffle(docs)
    return docs


@pytest.mark.parametrize(("seed", "rate"), [(1, 0.01), (2, 0.03), (3, 0.06)])
def test_near_duplicate_groups(spark, seed, rate):
    docs = near_corpus(seed, 160, rate) + [(500, None), (501, ""), (502, " \t"), (503, "Éa b"), (504, "éa b"), (505, "A b"), (506, "a  B"), (None, "a b"), (3, "a b"), (None, None)]
    got = ngram_join.groups(spark.createDataFrame(docs, "doc_id long, text string").repartition(5)).collect()
    order = lambda r: tuple((x is None, x or 0) for x in r)
    assert sorted((tuple(r) for r in got), key=order) == sorted(plain_groups(docs), key=order)


def test_one_of_each_group_stays(spark):
    docs = near_corpus(5, 80, 0.01) + [(500, None), (501, "")]
    frame = spark.createDataFrame([(*d, "x") for d in docs], "doc_id long, text string, component_id string")
    kept = ngram_join.keep_one(frame)
    assert kept.columns == frame.columns
    assert sorted(r.doc_id for r in kept.collect()) == sorted(k for k, _, c in plain_groups(docs) if c == k)
    assert ngram_join.groups(frame.limit(0)).collect() == []


def test_rows_that_share_a_key_go_by_their_own_texts(spark):
    text = [" ".join(f"{name}{i}" for i in range(40)) for name in "abc"]
    rows = [(1, text[0]), (2, text[0]), (2, text[1]), (3, text[1]), (3, None), (4, text[2]), (4, text[2])]
    kept = ngram_join.keep_one(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted(map(tuple, kept.collect()), key=str) == sorted([(1, text[0]), (2, text[1]), (3, None), (4, text[2]), (4, text[2])], key=str)


def test_components(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 101), (101, 100), (102, 101), (7, 7)] + [(200, i) for i in range(201, 230)]
    rnd = random.Random(2)
    rnd.shuffle(edges)
    got = {r.node: r.root for r in _graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(1, 41)}, 101: 100, 102: 100, **{i: 200 for i in range(201, 230)}}
    assert _graph.components(spark.createDataFrame([], "a long, b long")).collect() == []


@pytest.mark.parametrize("few", [200_000, 60, 0])
def test_components_of_few_edges_are_found_without_a_shuffle(spark, monkeypatch, few):
    """Rounds over few edges stay in one task; many, and many that become few, lead to the same components."""
    shuffled, whole = [], _graph.cut

    def cut(df, release=True):
        shuffled.append("Exchange" in df._jdf.queryExecution().executedPlan().toString())
        return whole(df, release)

    monkeypatch.setattr(_graph, "cut", cut)
    monkeypatch.setattr(_graph, "FEW_EDGES", few)
    rnd = random.Random(5)
    edges = [(rnd.randrange(120), rnd.randrange(120)) for _ in range(70)] + [(i, i + 1) for i in range(200, 230)]
    root = list(range(231))
    for _ in root:
        for a, b in edges:
            root[a] = root[b] = min(root[a], root[b])
    got = {r.node: r.root for r in _graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: r for i, r in enumerate(root) if i != r}
    assert shuffled[0] and any(shuffled[1:]) == (few < 100)


def test_first_partners_are_of_like_size(spark):
    """Nodes whose sizes tell that they are not similar are no pair, and of the pairs of a group one side is the same node."""
    asked = []

    def verify(pairs):
        asked.append(sorted((r.a, r.b) for r in pairs.collect()))
        return pairs.select("a", "b").where("false")

    members = [(1, node, 1) for node in range(10)] + [(b, node, 8 * b + 1) for b in (2, 3) for node in range(20, 27)] + [(4, node, 33) for node in (20, 23)] + [(5, node, 41) for node in (21, 23)]
    sizes = [(node, 100 * 2**node) for node in range(10)] + [(node, 1000) for node in range(20, 27)]
    _graph.similar_groups(spark.createDataFrame(members, "bucket long, node long, info int"), verify, spark.createDataFrame(sizes, "node long, n long"), 75).collect()
    assert asked[0] == [(23, b) for b in (20, 21, 22, 24, 25, 26)]
    assert all(a >= 20 and b >= 20 for pairs in asked for a, b in pairs)


# ---- exact top-k ---------------------------------------------------------------------------------------


def plain_top(rows, k=5, every=50):
    good = {}
    for key, v in rows:
        if key is not None and v is not None and all(c is not None and np.isfinite(c) for c in v):
            good.setdefault(key, set()).add(tuple(int(np.floor(256 * float(np.float32(c)))) for c in v))
    out = []
    for q in sorted(x for x in good if x % every == 0):
        scores = {(-sum(a * b for a, b in zip(u, v, strict=True)), i) for u in good[q] for i in good if i != q for v in good[i] if len(u) == len(v)}
        out += [(q, r, i, -s) for r, (s, i) in enumerate(sorted(scores)[:k], 1)]
    return out


def test_top_k(spark):
    rng = np.random.default_rng(3)
    rows = [(i, [float(c) for c in np.float32(rng.normal(size=6).round(1))]) for i in range(400)]
    rows += [(400, None), (450, [1.0, float("nan")] + [0.0] * 4), (401, [float("inf")] * 6), (402, [None] * 6), (None, [1.0] * 6), (500, [1.0, 2.0]), (501, [3.0, -1.0]), (0, rows[0][1]), (7, rows[7][1])]
    got = topk.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(4)).collect()
    assert sorted(tuple(r) for r in got) == plain_top(rows)
    assert topk.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>")).collect() == []


def test_top_k_with_large_components():
    q = np.array([[2.0**28, 3.0], [1.0, 1.0]])
    x = np.array([[2.0**27 + 1, 5.0], [7.0, 2.0**26]])
    assert topk.inner_products(q, x).tolist() == [[2**28 * (2**27 + 1) + 15, 7 * 2**28 + 3 * 2**26], [2**27 + 6, 7 + 2**26]]


# ---- pipeline --------------------------------------------------------------------------------------------


def test_pipeline_is_its_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    verdicts = {r.doc_id: r.predicted for r in toxicity.score(docs, toxicity.fit(docs, labels)).collect()}
    rows = [(r.doc_id, r.text) for r in docs.collect() if not verdicts[r.doc_id]]
    sys.path.insert(0, __file__.rpartition("/")[0])
    from test_line_dedup import expected

    rows = list(expected(rows).items())
    groups = plain_groups(rows)
    rows = [d for d, (key, _, component) in zip(rows, groups, strict=True) if component == key]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    rows = [d for d, r in zip(rows, plain_report(rows, items), strict=True) if not r[5]]
    coder = bpe.coder(*bpe.vocabulary())
    want = {k: hashlib.sha256(coder.encode(t)).hexdigest() for k, t in rows}
    got = {r.doc_id: r.ids_sha256 for r in corpus_pipeline.run(spark, sf).collect()}
    assert got == want and len(got) > 100


def test_stages_keep_the_columns(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "ngram_jaccard_join", "benchmark_decontamination", "byte_bpe"]
    out = corpus_pipeline.drop_lines(spark, docs, sf)
    assert out.schema.names == docs.schema.names and dict(out.dtypes) == dict(docs.dtypes)
    assert out.count() == docs.count() and line_dedup.LEAST_WORDS == 3
