"""Near duplicates, components, shingles against plain Python."""

import random
import re

import numpy as np

from linkgraph.llm import near_dup
from linkgraph.llm.common import text_bytes
from linkgraph.llm.components import connected_components
from linkgraph.llm.near_dup import NearDupParams, keep_first, near_duplicates
from linkgraph.llm.shingles import shingle_sets

import pyarrow as pa

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def plain_set(text):
    w = re.findall("[^\x20\x09-\x0d]+", (text or "").translate(LOW))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def variants(n, seed):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    out = []
    for _ in range(n):
        base = rng.choices(words, k=rng.randint(20, 90))
        out.append(" ".join(base))
        for _ in range(rng.randint(0, 4)):
            copy = list(base)
            for _ in range(rng.randint(0, 3)):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            out.append("  ".join(copy).upper() if rng.random() < 0.3 else " ".join(copy))
            base = copy
    return out


def test_shingle_counts():
    texts = ["", "a", "a b c d", "a b c d e", "A B\tc d e f", None, "x " * 40, "é è ü ß ñ o", " a  b\x0bc\x0cd e "]
    data, offsets = text_bytes(pa.array(texts))
    assert shingle_sets(data, offsets)[1].tolist() == [len(plain_set(t)) for t in texts]


def test_near_duplicates_against_all_pairs(docs_of):
    texts = [*variants(40, 3), "", None, "one two", "One  two", "three words here"]
    sets = [plain_set(t) for t in texts]
    parent = list(range(len(texts)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(texts)):
        for j in range(i + 1, len(texts)):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= 75 * (len(sets[i]) + len(sets[j]) - both):
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    docs = docs_of(enumerate(texts))
    got = {r["doc_id"]: r for r in near_duplicates(docs).collect()}
    assert {i: (r["n_shingles"], r["component_id"], r["kept"]) for i, r in got.items()} == {i: (len(sets[i]), root(i), root(i) == i) for i in range(len(texts))}
    assert {r["doc_id"] for r in keep_first(docs).select("doc_id").collect()} == {i for i in range(len(texts)) if root(i) == i}


def test_empty_table(docs_of):
    assert near_duplicates(docs_of([])).collect() == []


def test_components(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (9, 8), (7, 9), (5, 5), (3, 1), (20, 21), (21, 22), (22, 23), (23, 24)], "a long, b long")
    got = {r["node"]: r["component"] for r in connected_components(edges).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7, 9: 7, 20: 20, 21: 20, 22: 20, 23: 20, 24: 20}


def test_forest_ties_what_all_edges_tie():
    draw = np.random.default_rng(4)
    for size, edges in ((1, 0), (40, 15), (40, 60), (60, 1500)):
        a, b = draw.integers(0, size, (2, edges))
        kept, tree = near_dup._forest(a, b, draw.integers(0, 1 << 62, edges).astype(np.uint64), size)
        label = np.arange(size)
        for i, j in zip(a, b):
            label[label == label[j]] = label[i]
        same = lambda x: x[:, None] == x
        assert (same(label) == same(tree)).all()
        assert len(kept) == size - len(set(tree))


def test_blocks_find_every_link_of_a_group_near_the_threshold(docs_of):
    """Many copies just above or below the threshold; blocks of 8, whole sets and cut ones."""
    rng = random.Random(11)
    words = [f"w{i}" for i in range(500)]
    base = rng.choices(words, k=300)
    texts = []
    for _ in range(60):
        copy = list(base)
        for _ in range(rng.randint(3, 8)):
            copy[rng.randrange(len(copy))] = rng.choice(words)
        texts.append(" ".join(copy))
    sets = [plain_set(t) for t in texts]
    label = list(range(len(texts)))
    for x in range(len(texts)):
        for y in range(x):
            if 100 * len(sets[x] & sets[y]) >= 75 * len(sets[x] | sets[y]) and label[x] != label[y]:
                lo, hi = sorted((label[x], label[y]))
                label = [lo if v == hi else v for v in label]
    assert 5 < len(set(label)) < 60
    docs = docs_of(list(enumerate(texts)))
    for params in (NearDupParams(quick_rounds=1, block=8), NearDupParams(quick_rounds=1, block=8, sketch=256, sketch_least=160)):
        got = {r.doc_id: r.component_id for r in near_duplicates(docs, params).collect()}
        assert [got[i] for i in range(len(texts))] == label
