"""Candidates against all true links at many lengths and rates of change; nodes that share 64 bits."""

import random

import numpy as np
import pytest

from sheetgraph.llm import order_minhash
from sheetgraph.llm._shared import Scratch

VOCABULARY = np.random.default_rng(5).integers(1, 1 << 63, 3000, dtype=np.uint64)


def changed(words, times, kinds):
    out = list(words)
    for _ in range(times):
        kind, at = random.choice(kinds), random.randrange(len(out))
        if kind == "d" and len(out) > 1:
            del out[at]
        else:
            out[at : at + (kind == "s")] = [VOCABULARY[random.randrange(len(VOCABULARY))]]
    return np.array(out, np.uint64)


def share_found(n, rate, tries=80):
    """Share of links between texts of about n words that agree on a key."""
    found = seen = 0
    while seen < tries:
        a = VOCABULARY[np.random.randint(0, len(VOCABULARY), n)]
        b = changed(a, max(1, int(rate * n)), "s" if seen % 2 else "sid")
        if order_minhash.similarity(a.tolist(), b.tolist()) is None:
            continue
        seen += 1
        found += bool(set(order_minhash.keys_of(a).tolist()) & set(order_minhash.keys_of(b).tolist()))
    return found / seen


@pytest.mark.parametrize("n", [5, 8, 12, 17, 24])
def test_short_links_are_all_found(n):
    random.seed(n)
    np.random.seed(n)
    assert all(share_found(n, rate) == 1 for rate in (0.05, 0.1, 0.15, 0.2) if rate * n >= 1 or n < 20)


@pytest.mark.parametrize("n", [26, 30, 60, 100, 400])
def test_recall_of_longer_links(n):
    random.seed(n)
    np.random.seed(n)
    assert [share_found(n, rate) >= least for rate, least in ((0.05, 1), (0.1, 0.98), (0.15, 0.95), (0.19, 0.9))] == [True] * 4


def test_short_texts_around_the_border_against_all_pairs():
    """A small vocabulary, so that texts are near each other in all ways; lengths on both sides of EXACT."""
    random.seed(9)
    np.random.seed(9)
    for _ in range(400):
        n = random.randint(4, 30)
        a = VOCABULARY[np.random.randint(0, 4, n)]
        b = np.array(changed(a, random.randint(1, 6), "sid"), np.uint64)
        if min(len(a), len(b)) < order_minhash.EXACT and not np.array_equal(a, b) and order_minhash.similarity(a.tolist(), b.tolist()) is not None:
            assert set(order_minhash.keys_of(a).tolist()) & set(order_minhash.keys_of(b).tolist())


def test_nodes_that_share_their_bits_stay_apart(spark):
    """With 3 bits for a node nearly all texts clash; the classes are those of 64 bits."""
    random.seed(2)
    words = [f"w{k}" for k in range(400)]
    texts = [" ".join(random.choice(words) for _ in range(random.randint(6, 60))) for _ in range(40)]
    texts += [t + " more" for t in texts[:15] if len(t.split()) > 10] + texts[:5]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    wide, narrow = ({r.doc_id: (r.class_id, r.class_size) for r in order_minhash.classes(docs, Scratch(spark, "t"), bits=b).collect()} for b in (64, 3))
    assert wide == narrow and len({c for c, _ in wide.values()}) == 40


def test_distances_of_one_text_to_many_at_once():
    random.seed(4)
    for _ in range(60):
        many = [np.array(random.choices(range(6), k=random.randint(1, 40)), np.uint32) for _ in range(random.randint(1, 9))]
        one = np.array(random.choices(range(6), k=random.randint(1, 40)), np.uint32)
        assert order_minhash.Lanes(many).distances(one).tolist() == [order_minhash.banded_distance(one.tolist(), x.tolist(), 50) for x in many]


def test_late_links_against_all_pairs(spark):
    """Open buckets of texts of many lengths and of two components a bucket: what links comes out for each two components."""
    random.seed(6)
    words = [f"w{k}" for k in range(300)]
    texts = []
    for n in (6, 12, 30, 31, 38, 90, 110, 2_100):
        base = random.choices(words, k=n)
        for _ in range(9):
            other = list(base)
            for at in random.sample(range(n), min(n, int(random.choice((0.1, 0.2, 0.3, 0.5)) * n) + 1)):
                other[at] = random.choice(words)
            texts.append(other)
    rows = [(h, node, 0 if node % 5 == 0 else node, 0) for h in (7, 9) for node in range(len(texts)) if h == 7 or node % 3]
    scratch = Scratch(spark, "t")
    kept = scratch.keep(spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "__node long, __text string"))
    found = order_minhash._late_links(spark.createDataFrame(rows, "h long, node long, label long, main long"), kept, scratch).collect()
    label = {node: at for _, node, at, _ in rows}
    want = {frozenset((label[a], label[b])) for a in label for b in label if label[a] != label[b] and order_minhash.similarity(texts[a], texts[b]) is not None}
    assert want and {frozenset((label[r.a], label[r.b])) for r in found} == want
    assert all(order_minhash.similarity(texts[r.a], texts[r.b]) is not None for r in found)
