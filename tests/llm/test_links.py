import re
from collections import Counter

import numpy as np
import pytest

from planepack.llm import jaccard

DOC = "doc_id long, text string"


def brute_links(texts, n, num, den):
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").lower())
        k = min(n, len(w))
        sets.append(frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if w else frozenset())
    linked = lambda x, y: x and y and den * len(x & y) >= num * len(x | y)
    per = [sum(bool(i != j and linked(sets[i], sets[j])) for j in range(len(sets))) for i in range(len(sets))]
    first = {}
    for i, s in enumerate(sets):
        first.setdefault(s, i)
    copies = Counter(sets)
    own = [(i, s) for s, i in first.items() if s]
    return per, sorted((i, j, copies[x], copies[y]) for i, x in own for j, y in own if i < j and linked(x, y))


def test_chain_and_triangle_differ(spark):
    """A-B-C where A and C do not link, and three texts that all link, are components of three alike but not in their links."""
    words = [f"w{i}" for i in range(60)]
    chain = [words, ["x0", *words[1:]], ["x0", *words[1:59], "x1"]]
    wide = [f"v{i}" for i in range(60)]
    triangle = [wide, ["y0", *wide[1:]], ["y1", *wide[1:]]]
    texts = [" ".join(t) for t in chain + triangle]
    df = spark.createDataFrame(list(enumerate(texts)), DOC)
    # of 60 single words, one replaced leaves 59 / 61 shared, two leave 58 / 62
    got = {r.doc_id: (r.component_id, r.n_class, r.n_links) for r in jaccard.jaccard_components(df, n=1, num=96, den=100, links=True).collect()}
    assert got == {0: (0, 3, 1), 1: (0, 3, 2), 2: (0, 3, 1), 3: (3, 3, 2), 4: (3, 3, 2), 5: (3, 3, 2)}
    pairs = sorted((r.id_a, r.id_b) for r in jaccard.jaccard_links(df, n=1, num=96, den=100).collect())
    assert pairs == [(0, 1), (1, 2), (3, 4), (3, 5), (4, 5)]


@pytest.mark.parametrize("n,num", [(3, 90), (5, 80), (2, 60)])
def test_links_against_brute_force(spark, n, num):
    rng = np.random.default_rng(n)
    texts = [None, "", " \n", "A b", "a B"]
    for k in (1, 2, 9, 30, 60, 200):
        t = [f"w{i}" for i in rng.integers(0, 400, size=k)]
        for _ in range(9):
            w = list(t)
            for _ in range(rng.integers(0, 3)):
                w[rng.integers(len(w))] = f"n{rng.integers(50)}"
            texts.append(" ".join(w))
    per, pairs = brute_links(texts, n, num, 100)
    assert len(pairs) > 20
    df = spark.createDataFrame(list(enumerate(texts)), DOC)
    for kw in ({}, {"local_edges": 0, "block_tokens": 500}):
        got = sorted((r.doc_id, r.n_links) for r in jaccard.jaccard_components(df, n=n, num=num, links=True, **kw).collect())
        assert got == list(enumerate(per))
        assert sorted(tuple(r) for r in jaccard.jaccard_links(df, n=n, num=num, **kw).collect()) == pairs
        plain = jaccard.jaccard_components(df, n=n, num=num, **kw)
        assert sorted(plain.collect()) == sorted(jaccard.jaccard_components(df, n=n, num=num, links=True, **kw).drop("n_links").collect())
