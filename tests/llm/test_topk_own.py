import numpy as np

from planepack.llm import topk


def test_repeated_query_rows_in_a_large_tile(spark):
    """Six rows of the query's own in a tile of over 4 k rows leave the k best others."""
    k = 4
    rows = [(100, [8.0, 0.0])] * 6 + [(i, [i / 16, 1.0]) for i in range(1, 40)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").coalesce(1)
    got = [(r.rank, r.vec_id) for r in topk.exact_topk(df, k=k).orderBy("rank").collect()]
    assert got == [(1, 39), (2, 38), (3, 37), (4, 36)]


def test_lists_against_sorting():
    rng = np.random.default_rng(0)
    ids = np.concatenate([rng.permutation(200), rng.integers(0, 200, 200)])
    v = np.floor(rng.normal(size=(200, 4)) * 8)[ids]
    own = np.array([7, 3, 150])
    lists = topk.Lists(own, np.stack([v[np.nonzero(ids == i)[0][0]] for i in own]), 5)
    for lo in range(0, 400, 100):
        lists.merge(ids[lo : lo + 100], v[lo : lo + 100])
    for j, i in enumerate(own):
        want = sorted(((-int(v[np.nonzero(ids == i)[0][0]] @ v[r]), int(ids[r])) for r in range(400) if ids[r] != i))[:5]
        assert list(zip((-lists.score[j]).tolist(), lists.id[j].tolist())) == want


def test_components_at_the_edge_of_a_double(spark):
    """A component that is too large for its 1024-fold takes no part; scores at the ends of 64 bits keep their order."""
    rows = [(100, [1e300, 1.0]), (1, [1e300, 0.0]), (2, [-1e300, 0.0]), (3, [0.0, 1.0]), (4, [1.7e308, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [(r.rank, r.vec_id, r.score) for r in topk.exact_topk(df).orderBy("rank").collect()]
    assert got == [(1, 1, (1 << 63) - 1), (2, 3, 1 << 20), (3, 2, -(1 << 63))]
