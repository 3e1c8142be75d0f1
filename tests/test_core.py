import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from planepack import cluster, foundational, packing, pipeline
from planepack.codecs import CODECS
from planepack.features import entropy_of_counts
from planepack.words import as_planes

POINTS = np.array([[0.0], [1.0], [10.0], [12.0]])
WORDS = np.array([1.0, 1.5, 2.0, -2.5], "<f4").tobytes()


def test_hand_made_scores():
    two, three = [[0, 1], [2, 3]], [[0, 1], [2], [3]]
    assert cluster.cut(cluster.linkage(POINTS), 2) == two and cluster.cut(cluster.linkage(POINTS), 3) == three
    assert cluster.separation(two, POINTS) == 9 and cluster.separation(three, POINTS) == 2
    assert cluster.silhouette(two, POINTS) == pytest.approx(0.856163, abs=1e-6)
    assert cluster.silhouette(three, POINTS) == pytest.approx(0.447222, abs=1e-6)
    assert cluster.davies_bouldin(two, POINTS) == pytest.approx(0.142857, abs=1e-6)
    assert cluster.davies_bouldin(three, POINTS) == pytest.approx(0.049580, abs=1e-6)
    assert cluster.calinski_harabasz(two, POINTS) == pytest.approx(88.2)
    assert cluster.calinski_harabasz(three, POINTS) == pytest.approx(112.25)
    assert cluster.choose_partition(POINTS, "silhouette") == two
    assert cluster.choose_partition(POINTS, "davies_bouldin") == three


def test_set_partitions():
    assert [len(cluster.set_partitions(n)) for n in (1, 2, 3, 4, 8)] == [1, 2, 5, 15, 4140]
    assert all(cluster.is_partition(c, 4) for c in cluster.set_partitions(4))


def test_single_linkage_reaches_the_largest_gap():
    rng = np.random.default_rng(3)
    for _ in range(20):
        x = rng.normal(size=(4, 5))
        for k in (2, 3):
            best = max(cluster.separation(c, x) for c in cluster.set_partitions(4) if len(c) == k)
            assert cluster.separation(cluster.cut(cluster.linkage(x), k), x) == pytest.approx(best)


def test_worked_bytes():
    m = as_planes(WORDS, 4)
    assert [round(entropy_of_counts(np.bincount(m[:, p], minlength=256)), 6) for p in range(4)] == [1.5, 2.0, 0.0, 0.0]
    c = [[0, 1], [2, 3]]
    assert [s.hex().upper() for s in packing.pack(m, c, "byte")] == ["3F3F40C080C00020", "0000000000000000"]
    assert [s.hex().upper() for s in packing.pack(m, c, "value")] == ["3F803FC04000C020", "0000000000000000"]
    assert packing.byte_shuffle(WORDS, 4).hex().upper() == "3F3F40C080C000200000000000000000"
    assert round(entropy_of_counts(np.bincount(np.frombuffer(WORDS, np.uint8), minlength=256)), 6) == 1.966917
    ints = foundational.ordered_ints(np.frombuffer(WORDS, "<u4"))
    assert [f"{v:08X}" for v in ints.tolist()] == ["BF800000", "BFC00000", "C0000000", "3FDFFFFF"]


@given(st.binary(max_size=600), st.sampled_from(sorted(CODECS)), st.sampled_from([1, 2, 4, 8]))
@settings(max_examples=300, deadline=None)
def test_every_codec_restores_words(data, name, width):
    data = data[: len(data) // width * width]
    codec = CODECS[name]
    assert codec.decode(codec.encode(data, width, None), width, len(data)) == data


@pytest.mark.parametrize("name", sorted(CODECS))
def test_every_codec_on_shapes(name):
    codec = CODECS[name]
    for x in (np.full(700, 1.5), np.arange(700.0), np.random.default_rng(1).normal(size=700), np.array([np.nan, np.inf, -np.inf, 0.0, -0.0, 5e-324])):
        data = x.astype("<f8").tobytes()
        assert codec.decode(codec.encode(data, 8, None), 8, len(data)) == data


@pytest.mark.parametrize("packing_", ["byte", "value"])
@pytest.mark.parametrize("layout", ["decomposed", "monolithic"])
@pytest.mark.parametrize("name", ["zstd", "xor", "huffman"])
def test_blocks_round_trip(name, layout, packing_):
    data = np.random.default_rng(0).normal(size=300).astype("<f8").tobytes()
    spec = pipeline.PlanSpec(codec=name, layout=layout, packing=packing_, mode="user")
    for c in ([[0], [1, 2], [3, 4, 5, 6], [7]], [[i] for i in range(8)], [list(range(8))]):
        streams, raw, part, _ = pipeline.encode_block(data, 8, c, spec)
        assert pipeline.decode_block(streams, raw, part, 8, 300, CODECS[name].id, packing_) == data


def test_order_zero_entropy_is_invariant():
    data = np.random.default_rng(0).normal(size=1000).astype("<f4").tobytes()
    for c in cluster.set_partitions(4):
        after = b"".join(packing.transform(data, 4, c))
        assert sorted(after) == sorted(data)


def test_entry_runs_without_the_optional_folders(spark):
    import __spark_entry__ as e

    rows = e.entry(spark).collect()
    assert rows and all(r.exact for r in rows)
