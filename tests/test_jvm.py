import time

import numpy as np
import pytest

from planepack import ablation, jvm, pipeline
from planepack.codecs import CODECS


def shapes(width):
    rng = np.random.default_rng(width)
    kinds = {8: "<f8", 4: "<f4", 2: "<f2", 1: "u1"}
    for x in (np.zeros(20000), np.round(rng.normal(500, 200, 12000), 2), np.arange(9000.0), rng.integers(0, 50, 20000) * 1.0, np.array([np.nan, np.inf, -np.inf, -0.0, 5e-324]), rng.normal(size=9000), np.array([1.5]), np.array([])):
        yield (np.nan_to_num(x, posinf=1, neginf=0) % 256 if width == 1 else x).astype(kinds[width]).tobytes()
    yield rng.integers(0, 256, 150000).astype(np.uint8).tobytes()[: 150000 // width * width]  # longer than the window
    yield b"".join([b"abcd", b"abcde", b"\0" * 9, b"x"][k] for k in rng.integers(0, 4, 9000))[:32000]
    fib = [1, 1]
    while len(fib) < 20:
        fib.append(fib[-1] + fib[-2])
    x = np.repeat(np.arange(20, dtype=np.uint8), fib)  # codes longer than the decoder's table
    yield x[: len(x) // width * width].tobytes()


def test_same_bytes_as_the_python_loops(spark):
    assert jvm.register(spark)
    rows = [(i, w, c, bytearray(d)) for w in (1, 2, 4, 8) for i, d in enumerate(shapes(w)) for c in sorted(jvm.NAMES)]
    t = spark.createDataFrame(rows, "i int, w int, c string, data binary").selectExpr("*", "pp_jvm_code(data, w, c, -1) as enc").selectExpr("*", "pp_jvm_code(enc, w, c, octet_length(data)) as back")
    for r in t.collect():
        assert bytes(r.enc) == CODECS[r.c].encode(bytes(r.data), r.w, None), (r.i, r.w, r.c)
        assert r.back == r.data, (r.i, r.w, r.c)


@pytest.mark.parametrize("decode", [True, False])
def test_measures_equal_the_python_ones(spark, monkeypatch, decode):
    rng = np.random.default_rng(0)
    rows = [(n, w, bytearray(np.round(rng.normal(500, 200, 700 + i), 2).astype(f"<f{w}").tobytes())) for i in range(3) for n, w in (("a", 8), ("b", 4), ("c", 2), ("without", 4))]
    b = spark.createDataFrame(rows, "dataset string, width int, data binary")
    parts = {"a": [[0], [1, 2], [3, 4, 5, 6], [7]], "b": [[0, 1, 2], [3]], "c": []}
    jobs = [(f"{c}|{p}|{x}", pipeline.PlanSpec(codec=c, mode="user", packing=p, layout=x), parts) for c in [*sorted(jvm.NAMES), "zstd"] for p in ("byte", "value") for x in ("decomposed", "monolithic")]
    jobs += [(c, pipeline.PlanSpec(codec=c, mode="standard"), {}) for c in sorted(jvm.NAMES)]
    keep = ("dataset", "job", "raw", "enc", "enc_with_header", "streams", "exact", "cr")
    got = sorted(map(tuple, ablation.measure(b, jobs, decode).select(*keep).collect()))
    monkeypatch.setattr(jvm, "register", lambda spark: False)
    assert got == sorted(map(tuple, ablation.measure(b, jobs, decode).select(*keep).collect())) and len(got) == 3 * 36 + 4 * 8


def test_megabytes_in_seconds(spark):
    """What the loops in Python take minutes for."""
    data = np.round(np.random.default_rng(0).normal(500, 200, 1 << 19), 2).astype("<f8").tobytes()
    b = spark.createDataFrame([("a", 8, bytearray(data))], "dataset string, width int, data binary")
    t = time.perf_counter()
    got = ablation.measure(b, [(c, pipeline.PlanSpec(codec=c, mode="standard"), {}) for c in ("fastlz", "lz77", "huffman", "xor", "xor-of-128", "delta", "hashed", "stride-lz")]).collect()
    assert len(got) == 8 and all(r.exact for r in got) and time.perf_counter() - t < 15
