"""Entropies of words and of bytes in context, before and after the transform."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import sample_blocks
from .features import entropy_of
from .packing import transform


def word_entropy(df: DataFrame) -> DataFrame:
    """Entropy with the whole word as the symbol; null words are left out."""
    counts = df.filter("bits is not null").groupBy("dataset", "bits").agg(F.count(F.lit(1)).alias("c"))
    return counts.groupBy("dataset").agg(entropy_of("c").alias("word_entropy"), F.sum("c").alias("n"))


def _grams(x: np.ndarray, k: int) -> np.ndarray:
    """Every byte with the k bytes before it as one number, the byte itself lowest."""
    n = max(0, len(x) - k)
    g = np.zeros(n, np.int64)
    for j in range(k + 1):
        g = g << 8 | x[j : j + n].astype(np.int64)
    return g


_COUNT = pa.schema([("dataset", pa.string()), ("gram", pa.int64()), ("c", pa.int64())])
#: Distinct grams that a task holds before it sends them on.
HELD = 2_000_000


def gram_counts(blocks: DataFrame, k: int) -> DataFrame:
    """(dataset, gram, c): counts of (k + 1)-byte runs of the little-endian image of the words; runs stay inside a block."""

    def run(batches):
        state: dict[str, tuple] = {}

        def sent(ds):
            g, c = state.pop(ds)
            return pa.RecordBatch.from_arrays([pa.array([ds] * len(g), pa.string()), pa.array(g), pa.array(c)], schema=_COUNT)

        for r in batches:
            for ds, data in zip(*(r.column(i).to_pylist() for i in range(2)), strict=True):
                g, c = np.unique(_grams(np.frombuffer(data, np.uint8), k), return_counts=True)
                if ds in state:
                    both, where = np.unique(np.concatenate([state[ds][0], g]), return_inverse=True)
                    g, c = both, np.bincount(where, np.concatenate([state[ds][1], c])).astype(np.int64)
                state[ds] = g, c
                if len(g) > HELD:
                    yield sent(ds)
        for ds in list(state):
            yield sent(ds)

    t = blocks.select("dataset", "data").mapInArrow(run, "dataset string, gram long, c long")
    return t.groupBy("dataset", "gram").agg(F.sum("c").alias("c"))


def entropy_k(blocks: DataFrame, k: int, kind: str = "conditional", sample: float = 1.0) -> DataFrame:
    """(dataset, hk): entropy of a byte given the k before it; ``joint``: of the whole run.

    Contexts are whole numbers; tasks count before the shuffle.  Up to 256^(k + 1) groups: above k = 2 a large dataset is sampled by blocks.
    """
    both = gram_counts(blocks if sample >= 1 else sample_blocks(blocks, sample), k)
    if kind == "joint":
        return both.groupBy("dataset").agg(F.greatest(F.round(F.log2(F.sum("c")) - F.sum(F.col("c") * F.log2("c")) / F.sum("c"), 5) + 0.0, F.lit(0.0)).alias(f"h{k}"))
    h = both.groupBy("dataset", F.shiftright("gram", 8).alias("ctx")).agg(F.sum("c").alias("t"), F.sum(F.col("c") * F.log2("c")).alias("s"))
    # H(byte | context) = sum over contexts of t log2 t - s, by the number of all bytes
    return h.groupBy("dataset").agg(F.greatest(F.round((F.sum(F.col("t") * F.log2("t")) - F.sum("s")) / F.sum("t"), 5) + 0.0, F.lit(0.0)).alias(f"h{k}"))


_K = pa.schema([("dataset", pa.string()), ("k", pa.int32()), ("side", pa.string()), ("num", pa.float64()), ("total", pa.int64())])


def _conditional(x: np.ndarray, k: int) -> tuple[float, int]:
    """(sum over contexts of t log2 t - sum c log2 c, bytes)."""
    g = _grams(x, k)
    if not len(g):
        return 0.0, 0
    both, c = np.unique(g, return_counts=True)
    t = np.add.reduceat(c, np.nonzero(np.concatenate([[True], both[1:] >> 8 != both[:-1] >> 8]))[0]).astype(float)
    c = c.astype(float)
    return float((t * np.log2(t)).sum() - (c * np.log2(c)).sum()), len(g)


def before_after(blocks: DataFrame, partitions: dict, packing: str = "byte", most: int = 4) -> DataFrame:
    """(dataset, k, h_before, h_after): block-wise conditional entropies of the word image and of the cluster streams."""

    def run(batches):
        total: dict = {}
        for r in batches:
            for ds, width, data in zip(*(r.column(i).to_pylist() for i in range(3)), strict=True):
                image, streams = [data], transform(data, width, partitions[ds], packing)
                for k in range(most + 1):
                    for side, parts in (("before", image), ("after", streams)):
                        s = total.setdefault((ds, k, side), [0.0, 0])
                        for p in parts:
                            num, n = _conditional(np.frombuffer(p, np.uint8), k)
                            s[0] += num
                            s[1] += n
        if total:
            cols = zip(*((*key, *v) for key, v in total.items()), strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, _K, strict=True)], schema=_K)

    t = blocks.select("dataset", "width", "data").mapInArrow(run, "dataset string, k int, side string, num double, total long")
    h = lambda s: F.greatest(F.round(F.sum(F.when(F.col("side") == s, F.col("num"))) / F.sum(F.when(F.col("side") == s, F.col("total"))), 5) + 0.0, F.lit(0.0))
    return t.groupBy("dataset", "k").agg(h("before").alias("h_before"), h("after").alias("h_after"))


def order0(blocks: DataFrame, partitions: dict, packing: str = "byte") -> DataFrame:
    """Order-0 entropy of all bytes before and after: a permutation leaves the histogram alone."""
    schema = pa.schema([("dataset", pa.string()), ("side", pa.string()), ("hist", pa.list_(pa.int64()))])

    def run(batches):
        for r in batches:
            for ds, width, data in zip(*(r.column(i).to_pylist() for i in range(3)), strict=True):
                after = b"".join(transform(data, width, partitions[ds], packing))
                rows = [np.bincount(np.frombuffer(x, np.uint8), minlength=256).tolist() for x in (data, after)]
                yield pa.RecordBatch.from_arrays([pa.array([ds, ds]), pa.array(["before", "after"]), pa.array(rows, pa.list_(pa.int64()))], schema=schema)

    long = blocks.select("dataset", "width", "data").mapInArrow(run, "dataset string, side string, hist array<long>")
    counts = long.select("dataset", "side", F.posexplode("hist").alias("byte", "c")).groupBy("dataset", "side", "byte").agg(F.sum("c").alias("c")).filter("c > 0")
    return counts.groupBy("dataset", "side").agg(entropy_of("c").alias("h0"))
