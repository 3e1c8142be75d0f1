"""Functions for SQL: ``register(spark)`` makes them callable by name."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf

from . import cluster
from .codecs import CODECS
from .features import entropy_of_counts
from .packing import transform
from .words import _bits32, _bits64, _value32, _value64


def pp_entropy(v: pa.Array) -> pa.Array:
    """Byte entropy of a binary value; null for null and empty."""
    return pa.array([None if not b else entropy_of_counts(np.bincount(np.frombuffer(b, np.uint8), minlength=256)) for b in v.to_pylist()], pa.float64())


def pp_encode(v: pa.Array, codec: pa.Array) -> pa.Array:
    return pa.array([None if b is None else CODECS[c].encode(b, 1, None) for b, c in zip(v.to_pylist(), codec.to_pylist(), strict=True)], pa.binary())


def pp_decode(v: pa.Array, codec: pa.Array, n: pa.Array) -> pa.Array:
    return pa.array([None if b is None else CODECS[c].decode(b, 1, k) for b, c, k in zip(v.to_pylist(), codec.to_pylist(), n.to_pylist(), strict=True)], pa.binary())


def pp_pack(v: pa.Array, width: pa.Array, partition: pa.Array, packing: pa.Array) -> pa.Array:
    """Cluster streams of a little-endian word image."""
    rows = zip(v.to_pylist(), width.to_pylist(), partition.to_pylist(), packing.to_pylist(), strict=True)
    return pa.array([None if b is None else transform(b, w, p, k) for b, w, p, k in rows], pa.list_(pa.binary()))


def pp_entropy_agg(v: pd.Series) -> float:
    return entropy_of_counts(np.bincount(v.to_numpy().astype(np.int64), minlength=256))


def pp_hist_agg(v: pd.Series) -> list[int]:
    """Counts of the 256 byte values."""
    return np.bincount(v.to_numpy().astype(np.int64), minlength=256).tolist()


def pp_choose(v: pa.Array, score: pa.Array) -> pa.Array:
    """Partition from the feature vectors of the planes."""
    return pa.array([cluster.choose_partition(np.array(x, float), s) for x, s in zip(v.to_pylist(), score.to_pylist(), strict=True)], pa.list_(pa.list_(pa.int32())))


class PpSetPartitions:
    def eval(self, n: int):
        for i, p in enumerate(cluster.set_partitions(n)):
            yield i, len(p), p


class PpWords:
    """Words of a decoded block image."""

    def eval(self, data: bytes, width: int):
        yield from enumerate(np.frombuffer(data, {8: "<i8", 4: "<i4", 2: "<i2"}[width]).tolist())


class PpPlanes:
    def eval(self, bits: int, width: int):
        for p in range(width):
            yield p, bits >> 8 * (width - 1 - p) & 255


def _types() -> dict:
    """name -> (function, result type, wrapper); wrapped when asked for, since workers import this module without a session."""
    return {
        "word_bits": (_bits64, "bigint", arrow_udf), "word_bits32": (_bits32, "bigint", arrow_udf), "bits_word": (_value64, "double", arrow_udf), "bits_word32": (_value32, "float", arrow_udf),
        "pp_entropy": (pp_entropy, "double", arrow_udf), "pp_encode": (pp_encode, "binary", arrow_udf), "pp_decode": (pp_decode, "binary", arrow_udf), "pp_pack": (pp_pack, "array<binary>", arrow_udf),
        "pp_choose": (pp_choose, "array<array<int>>", arrow_udf), "pp_entropy_agg": (pp_entropy_agg, "double", pandas_udf), "pp_hist_agg": (pp_hist_agg, "array<bigint>", pandas_udf),
    }


def column(name: str):
    """The function for use on columns."""
    f, kind, wrap = _types()[name]
    return wrap(f, kind)


def register(spark: SparkSession) -> None:
    for name in _types():
        spark.udf.register(name, column(name))
    spark.udtf.register("pp_set_partitions", udtf(PpSetPartitions, returnType="part_id int, clusters int, partition array<array<int>>"))
    spark.udtf.register("pp_planes", udtf(PpPlanes, returnType="plane int, byte int"))
    spark.udtf.register("pp_words", udtf(PpWords, returnType="pos int, bits bigint"))
