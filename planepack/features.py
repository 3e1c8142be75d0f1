"""Features of byte planes: block entropies and byte frequencies, in SQL form and as mergeable partial sums over blocks."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .words import as_planes, shifted


def plane_bytes(df: DataFrame) -> DataFrame:
    """Long form: a row per (word, plane)."""
    byte = shifted(F.col("bits"), F.lit(8) * (F.col("width") - 1 - F.col("plane"))).bitwiseAND(F.lit(255)).cast("int")
    return df.withColumn("plane", F.explode(F.sequence(F.lit(0), F.col("width") - 1))).withColumn("byte", byte)


def entropy_of(count: str, *by: str):
    """log2(T) - sum(c log2 c) / T of a column of counts, exactly 0 for one symbol."""
    c = F.col(count)
    return F.greatest(F.round(F.log2(F.sum(c)) - F.sum(c * F.log2(c)) / F.sum(c), 6) + 0.0, F.lit(0.0))


def _counted(batches, by: bool, schema: pa.Schema):
    """Counts of every byte per dataset (and ``by`` value) and plane; without ``by`` a task sends at most 256 rows a plane."""
    whole: dict = {}
    for r in batches:
        names = r.column(0).dictionary_encode()
        valid = r.column(r.num_columns - 1).is_valid().to_numpy(zero_copy_only=False)
        code, widths = names.indices.to_numpy()[valid].astype(np.int64), r.column(1).to_numpy()[valid]
        bits = r.column(r.num_columns - 1).drop_null().to_numpy()
        of = r.column(2).to_numpy()[valid] if by else np.zeros(len(bits), np.int64)
        names = names.dictionary.to_pylist()
        for w in np.unique(widths).tolist():
            at = widths == w
            groups, where = np.unique((code[at] << 40) | of[at], return_inverse=True)
            groups = np.stack([groups >> 40, groups & ((1 << 40) - 1)])
            for p in range(w):
                byte = (bits[at] >> (8 * (w - 1 - p))) & 255
                counts = np.bincount(where * 256 + byte, minlength=256 * groups.shape[1]).reshape(-1, 256)
                if by:
                    g, v = np.nonzero(counts)
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(([names[i] for i in groups[0][g]], groups[1][g], np.full(len(g), p), v, counts[g, v]), schema, strict=True)], schema=schema)
                else:
                    for i, c in zip(groups[0].tolist(), counts, strict=True):
                        k = (names[i], p)
                        whole[k] = whole[k] + c if k in whole else c
    for (ds, p), c in whole.items():
        v = np.nonzero(c)[0]
        yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(([ds] * len(v), np.full(len(v), p), v, c[v]), schema, strict=True)], schema=schema)


def plane_hist(df: DataFrame, *by: str) -> DataFrame:
    """(dataset, [by,] plane, byte, cnt) of word rows in any order; ``by`` is at most one column of whole numbers from 0 to 2^40.  Null words count nowhere."""
    fields = [("dataset", pa.string()), *((c, pa.int64()) for c in by), ("plane", pa.int32()), ("byte", pa.int32()), ("cnt", pa.int64())]
    ddl = "dataset string, " + "".join(f"{c} long, " for c in by) + "plane int, byte int, cnt long"
    words = df.select("dataset", "width", *(F.col(c).cast("long").alias(c) for c in by), "bits")
    part = words.mapInArrow(lambda b: _counted(b, bool(by), pa.schema(fields)), ddl)
    return part.groupBy("dataset", *by, "plane", "byte").agg(F.sum("cnt").alias("cnt"))


def plane_hist_sql(df: DataFrame, *by: str) -> DataFrame:
    """The same with DataFrame functions only: a row per byte before the partial aggregation."""
    return plane_bytes(df).filter("bits is not null").groupBy("dataset", *by, "plane", "byte").agg(F.count(F.lit(1)).alias("cnt"))


def plane_entropy(df: DataFrame, *by: str) -> DataFrame:
    """Two aggregations: counts per byte, then the entropy of the counts."""
    return plane_hist(df, *by).groupBy("dataset", *by, "plane").agg(entropy_of("cnt").alias("h"))


def entropy_features(df: DataFrame) -> DataFrame:
    """Mean, sample deviation (0 for one block), maximum and minimum of the block entropies of each plane."""
    return plane_entropy(df, "block_id").groupBy("dataset", "plane").agg(
        F.round(F.avg("h") + 1e-9, 5).alias("h_avg"), F.round(F.coalesce(F.stddev_samp("h"), F.lit(0.0)) + 1e-9, 5).alias("h_std"), F.max("h").alias("h_max"), F.min("h").alias("h_min"))


def frequency_feature(df: DataFrame) -> DataFrame:
    """Normalised byte frequencies of each whole plane, in long form without zeros."""
    h = plane_hist(df)
    total = F.sum("cnt").over(Window.partitionBy("dataset", "plane"))
    return h.select("dataset", "plane", "byte", F.round(F.col("cnt") / total, 6).alias("freq"))


# ---------------------------------------------------------------- partial sums over blocks

_PART = pa.schema([("dataset", pa.string()), ("plane", pa.int32()), ("m", pa.int64()), ("mean", pa.float64()), ("m2", pa.float64()), ("h_max", pa.float64()), ("h_min", pa.float64()), ("hist", pa.list_(pa.int64()))])
PART_DDL = "dataset string, plane int, m long, mean double, m2 double, h_max double, h_min double, hist array<long>"
_FEATURE = pa.schema([("dataset", pa.string()), ("plane", pa.int32()), ("h_avg", pa.float64()), ("h_std", pa.float64()), ("h_max", pa.float64()), ("h_min", pa.float64()), ("hist", pa.list_(pa.int64()))])
FEATURE_DDL = "dataset string, plane int, h_avg double, h_std double, h_max double, h_min double, hist array<long>"


def entropy_of_counts(c: np.ndarray) -> float:
    c = c[c > 0].astype(float)
    t = c.sum()
    return max(0.0, float(np.log2(t) - (c * np.log2(c)).sum() / t)) if t else 0.0


class Stats:
    """Block entropies (count, mean, sum of squared deviations, maximum, minimum) and byte counts of a plane; two of them merge exactly."""

    __slots__ = ("m", "mean", "m2", "most", "least", "hist")

    def __init__(self, m=0, mean=0.0, m2=0.0, most=-1.0, least=9.0, hist=None):
        self.m, self.mean, self.m2, self.most, self.least = m, mean, m2, most, least
        self.hist = np.zeros(256, np.int64) if hist is None else hist

    def merge(self, o: Stats) -> None:
        m, gap = self.m + o.m, o.mean - self.mean
        if o.m:
            self.mean += gap * o.m / m
            self.m2 += o.m2 + gap * gap * self.m * o.m / m
        self.m, self.most, self.least = m, max(self.most, o.most), min(self.least, o.least)
        self.hist += o.hist

    def row(self) -> tuple:
        return self.m, self.mean, self.m2, self.most, self.least, self.hist.tolist()

    def features(self) -> list[float]:
        return [self.mean, float(np.sqrt(max(0.0, self.m2) / (self.m - 1))) if self.m > 1 else 0.0, self.most, self.least]


def _partials(batches):
    """A block never spans tasks, so block entropies are local; a task sends one row per dataset and plane."""
    state: dict = {}
    for r in batches:
        for ds, width, data in zip(*(r.column(i).to_pylist() for i in range(3)), strict=True):
            m = as_planes(data, width)
            for p in range(width):
                c = np.bincount(m[:, p], minlength=256)
                h = round(entropy_of_counts(c), 6)  # as in the SQL form, so both give the same features
                state.setdefault((ds, p), Stats()).merge(Stats(1, h, 0.0, h, h, c))
    if state:
        cols = list(zip(*((*k, *v.row()) for k, v in state.items()), strict=True))
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, _PART, strict=True)], schema=_PART)


def merged(batches) -> dict[str, list[Stats]]:
    """dataset -> statistics of its planes, from all partial rows of a task: the state is a few kilobytes a dataset, however many rows come."""
    state: dict = {}
    for r in batches:
        for ds, p, *v, hist in zip(*(c.to_pylist() for c in r.columns), strict=True):
            state.setdefault(ds, {}).setdefault(p, Stats()).merge(Stats(*v, np.array(hist, np.int64)))
    return {ds: [v for _, v in sorted(planes.items())] for ds, planes in state.items()}


def partial_features(blocks: DataFrame) -> DataFrame:
    """Partial rows with all rows of a dataset in one task: the shuffle has planes x tasks rows."""
    return blocks.select("dataset", "width", "data").mapInArrow(_partials, PART_DDL).repartition("dataset")


def feature_table(blocks: DataFrame) -> DataFrame:
    """(dataset, plane, h_avg, h_std, h_max, h_min, hist) from blocks."""

    def run(batches):
        for ds, planes in merged(batches).items():
            rows = [(ds, p, *x.features(), x.hist.tolist()) for p, x in enumerate(planes)]
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _FEATURE, strict=True)], schema=_FEATURE)

    return partial_features(blocks).mapInArrow(run, FEATURE_DDL)


def vectors(h: np.ndarray, hist: np.ndarray, features: str) -> np.ndarray:
    """(planes, 4), (planes, 256) or (planes, 260) from the entropy features and the byte counts."""
    freq = hist / np.maximum(1.0, hist.sum(1, keepdims=True))
    return h if features == "entropy" else freq if features == "frequency" else np.hstack([h, freq])


def collect_stats(blocks: DataFrame) -> dict[str, tuple[np.ndarray, np.ndarray]]:
    """dataset -> (entropy features, byte counts) of its planes, by one job: at most 8 x 260 numbers a dataset reach the driver."""
    out: dict[str, list] = {}
    for r in feature_table(blocks).collect():
        out.setdefault(r.dataset, []).append((r.plane, [r.h_avg, r.h_std, r.h_max, r.h_min], r.hist))
    return {d: (np.array([h for _, h, _ in sorted(v)]), np.array([c for _, _, c in sorted(v)], float)) for d, v in out.items()}


def collect_features(blocks: DataFrame, features: str = "frequency") -> dict[str, np.ndarray]:
    """dataset -> (planes, dimensions)."""
    return {d: vectors(h, hist, features) for d, (h, hist) in collect_stats(blocks).items()}


def pairwise_distance(df: DataFrame) -> DataFrame:
    """Euclidean distances between the frequency features of planes of a dataset (i < j), in SQL form."""
    f = frequency_feature(df)
    a = f.select("dataset", F.col("plane").alias("i"), "byte", F.col("freq").alias("fa"))
    planes = f.select("dataset", "plane").distinct()
    pairs = planes.withColumnRenamed("plane", "i").join(planes.withColumnRenamed("plane", "j"), "dataset").filter("i < j")  # at most 28 a dataset
    left = pairs.join(a, ["dataset", "i"])
    right = pairs.join(f.select("dataset", F.col("plane").alias("j"), "byte", F.col("freq").alias("fb")), ["dataset", "j"])
    d = left.join(right, ["dataset", "i", "j", "byte"], "full")
    gap = F.coalesce("fa", F.lit(0.0)) - F.coalesce("fb", F.lit(0.0))
    return d.groupBy("dataset", "i", "j").agg(F.round(F.sqrt(F.sum(gap * gap)), 5).alias("dist"))
