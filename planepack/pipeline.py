"""Fit, compress, decompress: blocks -> plane clusters -> independent streams -> container rows, and back.

After the one shuffle that puts words in order, everything is narrow: a block is packed, split and encoded inside the task that has it.
"""

from __future__ import annotations

import json
import struct
import time
import zlib
from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import cluster, features
from .blocks import sample_blocks
from .codecs import BY_ID, CODECS, stream_width
from .packing import ordered, pack, unpack
from .words import as_planes, from_planes


@dataclass(frozen=True)
class PlanSpec:
    codec: str = "zstd"
    level: int | None = None
    packing: str = "byte"  # or value
    layout: str = "decomposed"  # a stream per cluster, or monolithic: one stream
    mode: str = "dynamic"  # dynamic, static, user, standard
    features: str | None = None  # entropy, frequency, combined; None: by width
    score: str | None = None
    method: str = "single"
    sample: float = 0.3
    scope: str = "dataset"  # or block: a partition per block
    cluster_order: str = "plane"
    partition: tuple | None = None
    guard: str | bool = False  # keep the standard image where it is smaller: "sample" decides per dataset on sampled blocks, "block" (or True) on every block
    degenerate: str = "strict"  # rule for one cluster and for undefined scores, see cluster.choose_partition

    def with_(self, **kw) -> PlanSpec:
        return replace(self, **kw)


_FIT = pa.schema([("dataset", pa.string()), ("width", pa.int32()), ("candidates", pa.int32()), ("fit_ns", pa.int64()), ("partition", pa.list_(pa.list_(pa.int32())))])
FIT_DDL = "dataset string, width int, candidates int, fit_ns long, partition array<array<int>>"


def fit_table(blocks: DataFrame, spec: PlanSpec | None = None) -> DataFrame:
    """(dataset, width, candidates, fit_ns, partition): one pass over the sampled blocks, then every dataset is clustered in the task that has its statistics."""
    spec = spec or PlanSpec()
    sampled = sample_blocks(blocks, spec.sample) if spec.sample < 1 else blocks

    def run(batches):
        for ds, planes in features.merged(batches).items():
            t, n = time.perf_counter_ns(), len(planes)
            want, score = cluster.default_policy(n)
            x = features.vectors(np.array([p.features() for p in planes]), np.array([p.hist for p in planes], float), spec.features or want)
            c = cluster.choose_partition(x, spec.score or score, spec.method, spec.degenerate)
            row = (ds, n, 1 if n == 2 else n, time.perf_counter_ns() - t, c)
            yield pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(row, _FIT, strict=True)], schema=_FIT)

    return features.partial_features(sampled).mapInArrow(run, FIT_DDL)


def fit(blocks: DataFrame, spec: PlanSpec | None = None) -> dict[str, list[list[int]]]:
    """dataset -> partition, from a share of the blocks, by one job; only partitions reach the driver.

    Score ``measured`` takes, of the candidates for every cluster count, the one whose streams of the sampled blocks are smallest.  Guard ``sample``
    gives an empty partition (the standard image) to a dataset whose sampled blocks are smaller without the transform.
    """
    spec = spec or PlanSpec()
    if spec.score != "measured":
        out = {r.dataset: [list(g) for g in r.partition] for r in fit_table(blocks, spec).collect()}
        return guarded(blocks, out, spec) if spec.guard == "sample" else out
    from .ablation import measure

    sampled = sample_blocks(blocks, spec.sample)
    options: dict[str, dict] = {}
    for ds, (h, hist) in features.collect_stats(sampled).items():
        x = features.vectors(h, hist, spec.features or cluster.default_policy(len(h))[0])
        for c in cluster.linkage(x, spec.method):
            options.setdefault(str(c), {})[ds] = c
    plain = spec.with_(mode="user", score=None, guard=False)
    rows = measure(sampled, [(label, plain, parts) for label, parts in options.items()], decode=False).collect()  # a row per dataset and cluster count
    best = {}
    for r in sorted(rows, key=lambda r: (r.enc, len(options[r.job][r.dataset]))):
        best.setdefault(r.dataset, options[r.job][r.dataset])
    return guarded(blocks, best, spec) if spec.guard == "sample" else best


def guarded(blocks: DataFrame, partitions: dict, spec: PlanSpec) -> dict[str, list[list[int]]]:
    """Empty partitions for the datasets whose sampled blocks are smaller as standard images."""
    from .ablation import measure

    plain = spec.with_(mode="user", score=None, guard=False)
    rows = measure(sample_blocks(blocks, spec.sample), [("clustered", plain, partitions), ("standard", plain.with_(mode="standard"), {})], decode=False).collect()
    size = {(r.dataset, r.job): r.enc for r in rows}
    return {ds: [] if size[(ds, "standard")] < size[(ds, "clustered")] else c for ds, c in partitions.items()}


def block_partition(m: np.ndarray, spec: PlanSpec) -> list[list[int]]:
    """The partition of one block on its own; its entropies have no deviation."""
    n = m.shape[1]
    hists = np.stack([np.bincount(m[:, p], minlength=256) for p in range(n)])
    h = np.array([features.entropy_of_counts(c) for c in hists])
    fr = hists / max(1, len(m))
    want, score = cluster.default_policy(n)
    want, score = spec.features or want, spec.score or score
    ent = np.stack([h, np.zeros(n), h, h], 1)
    return cluster.choose_partition(ent if want == "entropy" else fr if want == "frequency" else np.hstack([ent, fr]), score, spec.method)


def encode_block(data: bytes, width: int, partition, spec: PlanSpec) -> tuple[list[bytes], list[int], list[list[int]], str]:
    """Payload streams, raw lengths, the partition used, and the variant."""
    codec = CODECS[spec.codec]
    if spec.mode == "standard" or (partition is not None and not len(partition) and spec.scope != "block"):
        return [codec.encode(data, width, spec.level)], [len(data)], [], "standard"
    m = as_planes(data, width)
    if spec.scope == "block":
        partition = block_partition(m, spec)
    if spec.cluster_order != "plane":
        h = [features.entropy_of_counts(np.bincount(m[:, p], minlength=256)) for p in range(width)]
        partition = ordered(partition, h, spec.cluster_order)
    raw = pack(m, partition, spec.packing)
    if spec.layout == "monolithic" and len(partition) > 1:
        raw = [b"".join(raw)]
        payload = [codec.encode(raw[0], 1, spec.level)]
    else:
        payload = [codec.encode(s, stream_width(width, len(g), spec.packing), spec.level) for s, g in zip(raw, partition, strict=True)]
    if spec.guard in (True, "block"):
        plain = codec.encode(data, width, spec.level)
        if len(plain) < sum(map(len, payload)):
            return [plain], [len(data)], [], "standard"
    return payload, [len(s) for s in raw], partition, "clustered"


def decode_block(streams, raw_len, partition, width, n, codec_id, packing) -> bytes:
    codec = BY_ID[codec_id]
    if not partition:
        return codec.decode(streams[0], width, raw_len[0])
    if len(streams) == 1 < len(partition):
        whole, at, raw = codec.decode(streams[0], 1, raw_len[0]), 0, []
        for g in partition:
            raw.append(whole[at : at + n * len(g)])
            at += n * len(g)
    else:
        raw = [codec.decode(s, stream_width(width, len(g), packing), k) for s, k, g in zip(streams, raw_len, partition, strict=True)]
    return from_planes(unpack(raw, partition, packing, n))


_CONTAINER = pa.schema(
    [("dataset", pa.string()), ("block_id", pa.int64()), ("n_values", pa.int32()), ("n_nulls", pa.int32()), ("validity", pa.binary()), ("word_width", pa.int32()), ("codec_id", pa.int32()), ("packing", pa.string()), ("partition", pa.list_(pa.list_(pa.int32()))), ("raw_len", pa.list_(pa.int32())), ("enc_len", pa.list_(pa.int32())), ("header_len", pa.int32()), ("crc32", pa.int64()), ("enc_ns", pa.int64()), ("min_bits", pa.int64()), ("max_bits", pa.int64())]
    + [(f"s{i}", pa.binary()) for i in range(8)]
)
CONTAINER_DDL = "dataset string, block_id long, n_values int, n_nulls int, validity binary, word_width int, codec_id int, packing string, partition array<array<int>>, raw_len array<int>, enc_len array<int>, header_len int, crc32 long, enc_ns long, min_bits long, max_bits long, " + ", ".join(f"s{i} binary" for i in range(8))
_BITS = {8: np.int64, 4: np.int32, 2: np.int16}
#: Fixed fields of a serialised row: version, length of the text header, block, words, nulls, codec, checksum, streams, length of the validity bits.
FIXED, PER_STREAM = "<BHqiiiIBi", "<II"


def text_header(ds: str, width: int, packing: str, partition) -> bytes:
    return json.dumps([ds, width, packing, partition or []]).encode()


def header_len(ds: str, width: int, packing: str, partition, streams: int, validity: bytes | None) -> int:
    """Bytes that a serialised row has besides its payload."""
    return struct.calcsize(FIXED) + len(text_header(ds, width, packing, partition)) + streams * struct.calcsize(PER_STREAM) + len(validity or b"")


def container_row(ds, width, block_id, n, nulls, validity, data, partition, spec: PlanSpec) -> tuple:
    t = time.perf_counter_ns()
    streams, raw, part, _ = encode_block(data, width, partition, spec)
    t = time.perf_counter_ns() - t
    w = np.frombuffer(data, _BITS[width])
    head = header_len(ds, width, spec.packing, part, len(streams), validity)
    return (ds, block_id, n, nulls, validity, width, CODECS[spec.codec].id, spec.packing, part, raw, list(map(len, streams)), head, zlib.crc32(data), t, int(w.min()) if n else None, int(w.max()) if n else None, *streams, *[None] * (8 - len(streams)))


def compress_blocks(blocks: DataFrame, partitions: dict | Callable, spec: PlanSpec | None = None) -> DataFrame:
    """Container rows; narrow.  ``partitions``: by dataset, or a function of its name."""
    spec = spec or PlanSpec()
    lookup = partitions if callable(partitions) else partitions.get

    def run(batches):
        for r in batches:
            for row in zip(*(r.column(i).to_pylist() for i in range(7)), strict=True):
                out = container_row(*row, lookup(row[0]), spec)
                yield pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(out, _CONTAINER, strict=True)], schema=_CONTAINER)

    return blocks.select("dataset", "width", "block_id", "n", "n_nulls", "validity", "data").mapInArrow(run, CONTAINER_DDL)


def compress(blocks: DataFrame, spec: PlanSpec | None = None, catalogue: dict | None = None) -> DataFrame:
    """Partition by the spec's mode, then container rows; only the dynamic mode reads the blocks twice."""
    spec = spec or PlanSpec()
    if spec.mode == "standard" or spec.scope == "block":
        return compress_blocks(blocks, {}, spec)
    if spec.mode == "user":
        given = [list(g) for g in spec.partition]
        return compress_blocks(blocks, lambda ds: given, spec)
    if spec.mode == "static":
        from .fixtures import DATASETS

        return compress_blocks(blocks, {ds: catalogue[(d[4], d[2])] for ds, d in DATASETS.items() if (d[4], d[2]) in catalogue}, spec)
    return compress_blocks(blocks, fit(blocks, spec), spec)


_BLOCK = pa.schema([("dataset", pa.string()), ("width", pa.int32()), ("block_id", pa.int64()), ("n", pa.int32()), ("n_nulls", pa.int32()), ("validity", pa.binary()), ("data", pa.binary()), ("dec_ns", pa.int64())])
BLOCK_DDL = "dataset string, width int, block_id long, n int, n_nulls int, validity binary, data binary, dec_ns long"


def decompress_blocks(container: DataFrame) -> DataFrame:
    """Blocks back from container rows; every block is held against its checksum.  Narrow: no shuffle."""

    def run(batches):
        for r in batches:
            for x in r.to_pylist():
                streams = [x[f"s{i}"] for i in range(len(x["raw_len"]))]
                t = time.perf_counter_ns()
                data = decode_block(streams, x["raw_len"], x["partition"], x["word_width"], x["n_values"], x["codec_id"], x["packing"])
                t = time.perf_counter_ns() - t
                if zlib.crc32(data) != x["crc32"]:
                    raise ValueError(f"block {x['block_id']} of {x['dataset']} is damaged")
                row = (x["dataset"], x["word_width"], x["block_id"], x["n_values"], x["n_nulls"], x["validity"], data, t)
                yield pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(row, _BLOCK, strict=True)], schema=_BLOCK)

    return container.drop("enc_ns", "min_bits", "max_bits", "enc_len", "header_len").mapInArrow(run, BLOCK_DDL)


def sizes(container: DataFrame) -> DataFrame:
    """(dataset, raw, enc, enc_with_header, blocks, streams, largest_unit, enc_ns): sums over blocks, never means of ratios."""
    per = F.col("n_values").cast("long") * F.col("word_width")
    enc = F.aggregate("enc_len", F.lit(0).cast("long"), lambda a, x: a + x)
    return container.groupBy("dataset").agg(
        F.sum(per).alias("raw"), F.sum(enc).alias("enc"), F.sum(enc + F.col("header_len")).alias("enc_with_header"),
        F.count(F.lit(1)).alias("blocks"), F.sum(F.size("enc_len")).alias("streams"), F.max(F.array_max("enc_len")).alias("largest_unit"), F.sum("enc_ns").alias("enc_ns"))


def build_catalogue(blocks: DataFrame, spec: PlanSpec | None = None) -> dict[tuple[str, str], list[list[int]]]:
    """(application, word type) -> partition, fitted on the merged samples of the category's datasets."""
    from .fixtures import DATASETS

    spec = spec or PlanSpec()
    name = F.create_map(*[F.lit(v) for d, k in DATASETS.items() for v in (d, f"{k[4]}|{k[2]}")])[F.col("dataset")]
    merged = sample_blocks(blocks, spec.sample).withColumn("dataset", name)
    got = fit(merged, spec.with_(sample=1.0))
    return {tuple(k.split("|")): v for k, v in got.items()}
