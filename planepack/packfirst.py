"""Transform first, then cut: the cluster streams of a whole column are laid out one after the other and cut into chunks.

The other order of the stages, kept for comparison: every byte is copied through a shuffle before it is encoded, and again after it is decoded.
Chunks are independent, so nothing larger than a chunk or a block is ever in memory.  Validity bits travel beside the streams as cluster -1.
"""

from __future__ import annotations

import itertools
import time
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import _BLOCK
from .codecs import BY_ID, CODECS
from .packing import pack, unpack
from .pipeline import PlanSpec
from .words import as_planes, from_planes

_SEGMENT = pa.schema([("dataset", pa.string()), ("width", pa.int32()), ("cluster", pa.int32()), ("chunk", pa.int64()), ("at", pa.int64()), ("data", pa.binary()), ("ns", pa.int64())])
_SEGMENT_DDL = "dataset string, width int, cluster int, chunk long, at long, data binary, ns long"
_CHUNK = pa.schema([("dataset", pa.string()), ("width", pa.int32()), ("cluster", pa.int32()), ("chunk", pa.int64()), ("codec_id", pa.int32()), ("raw_len", pa.int32()), ("crc32", pa.int64()), ("enc_ns", pa.int64()), ("payload", pa.binary())])
CHUNK_DDL = "dataset string, width int, cluster int, chunk long, codec_id int, raw_len int, crc32 long, enc_ns long, payload binary"
_BACK = pa.schema([("dataset", pa.string()), ("width", pa.int32()), ("block_id", pa.int64()), ("cluster", pa.int32()), ("at", pa.int64()), ("data", pa.binary()), ("ns", pa.int64())])
_BACK_DDL = "dataset string, width int, block_id long, cluster int, at long, data binary, ns long"


def _batch(rows: list, schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)


def lengths(blocks: DataFrame) -> dict[str, int]:
    """Words of every dataset: a row each reaches the driver."""
    return {r.dataset: r.n for r in blocks.groupBy("dataset").agg(F.sum("n").alias("n")).collect()}


def _places(block: int, n: int, per: int, total: int, members: int, packing: str):
    """(offset in the block's stream of a cluster, offset in the column's stream, length) of what a block holds of it."""
    start = block * per
    if packing == "value":
        yield 0, start * members, n * members
    else:
        for j in range(members):
            yield j * n, j * total + start, n


def compress_pack_first(blocks: DataFrame, partitions: dict, spec: PlanSpec, block_bytes: int, total: dict[str, int]) -> DataFrame:
    """Encoded chunks of ``block_bytes`` of the streams; ``total`` from :func:`lengths`."""

    def segments(batches):
        for r in batches:
            for ds, width, block, n, valid, data in zip(*(c.to_pylist() for c in r.columns), strict=True):
                t, rows = time.perf_counter_ns(), []
                m, per = as_planes(data, width), block_bytes // width
                for c, g in enumerate(partitions[ds]):
                    stream = pack(m, [g], spec.packing)[0]
                    for at, to, k in _places(block, n, per, total[ds], len(g), spec.packing):
                        while k:
                            chunk, where = divmod(to, block_bytes)
                            step = min(k, block_bytes - where)
                            rows.append([ds, width, c, chunk, where, stream[at : at + step], 0])
                            at, to, k = at + step, to + step, k - step
                rows[0][-1] = time.perf_counter_ns() - t
                if valid is not None:
                    rows.append([ds, width, -1, block, 0, valid, 0])
                yield _batch(rows, _SEGMENT)

    def encoded(batches):
        codec = CODECS[spec.codec]
        rows = (x for r in batches for x in zip(*(c.to_pylist() for c in r.columns), strict=True))
        for (ds, width, c, chunk), group in itertools.groupby(rows, lambda x: x[:4]):
            parts = list(group)
            t = time.perf_counter_ns()
            raw = b"".join(x[5] for x in parts)
            payload = raw if c < 0 else codec.encode(raw, 1, spec.level)
            ns = time.perf_counter_ns() - t + sum(x[6] for x in parts)
            yield _batch([(ds, width, c, chunk, 0 if c < 0 else codec.id, len(raw), zlib.crc32(raw), ns, payload)], _CHUNK)

    key = ["dataset", "width", "cluster", "chunk"]
    cells = blocks.select("dataset", "width", "block_id", "n", "validity", "data").mapInArrow(segments, _SEGMENT_DDL)
    return cells.repartition(*key).sortWithinPartitions(*key, "at").mapInArrow(encoded, CHUNK_DDL)


def decompress_pack_first(chunks: DataFrame, partitions: dict, spec: PlanSpec, block_bytes: int, total: dict[str, int]) -> DataFrame:
    """Blocks back from chunks, each held against its checksum: (dataset, width, block_id, n, n_nulls, validity, data, dec_ns)."""

    def cells(batches):
        for r in batches:
            for ds, width, c, chunk, codec, n_raw, crc, payload in zip(*(x.to_pylist() for x in r.columns), strict=True):
                if c < 0:
                    yield _batch([(ds, width, chunk, -1, 0, payload, 0)], _BACK)
                    continue
                t = time.perf_counter_ns()
                raw = BY_ID[codec].decode(payload, 1, n_raw)
                if zlib.crc32(raw) != crc:
                    raise ValueError(f"chunk {chunk} of {ds} is damaged")
                per, n_all, members, rows = block_bytes // width, total[ds], len(partitions[ds][c]), []
                lo, end = chunk * block_bytes, chunk * block_bytes + n_raw
                at = lo
                while at < end:  # up to the end of the block's share of this plane (or of these words)
                    j, word = divmod(at, n_all) if spec.packing == "byte" else (0, at // members)
                    block = word // per
                    n = min(per, n_all - block * per)
                    if spec.packing == "byte":
                        here, stop = j * n + word - block * per, j * n_all + block * per + n
                    else:
                        here, stop = at - block * per * members, (block * per + n) * members
                    stop = min(stop, end)
                    rows.append([ds, width, block, c, here, raw[at - lo : stop - lo], 0])
                    at = stop
                rows[0][-1] = time.perf_counter_ns() - t
                yield _batch(rows, _BACK)

    schema = pa.schema([*_BLOCK, ("dec_ns", pa.int64())])

    def joined(batches):
        rows = (x for r in batches for x in zip(*(c.to_pylist() for c in r.columns), strict=True))
        for (ds, width, block), group in itertools.groupby(rows, lambda x: x[:3]):
            t, ns, streams, valid = time.perf_counter_ns(), 0, [b""] * len(partitions[ds]), None
            held: dict[int, list] = {}
            for _, _, _, c, _, data, took in group:
                held.setdefault(c, []).append(data)
                ns += took
            for c, parts in held.items():
                if c < 0:
                    valid = parts[0]
                else:
                    streams[c] = b"".join(parts)
            n = sum(map(len, streams)) // width
            data = from_planes(unpack(streams, partitions[ds], spec.packing, n))
            nulls = 0 if valid is None else n - int(np.unpackbits(np.frombuffer(valid, np.uint8), bitorder="little")[:n].sum())
            yield _batch([(ds, width, block, n, nulls, valid, data, time.perf_counter_ns() - t + ns)], schema)

    key = ["dataset", "width", "block_id"]
    back = chunks.drop("enc_ns").mapInArrow(cells, _BACK_DDL)
    return back.repartition(*key).sortWithinPartitions(*key, "cluster", "at").mapInArrow(joined, "dataset string, width int, block_id long, n int, n_nulls int, validity binary, data binary, dec_ns long")
