"""Containers at rest: Parquet with a column per cluster stream, a manifest, pruned reads, and a serialised row."""

from __future__ import annotations

import json
import struct

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .blocks import words_of_blocks
from .pipeline import FIXED, PER_STREAM, decode_block, decompress_blocks, sizes, text_header

VERSION = 1


def write_container(container: DataFrame, path: str, mode: str = "errorifexists", **about) -> None:
    """Blocks under ``path/blocks`` (payloads are compressed already, so Parquet stores them as they are) and a manifest row a dataset."""
    container.write.mode(mode).option("compression", "uncompressed").partitionBy("dataset").parquet(f"{path}/blocks")
    spark = container.sparkSession
    manifest = sizes(spark.read.parquet(f"{path}/blocks")).withColumn("format_version", F.lit(VERSION)).withColumn("about", F.lit(json.dumps(about)))
    manifest.write.mode(mode).parquet(f"{path}/manifest")


def read_manifest(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/manifest")


def read_container(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/blocks")


def read_blocks(spark: SparkSession, path: str, dataset: str, lo: int, hi: int) -> DataFrame:
    """Blocks lo <= id < hi: pruned by partition folder and by Parquet statistics, then decoded."""
    return decompress_blocks(read_container(spark, path).filter((F.col("dataset") == dataset) & (F.col("block_id") >= lo) & (F.col("block_id") < hi)))


def read_range(spark: SparkSession, path: str, dataset: str, rn_lo: int, rn_hi: int, block_bytes: int, width: int) -> DataFrame:
    """Words rn_lo <= rn < rn_hi by position."""
    per = block_bytes // width
    words = words_of_blocks(read_blocks(spark, path, dataset, rn_lo // per, -(-rn_hi // per)))
    return words.withColumn("rn", F.col("block_id") * per + F.col("pos")).filter((F.col("rn") >= rn_lo) & (F.col("rn") < rn_hi))


def to_bytes(row: dict) -> bytes:
    """One container row as bytes: header, codec, partition, offsets, payloads."""
    streams = [row[f"s{i}"] for i in range(len(row["raw_len"]))]
    head, validity = text_header(row["dataset"], row["word_width"], row["packing"], row["partition"]), row["validity"] or b""
    fixed = struct.pack(FIXED, VERSION, len(head), row["block_id"], row["n_values"], row["n_nulls"], row["codec_id"], row["crc32"], len(streams), len(validity))
    return fixed + head + validity + b"".join(struct.pack(PER_STREAM, r, len(s)) for r, s in zip(row["raw_len"], streams, strict=True)) + b"".join(streams)


def from_bytes(b: bytes) -> dict:
    version, k, block, n, nulls, codec, crc, m, v = struct.unpack_from(FIXED, b)
    if version != VERSION:
        raise ValueError(f"format version {version}")
    at = struct.calcsize(FIXED)
    ds, width, packing, part = json.loads(b[at : at + k])
    at += k
    validity = b[at : at + v] or None
    at += v
    lens = [struct.unpack_from(PER_STREAM, b, at + 8 * i) for i in range(m)]
    at += 8 * m
    row = {"dataset": ds, "block_id": block, "n_values": n, "n_nulls": nulls, "validity": validity, "word_width": width, "codec_id": codec, "packing": packing, "partition": part, "raw_len": [r for r, _ in lens], "enc_len": [e for _, e in lens], "header_len": at, "crc32": crc}
    for i, (_, e) in enumerate(lens):
        row[f"s{i}"] = b[at : at + e]
        at += e
    return row


_SURVIVED = pa.schema([("dataset", pa.string()), ("block_id", pa.int64()), ("raw", pa.int64()), ("same", pa.bool_())])


def survives(container: DataFrame) -> DataFrame:
    """(dataset, block_id, raw, same) of every block: whether its row is equal after ``to_bytes`` and ``from_bytes``, and the bytes that the row that came back decodes to."""
    about = ("enc_ns", "min_bits", "max_bits")

    def run(batches):
        for r in batches:
            rows = []
            for row in r.to_pylist():
                back = from_bytes(to_bytes(row))
                same = all(back[k] == v for k, v in row.items() if k not in about and v is not None)
                streams = [back[f"s{i}"] for i in range(len(back["raw_len"]))]
                raw = len(decode_block(streams, back["raw_len"], back["partition"], back["word_width"], back["n_values"], back["codec_id"], back["packing"])) if same else 0
                rows.append((row["dataset"], row["block_id"], raw, same))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _SURVIVED, strict=True)], schema=_SURVIVED)

    return container.mapInArrow(run, "dataset string, block_id long, raw long, same boolean")


def read_rows(spark: SparkSession, path: str, dataset: str, block_bytes: int, width: int, keys: int = 1) -> DataFrame:
    """(rn, k1.., bits): decoded words beside their decoded order keys, which :func:`planepack.blocks.with_keys` has put into the container."""

    def words(name, w):
        t = words_of_blocks(decompress_blocks(read_container(spark, path).filter(F.col("dataset") == name)))
        return t.select((F.col("block_id") * (block_bytes // w) + F.col("pos")).alias("rn"), "bits")

    out = words(dataset, width)
    for i in range(1, keys + 1):
        out = out.join(words(f"{dataset}/k{i}", 8).withColumnRenamed("bits", f"k{i}"), "rn")
    return out
