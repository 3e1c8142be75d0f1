"""``spark.read.format("planepack")``: containers as a Python data source with block pruning; and raw dumps of words.

Paths go through Arrow's file systems, so they may be local, or URIs of any store that Arrow opens (``file``, ``hdfs``, ``s3``, ``gs``).
For other stores ``container`` reads and writes the same files through Spark itself.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, EqualTo, GreaterThanOrEqual, InputPartition, LessThan, WriterCommitMessage

from .blocks import _BITS, _flags
from .codecs import BY_ID  # noqa: F401  (registers codecs in the worker)
from .pipeline import decode_block

SCHEMA = "dataset string, block_id bigint, pos int, bits bigint"
_ROWS = pa.schema([("dataset", pa.string()), ("block_id", pa.int64()), ("pos", pa.int32()), ("bits", pa.int64())])


def opened(path: str) -> tuple[pa.fs.FileSystem, str]:
    """(file system, path in it) of a local path or a URI; Hadoop writes ``file:/x`` for ``file:///x``."""
    from pyarrow import fs

    if path.startswith("file:/") and not path.startswith("file://"):
        path = path.removeprefix("file:")
    if path.startswith(("s3a://", "s3n://")):
        path = f"s3{path[3:]}"
    return fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path)


class _Part(InputPartition):
    def __init__(self, path: str, group: int, lo: int, hi: int):
        self.path, self.group, self.lo, self.hi = path, group, lo, hi


class ContainerReader(DataSourceReader):
    """A partition per row group whose statistics allow a wanted block."""

    def __init__(self, options):
        self.path, self.dataset, self.lo, self.hi = options["path"], None, 0, 1 << 62

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("dataset",):
                self.dataset = f.value
            elif isinstance(f, EqualTo) and f.attribute == ("block_id",):
                self.lo, self.hi = max(self.lo, f.value), min(self.hi, f.value + 1)
            elif isinstance(f, GreaterThanOrEqual) and f.attribute == ("block_id",):
                self.lo = max(self.lo, f.value)
            elif isinstance(f, LessThan) and f.attribute == ("block_id",):
                self.hi = min(self.hi, f.value)
            else:
                yield f

    def partitions(self):
        import pyarrow.dataset as ds

        store, path = opened(self.path)
        parts = []
        for frag in ds.dataset(f"{path}/blocks", filesystem=store, format="parquet", partitioning="hive").get_fragments(filter=None if self.dataset is None else ds.field("dataset") == self.dataset):
            meta = frag.metadata
            at = meta.schema.to_arrow_schema().get_field_index("block_id")
            for g in range(meta.num_row_groups):
                s = meta.row_group(g).column(at).statistics
                if s is None or (s.max >= self.lo and s.min < self.hi):
                    parts.append(_Part(frag.path, g, self.lo, self.hi))
        return parts or [_Part("", 0, 0, 0)]

    def read(self, part):
        if not part.path:
            return
        import re
        from urllib.parse import unquote

        name = unquote(re.search(r"dataset=([^/]+)", part.path)[1])
        with opened(self.path)[0].open_input_file(part.path) as f:
            for batch in pq.ParquetFile(f).iter_batches(batch_size=64, row_groups=[part.group]):
                for x in batch.to_pylist():
                    if part.lo <= x["block_id"] < part.hi:
                        n, w = x["n_values"], x["word_width"]
                        data = decode_block([x[f"s{i}"] for i in range(len(x["raw_len"]))], x["raw_len"], x["partition"], w, n, x["codec_id"], x["packing"])
                        mask = None if x["validity"] is None else _flags(x["validity"], n) == 0
                        yield pa.RecordBatch.from_arrays([pa.array([name] * n, pa.string()), pa.array(np.full(n, x["block_id"])), pa.array(np.arange(n, dtype=np.int32)), pa.array(np.frombuffer(data, _BITS[w]).astype(np.int64), mask=mask)], schema=_ROWS)


class _Wrote(WriterCommitMessage):
    def __init__(self, files):
        self.files = files


class ContainerWriter(DataSourceArrowWriter):
    """Container rows to Parquet files under hidden names, which get their own on commit; files of lost tasks are never seen."""

    def __init__(self, options):
        self.path = options["path"]

    def write(self, iterator):
        from urllib.parse import quote

        store, path = opened(self.path)
        files = []
        for b in iterator:
            t = pa.Table.from_batches([b])
            for name in t["dataset"].unique().to_pylist():
                folder = f"{path}/blocks/dataset={quote(name, safe='')}"
                store.create_dir(folder, recursive=True)
                f = f"{folder}/_tmp-{uuid.uuid4().hex}"
                with store.open_output_stream(f) as out:
                    pq.write_table(t.filter(pa.compute.equal(t["dataset"], name)).drop(["dataset"]), out, compression="none")
                files.append(f)
        return _Wrote(files)

    def commit(self, messages):
        store = opened(self.path)[0]
        for m in messages:
            for f in m.files if m else []:
                store.move(f, f.replace("_tmp-", "part-") + ".parquet")

    def abort(self, messages):
        store = opened(self.path)[0]
        for m in messages:
            for f in m.files if m else []:
                store.delete_file(f)


class PlanepackSource(DataSource):
    @classmethod
    def name(cls):
        return "planepack"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return ContainerReader(self.options)

    def writer(self, schema, overwrite):
        if overwrite:
            raise ValueError("a container only takes more blocks: write in mode append to a new or existing path")
        return ContainerWriter(self.options)


def register(spark: SparkSession) -> None:
    """Make the format known to the session and let filters reach Python sources, without which Spark refuses a reader that prunes blocks."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(PlanepackSource)


# ---------------------------------------------------------------- headerless files of words

#: Bytes of a raw file that one row of work reads.
RAW_CHUNK = 8 << 20


def read_raw_words(spark: SparkSession, path: str, word: str, dataset: str = "raw", chunk: int = RAW_CHUNK) -> DataFrame:
    """Headerless little-endian files of words: (dataset, file, pos, bits).  A file is read in ranges by many tasks; no row holds a whole file."""
    from .words import TYPES

    width, kind, _ = TYPES[word]
    chunk -= chunk % width
    schema = pa.schema([("dataset", pa.string()), ("file", pa.string()), ("pos", pa.int64()), ("bits", pa.int64())])

    def run(batches):
        for r in batches:
            for file, lo, n in zip(*(c.to_pylist() for c in r.columns), strict=True):
                store, at = opened(file)
                with store.open_input_file(at) as f:
                    f.seek(lo)
                    bits = np.frombuffer(f.read(n), np.dtype(kind).newbyteorder("<")).astype(np.int64)
                for a in range(0, len(bits), 65536):
                    b = bits[a : a + 65536]
                    yield pa.RecordBatch.from_arrays([pa.array([dataset] * len(b), pa.string()), pa.array([file] * len(b), pa.string()), pa.array(np.arange(lo // width + a, lo // width + a + len(b))), pa.array(b)], schema=schema)

    files = spark.read.format("binaryFile").load(path).select("path", "length").filter("length > 0")
    if (odd := files.filter(F.col("length") % width != 0).limit(1).collect()):
        raise ValueError(f"{odd[0].path} does not hold whole words of {width} bytes")
    ranges = files.select("path", "length", F.explode(F.expr(f"sequence(0L, length - 1, {chunk}L)")).alias("lo"))
    ranges = ranges.select("path", "lo", F.least(F.lit(chunk), F.col("length") - F.col("lo")).alias("n"))
    return ranges.repartition("path", "lo").mapInArrow(run, "dataset string, file string, pos long, bits long")


def write_raw_words(blocks: DataFrame, path: str) -> None:
    """A headerless file per block, named by dataset and block; a repeated task writes the same file again."""

    def run(batches):
        store, at = opened(path)
        store.create_dir(at, recursive=True)
        for r in batches:
            for ds, block, data in zip(*(c.to_pylist() for c in r.columns), strict=True):
                f = f"{at}/_{uuid.uuid4().hex}"
                with store.open_output_stream(f) as out:
                    out.write(data)
                store.move(f, f"{at}/{ds}-{block:012d}.bin")
            yield pa.RecordBatch.from_arrays([pa.array([r.num_rows], pa.int64())], names=["n"])

    blocks.select("dataset", "block_id", "data").mapInArrow(run, "n long").write.format("noop").mode("overwrite").save()
