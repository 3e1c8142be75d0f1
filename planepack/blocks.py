"""Order and blocks.  Words are sorted once by ranges of the whole key; exact positions come from what each task wrote, never from a window over a dataset.

``gathered`` runs the one shuffle and writes the ordered words as pieces; ``cut`` makes blocks of any size from them without sorting again.
Null keys come first and are equal to each other; the order has to be unique, which is checked.  An empty dataset has no blocks.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .fixtures import KEYS
from .storage import small, written

#: Bytes of a block: between the first and second cache level of common cores.
BLOCK_BYTES = 256 * 1024
#: Bytes of words in one row of the ordered pieces.
PIECE_BYTES = 4 << 20
_K = [f"k{i + 1}" for i in range(KEYS)]
#: Words with equal keys, where they are allowed, are told apart by their bits.
_ORDER = ["dataset", *_K, "bits"]
_BITS = {8: np.int64, 4: np.int32, 2: np.int16}


def plan_block_bytes(n_bytes: int, cores: int, most: int = BLOCK_BYTES, least: int = 4096) -> int:
    """Halve the block until there are more blocks than cores."""
    while most > least and n_bytes / most <= cores:
        most //= 2
    return most


def _sorted(df: DataFrame, unique: bool = False) -> DataFrame:
    """Ranges of the whole key by sampled quantiles, so that a hot leading key is split as well; as many as the session's shuffle partitions.

    With ``unique`` words of equal keys are in one task, whatever their bits, so that they are noticed there.
    """
    return df.repartitionByRange(*(_ORDER[:-1] if unique else _ORDER)).sortWithinPartitions(*_ORDER)


def _starts(spans: DataFrame) -> DataFrame:
    """(dataset, task, before): from (dataset, task, c, first) the words of the dataset in earlier tasks less ``first``; a row per dataset and task, behind a size check."""
    before = F.sum("c").over(Window.partitionBy("dataset").orderBy("task")) - F.col("c") - F.col("first")
    spans = written(spans.select("dataset", "task", before.alias("before")), "spans")
    return small(spans, spans.count())


def ranked(df: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Adds ``rn`` (from 0), ``block_id`` and ``pos`` to every word row."""
    there = written(_sorted(df).withColumn("__at", F.monotonically_increasing_id()), "sorted")
    there = there.withColumn("task", F.shiftright("__at", 33))
    starts = _starts(there.groupBy("dataset", "task").agg(F.count(F.lit(1)).alias("c"), F.min("__at").alias("first")))
    per = F.floor(F.lit(block_bytes) / F.col("width"))
    placed = there.join(starts, ["dataset", "task"]).withColumn("rn", F.col("before") + F.col("__at")).drop("__at", "before", "task")
    return placed.withColumn("block_id", F.floor(F.col("rn") / per)).withColumn("pos", (F.col("rn") % per).cast("int"))


_PIECE = pa.schema([("dataset", pa.string()), ("width", pa.int32()), ("at", pa.int64()), ("n", pa.int32()), ("n_nulls", pa.int32()), ("repeated", pa.int64()), ("validity", pa.binary()), ("head", pa.binary()), ("body", pa.binary()), ("tail", pa.binary())])
_PIECE_DDL = "dataset string, width int, at long, n int, n_nulls int, repeated long, validity binary, head binary, body binary, tail binary"


class _Run:
    """Words of one dataset in a task, leaving as pieces."""

    def __init__(self, dataset: str, width: int, end_bytes: int):
        self.dataset, self.width, self.end = dataset, width, end_bytes // width
        self.at = self.held = self.repeated = 0
        self.words, self.nulls, self.last_key, self.last_word = [], [], None, 0

    def add(self, keys: np.ndarray, bits: np.ndarray, null: np.ndarray) -> None:
        self.repeated += int((keys[1:] == keys[:-1]).sum()) + (self.last_key is not None and self.last_key == keys[0])
        self.last_key = keys[-1]
        if null.any():  # null slots take the value before, which costs codecs least
            bits = np.concatenate([[self.last_word], bits])
            at = np.maximum.accumulate(np.where(np.concatenate([[False], null]), 0, np.arange(len(bits))))
            bits = bits[at][1:]
        self.last_word = bits[-1]
        self.words.append(bits.astype(_BITS[self.width]))
        self.nulls.append(null)
        self.held += len(bits)

    def piece(self) -> pa.RecordBatch:
        w, null = np.concatenate(self.words), np.concatenate(self.nulls)
        n, e = len(w), self.end
        valid = np.packbits(~null, bitorder="little").tobytes() if null.any() else None
        cut = max(e, n - e)
        row = (self.dataset, self.width, self.at, n, int(null.sum()), self.repeated, valid, w[:e].tobytes(), w[e:cut].tobytes(), w[cut:].tobytes())
        self.at += n
        self.words, self.nulls, self.held, self.repeated = [], [], 0, 0
        return pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(row, _PIECE, strict=True)], schema=_PIECE)


def _packed(end_bytes: int):
    def run(batches):
        now = None
        for r in batches:
            ends = pc.run_end_encode(r.column(0))
            keys, bits = r.column(2).to_numpy(), r.column(3)
            null, bits = bits.is_null().to_numpy(zero_copy_only=False), bits.fill_null(0).to_numpy()
            lo = 0
            for hi, ds in zip(ends.run_ends.to_pylist(), ends.values.to_pylist(), strict=True):
                if now is None or now.dataset != ds:
                    if now and now.held:
                        yield now.piece()
                    now = _Run(ds, r.column(1)[lo].as_py(), end_bytes)
                now.add(keys[lo:hi], bits[lo:hi], null[lo:hi])
                if now.held * now.width >= PIECE_BYTES:
                    yield now.piece()
                lo = hi
        if now and now.held:
            yield now.piece()

    return run


def gathered(df: DataFrame, end_bytes: int = BLOCK_BYTES, unique: bool = True) -> DataFrame:
    """The words of (dataset, width, k1..k5, bits) in order, as written pieces: (dataset, width, start, n, n_nulls, validity, head, body, tail).

    ``end_bytes`` is the largest block to be cut from them.  With ``unique`` an order key that two words of a dataset share is an error.
    """
    keyed = _sorted(df, unique).select("dataset", "width", F.xxhash64(*_K).alias("key"), "bits")
    pieces = written(keyed.mapInArrow(_packed(end_bytes), _PIECE_DDL).withColumn("task", F.spark_partition_id().cast("long")), "pieces")
    if unique and (bad := pieces.filter("repeated > 0").select("dataset").limit(1).collect()):
        raise ValueError(f"the order of {bad[0].dataset} is not unique")
    starts = _starts(pieces.groupBy("dataset", "task").agg(F.sum("n").alias("c"), F.lit(0).alias("first")))
    return pieces.join(starts, ["dataset", "task"]).select("dataset", "width", (F.col("before") + F.col("at")).alias("start"), "n", "n_nulls", "validity", "head", "body", "tail")


_BLOCK = pa.schema([("dataset", pa.string()), ("width", pa.int32()), ("block_id", pa.int64()), ("n", pa.int32()), ("n_nulls", pa.int32()), ("validity", pa.binary()), ("data", pa.binary())])
_BLOCK_DDL = "dataset string, width int, block_id long, n int, n_nulls int, validity binary, data binary"
_END = pa.schema([*_BLOCK, ("at", pa.int32())])


def _rows(rows: list, schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)


def _part(valid, lo: int, hi: int) -> tuple[int, bytes | None]:
    """Nulls and validity of words lo..hi of a piece."""
    if valid is None:
        return 0, None
    v = valid[lo:hi]
    nulls = int((v == 0).sum())
    return nulls, np.packbits(v, bitorder="little").tobytes() if nulls else None


def _flags(valid: bytes | None, n: int):
    return None if valid is None else np.unpackbits(np.frombuffer(valid, np.uint8), bitorder="little")[:n]


def _whole(block_bytes: int):
    """The blocks that lie inside one piece."""

    def run(batches):
        for r in batches:
            for ds, width, start, n, valid, *parts in zip(*(c.to_pylist() for c in r.columns), strict=True):
                per, flags, rows = block_bytes // width, _flags(valid, n), []
                data = memoryview(b"".join(parts))
                for lo in range(-start % per, n - per + 1, per):
                    rows.append((ds, width, (start + lo) // per, per, *_part(flags, lo, lo + per), bytes(data[lo * width : (lo + per) * width])))
                if rows:
                    yield _rows(rows, _BLOCK)

    return run


def _ends(block_bytes: int):
    """What a piece holds of the blocks that reach over its ends; the words between are not read."""

    def run(batches):
        for r in batches:
            for ds, width, start, n, valid, head, tail in zip(*(c.to_pylist() for c in r.columns), strict=True):
                per, flags, rows = block_bytes // width, _flags(valid, n), []
                both, first, last = head + tail, -start % per, (start + n) % per
                if len(both) < n * width and max(first, last) * width > len(tail):
                    raise ValueError(f"blocks of {block_bytes} bytes are larger than the ends of the pieces")
                if first:
                    k = min(first, n)
                    rows.append((ds, width, start // per, k, *_part(flags, 0, k), both[: k * width], start % per))
                if last and first <= n - last:
                    rows.append((ds, width, (start + n) // per, last, *_part(flags, n - last, n), both[len(both) - last * width :], 0))
                if rows:
                    yield _rows(rows, _END)

    return run


def _join(batches):
    rows = (row for r in batches for row in r.to_pylist())
    for (ds, width, block), group in itertools.groupby(rows, lambda x: (x["dataset"], x["width"], x["block_id"])):
        parts = list(group)
        n, nulls = sum(p["n"] for p in parts), sum(p["n_nulls"] for p in parts)
        valid = None
        if nulls:
            flags = [np.ones(p["n"], np.uint8) if p["validity"] is None else _flags(p["validity"], p["n"]) for p in parts]
            valid = np.packbits(np.concatenate(flags), bitorder="little").tobytes()
        yield _rows([(ds, width, block, n, nulls, valid, b"".join(p["data"] for p in parts))], _BLOCK)


def cut(pieces: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Blocks from pieces: narrow, but for the few blocks that reach over the end of a piece."""
    whole = pieces.select("dataset", "width", "start", "n", "validity", "head", "body", "tail").mapInArrow(_whole(block_bytes), _BLOCK_DDL)
    ends = pieces.select("dataset", "width", "start", "n", "validity", "head", "tail").mapInArrow(_ends(block_bytes), _BLOCK_DDL + ", at int")
    met = ends.repartition("dataset", "block_id").sortWithinPartitions("dataset", "block_id", "at").mapInArrow(_join, _BLOCK_DDL)
    return whole.unionByName(met)


def blocks(df: DataFrame, block_bytes: int = BLOCK_BYTES, unique: bool = True) -> DataFrame:
    """(dataset, width, block_id, n, n_nulls, validity, data): a row per block, data as little-endian words in order."""
    return cut(gathered(df, block_bytes, unique), block_bytes)


def contiguous_tasks(blocks: DataFrame, tasks: int) -> DataFrame:
    """Neighbouring blocks in the same task, in order."""
    return blocks.repartitionByRange(tasks, "dataset", "block_id").sortWithinPartitions("dataset", "block_id")


def with_keys(df: DataFrame, keys: int = 1) -> DataFrame:
    """The words and, as datasets ``name/k1`` and so on, their order keys: compressed beside the values they lead the way back to the rows."""
    out = df
    for i in range(1, keys + 1):
        out = out.unionByName(df.withColumn("dataset", F.concat("dataset", F.lit(f"/k{i}"))).withColumn("bits", F.col(f"k{i}")).withColumn("width", F.lit(8)))
    return out


def sample_blocks(df: DataFrame, fraction: float = 0.3, how: str = "blocks") -> DataFrame:
    """A deterministic share of the blocks of every dataset, in thousandths, block 0 among them; contiguity inside blocks stays.

    ``blocks`` spreads them evenly by a multiplicative step; ``prefix`` takes the first ones.
    """
    if how == "prefix":
        ends = df.groupBy("dataset").agg(F.ceil((F.max("block_id") + 1) * F.lit(fraction)).alias("__end"))
        ends = written(ends, "ends")
        return df.join(small(ends, ends.count()), "dataset").filter("block_id < __end").drop("__end")
    return df.filter(F.pmod(F.col("block_id") * 617, F.lit(1000)) < max(1, round(fraction * 1000)))


def sample_rows(ranked: DataFrame, fraction: float = 0.3) -> DataFrame:
    """A deterministic share of the words by position, in thousandths."""
    return ranked.filter(F.pmod(F.col("rn") * 617, F.lit(1000)) < max(1, round(fraction * 1000)))


def words_of_blocks(df: DataFrame) -> DataFrame:
    """(dataset, block_id, pos, bits) from blocks: the inverse of :func:`blocks`."""
    schema = pa.schema([("dataset", pa.string()), ("block_id", pa.int64()), ("pos", pa.int32()), ("bits", pa.int64())])

    def run(batches):
        for r in batches:
            for ds, width, block, n, valid, data in zip(*(r.column(i).to_pylist() for i in range(6)), strict=True):
                bits = np.frombuffer(data, _BITS[width]).astype(np.int64)
                mask = None if valid is None else _flags(valid, n) == 0
                yield pa.RecordBatch.from_arrays([pa.array([ds] * n, pa.string()), pa.array(np.full(n, block)), pa.array(np.arange(n, dtype=np.int32)), pa.array(bits, mask=mask)], schema=schema)

    return df.select("dataset", "width", "block_id", "n", "validity", "data").mapInArrow(run, "dataset string, block_id long, pos int, bits long")
