"""Streams of values: windowed plane statistics, sessions, a stateful block former, a stateful xor encoder, drift watch."""

from __future__ import annotations

import struct

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupStateTimeout

from .codecs import CODECS
from .features import entropy_of
from .packing import restore, transform
from .storage import fresh
from .words import shifted, word_bits

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
LATE = "10 minutes"


def stream_events(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """A table as a stream, an explicit schema: ``path`` is one Parquet file or a folder of part files, taken oldest first."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    reader = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger)
    if at.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory():
        return reader.parquet(path)
    folder, name = path.rsplit("/", 1)  # a file source watches folders
    return reader.option("pathGlobFilter", name).parquet(folder)


def deduplicated(events: DataFrame, late: str = LATE) -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def window_histogram(events: DataFrame, length: str = "1 day", slide: str | None = None, late: str = LATE) -> DataFrame:
    """Counts of each byte of each plane of the values as floats, per time window."""
    bits = word_bits(F.col("value"), "f32")
    e = events.withWatermark("ts", late).withColumn("bits", bits).withColumn("plane", F.explode(F.sequence(F.lit(0), F.lit(3))))
    byte = shifted(F.col("bits"), F.lit(8) * (3 - F.col("plane"))).bitwiseAND(F.lit(255)).cast("int")
    return e.groupBy(F.window("ts", length, slide or length).alias("w"), "plane", byte.alias("byte")).agg(F.count(F.lit(1)).alias("cnt")).select(F.col("w.start").alias("start"), "plane", "byte", "cnt")


def window_counts(events: DataFrame, length: str = "1 day", late: str = LATE) -> DataFrame:
    """Events per window; rows whose window the watermark has passed are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", length).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def window_entropy(hist: DataFrame) -> DataFrame:
    """Plane entropies of finished windows."""
    return hist.groupBy("start", "plane").agg(entropy_of("cnt").alias("h"), F.sum("cnt").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = LATE) -> DataFrame:
    """Sessions of each user with exact totals of cents."""
    total = F.sum(F.col("value").cast("decimal(18,2)")).cast("double")
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count(F.lit(1)).alias("n"), total.alias("total")).select(F.col("s.start").alias("start"), F.col("s.end").alias("end"), "user_id", "n", "total")


def preceded(events: DataFrame, first: str, then: str, within: str = "1 hour", late: str = LATE) -> DataFrame:
    """Stream-stream join: events of type ``then`` with every event ``first`` of the same user in the time before; the watermarks let old state go."""
    a = events.filter(F.col("event_type") == first).withWatermark("ts", late).select(F.col("user_id").alias("u"), F.col("ts").alias("ta"), F.col("event_id").alias("a"))
    b = events.filter(F.col("event_type") == then).withWatermark("ts", late).select("user_id", "ts", F.col("event_id").alias("b"))
    return a.join(b, F.expr(f"u = user_id and ta <= ts and ta >= ts - interval {within}")).select("a", "b")


def run_to_table(df: DataFrame, what: str, mode: str = "append", key: tuple[str, ...] = ()) -> DataFrame:
    """Run a stream over what is there and return its result.

    ``append``: batches are written once each, their ids in the path, so a repeated batch replaces itself.  ``complete``: the last batch is the
    result and overwrites the one before.  ``update``: the latest row of each ``key``.
    """
    spark = df.sparkSession
    out = fresh(spark, what)
    spark.createDataFrame([], df.schema).withColumn("batch", F.lit(-1).cast("long")).write.parquet(f"{out}/part=-1")

    def sink(batch: DataFrame, batch_id: int) -> None:
        at = f"{out}/part=0" if mode == "complete" else f"{out}/part={batch_id}"
        batch.withColumn("batch", F.lit(batch_id).cast("long")).write.mode("overwrite").parquet(at)

    q = df.writeStream.outputMode(mode).option("checkpointLocation", fresh(spark, "stream")).trigger(availableNow=True).foreachBatch(sink).start()
    q.awaitTermination()
    got = spark.read.schema(T.StructType([*df.schema.fields, T.StructField("batch", T.LongType())])).option("recursiveFileLookup", "true").parquet(out)
    if mode == "update":
        rest = [c for c in df.columns if c not in key]
        return got.groupBy(*key).agg(F.max_by(F.struct(*rest), "batch").alias("__r")).select(*key, *(F.col(f"__r.{c}").alias(c) for c in rest))
    return got.drop("batch")


SHARDS = 16
BLOCK_OUT = "event_type string, shard int, n int, raw int, enc int, ids binary, data binary"


def stream_blocks(events: DataFrame, block_words: int, partition, packing: str = "byte", codec: str = "zstd", shards: int = SHARDS, late: str = LATE) -> DataFrame:
    """Stateful block former: per event type and shard, values wait until a block is full and leave encoded; a timeout flushes the rest.

    Shards split a hot type; a key's state is less than a block.  ``ids`` are the event ids of the words, as differences.
    """

    def step(key, batches, state):
        held_ids, held = state.get if state.exists else (b"", b"")
        ids, vals = np.frombuffer(held_ids, np.int64), np.frombuffer(held, np.float32)
        rows = []

        def emit(i, v):
            enc = [CODECS[codec].encode(s, 1, None) for s in transform(v.astype("<f4").tobytes(), 4, partition, packing)]
            body = b"".join(struct.pack("<I", len(e)) + e for e in enc)
            rows.append((*key, len(v), 4 * len(v), len(body), CODECS["delta"].encode(i.astype("<i8").tobytes(), 8, None), body))

        if state.hasTimedOut:
            if len(vals):
                emit(ids, vals)
            state.remove()
        else:
            new = pd.concat(list(batches)).sort_values("event_id")
            ids = np.concatenate([ids, new["event_id"].to_numpy()])
            vals = np.concatenate([vals, new["value"].to_numpy().astype(np.float32)])
            while len(vals) >= block_words:
                emit(ids[:block_words], vals[:block_words])
                ids, vals = ids[block_words:], vals[block_words:]
            state.update((ids.tobytes(), vals.tobytes()))
            state.setTimeoutTimestamp(state.getCurrentWatermarkMs() + 60_000)
        if rows:
            yield pd.DataFrame(rows, columns=["event_type", "shard", "n", "raw", "enc", "ids", "data"])

    shard = F.pmod(F.col("event_id"), F.lit(shards)).cast("int").alias("shard")
    keyed = events.withWatermark("ts", late).select("event_type", shard, "event_id", "value", "ts").groupBy("event_type", "shard")
    return keyed.applyInPandasWithState(step, BLOCK_OUT, "ids binary, vals binary", "append", GroupStateTimeout.EventTimeTimeout)


def unblocked(formed: DataFrame, partition, packing: str = "byte", codec: str = "zstd") -> DataFrame:
    """(event_type, event_id, value) back from the rows of :func:`stream_blocks`."""
    schema = pa.schema([("event_type", pa.string()), ("event_id", pa.int64()), ("value", pa.float32())])

    def run(batches):
        for r in batches:
            for kind, n, ids, body in zip(*(c.to_pylist() for c in r.columns), strict=True):
                streams, at = [], 0
                for g in partition:
                    (k,) = struct.unpack_from("<I", body, at)
                    streams.append(CODECS[codec].decode(body[at + 4 : at + 4 + k], 1, n * len(g)))
                    at += 4 + k
                vals = np.frombuffer(restore(streams, 4, partition, packing, n), "<f4")
                yield pa.RecordBatch.from_arrays([pa.array([kind] * n, pa.string()), pa.array(np.frombuffer(CODECS["delta"].decode(ids, 8, 8 * n), "<i8")), pa.array(vals)], schema=schema)

    return formed.select("event_type", "n", "ids", "data").mapInArrow(run, "event_type string, event_id long, value float")


def stream_xor(events: DataFrame) -> DataFrame:
    """Stateful xor with the previous value of the user: (user_id, event_id, x, lead): leading zero bits of the xor."""
    out = "user_id long, event_id long, x long, lead int"

    def step(key, batches, state):
        prev = state.get[0] if state.exists else None
        new = pd.concat(list(batches)).sort_values("event_id")
        bits = new["value"].to_numpy().view(np.int64)
        before = np.concatenate([[bits[0] if prev is None else prev], bits[:-1]])
        x = bits ^ before
        state.update((int(bits[-1]),))
        yield pd.DataFrame({"user_id": key[0], "event_id": new["event_id"].to_numpy(), "x": x, "lead": [64 - int(v & (1 << 64) - 1).bit_length() for v in x.tolist()]})

    return events.select("user_id", "event_id", "value").groupBy("user_id").applyInPandasWithState(step, out, "prev long", "append", GroupStateTimeout.NoTimeout)


def distances(hist: DataFrame, reference: DataFrame) -> DataFrame:
    """(start, plane, distance): of the byte frequencies of each window to a reference (plane, byte, freq), which has at most 256 rows a plane."""
    f = hist.withColumn("freq", F.col("cnt") / F.sum("cnt").over(Window.partitionBy("start", "plane")))
    windows = f.select("start", "plane").distinct().join(F.broadcast(reference.withColumnRenamed("freq", "ref")), "plane")
    d = windows.join(f.select("start", "plane", "byte", "freq"), ["start", "plane", "byte"], "full").withColumn("gap", F.coalesce("freq", F.lit(0.0)) - F.coalesce("ref", F.lit(0.0)))
    return d.groupBy("start", "plane").agg(F.round(F.sqrt(F.sum(F.col("gap") * F.col("gap"))), 5).alias("distance"))


def drift(hist: DataFrame, reference: DataFrame, eps: float = 0.1) -> DataFrame:
    """Windows whose byte frequencies are farther than ``eps`` from the reference call for a new fit."""
    return distances(hist, reference).withColumn("refit", F.col("distance") > eps)


def watch(events: DataFrame, reference: DataFrame, eps: float = 0.1, length: str = "1 day", late: str = LATE) -> DataFrame:
    """The same live: each batch's finished windows are held against the reference as they close, and appended with the batch's id."""
    hist = window_histogram(events, length, late=late)
    spark, out = events.sparkSession, fresh(events.sparkSession, "drift")
    ref = reference.persist()
    schema = "start timestamp, plane int, distance double, refit boolean"
    spark.createDataFrame([], schema).write.parquet(f"{out}/part=-1")

    def sink(batch: DataFrame, batch_id: int) -> None:
        drift(batch, ref, eps).write.mode("overwrite").parquet(f"{out}/part={batch_id}")

    hist.writeStream.outputMode("append").option("checkpointLocation", fresh(spark, "stream")).trigger(availableNow=True).foreachBatch(sink).start().awaitTermination()
    ref.unpersist()
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(out)
