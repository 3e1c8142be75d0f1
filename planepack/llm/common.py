"""Helpers shared by the training-data operators: table access, shared scratch space, size-checked
broadcasts, and connected components over a distributed edge list."""

from __future__ import annotations

import contextlib
import ctypes
import gc

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from planepack.storage import BROADCAST_ROWS, forget, scratch, small, written  # noqa: F401  (shared with the operators)

#: Edges that one task may union in memory (16 bytes each); beyond it components are found by rounds of joins.
LOCAL_EDGES = 2_000_000

MASK = (1 << 64) - 1


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


#: Rows that an operator takes at a time: bounds a worker's memory on long texts.
ARROW_ROWS = 1000


def arrow(df: DataFrame, fn, ddl) -> DataFrame:
    """``mapInArrow`` whose function gets small slices of the batches, and whose worker gives its memory back to the system when a task ends.

    Spark takes the size of the batches it sends from the session when the plan runs, so a larger setting is lowered to ``ARROW_ROWS``; a smaller one stays.
    """
    conf, size = df.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(conf.get(size)) <= ARROW_ROWS:
        conf.set(size, ARROW_ROWS)

    def run(batches):
        try:
            yield from fn(r.slice(lo, ARROW_ROWS) for r in batches for lo in range(0, r.num_rows, ARROW_ROWS))
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):
                ctypes.CDLL(None).malloc_trim(0)

    return df.mapInArrow(run, ddl)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (shift-multiply avalanche), vectorised; uint64 wraps around."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def batch(schema: pa.Schema, *arrays) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([a if isinstance(a, pa.Array) else pa.array(a, f.type) for a, f in zip(arrays, schema, strict=True)], schema=schema)


# ---------------------------------------------------------------- connected components


def union_forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union-find over edges: every node with the smallest node of its tree, without the roots themselves."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    up = list(range(len(nodes)))
    for x, y in zip(at[: len(a)].tolist(), at[len(a) :].tolist(), strict=True):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        while up[y] != y:
            up[y] = up[up[y]]
            y = up[y]
        if x < y:
            up[y] = x
        elif y < x:
            up[x] = y
    root = np.asarray(up, dtype=np.int64)
    while len(root) and (root[root] != root).any():
        root = root[root]
    own = np.nonzero(root != np.arange(len(nodes)))[0]
    return nodes[own], nodes[root[own]]


_EDGE = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def _local_forest(batches):
    """Contract the edges of a task to a spanning forest, in bounded chunks."""
    a, b, n = [], [], 0
    for r in batches:
        a.append(r.column(0).to_numpy())
        b.append(r.column(1).to_numpy())
        n += r.num_rows
        if n > LOCAL_EDGES:
            x, y = union_forest(np.concatenate(a), np.concatenate(b))
            a, b, n = [x], [y], len(x)
            if n > LOCAL_EDGES // 2:
                yield batch(_EDGE, x, y)
                a, b, n = [], [], 0
    if n:
        yield batch(_EDGE, *union_forest(np.concatenate(a), np.concatenate(b)))


def forest_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).transform(arrow, _local_forest, "a long, b long")


def components(edges: DataFrame, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """(a, b) edges of longs -> (node, root): the smallest node that each node reaches; roots are listed too.

    Tasks first contract their own edges.  Up to ``local_edges`` remaining edges (counted) one task finishes;
    beyond it, rounds of hooking to the smallest neighbour and pointer jumping run as joins, with the state
    written to the shared folder after each round.  No edges reach the driver.
    """
    spark = edges.sparkSession
    left = written(forest_of(edges), "edges")
    n = left.count()
    if n <= local_edges:
        out = written(forest_of(left.coalesce(1)).select(F.col("a").alias("node"), F.col("b").alias("root")), "comp")
        forget(left)
    else:
        labels = written(left.select(F.explode(F.array("a", "b")).alias("node")).distinct().withColumn("root", F.col("node")), "labels")
        while n:
            both = left.select("a", "b").union(left.select(F.col("b"), F.col("a")))
            up = written(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("p")), "hook")
            while True:
                jump = written(up.alias("x").join(up.select(F.col("a").alias("q"), F.col("p").alias("pp")), F.col("x.p") == F.col("q")).select("a", F.col("pp").alias("p"), (F.col("pp") != F.col("p")).alias("moved")), "jump")
                moved = jump.filter("moved").limit(1).count()
                forget(up)
                up = jump.drop("moved")
                up._pp_path = jump._pp_path
                if not moved:
                    break
            new = written(labels.join(up.select(F.col("a").alias("root"), "p"), "root", "left").select("node", F.coalesce("p", "root").alias("root")), "labels")
            nxt = left.join(up.select("a", F.col("p").alias("pa")), "a").join(up.select(F.col("a").alias("b"), F.col("p").alias("pb")), "b").filter("pa <> pb").select(F.col("pa").alias("a"), F.col("pb").alias("b")).distinct()
            nxt = written(forest_of(nxt), "edges")
            for x in (labels, left, up):
                forget(x)
            labels, left, n = new, nxt, nxt.count()
        forget(left)
        out = labels.filter("node <> root")
        out._pp_path = labels._pp_path
    full = out.select("node", "root").union(out.select(F.col("root").alias("node"), "root").distinct())
    full._pp_path = out._pp_path
    return full
