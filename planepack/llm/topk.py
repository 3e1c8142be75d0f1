"""Exact top-k search: tiled matrix products, partial selection per tile, tree merging of per-query lists.

Queries are the rows whose id is divisible by ``every``; candidates are all rows but the query's own (rows with the
query's id).  Components become ``floor(1024 * x)`` and the score is the integer inner product, exact in
float64 while it stays under 2**53 (tiles with larger values use Python integers).

Queries come in blocks of at most ``block_bytes`` of vectors.  A block is held against the whole table in one scan: each task cuts its rows into
tiles, multiplies some thousand queries of the block at a time with a tile, keeps what can still enter a query's list, and merges tile after tile; the lists of
the tasks merge by a ranked window, which Spark prunes to k rows per query before and after the shuffle, and the block's result is written before the
next block is taken.  The driver and the tasks hold one block at a time; nothing is cross-joined and no list exceeds k.

Defined results: a vector that is null, or holds null or non-finite components, or whose id is null, takes no part, nor
does one with a component whose 1024-fold is beyond a double; vectors of another length than the query's take no part in its list; an empty table
gives no rows; ties go to the smaller id.
Repeated rows are separate candidates; of rows that repeat a query's id the one whose vector comes first in the order of its components asks.  A score
beyond 64 bits counts as the largest or smallest whole number of 64 bits.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common as C

#: Bytes of query vectors that are sent to the tasks at once, queries that meet a tile together, and rows of a tile.
BLOCK_BYTES, ABREAST, TILE = 64 << 20, 4096, 8192
_OUT = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])


def quantised(df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """Valid rows only, decided JVM-side: (vec_id, v array<double>)."""
    v = F.col(vec_col).cast("array<double>")
    fine = F.col(id_col).isNotNull() & v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x * 1024.0) != F.lit(float("inf"))))
    return df.filter(fine).select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v"))


def _matrices(r: pa.RecordBatch) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """ids and floor(1024 x) by vector length."""
    ids, col = r.column(0).to_numpy(), r.column(1)
    length = np.diff(col.offsets.to_numpy())
    flat = np.floor(col.flatten().to_numpy() * 1024.0)
    ends = np.concatenate([[0], np.cumsum(length)])
    out = {}
    for n in np.unique(length):
        rows = np.nonzero(length == n)[0]
        out[int(n)] = (ids[rows], flat.reshape(-1, n) if len(rows) == len(ids) else np.stack([flat[ends[i] : ends[i + 1]] for i in rows]))
    return out


def product(q: np.ndarray, t: np.ndarray) -> np.ndarray:
    """Exact integer inner products."""
    if np.abs(q).max(initial=0) * np.abs(t).max(initial=0) * q.shape[1] < 2.0**53:
        return (q @ t.T).astype(np.int64)
    exact = np.vectorize(int, otypes=[object])
    return np.clip(exact(q).dot(exact(t).T), -(1 << 63), (1 << 63) - 1).astype(np.int64)


class Lists:
    """The k best of each query so far, best first; merged tile after tile.  ``ids`` are distinct."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int):
        self.ids, self.vectors, self.k = ids, vectors, k
        self.score = np.full((len(ids), k), np.iinfo(np.int64).min)
        self.id = np.full((len(ids), k), np.iinfo(np.int64).max)
        self.n = np.zeros(len(ids), np.int64)
        self.order = np.argsort(ids, kind="stable")

    def merge(self, ids: np.ndarray, tile: np.ndarray) -> None:
        s = product(self.vectors, tile)
        mine = self.order[np.minimum(np.searchsorted(self.ids, ids, sorter=self.order), len(self.ids) - 1)]
        own = np.nonzero(self.ids[mine] == ids)[0]
        s[mine[own], own] = np.iinfo(np.int64).min  # a query's own rows, however many, take no place in the selection
        full = self.n >= self.k
        low = np.where(full, self.score[:, -1], np.iinfo(np.int64).min)
        if len(ids) > 4 * self.k:  # partial selection: at most the k best of the tile and what ties with the last
            low = np.maximum(low, np.partition(s, len(ids) - self.k, axis=1)[:, len(ids) - self.k])
        q, c = np.nonzero(s >= low[:, None])
        other = ids[c] != self.ids[q]
        q, c = q[other], c[other]
        if not len(q):
            return
        held = np.arange(self.k) < self.n[:, None]
        hq, hc = np.nonzero(held)
        query = np.concatenate([hq, q])
        score = np.concatenate([self.score[hq, hc], s[q, c]])
        vec = np.concatenate([self.id[hq, hc], ids[c]])
        order = np.lexsort((vec, ~score, query))
        query, score, vec = query[order], score[order], vec[order]
        place = np.arange(len(query)) - np.searchsorted(query, query)
        keep = place < self.k
        query, place = query[keep], place[keep]
        self.score[query, place] = score[keep]
        self.id[query, place] = vec[keep]
        self.n = np.maximum(self.n, np.bincount(query, minlength=len(self.n)))

    def rows(self):
        q, c = np.nonzero(np.arange(self.k) < self.n[:, None])
        return C.batch(_OUT, self.ids[q], self.id[q, c], self.score[q, c])


def _search(held, k: int):
    """``held``: the broadcast block, (ids, vectors) by vector length."""

    def run(batches):
        lists = {n: [Lists(ids[lo : lo + ABREAST], v[lo : lo + ABREAST], k) for lo in range(0, len(ids), ABREAST)] for n, (ids, v) in held.value.items()}
        for r in batches:
            for n, (ids, m) in _matrices(r).items():
                for some in lists.get(n, ()):
                    for i in range(0, len(ids), TILE):
                        some.merge(ids[i : i + TILE], m[i : i + TILE])
        for x in lists.values():
            for some in x:
                if some.n.any():
                    yield some.rows()

    return run


def _block(queries: DataFrame) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    held: dict[int, list] = {}
    for r in queries.toArrow().to_batches():
        for length, found in _matrices(r).items():
            held.setdefault(length, []).append(found)
    return {n: (np.concatenate([i for i, _ in x]), np.concatenate([m for _, m in x])) for n, x in held.items()}


def _ranked(found: DataFrame, k: int) -> DataFrame:
    """A tree of two levels: lists of some tasks merge first, then those of all."""
    best = Window.partitionBy("query_id", "part").orderBy(F.desc("score"), "vec_id")
    some = found.withColumn("part", F.pmod(F.spark_partition_id(), F.lit(16))).withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k)
    last = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return some.withColumn("rank", F.row_number().over(last).cast("int")).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def exact_topk(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", every: int = 100, k: int = 10, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    spark = df.sparkSession
    rows = quantised(df, id_col, vec_col)
    queries = rows.filter(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min("v").alias("v"))
    total = queries.agg(F.coalesce(F.sum(F.size("v").cast("long") * 8), F.lit(0))).first()[0]
    blocks = 1 if total <= block_bytes else -(-total * 4 // (block_bytes * 3))  # room for the imbalance of the hash
    out = None
    for b in range(blocks):
        mine = queries if blocks == 1 else queries.filter(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b)
        held = spark.sparkContext.broadcast(_block(mine))
        found = _ranked(rows.transform(C.arrow, _search(held, k), "query_id long, vec_id long, score long"), k)
        if blocks > 1:
            found = C.written(found, "lists")
            held.destroy()
        out = found if out is None else out.unionByName(found)
    return out


def op3(spark, sf_dir):
    return exact_topk(C.table(spark, sf_dir, "embeddings", "vec_id", "embedding"))


OP3_SQL = """
with v as (
  select cast(vec_id as bigint) as vec_id, list_transform(embedding, lambda x: cast(floor(1024 * cast(x as double)) as bigint)) as e from embeddings
  where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(embedding) > 0),
q as (select vec_id, list_transform(min(list_transform(embedding, lambda x: cast(x as double))), lambda x: cast(floor(1024 * x) as bigint)) as e from embeddings
  where vec_id % 100 = 0 and vec_id in (select vec_id from v) and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(embedding) > 0 group by vec_id),
s as (
  select q.vec_id as query_id, c.vec_id as vec_id, cast(list_inner_product(cast(q.e as double[]), cast(c.e as double[])) as bigint) as score
  from q join v c on q.vec_id <> c.vec_id),
r as (select query_id, cast(row_number() over (partition by query_id order by score desc, vec_id) as integer) as rank, vec_id, score from s)
select query_id, rank, vec_id, score from r where rank <= 10
"""
