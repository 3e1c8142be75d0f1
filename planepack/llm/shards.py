"""Sharding by proportional stratified interleaving, with DataFrame operations only.

Rows of a source are shuffled by a seeded digest of id and checksum and ranked; a row's fractional rank is (rank - 1/2) / rows of its source.  All rows in the
order of fractional rank repeat the mixture of the whole at every place, so cutting that order into pieces of equal
length gives shards that all match the mixture.  Law ``rows``: counts of the shards differ by one at most.

No window spans a whole source or the whole table: ranks are counted per bucket of the hash (and of the fractional rank), and
offsets of the buckets come from small count tables.  The text is reduced to size and checksum in the scan.

Defined results: null text has size 8 and the checksum of the empty string; null sources form a stratum; repeated rows are ordered by
what they hold and otherwise arbitrarily (equal rows are interchangeable); an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common as C

#: Rows that a bucket of the hash should have at most, and the least number of buckets.
BUCKET_ROWS, BUCKETS = 2_000_000, 1024


def _draw(*parts):
    """60 bits of a digest as a whole number: the seeded shuffle, the same in every engine."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 15), 16, 10).cast("long")


def shard(docs: DataFrame, shards: int = 24, seed: int = 17, buckets: int | None = None, stratum: str = "source", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    slim = docs.select(
        F.col(id_col).cast("long").alias("__id"),
        F.coalesce(F.concat(F.lit("s"), F.col(stratum).cast("string")), F.lit("")).alias("__s"),
        (F.coalesce(F.octet_length(text_col), F.lit(0)) + 8).cast("long").alias("__size"),
        F.crc32(F.coalesce(F.col(text_col), F.lit("")).cast("binary")).cast("long").alias("__crc"),
    )
    if buckets is None:  # a power of two that grows with the rows
        n, buckets = docs.count(), BUCKETS
        while n > buckets * BUCKET_ROWS:
            buckets *= 2
    slim = slim.withColumn("__u", _draw(F.lit(str(seed)), F.coalesce(F.col("__id").cast("string"), F.lit("none")), F.col("__crc").cast("string"))).withColumn("__b", F.pmod(F.shiftright("__u", 20), F.lit(buckets)))
    # offsets of the hash buckets inside each source: at most sources x buckets rows
    counts = slim.groupBy("__s", "__b").agg(F.count(F.lit(1)).alias("__c"))
    by_s = Window.partitionBy("__s")
    offsets = counts.select("__s", "__b", (F.sum("__c").over(by_s.orderBy("__b")) - F.col("__c")).alias("__before"), F.sum("__c").over(by_s).alias("__n"))
    order = Window.partitionBy("__s", "__b").orderBy("__u", "__id", "__crc", "__size")
    ranked = slim.withColumn("__r", F.row_number().over(order)).join(offsets, ["__s", "__b"])
    # the exact position of the fractional rank, as integers: (2 rank - 1) / (2 n)
    ranked = ranked.withColumn("__k", 2 * (F.col("__before") + F.col("__r")) - 1).withColumn("__f", F.col("__k") / (2 * F.col("__n")))
    ranked = ranked.withColumn("__fb", F.least(F.floor(F.col("__f") * buckets), F.lit(buckets - 1)).cast("long")).select("__id", "__s", "__size", "__crc", "__u", "__f", "__fb")
    ranked = C.written(ranked, "ranked")
    per = ranked.groupBy("__fb").agg(F.count(F.lit(1)).alias("__c"))
    over_all = Window.orderBy("__fb")  # at most ``buckets`` rows
    starts = per.select("__fb", (F.sum("__c").over(over_all) - F.col("__c")).alias("__start"), F.sum("__c").over(Window.partitionBy()).alias("__all"))
    fine = Window.partitionBy("__fb").orderBy("__f", F.md5(F.concat_ws(":", F.lit(str(seed)), "__s")), "__s", "__u", "__id", "__crc")
    placed = ranked.withColumn("__r", F.row_number().over(fine)).join(C.small(starts, buckets), "__fb")
    pos = F.col("__start") + F.col("__r") - 1
    placed = placed.withColumn("__pos", pos).withColumn("shard", F.expr(f"cast((__pos * {shards}) div __all as int)"))
    first = F.expr(f"(cast(shard as long) * __all + {shards - 1}) div {shards}")
    return placed.select(F.col("__id").alias(id_col), F.col("__size").alias("size"), F.col("__crc").alias("text_crc32"), F.lit("rows").alias("law"), "shard", (F.col("__pos") - first).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def op9(spark, sf_dir):
    return shard(C.table(spark, sf_dir, "documents", "doc_id", "text", "source"))


#: The checksum is run bit by bit over the bytes of each text, from the reversed polynomial 0xEDB88320.
OP9_SQL = """
with tb as (select list(c order by i) as t from (select i, list_reduce(list_prepend(i::bigint, range(0, 8)), lambda a, k: xor(a >> 1, 3988292384 * (a & 1))) as c from range(0, 256) r(i))),
x as (select doc_id, source, coalesce(text, '') as txt, hex(encode(coalesce(text, ''))) as h from documents),
d as (select doc_id, coalesce('s' || source, '') as s, cast(strlen(txt) + 8 as bigint) as size,
  xor(list_reduce(list_prepend(4294967295, list_transform(range(0, strlen(txt)), lambda i: ('0x' || substr(h, cast(2 * i + 1 as bigint), 2))::bigint)), lambda c, b: xor(c >> 8, t[cast(xor(c & 255, b) as integer) + 1])), 4294967295) as crc from x, tb),
u as (select *, ('0x' || substr(md5('17:' || coalesce(doc_id::varchar, 'none') || ':' || crc), 1, 15))::bigint as u from d),
r as (select *, row_number() over (partition by s order by (u >> 20) % 1024, u, doc_id, crc, size) as r, count(*) over (partition by s) as n from u),
p as (select *, row_number() over (order by (2 * r - 1) / (2 * n), md5('17:' || s), s, u, doc_id, crc) - 1 as pos, count(*) over () as total from r)
select cast(doc_id as bigint) as doc_id, size, crc as text_crc32, 'rows' as law, cast(pos * 24 // total as integer) as shard, cast(pos - ((pos * 24 // total) * total + 23) // 24 as bigint) as slot, cast(null as integer) as grown_shard from p
"""
