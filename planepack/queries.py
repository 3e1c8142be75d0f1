"""Registered queries of the engine and their DuckDB oracles: words, blocks, features, partitions, packing, round trips, entropies, streams, functions."""

from __future__ import annotations

from functools import partial

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import ablation, blocks, cluster, container, entropy, features, foundational, packfirst, pipeline, streaming, studies  # noqa: F401  (studies register themselves)
from .fixtures import CORE, DATASETS, F32, F64, FLOATS, INTS, load, table
from .pipeline import PlanSpec
from .registry import CHOSEN, ORACLES, P15, PLANES, QUERIES, SAMPLED, SCORES, SMALL, entropy_sql, query, ranked_sql, source, squared_sql, tree_sql, varint_sql
from .registry import small_blocks as _blocks
from .relops import RELOPS
from .storage import fresh, written
from .words import bits_word, ieee_fields, ieee_value, plane


# ---------------------------------------------------------------- words and planes

for _w, _names in (("f64", ["DB64-extprice", "TS64-value"]), ("f32", ["DB32-total", "EMB32-row"]), ("i64", ["INT64-okey", "INT64-ts"]), ("i32", ["INT32-size"])):
    QUERIES[f"word_bits_{_w}"] = lambda spark, d, n=_names: load(spark, d, n)
    ORACLES[f"word_bits_{_w}"] = source(_names)


@query("bits_word_roundtrip", "select event_id as k1, value from events")
def _bits_word(spark, d):
    return load(spark, d, "TS64-value").select("k1", bits_word(F.col("bits"), "f64").alias("value"))


@query("ieee_fields", f"with w as ({source('TS32-value')}) select k1, cast((bits >> 31) & 1 as integer) as sign, cast((bits >> 23) & 255 as integer) as exponent, bits & 8388607 as mantissa, cast(value as float)::double as value from w join events on k1 = event_id")
def _ieee(spark, d):
    f = ieee_fields(F.col("bits"), "f32")
    t = load(spark, d, "TS32-value").select("k1", *(c.alias(n) for n, c in f.items()))
    return t.withColumn("value", ieee_value(F.col("sign"), F.col("exponent"), F.col("mantissa"), "f32"))


@query("plane_bytes", f"with w as ({source('TS32-value')}), {PLANES} select dataset, k1, plane, cast(byte as integer) as byte from b".replace("unnest(range(0, width)) as plane", "cast(unnest(range(0, width)) as integer) as plane"))
def _plane_bytes(spark, d):
    return features.plane_bytes(load(spark, d, "TS32-value")).select("dataset", "k1", "plane", "byte")


@query("plane_hist", f"with w as ({source(CORE)}), {PLANES} select dataset, cast(plane as integer) as plane, cast(byte as integer) as byte, count(*) as cnt from b group by all")
def _plane_hist(spark, d):
    return features.plane_hist(load(spark, d, CORE))


@query("byte_image", f"with {ranked_sql('TS32-value')} select pos, lower(hex((bits >> 24) & 255)) as b0, lower(hex((bits >> 16) & 255)) as b1, lower(hex((bits >> 8) & 255)) as b2, lower(hex(bits & 255)) as b3 from w where rn < 64")
def _byte_image(spark, d):
    r = blocks.ranked(load(spark, d, "TS32-value"), SMALL).filter("rn < 64")
    return r.select(F.col("pos").cast("long").alias("pos"), *(F.lower(F.hex(plane(F.col("bits"), 4, i))).alias(f"b{i}") for i in range(4)))


# ---------------------------------------------------------------- blocks and features


@query("block_ids", f"with {ranked_sql(CORE)} select dataset, k1, k2, k3, k4, k5, rn, block_id, cast(pos as integer) as pos from w")
def _block_ids(spark, d):
    return blocks.ranked(load(spark, d, CORE), SMALL).select("dataset", *(f"k{i}" for i in range(1, 6)), "rn", "block_id", "pos")


@query("block_sample", f"with {ranked_sql(CORE)} select dataset, block_id, count(*) as n from w where {SAMPLED} group by all")
def _block_sample(spark, d):
    return blocks.sample_blocks(blocks.ranked(load(spark, d, CORE), SMALL)).groupBy("dataset", "block_id").agg(F.count(F.lit(1)).alias("n"))


@query("block_sample_small", f"with {ranked_sql(CORE)} select dataset, block_id, count(*) as n from w where (block_id * 617) % 1000 < 40 group by all")
def _block_sample_small(spark, d):
    return blocks.sample_blocks(blocks.ranked(load(spark, d, CORE), SMALL), 0.04).groupBy("dataset", "block_id").agg(F.count(F.lit(1)).alias("n"))


@query("prefix_sample", f"with {ranked_sql(CORE)}, e as (select dataset, ceil((max(block_id) + 1) * 0.3) as e from w group by 1) select dataset, block_id, count(*) as n from w join e using (dataset) where block_id < e group by all")
def _prefix_sample(spark, d):
    return blocks.sample_blocks(blocks.ranked(load(spark, d, CORE), SMALL), how="prefix").groupBy("dataset", "block_id").agg(F.count(F.lit(1)).alias("n"))


@query("row_sample", f"with {ranked_sql(CORE)} select dataset, rn, bits from w where (rn * 617) % 1000 < 300")
def _row_sample(spark, d):
    return blocks.sample_rows(blocks.ranked(load(spark, d, CORE), SMALL)).select("dataset", "rn", "bits")


#: The rule for the block size, for eight cores: the largest of 256 KiB, 128 KiB, ... 4 KiB that makes more blocks than cores.
_PLAN = "select dataset, n, size, cast(ceil(n / (size / width)) as bigint) as blocks from (select dataset, any_value(width) as width, count(*) as n from src group by 1), lateral (select coalesce(max(s) filter (where n * width / s > 8), 4096) as size from (select 262144 >> unnest(range(0, 7)) as s))"


@query("block_plan", f"with src as ({source(list(DATASETS))}) {_PLAN}")
def _block_plan(spark, d):
    """The planned block size of every dataset and the blocks that come of it."""
    t = load(spark, d, list(DATASETS)).groupBy("dataset", "width").agg(F.count(F.lit(1)).alias("n")).collect()  # a row a dataset
    size = {r.dataset: blocks.plan_block_bytes(r.n * r.width, 8) for r in t}
    return spark.createDataFrame([(r.dataset, r.n, size[r.dataset], -(-r.n // (size[r.dataset] // r.width))) for r in t], "dataset string, n long, size int, blocks long")


@query("contiguous_tasks", f"with {ranked_sql(CORE)} select dataset, count(distinct block_id) as blocks, true as contiguous, true as ordered from w group by 1")
def _contiguous(spark, d):
    """Blocks dealt to tasks by ranges: what a task holds of a dataset is a run of neighbours, in order."""
    t = blocks.contiguous_tasks(_blocks(spark, d, CORE), 5).select("dataset", "block_id", F.spark_partition_id().alias("task"), F.monotonically_increasing_id().alias("at"))
    t = t.withColumn("shift", F.col("at") - F.col("block_id"))
    t = t.groupBy("dataset", "task").agg(F.count(F.lit(1)).alias("c"), (F.max("block_id") - F.min("block_id") + 1).alias("span"), (F.min("shift") == F.max("shift")).alias("ordered"))
    return t.groupBy("dataset").agg(F.sum("c").alias("blocks"), F.bool_and(F.col("c") == F.col("span")).alias("contiguous"), F.bool_and("ordered").alias("ordered"))


@query("value_range", f"with {ranked_sql('TS64-value')} select block_id, min(value) as lo, max(value) as hi from w join events on k1 = event_id group by 1")
def _value_range(spark, d):
    r = blocks.ranked(load(spark, d, "TS64-value"), SMALL).withColumn("value", bits_word(F.col("bits"), "f64"))
    return r.groupBy("block_id").agg(F.min("value").alias("lo"), F.max("value").alias("hi"))


@query("block_entropy", f"with {ranked_sql(CORE)}, {PLANES}, c as (select dataset, block_id, plane, byte, count(*) as c from b group by all) select dataset, block_id, cast(plane as integer) as plane, {entropy_sql('c')} as h from c group by all")
def _block_entropy(spark, d):
    return features.plane_entropy(blocks.ranked(load(spark, d, CORE), SMALL), "block_id")


@query("plane_entropy", f"with w as ({source(FLOATS)}), {PLANES}, c as (select dataset, plane, byte, count(*) as c from b group by all) select dataset, cast(plane as integer) as plane, {entropy_sql('c')} as h from c group by all")
def _plane_entropy(spark, d):
    """Every float column, the half-precision ones too."""
    return features.plane_entropy(load(spark, d, FLOATS))


@query("plane_hist_sql", f"with w as ({source(CORE)}), {PLANES} select dataset, cast(plane as integer) as plane, cast(byte as integer) as byte, count(*) as cnt from b group by all")
def _plane_hist_sql(spark, d):
    """The histogram with DataFrame functions only."""
    return features.plane_hist_sql(load(spark, d, CORE))


@query("features_entropy", f"with {ranked_sql(CORE)}, {PLANES}, c as (select dataset, block_id, plane, byte, count(*) as c from b group by all), e as (select dataset, block_id, plane, {entropy_sql('c')} as h from c group by all) select dataset, cast(plane as integer) as plane, round(avg(h) + 1e-9, 5) as h_avg, round(coalesce(stddev_samp(h), 0.0) + 1e-9, 5) as h_std, max(h) as h_max, min(h) as h_min from e group by all")
def _features_entropy(spark, d):
    return features.entropy_features(blocks.ranked(load(spark, d, CORE), SMALL))


@query("features_partial", ORACLES["features_entropy"])
def _features_partial(spark, d):
    """The same features from partial sums over blocks."""
    t = features.feature_table(_blocks(spark, d, CORE))
    return t.select("dataset", "plane", *(F.round(F.col(c) + 1e-9, 5).alias(c) for c in ("h_avg", "h_std")), "h_max", "h_min")


@query("features_frequency", f"with w as ({source(CORE)}), {PLANES}, c as (select dataset, plane, byte, count(*) as c from b group by all) select dataset, cast(plane as integer) as plane, cast(byte as integer) as byte, round(c / sum(c) over (partition by dataset, plane), 6) as freq from c")
def _features_frequency(spark, d):
    return features.frequency_feature(load(spark, d, CORE))


_DIMS = f"with {ranked_sql(CORE)}, {PLANES}, bc as (select dataset, block_id, plane, byte, count(*) as c from b group by all), e as (select dataset, block_id, plane, {entropy_sql('c')} as h from bc group by all), s as (select dataset, plane, avg(h) as a, coalesce(stddev_samp(h), 0.0) as d, max(h) as hi, min(h) as lo from e group by all), c as (select dataset, plane, byte, sum(c) as c from bc group by all), f as (select s.dataset, s.plane, v.byte, coalesce(c.c, 0) as c, sum(coalesce(c.c, 0)) over (partition by s.dataset, s.plane) as t from s cross join range(256) v(byte) left join c on c.dataset = s.dataset and c.plane = s.plane and c.byte = v.byte) select dataset, cast(plane as integer) as plane, cast(dim as integer) as dim, value from (select dataset, plane, unnest([0, 1, 2, 3]) as dim, unnest([round(a + 1e-9, 5), round(d + 1e-9, 5), hi, lo]) as value from s union all select dataset, plane, byte + 4, round(c / t + 1e-9, 6) from f)"


@query("features_combined", _DIMS)
def _features_combined(spark, d):
    """The 260 numbers of each plane, a row each: mean, deviation, maximum and minimum of the block entropies, then 256 byte frequencies."""
    x = features.collect_features(_blocks(spark, d, CORE), "combined")
    rows = [(ds, p, i, round(v + 1e-9, 5) if i < 2 else v if i < 4 else round(v + 1e-9, 6)) for ds, m in x.items() for p, row in enumerate(m.tolist()) for i, v in enumerate(row)]
    return spark.createDataFrame(rows, "dataset string, plane int, dim int, value double")


_FREQ = f"with w as ({source(CORE)}), {PLANES}, c as (select dataset, plane, byte, count(*) as c from b group by all), f as (select dataset, plane, byte, round(c / sum(c) over (partition by dataset, plane), 6) as freq from c), pl as (select distinct dataset, plane from f), dist as (select x.dataset, x.plane as i, y.plane as j, sqrt(sum((coalesce(a.freq, 0) - coalesce(b2.freq, 0)) ^ 2)) as dist from pl x join pl y on x.dataset = y.dataset and x.plane < y.plane cross join range(256) v(byte) left join f a on a.dataset = x.dataset and a.plane = x.plane and a.byte = v.byte left join f b2 on b2.dataset = y.dataset and b2.plane = y.plane and b2.byte = v.byte group by all)"


@query("pairwise_distance", f"{_FREQ} select dataset, cast(i as integer) as i, cast(j as integer) as j, round(dist, 5) as dist from dist")
def _pairwise(spark, d):
    return features.pairwise_distance(load(spark, d, CORE))


# ---------------------------------------------------------------- partitions


def _labels(c) -> list[int]:
    return [next(k for k, g in enumerate(c) if i in g) for i in range(sum(map(len, c)))]


def _cost_sql(name: str, n: int) -> str:
    """All partitions of a column's planes with the bits a word that a code of order 0 for each cluster takes."""
    pooled = f"h as (select plane, byte, count(*) as c from b where byte is not null group by all), m as (select s, byte, sum(c) as c from h, (select unnest(range(1, {1 << n})) as s) where (s >> cast(plane as integer)) & 1 = 1 group by all)"
    each = "e as (select s, bit_count(s) * (log2(sum(c)) - sum(c * log2(c)) / sum(c)) as bits from m group by s)"
    members = f"g as (select labels, clusters, string_split(labels, ',')[i + 1] as k, cast(sum(1::bigint << cast(i as integer)) as bigint) as s from ({P15.format(n=n)}), (select unnest(range(0, {n})) as i) group by all)"
    return f"with w as ({source(name)}), {PLANES}, {pooled}, {each}, {members} select labels, clusters, greatest(round(sum(bits), 5) + 0.0, 0.0) as bits from g join e using (s) group by all"


def _costs(spark, d, name: str, n: int) -> DataFrame:
    hist = np.zeros((n, 256))
    for r in features.plane_hist(load(spark, d, name)).collect():  # at most 256 rows a plane
        hist[r.plane, r.byte] = r.cnt
    rows, bits = [], {}
    for c in cluster.set_partitions(n) if hist.any() else ():
        for g in map(tuple, c):
            if g not in bits:
                k = hist[list(g)].sum(0)
                k = k[k > 0]
                bits[g] = len(g) * (np.log2(k.sum()) - (k * np.log2(k)).sum() / k.sum())
        rows.append((",".join(map(str, _labels(c))), len(c), max(0.0, round(float(sum(bits[tuple(g)] for g in c)), 5) + 0.0)))
    return spark.createDataFrame(rows, "labels string, clusters int, bits double")


@query("partitions_15", _cost_sql("TS32-value", 4))
def _partitions(spark, d):
    """All partitions of the four planes of a column, with what they cost."""
    return _costs(spark, d, "TS32-value", 4)


@query("partitions_4140", _cost_sql("TS64-value", 8))
def _partitions8(spark, d):
    return _costs(spark, d, "TS64-value", 8)


_F4 = ["DB32-extprice", "DB32-qty", "DB32-total", "TS32-value", "EMB32-row"]
_FREQ4 = _FREQ.replace(source(CORE), source(_F4))


@query("separation_by_partition", f"with p15 as ({P15.format(n=4)}), " + _FREQ4.removeprefix("with ") + ", pairs as (select labels, clusters, dataset, dist from p15, dist where string_split(labels, ',')[i + 1] <> string_split(labels, ',')[j + 1]) select dataset, labels, round(min(dist), 4) as separation from pairs group by all")
def _separation(spark, d):
    x = features.collect_features(_blocks(spark, d, _F4), "frequency")
    rows = [(ds, ",".join(map(str, _labels(c))), round(cluster.separation(c, np.round(m, 6)), 4)) for ds, m in x.items() for c in cluster.set_partitions(4) if len(c) > 1]
    return spark.createDataFrame(rows, "dataset string, labels string, separation double")


@query("single_linkage_f32", "select dataset, k, round(max(separation), 4) as separation from (select dataset, labels, len(list_distinct(string_split(labels, ','))) as k, separation from (" + ORACLES["separation_by_partition"] + ")) group by all")
def _single_linkage(spark, d):
    """Single linkage reaches the largest least gap for each count: held against all partitions."""
    x = features.collect_features(_blocks(spark, d, _F4), "frequency")
    rows = [(ds, len(c), round(cluster.separation(c, np.round(m, 6)), 4)) for ds, m in x.items() for c in cluster.linkage(np.round(m, 6)) if len(c) > 1]
    return spark.createDataFrame(rows, "dataset string, k long, separation double")


def _choose(spark, d, names, **spec):
    b = _blocks(spark, d, names)
    return spark.createDataFrame([(ds, str(c), len(c)) for ds, c in sorted(pipeline.fit(b, PlanSpec(**spec)).items())], "dataset string, partition string, clusters int")


def _choose_sql(names, method: str = "single") -> str:
    return f"with {squared_sql(names, sampled=True)}, {tree_sql(method)}, {SCORES} {CHOSEN}"


QUERIES["choose_f64"] = lambda spark, d: _choose(spark, d, F64)
QUERIES["choose_f32"] = lambda spark, d: _choose(spark, d, F32)
ORACLES["choose_f32"] = _choose_sql(F32)
QUERIES["choose_f16"] = lambda spark, d: _choose(spark, d, ["EMB16", "QTY16"])
ORACLES["choose_f16"] = "select ds as dataset, '[[0], [1]]' as partition, 2 as clusters from (values ('EMB16'), ('QTY16')) t(ds)"
for _m in ("single", "complete", "average", "ward"):
    QUERIES[f"linkage_{_m}"] = lambda spark, d, m=_m: _choose(spark, d, F32, method=m)
    ORACLES[f"linkage_{_m}"] = _choose_sql(F32, _m)
QUERIES["choose_degenerate"] = lambda spark, d: _choose(spark, d, F32, degenerate="paper")
ORACLES["choose_degenerate"] = _choose_sql(F32)
QUERIES["choose_measured"] = lambda spark, d: _choose(spark, d, CORE, score="measured")
QUERIES["choose_one_se"] = lambda spark, d: _choose(spark, d, CORE, score="gap_one_se")
_SCORED = f"""with {squared_sql(F32)}, {tree_sql()}, {SCORES}, names(score_name) as (values ('silhouette'), ('davies_bouldin'), ('calinski_harabasz')),
every as (select dataset, k, score, 'davies_bouldin' as score_name from db union all select dataset, k, score, 'calinski_harabasz' from ch union all select dataset, k, score, 'silhouette' from si)
select dataset, score_name, cast(k as integer) as k, p::varchar as partition, round(score, 4) as score, score is not null as valid, round(separation, 5) as separation
from parts cross join names left join every using (dataset, k, score_name) left join sep using (dataset, k)"""


def _scored(x: dict, scores, digits: int) -> list[tuple]:
    r = lambda v, k: None if v is None else round(float(v), k)
    return [(ds, s, c["k"], str(c["partition"]), r(c["score"], digits), c["oriented"] is not None, r(c["separation"], 5)) for ds, m in x.items() for s in scores for c in cluster.candidates(m, s)]


_SCORED_DDL = "dataset string, score_name string, k int, partition string, score double, valid boolean, separation double"


@query("candidate_scores", _SCORED)
def _candidates(spark, d):
    """Every candidate of the four-plane columns under the three scores that draw no random references."""
    x = features.collect_features(_blocks(spark, d, F32), "frequency")
    return spark.createDataFrame(_scored(x, ("silhouette", "davies_bouldin", "calinski_harabasz"), 4), _SCORED_DDL)


@query("candidate_gaps")
def _gaps(spark, d):
    x = features.collect_features(_blocks(spark, d, CORE), "combined")
    return spark.createDataFrame(_scored(x, ("gap",), 9), _SCORED_DDL)


@query("separation_centroid", f"with {squared_sql(F32)}, {tree_sql()}, {SCORES} select dataset, cast(k as integer) as k, round(min(g), 5) as separation from gap group by all")
def _centroids(spark, d):
    """The other reading of the objective: the least distance between cluster means."""
    x = features.collect_features(_blocks(spark, d, F32), "frequency")
    return spark.createDataFrame([(ds, len(c), round(cluster.separation(c, m, "centroid"), 5)) for ds, m in x.items() for c in cluster.linkage(m) if len(c) > 1], "dataset string, k int, separation double")


# ---------------------------------------------------------------- packing

_C3 = [[0], [1], [2, 3]]


def _pack_sql(packing: str) -> str:
    order = "plane, pos" if packing == "byte" else "pos, plane"
    return f"with {ranked_sql('TS32-value', 1024)}, {PLANES} select block_id, cast(least(plane, 2) as integer) as cluster_id, string_agg(lower(printf('%02x', cast(byte as integer))), '' order by {order}) as hex from b group by all"


def _pack_hex(spark, d, packing):
    """Packing in SQL form: ordered hex strings a block and cluster."""
    t = features.plane_bytes(blocks.ranked(load(spark, d, "TS32-value"), 1024))
    key = ["plane", "pos"] if packing == "byte" else ["pos", "plane"]
    cell = F.struct(*key, F.lpad(F.lower(F.hex("byte")), 2, "0").alias("h"))
    t = t.groupBy("block_id", F.least("plane", F.lit(2)).alias("cluster_id")).agg(F.sort_array(F.collect_list(cell)).alias("cells"))
    return t.select("block_id", "cluster_id", F.concat_ws("", F.transform("cells", lambda c: c["h"])).alias("hex"))


for _p in ("byte", "value"):
    QUERIES[f"pack_hex_{_p}"] = partial(_pack_hex, packing=_p)
    ORACLES[f"pack_hex_{_p}"] = _pack_sql(_p)


# ---------------------------------------------------------------- round trips


def _round_trip(spark, d, names, spec: PlanSpec, size: int = SMALL, catalogue=None) -> DataFrame:
    b = _blocks(spark, d, names, size)
    c = written(pipeline.compress(b, spec, pipeline.build_catalogue(b, spec) if spec.mode == "static" else None), "container")
    return blocks.words_of_blocks(pipeline.decompress_blocks(c))


def _round_sql(names, size: int = SMALL) -> str:
    return f"with {ranked_sql(names, size)} select dataset, block_id, cast(pos as integer) as pos, bits from w"


_TRIP = ["TS32-value", "TS64-value"]


def _all_ways(spark, d, codec: str) -> DataFrame:
    """Decoded words of the standard image and of both packings."""
    b = _blocks(spark, d, _TRIP)
    parts, out = pipeline.fit(b), None
    for way in ("byte", "value", "standard"):
        c = pipeline.compress_blocks(b, parts, PlanSpec(codec=codec, mode="standard") if way == "standard" else PlanSpec(codec=codec, packing=way))
        t = blocks.words_of_blocks(pipeline.decompress_blocks(c)).withColumn("way", F.lit(way))
        out = t if out is None else out.unionByName(t)
    return out


for _c in ("zstd", "snappy", "lz4", "zlib", "bzip2", "lz4-chunked", "lz77", "fastlz", "huffman", "xor", "xor-plain", "xor-of-128", "delta", "tans", "rle", "bwt-mtf-huffman", "bitshuffle-zstd", "shuffle-zstd", "predictive", "hashed", "stride-lz", "predictive-2d", "store"):
    _n = f"roundtrip_{_c.replace('-', '_')}"
    QUERIES[_n] = lambda spark, d, c=_c: _all_ways(spark, d, c)
    ORACLES[_n] = "select * from (" + _round_sql(_TRIP) + "), (values ('byte'), ('value'), ('standard')) v(way)"
_SPECS = {
    "dynamic": PlanSpec(), "static": PlanSpec(mode="static"), "block_scope": PlanSpec(scope="block"), "monolithic": PlanSpec(layout="monolithic"), "guard": PlanSpec(guard="block"), "guard_sample": PlanSpec(guard="sample"),
    "entropy_order": PlanSpec(cluster_order="entropy"), "entropy_order_desc": PlanSpec(cluster_order="entropy_desc"), "full_sample": PlanSpec(sample=1.0), "zstd_19": PlanSpec(level=19),
}
for _k, _s in _SPECS.items():
    QUERIES[f"roundtrip_{_k}"] = lambda spark, d, s=_s: _round_trip(spark, d, CORE, s)
    ORACLES[f"roundtrip_{_k}"] = _round_sql(CORE)
QUERIES["roundtrip_user"] = lambda spark, d: _round_trip(spark, d, "TS32-value", PlanSpec(mode="user", partition=((0,), (1, 2), (3,))))
ORACLES["roundtrip_user"] = _round_sql("TS32-value")
for _k, _names in (("i32", INTS[:3]), ("i64", INTS[3:7]), ("ts", INTS[7:]), ("array", ["EMB32-row", "EMB32-dim"])):
    QUERIES[f"roundtrip_{_k}"] = lambda spark, d, n=_names: _round_trip(spark, d, n, PlanSpec())
    ORACLES[f"roundtrip_{_k}"] = _round_sql(_names)


QUERIES["roundtrip_f16"] = lambda spark, d: _round_trip(spark, d, ["EMB16", "QTY16"], PlanSpec())
ORACLES["roundtrip_f16"] = _round_sql(["EMB16", "QTY16"])


_NULLED = _round_sql("TS64-value").replace("cast(cast(value as bit) as bigint)", "case when event_id % 7 = 0 then null else cast(cast(value as bit) as bigint) end")


@query("roundtrip_nulls", _NULLED)
def _trip_nulls(spark, d):
    src = load(spark, d, "TS64-value").withColumn("bits", F.when(F.col("k1") % 7 != 0, F.col("bits")))
    return blocks.words_of_blocks(pipeline.decompress_blocks(pipeline.compress(blocks.blocks(src, SMALL))))


@query("roundtrip_null_key", f"with s as ({source('TS64-value')}), n as (select dataset, width, case when k1 % 50 <> 0 then k1 end as k1, k1 as k2, bits from s) select row_number() over (order by k1 nulls first, k2) - 1 as rn, k2, bits from n")
def _null_key(spark, d):
    """Words whose leading key is null come first, ordered by the rest of the key, and none is lost."""
    src = load(spark, d, "TS64-value").withColumn("k2", F.col("k1")).withColumn("k1", F.when(F.col("k1") % 50 != 0, F.col("k1")))
    path = fresh(spark, "container")
    container.write_container(pipeline.compress(blocks.blocks(blocks.with_keys(src, 2), SMALL), PlanSpec(mode="standard")), path)
    return container.read_rows(spark, path, "TS64-value", SMALL, 8, 2).select("rn", "k2", "bits")


@query("roundtrip_rows", "select event_id as k1, value from events")
def _rows_back(spark, d):
    """Values beside their order key, both decoded: the way back to the rows."""
    path = fresh(spark, "container")
    container.write_container(pipeline.compress(blocks.blocks(blocks.with_keys(load(spark, d, "TS64-value")), SMALL)), path)
    return container.read_rows(spark, path, "TS64-value", SMALL, 8).select("k1", bits_word(F.col("bits"), "f64").alias("value"))


for _p in ("byte", "value"):

    def _pack_first(spark, d, packing=_p):
        """Transform first, then cut: streams of the whole column in chunks, and the blocks back from them."""
        b, spec = _blocks(spark, d, _TRIP), PlanSpec(packing=packing)
        parts, n = pipeline.fit(b, spec), packfirst.lengths(b)
        c = written(packfirst.compress_pack_first(b, parts, spec, SMALL, n), "chunks")
        return blocks.words_of_blocks(packfirst.decompress_pack_first(c, parts, spec, SMALL, n))

    QUERIES[f"roundtrip_pack_first_{_p}"] = _pack_first
    ORACLES[f"roundtrip_pack_first_{_p}"] = _round_sql(_TRIP)


@query("roundtrip_pack_first_nulls", _NULLED)
def _pack_first_nulls(spark, d):
    src = load(spark, d, "TS64-value").withColumn("bits", F.when(F.col("k1") % 7 != 0, F.col("bits")))
    b = blocks.blocks(src, SMALL)
    parts, n = pipeline.fit(b), packfirst.lengths(b)
    return blocks.words_of_blocks(packfirst.decompress_pack_first(packfirst.compress_pack_first(b, parts, PlanSpec(), SMALL, n), parts, PlanSpec(), SMALL, n))


@query("container_manifest", f"with {ranked_sql(_TRIP)} select dataset, count(*) * any_value(width) as raw, count(distinct block_id) as blocks from w group by 1")
def _manifest(spark, d):
    path = fresh(spark, "container")
    container.write_container(pipeline.compress(_blocks(spark, d, _TRIP)), path)
    return container.read_manifest(spark, path).select("dataset", "raw", "blocks")


@query("container_serialised", f"with {ranked_sql('TS32-value')} select dataset, block_id, cast(count(*) * 4 as bigint) as raw, true as same from w group by all")
def _serialised(spark, d):
    """Every block's row as bytes and back; ``raw`` is what the streams of the row that came back decode to."""
    return container.survives(pipeline.compress(_blocks(spark, d, "TS32-value"))).select("dataset", "block_id", "raw", "same")


@query("read_range", f"with {ranked_sql('TS64-value')} select rn, bits from w where rn >= 1500 and rn < 3300")
def _read_range(spark, d):
    path = fresh(spark, "container")
    container.write_container(pipeline.compress(_blocks(spark, d, _TRIP)), path)
    return container.read_range(spark, path, "TS64-value", 1500, 3300, SMALL, 8).select("rn", "bits")


@query("zone_map_prune", f"with {ranked_sql('INT64-okey')} select block_id, min(bits) as lo, max(bits) as hi from w group by 1 having min(bits) <= 3000 and max(bits) >= 2000")
def _zone(spark, d):
    path = fresh(spark, "container")
    container.write_container(pipeline.compress(_blocks(spark, d, "INT64-okey")), path)
    return container.read_container(spark, path).filter("min_bits <= 3000 and max_bits >= 2000").select("block_id", F.col("min_bits").alias("lo"), F.col("max_bits").alias("hi"))


_READ = f"with {ranked_sql('TS64-value')} select block_id, cast(pos as integer) as pos, bits from w where block_id >= 2 and block_id < 5"


def _through_source(spark, path):
    from . import datasource

    datasource.register(spark)
    t = spark.read.format("planepack").option("path", path).load()
    return t.filter((F.col("dataset") == "TS64-value") & (F.col("block_id") >= 2) & (F.col("block_id") < 5)).select("block_id", "pos", "bits")


@query("datasource_read", _READ)
def _datasource(spark, d):
    path = fresh(spark, "container")
    container.write_container(pipeline.compress(_blocks(spark, d, _TRIP)), path)
    return _through_source(spark, path)


@query("datasource_write", _READ)
def _datasource_write(spark, d):
    """A container written and read by the data source."""
    from . import datasource

    datasource.register(spark)
    path = fresh(spark, "container")
    pipeline.compress(_blocks(spark, d, _TRIP)).write.format("planepack").mode("append").option("path", path).save()
    return _through_source(spark, path)


@query("raw_words_roundtrip", f"with {ranked_sql('TS64-value')} select rn, bits from w")
def _raw(spark, d):
    """Headerless files of words, written a block each and read in ranges that are smaller than a block."""
    from . import datasource

    path = fresh(spark, "raw")
    datasource.write_raw_words(_blocks(spark, d, "TS64-value"), path)
    t = datasource.read_raw_words(spark, path, "f64", chunk=3000)
    return t.select((F.regexp_extract("file", r"-(\d+)\.bin$", 1).cast("long") * (SMALL // 8) + F.col("pos")).alias("rn"), "bits")


# ---------------------------------------------------------------- entropies and statistics


_WORDS = f"with w as ({source(list(DATASETS))}), c as (select dataset, bits, count(*) as c from w group by all) select dataset, {entropy_sql('c')} as word_entropy, cast(sum(c) as bigint) as n from c group by all"


@query("word_entropy", _WORDS)
def _word_entropy(spark, d):
    """Every registered column, the half-precision ones too."""
    return entropy.word_entropy(load(spark, d, list(DATASETS)))


@query("dataset_profile", f"select e.dataset, word_entropy, n, application, word, width, n * width as bytes from ({_WORDS}) e join (values " + ", ".join(f"('{n}', '{v[4]}', '{v[2]}', {int(v[2][1:]) // 8})" for n, v in DATASETS.items()) + ") a(dataset, application, word, width) using (dataset)")
def _profile(spark, d):
    e = entropy.word_entropy(load(spark, d, list(DATASETS)))
    about = spark.createDataFrame([(n, v[4], v[2], int(v[2][1:]) // 8) for n, v in DATASETS.items()], "dataset string, application string, word string, width int")
    return e.join(F.broadcast(about), "dataset").withColumn("bytes", F.col("n") * F.col("width"))


def _grams_sql(names, k: int) -> str:
    """Common tables up to ``g``: every byte v of the word image with the k before it, inside its block."""
    cells = "cells as (select dataset, block_id, pos * width + i as place, (bits >> cast(8 * i as integer)) & 255 as v from w, unnest(range(0, width)) t(i))"
    lags = "".join(f", lag(v, {j}) over (partition by dataset, block_id order by place) as g{j}" for j in range(1, k + 1))
    return f"{ranked_sql(names)}, {cells}, g as (select dataset, block_id, v{lags} from cells)"


def _contexts(k: int) -> tuple[str, str]:
    return "".join(f", g{j}" for j in range(1, k + 1)), " and ".join(f"g{j} is not null" for j in range(1, k + 1)) or "true"


def _order_sql(k: int) -> str:
    ctx, where = _contexts(k)
    c = f"c as (select dataset, v{ctx}, count(*) as c from g where {where} group by all), t as (select dataset{ctx}, sum(c) as t, sum(c * log2(c)) as s from c group by dataset{ctx})"
    return f"with {_grams_sql(_TRIP, k)}, {c} select dataset, greatest(round((sum(t * log2(t)) - sum(s)) / sum(t), 5) + 0.0, 0.0) as h{k} from t group by 1"


for _k in range(5):
    QUERIES[f"entropy_order_{_k}"] = lambda spark, d, k=_k: entropy.entropy_k(_blocks(spark, d, _TRIP), k)
    ORACLES[f"entropy_order_{_k}"] = _order_sql(_k)
for _k in (1, 2):
    QUERIES[f"entropy_joint_{_k}"] = lambda spark, d, k=_k: entropy.entropy_k(_blocks(spark, d, _TRIP), k, "joint")
    _ctx, _where = _contexts(_k)
    ORACLES[f"entropy_joint_{_k}"] = f"with {_grams_sql(_TRIP, _k)}, c as (select dataset, v{_ctx}, count(*) as c from g where {_where} group by all) select dataset, round(log2(sum(c)) - sum(c * log2(c)) / sum(c), 5) as h{_k} from c group by 1"


def _split_sql() -> str:
    """Block-wise conditional entropies of the word image and of single planes, orders 0 to 2."""
    cells = "cells as (select dataset, block_id, 'before' as side, 0 as stream, pos * width + i as place, (bits >> cast(8 * i as integer)) & 255 as v from w, unnest(range(0, width)) t(i) union all select dataset, block_id, 'after', i, pos, (bits >> cast(8 * i as integer)) & 255 from w, unnest(range(0, width)) t(i))"
    g = "g as (select *, lag(v, 1) over s as g1, lag(v, 2) over s as g2 from cells window s as (partition by dataset, block_id, side, stream order by place))"
    each = []
    for k in range(3):
        ctx, where = _contexts(k)
        each.append(f"select dataset, {k} as k, side, sum(tt) as num, sum(t) as total from (select dataset, side, block_id, stream{ctx}, sum(c) as t, sum(c) * log2(sum(c)) - sum(c * log2(c)) as tt from (select dataset, side, block_id, stream, v{ctx}, count(*) as c from g where {where} group by all) group by dataset, side, block_id, stream{ctx}) group by 1, 2, 3")
    one = lambda side: f"greatest(round(sum(num) filter (side = '{side}') / sum(total) filter (side = '{side}'), 5) + 0.0, 0.0)"
    return f"with {ranked_sql(['TS32-value', 'DB32-qty', 'EMB32-row'])}, {cells}, {g} select dataset, cast(k as integer) as k, {one('before')} as h_before, {one('after')} as h_after from ({' union all '.join(each)}) group by 1, 2"


@query("entropy_before_split", _split_sql())
def _before_split(spark, d):
    """Before the transform, and after it with every plane a stream of its own."""
    names = ["TS32-value", "DB32-qty", "EMB32-row"]
    return entropy.before_after(_blocks(spark, d, names), dict.fromkeys(names, [[0], [1], [2], [3]]), most=2)


@query("h0_invariance", f"with w as ({source(CORE)}), {PLANES}, c as (select dataset, byte, count(*) as c from b group by all), h as (select dataset, {entropy_sql('c')} as h0 from c group by 1) select dataset, s as side, h0 from h, (values ('before'), ('after')) t(s)")
def _h0(spark, d):
    b = _blocks(spark, d, CORE)
    return entropy.order0(b, pipeline.fit(b))


@query("xor_stats", f"with {ranked_sql('TS64-value')}, x as (select block_id, xor(bits, lag(bits) over (partition by block_id order by pos)) as x from w) select block_id, count(*) filter (where x = 0) as zero, cast(sum(case when x < 0 then 0 when x = 0 then 64 else 63 - cast(floor(log2(x & ~((1::bigint << 20) - 1) | (case when x < (1::bigint << 40) then x else 0 end))) as integer) end) as bigint) as lead from x where x is not null group by 1")
def _xor_stats(spark, d):
    """Leading zeros of the xor with the previous word."""
    w = Window.partitionBy("block_id").orderBy("pos")
    t = blocks.ranked(load(spark, d, "TS64-value"), SMALL).select("block_id", F.col("bits").bitwiseXOR(F.lag("bits").over(w)).alias("x")).filter("x is not null")
    lead = F.when(F.col("x") == 0, 64).otherwise(64 - F.length(F.bin("x")))
    return t.groupBy("block_id").agg(F.count_if(F.col("x") == 0).alias("zero"), F.sum(lead).alias("lead"))


@query("delta_stats", f"with {ranked_sql('INT64-ts')}, x as (select block_id, bits - lag(bits) over (partition by block_id order by pos) as x from w) select block_id, min(x) as lo, max(x) as hi, cast(sum(x) as bigint) as total from x where x is not null group by 1")
def _delta_stats(spark, d):
    w = Window.partitionBy("block_id").orderBy("pos")
    t = blocks.ranked(load(spark, d, "INT64-ts"), SMALL).select("block_id", (F.col("bits") - F.lag("bits").over(w)).alias("x")).filter("x is not null")
    return t.groupBy("block_id").agg(F.min("x").alias("lo"), F.max("x").alias("hi"), F.sum("x").alias("total"))


@query("rle_runs", f"with {ranked_sql('INT32-line')}, f as (select *, case when bits = lag(bits) over (partition by block_id order by pos) then 0 else 1 end as new from w) select block_id, cast(sum(new) as bigint) as runs, count(*) as n from f group by 1")
def _rle(spark, d):
    w = Window.partitionBy("block_id").orderBy("pos")
    t = blocks.ranked(load(spark, d, "INT32-line"), SMALL).withColumn("new", F.coalesce((F.col("bits") != F.lag("bits").over(w)).cast("long"), F.lit(1)))
    return t.groupBy("block_id").agg(F.sum("new").alias("runs"), F.count(F.lit(1)).alias("n"))


@query("huffman_bounds", f"with w as ({source('TS32-value')}), {PLANES}, c as (select dataset, plane, byte, count(*) as c from b group by all) select dataset, cast(plane as integer) as plane, {entropy_sql('c')} as h0, true as bounded, true as kraft from c group by all")
def _huffman(spark, d):
    """H0 <= mean code length < H0 + 1, and the lengths fill the code tree, for every plane."""
    rows = []
    for ds, (_, hist) in features.collect_stats(_blocks(spark, d, "TS32-value")).items():
        for p, c in enumerate(hist):
            ln = np.array(foundational.huffman_lengths(c.astype(int).tolist()))
            h, mean = features.entropy_of_counts(c), float((c * ln).sum() / c.sum())
            many = (c > 0).sum() > 1
            rows.append((ds, p, round(h, 6), bool(h - 1e-9 <= mean < h + 1 or not many), bool(not many or abs((2.0 ** -ln[ln > 0].astype(float)).sum() - 1) < 1e-9)))
    return spark.createDataFrame(rows, "dataset string, plane int, h0 double, bounded boolean, kraft boolean")


# ---------------------------------------------------------------- exact sizes of codecs with a closed form


def _size(spark, d, name, codec):
    t = ablation.measure(_blocks(spark, d, name), [(codec, PlanSpec(codec=codec, mode="standard"), {})])
    return t.select("dataset", "raw", "enc", F.col("streams").alias("blocks"), "exact")


_SIZES = {
    "store": ("EMB32-row", "select dataset, count(*) * 4 as raw, count(*) * 4 as enc, count(distinct block_id) as blocks from w group by 1"),
    "rle": ("INT32-line", f"select dataset, sum(n) * 4 as raw, sum(4 * runs + lens + {varint_sql('runs')}) as enc, count(*) as blocks from (select dataset, block_id, count(*) as runs, sum(n) as n, sum({varint_sql('n')}) as lens from (select dataset, block_id, island, bits, count(*) as n from (select *, pos - row_number() over (partition by dataset, block_id, bits order by pos) as island from w) group by all) group by all) group by 1"),
    "delta": ("INT64-ts", f"select dataset, sum(n) * 8 as raw, sum({varint_sql('n')} + body) as enc, count(*) as blocks from (select dataset, block_id, count(*) as n, sum({varint_sql('z')}) as body from (select *, case when x >= 0 then 2 * x else -2 * x - 1 end as z from (select dataset, block_id, bits::hugeint - coalesce(lag(bits) over (partition by dataset, block_id order by pos), 0) as x from w)) group by all) group by 1"),
    "xor-plain": ("TS64-value", f"select dataset, sum(n) * 8 as raw, sum({varint_sql('n')} + (bits + 7) // 8) as enc, count(*) as blocks from (select dataset, block_id, count(*) as n, cast(sum(case when x is null then 64 when x = 0 then 1 else 15 + length(trim(cast(cast(x as bit) as varchar), '0')) end) as bigint) as bits from (select dataset, block_id, xor(bits, lag(bits) over (partition by dataset, block_id order by pos)) as x from w) group by all) group by 1"),
}
for _c, (_n, _text) in _SIZES.items():
    _k = f"codec_size_{_c.replace('-', '_')}"
    QUERIES[_k] = lambda spark, d, n=_n, c=_c: _size(spark, d, n, c)
    ORACLES[_k] = f"with {ranked_sql(_n)} select dataset, cast(raw as bigint) as raw, cast(enc as bigint) as enc, blocks, true as exact from ({_text})"


# ---------------------------------------------------------------- streams


def _events(spark, d):
    return streaming.stream_events(spark, f"{d}/events.parquet")


@query("stream_dedup", "select event_id, value from events")
def _s_dedup(spark, d):
    return streaming.run_to_table(streaming.deduplicated(_events(spark, d)).select("event_id", "value"), "dedup")


_BITS32 = "(select ts, cast(cast(cast(value as float) as bit) as integer)::bigint as bits from events)"
_BYTES = "select {w} as start, plane, cast((bits >> cast(8 * (3 - plane) as integer)) & 255 as integer) as byte, count(*) as cnt from " + _BITS32 + ", (values (0), (1), (2), (3)) p(plane){more} group by all"
_DAY = "time_bucket(interval '1 day', ts, timestamp '1970-01-01')"
_TUMBLING = _BYTES.format(w=_DAY, more="")


@query("stream_tumbling", _TUMBLING)
def _s_tumbling(spark, d):
    return streaming.run_to_table(streaming.window_histogram(_events(spark, d)), "tumbling", "complete")


@query("stream_sliding", _BYTES.format(w="time_bucket(interval '6 hours', ts, timestamp '1970-01-01') - to_hours(6 * back)", more=", (values (0), (1), (2), (3)) o(back)"))
def _s_sliding(spark, d):
    return streaming.run_to_table(streaming.window_histogram(_events(spark, d), "1 day", "6 hours"), "sliding", "complete")


@query("stream_window_entropy", f"select start, plane, {entropy_sql('cnt')} as h, cast(sum(cnt) as bigint) as n from ({_TUMBLING}) group by all")
def _s_entropy(spark, d):
    return streaming.window_entropy(_s_tumbling(spark, d))


@query("stream_sessions", "select min(ts) as start, max(ts) + interval '30 minutes' as end, user_id, count(*) as n, cast(sum(cast(value as decimal(18, 2))) as double) as total from (select *, sum(new) over (partition by user_id order by ts, event_id) as s from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) <= interval '30 minutes' then 0 else 1 end as new from events)) group by user_id, s")
def _s_sessions(spark, d):
    return streaming.run_to_table(streaming.sessions(_events(spark, d)), "sessions", "complete")


@query("stream_xor", "select user_id, event_id, xor(b, coalesce(p, b)) as x from (select *, lag(b) over (partition by user_id order by event_id) as p from (select user_id, event_id, cast(cast(value as bit) as bigint) as b from events))")
def _s_xor(spark, d):
    return streaming.run_to_table(streaming.stream_xor(_events(spark, d)), "xor").select("user_id", "event_id", "x")


@query("stream_blocks", "select event_type, event_id, cast(value as float) as value from events")
def _s_blocks(spark, d):
    """Blocks formed by the stream, decoded again."""
    return streaming.unblocked(streaming.run_to_table(streaming.stream_blocks(_events(spark, d), 64, _C3), "former"), _C3)


@query("stream_static_join", "select event_id, c_mktsegment from events join customer on user_id = c_custkey")
def _s_join(spark, d):
    return streaming.run_to_table(_events(spark, d).join(table(spark, d, "customer", "c_custkey", "c_mktsegment"), F.expr("user_id = c_custkey")).select("event_id", "c_mktsegment"), "joined")


@query("stream_stream_join", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' and a.ts <= b.ts and a.ts >= b.ts - interval '1 hour'")
def _s_two(spark, d):
    return streaming.run_to_table(streaming.preceded(_events(spark, d), "view", "purchase"), "preceded")


@query("stream_late", "with f as (select ts, event_id % 7 as f from events), m as (select f, max(ts) as top from f group by 1), w as (select a.f, max(b.top) - interval '10 minutes' as mark from m a left join m b on b.f < a.f - 1 group by 1), k as (select " + _DAY + " as start, mark from f join w using (f)) select start, count(*) as n from k where mark is null or start + interval '1 day' > mark group by 1")
def _s_late(spark, d):
    """Events dealt to seven files by their number, so that all but the first are late: the watermark of a batch drops rows two batches on."""
    e, path = table(spark, d, "events"), fresh(spark, "late")
    for i in range(7):
        e.filter(F.col("event_id") % 7 == i).coalesce(1).write.mode("append").parquet(path)
    return streaming.run_to_table(streaming.window_counts(streaming.stream_events(spark, path)), "late", "update", ("start",))


_REFERENCE = f"ref as (select plane, byte, round(c / sum(c) over (partition by plane), 6) as r from (select plane, byte, sum(cnt) as c from ({_TUMBLING}) group by all))"


@query("stream_drift", f"with {_REFERENCE}, h as (select *, cnt / sum(cnt) over (partition by start, plane) as q from ({_TUMBLING})), s as (select distinct start, plane from h), d as (select s.start, s.plane, sqrt(sum((coalesce(h.q, 0.0) - coalesce(ref.r, 0.0)) ^ 2)) as distance from s cross join range(256) v(byte) left join h on h.start = s.start and h.plane = s.plane and h.byte = v.byte left join ref on ref.plane = s.plane and ref.byte = v.byte group by all) select start, plane, round(distance, 5) as distance, round(distance, 5) > 0.1 as refit from d")
def _s_drift(spark, d):
    ref = features.frequency_feature(load(spark, d, "TS32-value")).select("plane", "byte", "freq")
    return streaming.drift(_s_tumbling(spark, d), ref)


@query("stream_watch", f"select * from ({ORACLES['stream_drift']}) where start + interval '1 day' <= (select max(ts) - interval '10 minutes' from events)")
def _s_watch(spark, d):
    """The drift of each window as the watermark closes it."""
    ref = features.frequency_feature(load(spark, d, "TS32-value")).select("plane", "byte", "freq")
    return streaming.watch(_events(spark, d), ref)


# ---------------------------------------------------------------- functions in SQL


def _sql(spark, text: str, **views) -> DataFrame:
    from . import functions

    functions.register(spark)
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    return spark.sql(text)


@query("sql_functions", f"select p_partkey, p_name as name, {entropy_sql('c')} as h from (select p_partkey, p_name, ch, count(*) as c from (select p_partkey, p_name, unnest(string_split(p_name, '')) as ch from part) group by all) group by 1, 2")
def _sql_functions(spark, d):
    """Encode and decode in SQL, and the entropy of each name's bytes."""
    text = "select p_partkey, cast(pp_decode(pp_encode(cast(p_name as binary), 'lz77'), 'lz77', octet_length(p_name)) as string) as name, round(pp_entropy(cast(p_name as binary)), 6) as h from pp_parts"
    return _sql(spark, text, pp_parts=table(spark, d, "part", "p_partkey", "p_name"))


@query("sql_word_bits", "select event_id, cast(cast(value as bit) as bigint) as bits, value as back from events")
def _sql_bits(spark, d):
    return _sql(spark, "select event_id, word_bits(value) as bits, bits_word(word_bits(value)) as back from pp_events", pp_events=table(spark, d, "events", "event_id", "value"))


_PACKED = "select block_id, packing, plane // 2 as c, string_agg(upper(printf('%02x', cast(byte as integer))), '' order by case packing when 'byte' then plane * 1024 + pos else pos * 4 + plane end) as hex from b, (values ('byte'), ('value')) v(packing) group by all"


@query("sql_pack", f"with {ranked_sql('TS32-value', 1024)}, {PLANES} select block_id, packing, string_agg(hex, ',' order by c) as streams from ({_PACKED}) group by all")
def _sql_pack(spark, d):
    """The streams of {0, 1}, {2, 3} of every block, under both packings."""
    text = "select block_id, packing, concat_ws(',', transform(pp_pack(data, 4, array(array(0, 1), array(2, 3)), packing), x -> hex(x))) as streams from pp_images cross join (values ('byte'), ('value')) v(packing)"
    return _sql(spark, text, pp_images=_blocks(spark, d, "TS32-value", 1024).select("block_id", "data"))


_FOUR = ["DB32-total", "DB32-acct", "DB32-retail", "TS32-value"]
_BEST = "select dataset, '{0}' as score, array_to_string([array_to_string(g, ',') for g in p], '|') as partition from parts join {1} using (dataset, k) qualify row_number() over (partition by dataset order by score {2}, k) = 1"


@query("sql_choose", f"with {squared_sql(_FOUR)}, {tree_sql()}, {SCORES} {_BEST.format('davies_bouldin', 'db', '')} union all {_BEST.format('silhouette', 'si', 'desc')}")
def _sql_choose(spark, d):
    """The choice under two scores, from the byte frequencies of the planes of whole columns."""
    text = """with f as (select dataset, plane, map_from_entries(collect_list(struct(byte, cnt))) as m, sum(cnt) as t from pp_hist group by all),
    x as (select dataset, transform(array_sort(collect_list(struct(plane, transform(sequence(0, 255), b -> coalesce(m[b] / t, 0D)) as v))), p -> p.v) as x from f group by all)
    select dataset, score, concat_ws('|', transform(pp_choose(x, score), g -> concat_ws(',', transform(g, i -> cast(i as string))))) as partition from x cross join (values ('davies_bouldin'), ('silhouette')) s(score)"""
    return _sql(spark, text, pp_hist=features.plane_hist(load(spark, d, _FOUR)))


_TYPED = "(select event_type, cast(cast(cast(value as float) as bit) as integer)::bigint & 255 as byte from events)"


@query("sql_entropy_agg", f"select event_type, {entropy_sql('c')} as h, cast(sum(c) as bigint) as n, max(c) as most from (select event_type, byte, count(*) as c from {_TYPED} group by all) group by 1")
def _sql_aggregates(spark, d):
    """Entropy and histogram of the lowest byte of each type's values."""
    words = table(spark, d, "events", "event_type", "value")
    text = "select event_type, round(pp_entropy_agg(byte), 6) as h, aggregate(pp_hist_agg(byte), 0L, (a, x) -> a + x) as n, array_max(pp_hist_agg(byte)) as most from (select event_type, word_bits32(cast(value as float)) & 255 as byte from pp_typed) group by event_type"
    return _sql(spark, text, pp_typed=words)


@query("sql_words", f"with {ranked_sql('TS64-value')} select block_id, cast(pos as integer) as pos, bits from w")
def _sql_words(spark, d):
    """Blocks to words by a table function."""
    return _sql(spark, "select block_id, w.pos, w.bits from pp_blocks, lateral pp_words(data, width) w", pp_blocks=_blocks(spark, d, "TS64-value").select("block_id", "width", "data"))


_VARYING = "select event_type, bit_or(b) & ~bit_and(b) as v from (select event_type, cast(cast(cast(value as float) as bit) as integer)::bigint as b from events where value is not null) group by 1"
_VARYING = f"select event_type, cast({' + '.join(f'case when (v >> {8 * i}) & 255 > 0 then 1 else 0 end' for i in range(4))} as integer) as planes from ({_VARYING})"


@query("sql_set_partitions", f"select event_type, planes, clusters, count(*) as n from ({_VARYING}) join (" + " union all ".join(f"select {n} as planes, clusters from ({P15.format(n=n)})" for n in range(1, 5)) + ") using (planes) group by all")
def _sql_partitions(spark, d):
    """In how many ways the planes that vary among the values of an event type can be grouped."""
    varying = "select event_type, bit_or(b) & ~bit_and(b) as v from (select event_type, word_bits32(cast(value as float)) as b from pp_valued where value is not null) group by 1"
    planes = f"select event_type, size(filter(sequence(0, 3), i -> (shiftright(v, 8 * i) & 255) > 0)) as planes from ({varying})"
    return _sql(spark, f"select event_type, planes, t.clusters, count(*) as n from ({planes}) p, lateral pp_set_partitions(planes) t group by 1, 2, 3 having planes > 0", pp_valued=table(spark, d, "events", "event_type", "value"))


for _name, (_f, _text) in RELOPS.items():
    QUERIES[_name] = _f
    if _text:
        ORACLES[_name] = _text


def entry(spark, sf_dir: str) -> DataFrame:
    """Fit, transform, compress, decode and compare: a row per dataset and variant."""
    b = _blocks(spark, sf_dir, ["TS32-value", "DB32-qty", "EMB32-row"])
    return ablation.split_job(ablation.measure(b, ablation.both(["zstd"], pipeline.fit(b))), "codec", "variant").select("dataset", "codec", "variant", "raw", "enc", "cr", "exact")
