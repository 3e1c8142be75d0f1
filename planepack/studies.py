"""The experiments: every study reads a block once and encodes all its variants in the block's task.

Sizes of compressed streams have no SQL form; rows that SQL can state (bytes, blocks, losslessness, partitions) are registered beside the studies,
and tests hold the sizes against the tools themselves.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import ablation, blocks, cluster, entropy, features, metrics, packfirst, pipeline
from .codecs import TOOLS
from .fixtures import DATASETS, F32, F64, FLOATS, INTS, load
from .pipeline import PlanSpec
from .registry import P15, PLANES, SMALL, query, ranked_sql, small_blocks, source
from .storage import written

#: Bytes of a block in the studies: several blocks a column at the given scales.
BLOCK = 65536
_F4 = ["DB32-extprice", "DB32-qty", "DB32-total", "TS32-value", "EMB32-row"]


def _blocks(spark, d, names, size: int = BLOCK) -> DataFrame:
    """Written once: a study reads its blocks several times."""
    return written(small_blocks(spark, d, names, size), "blocks")


def _cr(spark, d, names, tools=TOOLS, **spec) -> DataFrame:
    b = _blocks(spark, d, names)
    return ablation.split_job(ablation.measure(b, ablation.both(tools, pipeline.fit(b), **spec)), "codec", "variant")


def _about(df: DataFrame) -> DataFrame:
    rows = [(n, v[4], v[2]) for n, v in DATASETS.items()]
    return df.join(F.broadcast(df.sparkSession.createDataFrame(rows, "dataset string, application string, word string")), "dataset")


_TOTALS = "select dataset, cast(count(*) * any_value(width) as bigint) as raw, count(distinct block_id) as blocks from w group by 1"

# ---------------------------------------------------------------- ratios


def _cr_rows(spark, d) -> DataFrame:
    """The table behind the roll-ups: all columns, tools and both variants, computed once and written."""
    return written(_cr(spark, d, list(DATASETS)), "ratios")


@query("cr_table")
def _cr_table(spark, d):
    return metrics.improvement(_cr_rows(spark, d), "cr", "dataset", "codec")


@query("cr_summary")
def _cr_summary(spark, d):
    """The ratio table rolled up at once: by tool (with quartiles), by width, by domain, and all of it; ``level`` tells which."""
    t = written(_about(metrics.improvement(_cr_rows(spark, d), "cr", "dataset", "codec")), "table")
    g = [F.count(F.lit(1)).alias("n"), metrics.gmean("cr_clustered").alias("clustered"), metrics.gmean("cr_standard").alias("standard"), metrics.gmean("cr_improvement").alias("cri"), F.count_if(F.col("cr_improvement") < 1).alias("losses")]
    c, w, a = F.col("codec"), F.col("word"), F.col("application")
    return t.groupingSets([(c,), (w, c), (a, c), ()], c, w, a).agg(F.grouping_id().cast("long").alias("level"), *g)


@query("cr_distribution")
def _cr_dist(spark, d):
    return metrics.cr_distribution(_cr(spark, d, FLOATS), "cr", "codec", "variant")


@query("cr_by_width")
def _cr_width(spark, d):
    return _about(_cr_table(spark, d)).groupBy("word", "codec").agg(metrics.gmean("cr_improvement").alias("cri"))


@query("cr_by_domain")
def _cr_domain(spark, d):
    return _about(_cr_table(spark, d)).groupBy("application", "codec").agg(metrics.gmean("cr_clustered").alias("gmean"), metrics.gmean("cr_improvement").alias("cri"))


@query("cr_cube")
def _cr_cube(spark, d):
    return _about(_cr_rows(spark, d)).cube("application", "word", "codec", "variant").agg((F.sum("raw") / F.sum("enc")).alias("cr"), F.grouping_id().alias("gid"))


@query("cr_facts", f"with {ranked_sql(list(DATASETS), BLOCK)} select dataset, v as variant, raw, blocks, true as exact, true as bounded from ({_TOTALS}), (values ('standard'), ('clustered')) t(v)")
def _cr_facts(spark, d):
    """Of the ratio table with the default tool: bytes and blocks of every column, that all came back exactly, and that no stream grew beyond the tool's bound."""
    b = _blocks(spark, d, list(DATASETS))
    m = ablation.split_job(ablation.measure(b, ablation.both(["zstd"], pipeline.fit(b))), "codec", "variant")
    n = b.groupBy("dataset").agg(F.count(F.lit(1)).alias("blocks"))
    bounded = F.col("enc") <= F.col("raw") + F.col("raw") / 128 + 64 * F.col("streams")
    return m.join(n, "dataset").select("dataset", "variant", "raw", "blocks", "exact", bounded.alias("bounded"))


@query("worked_series")
def _worked(spark, d):
    return _cr(spark, d, "TS32-value", ["zstd"])


@query("predictive_vs_generic")
def _fig1(spark, d):
    c = _cr(spark, d, FLOATS, ["zstd", "predictive"])
    return c.join(entropy.word_entropy(load(spark, d, FLOATS)), "dataset").select("dataset", "word_entropy", "codec", "variant", "cr")


FOUNDATIONAL = ("lz77", "huffman", "xor", "delta")


@query("foundational_table")
def _foundational(spark, d):
    """Every column under both packings; the standard form has no packing and is encoded once."""
    b = _blocks(spark, d, list(DATASETS))
    parts = pipeline.fit(b)
    jobs = []
    for t in FOUNDATIONAL:
        jobs.append((f"{t}|standard|", PlanSpec(codec=t, mode="standard"), {}))
        jobs += [(f"{t}|clustered|{p}", PlanSpec(codec=t, mode="user", packing=p), parts) for p in ("byte", "value")]
    m = ablation.split_job(ablation.measure(b, jobs), "codec", "variant", "packing")
    m = m.withColumn("packing", F.explode(F.when(F.col("variant") == "standard", F.array(F.lit("byte"), F.lit("value"))).otherwise(F.array("packing"))))
    return metrics.improvement(m, "cr", "dataset", "codec", "packing")


@query("bitshuffle_table")
def _bitshuffle(spark, d):
    b = _blocks(spark, d, FLOATS)
    jobs = [("clustered", PlanSpec(mode="user"), pipeline.fit(b)), ("bitshuffle", PlanSpec(codec="bitshuffle-zstd", mode="standard"), {}), ("shuffle", PlanSpec(codec="shuffle-zstd", mode="standard"), {}), ("standard", PlanSpec(mode="standard"), {})]
    return ablation.measure(b, jobs).select("dataset", "job", "raw", "enc", "cr", "exact")


@query("predictive_table")
def _predictive(spark, d):
    """Every tool on the clusters against the predictive codec, in one dimension and in two."""
    b = _blocks(spark, d, FLOATS)
    parts = pipeline.fit(b)
    rivals = ("predictive", "predictive-2d")
    m = written(ablation.measure(b, [(t, PlanSpec(codec=t, mode="user"), parts) for t in TOOLS] + [(r, PlanSpec(codec=r, mode="standard"), {}) for r in rivals]), "measured")
    rival = m.filter(F.col("job").isin(*rivals)).select("dataset", F.col("job").alias("against"), F.col("cr").alias("rival"))
    return m.filter(~F.col("job").isin(*rivals)).join(rival, "dataset").groupBy("job", "against").agg(metrics.gmean("cr").alias("gmean"), metrics.gmean("rival").alias("gmean_rival"), metrics.win_rate("cr", "rival").alias("win_rate"))


@query("rival_float_codecs")
def _rivals(spark, d):
    return _cr(spark, d, FLOATS, ["hashed", "stride-lz", "xor-of-128"])


@query("mode_table")
def _modes(spark, d):
    b = _blocks(spark, d, FLOATS)
    dyn, cat = pipeline.fit(b), pipeline.build_catalogue(b)
    stat = {n: cat[(DATASETS[n][4], DATASETS[n][2])] for n in FLOATS}
    m = ablation.measure(b, [("dynamic", PlanSpec(mode="user"), dyn), ("static", PlanSpec(mode="user"), stat)])
    return m.groupBy("dataset").pivot("job", ["dynamic", "static"]).agg(F.first("cr")).withColumn("same", F.abs(F.col("dynamic") - F.col("static")) < 1e-12)


@query("static_catalogue")
def _catalogue(spark, d):
    cat = pipeline.build_catalogue(_blocks(spark, d, list(DATASETS), SMALL))
    return spark.createDataFrame([(*k, str(v)) for k, v in sorted(cat.items())], "application string, word string, partition string")


@query("catalogue_keys", "select distinct application, word, true as partition from (values " + ", ".join(f"('{v[4]}', '{v[2]}')" for v in DATASETS.values()) + ") t(application, word)")
def _catalogue_keys(spark, d):
    """Every application and word type has an entry, and it is a partition of the word's planes."""
    cat = pipeline.build_catalogue(small_blocks(spark, d, list(DATASETS)))
    return spark.createDataFrame([(a, w, cluster.is_partition(c, int(w[1:]) // 8)) for (a, w), c in cat.items()], "application string, word string, partition boolean")


# ---------------------------------------------------------------- choice of the partition


@query("feature_score_grid")
def _grid(spark, d):
    return ablation.feature_score_grid(_blocks(spark, d, F32 + F64))


@query("feature_score_gmean")
def _grid_gmean(spark, d):
    """Which of the twelve choices wins for each width, from 30 % of the blocks and from all of them."""
    b = _blocks(spark, d, F32 + F64)
    out = None
    for share in (0.3, 1.0):
        t = ablation.feature_score_grid(b, sample=share).withColumn("sample", F.lit(share))
        out = t if out is None else out.unionByName(t)
    return _about(out).groupBy("sample", "word", "features", "score").agg(metrics.gmean("cr").alias("gmean"))


def _optimal(spark, d) -> DataFrame:
    b = _blocks(spark, d, F32)
    parts = pipeline.fit(b)
    t = written(ablation.exhaustive(b, 4), "exhaustive")
    best = t.groupBy("dataset", "packing").agg(F.max("cr").alias("best"), F.max_by("partition", "cr").alias("best_partition"))
    mine = spark.createDataFrame([(k, str(v)) for k, v in parts.items()], "dataset string, partition string")
    return t.join(mine, ["dataset", "partition"]).join(best, ["dataset", "packing"]).select("dataset", "packing", "partition", "cr", "best", "best_partition", (F.col("cr") >= F.col("best") - 1e-12).alias("optimal"))


@query("exhaustive_table")
def _exhaustive(spark, d):
    return _optimal(spark, d)


@query("optimality_rate")
def _rate(spark, d):
    """The share of columns whose fitted partition is the best of all, and how near the others come."""
    return _optimal(spark, d).groupBy("packing").agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("optimal").cast("int")).alias("rate"), F.min(F.col("cr") / F.col("best")).alias("worst"), metrics.gmean(F.col("cr") / F.col("best")).alias("gmean"))


@query("exhaustive_facts", f"with p15 as (select labels from ({P15.format(n=4)})), {ranked_sql(F32, BLOCK)}, t as ({_TOTALS}) select dataset, packing, labels, raw, raw as enc from t, p15, (values ('byte'), ('value')) v(packing)")
def _exhaustive_facts(spark, d):
    """Every partition and packing of every column, without a codec: each takes all bytes, once."""
    t = ablation.exhaustive(_blocks(spark, d, F32), 4, "store")
    names = {str(c): ",".join(str(next(k for k, g in enumerate(c) if i in g)) for i in range(4)) for c in cluster.set_partitions(4)}
    label = F.create_map(*[F.lit(x) for kv in names.items() for x in kv])[F.col("partition")]
    return t.select("dataset", "packing", label.alias("labels"), "raw", "enc")


@query("exhaustive_valid", f"with {ranked_sql(F32, BLOCK)} select dataset, true as among, true as singles_agree, true as no_better from w group by 1")
def _exhaustive_ok(spark, d):
    """The fitted partition is one of the fifteen, packings agree on single planes, and sizes measured on their own equal those of the search."""
    b = _blocks(spark, d, F32)
    parts = pipeline.fit(b)
    t = written(ablation.exhaustive(b, 4), "exhaustive")
    mine = ablation.measure(b, [("mine", PlanSpec(mode="user"), parts)]).select("dataset", F.col("enc").alias("own"))
    named = spark.createDataFrame([(k, str(v)) for k, v in parts.items()], "dataset string, fitted string")
    singles = F.col("partition") == "[[0], [1], [2], [3]]"
    t = t.join(named, "dataset").join(mine, "dataset").groupBy("dataset").agg(
        F.bool_or(F.col("partition") == F.col("fitted")).alias("among"), (F.min(F.when(singles, F.col("enc"))) == F.max(F.when(singles, F.col("enc")))).alias("singles_agree"),
        (F.max(F.when((F.col("partition") == F.col("fitted")) & (F.col("packing") == "byte"), F.col("enc"))) == F.first("own")).alias("same"), (F.min(F.when(F.col("packing") == "byte", F.col("enc"))) <= F.first("own")).alias("least"))
    return t.select("dataset", "among", "singles_agree", (F.col("same") & F.col("least")).alias("no_better"))


@query("exhaustive_f64")
def _exhaustive64(spark, d):
    """All 4140 partitions on all blocks of one column; cluster streams are shared between partitions, so 255 encodes a block and packing do."""
    return ablation.exhaustive(_blocks(spark, d, "DB64-retail"), 8, "zstd").select("dataset", "packing", "partition", "cr")


@query("partition_space")
def _space(spark, d):
    """All partitions by the spread of their components' entropies, with their ratios."""
    b = _blocks(spark, d, F32)
    rows = [(ds, str(c), float(np.std([features.entropy_of_counts(sum(hist[i] for i in g)) for g in c]))) for ds, (_, hist) in features.collect_stats(b).items() for c in cluster.set_partitions(4)]
    std = spark.createDataFrame(rows, "dataset string, partition string, entropy_std double")
    return ablation.exhaustive(b, 4).join(std, ["dataset", "partition"])


@query("sample_stability")
def _stability(spark, d):
    b = _blocks(spark, d, FLOATS, SMALL)
    small, full = pipeline.fit(b), pipeline.fit(b, PlanSpec(sample=1.0))
    m = ablation.measure(b, [("sample", PlanSpec(mode="user"), small), ("full", PlanSpec(mode="user"), full)], decode=False)
    same = spark.createDataFrame([(k, small[k] == full[k]) for k in full], "dataset string, same_partition boolean")
    return m.groupBy("dataset").pivot("job", ["sample", "full"]).agg(F.first("cr")).join(same, "dataset")


@query("sample_stability_rate")
def _stability_rate(spark, d):
    """The share of columns with the same partition, and with the same ratio, from 30 % of the blocks."""
    same = (F.abs(F.col("sample") - F.col("full")) < 1e-12).cast("int")
    return _stability(spark, d).agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("same_partition").cast("int")).alias("same_partition"), F.avg(same).alias("same_ratio"), F.min(F.col("sample") / F.col("full")).alias("worst"))


@query("fit_cost")
def _fit_cost(spark, d):
    """Candidates and seconds of the clustering of every column beside the seconds of its compression."""
    b = _blocks(spark, d, list(DATASETS))
    t = written(pipeline.fit_table(b), "fits")
    parts = {r.dataset: [list(g) for g in r.partition] for r in t.select("dataset", "partition").collect()}
    m = ablation.measure(b, [("zstd", PlanSpec(mode="user"), parts)], decode=False).select("dataset", "enc_ns")
    return t.join(m, "dataset").select("dataset", "width", "candidates", "fit_ns", "enc_ns", (F.col("fit_ns") / (F.col("fit_ns") + F.col("enc_ns"))).alias("share"))


@query("fit_candidates", "select ds as dataset, w as width, case when w = 2 then 1 else w end as candidates, true as partition from (values " + ", ".join(f"('{n}', {int(v[2][1:]) // 8})" for n, v in DATASETS.items()) + ") t(ds, w)")
def _fit_candidates(spark, d):
    """As many candidates as planes, one for two planes; the choice covers every plane once."""
    t = pipeline.fit_table(small_blocks(spark, d, list(DATASETS)))
    covers = F.array_sort(F.flatten("partition")) == F.sequence(F.lit(0), F.col("width") - 1)
    return t.select("dataset", "width", "candidates", covers.alias("partition"))


@query("objective_study")
def _objective(spark, d):
    t = ablation.objective_study(_blocks(spark, d, F32))
    r = lambda a, b: F.corr(a, b)
    return t.groupBy("dataset").agg(r("separation", "intra").alias("r_intra"), r("separation", "inter").alias("r_inter"), r("separation", "cr").alias("r_cr"), r("separation_centroid", "cr").alias("r_centroid_cr"), F.count(F.lit(1)).alias("partitions"))


@query("kmeans_rival")
def _kmeans(spark, d):
    x = features.collect_features(_blocks(spark, d, F32 + F64, SMALL), "frequency")
    rows = [(ds, k, str(c := cluster.kmeans(m, k)), cluster.davies_bouldin(c, m), cluster.davies_bouldin(cluster.cut(cluster.linkage(m), k), m)) for ds, m in x.items() for k in range(2, len(m))]
    return spark.createDataFrame(rows, "dataset string, k int, partition string, kmeans double, hierarchical double")


# ---------------------------------------------------------------- entropies


@query("entropy_before_after")
def _before_after(spark, d):
    b = _blocks(spark, d, FLOATS)
    return entropy.before_after(b, pipeline.fit(b))


@query("spearman_table")
def _spearman(spark, d):
    b = _blocks(spark, d, FLOATS)
    parts = pipeline.fit(b)
    h = entropy.before_after(b, parts)
    m = ablation.measure(b, [("c", PlanSpec(mode="user"), parts)], decode=False).select("dataset", (F.col("enc") / F.col("raw")).alias("size"))
    return metrics.spearman(h.join(m, "dataset"), "size", "h_after", "k")


_SPEARMAN = "with x as (select n_nationkey % 5 as g, c_acctbal as a, c_nationkey as b from customer join nation on c_nationkey = n_nationkey), r as (select g, rank() over (partition by g order by a) + (count(*) over (partition by g, a) - 1) / 2 as ra, rank() over (partition by g order by b) + (count(*) over (partition by g, b) - 1) / 2 as rb from x) select g, round(corr(ra, rb), 6) as rho from r group by 1"


@query("spearman_rule", _SPEARMAN)
def _spearman_rule(spark, d):
    """The rank correlation itself, with ties, on plain columns."""
    from .fixtures import table

    t = table(spark, d, "customer", "c_acctbal", "c_nationkey").select((F.col("c_nationkey") % 5).cast("long").alias("g"), F.col("c_acctbal").alias("a"), F.col("c_nationkey").alias("b"))
    return metrics.spearman(t, "a", "b", "g").select("g", F.round("rho", 6).alias("rho"))


@query("metric_rules", "select c_mktsegment, round(exp(avg(ln(c_custkey + 1))), 4) as gmean, round(avg(case when c_acctbal > c_custkey then 1 else 0 end), 6) as wins from customer group by 1")
def _metric_rules(spark, d):
    """Geometric mean and win rate on plain columns."""
    from .fixtures import table

    t = table(spark, d, "customer", "c_mktsegment", "c_custkey", "c_acctbal")
    return t.groupBy("c_mktsegment").agg(F.round(metrics.gmean(F.col("c_custkey") + 1), 4).alias("gmean"), F.round(metrics.win_rate("c_acctbal", "c_custkey"), 6).alias("wins"))


# ---------------------------------------------------------------- packing, layout, order of stages, block size


@query("packing_table")
def _packing(spark, d):
    b = _blocks(spark, d, list(DATASETS))
    parts = pipeline.fit(b)
    return ablation.measure(b, [(p, PlanSpec(mode="user", packing=p), parts) for p in ("byte", "value")]).groupBy("dataset").pivot("job", ["byte", "value"]).agg(F.first("cr"))


@query("decomposition_table")
def _decomposition(spark, d):
    b = _blocks(spark, d, FLOATS)
    parts = pipeline.fit(b)
    return ablation.measure(b, [(f"{c}|{x}", PlanSpec(codec=c, mode="user", layout=x), parts) for c in ("zstd", "lz77", "huffman") for x in ("decomposed", "monolithic")]).select("dataset", "job", "cr")


#: Between a first-level and a last-level cache.
SWEEP = [k << 10 for k in (16, 64, 256, 1024, 4096, 8192, 16384, 32768)]


def _cut_each(spark, d, names):
    """The words are sorted once; blocks of every size are cut from the same pieces."""
    pieces = blocks.gathered(load(spark, d, names), max(SWEEP))
    for size in SWEEP:
        yield size, blocks.cut(pieces, size)


@query("block_sweep")
def _sweep(spark, d):
    out = None
    for size, b in _cut_each(spark, d, FLOATS):
        b = written(b, "blocks")
        m = ablation.measure(b, [("fastlz", PlanSpec(codec="fastlz", mode="user"), pipeline.fit(b))]).withColumn("block_bytes", F.lit(size))
        out = m if out is None else out.unionByName(m)
    return out.select("dataset", "block_bytes", "cr", "raw", "enc_ns", "dec_ns")


@query("block_sweep_facts", f"with src as ({source(FLOATS)}), n as (select dataset, any_value(width) as width, count(*) as n from src group by 1) select dataset, size as block_bytes, n * width as raw, cast(ceil(n / (size / width)) as bigint) as blocks, true as exact from n, (values {', '.join(f'({s})' for s in SWEEP)}) t(size)")
def _sweep_facts(spark, d):
    """Bytes and blocks of every column at every block size, stored and read back."""
    out = None
    for size, b in _cut_each(spark, d, FLOATS):
        m = ablation.measure(b, [("store", PlanSpec(codec="store", mode="standard"), {})]).withColumn("block_bytes", F.lit(size))
        out = m if out is None else out.unionByName(m)
    return out.select("dataset", "block_bytes", "raw", F.col("streams").alias("blocks"), "exact")


@query("order_table")
def _order(spark, d):
    """Standard, block first, and transform first; times hold the encoder and the copies into and out of the streams."""
    b = _blocks(spark, d, FLOATS)
    parts, n, spec = pipeline.fit(b), packfirst.lengths(b), PlanSpec(mode="user")
    a = ablation.measure(b, [("standard", PlanSpec(mode="standard"), {}), ("block_first", spec, parts)]).select("dataset", "job", "raw", "enc", "enc_ns", "dec_ns", "exact")
    c = written(packfirst.compress_pack_first(b, parts, spec, BLOCK, n), "chunks")
    back = packfirst.decompress_pack_first(c, parts, spec, BLOCK, n)
    check = b.select("dataset", "block_id", F.xxhash64("data").alias("want"))
    back = back.select("dataset", "block_id", "dec_ns", F.xxhash64("data").alias("got"), F.length("data").alias("raw")).join(check, ["dataset", "block_id"], "full")
    dec = back.groupBy("dataset").agg(F.sum("raw").cast("long").alias("raw"), F.sum("dec_ns").alias("dec_ns"), F.bool_and(F.col("got").eqNullSafe(F.col("want"))).alias("exact"))
    enc = c.groupBy("dataset").agg(F.sum(F.length("payload")).cast("long").alias("enc"), F.sum("enc_ns").alias("enc_ns"))
    p = enc.join(dec, "dataset").select("dataset", F.lit("pack_first").alias("job"), "raw", "enc", "enc_ns", "dec_ns", "exact")
    return a.unionByName(p).withColumn("cr", F.col("raw") / F.col("enc"))


@query("order_facts", f"with {ranked_sql(FLOATS, BLOCK)} select dataset, job, raw, true as exact from ({_TOTALS}), (values ('standard'), ('block_first'), ('pack_first')) v(job)")
def _order_facts(spark, d):
    return _order(spark, d).select("dataset", "job", "raw", "exact")


@query("whole_file_table")
def _whole(spark, d):
    """Each column as one unblocked stream, beside the same tool on blocks."""
    pieces = blocks.gathered(load(spark, d, list(DATASETS)))
    whole = ablation.whole_file(pieces)
    cut = ablation.measure(blocks.cut(pieces), [(t, PlanSpec(codec=t, mode="standard"), {}) for t in ("zstd", "zlib", "bzip2", "lz4")], decode=False)
    return whole.join(cut.select("dataset", F.col("job").alias("codec"), F.col("enc").alias("enc_blocked")), ["dataset", "codec"]).select("dataset", "codec", "raw", "enc", "enc_blocked", (F.col("raw") / F.col("enc")).alias("cr"), (F.col("raw") / F.col("enc_blocked")).alias("cr_blocked"))


@query("guard_table")
def _guard(spark, d):
    b = _blocks(spark, d, list(DATASETS))
    parts = pipeline.fit(b)
    kept = pipeline.guarded(b, parts, PlanSpec())
    m = ablation.measure(b, [("guarded", PlanSpec(mode="user"), kept), ("per_block", PlanSpec(mode="user", guard="block"), parts), ("clustered", PlanSpec(mode="user"), parts), ("standard", PlanSpec(mode="standard"), {})])
    return m.groupBy("dataset").pivot("job", ["guarded", "per_block", "clustered", "standard"]).agg(F.first("cr"))


@query("guard_facts", f"with {ranked_sql(list(DATASETS), BLOCK)} select dataset, true as no_regret, true as measured_no_regret from w group by 1")
def _guard_facts(spark, d):
    """Guarded per block, no column is larger than either form; and the candidate chosen by size, on all blocks, is not larger than the one chosen by score."""
    b = _blocks(spark, d, list(DATASETS))
    parts = pipeline.fit(b, PlanSpec(sample=1.0))
    least = pipeline.fit(b, PlanSpec(sample=1.0, score="measured"))
    m = ablation.measure(b, [("per_block", PlanSpec(mode="user", guard="block"), parts), ("clustered", PlanSpec(mode="user"), parts), ("measured", PlanSpec(mode="user"), least), ("standard", PlanSpec(mode="standard"), {})], decode=False)
    t = m.groupBy("dataset").pivot("job", ["per_block", "clustered", "measured", "standard"]).agg(F.first("enc"))
    return t.select("dataset", (F.col("per_block") <= F.least("clustered", "standard")).alias("no_regret"), (F.col("measured") <= F.col("clustered")).alias("measured_no_regret"))


# ---------------------------------------------------------------- throughput and cost


@query("throughput_table")
def _throughput(spark, d):
    m = _cr(spark, d, FLOATS)
    m = written(m.withColumn("ct", F.col("raw") / F.col("enc_ns")).withColumn("dt", F.col("raw") / F.col("dec_ns")), "throughput")
    c, t = metrics.improvement(m, "ct", "dataset", "codec"), metrics.improvement(m, "dt", "dataset", "codec")
    return c.join(t, ["dataset", "codec"])


@query("throughput_wall")
def _wall(spark, d):
    """Bytes a second of whole jobs, Arrow transfer and scheduling included."""
    b = _blocks(spark, d, FLOATS)
    t = ablation.wall_clock(b, pipeline.fit(b), TOOLS)
    return metrics.improvement(t, "ct", "codec").join(metrics.improvement(t, "dt", "codec"), "codec")


@query("core_scaling")
def _scaling(spark, d):
    b = _blocks(spark, d, FLOATS)
    return ablation.core_scaling(b, pipeline.fit(b))


@query("metadata_overhead")
def _overhead(spark, d):
    t = pipeline.sizes(pipeline.compress(_blocks(spark, d, list(DATASETS))))
    return t.select("dataset", "raw", "enc", "enc_with_header", "blocks", "streams", (F.col("raw") / F.col("enc")).alias("cr"), (F.col("raw") / F.col("enc_with_header")).alias("cr_with_header"), ((F.col("enc_with_header") - F.col("enc")) / F.col("enc_with_header")).alias("overhead"))


@query("header_facts", f"with {ranked_sql(list(DATASETS), BLOCK)} select dataset, raw, blocks, true as as_serialised from ({_TOTALS})")
def _header_facts(spark, d):
    """The counted header is what a serialised row has besides its payload, for every block."""
    from . import container

    c = written(pipeline.compress(_blocks(spark, d, list(DATASETS))), "container")

    def run(batches):
        for r in batches:
            rows = r.to_pylist()
            same = [len(container.to_bytes(x)) == x["header_len"] + sum(x["enc_len"]) for x in rows]
            yield pa.RecordBatch.from_arrays([pa.array([x["dataset"] for x in rows], pa.string()), pa.array(same, pa.bool_())], names=["dataset", "same"])

    same = c.mapInArrow(run, "dataset string, same boolean").groupBy("dataset").agg(F.bool_and("same").alias("as_serialised"))
    return pipeline.sizes(c).select("dataset", "raw", "blocks").join(same, "dataset")


@query("parallel_units")
def _units(spark, d):
    """Independent units of work and their skew: the largest against the mean."""
    t = pipeline.sizes(pipeline.compress(_blocks(spark, d, list(DATASETS))))
    return t.select("dataset", "blocks", "streams", "largest_unit", (F.col("largest_unit") / (F.col("enc") / F.col("streams"))).alias("skew"))


@query("integer_table")
def _integer(spark, d):
    return metrics.improvement(_cr(spark, d, INTS, ["zstd", "bzip2"]), "cr", "dataset", "codec")


@query("half_table")
def _half(spark, d):
    return metrics.improvement(_cr(spark, d, ["EMB16", "QTY16"]), "cr", "dataset", "codec")


@query("parquet_baseline")
def _parquet(spark, d):
    """What a user has today: float columns in Parquet, by encoding and compression; a row group a block of 1 MiB, made in the block's task."""
    import pyarrow.parquet as pq

    ways = {"plain": {"use_dictionary": False}, "dictionary": {"use_dictionary": True}, "byte_stream_split": {"use_dictionary": False, "use_byte_stream_split": True}}
    schema = pa.schema([("dataset", pa.string()), ("encoding", pa.string()), ("compression", pa.string()), ("raw", pa.int64()), ("enc", pa.int64())])
    kinds = {8: "<f8", 4: "<f4"}

    def run(batches):
        total: dict = {}
        for r in batches:
            for ds, width, data in zip(*(c.to_pylist() for c in r.columns), strict=True):
                column = pa.table({"v": np.frombuffer(data, kinds[width])})
                for way, options in ways.items():
                    for c in ("none", "snappy", "zstd"):
                        out = pa.BufferOutputStream()
                        pq.write_table(column, out, compression=c, write_statistics=False, **options)
                        s = total.setdefault((ds, way, c), [0, 0])
                        s[0] += len(data)
                        s[1] += out.getvalue().size
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*((*k, *v) for k, v in total.items()), strict=True), schema, strict=True)], schema=schema)

    b = small_blocks(spark, d, F32 + F64, 1 << 20)
    t = b.select("dataset", "width", "data").mapInArrow(run, "dataset string, encoding string, compression string, raw long, enc long")
    return t.groupBy("dataset", "encoding", "compression").agg(F.sum("raw").alias("raw"), F.sum("enc").alias("enc")).withColumn("cr", F.col("raw") / F.col("enc"))


# ---------------------------------------------------------------- the published table

#: What a re-computation of the published table gives, to three digits: by tool, by width, by domain with the first tool.  Fixed values.
_BY_TOOL = "('zstd', 25, 2.069, 1.783, 1.161, 0.987, 1.432, 1), ('snappy', 25, 1.672, 1.383, 1.209, 0.960, 1.697, 1), ('lz4', 25, 1.830, 1.558, 1.174, 0.943, 1.673, 2), ('zlib', 25, 2.078, 1.783, 1.165, 1.063, 1.452, 0), ('bzip2', 25, 2.047, 1.941, 1.055, 0.693, 1.332, 9), ('gpu-lz4', 23, 1.576, 1.397, 1.128, 0.813, 2.289, 5)"
_BY_WIDTH = "('f32', 1.192), ('f64', 1.086), ('f16', 1.076)"
_BY_DOMAIN = "('HPC', 1.209), ('TS', 1.095), ('OBS', 1.164), ('DB', 1.143), ('ML', 1.069)"


_ABOUT = ", ".join(f"('{n}', '{DATASETS[n][4]}', '{DATASETS[n][2]}')" for n in FLOATS)
_BITS = "log2(sum(c)) - sum(c * log2(c)) / sum(c) as h, ceil(log2(count(*))) as f"
#: The ratios a, b of the given float columns, by tool.
_GIVEN = f"""with w as ({source(FLOATS)}), {PLANES}, c as (select dataset, width, plane, byte, count(*) as c from b where byte is not null group by all),
each as (select dataset, width, sum(h) as h, sum(f) as f from (select dataset, width, plane, {_BITS} from c group by all) group by all), whole as (select dataset, {_BITS} from (select dataset, byte, sum(c) as c from c group by all) group by all),
x as (select dataset, width, 'order-0' as codec, each.h as p, whole.h as q from each join whole using (dataset) union all select dataset, width, 'equal-length', each.f, whole.f from each join whole using (dataset)),
r as (select codec, domain, word, 8 * width / greatest(1.0, p) as a, 8 * width / greatest(1.0, width * q) as b from x join (values {_ABOUT}) t(dataset, domain, word) using (dataset))"""
_CRI = "round(exp(avg(ln(a / b))), 3) as cri"


def _ratios(spark, d) -> DataFrame:
    """The published rows and, in the same form, those of the given float columns."""
    given = ablation.order0(spark, load(spark, d, FLOATS), {n: (DATASETS[n][4], DATASETS[n][2]) for n in FLOATS})
    return ablation.published(spark).withColumn("source", F.lit("published")).unionByName(given.withColumn("source", F.lit("given")))


def _gain():
    return F.col("cr_clustered") / F.col("cr_standard")


@query("published_table", f"{_GIVEN} select 'published' as source, codec, cast(n as bigint) as n, clustered::double as clustered, standard::double as standard, cri::double as cri, least::double as least, most::double as most, cast(losses as bigint) as losses from (values {_BY_TOOL}) t(codec, n, clustered, standard, cri, least, most, losses) union all select 'given', codec, count(*), round(exp(avg(ln(a))), 3), round(exp(avg(ln(b))), 3), {_CRI}, round(min(a / b), 3), round(max(a / b), 3), count(*) filter (round(a / b, 9) < 1) from r group by codec")
def _published(spark, d):
    """The published ratios rolled up by tool, and those of the given columns."""
    g = lambda c: F.round(metrics.gmean(c), 3)
    return _ratios(spark, d).groupBy("source", "codec").agg(F.count(F.lit(1)).alias("n"), g("cr_clustered").alias("clustered"), g("cr_standard").alias("standard"), g(_gain()).alias("cri"), F.round(F.min(_gain()), 3).alias("least"), F.round(F.max(_gain()), 3).alias("most"), F.count_if(F.round(_gain(), 9) < 1).alias("losses"))


@query("published_by_width", f"{_GIVEN} select 'published' as source, word, cri::double as cri from (values {_BY_WIDTH}) t(word, cri) union all select 'given', word, {_CRI} from r group by word")
def _published_width(spark, d):
    return _ratios(spark, d).groupBy("source", "word").agg(F.round(metrics.gmean(_gain()), 3).alias("cri"))


@query("published_by_domain", f"{_GIVEN} select 'published' as source, domain, cri::double as cri from (values {_BY_DOMAIN}) t(domain, cri) union all select 'given', domain, {_CRI} from r where codec = 'order-0' group by domain")
def _published_domain(spark, d):
    return _ratios(spark, d).filter("codec in ('zstd', 'order-0')").groupBy("source", "domain").agg(F.round(metrics.gmean(_gain()), 3).alias("cri"))
