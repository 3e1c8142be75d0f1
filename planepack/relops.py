"""Relational operators around the methods: scans, joins, aggregates, windows, sets, functions.  ``RELOPS``: name -> (query, oracle SQL)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .fixtures import table
from .storage import fresh, written

RELOPS: dict[str, tuple[Callable, str | None]] = {}


def _op(sql: str | None):
    def keep(f):
        RELOPS[f.__name__.strip("_")] = (f, sql)
        return f

    return keep


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, order: str, value: str) -> DataFrame:
    """Last earlier-or-equal row of ``right`` by key: one union, one sort, no range join; right rows come first on ties."""
    u = left.select(by, ts, F.col(order).alias("o"), F.lit(1).alias("side"), F.lit(None).cast("double").alias("v")).unionByName(right.select(by, ts, F.lit(None).cast("long").alias("o"), F.lit(0).alias("side"), F.col(value).alias("v")))
    w = Window.partitionBy(by).orderBy(ts, "side").rowsBetween(Window.unboundedPreceding, 0)
    return u.withColumn("last", F.last("v", ignorenulls=True).over(w)).filter("side = 1").select(by, F.col("o").alias(order), "last")


def range_join(points: DataFrame, ranges: DataFrame, x: str, lo: str, hi: str, bin_size: float) -> DataFrame:
    """lo <= x < hi by equi-joined bins and a residual filter; no nested loop."""
    b = F.floor(F.col(x) / bin_size)
    r = ranges.withColumn("__b", F.explode(F.sequence(F.floor(F.col(lo) / bin_size), F.floor(F.col(hi) / bin_size))))
    return points.withColumn("__b", b).join(r, "__b").filter((F.col(x) >= F.col(lo)) & (F.col(x) < F.col(hi))).drop("__b")


@_op("select l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice from lineitem where l_quantity between 10 and 12 and l_returnflag in ('A', 'N') and l_discount > 0.05")
def scan_filter(spark, d):
    t = table(spark, d, "lineitem").filter("l_quantity between 10 and 12 and l_returnflag in ('A', 'N') and l_discount > 0.05")
    return t.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")


def _round_trip(spark, d, fmt):
    t = table(spark, d, "orders", "o_orderkey", "o_totalprice", "o_orderstatus")
    path = fresh(spark, fmt)
    t.write.format(fmt).save(path)
    return spark.read.format(fmt).schema(t.schema).load(path)


for _fmt in ("csv", "json", "orc"):
    RELOPS[f"scan_{_fmt}_roundtrip"] = (lambda spark, d, f=_fmt: _round_trip(spark, d, f), "select o_orderkey, o_totalprice, o_orderstatus from orders")


@_op("select p_partkey, concat_ws('|', p_partkey, p_brand, p_size) as line from part")
def scan_text_roundtrip(spark, d):
    """Lines of text; the key is parsed back out of each."""
    path = fresh(spark, "text")
    table(spark, d, "part").select(F.concat_ws("|", "p_partkey", "p_brand", "p_size").alias("value")).write.text(path)
    return spark.read.text(path).select(F.split("value", r"\|")[0].cast("long").alias("p_partkey"), F.col("value").alias("line"))


@_op("select count(*) as n from lineitem")
def sink_noop(spark, d):
    """The sink of the timings: everything is computed and nothing kept; rows are counted on the way by an observation."""
    from pyspark.sql import Observation

    seen = Observation()
    table(spark, d, "lineitem").observe(seen, F.count(F.lit(1)).alias("n")).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["n"],)], "n long")


@_op("select event_id from events where event_type like 'p%' and not (user_id between 100 and 200) and props is distinct from '{\"k\": 1}' and regexp_matches(event_type, '^[a-z]+$')")
def filter_predicates(spark, d):
    e = table(spark, d, "events", "event_id", "event_type", "user_id", "props")
    return e.filter(F.col("event_type").like("p%") & ~F.col("user_id").between(100, 200) & ~F.col("props").eqNullSafe('{"k": 1}') & F.col("event_type").rlike("^[a-z]+$")).select("event_id")


_SPECIAL = "case when event_id % 11 = 0 then 'NaN'::double when event_id % 11 = 1 then 'Infinity'::double when event_id % 11 = 2 then '-Infinity'::double when event_id % 11 = 3 then -0.0::double when event_id % 11 = 4 then 0.0::double when event_id % 11 = 5 then null else value end"


@_op(f"with s as (select event_id, {_SPECIAL} as v, case when event_id % 11 = 3 then true else false end as neg from events) select count(*) filter (where isnan(v)) as nans, count(*) filter (where isinf(v) and v > 0) as pos, count(*) filter (where isinf(v) and v < 0) as negs, count(*) filter (where neg) as minus_zeros, count(*) filter (where v = 0 and not neg) as zeros, count(*) filter (where v is null) as nulls from s")
def filter_special_values(spark, d):
    """NaN, infinities and the two zeros, the zeros told apart by their bits."""
    from .words import word_bits

    r, inf = F.col("event_id") % 11, float("inf")
    v = F.when(r == 0, F.lit(float("nan"))).when(r == 1, F.lit(inf)).when(r == 2, F.lit(-inf)).when(r == 3, F.lit(-0.0)).when(r == 4, F.lit(0.0)).when(r == 5, F.lit(None)).otherwise(F.col("value"))
    t = table(spark, d, "events", "event_id", "value").select(v.cast("double").alias("v")).withColumn("bits", word_bits(F.col("v"), "f64"))
    c = F.count_if
    return t.agg(c(F.isnan("v")).alias("nans"), c(F.col("v") == inf).alias("pos"), c(F.col("v") == -inf).alias("negs"), c(F.col("bits") == -(1 << 63)).alias("minus_zeros"), c((F.col("v") == 0) & (F.col("bits") == 0)).alias("zeros"), c(F.col("v").isNull()).alias("nulls"))


@_op("select c_custkey, case when c_acctbal < 0 then 'debt' when c_acctbal < 1000 then 'low' else 'fine' end as band, coalesce(nullif(c_nationkey, 0), -1) as nation, greatest(c_acctbal, 0.0) as owed, least(c_acctbal, 100.0) as capped from customer")
def fn_conditional(spark, d):
    b = F.col("c_acctbal")
    return table(spark, d, "customer").select("c_custkey", F.when(b < 0, "debt").when(b < 1000, "low").otherwise("fine").alias("band"), F.coalesce(F.nullif(F.col("c_nationkey"), F.lit(0)), F.lit(-1)).alias("nation"), F.greatest(b, F.lit(0.0)).alias("owed"), F.least(b, F.lit(100.0)).alias("capped"))


@_op("select distinct l_partkey, l_suppkey from lineitem")
def drop_duplicates(spark, d):
    return table(spark, d, "lineitem", "l_partkey", "l_suppkey").dropDuplicates(["l_partkey", "l_suppkey"])


@_op("select o_orderpriority, count(*) as n, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from orders join lineitem on o_orderkey = l_orderkey group by 1")
def join_inner(spark, d):
    j = table(spark, d, "orders", "o_orderkey", "o_orderpriority").join(table(spark, d, "lineitem", "l_orderkey", "l_extendedprice", "l_discount"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.expr("l_extendedprice * (1 - l_discount)")), 2).alias("revenue"))


@_op("select r_name, count(*) as n, round(sum(c_acctbal), 2) as balance from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1")
def join_broadcast(spark, d):
    j = table(spark, d, "customer", "c_nationkey", "c_acctbal").join(F.broadcast(table(spark, d, "nation")), F.expr("c_nationkey = n_nationkey")).join(F.broadcast(table(spark, d, "region")), F.expr("n_regionkey = r_regionkey"))
    return j.groupBy("r_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


_KEYS_SQL = "(select distinct l_orderkey from lineitem)"
for _how, _sql in (("left", "left join"), ("right", "right join"), ("full", "full join"), ("left_semi", "semi join"), ("left_anti", "anti join")):
    _cols = "o_orderkey" if "_" in _how else "o_orderkey, l_orderkey"
    RELOPS[f"join_{_how}"] = (
        lambda spark, d, how=_how: table(spark, d, "orders", "o_orderkey").join(table(spark, d, "lineitem", "l_orderkey").distinct(), F.expr("o_orderkey = l_orderkey"), how),
        f"select {_cols} from (select o_orderkey from orders) o {_sql} {_KEYS_SQL} l on o_orderkey = l_orderkey",
    )


@_op("select user_id, event_id, last(value) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as last from events")
def join_asof(spark, d):
    e = table(spark, d, "events", "user_id", "event_id", "ts", "value")
    return asof_join(e, e, "user_id", "ts", "event_id", "value")


@_op("select event_id, lo from events join (select i * 10.0 as lo, i * 10.0 + 10.0 as hi from range(0, 60) t(i)) on value >= lo and value < hi")
def join_range(spark, d):
    r = spark.range(60).select((F.col("id") * 10.0).alias("lo"), (F.col("id") * 10.0 + 10.0).alias("hi"))
    return range_join(table(spark, d, "events", "event_id", "value"), r, "value", "lo", "hi", 25.0).select("event_id", "lo")


@_op("select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_id < b.event_id and epoch_us(b.ts) - epoch_us(a.ts) <= 3600000000")
def join_interval(spark, d):
    e = table(spark, d, "events", "user_id", "event_id", "ts").withColumn("us", F.expr("unix_micros(to_timestamp(ts))"))
    hour = 3_600_000_000
    a = e.select("user_id", F.col("event_id").alias("a"), F.col("us").alias("ua"), F.explode(F.array(F.expr(f"us div {hour}"), F.expr(f"us div {hour} + 1"))).alias("bin"))
    b = e.select("user_id", F.col("event_id").alias("b"), F.col("us").alias("ub"), F.expr(f"us div {hour}").alias("bin"))
    return a.join(b, ["user_id", "bin"]).filter(f"a < b and ub - ua <= {hour}").select("a", "b")


@_op("select n_name, r_name from nation, region where n_regionkey <> r_regionkey")
def join_cross(spark, d):
    """Every pair of two tables that are fixed and tiny, with a residual condition."""
    return table(spark, d, "nation").crossJoin(F.broadcast(table(spark, d, "region"))).filter("n_regionkey <> r_regionkey").select("n_name", "r_name")


@_op("select p_partkey, i as plane, cast((p_partkey >> cast(8 * (7 - i) as integer)) & 255 as integer) as byte from part, (select cast(unnest(range(0, 8)) as integer) as i)")
def join_lateral(spark, d):
    """A row of the left side feeds a table function."""
    from . import functions

    functions.register(spark)
    table(spark, d, "part", "p_partkey").createOrReplaceTempView("pp_part")
    return spark.sql("select p_partkey, t.plane, t.byte from pp_part, lateral pp_planes(p_partkey, 8) t")


@_op("select l_returnflag, l_linestatus, sum(l_quantity) as q, round(avg(l_extendedprice), 4) as p, count(*) as n, min(l_tax) as lo, max(l_tax) as hi from lineitem group by 1, 2")
def agg_hash(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("q"), F.round(F.avg("l_extendedprice"), 4).alias("p"), F.count(F.lit(1)).alias("n"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"))


@_op("select round(var_samp(value), 4) as vs, round(var_pop(value), 4) as vp, round(stddev_samp(value), 5) as ss, round(corr(value, user_id), 5) as c, round(covar_pop(value, user_id), 3) as cp, round(regr_slope(value, user_id), 7) as slope from events")
def agg_moments(spark, d):
    r = lambda e, k: F.round(F.expr(e), k)
    return table(spark, d, "events").agg(r("var_samp(value)", 4).alias("vs"), r("var_pop(value)", 4).alias("vp"), r("stddev_samp(value)", 5).alias("ss"), r("corr(value, user_id)", 5).alias("c"), r("covar_pop(value, user_id)", 3).alias("cp"), r("regr_slope(value, user_id)", 7).alias("slope"))


@_op("select event_type, round(quantile_cont(value, 0.25), 6) as q1, round(quantile_cont(value, 0.5), 6) as q2, round(quantile_cont(value, 0.75), 6) as q3 from events group by 1")
def agg_quantiles(spark, d):
    q = lambda p: F.round(F.percentile("value", F.lit(p)), 6)
    return table(spark, d, "events").groupBy("event_type").agg(q(0.25).alias("q1"), q(0.5).alias("q2"), q(0.75).alias("q3"))


@_op("select count(distinct l_partkey) as parts, count(distinct l_suppkey) as supps, count(*) filter (where l_tax = 0) as untaxed from lineitem")
def agg_distinct(spark, d):
    return table(spark, d, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("supps"), F.count_if(F.col("l_tax") == 0).alias("untaxed"))


@_op("select (select count(distinct l_partkey) from lineitem) as parts, true as near, true as sketch_near")
def agg_distinct_approximate(spark, d):
    """The exact count, and whether the approximate one and a merged sketch stay within 5 %."""
    t = table(spark, d, "lineitem", "l_partkey", "l_returnflag")
    sketch = t.groupBy("l_returnflag").agg(F.hll_sketch_agg("l_partkey", 14).alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("e"))
    one = t.agg(F.count_distinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.01).alias("a")).crossJoin(sketch)  # one row each
    near = lambda c: F.abs(F.col(c) - F.col("parts")) <= 0.05 * F.col("parts")
    return one.select("parts", near("a").alias("near"), near("e").alias("sketch_near"))


@_op("with m as (select event_type, value - avg(value) over (partition by event_type) as c from events) select event_type, round(avg(c ** 3) / avg(c ** 2) ** 1.5, 6) as skew, round(avg(c ** 4) / avg(c ** 2) ** 2 - 3, 6) as kurt from m group by 1")
def agg_shape(spark, d):
    """Skewness and excess kurtosis of the population."""
    return table(spark, d, "events").groupBy("event_type").agg(F.round(F.skewness("value"), 6).alias("skew"), F.round(F.kurtosis("value"), 6).alias("kurt"))


@_op("select event_type, quantile_disc(value, 0.5) as median, true as near, true as sketch_near from events group by 1")
def agg_quantiles_approximate(spark, d):
    """The exact lower median, and whether the approximate one and a sketch lie between the 48 % and 52 % quantiles."""
    q = lambda p: F.percentile("value", F.lit(p))
    t = table(spark, d, "events").groupBy("event_type").agg(F.expr("percentile_disc(0.5) within group (order by value)").alias("median"), q(0.48).alias("lo"), q(0.52).alias("hi"), F.approx_percentile("value", 0.5, F.lit(10000)).alias("a"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value, 800), 0.5)").alias("k"))
    return t.select("event_type", "median", F.col("a").between(F.col("lo"), F.col("hi")).alias("near"), F.col("k").between(F.col("lo"), F.col("hi")).alias("sketch_near"))


@_op("select o_orderpriority, (select max(n) from (select count(*) as n from orders i where i.o_orderpriority = o.o_orderpriority group by o_orderstatus)) as most from (select distinct o_orderpriority from orders) o")
def agg_mode(spark, d):
    """How often the commonest status occurs."""
    t = table(spark, d, "orders")
    top = t.groupBy("o_orderpriority").agg(F.mode("o_orderstatus").alias("m"))
    return t.join(F.broadcast(top), "o_orderpriority").filter("o_orderstatus = m").groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("most"))


@_op("select l_returnflag, l_linestatus, l_linenumber, count(*) as n, cast(grouping_id(l_returnflag, l_linestatus, l_linenumber) as bigint) as gid from lineitem group by grouping sets ((l_returnflag, l_linestatus), (l_linenumber), ())")
def agg_grouping_sets(spark, d):
    t = table(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_linenumber")
    f, s, n = F.col("l_returnflag"), F.col("l_linestatus"), F.col("l_linenumber")
    return t.groupingSets([(f, s), (n,), ()], f, s, n).agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("gid"))


@_op("select p_partkey, name, value from (unpivot (select p_partkey, cast(p_size as double) as p_size, p_retailprice from part) on p_size, p_retailprice into name name value value)")
def agg_unpivot(spark, d):
    t = table(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return t.unpivot("p_partkey", ["p_size", "p_retailprice"], "name", "value")


@_op("select least(greatest(cast(floor((value - 0) / 50) as bigint) + 1, 0), 11) as bucket, count(*) as n from events group by 1")
def agg_width_bucket(spark, d):
    """An equal-width histogram with open ends."""
    return table(spark, d, "events", "value").groupBy(F.width_bucket("value", F.lit(0.0), F.lit(500.0), F.lit(10).cast("long")).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@_op("select count(*) as n, 20 as bins from events")
def agg_histogram_numeric(spark, d):
    """A histogram whose bins follow the data: their heights add up to all rows."""
    t = table(spark, d, "events", "value").agg(F.histogram_numeric("value", F.lit(20)).alias("h"))
    return t.select(F.round(F.aggregate("h", F.lit(0.0), lambda a, x: a + x["y"])).cast("long").alias("n"), F.size("h").alias("bins"))


@_op("select event_type, count(*) as n, true as never_below, true as near from events group by 1")
def agg_count_min(spark, d):
    """Exact counts, and that a count-min sketch of the whole column never falls below them nor exceeds them by 1 % of all rows."""
    e = table(spark, d, "events", "event_type")
    sketch = bytes(e.agg(F.count_min_sketch("event_type", F.lit(0.001), F.lit(0.99), F.lit(7)).alias("s")).first().s)
    total = e.count()
    jvm = spark._jvm
    held = jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(jvm.java.io.ByteArrayInputStream(sketch))
    rows = [(r.event_type, r.n, held.estimateCount(r.event_type)) for r in e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n")).collect()]  # a row a type
    return spark.createDataFrame([(t, n, c >= n, c <= n + 0.01 * total) for t, n, c in rows], "event_type string, n long, never_below boolean, near boolean")


#: Prices are whole cents: exact decimal sums, as sums of doubles depend on the order of rows and can round either way.
_CUBE = "select {k} from orders group by {g}(o_orderstatus, o_orderpriority)"
for _g in ("cube", "rollup"):
    RELOPS[f"agg_{_g}"] = (
        lambda spark, d, g=_g: getattr(table(spark, d, "orders"), g)("o_orderstatus", "o_orderpriority").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total"), F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("gid")),
        _CUBE.format(k="o_orderstatus, o_orderpriority, cast(sum(cast(o_totalprice as decimal(18, 2))) as double) as total, count(*) as n, cast(grouping_id(o_orderstatus, o_orderpriority) as bigint) as gid", g=_g),
    )


@_op("select o_orderpriority, count(*) filter (where o_orderstatus = 'F') as f, count(*) filter (where o_orderstatus = 'O') as o, count(*) filter (where o_orderstatus = 'P') as p from orders group by 1")
def agg_pivot(spark, d):
    t = table(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count()
    return t.select("o_orderpriority", *(F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "FOP"))


@_op("select event_type, arg_max(event_id, value) as top, arg_min(event_id, value) as low, bool_or(value > 500) as big from events group by 1")
def agg_best_by(spark, d):
    """Of events with equal values the first, by its number, is the best; rows without a value or number take no part in it."""
    e = table(spark, d, "events", "event_type", "event_id", "value")
    held = F.col("value").isNotNull() & F.col("event_id").isNotNull()
    best = lambda f, tie: f("event_id", F.when(held, F.struct("value", tie)))
    return e.groupBy("event_type").agg(best(F.max_by, -F.col("event_id")).alias("top"), best(F.min_by, F.col("event_id")).alias("low"), F.bool_or(F.col("value") > 500).alias("big"))


@_op("select bit_or(l_orderkey) as o, bit_and(l_orderkey) as a, bit_xor(l_orderkey) as x, bit_or(l_orderkey) & ~bit_and(l_orderkey) as varying from lineitem")
def agg_varying_bits(spark, d):
    return table(spark, d, "lineitem", "l_orderkey").agg(F.bit_or("l_orderkey").alias("o"), F.bit_and("l_orderkey").alias("a"), F.bit_xor("l_orderkey").alias("x")).withColumn("varying", F.expr("o & ~a"))


_WIN = "select event_id, row_number() over w as rn, cast(rank() over v as integer) as rk, cast(dense_rank() over v as integer) as dr, cast(ntile(4) over w as integer) as nt, round(percent_rank() over v, 6) as pr, round(cume_dist() over v, 6) as cd from events window w as (partition by user_id order by ts, event_id), v as (partition by user_id order by event_type)"


@_op(_WIN.replace("row_number() over w", "cast(row_number() over w as integer)"))
def window_rank(spark, d):
    w, v = Window.partitionBy("user_id").orderBy("ts", "event_id"), Window.partitionBy("user_id").orderBy("event_type")
    return table(spark, d, "events").select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"))


@_op("select event_id, lag(value) over w as prev, lead(value) over w as next, first_value(value) over w as first, round(sum(value) over (partition by user_id order by ts, event_id rows between 3 preceding and current row), 4) as moving, round(sum(value) over w, 3) as running from events window w as (partition by user_id order by ts, event_id)")
def window_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select("event_id", F.lag("value").over(w).alias("prev"), F.lead("value").over(w).alias("next"), F.first_value("value").over(w).alias("first"), F.round(F.sum("value").over(w.rowsBetween(-3, 0)), 4).alias("moving"), F.round(F.sum("value").over(w), 3).alias("running"))


@_op("select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row) as day from events")
def window_time_range(spark, d):
    e = table(spark, d, "events").withColumn("us", F.expr("unix_micros(to_timestamp(ts))"))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)).alias("day"))


@_op("with g as (select user_id, event_type, row_number() over (partition by user_id order by ts, event_id) - row_number() over (partition by user_id, event_type order by ts, event_id) as island from events) select user_id, event_type, island, count(*) as run from g group by all")
def window_runs(spark, d):
    a, b = Window.partitionBy("user_id").orderBy("ts", "event_id"), Window.partitionBy("user_id", "event_type").orderBy("ts", "event_id")
    e = table(spark, d, "events").withColumn("island", (F.row_number().over(a) - F.row_number().over(b)).cast("long"))
    return e.groupBy("user_id", "event_type", "island").agg(F.count(F.lit(1)).alias("run"))


@_op("select event_id, nth_value(value, 2) over w as second, last_value(value) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as last from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)")
def window_nth(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.nth_value("value", 2).over(w).alias("second"), F.last_value("value").over(w).alias("last"))


for _name, _asc, _nulls in (("asc_first", True, "first"), ("asc_last", True, "last"), ("desc_first", False, "first"), ("desc_last", False, "last")):

    def _ordered(spark, d, asc=_asc, nulls=_nulls):
        """A global sort by ranges; the place of each row comes from its task and its place there."""
        e = table(spark, d, "events", "event_id", "value").withColumn("v", F.when(F.col("event_id") % 7 != 0, F.col("value")))
        by = getattr(F.col("v"), f"{'asc' if asc else 'desc'}_nulls_{nulls}")()
        out = written(e.orderBy(by, "event_id").select("event_id", F.monotonically_increasing_id().alias("at")), "ordered")
        out = out.withColumn("task", F.shiftright("at", 33))
        spans = out.groupBy("task").agg(F.count(F.lit(1)).alias("c"), F.min("at").alias("lo"))  # a row a task
        spans = spans.select("task", (F.sum("c").over(Window.orderBy("task")) - F.col("c") - F.col("lo")).alias("shift"))
        return out.join(F.broadcast(spans), "task").select("event_id", (F.col("at") + F.col("shift")).alias("place"))

    RELOPS[f"sort_{_name}"] = (_ordered, f"select event_id, row_number() over (order by case when event_id % 7 <> 0 then value end {'asc' if _asc else 'desc'} nulls {_nulls}, event_id) - 1 as place from events")


@_op("select user_id, event_id, value from (select *, row_number() over (partition by user_id order by value desc, event_id) as r from events) where r <= 2")
def top_k_per_group(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    return table(spark, d, "events").withColumn("r", F.row_number().over(w)).filter("r <= 2").select("user_id", "event_id", "value")


@_op("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")
def top_k_global(spark, d):
    return table(spark, d, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


for _name, _f, _sql in (
    ("union_all", lambda a, b: a.unionAll(b), "union all"), ("union_distinct", lambda a, b: a.union(b).distinct(), "union"), ("intersect", lambda a, b: a.intersect(b), "intersect"),
    ("intersect_all", lambda a, b: a.intersectAll(b), "intersect all"), ("except", lambda a, b: a.subtract(b), "except"), ("except_all", lambda a, b: a.exceptAll(b), "except all"),
):
    RELOPS[f"set_{_name}"] = (
        lambda spark, d, f=_f: f(table(spark, d, "customer").select(F.col("c_nationkey").alias("k")), table(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))),
        f"select c_nationkey as k from customer {_sql} select s_nationkey as k from supplier",
    )


@_op("select p_partkey, upper(p_brand) as u, length(p_name) as n, substr(p_name, 2, 4) as s, concat_ws('-', p_brand, p_type) as c, lpad(cast(p_size as varchar), 4, '0') as z, md5(p_name) as m, lower(hex(p_brand)) as h from part")
def fn_string(spark, d):
    return table(spark, d, "part").select("p_partkey", F.upper("p_brand").alias("u"), F.length("p_name").alias("n"), F.substring("p_name", 2, 4).alias("s"), F.concat_ws("-", "p_brand", "p_type").alias("c"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("z"), F.md5("p_name").alias("m"), F.lower(F.hex("p_brand")).alias("h"))


@_op("select o_orderkey, cast(year(o_orderdate) as integer) as y, cast(month(o_orderdate) as integer) as m, date_trunc('month', o_orderdate)::date as t, cast(o_orderdate as date) + 30 as p, epoch_us(o_orderdate) as us from orders")
def fn_date(spark, d):
    t = table(spark, d, "orders")
    return t.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_trunc("month", "o_orderdate").cast("date").alias("t"), F.date_add(F.col("o_orderdate").cast("date"), 30).alias("p"), F.expr("unix_micros(to_timestamp(o_orderdate))").alias("us"))


@_op("select event_id, cast(json_extract(props, '$.k') as bigint) as k from events")
def fn_json(spark, d):
    return table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@_op("select vec_id, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * x)), 5) as norm2, len(list_filter(embedding, lambda x: x > 0)) as positive, list_max(embedding) as top from embeddings")
def fn_array(spark, d):
    e = F.col("embedding")
    sq = F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.round(sq, 5).alias("norm2"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.array_max(e).alias("top"))


@_op("select l_orderkey, l_linenumber, l_partkey, l_suppkey, (l_orderkey << 3) & 1023 as a, xor(l_partkey, l_suppkey) as x, bit_count(l_orderkey) as bits from lineitem")
def fn_bits(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.shiftleft("l_orderkey", 3).bitwiseAND(F.lit(1023)).alias("a"), F.col("l_partkey").bitwiseXOR(F.col("l_suppkey")).alias("x"), F.bit_count("l_orderkey").alias("bits"))


@_op("select event_id, round(log2(value + 1), 6) as l2, round(ln(value + 1), 6) as l, round(exp(-value / 100), 6) as e, round(sqrt(value), 6) as s, round(power(value, 1.5), 3) as p, floor(value)::bigint as f, ceil(value)::bigint as c, sign(value - 100)::double as g, ((event_id - 5) % 7 + 7) % 7 as m, round(sin(value), 6) as si, abs(value - 100) as a from events")
def fn_math(spark, d):
    v = F.col("value")
    r = lambda c, k=6: F.round(c, k)
    return table(spark, d, "events", "event_id", "value").select("event_id", r(F.log2(v + 1)).alias("l2"), r(F.ln(v + 1)).alias("l"), r(F.exp(-v / 100)).alias("e"), r(F.sqrt(v)).alias("s"), r(F.pow(v, F.lit(1.5)), 3).alias("p"), F.floor(v).alias("f"), F.ceil(v).alias("c"), F.signum(v - 100).alias("g"), F.pmod(F.col("event_id") - 5, F.lit(7)).alias("m"), r(F.sin(v)).alias("si"), F.abs(v - 100).alias("a"))


@_op("select o_orderstatus, string_agg(o_orderpriority || '=' || n, ',' order by o_orderpriority) as counts, max(n) as most, count(*) filter (where n > 50) as common from (select o_orderstatus, o_orderpriority, count(*) as n from orders group by 1, 2) group by 1")
def fn_map(spark, d):
    """Counts per status as a map: built, filtered, transformed and read back."""
    t = table(spark, d, "orders").groupBy("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))
    t = t.groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m"))
    text = F.transform_values("m", lambda k, v: F.concat(k, F.lit("="), v.cast("string")))
    keys = F.array_sort(F.map_keys("m"))
    return t.select("o_orderstatus", F.concat_ws(",", F.transform(keys, lambda k: F.element_at(text, k))).alias("counts"), F.array_max(F.map_values("m")).alias("most"), F.size(F.map_filter("m", lambda k, v: v > 50)).cast("long").alias("common"))


@_op("select event_id, cast(json_extract(props, '$.k') as bigint) as k, cast(json_extract(props, '$.k') as bigint) as t, cast(json_extract(props, '$.k') as bigint) as v, '{\"id\":' || event_id || ',\"type\":\"' || event_type || '\"}' as j from events")
def fn_json_parse(spark, d):
    """One key by a schema, by a tuple and by a variant; and a row as JSON."""
    e = table(spark, d, "events", "event_id", "event_type", "props")
    kind = F.schema_of_json(F.lit('{"k": 1}'))
    e = e.select("event_id", "event_type", "props", F.json_tuple("props", "k").alias("t"))
    return e.select("event_id", F.from_json("props", kind)["k"].alias("k"), F.col("t").cast("long").alias("t"), F.variant_get(F.parse_json("props"), "$.k", "long").alias("v"), F.to_json(F.struct(F.col("event_id").alias("id"), F.col("event_type").alias("type"))).alias("j"))


@_op("select p_partkey, p_size + 1 as size, upper(p_brand) as brand, p_retailprice as price from part")
def fn_struct(spark, d):
    """Nested rows: built, a field replaced, one dropped, one renamed."""
    s = F.named_struct(F.lit("size"), F.col("p_size"), F.lit("brand"), F.col("p_brand"), F.lit("kind"), F.col("p_type"), F.lit("price"), F.col("p_retailprice"))
    t = table(spark, d, "part").select("p_partkey", s.alias("s"))
    t = t.withColumn("s", F.col("s").withField("size", F.col("s.size") + 1).dropFields("kind"))
    return t.select("p_partkey", "s.size", F.upper("s.brand").alias("brand"), "s.price")


@_op("select count(*) as n, true as uniform, true as repeatable, true as by_key from events")
def fn_random(spark, d):
    """Seeded draws: uniform to 5 %, equal when drawn again, and those by key independent of the layout."""
    by_key = F.pmod(F.xxhash64("event_id", F.lit(7)), F.lit(1000)) / 1000.0
    e = table(spark, d, "events", "event_id").select("event_id", F.rand(7).alias("u"), by_key.alias("k"))
    one = e.agg(F.count(F.lit(1)).alias("n"), F.avg("u").alias("a"), F.avg("k").alias("k"))
    two = e.agg(F.avg("u").alias("a2"))
    spread = e.repartition(5).agg(F.avg("k").alias("k2"))
    t = one.crossJoin(two).crossJoin(spread)  # one row each
    return t.select("n", (F.abs(F.col("a") - 0.5) < 0.05).alias("uniform"), (F.abs(F.col("a") - F.col("a2")) < 1e-9).alias("repeatable"), (F.abs(F.col("k") - F.col("k2")) < 1e-9).alias("by_key"))
