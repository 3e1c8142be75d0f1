"""The dataset registry: numeric columns of the given tables with an explicit, unique order."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .words import TYPES, word_bits

_LINE = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "unix_micros(to_timestamp(l_shipdate))")
#: name: (table, value expression, word type, order expressions, application)
DATASETS: dict[str, tuple] = {}


def _add(name, tbl, value, word, order, app):
    DATASETS[name] = (tbl, value, word, order if isinstance(order, tuple) else (order,), app)


for _short, _tbl, _col, _order in (
    ("extprice", "lineitem", "l_extendedprice", _LINE), ("qty", "lineitem", "l_quantity", _LINE), ("disc", "lineitem", "l_discount", _LINE), ("tax", "lineitem", "l_tax", _LINE),
    ("total", "orders", "o_totalprice", "o_orderkey"), ("acct", "customer", "c_acctbal", "c_custkey"), ("retail", "part", "p_retailprice", "p_partkey"),
):
    _add(f"DB64-{_short}", _tbl, _col, "f64", _order, "DB")
    _add(f"DB32-{_short}", _tbl, _col, "f32", _order, "DB")
_add("TS64-value", "events", "value", "f64", "event_id", "TS")
_add("TS32-value", "events", "value", "f32", "event_id", "TS")
_add("TS64-user", "events", "value", "f64", ("user_id", "unix_micros(to_timestamp(ts))", "event_id"), "TS")
_add("EMB32-row", "embeddings", "x", "f32", ("vec_id", "dim"), "EMB")
_add("EMB32-dim", "embeddings", "x", "f32", ("dim", "vec_id"), "EMB")
_add("EMB16", "embeddings", "x", "f16", ("vec_id", "dim"), "EMB")
_add("QTY16", "lineitem", "l_quantity", "f16", _LINE, "DB")
_add("INT32-line", "lineitem", "l_linenumber", "i32", _LINE, "INT")
_add("INT32-size", "part", "p_size", "i32", "p_partkey", "INT")
_add("INT32-nation", "customer", "c_nationkey", "i32", "c_custkey", "INT")
_add("INT64-okey", "lineitem", "l_orderkey", "i64", _LINE, "INT")
_add("INT64-pkey", "lineitem", "l_partkey", "i64", _LINE, "INT")
_add("INT64-user", "events", "user_id", "i64", "event_id", "INT")
_add("INT64-chars", "documents", "n_chars", "i64", "doc_id", "INT")
_add("INT64-ts", "events", "unix_micros(to_timestamp(ts))", "i64", "event_id", "INT")
_add("INT64-ship", "lineitem", "unix_micros(to_timestamp(l_shipdate))", "i64", _LINE, "INT")
_add("INT64-odate", "orders", "unix_micros(to_timestamp(o_orderdate))", "i64", "o_orderkey", "INT")

FLOATS = [n for n, d in DATASETS.items() if d[2][0] == "f"]
F32 = [n for n, d in DATASETS.items() if d[2] == "f32"]
F64 = [n for n, d in DATASETS.items() if d[2] == "f64"]
INTS = [n for n, d in DATASETS.items() if d[2][0] == "i"]
#: One of each kind, for the narrower studies.
CORE = ["DB64-extprice", "DB32-extprice", "DB32-qty", "TS64-value", "TS32-value", "EMB32-row"]
KEYS = 5


def width_of(name: str) -> int:
    return TYPES[DATASETS[name][2]][0]


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def _rows(df: DataFrame, tbl: str) -> DataFrame:
    return df.select("vec_id", F.posexplode("embedding").alias("dim", "x")) if tbl == "embeddings" else df


def _value(name: str):
    kind = {"f64": "double", "f32": "float", "f16": "float", "i64": "long", "i32": "int"}[DATASETS[name][2]]
    return F.expr(DATASETS[name][1]).cast(kind)


def _keys(name: str) -> list:
    order = DATASETS[name][3]
    return [(F.expr(order[i]) if i < len(order) else F.lit(0)).cast("long").alias(f"k{i + 1}") for i in range(KEYS)]


def values(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(dataset, k1..k5, value): only the value and its keys are read."""
    df = _rows(table(spark, sf_dir, DATASETS[name][0]), DATASETS[name][0])
    return df.select(F.lit(name).alias("dataset"), *_keys(name), _value(name).alias("value"))


def load(spark: SparkSession, sf_dir: str, names) -> DataFrame:
    """(dataset, width, k1..k5, bits) of several datasets: one scan a table, whose columns leave it together as words."""
    by_table: dict[str, list[str]] = {}
    for n in [names] if isinstance(names, str) else names:
        by_table.setdefault(DATASETS[n][0], []).append(n)
    parts = []
    for tbl, held in by_table.items():
        df = _rows(table(spark, sf_dir, tbl), tbl)
        bits = {n: word_bits(_value(n), DATASETS[n][2]) for n in held}
        if len(held) == 1:
            (n,) = held
            parts.append(df.select(F.lit(n).alias("dataset"), F.lit(width_of(n)).alias("width"), *_keys(n), bits[n].alias("bits")))
            continue
        df = df.select(*(F.struct(*_keys(n)).alias(f"__k{i}") for i, n in enumerate(held)), *(bits[n].alias(f"__b{i}") for i, n in enumerate(held)))
        word = lambda i, n: F.struct(F.lit(n).alias("dataset"), F.lit(width_of(n)).alias("width"), *(F.col(f"__k{i}.k{j + 1}").alias(f"k{j + 1}") for j in range(KEYS)), F.col(f"__b{i}").alias("bits"))
        parts.append(df.select(F.inline(F.array(*(word(i, n) for i, n in enumerate(held))))))
    return reduce(DataFrame.unionByName, parts)
