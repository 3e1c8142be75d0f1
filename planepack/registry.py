"""The registry of queries and their DuckDB oracles, and the SQL that oracles share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from . import blocks
from .fixtures import DATASETS, load

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}
#: Small enough for several blocks a dataset at test scale.
SMALL = 8192


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def small_blocks(spark, d, names, size: int = SMALL) -> DataFrame:
    return blocks.blocks(load(spark, d, names), size)


# ---------------------------------------------------------------- words

_BITS = {"f64": "cast(cast({} as bit) as bigint)", "f32": "cast(cast(cast(cast({} as float) as bit) as integer) as bigint)", "i64": "cast({} as bigint)", "i32": "cast({} as bigint)"}


def _half(cols: str, src: str) -> str:
    """Half-precision bits from the fields of the float: round to nearest, ties to even, subnormals, and infinity above the range."""
    fields = f"select {cols}, (b >> 31) & 1 as s, (b >> 23) & 255 as e, b & 8388607 as m from ({src})"
    small = f"select *, least(126 - e, 30) as sh, m | 8388608 as mm from ({fields})"
    normal = "((e - 112) << 10 | (m >> 13)) + case when (m & 8191) > 4096 or ((m & 8191) = 4096 and ((m >> 13) & 1) = 1) then 1 else 0 end"
    rest = "(mm & ((1::bigint << cast(greatest(sh, 1) as integer)) - 1))"
    tie = "(1::bigint << cast(greatest(sh, 1) - 1 as integer))"
    low = "(mm >> cast(greatest(sh, 0) as integer))"
    sub = f"{low} + case when {rest} > {tie} or ({rest} = {tie} and ({low} & 1) = 1) then 1 else 0 end"
    h = f"case when e = 255 and m > 0 then 32256 when e >= 143 then 31744 when e > 112 then {normal} when e < 102 then 0 else {sub} end"
    return f"select {cols}, cast(case when s = 1 then h - 32768 else h end as bigint) as bits from (select *, {h} as h from ({small}))"


def source(names) -> str:
    """(dataset, width, k1..k5, bits) of registered datasets."""
    parts = []
    for n in [names] if isinstance(names, str) else names:
        tbl, value, word, order, _ = DATASETS[n]
        sql = lambda e: e.replace("unix_micros(to_timestamp(", "epoch_us((")
        keys = ", ".join(f"cast({sql(order[i]) if i < len(order) else '0'} as bigint) as k{i + 1}" for i in range(5))
        src = tbl if tbl != "embeddings" else "(select vec_id, d - 1 as dim, embedding[d] as x from embeddings, unnest(range(1, len(embedding) + 1)) t(d))"
        if word == "f16":
            raw = f"select {keys}, {_BITS['f32'].format(sql(value))} & 4294967295 as b from {src}"
            parts.append(f"select '{n}' as dataset, 2 as width, * from ({_half('k1, k2, k3, k4, k5', raw)})")
        else:
            parts.append(f"select '{n}' as dataset, {int(word[1:]) // 8} as width, {keys}, {_BITS[word].format(sql(value))} as bits from {src}")
    return " union all ".join(parts)


def ranked_sql(names, size: int = SMALL) -> str:
    """Common table ``w``: words with rn, block_id and pos."""
    return f"src as ({source(names)}), rk as (select *, row_number() over (partition by dataset order by k1, k2, k3, k4, k5) - 1 as rn from src), w as (select *, rn // ({size} // width) as block_id, rn % ({size} // width) as pos from rk)"


#: Common table ``b``: a row per byte of the words of ``w``.
PLANES = "p as (select *, unnest(range(0, width)) as plane from w), b as (select *, (bits >> cast(8 * (width - 1 - plane) as integer)) & 255 as byte from p)"
#: The blocks that a 30 % sample takes.
SAMPLED = "(block_id * 617) % 1000 < 300"


def entropy_sql(c: str) -> str:
    return f"greatest(round(log2(sum({c})) - sum({c} * log2({c})) / sum({c}), 6) + 0.0, 0.0)"


def varint_sql(x: str) -> str:
    """Bytes of a variable-length whole number."""
    return "(1 + " + " + ".join(f"case when {x} >= {1 << 7 * k}::hugeint then 1 else 0 end" for k in range(1, 10)) + ")"


# ---------------------------------------------------------------- partitions of four planes

P15 = "with recursive l(n, labels, top) as (select 1, '0', 0 union all select n + 1, labels || ',' || v, greatest(top, v) from l, unnest(range(0, top + 2)) t(v) where n < {n}) select labels, cast(top + 1 as integer) as clusters from l where n = {n}"


def squared_sql(names, sampled: bool = False, size: int = SMALL) -> str:
    """Common table ``d2`` (dataset, i, j, d2): squared distances of the byte frequencies of all plane pairs."""
    where = f"where {SAMPLED}" if sampled else ""
    return (
        f"{ranked_sql(names, size)}, {PLANES}, c as (select dataset, plane, byte, count(*) as c from b {where} group by all), f as (select dataset, plane, byte, c / sum(c) over (partition by dataset, plane) as freq from c), "
        "pl as (select distinct dataset, plane from f), dense as (select pl.dataset, pl.plane, v.byte, coalesce(f.freq, 0.0) as freq from pl cross join range(256) v(byte) left join f on f.dataset = pl.dataset and f.plane = pl.plane and f.byte = v.byte), "
        "d2 as (select x.dataset, x.plane as i, y.plane as j, sum((x.freq - y.freq) ^ 2) as d2 from dense x join dense y on x.dataset = y.dataset and x.byte = y.byte group by all)"
    )


#: Merge costs of the second step for four planes: the merged pair (i, j) with a third plane b.
_SECOND = {
    "single": "least(sqrt(ib.d2), sqrt(jb.d2))", "complete": "greatest(sqrt(ib.d2), sqrt(jb.d2))", "average": "(sqrt(ib.d2) + sqrt(jb.d2)) / 2",
    "ward": "2.0 / 3 * ((ib.d2 + jb.d2) / 2 - ij.d2 / 4)",
}


def tree_sql(method: str = "single") -> str:
    """Common table ``parts`` (dataset, k, p): the agglomerative tree of four planes from ``d2``, partitions as sorted lists of lists."""
    both = "bc.d2 / 2" if method == "ward" else "sqrt(bc.d2)"
    return (
        "ij as (select dataset, i, j, d2 from d2 where i < j qualify row_number() over (partition by dataset order by round(sqrt(d2), 12), i, j) = 1), "
        "others as (select ij.dataset, list_sort(list(pl.plane)) as o from ij join pl on pl.dataset = ij.dataset and pl.plane <> ij.i and pl.plane <> ij.j group by 1), "
        f"second as (select ij.dataset, list_sort([list_sort([ij.i, ij.j, ib.j]), [bc.i + bc.j - ib.j]]) as p, {_SECOND[method]} as cost from ij join others using (dataset) join d2 bc on bc.dataset = ij.dataset and bc.i = o[1] and bc.j = o[2] "
        "join d2 ib on ib.dataset = ij.dataset and ib.i = ij.i and ib.j in (o[1], o[2]) join d2 jb on jb.dataset = ij.dataset and jb.i = ij.j and jb.j = ib.j "
        f"union all select ij.dataset, list_sort([[ij.i, ij.j], o]) as p, {both} as cost from ij join others using (dataset) join d2 bc on bc.dataset = ij.dataset and bc.i = o[1] and bc.j = o[2]), "
        "parts as (select dataset, 4 as k, [[0], [1], [2], [3]] as p from ij union all select dataset, 3, list_sort([[i, j], [o[1]], [o[2]]]) from ij join others using (dataset) "
        "union all select dataset, 2, p from second qualify row_number() over (partition by dataset order by round(cost, 12)) = 1 union all select dataset, 1, [[0, 1, 2, 3]] from ij)"
    )


#: From ``d2`` and ``parts``: clusters, members, scatter, gaps of the centroids, and the scores of every candidate.
SCORES = (
    "cl as (select dataset, k, ci, p[ci] as g from parts, unnest(range(1, k + 1)) t(ci)), mem as (select dataset, k, ci, unnest(g) as pl, len(g) as a from cl), "
    "ss as (select m.dataset, m.k, m.ci, any_value(m.a) as a, sum(d2.d2) / (2 * any_value(m.a) ^ 2) as ss from mem m join mem q on m.dataset = q.dataset and m.k = q.k and m.ci = q.ci join d2 on d2.dataset = m.dataset and d2.i = m.pl and d2.j = q.pl group by 1, 2, 3), "
    "one as (select m.dataset, m.k, m.ci, m.pl, sqrt(greatest(0.0, sum(d2.d2) / any_value(m.a) - any_value(ss.ss))) as s from mem m join mem q on m.dataset = q.dataset and m.k = q.k and m.ci = q.ci join d2 on d2.dataset = m.dataset and d2.i = m.pl and d2.j = q.pl join ss on ss.dataset = m.dataset and ss.k = m.k and ss.ci = m.ci group by 1, 2, 3, 4), "
    "sc as (select dataset, k, ci, avg(s) as s from one group by all), "
    "gap as (select m.dataset, m.k, m.ci as x, q.ci as y, sqrt(greatest(0.0, avg(d2.d2) - any_value(sx.ss) - any_value(sy.ss))) as g, min(sqrt(d2.d2)) as least, avg(sqrt(d2.d2)) as mean from mem m join mem q on m.dataset = q.dataset and m.k = q.k and m.ci <> q.ci join d2 on d2.dataset = m.dataset and d2.i = m.pl and d2.j = q.pl join ss sx on sx.dataset = m.dataset and sx.k = m.k and sx.ci = m.ci join ss sy on sy.dataset = q.dataset and sy.k = q.k and sy.ci = q.ci group by 1, 2, 3, 4), "
    "db as (select dataset, k, avg(r) as score from (select gap.dataset, gap.k, x, max(case when g = 0 then 'Infinity'::double else (a.s + b.s) / g end) as r from gap join sc a on a.dataset = gap.dataset and a.k = gap.k and a.ci = x join sc b on b.dataset = gap.dataset and b.k = gap.k and b.ci = y group by 1, 2, 3) where k between 2 and 3 group by all), "
    "within as (select dataset, k, sum(ss * a) as w from ss group by all), whole as (select dataset, sum(d2) / 8 as t from d2 group by 1), "
    "ch as (select dataset, k, case when w = 0 then 'Infinity'::double else ((t - w) / (k - 1)) / (w / (4 - k)) end as score from within join whole using (dataset) where k between 2 and 3), "
    "own as (select m.dataset, m.k, m.pl, avg(sqrt(d2.d2)) as a from mem m join mem q on m.dataset = q.dataset and m.k = q.k and m.ci = q.ci and m.pl <> q.pl join d2 on d2.dataset = m.dataset and d2.i = m.pl and d2.j = q.pl group by 1, 2, 3), "
    "other as (select dataset, k, pl, min(b) as b from (select m.dataset, m.k, m.pl, q.ci, avg(sqrt(d2.d2)) as b from mem m join mem q on m.dataset = q.dataset and m.k = q.k and m.ci <> q.ci join d2 on d2.dataset = m.dataset and d2.i = m.pl and d2.j = q.pl group by 1, 2, 3, 4) group by all), "
    "si as (select dataset, k, sum(case when greatest(a, b) = 0 then 0 else (b - a) / greatest(a, b) end) / 4 as score from own join other using (dataset, k, pl) where k between 2 and 3 group by all), "
    "sep as (select dataset, k, min(least) as separation from gap group by all)"
)
CHOSEN = "select dataset, p::varchar as partition, cast(k as integer) as clusters from parts join db using (dataset, k) qualify row_number() over (partition by dataset order by score, k) = 1"
