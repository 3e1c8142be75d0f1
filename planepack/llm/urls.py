"""URL filters: a bit-parallel automaton that runs all glob rules at once.

Globs (``*`` any run, ``?`` any byte) over a canonical form of the URL, ``.host<0xFF>path``, are packed into one multiword
Shift-And machine: a bit is "this much of this rule has matched", a byte of the URL is one shift, one mask and one self-loop mask for
all rules, and a batch of URLs steps together.  The canonical form starts with a dot, so ``*.example.org`` fits the host itself and
every subdomain.

Verdict: the longest fitting host-and-path rule (length of host and path; then block before allow, then the rule's text); without one,
``block`` if one of the method's own globs fits, else ``allow``.  Defined results: a null URL or one without ``://`` has empty host and
path and is allowed; hosts keep their port; matching is by bytes of UTF-8; repeated rows give repeated rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

#: (verdict, host, path): fixed rules of the query.
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
#: The method's own globs over the canonical form.
GLOBS = ("*.casino*\xff*", "*.adult-*\xff*", "*.free-bets*\xff*", "*.spam-*\xff*", "*-win.*\xff*", "*\xff*/ads/*", "*\xff*/track?.gif")
SEP = b"\xff"


#: One byte whatever it is, and any run of bytes.
ANY, RUN = -1, -2


def glob(pattern: bytes) -> list[int]:
    return [RUN if c == 0x2A else ANY if c == 0x3F else c for c in pattern]


class ShiftAnd:
    """Multiword Shift-And over bytes for many globs; state bits in little-endian 64-bit words."""

    def __init__(self, globs: list):
        """Globs as bytes, or as lists of byte values with ``ANY`` and ``RUN`` for the two wildcards."""
        marks, self.accept = [], []  # per bit: which bytes lead to it, does it loop, does it start
        accepts, loops, starts = [], [], []
        for g in globs:
            starts.append(len(accepts))
            accepts.append(None)
            loops.append(False)
            for c in glob(g) if isinstance(g, bytes) else g:
                if c == RUN:
                    loops[-1] = True
                else:
                    accepts.append(c)
                    loops.append(False)
            self.accept.append(len(accepts) - 1)
        self.words = w = max(1, -(-len(accepts) // 64))
        bits = np.zeros((256, w * 64), bool)
        for i, c in enumerate(accepts):
            if c is not None:
                bits[slice(None) if c == -1 else c, i] = True
        pack = lambda b: np.packbits(b, axis=-1, bitorder="little").view("<u8").reshape(*b.shape[:-1], w)
        self.masks = pack(bits)
        self.loop = pack(np.array(loops + [False] * (w * 64 - len(loops))))
        start = np.zeros(w * 64, bool)
        start[starts] = True
        self.start = pack(start)

    def match(self, texts: list[bytes]) -> np.ndarray:
        """(texts, globs) booleans."""
        n = len(texts)
        length = np.array([len(t) for t in texts], np.int64)
        order = np.argsort(-length, kind="stable")
        buf = np.frombuffer(b"".join(texts[i] for i in order) + b"\0", np.uint8)
        length = length[order]
        at = np.cumsum(length) - length
        d = np.tile(self.start, (n, 1))
        k, pos = n, 0
        while True:
            while k and length[k - 1] <= pos:
                k -= 1
            if not k:
                break
            now = d[:k]
            step = now << np.uint64(1)
            if self.words > 1:
                step[:, 1:] |= now[:, :-1] >> np.uint64(63)
            d[:k] = (step & self.masks[buf[at[:k] + pos]]) | (now & self.loop)
            pos += 1
        out = np.empty((n, len(self.accept)), bool)
        for j, b in enumerate(self.accept):
            out[order, j] = (d[:, b // 64] >> np.uint64(b % 64)) & np.uint64(1)
        return out


def split_url(df: DataFrame, url: str = "url") -> DataFrame:
    """Adds host and path, JVM-side."""
    at = F.locate("://", F.col(url))
    rest = F.when(at > 0, F.expr(f"substring({url}, locate('://', {url}) + 3)")).otherwise(F.lit(""))
    host = F.regexp_extract(F.coalesce(rest, F.lit("")), r"(?s)^([^/?#]*)", 1)
    tail = F.regexp_extract(F.coalesce(rest, F.lit("")), r"(?s)^[^/?#]*([^?#]*)", 1)
    return df.withColumn("host", F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")).withColumn("path", tail)


def judge(pages: DataFrame, rules=RULES, globs=GLOBS) -> DataFrame:
    """page_id, host, path, rule, verdict per row."""
    ranked = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[0] != "block", r[1] + r[2]))
    patterns = [[RUN, *b".", *h.encode(), *SEP, *p.encode(), RUN] for _, h, p in ranked]  # every character of a rule stands for itself
    patterns += [g.encode("latin-1") for g in globs]
    schema = pa.schema([("page_id", pa.int64()), ("host", pa.string()), ("path", pa.string()), ("rule", pa.string()), ("verdict", pa.string())])

    def run(batches):
        machine = ShiftAnd(patterns)
        for r in batches:
            hosts, paths = r.column(1).to_pylist(), r.column(2).to_pylist()
            fits = machine.match([b"." + h.encode() + SEP + p.encode() for h, p in zip(hosts, paths, strict=True)])
            first = np.where(fits[:, : len(ranked)].any(1), fits[:, : len(ranked)].argmax(1), -1)
            own = fits[:, len(ranked) :].any(1) & np.array([bool(h) for h in hosts], bool)
            yield C.batch(schema, r.column(0), r.column(1), r.column(2), pa.array([ranked[i][1] + ranked[i][2] if i >= 0 else None for i in first], pa.string()), pa.array([ranked[i][0] if i >= 0 else "block" if b else "allow" for i, b in zip(first, own, strict=True)]))

    return split_url(pages.select(F.col("page_id").cast("long").alias("page_id"), "url")).select("page_id", "host", "path").transform(C.arrow, run, "page_id long, host string, path string, rule string, verdict string")


def op10(spark, sf_dir):
    return judge(C.table(spark, sf_dir, "pages", "page_id", "url"))


OP10_SQL = r"""
with u as (select page_id, case when contains(url, '://') then substr(url, instr(url, '://') + 3) else '' end as rest from pages),
h as (select page_id, translate(regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host, regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) as path from u),
rules(verdict, h, p) as (values ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
m as (select page_id, host, path, (select struct_pack(r := r.h || r.p, v := r.verdict) from rules r where ends_with('.' || host, '.' || r.h) and starts_with(path, r.p) order by length(r.h || r.p) desc limit 1) as w from h)
select cast(page_id as bigint) as page_id, host, path, w.r as rule, coalesce(w.v, case when regexp_matches(host, '(^|\.)(casino|adult-|free-bets|spam-)') or contains('.' || host, '-win.') or contains(path, '/ads/') or regexp_matches(path, '/track.\.gif$') then 'block' else 'allow' end) as verdict from m
"""
