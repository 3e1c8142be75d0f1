"""Secret scans: base patterns, and a token-efficiency test that exposes random strings.

Base kinds (leftmost, non-overlapping, each kind on its own): ``assign``, ``access`` and ``hex``.  The test adds spans of kind ``random``:
runs of ``[A-Za-z0-9+/_=-]`` of at least ``MIN_RUN`` characters with a letter, whose characters per
token under a public byte-pair vocabulary are at most ``MAX_RATIO``; natural words merge into long tokens, random strings do not.
Known digests (hex of the common digest lengths, UUIDs), numbers and identifiers (snake, kebab or camel words, paths) are left out,
and so are runs that overlap a base span.  An identifier has no digit that touches a lower-case letter or precedes a letter, and more than half of
its letters are in pieces that are words by the same test: characters per token above ``MAX_RATIO``.

Defined results: null text is empty; offsets are code points, end exclusive; empty span lists give the digest of the empty string;
repeated rows give repeated rows.
"""

from __future__ import annotations

import base64
import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

ANY = lambda s: "".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in s)
KEYWORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ASSIGN = re.compile(f"({'|'.join(map(ANY, ('password', 'passwd', 'secret', 'token', 'api_?key')))})" + r"""["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{24,}")
RUN = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{20,}")
KINDS = {"assign": 0, "access": 1, "hex": 2, "random": 3}
MIN_RUN, MAX_RATIO, STRETCH = 20, 2.2, 4096
DIGEST = re.compile(r"(?:[0-9a-f]{32}|[0-9a-f]{40}|[0-9a-f]{56}|[0-9a-f]{64}|[0-9a-f]{96}|[0-9a-f]{128}|[0-9A-F]{32}|[0-9A-F]{40}|[0-9A-F]{64}|[0-9a-fA-F]{8}-(?:[0-9a-fA-F]{4}-){3}[0-9a-fA-F]{12})")
MIXED = re.compile(r"[0-9][A-Za-z]|[a-z][0-9]")
PIECE = re.compile(r"[A-Z]+(?![a-z])|[A-Z]?[a-z]+")
#: The default of a parameter: a public rank file of the machine, never copied.
VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: Runs whose verdict a worker keeps, and the longest of them.
RATIO_CACHE, CACHED_RUN = 100_000, 200
_encoders: dict[str, object] = {}


def encoder(path: str = VOCABULARY):
    """The tiktoken encoding of a rank file; one a process."""
    if path not in _encoders:
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        _encoders[path] = tiktoken.Encoding("ranks", pat_str=r"\p{L}+|\p{N}+|[^\p{L}\p{N}]+", mergeable_ranks=ranks, special_tokens={})
    return _encoders[path]


def ratio(run: str, path: str = VOCABULARY) -> float:
    """Characters per token; tokens are counted in stretches of ``STRETCH`` characters, so any length costs linear time."""
    e = encoder(path)
    return len(run) / max(1, sum(len(e.encode_ordinary(run[i : i + STRETCH])) for i in range(0, len(run), STRETCH)))


def identifier(run: str, path: str, max_ratio: float) -> bool:
    if MIXED.search(run):
        return False
    pieces = PIECE.findall(run)
    return 2 * sum(len(p) for p in pieces if len(p) > max_ratio and ratio(p, path) > max_ratio) > sum(map(len, pieces))


def exposes(run: str, path: str, max_ratio: float) -> bool:
    if not re.search("[A-Za-z]", run) or DIGEST.fullmatch(run) or ratio(run, path) > max_ratio:
        return False
    return not identifier(run, path, max_ratio)


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the base patterns, in order."""
    out = []
    low = text.lower()
    if any(k in low for k in KEYWORDS):
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


def scan(text: str, path: str = VOCABULARY, max_ratio: float = MAX_RATIO, seen: dict | None = None) -> tuple[list, list]:
    """Base spans, and all spans with those that the token-efficiency test adds."""
    base = base_spans(text)
    extra, seen = [], {} if seen is None else seen
    at = far = 0  # base spans that begin before the run's end, and where the last of them ends
    for m in RUN.finditer(text):
        while at < len(base) and base[at][0] < m.end():
            far = max(far, base[at][2])
            at += 1
        if far > m.start():
            continue
        run = m.group()
        if (bad := seen.get(run)) is None:
            bad = exposes(run, path, max_ratio)
            if len(run) <= CACHED_RUN:
                if len(seen) >= RATIO_CACHE:
                    seen.clear()
                seen[run] = bad
        if bad:
            extra.append((m.start(), 3, m.end()))
    return base, sorted(base + extra)


NAMES = list(KINDS)


def joined(spans) -> str:
    return ",".join(f"{NAMES[k]}:{a}:{b}" for a, k, b in spans)


def scan_secrets(docs: DataFrame, vocabulary: str = VOCABULARY, max_ratio: float = MAX_RATIO) -> DataFrame:
    """Per row: doc_id, n_assign, n_access, n_hex, base_sha256, spans."""
    schema = pa.schema([("doc_id", pa.int64()), *((f"n_{k}", pa.int64()) for k in NAMES[:3]), ("base_sha256", pa.string()), ("spans", pa.string())])

    def run(batches):
        seen: dict = {}
        for r in batches:
            rows = [scan(t or "", vocabulary, max_ratio, seen) for t in r.column(1).to_pylist()]
            yield C.batch(schema, r.column(0), *(pa.array([sum(k == i for _, k, _ in b) for b, _ in rows], pa.int64()) for i in range(3)), pa.array([hashlib.sha256(joined(b).encode()).hexdigest() for b, _ in rows]), pa.array([joined(a) for _, a in rows], pa.string()))

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").transform(C.arrow, run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redacted(text: str, spans) -> str:
    out, at = [], 0
    for a, k, b in spans:
        if a >= at:
            out += [text[at:a], f"<{NAMES[k]}>"]
        at = max(at, b)
    return "".join([*out, text[at:]]) if spans else text


def redact(docs: DataFrame, vocabulary: str = VOCABULARY, max_ratio: float = MAX_RATIO) -> DataFrame:
    """``docs`` with every span of ``text`` replaced by a mark of its kind.

    Of overlapping spans the first is marked and the rest of the other goes with it.  Null and empty texts, repeated rows, null ids and further
    columns of any name stay as they are; an empty table stays empty.
    """
    at = docs.columns.index("text")

    def run(batches):
        seen: dict = {}
        for r in batches:
            new = [t if t is None else redacted(t, scan(t, vocabulary, max_ratio, seen)[1]) for t in r.column(at).to_pylist()]
            yield r.set_column(at, r.schema.field(at), pa.array(new, r.schema.field(at).type))

    return docs.transform(C.arrow, run, docs.schema)


_SQL = {"assign": r"""([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)""", "access": "()(AKIA[A-Z0-9]+)", "hex": "()([0-9a-f]+)"}
_LEAST = {"assign": 6, "access": 20, "hex": 24}
#: Matches of a kind with what lies between them: the lengths before a match give its place.
_MATCHES = " union all ".join(f"select rid, '{k}' as kind, {i} as n, {_LEAST[k]} as least, regexp_extract_all(t, '{p}') as found, regexp_extract_all(t, '{p}', 2) as core, string_split_regex(t, '{p}') as gaps from d" for i, (k, p) in enumerate(_SQL.items()))
BASE_SQL = f"""
with d as (select row_number() over () as rid, doc_id, coalesce(text, '') as t from documents), m as ({_MATCHES}),
x as (select rid, kind, n, least, i, length(found[i]) as len, length(core[i]) as core, length(gaps[i]) as gap from m, unnest(range(1, len(found) + 1)) u(i)),
s as (select *, sum(gap + len) over (partition by rid, n order by i) as stop from x),
f as (select rid, kind, n, cast(stop - len as bigint) as start, cast(stop as bigint) as stop from s where core >= least),
g as (select rid, count(*) filter (n = 0) as a, count(*) filter (n = 1) as b, count(*) filter (n = 2) as c, string_agg(kind || ':' || start || ':' || stop, ',' order by start, n) as spans from f group by rid)
select doc_id, coalesce(a, 0) as n_assign, coalesce(b, 0) as n_access, coalesce(c, 0) as n_hex, sha256(coalesce(spans, '')) as base_sha256 from d left join g using (rid)
"""


def base_columns(spark, sf_dir):
    """The columns of the scan that have a SQL form."""
    return op6(spark, sf_dir).drop("spans")


def op6(spark, sf_dir):
    return scan_secrets(C.table(spark, sf_dir, "documents", "doc_id", "text"))
