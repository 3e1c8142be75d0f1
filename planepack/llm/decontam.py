"""Benchmark decontamination with a generalised suffix automaton of the normalised test items.

The automaton is built over the words of the items and sent to the tasks.  A benchmark of more than ``PART_CHARS`` characters is cut into parts with an
automaton each; a task reads one part's automaton at a time and unites what the parts find, so the result is the same and memory stays bounded
(by the longest single item beyond that).
Training words stream through it; the longest matching length at each word tells which windows end there.  Words that are in no item,
or whose neighbour pair is in no item, cannot lie in a window; they are skipped with array operations, so the automaton only steps
through runs that could match.

A window is ``width`` consecutive words of an item; an item with fewer words, but some, is one window.  ``hits`` reports;
``remove_spans`` deletes hit spans of at least ``min_words`` words and drops documents in which more than ``max_coverage`` of the words are hit.

Defined results: null or wordless text has 0 words and 0 hits; null item texts have no windows; equal items are all
reported; a null item_id counts as an item but its id is left out of the digest; repeated rows give repeated rows.
"""

from __future__ import annotations

import hashlib
import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from planepack.datasource import opened
from planepack.storage import fresh

from . import common as C

WIDTH = 10
#: Benchmark text behind one automaton, in characters, and document text that a task holds against the parts in turn.
PART_CHARS, HELD_CHARS = 4_000_000, 32_000_000
#: A-Z lower-cased, every other ASCII byte that is no letter or digit becomes a space.
NORMAL = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c > 127 else 32 for c in range(256))
VOCAB_CACHE = 200_000


def words_of(text: bytes | None) -> list[bytes]:
    return text.translate(NORMAL).split() if text else []


class SuffixAutomaton:
    """Generalised suffix automaton over integer words; states know which items hold a window that ends in them."""

    def __init__(self, items: list[tuple[object, list[bytes]]], width: int = WIDTH):
        self.width = width
        self.vocab: dict[bytes, int] = {}
        self.next: list[dict[int, int]] = [{}]
        self.link, self.len = [-1], [0]
        self.ids = [i for i, _ in items]
        coded = [[self.vocab.setdefault(w, len(self.vocab)) for w in words] for _, words in items]
        self.one = [0 < len(x) <= width for x in coded]
        for x in coded:
            last = 0
            for w in x:
                last = self._extend(last, w)
        # windows: which items have one that ends in a state, by window length
        ends: dict[tuple[int, int], set[int]] = {}
        self.shortest = width
        for k, x in enumerate(coded):
            size = min(width, len(x))
            if size:
                self.shortest = min(self.shortest, size)
                state, length = 0, 0
                for j, w in enumerate(x):
                    state, length = self.step(state, length, w)
                    if j + 1 >= size:
                        s = state
                        while self.len[self.link[s]] >= size:
                            s = self.link[s]
                        ends.setdefault((s, size), set()).add(k)
        self.windows: dict[int, list[tuple[int, tuple[int, ...]]]] = {}
        for (s, size), who in sorted(ends.items()):
            self.windows.setdefault(s, []).append((size, tuple(sorted(who))))
        # for every state the nearest state on its suffix path (itself included) that has windows
        self.up = [-1] * len(self.link)
        for s in sorted(range(len(self.link)), key=self.len.__getitem__):
            self.up[s] = s if s in self.windows else self.up[self.link[s]] if s else -1
        v = len(self.vocab) + 1
        pairs = np.unique(np.array([a * v + b for x in coded for a, b in zip(x, x[1:], strict=False)], np.int64))
        self.pairs, self.v = pairs, v

    def _extend(self, last: int, w: int) -> int:
        nxt, link, length = self.next, self.link, self.len
        if w in nxt[last]:
            q = nxt[last][w]
            return q if length[q] == length[last] + 1 else self._clone(last, w, q)
        cur = len(nxt)
        nxt.append({})
        length.append(length[last] + 1)
        link.append(0)
        p = last
        while p != -1 and w not in nxt[p]:
            nxt[p][w] = cur
            p = link[p]
        if p != -1:
            q = nxt[p][w]
            link[cur] = q if length[q] == length[p] + 1 else self._clone(p, w, q)
        return cur

    def _clone(self, p: int, w: int, q: int) -> int:
        c = len(self.next)
        self.next.append(dict(self.next[q]))
        self.len.append(self.len[p] + 1)
        self.link.append(self.link[q])
        self.link[q] = c
        while p != -1 and self.next[p].get(w) == q:
            self.next[p][w] = c
            p = self.link[p]
        return c

    def step(self, state: int, length: int, w: int) -> tuple[int, int]:
        """One word further: the state and the length of the longest match that ends there."""
        while state and w not in self.next[state]:
            state = self.link[state]
            length = self.len[state]
        if w in self.next[state]:
            return self.next[state][w], length + 1
        return 0, 0

    def scan(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray, set[int]]:
        """Hit flags of the words, flags of those inside an item that is one window itself, and the items whose windows occur.  codes: -1 for words of no item."""
        n = len(codes)
        marks, wholes, found = np.zeros(n + 1, np.int64), np.zeros(n + 1, np.int64), set()
        if self.shortest >= 2:
            both = codes[:-1] * self.v + codes[1:]
            if not len(self.pairs) or n < 2:
                return marks[:n] > 0, wholes[:n] > 0, found
            at = np.minimum(np.searchsorted(self.pairs, both), len(self.pairs) - 1)
            ok = (self.pairs[at] == both) & (codes[:-1] >= 0) & (codes[1:] >= 0)
            edge = np.diff(np.concatenate([[0], ok.astype(np.int8), [0]]))
            starts, ends = np.nonzero(edge == 1)[0], np.nonzero(edge == -1)[0] + 1
        else:
            edge = np.diff(np.concatenate([[0], (codes >= 0).astype(np.int8), [0]]))
            starts, ends = np.nonzero(edge == 1)[0], np.nonzero(edge == -1)[0]
        long = ends - starts >= self.shortest
        for a, b in zip(starts[long].tolist(), ends[long].tolist(), strict=True):
            state, length = 0, 0
            for j, w in enumerate(codes[a:b].tolist(), a + 1):
                state, length = self.step(state, length, w)
                s = self.up[state]
                most = whole = 0
                while s > 0:
                    for size, who in self.windows[s]:
                        if size <= length:
                            found.update(who)
                            most = max(most, size)
                            if any(self.one[k] for k in who):
                                whole = max(whole, size)
                    s = self.up[self.link[s]]
                if most:
                    marks[j - most] += 1
                    marks[j] -= 1
                if whole:
                    wholes[j - whole] += 1
                    wholes[j] -= 1
        return np.cumsum(marks)[:n] > 0, np.cumsum(wholes)[:n] > 0, found


class _Codes(dict):
    def __init__(self, vocab):
        super().__init__(vocab)
        self.top = len(vocab) + VOCAB_CACHE
        self.vocab = vocab

    def __missing__(self, w):
        if len(self) >= self.top:
            self.clear()
            self.update(self.vocab)
        self[w] = -1
        return -1


class Benchmark:
    """The automata of all parts: one sent to the tasks, or a file each in the shared folder."""

    def __init__(self, items: DataFrame, width: int = WIDTH, part_chars: int = PART_CHARS):
        spark = items.sparkSession
        rows = items.select(F.col("item_id").cast("string").alias("i"), F.col("text").alias("t"))
        chars = rows.agg(F.coalesce(F.sum(F.length("t")), F.lit(0))).first()[0]
        self.parts = max(1, -(-chars // part_chars))
        self.files, self.held = [], None
        for p in range(self.parts):  # one part at a time on the driver
            mine = rows if self.parts == 1 else rows.filter(F.pmod(F.xxhash64("i", "t"), F.lit(self.parts)) == p)
            auto = SuffixAutomaton([(r.i, words_of(r.t.encode() if r.t is not None else None)) for r in mine.collect()], width)
            if self.parts == 1:
                self.held = spark.sparkContext.broadcast(auto)
            else:
                path = fresh(spark, "automaton")
                store, at = opened(path)
                with store.open_output_stream(at) as f:
                    pickle.dump(auto, f)
                self.files.append(path)

    def automata(self):
        """One after the other."""
        if self.held is not None:
            yield self.held.value
        for path in self.files:
            store, at = opened(path)
            with store.open_input_stream(at) as f:
                yield pickle.load(f)

    def scanned(self, batches, column: int):
        """(batch, [(words, hit flags, whole-item flags, ids of the items)]): every batch with what all parts find in its texts; null texts have no words."""
        if self.held is not None:
            auto = self.held.value
            codes = _Codes(auto.vocab)
            for r in batches:
                yield r, [_found(auto, codes, words_of(t)) for t in r.column(column).cast(pa.large_binary()).to_pylist()]
            return
        waiting, size = [], 0

        def all_parts():
            texts = [[words_of(t) for t in r.column(column).cast(pa.large_binary()).to_pylist()] for r in waiting]
            out = [[(len(w), np.zeros(len(w), bool), np.zeros(len(w), bool), []) for w in x] for x in texts]
            for auto in self.automata():
                codes = _Codes(auto.vocab)
                for x, y in zip(texts, out, strict=True):
                    for w, (_, hit, whole, ids) in zip(x, y, strict=True):
                        _, h, o, i = _found(auto, codes, w)
                        hit |= h
                        whole |= o
                        ids += i
            return zip(list(waiting), out, strict=True)

        for r in batches:
            waiting.append(r)
            size += r.nbytes
            if size > HELD_CHARS:
                yield from all_parts()
                waiting.clear()
                size = 0
        if waiting:
            yield from all_parts()


def _found(auto: SuffixAutomaton, codes, words: list[bytes]) -> tuple:
    hit, whole, items = auto.scan(np.fromiter(map(codes.__getitem__, words), np.int64, len(words)))
    return len(words), hit, whole, [auto.ids[i] for i in items]


def hits(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, part_chars: int = PART_CHARS) -> DataFrame:
    """Per row: doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    held = Benchmark(benchmark, width, part_chars)
    schema = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_())])

    def run(batches):
        for r, found in held.scanned(batches, 1):
            digest = [hashlib.sha256(",".join(sorted(i for i in ids if i is not None)).encode()).hexdigest() for _, _, _, ids in found]
            n_hit = [int(hit.sum()) for _, hit, _, _ in found]
            yield C.batch(schema, r.column(0), pa.array([n for n, _, _, _ in found], pa.int64()), pa.array(n_hit, pa.int64()), pa.array([len(ids) for _, _, _, ids in found], pa.int64()), pa.array(digest, pa.string()), pa.array([h > 0 for h in n_hit], pa.bool_()))

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").transform(C.arrow, run, "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean")


#: The byte ranges of the words of a text, in step with words_of().
def _spans(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    white = np.frombuffer(b" " + text.translate(NORMAL) + b" ", np.uint8) == 32
    edge = np.diff(white.astype(np.int8))
    return np.nonzero(edge == -1)[0], np.nonzero(edge == 1)[0]


def cleaned(text: bytes, hit: np.ndarray, whole: np.ndarray, min_words: int, max_coverage: float) -> bytes | None:
    """The text without its hit spans; None if too much of it is hit; unchanged text if nothing is.

    A span shorter than ``min_words`` is cut if it holds a whole item.
    """
    if not hit.any():
        return text
    if hit.sum() > max_coverage * len(hit):
        return None
    a, b = _spans(text)
    edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    out, at = [], 0
    for i, j in zip(np.nonzero(edge == 1)[0].tolist(), np.nonzero(edge == -1)[0].tolist(), strict=True):
        if j - i >= min_words or whole[i:j].any():
            out.append(text[at : a[i]])
            at = int(b[j - 1])
    return b"".join([*out, text[at:]])


def remove_spans(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, min_words: int = WIDTH, max_coverage: float = 0.5, part_chars: int = PART_CHARS) -> DataFrame:
    """``docs`` with hit spans of at least ``min_words`` words, or of a whole item, cut out of ``text``; rows covered beyond ``max_coverage`` go.

    Null and empty texts, null ids, repeated rows and further columns of any name stay as they are; an empty table stays empty, and an empty
    benchmark changes nothing.
    """
    held, at = Benchmark(benchmark, width, part_chars), docs.columns.index("text")

    def run(batches):
        for r, found in held.scanned(batches, at):
            texts = r.column(at).cast(pa.large_binary()).to_pylist()
            new = [None if t is None else cleaned(t, hit, whole, min_words, max_coverage) for t, (_, hit, whole, _) in zip(texts, found, strict=True)]
            keep = pa.array([t is None or x is not None for t, x in zip(texts, new, strict=True)], pa.bool_())
            col = pa.array(new, pa.large_binary()).cast(pa.large_string()).cast(r.schema.field(at).type)
            yield r.set_column(at, r.schema.field(at), col).filter(keep)

    return docs.transform(C.arrow, run, docs.schema)


def op5(spark, sf_dir):
    return hits(C.table(spark, sf_dir, "documents", "doc_id", "text"), C.table(spark, sf_dir, "benchmark", "item_id", "text"))


OP5_SQL = r"""
with d as (select row_number() over () as rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents),
b as (select cast(item_id as varchar) as item, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from benchmark),
bw as (select item, least(10, len(w)) as size, array_to_string(w[i : i + least(10, len(w)) - 1], ' ') as win from b, unnest(range(1, greatest(0, len(w) - least(10, len(w)) + 1) + 1)) t(i) where len(w) > 0),
sizes as (select distinct size from bw),
dw as (select rid, i, size, array_to_string(w[i : i + size - 1], ' ') as win from d, sizes, unnest(range(1, greatest(0, len(w) - size + 1) + 1)) t(i)),
m as (select rid, i, dw.size, item from dw join bw on dw.win = bw.win and dw.size = bw.size),
h as (select rid, count(distinct i + k) as n_hit from m, unnest(range(0, size)) t(k) group by rid),
x as (select rid, count(*) as n_items, string_agg(item, ',' order by item) as items from (select distinct rid, item from m) group by rid)
select doc_id, cast(len(w) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items, sha256(coalesce(items, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from d left join h using (rid) left join x using (rid)
"""
