"""SentencePiece encoding by forward filtering and backward sampling, and lossless decoding.

A public SentencePiece vocabulary gives the pieces; its merge ranks give piece probabilities by Zipf's law,
log p = -log(rank + ``shift``), since the file holds ranks and no counts.  The lattice of a text holds every piece at every place.
Forward filtering sums the probability of all segmentations up to each place; backward sampling draws from the end which piece ends
there, in proportion, so a segmentation comes out with its exact posterior probability (sharpened by ``theta``; a large one gives
nearly the best segmentation).

No piece holds a space behind another character and none holds a line feed, so the lattice falls apart exactly into units (spaces and the
word behind them).  The filtered lattice of a unit is kept for its next occurrence, and the draws of all units of a
batch run together as array operations.  The random numbers are hashes of (seed, row key, unit, step): a row's result depends on
nothing else.

Lossless: a space stands for the vocabulary's word mark; characters in no piece, the word mark's own character among them, become
UTF-8 byte pieces; one leading space is added and taken away.  Defined results: null text gives null ids and 0 pieces;
empty text gives the leading space only; a null key counts as 0; equal keys and texts give equal results.
"""

from __future__ import annotations

import math
import re
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

#: The default of a parameter: a public vocabulary of the machine, never copied.
MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
UNIT = re.compile(r" *[^ \n]+|\n| +")
SHIFT, THETA, BYTE_LOGP = 50.0, 1.0, -20.0
#: Edges of kept unit lattices a worker may hold (12 bytes each, and the units themselves).
MAX_EDGES = 2_000_000
#: Rows that are drawn together, bytes of text after which no more join them, and characters from which a unit is cut into its independent parts.
ROWS, CHARS, LONG = 256, 500_000, 64
_vocab: dict[str, tuple] = {}
_tries: dict[str, tuple] = {}


def vocabulary(path: str = MODEL):
    """(piece -> (id, log p)), ids of the 256 byte pieces, bytes of every id."""
    if path not in _vocab:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces, byte_ids, raw = {}, [0] * 256, []
        for i in range(sp.get_piece_size()):
            p = sp.id_to_piece(i)
            if sp.is_byte(i):
                byte_ids[int(p[3:5], 16)] = i
                raw.append(bytes([int(p[3:5], 16)]))
            elif sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i):
                raw.append(b"")
            else:
                s = p.replace(MARK, " ")
                pieces[s] = (i, -math.log(max(0.0, -sp.get_score(i)) + SHIFT))
                raw.append(s.encode())
        _vocab[path] = (pieces, byte_ids, raw, max(map(len, pieces)))
    return _vocab[path]


class PieceTrie:
    """Prefix trie of the pieces as arrays: a dense table for the commonest characters, a sorted key list for the rest."""

    COMMON = 64

    def __init__(self, pieces: dict[str, tuple[int, float]]):
        count: dict[str, int] = {}
        for p in pieces:
            for c in p:
                count[c] = count.get(c, 0) + 1
        chars = sorted(count, key=lambda c: (-count[c], c))
        self.cls = np.zeros(0x110000, np.int32)
        self.cls[[ord(c) for c in chars]] = np.arange(1, len(chars) + 1)
        code = {c: i for i, c in enumerate(chars, 1)}
        step, ids = {}, [-1]
        for p, (i, _) in pieces.items():
            s = 0
            for c in p:
                k = (s << 20) | code[c]
                s = step.setdefault(k, len(ids))
                if s == len(ids):
                    ids.append(-1)
            ids[s] = i
        self.piece = np.array(ids, np.int32)
        keys = np.array(sorted(step), np.int64)
        to = np.array([step[k] for k in keys.tolist()], np.int32)
        self.dense = np.zeros((len(ids), self.COMMON), np.int32)
        c = keys & 0xFFFFF
        near = c < self.COMMON
        self.dense[keys[near] >> 20, c[near]] = to[near]
        self.keys, self.to = keys[~near], to[~near]

    def step(self, state: np.ndarray, cls: np.ndarray) -> np.ndarray:
        """Next states, 0 where there is none."""
        near = cls < self.COMMON
        if near.all():
            return self.dense[state, cls]
        out = np.zeros(len(state), np.int32)
        out[near] = self.dense[state[near], cls[near]]
        far = ~near
        k = (state[far].astype(np.int64) << 20) | cls[far]
        at = np.minimum(np.searchsorted(self.keys, k), max(0, len(self.keys) - 1))
        if len(self.keys):
            out[far] = np.where(self.keys[at] == k, self.to[at], 0)
        return out


class Lattices:
    """Filtered lattices of units in flat arrays.

    A unit's nodes are the places between its characters.  A node's edges lie together from ``first[node]`` (-1 at the unit's start):
    ``cum`` is the running probability of the pieces that end there, ``back`` the node where the piece begins, ``emit`` its id, or
    -1 - code point for a character in no piece, which becomes its UTF-8 byte pieces.
    """

    def __init__(self, path: str = MODEL, theta: float = THETA):
        self.pieces, self.bytes, self.raw, self.longest = vocabulary(path)
        if path not in _tries:
            logp = np.zeros(len(self.raw))
            for i, p in self.pieces.values():
                logp[i] = p
            _tries[path] = (PieceTrie(self.pieces), logp)
        self.trie, self.logp = _tries[path]
        self.theta = theta
        self.clear()

    def clear(self):
        self.end: dict[str, int] = {}
        self.nodes = self.n = 0
        self.first = np.empty(0, np.int32)
        self.cum, self.back, self.emit = np.empty(0, np.float32), np.empty(0, np.int32), np.empty(0, np.int32)

    def _put(self, name: str, at: int, x: np.ndarray) -> None:
        old = getattr(self, name)
        if at + len(x) > len(old):
            grown = np.empty(max(at + len(x), len(old) * 3 // 2), old.dtype)
            grown[:at] = old[:at]
            setattr(self, name, old := grown)
        old[at : at + len(x)] = x

    def add(self, units: list[str]) -> None:
        """Filter the lattices of new units together."""
        text = np.frombuffer("".join(units).encode("utf-32-le", "surrogatepass"), np.uint32)
        length = np.array([len(u) for u in units], np.int64)
        n, unit = len(text), np.repeat(np.arange(len(units)), length)
        stop = np.cumsum(length)
        begin = stop - length
        limit, cls = stop[unit], self.trie.cls[text]
        starts, ends, ids = [], [], []
        alive, state = np.arange(n), np.zeros(n, np.int32)
        single = np.zeros(n, bool)
        for d in range(1, self.longest + 1):
            state = self.trie.step(state, cls[alive + (d - 1)])
            ok = state > 0
            alive, state = alive[ok], state[ok]
            piece = self.trie.piece[state]
            has = piece >= 0
            starts.append(alive[has])
            ends.append(alive[has] + d)
            ids.append(piece[has])
            if d == 1:
                single[alive[has]] = True
            ok = alive + d < limit[alive]
            alive, state = alive[ok], state[ok]
            if not len(alive):
                break
        odd = np.nonzero(~single)[0]
        cp = text[odd].astype(np.int64)
        n_bytes = 1 + (cp > 0x7F) + (cp > 0x7FF) + (cp > 0xFFFF)
        starts.append(odd)
        ends.append(odd + 1)
        logs = np.concatenate([self.logp[np.concatenate(ids)], BYTE_LOGP * n_bytes]) * self.theta
        emit = np.concatenate([*ids, (-1 - cp).astype(np.int32)])
        start, end = np.concatenate(starts), np.concatenate(ends)
        level = end - begin[unit[start]]
        order = np.argsort(level * (n + 1) + end, kind="stable")
        start, end, level, logs, emit = start[order], end[order], level[order], logs[order], emit[order]
        u = unit[start]
        back, node = start + u, end + u  # within this call; unit k has length[k] + 1 nodes
        head = np.concatenate([[True], node[1:] != node[:-1]])
        at = np.nonzero(head)[0]
        group = np.cumsum(head) - 1
        first = np.full(n + len(units), -1, np.int32)
        first[node[at]] = self.n + at
        alpha = np.zeros(n + len(units))
        cum = np.empty(len(node))
        bounds = np.searchsorted(level, np.arange(1, int(length.max()) + 2))
        for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            g0 = group[lo]
            heads = at[g0 : group[hi - 1] + 1] - lo
            own = group[lo:hi] - g0
            w = alpha[back[lo:hi]] + logs[lo:hi]
            top = np.maximum.reduceat(w, heads)
            e = np.exp(w - top[own])
            run = np.cumsum(e)
            before = run[heads] - e[heads]
            total = np.add.reduceat(e, heads)
            cum[lo:hi] = (run - before[own]) / total[own]
            alpha[node[at[g0 : g0 + len(heads)]]] = top + np.log(total)
        cum[np.concatenate([at[1:] - 1, [len(cum) - 1]])] = 2.0
        self._put("first", self.nodes, first)
        for name, x in (("cum", cum), ("back", back + self.nodes), ("emit", emit)):
            self._put(name, self.n, x)
        self.end.update(zip(units, (stop + np.arange(len(units)) + self.nodes).tolist(), strict=True))
        self.n += len(node)
        self.nodes += n + len(units)

    def split(self, unit: str) -> list[str]:
        """A unit cut where no piece reaches over: its lattice falls apart there, so long runs without spaces are filtered and drawn side by side."""
        text = np.frombuffer(unit.encode("utf-32-le", "surrogatepass"), np.uint32)
        cls, n = self.trie.cls[text], len(text)
        over = np.zeros(n + 1, np.int64)
        alive, state = np.arange(n), np.zeros(n, np.int32)
        for d in range(1, self.longest + 1):
            state = self.trie.step(state, cls[alive + (d - 1)])
            ok = state > 0
            alive, state = alive[ok], state[ok]
            if d > 1:  # a piece over s .. s + d bars the places between
                s = alive[self.trie.piece[state] >= 0]
                np.add.at(over, s + 1, 1)
                np.add.at(over, s + d, -1)
            ok = alive + d < n
            alive, state = alive[ok], state[ok]
            if not len(alive):
                break
        cuts = np.nonzero(np.cumsum(over)[1:n] == 0)[0] + 1
        return [unit[a:b] for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), n], strict=True)]

    def sample(self, texts: list[str], keys: np.ndarray, seed: int) -> tuple[np.ndarray, np.ndarray]:
        """Piece ids of all texts in a row, and how many each has."""
        if self.n > MAX_EDGES:
            self.clear()
        per_text = [[x for u in UNIT.findall(" " + t) for x in (self.split(u) if len(u) > LONG else (u,))] for t in texts]
        sizes = np.array([len(x) for x in per_text], np.int64)
        units = [u for x in per_text for u in x]
        if not units:
            return np.empty(0, np.int32), np.zeros(len(texts), np.int64)
        if new := set(units).difference(self.end):
            self.add(sorted(new))
        at = np.fromiter(map(self.end.__getitem__, units), np.int64, len(units))
        nth = np.arange(len(at)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        base = np.repeat(C.mix(keys.astype(np.int64).view(np.uint64) + np.uint64(seed)), sizes) + nth.astype(np.uint64) * np.uint64(0xD1B54A32D192ED03)
        steps = np.zeros(len(at), np.int64)
        alive, who, out = np.arange(len(at)), [], []
        k = 0
        while len(alive):
            u = (C.mix(base + np.uint64((k + 1) * 0x9E3779B97F4A7C15 & C.MASK)) >> np.uint64(11)).astype(np.float64) * 2.0**-53
            e = self.first[at]
            low = np.nonzero(self.cum[e] <= u)[0]
            while len(low):
                e[low] += 1
                low = low[self.cum[e[low]] <= u[low]]
            who.append(alive)
            out.append(self.emit[e])
            at = self.back[e]
            k += 1
            more = self.first[at] >= 0
            steps[alive[~more]] = k
            alive, at, base = alive[more], at[more], base[more]
        total = np.cumsum(steps)
        ids = np.empty(int(total[-1]), np.int32)
        for k, (w, x) in enumerate(zip(who, out, strict=True)):
            ids[total[w] - 1 - k] = x
        per = np.diff(np.concatenate([[0], total])[np.concatenate([[0], np.cumsum(sizes)])])
        return self._bytes(ids, per)

    def _bytes(self, ids: np.ndarray, per: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Expand characters in no piece to their byte pieces."""
        odd = np.nonzero(ids < 0)[0]
        if not len(odd):
            return ids, per
        cp = -1 - ids[odd].astype(np.int64)
        width = np.ones(len(ids), np.int64)
        width[odd] = 1 + (cp > 0x7F) + (cp > 0x7FF) + (cp > 0xFFFF)
        place = np.cumsum(width) - width
        out = np.repeat(ids, width)
        for c in np.unique(cp).tolist():
            where = place[odd[cp == c]]
            for j, b in enumerate(chr(c).encode("utf-8", "surrogatepass")):
                out[where + j] = self.bytes[b]
        ends = np.concatenate([place, [len(out)]])[np.concatenate([[0], np.cumsum(per)])]
        return out, np.diff(ends)


def decode(ids, raw: list[bytes]) -> str:
    """The text behind piece ids; the leading space goes."""
    return b"".join(map(raw.__getitem__, ids))[1:].decode("utf-8", "surrogatepass")


def _slices(whole: pa.RecordBatch):
    """Rows that are drawn together: at most ``ROWS``, and no more after ``CHARS`` bytes of text."""
    size = pc.fill_null(pc.binary_length(whole.column(1)), 0).to_numpy().astype(np.int64)
    lo = 0
    while lo < whole.num_rows:
        some = np.cumsum(size[lo : lo + ROWS])
        n = min(len(some), int(np.searchsorted(some, CHARS)) + 1)
        yield whole.slice(lo, n)
        lo += n


def _encode(batches, path, seed, theta, with_text):
    lat = Lattices(path, theta)
    fields = [("doc_id", pa.int64()), ("n_pieces", pa.int64()), ("ids", pa.list_(pa.int32())), ("lossless", pa.bool_())]
    schema = pa.schema(fields + ([("decoded", pa.string())] if with_text else []))
    for whole in batches:
        for r in _slices(whole):
            texts = r.column(1).to_pylist()
            keys = r.column(0).fill_null(0).to_numpy()
            there = [i for i, t in enumerate(texts) if t is not None]
            ids, per = lat.sample([texts[i] for i in there], keys[there], seed)
            count = np.zeros(len(texts), np.int64)
            count[there] = per
            offsets = np.concatenate([[0], np.cumsum(count)])
            plain = ids.tolist()
            back = [None if t is None else decode(plain[a:b], lat.raw) for t, a, b in zip(texts, offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
            off = pa.array(offsets.astype(np.int32), pa.int32(), mask=np.concatenate([np.array([t is None for t in texts], bool), [False]]))
            cols = [r.column(0), pa.array(count), pa.ListArray.from_arrays(off, pa.array(ids)), pa.array([None if t is None else t == b for t, b in zip(texts, back, strict=True)], pa.bool_())]
            yield C.batch(schema, *cols, *([pa.array(back, pa.string())] if with_text else []))


def encode(docs: DataFrame, model: str = MODEL, seed: int = 7, theta: float = THETA, decoded: bool = False) -> DataFrame:
    """Per row: doc_id, n_pieces, ids array<int>, lossless (the decoded ids equal the text), and the decoded text if asked for."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").transform(C.arrow, partial(_encode, path=model, seed=seed, theta=theta, with_text=decoded), "doc_id long, n_pieces long, ids array<int>, lossless boolean" + ", decoded string" * decoded)


def decode_ids(df: DataFrame, model: str = MODEL, ids: str = "ids") -> DataFrame:
    """doc_id and text of encoded rows."""

    def run(batches):
        raw = vocabulary(model)[2]
        schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string())])
        for r in batches:
            yield C.batch(schema, r.column(0), pa.array([None if x is None else decode(x, raw) for x in r.column(1).to_pylist()], pa.string()))

    return df.select("doc_id", ids).transform(C.arrow, run, "doc_id long, text string")


def op1(spark, sf_dir):
    return encode(C.table(spark, sf_dir, "documents", "doc_id", "text"))
