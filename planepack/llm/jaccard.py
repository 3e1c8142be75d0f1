"""N-gram Jaccard join by a prefix tree over globally ordered n-gram sets.

A document becomes its set of n-word shingles (64-bit hashes).  Two documents link when
``den * |x & y| >= num * |x | y|``.  :func:`jaccard_components` returns the connected components of all links and, on demand,
the number of links of every row; :func:`jaccard_links` returns the links themselves, between one document of each set.

1. Every document is reduced to (size, fingerprint of the set).  Documents with equal sets are one node.
2. Nodes that could link are brought together by an exact signature: inside a size band the hash space is cut
   into parts; linked sets differ in at most K elements, so among the first K + 1 non-empty parts (in the order
   of the parts' own hashes) at least one is equal.  A set with too few non-empty parts for that argument
   also emits its first K + 1 single n-grams; a pair of such sets shares one of those.  A signature that many sets of a batch
   have sends one row for them all, so a hot one sends a row a batch.  Sets that share a signature are then held against
   each other's sizes and parity sketches, which bound the difference from below: most chance meetings (a shared
   passage) end here.
3. Components of the signature graph (a superset of the links) bound which sets have to meet.  One task gets the
   sets of a component; a component above ``block_tokens`` n-grams is cut into blocks and every pair of blocks
   meets, so memory stays bounded and no link is lost.
4. There the sets, ordered rarest n-gram first, are laid out as a prefix tree (lexicographic order plus the
   lengths of common prefixes).  A query walks it by depth: rows below one node share the overlap counted for
   that node, and subtrees whose remaining lengths cannot reach the required overlap are pruned.  For components alone
   the walk visits only sets that are not in the query's component yet and emits a spanning forest.  For links every
   set is held against all sets behind it, so each pair is found once: inside a block by the task of that block, across blocks by
   the task of the two.  Counts leave a task as one row a set, so the pairs of a large group are never rows.

Defined results: null, empty or blank text has no n-grams, size 0, and is a component of its own; with fewer than n words
the whole sequence is the one n-gram; repeated rows give repeated result rows; a null id links, but is never a
component's id unless all its ids are null.
"""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common as C

LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
#: Distinct words whose hashes a worker keeps.
WORD_CACHE = 200_000


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= WORD_CACHE:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def shingles(text: bytes | None, n: int, hashes: WordHashes) -> np.ndarray:
    """Sorted distinct n-gram hashes of a UTF-8 text; words are what ASCII white space separates."""
    words = text.translate(LOWER).split() if text else []
    if not words:
        return np.empty(0, np.uint64)
    w = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    k = min(n, len(w))
    h = np.full(len(w) - k + 1, k, np.uint64)
    for i in range(k):
        h = h * np.uint64(0x9E3779B97F4A7C15) + w[i : len(w) - k + 1 + i]
    return np.unique(C.mix(h))


def fingerprint(s: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(s.tobytes()) >> 1


def band_edges(top: int) -> list[int]:
    e = [1]
    while e[-1] <= top:
        e.append(max(e[-1] + 1, e[-1] * 3 // 2))
    return e


def signatures(s: np.ndarray, num: int, den: int) -> np.ndarray:
    """Signatures of a set: two sets that link have at least one in common."""
    n, cs = len(s), np.concatenate([np.zeros(1, np.uint64), np.cumsum(C.mix(s))])
    edges, out = band_edges(n), []
    own = len(edges) - 2
    for b in range(own, -1, -1):
        most = min(n, edges[b + 1] - 1)
        if b < own and most * den < num * n:
            break  # no set of this band is large enough to link with this one
        k = most * (den - num) // num
        top = (edges[b + 1] - 1) * (den - num) // num
        parts = top + (top * 7 + 19) // 20 + 2 if top else 1
        at = ((s >> np.uint64(32)) * np.uint64(parts)) >> np.uint64(32)
        first = np.nonzero(np.concatenate([[True], at[1:] != at[:-1]]))[0]
        sums = np.diff(np.concatenate([cs[first], cs[-1:]]))
        sig = np.sort(C.mix(sums ^ C.mix(at[first] + np.uint64((b + 1) << 32))))
        out.append(sig[: k + 1])
        if len(sig) <= k:
            out.append(C.mix(s[: k + 1] ^ np.uint64(0xA5A5A5A500000000 + b)))
    return np.concatenate(out)


def _texts(r: pa.RecordBatch, i: int) -> list:
    col = r.column(i)
    return col.cast(pa.large_binary()).to_pylist()


#: Members of one signature in a batch from which they travel as one row, and members of a signature that are compared by sketches.
HOT, GROUP = 64, 20_000


def sketch(s: np.ndarray) -> bytes:
    """Parity of the n-grams per hash bucket, as many buckets as the power of two above the set's size.

    Two sets differ in at least as many n-grams as their sketches in bits; halving a sketch by xor gives the smaller one.
    """
    size = 64
    while size < len(s) and size < 65536:
        size *= 2
    odd = np.bincount((s & np.uint64(size - 1)).astype(np.int64), minlength=size) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def sketch_forest(sizes: np.ndarray, sketches: list[bytes], num: int, den: int) -> list[tuple[int, int]]:
    """Spanning links of the sets that their sizes and sketches do not keep apart: a superset of the true links."""
    words = min(map(len, sketches)) // 8
    m = np.empty((len(sketches), words), np.uint64)
    for i, x in enumerate(sketches):
        v = np.frombuffer(x, np.uint64)
        while len(v) > words:
            v = v[: len(v) // 2] ^ v[len(v) // 2 :]
        m[i] = v
    left, out = np.arange(1, len(sketches)), []
    todo = [0]
    while len(left):
        if not todo:
            todo, left = [int(left[0])], left[1:]
            continue
        q = todo.pop()
        n, k = sizes[left], sizes[q]
        near = (np.bitwise_count(m[left] ^ m[q]).sum(1) * (den + num) <= (n + k) * (den - num)) & (np.minimum(n, k) * den >= np.maximum(n, k) * num)
        for y in left[near].tolist():
            todo.append(y)
            out.append((q, y))
        left = left[~near]
    return out


def _sizes(batches, n):
    hashes = WordHashes()
    schema = pa.schema([("__id", pa.int64()), ("__n", pa.int64()), ("__fp", pa.int64()), ("__sketch", pa.binary())])
    for r in batches:
        sizes, fps, marks = [], [], []
        for t in _texts(r, 1):
            s = shingles(t, n, hashes)
            sizes.append(len(s))
            fps.append(fingerprint(s) if len(s) else None)
            marks.append(sketch(s) if len(s) else None)
        yield C.batch(schema, r.column(0), pa.array(sizes, pa.int64()), pa.array(fps, pa.int64()), pa.array(marks, pa.binary()))


_SIG = pa.schema([("sig", pa.int64()), ("a", pa.int64()), ("b", pa.int64())])
#: Documents whose signatures are sorted together before they leave a task.
BATCH = 2500


def _signed(batches, n, num, den):
    """(sig, node, null); (sig, node, node) where a node stands for many of its batch, and then (null, node, node) for those."""
    hashes = WordHashes()
    for whole in batches:
        for r in (whole.slice(lo, BATCH) for lo in range(0, whole.num_rows, BATCH)):
            sigs, fps, seen = [], [], set()
            for t in _texts(r, 0):
                s = shingles(t, n, hashes)
                if len(s) and (fp := fingerprint(s)) not in seen:
                    seen.add(fp)
                    x = signatures(s, num, den)
                    sigs.append(x)
                    fps.append(np.full(len(x), fp, np.int64))
            if not sigs:
                continue
            sig, fp = np.concatenate(sigs), np.concatenate(fps)
            order = np.argsort(sig, kind="stable")
            sig, fp = sig[order], fp[order]
            first = np.nonzero(np.concatenate([[True], sig[1:] != sig[:-1]]))[0]
            many = np.diff(np.concatenate([first, [len(sig)]]))
            hot = np.repeat(many >= HOT, many)
            lead = np.repeat(first, many)
            keep = ~hot | (lead == np.arange(len(sig)))
            yield C.batch(_SIG, sig[keep].view(np.int64), fp[keep], pa.array(fp[keep], mask=~hot[keep]))
            if not keep.all():
                pairs = np.unique(np.stack([fp[lead[~keep]], fp[~keep]]), axis=1)
                yield C.batch(_SIG, pa.nulls(pairs.shape[1], pa.int64()), pairs[0], pairs[1])


_MET = pa.schema([("g", pa.int64()), ("a", pa.int64()), ("b", pa.int64())])


def _met(batches):
    """Nodes that share a signature: (null, node, node) edges, or (group, node, null) members of a group still to be compared.

    Groups with equal members are one group.  The task's share of signatures is bounded by how many partitions there are.
    """
    sig, node, stands, ea, eb = [], [], [], [np.empty(0, np.int64)], [np.empty(0, np.int64)]
    for r in batches:
        s, x, y = r.column(0), r.column(1).to_numpy(), r.column(2)
        edge = s.is_null().to_numpy(zero_copy_only=False)
        if edge.any():
            ea.append(x[edge])
            eb.append(y.fill_null(0).to_numpy()[edge])
        sig.append(s.drop_null().to_numpy())
        node.append(x[~edge])
        stands.append(y.is_valid().to_numpy(zero_copy_only=False)[~edge])
    if not sig:
        return
    s, x, h = np.concatenate(sig), np.concatenate(node), np.concatenate(stands)
    order = np.lexsort((~h, x, s))
    s, x, h = s[order], x[order], h[order]
    new = np.concatenate([[True], (s[1:] != s[:-1]) | (x[1:] != x[:-1])]) if len(s) else np.empty(0, bool)
    s, x, h = s[new], x[new], h[new]
    first = np.nonzero(np.concatenate([[True], s[1:] != s[:-1]]))[0] if len(s) else np.empty(0, np.int64)
    many = np.diff(np.concatenate([first, [len(s)]]))
    whole = np.logical_or.reduceat(h, first) | (many > GROUP) if len(s) else np.empty(0, bool)
    seen, gids, members = set(), [], []
    for i, k, chain in zip(first[many > 1].tolist(), many[many > 1].tolist(), whole[many > 1].tolist(), strict=True):
        m = x[i : i + k]
        if (g := xxhash.xxh3_64_intdigest(m.tobytes()) >> 1) in seen:
            continue
        seen.add(g)
        if chain:
            ea.append(m[:-1])
            eb.append(m[1:])
        else:
            gids.append((g, k))
            members.append(m)
    lo, hi = np.concatenate(ea), np.concatenate(eb)
    if len(lo):
        a, b = C.union_forest(*np.unique(np.stack([lo, hi]), axis=1))
        yield C.batch(_MET, pa.nulls(len(a), pa.int64()), a, b)
    if gids:
        g = np.repeat(np.array([g for g, _ in gids], np.int64), [k for _, k in gids])
        yield C.batch(_MET, g, np.concatenate(members), pa.nulls(len(g), pa.int64()))


def _compared(batches, num, den):
    """Groups arrive sorted: (g, node, size, sketch) -> edges that sizes and sketches allow."""
    key, nodes, sizes, marks = None, [], [], []

    def edges():
        pairs = sketch_forest(np.array(sizes), marks, num, den) if len(nodes) > 1 else []
        return [nodes[i] for i, _ in pairs], [nodes[j] for _, j in pairs]

    a, b = [], []
    for r in batches:
        for g, node, n, mark in zip(*(r.column(i).to_pylist() for i in range(4)), strict=True):
            if g != key:
                for x, y in zip((a, b), edges(), strict=True):
                    x += y
                key, nodes, sizes, marks = g, [], [], []
            nodes.append(node)
            sizes.append(n)
            marks.append(mark)
        if len(a) > 100_000:
            yield C.batch(C._EDGE, *C.union_forest(np.array(a), np.array(b)))
            a, b = [], []
    for x, y in zip((a, b), edges(), strict=True):
        x += y
    if a:
        yield C.batch(C._EDGE, *C.union_forest(np.array(a), np.array(b)))


class PrefixTree:
    """Sets in one prefix tree: dense n-gram numbers, rarest first, rows in lexicographic order with common-prefix lengths."""

    def __init__(self, sets: list[np.ndarray], num: int, den: int):
        self.num, self.den = num, den
        tokens, at, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        rank = np.empty(len(tokens), np.int64)
        rank[np.lexsort((tokens, count))] = np.arange(len(tokens))
        at = rank[at]
        ends = np.cumsum([len(s) for s in sets])
        rows = [np.sort(x) for x in np.split(at, ends[:-1])]
        self.order = sorted(range(len(rows)), key=lambda i: rows[i].astype(">u4").tobytes())
        rows = [rows[i] for i in self.order]
        self.len = np.array([len(x) for x in rows])
        self.start = np.concatenate([[0], np.cumsum(self.len)[:-1]])
        self.flat = np.concatenate(rows)
        self.lcp = np.zeros(len(rows), np.int64)
        for i in range(1, len(rows)):
            m = min(len(rows[i]), len(rows[i - 1]))
            ne = rows[i][:m] != rows[i - 1][:m]
            j = int(ne.argmax()) if m else 0
            self.lcp[i] = j if m and ne[j] else m
        self.has = np.zeros(len(tokens), bool)
        self._post(np.arange(len(rows)))

    def _post(self, rows: np.ndarray) -> None:
        """Where each n-gram stands in the prefixes of the given rows."""
        take = self.len[rows] - -(-self.num * self.len[rows] // self.den) + 1
        who = np.repeat(rows, take)
        at = np.repeat(self.start[rows], take) + np.arange(len(who)) - np.repeat(np.cumsum(take) - take, take)
        tok = self.flat[at]
        order = np.argsort(tok, kind="stable")
        self.tok, self.who = tok[order], who[order]

    def candidates(self, q: int, fresh: np.ndarray) -> np.ndarray:
        n = int(self.len[q])
        mine = self.flat[self.start[q] : self.start[q] + n - -(-self.num * n // self.den) + 1]
        lo, hi = np.searchsorted(self.tok, mine), np.searchsorted(self.tok, mine, "right")
        full = hi > lo
        if not full.any():
            return np.empty(0, np.int64)
        met = np.zeros(len(fresh), bool)
        for i, j in zip(lo[full], hi[full], strict=True):
            met[self.who[i:j]] = True
        c = np.nonzero(met & fresh)[0]
        m = self.len[c]
        return c[(self.den * np.minimum(m, n) >= self.num * np.maximum(m, n))]

    def linked(self, q: int, rows: np.ndarray) -> np.ndarray:
        """Rows (ascending) that link with q: a walk by depth that shares overlaps and prunes by remaining lengths."""
        n = int(self.len[q])
        mine = self.flat[self.start[q] : self.start[q] + n]
        self.has[mine] = True
        need = -(-self.num * (n + self.len[rows]) // (self.num + self.den))
        low = np.zeros(len(rows), np.int64)
        if len(rows) > 1:
            cut = np.minimum.reduceat(self.lcp, np.stack([rows[:-1] + 1, rows[1:] + 1], 1).ravel()[:-1]) if rows[-1] + 1 >= len(self.lcp) else np.minimum.reduceat(self.lcp, np.stack([rows[:-1] + 1, rows[1:] + 1], 1).ravel())
            low[1:] = cut[::2]
        overlap, depth, step = np.zeros(len(rows), np.int64), 0, 16
        out = []
        while len(rows):
            length = self.len[rows]
            upto = np.minimum(length, depth + step)
            lead = np.concatenate([[True], low[1:] < upto[1:]]) | (upto != np.concatenate([[0], upto[:-1]]))
            ids = np.nonzero(lead)[0]
            take = upto[ids] - depth
            at = np.repeat(self.start[rows[ids]] + depth, take) + np.arange(int(take.sum())) - np.repeat(np.cumsum(take) - take, take)
            sums = np.concatenate([[0], np.cumsum(self.has[self.flat[at]])])
            ends = np.cumsum(take)
            overlap += (sums[ends] - sums[ends - take])[np.cumsum(lead) - 1]
            depth += step
            step *= 2
            done = upto == length
            out.append(rows[done & (overlap >= need)])
            alive = ~done & (overlap + np.minimum(length - upto, n - overlap) >= need)
            if not alive.all():
                at = np.nonzero(alive)[0]
                if len(at):
                    starts = np.concatenate([[0], at[:-1] + 1])
                    low = np.minimum.reduceat(low, starts)
                    low[0] = 0
                rows, overlap, need = rows[at], overlap[at], need[at]
                low = low[: len(rows)]
        self.has[mine] = False
        return np.concatenate(out) if out else rows

    def forest(self) -> list[tuple[int, int]]:
        """Links that span the components, as positions in the input list."""
        m, out = len(self.order), []
        fresh, left = np.ones(m, bool), m
        posted = m
        for seed in range(m):
            if not fresh[seed]:
                continue
            fresh[seed] = False
            left -= 1
            todo = [seed]
            while todo and left:
                q = todo.pop()
                if posted > 64 and left < posted // 2:
                    self._post(np.nonzero(fresh)[0])
                    posted = left
                c = self.candidates(q, fresh)
                if len(c):
                    for y in self.linked(q, c).tolist():
                        fresh[y] = False
                        left -= 1
                        todo.append(y)
                        out.append((self.order[q], self.order[y]))
            if not left:
                break
        return out

    def links(self, sides: np.ndarray | None = None):
        """Every link once: (position, positions of its partners) in the input list.  With ``sides`` (per input set), only links across them."""
        m, order = len(self.order), np.array(self.order)
        side = None if sides is None else np.asarray(sides)[order]
        behind, posted = np.ones(m, bool), m
        for q in range(m - 1):
            behind[q] = False
            left = m - 1 - q
            if posted > 64 and left < posted // 2:
                self._post(np.arange(q + 1, m))
                posted = left
            c = self.candidates(q, behind if side is None else behind & (side != side[q]))
            if len(c):
                y = self.linked(q, c)
                if len(y):
                    yield int(order[q]), order[y]


_LINK = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("n", pa.int64())])
#: Links that leave a task together.
LINKS = 100_000


def _tree_forest(fps, sets, sides, copies, num, den):
    pairs = PrefixTree(sets, num, den).forest()
    if pairs:
        yield C.batch(_LINK, fps[[i for i, _ in pairs]], fps[[j for _, j in pairs]], pa.nulls(len(pairs), pa.int64()))


def _tree_counts(fps, sets, sides, copies, num, den):
    """(node, node, null): links that span the components; (node, null, n): linked documents of each set in this tree."""
    up, n, a, b = np.arange(len(sets)), np.zeros(len(sets), np.int64), [], []
    for q, y in PrefixTree(sets, num, den).links(sides):
        n[q] += copies[y].sum()
        n[y] += copies[q]
        roots = set()
        for r in np.unique(up[np.append(y, q)]).tolist():
            while up[r] != r:
                r = int(up[r])
            roots.add(r)
        least = min(roots)
        rest = sorted(roots - {least})
        a += [least] * len(rest)
        b += rest
        up[rest] = least
        up[y] = least
        up[q] = least
    own = np.nonzero(n)[0]
    if len(own):
        yield C.batch(_LINK, fps[a], fps[b], pa.nulls(len(a), pa.int64()))
        yield C.batch(_LINK, fps[own], pa.nulls(len(own), pa.int64()), n[own])


def _tree_links(fps, sets, sides, copies, num, den):
    a, b, k = [], [], 0
    for q, y in PrefixTree(sets, num, den).links(sides):
        a.append(np.full(len(y), fps[q]))
        b.append(fps[y])
        k += len(y)
        if k > LINKS:
            yield C.batch(_LINK, np.concatenate(a), np.concatenate(b), pa.nulls(k, pa.int64()))
            a, b, k = [], [], 0
    if k:
        yield C.batch(_LINK, np.concatenate(a), np.concatenate(b), pa.nulls(k, pa.int64()))


def _joined(batches, n, num, den, tree):
    """Groups arrive sorted: (key, node, block, across, copies, text); each is one prefix tree."""
    hashes = WordHashes()

    def solve(sets, across):
        if len(sets) > 1:
            fps = np.array(list(sets), np.int64)
            own, sides, copies = zip(*sets.values(), strict=True)
            yield from tree(fps, list(own), np.array(sides) if across else None, np.array(copies, np.int64), num, den)

    key, sets, across = None, {}, False
    for r in batches:
        for k, fp, side, cross, c, text in zip(*(r.column(i).to_pylist() for i in range(5)), _texts(r, 5), strict=True):
            if k != key:
                yield from solve(sets, across)
                key, sets, across = k, {}, cross
            if fp not in sets:
                s = shingles(text, n, hashes)
                if len(s) and fingerprint(s) == fp:
                    sets[fp] = s, side, c
    yield from solve(sets, across)


def _searched(docs, id_col, text_col, n, num, den, block_tokens, local_edges, tree):
    """Rows with size and fingerprint, one row for each set, and what ``tree`` gives for all sets that could link."""
    if not 0 < num <= den or 2 * num <= den:
        raise ValueError("the threshold must lie above 1/2 and up to 1")
    base = docs.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).alias("__text"))
    sizes = C.written(base.transform(C.arrow, partial(_sizes, n=n), "__id long, __n long, __fp long, __sketch binary"), "sizes")
    total, rows = sizes.agg(F.coalesce(F.sum("__n"), F.lit(0)), F.count(F.lit(1))).first()
    per = max(1, round(total * (den - num) / num * 1.3))
    parts = max(8, -(-per // 1_000_000))
    sigs = base.select("__text").transform(C.arrow, partial(_signed, n=n, num=num, den=den), "sig long, a long, b long")
    met = C.written(sigs.repartition(parts, F.coalesce("sig", "a")).transform(C.arrow, _met, "g long, a long, b long"), "met")
    nodes = sizes.filter("__fp is not null").groupBy(F.col("__fp").alias("node")).agg(F.min("__id").alias("__id"), F.first("__n").alias("__n"), F.first("__sketch").alias("__sketch"), F.count(F.lit(1)).alias("__copies"))
    pending = met.filter("g is not null").select("g", F.col("a").alias("node")).distinct().join(nodes.select("node", "__n", "__sketch"), "node").select("g", "node", "__n", "__sketch")
    compared = pending.repartition("g").sortWithinPartitions("g").transform(C.arrow, partial(_compared, num=num, den=den), "a long, b long")
    near = C.components(met.filter("g is null").select("a", "b").union(compared), local_edges)
    C.forget(met)
    members = near.join(nodes.drop("__sketch"), "node")
    members = C.written(members, "members")
    heavy = members.groupBy("root").agg(F.sum("__n").alias("__sum")).filter(F.col("__sum") > block_tokens).select("root", F.ceil(F.col("__sum") * 2 / block_tokens).cast("int").alias("__blocks"))
    n_members = members.count()
    placed = members.join(F.broadcast(heavy) if n_members <= C.BROADCAST_ROWS else heavy, "root", "left")
    blk = F.pmod(F.xxhash64("node"), F.col("__blocks")).cast("int")
    groups = F.when(F.col("__blocks").isNull(), F.array(F.lit("")).cast("array<string>")).otherwise(
        F.transform(F.sequence(F.lit(0), F.col("__blocks") - 1), lambda j: F.concat_ws("-", F.least(j, blk).cast("string"), F.greatest(j, blk).cast("string")))
    )
    pair = F.split("__group", "-")
    placed = placed.withColumn("__group", F.explode(groups)).select("__id", F.col("node").alias("__node"), F.concat_ws(":", F.col("root").cast("string"), "__group").alias("__key"), F.coalesce(blk, F.lit(0)).alias("__block"), ((F.size(pair) == 2) & (F.get(pair, F.lit(0)) != F.get(pair, F.lit(1)))).alias("__across"), "__copies")
    placed = placed.withColumn("__across", F.coalesce("__across", F.lit(False)))
    brought = base.filter("__text is not null").withColumn("__at", F.coalesce("__id", F.lit(-(1 << 62)))).join(C.small(placed.withColumn("__at", F.coalesce("__id", F.lit(-(1 << 62)))).drop("__id"), n_members), "__at")
    found = brought.select("__key", "__node", "__block", "__across", "__copies", "__text").repartition(max(8, min(2048, -(-n_members // 2000))), "__key").sortWithinPartitions("__key").transform(C.arrow, partial(_joined, n=n, num=num, den=den, tree=tree), "a long, b long, n long")
    return sizes, nodes, near, found


def jaccard_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = 3, num: int = 90, den: int = 100, block_tokens: int = 8_000_000, local_edges: int = C.LOCAL_EDGES, links: bool = False) -> DataFrame:
    """(id, n_shingles, component_id, n_class) per row of ``docs``; see the module's docstring.  ``num/den`` must exceed 1/2.

    ``n_class`` is the size of the component.  With ``links`` there is also ``n_links``: the other rows that this row links with.
    """
    sizes, nodes, near, found = _searched(docs, id_col, text_col, n, num, den, block_tokens, local_edges, _tree_counts if links else _tree_forest)
    found = C.written(found, "links") if links else found
    true = C.components(found.filter("b is not null").select("a", "b"), local_edges)
    n_true = true.count()
    # sets, not rows, meet on the component's key: however many copies a set has, it is one row there
    keyed = nodes.select(F.col("node").alias("__fp"), "__id", "__copies").join(C.small(true.select(F.col("node").alias("__fp"), F.col("root").alias("__root")), n_true), "__fp", "left").withColumn("__root", F.coalesce("__root", "__fp"))
    keyed = C.written(keyed, "keyed")
    least = C.written(keyed.groupBy("__root").agg(F.min("__id").alias("__least"), F.sum("__copies").alias("__c")).filter("__c > 1"), "least")
    own = keyed.join(C.small(least, least.count()), "__root").drop("__id", "__root")
    if links:
        others = found.filter("b is null").groupBy(F.col("a").alias("__fp")).agg(F.sum("n").alias("__links"))
        own = own.join(C.small(others, n_true), "__fp", "left")
    own = C.written(own, "own")
    C.forget(near)
    apart = F.coalesce("__fp", -1 - F.pmod(F.xxhash64("__id"), F.lit(1 << 40)))  # rows without a set find nothing, and not all in one task
    out = sizes.withColumn("__fp", apart).join(C.small(own, own.count()), "__fp", "left")
    cols = [F.col("__id").alias(id_col), F.col("__n").alias("n_shingles"), F.coalesce("__least", "__id").alias("component_id"), F.coalesce("__c", F.lit(1)).alias("n_class")]
    if links:
        cols.append((F.coalesce("__links", F.lit(0)) + F.coalesce(F.col("__copies") - 1, F.lit(0))).alias("n_links"))
    return out.select(*cols)


def jaccard_links(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = 3, num: int = 90, den: int = 100, block_tokens: int = 8_000_000, local_edges: int = C.LOCAL_EDGES) -> DataFrame:
    """(id_a, id_b, copies_a, copies_b): every link between two different sets once, each set by the smallest id of its documents."""
    _, nodes, near, found = _searched(docs, id_col, text_col, n, num, den, block_tokens, local_edges, _tree_links)
    found = C.written(found.select("a", "b"), "links")
    C.forget(near)
    end = lambda c: nodes.select(F.col("node").alias(c), F.struct(F.col("__id").isNull().alias("none"), F.col("__id").alias("id"), F.col("node").alias("node"), F.col("__copies").alias("copies")).alias(f"__{c}"))
    both = found.join(end("a"), "a").join(end("b"), "b")
    lo, hi = F.least("__a", "__b"), F.greatest("__a", "__b")
    return both.select(lo["id"].alias("id_a"), hi["id"].alias("id_b"), lo["copies"].alias("copies_a"), hi["copies"].alias("copies_b"))


def op2(spark, sf_dir):
    return jaccard_components(C.table(spark, sf_dir, "documents", "doc_id", "text"), links=True)


def _printed(batches, at, n):
    """The batch with the fingerprint of the text where its last column is true, in place of that column."""
    hashes = WordHashes()
    for r in batches:
        fps = [None] * r.num_rows
        for i, (wanted, t) in enumerate(zip(r.column(r.num_columns - 1).to_pylist(), _texts(r, at), strict=True)):
            if wanted and len(s := shingles(t, n, hashes)):
                fps[i] = fingerprint(s)
        yield pa.RecordBatch.from_arrays([*r.columns[:-1], pa.array(fps, pa.int64())], names=[*r.schema.names[:-1], "__fp"])


def drop_near_duplicates(docs: DataFrame, n: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """Keep one row of each component: the one with the smallest id (nulls last), then fingerprint, then hash of the row.

    A row is told by its id and its set, so rows that share an id are judged on their own texts; of repeated rows one stays.
    Rows without n-grams (null, empty or blank text) stay.  Further columns may have any name; an empty table stays empty.
    """
    names = docs.columns
    at, key = names.index("text"), names.index("doc_id")
    plain = docs.toDF(*(f"d{i}" for i in range(len(names))))  # names of the table cannot clash with those of the joins
    sizes, _, near, found = _searched(plain, f"d{key}", f"d{at}", n, num, den, 8_000_000, C.LOCAL_EDGES, _tree_forest)
    true = C.components(found.select("a", "b"))
    roots = C.small(true.select(F.col("node").alias("fp"), F.col("root").alias("__root")), true.count())
    rows = sizes.filter("__fp is not null").groupBy(F.col("__id").alias("id"), F.col("__fp").alias("fp")).agg(F.count(F.lit(1)).alias("__c")).join(roots, "fp", "left").withColumn("__root", F.coalesce("__root", "fp"))
    rows = C.written(rows, "rows")
    order = F.struct(F.col("id").isNull().alias("none"), F.coalesce("id", F.lit(0)).alias("id"), F.col("fp").alias("fp"))
    kept = C.written(rows.groupBy("__root").agg(F.min(order).alias("__kept"), F.sum("__c").alias("__all")).filter("__all > 1"), "kept")
    judged = rows.join(C.small(kept, kept.count()), "__root").select("id", "fp", (F.col("__kept") != order).alias("__gone"), "__c").filter("__gone or __c > 1")
    judged = C.written(judged, "judged")
    C.forget(near)
    count = judged.count()
    ids = C.small(judged.select(F.col("id").alias("__jid")).distinct().withColumn("__judged", F.lit(True)), count)
    own = F.col(f"d{key}").cast("long")
    marked = plain.join(ids, own.eqNullSafe(F.col("__jid")), "left").select(*plain.columns, F.coalesce("__judged", F.lit(False)).alias("__judged"))
    schema = T.StructType([*plain.schema.fields, T.StructField("__fp", T.LongType())])
    printed = marked.transform(C.arrow, partial(_printed, at=at, n=n), schema)
    verdict = C.small(judged.select(F.col("id").alias("__jid"), F.col("fp").alias("__jfp"), "__gone"), count)
    both = printed.join(verdict, (F.col("__fp") == F.col("__jfp")) & own.eqNullSafe(F.col("__jid")), "left")
    first = Window.partitionBy(f"d{key}", "__fp").orderBy(F.xxhash64(*plain.columns))
    repeated = both.filter("not __gone").withColumn("__row", F.row_number().over(first)).filter("__row = 1")
    return both.filter("__gone is null").select(*plain.columns).union(repeated.select(*plain.columns)).toDF(*names)


OP2_SQL = r"""
with recursive d as (select row_number() over () as rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
g as (select distinct rid, array_to_string(w[i : i + least(3, len(w)) - 1], ' ') as g from d, unnest(range(1, greatest(0, len(w) - least(3, len(w)) + 1) + 1)) t(i) where len(w) > 0),
n as (select rid, count(*) as n from g group by rid),
p as (select a.rid as a, b.rid as b from g a join g b on a.g = b.g join n x on x.rid = a.rid join n y on y.rid = b.rid where a.rid <> b.rid and 100 * least(x.n, y.n) >= 90 * greatest(x.n, y.n)
  group by a.rid, b.rid, x.n, y.n having 100 * count(*) >= 90 * (x.n + y.n - count(*))),
r(a, b) as (select rid, rid from d union select r.a, p.b from r join p on r.b = p.a),
c as (select r.a, min(d.doc_id) as least, count(*) as n_class from r join d on d.rid = r.b group by r.a)
select d.doc_id, cast(coalesce(n.n, 0) as bigint) as n_shingles, c.least as component_id, c.n_class, cast(coalesce(l.n_links, 0) as bigint) as n_links
from d left join n using (rid) join c on c.a = d.rid left join (select a, count(*) as n_links from p group by a) l on l.a = d.rid
"""
