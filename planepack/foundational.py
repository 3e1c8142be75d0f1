"""Foundational and float-specific codecs, written here.  They show ratios; the compiled codecs are the fast path."""

from __future__ import annotations

import heapq
import struct

import numpy as np

# ---------------------------------------------------------------- varints and bits


def _varint(n: int) -> bytes:
    out = bytearray()
    while n >= 0x80:
        out.append(n & 0x7F | 0x80)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(b: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        c = b[at]
        at += 1
        n |= (c & 0x7F) << shift
        if c < 0x80:
            return n, at
        shift += 7


class BitWriter:
    def __init__(self):
        self.value, self.n, self.out = 0, 0, bytearray()

    def put(self, v: int, bits: int) -> None:
        self.value = (self.value << bits) | v
        self.n += bits
        while self.n >= 8:
            self.n -= 8
            self.out.append(self.value >> self.n & 0xFF)
        self.value &= (1 << self.n) - 1

    def bytes(self) -> bytes:
        if self.n:
            self.out.append(self.value << (8 - self.n) & 0xFF)
            self.n = self.value = 0
        return bytes(self.out)


class BitReader:
    def __init__(self, b: bytes):
        self.b, self.at, self.value, self.n = b, 0, 0, 0

    def get(self, bits: int) -> int:
        while self.n < bits:
            self.value = self.value << 8 | (self.b[self.at] if self.at < len(self.b) else 0)
            self.at += 1
            self.n += 8
        self.n -= bits
        v = self.value >> self.n
        self.value &= (1 << self.n) - 1
        return v


# ---------------------------------------------------------------- LZ77


def lz77_encode(data: bytes, window: int = 65535, least: int = 4, chain: int = 16) -> bytes:
    """Literal runs and (length, distance) references; hash chains over 4-byte prefixes.  chain=1 is the greedy fast variant."""
    out, table, lit, i, n = bytearray(_varint(len(data))), {}, 0, 0, len(data)
    while i < n:
        best, where = 0, 0
        if i + least <= n:
            k = data[i : i + least]
            seen = table.get(k)
            if seen:
                for j in reversed(seen):
                    if i - j > window:
                        break
                    m = least
                    while i + m < n and m < 65535 and data[j + m] == data[i + m]:
                        m += 1
                    if m > best:
                        best, where = m, i - j
                seen.append(i)
                if len(seen) > chain:
                    del seen[0]
            else:
                table[k] = [i]
        if best >= least:
            out += _varint(i - lit) + data[lit:i] + _varint(best) + _varint(where)
            for j in range(i + 1, min(i + best, n - least), max(1, best // 8)):
                table.setdefault(data[j : j + least], []).append(j)
                if len(table[data[j : j + least]]) > chain:
                    del table[data[j : j + least]][0]
            i += best
            lit = i
        else:
            i += 1
    if lit < n:
        out += _varint(n - lit) + data[lit:]
    return bytes(out)


def lz77_decode(b: bytes) -> bytes:
    n, at = _read_varint(b, 0)
    out = bytearray()
    while len(out) < n:
        k, at = _read_varint(b, at)
        out += b[at : at + k]
        at += k
        if len(out) < n:
            m, at = _read_varint(b, at)
            d, at = _read_varint(b, at)
            for _ in range(-(-m // d)):
                out += out[len(out) - d : len(out) - d + min(d, m)]
                m -= min(d, m)
    return bytes(out)


# ---------------------------------------------------------------- Huffman


def huffman_lengths(counts) -> list[int]:
    heap = [(int(c), i, (i,)) for i, c in enumerate(counts) if c]
    length = [0] * len(counts)
    if len(heap) == 1:
        length[heap[0][1]] = 1
        return length
    heapq.heapify(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for s in a[2] + b[2]:
            length[s] += 1
        heapq.heappush(heap, (a[0] + b[0], min(a[1], b[1]), a[2] + b[2]))
    return length


def _canonical(length: list[int]) -> dict[int, tuple[int, int]]:
    code, prev, out = 0, 0, {}
    for ln, s in sorted((ln, s) for s, ln in enumerate(length) if ln):
        code <<= ln - prev
        out[s] = (code, ln)
        code, prev = code + 1, ln
    return out


def huffman_encode(data: bytes) -> bytes:
    """Canonical prefix code; the header has the code lengths of the symbols that occur."""
    x = np.frombuffer(data, np.uint8)
    length = huffman_lengths(np.bincount(x, minlength=256).tolist())
    used = [s for s in range(256) if length[s]]
    head = _varint(len(data)) + bytes([len(used) & 0xFF]) + b"".join(bytes([s, length[s]]) for s in used)
    if not len(x):
        return head
    codes = _canonical(length)
    bits = {s: np.array([c >> (ln - 1 - k) & 1 for k in range(ln)], np.uint8) for s, (c, ln) in codes.items()}
    size = np.array(length)[x]
    total = np.zeros(int(size.sum()), np.uint8)
    start = np.cumsum(size) - size
    for s, b in bits.items():
        at = start[x == s]
        for k, v in enumerate(b):
            total[at + k] = v
    return head + np.packbits(total).tobytes()


def huffman_decode(b: bytes) -> bytes:
    n, at = _read_varint(b, 0)
    if not n:
        return b""
    used = b[at] or 256
    at += 1
    length = [0] * 256
    for i in range(used):
        length[b[at + 2 * i]] = b[at + 2 * i + 1]
    at += 2 * used
    by_code = {(ln, c): s for s, (c, ln) in _canonical(length).items()}
    out, code, ln = bytearray(), 0, 0
    for bit in np.unpackbits(np.frombuffer(b[at:], np.uint8)).tolist():
        code, ln = code << 1 | bit, ln + 1
        s = by_code.get((ln, code))
        if s is not None:
            out.append(s)
            code = ln = 0
            if len(out) == n:
                break
    return bytes(out)


# ---------------------------------------------------------------- tANS


def tans_encode(data: bytes, log: int = 11) -> bytes:
    """Order-0 table entropy coding with a table of 2**log states."""
    x = np.frombuffer(data, np.uint8)
    if not len(x):
        return _varint(0)
    size = 1 << log
    freq = _normalise(np.bincount(x, minlength=256), size)
    enc = _tans_tables(freq, size)[0]
    state, bits = size, []
    for s in x[::-1].tolist():
        k = 0
        while (state >> k) >= 2 * freq[s]:
            k += 1
        bits.append((state & ((1 << k) - 1), k))
        state = enc[s][(state >> k) - freq[s]]
    w = BitWriter()
    for v, k in reversed(bits):
        w.put(v, k)
    used = [s for s in range(256) if freq[s]]
    return _varint(len(x)) + bytes([len(used) & 0xFF]) + b"".join(struct.pack("<BH", s, freq[s]) for s in used) + struct.pack("<I", state) + w.bytes()


def tans_decode(b: bytes, log: int = 11) -> bytes:
    n, at = _read_varint(b, 0)
    if not n:
        return b""
    used = b[at] or 256
    at += 1
    freq = [0] * 256
    for i in range(used):
        s, f = struct.unpack_from("<BH", b, at + 3 * i)
        freq[s] = f
    at += 3 * used
    size = 1 << log
    dec = _tans_tables(freq, size)[1]
    state = struct.unpack_from("<I", b, at)[0]
    r, out = BitReader(b[at + 4 :]), bytearray()
    for _ in range(n):
        s, base = dec[state - size]
        out.append(s)
        k = 0
        while (base << k) < size:
            k += 1
        state = (base << k) + r.get(k)
    return bytes(out)


def _normalise(count, size: int) -> list[int]:
    total = int(count.sum())
    f = [max(1, int(c) * size // total) if c else 0 for c in count]
    while sum(f) != size:
        step = 1 if sum(f) < size else -1
        s = max((i for i in range(256) if f[i] > (1 if step < 0 else 0)), key=lambda i: f[i])
        f[s] += step
    return f


def _tans_tables(freq, size: int):
    spread, at, step = [0] * size, 0, (size >> 1) + (size >> 3) + 3
    for s in range(256):
        for _ in range(freq[s]):
            spread[at] = s
            at = (at + step) & (size - 1)
    nxt = list(freq)
    enc, dec = {s: [0] * freq[s] for s in range(256) if freq[s]}, []
    for i, s in enumerate(spread):
        dec.append((s, nxt[s]))
        enc[s][nxt[s] - freq[s]] = size + i
        nxt[s] += 1
    return enc, dec


# ---------------------------------------------------------------- XOR with the previous word


def _references(x: np.ndarray, back: int) -> list[int]:
    """How far back the word lies, of the ``back`` before, whose xor ends in the most zeros; the nearest of equal ones."""
    x = x.astype(np.uint64)
    best, ref = np.zeros(len(x), np.uint64), np.ones(len(x), np.int64)
    for k in range(1, min(back, len(x) - 1) + 1):
        z = x[k:] ^ x[:-k]
        z = (z & (~z + np.uint64(1))) - np.uint64(1)  # 2^zeros - 1; the largest number for equal words
        better = z > best[k:]
        best[k:][better] = z[better]
        ref[k:][better] = k
    return ref.tolist()


def xor_encode(data: bytes, width: int, reuse: bool = True, back: int = 1) -> bytes:
    """First word raw; then xor with the word ``back`` before (or the best of 128 for back=128): zero is one bit, else the window of significant bits."""
    n = len(data) // width
    words = [int.from_bytes(data[i * width : (i + 1) * width], "little") for i in range(n)]
    bits, w, window = 8 * width, BitWriter(), None
    size = bits.bit_length()
    refs = _references(np.frombuffer(data[: n * width], f"<u{width}"), back) if back > 1 else None
    for i, v in enumerate(words):
        if not i:
            w.put(v, bits)
            continue
        ref = 1
        if back > 1:
            ref = refs[i]
            w.put(ref - 1, 7)
        x = words[i - ref] ^ v
        if not x:
            w.put(0, 1)
            continue
        lead, trail = bits - x.bit_length(), (x & -x).bit_length() - 1
        if reuse and window and lead >= window[0] and trail >= window[1]:
            w.put(0b10, 2)
            w.put(x >> window[1], bits - window[0] - window[1])
        else:
            w.put(0b11 if reuse else 1, 2 if reuse else 1)
            w.put(lead, size)
            w.put(bits - lead - trail, size)
            w.put(x >> trail, bits - lead - trail)
            window = (lead, trail)
    return _varint(n) + w.bytes() + data[n * width :]


def xor_decode(b: bytes, width: int, total: int, reuse: bool = True, back: int = 1) -> bytes:
    n, at = _read_varint(b, 0)
    tail = total - n * width
    r, bits, words, window = BitReader(b[at : len(b) - tail]), 8 * width, [], None
    size = bits.bit_length()
    for i in range(n):
        if not i:
            words.append(r.get(bits))
            continue
        ref = r.get(7) + 1 if back > 1 else 1
        if not r.get(1):
            words.append(words[-ref])
            continue
        if reuse and not r.get(1):
            lead, trail = window
        else:
            lead = r.get(size)
            trail = bits - lead - r.get(size)
            window = (lead, trail)
        words.append(words[-ref] ^ r.get(bits - lead - trail) << trail)
    return b"".join(v.to_bytes(width, "little") for v in words) + (b[len(b) - tail :] if tail else b"")


# ---------------------------------------------------------------- differences, runs, BWT, MTF

_UNSIGNED = {1: np.uint8, 2: np.uint16, 4: np.uint32, 8: np.uint64}


def _words(data: bytes, width: int) -> tuple[np.ndarray, bytes]:
    n = len(data) // width * width
    return np.frombuffer(data[:n], _UNSIGNED[width]), data[n:]


def delta_encode(data: bytes, width: int) -> bytes:
    """Differences of consecutive words, zigzag, as variable-length bytes."""
    x, tail = _words(data, width)
    d = np.diff(x, prepend=x.dtype.type(0))
    signed = d.view(np.dtype(f"i{width}"))
    z = (d << d.dtype.type(1)) ^ (signed >> (8 * width - 1)).view(d.dtype)
    return _varint(len(x)) + b"".join(map(_varint, z.tolist())) + tail


def delta_decode(b: bytes, width: int, total: int) -> bytes:
    n, at = _read_varint(b, 0)
    z = []
    for _ in range(n):
        v, at = _read_varint(b, at)
        z.append(v >> 1 ^ -(v & 1))
    t = _UNSIGNED[width]
    return np.cumsum(np.array([v & ((1 << 8 * width) - 1) for v in z], np.uint64).astype(t), dtype=t).tobytes() + b[at:]


def rle_encode(data: bytes, width: int = 1) -> bytes:
    x, tail = _words(data, width)
    if not len(x):
        return _varint(0) + tail
    at = np.nonzero(np.concatenate([[True], x[1:] != x[:-1]]))[0]
    runs = np.diff(np.concatenate([at, [len(x)]]))
    return _varint(len(at)) + b"".join(map(_varint, runs.tolist())) + x[at].tobytes() + tail


def rle_decode(b: bytes, width: int, total: int) -> bytes:
    k, at = _read_varint(b, 0)
    runs = []
    for _ in range(k):
        v, at = _read_varint(b, at)
        runs.append(v)
    x = np.frombuffer(b[at : at + k * width], _UNSIGNED[width])
    return np.repeat(x, np.array(runs, np.int64)).tobytes() + b[at + k * width :]


def bwt(data: bytes) -> bytes:
    """Rotation sort by prefix doubling; the index of the original rotation comes first."""
    n = len(data)
    if not n:
        return struct.pack("<I", 0)
    x = np.frombuffer(data, np.uint8)
    rank, k = np.unique(x, return_inverse=True)[1].astype(np.int64), 1
    order = np.argsort(rank, kind="stable")
    while k < n:
        key = rank * (rank.max() + 1) + rank[(np.arange(n) + k) % n]
        order = np.argsort(key, kind="stable")
        new = np.concatenate([[0], np.cumsum(key[order][1:] != key[order][:-1])])
        rank[order] = new
        if new[-1] == n - 1:
            break
        k *= 2
    return struct.pack("<I", int(np.nonzero(order == 0)[0][0])) + x[(order - 1) % n].tobytes()


def unbwt(b: bytes) -> bytes:
    (at,) = struct.unpack_from("<I", b)
    last = np.frombuffer(b[4:], np.uint8)
    nxt = np.argsort(last, kind="stable").tolist()
    first, out = np.sort(last).tolist(), bytearray()
    for _ in range(len(last)):
        out.append(first[at])
        at = nxt[at]
    return bytes(out)


def mtf(data: bytes) -> bytes:
    table, out = list(range(256)), bytearray()
    for c in data:
        i = table.index(c)
        out.append(i)
        if i:
            table.insert(0, table.pop(i))
    return bytes(out)


def unmtf(data: bytes) -> bytes:
    table, out = list(range(256)), bytearray()
    for i in data:
        c = table.pop(i)
        out.append(c)
        table.insert(0, c)
    return bytes(out)


# ---------------------------------------------------------------- float-specific rivals


def ordered_ints(x: np.ndarray) -> np.ndarray:
    """Float bits to unsigned integers in the order of the values."""
    top = x.dtype.type(1 << (8 * x.dtype.itemsize - 1))
    return np.where(x & top, ~x, x | top)


def unordered_ints(y: np.ndarray) -> np.ndarray:
    top = y.dtype.type(1 << (8 * y.dtype.itemsize - 1))
    return np.where(y & top, y & ~top, ~y)


def _classes(z: np.ndarray, width: int) -> bytes:
    """Zigzag residuals as entropy-coded bit lengths and raw low bits."""
    u = z.astype(np.uint64)
    length = np.zeros(len(u), np.int64)
    for s in (32, 16, 8, 4, 2, 1):
        big = u >> np.uint64(s) > 0
        length += s * big
        u = np.where(big, u >> np.uint64(s), u)
    length += (u > 0).astype(np.int64)
    low = np.maximum(length - 1, 0)
    at = np.cumsum(low) - low
    bits = np.zeros(int(low.sum()), np.uint8)
    v = z.astype(np.uint64)
    for k in range(8 * width):
        has = low > k
        bits[at[has] + k] = (v[has] >> np.uint64(k)) & np.uint64(1)
    head = huffman_encode(length.astype(np.uint8).tobytes())
    return struct.pack("<I", len(head)) + head + np.packbits(bits).tobytes()


def _unclasses(b: bytes, width: int) -> np.ndarray:
    (k,) = struct.unpack_from("<I", b)
    length = np.frombuffer(huffman_decode(b[4 : 4 + k]), np.uint8).astype(np.int64)
    bits = np.unpackbits(np.frombuffer(b[4 + k :], np.uint8)).astype(np.uint64)
    low = np.maximum(length - 1, 0)
    at = np.cumsum(low) - low
    v = np.where(length > 0, np.uint64(1) << low.astype(np.uint64), np.uint64(0))
    for j in range(8 * width):
        has = low > j
        v[has] |= bits[at[has] + j] << np.uint64(j)
    return v.astype(_UNSIGNED[width])


def predictive_encode(data: bytes, width: int) -> bytes:
    """Order-preserving integers, previous-value prediction, residual classes entropy-coded."""
    x, tail = _words(data, width)
    y = ordered_ints(x)
    d = np.diff(y, prepend=y.dtype.type(0))
    s = d.view(np.dtype(f"i{width}"))
    return _classes((d << d.dtype.type(1)) ^ (s >> (8 * width - 1)).view(d.dtype), width) + tail


def predictive_decode(b: bytes, width: int, total: int) -> bytes:
    tail = total % width
    z = _unclasses(b[: len(b) - tail], width)
    d = (z >> z.dtype.type(1)) ^ (~(z & z.dtype.type(1)) + z.dtype.type(1))
    return unordered_ints(np.cumsum(d, dtype=z.dtype)).tobytes() + (b[len(b) - tail :] if tail else b"")


#: Row lengths that the two-dimensional predictor tries, in words; 0 is the previous value alone.
ROWS = (0, 8, 16, 32, 64, 128, 256)


def _residuals(y: np.ndarray, row: int) -> np.ndarray:
    """Differences to left + above - above left, where rows follow each other; what lies before the first word counts as 0."""
    d = np.diff(y, prepend=y.dtype.type(0))
    if row:
        up = np.zeros_like(d)
        up[row:] = d[:-row]
        d = d - up
    return d


def predictive2_encode(data: bytes, width: int) -> bytes:
    """As the predictive codec, with the neighbours in a row and column as predictor; the row length with the fewest residual bits is kept."""
    x, tail = _words(data, width)
    y = ordered_ints(x)
    best = None
    for row in ROWS:
        if row < max(1, len(y)):
            d = _residuals(y, row)
            s = d.view(np.dtype(f"i{width}"))
            z = (d << d.dtype.type(1)) ^ (s >> (8 * width - 1)).view(d.dtype)
            cost = float(np.log2(z.astype(float) + 1).sum())
            if best is None or cost < best[0]:
                best = cost, row, z
    return struct.pack("<H", best[1]) + _classes(best[2], width) + tail


def predictive2_decode(b: bytes, width: int, total: int) -> bytes:
    tail = total % width
    (row,) = struct.unpack_from("<H", b)
    z = _unclasses(b[2 : len(b) - tail], width)
    d = (z >> z.dtype.type(1)) ^ (~(z & z.dtype.type(1)) + z.dtype.type(1))
    if row:  # sums down the columns undo the upper half of the predictor
        padded = np.concatenate([d, np.zeros(-len(d) % row, d.dtype)]).reshape(-1, row)
        d = np.cumsum(padded, axis=0, dtype=d.dtype).reshape(-1)[: len(d)]
    return unordered_ints(np.cumsum(d, dtype=z.dtype)).tobytes() + (b[len(b) - tail :] if tail else b"")


def hashed_encode(data: bytes, width: int, log: int = 12, decode: int | None = None) -> bytes:
    """Two hash-table predictors (of values and of differences); the better xor keeps its low bytes.  ``decode`` gives the inverse."""
    size, mask = 1 << log, (1 << 8 * width) - 1
    fcm, dfcm, h1, h2, last = [0] * size, [0] * size, 0, 0, 0
    shift = 8 * width - min(8 * width, 16)
    if decode is None:
        n = len(data) // width
        heads, rest = bytearray(), bytearray()
    else:
        n = decode // width
        heads, rest, at, out = data[:n], data[n:], 0, bytearray()
    for i in range(n):
        p1, p2 = fcm[h1], (last + dfcm[h2]) & mask
        if decode is None:
            v = int.from_bytes(data[i * width : (i + 1) * width], "little")
            x, which = (v ^ p1, 0) if v ^ p1 <= v ^ p2 else (v ^ p2, 1)
            k = -(-x.bit_length() // 8)
            heads.append(which << 4 | k)
            rest += x.to_bytes(k, "little")
        else:
            which, k = heads[i] >> 4, heads[i] & 15
            v = int.from_bytes(rest[at : at + k], "little") ^ (p2 if which else p1)
            at += k
            out += v.to_bytes(width, "little")
        d = (v - last) & mask
        fcm[h1], dfcm[h2] = v, d
        h1, h2, last = (h1 << 6 ^ v >> shift) & (size - 1), (h2 << 2 ^ d >> shift) & (size - 1), v
    if decode is None:
        return bytes(heads + rest) + data[n * width :]
    return bytes(out) + bytes(rest[at:])


def stride_encode(data: bytes, width: int) -> bytes:
    """Byte differences at word stride, shuffled, then LZ."""
    x = np.frombuffer(data, np.uint8)
    d = x.copy()
    d[width:] -= x[:-width]
    n = len(d) // width * width
    return lz77_encode(d[:n].reshape(-1, width).T.tobytes() + d[n:].tobytes(), chain=4)


def stride_decode(b: bytes, width: int, total: int) -> bytes:
    raw = np.frombuffer(lz77_decode(b), np.uint8)
    n = len(raw) // width * width
    d = np.concatenate([raw[:n].reshape(width, -1).T.reshape(-1), raw[n:]])
    out = d.copy()
    for k in range(width):
        out[k::width] = np.cumsum(d[k::width], dtype=np.uint8)
    return out.tobytes()
