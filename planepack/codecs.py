"""Codec registry: every codec runs standard (on the word image) and on the streams of the plane clusters."""

from __future__ import annotations

import bz2
import zlib
from collections.abc import Callable
from dataclasses import dataclass

import pyarrow as pa

from . import foundational as f
from .packing import bit_shuffle, bit_unshuffle, byte_shuffle, restore


@dataclass(frozen=True)
class Codec:
    """encode(data, width, level) -> bytes; decode(payload, width, raw length) -> bytes."""

    id: int
    name: str
    kind: str
    encode: Callable[[bytes, int, int | None], bytes]
    decode: Callable[[bytes, int, int], bytes]


def _arrow(name: str):
    def enc(d, w, lv):
        return pa.Codec(name, compression_level=lv).compress(d, asbytes=True) if name == "zstd" and lv is not None else pa.compress(d, name, asbytes=True)

    return enc, lambda b, w, n: pa.decompress(b, n, name, asbytes=True) if n else b""


def _chunked(d, w, lv, size=65536):
    parts = [pa.compress(d[i : i + size], "lz4_raw", asbytes=True) for i in range(0, len(d), size)]
    return b"".join(len(p).to_bytes(4, "little") + p for p in parts)


def _unchunked(b, w, n, size=65536):
    out, at = [], 0
    while n > 0:
        k = int.from_bytes(b[at : at + 4], "little")
        out.append(pa.decompress(b[at + 4 : at + 4 + k], min(size, n), "lz4_raw", asbytes=True))
        at, n = at + 4 + k, n - size
    return b"".join(out)


def _sorted_rotations(d, w, lv):
    turned = f.bwt(d)
    return f.huffman_encode(f.mtf(turned[4:])) + turned[:4]


_zstd, _unzstd = _arrow("zstd")
_CODECS = [
    Codec(0, "store", "none", lambda d, w, lv: d, lambda b, w, n: b),
    Codec(1, "lz77", "foundational", lambda d, w, lv: f.lz77_encode(d), lambda b, w, n: f.lz77_decode(b)),
    Codec(2, "fastlz", "foundational", lambda d, w, lv: f.lz77_encode(d, chain=1), lambda b, w, n: f.lz77_decode(b)),
    Codec(3, "huffman", "foundational", lambda d, w, lv: f.huffman_encode(d), lambda b, w, n: f.huffman_decode(b)),
    Codec(4, "xor", "foundational", lambda d, w, lv: f.xor_encode(d, w), lambda b, w, n: f.xor_decode(b, w, n)),
    Codec(5, "delta", "foundational", lambda d, w, lv: f.delta_encode(d, w), lambda b, w, n: f.delta_decode(b, w, n)),
    Codec(6, "zstd", "hybrid", _zstd, _unzstd),
    Codec(7, "snappy", "hybrid", *_arrow("snappy")),
    Codec(8, "lz4", "hybrid", *_arrow("lz4_raw")),
    Codec(9, "zlib", "hybrid", lambda d, w, lv: zlib.compress(d, 6 if lv is None else lv), lambda b, w, n: zlib.decompress(b)),
    Codec(10, "bzip2", "hybrid", lambda d, w, lv: bz2.compress(d, 9 if lv is None else lv), lambda b, w, n: bz2.decompress(b)),
    Codec(11, "lz4-chunked", "hybrid", _chunked, _unchunked),
    Codec(12, "tans", "component", lambda d, w, lv: f.tans_encode(d), lambda b, w, n: f.tans_decode(b)),
    Codec(13, "rle", "component", lambda d, w, lv: f.rle_encode(d, w), lambda b, w, n: f.rle_decode(b, w, n)),
    Codec(14, "bwt-mtf-huffman", "component", _sorted_rotations, lambda b, w, n: f.unbwt(b[-4:] + f.unmtf(f.huffman_decode(b[:-4])))),
    Codec(15, "xor-plain", "foundational", lambda d, w, lv: f.xor_encode(d, w, reuse=False), lambda b, w, n: f.xor_decode(b, w, n, reuse=False)),
    Codec(16, "shuffle-zstd", "transform", lambda d, w, lv: _zstd(byte_shuffle(d, w), w, lv), lambda b, w, n: restore([_unzstd(b, w, n)], w, [list(range(w))], "byte", n // w)),
    Codec(17, "bitshuffle-zstd", "transform", lambda d, w, lv: _zstd(bit_shuffle(d, w), w, lv), lambda b, w, n: bit_unshuffle(_unzstd(b, w, n), w)),
    Codec(18, "predictive", "float", lambda d, w, lv: f.predictive_encode(d, w), lambda b, w, n: f.predictive_decode(b, w, n)),
    Codec(19, "hashed", "float", lambda d, w, lv: f.hashed_encode(d, w), lambda b, w, n: f.hashed_encode(b, w, decode=n)),
    Codec(20, "stride-lz", "float", lambda d, w, lv: f.stride_encode(d, w), lambda b, w, n: f.stride_decode(b, w, n)),
    Codec(22, "predictive-2d", "float", lambda d, w, lv: f.predictive2_encode(d, w), lambda b, w, n: f.predictive2_decode(b, w, n)),
    Codec(21, "xor-of-128", "foundational", lambda d, w, lv: f.xor_encode(d, w, back=128), lambda b, w, n: f.xor_decode(b, w, n, back=128)),
]
CODECS = {c.name: c for c in _CODECS}
BY_ID = {c.id: c for c in _CODECS}
#: The six general tools of the comparisons; the last is a chunked CPU stand-in for a GPU tool.
TOOLS = ["zstd", "snappy", "lz4", "zlib", "bzip2", "lz4-chunked"]


def stream_width(width: int, members: int, packing: str) -> int:
    """The word of word-wise codecs on a cluster stream: the cluster's bytes of a word if they lie together, else one byte."""
    return members if packing == "value" and members in (1, 2, 4, 8) else 1


class streamed:  # noqa: N801
    """Bytes that a tool makes of an unblocked stream: ``put`` pieces, ``close`` gives the size.  Nothing is kept."""

    def __init__(self, name: str):
        self.size = 0
        if name == "lz4":
            self.sink = pa.PythonFile(self, mode="w")
            self.out = pa.CompressedOutputStream(self.sink, "lz4")
            self.put, self.finish = self.out.write, self.out.close
            return
        import zstandard

        c = {"zstd": lambda: zstandard.ZstdCompressor(level=3).compressobj(), "zlib": lambda: zlib.compressobj(6), "bzip2": lambda: bz2.BZ2Compressor(9)}[name]()
        self.put, self.finish = lambda b: self.write(c.compress(b)), lambda: self.write(c.flush())

    #: What Arrow asks of a file.
    closed = False

    def write(self, b) -> int:
        self.size += len(b)
        return len(b)

    def flush(self) -> None:
        pass

    def close(self) -> int:
        if not self.closed:
            self.closed = True
            self.finish()
        return self.size
