"""Packing the planes of a block into cluster streams, and back."""

from __future__ import annotations

import numpy as np

from .words import as_planes, from_planes


def pack(m: np.ndarray, partition, packing: str = "byte") -> list[bytes]:
    """Streams of the clusters: ``byte`` keeps each plane together, ``value`` each word's bytes."""
    return [np.ascontiguousarray(m[:, g].T if packing == "byte" else m[:, g]).tobytes() for g in partition]


def unpack(streams: list[bytes], partition, packing: str, n: int) -> np.ndarray:
    m = np.empty((n, sum(map(len, partition))), np.uint8)
    for s, g in zip(streams, partition, strict=True):
        x = np.frombuffer(s, np.uint8)
        m[:, g] = x.reshape(len(g), n).T if packing == "byte" else x.reshape(n, len(g))
    return m


def transform(data: bytes, width: int, partition, packing: str = "byte") -> list[bytes]:
    return pack(as_planes(data, width), partition, packing)


def restore(streams: list[bytes], width: int, partition, packing: str, n: int) -> bytes:
    return from_planes(unpack(streams, partition, packing, n))


def byte_shuffle(data: bytes, width: int) -> bytes:
    return transform(data, width, [list(range(width))], "byte")[0]


def bit_shuffle(data: bytes, width: int) -> bytes:
    """Bit planes of the words up to a multiple of eight; the tail words follow as they are."""
    n = len(data) // width // 8 * 8
    head = np.unpackbits(as_planes(data[: n * width], width).copy(), axis=1)
    return np.packbits(np.ascontiguousarray(head.T).reshape(-1)).tobytes() + data[n * width :]


def bit_unshuffle(data: bytes, width: int) -> bytes:
    n = len(data) // width // 8 * 8
    bits = np.unpackbits(np.frombuffer(data[: n * width], np.uint8)).reshape(width * 8, n)
    return from_planes(np.packbits(np.ascontiguousarray(bits.T), axis=1)) + data[n * width :]


def ordered(partition, entropies=None, order: str = "plane"):
    """Clusters in plane order, or by mean plane entropy."""
    if order == "plane":
        return partition
    return sorted(partition, key=lambda g: (1 if order == "entropy" else -1) * float(np.mean([entropies[i] for i in g])))
