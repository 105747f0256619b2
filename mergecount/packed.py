"""Compact encodings of sketches.

``gamma``: the cut, then every cell's value + 2 with a self-delimiting code of 2 floor(ld) + 1 bits
(an Elias gamma code), bit-packed. ``bytes``: one byte per cell. ``deflate``: the same, compressed.
``indexed``: gamma with the place of every ``STRIDE``-th cell, so that one cell is
read without the others (``cell``). Equal states have equal bytes.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np

from .cuts import cell_bits

CODECS = ("gamma", "bytes", "deflate", "indexed")
STRIDE = 64
_HEAD = struct.Struct(">BBqIIh")  # version, codec, seed fingerprint, tables, bins, cut
VERSION = 1


def gamma_encode(values: np.ndarray) -> bytes:
    """Bits of positive integers: floor(ld x) zeros, then x from its highest bit."""
    x = values.ravel().astype(np.int64)
    width = np.frexp(x)[1] - 1
    ends = np.cumsum(2 * width + 1)
    bits = np.zeros(int(ends[-1]) if len(ends) else 0, dtype=np.uint8)
    for i in range(int(width.max(initial=0)) + 1):  # bit i counts from the last
        own = width >= i
        bits[ends[own] - 1 - i] = (x[own] >> i) & 1
    return np.packbits(bits).tobytes()


def gamma_decode(data: bytes, count: int) -> np.ndarray:
    """Only the walk from code to code is serial; widths and values come from whole arrays."""
    bits = np.unpackbits(np.frombuffer(data, dtype=np.uint8))
    if not count:
        return np.zeros(0, dtype=np.int64)
    places = np.arange(len(bits))
    first_one = np.minimum.accumulate(np.where(bits, places, len(bits))[::-1])[::-1]
    following = (2 * (first_one - places) + 1 + places).tolist()
    starts, at = [], 0
    for _ in range(count):
        starts.append(at)
        at = following[at]
    start = np.array(starts)
    width = first_one[start] - start
    out = np.zeros(count, dtype=np.int64)
    for i in range(int(width.max()) + 1):
        own = width >= i
        out[own] = out[own] << 1 | bits[start[own] + width[own] + i]
    return out


def encode(levels: np.ndarray, q: int, fingerprint: int, codec: str = "gamma") -> bytes:
    head = _HEAD.pack(VERSION, CODECS.index(codec), fingerprint, *levels.shape, q)
    values = levels.astype(np.int64) + 2
    if codec == "gamma":
        return head + gamma_encode(values)
    if codec == "indexed":
        ends = np.cumsum(2 * cell_bits(values.ravel() - 2) + 1)
        starts = np.concatenate([[0], ends])[: values.size : STRIDE]
        return head + starts.astype("<u4").tobytes() + gamma_encode(values)
    body = (levels + 1).astype(np.uint8).tobytes()
    return head + (zlib.compress(body, 6) if codec == "deflate" else body)


def info(data: bytes) -> dict:
    version, codec, fingerprint, l, b, q = _HEAD.unpack_from(data)  # noqa: E741
    if version != VERSION:
        raise ValueError(f"unknown sketch version {version}")
    return {"codec": CODECS[codec], "seed_fp": fingerprint, "l": l, "b": b, "q": q}


def decode(data: bytes) -> tuple[np.ndarray, int, int]:
    """Levels, cut and seed fingerprint."""
    head = info(data)
    body, shape = data[_HEAD.size :], (head["l"], head["b"])
    if head["codec"] == "indexed":
        body = body[4 * -(-shape[0] * shape[1] // STRIDE) :]
    if head["codec"] in ("gamma", "indexed"):
        levels = gamma_decode(body, shape[0] * shape[1]) - 2
    else:
        levels = np.frombuffer(zlib.decompress(body) if head["codec"] == "deflate" else body, dtype=np.uint8).astype(np.int64) - 1
    return levels.reshape(shape).astype(np.int8), head["q"], head["seed_fp"]


def cell(data: bytes, table: int, place: int) -> int:
    """Level of one cell of an ``indexed`` sketch (-1 if empty): at most STRIDE codes are read."""
    head = info(data)
    if head["codec"] != "indexed":
        raise ValueError("only the indexed codec has random access")
    count = head["l"] * head["b"]
    at = table * head["b"] + place
    index = 4 * -(-count // STRIDE)
    start = int(np.frombuffer(data, dtype="<u4", count=index // 4, offset=_HEAD.size)[at // STRIDE])
    first = _HEAD.size + index + start // 8
    bits = np.unpackbits(np.frombuffer(data[first : first + STRIDE * 2 + 16], dtype=np.uint8))[start % 8 :]  # a code has 15 bits at most
    k = 0
    for _ in range(at % STRIDE + 1):
        width = int(np.argmax(bits[k:]))
        value = int("".join(map(str, bits[k + width : k + 2 * width + 1])), 2)
        k += 2 * width + 1
    return value - 2


def size_bits(levels: np.ndarray, q: int) -> int:
    """Exact bits of the gamma form: cells and the cut."""
    return int((2 * cell_bits(levels) + 1).sum()) + max(1, int(q).bit_length())


def digest(data: bytes) -> str:
    return hashlib.sha256(data).hexdigest()
