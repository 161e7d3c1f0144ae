"""Words of whole texts in Arrow batches, and packed columns of integers, both by array operations.

A word is a run of anything but ASCII white space, with A-Z in lower case. Its hash is Spark's ``xxhash64``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_INSIDE = np.ones(256, bool)
_INSIDE[[9, 10, 11, 12, 13, 32]] = False
#: Bytes of text that are worked on at once; a longer text is worked on alone.
PART = 8 << 20
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
_SEED = np.uint64(42)


def _turned(x: np.ndarray, k: int) -> np.ndarray:
    return (x << np.uint64(k)) | (x >> np.uint64(64 - k))


def xxhash64(data: np.ndarray, start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Hashes, as signed integers, of the slices of ``data``, which must go on for 8 bytes after the last one."""
    eight = np.ndarray((max(len(data) - 7, 0),), "<u8", data, strides=(1,))
    size, at = length.astype(np.uint64), start.copy()
    h = np.full(len(start), _SEED + _P5 if _SEED else _P5, np.uint64)
    with np.errstate(over="ignore"):
        long = np.flatnonzero(length >= 32)
        if len(long):
            lanes = [np.full(len(long), x, np.uint64) for x in (_SEED + _P1 + _P2, _SEED + _P2, _SEED, _SEED - _P1)]
            on, stripes, k = np.arange(len(long)), length[long] // 32, 0
            while len(on):
                for i, lane in enumerate(lanes):
                    lane[on] = _turned(lane[on] + eight[start[long[on]] + 32 * k + 8 * i] * _P2, 31) * _P1
                k += 1
                on = on[stripes[on] > k]
            total = _turned(lanes[0], 1) + _turned(lanes[1], 7) + _turned(lanes[2], 12) + _turned(lanes[3], 18)
            for lane in lanes:
                total = (total ^ (_turned(lane * _P2, 31) * _P1)) * _P1 + _P4
            h[long], at[long] = total, start[long] + 32 * stripes
        h += size
        left = length - (at - start)
        on = np.flatnonzero(left >= 8)
        while len(on):
            h[on] = _turned(h[on] ^ (_turned(eight[at[on]] * _P2, 31) * _P1), 27) * _P1 + _P4
            at[on] += 8
            left[on] -= 8
            on = on[left[on] >= 8]
        on = np.flatnonzero(left >= 4)
        if len(on):
            h[on] = _turned(h[on] ^ ((eight[at[on]] & np.uint64(0xFFFFFFFF)) * _P1), 23) * _P2 + _P3
            at[on] += 4
            left[on] -= 4
        on = np.flatnonzero(left > 0)
        while len(on):
            h[on] = _turned(h[on] ^ (data[at[on]].astype(np.uint64) * _P5), 11) * _P1
            at[on] += 1
            left[on] -= 1
            on = on[left[on] > 0]
        h = (h ^ (h >> np.uint64(33))) * _P2
        h = (h ^ (h >> np.uint64(29))) * _P3
    return (h ^ (h >> np.uint64(32))).view(np.int64)


class Words:
    """The words of consecutive texts: bytes, each word's start, length, hash and text, and words of each text."""

    def __init__(self, data: np.ndarray, bounds: np.ndarray):
        n = len(data)
        self.data = np.zeros(n + 8, np.uint8)
        np.take(_LOWER, data, out=self.data[:n])
        inside = _INSIDE[data]
        first, last = inside.copy(), inside.copy()
        first[1:] &= ~inside[:-1]
        last[:-1] &= ~inside[1:]
        edges = bounds[:-1][bounds[:-1] < bounds[1:]]  # where a text that is not empty begins
        first[edges] = inside[edges]
        before = edges[edges > 0] - 1
        last[before] = inside[before]
        self.start = np.flatnonzero(first)
        self.length = np.flatnonzero(last) + 1 - self.start
        self.hash = xxhash64(self.data, self.start, self.length)
        of = np.searchsorted(bounds[:-1], self.start, "right") - 1
        self.of, self.count = of, np.bincount(of, minlength=len(bounds) - 1)

    def strings(self, at: np.ndarray) -> pa.Array:
        """The words of these numbers."""
        length = self.length[at]
        ends = np.cumsum(length)
        place = np.arange(ends[-1] if len(ends) else 0) + np.repeat(self.start[at] - (ends - length), length)
        offsets = np.concatenate(([0], ends)).astype(np.int32)
        return pa.StringArray.from_buffers(len(at), pa.py_buffer(offsets), pa.py_buffer(self.data[place]))


def parts(texts: pa.Array) -> Iterator[tuple[int, int, Words]]:
    """First and last row (excluded) and words of pieces of a batch; no text is cut. No text is null."""
    wide = pa.types.is_large_string(texts.type)
    _, offsets, data = texts.buffers()
    bounds = np.frombuffer(offsets, np.int64 if wide else np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64) if len(texts) else np.zeros(1, np.int64)
    at = 0
    while at < len(texts):
        to = max(int(np.searchsorted(bounds, bounds[at] + PART, "right")) - 1, at + 1)
        size = int(bounds[to] - bounds[at])
        piece = np.frombuffer(data, np.uint8, size, int(bounds[at])) if size else np.zeros(0, np.uint8)
        yield at, to, Words(piece, bounds[at : to + 1] - bounds[at])
        at = to


def pack(*columns: np.ndarray) -> bytes:
    """Columns of integers as differences, laid out by byte and compressed; short for sorted or small numbers."""
    planes = []
    for column in columns:
        step = np.diff(column.astype(np.int64, copy=False).view(np.uint64), prepend=np.uint64(0)).view(np.int64)
        step = (step << 1) ^ (step >> 63)
        planes.append(step.view(np.uint8).reshape(-1, 8).T.ravel())
    return np.array([len(c) for c in columns], np.int64).tobytes() + pa.Codec("zstd", 1).compress(np.concatenate(planes), asbytes=True)


def unpack(packed: bytes | memoryview, columns: int) -> list[np.ndarray]:
    sizes = np.frombuffer(packed, np.int64, columns)
    raw = np.frombuffer(pa.Codec("zstd").decompress(memoryview(packed)[8 * columns :], int(sizes.sum()) * 8, asbytes=True), np.uint8)
    out, at = [], 0
    for n in sizes.tolist():
        step = np.ascontiguousarray(raw[at : at + 8 * n].reshape(8, n).T).view(np.uint64).ravel()
        step = (step >> np.uint64(1)) ^ (np.uint64(0) - (step & np.uint64(1)))
        out.append(np.cumsum(step, dtype=np.uint64).view(np.int64))
        at += 8 * n
    return out
