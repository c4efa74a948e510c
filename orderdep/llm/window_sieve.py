"""Cuts texts into runs of window starts that share an anchor, so that equal windows always meet under one key.

Every window of ``length`` bytes has one anchor: the first of its ``gram``-byte strings with the smallest hash.
Neighbouring starts mostly share it; such a run of starts is one row, keyed by the anchor's hash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import xxhash

GRAM = 32
_PIECE = 1 << 19
_POSITION = np.uint64((1 << 20) - 1)
_TABLE = np.random.Generator(np.random.PCG64(20_011)).integers(0, 1 << 63, 256, np.uint64) * np.uint64(2) + np.uint64(1)
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3)]


def gram_hashes(data: np.ndarray, size: int) -> np.ndarray:
    """A 64-bit hash of each string of ``size`` (a power of two) bytes."""
    h, m, k = _TABLE[data], 1, 0
    while m < size:
        h = h[:-m] * _MIX[k] + h[m:]
        h ^= h >> np.uint64(29)
        m, k = 2 * m, k + 1
    h *= _MIX[k]
    h ^= h >> np.uint64(32)
    return h


def sliding_least(values: np.ndarray, width: int) -> np.ndarray:
    """Smallest of each ``width`` neighbours."""
    m = 1
    while 2 * m <= width:
        values = np.minimum(values[:-m], values[m:])
        m *= 2
    return np.minimum(values[: len(values) - (width - m)], values[width - m :]) if width > m else values


def pieces(texts: list[bytes], length: int) -> Iterator[tuple[bytes, list[tuple[int, int, int, int]]]]:
    """Texts gathered into buffers; (text, where it starts in the buffer, bytes, where the buffer starts in the text).

    A text longer than a buffer is cut so that every window lies whole in some piece.
    """
    held: list[bytes] = []
    spans: list[tuple[int, int, int, int]] = []
    size = 0
    for k, t in enumerate(texts):
        if len(t) < length:
            continue
        for at in range(0, len(t) - length + 1, _PIECE):
            part = t[at : at + _PIECE + length - 1] if at or len(t) > _PIECE + length - 1 else t
            spans.append((k, size, len(part), at))
            held.append(part)
            size += len(part)
            if size >= _PIECE // 2:
                yield b"".join(held), spans
                held, spans, size = [], [], 0
    if held:
        yield b"".join(held), spans


def runs(texts: list[bytes], length: int, gram: int = GRAM) -> Iterator[tuple[np.ndarray, ...]]:
    """Arrays (text, first start, starts, anchor hash, content hash) of the runs of some texts."""
    for buffer, spans in pieces(texts, length):
        data = np.frombuffer(buffer, np.uint8)
        h = gram_hashes(data, gram)
        key = (h & ~_POSITION) | np.arange(len(h), dtype=np.uint64)
        anchor = (sliding_least(key, length - gram + 1) & _POSITION).astype(np.int64)
        owner = np.repeat(np.arange(len(spans)), [s[2] for s in spans])[: len(anchor)]
        firsts = np.array([s[1] for s in spans])
        ends = np.array([s[1] + s[2] for s in spans]) - length + 1
        at = np.arange(len(anchor))
        valid = at < ends[owner]
        new = valid & np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (owner[1:] != owner[:-1])])
        first = np.flatnonzero(new)
        own = owner[first]
        end = np.minimum(np.concatenate([first[1:], [len(anchor)]]), ends[own])
        digest = xxhash.xxh3_64_intdigest
        content = np.array([digest(buffer[a : b + length - 1]) for a, b in zip(first.tolist(), end.tolist())], np.uint64)
        shift = np.array([s[3] for s in spans]) - firsts
        yield np.array([s[0] for s in spans])[own], first + shift[own], end - first, h[anchor[first]].view(np.int64), content.view(np.int64)
