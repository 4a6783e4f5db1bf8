"""Vectorised byte-text kernels shared by the operators: words, hashes, shingles, rolling q-grams.

Texts are joined into slices of about ``SLICE`` bytes, so memory follows the slice (or the one longest text),
never the Arrow batch. All arithmetic is modulo 2**64.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

SLICE = 1 << 20
_BASE = np.uint64(0x9E3779B97F4A7C15)
_POWERS = np.ones(1, np.uint64)


def powers(n: int) -> np.ndarray:
    global _POWERS
    if len(_POWERS) < n:
        table = np.full(max(n, 2 * len(_POWERS), 4096), _BASE, np.uint64)
        table[0] = 1
        _POWERS = np.multiply.accumulate(table)
    return _POWERS


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply), vectorised."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def slices(texts: list[bytes], size: int = SLICE) -> Iterator[tuple[int, int]]:
    """Ranges of ``texts`` holding about ``size`` bytes each; a longer text stands alone."""
    at, held = 0, 0
    for i, t in enumerate(texts):
        if held and held + len(t) > size:
            yield at, i
            at, held = i, 0
        held += len(t)
    if at < len(texts):
        yield at, len(texts)


WHITE = np.zeros(256, bool)
WHITE[[9, 10, 11, 12, 13, 32]] = True


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The texts with a line feed after each, and where each begins (one more entry: the end)."""
    begins = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) + 1 for t in texts], out=begins[1:])
    return np.frombuffer(b"\n".join(texts) + b"\n", np.uint8), begins


def words(buffer: np.ndarray, separators: np.ndarray = WHITE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and 64-bit hash of every maximal run of non-separator bytes."""
    inside = ~separators[buffer]
    edge = np.flatnonzero(np.diff(np.concatenate(([False], inside, [False])).view(np.int8)))
    starts, ends = edge[::2], edge[1::2]
    if not len(starts):
        return starts, ends, np.empty(0, np.uint64)
    length = ends - starts
    many = (length + 7) // 8
    offsets = np.cumsum(many) - many
    place = np.arange(int(many.sum())) - np.repeat(offsets, many)
    # eight bytes at a time, each mixed with its place before they are added: unlike a polynomial, no pattern of bytes cancels out
    eights = np.ndarray(len(buffer) + 1, "<u8", np.concatenate((buffer, np.zeros(8, np.uint8))), strides=(1,))
    value = eights[np.repeat(starts, many) + 8 * place]
    left = np.repeat(length, many) - 8 * place
    short = left < 8
    value[short] &= (np.uint64(1) << (left[short] * 8).astype(np.uint64)) - np.uint64(1)
    whole = np.add.reduceat(mix(value + mix(place.astype(np.uint64) + np.uint64(1))), offsets)
    return starts, ends, mix(whole ^ mix(length.astype(np.uint64)))


def rolling(buffer: np.ndarray, q: int) -> np.ndarray:
    """Hash of the ``q`` bytes from every position, by doubling; shorter than the buffer by ``q - 1``."""
    if len(buffer) < q:
        return np.empty(0, np.uint64)
    pw = powers(q + 1)
    block, width, out, done = buffer.astype(np.uint64) + np.uint64(1), 1, None, 0
    rest = q
    while rest:
        if rest & 1:
            if out is None:
                out = block
            else:
                n = len(block) - done
                out = out[:n] + block[done:] * pw[done]
            done += width
        rest >>= 1
        if rest:
            block = block[:-width] + block[width:] * pw[width]
            width *= 2
    return mix(out[: len(buffer) - q + 1])


def shingles(texts: list[bytes], k: int = 5) -> list[np.ndarray]:
    """Sorted distinct hashes of ``k`` consecutive words of each text (A-Z lower-cased, ASCII white space parts
    words); with 1 to ``k-1`` words one hash of the whole sequence; without words none."""
    out: list[np.ndarray] = []
    for lo, hi in slices(texts):
        part = [t.lower() for t in texts[lo:hi]]
        buffer, begins = joined(part)
        starts, _, hashed = words(buffer)
        first = np.searchsorted(starts, begins)
        coef = mix(np.arange(1, k + 1, dtype=np.uint64))
        coef |= np.uint64(1)
        n = len(hashed) - k + 1
        if n > 0:
            rolled = hashed[:n] * coef[0]
            for i in range(1, k):
                rolled = rolled + hashed[i : n + i] * coef[i]
            rolled = mix(rolled)
        for i in range(len(part)):
            a, b = int(first[i]), int(first[i + 1])
            if b - a >= k:
                out.append(np.unique(rolled[a : b - k + 1]))
            elif b > a:
                own = hashed[a:b] * coef[: b - a]
                out.append(mix(np.array([own.sum(dtype=np.uint64) ^ np.uint64(b - a)], np.uint64)))
            else:
                out.append(np.empty(0, np.uint64))
    return out
