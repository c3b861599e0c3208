"""Byte-level kernels shared by the text operators: word spans, 64-bit word and shingle hashes.

Everything works on one numpy buffer for a batch of texts, so that Python runs once per
batch or per text and never once per word.
"""

from __future__ import annotations

import ctypes
import functools
import gc

import numpy as np

U64 = np.uint64
#: Odd multiplier of the polynomial hash modulo 2**64; its inverse undoes a start offset.
BASE = 0x9E3779B97F4A7C15 | 1
BASE_INV = pow(BASE, -1, 1 << 64)

#: Bytes that end a word: space, tab, newline, vertical tab, form feed, carriage return.
IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
#: A-Z to a-z, all other bytes as they are.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


#: Powers of the hash's base and of its inverse, as long as they were ever needed.
_held: dict[bool, np.ndarray] = {}


def trim() -> None:
    """Give freed memory back to the system: a Python worker outlives its tasks, and several share an executor's limit."""
    import pyarrow

    gc.collect()
    _held.clear()
    pyarrow.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass  # a C library without it


def tidy(run):
    """A generator function that trims when it has ended."""

    @functools.wraps(run)
    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            trim()

    return wrapped


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser that spreads every input bit over the 64 output bits."""
    x = np.asarray(x, dtype=U64)
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


#: A random 64-bit value for each byte, from the mixer itself.
BYTE_VALUE = mix64(np.arange(1, 257, dtype=U64) * U64(0xD1342543DE82EF95))


def powers(n: int, inverse: bool = False) -> np.ndarray:
    """The first n powers of the base, or of its inverse. The longest array so far is kept, and only that."""
    have = _held.get(inverse)
    if have is None or len(have) < n:
        size, base = 1 << max(12, int(n - 1).bit_length()), BASE_INV if inverse else BASE
        have = np.empty(size, dtype=U64)
        have[0] = 1
        done = 1
        while done < size:  # doubling: powers of [0, 2k) from those of [0, k)
            have[done : 2 * done] = have[:done] * U64(pow(base, done, 1 << 64))
            done *= 2
        _held[inverse] = have
    return have[:n]


class PrefixHash:
    """Hashes of any slice of a byte buffer in constant time after one pass.

    rows: where the slices' rows begin; slices then stay within a row, exponents start anew with
    each, and long buffers of short rows need few powers.
    """

    def __init__(self, buf: np.ndarray, rows: np.ndarray | None = None):
        n = len(buf)
        self.at = None
        if rows is not None:
            self.at = np.arange(n + 1, dtype=np.int32)
            self.at -= np.repeat(rows, np.diff(np.append(rows, n + 1))).astype(np.int32)
        self.sums = np.zeros(n + 1, dtype=U64)
        step = 1 << 18
        for a in range(0, n, step):
            b = min(n, a + step)
            part = BYTE_VALUE[buf[a:b]]
            part *= powers(n)[a:b] if self.at is None else powers(int(self.at[a:b].max()) + 1)[self.at[a:b]]
            part[:1] += self.sums[a : a + 1]
            np.cumsum(part, out=self.sums[a + 1 : b + 1])
        self.inv = powers(n + 1 if self.at is None else int(self.at.max(initial=0)) + 1, inverse=True)

    def raw(self, start, end) -> np.ndarray:
        """Linear hash of buf[start:end], independent of where the slice stands."""
        return (self.sums[end] - self.sums[start]) * self.inv[start if self.at is None else self.at[start]]


def join_texts(texts) -> tuple[np.ndarray, np.ndarray]:
    """One buffer with every text as UTF-8 followed by a newline; null counts as empty. Offsets have one entry more than texts."""
    raw = [t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in texts]
    offsets = np.zeros(len(raw) + 1, dtype=np.int64)
    np.cumsum([len(r) + 1 for r in raw], out=offsets[1:])
    return np.frombuffer(b"\n".join([*raw, b""]), dtype=np.uint8), offsets


def word_spans(buf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words in a buffer that ends with a space byte."""
    if not len(buf):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    space = IS_SPACE[buf]
    edge = np.flatnonzero(space[1:] != space[:-1]) + 1
    if not space[0]:
        edge = np.concatenate(([0], edge))
    return edge[0::2], edge[1::2]


#: Multipliers that make a shingle's hash depend on the order of its words.
ORDER_K = mix64(np.arange(11, 11 + 64, dtype=U64)) | U64(1)


def shingle_hashes(texts, width: int = 5) -> list[np.ndarray]:
    """For each text the sorted distinct hashes of its runs of `width` words (A-Z lowered).

    A text with fewer words gives one hash of its whole word sequence; a null text or one
    without words gives an empty array.
    """
    buf, offsets = join_texts(texts)
    buf = LOWER[buf]
    starts, ends = word_spans(buf)
    words = mix64(PrefixHash(buf).raw(starts, ends) + (ends - starts).astype(U64))
    cut = np.searchsorted(starts, offsets)
    if len(words) >= width:
        sums = sum(words[j : len(words) - width + 1 + j] * ORDER_K[j] for j in range(width))
        sums = mix64(sums + U64(width))
    out = []
    for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
        if b - a >= width:
            out.append(np.unique(sums[a : b - width + 1]))
        elif b > a:
            w = words[a:b]
            out.append(mix64((w * ORDER_K[: b - a]).sum(dtype=U64, keepdims=True) + U64(b - a)))
        else:
            out.append(np.zeros(0, dtype=U64))
    return out


def text_batches(texts, max_bytes: int = 1 << 20):
    """Slices of a sequence of texts whose characters add up to about max_bytes, at least one text each."""
    at, size = 0, 0
    for i, t in enumerate(texts):
        n = len(t) if isinstance(t, str) else 0
        if i > at and size + n > max_bytes:
            yield slice(at, i)
            at, size = i, 0
        size += n
    if len(texts) > at:
        yield slice(at, len(texts))
