"""Byte-level text kernels shared by the corpus operators (numpy, no Spark).

Texts are handled as UTF-8 bytes inside Arrow buffers.  A block holds many short texts or
one long text, so memory follows ``BLOCK_BYTES`` and the longest single text.

Hashes only propose: an operator that reports equal words or shingles compares the words.
"""

from __future__ import annotations

import ctypes
import functools
import gc
import hashlib

import numpy as np
import pyarrow as pa

#: Bytes of text that a kernel works on at once (longer single texts form their own block).
BLOCK_BYTES = 1 << 18

#: Words of up to this many bytes are hashed eight bytes at a time, longer ones one by one.
LANE_BYTES = 64

_U = np.uint64
_SEED = _U(0x9E3779B97F4A7C15)
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_REST = np.array([0, *((1 << 8 * i) - 1 for i in range(1, 8)), (1 << 64) - 1], _U)


_held: dict = {}


def hold(owner, make):
    """One large object per Python worker: workers are reused by other operators' tasks, and
    what an earlier operator needed must not stay in their memory."""
    if owner not in _held:
        _held.clear()
        _held[owner] = make()
    return _held[owner]


def release() -> None:
    """Let go of what another operator left in this worker."""
    if _held:
        _held.clear()
        give_back()


def give_back() -> None:
    """Return freed memory to the machine: a worker lives on, idle, beside other tasks."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass  # another C library: it decides by itself


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
        return x ^ (x >> _U(31))


def blocks(texts: pa.Array):
    """Yield (first row, offsets, bytes) for runs of rows; a null text counts as empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.cast(pa.large_string()).fill_null("") if len(texts) else texts.cast(pa.large_string())
    if not len(texts):
        return
    _, off, data = texts.buffers()
    off = np.frombuffer(off, np.int64)[texts.offset:texts.offset + len(texts) + 1]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    i = 0
    while i < len(texts):
        j = max(i + 1, int(np.searchsorted(off, off[i] + BLOCK_BYTES, "right")) - 1)
        yield i, off[i:j + 1] - off[i], data[off[i]:off[j]]
        i = j


def _word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word: its lanes of eight bytes are mixed in one after the other."""
    size = ends - starts
    wide = np.zeros(len(data) + 8, np.uint8)
    wide[:len(data)] = data
    lanes = np.ndarray((len(data) + 1,), "<u8", wide, strides=(1,))  # eight bytes from any place on
    with np.errstate(over="ignore"):
        h = mix(size.astype(_U) * _SEED + _U(1))
        todo, at = None, 0
        while True:
            s, left = (starts, size) if todo is None else (starts[todo] + at, size[todo] - at)
            if not len(s):
                break
            lane = lanes[s] & _REST[np.minimum(left, 8)]
            if todo is None:
                h = mix((h ^ lane) * _SEED + _U(at + 3))
                todo = np.flatnonzero((size > 8) & (size <= LANE_BYTES))
            else:
                h[todo] = mix((h[todo] ^ lane) * _SEED + _U(at + 3))
                todo = todo[left > 8]
            at += 8
    for i in np.flatnonzero(size > LANE_BYTES):
        h[i] = int.from_bytes(hashlib.blake2b(data[starts[i]:ends[i]].tobytes(), digest_size=8).digest(), "little")
    return h


def words(off: np.ndarray, data: np.ndarray, fold: bool = True):
    """Hash every word of a block: (starts, ends, hashes, first word of each text + end)."""
    n = len(data)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(0, _U), np.zeros(len(off), np.int64)
    ink = ~_SPACE[data]
    brk = np.zeros(n + 1, bool)
    brk[off] = True
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = ink[:-1]
    starts = np.flatnonzero(ink & (~before | brk[:n]))
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = ink[1:]
    ends = np.flatnonzero(ink & (~after | brk[1:])) + 1
    return starts, ends, _word_hashes(_FOLD[data] if fold else data, starts, ends), np.searchsorted(starts, off)


def plain_words(raw: bytes) -> list[bytes]:
    """The words of a text in UTF-8 as ``words`` cuts them, A-Z lower-cased."""
    return raw.lower().split()


def plain_shingles(w: list[bytes], k: int) -> set[bytes]:
    """The distinct shingles of ``shingle_sets`` as bytes, for exact comparison."""
    return {b" ".join(w[i:i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {b" ".join(w)} if w else set()


@functools.lru_cache(None)
def _salts(k: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix((np.arange(k + 1, dtype=_U) + _U(7)) * _U(0xD1342543DE82EF95)) | _U(1)


def word_grams(h: np.ndarray, k: int, whole: int) -> np.ndarray:
    """Hash of each run of ``k`` words; runs shorter than the ``whole`` shingle carry their length."""
    c = _salts(whole)
    m = max(0, len(h) - k + 1)
    with np.errstate(over="ignore"):
        s = h[:m] * c[0]
        for j in range(1, k):
            s += h[j:j + m] * c[j]
        return mix(s if k == whole else s + c[whole] * _U(k))


def sets_of(h: np.ndarray, first: np.ndarray, k: int):
    """Yield the shingle set of each text of a block from its word hashes (see ``shingle_sets``)."""
    s = word_grams(h, k, k)
    for a, b in zip(first[:-1], first[1:], strict=True):
        if b - a >= k:
            yield np.unique(s[a:b - k + 1])
        elif b > a:
            yield word_grams(h[a:b], int(b - a), k)
        else:
            yield h[:0]


def shingle_sets(texts: pa.Array, k: int = 5):
    """Yield per text the sorted distinct 64-bit hashes of its ``k``-word shingles.

    Words are maximal runs of bytes other than 0x20 and 0x09-0x0D, A-Z lower-cased.  A text
    of 1 to k-1 words has its whole sequence as its one shingle; without words the set is
    empty.
    """
    for _, off, data in blocks(texts):
        _, _, h, first = words(off, data)
        yield from sets_of(h, first, k)
