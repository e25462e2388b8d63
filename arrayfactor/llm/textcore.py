"""Vectorised word hashing over Arrow text buffers.

A batch of texts is one UTF-8 buffer with offsets. All word rules of the operators split at ASCII
characters only, so words can be found bytewise: every byte of a multi-byte character is a word
byte. Each word gets a 64-bit hash (a polynomial over random byte values, finalised), so that no
Python object is made per word. Work goes in chunks of about a megabyte, whole texts each, which
bounds memory by the chunk or the longest single text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

U64 = np.uint64
_RATIO = 0x9E3779B97F4A7C13  # odd, 3 modulo 4
_CHUNK_BYTES = 1 << 20


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on unsigned 64-bit values."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def stream(seed: int, n: int) -> np.ndarray:
    """n reproducible 64-bit values."""
    with np.errstate(over="ignore"):
        return mix64(np.arange(1, n + 1, dtype=U64) * U64(0x9E3779B97F4A7C15) + U64(seed))


def _tables(kind: str) -> tuple[np.ndarray, np.ndarray]:
    code = np.arange(256)
    lower = np.where((code >= 65) & (code <= 90), code + 32, code)
    space = (code == 32) | ((code >= 9) & (code <= 13))
    alnum = ((code >= 48) & (code <= 57)) | ((lower >= 97) & (lower <= 122)) | (code >= 128)
    if kind == "alnum":  # runs of ASCII letters, digits and non-ASCII, case folded
        cls, fold = alnum.astype(np.uint8), lower
    elif kind == "space":  # runs of anything but white space, case folded
        cls, fold = (~space).astype(np.uint8), lower
    elif kind == "mixed":  # word runs and punctuation runs, case kept
        cls, fold = np.where(space, 0, np.where(alnum, 1, 2)).astype(np.uint8), code
    else:
        raise ValueError(kind)
    value = stream(11, 256)[fold]
    value[cls == 0] = 0
    return cls, value


_TABLES = {kind: _tables(kind) for kind in ("alnum", "space", "mixed")}
_POWERS = np.ones(1, U64)


def _powers(n: int) -> np.ndarray:
    global _POWERS
    if len(_POWERS) < n:
        size = max(n, 256, 2 * len(_POWERS))
        steps = np.full(size, _RATIO, U64)
        steps[0] = 1
        with np.errstate(over="ignore"):
            _POWERS = np.multiply.accumulate(steps)
    return _POWERS


@dataclass
class Words:
    """Words of consecutive texts: hashes, byte ranges, and where each text's words begin."""

    hash: np.ndarray
    start: np.ndarray
    end: np.ndarray
    ptr: np.ndarray

    @property
    def count(self) -> np.ndarray:
        return np.diff(self.ptr)


def find_words(buf: np.ndarray, offs: np.ndarray, kind: str) -> Words:
    """All words of the texts ``buf[offs[i]:offs[i+1]]``."""
    cls_of, value_of = _TABLES[kind]
    n = len(buf)
    if not n:
        none = np.zeros(0, np.int64)
        return Words(np.zeros(0, U64), none, none, np.zeros(len(offs), np.int64))
    cls = cls_of[buf]
    edge = np.ones(n + 1, bool)
    edge[1:n] = cls[1:] != cls[:-1]
    edge[offs] = True
    cuts = np.flatnonzero(edge)
    is_word = cls[cuts[:-1]] != 0
    first, last = cuts[:-1][is_word], cuts[1:][is_word]
    if not len(first):
        return Words(np.zeros(0, U64), first, first, np.zeros(len(offs), np.int64))
    at = np.arange(first[0], n, dtype=np.int32 if n < 2**31 else np.int64)
    at -= np.repeat(first.astype(at.dtype), np.diff(np.append(first, n)))
    power = _powers(int(at.max()) + 1)
    with np.errstate(over="ignore"):
        terms = value_of[buf[first[0] :]]
        terms *= power[at]
        h = mix64(np.add.reduceat(terms, first - first[0]) + U64(1))
    return Words(h, first, last, np.searchsorted(first, offs))


def chunks(texts: pa.Array, limit: int = _CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of pieces of an Arrow text column; null is empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    if texts.null_count:
        texts = texts.fill_null("")
    if not pa.types.is_large_string(texts.type):
        texts = texts.cast(pa.large_string())
    n = len(texts)
    if not n:
        return
    _, offsets, data = texts.buffers()
    offs = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + n + 1]
    buf = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    lo = 0
    while lo < n:
        hi = int(np.searchsorted(offs, offs[lo] + limit, side="right")) - 1
        hi = min(n, max(hi, lo + 1))
        yield lo, hi, buf[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
        lo = hi


def per_doc_sum(values: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """Sum of values over each text's words; zero for texts without words."""
    total = np.concatenate([[0], np.cumsum(values, dtype=np.float64 if values.dtype.kind == "f" else np.int64)])
    return total[ptr[1:]] - total[ptr[:-1]]


def ngrams(hashes: np.ndarray, ptr: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash of each run of ``size`` words inside one text, its first word's position)."""
    n = len(hashes)
    if n < size:
        return np.zeros(0, U64), np.zeros(0, np.int64)
    with np.errstate(over="ignore"):
        h = hashes[: n - size + 1].copy()
        for k in range(1, size):
            h = h * U64(0xD6E8FEB86659FD93) + hashes[k : n - size + 1 + k]
        h = mix64(h)
    ok = np.ones(n - size + 1, bool)
    for k in range(1, size):  # a run that starts in the last size-1 words of a text would cross into the next
        at = ptr[1:-1] - k
        ok[at[(at >= 0) & (at < len(ok))]] = False
    # texts shorter than ``size`` mark positions of earlier texts as well; those cross too
    return h[ok], np.flatnonzero(ok)


def prefix_hash(buf: np.ndarray, w: Words, size: int, kind: str = "alnum") -> np.ndarray:
    """Hash of the first ``size`` bytes of each word (of all of a shorter one)."""
    value_of, power = _TABLES[kind][1], _powers(size)
    h = np.full(len(w.hash), U64(size) * U64(0x1234567))
    with np.errstate(over="ignore"):
        for k in range(size):
            at = w.start + k
            inside = at < w.end
            h += np.where(inside, value_of[buf[np.where(inside, at, w.start)]] * power[k], U64(0))
    return mix64(h)
