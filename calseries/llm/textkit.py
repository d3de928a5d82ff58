"""Vectorised views of texts: many texts as one byte array, the runs of bytes in it, and 64-bit hashes of runs."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from .common import travels

travels(__name__)

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
LETTER = np.zeros(256, bool)
LETTER[65:91] = LETTER[97:123] = LETTER[128:] = True
BASE = 0x9E3779B97F4A7C15 | 1
U = np.uint64


@dataclass
class Slab:
    """Texts laid end to end: ``buf[off[i]:off[i + 1]]`` is text ``lo + i`` of the batch."""

    lo: int
    buf: np.ndarray
    off: np.ndarray

    def __len__(self) -> int:
        return len(self.off) - 1


def slabs(texts: pa.Array, limit: int = 1 << 20, most: int = 1000) -> Iterator[Slab]:
    """The texts of a batch in slabs of about ``limit`` bytes and at most ``most`` texts; a longer text is a slab of
    its own. Nulls are empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.cast(pa.large_string()).fill_null("")
    n = len(texts)
    if not n:
        return
    off = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + n + 1]
    data = texts.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + limit, "right")) - 1)
        hi = min(hi, n, lo + most)
        yield Slab(lo, raw[off[lo] : off[hi]], off[lo : hi + 1] - off[lo])
        lo = hi


def runs(mask: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and texts of the maximal runs of true bytes; no run crosses from a text into the next."""
    n = len(mask)
    if not n:
        e = np.zeros(0, np.int64)
        return e, e, e
    before = np.zeros(n, bool)
    before[1:] = mask[:-1]
    firsts = off[:-1]
    before[firsts[firsts < n]] = False
    after = np.zeros(n, bool)
    after[:-1] = ~before[1:] | ~mask[1:]
    after[-1] = True
    starts = np.flatnonzero(mask & ~before)
    ends = np.flatnonzero(mask & after) + 1
    return starts, ends, np.searchsorted(off, starts, "right") - 1


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    h = (h ^ (h >> U(30))) * U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> U(27))) * U(0x94D049BB133111EB)
    return h ^ (h >> U(31))


#: Masks of the lowest 0 to 8 bytes of a word.
LOW_BYTES = np.array([(1 << 8 * k) - 1 for k in range(9)], U)


def hash_runs(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each run of ``values`` (bytes or code points); equal runs have equal hashes.

    A run is read in blocks of eight bytes, the last one filled up with zeros. Every block goes through a bijection of
    its own place and takes that place's odd factor before the blocks are added up, so that no repetitive text cancels."""
    wide = values.dtype.itemsize
    raw = np.zeros(values.nbytes + 8, np.uint8)
    raw[:-8] = values.view(np.uint8)
    words = np.ndarray(len(raw) - 7, "<u8", raw, strides=(1,))
    lo, size = starts * wide, (ends - starts) * wide
    blocks = (size + 7) >> 3
    cut = spans(blocks)
    place = np.arange(cut[-1]) - np.repeat(cut[:-1], blocks)
    x = words[np.repeat(lo, blocks) + 8 * place]
    x &= LOW_BYTES[np.minimum(np.repeat(size, blocks) - 8 * place, 8)]
    key = mix(place.astype(U) * U(BASE) + U(BASE))
    cum = np.zeros(len(x) + 1, U)
    np.cumsum(mix(x ^ key) * (key | U(1)), out=cum[1:])
    return mix(cum[cut[1:]] - cum[cut[:-1]] + size.astype(U))


def windows(h: np.ndarray, owner: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all ``k`` words in a row within one text, and the position of each window's first word."""
    if len(h) < k:
        return np.zeros(0, U), np.zeros(0, np.int64)
    out = h[: len(h) - k + 1].copy()
    for i in range(1, k):
        out = mix(out * U(BASE)) + h[i : len(h) - k + 1 + i]
    at = np.flatnonzero(owner[: len(h) - k + 1] == owner[k - 1 :])
    return mix(out[at]), at


def count_chars(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Code points in each run of UTF-8 bytes."""
    cum = np.zeros(len(buf) + 1, np.int64)
    np.cumsum((buf & 0xC0) != 0x80, out=cum[1:])
    return cum[ends] - cum[starts]


def per_text(weights: np.ndarray | None, owner: np.ndarray, n: int) -> np.ndarray:
    """Sums by text, as whole numbers unless ``weights`` are fractions."""
    if weights is None:
        return np.bincount(owner, minlength=n)
    out = np.bincount(owner, weights=weights, minlength=n)
    return out if weights.dtype.kind == "f" else out.astype(np.int64)


def distinct_by_text(h: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct hashes of each text, cut to 54 bits, ascending, text after text; and their texts (under 1024)."""
    if not len(h):
        return h, owner
    key = np.sort((owner.astype(U) << U(54)) | (h >> U(10)))
    keep = np.ones(len(key), bool)
    keep[1:] = key[1:] != key[:-1]
    key = key[keep]
    return key & U((1 << 54) - 1), (key >> U(54)).astype(np.int64)


def twice(h: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which hashes occur more than once in their text, and which come after an equal one."""
    key = mix(h + mix(owner.astype(U) + U(1)))
    order = np.argsort(key, kind="stable")
    k = key[order]
    same = k[1:] == k[:-1]
    any_, later = np.zeros(len(h), bool), np.zeros(len(h), bool)
    any_[order[1:][same]] = True
    any_[order[:-1][same]] = True
    later[order[1:][same]] = True
    return any_, later


def spans(counts: np.ndarray) -> np.ndarray:
    """Offsets of consecutive groups of these lengths."""
    out = np.zeros(len(counts) + 1, np.int64)
    np.cumsum(counts, out=out[1:])
    return out
