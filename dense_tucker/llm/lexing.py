"""Word splitting and hashing over whole batches of UTF-8 bytes, without a Python loop per word.

A span's hash takes its bytes eight at a time, each step scrambled by a bijection of 64-bit values; spans of
more than LONG bytes are hashed one by one with XXH64. So equal spans have equal hashes in every process, and unequal spans
of up to eight bytes and equal length never have. Where an answer must be exact, same_spans() compares the bytes of spans
whose hashes meet.
"""

from __future__ import annotations

import numpy as np
import xxhash

#: Bytes beyond which spans are hashed and compared one by one.
LONG = 256
_SEED = 0x5851F42D4C957F2D
_MASKS = np.asarray([(1 << 8 * k) - 1 for k in range(8)] + [(1 << 64) - 1], np.uint64)

#: Byte classes. White space: 0x20 and 0x09-0x0D; the rest is word.
SPACED = np.ones(256, bool)
SPACED[[0x20, *range(0x09, 0x0E)]] = False
#: Digits, letters a-z (after lower-casing) and all bytes of non-ASCII characters.
ALNUM = np.zeros(256, bool)
ALNUM[0x30:0x3A] = True
ALNUM[0x61:0x7B] = True
ALNUM[0x80:] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit values."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    return x


def eights(padded: np.ndarray) -> np.ndarray:
    """The eight bytes from each position on, as one number, up to eight bytes before the end."""
    return np.ndarray((len(padded) - 7,), "<u8", padded.data, 0, (1,))


def _eights(data: np.ndarray) -> np.ndarray:
    return eights(np.concatenate([data, np.zeros(8, np.uint8)]))


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of every span of bytes."""
    size = ends - starts
    h = mix(size.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    if not len(size):
        return h
    eights = _eights(data)
    live = np.flatnonzero((size > 0) & (size <= LONG))
    at, left = starts[live], size[live]
    while len(live):
        part = eights[at] & _MASKS[np.minimum(left, 8)]
        h[live] = mix(h[live] ^ part)
        more = left > 8
        live, at, left = live[more], at[more] + 8, left[more] - 8
    whole = None
    for i in np.flatnonzero(size > LONG).tolist():
        whole = whole if whole is not None else memoryview(np.ascontiguousarray(data))
        h[i] = xxhash.xxh64_intdigest(whole[int(starts[i]) : int(ends[i])], _SEED)
    return h


def same_spans(data: np.ndarray, starts: np.ndarray, other: np.ndarray, others: np.ndarray, size: np.ndarray, padded: bool = False) -> np.ndarray:
    """Whether the `size` bytes of data from `starts` on equal those of other (with eight spare bytes if padded) from `others` on, pair by pair."""
    same = np.ones(len(size), bool)
    if not len(size):
        return same
    one = _eights(data)
    two = one if other is data else eights(other) if padded else _eights(other)
    live = np.flatnonzero((size > 0) & (size <= LONG))
    a, b, left = starts[live], others[live], size[live]
    while len(live):
        equal = (one[a] ^ two[b]) & _MASKS[np.minimum(left, 8)] == 0
        same[live[~equal]] = False
        more = (left > 8) & equal
        live, a, b, left = live[more], a[more] + 8, b[more] + 8, left[more] - 8
    for i in np.flatnonzero(size > LONG).tolist():
        n = int(size[i])
        same[i] = np.array_equal(data[int(starts[i]) : int(starts[i]) + n], other[int(others[i]) : int(others[i]) + n])
    return same


def numbered(data: np.ndarray, h: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A number for every span, equal for equal bytes only: by hash, bytes compared; spans whose hashes alone meet get numbers of their own."""
    _, first, number = np.unique(h, return_index=True, return_inverse=True)
    lead = first[number]
    size = ends - starts
    wrong = np.flatnonzero((size != size[lead]) | ~same_spans(data, starts, data, starts[lead], np.minimum(size, size[lead])))
    if len(wrong):
        known: dict[bytes, int] = {}
        for i in wrong.tolist():
            number[i] = len(first) + known.setdefault(data[starts[i] : ends[i]].tobytes(), len(known))
    return number


def spans(inside: np.ndarray, doc_starts: np.ndarray, doc_ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of `inside` bytes; no run crosses a text's border."""
    n = len(inside)
    before = np.zeros(n, bool)
    before[1:] = inside[:-1]
    before[doc_starts[doc_starts < n]] = False
    after = np.zeros(n, bool)
    after[:-1] = inside[1:]
    last = doc_ends[doc_ends > doc_starts] - 1
    after[last] = False
    return np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1


def owners(positions: np.ndarray, doc_starts: np.ndarray, doc_ends: np.ndarray) -> np.ndarray:
    """Row of each position (empty rows own none)."""
    return np.searchsorted(doc_ends, positions, "right")


def tally(positions: np.ndarray, doc_starts: np.ndarray, doc_ends: np.ndarray) -> np.ndarray:
    """Number of sorted positions in each text."""
    return np.searchsorted(positions, doc_ends, "left") - np.searchsorted(positions, doc_starts, "left")


def sums_by(values: np.ndarray, doc_starts: np.ndarray, doc_ends: np.ndarray) -> np.ndarray:
    """Sum of per-byte values for each text (ascending, disjoint), without an array of running sums."""
    out = np.zeros(len(doc_starts), np.int64)
    full = np.flatnonzero(doc_ends > doc_starts)
    if len(full):
        cuts = np.stack([doc_starts[full], doc_ends[full]], 1).ravel()
        if cuts[-1] == len(values):
            cuts = cuts[:-1]
        out[full] = np.add.reduceat(values, cuts, dtype=np.int64)[::2]
    return out


def words(data: np.ndarray, doc_starts: np.ndarray, doc_ends: np.ndarray, table: np.ndarray = SPACED, lower: bool = False):
    """Hash, first byte, end byte and row of every word."""
    if lower:
        data = LOWER[data]
    a, b = spans(table[data], doc_starts, doc_ends)
    return span_hashes(data, a, b), a, b, owners(a, doc_starts, doc_ends)


def hash_word(word: bytes) -> int:
    """Hash of one word, as words() gives it."""
    data = np.frombuffer(word, np.uint8)
    return int(span_hashes(data, np.array([0]), np.array([len(data)]))[0])
