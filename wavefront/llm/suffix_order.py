"""Suffix order by difference cover, one bucket at a time.

A difference cover D of period v holds, for any two positions i and j, a shift below v that takes both onto positions
whose residue is in D. So once the suffixes at those cover positions are ranked, any two suffixes compare by fewer
than v bytes and one look-up. Buckets of suffixes are then sorted one by one: memory holds the text, the cover ranks
and one bucket, never a whole suffix array's working space.

``suffix_array`` orders all suffixes of one text. ``repeated_starts`` is the same construction cut at a fixed depth
and run over a block of many short texts: it tells which starts of a ``LENGTH``-byte string have an equal elsewhere.
"""

from __future__ import annotations

import functools

import numpy as np


@functools.cache
def difference_cover(v: int) -> tuple[int, ...]:
    """A small cover of period v, grown greedily: each step takes the residue that adds most new differences."""
    cover, open_ = [0], set(range(1, v))
    while open_:
        gain = {r: len({d for c in cover for d in ((r - c) % v, (c - r) % v)} & open_) for r in range(v) if r not in cover}
        best = max(gain, key=lambda r: (gain[r], -r))
        open_ -= {d for c in cover for d in ((best - c) % v, (c - best) % v)}
        cover.append(best)
    return tuple(sorted(cover))


@functools.cache
def shift_table(v: int) -> np.ndarray:
    """[i mod v, j mod v] -> the least shift that takes both onto the cover."""
    inside = np.isin(np.arange(2 * v) % v, difference_cover(v))
    out = np.zeros((v, v), np.int64)
    for i in range(v):
        for j in range(v):
            out[i, j] = next(s for s in range(v) if inside[i + s] and inside[j + s])
    return out


def dense_rank(*keys: np.ndarray) -> np.ndarray:
    """Rank of each row of the keys, equal rows alike, the first key most significant."""
    rank = np.unique(keys[0], return_inverse=True)[1].astype(np.uint64)
    for k in keys[1:]:
        low = np.unique(k, return_inverse=True)[1].astype(np.uint64)
        rank = np.unique((rank << np.uint64(32)) | low, return_inverse=True)[1].astype(np.uint64)
    return rank


def words_at(text: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The eight bytes from each position as one big-endian number, whose order is the bytes' order."""
    out = np.zeros(len(at), np.uint64)
    for k in range(8):
        out = (out << np.uint64(8)) | text[at + k].astype(np.uint64)
    return out


class CoverRanks:
    """Ranks of the suffixes at cover positions, by prefix doubling in steps of the period.

    ``depth`` None ranks whole suffixes; otherwise the first ``depth`` bytes, a multiple of the period that is a
    power of two times v or the sum of two such.
    """

    def __init__(self, text: np.ndarray, v: int, depth: int | None = None):
        self.v, self.cover = v, np.array(difference_cover(v))
        rows = -(-len(text) // v) + 1
        self.slot = np.full(v, -1, np.int64)
        self.slot[self.cover] = np.arange(len(self.cover))
        padded = np.zeros(rows * v + 2 * v + 8, np.uint8)
        padded[: len(text)] = text
        at = (np.arange(rows)[:, None] * v + self.cover[None, :]).ravel()
        keys = [words_at(padded, at + k) for k in range(0, v, 8)]
        if depth is None:  # a suffix that ends first is less: its length within the text breaks the tie with zero bytes
            keys.append(np.clip(len(text) - at, 0, v).astype(np.uint64))
        rank = dense_rank(*keys).reshape(rows, len(self.cover))
        levels, reach = {v: rank}, v
        while depth is None and int(rank.max()) + 1 < rank.size and reach < len(text) + v or depth is not None and 2 * reach <= depth:
            rank = self._joined(rank, rank, reach)
            reach *= 2
            levels[reach] = rank
        if depth is not None and reach < depth:
            rank = self._joined(rank, levels[depth - reach], reach)
        self.rank = rank

    def _joined(self, left: np.ndarray, right: np.ndarray, step: int) -> np.ndarray:
        k = step // self.v
        beyond = np.zeros_like(right)
        beyond[:-k] = right[k:] + np.uint64(1) if k < len(right) else beyond[:-k]
        return np.unique((left.ravel() << np.uint64(32)) | beyond.ravel(), return_inverse=True)[1].astype(np.uint64).reshape(left.shape)

    def at(self, position: np.ndarray) -> np.ndarray:
        return self.rank[position // self.v, self.slot[position % self.v]]


def suffix_array(text: bytes, v: int = 32) -> np.ndarray:
    """Starts of all suffixes of ``text`` in order, bucket by bucket (a bucket: suffixes with the same first byte)."""
    data = np.frombuffer(text, np.uint8)
    n = len(data)
    if not n:
        return np.empty(0, np.int64)
    cover, shift = CoverRanks(data, v), shift_table(v)

    def compare(i: int, j: int) -> int:
        s = int(shift[i % v, j % v])
        a, b = text[i : i + s], text[j : j + s]
        if a != b:
            return -1 if a < b else 1
        p, q = (int(cover.at(np.array([x + s]))[0]) if x + s < n else -1 for x in (i, j))
        return (p > q) - (p < q)

    out = []
    for first in range(256):
        bucket = np.flatnonzero(data == first)
        out += sorted(bucket.tolist(), key=functools.cmp_to_key(compare))
    return np.array(out, np.int64)


LENGTH = 400
PERIOD = 16
_INNER = 384  # PERIOD * (16 + 8): what the cover ranks compare; the other 16 bytes of a string lie before and after


def repeated_starts(slices: list[bytes], bucket: np.ndarray, anchor: np.ndarray, weight: np.ndarray) -> list[np.ndarray]:
    """For each slice a boolean for each start of a LENGTH-byte string in it: does an equal string start elsewhere?

    Slices of one ``bucket`` hold the same anchor, ``anchor[i]`` bytes from the slice's start, and equal strings of a
    bucket lie alike around it. ``weight[i]`` is how often the slice stands in the corpus. Slices are laid out with
    their anchors on multiples of the period, so equal strings agree modulo it, one shift serves a whole bucket, and
    a string's key is its bytes before the cover position, the cover rank and the bytes after.
    """
    length = np.array([len(s) for s in slices], np.int64)
    base = np.zeros(len(slices), np.int64)
    room = (length + 2 * PERIOD + PERIOD - 1) // PERIOD * PERIOD
    block = np.concatenate(([0], np.cumsum(room)))
    base = block[:-1] + (-anchor) % PERIOD
    text = np.zeros(int(block[-1]) + LENGTH + 2 * PERIOD, np.uint8)
    for b, s in zip(base.tolist(), slices, strict=True):
        text[b : b + len(s)] = np.frombuffer(s, np.uint8)
    cover = CoverRanks(text, PERIOD, _INNER)
    starts_of = length - LENGTH + 1
    owner = np.repeat(np.arange(len(slices)), starts_of)
    ends = np.cumsum(starts_of)
    within = np.arange(int(ends[-1])) - np.repeat(ends - starts_of, starts_of)
    at = base[owner] + within
    shift = shift_table(PERIOD).diagonal()[at % PERIOD]
    zero = np.zeros(1, np.uint64)
    head, tail = words_at(text, at), words_at(text, at + 8)
    low, last = words_at(text, at + LENGTH - 16), words_at(text, at + LENGTH - 8)
    full = np.uint64(0xFFFFFFFFFFFFFFFF)

    def keep(n: np.ndarray) -> np.ndarray:  # mask of the first n (0..8) bytes of a word
        n = np.clip(n, 0, 8).astype(np.uint64)
        return np.where(n == 0, zero, full << (np.uint64(8) * (np.uint64(8) - np.maximum(n, np.uint64(1)))))

    before = dense_rank(head & keep(shift), tail & keep(shift - 8))
    after = dense_rank(low & ~keep(shift), last & ~keep(shift - 8))
    place = (np.asarray(bucket, np.int64)[owner] << 12) + (within - anchor[owner] + 2048)
    where = np.unique(place, return_inverse=True)[1].astype(np.uint64)
    key = dense_rank(where, before, cover.at(at + shift), after)
    times = np.zeros(int(key.max()) + 1, np.int64)
    np.add.at(times, key.astype(np.int64), np.asarray(weight, np.int64)[owner])
    again = times[key.astype(np.int64)] > 1
    return np.split(again, ends[:-1])
