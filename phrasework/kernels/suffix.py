"""Suffix order of one string, and the factors and extensions that follow from it, in linear space.

Positions are 0-based here and in all kernels; DataFrames show them 1-based.
"""

from __future__ import annotations

import numpy as np

#: Bits of a packed run of characters; floats hold them exactly, so ``frexp`` finds the first difference.
PACKED_BITS = 52
#: Pairs below which a long comparison goes pair by pair, in blocks that double.
FEW_PAIRS = 64


def codes_of(text: str | bytes, unit: str = "codepoint") -> np.ndarray:
    """The string as integers: code points, or UTF-8 bytes with ``unit='byte'``."""
    if isinstance(text, str):
        text = text.encode("utf-8" if unit == "byte" else "utf-32-le", "surrogatepass")
        return np.frombuffer(text, np.uint8 if unit == "byte" else "<i4")
    return np.frombuffer(text, np.uint8)


def _group_starts(first: np.ndarray, kind: type) -> np.ndarray:
    """For each slot the slot that begins its group, given where groups begin."""
    return np.maximum.accumulate(np.where(first, np.arange(len(first), dtype=kind), kind(0)))


def _shared(first: np.ndarray) -> np.ndarray:
    """Slots whose group has more than one member."""
    follows = np.append(~first[1:], False) if len(first) else first
    return np.flatnonzero(~first | follows)


def _packed(codes: np.ndarray) -> tuple[np.ndarray, int, int]:
    """(runs, bits, size): the next ``size`` characters of each position as one integer, 0 behind the end."""
    small = codes.dtype.itemsize == 1 or int(codes.max()) < 1 << 16
    seen = np.flatnonzero(np.bincount(codes, minlength=1)) if small else np.unique(codes)
    if small:
        names = np.zeros(int(seen[-1]) + 1, np.int64)
        names[seen] = np.arange(1, len(seen) + 1)
        dense = names[codes]
    else:
        dense = np.searchsorted(seen, codes) + 1
    bits = len(seen).bit_length()
    size = max(1, PACKED_BITS // bits)
    runs, have = dense, 1
    while have < size:
        take = min(have, size - have)  # the first ``take`` characters of what starts ``have`` further on
        ahead = runs >> (bits * (have - take))
        runs = runs << (bits * take)
        runs[:-have] |= ahead[have:]
        have += take
    return runs, bits, size


class SuffixIndex:
    """Suffix array ``sa``, its inverse ``rank`` and ``lcp`` array of a string.

    Order by prefix doubling from packed runs of characters; a round sorts only suffixes that
    still share their rank. LCPs compare only pairs whose characters before differ: along the
    text each other value is the one before less one.
    """

    def __init__(self, codes: np.ndarray):
        n = self.n = len(codes)
        kind = self.kind = np.int32 if n < 1 << 31 else np.int64
        self._mins: list[np.ndarray] | None = None
        if not n:
            self.sa = self.rank = self.lcp = np.zeros(0, kind)
            return
        runs, bits, size = _packed(codes)
        self.sa, self.rank = self._order(runs, size, kind)
        self.lcp = self._common(codes, runs, bits, size, kind)

    def _order(self, runs: np.ndarray, size: int, kind: type) -> tuple[np.ndarray, np.ndarray]:
        n = self.n
        order = np.argsort(runs).astype(kind)
        ordered = runs[order]
        first = np.ones(n, bool)
        first[1:] = ordered[1:] != ordered[:-1]
        del ordered
        rank = np.empty(n, kind)
        rank[order] = _group_starts(first, kind)
        live = _shared(first).astype(kind)
        step = size
        while len(live):  # slots of the order whose group has more than one suffix
            at = order[live]
            key = rank[at].astype(np.int64) * (n + 1)
            ahead = at + kind(step)
            fits = ahead < n
            key[fits] += rank[ahead[fits]] + np.int64(1)
            by_key = np.argsort(key)
            at, key = at[by_key], key[by_key]
            order[live] = at
            first = np.ones(len(live), bool)
            first[1:] = key[1:] != key[:-1]
            rank[at] = live[_group_starts(first, kind)]
            live = live[_shared(first)]
            step *= 2
        return order, rank

    def _common(self, codes: np.ndarray, runs: np.ndarray, bits: int, size: int, kind: type) -> np.ndarray:
        n, sa = self.n, self.sa
        before = np.full(n, -1, kind)
        before[sa[1:]] = sa[:-1]
        fresh = np.ones(n, bool)
        fresh[1:] = (before[1:] <= 0) | (codes[:-1] != codes[before[1:] - 1])
        along = np.zeros(n, kind)
        left = np.flatnonzero(fresh & (before >= 0)).astype(kind)
        right = before[left]
        del before
        done = kind(0)
        runs = np.append(runs, 0)  # a suffix may end just where its next run would begin
        while len(left) > FEW_PAIRS:
            differ = runs[left + done] ^ runs[right + done]
            apart = np.flatnonzero(differ)
            along[left[apart]] = done + (size * bits - np.frexp(differ[apart].astype(np.float64))[1]) // bits
            keep = differ == 0
            left, right = left[keep], right[keep]
            done += kind(size)
        for a, b in zip(left.tolist(), right.tolist()):
            along[a] = _common_prefix(codes, a, b, int(done))
        at = np.arange(n, dtype=kind)
        start = np.maximum.accumulate(np.where(fresh, at, kind(0)))
        along = along[start] - (at - start)
        return along[sa]

    def lce(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Length of the longest common prefix of suffixes i and j, pair by pair; n - i where i = j.

        Range minima over ``lcp``; their table, n log n in space, is built on first use only.
        """
        i, j = np.asarray(i, np.int64), np.asarray(j, np.int64)
        if self._mins is None:
            self._mins = [self.lcp]
            while (2 << (len(self._mins) - 1)) <= self.n:
                half = 1 << (len(self._mins) - 1)
                self._mins.append(np.minimum(self._mins[-1][:-half], self._mins[-1][half:]))
        out = (self.n - i).astype(np.int64)
        apart = np.flatnonzero(i != j)
        a, b = self.rank[i[apart]].astype(np.int64), self.rank[j[apart]].astype(np.int64)
        low, high = np.minimum(a, b) + 1, np.maximum(a, b) + 1
        level = np.frexp((high - low).astype(np.float64))[1] - 1
        for t in np.unique(level):
            at = np.flatnonzero(level == t)
            out[apart[at]] = np.minimum(self._mins[t][low[at]], self._mins[t][high[at] - (1 << int(t))])
        return out


def _common_prefix(codes: np.ndarray, a: int, b: int, done: int) -> int:
    """Common prefix of suffixes a and b that agree on ``done`` characters, by growing blocks."""
    n, block = len(codes), 64
    while True:
        size = min(block, n - max(a, b) - done)
        if size <= 0:
            return done
        differ = codes[a + done : a + done + size] != codes[b + done : b + done + size]
        if differ.any():
            return done + int(differ.argmax())
        done += size
        block = min(2 * block, 1 << 20)


#: Jumps a slot, and slots a round of them, up to which jumping goes on before a stack takes over.
JUMPS_PER_SLOT, SLOTS_PER_ROUND = 32, 256


def _nearest_slots(value: np.ndarray, gap: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray | None]:
    """For each slot the nearest earlier slot of a smaller value (-1: none), and the least gap up to it.

    ``gap[k]`` belongs to the step from slot k - 1 to k; with gaps, slots that reach one of 0
    stop there. All slots jump together: what lies between a slot and the one it points to is
    too large, and so is what lies between that one and where it points. Few orders need many
    jumps; those are left to a stack.
    """
    n = len(value)
    kind = value.dtype.type
    to = np.arange(-1, n - 1, dtype=kind)
    least = None if gap is None else gap.copy()
    live = np.arange(1, n, dtype=kind)
    left = n * JUMPS_PER_SLOT
    while left > 0:
        if least is not None:
            live = live[least[live] > 0]
        left -= len(live) + SLOTS_PER_ROUND
        step = to[live]
        more = value[step] > value[live]
        live, step = live[more], step[more]
        if not len(live):
            return to, least
        if least is not None:
            least[live] = np.minimum(least[live], least[step])
        to[live] = to[step]
        live = live[to[live] >= 0]
    return _nearest_by_stack(value, gap)


def _nearest_by_stack(value: np.ndarray, gap: np.ndarray | None) -> tuple[np.ndarray, np.ndarray | None]:
    to, stack = np.empty_like(value), []
    least = None if gap is None else gap.copy()
    steps = [0] * len(value) if gap is None else gap.tolist()
    held: list[int] = []  # least gap from each stacked slot to the one below it
    for k, v in enumerate(value.tolist()):
        now = steps[k]
        while stack and stack[-1][1] > v:
            stack.pop()
            now = min(now, held.pop())
        to[k] = stack[-1][0] if stack else -1
        if least is not None:
            least[k] = now
        stack.append((k, v))
        held.append(now)
    return to, least


def nearest(order: np.ndarray, larger: bool) -> np.ndarray:
    """For each text position, the nearest earlier entry of ``order`` that is smaller (or larger); -1 if none."""
    order = np.asarray(order)
    to, _ = _nearest_slots(-order if larger else order)
    out = np.full(len(order), -1, np.int64)
    out[order] = np.where(to >= 0, order[np.maximum(to, 0)], -1)
    return out


def factor(index: SuffixIndex, later: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Longest earlier (or later) occurrence at each position: lengths, and one place each (-1: none)."""
    n, kind = index.n, index.kind
    if not n:
        return np.zeros(0, kind), np.zeros(0, kind)
    sides = []
    for order, gap in ((index.sa, index.lcp), (index.sa[::-1], np.concatenate([np.zeros(1, kind), index.lcp[:0:-1]]))):
        to, least = _nearest_slots(-order if later else order, gap)
        least[to < 0] = 0
        sides.append((order[np.maximum(to, 0)], least))
    (below, a), (above, b) = sides[0], (sides[1][0][::-1], sides[1][1][::-1])
    length, ref = np.empty(n, kind), np.empty(n, kind)
    best = np.maximum(a, b)
    length[index.sa] = best
    ref[index.sa] = np.where(best == 0, kind(-1), np.where(a >= b, below, above))
    return length, ref


def rightmost_next(index: SuffixIndex, lengths: np.ndarray, refs: np.ndarray | None = None) -> np.ndarray:
    """Largest position that shares the longest later occurrence of suffix i; i itself where there is none.

    ``lengths`` and ``refs`` are what :func:`factor` gives. A place that is not yet the rightmost
    one has a later occurrence at least as long itself, so all positions follow such references together.
    """
    if refs is None:
        lengths, refs = factor(index, later=True)
    at = np.arange(index.n, dtype=index.kind)
    to = np.where(lengths > 0, refs, at)
    live = np.flatnonzero(lengths > 0)
    while len(live):
        step = to[live]
        more = lengths[step] >= lengths[live]
        live = live[more]
        to[live] = to[step[more]]
    return to
