"""Further parses of one string that serve as comparisons, and exhaustive ones for tiny strings.

Phrases are (start, length, reference) with reference -1 for a literal.
"""

from __future__ import annotations

import heapq
from itertools import combinations

import numpy as np

from phrasework.kernels.greedy import Phrases, references, resolve
from phrasework.kernels.suffix import SuffixIndex

#: Longest string that the exhaustive searches take.
EXHAUSTIVE = 10


def largest_first_parse(codes: np.ndarray, threshold: int = 2, index: SuffixIndex | None = None) -> Phrases:
    """Take the largest remaining LCP entry of at least ``threshold`` as a copy, again and again.

    A suffix copies from the one a rank above it. Positions once taken are gone: entries that
    begin there are dropped and entries that run into them are clipped.
    """
    index = index or SuffixIndex(codes)
    n = index.n
    taken = np.zeros(n + 1, bool)
    taken[n] = True
    heap = [(-int(index.lcp[r]), int(index.sa[r]), int(index.sa[r - 1])) for r in range(1, n) if index.lcp[r] >= threshold]
    heapq.heapify(heap)
    copies: dict[int, tuple[int, int]] = {}
    while heap:
        size, at, ref = heapq.heappop(heap)
        if taken[at]:
            continue
        run = taken[at : at - size + 1]
        free = int(run.argmax()) if run.any() else -size
        if free < -size:
            if free >= threshold:
                heapq.heappush(heap, (-free, at, ref))
            continue
        copies[at] = (free, ref)
        taken[at : at + free] = True
    out, i = [], 0
    while i < n:
        size, ref = copies.get(i, (1, -1))
        out.append((i, size, ref))
        i += size
    return out


def bwt(index: SuffixIndex, codes: np.ndarray) -> np.ndarray:
    """Last column of the sorted rotations of the string with an end mark; the mark is -1."""
    last = np.where(index.sa > 0, codes[np.maximum(index.sa - 1, 0)], -1) if index.n else np.zeros(0, np.int64)
    return np.concatenate([codes[-1:], last])


def bwt_runs(codes: np.ndarray, index: SuffixIndex | None = None) -> int:
    """Number of equal-letter runs of the transform."""
    column = bwt(index or SuffixIndex(codes), codes)
    return int(1 + np.count_nonzero(np.diff(column))) if len(codes) else 0


def bwt_run_parse(codes: np.ndarray, index: SuffixIndex | None = None) -> Phrases:
    """Copies that the transform's runs imply, at most two phrases a run.

    Where the characters before two neighbours of the suffix order agree, the later rank's one
    copies the earlier one's. Along the text such copies continue each other; a phrase ends
    where their distance changes.
    """
    index = index or SuffixIndex(codes)
    n = index.n
    ref = np.full(n, -1, np.int64)
    rank = index.rank
    for p in range(n):
        follow = rank[p + 1] if p + 1 < n else -1
        above = index.sa[follow - 1] if follow > 0 else n if follow == 0 else -1
        if above > 0 and codes[above - 1] == codes[p]:
            ref[p] = above - 1
    out, i = [], 0
    while i < n:
        j = i + 1
        if ref[i] >= 0:
            while j < n and ref[j] == ref[i] + j - i:
                j += 1
        out.append((i, j - i, int(ref[i])))
        i = j
    return out


def is_attractor(codes: np.ndarray, positions: set[int]) -> bool:
    """Whether every substring has an occurrence that covers one of the positions."""
    text, n = codes.tolist(), len(codes)
    for size in range(1, n + 1):
        covered: dict[tuple, bool] = {}
        for i in range(n - size + 1):
            key = tuple(text[i : i + size])
            covered[key] = covered.get(key, False) or any(i <= p < i + size for p in positions)
        if not all(covered.values()):
            return False
    return True


def attractor_parse(codes: np.ndarray, positions: set[int]) -> Phrases:
    """Literals at the attractor, and between them copies that double away from it.

    A stretch between two attractor positions is cut into pieces whose lengths double with
    their distance from the nearer one; each piece copies an occurrence that covers an
    attractor position. Pieces that would make a chain endless are cut in half, single
    characters becoming literals.
    """
    if not is_attractor(codes, positions):
        raise ValueError("not an attractor")
    text, n = codes.tolist(), len(codes)
    marks = sorted(positions)
    refs = np.full(n, -1, np.int64)
    pieces: list[tuple[int, int]] = [(p, 1) for p in marks]
    bounds = [-1, *marks, n]
    for a, b in zip(bounds[:-1], bounds[1:]):
        left, right, size = a + 1, b, 1
        while left < right:
            take = min(size, right - left)
            pieces.append((left, take))
            left += take
            if left < right:
                take = min(size, right - left)
                right -= take
                pieces.append((right, take))
            size *= 2
    out: Phrases = []
    todo = sorted(pieces)
    while todo:
        start, size = todo.pop(0)
        if start in positions and size == 1:
            out.append((start, 1, -1))
            continue
        own = text[start : start + size]
        done = False
        for ref in range(n - size + 1):
            if ref != start and text[ref : ref + size] == own and any(ref <= p < ref + size for p in positions):
                refs[start : start + size] = np.arange(ref, ref + size)
                if (resolve(refs)[0] >= 0).all():
                    out.append((start, size, ref))
                    done = True
                    break
                refs[start : start + size] = -1
        if not done:
            if size == 1:
                out.append((start, 1, -1))
            else:
                todo[:0] = [(start, size // 2), (start + size // 2, size - size // 2)]
    return sorted(out)


def smallest_parse(codes: np.ndarray) -> Phrases:
    """A parse of the fewest phrases, by trying all; only for up to ``EXHAUSTIVE`` characters."""
    n = len(codes)
    if n > EXHAUSTIVE:
        raise ValueError(f"more than {EXHAUSTIVE} characters")
    text = codes.tolist()
    places = {(i, size): [j for j in range(n - size + 1) if j != i and text[j : j + size] == text[i : i + size]] for i in range(n) for size in range(1, n - i + 1)}

    def fill(i: int, left: int, phrases: Phrases) -> Phrases | None:
        if i == n:
            return phrases if (resolve(references(phrases, n))[0] >= 0).all() else None
        if not left:
            return None
        for size in range(n - i, 0, -1):
            if left == 1 and i + size < n:
                break
            choices = places[i, size] + ([-1] if size == 1 else [])
            for ref in choices:
                got = fill(i + size, left - 1, [*phrases, (i, size, ref)])
                if got is not None:
                    return got
        return None

    for count in range(n + 1):
        got = fill(0, count, [])
        if got is not None:
            return got
    raise AssertionError("unreachable")


def smallest_attractor(codes: np.ndarray) -> set[int]:
    """An attractor of the fewest positions, by trying all; only for up to ``EXHAUSTIVE`` characters."""
    n = len(codes)
    if n > EXHAUSTIVE:
        raise ValueError(f"more than {EXHAUSTIVE} characters")
    for count in range(n + 1):
        for chosen in combinations(range(n), count):
            if is_attractor(codes, set(chosen)):
                return set(chosen)
    raise AssertionError("unreachable")
