"""One-sided and suffix-order parses of one string, and helpers for any parse.

Phrases are (start, length, reference) with reference -1 for a literal.
"""

from __future__ import annotations

import numpy as np

from phrasework.kernels.sources import machine
from phrasework.kernels.suffix import SuffixIndex, factor

Phrases = list[tuple[int, int, int]]


def jump(lengths: np.ndarray, refs: np.ndarray) -> Phrases:
    """Walk from the start, by each position's length or one character where that is zero."""
    lengths, refs = machine(lengths), machine(refs)
    out, i = [], 0
    while i < len(lengths):
        size = lengths[i]
        out.append((i, size or 1, refs[i] if size else -1))
        i += size or 1
    return out


def left_parse(codes: np.ndarray, index: SuffixIndex | None = None) -> Phrases:
    """Longest earlier occurrence each time; overlap is allowed."""
    return jump(*factor(index or SuffixIndex(codes)))


def right_parse(codes: np.ndarray, index: SuffixIndex | None = None) -> Phrases:
    """Longest later occurrence each time."""
    return jump(*factor(index or SuffixIndex(codes), later=True))


def lex_parse(codes: np.ndarray, index: SuffixIndex | None = None) -> Phrases:
    """Copy from the suffix one rank above, as far as the two agree."""
    index = index or SuffixIndex(codes)
    before = np.where(index.rank > 0, index.sa[np.maximum(index.rank - 1, 0)], -1) if index.n else np.zeros(0, np.int64)
    return jump(index.lcp[index.rank] if index.n else np.zeros(0, np.int64), before)


def map_back(phrases: Phrases, n: int) -> Phrases:
    """Phrases of the reversed string in the string's own positions, in its own order."""
    return [(n - s - size, size, n - ref - size if ref >= 0 else -1) for s, size, ref in reversed(phrases)]


def backward_parse(codes: np.ndarray) -> Phrases:
    """From the end, the longest substring ending here that also ends earlier."""
    return map_back(right_parse(codes[::-1]), len(codes))


def literal_parse(codes: np.ndarray) -> Phrases:
    return [(i, 1, -1) for i in range(len(codes))]


def references(phrases: Phrases, n: int) -> np.ndarray:
    """Position each position refers to; -1 for literals and for what no phrase covers."""
    out = np.full(n, -1, np.int64)
    for start, size, ref in phrases:
        if ref >= 0:
            out[start : start + size] = np.arange(ref, ref + size)
    return out


def resolve(refs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(source, hops) of each position by pointer doubling; source -1 where the chase never ends."""
    n = len(refs)
    at, hops = np.where(refs >= 0, refs, np.arange(n)), (refs >= 0).astype(np.int64)
    for _ in range(max(1, n).bit_length() + 1):
        hops = hops + hops[at]
        at = at[at]
    done = refs[at] < 0 if n else np.zeros(0, bool)
    return np.where(done, at, -1), np.where(done, hops, -1)


def decode(phrases: Phrases, literals: dict[int, int], n: int) -> np.ndarray | None:
    """Characters of a parse, or None if a chain of references never ends."""
    source, _ = resolve(references(phrases, n))
    if (source < 0).any():
        return None
    return np.array([literals[s] for s in source.tolist()], np.int64)
