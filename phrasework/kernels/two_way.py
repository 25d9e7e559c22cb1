"""Greedy two-way parse of one string: longest copy from the left or the right that decodes.

Phrases are (start, length, reference) with reference -1 for a literal.
"""

from __future__ import annotations

from array import array
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np

from phrasework.kernels.suffix import SuffixIndex, factor, rightmost_next
from phrasework.kernels.sources import Overlay, Sources, machine

TIES = ("rightmost", "leftmost", "walk_lower", "walk_upper", "nearest_right", "nearest_left")
SIDES = ("both", "left", "right")


@dataclass(frozen=True)
class Options:
    """How the parse chooses among candidates, and which parts of it are replaced for comparison."""

    tie: str = "rightmost"
    search: str = "pruned"
    validity: str = "classes"
    overlay: bool = True
    floor: bool = True
    sides: str = "both"
    max_candidates: int | None = None
    link: str = "directed"

    def __post_init__(self):
        for name, allowed in (("tie", TIES), ("search", ("pruned", "exhaustive")), ("validity", ("classes", "graph")), ("sides", SIDES)):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")
        if self.max_candidates is not None and self.max_candidates < 1:
            raise ValueError("max_candidates must be positive")


#: The rules for which the search has a loop of its own.
PLAIN = Options()
#: Places of equal LCE from which they are tested together, and the most of them at once.
MANY, MOST = 32, 4096


@dataclass
class Trace:
    """Work of one phrase search."""

    candidates: int = 0
    groups: int = 0
    finds: int = 0
    unions: int = 0
    stop_lce: int = 0
    tests: int = 0


@dataclass
class Parse:
    phrases: list[tuple[int, int, int]] = field(default_factory=list)
    traces: list[Trace] = field(default_factory=list)


def walk(sa: Sequence[int], rank: Sequence[int], lcp: Sequence[int], i: int, upper_first: bool = False) -> Iterator[tuple[int, int]]:
    """(LCE with i, position) of the other suffixes, largest LCE first, by two cursors from i's rank."""
    n = len(sa)  # ``lcp`` may have a last 0 more
    low, high = rank[i] - 1, rank[i] + 1
    below = lcp[rank[i]] if low >= 0 else 0
    above = lcp[high] if high < n else 0
    while below or above:
        if below > above or (below == above and not upper_first):
            yield below, sa[low]
            below = min(below, lcp[low]) if low else 0
            low -= 1
        else:
            yield above, sa[high]
            high += 1
            above = min(above, lcp[high]) if high < n else 0


def ordered(stream: Iterator[tuple[int, int]], i: int, tie: str, least: int = 0) -> Iterator[tuple[int, list[int]]]:
    """Groups of equal LCE above ``least``, each in the order of the tie rule."""
    keys = {"rightmost": lambda j: -j, "leftmost": lambda j: j, "nearest_right": lambda j: (abs(j - i), -j), "nearest_left": lambda j: (abs(j - i), j)}
    group, now = [], 0
    for lce, j in stream:
        if lce <= least:
            break
        if lce != now and group:
            yield now, group if tie.startswith("walk") else sorted(group, key=keys[tie])
            group = []
        now = lce
        group.append(j)
    if group:
        yield now, group if tie.startswith("walk") else sorted(group, key=keys[tie])


class TwoWay:
    """State of a parse: suffix data, classes of positions with one source, phrases so far.

    All arrays hold machine integers, so a parse takes a fixed number of bytes a character.
    """

    def __init__(self, codes: np.ndarray, options: Options = Options(), index: SuffixIndex | None = None):
        self.codes, self.options = codes, options
        self.index = index or SuffixIndex(codes)
        self.n = self.index.n
        self.next_len: array | None = None
        # Among later places of the floor's length only the rightmost is known at once; other tie rules
        # use the floor only where the stream is cut short anyway.
        exact = options.tie == "rightmost" and options.search == "pruned"
        if options.floor and options.sides != "left" and (exact or options.max_candidates is not None):
            lengths, refs = factor(self.index, later=True)
            if options.tie == "rightmost":
                refs = np.where(lengths > 0, rightmost_next(self.index, lengths, refs), refs)
            self.next_len, self.next_ref = machine(lengths), machine(refs)
            # The largest LCE of a position with any other: above the floor only left candidates are left.
            beside = np.append(self.index.lcp, self.index.lcp[:0].dtype.type(0))
            self.top = machine(np.maximum(beside[self.index.rank], beside[self.index.rank + 1]))
        self.sa, self.rank = machine(self.index.sa), machine(self.index.rank)
        self.lcp = machine(np.append(self.index.lcp, self.index.lcp.dtype.type(0)))
        self.sources = Sources(self.n, options.link)
        self.phrases: list[tuple[int, int, int]] = []
        self.at = 0

    def extension(self, i: int, j: int, lce: int) -> int:
        """Longest copy of j at i, up to ``lce``, that leaves every chain of references finite."""
        if j > i and self.options.validity == "classes":
            return lce
        if self.options.validity == "graph":
            return self._extension_by_graph(i, j, lce)
        if self.options.overlay:
            return self._extension_on_overlay(i, j, lce)
        return self._extension_with_undo(i, j, lce)

    def _extension_on_overlay(self, i: int, j: int, lce: int) -> int:
        if self.sources.label is not None:
            over = Overlay(self.sources)
            for k in range(lce):
                target = over.source(j + k)
                if target == i + k:
                    return k
                over.merge(i + k, target)
            return lce
        got = self.sources.acyclic(i, j, lce)
        self.sources.finds += got + (got < lce)
        return got

    def _extension_with_undo(self, i: int, j: int, lce: int) -> int:
        """Merge for real, without shortening paths, and take the merges back."""
        if self.sources.label is not None:
            raise ValueError("undo needs the directed link rule")
        up, size = self.sources.up, 0
        for k in range(lce):
            target = j + k
            while up[target] != target:
                target = up[target]
            self.sources.finds += 1
            if target == i + k:
                break
            up[i + k] = target
            size += 1
        up[i : i + size] = array(up.typecode, range(i, i + size))
        return size

    def _extension_by_graph(self, i: int, j: int, lce: int) -> int:
        refs = self.references()
        for k in range(lce):
            refs[i + k] = j + k
            x, hops = i + k, 0
            while refs[x] >= 0 and hops <= self.n:
                x, hops = refs[x], hops + 1
            if hops > self.n:
                return k
        return lce

    def references(self) -> list[int]:
        """Where each position refers to after completion by literals; -1 for a literal."""
        refs = [-1] * self.n
        for start, length, ref in self.phrases:
            if ref >= 0:
                for k in range(length):
                    refs[start + k] = ref + k
        return refs

    def profile(self) -> list[int]:
        """Extension of every reference at the current position; 0 for the position itself."""
        i = self.at
        lces = self.index.lce(np.full(self.n, i), np.arange(self.n)).tolist()
        return [0 if j == i else self.extension(i, j, lces[j]) for j in range(self.n)]

    def longest(self, trace: Trace | None = None) -> tuple[int, int]:
        """(length, reference) of the next phrase; length 0 means a literal."""
        i, o = self.at, self.options
        trace = trace or Trace()
        before = self.sources.finds
        best, ref = 0, -1
        if o.search == "exhaustive":
            lces = self.index.lce(np.full(self.n, i), np.arange(self.n))
            for j in np.lexsort((-np.arange(self.n), -lces)).tolist():
                if j != i and self._allowed(i, j):
                    trace.candidates += 1
                    got = self.extension(i, j, int(lces[j]))
                    if got > best:
                        best, ref = got, j
            trace.finds += self.sources.finds - before
            return best, ref
        floor, floor_ref = 0, -1
        if self.next_len is not None and o.sides != "left":
            floor, floor_ref = self.next_len[i], self.next_ref[i]
            if floor == self.top[i]:
                trace.candidates += floor > 0
                return floor, floor_ref
            if o == PLAIN:
                return self._longest_left(i, floor, floor_ref, trace)
        stream = walk(self.sa, self.rank, self.lcp, i, o.tie == "walk_upper")
        for lce, group in ordered(stream, i, o.tie, floor):
            trace.groups += 1
            if lce <= best:
                trace.stop_lce = lce
                break
            for j in group:
                if not self._allowed(i, j):
                    continue
                trace.candidates += 1
                trace.tests += j < i
                got = self.extension(i, j, lce)
                if got > best:
                    best, ref = got, j
                if best == lce or (o.max_candidates is not None and trace.candidates >= o.max_candidates):
                    break
            if best == lce or (o.max_candidates is not None and trace.candidates >= o.max_candidates):
                trace.stop_lce = lce
                break
        if floor > best:
            best, ref = floor, floor_ref
            trace.candidates += 1
        trace.finds += self.sources.finds - before
        return best, ref

    def _longest_left(self, i: int, floor: int, floor_ref: int, trace: Trace) -> tuple[int, int]:
        """The default rules above a floor: only places to the left can be longer, rightmost first.

        ``walk``, ``ordered`` and the test without calls or generators.
        """
        sa, lcp, up, acyclic = self.sa, self.lcp, self.sources.up, self.sources.acyclic
        low = self.rank[i]
        high = low + 1
        below, above = lcp[low], lcp[high]
        best, ref = 0, -1
        tested = chars = 0
        while True:
            now = below if below >= above else above
            if now <= floor or now <= best:
                break
            trace.groups += 1
            group = []
            while below == now:
                low -= 1
                group.append(sa[low])
                if lcp[low] < below:
                    below = lcp[low]
                elif len(group) > MANY:
                    end, low = low, self._run_end(low, now, -1)
                    group.extend(sa[low:end])
                    below = lcp[low]
            while above == now:
                group.append(sa[high])
                high += 1
                if lcp[high] < above:
                    above = lcp[high]
                elif len(group) > MANY:
                    end, high = high, self._run_end(high, now, 1)
                    group.extend(sa[end:high])
                    above = lcp[high]
            if len(group) > MANY:
                count, work, got, j = self._first_longest(i, group, now, best)
                tested += count
                chars += work
                if j >= 0:
                    best, ref = got, j
            else:
                if len(group) > 1:
                    group.sort(reverse=True)
                for j in group:
                    tested += 1
                    x = j
                    while up[x] != x:
                        up[x] = x = up[up[x]]
                    if x == i:  # most fail at once
                        chars += 1
                        continue
                    got = acyclic(i, j, now)
                    chars += got + (got < now)
                    if got > best:
                        best, ref = got, j
                        if got == now:
                            break
            if best == now:
                break
        trace.candidates += tested + (floor > best)
        trace.tests += tested
        trace.finds += chars
        trace.stop_lce = now
        self.sources.finds += chars
        return (floor, floor_ref) if floor > best else (best, ref)

    def _run_end(self, start: int, least: int, way: int) -> int:
        """Where the walk from ``start`` first meets an LCP below ``least``; it lies one before that, downwards."""
        lcp, block = np.frombuffer(self.lcp, self.lcp.typecode), 256
        while True:
            part = lcp[max(start - block + 1, 0) : start + 1][::-1] if way < 0 else lcp[start : start + block]
            short = part < least
            if short.any():
                return start + way * int(short.argmax())
            start += way * len(part)
            block *= 2

    def _first_longest(self, i: int, group: list[int], length: int, best: int) -> tuple[int, int, int, int]:
        """(places tested, characters tested, length, place) of the first longest copy beyond ``best``.

        The group's places are tested together, rightmost first, in blocks that grow; -1: none.
        """
        places = np.sort(np.array(group, self.index.kind))[::-1]
        live = np.flatnonzero(self.sources.follow(places) != i)  # most fail at their first character
        done, found, size, tested, work = 0, -1, 2 * MANY, len(places), 0
        while done < len(live):
            part = places[live[done : done + size]]
            got = self.sources.acyclic_many(i, part, length)
            full = np.flatnonzero(got == length)
            used = got[: int(full[0]) + 1] if len(full) else got
            work += int((used + (used < length)).sum())
            k = int(used.argmax())
            if used[k] > best:
                best, found = int(used[k]), int(part[k])
            done += len(used)
            if len(full):
                tested = int(live[done - 1]) + 1
                break
            size = min(2 * size, MOST)
        chars = work + tested - done
        return tested, chars, best, found

    def _allowed(self, i: int, j: int) -> bool:
        return self.options.sides == "both" or (j < i) == (self.options.sides == "left")

    def commit(self, length: int, ref: int) -> None:
        """Append a phrase and merge its positions with what they refer to."""
        if length:
            self.sources.merge_run(self.at, ref, length)
        self.phrases.append((self.at, max(1, length), ref if length else -1))
        self.at += max(1, length)

    def _run_plain(self) -> Parse:
        """The whole parse under the default rules; where the floor can't be beaten, no search at all."""
        at, n, up, out = self.at, self.n, self.sources.up, self.phrases
        lengths, refs, top, search = self.next_len, self.next_ref, self.top, self._longest_left
        trace, covered = Trace(), 0
        while at < n:
            size, ref = lengths[at], refs[at]
            if size != top[at]:
                size, ref = search(at, size, ref, trace)
            if size:
                up[at : at + size] = up[ref : ref + size]
                covered += size
                out.append((at, size, ref))
                at += size
            else:
                out.append((at, 1, -1))
                at += 1
        self.at = at
        self.sources.unions += covered
        return Parse(out, [])

    def run(self, traced: bool = False) -> Parse:
        if self.options == PLAIN and not traced:
            return self._run_plain()
        traces = []
        while self.at < self.n:
            trace = Trace()
            unions = self.sources.unions
            self.commit(*self.longest(trace))
            if traced:
                trace.unions = self.sources.unions - unions
                traces.append(trace)
        return Parse(self.phrases, traces)


def two_way(codes: np.ndarray, options: Options = Options()) -> list[tuple[int, int, int]]:
    return TwoWay(codes, options).run().phrases
