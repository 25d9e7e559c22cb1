"""Which literal each position's chain of references ends in, as disjoint sets."""

from __future__ import annotations

from array import array

import numpy as np

#: Length from which the chains of a run are followed together.
LONG_RUN = 64
#: Targets times length up to which all targets are tested together.
MOST_CELLS = 1 << 22
#: Links of the whole string that could be followed in the time of one step of many positions together.
STEP_COST = 64


def machine(values: np.ndarray) -> array:
    """The values as machine integers that Python code reads one by one."""
    out = array("i" if values.dtype.itemsize == 4 else "q")
    out.frombytes(np.ascontiguousarray(values).data.cast("B") if len(values) else b"")
    return out


class Sources:
    """Disjoint sets whose representative is the literal at the end of every member's chain.

    ``link='directed'`` hangs the new position below its target, so roots are sources by
    themselves; ``'by_size'`` hangs the smaller set and keeps the source as a label.
    """

    def __init__(self, n: int = 0, link: str = "directed"):
        if link not in ("directed", "by_size"):
            raise ValueError(f"unknown link rule {link!r}")
        self.up = machine(np.arange(n, dtype=np.int32 if n < 1 << 31 else np.int64))
        self.size = array(self.up.typecode, [1]) * n if link == "by_size" else None
        self.label = self.up[:] if link == "by_size" else None
        self.finds = self.unions = self.steps = 0

    def add(self) -> int:
        """A new position in a set of its own."""
        new = len(self.up)
        self.up.append(new)
        if self.size is not None:
            self.size.append(1)
            self.label.append(new)
        return new

    def root(self, x: int) -> int:
        up = self.up
        self.finds += 1
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    def source(self, x: int) -> int:
        x = self.root(x)
        return x if self.label is None else self.label[x]

    def merge(self, new: int, target: int) -> None:
        """Let ``new``, so far its own source, refer to ``target``."""
        a, b = self.root(new), self.root(target)
        self.unions += 1
        if a == b:
            return
        if self.size is None:
            self.up[a] = b
            return
        label = self.label[b]
        if self.size[a] > self.size[b]:
            a, b = b, a
        self.up[a] = b
        self.size[b] += self.size[a]
        self.label[b] = label

    def merge_run(self, new: int, target: int, length: int) -> None:
        """``merge`` of ``length`` positions in a row, none of which closes a cycle.

        With directed links a new position takes over what its target points to, one copy of a slice.
        """
        if self.size is not None:
            for k in range(length):
                self.merge(new + k, target + k)
            return
        self.unions += length
        self.up[new : new + length] = self.up[target : target + length]

    def acyclic(self, new: int, target: int, length: int) -> int:
        """How many positions from ``new`` can refer to those from ``target`` before a chain closes.

        Merges made on the way are kept aside and forgotten. Needs directed links.
        """
        up = self.up
        if length >= LONG_RUN:
            roots = self._roots(target, length)
            inside = (roots >= new) & (roots < new + length)
            if not inside.any():
                return length
        merged: dict[int, int] = {}
        for k in range(length):
            x = target + k
            above = up[x]
            while above != x:
                top = up[above]
                if top == above:
                    x = above
                    break
                up[x] = top
                x = top
                above = up[x]
            if x >= new:
                while x in merged:
                    x = merged[x]
                if x == new + k:
                    return k
            merged[new + k] = x
        return length

    def acyclic_many(self, new: int, targets: np.ndarray, length: int) -> np.ndarray:
        """``acyclic`` for each of many targets, character by character for those still open."""
        out = np.full(len(targets), length, np.int64)
        rows = np.arange(len(targets))
        merged = np.empty((len(targets), length), np.int64) if length * len(targets) <= MOST_CELLS else None
        if merged is None:
            return np.array([self.acyclic(new, j, length) for j in targets.tolist()], np.int64)
        for k in range(length):
            at = targets[rows] + k
            x = self.follow(at)
            while k:
                inside = np.flatnonzero((x >= new) & (x < new + k))
                if not len(inside):
                    break
                x[inside] = merged[rows[inside], x[inside] - new]
            merged[rows, k] = x
            closed = x == new + k
            if closed.any():
                out[rows[closed]] = k
                rows = rows[~closed]
                if not len(rows):
                    break
        return out

    def _roots(self, start: int, length: int) -> np.ndarray:
        """Sources of a run of positions, whose links are shortened to them."""
        return self.follow(np.arange(start, start + length))

    def follow(self, at: np.ndarray) -> np.ndarray:
        """Roots of many positions, to which their links are shortened, all links on the way being halved.

        Chains can be as long as the string; once steps taken make up a good part of its length, every
        link of the string is brought to its root by doubling.
        """
        up = np.frombuffer(self.up, self.up.typecode)
        first = at
        while True:
            above = up[at]
            if (above == at).all():
                up[first] = above
                return above
            at_next = up[above]
            up[at] = at_next
            at = at_next
            self.steps += 1
            if self.steps * STEP_COST > len(up):
                self.steps = 0
                while True:
                    above = up[up]
                    if (above == up).all():
                        break
                    up[:] = above


class Overlay:
    """Merges on top of ``Sources`` that are forgotten together; holds only what it touches."""

    def __init__(self, base: Sources):
        self.base = base
        self.over: dict[int, int] = {}

    def source(self, x: int) -> int:
        x = self.base.source(x)
        while x in self.over:
            x = self.over[x]
        return x

    def merge(self, new: int, target_source: int) -> None:
        self.over[new] = target_source
