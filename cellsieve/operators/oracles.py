"""Search oracles (M6, M20-M22, M26): enumerate the itemsets of one cell until their weight exceeds a bound.

Both work on spec.Data: items in order of rising support, covers as bitmaps.  Item j is bit j of masks and of XOR rows.  An oracle stops as soon as the weight
found exceeds the bound, and says so, so a cell that is far too heavy costs little.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from typing import Protocol

from ..functions.gf2 import Conflict, Gf2System
from ..functions.hashing import draw_py
from ..spec import Constraints, Data, Quality


@dataclass
class CellResult:
    """solutions: (mask, freq, positive freq, weight); overflow: the bound was exceeded and the search broken off."""

    solutions: list[tuple[int, int, int, int]] = field(default_factory=list)
    weight: int = 0
    overflow: bool = False
    nodes: int = 0
    #: Bytes of XOR rows on the search stack at once, the most so far.
    xor_bytes: int = 0


class Oracle(Protocol):
    """Whatever enumerates binary-coded solutions under XOR rows can be plugged in."""

    data: Data

    def solve(self, xors: list[tuple[int, int]], bound: float | None = None) -> CellResult: ...


def xor_rows(data: Data, seed: int, run: int, m: int) -> list[tuple[int, int]]:
    """The first m random constraints of a run: the same bits as the relational sampler's, keyed by item names (A.3)."""
    if data.words[:2] != (seed, run):
        data.words = (seed, run, [draw_py(seed, run, i) for i in reversed(data.items)])
    rhs = draw_py(seed, run, "parity")
    return [(int("".join("1" if w >> k & 1 else "0" for w in data.words[2]) or "0", 2), rhs >> k & 1) for k in range(m)]


class Search:
    def __init__(self, data: Data, constraints: Constraints, quality: Quality) -> None:
        self.data, self.c, self.q = data, constraints.bound(data.transactions), quality
        self.frequent = [j for j, b in enumerate(data.bitmaps) if data.count(b) >= self.c.minsup]
        self.frequent_mask = sum(1 << j for j in self.frequent)
        at = {i: j for j, i in enumerate(data.items)}
        self.must = sum(1 << at[i] for i in set(self.c.must) if i in at)
        self.impossible = any(i not in at for i in self.c.must)
        self.must_not = sum(1 << at[i] for i in set(self.c.must_not) if i in at)
        self.implied: dict[int, int] = {}
        for a, b in self.c.implies:
            if a in at:
                self.implied[at[a]] = self.implied.get(at[a], 0) | (1 << at[b] if b in at else 1 << len(data.items))
        self.groups: dict[str, int] = {}
        for j, i in enumerate(data.items):
            self.groups[i.partition("=")[0]] = self.groups.get(i.partition("=")[0], 0) | 1 << j

    def solve(self, xors: list[tuple[int, int]], bound: float | None = None) -> CellResult:
        out = CellResult()
        for s in self.stream(xors, out):
            out.solutions.append(s)
            out.weight += s[3]
            if bound is not None and out.weight > bound:
                out.overflow = True
                break
        return out

    def stream(self, xors: list[tuple[int, int]], out: CellResult) -> Iterator[tuple[int, int, int, int]]:
        raise NotImplementedError

    def admissible(self, mask: int, freq: int, pos: int) -> bool:
        """Every constraint but closedness, judged on one itemset with its supports."""
        c, size = self.c, mask.bit_count()
        if freq < c.minsup or c.max_sup is not None and freq > c.max_sup or pos < c.min_pos:
            return False
        if size < c.min_len or c.max_len is not None and size > c.max_len or not mask and not c.allow_empty:
            return False
        if self.impossible or mask & self.must != self.must or mask & self.must_not:
            return False
        if any(mask >> a & 1 and b & ~mask for a, b in self.implied.items()):
            return False
        return not c.one_per_attribute or all((mask & g).bit_count() <= 1 for g in self.groups.values())

    def valid(self, mask: int, cover: int) -> bool:
        """Every constraint of the task."""
        if not self.admissible(mask, self.data.count(cover), self.data.count_pos(cover)):
            return False
        return not self.c.closed or all(mask >> j & 1 or cover & b != cover for j, b in enumerate(self.data.bitmaps))

    def branch(self, j: int) -> CellResult:
        """Weight and number of the patterns whose first frequent item is j, without a bound; no pattern is kept."""
        out = CellResult()
        c = self.c
        later = self.frequent[self.frequent.index(j) + 1 :]
        earlier = [i for i in self.frequent if i not in later and i != j]
        names = self.data.items
        inner = type(self)(self.data, Constraints(**{**c.__dict__, "must": (*c.must, names[j]), "must_not": (*c.must_not, *(names[i] for i in earlier))}), self.q)
        for s in inner.stream([], out) if isinstance(self, GenericOracle) else self.node(1 << j, self.data.support(1 << j), later, Gf2System(), out):
            out.weight += s[3]
            out.solutions = [(0, 0, 0, (out.solutions[0][3] if out.solutions else 0) + 1)]
        return out

    def solution(self, mask: int, cover: int, freq: int) -> tuple[int, int, int, int] | None:
        return self.judged(mask, freq, self.data.count_pos(cover))

    def judged(self, mask: int, freq: int, pos: int) -> tuple[int, int, int, int] | None:
        if self.c.max_sup is not None and freq > self.c.max_sup or pos < self.c.min_pos:
            return None
        w = self.q.weight(mask.bit_count(), freq, pos)
        return (mask, freq, pos, w) if w > 0 else None

    def names(self, mask: int) -> str:
        return ",".join(sorted(i for j, i in enumerate(self.data.items) if mask >> j & 1))


class TidsetOracle(Search):
    """Vertical depth-first enumeration of frequent itemsets with parity propagation (M22); minimum frequency and lengths only.

    A node is a prefix with its cover, the items that may still join it (all later in the order, all frequent with it) and the XOR system over them.
    Items that drop out are 0 in the system; items that the system forces to 1 join the prefix, whose cover shrinks, so that further
    items may drop out, until nothing moves (M22a).  A prefix is a solution where the system holds with all items left at 0, and is extended
    in any case.  Supports come from those that the process remembers, and covers are made only where one is missing."""

    def stream(self, xors, out):
        c, data = self.c, self.data
        if c.closed or c.must or c.must_not or c.implies or c.one_per_attribute:
            raise ValueError("the tidset oracle knows minimum frequency and lengths only; use the generic one")
        try:
            system = Gf2System(xors)
            infrequent = (1 << len(data.items)) - 1 & ~self.frequent_mask
            system.assign(0, infrequent)
        except Conflict:
            return
        yield from self.node(0, data.transactions, list(self.frequent), system, out)

    def node(self, prefix, freq, suffixes, system, out, held=0):
        c, data = self.c, self.data
        supports, cover = data.supports, None
        out.nodes += 1
        held += len(system.rows) * (len(data.items) // 8 + 1)
        out.xor_bytes = max(out.xor_bytes, held)
        while True:
            kept, dropped = [], 0
            for j in suffixes:
                got = supports.get(prefix | 1 << j)
                if got is None:
                    cover = data.cover(prefix) if cover is None else cover
                    got = data.remember(prefix | 1 << j, data.count(cover & data.bitmaps[j]))
                if got >= c.minsup:
                    kept.append(j)
                else:
                    dropped |= 1 << j
            suffixes = kept
            try:
                if dropped:
                    system.assign(0, dropped)
                ones, zeros = system.propagate()
            except Conflict:
                return
            if not ones | zeros:
                break
            suffixes = [j for j in suffixes if not (ones | zeros) >> j & 1]
            if ones:
                prefix, cover = prefix | ones, None
                freq = data.support(prefix)
                if freq < c.minsup:
                    return
        size = prefix.bit_count()
        if size + len(suffixes) < c.min_len or c.max_len is not None and size > c.max_len:
            return
        if size >= c.min_len and (prefix or c.allow_empty) and system.satisfied_by_zero():
            s = self.judged(prefix, freq, data.support_pos(prefix))
            if s:
                yield s
        before = 0
        for k, j in enumerate(suffixes):
            child = system.copy()
            try:
                child.assign(1 << j, before)
            except Conflict:
                before |= 1 << j
                continue
            yield from self.node(prefix | 1 << j, data.support(prefix | 1 << j), suffixes[k + 1 :], child, out, held)
            before |= 1 << j


class GenericOracle(Search):
    """Constraint propagation over item variables (M21): every constraint and the XOR system run until none changes anything, then one free item is
    branched on, 1 first.  XORs hold item variables only, since these determine the covers (M21a)."""

    def stream(self, xors, out):
        data = self.data
        # infrequent items are out, and can't stand in all that a frequent set covers, so nothing below looks at them
        out_at_once = self.must_not | (1 << len(data.items)) - 1 & ~self.frequent_mask
        if self.impossible or self.must & out_at_once:
            return
        free = self.frequent_mask
        try:
            system = Gf2System(xors)
            system.assign(self.must, out_at_once)
        except Conflict:
            return
        cover = data.everything
        for j in range(self.must.bit_length()):
            if self.must >> j & 1:
                cover &= data.bitmaps[j]
        stack = [(self.must, out_at_once, free & ~self.must & ~out_at_once, cover, system)]
        while stack:
            ones, zeros, free, cover, system = stack.pop()
            out.nodes += 1
            out.xor_bytes = max(out.xor_bytes, (len(stack) + 1) * len(system.rows) * (len(data.items) // 8 + 1))
            state = self.fixpoint(ones, zeros, free, cover, system)
            if state is None:
                continue
            ones, zeros, free, cover = state
            freq = data.count(cover)
            if not free:
                if (ones or self.c.allow_empty) and ones.bit_count() >= self.c.min_len:
                    s = self.solution(ones, cover, freq)
                    if s:
                        yield s
                continue
            j = min((j for j in self.frequent if free >> j & 1), key=lambda j: data.count(cover & data.bitmaps[j]))
            bit = 1 << j
            for one in (False, True):  # the last pushed comes first
                child = system.copy()
                try:
                    child.assign(bit if one else 0, 0 if one else bit)
                except Conflict:
                    continue
                stack.append((ones | bit, zeros, free & ~bit, cover & data.bitmaps[j], child) if one else (ones, zeros | bit, free & ~bit, cover, child))

    def fixpoint(self, ones, zeros, free, cover, system):
        c, data = self.c, self.data
        while True:
            before = ones, zeros
            freq = data.count(cover)
            if freq < c.minsup or ones.bit_count() + free.bit_count() < c.min_len:
                return None
            new_one = new_zero = 0
            if c.max_len is not None:
                if ones.bit_count() > c.max_len:
                    return None
                if ones.bit_count() == c.max_len:
                    new_zero |= free
            for j in self.frequent:
                bit, b = 1 << j, data.bitmaps[j]
                if ones & bit:
                    if j in self.implied:
                        if self.implied[j] & zeros or self.implied[j] >> len(data.items):
                            return None
                        new_one |= self.implied[j] & free
                    continue
                both = cover & b
                contained = c.closed and both == cover
                if contained and zeros & bit:
                    return None
                if free & bit:
                    if contained:
                        new_one |= bit
                    elif data.count(both) < c.minsup:
                        new_zero |= bit
                    elif j in self.implied and (self.implied[j] & zeros or self.implied[j] >> len(data.items)):
                        new_zero |= bit
            if c.one_per_attribute:
                for group in self.groups.values():
                    if (ones & group).bit_count() > 1:
                        return None
                    if ones & group:
                        new_zero |= group & free
            if new_one & new_zero:
                return None
            try:
                system.assign(new_one, new_zero)
                more_one, more_zero = system.propagate()
            except Conflict:
                return None
            new_one, new_zero = new_one | more_one & free, new_zero | more_zero & free
            if new_one & new_zero or more_one & zeros or more_zero & ones:
                return None
            ones, zeros, free = ones | new_one, zeros | new_zero, free & ~(new_one | new_zero)
            for j in range(new_one.bit_length()):
                if new_one >> j & 1:
                    cover &= data.bitmaps[j]
            if (ones, zeros) == before:
                return ones, zeros, free, cover


ORACLES = {"tidset": TidsetOracle, "generic": GenericOracle}
