"""Linear systems over two values (M20): elimination with units and conflicts, on Python integers as bit rows.

Bit j of a row is the coefficient of variable j; a row and its parity bit say that the XOR of its variables equals the parity.  Pivots
are the highest bits, so that with a search that fixes variables in rising order the tail of the order is forced instead of branched on,
and only rows that hold the assigned variable are touched (M20d).  Rows are integers of any width, so wide, sparse systems need no dense
matrix; `SparseSystem` keeps sets of variables instead (M20e).
"""

from __future__ import annotations

from collections.abc import Iterable


class Conflict(Exception):
    """The rows contradict each other."""


class Gf2System:
    __slots__ = ("rows", "ops")

    def __init__(self, rows: Iterable[tuple[int, int]] = ()) -> None:
        #: (coefficients, parity) in echelon form, and the number of row additions so far.
        self.rows: list[tuple[int, int]] = []
        self.ops = 0
        for mask, parity in rows:
            self.add(mask, parity)

    def copy(self) -> Gf2System:
        out = Gf2System()
        out.rows = list(self.rows)
        return out

    def add(self, mask: int, parity: int) -> None:
        """Adds an equation; raises Conflict where it cannot hold."""
        for m, p in self.rows:
            if mask >> (m.bit_length() - 1) & 1:
                mask, parity = mask ^ m, parity ^ p
                self.ops += 1
        if not mask:
            if parity:
                raise Conflict
            return
        top = mask.bit_length() - 1
        for i, (m, p) in enumerate(self.rows):
            if m >> top & 1:
                self.rows[i] = (m ^ mask, p ^ parity)
                self.ops += 1
        self.rows.append((mask, parity))

    def units(self) -> tuple[int, int]:
        """(variables that must be 1, variables that must be 0) by rows with one variable."""
        ones = zeros = 0
        for m, p in self.rows:
            if not m & (m - 1):
                if p:
                    ones |= m
                else:
                    zeros |= m
        return ones, zeros

    def assign(self, ones: int, zeros: int) -> None:
        """Fixes variables: those set to 1 flip the parity of their rows, and all leave the rows."""
        gone = ones | zeros
        touched = [(m & ~gone, p ^ ((m & ones).bit_count() & 1)) for m, p in self.rows if m & gone]
        if touched:
            self.rows = [(m, p) for m, p in self.rows if not m & gone]
            for m, p in touched:
                self.add(m, p)

    def propagate(self) -> tuple[int, int]:
        """Assigns units until none is left; gives all variables that were forced, as (ones, zeros)."""
        all_ones = all_zeros = 0
        while True:
            ones, zeros = self.units()
            if not ones | zeros:
                return all_ones, all_zeros
            all_ones, all_zeros = all_ones | ones, all_zeros | zeros
            self.assign(ones, zeros)

    def satisfied_by_zero(self) -> bool:
        """Whether all equations hold when every variable left is 0 (A.2)."""
        return all(not p for _, p in self.rows)


class SparseSystem:
    """The same with sets of variables, for wide item sets with sparse rows."""

    def __init__(self, rows: Iterable[tuple[Iterable[int], int]] = ()) -> None:
        self.rows: dict[int, tuple[frozenset[int], int]] = {}
        for variables, parity in rows:
            self.add(frozenset(variables), parity)

    def add(self, variables: frozenset[int], parity: int) -> None:
        for top in sorted(variables & self.rows.keys(), reverse=True):
            if top in variables:
                v, p = self.rows[top]
                variables, parity = variables ^ v, parity ^ p
        if not variables:
            if parity:
                raise Conflict
            return
        top = max(variables)
        for key, (v, p) in list(self.rows.items()):
            if top in v:
                self.rows[key] = (v ^ variables, p ^ parity)
        self.rows[top] = (variables, parity)

    def units(self) -> dict[int, int]:
        return {next(iter(v)): p for v, p in self.rows.values() if len(v) == 1}
