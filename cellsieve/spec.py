"""Mining tasks: constraints, qualities, and what is asked for."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np

from .params import check_kappa


@dataclass(frozen=True)
class Constraints:
    """On one itemset.  minsup is the absolute support; theta is turned into it by `bound`.

    closed: no further item stands in all covered transactions.  must, must_not and implies name items.  one_per_attribute: items are
    `attribute=value`, and at most one value of each attribute may be chosen.
    """

    theta: float | None = None
    minsup: int | None = None
    min_len: int = 1
    max_len: int | None = None
    closed: bool = False
    max_sup: int | None = None
    min_pos: int = 0
    must: tuple[str, ...] = ()
    must_not: tuple[str, ...] = ()
    implies: tuple[tuple[str, str], ...] = ()
    one_per_attribute: bool = False
    allow_empty: bool = False

    def bound(self, transactions: int) -> Constraints:
        if self.theta is not None and not 0 < self.theta <= 1:
            raise ValueError("theta must lie in (0, 1]")
        if self.min_len < 0:
            raise ValueError("min_len must not be negative")
        minsup = self.minsup if self.minsup is not None else max(1, math.ceil((self.theta or 0) * transactions - 1e-9))
        return Constraints(**{**self.__dict__, "minsup": minsup})


def F(theta: float) -> Constraints:  # noqa: N802
    """Minimum frequency alone."""
    return Constraints(theta=theta)


def FCL(theta: float, min_len: int) -> Constraints:  # noqa: N802
    """Minimum frequency, closed, minimum length."""
    return Constraints(theta=theta, closed=True, min_len=min_len)


MICRO = 1_000_000


@dataclass(frozen=True)
class Quality:
    """weight(items, freq, pos) is an integer numerator, scale the C that is no smaller; tilt bounds largest / smallest weight."""

    name: str
    weight: Callable[[int, int, int], int]
    scale: Callable[[dict], float]
    tilt: Callable[[dict, Constraints], float]
    spark: str
    labelled: bool = False
    #: Weights may exceed 64 bits.
    wide: bool = False


QUALITIES = {
    "uniform": Quality("uniform", lambda n, f, p: 1, lambda s: 1, lambda s, c: 1, "1"),
    "freq": Quality("freq", lambda n, f, p: f, lambda s: s["transactions"], lambda s, c: s["transactions"] / c.minsup, "freq"),
    # in millionths, so that sums are exact
    "purity": Quality("purity", lambda n, f, p: MICRO * max(p, f - p) // f, lambda s: MICRO, lambda s, c: 2, f"{MICRO} * greatest(freq_pos, freq - freq_pos) div freq", True),
    "area": Quality("area", lambda n, f, p: f * n, lambda s: s["ones"], lambda s, c: s["ones"] / (c.minsup * max(1, c.min_len)), "freq * size"),
    "freq4": Quality("freq4", lambda n, f, p: f**4, lambda s: s["transactions"] ** 4, lambda s, c: (s["transactions"] / c.minsup) ** 4, "CAST(freq AS DECIMAL(19,0)) * freq * freq * freq", wide=True),
}


def high_tilt(name: str, transactions: int, positive: int) -> Quality:
    """chi2, information gain (`gain`) or weighted relative accuracy (`wracc`) of a pattern against the label, whole millionths (Q7).

    None has a tilt bound: the least positive value may be as small as a millionth, so sample them by cells.sample_tilt_sliced or between two
    bounds of the quality (K9).  The label is positive in `positive` of the transactions."""
    n, q = float(transactions), positive / transactions if transactions else 0.0
    entropy = lambda x: 0.0 if x <= 0 or x >= 1 else -x * math.log2(x) - (1 - x) * math.log2(1 - x)

    def weight(_: int, f: int, p: int) -> int:
        if not f or not 0 < q < 1:
            return 0
        if name == "chi2":
            value = n * (p / n - f / n * q) ** 2 / (q * (1 - q) * (f / n) * (1 - f / n)) if f < n else 0.0
        elif name == "gain":
            value = entropy(q) - f / n * entropy(p / f) - ((n - f) / n * entropy((positive - p) / (n - f)) if f < n else 0.0)
        else:
            value = abs(p / n - f / n * q)
        return math.floor(max(0.0, value) * MICRO + 1e-6)

    x, f, rest = f"(freq_pos / {n}D)", f"(freq / {n}D)", f"({n}D - freq)"
    h = lambda v: f"(CASE WHEN {v} <= 0 OR {v} >= 1 THEN 0D ELSE -{v} * log2({v}) - (1 - {v}) * log2(1 - {v}) END)"
    value = {
        "chi2": f"CASE WHEN freq < {n}D THEN {n}D * power({x} - {f} * {q}D, 2) / ({q * (1 - q)}D * {f} * (1 - {f})) ELSE 0D END",
        "gain": f"{entropy(q)}D - {f} * {h('(freq_pos / freq)')} - CASE WHEN freq < {n}D THEN {rest} / {n}D * {h(f'(({float(positive)}D - freq_pos) / {rest})')} ELSE 0D END",
        "wracc": f"abs({x} - {f} * {q}D)",
    }[name]
    spark = f"CAST(floor(greatest({value}, 0D) * {MICRO} + 1e-6D) AS BIGINT)" if 0 < q < 1 else "0"
    return Quality(name, weight, lambda s: MICRO * {"chi2": n, "gain": 1.0, "wracc": 0.25}[name], lambda s, c: math.inf, spark, True)


def black_box(name: str, fn: Callable[[int, int, int], int], scale: float, tilt: float) -> Quality:
    """Any function of (items, freq, positive freq) with integer results up to `scale` (Q8)."""
    return Quality(name, fn, lambda s: scale, lambda s, c: tilt, "")


#: Supports that a process remembers.
SUPPORTS_HELD = 1 << 19


@dataclass
class Data:
    """Condensed transactions in one process: items in order of rising support, one bitmap over condensed rows per item.

    count(bitmap) adds the multiplicities of the rows in it, by bit planes of the multiplicities.
    """

    items: list[str]
    bitmaps: list[int]
    mult: Sequence[int]
    positive: Sequence[int]
    planes: list[int] = field(default_factory=list)
    pos_planes: list[int] = field(default_factory=list)
    #: (seed, run, words of the items, the last first) of the run that was asked for last.
    words: tuple = (None, None, [])

    #: Supports that the searches of this process have counted so far, and positive supports, by mask.
    supports: dict[int, int] = field(default_factory=dict)
    positives: dict[int, int] = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.planes, self.pos_planes = planes(self.mult), planes(self.positive)
        self.transactions = int(sum(self.mult))

    @property
    def everything(self) -> int:
        return (1 << len(self.mult)) - 1

    def count(self, bits: int) -> int:
        return sum((bits & p).bit_count() << k for k, p in enumerate(self.planes))

    def count_pos(self, bits: int) -> int:
        return sum((bits & p).bit_count() << k for k, p in enumerate(self.pos_planes))

    def cover(self, mask: int) -> int:
        out = self.everything
        while mask:
            low = mask & -mask
            out &= self.bitmaps[low.bit_length() - 1]
            mask ^= low
        return out

    def support(self, mask: int) -> int:
        """count(cover(mask)); every cell's search meets the same itemsets, so SUPPORTS_HELD are remembered."""
        got = self.supports.get(mask)
        return self.remember(mask, self.count(self.cover(mask))) if got is None else got

    def remember(self, mask: int, n: int) -> int:
        if len(self.supports) < SUPPORTS_HELD:
            self.supports[mask] = n
        return n

    def support_pos(self, mask: int) -> int:
        got = self.positives.get(mask)
        if got is None:
            got = self.count_pos(self.cover(mask))
            if len(self.positives) < SUPPORTS_HELD:
                self.positives[mask] = got
        return got

    @property
    def ones(self) -> int:
        return sum(self.count(b) for b in self.bitmaps)

    def stats(self) -> dict:
        return {"transactions": self.transactions, "ones": self.ones, "items": len(self.items)}

    @staticmethod
    def of(rows: Sequence[tuple[Sequence[str], int, int]]) -> Data:
        """rows: (items, multiplicity, of these positive)."""
        support: dict[str, int] = {}
        for items, m, _ in rows:
            for i in set(items):
                support[i] = support.get(i, 0) + m
        names = sorted(support, key=lambda i: (support[i], i))
        at = {i: k for k, i in enumerate(names)}
        packed = [bytearray(len(rows) // 8 + 1) for _ in names]
        for r, (items, _, _) in enumerate(rows):
            for i in set(items):
                packed[at[i]][r >> 3] |= 1 << (r & 7)
        return Data(names, [int.from_bytes(b, "little") for b in packed], [m for _, m, _ in rows], [p for _, _, p in rows])


def planes(numbers: Sequence[int]) -> list[int]:
    """A bitmap for each binary digit of the numbers."""
    held = np.asarray(numbers, np.int64)
    return [int.from_bytes(np.packbits((held >> k & 1).astype(np.uint8), bitorder="little").tobytes(), "little") for k in range(int(held.max(initial=0)).bit_length())]


@dataclass(frozen=True)
class MiningTask:
    constraints: Constraints
    quality: Quality
    kappa: float = 0.9
    seed: int = 42

    def __post_init__(self) -> None:
        check_kappa(self.kappa)
