"""Parameter schedules: laws, block lengths, tolerances, thresholds and cell widths, all from exact integers."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, replace
from fractions import Fraction
from math import ceil, log2

from ..functions.typeindex import TypicalSet, char_of, digit_width


@dataclass(frozen=True)
class Law:
    """A finite alphabet with counts; probabilities stay ratios of integers."""

    symbols: tuple[str, ...]
    counts: tuple[int, ...]

    @property
    def k(self) -> int:
        return len(self.counts)

    @property
    def total(self) -> int:
        return sum(self.counts)

    @property
    def entropy(self) -> float:
        return -sum(c / self.total * log2(c / self.total) for c in self.counts if c)

    @property
    def dyadic(self) -> bool:
        return all(c and self.total % c == 0 and (self.total // c).bit_count() == 1 for c in self.counts)

    @property
    def chars(self) -> str:
        return "".join(char_of(i) for i in range(self.k))


@dataclass(frozen=True)
class Level:
    fanout: int
    num: int
    den: int
    symbols: int  # of a whole unit
    width: int  # bits of a whole unit's cell
    header: int


@dataclass(frozen=True)
class LadderSchedule:
    """``num/den`` is the tolerance at level 0; the tolerance of the open share halves with every level."""

    k: int
    b0: int
    num: int
    den: int
    k0_nominal: int
    k0_tight: int
    levels: tuple[Level, ...]
    digit_bits: int
    raw_bits: int
    universal: bool = False  # words are LZ words of ``word_bits``; what doesn't fit is open

    @property
    def k0(self) -> int:
        return max(self.k0_nominal, self.k0_tight)

    def word_bits(self, n_sym: int) -> int:
        """Bits of an LZ word: ``k0``, or its share for a longer or shorter last block."""
        return self.k0 * n_sym // self.b0

    @property
    def widths(self) -> list[int]:
        return [self.k0, *(x.width for x in self.levels)]

    @property
    def bounds_apply(self) -> bool:
        return Fraction(self.num, self.den) < Fraction(1, 2)

    def to_json(self) -> str:
        return json.dumps(asdict(self))


def ladder_schedule(law: Law, b0: int, num: int, den: int, fanouts: list[int], n: int | None = None) -> LadderSchedule:
    """Explicit block length and fan-outs; levels longer than the sequence are left out."""
    eps = Fraction(num, den)
    nominal = ceil((law.entropy + float(eps)) * b0)
    tight = max(1, TypicalSet(list(law.counts), num, den, b0).size.bit_length())
    digit = digit_width(law.k + 1)
    levels, symbols, units = [], b0, None if n is None else n // b0
    for i, fan in enumerate(fanouts, 1):
        if units is not None:
            units //= fan
            if units < 1:
                break
        e = eps / 2**i
        slots = fan * e.numerator // e.denominator
        if slots < 1:
            raise ValueError(f"level {i} has room for no open child: fan-out {fan}, tolerance {e}")
        levels.append(Level(fan, e.numerator, e.denominator, symbols * fan, fan + slots * symbols * digit, fan))
        symbols *= fan
    return LadderSchedule(law.k, b0, num, den, nominal, tight, tuple(levels), digit, digit_width(law.k))


def universal_schedule(law: Law, b0: int, slack: Fraction, num: int, den: int, fanouts: list[int], n: int | None = None) -> LadderSchedule:
    """Words of entropy plus ``slack`` bits a symbol; a width that isn't below the raw one is refused."""
    k0 = ceil((law.entropy + float(slack)) * b0)
    if k0 >= b0 * digit_width(law.k):
        raise ValueError(f"LZ words of {k0} bits don't beat raw blocks of {b0} symbols")
    return replace(ladder_schedule(law, b0, num, den, fanouts, n), k0_nominal=k0, k0_tight=0, universal=True)


def block_length(law: Law, eps0: float, alpha: int = 8) -> int:
    """Block length from which a block is open with probability eps0**alpha at most (Chernoff over the symbols).

    Two tails per symbol, each below exp(-eps0**2 * p * b / 3).
    """
    from math import log

    least = min(c / law.total for c in law.counts if c)
    return ceil(3 / (eps0 * eps0 * least) * (log(2 * law.k) + alpha * log(1 / eps0)))


def unit_symbols(b0: int, level: int) -> int:
    """Symbols of a level's unit when fan-outs start at 4*b0 and grow fourfold."""
    return b0 ** (level + 1) * 2 ** (level * (level + 1))


def paper_levels(n: int, b0: int) -> int:
    level = 0
    while unit_symbols(b0, level + 1) <= n:
        level += 1
    return level


@dataclass(frozen=True)
class RankedSchedule:
    b0: int
    b1: int
    num: int
    den: int
    word_bits: int
    raw_bits: int
    open_num: int
    open_den: int

    @property
    def subs(self) -> int:
        return self.b0 // self.b1

    @property
    def y_bits(self) -> int:
        """Room for the words of a block of which the allowed share is raw."""
        raw = self.subs * self.open_num // self.open_den
        return raw * self.raw_bits + (self.subs - raw) * self.word_bits

    @property
    def open_most(self) -> int:
        return self.subs * self.open_num // self.open_den


def ranked_schedule(law: Law, b0: int, b1: int, num: int, den: int, open_num: int, open_den: int) -> RankedSchedule:
    size = TypicalSet(list(law.counts), num, den, b1).size
    return RankedSchedule(b0, b1, num, den, max(1, (size - 1).bit_length()), b1 * digit_width(law.k), open_num, open_den)


def ranked_lengths(law: Law, n: int, eps: float) -> tuple[int, int]:
    """(b0, b1) whose design probabilities hold: sub-blocks open at most 1/log2(n)**2, blocks failing at most n**-2."""
    from math import log

    least = min(c / law.total for c in law.counts if c)
    logn = log2(max(n, 4))
    b1 = ceil(3 / (eps * eps * least) * (log(2 * law.k) + 2 * log(logn)))
    subs = max(1, ceil(2 * logn / max(log2(max(logn, 2)), 1)))
    return b1 * subs, b1


PRESETS = {
    "demo3": dict(source="li_small_qty", b0=128, num=1, den=2, fanouts=[8, 16]),
    "deep3": dict(source="li_small_qty", b0=64, num=1, den=2, fanouts=[8, 16]),
    "calm": dict(source="li_zero_tax", b0=256, num=1, den=2, fanouts=[8, 16]),
    "flag3": dict(source="li_flag", b0=32, num=1, den=2, fanouts=[8, 16]),
    "universal": dict(source="li_zero_tax", b0=256, num=1, den=2, fanouts=[8, 16], slack=Fraction(2, 5)),
    "index16": dict(source="li_small_qty", b0=16, num=1, den=2, fanouts=[8, 16]),
}
RANKED_DEMO = dict(source="li_small_qty", b0=1024, b1=64, num=1, den=2, open_num=1, open_den=2)


def write_preamble(b0: int, k0: int) -> str:
    """Bits that tell a reader ``b0`` and ``k0``: their common width in unary, a zero, then both numbers."""
    width = max(b0.bit_length(), k0.bit_length(), 1)
    return "1" * width + "0" + format(b0, f"0{width}b") + format(k0, f"0{width}b")


def read_preamble(bits: str) -> tuple[int, int, int]:
    """``b0``, ``k0`` and the number of bits they took."""
    width = bits.index("0")
    at = width + 1
    return int(bits[at : at + width], 2), int(bits[at + width : at + 2 * width], 2), at + 2 * width
