"""Typical sets: exact bounds, exact sizes, and the numbering of their members.

A block is settled if every symbol's count lies within the tolerance of its expected count; all tests are integer
tests, so engines agree bit for bit.  Members are numbered from 1 (0 is the zero word of an open block): symbols
are placed from the last to the first; for each one smaller counts come first, then the places it takes among the
slots that are left, in lexicographic order.
"""

from __future__ import annotations

from functools import cached_property
from math import comb

FIRST_CHAR = 48


def char_of(code: int) -> str:
    return chr(FIRST_CHAR + code)


class TypicalSet:
    """Sequences of ``length`` symbols that are typical for the law ``counts`` at tolerance ``num/den``."""

    def __init__(self, counts: list[int], num: int, den: int, length: int):
        self.counts, self.num, self.den, self.length = list(counts), num, den, length
        self.total = sum(counts)

    @cached_property
    def bounds(self) -> list[tuple[int, int]]:
        """Least and greatest admitted count of every symbol."""
        out = []
        for c in self.counts:
            low = -(-self.length * c * (self.den - self.num) // (self.total * self.den))
            high = self.length * c * (self.den + self.num) // (self.total * self.den)
            out.append((max(0, low), min(high, self.length)))
        return out

    @cached_property
    def _ways(self) -> list[list[int]]:
        """ways[a][r]: arrangements of r slots by the symbols below a."""
        ways = [[1] + [0] * self.length]
        for low, high in self.bounds:
            below = ways[-1]
            ways.append([sum(comb(r, c) * below[r - c] for c in range(low, min(high, r) + 1)) for r in range(self.length + 1)])
        return ways

    @property
    def size(self) -> int:
        return self._ways[-1][self.length]

    def admits(self, codes: list[int]) -> bool:
        return len(codes) == self.length and all(low <= codes.count(a) <= high for a, (low, high) in enumerate(self.bounds))

    def index(self, codes: list[int]) -> int:
        """Number of a member, from 1; 0 for what isn't one."""
        if not self.admits(codes):
            return 0
        rank, left = 0, list(codes)
        parts = []
        for a in range(len(self.counts) - 1, 0, -1):
            r, c = len(left), left.count(a)
            below = self._ways[a]
            skipped = sum(comb(r, x) * below[r - x] for x in range(self.bounds[a][0], c))
            place, ahead = 0, c
            for i, code in enumerate(left):
                if code == a:
                    place += comb(r - 1 - i, ahead)
                    ahead -= 1
            parts.append((skipped, place, below[r - c]))
            left = [x for x in left if x != a]
        for skipped, place, rest in reversed(parts):
            rank = skipped + place * rest + rank
        return rank + 1

    def unindex(self, number: int) -> list[int]:
        rank = number - 1
        slots: list[int | None] = [None] * self.length
        free = list(range(self.length))
        for a in range(len(self.counts) - 1, 0, -1):
            r, below = len(free), self._ways[a]
            c = self.bounds[a][0]
            while rank >= comb(r, c) * below[r - c]:
                rank -= comb(r, c) * below[r - c]
                c += 1
            place, rank = divmod(rank, below[r - c])
            ahead = c
            taken = []
            for i in range(r):
                if ahead and place >= comb(r - 1 - i, ahead):
                    place -= comb(r - 1 - i, ahead)
                    ahead -= 1
                    taken.append(free[i])
            for t in taken:
                slots[t] = a
            gone = set(taken)
            free = [t for t in free if t not in gone]
        return [0 if s is None else s for s in slots]


def word_width(k0: int, members: TypicalSet) -> int:
    """Bits of a settled block's word: the schedule's, or as many as the numbers of a longer last block need."""
    return max(k0, members.size.bit_length())


def to_bits(number: int, width: int) -> str:
    return format(number, f"0{width}b") if width else ""


def pack_bits(bits: str) -> bytes:
    """Bits, first one highest, filled up to whole bytes with zeros."""
    return int(bits.ljust(-(-len(bits) // 8) * 8, "0") or "0", 2).to_bytes(-(-len(bits) // 8), "big")


def unpack_bits(data: bytes, n: int) -> str:
    return "".join(format(b, "08b") for b in data)[:n]


def digit_width(k: int) -> int:
    """Bits of one digit out of k."""
    return max(1, (k - 1).bit_length())


def radix_pack(digits: list[int], base: int) -> int:
    out = 0
    for d in digits:
        out = out * base + d
    return out


def radix_unpack(number: int, base: int, n: int) -> list[int]:
    out = []
    for _ in range(n):
        number, d = divmod(number, base)
        out.append(d)
    return out[::-1]
