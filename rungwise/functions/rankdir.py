"""Rank and select on bit vectors: mini-blocks as (popcount, number within their class) under running counts."""

from __future__ import annotations

from math import comb

MINI = 15


def class_number(bits: str) -> int:
    ahead, n, out = bits.count("1"), len(bits), 0
    for i, b in enumerate(bits):
        if b == "1":
            out += comb(n - 1 - i, ahead)
            ahead -= 1
    return out


def class_bits(number: int, ones: int, n: int) -> str:
    out = ""
    for i in range(n):
        if ones and number >= comb(n - 1 - i, ones):
            number -= comb(n - 1 - i, ones)
            ones -= 1
            out += "1"
        else:
            out += "0"
    return out


class RankDirectory:
    """A bit vector that answers rank with one running count and one mini-block."""

    def __init__(self, bits: str, mini: int = MINI):
        self.n, self.mini = len(bits), mini
        parts = [bits[i : i + mini] for i in range(0, len(bits), mini)]
        self.minis = [(p.count("1"), class_number(p), len(p)) for p in parts]
        self.before, at = [], 0
        for ones, _, _ in self.minis:
            self.before.append(at)
            at += ones
        self.ones = at

    def bits(self) -> str:
        return "".join(class_bits(number, ones, n) for ones, number, n in self.minis)

    def rank(self, i: int) -> int:
        """Ones among the first i bits."""
        if i <= 0:
            return 0
        if i >= self.n:
            return self.ones
        part, rest = divmod(i, self.mini)
        ones, number, n = self.minis[part]
        return self.before[part] + class_bits(number, ones, n)[:rest].count("1")

    def select(self, k: int) -> int:
        """Place (from 0) of the k-th one (from 1), by bisection on rank; -1 if there are fewer."""
        if not 1 <= k <= self.ones:
            return -1
        low, high = 0, self.n
        while low < high:
            mid = (low + high) // 2
            low, high = (mid + 1, high) if self.rank(mid) < k else (low, mid)
        return low - 1

    def cost_bits(self) -> int:
        """Bits of classes, numbers and running counts."""
        return sum((n).bit_length() + (comb(n, ones) - 1).bit_length() for ones, _, n in self.minis) + len(self.minis) * self.n.bit_length()
