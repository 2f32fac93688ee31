"""Numbering, packing, LZ78 and rank structures against enumeration."""

import itertools
import random
from fractions import Fraction

import pytest

from rungwise.functions import lz, rankdir
from rungwise.functions.typeindex import TypicalSet, digit_width, pack_bits, radix_pack, radix_unpack, to_bits, unpack_bits


@pytest.mark.parametrize(("counts", "length"), [([7, 3], 10), ([5, 3, 2], 7), ([1], 5), ([2, 2, 1, 1], 6), ([9, 1], 1)])
def test_index_is_a_bijection(counts, length):
    t = TypicalSet(counts, 1, 2, length)
    members = [list(c) for c in itertools.product(range(len(counts)), repeat=length) if t.admits(list(c))]
    assert sorted(map(t.index, members)) == list(range(1, t.size + 1))
    assert all(t.unindex(t.index(m)) == m for m in members)


def test_bounds_equal_fractions():
    t = TypicalSet([53984, 6016], 1, 2, 128)
    for (low, high), c in zip(t.bounds, t.counts, strict=True):
        p, eps = Fraction(c, t.total), Fraction(1, 2)
        assert [x for x in range(129) if abs(Fraction(x, 128) - p) <= eps * p] == list(range(low, high + 1))


def test_bits_and_digits():
    assert unpack_bits(pack_bits("10110"), 5) == "10110" and digit_width(3) == 2 and digit_width(2) == 1 and digit_width(1) == 1
    assert to_bits(5, 6) == "000101" and radix_unpack(radix_pack([2, 0, 1, 2], 3), 3, 4) == [2, 0, 1, 2]


def test_lz78_round_trips_and_lengths():
    rng = random.Random(1)
    for _ in range(200):
        k = rng.choice([1, 2, 3, 5])
        codes = [rng.randrange(k) for _ in range(rng.randrange(90))]
        bits = lz.encode(codes, k)
        assert len(bits) == lz.code_length(codes, k) and lz.decode(bits, k, len(codes)) == codes
        word = lz.fixed_word(codes, k, len(bits) + 7)
        assert word[0] == "1" and len(word) == len(bits) + 7 and lz.read_fixed_word(word, k, len(codes)) == codes
        assert lz.fixed_word(codes, k, len(bits)) is None


@pytest.mark.parametrize("n", [1, 12, 63, 500])
def test_rank_and_select(n):
    rng = random.Random(n)
    bits = "".join(rng.choice("0001") for _ in range(n))
    r = rankdir.RankDirectory(bits)
    assert r.bits() == bits and [r.rank(i) for i in range(n + 1)] == [bits[:i].count("1") for i in range(n + 1)]
    assert [r.select(i + 1) for i in range(bits.count("1"))] == [i for i, b in enumerate(bits) if b == "1"] and r.select(n + 1) == -1
