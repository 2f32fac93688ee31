"""LZ78 with growing pointers: phrase i spends ceil(log2 i) bits on its pointer and a fixed width on its symbol.

A last phrase that is already known spends its pointer only.
"""

from __future__ import annotations

from .typeindex import digit_width, to_bits


def phrases(codes: list[int]) -> list[tuple[int, int | None]]:
    """(number of the longest known prefix, next symbol or None) of every phrase; 0 is the empty phrase."""
    known: dict[tuple[int, int], int] = {}
    out, at = [], 0
    for code in codes:
        if (at, code) in known:
            at = known[at, code]
        else:
            known[at, code] = len(known) + 1
            out.append((at, code))
            at = 0
    if at:
        out.append((at, None))
    return out


def pointer_bits(i: int) -> int:
    """Bits to name one of i known phrases, the empty one included."""
    return (i - 1).bit_length()


def code_length(codes: list[int], k: int) -> int:
    width = digit_width(k)
    return sum(pointer_bits(i) + (width if symbol is not None else 0) for i, (_, symbol) in enumerate(phrases(codes), 1))


def encode(codes: list[int], k: int) -> str:
    width = digit_width(k)
    return "".join(to_bits(p, pointer_bits(i)) + (to_bits(s, width) if s is not None else "") for i, (p, s) in enumerate(phrases(codes), 1))


def decode(bits: str, k: int, n: int) -> list[int]:
    """The first n symbols that ``bits`` stand for; further bits are padding."""
    width, at, out, book = digit_width(k), 0, [], [()]
    while len(out) < n:
        i = len(book)
        w = pointer_bits(i)
        pointer = int(bits[at : at + w] or "0", 2)
        at += w
        phrase = book[pointer]
        if len(out) + len(phrase) < n:
            phrase = (*phrase, int(bits[at : at + width], 2))
            at += width
            book.append(phrase)
        out += phrase
    return out[:n]


def fixed_word(codes: list[int], k: int, width: int) -> str | None:
    """Flag 1, the LZ bits and zero padding in ``width`` bits; None if they don't fit (the block stays open)."""
    bits = encode(codes, k)
    return None if len(bits) > width - 1 else ("1" + bits).ljust(width, "0")


def read_fixed_word(word: str, k: int, n: int) -> list[int]:
    return decode(word[1:], k, n)
