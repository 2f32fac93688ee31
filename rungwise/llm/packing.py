"""Hierarchical multi-length packing of token sequences.

Documents are cut into full windows of the longest tier and a remainder.  Remainders are routed to the smallest
tier that holds them.  Every tier is packed in turn, longest first: a remainder opens a window, gaps are filled
from the shorter tiers (best fit by length, then a cut piece that closes the gap), so a window is left open only
when a block has run out of pieces; that last rest is stored as windows of powers of two, which need no padding.
A block is a bounded stretch of one input partition, packed in memory and written without any shuffle; sequence
ids carry the partition number, so a task that runs again gives the same rows.  Windows of a tier are dealt into
step groups of equal token counts.
"""

from __future__ import annotations

import base64
import functools
import json
import re
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import small_batches

TIERS = (256, 512, 1024)
#: Tokens that one block holds before it is packed.
BLOCK_TOKENS = 4_000_000
#: Tokens of one step group.
STEP_TOKENS = 16_384
#: Space-delimited pieces whose ids a worker remembers.
REMEMBERED = 200_000


class Ids(dict):
    """Little-endian 16-bit ids of pieces of text that follow a space, remembered up to ``REMEMBERED`` pieces."""

    def __init__(self, encode):
        super().__init__()
        self.encode = encode

    def __missing__(self, piece: str) -> bytes:
        ids = np.array(self.encode(" " + piece), "<u2").tobytes()
        if len(self) < REMEMBERED:
            self[piece] = ids
        return ids


@functools.cache
def _encoder(name: str):
    """The remembered ids of the vocabulary ``name`` (a tokenizers file), its added tokens' strings and a splitter at them.

    Merges come from the same vocabulary's ``.tiktoken`` file, which is some seven times as fast; the added tokens
    are read from the tokenizers file itself.
    """
    import public_tokenizers as places
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(places.path(name.replace(".json", ".tiktoken")), "rb"))}
    encode = tiktoken.Encoding("packing", pat_str=places.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
    added = {t["content"]: t["id"] for t in json.load(open(places.path(name), encoding="utf-8"))["added_tokens"]}
    if max([*ranks.values(), *added.values()]) > 0xFFFF:
        raise ValueError("the vocabulary needs more than 16 bits")
    splitter = re.compile("(" + "|".join(map(re.escape, sorted(added, key=len, reverse=True))) + ")").split if added else None
    return Ids(encode), {k: np.array([v], "<u2").tobytes() for k, v in added.items()}, splitter


#: A single space between two characters that aren't white space: no pre-token reaches over it.
_gaps = re.compile(r"(?<=\S) (?=\S)").split
_odd = re.compile(r" \s|\s$").search


def _plain_ids(text: str, ids: Ids) -> bytes:
    """Pre-tokens never reach over a gap, so the pieces behind gaps (each with its space in front) are remembered."""
    head, *rest = _gaps(text) if _odd(text) else text.split(" ")
    return b"".join([np.array(ids.encode(head), "<u2").tobytes(), *map(ids.__getitem__, rest)])


def token_ids(text: str | None, name: str = "byte_bpe_50k.json") -> np.ndarray:
    """Ids of ``text`` as the tokenizers file ``name`` gives them with ``add_special_tokens=False``, then id 0.

    A text is cut at the strings of the file's added tokens first; those have their own ids.
    """
    ids, added, splitter = _encoder(name)
    text = text or ""
    if not any(token in text for token in added):
        return np.frombuffer(_plain_ids(text, ids) + b"\0\0", "<u2")
    return np.frombuffer(b"".join([added.get(part) or _plain_ids(part, ids) for part in splitter(text) if part]) + b"\0\0", "<u2")


class Shelf:
    """Pieces by length, with a bit set of the lengths at hand."""

    def __init__(self):
        self.by: dict[int, list] = defaultdict(list)
        self.mask = 0

    def put(self, piece: tuple[int, int, int]) -> None:
        self.by[piece[2]].append(piece)
        self.mask |= 1 << piece[2]

    def take(self, length: int) -> tuple[int, int, int]:
        pieces = self.by[length]
        out = pieces.pop()
        if not pieces:
            self.mask &= ~(1 << length)
        return out

    def fitting(self, most: int) -> int:
        """The largest length at hand up to ``most``; 0 if there is none."""
        return (self.mask & ((2 << most) - 1)).bit_length() - 1 if self.mask & ((2 << most) - 1) else 0

    def shortest(self) -> int:
        return (self.mask & -self.mask).bit_length() - 1 if self.mask else 0


def pack(lengths: list[int], tiers: tuple[int, ...] = TIERS) -> list[tuple[int, list[tuple[int, int, int]]]]:
    """Windows ``(tier, [(document, start, length), ...])`` that hold every token of documents once.

    Every window is full: its pieces add up to its size, which is the longest tier or a power of two.
    """
    longest = max(tiers)
    windows: list[tuple[int, list]] = []
    shelves = {t: Shelf() for t in sorted(tiers)}
    for i, n in enumerate(lengths):
        whole = n - n % longest
        windows += [(longest, [(i, at, longest)]) for at in range(0, whole, longest)]
        if n > whole:
            shelves[next(t for t in sorted(tiers) if n - whole <= t)].put((i, whole, n - whole))

    def filler(gap: int, own: int):
        """A piece of at most ``gap`` tokens: the best fit from shorter tiers, else a cut one."""
        below = [shelves[t] for t in sorted(tiers, reverse=True) if t <= own]
        fits = [(s.fitting(gap), s) for s in below]
        size, shelf = max(fits, key=lambda x: x[0])
        if size == gap or size and size * 2 >= gap:
            return shelf.take(size)
        for shelf in reversed(below):  # the shortest tier gives the piece to be cut
            if n := shelf.shortest():
                if n <= gap:
                    return shelf.take(shelf.fitting(gap))
                i, at, n = shelf.take(n)
                back = (i, at + gap, n - gap)
                shelves[next(t for t in sorted(tiers) if back[2] <= t)].put(back)
                return (i, at, gap)
        return None

    for tier in sorted(tiers, reverse=True):
        own = shelves[tier]
        while own.mask:
            first = own.take(own.fitting(tier))
            window, gap = [first], tier - first[2]
            while gap and (piece := filler(gap, tier)):
                window.append(piece)
                gap -= piece[2]
            if not gap:
                windows.append((tier, window))
                continue
            left = tier - gap  # nothing is left in the block: powers of two hold the rest
            for size in (1 << k for k in range(left.bit_length() - 1, -1, -1) if left >> k & 1):
                part, room = [], size
                while room:
                    i, at, n = window.pop(0)
                    part.append((i, at, min(n, room)))
                    if n > room:
                        window.insert(0, (i, at + room, n - room))
                    room -= part[-1][2]
                windows.append((size, part))
    return windows


PACKED = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, window int, step_group long"


def pack_documents(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", tiers: tuple[int, ...] = TIERS, block_tokens: int = BLOCK_TOKENS, with_ids: bool = False) -> DataFrame:
    """One row per piece of every row of ``docs`` (columns ``PACKED``, and ``ids`` if asked for).

    Every id of a document (its text's ids, then 0) lies in exactly one piece.  A null text counts as empty and
    gives one piece with the closing id; repeated rows are packed each for itself; an empty table gives an empty
    result; other columns are ignored.  ``window`` is the size of the sequence, always the longest tier or a
    power of two, so no sequence holds padding.
    """
    small_batches(docs.sparkSession)
    schema = PACKED + (", ids binary" if with_ids else "")

    def run(batches):
        part = TaskContext.get().partitionId()
        made, steps = 0, defaultdict(int)
        held: list[tuple[int, np.ndarray]] = []
        size = 0

        def block():
            nonlocal made
            cols: list[list] = [[] for _ in range(9 + with_ids)]
            for window, pieces in pack([len(ids) for _, ids in held], tiers):
                sequence, offset = (part << 33) + made, 0
                group = (part << 33) + (window.bit_length() << 27) + steps[window] // STEP_TOKENS
                steps[window] += window
                made += 1
                for i, start, length in pieces:
                    doc_id, ids = held[i]
                    raw = ids[start : start + length].astype("<u4").tobytes()
                    for c, v in zip(cols, (doc_id, start, length, zlib.crc32(raw), len(ids), sequence, offset, window, group, raw), strict=False):
                        c.append(v)
                    offset += length
            kinds = [pa.int64()] * 7 + [pa.int32(), pa.int64()] + [pa.binary()] * with_ids
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [x.split()[0] for x in schema.split(", ")])

        for batch in batches:
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                held.append((doc_id, token_ids(text, vocabulary)))
                size += len(held[-1][1])
                if size >= block_tokens:
                    yield block()
                    held, size = [], 0
        if held:
            yield block()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, schema)
