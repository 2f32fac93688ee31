"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

The symbols are words, the patterns are the benchmark's windows.  Patterns of one length share a search: a shift
table tells for a block of two words how far the window may jump, a bucket of patterns hangs on each block that
ends one, and the words are compared directly before an occurrence counts.  The benchmark is cut into blocks of
bounded bytes; each block is searched in its own pass over the documents, so nothing shipped to the executors
grows without bound.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, small_batches

WINDOW = 13
#: Bytes of benchmark text in one search block.
BLOCK_BYTES = 8_000_000

# every ASCII byte that isn't a digit or a letter parts words; A-Z turn into a-z
_FOLD = bytes(ord(" ") if b < 0x30 or 0x3A <= b <= 0x40 or 0x5B <= b <= 0x60 or 0x7B <= b <= 0x7F else b + 32 if 0x41 <= b <= 0x5A else b for b in range(256))


def fold_words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_FOLD).split()


@dataclass
class Searcher:
    """Wu-Manber tables for patterns of one length, over word numbers (0: a word no pattern has)."""

    length: int
    block: int = 2
    shift: dict = field(default_factory=dict)
    buckets: dict = field(default_factory=dict)

    def __post_init__(self):
        self.block = min(self.block, self.length)

    def add(self, pattern: tuple[int, ...], items: list[str]) -> None:
        b, m = self.block, self.length
        for end in range(b, m + 1):
            key = pattern[end - b : end]
            self.shift[key] = min(self.shift.get(key, m), m - end)
        self.buckets.setdefault(pattern[m - b :], {}).setdefault(pattern, []).extend(items)

    def find(self, words: list[int]):
        """(start, items) of every occurrence."""
        m, b, n = self.length, self.block, len(words)
        jump, far, get, buckets = self.shift.get, m - b + 1, self.shift.get, self.buckets
        end = m
        while end <= n:
            key = (words[end - 2], words[end - 1]) if b == 2 else (words[end - 1],)
            step = get(key, far)
            if step:
                end += step
                continue
            found = buckets[key].get(tuple(words[end - m : end]))
            if found is not None:
                yield end - m, found
            end += 1


def compile_patterns(items: list[tuple[str, str | None]]) -> tuple[dict[bytes, int], list[Searcher]]:
    """Word numbers and one searcher per pattern length, for the windows of ``(item_id, text)`` pairs."""
    numbers: dict[bytes, int] = {}
    searchers: dict[int, Searcher] = {}
    windows: dict[tuple[int, ...], list[str]] = {}
    for item, text in items:
        words = [numbers.setdefault(w, len(numbers) + 1) for w in fold_words(text)]
        if words:
            size = min(WINDOW, len(words))
            for window in {tuple(words[i : i + size]) for i in range(len(words) - size + 1)}:
                windows.setdefault(window, []).append(item)
    for window, owners in windows.items():
        searchers.setdefault(len(window), Searcher(len(window))).add(window, owners)
    return numbers, [searchers[k] for k in sorted(searchers)]


def search_text(text: str | None, numbers: dict[bytes, int], searchers: list[Searcher]) -> tuple[int, list[int], set[str]]:
    """(words, flat [start, end, start, end ...] of merged hit stretches, items found)."""
    folded = fold_words(text)
    get = numbers.get
    words = [get(w, 0) for w in folded]
    spans: list[tuple[int, int]] = []
    items: set[str] = set()
    for s in searchers:
        for start, owners in s.find(words):
            spans.append((start, start + s.length))
            items.update(owners)
    return len(words), union(spans), items


def union(spans: list[tuple[int, int]]) -> list[int]:
    out: list[int] = []
    for a, b in sorted(spans):
        if out and a <= out[-1]:
            out[-1] = max(out[-1], b)
        else:
            out += [a, b]
    return out


def _blocks(benchmark: DataFrame) -> list[list[tuple[str, str | None]]]:
    """The benchmark in blocks of bounded bytes, one driver fetch per block."""
    sized = benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null")
    total = sized.agg(F.sum(F.coalesce(F.octet_length("text"), F.lit(0)) + 64)).first()[0] or 0
    n = max(1, -(-total // (BLOCK_BYTES // 2)))
    if n == 1:
        yield [(r.item_id, r.text) for r in sized.collect()]
        return
    for k in range(n):
        yield [(r.item_id, r.text) for r in sized.where(F.pmod(F.xxhash64("item_id"), F.lit(n)) == k).toLocalIterator()]


_FOUND = "doc_id long, row long, n_words long, spans array<int>, items array<string>"


def _searched(docs: DataFrame, items: list[tuple[str, str | None]]) -> DataFrame:
    numbers, searchers = compile_patterns(items)
    tables = docs.sparkSession.sparkContext.broadcast((numbers, searchers))

    def run(batches):
        numbers, searchers = tables.value
        for batch in batches:
            found = [search_text(t, numbers, searchers) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("row"), pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.list_(pa.int32())), pa.array([sorted(f[2]) for f in found], pa.list_(pa.string()))],
                ["doc_id", "row", "n_words", "spans", "items"],
            )

    return docs.mapInArrow(run, _FOUND)


_RESULT = "doc_id long, row long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


def _judged(batches):
    for batch in batches:
        rows = []
        for doc_id, row, n, spans, items in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "row", "n_words", "spans", "items")), strict=True):
            flat = union(list(zip(spans[::2], spans[1::2], strict=True)))
            hit = sum(flat[1::2]) - sum(flat[::2])
            names = sorted(set(items))
            rows.append((doc_id, row, n, hit, len(names), hashlib.sha256(",".join(names).encode()).hexdigest(), hit > 0 and 20 * hit >= n))
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_())
        names = ["doc_id", "row", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names)


def judge(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_words, n_hit, n_items, items_sha256, contaminated.

    A null or wordless text has no words and is clean; wordless items have no window; equal windows of several
    items count for each; repeated rows are judged alike; with an empty benchmark every document is clean; an
    empty table gives an empty result.  Items with a null id are left out, other columns are ignored.
    """
    small_batches(docs.sparkSession)
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    blocks = _blocks(benchmark)
    first = next(blocks)
    rows = plain.withColumn("row", F.lit(0).cast("long"))
    found = _searched(rows, first)
    rest = next(blocks, None)
    if rest is not None:  # beyond one block: rows get numbers that hold for all passes
        rows = cut(plain.withColumn("row", F.monotonically_increasing_id()))
        found = _searched(rows, first)
        while rest is not None:
            found = found.unionByName(_searched(rows, rest))
            rest = next(blocks, None)
        found = found.groupBy("doc_id", "row").agg(F.max("n_words").alias("n_words"), F.flatten(F.collect_list("spans")).alias("spans"), F.flatten(F.collect_list("items")).alias("items"))
    return found.mapInArrow(_judged, _RESULT).drop("row")


def clean_documents(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of ``docs``, with all their columns, that aren't contaminated (same rule as ``judge``)."""
    small_batches(docs.sparkSession)
    blocks = _blocks(benchmark)
    first = next(blocks)
    if next(blocks, None) is None:
        numbers, searchers = compile_patterns(first)
        tables = docs.sparkSession.sparkContext.broadcast((numbers, searchers))

        def run(batches):
            numbers, searchers = tables.value
            for batch in batches:
                keep = []
                for text in batch.column("text").cast(pa.string()).to_pylist():
                    n, flat, _ = search_text(text, numbers, searchers)
                    hit = sum(flat[1::2]) - sum(flat[::2])
                    keep.append(not (hit > 0 and 20 * hit >= n))
                yield batch.filter(pa.array(keep, pa.bool_()))

        return docs.mapInArrow(run, docs.schema)
    numbered = cut(docs.withColumn("__row", F.monotonically_increasing_id()))
    bad = judge(numbered.select(F.col("__row").alias("doc_id"), "text"), benchmark).where("contaminated").select(F.col("doc_id").alias("__row"))
    return numbered.join(bad, "__row", "left_anti").drop("__row")
