"""SimHash near-duplicates by multi-index hashing.

Fingerprints: every bit is the strict majority of that bit in the XXH64 values of a text's word shingles.
Search: a fingerprint's bits are parted into segments, and one table per segment is keyed by the segment's value.
Two fingerprints at ``MAX_DISTANCE`` bits or less agree up to a small radius in some segment (pigeonhole), so each
fingerprint enumerates a small Hamming ball within each segment, fetches the tables' entries under those values,
and complete distances are verified before a link counts.

A segment value that very many different fingerprints share would make pairs by the square.  Fingerprints of such
crowded values (over ``CROWD``) meet among themselves at midpoints instead: two of them at distance 2 or less share
a value one flipped bit away from both, and tying all that share a midpoint to the smallest one keeps what is
connected while rows stay in proportion to fingerprints.
"""

from __future__ import annotations

from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, keyed_join, scratch, small_batches
from .components import components

#: Two segments of 32 bits: a value of one is shared by chance by one in 4 billion fingerprints.
SEGMENTS = 2
MAX_DISTANCE = 2
#: Rows under one segment value from which on its fingerprints meet at midpoints.
CROWD = 200


def fingerprint(text: str | None, words_per_shingle: int = 3, seed: int = 42) -> int:
    """Unsigned 64-bit fingerprint; zero for a text without words (null included)."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    k = words_per_shingle
    shingles = [b" ".join(words)] if len(words) < k else list(map(b" ".join, zip(*(words[i:] for i in range(k)), strict=False)))
    hashed = np.fromiter(map(xxhash.xxh64_intdigest, shingles, repeat(seed)), np.uint64, len(shingles))
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashed), 1 << 15):  # bounded memory on very long texts
        ones += np.unpackbits(hashed[at : at + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(hashed), bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, words_per_shingle: int = 3) -> DataFrame:
    """``(doc_id, fp BIGINT)`` for every row; the bits of ``fp`` are the fingerprint's."""
    small_batches(docs.sparkSession)

    def run(batches):
        for batch in batches:
            seen: dict = {}
            out = []
            for text in batch.column("text").to_pylist():
                if text not in seen:
                    seen[text] = fingerprint(text, words_per_shingle)
                out.append(seen[text])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.array(out, np.uint64).view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, fp long")


def radii(distance: int, segments: int) -> list[int]:
    """Radius of each segment's ball (-1: not searched) such that any pair within ``distance`` meets in some segment.

    With distance = segments * r + rest, a pair outside radius r in the first rest + 1 segments and outside r - 1 in
    the others differs in (rest + 1) * (r + 1) + (segments - rest - 1) * r > distance bits.
    """
    r, rest = divmod(distance, segments)
    return [r if i <= rest else r - 1 for i in range(segments)]


def _flips(width: int, radius: int) -> list[int]:
    """Masks of up to ``radius`` of ``width`` bits."""
    return [sum(1 << i for i in at) for w in range(radius + 1) for at in combinations(range(width), w)]


def _segment(fp, number: int, segments: int):
    width = 64 // segments
    return F.shiftrightunsigned(fp, number * width).bitwiseAND(F.lit((1 << width) - 1))


def tables(distinct_fps: DataFrame, segments: int = SEGMENTS) -> DataFrame:
    """``(segment, value, fp)``: the tables' entries, one per fingerprint and segment."""
    entries = F.array(*[F.struct(F.lit(k).alias("segment"), _segment(F.col("fp"), k, segments).alias("value")) for k in range(segments)])
    return distinct_fps.select("fp", F.explode(entries).alias("e")).select("e.segment", "e.value", "fp")


def probes(distinct_fps: DataFrame, distance: int = MAX_DISTANCE, segments: int = SEGMENTS) -> DataFrame:
    """``(segment, value, fp)``: the values that a fingerprint looks up, a Hamming ball in each searched segment."""

    def ball(k: int, radius: int):
        masks = F.array(*[F.lit(m).cast("long") for m in _flips(64 // segments, radius)])
        return F.transform(masks, lambda m: F.struct(F.lit(k).alias("segment"), _segment(F.col("fp"), k, segments).bitwiseXOR(m).alias("value")))

    balls = [ball(k, r) for k, r in enumerate(radii(distance, segments)) if r >= 0]
    return distinct_fps.select("fp", F.explode(F.concat(*balls)).alias("e")).select("e.segment", "e.value", "fp")


def _apart(a: str, b: str):
    return F.bit_count(F.col(a).bitwiseXOR(F.col(b)))


def midpoint_links(distinct_fps: DataFrame) -> DataFrame:
    """Links that connect the fingerprints at 2 bits or less, 65 rows a fingerprint, however dense they lie."""
    slots = distinct_fps.select("fp", F.explode(F.expr("concat(array(fp), transform(sequence(0, 63), i -> fp ^ shiftleft(1L, i)))")).alias("slot"))
    first = slots.groupBy("slot").agg(F.min("fp").alias("centre"), F.max("fp").alias("last")).where("centre <> last").select("slot", "centre")
    return slots.join(first, "slot").where(F.col("fp") != F.col("centre")).select(F.col("fp").alias("a"), F.col("centre").alias("b")).distinct()


def links(distinct_fps: DataFrame, segments: int = SEGMENTS, crowd: int = CROWD) -> DataFrame:
    """Links ``(a, b)`` that connect exactly the distinct fingerprints at ``MAX_DISTANCE`` or less."""
    entries, asked = tables(distinct_fps, segments), probes(distinct_fps, MAX_DISTANCE, segments)
    tagged = entries.withColumn("held", F.lit(True)).unionByName(asked.withColumn("held", F.lit(False)))
    # what nobody else looks up makes no pair: an entry always has its own probe under its value
    sizes = tagged.groupBy("segment", "value").agg(F.count("*").alias("n"), F.max("held").alias("held"), F.min("fp").alias("low"), F.max("fp").alias("high")).where("held and low <> high").select("segment", "value", "n")
    met = cut(tagged.join(sizes, ["segment", "value"]))
    near = met.where((F.col("n") <= crowd) & F.col("held")).select("segment", "value", F.col("fp").alias("a")).join(met.where((F.col("n") <= crowd) & ~F.col("held")).select("segment", "value", F.col("fp").alias("b")), ["segment", "value"])
    pairs = near.where((F.col("a") != F.col("b")) & (_apart("a", "b") <= MAX_DISTANCE)).select("a", "b")
    crowded = met.where(F.col("n") > crowd).select("fp").distinct()
    return pairs.unionByName(midpoint_links(crowded)).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def near_duplicates(docs: DataFrame, words_per_shingle: int = 3) -> DataFrame:
    """``(doc_id, fp, component_id)`` for every row of ``docs``.

    ``component_id`` is the smallest doc_id reachable over links of two or fewer differing bits.  Null and blank
    texts have fingerprint zero and link like any other; repeated rows and ids stay; an empty table gives an
    empty result; other columns are ignored.  A null doc_id keeps its row and takes no part in the minimum.
    """
    rows = cut(fingerprints(docs, words_per_shingle))
    fps = rows.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("n"))
    with scratch() as keep:
        found = keep(cut(components(links(fps.select("fp")))))
    classes = found.select(F.col("node").alias("fp"), F.col("component").alias("class"))
    known = fps.join(classes, "fp", "left").select("fp", "least", "n", F.coalesce("class", "fp").alias("class"))
    least = known.groupBy("class").agg(F.min("least").alias("component_id"))
    total = rows.count()
    named = known.join(least, "class").select("fp", "component_id", F.col("n").alias("__n"))
    return keyed_join(rows, named, "fp", total).select("doc_id", "fp", "component_id")


def hex_digits(fp):
    """16 lowercase hex digits of a fingerprint column."""
    return F.lpad(F.lower(F.hex(fp)), 16, "0")
