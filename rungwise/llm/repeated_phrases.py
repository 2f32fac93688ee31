"""Removal of long passages that repeat across documents, located with sharded Aho-Corasick automata.

Candidates.  A window is ``WINDOW`` consecutive words.  Of the 12-word grams in a window the one with the smallest
hash is its anchor; equal windows have equal anchors.  Consecutive windows of a document that share an anchor form
a run (about 20 windows), and one row per run (anchor, hash of the run's words) is enough to find most repeats: a
run equal to a run of a smaller doc_id repeats as a whole.  Only runs whose anchor occurs with different
surroundings are resolved window by window.  All counting is by partial aggregates, so copies in any number cost no
more than their own rows; hot runs and windows are spread over all tasks.

Confirming and locating.  Hashes only say where to look.  Every stretch that seems to repeat is covered with windows,
and the texts of these windows are taken from the smallest document that has them: these are the patterns.  Documents
are dealt to shards; a shard compiles the patterns asked for by its documents into one automaton and streams its
documents through it.  Only words inside an occurrence of a pattern of a smaller doc_id go, so what is removed is
decided by comparing texts.
"""

from __future__ import annotations

import hashlib

import ahocorasick
import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, drop_cut, keyed_join, scratch, small_batches

WINDOW = 50
GRAM = 12
#: Bytes of patterns that a shard's automaton holds, about.
SHARD_BYTES = 2_000_000
#: Shards whose requests to one document travel in one row.
SHARDS_A_ROW = 1024
_ODD = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0xFF51AFD7ED558CCD))


def _mix(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    x = left * _ODD[0] ^ (right * _ODD[1] + (right >> np.uint64(31)))
    x ^= x >> np.uint64(33)
    x *= _ODD[2]
    x ^= x >> np.uint64(29)
    return x


def gram_hashes(words: np.ndarray, length: int) -> np.ndarray:
    """Hash of every ``length`` consecutive word hashes, by doubling."""
    n = len(words)
    if n < length:
        return np.empty(0, np.uint64)
    out, at, power, size = None, 0, words, 1
    while size <= length:
        if length & size:
            part = power[at : at + n - length + 1]
            out = part if out is None else _mix(out, part)
            at += size
        if size * 2 <= length:
            power = _mix(power[: len(power) - size], power[size:])
        size *= 2
    return out


def sliding_min(values: np.ndarray, length: int) -> np.ndarray:
    power, size = values, 1
    while size * 2 <= length:
        power = np.minimum(power[: len(power) - size], power[size:])
        size *= 2
    rest = length - size
    return np.minimum(power[: len(power) - rest], power[rest:]) if rest else power


def split_words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").split()


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))


def runs_of(words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(anchor, run hash, first window, number of windows) of every run, and the hash of every window."""
    hashed = word_hashes(words)
    anchors = sliding_min(gram_hashes(hashed, GRAM), WINDOW - GRAM + 1)
    windows = gram_hashes(hashed, WINDOW)
    first = np.flatnonzero(np.concatenate(([True], anchors[1:] != anchors[:-1])))
    count = np.diff(np.append(first, len(anchors)))
    # a run's hash: its first and last window and its length fix every word only together with the windows
    # between, so all windows are folded in
    folded = np.bitwise_xor.reduceat(_mix(windows, (np.arange(len(windows)) - np.repeat(first, count)).astype(np.uint64)), first)
    return anchors[first], _mix(folded, count.astype(np.uint64)), first, count, windows


_KEY = "doc_id long, rk long"


def _keyed(docs: DataFrame) -> DataFrame:
    """Rows with a key that also tells repeated ids with other texts apart."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("rk", F.xxhash64("text"))


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def _run_rows(batches):
    for batch in batches:
        ids, keys = batch.column("doc_id").to_pylist(), batch.column("rk").to_pylist()
        parts = []
        for i, text in enumerate(batch.column("text").to_pylist()):
            words = split_words(text)
            if len(words) < WINDOW or ids[i] is None:
                continue
            anchor, run, first, count, _ = runs_of(words)
            parts.append((ids[i], keys[i], anchor, run, first, count))
        if parts:
            sizes = [len(p[2]) for p in parts]
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.repeat(np.array([p[0] for p in parts], np.int64), sizes)), pa.array(np.repeat(np.array([p[1] for p in parts], np.int64), sizes)), _signed(np.concatenate([p[2] for p in parts])), _signed(np.concatenate([p[3] for p in parts])), pa.array(np.concatenate([p[4] for p in parts]).astype(np.int32)), pa.array(np.concatenate([p[5] for p in parts]).astype(np.int32))],
                ["doc_id", "rk", "anchor", "run", "first", "n_win"],
            )


_FOUND = "doc_id long, rk long, text string, first int, window long"


def _window_rows(batches):
    """Every document (its text), and the hashes of the windows in those of its runs that need them."""
    names = [c.split()[0] for c in _FOUND.split(", ")]
    for batch in batches:
        ids, keys, spans = batch.column("doc_id").to_pylist(), batch.column("rk").to_pylist(), batch.column("spans").to_pylist()
        n = len(ids)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("rk"), batch.column("text").cast(pa.string()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.int64())], names)
        out = []
        for i, text in enumerate(batch.column("text").to_pylist()):
            if spans[i]:
                windows = gram_hashes(word_hashes(split_words(text)), WINDOW)
                at = np.concatenate([np.arange(s["first"], s["first"] + s["n_win"]) for s in spans[i]])
                out.append((ids[i], keys[i], at, windows[at]))
        if out:
            sizes = [len(x[2]) for x in out]
            total = sum(sizes)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.array([x[0] for x in out], np.int64), sizes)), pa.array(np.repeat(np.array([x[1] for x in out], np.int64), sizes)), pa.nulls(total, pa.string()), pa.array(np.concatenate([x[2] for x in out]).astype(np.int32)), _signed(np.concatenate([x[3] for x in out]))], names)


def candidates(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Documents that share anchors, ``(doc_id, rk, text)``, and what seems to repeat in them:
    ``(doc_id, rk, first, n_win, owner)``, windows that also start in a smaller doc_id, with the place
    ``owner(doc_id, rk, first)`` of the first one's smallest equal."""
    keyed = _keyed(docs)
    runs = cut(keyed.mapInArrow(_run_rows, f"{_KEY}, anchor long, run long, first int, n_win int"))
    total = runs.count()
    # an anchor of one document only can't stand in a repeat
    shared = runs.groupBy("anchor").agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high"), F.count("*").alias("__n")).where("low < high").select("anchor", "__n")
    met = cut(keyed_join(runs, shared, "anchor", total))
    drop_cut(runs)
    total = met.count()
    owners = cut(met.groupBy("anchor", "run").agg(F.min(F.struct("doc_id", "rk", "first")).alias("owner"), F.count("*").alias("rows")))
    shapes = owners.groupBy("anchor").agg(F.count("*").alias("__n"), (F.count("*") > 1).alias("mixed"))
    known = keyed_join(owners, shapes, "anchor", total).select("run", "owner", "mixed", F.col("rows").alias("__n"))
    told = cut(keyed_join(met.drop("anchor"), known, "run", total).select("doc_id", "rk", "first", "n_win", "owner", (F.col("owner.doc_id") < F.col("doc_id")).alias("whole"), "mixed"))
    drop_cut(met)
    spans = told.groupBy("doc_id", "rk").agg(F.collect_list(F.when(F.col("mixed") & ~F.col("whole"), F.struct("first", "n_win"))).alias("spans"))
    found = cut(keyed.join(spans, ["doc_id", "rk"]).dropDuplicates(["doc_id", "rk"]).select("doc_id", "rk", "text", "spans").mapInArrow(_window_rows, _FOUND))
    # windows of whole runs can be the smallest equals of single ones, but their runs' owners are smaller still
    windows = found.where("window is not null").select("doc_id", "rk", "first", "window")
    least = windows.groupBy("window").agg(F.min(F.struct("doc_id", "rk", "first")).alias("owner"), F.max("doc_id").alias("last"), F.count("*").alias("__n")).where("owner.doc_id < last").drop("last")
    single = keyed_join(windows, least, "window", windows.count()).where("owner.doc_id < doc_id").select("doc_id", "rk", "first", F.lit(1).alias("n_win"), "owner")
    repeated = cut(told.where("whole").select("doc_id", "rk", "first", "n_win", "owner").unionByName(single))
    return found.where("window is null").select("doc_id", "rk", "text"), repeated


def cover(spans: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    """Of windows given as sorted ``(first, number, ...)`` ranges, few that cover the same words: ``(range, start)`` pairs."""
    out: list[tuple[int, int]] = []
    i, covered = 0, -1
    while i < len(spans):
        if spans[i][0] > covered:  # a new stretch begins
            out.append((i, spans[i][0]))
            covered = spans[i][0] + WINDOW
        # of the windows that begin within what is covered, the last one reaches furthest
        best, j = None, i
        while j < len(spans) and spans[j][0] <= covered:
            at = min(spans[j][0] + spans[j][1] - 1, covered)
            if at + WINDOW > covered and (best is None or at > best[1]):
                best = (j, at)
            j += 1
        if best is None:
            i = j
        else:
            out.append(best)
            covered = best[1] + WINDOW
            while i < len(spans) and spans[i][0] + spans[i][1] + WINDOW - 1 <= covered:
                i += 1
    return out


def _requests(batches):
    """The places whose windows cover what seems to repeat in a document."""
    names = ["doc_id", "rk", "own_id", "own_rk", "own_first"]
    for batch in batches:
        rows = []
        for doc_id, rk, spans in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "rk", "spans")), strict=True):
            ranges = sorted((s["first"], s["n_win"], k) for k, s in enumerate(spans))
            for i, start in cover(ranges):
                first, _, k = ranges[i]
                o = spans[k]["owner"]
                rows.append((doc_id, rk, o["doc_id"], o["rk"], o["first"] + start - first))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32()), strict=True)], names)


def _pattern_rows(batches):
    """The texts of the windows that shards asked a document for."""
    for batch in batches:
        rows = []
        for doc_id, text, asked in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "text", "asked")), strict=True):
            words = split_words(text)
            rows += [(x["shard"], 0, doc_id, None, b" ".join(words[x["first"] : x["first"] + WINDOW]).decode("utf-8", "surrogatepass")) for x in asked]
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.string()), strict=True)], ["shard", "kind", "doc_id", "rk", "text"])


def removed_words(doc_id: int, words: list[bytes], automaton) -> np.ndarray:
    """Which words an occurrence of a smaller document's pattern covers."""
    gone = np.zeros(len(words), bool)
    if len(words) >= WINDOW:
        begins = np.cumsum([0, *(len(w) + 1 for w in words)])
        for end, owner in automaton.iter(" " + b" ".join(words).decode("latin-1") + " "):
            if owner < doc_id:
                last = int(np.searchsorted(begins, end))
                gone[last - WINDOW : last] = True
    return gone


def compiled(patterns: dict[str, int]):
    """One automaton for patterns (words joined by single spaces, as Latin-1 bytes) with their smallest document."""
    automaton = ahocorasick.Automaton()
    for text, doc_id in patterns.items():
        automaton.add_word(f" {text} ", doc_id)
    automaton.make_automaton()
    return automaton


def _streamed(batches):
    """Rows sorted by shard, patterns first: each shard's automaton is compiled, then its documents run through it."""
    names = ["doc_id", "rk", "n_removed", "kept_sha256", "kept_text"]
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string())
    now, patterns, automaton = None, {}, None
    for batch in batches:
        rows = []
        for shard, kind, doc_id, rk, text in zip(*(batch.column(c).to_pylist() for c in ("shard", "kind", "doc_id", "rk", "text")), strict=True):
            if shard != now:
                now, patterns, automaton = shard, {}, None
            if kind == 0:
                known = text.encode("utf-8", "surrogatepass").decode("latin-1")
                patterns[known] = min(doc_id, patterns.get(known, doc_id))
                continue
            if not patterns:
                continue
            if automaton is None:
                automaton = compiled(patterns)
            words = split_words(text)
            gone = removed_words(doc_id, words, automaton)
            if gone.any():
                kept = b" ".join([w for w, g in zip(words, gone.tolist(), strict=True) if not g])
                rows.append((doc_id, rk, int(gone.sum()), hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "surrogatepass")))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def changed(docs: DataFrame) -> DataFrame:
    """``(doc_id, rk, n_removed, kept_sha256, kept_text)`` of the documents that lose words."""
    texts, repeated = candidates(docs)
    spans = repeated.groupBy("doc_id", "rk").agg(F.collect_list(F.struct("first", "n_win", "owner")).alias("spans"))
    asked = cut(spans.mapInArrow(_requests, "doc_id long, rk long, own_id long, own_rk long, own_first int"))
    shards = max(1, -(-asked.count() * WINDOW * 8 // SHARD_BYTES))
    shard = F.pmod(F.xxhash64("doc_id", "rk"), F.lit(shards))
    by_owner = asked.select(shard.alias("shard"), F.col("own_id").alias("doc_id"), F.col("own_rk").alias("rk"), F.col("own_first").alias("first")).distinct()
    by_owner = by_owner.groupBy("doc_id", "rk", F.floor(F.col("shard") / SHARDS_A_ROW).alias("part")).agg(F.collect_list(F.struct("shard", "first")).alias("asked"))
    patterns = texts.join(by_owner.hint("merge"), ["doc_id", "rk"]).select("doc_id", "text", "asked").mapInArrow(_pattern_rows, "shard long, kind int, doc_id long, rk long, text string")
    dealt = patterns.unionByName(texts.select(shard.alias("shard"), F.lit(1).alias("kind"), "doc_id", "rk", "text"))
    return dealt.repartition("shard").sortWithinPartitions("shard", "kind").mapInArrow(_streamed, f"{_KEY}, n_removed long, kept_sha256 string, kept_text string")


def _plain(batches, with_text: bool):
    for batch in batches:
        rows = []
        for text in batch.column("text").to_pylist():
            words = split_words(text)
            kept = b" ".join(words)
            rows.append((len(words), hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "surrogatepass") if with_text else None))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("rk"), *(pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.string(), pa.string()), strict=True))], ["doc_id", "rk", "n_words", "whole_sha256", "whole_text"])


def remove_repeats(docs: DataFrame, with_text: bool = True) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_words, n_removed, kept_sha256 and (optionally) kept_text.

    A word goes if a window of ``WINDOW`` words that covers it also starts in a document with a smaller doc_id,
    judged on the input.  Null and blank texts have no words and an empty kept text; a null doc_id is never
    compared; repeated rows are judged alike; an empty table gives an empty result; other columns are ignored.
    """
    small_batches(docs.sparkSession)
    with scratch() as keep:
        lost = keep(cut(changed(docs).select("doc_id", "rk", "n_removed", "kept_sha256", *(["kept_text"] if with_text else []))))
    every = _keyed(docs).mapInArrow(lambda batches: _plain(batches, with_text), f"{_KEY}, n_words long, whole_sha256 string, whole_text string")
    out = every.join(lost, ["doc_id", "rk"], "left")
    text = [F.coalesce("kept_text", "whole_text").alias("kept_text")] if with_text else []
    return out.select("doc_id", "n_words", F.coalesce("n_removed", F.lit(0).cast("long")).alias("n_removed"), F.coalesce("kept_sha256", "whole_sha256").alias("kept_sha256"), *text)
