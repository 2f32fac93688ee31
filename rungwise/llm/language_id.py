"""Language identification with error-correcting output codes.

Each language has a codeword; each bit of the code is a binary question ("is the language in this half?") that a
classifier over hashed character n-grams answers with a margin: the mean weight of a text's n-grams, shrunk towards
zero for short texts and scaled so that a typical training text answers with ``CONFIDENT`` logits.  Decoding weighs
every bit by the logistic loss of its margin and takes the codeword with the smallest sum.  The runner-up tells how
ambiguous the answer is: a text in two languages has middling margins on the bits that part them.
"""

from __future__ import annotations

import itertools
import re
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import small_batches

#: Labelled rows of each language that the classifiers are fitted on at most, about (chosen by a hash).
TRAIN_ROWS = 4000
ORDERS = (1, 2, 3)
BITS = 15
#: Logits that the median training text gets on every bit.
CONFIDENT = 4.0
#: A margin is shrunk as if this many n-grams of no language stood beside the text's own.
PRIOR_GRAMS = 12
#: Answers with a smaller score are flagged.
AMBIGUOUS = 0.9
_CHUNK = 1 << 16
_letter = re.compile(r"[^\W\d_]").search


def codewords(n: int) -> np.ndarray:
    """An n x m matrix of -1 and +1: all splits of up to 6 classes, else the best of 50 random codes."""
    if n <= 1:
        return np.ones((n, 1), np.int8)
    if n <= 6:
        cols = [c for c in itertools.product((-1, 1), repeat=n) if c[0] == 1 and len(set(c)) == 2]
        return np.array(cols, np.int8).T
    rng, width = np.random.default_rng(7), int(np.ceil(10 * np.log2(n)))
    codes = [rng.choice(np.array([-1, 1], np.int8), (n, width)) for _ in range(50)]
    apart = lambda c: ((width - c.astype(int) @ c.T.astype(int)) // 2 + width * np.eye(n, dtype=int)).min()
    best = max(codes, key=apart)
    return best[:, [len(set(col)) == 2 for col in best.T]]


def grams(text: str):
    """Hashed n-gram numbers of a whole text, in chunks of bounded size; digits and marks count as gaps."""
    points = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    for at in range(0, len(points), _CHUNK):
        cps = points[at : at + _CHUNK + max(ORDERS) - 1].astype(np.uint64)
        cps[(cps < 97) | ((cps > 122) & (cps < 128))] = 32
        for k in ORDERS:
            n = min(len(cps) - k + 1, _CHUNK)
            if n <= 0:
                continue
            h = cps[:n] + np.uint64(k * 7919)
            for j in range(1, k):
                h = h * np.uint64(0x9E3779B97F4A7C15) + cps[j : j + n]
            h *= np.uint64(0xFF51AFD7ED558CCD)
            yield (h >> np.uint64(64 - BITS)).astype(np.int64)


@dataclass
class Model:
    languages: list[str]
    code: np.ndarray  # languages x bits
    weights: np.ndarray  # features x bits
    scale: np.ndarray  # logits of a margin of one, by bit

    def margins(self, text: str) -> np.ndarray:
        """Mean weights of the whole text's n-grams by bit, shrunk for short texts and scaled to logits."""
        total, n = np.zeros(self.code.shape[1]), 0
        for numbers in grams(text):
            counts = np.bincount(numbers, minlength=1 << BITS) if len(numbers) > (1 << BITS) // 2 else None
            total += counts @ self.weights if counts is not None else self.weights[numbers].sum(axis=0, dtype=np.float64)
            n += len(numbers)
        return total / (n + PRIOR_GRAMS) * self.scale

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        """(language or und, score from 0 to 1, whether the answer is ambiguous)."""
        if not self.languages or text is None or not _letter(text):
            return "und", 0.0, True
        loss = np.logaddexp(0, -self.code * self.margins(text)).sum(axis=1)
        share = np.exp(-(loss - loss.min()) * 2 / max(1, self.code.shape[1]))
        score = float(share.max() / share.sum())
        return self.languages[int(loss.argmin())], score, score < AMBIGUOUS


def held_out(doc_id):
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def fit(docs: DataFrame, train_rows: int = TRAIN_ROWS) -> Model:
    """Fit on labelled rows outside the held-out fifth: about ``train_rows`` whole texts of each language.

    Only n-gram counts by language reach the driver, as many numbers as there are features times languages.
    """
    labelled = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).where("lang is not null and text is not null and doc_id is not null").where(~held_out(F.col("doc_id")))
    counts = {r.lang: r.n for r in labelled.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    languages = sorted(counts)
    if not languages:
        return Model([], codewords(0), np.zeros((1 << BITS, 1), np.float32), np.ones(1))
    share = F.element_at(F.create_map(*itertools.chain.from_iterable((F.lit(k), F.lit(min(1.0, train_rows / n))) for k, n in counts.items())), F.col("lang"))
    chosen = labelled.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < share * (1 << 20)).select("lang", "text")
    place = {k: i for i, k in enumerate(languages)}

    def count(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text").to_pylist(), strict=True):
                row = sums.setdefault(place[lang], np.zeros(1 << BITS, np.int64))
                for numbers in grams(text):
                    row += np.bincount(numbers, minlength=1 << BITS)
        for k, row in sums.items():
            at = np.flatnonzero(row)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), k, np.int32)), pa.array(at.astype(np.int32)), pa.array(row[at])], ["k", "feature", "n"])

    small_batches(docs.sparkSession)
    found = chosen.mapInArrow(count, "k int, feature int, n long").groupBy("k", "feature").agg(F.sum("n").alias("n")).toPandas()
    table = np.full((len(languages), 1 << BITS), 0.5)
    table[found.k.to_numpy(), found.feature.to_numpy()] += found.n.to_numpy()
    shares = table / table.sum(axis=1, keepdims=True)
    code = codewords(len(languages))
    weights = np.stack([np.log(shares[col > 0].mean(axis=0)) - np.log(shares[col < 0].mean(axis=0)) if (col < 0).any() else np.zeros(1 << BITS) for col in code.T], axis=1)
    return calibrated(Model(languages, code, weights.astype(np.float32), np.ones(code.shape[1])), chosen)


def calibrated(model: Model, chosen: DataFrame) -> Model:
    """The model scaled so that the median text of ``chosen(lang, text)`` has ``CONFIDENT`` logits on each bit.

    One number a bit reaches the driver: the median of the texts' unscaled margins.
    """
    shipped = chosen.sparkSession.sparkContext.broadcast(model)

    def sizes(batches):
        model = shipped.value
        for batch in batches:
            found = [np.abs(model.margins(t)) for t in batch.column("text").to_pylist() if _letter(t)]
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(list(m), pa.float64()) for m in np.array(found).T], [f"m{i}" for i in range(model.code.shape[1])])

    bits = range(model.code.shape[1])
    middle = chosen.mapInArrow(sizes, ", ".join(f"m{i} double" for i in bits)).agg(*[F.percentile_approx(f"m{i}", 0.5).alias(f"m{i}") for i in bits]).first()
    return replace(model, scale=np.array([CONFIDENT / x if x else 1.0 for x in middle]))


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """One row per row of ``docs``: doc_id, held_out, lang_pred, score, ambiguous, from the whole text alone.

    ``und`` for a null text, a text without letters, or when nothing could be learned.  Repeated rows get equal
    answers, an empty table gives an empty result, other columns are ignored, a null doc_id isn't held out.
    """
    small_batches(docs.sparkSession)
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        model = shipped.value
        for batch in batches:
            answers = [model.predict(t) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array([a[0] for a in answers], pa.string()), pa.array([a[1] for a in answers], pa.float64()), pa.array([a[2] for a in answers], pa.bool_())], ["doc_id", "held_out", "lang_pred", "score", "ambiguous"])

    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("held_out", F.coalesce(held_out(F.col("doc_id")), F.lit(False)))
    return plain.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double, ambiguous boolean")


def identify(docs: DataFrame, train_rows: int = TRAIN_ROWS) -> DataFrame:
    return predict(docs, fit(docs, train_rows))


def keep_identified(docs: DataFrame) -> DataFrame:
    """The rows of ``docs``, all columns, whose text has a language (the answer isn't ``und``)."""
    model = fit(docs)
    small_batches(docs.sparkSession)
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        model = shipped.value
        for batch in batches:
            yield batch.filter(pa.array([model.predict(t)[0] != "und" for t in batch.column("text").cast(pa.string()).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
