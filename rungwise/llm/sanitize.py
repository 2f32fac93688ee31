"""Personal data by patterns, and information-theoretic sanitisation of the terms that give it away.

Base spans come from fixed patterns.  Protected entities are the four kinds of base spans, secrets (long tokens of
letters and digits that look random) and every value found.  The corpus tells how strongly a term discloses an
entity: with N documents, n(e) that hold the entity, n(t) that hold the term and n(t,e) that hold both (for a value:
that hold the term within ``NEAR_WORDS`` words of it), a term's pointwise mutual information with the entity is
compared with the entity's own information content.  Terms that give away at least ``DISCLOSURE`` of it, on the
evidence of ``SUPPORT`` or more different texts, are spans wherever they stand in the corpus, near a mention or not,
and are generalised like the data itself.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import Counter
from math import log2

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, keyed_join, small_batches

KINDS = ("email", "ip", "card", "phone")
#: Protected beside the base kinds; their spans are marked too.
SECRET = "secret"
ENTITIES = (*KINDS, SECRET)
DISCLOSURE = 0.9
SUPPORT = 5
#: Words looked at on each side of a value's mention.
NEAR_WORDS = 6
#: Different terms that a task counts before it hands them on.
HELD_TERMS = 200_000
#: Disclosing terms that one pass over the documents looks for, at most; more terms take more passes.
SHIPPED_TERMS = 200_000
#: A secret has this many characters or more, letters and digits both, and this many bits a character.
SECRET_CHARS, SECRET_BITS = 24, 3.0

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_domain = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+").match
# starting at a digit run's first digit and taking whole runs finds the same leftmost matches in linear time
_ip = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]+").finditer
_card = re.compile(r"[0-9](?:[\x20-]?[0-9])+").finditer
_phone = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]").finditer
_word = re.compile(r"[^\W_]+").finditer
_words = re.compile(r"[^\W_]+").findall
_token = re.compile(r"[A-Za-z0-9+/_-]{%d,}" % SECRET_CHARS).finditer
_no_digit = re.compile(r"[^0-9]+").sub


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches, found from each @ backwards so that long tokens cost linear time."""
    out, last, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > last and text[start - 1] in _LOCAL:
            start -= 1
        found = _domain(text, at + 1) if start < at else None
        if found:
            out.append((start, found.end()))
            last = found.end()
        else:
            last = max(last, at + 1) if start == at else last
        at = text.find("@", max(at + 1, last))
    return out


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def base_spans(text: str | None) -> list[tuple[str, int, int]]:
    """(kind, start, end) in code points, by kind as listed, then start."""
    text = text or ""
    out = [("email", a, b) for a, b in emails(text)] if "@" in text else []
    for m in _ip(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or "0") <= 255 for p in m[0].split(".")):
            out.append(("ip", *m.span()))
    for m in _card(text):
        digits = _no_digit("", m[0])
        if 13 <= len(digits) <= 19 and luhn(digits):
            out.append(("card", *m.span()))
    if "+" in text:
        out += [("phone", *m.span()) for m in _phone(text) if 9 <= len(_no_digit("", m[0])) <= 15]
    return out


def joined(spans) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def secrets(text: str, taken: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """Long random-looking tokens outside the spans ``taken``."""
    out = []
    for m in _token(text):
        body = m[0]
        if any(c.isdigit() for c in body) and any(c.isalpha() for c in body) and not any(a < m.end() and m.start() < b for _, a, b in taken):
            counts = Counter(body).values()
            if sum(-n * log2(n / len(body)) for n in counts) >= SECRET_BITS * len(body):
                out.append((SECRET, *m.span()))
    return out


def blanked(text: str, spans: list[tuple[str, int, int]]) -> str:
    """``text`` with spaces in place of the spans, so that what is protected isn't its own evidence."""
    parts, at = [], 0
    for a, b in sorted((a, b) for _, a, b in spans):
        if b > at:
            parts += [text[at : max(a, at)], " " * (b - max(a, at))]
            at = b
    return "".join([*parts, text[at:]])


def contexts(text: str, bare: str, spans: list[tuple[str, int, int]]) -> set[tuple[str, str]]:
    """(value, term) for the ``NEAR_WORDS`` words of the blanked text ``bare`` on each side of every value."""
    words = [(m.start(), m[0].lower()) for m in _word(bare)]
    starts = [s for s, _ in words]
    out = set()
    for kind, a, b in spans:
        value = f"{kind} {text[a:b].lower()}"
        at = bisect_left(starts, a)
        out |= {(value, w) for _, w in words[max(0, at - NEAR_WORDS) : at + NEAR_WORDS]}
    return out


#: A row is a document's (``term`` null), or the counts of a term in many documents: with it, and by kind with it and the kind.
_SCANNED = "doc_id long, rk long, n_email long, n_ip long, n_card long, n_phone long, base string, hidden string, entities array<string>, near array<struct<entity:string,term:string>>, term string, n_term long, n_with array<long>"


def _scan(batches):
    pair = pa.list_(pa.struct([("entity", pa.string()), ("term", pa.string())]))
    kinds = (pa.int64(), pa.int64(), *[pa.int64()] * 4, pa.string(), pa.string(), pa.list_(pa.string()), pair, pa.string(), pa.int64(), pa.list_(pa.int64()))
    names = [c.split()[0] for c in _SCANNED.split(", ")]
    held: Counter = Counter()
    beside: dict[str, list[int]] = {}

    def counted():
        terms = list(held)
        none = [0] * len(ENTITIES)
        columns = [None] * 10 + [terms, list(held.values()), [beside.get(t, none) for t in terms]]
        batch = pa.RecordBatch.from_arrays([pa.nulls(len(terms), k) if c is None else pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)
        held.clear()
        beside.clear()
        return batch

    for batch in batches:
        rows = []
        for doc_id, rk, text in zip(batch.column("doc_id").to_pylist(), batch.column("rk").to_pylist(), batch.column("text").to_pylist(), strict=True):
            text = text or ""
            spans = base_spans(text)
            more = secrets(text, spans)
            n = Counter(k for k, _, _ in spans)
            entities, near, bare = [], [], text
            if spans or more:
                bare = blanked(text, spans + more)
                entities = sorted({k for k, _, _ in spans + more} | {f"{k} {text[a:b].lower()}" for k, a, b in spans + more})
                near = [{"entity": e, "term": t} for e, t in sorted(contexts(text, bare, spans + more))]
            terms = set(_words(bare.lower()))
            held.update(terms)
            if entities:
                flags = [int(e in entities) for e in ENTITIES]
                for t in terms:
                    beside[t] = [x + y for x, y in zip(beside.get(t, [0] * len(flags)), flags, strict=True)]
            rows.append((doc_id, rk, *(n[k] for k in KINDS), joined(spans), joined(more), entities, near))
        yield pa.RecordBatch.from_arrays([*(pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds[:10], strict=True)), *(pa.nulls(len(rows), k) for k in kinds[10:])], names)
        if len(held) > HELD_TERMS:
            yield counted()
    if held:
        yield counted()


def disclosing(scanned: DataFrame, disclosure: float = DISCLOSURE, support: int = SUPPORT) -> DataFrame:
    """``(term, share)``: terms that give away at least ``disclosure`` of an entity's information, and the greatest share."""
    found = scanned.where("term is null")
    total = float(found.count())
    terms = scanned.where("term is not null").groupBy("term").agg(F.sum("n_term").alias("n_term"), *[F.sum(F.col("n_with")[i]).alias(f"w{i}") for i in range(len(ENTITIES))])
    terms = cut(terms.where(f"n_term >= {support}"))
    texts = found.where(F.size("entities") > 0).groupBy("rk").agg(F.count("*").alias("rows"), F.first("entities").alias("entities"), F.first("near").alias("near"))
    texts = cut(texts)
    n_entity = texts.select(F.explode("entities").alias("entity"), "rows").groupBy("entity").agg(F.sum("rows").alias("n_entity"))
    by_kind = terms.select("term", "n_term", F.explode(F.array(*[F.struct(F.lit(e).alias("entity"), F.col(f"w{i}").alias("n_both")) for i, e in enumerate(ENTITIES)])).alias("x")).select("x.entity", "term", "n_term", "x.n_both").where(f"n_both >= {support}")
    by_value = texts.select(F.explode("near").alias("x"), "rows").groupBy(F.col("x.entity").alias("entity"), F.col("x.term").alias("term")).agg(F.count("*").alias("texts"), F.sum("rows").alias("n_both")).where(f"texts >= {support}").drop("texts").join(terms.select("term", "n_term"), "term")
    pairs = by_kind.unionByName(by_value.select(*by_kind.columns)).join(n_entity, "entity")
    information = F.log2(total / F.col("n_entity"))
    mutual = F.log2(F.col("n_both") * total / (F.col("n_term") * F.col("n_entity")))
    # an entity that stands in every document tells nothing and can't be given away
    strong = pairs.where((information > 0) & (mutual >= disclosure * information))
    return cut(strong.groupBy("term").agg(F.max(F.least(mutual / information, F.lit(1.0))).alias("share")))


def _placed(docs: DataFrame, told: DataFrame) -> DataFrame:
    """``(doc_id, rk, start, end, term)``: every occurrence of terms of ``told`` outside protected spans, terms in blocks of ``SHIPPED_TERMS``."""
    spark = docs.sparkSession
    blocks = max(1, -(-told.count() // SHIPPED_TERMS))
    dealt = told.select("term", F.pmod(F.xxhash64("term"), F.lit(blocks)).alias("block"))
    out = None
    for k in range(blocks):
        shipped = spark.sparkContext.broadcast(frozenset(r.term for r in dealt.where(F.col("block") == k).collect()))

        def run(batches, shipped=shipped):
            known = shipped.value
            for batch in batches:
                rows = []
                for doc_id, rk, text in zip(batch.column("doc_id").to_pylist(), batch.column("rk").to_pylist(), batch.column("text").to_pylist(), strict=True):
                    low = (text or "").lower()
                    if known.isdisjoint(_words(low)):
                        continue
                    spans = base_spans(text)
                    taken = [(a, b) for _, a, b in spans + secrets(text, spans)]
                    rows += [(doc_id, rk, m.start(), m.end(), m[0].lower()) for m in _word(text) if m[0].lower() in known and not any(m.start() < b and a < m.end() for a, b in taken)]
                if rows:
                    kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.string())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["doc_id", "rk", "start", "end", "term"])

        one = docs.mapInArrow(run, "doc_id long, rk long, start int, end int, term string")
        out = one if out is None else out.unionByName(one)
    return out


def find_personal_data(docs: DataFrame, disclosure: float = DISCLOSURE, support: int = SUPPORT) -> DataFrame:
    """One row per row of ``docs``: doc_id, rk, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_term.

    ``spans`` lists all spans as kind:start:end (code points, end exclusive): base kinds first, then secrets, then
    every occurrence of a disclosing term outside them, each by start.  A null text counts as empty; repeated rows
    are judged alike, rows of one id with other texts each by its own; an empty table gives an empty result; other
    columns are ignored.
    """
    small_batches(docs.sparkSession)
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("rk", F.xxhash64("text"))
    scanned = cut(keyed.mapInArrow(_scan, _SCANNED))
    told = disclosing(scanned, disclosure, support).select("term")
    placed = cut(_placed(keyed, told))
    # copies of one text are one piece of evidence
    evidence = placed.groupBy("term", "rk").agg(F.count("*").alias("rows")).groupBy("term").agg(F.count("*").alias("texts"), F.sum("rows").alias("__n")).where(F.col("texts") >= support).drop("texts")
    places = keyed_join(placed, evidence, "term", placed.count()).groupBy(F.col("doc_id").alias("id"), F.col("rk").alias("key")).agg(F.array_sort(F.collect_set(F.struct("start", "end"))).alias("places"))
    text = F.array_join(F.transform("places", lambda p: F.concat(F.lit("term:"), p["start"].cast("string"), F.lit(":"), p["end"].cast("string"))), ",")
    out = scanned.where("term is null").drop("entities", "near", "term", "n_term", "n_with")
    out = out.join(places.select("id", "key", F.size("places").cast("long").alias("n_term"), text.alias("terms")), F.col("doc_id").eqNullSafe(F.col("id")) & (F.col("rk") == F.col("key")), "left")
    spans = F.array_join(F.filter(F.array("base", "hidden", F.coalesce("terms", F.lit(""))), lambda x: x != ""), ",")
    return out.select("doc_id", "rk", "n_email", "n_ip", "n_card", "n_phone", F.sha2(F.col("base").cast("binary"), 256).alias("base_sha256"), spans.alias("spans"), F.coalesce("n_term", F.lit(0).cast("long")).alias("n_term"))


def masked(text: str | None, spans: str) -> str | None:
    """``text`` with every span replaced by its kind in brackets (overlapping spans by the first's)."""
    if not text or not spans:
        return text
    parts, at = [], 0
    for start, end, kind in sorted((int(a), int(b), k) for k, a, b in (s.split(":") for s in spans.split(","))):
        if start >= at:
            parts += [text[at:start], f"[{kind.upper()}]"]
        at = max(at, end)
    return "".join([*parts, text[at:]])


def sanitise(docs: DataFrame, disclosure: float = DISCLOSURE, support: int = SUPPORT) -> DataFrame:
    """``docs`` with ``text`` masked; all rows and columns stay."""
    found = find_personal_data(docs, disclosure, support).select(F.col("doc_id").alias("__id"), F.col("rk").alias("__rk"), F.col("spans").alias("__spans")).where("__spans <> ''").dropDuplicates(["__id", "__rk"])

    names = docs.columns

    def run(batches):
        for batch in batches:
            texts = [masked(t, s or "") for t, s in zip(batch.column("text").to_pylist(), batch.column("__spans").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(texts, pa.string()) if n == "text" else batch.column(n) for n in names], names)

    on = F.col("doc_id").eqNullSafe(F.col("__id")) & (F.xxhash64(docs["text"].cast("string")) == F.col("__rk"))
    return docs.join(found, on, "left").drop("__id", "__rk").mapInArrow(run, docs.schema)
