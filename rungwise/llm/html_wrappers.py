"""Main text of web pages through wrappers inferred from pages of the same host.

A wrapper is a union-free expression over a page's structure: a tree of nodes in order, each plain, optional (?)
or repeated (+), with text slots.  Pages of a host are aligned one after the other: equal nodes meet, a node that
only one side has becomes optional, neighbouring equal nodes fold into a repeated group, and texts that differ
turn a slot from a constant into a variable.  Alignment is a fold of partial wrappers (per input batch, then per
host and part, then per host), so a host with a third of all pages is never gathered in one task.

The host's wrapper decides what is content.  The region is found by following, from the root, the unrepeated node
that holds most of the host's variable text; every page's text is what stands at that region, without slots that
are constant on many different pages.  Tags and names are a prior: menus, headers, footers, sidebars, notices,
adverts, forms and comments carry no text, ``article`` and ``main`` narrow the region if they hold most of it, and
their words need four times the evidence to count as constant.  A host with few different pages has no evidence;
its pages are judged by their own structure.
"""

from __future__ import annotations

import html as entities
import json
import re
from functools import reduce

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, keyed_join, small_batches

#: Different pages that a slot must have been seen on, always the same, before it counts as boilerplate.
SURE_PAGES = 5
#: The same inside ``article`` and ``main``.
SURE_INSIDE = 4 * SURE_PAGES
#: Share of the variable text that a node must hold to be followed.
MOST = 0.7
#: Deeper elements are laid flat into their ancestor at this depth (their texts and blocks stay).
MAX_DEPTH = 200
#: Parts that a host's partial wrappers are folded in.
PARTS = 64

# fixed values of HTML
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_RAW = frozenset("script style noscript template iframe svg math object textarea select button title".split())
_BLOCK = frozenset("address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
_CLOSES_P = _BLOCK - {"br", "body", "html", "option", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "legend"}
_SAME_CLOSES = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
_AWAY = frozenset("nav aside footer form head dialog menu".split())
_AWAY_ROLES = frozenset("navigation banner contentinfo search complementary alert dialog".split())
_AWAY_NAMES = frozenset("ad ads advert adverts advertisement sponsored sponsor promo promotion banner nav navbar navigation menu sidebar footer header masthead breadcrumb breadcrumbs cookie cookies consent notice notices alert popup modal comment comments respond disqus reactions share sharing social related recommended newsletter subscribe subscription widget toolbar pagination pager copyright legal disclaimer login signup skip".split())

#: Elements without a class that are told apart by what they begin with.
_PLAIN = frozenset("div section span td".split())
#: Text blocks; a region never lies inside one.
_TEXTS = frozenset("p li blockquote pre h1 h2 h3 h4 h5 h6 dd dt td th figure table ul ol dl".split())

_tag = re.compile(r"<(/?)([A-Za-z][A-Za-z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*+)>").match
_attribute = re.compile(r"([A-Za-z-]+)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s\"'>]+)").findall
_name_parts = re.compile(r"[A-Za-z]+").findall


class Node:
    __slots__ = ("key", "name", "away", "children")

    def __init__(self, key: str, name: str, away: bool):
        self.key, self.name, self.away, self.children = key, name, away, []


def _is_away(name: str, attributes: dict[str, str], in_article: bool) -> bool:
    if name in _AWAY or (name == "header" and not in_article):
        return True
    if attributes.get("role") in _AWAY_ROLES or "hidden" in attributes or attributes.get("aria-hidden") == "true":
        return True
    if name in ("html", "body", "article", "main", "h1", "p"):
        return False
    return any(p.lower() in _AWAY_NAMES for a in ("class", "id") for v in attributes.get(a, "").split() for p in _name_parts(v))


def parse(source: str) -> Node:
    """A lenient tree of elements and strings; broken nesting is closed the way browsers do, roughly."""
    root = Node("", "", False)
    stack, at, n, articles = [root], 0, len(source), 0
    text: list[str] = []

    def flush():
        if text:
            stack[-1].children.append("".join(text))
            text.clear()

    def close(to: int):
        nonlocal articles
        flush()
        articles -= sum(x.name in ("article", "main") for x in stack[to:])
        if not stack[to].key and stack[to].name in _BLOCK:  # laid flat: the block ends here
            stack[to].children.append(Node("br", "br", False))
        del stack[to:]

    def opened(names, until) -> int | None:
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].name in names:
                return i
            if stack[i].name in until:
                return None
        return None

    while at < n:
        lt = source.find("<", at)
        if lt < 0:
            text.append(source[at:])
            break
        if lt > at:
            text.append(source[at:lt])
        if source.startswith("<!--", lt):
            end = source.find("-->", lt + 4)
            at = n if end < 0 else end + 3
            continue
        if source.startswith(("<!", "<?"), lt):
            end = source.find(">", lt)
            at = n if end < 0 else end + 1
            continue
        m = _tag(source, lt)
        if not m:
            text.append("<")
            at = lt + 1
            continue
        at = m.end()
        closing, name, rest = m[1], m[2].lower(), m[3]
        if closing:
            if name == "br":
                flush()
                stack[-1].children.append(Node("br", "br", False))
            elif (i := opened({name}, ())) is not None:
                # an inline end tag doesn't reach over a block
                if name in _BLOCK or not any(x.name in _BLOCK for x in stack[i + 1 :]):
                    close(i)
            continue
        if name in _CLOSES_P and (i := opened({"p"}, {"table", "button", "article", "div", "li", "td"})) is not None:
            close(i)
        if name in _SAME_CLOSES and (i := opened(*_SAME_CLOSES[name])) is not None:
            close(i)
        attributes = {k.lower(): v.strip("\"'") for k, v in _attribute(rest)} if rest.strip() else {}
        if re.search(r"(?:^|\s)hidden(?=\s|$)", rest):
            attributes["hidden"] = ""
        raw = name in _RAW
        node = Node(name + "".join(f".{c}" for c in sorted(re.sub(r"\d+", "", attributes.get("class", "")).split())), name, raw or _is_away(name, attributes, articles > 0))
        flush()
        stack[-1].children.append(node)
        if len(stack) > MAX_DEPTH and not node.away and name not in _VOID:
            inner = Node("", name, False)
            inner.children = stack[-1].children
            if not raw and not rest.endswith("/"):
                stack.append(inner)
                articles += name in ("article", "main")
            continue
        if raw and not rest.endswith("/"):
            end = re.compile(f"</{name}\\b[^>]*>", re.IGNORECASE).search(source, at)
            at = n if end is None else end.end()
        elif name not in _VOID and not rest.endswith("/"):
            stack.append(node)
            articles += name in ("article", "main")
    flush()
    return root


# A wrapper node: {"k": key, "m": "1" | "?" | "+" | "*", "t": slot, "v": characters, "p": pages, "c": [nodes], "a": away}.
# A slot is None (never text), an integer (the hash of one constant text) or True (variable); "v" counts characters of
# text outside links, "p" holds the smallest SURE_INSIDE hashes of the different pages that showed text there.


def _key(node: Node) -> str:
    if node.key not in _PLAIN:
        return node.key
    return f"{node.key}({next((c.name for c in node.children if isinstance(c, Node) and c.name not in _RAW), '')})"


def _said(node: Node) -> str:
    return " ".join(" ".join(c for c in node.children if isinstance(c, str)).split())


def page_hash(page: Node) -> int:
    """Hash of what the page says outside menus, adverts and the like: pages that differ there only are one page."""
    said = []
    for node, _ in _walk(page):
        said += [c for c in node.children if isinstance(c, str)]
    return xxhash.xxh64_intdigest(" ".join(" ".join(said).split()).encode("utf-8", "surrogatepass"))


def wrap(node: Node, page: int | None = None, linked: bool = False) -> dict:
    """The wrapper of a single page: children with the same key fold into repeated groups, so a level has each key once."""
    top = page is None
    page = page_hash(node) if top else page
    said, linked = _said(node), linked or node.name == "a"
    place: dict[str, int] = {}
    kids: list[dict] = []
    for child in node.children:
        if isinstance(child, str) or child.name in _RAW:
            continue
        kid = wrap(child, page, linked)
        i = place.setdefault(kid["k"], len(kids))
        if i == len(kids):
            kids.append(kid)
        else:
            kids[i] = align(kids[i], kid) | {"m": "+"}
    slot = xxhash.xxh64_intdigest(said.encode("utf-8", "surrogatepass")) >> 1 if said else None
    return {"k": _key(node), "m": "1", "t": slot, "v": 0 if linked else len(said), "p": [page] if said or top else [], "c": kids, "a": int(node.away)}


_OPTIONAL = {"1": "?", "+": "*", "?": "?", "*": "*"}


def _maybe(kid: dict) -> dict:
    return kid | {"m": _OPTIONAL[kid["m"]]}


def align(a: dict, b: dict) -> dict:
    """The expression that covers both: mismatches turn into optional nodes, repeated nodes and text slots."""
    slot = a["t"] if b["t"] is None or (a["t"] is not True and a["t"] == b["t"]) else b["t"] if a["t"] is None else True
    left, right = {kid["k"] for kid in a["c"]}, {kid["k"]: kid for kid in b["c"]}
    out, pending = [], iter(b["c"])
    passed: set[str] = set()

    def extras(until: str | None):
        """What only b has, before b's node ``until``."""
        for kid in pending:
            passed.add(kid["k"])
            if kid["k"] == until:
                return
            if kid["k"] not in left:
                out.append(_maybe(kid))

    for kid in a["c"]:
        other = right.get(kid["k"])
        if other is None:
            out.append(_maybe(kid))
            continue
        if kid["k"] not in passed:
            extras(kid["k"])
        marks = kid["m"] + other["m"]
        many, maybe = "+" in marks or "*" in marks, "?" in marks or "*" in marks
        out.append(align(kid, other) | {"m": "*" if many and maybe else "+" if many else "?" if maybe else "1"})
    extras(None)
    return {"k": a["k"], "m": a["m"], "t": slot, "v": a["v"] + b["v"], "p": sorted({*a["p"], *b["p"]})[:SURE_INSIDE], "c": out, "a": a["a"] & b["a"]}


def expression(w: dict) -> str:
    """The wrapper as a union-free regular expression, for reading."""
    inner = ("#TEXT" if w["t"] is True else f"#{w['t']:x}" if w["t"] is not None else "") + "".join(map(expression, w["c"]))
    return f"<{w['k']}>{inner}</>" + ("" if w["m"] == "1" else w["m"])


def merge_wrappers(partial: list[dict]) -> dict:
    """Fold of ``{"n": pages, "w": wrapper}`` parts."""
    return {"n": sum(p["n"] for p in partial), "w": reduce(align, (p["w"] for p in partial))}


def _name(key: str) -> str:
    return re.split(r"[.(]", key, maxsplit=1)[0]


def _constant(slot: dict, inside: bool) -> bool:
    """Whether a slot is template: always the same text, on enough different pages."""
    return slot["t"] is not None and slot["t"] is not True and len(slot["p"]) >= (SURE_INSIDE if inside else SURE_PAGES)


def _masses(slot: dict, out: dict[int, int], inside: bool = False) -> int:
    """Characters of variable text at and below every node of a wrapper, by the node's identity."""
    inside = inside or _name(slot["k"]) in ("article", "main")
    own = 0 if slot["a"] else (0 if _constant(slot, inside) else slot["v"]) + sum([_masses(c, out, inside) for c in slot["c"]])
    out[id(slot)] = own
    return own


def region(wrapper: dict) -> tuple[tuple[str, ...], bool]:
    """Keys that lead to the node that holds the host's content, and whether it is narrowed to articles below it."""
    masses: dict[int, int] = {}
    _masses(wrapper, masses)
    node, path = wrapper, []
    while True:
        kids = [c for c in node["c"] if not c["a"]]
        best = max(kids, key=lambda c: masses[id(c)], default=None)
        if best is None or best["m"] in "+*" or _name(best["k"]) not in _BLOCK or _name(best["k"]) in _TEXTS or masses[id(best)] < MOST * masses[id(node)] or not masses[id(best)]:
            break
        node, path = best, [*path, best["k"]]
    held, stack = 0, list(node["c"])
    while stack:
        at = stack.pop()
        if _name(at["k"]) in ("article", "main") and not at["a"]:
            held += masses[id(at)]
        elif not at["a"]:
            stack += at["c"]
    return tuple(path), 2 * held > masses[id(node)] > 0


def blocks(page: Node, wrapper: dict | None) -> list[str]:
    """Text blocks of the content, in page order; ``wrapper`` is the host's, or None if it has too little evidence."""
    if wrapper is not None and len(wrapper["w"]["p"]) >= SURE_PAGES:
        found = _at_region(page, wrapper["w"], wrapper.setdefault("region", region(wrapper["w"])))
        if found:
            return found
    own = wrap(page)
    return _at_region(page, own, region(own)) or []


def _at_region(page: Node, slots: dict, where: tuple[tuple[str, ...], bool]) -> list[str] | None:
    """What the page says at the region; None if the page hasn't got it or says nothing there."""
    path, narrowed = where
    nodes, slot = [page], slots
    for key in path:
        nodes = [c for node in nodes for c in node.children if isinstance(c, Node) and not c.away and _key(c) == key]
        slot = next((c for c in slot["c"] if c["k"] == key), None)
        if not nodes or slot is None:
            return None
    inside = any(_name(key) in ("article", "main") for key in path)
    out: list[str] = []
    for node in nodes:
        picked = _articles(node, slot) if narrowed else []
        for part, its in picked or [(node, slot)]:
            _say(part, its, out, inside or bool(picked))
    return out or None


def _articles(node: Node, slot: dict | None) -> list[tuple[Node, dict | None]]:
    """The outermost article and main nodes below ``node``, in page order, with their slots."""
    out, stack = [], [(node, slot)]
    while stack:
        now, its = stack.pop()
        if now is not node and now.name in ("article", "main"):
            out.append((now, its))
            continue
        kids = {c["k"]: c for c in its["c"]} if its else {}
        stack += [(c, kids.get(_key(c))) for c in reversed(now.children) if isinstance(c, Node) and not c.away]
    return out


def _walk(node: Node, path=()):
    """(node, keys from the root) of every element that isn't away."""
    stack = [(node, path)]
    while stack:
        now, at = stack.pop()
        yield now, at
        stack += [(c, (*at, c.key)) for c in reversed(now.children) if isinstance(c, Node) and not c.away]


def _say(node: Node, slots: dict | None, out: list[str], inside: bool) -> None:
    """Append the blocks of ``node``; block slots that are constant and not repeated are left out."""
    line: list[str] = []

    def end():
        said = " ".join("".join(line).split())
        line.clear()
        if said:
            out.append(said)

    def visit(at: Node, slot: dict | None, deep: bool):
        kids = {c["k"]: c for c in slot["c"]} if slot else {}
        deep = deep or at.name in ("article", "main")
        silent = slot is not None and at.name in _BLOCK and slot["m"] in "1?" and _constant(slot, deep)
        for child in at.children:
            if isinstance(child, str):
                if not silent:
                    line.append(entities.unescape(child))
            elif not child.away:
                if child.name in _BLOCK:
                    end()
                    visit(child, kids.get(_key(child)), deep)
                    end()
                else:
                    visit(child, kids.get(_key(child)), deep)

    visit(node, slots, inside)
    end()


def main_text(source: str | None, wrapper: dict | None = None) -> str:
    return "\n".join(blocks(parse(source), wrapper)) if source else ""


def _host(url):
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1)), F.lit(""))


def infer_wrappers(pages: DataFrame) -> DataFrame:
    """``(host, n_pages, wrapper)``: one wrapper, as JSON, per host; equal pages of a batch count once."""
    small_batches(pages.sparkSession)

    def partial(batches):
        for number, batch in enumerate(batches):
            found: dict[str, tuple[int, dict]] = {}
            seen = set()
            for host, source in zip(batch.column("host").to_pylist(), batch.column("html").to_pylist(), strict=True):
                if not source or (host, source) in seen:
                    continue
                seen.add((host, source))
                w = wrap(parse(source))
                n, old = found.get(host, (0, None))
                found[host] = (n + 1, w if old is None else align(old, w))
            yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.string()), pa.array([n for n, _ in found.values()], pa.int64()), pa.array([json.dumps(w) for _, w in found.values()], pa.string())], ["host", "n", "wrapper"])

    def fold(table: pa.Table) -> pa.Table:
        done = merge_wrappers([{"n": n, "w": json.loads(w)} for n, w in sorted(zip(table.column("n").to_pylist(), table.column("wrapper").to_pylist(), strict=True))])
        return pa.table({"host": pa.array([table.column("host")[0].as_py()], pa.string()), "n": pa.array([done["n"]], pa.int64()), "wrapper": pa.array([json.dumps(done["w"])], pa.string())})

    parts = pages.select(_host(F.col("url").cast("string")).alias("host"), F.col("html").cast("string").alias("html")).mapInArrow(partial, "host string, n long, wrapper string")
    equal = parts.groupBy("host", "wrapper").agg(F.sum("n").alias("n")).withColumn("part", F.pmod(F.xxhash64("wrapper"), F.lit(PARTS)))
    once = equal.select("host", "part", "n", "wrapper").groupBy("host", "part").applyInArrow(lambda t: fold(t.drop_columns(["part"])), "host string, n long, wrapper string")
    return once.groupBy("host").applyInArrow(fold, "host string, n long, wrapper string").select("host", F.col("n").alias("n_pages"), "wrapper")


#: Bytes of wrappers that are shipped to every executor at most; beyond it they are joined.
SHIPPED_BYTES = 8_000_000


def extract(pages: DataFrame) -> DataFrame:
    """One row per row of ``pages``: page_id, url, text, n_chars.

    A null or empty page has the empty text; a page without a url belongs to the host without a name; repeated
    rows give equal texts; broken markup is read leniently; an empty table gives an empty result; other columns
    are ignored.
    """
    spark = pages.sparkSession
    small_batches(spark)
    wrappers = cut(infer_wrappers(pages))
    size = wrappers.agg(F.sum(F.octet_length("wrapper"))).first()[0] or 0
    plain = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"), _host(F.col("url").cast("string")).alias("host"))

    def texts(batch, of):
        said = [main_text(h, w) for h, w in zip(batch.column("html").to_pylist(), of, strict=True)]
        return pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(said, pa.string()), pa.array([len(s) for s in said], pa.int64())], ["page_id", "url", "text", "n_chars"])

    schema = "page_id long, url string, text string, n_chars long"
    if size <= SHIPPED_BYTES:
        shipped = spark.sparkContext.broadcast({r.host: {"n": r.n_pages, "w": json.loads(r.wrapper)} for r in wrappers.collect()})

        def run(batches):
            known = shipped.value
            for batch in batches:
                yield texts(batch, [known.get(h) for h in batch.column("host").to_pylist()])

        return plain.mapInArrow(run, schema)

    def run_joined(batches):
        known: tuple = (None, None)
        for batch in batches:
            of = []
            for n, w in zip(batch.column("n_pages").to_pylist(), batch.column("wrapper").to_pylist(), strict=True):
                if known[0] != w:
                    known = (w, {"n": n, "w": json.loads(w)})
                of.append(known[1])
            yield texts(batch, of)

    # a hot host's wrapper is broadcast, so that its pages stay where they are
    said = F.col("html").isNotNull() & (F.col("html") != "")
    met = keyed_join(plain.where(said), wrappers.withColumn("__n", F.col("n_pages")), "host", plain.count())
    none = plain.where(~said | said.isNull()).select("page_id", "url", F.lit("").alias("text"), F.lit(0).cast("long").alias("n_chars"))
    return met.mapInArrow(run_joined, schema).unionByName(none)
