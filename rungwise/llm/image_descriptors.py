"""Copies of images found by local descriptors.

Every image is looked at in several scales of its own pixels (small ones enlarged, large ones reduced by powers of
two, so a crop keeps its scale); Harris corners get an orientation from their intensity centroid and a descriptor of
binary comparisons turned by it.  Descriptors meet in Hamming tables (equal 32-bit bands), complete distances are
verified, and a pair of images is linked if enough matches agree on one rotation, scale and shift.

All pairs of images are judged by all matches: two descriptors match if they meet in a table and are ``MAX_DISTANCE``
bits apart at most.  Band values that many images share are no keys to deal rows by, so images are dealt in blocks, every
pair of blocks is one task with tables of its own, and no match leaves it: rows grow with images times blocks (the root of
their number), not with pairs.  Meetings are counted by pair of images first, then by pair, rotation and scale, and
descriptors are compared only where enough meet for a link.  Counting itself still grows with the pairs of descriptors that
share a band value.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, scratch, small_batches
from .components import components

#: Images with shorter sides are enlarged, with longer ones reduced, by powers of two.
MIN_SIDE, MAX_SIDE = 24, 128
SCALES = (1.0, 0.5)
RADIUS = 5
MIN_RESPONSE = 0.01
MAX_DISTANCE = 18
MIN_MATCHES = 4
#: Pairs of descriptors with an equal band that one task holds at a time (one image's at least).
MEETINGS = 120_000
#: Pixels of one cell of the vote on shifts.
CELL = 8

_rng = np.random.default_rng(20)
_disc = np.array([(y, x) for y in range(-4, 5) for x in range(-4, 5) if y * y + x * x <= 16])
_tests = np.clip(_rng.normal(0, RADIUS / 2, (128, 4)), -RADIUS, RADIUS)

#: Rotation and scale cell by differences of scale and angle, for two overlapping grids of rotations.
_ALIKE = [np.array([((d + t) % 24 // 2) * 3 + s for s in range(3) for d in range(-24, 24)]) for t in range(2)]


def _resized(images: np.ndarray, side: int) -> np.ndarray:
    """Bilinear, for a stack of square images."""
    n = images.shape[1]
    at = np.clip((np.arange(side) + 0.5) * n / side - 0.5, 0, n - 1)
    lo = np.minimum(at.astype(int), max(n - 2, 0))
    hi, f = np.minimum(lo + 1, n - 1), (at - lo).astype(np.float32)
    rows = images[:, lo] * (1 - f)[None, :, None] + images[:, hi] * f[None, :, None]
    return rows[:, :, lo] * (1 - f)[None, None] + rows[:, :, hi] * f[None, None]


def _box(x: np.ndarray) -> np.ndarray:
    p = np.pad(x, ((0, 0), (1, 1), (1, 1)), mode="edge")
    return sum(p[:, i : i + x.shape[1], j : j + x.shape[2]] for i in range(3) for j in range(3)) / 9


def corners(images: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(image, y, x) of local maxima of the Harris response that stand out in their image."""
    gy, gx = np.gradient(images, axis=(1, 2))
    a, b, c = _box(gx * gx), _box(gy * gy), _box(gx * gy)
    r = a * b - c * c - 0.05 * (a + b) ** 2
    p = np.pad(r, ((0, 0), (1, 1), (1, 1)), constant_values=-np.inf)
    near = np.max([p[:, i : i + r.shape[1], j : j + r.shape[2]] for i in range(3) for j in range(3)], axis=0)
    top = r.max(axis=(1, 2), keepdims=True)
    good = (r == near) & (r > MIN_RESPONSE * top) & (top > 1e-12)
    good[:, :2] = good[:, -2:] = good[:, :, :2] = good[:, :, -2:] = False
    return np.nonzero(good)


def describe(images: np.ndarray) -> dict[str, np.ndarray]:
    """Descriptors of a stack of square images: image, y, x (in full-size pixels), scale, angle (15-degree steps), bits."""
    parts = []
    for level, scale in enumerate(SCALES):
        stack = _box(_resized(images.astype(np.float32), round(images.shape[1] * scale)))
        side = stack.shape[1]
        i, y, x = corners(stack)
        if not len(i):
            continue
        inside = lambda v: np.clip(v, 0, side - 1)
        patch = stack[i[:, None], inside(y[:, None] + _disc[:, 0]), inside(x[:, None] + _disc[:, 1])]
        patch = patch - patch.mean(axis=1, keepdims=True)
        step = np.round(np.arctan2((patch * _disc[:, 0]).sum(1), (patch * _disc[:, 1]).sum(1)) / (np.pi / 12)).astype(int) % 24
        cos, sin = np.cos(step * np.pi / 12)[:, None], np.sin(step * np.pi / 12)[:, None]

        def seen(dy, dx):
            yy = inside(np.round(y[:, None] + sin * dx + cos * dy).astype(int))
            xx = inside(np.round(x[:, None] + cos * dx - sin * dy).astype(int))
            return stack[i[:, None], yy, xx]

        bits = seen(_tests[:, 0], _tests[:, 1]) < seen(_tests[:, 2], _tests[:, 3])
        parts.append((i, np.round(y / scale), np.round(x / scale), np.full(len(i), level), step, np.packbits(bits, axis=1).view(np.int32)))
    if not parts:
        return {k: np.empty(0, int) for k in ("image", "y", "x", "scale", "angle")} | {"bits": np.empty((0, 4), np.int32)}
    return dict(zip(("image", "y", "x", "scale", "angle", "bits"), (np.concatenate(p) for p in zip(*parts, strict=True)), strict=True))


def _side(side: int) -> int:
    while side < MIN_SIDE:
        side *= 2
    while side > MAX_SIDE:
        side = -(-side // 2)
    return side


def _squares(vectors: list) -> dict[int, tuple[list[int], np.ndarray]]:
    """Rows that are square images, by the side they are looked at in; values from 0 to 1."""
    found: dict[int, tuple[list[int], list]] = {}
    for i, v in enumerate(vectors):
        n = len(v) if v is not None else 0
        side = int(n**0.5)
        if side >= 4 and side * side == n and all(x is not None and np.isfinite(x) for x in v):
            image = np.array(v, np.float32).reshape(1, side, side)
            low, high = image.min(), image.max()
            rows, stack = found.setdefault(_side(side), ([], []))
            rows.append(i)
            stack.append(_resized((image - low) / max(high - low, 1e-9), _side(side))[0])
    return {side: (rows, np.stack(stack)) for side, (rows, stack) in found.items()}


_SCHEMA = "img long, y int, x int, scale int, angle int, b0 int, b1 int, b2 int, b3 int"


def descriptors(images: DataFrame) -> DataFrame:
    """``images(img, pixels array<float>)`` -> one row per descriptor; what isn't a square image has none."""
    small_batches(images.sparkSession)

    def run(batches):
        for batch in batches:
            ids = np.array(batch.column("img").to_pylist(), np.int64)
            for rows, stack in _squares(batch.column("pixels").to_pylist()).values():
                d = describe(stack)
                yield pa.RecordBatch.from_arrays([pa.array(ids[np.array(rows)][d["image"]]), *(pa.array(d[k].astype(np.int32)) for k in ("y", "x", "scale", "angle")), *(pa.array(np.ascontiguousarray(d["bits"][:, k])) for k in range(4))], [c.split()[0] for c in _SCHEMA.split(", ")])

    return images.select(F.col("img").cast("long").alias("img"), F.col("pixels").cast("array<float>").alias("pixels")).mapInArrow(run, _SCHEMA)


def _tables(table: pa.Table, block: int) -> dict[str, np.ndarray]:
    """Descriptors of one block's images, sorted by image: img, place, bits (n x 4)."""
    part = table.filter(pc.equal(table.column("blk"), block)).sort_by("img").combine_chunks()
    lists = [part.column(c).combine_chunks() for c in ("place", "b0", "b1", "b2", "b3")]
    sizes = np.asarray(pc.list_value_length(lists[0]).fill_null(0), np.int64) if len(part) else np.empty(0, np.int64)
    flat = [np.asarray(x.flatten(), np.int32) if len(part) else np.empty(0, np.int32) for x in lists]
    return {"img": np.repeat(np.asarray(part.column("img"), np.int64), sizes), "place": flat[0], "bits": np.stack(flat[1:], axis=1)}


def _agreeing(pair: np.ndarray, apart: np.ndarray) -> np.ndarray:
    """Which meetings are in pairs of images where at least ``MIN_MATCHES`` meetings agree on rotation and scale.

    ``pair`` numbers the pairs from 0, ``apart`` is the difference of ``_posed``.  Either image may come first: the two grids
    of rotations then change their parts.
    """
    enough = np.zeros(len(pair), bool)
    for cell in _ALIKE:
        at = pair * 36 + cell[apart + 72]
        enough |= (np.bincount(at) >= MIN_MATCHES)[at]
    return enough


def _posed(place: np.ndarray) -> np.ndarray:
    """Scale and angle as one number, so that differences tell both."""
    scale, angle = _unpacked(place)[2:]
    return scale * 48 + angle


def _votes(one: dict, other: dict, p: np.ndarray, q: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Links ``(a, b, matches)`` among close descriptors p of ``one`` and q of ``other``; each p's image is the greater one.

    Rotations and shifts are voted on in two overlapping grids each, so that no placement lies on a border of all.
    """
    order = np.lexsort((other["img"][q], one["img"][p]))
    p, q = p[order], q[order]
    a, b = one["img"][p], other["img"][q]
    pair = np.cumsum(np.r_[False, (a[1:] != a[:-1]) | (b[1:] != b[:-1])][: len(a)])
    near = _agreeing(pair, _posed(one["place"][p]) - _posed(other["place"][q]))
    p, q, pair = p[near], q[near], pair[near]
    if not len(p):
        return (np.empty(0, np.int64),) * 3
    (py, px, ps, pt), (qy, qx, qs, qt) = _unpacked(one["place"][p]), _unpacked(other["place"][q])
    turn = (pt - qt) % 24
    new = np.r_[True, pair[1:] != pair[:-1]]
    pair = np.cumsum(new) - 1
    a, b, best = one["img"][p[new]], other["img"][q[new]], np.zeros(pair[-1] + 1, np.int64)
    rad, scale = turn * (np.pi / 12), np.array(SCALES)
    ratio = scale[qs] / scale[ps]
    dx = px - ratio * (np.cos(rad) * qx - np.sin(rad) * qy)
    dy = py - ratio * (np.sin(rad) * qx + np.cos(rad) * qy)
    corner = (py << 9) | (px << 1) | ps
    for grid in range(8):
        t, x, y = ((grid >> bit) & 1 for bit in range(3))
        cell = (pair * 12 + (turn + t) % 24 // 2) * 3 + ps - qs + 1
        for d, half in ((dx, x), (dy, y)):
            cell = (cell << 8) + np.floor(d / CELL + half / 2).astype(np.int64) + 128
        # cells that share a slot are counted together, so nothing that is enough is left out
        slot = cell % (4 * len(cell) + 1)
        crowded = np.flatnonzero((np.bincount(slot) >= MIN_MATCHES)[slot])
        placed = np.unique((cell[crowded] << 17) | corner[crowded]) >> 17
        cells, n = np.unique(placed, return_counts=True)
        np.maximum.at(best, (cells >> 16) // 36, n)
    good = best >= MIN_MATCHES
    return a[good], b[good], best[good]


def _unpacked(place: np.ndarray) -> list[np.ndarray]:
    """y, x, scale and angle."""
    wide = place.astype(np.int64)
    return [wide >> 14, wide >> 6 & 255, wide >> 5 & 1, wide & 31]


def _numbered(img: np.ndarray) -> np.ndarray:
    """Images, which come sorted, numbered from 0."""
    return np.cumsum(np.r_[False, img[1:] != img[:-1]][: len(img)])


def _meetings(one: dict, other: dict, same: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``other``'s descriptors by band in the order of its values; by band and descriptor of ``one`` the first place and the number of its equals.

    A block meets itself once: each descriptor's equals are those before it.
    """
    order = np.argsort(other["bits"], axis=0, kind="stable").T
    low, high = np.empty((2, 4, len(one["img"])), np.int64)
    for k, asked in enumerate(np.argsort(one["bits"], axis=0).T):
        values, needles = other["bits"][order[k], k], one["bits"][asked, k]
        low[k, asked] = np.searchsorted(values, needles, "left") + k * len(values)
        if same:
            high[k, order[k]] = np.arange(len(values)) + k * len(values)
        else:
            high[k, asked] = np.searchsorted(values, needles, "right") + k * len(values)
    return order.ravel(), low, high - low


def _links_between(one: dict, other: dict, same: bool):
    """Yields links ``(a, b, matches)``, a > b, of the images of two blocks, all links of some of ``one``'s images at a time.

    A link needs ``MIN_MATCHES`` matches, so meetings are counted by pair of images first, and only pairs with as many have
    descriptors compared.
    """
    if not len(one["img"]) or not len(other["img"]):
        return
    (order, low, count), mine, theirs = _meetings(one, other, same), _numbered(one["img"]), _numbered(other["img"])
    width, images, posed = theirs[-1] + 1, theirs[order], [_posed(side["place"]) for side in (one, other)]
    ends = np.r_[np.nonzero(mine[1:] != mine[:-1])[0] + 1, len(mine)]
    met = np.cumsum(count.sum(axis=0))[ends - 1]
    first, done, close = 0, 0, []
    while first < len(ends):
        last = max(first + 1, int(np.searchsorted(met, done + MEETINGS, "right")))
        start, end, done = ends[first - 1] if first else 0, ends[last - 1], met[last - 1]
        n = count[:, start:end].ravel()
        row = np.tile((mine[start:end] - first) * width, 4)
        asked = np.repeat(np.arange(len(n)), n)
        at = (low[:, start:end].ravel() - np.cumsum(n) + n)[asked]
        at += np.arange(len(at))
        cell = row[asked]
        cell += images[at]
        # where meetings are rare, pairs share slots; that counts too many at most, and votes tell the pairs apart
        slots = min((last - first) * width, 2 * MEETINGS + 1)
        if slots < (last - first) * width:
            cell %= slots
        enough = np.bincount(cell, minlength=slots) >= MIN_MATCHES
        kept = np.flatnonzero(enough[cell])
        (band, p), q, pair = np.divmod(asked[kept], end - start), order[at[kept]], (np.cumsum(enough) - 1)[cell[kept]]
        p += start
        good = _agreeing(pair, posed[0][p] - posed[1][q])
        if same:
            good &= mine[p] > theirs[q]
        p, q, band = p[good], q[good], band[good]
        apart = one["bits"][p] ^ other["bits"][q]
        # a pair that an earlier band has brought together is not taken twice
        good = (np.bitwise_count(apart.view(np.uint32)).sum(axis=1) <= MAX_DISTANCE) & ((apart == 0).argmax(axis=1) == band)
        close.append((p[good], q[good]))
        first = last
        if first == len(ends) or sum(len(x) for x, _ in close) > MEETINGS:
            p, q = (np.concatenate(x) for x in zip(*close, strict=True))
            up, close = one["img"][p] > other["img"][q], []
            yield _votes(one, other, p[up], q[up])
            if not same:
                yield _votes(other, one, q[~up], p[~up])


def _forest(a: np.ndarray, b: np.ndarray, matches: np.ndarray) -> tuple[np.ndarray, ...]:
    """``(img, root, n_links, matches)`` of the images with links; root is the smallest image reachable over them."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    n, most = np.bincount(at, minlength=len(ids)), np.zeros(len(ids), np.int64)
    np.maximum.at(most, at, np.concatenate([matches, matches]))
    root, (u, v) = np.arange(len(ids)), np.split(at, 2)
    while len(u):
        low = np.minimum(root[u], root[v])
        before = root.copy()
        np.minimum.at(root, root[u], low)
        np.minimum.at(root, root[v], low)
        root = root[root]
        if (before == root).all():
            break
    return ids, ids[root], n, most


def _compared(found: DataFrame, block: int | None, schema: str, fold) -> DataFrame:
    """``fold`` of the links of every pair of blocks; an image's descriptors go once to each pair of its block."""
    descriptor = F.struct((F.col("y") * 16384 + F.col("x") * 64 + F.col("scale") * 32 + F.col("angle")).cast("int").alias("place"), "b0", "b1", "b2", "b3")
    images = cut(found.groupBy("img").agg(F.collect_list(descriptor).alias("d")).select("img", "d.place", "d.b0", "d.b1", "d.b2", "d.b3"))
    n = images.count()
    blocks = max(1, -(-n // block) if block else round((n / 400) ** 0.5))

    def run(table: pa.Table) -> pa.Table:
        low, high = table.column("low")[0].as_py(), table.column("high")[0].as_py()
        one = _tables(table, low)
        parts = list(_links_between(one, one if low == high else _tables(table, high), low == high))
        columns = fold(*(np.concatenate([x[i] for x in parts] or [np.empty(0, np.int64)]).astype(np.int64) for i in range(3)))
        return pa.table([pa.array(c.astype(np.int64)) for c in columns], [c.split()[0] for c in schema.split(", ")])

    own = images.withColumn("blk", F.pmod(F.xxhash64("img"), F.lit(blocks)).cast("int"))
    dealt = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    return dealt.select("img", "blk", F.least("blk", "other").alias("low"), F.greatest("blk", "other").alias("high"), "place", "b0", "b1", "b2", "b3").groupBy("low", "high").applyInArrow(run, schema)


def copy_links(found: DataFrame, block: int | None = None) -> DataFrame:
    """All links ``(a, b, matches)``, a > b, between images whose descriptors agree on one placement.

    ``block`` is the number of images of a block; it changes no result.
    """
    return _compared(found, block, "a long, b long, matches long", lambda *links: links)


def linked_images(found: DataFrame, block: int | None = None) -> DataFrame:
    """``(img, root, n_links, matches)`` by pair of blocks, which stand for all links: a tree's edge img - root, counts that add up."""
    return _compared(found, block, "img long, root long, n_links long, matches long", _forest)


def image_copies(images: DataFrame, id_col: str = "vec_id", pixels_col: str = "embedding") -> DataFrame:
    """One row per row of ``images``: image_id, class_id, n_links, matches.

    The pixels are square grey images in row order (a vector of n*n numbers).  Exactly equal images are taken
    together first and share a class.  ``class_id`` is the smallest image id of the class; ``n_links`` counts all
    verified links of the image's representative with different images.  Null, empty or non-square pixels and flat images have no
    descriptor and are alone unless equal; repeated rows stay; an empty table gives an empty result; other
    columns are ignored.
    """
    plain = images.select(F.col(id_col).cast("long").alias("image_id"), F.col(pixels_col).cast("array<float>").alias("pixels")).withColumn("same", F.when(F.size("pixels") > 0, F.xxhash64("pixels")))
    reps = cut(plain.where("same is not null").groupBy("same").agg(F.min(F.struct("image_id", "pixels")).alias("m")).select("same", F.col("m.image_id").alias("img"), F.col("m.pixels").alias("pixels")))
    with scratch() as keep:
        linked = keep(cut(linked_images(cut(descriptors(reps.where("img is not null"))))))
        classes = keep(cut(components(linked.select(F.col("img").alias("a"), F.col("root").alias("b")))))
    degree = linked.groupBy("img").agg(F.sum("n_links").alias("n_links"), F.max("matches").alias("matches"))
    told = reps.select("same", "img").join(classes, F.col("img") == F.col("node"), "left").join(degree, "img", "left")
    told = told.select("same", F.coalesce("component", "img").alias("class_id"), F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("matches", F.lit(0)).alias("matches"))
    joined = plain.select("image_id", "same").join(told, "same", "left")
    return joined.select("image_id", F.coalesce("class_id", "image_id").alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("matches", F.lit(0)).cast("long").alias("matches"))
