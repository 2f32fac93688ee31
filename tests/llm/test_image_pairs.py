from collections import defaultdict

import numpy as np
import pytest

from rungwise.llm import image_descriptors


def _table(images):
    d = image_descriptors.describe(image_descriptors._resized(images.astype(np.float32), 32))
    order = np.argsort(d["image"], kind="stable")
    place = (d["y"] * 16384 + d["x"] * 64 + d["scale"] * 32 + d["angle"]).astype(np.int32)
    return {"img": d["image"][order].astype(np.int64), "place": place[order], "bits": d["bits"][order]}


def _by_hand(table):
    """All links by comparing all descriptors, and the number of matches of all pairs."""
    links, n = [], 0
    img, (y, x, s, t) = table["img"], image_descriptors._unpacked(table["place"])
    for a in np.unique(img):
        mine, below = np.nonzero(img == a)[0], np.nonzero(img < a)[0]
        apart = table["bits"][mine][:, None] ^ table["bits"][below][None]
        p, q = np.nonzero((np.bitwise_count(apart.view(np.uint32)).sum(axis=2) <= image_descriptors.MAX_DISTANCE) & (apart == 0).any(axis=2))
        n += len(p)
        found = defaultdict(set)
        for i, j in zip(mine[p], below[q], strict=True):
            turn, ratio = (t[i] - t[j]) % 24, image_descriptors.SCALES[s[j]] / image_descriptors.SCALES[s[i]]
            cos, sin = np.cos(turn * np.pi / 12), np.sin(turn * np.pi / 12)
            dx, dy = x[i] - ratio * (cos * x[j] - sin * y[j]), y[i] - ratio * (sin * x[j] + cos * y[j])
            for grid in np.ndindex(2, 2, 2):
                cell = (turn + grid[0]) % 24 // 2, s[i] - s[j], dx // image_descriptors.CELL if not grid[1] else (dx / image_descriptors.CELL + 0.5) // 1, dy // image_descriptors.CELL if not grid[2] else (dy / image_descriptors.CELL + 0.5) // 1
                found[img[j], grid, cell].add((y[i], x[i], s[i]))
        best = defaultdict(int)
        for (b, *_), corners in found.items():
            best[b] = max(best[b], len(corners))
        links += [(a, b, k) for b, k in best.items() if k >= image_descriptors.MIN_MATCHES]
    return sorted(links), n


@pytest.mark.parametrize("meetings", [60, 10**6])
def test_links_equal_all_comparisons_though_few_pairs_are_compared(monkeypatch, meetings):
    rng = np.random.default_rng(21)
    base = rng.normal(size=(150, 8, 8))
    table = _table(np.concatenate([base, base[:25] + rng.normal(0, 0.1, (25, 8, 8)), np.rot90(base[:25], axes=(1, 2))])[rng.permutation(200)])
    expected, matches = _by_hand(table)
    votes, judged = image_descriptors._votes, []
    monkeypatch.setattr(image_descriptors, "_votes", lambda one, other, p, q, *more: judged.append(len(p)) or votes(one, other, p, q, *more))
    monkeypatch.setattr(image_descriptors, "MEETINGS", meetings)
    halves = [{k: v[table["img"] % 2 == i] for k, v in table.items()} for i in range(2)]
    for pairs in ([(table, table)], [(halves[0], halves[0]), (halves[1], halves[1]), (halves[0], halves[1])]):
        judged.clear()
        parts = [x for one, other in pairs for x in image_descriptors._links_between(one, other, one is other)]
        assert sorted(tuple(map(int, r)) for x in parts for r in zip(*x, strict=True)) == expected
        # images share common band values, but few pairs share enough of them for a link
        assert sum(judged) < 0.2 * matches, (sum(judged), matches)
    assert len(expected) >= 50
    nothing = {k: v[:0] for k, v in table.items()}
    assert not any(len(x[0]) for pair in ((nothing, table), (table, nothing)) for x in image_descriptors._links_between(*pair, False))
