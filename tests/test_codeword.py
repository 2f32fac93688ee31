from rungwise.functions.typeindex import FIRST_CHAR, TypicalSet, char_of
from rungwise.operators import codeword
from rungwise.queries import _store
from rungwise.storage_queries import _edited


def test_codeword_alone_gives_the_sequence_back(spark, sf):
    store = _store(spark, sf.replace("0.001", "0.01"), "deep3", words=True)
    s, law = store.schedule, store.law
    rows = codeword.codeword(store).collect()
    whole = "".join(r.bits for r in sorted(rows, key=lambda r: (r.level, r.cell)))
    assert all(whole[r.at : r.at + len(r.bits)] == r.bits for r in rows)
    cell = {(r.level, r.cell): r.bits for r in rows}
    wide, sets, found = s.digit_bits, {}, {0: 0, 1: 0, 2: 0, None: 0}

    def slot(level, group, children, child_symbols, child):
        """Bits of a child's slot in its group's cell, or None if its header doesn't hold it."""
        header = cell[level, group][:children]
        at = child - group * s.levels[level - 1].fanout
        return None if header[at] == "0" else cell[level, group][children + header[:at].count("1") * child_symbols * wide :]

    kids = [{(r.grp): r.n_child for r in g.collect()} for g in store.groups]
    for r in store.state.select("blk", "n_sym", "body", "g1", "g2", "home").collect():
        word, home, text = cell[0, r.blk], None, None
        if "1" in word:
            t = sets.setdefault(r.n_sym, TypicalSet(list(law.counts), s.num, s.den, r.n_sym))
            home, text = 0, "".join(map(char_of, t.unindex(int(word, 2) if r.n_sym == s.b0 else int(word, 2) >> (len(word) - max(s.k0, t.size.bit_length())))))
        else:
            bits = slot(1, r.g1, kids[0][r.g1], s.b0, r.blk)
            if bits is not None:
                home = 1
            else:
                bits = slot(2, r.g2, kids[1][r.g2], s.b0 * s.levels[0].fanout, r.g1)
                if bits is not None:
                    home, bits = 2, bits[(r.blk - r.g1 * s.levels[0].fanout) * s.b0 * wide :]
            if home:
                text = "".join(chr(FIRST_CHAR + int(bits[i * wide : (i + 1) * wide], 2)) for i in range(r.n_sym))
        assert home == r.home
        assert home is None or text == r.body
        found[home] += 1
    assert found[0] and found[1] and found[2]


def test_flipped_bits_against_a_scan(spark, sf):
    sf = sf.replace("0.001", "0.01")
    before, after = _edited(spark, sf, "deep3")
    old, new = ({(r.level, r.cell): r.bits for r in codeword.cells(x).collect()} for x in (before, after))
    want = {}
    for k in old:
        if old[k] != new[k]:
            n = max(len(old[k]), len(new[k]))
            c, w, f = want.get(k[0], (0, 0, 0))
            want[k[0]] = (c + 1, w + n, f + sum(a != b for a, b in zip(old[k].ljust(n, "0"), new[k].ljust(n, "0"), strict=True)))
    got = {r.level: (r.cells, r.rewritten_bits, r.flipped_bits) for r in codeword.flipped(before, after).collect()}
    assert got == want and want
    assert codeword.flipped(before, before).isEmpty()
