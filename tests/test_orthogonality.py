"""Reduction and direct join over all coordinates: no prefix of the vectors decides."""

from phraseloom.operators import orthogonality as ov


def _table(spark):
    one = lambda *at: [1.0 if j in at else -1.0 for j in range(64)]
    # all vectors agree on the first ten coordinates; 0-1 and 4-1 meet only in the last one, 2-5 in coordinate 41
    rows = [(0, one(63)), (1, one(20, 63)), (2, one(40)), (3, one(12)), (4, one(12, 63)), (5, one(40, 41)), (6, one(40)), (8, one(50)), (10, one()), (12, one(33, 34))]
    return spark.createDataFrame(rows, "vec_id long, embedding array<double>"), dict(rows)


def test_all_coordinates_count(spark):
    table, rows = _table(spark)
    bits = {key: "".join("1" if x > 0 else "0" for x in v) for key, v in rows.items()}
    a, b = ({bits[key] for key in bits if key % 2 == side} for side in (0, 1))
    apart = {(u, v): all("1" not in (x,) or y == "0" for x, y in zip(u, v, strict=True)) for u in b for v in a}
    assert set(apart.values()) == {True, False}
    sets = ov.whole_patterns(table)
    for size in (2, 4, 9):
        got = {(r["u"], r["v"]): (r["phrases"], r["orthogonal"]) for r in ov.whole_phrase_counts(*sets, size).collect()}
        assert got == {pair: (65 if x else 66, x) for pair, x in apart.items()}
    assert {(r["u"], r["v"]): r["phrases"] for r in ov.whole_pair_gadget(*sets).collect()} == {pair: 64 if x else 65 for pair, x in apart.items()}
    count = {u: sum(apart[u, v] for v in a) for u in b}
    joined = {r["u"]: r for r in ov.whole_join(*sets).collect()}
    assert {u: r["orthogonal"] for u, r in joined.items()} == count == {r["u"]: r["orthogonal"] for r in ov.whole_decide(*sets).collect()}
    copies = lambda side, x: sum(bits[key] == x for key in bits if key % 2 == side)
    assert {u: r["row_pairs"] for u, r in joined.items()} == {u: sum(copies(1, u) * copies(0, v) for v in a if apart[u, v]) for u in b}
