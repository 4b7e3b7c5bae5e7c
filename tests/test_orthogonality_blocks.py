"""All queries of a block at once: the same phrases as one parse per query, and fast enough for a table of 0.1 GB."""

import random
import time

from phraseloom.functions import gadgets as g
from phraseloom.functions import kernels as k
from phraseloom.operators import orthogonality as ov


def _patterns(count, d, seed, share=0.3):
    draw = random.Random(seed)
    return sorted({"".join("1" if draw.random() < share else "0" for _ in range(d)) for _ in range(count)})


def _covering(head, tail):
    at, count = len(head), 0
    while at < len(head + tail):
        at, count = at + max(1, k.earlier_factor(head + tail, at)[0]), count + 1
    return count


def test_counts_equal_one_parse_per_query():
    for d, size in ((1, 1), (5, 3), (12, 9), (12, 14), (33, 7)):
        own, us = _patterns(size, d, d), sorted({*_patterns(25, d, 99), "0" * d, "1" * d})
        counts = ov._counts(own, us)
        for column, u in enumerate(us):
            assert counts[:, column].tolist() == ov.phrases_per_vector(ov._squared(own, d), int(u, 2), d)[: len(own)]


def test_simple_gadgets_equal_one_parse_per_query(spark):
    d = 12
    a, b = _patterns(20, d, 1), _patterns(15, d, 2)
    sets = [spark.createDataFrame([(x, 1) for x in rows], "bits string, copies long") for rows in (a, b)]
    vector = lambda v: g.simple_vector(ov._vector(int(v, 2), d))
    head = {u: ov._simple_head(int(u, 2), d) for u in b}
    got = {(r["u"], r["v"]): r["phrases"] for r in ov.whole_pair_gadget(*sets, 7).collect()}
    assert got == {(u, v): _covering(head[u], vector(v)) for u in b for v in a}
    naive = {r["u"]: (r["vectors"], r["phrases"]) for r in ov.whole_naive_set(*sets, 100).collect()}
    assert naive == {u: (len(a), _covering(head[u], "".join(map(vector, a)))) for u in b}


def test_sizes_equal_the_strings(spark):
    d = 6
    a, b = _patterns(11, d, 3), _patterns(5, d, 4)
    sets = [spark.createDataFrame([(x, 1) for x in rows], "bits string, copies long") for rows in (b, a)]
    got = {r["u"]: r.asDict() for r in ov.whole_sizes(*sets, 100).collect()}
    square = ov._squared(a, d)
    for u in b:
        fresh = g.Fresh()
        first = len(g.dictionary(len(square), d, fresh))
        ones, mine = (g.query_vector(ov._vector(x, d), len(square), g.Fresh()) for x in ((1 << d) - 1, int(u, 2)))
        matrix = sum(map(len, g.matrix([ov._vector(v, d) for v in square], fresh)))
        assert got[u] == {"u": u, "n": len(square), "dictionary_symbols": first, "query_symbols": len(mine), "matrix_symbols": matrix, "substitutions": sum(x != y for x, y in zip(ones, mine, strict=True))}


def test_many_queries_of_one_block_are_fast():
    own, us = _patterns(9, 64, 5, 0.5), _patterns(4000, 64, 6, 0.5)
    began = time.perf_counter()
    assert set(ov._counts(own, us).ravel().tolist()) <= {65, 66}
    assert time.perf_counter() - began < 10  # one parse per query took about a minute
