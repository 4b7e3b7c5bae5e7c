"""Narrow blocks with known factors: the nodes that change are covered, node by node as in the transition, at many times its speed."""

import random
import time

import numpy as np

from phraseloom.functions import transition as t


def _strings(seed):
    draw = random.Random(seed)
    for n in (1, 2, 3, 5, 9, 17, 40, 90, 300):
        for symbols in ("a", "ab", "abcd", "aeinrst -"):
            yield "".join(draw.choice(symbols) for _ in range(n))
        yield ("ab" * n)[:n]
        yield ("aab" * n)[: n - 1] + "c"


def test_equals_transition_and_rebuild():
    draw = random.Random(7)
    for s in _strings(3):
        for m in (1, 2, 4, 7):
            for every in (False, True):
                op = draw.choice(["sub", "ins", "del"]) if len(s) > 1 else draw.choice(["sub", "ins"])
                z, symbol = draw.randint(1, len(s) + (op == "ins")), draw.choice("abe")
                new, want, _ = t.transition(s, op, z, symbol, m, None, every)
                before, after = (np.array(t.parents_of(x)) for x in (s, new))
                got = t.transition_known(s, op, z, symbol, m, before, after, every)
                assert got[0] == new and got[1].tolist() == want == after.tolist(), (s, op, z, symbol, m, every)


def test_covers_no_more_than_transition():
    """Wrong factors outside the classes stay as they are: what is copied from the new string is what the transition sets."""
    draw = random.Random(8)
    for s in _strings(4):
        for m in (1, 2, 4):
            z, symbol = draw.randint(1, len(s)), draw.choice("abe")
            for every in (False, True):
                new, _, log = t.transition(s, "sub", z, symbol, m, None, every)
                before, after = (np.array(t.parents_of(x)) for x in (s, new))
                set_ = t.transition_known(s, "sub", z, symbol, m, before, after, every, touched=True)
                assert int(set_.sum()) == log.touched, (s, z, symbol, m, every)


def test_narrow_blocks_are_fast():
    draw = random.Random(9)
    s = "".join(draw.choice("aeinrst dlum") for _ in range(60_000))
    began = time.perf_counter()
    new = t.apply_edit(s, "sub", 30_000, "x")
    before, after = t.parent_arrays([s, new])
    assert t.transition_known(s, "sub", 30_000, "x", 1, before, after)[1].tolist() == after.tolist()
    assert time.perf_counter() - began < 0.6  # one by one, the lists took seconds


def test_without_log_equals_with_log():
    draw = random.Random(10)
    for s in _strings(11):
        for every in (False, True):
            for m in (None, 1, 3):
                op = draw.choice(["sub", "ins", "del"]) if len(s) > 1 else "ins"
                z, symbol = draw.randint(1, len(s) + (op == "ins")), draw.choice("abe")
                assert t.transition(s, op, z, symbol, m, None, every, logged=False)[:2] == t.transition(s, op, z, symbol, m, None, every)[:2]


def test_without_log_equals_rebuild():
    """Also from parents that are given, which is how replays call it."""
    draw = random.Random(12)
    for s in _strings(13):
        for op in ("sub", "ins", "del")[: 3 if len(s) > 1 else 2]:
            z, symbol = draw.randint(1, len(s)), draw.choice("abe")
            kept = t.parents_of(s)
            new, with_log, _ = t.transition(s, op, z, symbol, 2, kept)
            assert t.transition(s, op, z, symbol, 2, kept, logged=False)[1] == with_log == t.parents_of(new)
