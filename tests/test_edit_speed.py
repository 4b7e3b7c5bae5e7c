"""Edits of long strings: few searches, one suffix order for many strings, and no shuffle for the scripts."""

import random

import pytest

from phraseloom.functions import kernels as k
from phraseloom.functions import transition as t
from phraseloom.operators import changes


def _plain(s: str) -> list[int]:
    out, last = [], 0
    for i in range(len(s)):
        last, _ = k.earlier_factor(s, i, known=max(0, last - 1))
        out.append(last)
    return out


def test_factors_of_many_texts():
    r = random.Random(3)
    words = ["".join(r.choice("abcdef \n") for _ in range(r.randint(1, 90))) for _ in range(6)]
    texts = ["", "a", "a" * 700, "abcab" * 120 + "x" + "abcab" * 60, "".join(r.choice(words) for _ in range(20)), "日本" * 90 + "".join(map(chr, range(0x4E00, 0x4F00))), "".join(r.choice("ab") for _ in range(500))]
    assert [x.tolist() for x in k.lpf_many(texts)] == [_plain(s) for s in texts] and not list(k.lpf_many([]))
    assert list(t.parents_of_many(texts)) == [t.parents_of(s) for s in texts]


@pytest.mark.parametrize("m", [None, 1, 2, 4])
@pytest.mark.parametrize("op", ["sub", "ins", "del"])
def test_transition_searches_little(monkeypatch, m, op):
    """Before, narrow blocks searched the text once for nearly every place of both strings."""
    r, asked = random.Random(4), []
    words = ["".join(r.choice("aeinrst") for _ in range(r.randint(2, 7))) for _ in range(60)]
    s = " ".join(r.choice(words) for _ in range(500))
    parents = t.parents_of(s)
    whole = t.earlier_factor
    monkeypatch.setattr(t, "earlier_factor", lambda *a, **b: asked.append(0) or whole(*a, **b))
    new, got, log = t.transition(s, op, 700, "x", m, parents)
    assert got == t.parents_of(new) and log.factor_probes > len(asked) and len(asked) <= t.SEARCHES


def test_scripts_need_no_shuffle(spark):
    strings = spark.createDataFrame([(3, "abracadabra"), (4, "abc"), (5, "banana")], "sid long, body string")
    scripts = changes.edit_script(strings, 3, ("sub", "ins"), "xyz")
    assert "Exchange" not in scripts._jdf.queryExecution().executedPlan().toString()
    rows = {r["sid"]: [tuple(e) for e in r["ops"]] for r in scripts.collect()}
    want = {sid: [(q, ("sub", "ins")[q % 2], 1 + (7 * sid + 13 * q) % (n - 3), "xyz"[(sid + q) % 3]) for q in (1, 2, 3)] for sid, n in ((3, 11), (5, 6))}
    assert rows == want
    assert sorted((r["sid"], r["seq"], r["op"], r["pos"], r["sym"]) for r in changes.edit_rows(strings, 3, ("sub", "ins"), "xyz").collect()) == sorted((sid, *e) for sid, ops in want.items() for e in ops)
