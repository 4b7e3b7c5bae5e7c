"""Every transition equals a rebuild; the classes are all needed."""

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from phraseloom.functions import transition as t

strings = st.one_of(st.text("ab", min_size=1, max_size=45), st.text("abcd", min_size=1, max_size=45), st.tuples(st.text("ab", min_size=1, max_size=6), st.integers(1, 9)).map(lambda x: x[0] * x[1]))


@given(strings, st.sampled_from(["sub", "ins", "del"]), st.integers(0, 10**6), st.sampled_from("abx"), st.sampled_from([None, 1, 2, 3, 4, 6]), st.booleans())
@settings(max_examples=500, deadline=None)
def test_transition_equals_rebuild(s, op, at, symbol, m, every):
    if op == "del" and len(s) == 1:
        return
    z = 1 + at % (len(s) + (op == "ins"))
    new, parents, log = t.transition(s, op, z, symbol, m, all_occurrences=every)
    assert new == t.apply_edit(s, op, z, symbol) and parents == t.parents_of(new)
    assert t.phrase_count(parents) == t.phrase_count(t.parents_of(new)) and log.touched >= 0


@pytest.mark.parametrize(("old", "z", "symbol", "new", "counts"), [("abcabcabcabc", 5, "d", "abcadcabcabc", (4, 8)), ("aaaaaaaaaa", 4, "b", "aaabaaaaaa", (2, 5)), ("abaababaabaab", 8, "b", "abaababbabaab", (6, 7)), ("abracadabraabracadabra", 6, "x", "abracxdabraabracadabra", (9, 11))])
def test_golden_substitutions(old, z, symbol, new, counts):
    got, parents, _ = t.transition(old, "sub", z, symbol, 2)
    assert got == new and (t.phrase_count(t.parents_of(old)), t.phrase_count(parents)) == counts


@given(strings, st.integers(0, 10**6), st.sampled_from("abx"))
@settings(max_examples=100, deadline=None)
def test_substitution_is_delete_and_insert(s, at, symbol):
    z = 1 + at % len(s)
    one = t.transition(s, "sub", z, symbol)
    middle, parents, _ = t.transition(s, "del", z, None)
    two = t.transition(middle, "ins", z, symbol, parents=parents)
    assert one[:2] == two[:2]


@pytest.mark.parametrize("skipped", ["super_light", "light", "left_heavy", "right_heavy"])
def test_no_class_can_be_left_out(skipped):
    import random

    r = random.Random(5)
    wrong = 0
    for _ in range(400):
        s = "".join(r.choice("ab") for _ in range(40))
        z = r.randint(1, 40)
        new, parents, _ = t.transition(s, "sub", z, "x", 3, skip=(skipped,))
        wrong += parents != t.parents_of(new)
    assert wrong > 0


def test_pruned_clusters_need_fewer_probes_on_periodic_strings():
    s = "ab" * 200
    pruned, full = (t.transition(s, "sub", 200, "x", 8, all_occurrences=x)[2] for x in (False, True))
    assert pruned.critical < full.critical and pruned.moves < full.moves
