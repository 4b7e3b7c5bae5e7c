"""Index classes of a substitution against their definitions, by listing all substrings."""

import random

import pytest

from phraseloom.functions import transition as t


def factors(s):
    out = []
    for i in range(len(s)):
        best = 0
        while i + best < len(s) and s.find(s[i : i + best + 1], 0, i + best) >= 0:
            best += 1
        out.append(max(1, best))
    return out


def heavy(old, new, anchor, places):
    x, y = factors(old), factors(new)
    return {i for i in range(1, len(old) + 1) if x[i - 1] != y[i - 1] and any(i <= k <= i + min(x[i - 1], y[i - 1]) - len(anchor) for k in places)}


def light(text, z, m):
    out = set()
    for low in range(max(1, z - m), z + 1):
        for high in range(z, min(len(text), z + m) + 1):
            at = text.find(text[low - 1 : high], z)
            out |= {at + 1} if at >= 0 else set()
    return out


@pytest.mark.parametrize("every", [False, True])
def test_classes_follow_their_definitions(every):
    draw = random.Random(5)
    for _ in range(400):
        s = "".join(draw.choices("ab", k=draw.randint(2, 40))) if draw.random() < 0.6 else (draw.choice(["ab", "a", "aab"]) * 20)[: draw.randint(2, 40)]
        z, m = draw.randint(1, len(s)), draw.randint(1, 4)
        new, parents, log = t.transition(s, "sub", z, draw.choice("abc"), m, all_occurrences=every)
        active = {i for i, (a, b) in enumerate(zip(t.parents_of(s), parents, strict=True), 1) if a != b}
        assert log.members["light"] == light(s, z, m) | light(new, z, m)
        for name, low, high in (("left_heavy", max(1, z - m), z - 1), ("right_heavy", z + 1, min(len(s), z + m))):
            anchor = s[low - 1 : high]
            places = [k for k in range(1, len(s) - len(anchor) + 2) if anchor and s[k - 1 :].startswith(anchor) and new[k - 1 :].startswith(anchor)]
            assert log.members[name] & active == heavy(s, new, anchor, places)
        assert active <= set().union(*log.members.values())
        if not every:
            assert sum(log.critical_parts.values()) == log.critical


def test_clean_intervals_hold_one_parent():
    draw = random.Random(6)
    for _ in range(300):
        s = "".join(draw.choices("ab", k=draw.randint(2, 30)))
        new = t.apply_edit(s, "sub", draw.randint(1, len(s)), draw.choice("ab"))
        old, now = t.OnDemand(s, None), t.OnDemand(new, None)
        i = draw.randint(1, len(s))
        j = draw.randint(i, len(s))
        spans = t.clean_intervals(t.critical_lists(old, now, i, j), i)
        assert spans[-1][1] == i and all(b + 1 == c for (_, b), (c, _) in zip(spans, spans[1:], strict=False))
        for a, b in spans:
            assert len({old.reach(x) for x in range(a, b + 1)}) == len({now.reach(x) for x in range(a, b + 1)}) == 1
