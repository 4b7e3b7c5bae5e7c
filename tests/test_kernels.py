"""Kernels against definitions, golden strings, and round trips."""

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from phraseloom.functions import kernels as k

GOLDEN = {
    "a": [0], "aaaa": [0, 3, 2, 1], "abab": [0, 0, 2, 1], "abcabcabc": [0, 0, 0, 6, 5, 4, 3, 2, 1], "aabaabaaab": [0, 1, 0, 5, 4, 3, 2, 3, 2, 1],
    "mississippi": [0, 0, 0, 1, 4, 3, 2, 1, 0, 1, 1], "abracadabra": [0, 0, 0, 1, 0, 1, 0, 4, 3, 2, 1], "banana": [0, 0, 0, 3, 2, 1],
}
texts = st.one_of(st.text("ab", max_size=40), st.text("abc", max_size=40), st.tuples(st.text("ab", min_size=1, max_size=5), st.integers(1, 12)).map(lambda x: x[0] * x[1]), st.text(max_size=20))


def by_definition(s):
    out = []
    for i in range(len(s)):
        best = 0
        while i + best < len(s) and s.find(s[i : i + best + 1], 0, i + best) >= 0:
            best += 1
        out.append(best)
    return out


@pytest.mark.parametrize("s", GOLDEN)
def test_golden_factors(s):
    assert k.lpf(s) == GOLDEN[s] == k.lpf_by_suffix_array(s).tolist()


@pytest.mark.parametrize(("s", "no_overlap", "trie", "period"), [("aaaa", 3, 3, 1), ("abcabcabc", 5, 6, 3), ("mississippi", 9, 8, 11), ("abracadabra", 8, 7, 7), ("banana", 5, 5, 6), ("aabaabaaab", 6, 6, 7)])
def test_golden_variants(s, no_overlap, trie, period):
    assert sum(1 for _ in k.parse(s, overlap=False)) == no_overlap
    assert sum(1 for _ in k.trie_parse(s)) == trie
    assert k.smallest_period(s) == period


def test_golden_transform_and_complexity():
    assert [k.bwt_runs(s) for s in ("banana", "mississippi", "abracadabra", "aaaa")] == [5, 9, 8, 2]
    assert [k.substring_complexity(s)[1] for s in ("aaaa", "abab", "mississippi", "abracadabra", "banana")] == [1, 2, 4, 5, 3]
    assert (k.suffix_array("banana") + 1).tolist() == [6, 4, 2, 1, 5, 3]


@given(texts)
@settings(max_examples=300, deadline=None)
def test_factors_parse_and_code(s):
    lengths = by_definition(s)
    assert k.lpf(s) == lengths == k.lpf_by_suffix_array(s).tolist()
    reach = k.reach(lengths)
    assert all(a <= b for a, b in zip(reach, reach[1:], strict=False))
    phrases = list(k.parse_with_sources(s))
    assert k.decode(phrases) == s
    at = 1
    for lo, hi, source, symbol in phrases:
        assert lo == at and hi == reach[lo - 1] - 1 and (source is None) == (symbol is not None)
        at = hi + 1
    assert at == len(s) + 1
    for variant in (k.parse(s, overlap=False), k.trie_parse(s), k.parse_to_phrase_ends(s)):
        assert "".join(s[lo - 1 : hi] for lo, hi, _ in variant) == s


@given(texts)
@settings(max_examples=100, deadline=None)
def test_greedy_is_minimal(s):
    lengths = by_definition(s)
    best = [0] + [10**9] * len(s)
    for i in range(len(s)):
        for step in range(1, max(1, lengths[i]) + 1):
            best[i + step] = min(best[i + step], best[i] + 1)
    assert sum(1 for _ in k.parse(s)) == best[len(s)]


@given(texts, st.text("ab", min_size=1, max_size=4))
@settings(max_examples=100, deadline=None)
def test_occurrences_and_clusters(s, p):
    starts = [i for i in range(len(s)) if s.startswith(p, i)]
    assert k.occurrences(s, p) == starts
    period = k.smallest_period(p)
    assert [x for a, b in k.clusters(starts, period) for x in range(a, b + 1, period)] == starts


@given(st.integers(1, 300), st.integers(0, 300))
def test_cover(a, more):
    pieces = k.cover(a, a + more)
    assert [x for _, lo, hi in pieces for x in range(lo, hi + 1)] == list(range(a, a + more + 1))
    per_level = [p[0] for p in pieces]
    assert max(map(per_level.count, per_level)) <= 16


@given(st.integers(1, 60), st.integers(0, 4), st.lists(st.tuples(st.booleans(), st.integers(1, 60)), max_size=60))
@settings(max_examples=150, deadline=None)
def test_partitions_stay_valid(n, level, ops):
    part = k.Partition(n, level)
    for insert, pos in ops:
        size = sum(part.lengths)
        if insert:
            part.insert(min(pos, size + 1))
        elif size > 1:
            part.delete(min(pos, size))
        assert part.valid()


@given(st.lists(texts, max_size=5))
@settings(max_examples=300, deadline=None)
def test_strings_parsed_together(several):
    for s, phrases in zip(several, k.parse_many(several), strict=True):
        assert [p[:3] for p in phrases] == list(k.parse(s))
        assert all(source < lo and s[source - 1 : source - 1 + length] == s[lo - 1 : hi] for lo, hi, length, source in phrases if length)
        assert k.decode((lo, hi, source or None, None if length else s[lo - 1]) for lo, hi, length, source in phrases) == s
        assert k.suffix_array(s).tolist() == sorted(range(len(s)), key=lambda i: s[i:])


def test_long_runs_beside_other_symbols():
    s = "ab" * 300 + "c" * 5000 + "ab" * 2500
    assert [p[:3] for p in next(k.parse_many([s]))] == list(k.parse(s))


def test_long_strings_use_the_suffix_array():
    s = "ab" * 2000 + "x" + "ab" * 1500
    assert k.lpf(s)[4001] == 3000 and len(list(k.parse(s))) == 5
