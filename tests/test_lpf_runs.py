"""Long repeats: consecutive places with consecutive earlier places take one comparison in all."""

import random

import numpy as np

from phraseloom.functions import kernels as k


def test_long_repeats_equal_the_suffix_array():
    draw = random.Random(5)
    block = "".join(draw.choice("abcdefgh ") for _ in range(400))
    texts = [block + "x" + block[30:] + block[:200] + "y" + block, "ab" * 300 + "c" + "ba" * 200, "a" * 500 + "b" + "a" * 499, block[::-1] + block, "", "q"]
    for group in (texts, texts[::-1], [texts[0]]):
        for rounds in (0, 1, 6):
            for s, got in zip(group, k.lpf_many(group, rounds), strict=True):
                assert got.tolist() == k.lpf_by_suffix_array(s).tolist()


def test_nearest_smaller_on_few_and_many_long_chains():
    draw = np.random.default_rng(6)
    for n in (1, 2, 70, 3000):
        for values in (np.arange(n), np.arange(n)[::-1], draw.permutation(n), np.concatenate([draw.permutation(n) + n, np.arange(n)[::-1]])):
            want, stack = [], []
            for i, v in enumerate(values.tolist()):
                while stack and values[stack[-1]] > v:
                    stack.pop()
                want.append(stack[-1] if stack else -1)
                stack.append(i)
            assert k._nearest_smaller(values).tolist() == want


def test_a_repeat_takes_few_comparisons(monkeypatch):
    draw = random.Random(7)
    block, calls = "".join(draw.choice("abcdefgh ") for _ in range(3000)), []
    plain = k.agreement
    monkeypatch.setattr(k, "agreement", lambda *a: calls.append(a) or plain(*a))
    found = next(k.lpf_many([block + "x" + block]))
    assert found[3001] == 3000 and len(calls) < 100  # one for each place of the repeat before
