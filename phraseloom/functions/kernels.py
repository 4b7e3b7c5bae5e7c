"""Kernels on one string: no Spark here.

Strings are Python strings (one code point per symbol); sequences of other symbols are mapped to code points first, see
``symbols.as_text``. Positions of results are 1-based and ranges closed, as everywhere in this engine.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterable, Iterator

import numpy as np


def agreement(s: str, i: int, j: int, known: int = 0) -> int:
    """Length of the longest common prefix of the suffixes at the 0-based places i and j."""
    n, length, step = len(s) - max(i, j), known, 16
    while length < n:
        if s[i + length : i + length + step] == s[j + length : j + length + step] and length + step <= n:
            length, step = length + step, min(4 * step, 1 << 16)
        elif step == 1:
            return length
        else:
            step = max(1, step // 4)
            if step == 1 and s[i + length] != s[j + length]:
                return length
    return length


def agreement_back(s: str, i: int, j: int) -> int:
    """Length of the longest common suffix of the prefixes that end at the 0-based places i and j."""
    k = 0
    while k <= min(i, j) and s[i - k] == s[j - k]:
        k += 1
    return k


def earlier_factor(s: str, i: int, overlap: bool = True, known: int = 0) -> tuple[int, int]:
    """Longest factor at the 0-based place i that also starts earlier, and the leftmost such start (-1: none).

    A start of a longer factor is a start of every shorter one, so the search for the next length goes on where the last
    one was found: one pass over the text before i. ``known``: a length that certainly occurs earlier.
    """
    n, length, source, at = len(s), known, -1, 0
    if known:
        source = s.find(s[i : i + known], 0, i + known - 1 if overlap else i)
        at = source + 1
        if source >= 0:
            length = _grown(s, i, source, known, overlap)
    while i + length < n:
        found = s.find(s[i : i + length + 1], at, i + length if overlap else i)
        if found < 0:
            break
        source, at = found, found + 1
        length = _grown(s, i, found, length + 1, overlap)
    return length, source


def _grown(s: str, i: int, source: int, length: int, overlap: bool) -> int:
    length = agreement(s, source, i, length)
    return length if overlap else min(length, i - source)


def parse(s: str, overlap: bool = True) -> Iterator[tuple[int, int, int]]:
    """Phrases ``(lo, hi, length)`` of the greedy parse; length 0 marks a fresh symbol."""
    i = 0
    while i < len(s):
        length, _ = earlier_factor(s, i, overlap)
        yield i + 1, i + max(1, length), length
        i += max(1, length)


def parse_with_sources(s: str, overlap: bool = True) -> Iterator[tuple[int, int, int | None, str | None]]:
    """Phrases ``(lo, hi, source, symbol)``: the rightmost source of a copy, or the symbol of a fresh phrase."""
    for lo, hi, length in parse(s, overlap):
        if length:
            yield lo, hi, s.rfind(s[lo - 1 : hi], 0, hi - 1 if overlap else lo - 1) + 1, None
        else:
            yield lo, hi, None, s[lo - 1]


def decode(phrases: Iterable[tuple[int, int, int | None, str | None]]) -> str:
    out: list[str] = []
    for lo, hi, source, symbol in phrases:
        if symbol is not None:
            out.append(symbol)
        else:
            size = hi - lo + 1
            copied = out[source - 1 : source - 1 + size]
            while len(copied) < size:  # a source that runs into its own copy repeats
                copied += copied[: size - len(copied)]
            out += copied
    return "".join(out)


def lpf(s: str) -> list[int]:
    """Longest previous factor of every place (0 where the symbol is fresh)."""
    if len(s) > 128:
        return next(lpf_many([s])).tolist()
    out, last = [], 0
    for i in range(len(s)):
        last, _ = earlier_factor(s, i, known=max(0, last - 1))
        out.append(last)
    return out


def witnesses(s: str, lengths: list[int]) -> list[int | None]:
    """Rightmost earlier start of each place's longest previous factor (1-based)."""
    return [s.rfind(s[i : i + x], 0, i + x - 1) + 1 if x else None for i, x in enumerate(lengths)]


def reach(lengths: list[int]) -> list[int]:
    return [i + 1 + max(1, x) for i, x in enumerate(lengths)]


def codes(s: str) -> np.ndarray:
    return np.frombuffer(s.encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.int64)


def suffix_array(s: str) -> np.ndarray:
    """0-based places in the order of their suffixes."""
    return _order(*_joined([s])[:3])[0][1:] if s else np.zeros(0, np.int64)


def _joined(texts: list[str]) -> tuple[np.ndarray, np.ndarray, int, np.ndarray]:
    """Symbols of all texts as small numbers, each text closed by one 0; the text of every place; bits a symbol; first places."""
    c = codes("".join(texts))
    sizes = np.array([len(t) for t in texts], np.int64)
    number = np.zeros(int(c.max(initial=0)) + 1, np.int64)
    number[c] = 1
    number = np.cumsum(number)
    starts = np.concatenate([[0], np.cumsum(sizes + 1)[:-1]])
    home = np.repeat(np.arange(len(texts)), sizes + 1)
    x = np.zeros(len(home), np.int64)
    inside = np.ones(len(home), bool)
    inside[starts + sizes] = False
    x[inside] = number[c]
    return x, home, int(x.max(initial=1)).bit_length(), starts


def _packed(x: np.ndarray, bits: int, per: int) -> np.ndarray:
    """The next ``per`` symbols of each place as one number (0 behind the end)."""
    padded = np.concatenate([x, np.zeros(per, np.int64)])
    key = np.zeros(len(x), np.int64)
    for t in range(per):
        key = key << bits | padded[t : t + len(x)]
    return key


def _order(x: np.ndarray, home: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Places by text and suffix, the packed symbols, and how many are packed.

    Packed symbols sort most suffixes at once; prefix doubling goes on inside the groups that are still equal. Equal
    members of a group lie in one text and so do their next k symbols, as the closing 0s would differ.
    """
    n, room = len(x), 62 - int(home[-1]).bit_length()
    per = max(1, room // bits)
    key = _packed(x, bits, per)
    order = np.argsort(home << (per * bits) | key)
    new = np.ones(n + 1, bool)
    new[1:n] = (key[order[1:]] != key[order[:-1]]) | (home[order[1:]] != home[order[:-1]])
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(new[:n], np.arange(n), 0))
    rows = np.flatnonzero(~(new[:n] & new[1:]))
    k = per
    while len(rows):
        places = order[rows]
        pair = rank[places] * n + rank[places + k]
        turn = np.argsort(pair)
        places, pair = places[turn], pair[turn]
        order[rows] = places
        new = np.ones(len(rows) + 1, bool)
        new[1:-1] = pair[1:] != pair[:-1]
        rank[places] = np.maximum.accumulate(np.where(new[:-1], rows, 0))
        rows = rows[~(new[:-1] & new[1:])]
        k *= 2
    return order, key, per


def _nearest_smaller(values: np.ndarray) -> np.ndarray:
    """Index of the nearest smaller value to the left (-1: none), by pointer jumping over larger ones.

    Chains that jumping shortens too slowly (runs of one symbol beside others) end in one walk in rising order, from the left
    neighbour on over final pointers, which passes every place once.
    """
    n = len(values)
    closed = np.append(values, -1)  # index -1 reads this end
    jump = np.arange(n) - 1
    open_ = np.flatnonzero(closed[jump] > values)
    for _ in range(48):
        jump[open_] = jump[jump[open_]]
        open_ = open_[closed[jump[open_]] > values[open_]]
    if 16 * len(open_) < n:
        for i in open_.tolist():
            j, value = i - 1, values.item(i)
            while closed.item(j) > value:
                j = jump.item(j)
            jump[i] = j
    else:
        to, at = jump.tolist(), closed.tolist()
        for i in open_.tolist():
            j = i - 1
            while at[j] > at[i]:
                j = to[j]
            to[i] = j
        jump = np.array(to, np.int64)
    return jump


def _shared(a: np.ndarray, b: np.ndarray, bits: int, per: int) -> np.ndarray:
    """Equal leading symbols of packed numbers."""
    differ = a ^ b
    differ &= ~(differ >> 1)  # the highest bit stays, and rounding to a float cannot pass it
    highest = np.maximum((differ.astype(np.float64).view(np.int64) >> 52) - 1022, 0)  # number of the highest bit, from the exponent; 0: equal
    return ((per * bits - np.arange(64)) // bits)[highest]


def _earlier(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, int, np.ndarray, int]:
    """Both earlier neighbours in suffix order of every place (-1: none in its text), symbols they share up to a limit, first places, limit, packed symbols, bits of one."""
    x, home, bits, starts = _joined(texts)
    order, key, per = _order(x, home, bits)
    n = len(order)
    out = []
    for values, back in ((order, False), (order[::-1], True)):
        jump = _nearest_smaller(values)
        near = np.full(n, -1, np.int64)
        near[values] = np.where(jump >= 0, values[jump], -1)
        near[near < starts[home]] = -1  # a neighbour in another text
        out.append(near)
        shared = _shared(key, key[near], bits, per)
        shared[near < 0] = 0
        out.append(shared)
    return (*out, starts, per, key, bits)


def parse_many(texts: list[str]) -> Iterator[list[tuple[int, int, int, int]]]:
    """For each text its phrases ``(lo, hi, length, source)``; length and source 0 mark a fresh symbol.

    One suffix order serves all texts. A longest previous factor starts at the nearest earlier place on either side of
    that order; symbols are compared at phrase starts only, so the comparisons add up to the texts' lengths.
    """
    if not texts:
        return
    left, left_shared, right, right_shared, starts, limit, _, _ = _earlier(texts)
    for s, start in zip(texts, starts.tolist(), strict=True):
        part = slice(start, start + len(s))
        sides = left[part].tolist(), left_shared[part].tolist(), right[part].tolist(), right_shared[part].tolist()
        yield _phrases(s, start, limit, *sides)


def _grown_runs(texts: list[str], starts: np.ndarray, rows: np.ndarray, near: np.ndarray, shared: np.ndarray) -> np.ndarray:
    """Common symbols of the places ``rows`` (rising) and ``near``, of which ``shared`` are known.

    Consecutive places whose other places are consecutive too end at the same difference, so a run of them takes one comparison.
    """
    apart = rows - near
    first = np.flatnonzero(np.append(True, (rows[1:] != rows[:-1] + 1) | (apart[1:] != apart[:-1])))
    sizes = np.diff(np.append(first, len(rows)))
    at = rows[first]
    homes = np.searchsorted(starts, at, "right") - 1
    last, common, found = -2, 0, []
    for i, source, known, home, start, size in zip(at.tolist(), near[first].tolist(), shared[first].tolist(), homes.tolist(), starts[homes].tolist(), sizes.tolist(), strict=True):
        common = agreement(texts[home], source - start, i - start, max(known, common - 1) if i == last + 1 else known)
        found.append(common)
        last, common = i + size - 1, common - size + 1
    return np.repeat(np.array(found, np.int64) + at, sizes) - rows


def lpf_many(texts: list[str], rounds: int = 6) -> Iterator[np.ndarray]:
    """For each text the longest previous factor of every place, by one suffix order for all texts.

    Places that share all packed symbols with a neighbour go on by further packed symbols, a few rounds over all of them; what
    is longer goes on by comparisons from the left, as the place before gives all but one of a place's common symbols.
    """
    if not texts:
        return
    *sides, starts, limit, key, bits = _earlier(texts)
    best = np.zeros(len(key), np.int64)
    for near, shared in (sides[:2], sides[2:]):
        rows = np.flatnonzero(shared >= limit)
        for _ in range(rounds):
            more = _shared(key[rows + shared[rows]], key[near[rows] + shared[rows]], bits, limit)
            shared[rows] += more
            rows = rows[more >= limit]
        if len(rows):
            shared[rows] = _grown_runs(texts, starts, rows, near[rows], shared[rows])
        np.maximum(best, shared, out=best)
    for s, start in zip(texts, starts.tolist(), strict=True):
        yield best[start : start + len(s)]


def _phrases(s: str, start: int, limit: int, left: list[int], left_shared: list[int], right: list[int], right_shared: list[int]) -> list[tuple[int, int, int, int]]:
    out, i, n = [], 0, len(s)
    while i < n:
        length, source = left_shared[i], left[i]
        if length >= limit:
            length = agreement(s, source - start, i, limit)
        other = right_shared[i]
        if other >= limit:
            other = agreement(s, right[i] - start, i, limit)
        if other > length:
            length, source = other, right[i]
        if length:
            out.append((i + 1, i + length, length, source - start + 1))
            i += length
        else:
            i += 1
            out.append((i, i, 0, 0))
    return out


def lcp_array(s: str, order: np.ndarray) -> np.ndarray:
    """Common prefix of each suffix with the one before it in order (0 for the first)."""
    n = len(order)
    place = order.tolist()
    rank = [0] * n
    for k, i in enumerate(place):
        rank[i] = k
    out, h = [0] * n, 0
    for i in range(n):
        if rank[i]:
            h = agreement(s, i, place[rank[i] - 1], h)
            out[rank[i]] = h
            h = max(0, h - 1)
        else:
            h = 0
    return np.array(out, np.int64)


def lpf_by_suffix_array(s: str) -> np.ndarray:
    """Longest previous factors from the nearest earlier places on both sides of the suffix order."""
    order = suffix_array(s)
    lcp = lcp_array(s, order).tolist()
    out = [0] * len(order)
    stack: list[tuple[int, int]] = []  # (place, common prefix with the entry below)
    for place, shared in zip([*order.tolist(), -1], [*lcp, 0], strict=True):
        while stack and stack[-1][0] > place:
            top, below = stack.pop()
            out[top] = max(out[top], below, shared)
            shared = min(shared, below)
        if place >= 0:
            out[place] = max(out[place], shared)
            stack.append((place, shared))
    return np.array(out, np.int64)


def smallest_period(s: str) -> int:
    border, k = [0] * len(s), 0
    for i in range(1, len(s)):
        while k and s[i] != s[k]:
            k = border[k - 1]
        k += s[i] == s[k]
        border[i] = k
    return len(s) - border[-1] if s else 0


def occurrences(s: str, pattern: str, low: int = 0, high: int | None = None) -> list[int]:
    """0-based starts of all occurrences, overlapping ones too, inside s[low:high]."""
    out: list[int] = []
    if pattern:
        at = s.find(pattern, low, len(s) if high is None else high)
        while at >= 0:
            out.append(at)
            at = s.find(pattern, at + 1, len(s) if high is None else high)
    return out


def clusters(starts: list[int], period: int) -> list[tuple[int, int]]:
    """Maximal progressions of the period among the starts, as (first, last)."""
    out: list[tuple[int, int]] = []
    for a in starts:
        if out and a - out[-1][1] == period:
            out[-1] = (out[-1][0], a)
        else:
            out.append((a, a))
    return out


def runs(s: str) -> list[tuple[int, int, int]]:
    """Maximal repetitions ``(lo, hi, period)`` (1-based, at least two periods, smallest period)."""
    out = set()
    n = len(s)
    for p in range(1, n // 2 + 1):
        i = 0
        while i + p < n:
            length = agreement(s, i, i + p)
            if length >= p:
                lo, hi = i, i + p + length - 1
                if smallest_period(s[lo : lo + 2 * p]) == p:
                    out.add((lo + 1, hi + 1, p))
            i += length + 1
    return sorted(out)


def trie_parse(s: str) -> Iterator[tuple[int, int, int]]:
    """Phrases ``(lo, hi, parent)`` of the dictionary parse: an earlier phrase and one more symbol (parent 0: none)."""
    children: dict[tuple[int, str], int] = {}
    at, ordinal = 0, 0
    while at < len(s):
        node, lo = 0, at
        while at < len(s) and (node, s[at]) in children:
            node = children[node, s[at]]
            at += 1
        if at < len(s):
            children[node, s[at]] = ordinal = ordinal + 1
            at += 1
        yield lo + 1, at, node


def parse_to_phrase_ends(s: str) -> Iterator[tuple[int, int, int]]:
    """Phrases ``(lo, hi, length)`` whose source must end where an earlier phrase ends; otherwise a single symbol."""
    ends: list[int] = []
    i = 0
    while i < len(s):
        best = 0
        for e in ends:
            longest = min(len(s) - i, e)
            for length in range(longest, best, -1):
                if s[e - length : e] == s[i : i + length]:
                    best = length
                    break
        yield i + 1, i + max(1, best), best
        i += max(1, best)
        ends.append(i)


def bwt_runs(s: str) -> int:
    """Runs of equal symbols in the transform of the string with a smallest end mark."""
    order = suffix_array(s)
    c = codes(s)
    column = np.concatenate([c[-1:], np.where(order > 0, c[order - 1], -1)]) if len(c) else c
    return int(1 + (column[1:] != column[:-1]).sum()) if len(column) else 0


def substring_complexity(s: str) -> tuple[int, float]:
    """The length k at which (distinct substrings of length k) / k is largest, and that value."""
    n = len(s)
    if not n:
        return 0, 0.0
    order = suffix_array(s)
    lcp = lcp_array(s, order)
    size = n - order  # a suffix of this size brings new substrings of the lengths lcp+1 .. size
    change = np.zeros(n + 2, np.int64)
    np.add.at(change, lcp + 1, 1)
    np.add.at(change, size + 1, -1)
    counts = np.cumsum(change)[1 : n + 1]
    ratio = counts / np.arange(1, n + 1)
    best = int(ratio.argmax())
    return best + 1, float(ratio[best])


def cover(a: int, b: int) -> list[tuple[int, int, int]]:
    """Pieces ``(level, lo, hi)`` of the aligned partitions that cover [a..b], largest first fit from the left."""
    out = []
    while a <= b:
        level = min(((a - 1) & -(a - 1)).bit_length() - 1 if a > 1 else 62, (b - a + 1).bit_length() - 1)
        out.append((level, a, a + (1 << level) - 1))
        a += 1 << level
    return out


class Partition:
    """Intervals of one scale k: each shorter than 2^(k+1), two neighbours at least 2^k together."""

    def __init__(self, n: int, level: int) -> None:
        self.level, size = level, 1 << level
        self.lengths = [size] * (n // size) + ([n % size] if n % size else [])

    def _at(self, pos: int) -> int:
        k = 0
        while k < len(self.lengths) - 1 and pos > self.lengths[k]:
            pos -= self.lengths[k]
            k += 1
        return k

    def insert(self, pos: int) -> int:
        """Grow the interval at pos; returns how many intervals were rebuilt."""
        if not self.lengths:
            self.lengths = [1]
            return 1
        k = self._at(pos)
        self.lengths[k] += 1
        if self.lengths[k] < 2 << self.level:
            return 1
        half = self.lengths[k] // 2
        self.lengths[k : k + 1] = [half, self.lengths[k] - half]
        return 2

    def delete(self, pos: int) -> int:
        k = self._at(pos)
        self.lengths[k] -= 1
        rebuilt = 1
        if not self.lengths[k]:
            del self.lengths[k]
            k = max(0, k - 1)
        for left in (k - 1, k):
            if 0 <= left < len(self.lengths) - 1 and self.lengths[left] + self.lengths[left + 1] < 1 << self.level:
                self.lengths[left : left + 2] = [self.lengths[left] + self.lengths[left + 1]]
                rebuilt += 1
                break
        return rebuilt

    def valid(self) -> bool:
        return all(0 < x < 2 << self.level for x in self.lengths) and all(a + b >= 1 << self.level for a, b in zip(self.lengths, self.lengths[1:], strict=False))


class BudgetedRebuild:
    """Background building: every update queues work for the intervals it touched and does at most ``budget`` steps."""

    def __init__(self, budget: int = 8) -> None:
        self.budget, self.queue, self.longest = budget, 0, 0

    def update(self, work: int) -> int:
        self.queue += work
        done = min(self.budget, self.queue)
        self.queue -= done
        self.longest = max(self.longest, self.queue)
        return done


def first_above(values: list[int], limit: int) -> int:
    """First index of a non-decreasing list whose value exceeds limit."""
    return bisect_left(values, limit + 1)


def fewest_phrases(s: str) -> int:
    """Least number of phrases of any valid factorization, over all of them: a phrase is one symbol or any factor that started earlier."""
    lengths, best = lpf(s), [0] + [len(s)] * len(s)
    for i, longest in enumerate(lengths):
        for j in range(i + 1, i + max(1, longest) + 1):
            best[j] = min(best[j], best[i] + 1)
    return best[len(s)]


def skyline_sizes(s: str, places: list[int]) -> tuple[int, int]:
    """Over each place and the earlier ones: pairs of agreements (back, ahead), and those that no other of its pairs dominates."""
    points = total = 0
    for at, i in enumerate(places):
        pairs = sorted({(agreement_back(s, j, i), agreement(s, j, i)) for j in places[:at]}, reverse=True)
        best = -1
        for _, ahead in pairs:
            if ahead > best:
                best, total = ahead, total + 1
        points += at
    return points, total


class Positions:
    """Nodes of a changing string in blocks: node to number and number to node by the sizes of the blocks before."""

    def __init__(self, n: int) -> None:
        self.width = max(4, int(n**0.5))
        self.blocks = [list(range(a, min(a + self.width, n + 1))) for a in range(1, n + 1, self.width)] or [[]]
        self.home = {node: block for block in self.blocks for node in block}
        self.next = n + 1

    def _at(self, pos: int) -> tuple[int, int]:
        for k, block in enumerate(self.blocks):
            if pos <= len(block):
                return k, pos - 1
            pos -= len(block)
        return len(self.blocks) - 1, len(self.blocks[-1])

    def node(self, pos: int) -> int:
        k, at = self._at(pos)
        return self.blocks[k][at]

    def pos(self, node: int) -> int:
        home, before = self.home[node], 0
        for block in self.blocks:
            if block is home:
                return before + block.index(node) + 1
            before += len(block)
        raise KeyError(node)

    def insert(self, pos: int) -> int:
        """A new node that gets number ``pos``."""
        k, at = self._at(pos)
        block, node = self.blocks[k], self.next
        self.next += 1
        block.insert(at, node)
        self.home[node] = block
        if len(block) > 2 * self.width:
            tail = block[self.width :]
            del block[self.width :]
            self.blocks.insert(k + 1, tail)
            for x in tail:
                self.home[x] = tail
        return node

    def delete(self, pos: int) -> int:
        k, at = self._at(pos)
        node = self.blocks[k].pop(at)
        del self.home[node]
        if not self.blocks[k] and len(self.blocks) > 1:
            del self.blocks[k]
        return node
