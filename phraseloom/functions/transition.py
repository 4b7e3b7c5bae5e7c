"""One edit of one string: which reach edges may change, and their new values.

Old and new string live on one axis of nodes. An inserted symbol is a node that the old string lacks, a deleted one a
node that the new string lacks; everything else keeps its node. Candidates come from four classes around the edit:
near it (super-light), leftmost later copies of windows over it (light), and indices whose old and new copy both hold an
unchanged occurrence of the block left or right of it (heavy, per side). Each class sets the parents it finds from
previous-factor queries on the new string; all other parents stay.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

from phraseloom.functions.kernels import clusters, codes, earlier_factor, lpf, lpf_many, occurrences, smallest_period

#: Searches of one string after which all its factors are tabulated: about what the table costs, at any length.
SEARCHES = 150


class OnDemand:
    """Previous-factor queries on one string, each answered once; the count of answers is the cost measure.

    Answers come from ``parents``, where they are known already, otherwise from searches, which begin at what the nearest
    answers to both sides leave open. After ``SEARCHES`` searches one suffix order of the text answers the rest.
    """

    def __init__(self, text: str, gap: int | None, parents: list[int] | None = None) -> None:
        self.text, self.gap, self.memory, self.parents = text, gap, {}, parents
        self.matches, self.searches, self.asked = 0, 0, []

    def node(self, pos: int) -> int:
        return pos + 1 if self.gap is not None and pos >= self.gap else pos

    def pos(self, node: int) -> int:
        """Position of a node; the absent node reads as its successor."""
        return node - 1 if self.gap is not None and node > self.gap else node

    def reach(self, pos: int) -> int:
        found = self.memory.get(pos)
        if found is None:
            found = self.memory[pos] = self._search(pos) if self.parents is None else self.parents[pos - 1]
        return found

    def _search(self, pos: int) -> int:
        if self.searches >= SEARCHES:
            self.parents = parents_of(self.text)
            return self.parents[pos - 1]
        at = bisect_left(self.asked, pos)
        low = self.memory[self.asked[at - 1]] if at else 0
        if at < len(self.asked) and low == self.memory[self.asked[at]]:
            found = low  # reach is non-decreasing
        else:
            self.searches += 1
            found = pos + max(1, earlier_factor(self.text, pos - 1, known=max(0, low - pos))[0])
        self.asked.insert(at, pos)
        return found

    def bisect(self, low: int, high: int, limit: int) -> int:
        """Least position in [low..high] whose reach exceeds limit (high + 1: none); reach is non-decreasing."""
        high += 1
        if self.parents is not None:
            memory, parents = self.memory, self.parents
            while low < high:
                middle = (low + high) >> 1
                found = memory[middle] = parents[middle - 1]
                if found > limit:
                    high = middle
                else:
                    low = middle + 1
            return low
        while low < high:
            middle = (low + high) // 2
            if self.reach(middle) > limit:
                high = middle
            else:
                low = middle + 1
        return low

    def critical(self, i: int, j: int) -> list[int]:
        """Places up to i, in falling order, where the reach changes and exceeds j; the first entry is i itself."""
        if i < 1 or self.reach(i) <= j:
            return [i]
        least = self.bisect(1, i, j)
        out, x = [i], i
        while True:
            x = self.bisect(least, x, self.reach(x) - 1)
            out.append(x)
            if x <= least:
                return out
            x -= 1


@dataclass
class Log:
    active: int = 0
    touched: int = 0
    moves: int = 0
    factor_probes: int = 0
    match_probes: int = 0
    critical: int = 0
    clusters: int = 0
    sizes: dict[str, int] = field(default_factory=lambda: {"super_light": 0, "light": 0, "left_heavy": 0, "right_heavy": 0})
    #: Nodes by class; heavy ones by the definition, without block starts that are set although their factors end inside the block.
    members: dict[str, set[int]] = field(default_factory=lambda: {"left_heavy": set(), "right_heavy": set()})
    critical_parts: dict[str, int] = field(default_factory=lambda: {"starts": 0, "end": 0, "near": 0})


def apply_edit(s: str, op: str, z: int, symbol: str | None) -> str:
    """``op``: sub, ins (before position z; n+1 appends) or del."""
    return s[: z - 1] + (symbol if op != "del" else "") + s[z - 1 + (op != "ins") :]


def default_width(n: int) -> int:
    m = max(1, round(n ** (1 / 3)))
    return m + (m**3 < n)


def old_parents(s: str, op: str, z: int, parents: list[int] | None = None) -> list[int]:
    """Parents before the edit on the common axis, entry k - 1 for node k; 0 for an inserted node."""
    values = parents_of(s) if parents is None else parents
    if op != "ins":
        return list(values)
    moved = bisect_left(values, z)  # reach is non-decreasing
    values = values[:moved] + [r + 1 for r in values[moved:]]
    values.insert(z - 1, 0)
    return values


def transition(s: str, op: str, z: int, symbol: str | None, m: int | None = None, parents: list[int] | None = None, all_occurrences: bool = False, skip: tuple[str, ...] = (), logged: bool = True) -> tuple[str, list[int], Log]:
    """The new string, its parents, and the cost log (empty unless ``logged``). ``all_occurrences``: no pruning of clusters; ``skip``: classes left out."""
    new = apply_edit(s, op, z, symbol)
    m = default_width(max(len(s), len(new))) if m is None else m
    parents = parents_of(s) if parents is None else parents
    before, after = OnDemand(s, z if op == "ins" else None, parents), OnDemand(new, z if op == "del" else None)
    size = max(len(s), len(new))
    now = old_parents(s, op, z, parents)
    if op == "del":
        here, behind = bisect_left(now, z), bisect_right(now, z)  # reach is non-decreasing
        now[here:behind] = [z + 1] * (behind - here)
    log, classes, old = Log(), {name: set() for name in Log().sizes}, {}

    def present(node: int) -> bool:
        return 1 <= node <= size and not (op == "del" and node == z)

    def set_parent(name: str, node: int, parent: int | None = None) -> None:
        if present(node):
            classes[name].add(node)
            old.setdefault(node, now[node - 1])
            now[node - 1] = after.node(after.reach(after.pos(node))) if parent is None else parent

    def set_range(name: str, first: int, last: int, parent: int) -> None:
        if logged:
            for node in range(first, last + 1):
                set_parent(name, node, parent)
        else:
            now[first - 1 : last] = [parent] * (last - first + 1)  # the absent node's entry goes in the end

    if op == "ins":
        old[z], now[z - 1] = 0, after.node(after.reach(z))
    if "super_light" not in skip:
        for node in range(max(1, z - m - 1), z + 1):
            if present(node):
                set_parent("super_light", node)
                log.moves += 1
    if "light" not in skip:
        for t in (before, after):
            found = _light(t, z, m, size)
            for node in found if logged else set(found):
                set_parent("light", node)
                log.moves += 1
    for name, (lo, hi) in {"left_heavy": (z - m, z - 1), "right_heavy": (z + 1, z + m)}.items():
        if name not in skip and max(1, lo) <= min(size, hi):
            _heavy(name, before, after, z, max(1, lo), min(size, hi), set_range, present, log if logged else None, all_occurrences)

    if not logged:
        if op == "del":
            del now[z - 1]
            now = [p - 1 if p > z else p for p in now]
        return new, now, Log()
    log.active = sum(now[node - 1] != parent for node, parent in old.items())
    log.touched = len(set().union(*classes.values()))
    log.members |= {name: classes[name] for name in ("super_light", "light")}
    log.sizes = {name: len(nodes) for name, nodes in classes.items()}
    log.factor_probes, log.match_probes = len(before.memory) + len(after.memory), before.matches + after.matches
    if op == "del":
        del now[z - 1]
        now = [p - 1 if p > z else p for p in now]
    return new, now, log


def _light(t: OnDemand, z: int, m: int, size: int) -> Iterator[int]:
    """Nodes of the leftmost later copies of the windows z - a .. z + b.

    A window's first copy lies behind that of the window one symbol shorter on the right, and not before the place left of
    that of the window one symbol shorter on the left, so every search goes on from there; a window has none if those have none.
    """
    tail, shorter, none = t.pos(z + 1) - 1, [], m + 1
    for a in range(0, min(m, z - 1) + 1):
        low, last, found_at = t.pos(z - a), tail, []
        for b in range(0, m + 1):
            if z + b > size:
                break
            high = t.pos(z + b) if not (t.gap == z and b == 0) else z - 1
            if high < low:
                found_at.append(tail)
                continue
            t.matches += 1
            found = -1
            if b < none:
                found = t.text.find(t.text[low - 1 : high], max(last, shorter[b] - 1 if b < len(shorter) else tail))
            if found < 0:
                none = b
                break
            last = found
            found_at.append(found)
            yield t.node(found + 1)
        shorter = found_at


def _heavy(name: str, before: OnDemand, after: OnDemand, z: int, lo: int, hi: int, set_range, present, log: Log | None, every: bool) -> None:
    """Occurrences of the block in the unchanged pieces; per cluster three witnesses, per witness a clean partition."""
    anchor = before.text[before.pos(lo) - 1 : before.pos(hi)]
    width, period = len(anchor), smallest_period(anchor)
    done, counted = {}, {}  # how far the intervals from a node on are set already: blocks that lie close share most of theirs
    for piece_low, piece_high in ((1, z - 1), (z + 1, max(before.node(len(before.text)), after.node(len(after.text))))):
        if piece_high - piece_low + 1 < width:
            continue
        starts = [before.node(x + 1) for x in occurrences(before.text, anchor, before.pos(piece_low) - 1, before.pos(piece_high))]
        before.matches += 1
        groups = clusters(starts, period)
        if log is not None:
            log.clusters += len(groups)
        for first, last in groups:
            if every:
                pairs = [(i, i + width - 1) for i in range(first, last + 1, period)]
            else:
                end = last + width - 1
                text, at = before.text, before.pos(end)
                while end < piece_high and text[at] == text[at - period]:
                    end, at = end + 1, at + 1
                pairs = [(first, first + width - 1), (last, end)]
                if first + period <= last:
                    pairs.insert(1, (first + period, first + period + width - 1))
                begin, at = first, before.pos(first) - 1
                while begin > piece_low and text[at - 1] == text[at - 1 + period]:
                    begin, at = begin - 1, at - 1
            for i, j in pairs:
                lists = critical_lists(before, after, i, j)
                if log is None:
                    _set_clean(lists, i, done, set_range, present, name, after)
                    continue
                log.critical += sum(map(len, lists))
                beyond = all(t.reach(t.pos(i)) > t.pos(j) for t in (before, after))
                if not every:
                    part = "near" if begin - 1 <= z <= end + 1 else "end" if (i, j) == (last, end) else "starts"
                    log.critical_parts[part] += sum(map(len, lists))
                for a, b in clean_intervals(lists, i):
                    head = a if present(a) else a + 1
                    if head > b or not present(head):
                        continue
                    log.moves += 1
                    if (fresh := done.get(head, head)) <= b:
                        done[head], parent = b + 1, after.node(after.reach(after.pos(head)))
                        set_range(name, fresh, b, parent)
                    if beyond and (fresh := counted.get(head, head)) <= b:
                        counted[head] = b + 1
                        log.members[name].update(range(fresh, b + 1))


def _set_clean(lists: list[list[int]], i: int, done: dict[int, int], set_range, present, name: str, after: OnDemand) -> None:
    for a, b in clean_intervals(lists, i):
        head = a if present(a) else a + 1
        if head <= b and present(head) and (fresh := done.get(head, head)) <= b:
            done[head] = b + 1
            set_range(name, fresh, b, after.node(after.reach(after.pos(head))))


def critical_lists(before: OnDemand, after: OnDemand, i: int, j: int) -> list[list[int]]:
    """Nodes of the critical indices of the block i..j in the old and in the new string."""
    return [[t.node(x) for x in t.critical(t.pos(i), t.pos(j))] for t in (before, after)]


def clean_intervals(lists: list[list[int]], i: int) -> list[tuple[int, int]]:
    """Intervals up to i inside which no parent changes, in either string; they begin where both lists have begun."""
    floor = max(min(x) for x in lists)
    cuts = sorted({x for part in lists for x in part if floor <= x <= i})
    return list(zip(cuts, [*[c - 1 for c in cuts[1:]], cuts[-1]], strict=True))


def _on_axis(op: str, z: int, before: np.ndarray, after: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Parents of the old and of the new string on the common axis (0: a node that the string lacks)."""
    if op == "ins":
        return np.insert(before + (before >= z), z - 1, 0), after
    if op == "del":
        return np.where(before == z, z + 1, before), np.insert(after + (after >= z), z - 1, 0)
    return before, after


def transition_known(s: str, op: str, z: int, symbol: str | None, m: int, before: np.ndarray, after: np.ndarray, all_occurrences: bool = False, touched: bool = False) -> tuple[str, np.ndarray] | np.ndarray:
    """``transition`` without its log, where the factors of both strings are known: the new string and its parents.
    ``touched``: which nodes it sets, instead.

    Narrow blocks occur at so many places that their critical lists ask for most factors. The classes are the same; the
    lists of all blocks are found together, and together they cover the nodes from where the later list begins up to the block.
    """
    new = apply_edit(s, op, z, symbol)
    size = max(len(s), len(new))
    old, fresh = OnDemand(s, z if op == "ins" else None, []), OnDemand(new, z if op == "del" else None, [])
    now, then = _on_axis(op, z, before, after)
    change = np.zeros(size + 2, np.int64)  # where covered ranges of nodes begin and end
    change[max(1, z - m - 1)] += 1
    change[min(z, size) + 1] -= 1
    near = np.array([node for t in (old, fresh) for node in _light(t, z, m, size)], np.int64)
    text = codes(s)
    end_node = max(old.node(len(s)), fresh.node(len(new)))
    for lo, hi in ((z - m, z - 1), (z + 1, z + m)):
        lo, hi = max(1, lo), min(size, hi)
        if lo <= hi:
            anchor = s[old.pos(lo) - 1 : old.pos(hi)]
            for piece in ((1, z - 1), (z + 1, end_node)):
                if anchor and piece[1] - piece[0] + 1 >= len(anchor):
                    i, j = _blocks(text, codes(anchor), smallest_period(anchor), piece, old.pos(piece[0]) - piece[0], all_occurrences)
                    floor = np.maximum(_first_beyond(i, j, before, old.gap), _first_beyond(i, j, after, fresh.gap))
                    np.add.at(change, floor, 1)
                    np.add.at(change, i + 1, -1)
    covered = np.cumsum(change)[1 : size + 1] > 0
    covered[near - 1] = True
    if op == "ins":
        covered[z - 1] = True
    if touched:
        return covered
    now = np.where(covered, then, now)
    if op == "del":
        now = np.delete(now, z - 1)
        now -= now > z
    return new, now


def _blocks(text: np.ndarray, anchor: np.ndarray, period: int, piece: tuple[int, int], shift: int, every: bool) -> tuple[np.ndarray, np.ndarray]:
    """First and last nodes of the block's witnesses inside a piece: three of each cluster, or every occurrence."""
    width, low, high = len(anchor), piece[0] + shift - 1, piece[1] + shift
    hit = text[low : high - width + 1] == anchor[0]
    for x in range(1, width):
        hit &= text[low + x : high - width + 1 + x] == anchor[x]
    starts = np.flatnonzero(hit) + piece[0]
    if every or not len(starts):
        return starts, starts + width - 1
    apart = np.diff(starts) != period
    first, last = starts[np.append(True, apart)], starts[np.append(apart, True)]
    breaks = np.append(np.flatnonzero(text[period:] != text[:-period]) + period, len(text)) if period < len(text) else np.array([len(text)])
    end = last + width - 1
    end = np.minimum(breaks[np.searchsorted(breaks, end + shift)] - shift, piece[1])
    second = first[first + period <= last] + period
    return np.concatenate([first, second, last]), np.concatenate([first + width - 1, second + width - 1, end])


def _first_beyond(i: np.ndarray, j: np.ndarray, parents: np.ndarray, gap: int | None) -> np.ndarray:
    """The node where the critical list of each block i..j ends: the first whose parent lies behind j, i itself if none does."""
    if gap is not None:
        i, j = i - (i > gap), j - (j > gap)
    found = np.minimum(i, np.searchsorted(parents, j, "right") + 1)
    return found if gap is None else found + (found >= gap)


def parents_of(s: str) -> list[int]:
    return [i + 1 + max(1, x) for i, x in enumerate(lpf(s))]


def parents_of_many(texts: list[str]) -> Iterator[list[int]]:
    """Parents of every text, by one suffix order for all."""
    return (x.tolist() for x in parent_arrays(texts))


def parent_arrays(texts: list[str]) -> Iterator[np.ndarray]:
    return (np.arange(1, len(x) + 1) + np.maximum(x, 1) for x in lpf_many(texts))


def phrase_count(parents: list[int] | np.ndarray) -> int:
    at, count, n = 1, 0, len(parents)
    next_ = parents.item if isinstance(parents, np.ndarray) else parents.__getitem__
    while at <= n:
        at, count = next_(at - 1), count + 1
    return count
