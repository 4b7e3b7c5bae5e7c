"""Strings under edits: replay by transition, by rebuild, and on demand; classes, costs, sliding windows."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from itertools import islice

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phraseloom.functions import kernels as k
from phraseloom.functions import transition as t
from phraseloom.operators.per_string import flat_map, flat_map_groups

COUNTS = "sid long, seq long, n long, phrases long"


def edit_rows(strings: DataFrame, edits: int = 3, kinds: tuple[str, ...] = ("sub", "ins", "del"), alphabet: str = "aeinrst") -> DataFrame:
    """The edits of ``edit_script``, one a row: ``(sid, body, seq, op, pos, sym)``."""
    rows = edit_script(strings, edits, kinds, alphabet).select("sid", "body", F.explode("ops").alias("e"))
    return rows.select("sid", "body", *[F.col(f"e.{c}").alias(c) for c in ("seq", "op", "pos", "sym")])


def edit_script(strings: DataFrame, edits: int = 3, kinds: tuple[str, ...] = ("sub", "ins", "del"), alphabet: str = "aeinrst") -> DataFrame:
    """The edits of each string in order, as arithmetic on ``sid`` and their number fixes them: ``(sid, body, ops)``.

    The position is taken modulo the shortest length that the edits can reach.
    """
    n = F.greatest(F.char_length("body") - edits, F.lit(1)).cast("long")

    def entry(q):
        op = F.element_at(F.array(*map(F.lit, kinds)), (F.pmod(q, F.lit(len(kinds))) + 1).cast("int"))
        sym = F.substring(F.lit(alphabet), (F.pmod(F.col("sid") + q, F.lit(len(alphabet))) + 1).cast("int"), F.lit(1))
        return F.struct(q.alias("seq"), op.alias("op"), (1 + F.pmod(7 * F.col("sid") + 13 * q, n)).alias("pos"), sym.alias("sym"))

    numbers = F.sequence(F.lit(1).cast("long"), F.lit(edits).cast("long"))
    return strings.where(F.char_length("body") > edits).select("sid", "body", F.transform(numbers, entry).alias("ops"))


#: Blocks up to this width occur so often that a suffix order of the new strings costs less than searches.
NARROW = 4


def _rebuilt(held: list[tuple]) -> Iterator[list[np.ndarray]]:
    """For each ``(sid, body, ops)`` the parents after every edit, by one suffix order for all versions of all strings."""
    texts = []
    for _, s, ops in held:
        for e in ops:
            s = t.apply_edit(s, e["op"], e["pos"], e["sym"])
            texts.append(s)
    parents = t.parent_arrays(texts)
    for _, _, ops in held:
        yield list(islice(parents, len(ops)))


def _with_parents(scripts: DataFrame, kernel: Callable[[int, str, list[dict], list[int]], Iterable[tuple]], schema: str) -> DataFrame:
    """``kernel`` on the id, the string, its edits, and the string's parents before them; one suffix order for a group of strings."""

    def run(held: list[tuple]) -> Iterator[tuple]:
        for (sid, s, ops), parents in zip(held, t.parents_of_many([s for _, s, _ in held]), strict=True):
            yield from kernel(sid, s, ops, parents)

    return flat_map_groups(scripts.select("sid", "body", "ops"), run, schema)


def replay_transition(scripts: DataFrame, m: int | None = None, all_occurrences: bool = False) -> DataFrame:
    """Phrase count after every edit, the forest kept by transitions."""
    if m is not None and m <= NARROW:
        return _replay_narrow(scripts, m, all_occurrences)

    def kernel(sid: int, s: str, ops: list[dict], parents: list[int]) -> Iterator[tuple]:
        for e in ops:
            s, parents, _ = t.transition(s, e["op"], e["pos"], e["sym"], m, parents, all_occurrences, logged=False)
            yield sid, e["seq"], len(s), t.phrase_count(parents)

    return _with_parents(scripts, kernel, COUNTS)


def _replay_narrow(scripts: DataFrame, m: int, all_occurrences: bool) -> DataFrame:
    """The same for narrow blocks: the previous-factor queries on all new strings of a group are answered by one suffix order."""

    def run(held: list[tuple]) -> Iterator[tuple]:
        kept = list(t.parent_arrays([s for _, s, _ in held]))
        for (sid, s, ops), parents, rebuilt in zip(held, kept, _rebuilt(held), strict=True):
            for e, after in zip(ops, rebuilt, strict=True):
                s, parents = t.transition_known(s, e["op"], e["pos"], e["sym"], m, parents, after, all_occurrences)
                yield sid, e["seq"], len(s), t.phrase_count(parents)

    return flat_map_groups(scripts.select("sid", "body", "ops"), run, COUNTS)


def replay_rebuild(scripts: DataFrame) -> DataFrame:
    """The baseline that builds all parents of the whole string again after every edit."""

    def run(held: list[tuple]) -> Iterator[tuple]:
        for (sid, _, ops), rebuilt in zip(held, _rebuilt(held), strict=True):
            for e, parents in zip(ops, rebuilt, strict=True):
                yield sid, e["seq"], len(parents), t.phrase_count(parents)

    return flat_map_groups(scripts.select("sid", "body", "ops"), run, COUNTS)


def replay_on_demand(scripts: DataFrame) -> DataFrame:
    """The baseline that keeps no forest: as many previous-factor queries as there are phrases, at query time."""

    def run(held: list[tuple]) -> Iterator[tuple]:
        for number in range(max((len(ops) for _, _, ops in held), default=0)):
            held = [(sid, t.apply_edit(s, *(ops[number][c] for c in ("op", "pos", "sym"))), ops) for sid, s, ops in held if number < len(ops)]
            for (sid, s, ops), phrases in zip(held, k.parse_many([s for _, s, _ in held]), strict=True):
                yield sid, ops[number]["seq"], len(s), len(phrases)

    return flat_map_groups(scripts.select("sid", "body", "ops"), run, COUNTS)


def edit_costs(scripts: DataFrame, m: int | None = None, all_occurrences: bool = False) -> DataFrame:
    """Per edit: active indices, class sizes, moves, critical entries, clusters, probes, and equality with a rebuild."""

    def run(held: list[tuple]) -> Iterator[tuple]:
        for (sid, s, ops), parents, rebuilt in zip(held, t.parents_of_many([s for _, s, _ in held]), _rebuilt(held), strict=True):
            for e, again in zip(ops, rebuilt, strict=True):
                s, parents, log = t.transition(s, e["op"], e["pos"], e["sym"], m, parents, all_occurrences)
                z = log.sizes
                yield sid, e["seq"], len(s), log.active, z["super_light"], z["light"], z["left_heavy"], z["right_heavy"], log.touched, log.moves, log.critical, log.clusters, log.factor_probes, log.match_probes, parents == again.tolist()

    return flat_map_groups(scripts.select("sid", "body", "ops"), run, "sid long, seq long, n long, active long, super_light long, light long, left_heavy long, right_heavy long, touched long, moves long, critical long, clusters long, factor_probes long, match_probes long, equals_rebuild boolean")


def active_indices(old: DataFrame, new: DataFrame) -> DataFrame:
    """Places whose reach differs between two tables ``(sid, pos, reach)`` of strings of one length."""
    joined = old.select("sid", "pos", F.col("reach").alias("before")).join(new.select("sid", "pos", F.col("reach").alias("after")), ["sid", "pos"], "full")
    return joined.where(~F.col("before").eqNullSafe(F.col("after")))


def sliding_counts(symbols: DataFrame, size: int) -> DataFrame:
    """Phrases of the last ``size`` symbols after each one: rows ``(sid, body)`` hold a key's whole ordered string."""

    def kernel(sid: int, s: str) -> list[tuple]:
        return [(sid, i, min(i, size), sum(1 for _ in k.parse(s[max(0, i - size) : i]))) for i in range(1, len(s) + 1)]

    return flat_map(symbols.select("sid", "body"), kernel, "sid long, ord long, n long, phrases long")


def growth_counts(strings: DataFrame) -> DataFrame:
    """Phrases after each appended part: rows ``(sid, parts)``; the greedy parse of a prefix is kept, only its end is redone."""

    def kernel(sid: int, parts: list[str]) -> list[tuple]:
        out, text, phrases = [], "", []
        for turn, part in enumerate(parts):
            text = text + ("\n" if turn else "") + part
            if phrases:
                phrases.pop()  # the last phrase may grow
            i = phrases[-1] if phrases else 0
            while i < len(text):
                i += max(1, k.earlier_factor(text, i)[0])
                phrases.append(i)
            out.append((sid, turn, len(text), len(phrases)))
        return out

    return flat_map(strings.select("sid", "parts"), kernel, "sid long, turn long, n long, phrases long")


def query_mix(scripts: DataFrame) -> DataFrame:
    """After each edit the three phrase queries, answered on the kept forest: phrase number ``ord``, the phrase that holds ``pos``, and the parse length of the prefix that ends there."""

    def kernel(sid: int, s: str, ops: list[dict], parents: list[int]) -> list[tuple]:
        out = []
        for e in ops:
            s, parents, _ = t.transition(s, e["op"], e["pos"], e["sym"], None, parents, logged=False)
            asked, wanted = 1 + (7 * sid + 3 * e["seq"]) % len(s), 1 + (sid + e["seq"]) % 7
            at, count, lo, selected, found = 1, 0, 0, None, None
            while at <= len(s):
                lo, at, count = at, parents[at - 1], count + 1
                selected = (lo, at - 1) if count == wanted else selected
                found = (lo, at - 1, count) if lo <= asked < at else found
            out.append((sid, e["seq"], wanted, *(selected or (None, None)), asked, *found))
        return out

    return _with_parents(scripts, kernel, "sid long, seq long, ord long, ord_lo long, ord_hi long, pos long, pos_lo long, pos_hi long, prefix_phrases long")


def dynamic_positions(scripts: DataFrame) -> DataFrame:
    """After each edit the node of the edited number, its number again, and whether all nodes keep their order (numbers of the nodes to its sides)."""

    def kernel(sid: int, s: str, ops: list[dict]) -> list[tuple]:
        out, order, n = [], k.Positions(len(s)), len(s)
        for e in ops:
            if e["op"] == "ins":
                order.insert(e["pos"])
                n += 1
            elif e["op"] == "del":
                order.delete(e["pos"])
                n -= 1
            pos = min(e["pos"], n)
            node = order.node(pos)
            sides = [order.pos(order.node(x)) == x for x in (max(1, pos - 1), pos, min(n, pos + 1))]
            out.append((sid, e["seq"], n, node, order.pos(node), all(sides)))
        return out

    return flat_map(scripts.select("sid", "body", "ops"), kernel, "sid long, seq long, n long, node long, pos long, consistent boolean")
