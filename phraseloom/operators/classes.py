"""Classes of the indices around a substitution, critical indices, and clean intervals, as tables.

Rows are scripts ``(sid, body, ops)`` of substitutions, so that places of the old and the new string are the same.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from phraseloom.functions import transition as t
from phraseloom.operators.per_string import flat_map

CLASSES = ("super_light", "light", "left_heavy", "right_heavy")


def _edits(s: str, ops: list[dict], m: int | None, every: bool = False):
    """For each edit: number, old and new parents, cost log, new string."""
    parents = t.parents_of(s)
    for e in ops:
        old = parents
        s, parents, log = t.transition(s, e["op"], e["pos"], e["sym"], m, parents, every)
        yield e, old, parents, log, s


def index_classes(scripts: DataFrame, m: int | None = None, all_occurrences: bool = False) -> DataFrame:
    """Every index whose parent changes, with both parents and the classes whose update sets it."""

    def kernel(sid: int, s: str, ops: list[dict]) -> list[tuple]:
        out = []
        for e, old, new, log, _ in _edits(s, ops, m, all_occurrences):
            out += [(sid, e["seq"], i, a, b, *(i in log.members[c] for c in CLASSES)) for i, (a, b) in enumerate(zip(old, new, strict=True), 1) if a != b]
        return out

    return flat_map(scripts.select("sid", "body", "ops"), kernel, "sid long, seq long, pos long, before long, after long, " + ", ".join(f"{c} boolean" for c in CLASSES))


def updated(scripts: DataFrame, name: str, m: int | None = None) -> DataFrame:
    """Every index that the update of one class sets, changed or not, and its parent afterwards."""

    def kernel(sid: int, s: str, ops: list[dict]) -> list[tuple]:
        return [(sid, e["seq"], i, new[i - 1]) for e, _, new, log, _ in _edits(s, ops, m) for i in sorted(log.members[name])]

    return flat_map(scripts.select("sid", "body", "ops"), kernel, "sid long, seq long, pos long, parent long")


def transition_log(scripts: DataFrame, m: int | None = None) -> DataFrame:
    """Moves, clusters, and the lengths of the critical lists: of first and second witnesses, of run ends, and of clusters whose run lies at the edit."""

    def kernel(sid: int, s: str, ops: list[dict]) -> list[tuple]:
        out = []
        for e, _, _, log, new in _edits(s, ops, m):
            part = log.critical_parts
            out.append((sid, e["seq"], len(new), log.moves, log.clusters, log.critical, part["starts"], part["end"], part["near"]))
        return out

    return flat_map(scripts.select("sid", "body", "ops"), kernel, "sid long, seq long, n long, moves long, clusters long, critical long, critical_starts long, critical_end long, critical_near long")


def critical_indices(blocks: DataFrame) -> DataFrame:
    """Critical indices of the block i..j: rows ``(sid, body, i, j)`` give ``(sid, pos)``."""
    return flat_map(blocks.select("sid", "body", "i", "j"), lambda sid, s, i, j: [(sid, x) for x in sorted(set(t.OnDemand(s, None).critical(i, j)))], "sid long, pos long")


def clean_intervals(blocks: DataFrame) -> DataFrame:
    """Clean intervals of the block i..j over an edit: rows ``(sid, body, ops, i, j)`` with one substitution give ``(sid, lo, hi, before, after)``."""

    def kernel(sid: int, s: str, ops: list[dict], i: int, j: int) -> list[tuple]:
        old, new = t.OnDemand(s, None), t.OnDemand(t.apply_edit(s, ops[0]["op"], ops[0]["pos"], ops[0]["sym"]), None)
        return [(sid, a, b, old.reach(a), new.reach(a)) for a, b in t.clean_intervals(t.critical_lists(old, new, i, j), i)]

    return flat_map(blocks.select("sid", "body", "ops", "i", "j"), kernel, "sid long, lo long, hi long, before long, after long")
