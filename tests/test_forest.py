"""Depths and ancestors of the reach forest stay inside each string's row: no join, so nothing is gathered for a broadcast."""

import random

from phraseloom.functions import kernels as k
from phraseloom.operators import phrases as ph


def test_forest_without_joins(spark):
    r = random.Random(8)
    strings = {1: "a", 2: "abracadabra", 3: "a" * 40, 4: "".join(r.choice("ab") for _ in range(300))}
    parents = {sid: [i + 1 + max(1, x) for i, x in enumerate(k.lpf(s))] for sid, s in strings.items()}
    table = spark.createDataFrame([(sid, pos, up) for sid, ups in parents.items() for pos, up in enumerate(ups, 1)], "sid long, pos long, reach long")
    depths, above = {}, {steps: {} for steps in (1, 2, 3, 6)}
    for sid, ups in parents.items():
        for node in range(1, len(ups) + 1):
            path = [node]
            while path[-1] <= len(ups):
                path.append(ups[path[-1] - 1])
            depths[sid, node] = len(path) - 1
            for steps, found in above.items():
                if len(path) > steps:
                    found[sid, node] = path[steps]
    got = ph.forest_depths(table, 300)
    assert {(r["sid"], r["node"]): r["depth"] for r in got.collect()} == depths
    for steps, want in above.items():
        hops = ph.forest_ancestor(table, steps)
        assert {(r["sid"], r["node"]): r["ancestor"] for r in hops.collect()} == want
    for rows in (got, hops):
        assert "Join" not in rows._jdf.queryExecution().optimizedPlan().toString()
