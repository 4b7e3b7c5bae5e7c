"""Queries that take whole documents, conversations, or the whole event string."""

import itertools
import random

import duckdb
import pytest

import __spark_entry__ as entry
from phraseloom.functions import kernels as k

DATA = "/root/testdata/sf0.001"
QUERIES = entry.queries()


def test_root_path_reads_every_event(spark):
    s = "".join(x for (x,) in duckdb.sql(f"SELECT substr(event_type, 1, 1) FROM '{DATA}/events.parquet' ORDER BY event_id").fetchall())
    got = [tuple(x) for x in QUERIES["huge_root_path_events"](spark, DATA).orderBy("ord").collect()]
    assert got == [(o, lo, hi) for o, (lo, hi, _) in enumerate(k.parse(s), 1)] and got[-1][2] == len(s) == 1000


@pytest.mark.parametrize(("of", "text"), [("documents", "SELECT doc_id, text FROM '{}/documents.parquet'"), ("conversations", "SELECT conv_id, string_agg(text, chr(10) ORDER BY turn) FROM '{}/conversations.parquet' GROUP BY conv_id")])
def test_edits_of_whole_strings(spark, of, text):
    rows = [(key, len(s)) for key, s in duckdb.sql(text.format(DATA)).fetchall() if len(s) > 3]
    want = sorted(map(tuple, QUERIES[f"baseline_rebuild_{of}"](spark, DATA).collect()))
    assert [r[:3] for r in want] == sorted((key, q, n + (0, 1, 0, 0)[q]) for key, n in rows for q in (1, 2, 3))  # ins, del, sub
    for name in (f"edit_replay_mixed_{of}", f"baseline_on_demand_{of}", f"heavy_all_occurrences_{of}"):
        assert sorted(map(tuple, QUERIES[name](spark, DATA).collect())) == want
    costs = QUERIES[f"edit_costs_{of}"](spark, DATA).collect()
    assert len(costs) == len(want) and all(r["equals_rebuild"] for r in costs)


def test_internal_match_grows(spark):
    docs = {key: s for key, s in duckdb.sql(f"SELECT doc_id, text FROM '{DATA}/documents.parquet' WHERE text <> ''").fetchall()}
    found = {}
    for r in QUERIES["internal_match_grown"](spark, DATA).where("kind = 'document'").collect():
        found.setdefault(r["sid"], []).extend(range(r["first"], r["last"] + 1, r["step"]))
    for key, s in docs.items():
        size, low = max(1, len(s) // 16), len(s) // 2
        start = max(0, low - size // 2)
        assert sorted(found[key]) == [i + 1 for i in range(start, min(len(s), start + 2 * size) - size + 1) if s[i : i + size] == s[low : low + size]]


def test_active_places_of_turns_and_copies(spark):
    turns = duckdb.sql(f"SELECT conv_id, turn, text FROM '{DATA}/conversations.parquet' ORDER BY ALL").fetchall()
    docs = duckdb.sql(f"SELECT doc_id, text FROM '{DATA}/documents.parquet' WHERE length(text) >= 40 ORDER BY doc_id").fetchall()
    heads, copies = {}, []
    for key, s in docs:
        copies += [(heads[s[:40]], (s,))] if s[:40] in heads else []
        heads[s[:40]] = (key, s)
    pairs = {
        "turns": {(a[0] << 32) + a[1]: (a[2], b[2]) for a, b in zip(turns, turns[1:]) if a[0] == b[0]},
        "documents": {key: (s, t) for (key, s), (t,) in copies},
    }
    for kind, want in pairs.items():
        got = {r["sid"]: r["active"] for r in QUERIES[f"near_copy_active_{kind}"](spark, DATA).collect()}
        reach = {key: [k.reach(k.lpf(x)) for x in pair] for key, pair in want.items()}
        assert got == {key: sum(x != y for x, y in zip(a, b)) + abs(len(a) - len(b)) for key, (a, b) in reach.items()}


def test_fewest_phrases_over_all_factorizations():
    r = random.Random(5)
    for _ in range(60):
        s = "".join(r.choice("ab") for _ in range(r.randint(1, 9)))
        least = len(s)
        for cuts in itertools.product((0, 1), repeat=len(s) - 1):
            ends = [i + 1 for i, c in enumerate(cuts) if c] + [len(s)]
            spans = list(zip([0, *ends], ends))
            if all(b - a == 1 or s.find(s[a:b]) < a for a, b in spans):
                least = min(least, len(spans))
        assert k.fewest_phrases(s) == least == sum(1 for _ in k.parse(s))


def test_skyline_sizes_by_definition():
    r = random.Random(6)
    for _ in range(40):
        s = "".join(r.choice("ab") for _ in range(r.randint(2, 30)))
        places, total = k.occurrences(s, s[:1]), 0
        for at, i in enumerate(places):
            pairs = {(k.agreement_back(s, j, i), k.agreement(s, j, i)) for j in places[:at]}
            total += sum(not any(x != y and x[0] <= y[0] and x[1] <= y[1] for y in pairs) for x in pairs)
        assert k.skyline_sizes(s, places) == (len(places) * (len(places) - 1) // 2, total)


def test_positions_follow_a_plain_list():
    r = random.Random(7)
    for n in (1, 5, 60):
        order, plain = k.Positions(n), list(range(1, n + 1))
        for _ in range(300):
            if r.random() < 0.6 or len(plain) < 2:
                at = r.randint(1, len(plain) + 1)
                plain.insert(at - 1, order.insert(at))
            else:
                at = r.randint(1, len(plain))
                assert order.delete(at) == plain.pop(at - 1)
            assert [order.node(i) for i in range(1, len(plain) + 1)] == plain and [order.pos(x) for x in plain] == list(range(1, len(plain) + 1))


def test_query_mix_and_positions_of_documents(spark):
    edits = {(r["sid"], r["seq"]): r for r in QUERIES["query_mix"](spark, DATA).collect()}
    from phraseloom.functions.transition import apply_edit
    from phraseloom.workloads import _long_scripts

    for row in _long_scripts(spark, DATA).collect():
        s = row["body"]
        for e in row["ops"]:
            s = apply_edit(s, e["op"], e["pos"], e["sym"])
            got, phrases = edits[row["sid"], e["seq"]], [(lo, hi) for lo, hi, _ in k.parse(s)]
            assert (got["ord_lo"], got["ord_hi"]) == (phrases[got["ord"] - 1] if got["ord"] <= len(phrases) else (None, None))
            assert phrases[got["prefix_phrases"] - 1] == (got["pos_lo"], got["pos_hi"]) and got["pos_lo"] <= got["pos"] <= got["pos_hi"]
    rows = QUERIES["dynamic_positions"](spark, DATA).collect()
    assert len(rows) == len(edits) and all(r["consistent"] for r in rows)
    pairs = QUERIES["relative_phrases"](spark, DATA).collect()
    assert len(pairs) == QUERIES["passage_occurrences"](spark, DATA).count() and all(r["phrases"] <= r["alone"] for r in pairs)
