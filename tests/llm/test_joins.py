"""Near duplicates and line deduplication against brute force."""

import random
import re
from collections import defaultdict

import pytest

from phraseloom.llm import byte_words as bw
from phraseloom.llm import jaccard_join, line_dedup

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def shingle_set(text, size):
    words = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(words[i : i + size]) for i in range(len(words) - size + 1)} if len(words) >= size else ({tuple(words)} if words else set())


def near_copies(n, seed):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("aeioukmnrst") for _ in range(r.randint(1, 7)))
    base = [[word() for _ in range(r.choice([3, 20, 60, 120]))] for _ in range(max(2, n // 12))]
    shared = " ".join(word() for _ in range(40))
    out = []
    for i in range(n):
        words = list(r.choice(base))
        for _ in range(r.choice([0, 0, 1, 1, 2, 3, 6])):
            words[r.randrange(len(words))] = word()
        out.append((i, " ".join(words) + (f"\n{shared}" if r.random() < 0.4 else "")))
    return out


def brute_components(rows, size, percent):
    sets = [shingle_set(t, size) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                root[max(find(a), find(b))] = min(find(a), find(b))
    least = defaultdict(list)
    for i in range(len(rows)):
        least[find(i)].append(rows[i][0])
    name = {k: min((x for x in v if x is not None), default=None) for k, v in least.items()}
    return [(rows[i][0], len(sets[i]), name[find(i)] if sets[i] else rows[i][0]) for i in range(len(rows))]


@pytest.mark.parametrize(("seed", "size", "percent"), [(1, 4, 85), (2, 5, 80)])
def test_components_match_brute_force(spark, seed, size, percent):
    rows = near_copies(150, seed)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    found = jaccard_join.near_duplicates(df, size, percent).collect()
    assert sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in found) == sorted(brute_components(rows, size, percent))
    kept = {r["doc_id"] for r in jaccard_join.keep_one_per_group(df, size, percent).collect()}
    assert kept == {c for _, _, c in brute_components(rows, size, percent)}


def test_edges(edges, edge_rows, nothing):
    found = jaccard_join.near_duplicates(edges)
    rows = sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in found.collect()), key=repr)
    assert rows == sorted(brute_components([t[:2] for t in edge_rows], 4, 85), key=repr)
    kept = jaccard_join.keep_one_per_group(edges, 4, 85)
    assert kept.columns == edges.columns
    ids = sorted((r["doc_id"] for r in kept.collect()), key=repr)
    assert ids.count(1) == 1 and 2 not in ids and ids.count(4) == 1
    assert all(k in ids for k in (5, 6, 7, 8, 9, 10, 11, 12))  # without words nothing is a copy of anything
    assert jaccard_join.near_duplicates(nothing).count() == 0 and jaccard_join.keep_one_per_group(nothing).count() == 0


def test_words_and_shingles_of_bytes():
    import pyarrow as pa

    texts = ["", "a", "a b", " a  b\tc\nd ", "A B c D e f", None, "é É 日本　x", "x" * 50 + " y"]
    for table, pattern in ((bw.NOT_SPACE, WORD), (bw.ALNUM, re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"))):
        want = [pattern.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) for t in texts]
        for most in (8 << 20, 7):
            values, at = bw.words(*bw.buffers(pa.array(texts)), table, most)
            assert [int(n) for n in at[1:] - at[:-1]] == [len(w) for w in want]
            names = defaultdict(set)
            for value, word in zip(values.tolist(), (w for ws in want for w in ws), strict=True):
                names[word].add(value)
            assert all(len(v) == 1 for v in names.values()) and len({min(v) for v in names.values()}) == len(names)


def brute_lines(rows, percent):
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0))
    seen, gone = [], defaultdict(list)
    for key, text in order:
        if text is None:
            continue
        for pos, line in enumerate(text.split("\n")):
            words = frozenset(WORD.findall(line.lower()))
            if not words:
                continue
            if any(100 * len(words & s) >= percent * len(words | s) for s in seen):
                gone[key].append(pos)
            seen.append(words)
    return {key: gone[key] for key, text in rows}


@pytest.mark.parametrize(("frequent", "percent"), [(511, 80), (3, 80), (1, 50), (3, 30)])
def test_lines_match_brute_force(spark, frequent, percent, monkeypatch):
    """With a low frequency limit nearly all words are frequent, so that pair keys, leaders, and the last round work."""
    monkeypatch.setattr(line_dedup, "FREQUENT", frequent)
    r = random.Random(frequent)
    lines = [" ".join("".join(r.choice("abcdefg") for _ in range(r.randint(1, 3))) for _ in range(r.choice([1, 2, 5, 10, 30, 130]))) for _ in range(25)]

    def changed(line):
        words = line.split(" ")
        for _ in range(r.choice([0, 0, 1, 1, 2, 4])):
            words[r.randrange(len(words))] = r.choice("abcdefg") * r.randint(1, 5)
        return " ".join(words)

    rows = [(i, "\n".join(changed(r.choice(lines)) for _ in range(r.randint(1, 8)))) for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_lines(rows, percent)
    assert {x["doc_id"]: x["removed_lines"] for x in line_dedup.line_report(df, percent).collect()} == want
    texts = {x["doc_id"]: x["text"] for x in line_dedup.deduplicate_lines(df, percent).collect()}
    assert texts == {k: "\n".join(line for p, line in enumerate(t.split("\n")) if p not in want[k]) for k, t in rows}


def test_one_common_frequent_word_can_do(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "FREQUENT", 1)
    rows = [(0, "a\na b\na zz\na yy")]
    found = line_dedup.line_report(spark.createDataFrame(rows, "doc_id long, text string"), 50).first()
    assert found["removed_lines"] == brute_lines(rows, 50)[0] == [1, 2, 3]


def test_line_edges(edges, edge_rows, nothing):
    out = line_dedup.deduplicate_lines(edges)
    assert out.columns == edges.columns and out.count() == len(edge_rows)
    by_key = defaultdict(list)
    for r in out.collect():
        by_key[r["doc_id"]].append(r["text"])
    assert by_key[1] == [edge_rows[0][1]] and by_key[2] == [""] and by_key[5] == [None] and by_key[6] == [""] and by_key[7] == [" \n\t \n"]
    assert by_key[14] == [""]  # all its lines with words are earlier ones
    assert len(by_key[4]) == 2 and len(set(by_key[4])) == 1  # equal rows are one document
    assert line_dedup.line_report(nothing).count() == 0 and line_dedup.deduplicate_lines(nothing).count() == 0


def test_words_and_pairs_of_a_line_come_from_one_generator(spark):
    """Alone, the pairs would grow with every word that becomes frequent, and the lines would be read twice."""
    nodes = spark.createDataFrame([], "id long, doc long, m int, sig long, wide array<long>, gone boolean, prefix array<long>")
    plan = line_dedup._entries(nodes, 80)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Generate ") == 1


def test_a_filter_of_wanted_hashes_needs_no_join(spark, monkeypatch):
    from phraseloom.llm import common

    plans = []
    monkeypatch.setattr(common, "durable", lambda df: plans.append(df._jdf.queryExecution().optimizedPlan().toString()) or df)
    hashes = spark.createDataFrame([(x,) for x in (0, 63, 64, -1, (1 << 23) + 5, 7 << 40)], "h long")
    lit = common.bit_set(hashes)
    assert hashes.where(common.is_lit(lit, hashes.h)).count() == 6
    assert spark.range(20).where(common.is_lit(lit, common.F.col("id"))).count() == 2  # 0 and 5
    assert "Join" not in plans[0]


def test_bitmaps_tell_small_sets_just_below_the_threshold_apart():
    """Sets of 90 with a similarity of 0.82: two bits a shingle left room for 0.85 in nearly all."""
    import numpy as np

    r = np.random.default_rng(5)
    passed = 0
    for _ in range(50):
        values = r.integers(1 << 63, size=99, dtype=np.uint64)
        bits = (jaccard_join._bitmap(x) for x in (values[:90], values[9:]))
        apart = sum(int(x).bit_count() for x in np.bitwise_xor(*bits).view(np.uint64))
        assert apart <= 18
        passed += (180 - apart) // 2 >= -(-85 * 180 // 185)
    assert passed <= 25
