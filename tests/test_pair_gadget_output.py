"""Every pair comes out, and on disk a column of patterns stays codes: past a dictionary's size each pair took its query's pattern."""

import random

import pyarrow.parquet as pq

from phraseloom.operators import orthogonality as ov


def _patterns(count, seed):
    draw, found = random.Random(seed), set()
    while len(found) < count:
        found.add("".join("1" if draw.random() < 0.1 else "0" for _ in range(64)))
    return sorted(found)


def test_many_patterns_are_written_as_codes(spark, tmp_path):
    a, b = _patterns(24, 1), _patterns(30_000, 2)
    sets = [spark.createDataFrame([(x, 1) for x in rows], "bits string, copies long") for rows in (a, b)]
    ov.whole_pair_gadget(*sets, 2).write.parquet(out := str(tmp_path / "pairs"))
    files = [pq.ParquetFile(p) for p in (tmp_path / "pairs").glob("*.parquet")]
    chunks = [f.metadata.row_group(i).column(c) for f in files for i in range(f.metadata.num_row_groups) for c in range(2)]
    assert {e for x in chunks for e in x.encodings} <= {"PLAIN_DICTIONARY", "RLE_DICTIONARY", "RLE", "BIT_PACKED"}
    rows = pq.read_table(out).to_pydict()
    assert len(rows["u"]) == len(a) * len(b)
    numbers = {x: int(x, 2) for x in [*a, *b]}
    want = {(u, v): 64 + (numbers[u] & numbers[v] != 0) for u in b for v in a}
    assert set(want.values()) == {64, 65}
    assert dict(zip(zip(rows["u"], rows["v"], strict=True), rows["phrases"], strict=True)) == want


def test_patterns_of_a_task_fit_a_dictionary(spark):
    a, b = _patterns(500, 3), _patterns(400, 4)
    sets = [spark.createDataFrame([(x, 1) for x in rows], "bits string, copies long") for rows in (a, b)]
    before, ov.DICTIONARY = ov.DICTIONARY, 100 * 68
    try:
        tiles, groups = ov._tiles(*sets, 10)
        tasks = tiles.rdd.mapPartitions(lambda rows: [[(r["own"], r["us"]) for r in rows]]).collect()
        assert sorted(u for r in groups.collect() for u in r["us"]) == b
    finally:
        ov.DICTIONARY = before
    for task in tasks:
        assert len({u for _, us in task for u in us}) <= 200
        assert len({v for own, _ in task for v in own}) <= 200
    pairs = [(u, v) for task in tasks for own, us in task for u in us for v in own]
    assert len(pairs) == len(set(pairs)) == len(a) * len(b)
