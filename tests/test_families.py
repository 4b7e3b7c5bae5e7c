"""Families are spelled with what the parts give: their keys choose the family, their names the symbols."""

import duckdb
import pytest

import __spark_entry__ as entry
from phraseloom.functions import kernels as k

QUERIES = entry.queries()
NAMES = {6: "ab", 7: "cold bolt", 8: "c#", 9: "ba", 10: "xy", 11: "a|", 12: "ab"}


@pytest.mark.parametrize("name", ["family_phrases", "family_parse_stats", "family_runs"])
def test_families_follow_the_parts(spark, tmp_path, name):
    rows = [*NAMES.items(), (13, "x"), (14, None)]
    spark.createDataFrame(rows, "p_partkey long, p_name string").coalesce(1).write.parquet(str(tmp_path / "part.parquet"))
    got = QUERIES[name](spark, str(tmp_path)).collect()
    assert {r["sid"] for r in got} == set(NAMES)
    if name == "family_phrases":
        duck = duckdb.connect()
        duck.execute(f"CREATE VIEW part AS SELECT * FROM '{tmp_path}/part.parquet/*.parquet'")
        assert sorted(tuple(r[c] for c in ("sid", "ord", "lo", "hi")) for r in got) == sorted(duck.execute(entry.oracle_sql()[name]).fetchall())
        assert [(r["lo"], r["hi"]) for r in sorted(got, key=lambda r: r["ord"]) if r["sid"] == 7] == [(lo, hi) for lo, hi, _ in k.parse("co" * 48)]
    if name == "family_runs":
        assert {(r["lo"], r["hi"], r["period"]) for r in got if r["sid"] == 7} == {(1, 96, 2)}
    if name == "family_parse_stats":
        assert {(r["n"], r["phrases"]) for r in got if r["sid"] == 7} == {(n, 3) for n in (1_000, 10_000, 100_000)}
