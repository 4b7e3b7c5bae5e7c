"""Every registered query with SQL equals it on the smallest tables; the others run; the reduction behaves as described."""

import datetime
import math

import duckdb
import pytest

import __spark_entry__ as entry

DATA = "/root/testdata/sf0.001"
QUERIES = {n: q for n, q in entry.queries().items() if not n.startswith("op") and n != "pipeline"}
ORACLES = entry.oracle_sql()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return con


def plain(value):
    if isinstance(value, float):
        return None if math.isnan(value) else round(value, 6)
    if isinstance(value, datetime.datetime):
        return value.replace(tzinfo=None)
    return value


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, duck, name):
    df = QUERIES[name](spark, DATA)
    columns = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in columns) for r in df.collect()), key=repr)
    if name not in ORACLES:
        assert got
        return
    cursor = duck.execute(ORACLES[name])
    names = [c[0] for c in cursor.description]
    assert sorted(names) == columns
    order = [names.index(c) for c in columns]
    assert got == sorted((tuple(plain(row[i]) for i in order) for row in cursor.fetchall()), key=repr)


def test_entry(spark):
    assert entry.entry(spark).count() == 200


def test_naive_construction_fails(spark):
    """The simple gadgets copy one another: their counts no longer tell orthogonal vectors apart."""
    counts = {r["u"]: r["phrases"] for r in QUERIES["ov_naive_failure"](spark, DATA).collect()}
    honest = {r["u"]: 0 for r in QUERIES["ov_decide"](spark, DATA).collect()}
    for r in QUERIES["ov_pair_gadget"](spark, DATA).collect():
        honest[r["u"]] += r["phrases"]
    assert any(counts[u] != honest[u] for u in counts)
