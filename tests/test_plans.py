"""Streams and the plans for one huge string."""

import random

from pyspark.sql import functions as F

from phraseloom.functions import kernels as k
from phraseloom.operators import changes
from phraseloom.plans import huge_string
from phraseloom.streaming import stream


def test_suffix_ranks_and_root_path(spark):
    r = random.Random(3)
    s = "".join(r.choice("ab") for _ in range(90)) + "ab" * 20
    df = spark.createDataFrame([(i, c) for i, c in enumerate(s, 1)], "pos long, sym string")
    ranks = {x["pos"]: x["rank"] for x in huge_string.suffix_ranks(df, parts=3).collect()}
    assert [p for p, _ in sorted(ranks.items(), key=lambda x: x[1])] == (k.suffix_array(s) + 1).tolist()
    reaches = spark.createDataFrame(list(enumerate(k.reach(k.lpf(s)), 1)), "pos long, reach long")
    for block in (4, 16, 1 << 20):
        got = [tuple(x) for x in huge_string.root_path(reaches, block).orderBy("ord").collect()]
        assert got == [(o, lo, hi) for o, (lo, hi, _) in enumerate(k.parse(s), 1)]


def test_replayed_edits_equal_the_rebuild(spark, tmp_path):
    strings = spark.createDataFrame([(1, "abracadabra"), (2, "aaaaaaaaaa"), (3, "mississippi")], "sid long, body string")
    scripts = changes.edit_script(strings, 4)
    rows = scripts.select("sid", F.explode("ops").alias("e")).select("sid", "e.*")
    rows.unionByName(rows.where("seq = 2")).coalesce(1).write.parquet(str(tmp_path / "edits"))  # one edit comes twice
    live = spark.readStream.schema(rows.schema).parquet(str(tmp_path / "edits"))
    out = stream.replay_edits(live, strings)
    q = out.writeStream.format("memory").queryName("replayed").outputMode("append").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    q.awaitTermination()
    want = sorted(map(tuple, changes.replay_rebuild(scripts).collect()))
    assert sorted(map(tuple, spark.table("replayed").collect())) == want
    assert sorted(map(tuple, changes.replay_transition(scripts).collect())) == want == sorted(map(tuple, changes.replay_on_demand(scripts).collect()))


def in_files(df, order, folder, files):
    """Rows dealt to files in a shuffled order, which a stream reads one by one."""
    rows = df.collect()
    random.Random(order).shuffle(rows)
    for n in range(files):
        df.sparkSession.createDataFrame(rows[n::files], df.schema).coalesce(1).write.mode("append").parquet(str(folder))
    return df.sparkSession.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(folder))


def test_replayed_edits_wait_for_earlier_ones(spark, tmp_path):
    strings = spark.createDataFrame([(1, "abracadabra"), (2, "aaaaaaaaaa"), (3, "mississippi")], "sid long, body string")
    scripts = changes.edit_script(strings, 6)
    rows = scripts.select("sid", F.explode("ops").alias("e")).select("sid", "e.*")
    out = stream.replay_edits(in_files(rows, 5, tmp_path / "edits", 4), strings)
    out.writeStream.format("memory").queryName("mixed").outputMode("append").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start().awaitTermination()
    assert sorted(map(tuple, spark.table("mixed").collect())) == sorted(map(tuple, changes.replay_rebuild(scripts).collect()))


def test_late_events_take_their_place(spark, tmp_path):
    r = random.Random(8)
    events = [(e, r.randint(1, 2), r.choice(["view", "click", "error"])) for e in range(60)]
    df = spark.createDataFrame(events, "event_id long, user_id long, event_type string").withColumn("ts", F.timestamp_seconds(F.lit(1_700_000_000) + F.col("event_id") * 60))
    got = stream.sliding_counts_of(in_files(df, 2, tmp_path / "events", 4), 5).collect()
    want = []
    for user in (1, 2):
        symbols = "".join(kind[0] for _, u, kind in events if u == user)
        want += [(user, n, min(n, 5), sum(1 for _ in k.parse(symbols[max(0, n - 5) : n]))) for n in range(1, len(symbols) + 1)]
    assert sorted(tuple(x) for x in got) == want
