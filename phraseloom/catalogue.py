"""One registered query per relational operator kind, around phrases and lengths, on whole tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from phraseloom.functions.kernels import parse_many
from phraseloom.operators import phrases as ph
from phraseloom.plans import oracles as o
from phraseloom.sources import tables as src
from phraseloom.workloads import query


def _phrases(spark: SparkSession, d: str) -> DataFrame:
    """Phrases of the passages: sid, ord, lo, hi, and their length."""
    return ph.parse(src.passages(spark, d)).select("sid", "ord", "lo", "hi", (F.col("hi") - F.col("lo") + 1).alias("size"))


def _w(then: str) -> str:
    return o.phrases(o.PASSAGES, then.replace("PHRASES", "(SELECT sid, ord, lo, hi, hi - lo + 1 AS size FROM w)"))


def _docs(spark: SparkSession, d: str) -> DataFrame:
    return src.table(spark, d, "documents").select("doc_id", "text", "lang", "source", "n_chars")


def _labels(spark: SparkSession, d: str) -> DataFrame:
    return src.table(spark, d, "labels")


# --- scans, projections ---


@query("scan_strings", "SELECT doc_id AS sid, length(text) AS n, octet_length(encode(text)) AS bytes FROM documents")
def scan_strings(spark: SparkSession, d: str) -> DataFrame:
    s = src.documents(spark, d)
    return s.select("sid", F.char_length("body").cast("long").alias("n"), F.octet_length("body").cast("long").alias("bytes"))


@query("filter_lengths", "SELECT doc_id, n_chars FROM documents WHERE n_chars BETWEEN 500 AND 5000 AND lang IN ('en', 'fr') AND regexp_matches(text, '[0-9]')")
def filter_lengths(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).where(F.col("n_chars").between(500, 5000) & F.col("lang").isin("en", "fr") & F.col("text").rlike("[0-9]")).select("doc_id", "n_chars")


@query("symbolize_chars", "SELECT sym, count(*) AS times FROM (SELECT unnest(string_split(text, '')) AS sym FROM benchmark) GROUP BY sym")
def symbolize_chars(spark: SparkSession, d: str) -> DataFrame:
    return src.passages(spark, d).select(F.explode(F.split("body", "")).alias("sym")).where("sym != ''").groupBy("sym").agg(F.count(F.lit(1)).alias("times"))


@query("symbolize_words", "SELECT word, count(*) AS times, dense_rank() OVER (ORDER BY count(*) DESC, word) AS sym_id FROM (SELECT unnest(string_split(text, ' ')) AS word FROM benchmark) GROUP BY word")
def symbolize_words(spark: SparkSession, d: str) -> DataFrame:
    words = src.passages(spark, d).select(F.explode(F.split("body", " ")).alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("times"))
    return words.select("word", "times", F.dense_rank().over(Window.orderBy(F.desc("times"), "word")).cast("long").alias("sym_id"))


@query("symbolize_buckets", "SELECT c_custkey, ntile(8) OVER (ORDER BY c_acctbal, c_custkey) AS bucket FROM customer")
def symbolize_buckets(spark: SparkSession, d: str) -> DataFrame:
    return src.table(spark, d, "customer").select("c_custkey", F.ntile(8).over(Window.orderBy("c_acctbal", "c_custkey")).cast("long").alias("bucket"))


@query("symbolize_signs", f"WITH {o.patterns(6)} SELECT side, bits, count(*) AS times FROM p GROUP BY side, bits")
def symbolize_signs(spark: SparkSession, d: str) -> DataFrame:
    from phraseloom.operators.orthogonality import pattern

    return src.table(spark, d, "embeddings").groupBy((F.col("vec_id") % 2).alias("side"), pattern("embedding", 6).alias("bits")).agg(F.count(F.lit(1)).alias("times"))


# --- joins ---


@query("join_inner", "SELECT l.quality, count(*) AS docs, CAST(sum(d.n_chars) AS BIGINT) AS symbols FROM documents d JOIN labels l USING (doc_id) GROUP BY l.quality")
def join_inner(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).select("doc_id", "n_chars").join(_labels(spark, d).hint("shuffle_hash"), "doc_id").groupBy("quality").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_chars").alias("symbols"))


@query("join_left", "SELECT d.doc_id, l.quality FROM documents d LEFT JOIN labels l USING (doc_id)")
def join_left(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).select("doc_id").join(_labels(spark, d), "doc_id", "left").select("doc_id", "quality")


@query("join_full", "SELECT coalesce(o.o_orderkey, l.l_orderkey) AS orderkey, o.o_orderkey IS NULL AS no_order, l.l_orderkey IS NULL AS no_lines FROM orders o FULL JOIN (SELECT DISTINCT l_orderkey FROM lineitem) l ON o.o_orderkey = l.l_orderkey")
def join_full(spark: SparkSession, d: str) -> DataFrame:
    orders, lines = src.table(spark, d, "orders").select("o_orderkey"), src.table(spark, d, "lineitem").select("l_orderkey").distinct()
    return orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "full").select(F.coalesce("o_orderkey", "l_orderkey").alias("orderkey"), F.col("o_orderkey").isNull().alias("no_order"), F.col("l_orderkey").isNull().alias("no_lines"))


@query("join_semi", "SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.toxic = 1)")
def join_semi(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).select("doc_id").join(_labels(spark, d).where("toxic = 1"), "doc_id", "left_semi")


@query("join_anti", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def join_anti(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).select("doc_id").join(_labels(spark, d), "doc_id", "left_anti")


@query("join_broadcast", "SELECT r_name, n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, n_name")
def join_broadcast(spark: SparkSession, d: str) -> DataFrame:
    """Nations and regions are tables of a fixed size."""
    nations = src.table(spark, d, "nation").join(src.table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return src.table(spark, d, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"))


@query("join_range", _w("SELECT q.sid, q.pos, p.ord FROM (SELECT sid, unnest(range(1, length(body) + 1, 10)) AS pos FROM s) q JOIN PHRASES p ON p.sid = q.sid AND q.pos BETWEEN p.lo AND p.hi"))
def join_range(spark: SparkSession, d: str) -> DataFrame:
    """Positions inside phrases by bins: an equality join on (sid, bin) and a residual condition."""
    width = 32
    asked = src.passages(spark, d).where("body != ''").select("sid", F.explode(F.expr("sequence(1L, cast(char_length(body) as long), 10L)")).alias("pos")).withColumn("bin", F.expr(f"pos div {width}"))
    binned = _phrases(spark, d).withColumn("bin", F.explode(F.expr(f"sequence(lo div {width}, hi div {width})")))
    return asked.join(binned, ["sid", "bin"]).where("pos between lo and hi").select("sid", "pos", "ord")


@query("join_as_of", "SELECT e.event_id, (SELECT max(o.o_orderdate) FROM orders o WHERE o.o_custkey = e.user_id AND o.o_orderdate <= e.ts) AS last_order FROM events e")
def join_as_of(spark: SparkSession, d: str) -> DataFrame:
    """The customer's last order at the time of an event: one union and one ordered window, no range join."""
    events = src.table(spark, d, "events").select(F.col("user_id").alias("k"), F.col("ts").alias("at"), F.lit(1).alias("kind"), "event_id", F.lit(None).cast("timestamp").alias("o"))
    orders = src.table(spark, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("at"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"), F.col("o_orderdate").alias("o"))
    w = Window.partitionBy("k").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    return events.unionByName(orders).withColumn("last_order", F.last("o", ignorenulls=True).over(w)).where("kind = 1").select("event_id", "last_order")


@query("join_overlap", _w("SELECT a.sid, a.ord AS ord_a, b.ord AS ord_b FROM PHRASES a JOIN PHRASES b ON a.sid = b.sid AND a.lo <= b.hi + 1 AND b.lo <= a.hi + 1 AND a.ord < b.ord AND b.size > 1"))
def join_overlap(spark: SparkSession, d: str) -> DataFrame:
    """Phrases that touch one another: interval overlap by bins."""
    width = 32
    p = _phrases(spark, d).withColumn("bin", F.explode(F.expr(f"sequence(lo div {width}, (hi + 1) div {width})")))
    a, b = (p.select("sid", "bin", *[F.col(c).alias(f"{c}_{x}") for c in ("ord", "lo", "hi", "size")]) for x in "ab")
    return a.join(b, ["sid", "bin"]).where("lo_a <= hi_b + 1 and lo_b <= hi_a + 1 and ord_a < ord_b and size_b > 1").select("sid", "ord_a", "ord_b").distinct()


@query("join_self", "SELECT a.conv_id, a.turn, length(b.text) - length(a.text) AS grown FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
def join_self(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("conv_id").orderBy("turn")
    t = src.table(spark, d, "conversations").select("conv_id", "turn", F.char_length("text").cast("long").alias("n"))
    led = t.withColumn("n2", F.lead("n").over(w)).withColumn("t2", F.lead("turn").over(w))
    return led.where("t2 = turn + 1").select("conv_id", "turn", (F.col("n2") - F.col("n")).alias("grown"))


# --- aggregates ---


@query("agg_phrases", _w("SELECT sid, count(*) AS phrases, max(size) AS longest, string_agg(CAST(size AS VARCHAR), ',' ORDER BY ord) AS sizes FROM PHRASES GROUP BY sid"))
def agg_phrases(spark: SparkSession, d: str) -> DataFrame:
    sizes = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ord", "size"))), lambda e: e["size"].cast("string")), ",")
    return _phrases(spark, d).groupBy("sid").agg(F.count(F.lit(1)).alias("phrases"), F.max("size").alias("longest"), sizes.alias("sizes"))


@query("agg_distinct", "SELECT lang, count(DISTINCT text) AS texts, count(DISTINCT source) AS sources FROM documents GROUP BY lang")
def agg_distinct(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).groupBy("lang").agg(F.countDistinct("text").alias("texts"), F.countDistinct("source").alias("sources"))


@query("agg_rollup", "SELECT lang, source, count(*) AS docs, CAST(sum(n_chars) AS BIGINT) AS symbols FROM documents GROUP BY ROLLUP (lang, source)")
def agg_rollup(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).rollup("lang", "source").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_chars").alias("symbols"))


@query("agg_cube", "SELECT lang, quality, count(*) AS docs FROM documents JOIN labels USING (doc_id) GROUP BY CUBE (lang, quality)")
def agg_cube(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).select("doc_id", "lang").join(_labels(spark, d), "doc_id").cube("lang", "quality").agg(F.count(F.lit(1)).alias("docs"))


@query("agg_grouping_sets", "SELECT lang, source, count(*) AS docs FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).groupingSets([("lang",), ("source",), ()], "lang", "source").agg(F.count(F.lit(1)).alias("docs"))


@query("agg_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY user_id")
def agg_pivot(spark: SparkSession, d: str) -> DataFrame:
    counted = src.table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
    return counted.select("user_id", F.coalesce("click", F.lit(0)).cast("long").alias("click"), F.coalesce("view", F.lit(0)).cast("long").alias("view"))


@query("agg_unpivot", "SELECT doc_id, name, CAST(value AS BIGINT) AS value FROM (SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels)")
def agg_unpivot(spark: SparkSession, d: str) -> DataFrame:
    return _labels(spark, d).select("doc_id", F.col("quality").cast("long").alias("quality"), F.col("toxic").cast("long").alias("toxic")).unpivot("doc_id", ["quality", "toxic"], "name", "value")


@query("agg_percentile", "SELECT lang, CAST(quantile_cont(n_chars, 0.5) AS DOUBLE) AS median FROM documents GROUP BY lang")
def agg_percentile(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).groupBy("lang").agg(F.percentile("n_chars", 0.5).cast("double").alias("median"))


@query("agg_udaf", o.phrases(o.PARTS, "SELECT p_brand, sum(c) AS phrases, max(c) AS most FROM (SELECT sid, count(*) AS c FROM w GROUP BY sid) JOIN part ON p_partkey = sid GROUP BY p_brand").replace("sum(c)", "CAST(sum(c) AS BIGINT)"))
def agg_udaf(spark: SparkSession, d: str) -> DataFrame:
    """An aggregate function of its own: phrases per brand, counted by name inside and added outside, so that no group meets in one task."""

    @F.pandas_udf("long")
    def phrases_of(names: pd.Series) -> int:
        return sum(map(len, parse_many(names.tolist())))

    parts = src.table(spark, d, "part").where("p_name IS NOT NULL")
    return parts.groupBy("p_brand", "p_partkey").agg(phrases_of("p_name").alias("c")).groupBy("p_brand").agg(F.sum("c").alias("phrases"), F.max("c").alias("most"))


@query("join_theta", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey < r_regionkey AND length(n_name) > length(r_name) - 3")
def join_theta(spark: SparkSession, d: str) -> DataFrame:
    """No key at all: two tables whose sizes the schema fixes."""
    return src.table(spark, d, "nation").join(F.broadcast(src.table(spark, d, "region")), (F.col("n_regionkey") < F.col("r_regionkey")) & (F.char_length("n_name") > F.char_length("r_name") - 3)).select("n_name", "r_name")


@query("agg_approx_words")
def agg_approx_words(spark: SparkSession, d: str) -> DataFrame:
    """Approximate distinct words per language, beside the exact operators (sizes that never fit exact counting)."""
    return _docs(spark, d).select("lang", F.explode(F.split("text", " ")).alias("word")).groupBy("lang").agg(F.approx_count_distinct("word").alias("words"))


# --- windows, top-k, sets ---


@query("win_ranks", _w("SELECT sid, ord, size, row_number() OVER v AS rn, rank() OVER u AS rk, dense_rank() OVER u AS dr, lag(size) OVER o AS before, sum(size) OVER (PARTITION BY sid ORDER BY ord) AS covered FROM PHRASES WINDOW v AS (PARTITION BY sid ORDER BY size DESC, ord), u AS (PARTITION BY sid ORDER BY size DESC), o AS (PARTITION BY sid ORDER BY ord)").replace("sum(size)", "CAST(sum(size)").replace("ORDER BY ord) AS covered", "ORDER BY ord) AS BIGINT) AS covered"))
def win_ranks(spark: SparkSession, d: str) -> DataFrame:
    v, u, t = (Window.partitionBy("sid").orderBy(*c) for c in ((F.desc("size"), "ord"), (F.desc("size"),), ("ord",)))
    return _phrases(spark, d).select("sid", "ord", "size", F.row_number().over(v).cast("long").alias("rn"), F.rank().over(u).cast("long").alias("rk"), F.dense_rank().over(u).cast("long").alias("dr"), F.lag("size").over(t).alias("before"), F.sum("size").over(t).alias("covered"))


@query("win_frames", _w("SELECT sid, ord, CAST(sum(size) OVER (PARTITION BY sid ORDER BY ord ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS BIGINT) AS last_five, count(*) OVER (PARTITION BY sid ORDER BY lo RANGE BETWEEN 20 PRECEDING AND CURRENT ROW) AS near FROM PHRASES"))
def win_frames(spark: SparkSession, d: str) -> DataFrame:
    rows, span = Window.partitionBy("sid").orderBy("ord").rowsBetween(-4, 0), Window.partitionBy("sid").orderBy("lo").rangeBetween(-20, 0)
    return _phrases(spark, d).select("sid", "ord", F.sum("size").over(rows).alias("last_five"), F.count(F.lit(1)).over(span).alias("near"))


@query("topk_phrases", _w("SELECT sid, ord, size FROM (SELECT *, row_number() OVER (PARTITION BY sid ORDER BY size DESC, ord) AS rn FROM PHRASES) WHERE rn <= 3"))
def topk_phrases(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("sid").orderBy(F.desc("size"), "ord")
    return _phrases(spark, d).withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("sid", "ord", "size")


@query("topk_compressible")
def topk_compressible(spark: SparkSession, d: str) -> DataFrame:
    stats = ph.parse_stats(src.documents(spark, d)).withColumn("ratio", F.round(F.col("ints") / F.greatest("n", F.lit(1)), 6))
    return stats.orderBy("ratio", "sid").limit(20)


def _texts(spark: SparkSession, d: str, odd: int) -> DataFrame:
    s = src.passages(spark, d)
    return ph.parse(s).join(s, "sid").where(F.col("sid") % 2 == odd).select(F.substring("body", F.col("lo"), F.col("hi") - F.col("lo") + 1).alias("phrase"))


def _sql_texts(odd: int) -> str:
    return f"SELECT substr(s.body, w.lo, w.hi - w.lo + 1) AS phrase FROM w JOIN s USING (sid) WHERE sid % 2 = {odd}"


for _name, _sql, _f in (
    ("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_union_all", "UNION ALL", lambda a, b: a.unionByName(b)), ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("set_except", "EXCEPT", lambda a, b: a.subtract(b)), ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(_name, o.phrases(o.PASSAGES, f"{_sql_texts(0)} {_sql} {_sql_texts(1)}"))(lambda spark, d, f=_f: f(_texts(spark, d, 0), _texts(spark, d, 1)))


@query("dedup_texts", "SELECT md5(text) AS digest, min(doc_id) AS first_doc, count(*) AS copies FROM documents GROUP BY text")
def dedup_texts(spark: SparkSession, d: str) -> DataFrame:
    """Equal texts by digest; a digest only groups, the digest is the result."""
    return _docs(spark, d).groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("first_doc"), F.count(F.lit(1)).alias("copies"))


# --- scalars ---


@query("fn_strings", "SELECT p_partkey, reverse(p_name) AS r, repeat(left(p_name, 2), 3) AS rep, translate(p_name, 'aeiou', '12345') AS t, CAST(strpos(p_name, ' ') AS BIGINT) AS sp, levenshtein(p_name, p_brand) AS dist, left(p_name, 2) || 'x' || substr(p_name, 4) AS changed, md5(p_name) AS h FROM part")
def fn_strings(spark: SparkSession, d: str) -> DataFrame:
    p = src.table(spark, d, "part")
    return p.select(
        "p_partkey", F.reverse("p_name").alias("r"), F.repeat(F.left("p_name", F.lit(2)), 3).alias("rep"), F.translate("p_name", "aeiou", "12345").alias("t"), F.instr("p_name", " ").cast("long").alias("sp"),
        F.levenshtein("p_name", "p_brand").cast("long").alias("dist"), F.overlay("p_name", F.lit("x"), 3, 1).alias("changed"), F.md5("p_name").alias("h"),
    )


@query("fn_dates", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS events, max(epoch_us(ts)) AS last_us FROM events GROUP BY 1, 2")
def fn_dates(spark: SparkSession, d: str) -> DataFrame:
    return src.table(spark, d, "events").groupBy(F.date_trunc("day", "ts").alias("day"), "event_type").agg(F.count(F.lit(1)).alias("events"), F.max(F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01', cast(ts as timestamp_ntz))")).alias("last_us"))


@query("fn_math", "SELECT doc_id, round(cbrt(n_chars), 6) AS cube_root, CAST(ceil(log2(n_chars + 1)) AS BIGINT) AS bits, bit_count(n_chars) AS ones, n_chars % 7 AS rest FROM documents")
def fn_math(spark: SparkSession, d: str) -> DataFrame:
    n = F.col("n_chars")
    return _docs(spark, d).select("doc_id", F.round(F.cbrt(n), 6).alias("cube_root"), F.ceil(F.log2(n + 1)).cast("long").alias("bits"), F.bit_count(n).cast("long").alias("ones"), F.pmod(n, F.lit(7)).alias("rest"))


@query("fn_arrays", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS positive, round(CAST(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)) AS DOUBLE), 4) AS norm2 FROM embeddings")
def fn_arrays(spark: SparkSession, d: str) -> DataFrame:
    e = src.table(spark, d, "embeddings")
    norm = F.aggregate("embedding", F.lit(0.0), lambda acc, x: acc + x.cast("double") * x.cast("double"))
    return e.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.round(norm, 4).alias("norm2"))


@query("fn_json", "SELECT user_id, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY user_id")
def fn_json(spark: SparkSession, d: str) -> DataFrame:
    return src.table(spark, d, "events").groupBy("user_id").agg(F.sum(F.from_json("props", "k long")["k"]).alias("total"))


@query("fn_maps", "SELECT l_orderkey, count(*) FILTER (WHERE l_returnflag = 'R') AS returned, count(*) AS lines FROM lineitem GROUP BY l_orderkey")
def fn_maps(spark: SparkSession, d: str) -> DataFrame:
    flags = src.table(spark, d, "lineitem").groupBy("l_orderkey", "l_returnflag").agg(F.count(F.lit(1)).alias("n")).groupBy("l_orderkey").agg(F.map_from_entries(F.collect_list(F.struct("l_returnflag", "n"))).alias("m"))
    total = F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda acc, x: acc + x)
    return flags.select("l_orderkey", F.coalesce(F.try_element_at("m", F.lit("R")), F.lit(0)).cast("long").alias("returned"), total.alias("lines"))


# --- SQL surface ---


@query("sql_surface", o.phrases(o.PASSAGES, "SELECT sid, count(*) AS phrases, max(hi - lo + 1) AS longest FROM w GROUP BY sid"))
def sql_surface(spark: SparkSession, d: str) -> DataFrame:
    from phraseloom.sql_surface import register

    register(spark)
    src.passages(spark, d).createOrReplaceTempView("phrase_strings")
    return spark.sql("SELECT s.sid, count(*) AS phrases, max(p.hi - p.lo + 1) AS longest FROM phrase_strings s, LATERAL greedy_phrases(s.body) p GROUP BY s.sid")


@query("sql_scalars", o.phrases(o.PARTS, "SELECT sid, count(*) AS phrases FROM w GROUP BY sid"))
def sql_scalars(spark: SparkSession, d: str) -> DataFrame:
    from phraseloom.sql_surface import register

    register(spark)
    src.part_names(spark, d).createOrReplaceTempView("phrase_names")
    return spark.sql("SELECT sid, phrase_count(body) AS phrases FROM phrase_names WHERE body <> ''")


@query("star_report", "SELECT c_mktsegment, r_name, count(*) AS orders, CAST(sum(c.lines) AS BIGINT) AS lines FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN (SELECT l_orderkey, count(*) AS lines FROM lineitem GROUP BY l_orderkey) c ON c.l_orderkey = o_orderkey GROUP BY c_mktsegment, r_name")
def star_report(spark: SparkSession, d: str) -> DataFrame:
    lines = src.table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("lines"))
    nations = src.table(spark, d, "nation").join(src.table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    orders = src.table(spark, d, "orders").join(src.table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))
    return orders.join(lines, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("c_mktsegment", "r_name").agg(F.count(F.lit(1)).alias("orders"), F.sum("lines").alias("lines"))
