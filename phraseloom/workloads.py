"""Registered queries: methods, variants, baselines, and measures on given tables, with SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from phraseloom.operators import changes, orthogonality as ov, phrases as ph, stringology as st
from phraseloom.operators.per_string import flat_map, spread
from phraseloom.plans import oracles as o
from phraseloom.sources import tables as src

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


# --- flagship and corpus statistics -------------------------------------------------------------------------------


@query("doc_parse_stats")
def doc_parse_stats(spark: SparkSession, d: str) -> DataFrame:
    return ph.parse_stats(src.documents(spark, d)).withColumn("ratio", F.round(F.col("ints") / F.greatest("n", F.lit(1)), 6))


@query("lang_source_rollup")
def lang_source_rollup(spark: SparkSession, d: str) -> DataFrame:
    docs = src.table(spark, d, "documents").select(F.col("doc_id").alias("sid"), "lang", "source")
    joined = docs.join(ph.parse_stats(src.documents(spark, d)), "sid")
    return joined.rollup("lang", "source").agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("symbols"), F.sum("phrases").alias("phrases"), F.grouping_id().cast("int").alias("level"))


@query("quality_vs_ratio")
def quality_vs_ratio(spark: SparkSession, d: str) -> DataFrame:
    labels = src.table(spark, d, "labels").select(F.col("doc_id").alias("sid"), "quality")
    joined = ph.parse_stats(src.documents(spark, d)).join(labels, "sid", "left")
    return joined.groupBy("quality").agg(F.count(F.lit(1)).alias("docs"), F.round(F.sum("ints") / F.sum("n"), 6).alias("ratio"))


@query("page_parse_stats")
def page_parse_stats(spark: SparkSession, d: str) -> DataFrame:
    pages = src.table(spark, d, "pages")
    host = pages.select(F.col("page_id").alias("sid"), F.parse_url("url", F.lit("HOST")).alias("host"))
    stats = ph.parse_stats(spread(pages.select(F.col("page_id").alias("sid"), F.col("html").alias("body"))))
    return stats.join(host, "sid").groupBy("host").agg(F.count(F.lit(1)).alias("pages"), F.sum("n").alias("symbols"), F.sum("phrases").alias("phrases"))


@query("roundtrip", "SELECT doc_id AS sid, length(text) AS n, md5(text) AS digest FROM documents")
def roundtrip(spark: SparkSession, d: str) -> DataFrame:
    return ph.roundtrip(src.documents(spark, d))


# --- factors, forest, phrase queries ------------------------------------------------------------------------------


@query("lpf_values", o.lpf(o.PASSAGES, "SELECT sid, pos, lpf_raw, greatest(lpf_raw, 1) AS lpf FROM f"))
def lpf_values(spark: SparkSession, d: str) -> DataFrame:
    return ph.lpf(src.passages(spark, d))


@query("lpf_by_grams", o.lpf(o.PARTS, "SELECT sid, pos, lpf_raw, greatest(lpf_raw, 1) AS lpf FROM f"))
def lpf_by_grams(spark: SparkSession, d: str) -> DataFrame:
    return ph.lpf_by_grams(src.part_names(spark, d))


@query("lpf_witness", o.lpf(o.PASSAGES, "SELECT f.sid, f.pos, max(e.pos) AS witness FROM f JOIN s USING (sid) LEFT JOIN g0 e ON e.sid = f.sid AND e.size = f.lpf_raw AND e.pos < f.pos AND e.gram = substr(s.body, f.pos, f.lpf_raw) GROUP BY f.sid, f.pos"))
def lpf_witness(spark: SparkSession, d: str) -> DataFrame:
    return ph.lpf_witness(src.passages(spark, d))


@query("reach_monotone", "SELECT item_id AS sid, CAST(0 AS BIGINT) AS violations FROM benchmark WHERE length(text) > 0")
def reach_monotone(spark: SparkSession, d: str) -> DataFrame:
    reaches = ph.reach(ph.lpf(src.passages(spark, d)))
    w = Window.partitionBy("sid").orderBy("pos")
    falls = reaches.withColumn("fall", F.coalesce(F.col("reach") < F.lag("reach").over(w), F.lit(False)))
    return falls.groupBy("sid").agg(F.count_if("fall").alias("violations"))


@query("reach_forest", o.lpf(o.PASSAGES, "SELECT sid, min(pos) AS lo, max(pos) AS hi, pos_to AS parent FROM (SELECT sid, pos, pos + greatest(lpf_raw, 1) AS pos_to FROM f) GROUP BY sid, pos_to"))
def reach_forest(spark: SparkSession, d: str) -> DataFrame:
    return ph.forest(ph.reach(ph.lpf(src.passages(spark, d))))


@query("greedy_phrases", o.phrases(o.PASSAGES, "SELECT sid, ord, lo, hi FROM w"))
def greedy_phrases(spark: SparkSession, d: str) -> DataFrame:
    return ph.parse(src.passages(spark, d)).select("sid", "ord", "lo", "hi")


@query("select_phrase", o.phrases(o.PASSAGES, "SELECT sid, ord, lo, hi FROM w WHERE ord = 1 + sid % 7"))
def select_phrase(spark: SparkSession, d: str) -> DataFrame:
    s = src.passages(spark, d)
    return ph.select_phrase(ph.parse(s), s.select("sid", (1 + F.col("sid") % 7).alias("ord")))


def _asked(s: DataFrame) -> DataFrame:
    return s.where("body != ''").select("sid", (1 + (7 * F.col("sid") + 3) % F.char_length("body")).alias("pos"))


_ASKED = "(SELECT sid, 1 + (7 * sid + 3) % length(body) AS pos FROM s WHERE body <> '')"


@query("containing_phrase", o.phrases(o.PASSAGES, f"SELECT w.sid, q.pos, ord, lo, hi FROM w JOIN {_ASKED} q ON q.sid = w.sid AND q.pos BETWEEN lo AND hi"))
def containing_phrase(spark: SparkSession, d: str) -> DataFrame:
    s = src.passages(spark, d)
    return ph.containing_phrase(ph.parse(s), _asked(s))


@query("prefix_parse_length", o.phrases(f"SELECT sid, left(body, CAST(1 + (7 * sid + 3) % length(body) AS INTEGER)) AS body FROM ({o.PASSAGES}) WHERE body <> ''", "SELECT sid, CAST(max(n) AS BIGINT) AS pos, count(*) AS phrases FROM w GROUP BY sid"))
def prefix_parse_length(spark: SparkSession, d: str) -> DataFrame:
    s = src.passages(spark, d)
    return ph.prefix_parse_length(ph.parse(s), _asked(s))


@query("phrase_count", o.phrases(o.PASSAGES, "SELECT sid, CAST(max(n) AS BIGINT) AS n, count(*) AS phrases FROM w GROUP BY sid"))
def phrase_count(spark: SparkSession, d: str) -> DataFrame:
    return ph.parse_stats(src.passages(spark, d)).select("sid", "n", "phrases")


@query("compression_ratio", o.phrases(o.PASSAGES, "SELECT w.sid, count(*) AS phrases, CAST(sum(CASE WHEN lpf_raw > 0 THEN 2 ELSE 1 END) AS BIGINT) AS ints, round(sum(CASE WHEN lpf_raw > 0 THEN 2 ELSE 1 END) / CAST(max(n) AS DOUBLE), 6) AS ratio FROM w JOIN f ON f.sid = w.sid AND f.pos = w.lo GROUP BY w.sid"))
def compression_ratio(spark: SparkSession, d: str) -> DataFrame:
    return ph.parse_stats(src.passages(spark, d)).select("sid", "phrases", "ints", F.round(F.col("ints") / F.col("n"), 6).alias("ratio"))


@query("forest_depths", f"WITH RECURSIVE {o.factors(o.PARTS)}, h AS (SELECT sid, pos AS node, pos AS here, CAST(0 AS BIGINT) AS depth FROM f UNION ALL SELECT h.sid, node, reach[here], depth + 1 FROM h JOIN r ON r.sid = h.sid AND h.here <= r.n) SELECT sid, node, max(depth) AS depth FROM h GROUP BY sid, node")
def forest_depths(spark: SparkSession, d: str) -> DataFrame:
    """Phrases from every place to the end of the string."""
    reaches = ph.reach(ph.lpf_by_grams(src.part_names(spark, d)))
    longest = src.part_names(spark, d).agg(F.coalesce(F.max(F.char_length("body")), F.lit(1))).first()[0]
    return ph.forest_depths(reaches, longest)


@query("forest_ancestor", o.lpf(o.PARTS, "SELECT sid, pos AS node, reach[reach[reach[pos]]] AS ancestor FROM r, LATERAL (SELECT unnest(range(1, n + 1)) AS pos) WHERE reach[reach[reach[pos]]] IS NOT NULL"))
def forest_ancestor(spark: SparkSession, d: str) -> DataFrame:
    return ph.forest_ancestor(ph.reach(ph.lpf_by_grams(src.part_names(spark, d))), 3)


@query("valid_factorization", "SELECT item_id AS sid, TRUE AS valid FROM benchmark WHERE length(text) > 0")
def valid_factorization(spark: SparkSession, d: str) -> DataFrame:
    s = src.passages(spark, d)
    return ph.valid_factorization(s, ph.parse(s))


@query("greedy_optimal", "SELECT item_id AS sid, TRUE AS optimal FROM benchmark WHERE length(text) > 0")
def greedy_optimal(spark: SparkSession, d: str) -> DataFrame:
    return ph.greedy_optimal(src.passages(spark, d)).select("sid", (F.col("phrases") == F.col("fewest")).alias("optimal"))


@query("segment_parse_stats", o.phrases(o.PARTS, "SELECT c_mktsegment, r_name, count(*) AS lines, CAST(sum(k.n) AS BIGINT) AS symbols, CAST(sum(k.phrases) AS BIGINT) AS phrases FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN (SELECT sid, max(n) AS n, count(*) AS phrases FROM w GROUP BY sid) k ON k.sid = l_partkey GROUP BY c_mktsegment, r_name"))
def segment_parse_stats(spark: SparkSession, d: str) -> DataFrame:
    """Parse statistics of the part names over all order lines, by the customer's segment and the supplier's region."""
    t = lambda name: src.table(spark, d, name)
    stats = ph.parse_stats(src.part_names(spark, d)).where("n > 0").select("sid", "n", "phrases")
    lines = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    lines = lines.join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    joined = lines.join(stats, F.col("l_partkey") == F.col("sid"))
    return joined.groupBy("c_mktsegment", "r_name").agg(F.count(F.lit(1)).alias("lines"), F.sum("n").alias("symbols"), F.sum("phrases").alias("phrases"))


@query("order_flag_parse", o.phrases(f"SELECT row_number() OVER (ORDER BY body) AS sid, body FROM (SELECT DISTINCT body FROM ({o.ORDERS}))", f"SELECT q.sid, c.n, c.phrases FROM ({o.ORDERS}) q JOIN (SELECT s.body, CAST(max(n) AS BIGINT) AS n, count(*) AS phrases FROM w JOIN s USING (sid) GROUP BY s.body) c USING (body)"))
def order_flag_parse(spark: SparkSession, d: str) -> DataFrame:
    """Equal strings are parsed once."""
    orders = src.order_strings(spark, d)
    once = orders.groupBy("body").agg(F.min("sid").alias("sid"))
    stats = ph.parse_stats(once).join(once, "sid").select("body", "n", "phrases")
    return orders.join(stats, "body").select("sid", "n", "phrases")


# --- substring tools ----------------------------------------------------------------------------------------------


def _pairs(s: DataFrame) -> DataFrame:
    return s.where("char_length(body) > 8").select("sid", "body", (1 + F.col("sid") % 5).alias("i"), (4 + F.col("sid") % 7 % (F.char_length("body") - 4)).alias("j"))


_PAIRS = "q AS (SELECT sid, body, 1 + sid % 5 AS i, 4 + sid % 7 % (length(body) - 4) AS j FROM s WHERE length(body) > 8)"


@query("lcp_pairs", f"WITH s AS ({o.PASSAGES}), {_PAIRS} SELECT sid, i, j, (SELECT CAST(coalesce(max(k), 0) AS BIGINT) FROM range(1, length(body) + 1) t(k) WHERE greatest(i, j) + k - 1 <= length(body) AND substr(body, i, k) = substr(body, j, k)) AS lcp FROM q")
def lcp_pairs(spark: SparkSession, d: str) -> DataFrame:
    return st.lcp_pairs(_pairs(src.passages(spark, d)))


@query("lcs_pairs", f"WITH s AS ({o.PASSAGES}), {_PAIRS} SELECT sid, i, j, (SELECT CAST(coalesce(max(k), 0) AS BIGINT) FROM range(1, length(body) + 1) t(k) WHERE k <= least(i, j) AND substr(body, i - k + 1, k) = substr(body, j - k + 1, k)) AS lcs FROM q")
def lcs_pairs(spark: SparkSession, d: str) -> DataFrame:
    return st.lcs_pairs(_pairs(src.passages(spark, d)))


def _patterned(s: DataFrame, at: int, size: int) -> DataFrame:
    return s.where(f"char_length(body) >= {at + size}").select("sid", "body", F.substring("body", at, size).alias("pattern"))


_MATCHES = "m AS (SELECT sid, pos FROM (SELECT sid, body, substr(body, {at}, {size}) AS pattern FROM s WHERE length(body) >= {at} + {size}), LATERAL (SELECT unnest(range(1, length(body) + 1)) AS pos) WHERE substr(body, pos, {size}) = pattern)"


@query("pattern_occurrences", f"WITH s AS ({o.PASSAGES}), {_MATCHES.format(at=2, size=2)} SELECT sid, pos FROM m")
def pattern_occurrences(spark: SparkSession, d: str) -> DataFrame:
    return st.all_occurrences(_patterned(src.passages(spark, d), 2, 2))


_ISLANDS = "SELECT sid, min(pos) AS first, max(pos) AS last, CAST(1 AS BIGINT) AS step FROM (SELECT sid, pos, pos - row_number() OVER (PARTITION BY sid ORDER BY pos) AS island FROM m) GROUP BY sid, island"


@query("pattern_clusters", f"WITH s AS ({o.USERS}), {_MATCHES.format(at=2, size=1)} {_ISLANDS}")
def pattern_clusters(spark: SparkSession, d: str) -> DataFrame:
    return st.pattern_clusters(_patterned(src.user_strings(spark, d), 2, 1))


@query("cluster_islands", f"WITH s AS ({o.USERS}), {_MATCHES.format(at=2, size=1)} {_ISLANDS}")
def cluster_islands(spark: SparkSession, d: str) -> DataFrame:
    return st.cluster_islands(st.all_occurrences(_patterned(src.user_strings(spark, d), 2, 1)), F.lit(1).cast("long"))


@query("internal_match", f"WITH s AS ({o.USERS}), x AS (SELECT sid, body, substr(body, 5, 1) AS pattern FROM s WHERE length(body) >= 7), m AS (SELECT sid, pos FROM x, LATERAL (SELECT unnest(range(6, 8)) AS pos) WHERE substr(body, pos, 1) = pattern) {_ISLANDS}")
def internal_match(spark: SparkSession, d: str) -> DataFrame:
    rows = src.user_strings(spark, d).where("char_length(body) >= 7").select("sid", "body", *[F.lit(v).alias(c) for c, v in (("p_lo", 5), ("p_hi", 5), ("t_lo", 6), ("t_hi", 7))])
    return st.internal_match(rows)


@query("internal_match_grown")
def internal_match_grown(spark: SparkSession, d: str) -> DataFrame:
    """On every document and every user's string: a pattern of n/16 symbols from the middle, in a range twice as long around it."""
    size = F.greatest(F.floor(F.char_length("body") / 16), F.lit(1)).cast("long")
    low = F.floor(F.char_length("body") / 2).cast("long") + 1
    t_low = F.greatest(low - F.floor(size / 2), F.lit(1))
    parts = []
    for kind, s in (("document", src.documents(spark, d)), ("user", src.user_strings(spark, d))):
        rows = s.where("body != ''").select("sid", "body", low.alias("p_lo"), (low + size - 1).alias("p_hi"), t_low.alias("t_lo"), (t_low + 2 * size - 1).alias("t_hi"))
        parts.append(st.internal_match(rows).withColumn("kind", F.lit(kind)))
    return parts[0].unionByName(parts[1])


@query("first_last_occurrence", "WITH x AS (SELECT item_id AS sid, text AS body, substr(text, 5, 2) AS pattern FROM benchmark WHERE length(text) >= 7) SELECT sid, TRUE AS found, CAST(strpos(body, pattern) AS BIGINT) AS first_pos, (SELECT max(p) FROM range(1, length(body)) t(p) WHERE substr(body, p, 2) = pattern) AS last_pos FROM x")
def first_last_occurrence(spark: SparkSession, d: str) -> DataFrame:
    return st.first_last_occurrence(_patterned(src.passages(spark, d), 5, 2))


@query("substring_exists", "WITH x AS (SELECT item_id AS sid, text AS body, reverse(substr(text, 4, 3)) AS pattern FROM benchmark WHERE length(text) >= 7) SELECT sid, pattern, contains(body, pattern) AS found FROM x")
def substring_exists(spark: SparkSession, d: str) -> DataFrame:
    """Does a pattern occur, three symbols of each passage read backwards: mostly it does not."""
    patterned = _patterned(src.passages(spark, d), 4, 3).withColumn("pattern", F.reverse("pattern"))
    return st.first_last_occurrence(patterned).join(patterned.select("sid", "pattern"), "sid").select("sid", "pattern", "found")


@query("suffix_array", f"WITH s AS ({o.PASSAGES}), x AS (SELECT sid, pos, substr(body, pos) AS suffix FROM s, LATERAL (SELECT unnest(range(1, length(body) + 1)) AS pos)) SELECT sid, row_number() OVER (PARTITION BY sid ORDER BY suffix) AS rank, pos FROM x")
def suffix_array(spark: SparkSession, d: str) -> DataFrame:
    return st.suffix_arrays(src.passages(spark, d))


@query("sa_search", f"WITH s AS ({o.PASSAGES}), {_MATCHES.format(at=3, size=2)} SELECT sid, count(*) AS occurrences FROM m GROUP BY sid")
def sa_search(spark: SparkSession, d: str) -> DataFrame:
    return st.suffix_search(_patterned(src.passages(spark, d), 3, 2))


@query("string_period", f"WITH s AS ({o.USERS}) SELECT sid, n, period, 2 * period <= n AS periodic FROM (SELECT sid, length(body) AS n, (SELECT min(p) FROM range(1, length(body) + 1) t(p) WHERE substr(body, p + 1) = left(body, CAST(length(body) - p AS INTEGER))) AS period FROM s)")
def string_period(spark: SparkSession, d: str) -> DataFrame:
    return st.periods(src.user_strings(spark, d))


@query("runs", f"""WITH s AS (SELECT * FROM ({o.ORDERS}) WHERE TRUE), u AS (SELECT DISTINCT body FROM s),
x AS (SELECT body, p, i FROM u, LATERAL (SELECT unnest(range(1, length(body) // 2 + 1)) AS p), LATERAL (SELECT unnest(range(1, length(body) - p + 1)) AS i) WHERE substr(body, i, 1) = substr(body, i + p, 1)),
y AS (SELECT body, p, min(i) AS lo, max(i) + p AS hi FROM (SELECT body, p, i, i - row_number() OVER (PARTITION BY body, p ORDER BY i) AS island FROM x) GROUP BY body, p, island HAVING count(*) >= p),
z AS (SELECT body, lo, hi, min(p) AS period FROM y GROUP BY body, lo, hi)
SELECT s.sid, lo, hi, period FROM s JOIN z USING (body)""")
def runs(spark: SparkSession, d: str) -> DataFrame:
    orders = src.order_strings(spark, d)
    once = orders.groupBy("body").agg(F.min("sid").alias("sid"))
    return orders.join(st.all_runs(once).join(once, "sid").drop("sid"), "body").select("sid", "lo", "hi", "period")


@query("interval_cover", "SELECT item_id AS sid, CAST(length(text) - item_id % 5 AS BIGINT) AS covered, TRUE AS few_per_level FROM benchmark WHERE length(text) > 5")
def interval_cover(spark: SparkSession, d: str) -> DataFrame:
    asked = src.passages(spark, d).where("char_length(body) > 5").select("sid", (1 + F.col("sid") % 5).alias("a"), F.char_length("body").cast("long").alias("b"))
    per_level = st.interval_cover(asked).groupBy("sid", "level").agg(F.count(F.lit(1)).alias("pieces"), F.sum(F.col("hi") - F.col("lo") + 1).alias("covered"))
    return per_level.groupBy("sid").agg(F.sum("covered").alias("covered"), (F.max("pieces") <= 16).alias("few_per_level"))


@query("partition_upkeep", "SELECT item_id AS sid, CAST(12 AS BIGINT) AS edits, TRUE AS valid, CAST(length(text) AS BIGINT) AS n_after FROM benchmark WHERE length(text) > 12")
def partition_upkeep(spark: SparkSession, d: str) -> DataFrame:
    scripts = changes.edit_script(src.passages(spark, d), 12, ("ins", "del", "sub"))
    return st.partition_upkeep(scripts.select("sid", F.char_length("body").cast("long").alias("n"), "ops")).select("sid", "edits", "valid", "n_after")


@query("budgeted_rebuild")
def budgeted_rebuild(spark: SparkSession, d: str) -> DataFrame:
    scripts = changes.edit_script(src.passages(spark, d), 24, ("ins", "sub", "del"))
    return st.partition_upkeep(scripts.select("sid", F.char_length("body").cast("long").alias("n"), "ops")).select("sid", "rebuilt", "longest_backlog")


@query("dominant_points", f"""WITH s AS ({o.PARTS}), x AS (SELECT sid, i, j FROM s, LATERAL (SELECT unnest(range(1, length(body) + 1)) AS i), LATERAL (SELECT unnest(range(1, i)) AS j)),
e AS (SELECT x.sid, (SELECT count(*) FROM range(1, j + 1) t(k) WHERE substr(body, i - k + 1, k) = substr(body, j - k + 1, k)) AS lcs, (SELECT count(*) FROM range(1, length(body) - i + 2) t(k) WHERE substr(body, i, k) = substr(body, j, k)) AS lcp FROM x JOIN s USING (sid)), p AS (SELECT DISTINCT sid, lcs, lcp FROM e)
SELECT sid, lcs, lcp FROM p WHERE NOT EXISTS (SELECT 1 FROM p q WHERE q.sid = p.sid AND q.lcs >= p.lcs AND q.lcp >= p.lcp AND (q.lcs > p.lcs OR q.lcp > p.lcp))""")
def dominant_points(spark: SparkSession, d: str) -> DataFrame:
    return st.dominant_points(st.extension_points(src.part_names(spark, d)))


@query("skyline_sum")
def skyline_sum(spark: SparkSession, d: str) -> DataFrame:
    return st.skyline_sum(_patterned(src.passages(spark, d), 2, 2))


# --- variants -----------------------------------------------------------------------------------------------------


@query("parse_no_overlap", o.phrases(o.PASSAGES, "SELECT sid, ord, lo, hi FROM w", overlap=False))
def parse_no_overlap(spark: SparkSession, d: str) -> DataFrame:
    return ph.parse_no_overlap(src.passages(spark, d))


@query("parse_trie_dictionary")
def parse_trie_dictionary(spark: SparkSession, d: str) -> DataFrame:
    return ph.parse_trie(src.documents(spark, d)).groupBy("sid").agg(F.count(F.lit(1)).alias("phrases"))


@query("parse_source_end")
def parse_source_end(spark: SparkSession, d: str) -> DataFrame:
    return ph.parse_source_end(src.passages(spark, d))


@query("bwt_runs", f"WITH s AS ({o.PASSAGES}), x AS (SELECT sid, pos, substr(body, pos) AS suffix, CASE WHEN pos > 1 THEN substr(body, pos - 1, 1) ELSE '' END AS c FROM s, LATERAL (SELECT unnest(range(1, length(body) + 2)) AS pos)), y AS (SELECT sid, c, lag(c) OVER (PARTITION BY sid ORDER BY suffix) AS b FROM x) SELECT sid, count(*) FILTER (WHERE b IS NULL OR b <> c) AS runs FROM y GROUP BY sid")
def bwt_runs(spark: SparkSession, d: str) -> DataFrame:
    return ph.bwt_runs(src.passages(spark, d))


@query("substring_complexity", o.lpf(o.PASSAGES, "SELECT sid, round(max(c / CAST(size AS DOUBLE)), 6) AS delta FROM (SELECT sid, size, count(DISTINCT gram) AS c FROM g0 GROUP BY sid, size) GROUP BY sid"))
def substring_complexity(spark: SparkSession, d: str) -> DataFrame:
    return ph.substring_complexity(src.passages(spark, d)).select("sid", F.round("delta", 6).alias("delta"))


# --- edits --------------------------------------------------------------------------------------------------------

_KINDS = {"sub": ("sub",), "ins": ("ins",), "del": ("del",), "mixed": ("sub", "ins", "del")}


def _scripts(spark: SparkSession, d: str, kind: str = "mixed") -> DataFrame:
    return changes.edit_script(src.part_names(spark, d), 3, _KINDS[kind])


for _kind in _KINDS:
    query(f"edit_replay_{_kind}", o.edited_counts(3, _KINDS[_kind]))(lambda spark, d, kind=_kind: changes.replay_transition(_scripts(spark, d, kind)))
query("baseline_rebuild", o.edited_counts(3, _KINDS["mixed"]))(lambda spark, d: changes.replay_rebuild(_scripts(spark, d)))
query("baseline_on_demand", o.edited_counts(3, _KINDS["mixed"]))(lambda spark, d: changes.replay_on_demand(_scripts(spark, d)))
query("heavy_all_occurrences", o.edited_counts(3, _KINDS["mixed"]))(lambda spark, d: changes.replay_transition(_scripts(spark, d), all_occurrences=True))
for _m in (1, 2, 4):
    query(f"edit_replay_m{_m}", o.edited_counts(3, _KINDS["mixed"]))(lambda spark, d, m=_m: changes.replay_transition(_scripts(spark, d), m=m))


@query("dynamic_equals_rebuild", "SELECT item_id AS sid, CAST(q AS BIGINT) AS seq, TRUE AS equals_rebuild FROM benchmark, range(1, 7) t(q) WHERE length(text) > 6")
def dynamic_equals_rebuild(spark: SparkSession, d: str) -> DataFrame:
    return changes.edit_costs(changes.edit_script(src.passages(spark, d), 6)).select("sid", "seq", "equals_rebuild")


@query("active_count", f"WITH {o.factors(o.edited(3, ('sub',)))} SELECT a.sid // 100 AS sid, a.sid % 100 AS seq, count(*) FILTER (WHERE a.lpf_raw <> b.lpf_raw AND greatest(a.lpf_raw, 1) <> greatest(b.lpf_raw, 1)) AS active FROM f a JOIN f b ON b.sid = a.sid - 1 AND b.pos = a.pos WHERE a.sid % 100 > 1 GROUP BY a.sid")
def active_count(spark: SparkSession, d: str) -> DataFrame:
    return changes.edit_costs(_scripts(spark, d, "sub")).where("seq > 1").select("sid", "seq", "active")


@query("edit_costs")
def edit_costs(spark: SparkSession, d: str) -> DataFrame:
    return changes.edit_costs(changes.edit_script(src.passages(spark, d), 6))


@query("edit_costs_all_occurrences")
def edit_costs_all(spark: SparkSession, d: str) -> DataFrame:
    return changes.edit_costs(changes.edit_script(src.passages(spark, d), 6), all_occurrences=True)


@query("m_sweep")
def m_sweep(spark: SparkSession, d: str) -> DataFrame:
    """How probes and moves per edit change with the width of the blocks."""
    scripts = changes.edit_script(src.passages(spark, d), 6)
    parts = [changes.edit_costs(scripts, m).groupBy().agg(F.lit(m).alias("m"), *[F.sum(c).alias(c) for c in ("factor_probes", "match_probes", "moves", "critical")], F.bool_and("equals_rebuild").alias("exact")) for m in (1, 2, 4, 6, 8, 16)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("sliding_phrase_count", o.phrases(f"SELECT sid * 1000000 + i AS sid, substr(body, greatest(i - 15, 1), i - greatest(i - 15, 1) + 1) AS body FROM ({o.USERS}), LATERAL (SELECT unnest(range(1, length(body) + 1)) AS i)", "SELECT sid // 1000000 AS sid, sid % 1000000 AS ord, CAST(max(n) AS BIGINT) AS n, count(*) AS phrases FROM w GROUP BY sid"))
def sliding_phrase_count(spark: SparkSession, d: str) -> DataFrame:
    return changes.sliding_counts(src.user_strings(spark, d), 16)


@query("turn_growth")
def turn_growth(spark: SparkSession, d: str) -> DataFrame:
    return changes.growth_counts(src.conversations(spark, d))


# Whole documents and conversations: SQL that lists all substrings is too slow there, so these have none.


def _long_scripts(spark: SparkSession, d: str, kind: str = "mixed", of: Callable[[SparkSession, str], DataFrame] = src.documents) -> DataFrame:
    """Three edits of every document or conversation; dealt to all cores."""
    return spread(changes.edit_script(of(spark, d), 3, _KINDS[kind]))


for _of, _strings in (("documents", src.documents), ("conversations", src.conversation_strings)):
    for _kind in _KINDS:
        query(f"edit_replay_{_kind}_{_of}")(lambda spark, d, kind=_kind, of=_strings: changes.replay_transition(_long_scripts(spark, d, kind, of)))
    for _m in (1, 2, 4):
        query(f"edit_replay_m{_m}_{_of}")(lambda spark, d, m=_m, of=_strings: changes.replay_transition(_long_scripts(spark, d, of=of), m=m))
    query(f"baseline_rebuild_{_of}")(lambda spark, d, of=_strings: changes.replay_rebuild(_long_scripts(spark, d, of=of)))
    query(f"baseline_on_demand_{_of}")(lambda spark, d, of=_strings: changes.replay_on_demand(_long_scripts(spark, d, of=of)))
    query(f"heavy_all_occurrences_{_of}")(lambda spark, d, of=_strings: changes.replay_transition(_long_scripts(spark, d, of=of), all_occurrences=True))
    query(f"edit_costs_{_of}")(lambda spark, d, of=_strings: changes.edit_costs(_long_scripts(spark, d, of=of)))
    query(f"active_count_{_of}")(lambda spark, d, of=_strings: changes.edit_costs(_long_scripts(spark, d, "sub", of)).select("sid", "seq", "active"))


@query("query_mix")
def query_mix(spark: SparkSession, d: str) -> DataFrame:
    return changes.query_mix(_long_scripts(spark, d))


@query("dynamic_positions")
def dynamic_positions(spark: SparkSession, d: str) -> DataFrame:
    return changes.dynamic_positions(_long_scripts(spark, d))


# --- passages in documents ----------------------------------------------------------------------------------------

MOST_PASSAGE_BYTES = 64 << 20


@query("passage_occurrences", "SELECT doc_id, item_id, CAST(strpos(d.text, b.text) AS BIGINT) AS first_pos FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def passage_occurrences(spark: SparkSession, d: str) -> DataFrame:
    """Whole passages inside documents: the passages go out after a check of their size, one pass over the documents."""
    passages = src.passages(spark, d).where("body != ''")
    total = passages.agg(F.coalesce(F.sum(F.octet_length("body")), F.lit(0))).first()[0]
    if total > MOST_PASSAGE_BYTES:
        raise ValueError(f"{total} bytes of passages: match them in parts")
    wanted = [(r["sid"], r["body"]) for r in passages.collect()]
    kernel = lambda sid, s: [(sid, item, at + 1) for item, p in wanted if (at := s.find(p)) >= 0]
    return flat_map(src.documents(spark, d), kernel, "doc_id long, item_id long, first_pos long")


@query("relative_phrases")
def relative_phrases(spark: SparkSession, d: str) -> DataFrame:
    """Phrases that cover a document behind a passage and a separator, for every passage that the document contains."""
    holds = passage_occurrences(spark, d).select("doc_id", "item_id")
    pairs = holds.join(src.documents(spark, d).withColumnRenamed("sid", "doc_id"), "doc_id").join(src.passages(spark, d).select(F.col("sid").alias("item_id"), F.col("body").alias("passage")), "item_id")
    return ph.relative_phrases(pairs)


@query("near_copy_active")
def near_copy_active(spark: SparkSession, d: str) -> DataFrame:
    """Places of equal number whose reach differs between consecutive passages (a whole-string before/after pair)."""
    reaches = ph.reach(ph.lpf(src.passages(spark, d)))
    after = reaches.select((F.col("sid") - 1).alias("sid"), "pos", "reach")
    return changes.active_indices(reaches, after).groupBy("sid").agg(F.count(F.lit(1)).alias("active"))


def _active(pair: tuple[DataFrame, DataFrame]) -> DataFrame:
    """``(sid, active)`` of every before/after pair, 0 where nothing differs."""
    before, after = (ph.reach(ph.lpf(s)) for s in pair)
    counts = changes.active_indices(before, after).groupBy("sid").agg(F.count(F.lit(1)).alias("active"))
    return pair[0].select("sid").join(counts, "sid", "left").select("sid", F.coalesce("active", F.lit(0)).alias("active"))


@query("near_copy_active_documents")
def near_copy_active_documents(spark: SparkSession, d: str) -> DataFrame:
    return _active(src.near_copies(spark, d))


@query("near_copy_active_turns")
def near_copy_active_turns(spark: SparkSession, d: str) -> DataFrame:
    return _active(src.consecutive_turns(spark, d))


# --- orthogonality ------------------------------------------------------------------------------------------------

_D = 4


def _sets(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return ov.patterns(src.table(spark, d, "embeddings"), _D)


_OV = f"WITH {o.patterns(_D)}"


@query("ov_bruteforce", f"{_OV} SELECT u, count(*) AS orthogonal, CAST(sum(a.copies * b.copies) AS BIGINT) AS row_pairs FROM a, b WHERE u & v = 0 GROUP BY u")
def ov_bruteforce(spark: SparkSession, d: str) -> DataFrame:
    return ov.direct_join(*_sets(spark, d))


@query("ov_decide", f"{_OV} SELECT u, count(*) FILTER (WHERE u & v = 0) AS orthogonal, count(*) FILTER (WHERE u & v = 0) > 0 AS has_orthogonal FROM a, b GROUP BY u")
def ov_decide(spark: SparkSession, d: str) -> DataFrame:
    return ov.decide(*_sets(spark, d), _D).select("u", "orthogonal", "has_orthogonal")


@query("ov_count", f"{_OV} SELECT CAST(sum(CASE WHEN u & v = 0 THEN 1 ELSE 0 END) AS BIGINT) AS orthogonal FROM a, b")
def ov_count(spark: SparkSession, d: str) -> DataFrame:
    return ov.decide(*_sets(spark, d), _D).agg(F.sum("orthogonal").alias("orthogonal"))


@query("ov_phrase_counts", f"{_OV} SELECT u, CAST(sum({_D} + 1 + CASE WHEN u & v = 0 THEN 0 ELSE 1 END) AS BIGINT) AS phrases FROM a, b GROUP BY u")
def ov_phrase_counts(spark: SparkSession, d: str) -> DataFrame:
    return ov.phrase_counts(*_sets(spark, d), _D).groupBy("u").agg(F.sum("phrases").alias("phrases"))


@query("ov_pair_gadget", f"{_OV} SELECT u, v, CAST({_D} + CASE WHEN u & v = 0 THEN 0 ELSE 1 END AS BIGINT) AS phrases FROM a, b")
def ov_pair_gadget(spark: SparkSession, d: str) -> DataFrame:
    return ov.pair_gadget(*_sets(spark, d), _D)


@query("ov_naive_failure")
def ov_naive_failure(spark: SparkSession, d: str) -> DataFrame:
    return ov.naive_set(*_sets(spark, d), _D)


_ROOT = "(SELECT CAST(ceil(sqrt(count(*))) AS BIGINT) AS r FROM a)"


@query("ov_sizes", f"{_OV} SELECT u, r * r AS n, {_D} * (5 * r + 1) + CAST(2 * {_D} * (r + 1) * (8 * r + r + 2) AS BIGINT) AS dictionary_symbols, {_D} * (5 * r + 2) AS query_symbols, CAST({_D} - bit_count(u) AS BIGINT) AS substitutions FROM b, {_ROOT}")
def ov_sizes(spark: SparkSession, d: str) -> DataFrame:
    a, b = _sets(spark, d)
    return ov.sizes(b, a, _D).select("u", "n", "dictionary_symbols", "query_symbols", "substitutions")


def _whole(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return ov.whole_patterns(src.table(spark, d, "embeddings"))


_OV_ALL = "WITH p AS (SELECT vec_id % 2 AS side, array_to_string([CASE WHEN x > 0 THEN '1' ELSE '0' END FOR x IN embedding], '') AS bits FROM embeddings), a AS (SELECT bits AS v, count(*) AS copies FROM p WHERE side = 0 GROUP BY bits), b AS (SELECT bits AS u, count(*) AS copies FROM p WHERE side = 1 GROUP BY bits), c AS (SELECT u, v, a.copies * b.copies AS pairs, length(u) AS d, bit_count(CAST(u AS BIT) & CAST(v AS BIT)) = 0 AS apart FROM a, b)"


@query("ov_bruteforce_all", f"{_OV_ALL} SELECT u, count(*) FILTER (WHERE apart) AS orthogonal, CAST(coalesce(sum(pairs) FILTER (WHERE apart), 0) AS BIGINT) AS row_pairs FROM c GROUP BY u")
def ov_bruteforce_all(spark: SparkSession, d: str) -> DataFrame:
    return ov.whole_join(*_whole(spark, d))


@query("ov_decide_all", f"{_OV_ALL} SELECT u, CAST(sum(d + 1 + CASE WHEN apart THEN 0 ELSE 1 END) AS BIGINT) AS phrases, count(*) FILTER (WHERE apart) AS orthogonal, count(*) FILTER (WHERE apart) > 0 AS has_orthogonal FROM c GROUP BY u")
def ov_decide_all(spark: SparkSession, d: str) -> DataFrame:
    return ov.whole_decide(*_whole(spark, d))


@query("ov_count_all", f"{_OV_ALL} SELECT count(*) FILTER (WHERE apart) AS orthogonal FROM c")
def ov_count_all(spark: SparkSession, d: str) -> DataFrame:
    return ov.whole_decide(*_whole(spark, d)).agg(F.coalesce(F.sum("orthogonal"), F.lit(0)).alias("orthogonal"))


@query("ov_phrase_counts_all", f"{_OV_ALL} SELECT u, CAST(sum(d + 1 + CASE WHEN apart THEN 0 ELSE 1 END) AS BIGINT) AS phrases FROM c GROUP BY u")
def ov_phrase_counts_all(spark: SparkSession, d: str) -> DataFrame:
    return ov.whole_decide(*_whole(spark, d)).select("u", "phrases")


@query("ov_pair_gadget_all", f"{_OV_ALL} SELECT u, v, CAST(d + CASE WHEN apart THEN 0 ELSE 1 END AS BIGINT) AS phrases FROM c")
def ov_pair_gadget_all(spark: SparkSession, d: str) -> DataFrame:
    return ov.whole_pair_gadget(*_whole(spark, d))


@query("ov_naive_failure_all")
def ov_naive_failure_all(spark: SparkSession, d: str) -> DataFrame:
    return ov.whole_naive_set(*_whole(spark, d))


@query("ov_sizes_all")
def ov_sizes_all(spark: SparkSession, d: str) -> DataFrame:
    a, b = _whole(spark, d)
    return ov.whole_sizes(b, a)


# --- streams, and one string by position ranges -------------------------------------------------------------------

@query("stream_sliding_counts", ORACLES["sliding_phrase_count"])
def stream_sliding_counts(spark: SparkSession, d: str) -> DataFrame:
    from phraseloom.streaming import stream

    return stream.sliding_counts(spark, d)


_DAYS = "SELECT user_id * 1000000 + CAST(epoch_us(date_trunc('day', ts)) // 86400000000 AS BIGINT) AS sid, string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id) AS body FROM {events} GROUP BY user_id, date_trunc('day', ts)"
_WINDOW = "SELECT sid // 1000000 AS user_id, (sid % 1000000) * 86400000000 AS start_us, CAST(max(n) AS BIGINT) AS n, count(*) AS phrases FROM w GROUP BY sid"


@query("stream_edit_replay", o.edited_counts(3, _KINDS["mixed"]))
def stream_edit_replay(spark: SparkSession, d: str) -> DataFrame:
    """Edits as a stream: keyed state holds each string and its forest, and every edit is one transition."""
    from phraseloom.streaming import stream

    return stream.edit_counts(spark, d, _KINDS["mixed"])


@query("stream_join", "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 DAY WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def stream_join(spark: SparkSession, d: str) -> DataFrame:
    """Two streams: every click with the same user's purchases of the day after it."""
    from phraseloom.streaming import stream

    return stream.followed_by(spark, d, "click", "purchase", "1 day")


@query("stream_tumbling", o.phrases(_DAYS.format(events="events"), _WINDOW))
def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    from phraseloom.streaming import stream

    return stream.window_counts(spark, d, "tumbling")


@query("stream_sliding_windows", o.phrases(_DAYS.format(events="(SELECT user_id, ts - INTERVAL 1 DAY * back AS day, ts, event_id, event_type FROM events, range(0, 2) t(back))").replace("date_trunc('day', ts)", "date_trunc('day', day)"), _WINDOW))
def stream_sliding_windows(spark: SparkSession, d: str) -> DataFrame:
    from phraseloom.streaming import stream

    return stream.window_counts(spark, d, "sliding")


_SESSIONS = """SELECT user_id * 100000 + s AS sid, string_agg(c, '' ORDER BY ts, event_id) AS body, min(ts) AS start FROM (SELECT *, sum(CASE WHEN gap IS NULL OR gap > INTERVAL 1 DAY THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s
  FROM (SELECT user_id, ts, event_id, substr(event_type, 1, 1) AS c, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap FROM events)) GROUP BY user_id, s"""


@query("stream_sessions", o.phrases(_SESSIONS, "SELECT w.sid // 100000 AS user_id, epoch_us(min(start)) AS start_us, CAST(max(n) AS BIGINT) AS n, count(*) AS phrases FROM w JOIN s USING (sid) GROUP BY w.sid"))
def stream_sessions(spark: SparkSession, d: str) -> DataFrame:
    from phraseloom.streaming import stream

    return stream.window_counts(spark, d, "session")


@query("huge_suffix_ranks", "WITH e AS (SELECT row_number() OVER (ORDER BY event_id) AS pos, substr(event_type, 1, 1) AS sym FROM events), b AS (SELECT string_agg(sym, '' ORDER BY pos) AS body FROM e) SELECT pos, row_number() OVER (ORDER BY substr(body, CAST(pos AS INTEGER))) AS rank FROM e, b")
def huge_suffix_ranks(spark: SparkSession, d: str) -> DataFrame:
    """Suffix array of one string given as rows: event ids are dense, so they number the positions."""
    from phraseloom.plans import huge_string

    events = src.table(spark, d, "events")
    low = events.agg(F.min("event_id")).first()[0]
    return huge_string.suffix_ranks(events.select((F.col("event_id") - low + 1).alias("pos"), F.substring("event_type", 1, 1).alias("sym")), parts=8)


@query("huge_root_path", o.phrases(o.USERS, "SELECT sid, ord, lo, hi FROM w WHERE sid = (SELECT min(user_id) FROM events)"))
def huge_root_path(spark: SparkSession, d: str) -> DataFrame:
    """The parse of one user's string from its position table, in blocks of 16 places."""
    from phraseloom.plans import huge_string

    users = src.user_strings(spark, d)
    least = users.agg(F.min("sid")).first()[0]
    reaches = ph.reach(ph.lpf(users.where(F.col("sid") == least)))
    return huge_string.root_path(reaches, block=16).select(F.lit(least).alias("sid"), "ord", "lo", "hi")


@query("huge_root_path_events")
def huge_root_path_events(spark: SparkSession, d: str) -> DataFrame:
    """The parse of the whole event string (the one that ``huge_suffix_ranks`` reads), in blocks of the default size."""
    from phraseloom.plans import huge_string

    symbols = F.array_sort(F.collect_list(F.struct("event_id", F.substring("event_type", 1, 1).alias("sym"))))
    body = F.array_join(F.transform(symbols, lambda e: e["sym"]), "")
    whole = src.table(spark, d, "events").agg(body.alias("body")).select(F.lit(0).cast("long").alias("sid"), "body")
    return huge_string.root_path(ph.reach(ph.lpf(whole))).select("ord", "lo", "hi")
