"""Registered queries on the classes of one substitution in every order string, with SQL from the definitions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phraseloom.operators import changes, classes
from phraseloom.operators.per_string import spread
from phraseloom.plans import oracles as o
from phraseloom.sources import tables as src
from phraseloom.workloads import query

#: Width of the blocks beside the edit.
M = 2
SYMBOLS = "AFNOR"


def _scripts(spark: SparkSession, d: str) -> DataFrame:
    return spread(changes.edit_script(src.order_strings(spark, d), 1, ("sub",), SYMBOLS))


def _blocks(strings: DataFrame) -> DataFrame:
    """A block i..j in each string, fixed by arithmetic."""
    i = 1 + F.pmod(5 * F.col("sid"), F.char_length("body").cast("long"))
    return strings.withColumn("i", i).withColumn("j", F.least(i + F.col("sid") % 3, F.char_length("body")))


_I = "1 + (5 * sid) % length(body)"
_BLOCKS = f"SELECT sid, {_I} AS i, least({_I} + sid % 3, length(body)) AS j FROM ({o.ORDERS}) WHERE length(body) > 1"
#: Old strings have the number 0, new ones 1; ``e`` is the edit, ``p`` the shorter factor (1: fresh) and both parents of every place.
_BOTH = f"""{o.factors(f"SELECT sid * 100 AS sid, body FROM ({o.ORDERS}) WHERE length(body) > 1 UNION ALL ({o.edited(1, ('sub',), SYMBOLS, o.ORDERS)})")},
e AS MATERIALIZED (SELECT sid, 1 + (7 * sid + 13) % greatest(length(body) - 1, 1) AS z, length(body) AS n FROM ({o.ORDERS}) WHERE length(body) > 1),
p AS MATERIALIZED (SELECT a.sid // 100 AS sid, a.pos, least(greatest(a.lpf_raw, 1), greatest(b.lpf_raw, 1)) AS common, a.pos + greatest(a.lpf_raw, 1) AS before, b.pos + greatest(b.lpf_raw, 1) AS after
  FROM f a JOIN f b ON b.sid = a.sid + 1 AND b.pos = a.pos WHERE a.sid % 100 = 0)"""
#: Leftmost later copies of the windows over the edit.
_LIGHT = f"""light AS MATERIALIZED (SELECT DISTINCT sid, pos FROM (SELECT e.sid, w.sid, w.pos, w.size, min(c.pos) AS pos
  FROM e JOIN g0 w ON w.sid // 100 = e.sid AND w.pos BETWEEN e.z - {M} AND e.z AND w.pos + w.size - 1 BETWEEN e.z AND e.z + {M}
  JOIN g0 c ON c.sid = w.sid AND c.gram = w.gram AND c.pos > e.z GROUP BY e.sid, w.sid, w.pos, w.size) t(sid, version, low, size, pos))"""
#: Places where the block beside the edit stands in the old and in the new string.
_BLOCK = f"""block AS (SELECT sid, 'l' AS side, greatest(1, z - {M}) AS lo, z - greatest(1, z - {M}) AS size FROM e UNION ALL SELECT sid, 'r', z + 1, least({M}, n - z) FROM e),
stands AS MATERIALIZED (SELECT k.sid, k.side, k.size, x.pos FROM block k JOIN g0 a ON a.sid = 100 * k.sid AND a.pos = k.lo AND a.size = k.size
  JOIN g0 x ON x.sid = a.sid AND x.gram = a.gram JOIN g0 y ON y.sid = a.sid + 1 AND y.gram = a.gram AND y.pos = x.pos),
heavy AS MATERIALIZED (SELECT DISTINCT p.sid, p.pos, side FROM p JOIN stands s ON s.sid = p.sid AND s.pos BETWEEN p.pos AND p.pos + p.common - s.size WHERE before <> after)"""
_HEAVY_ROWS = f"WITH {_BOTH}, {_BLOCK} SELECT sid, pos, CAST(bool_or(side = 'l') AS BOOLEAN) AS left_heavy, CAST(bool_or(side = 'r') AS BOOLEAN) AS right_heavy FROM heavy GROUP BY sid, pos"
_CLASSES = f"""WITH {_BOTH}, {_LIGHT}, {_BLOCK}, c AS (SELECT p.sid, p.pos, before, after, p.pos BETWEEN e.z - {M + 1} AND e.z AS super_light, q.pos IS NOT NULL AS light, l.pos IS NOT NULL AS left_heavy, r.pos IS NOT NULL AS right_heavy
  FROM p JOIN e ON e.sid = p.sid LEFT JOIN light q ON q.sid = p.sid AND q.pos = p.pos LEFT JOIN heavy l ON l.sid = p.sid AND l.pos = p.pos AND l.side = 'l' LEFT JOIN heavy r ON r.sid = p.sid AND r.pos = p.pos AND r.side = 'r' WHERE before <> after)"""
#: A list per string and block: i itself and, if its parent exceeds j, the first places of all parents above j, up to i.
_LISTS = """lists AS MATERIALIZED (SELECT sid, i AS pos FROM t UNION SELECT t.sid, c.lo FROM t JOIN f x ON x.sid = t.sid AND x.pos = t.i AND x.pos + greatest(x.lpf_raw, 1) > t.j
  JOIN (SELECT sid, pos + greatest(lpf_raw, 1) AS reach, min(pos) AS lo FROM f GROUP BY ALL) c ON c.sid = t.sid AND c.reach > t.j AND c.lo <= t.i)"""


@query("active_indices", f"WITH {_BOTH} SELECT sid, pos, before, after FROM p WHERE before <> after")
def active_indices(spark: SparkSession, d: str) -> DataFrame:
    return classes.index_classes(_scripts(spark, d), M).select("sid", "pos", "before", "after")


@query("index_classes", f"{_CLASSES} SELECT sid, pos, super_light, light, left_heavy, right_heavy FROM c")
def index_classes(spark: SparkSession, d: str) -> DataFrame:
    return classes.index_classes(_scripts(spark, d), M).select("sid", "pos", *classes.CLASSES)


@query("super_light", f"WITH {_BOTH} SELECT sid, pos, after AS parent FROM p JOIN e USING (sid) WHERE pos BETWEEN z - {M + 1} AND z")
def super_light(spark: SparkSession, d: str) -> DataFrame:
    return classes.updated(_scripts(spark, d), "super_light", M).select("sid", "pos", "parent")


@query("light_indices", f"WITH {_BOTH}, {_LIGHT} SELECT sid, pos, after AS parent FROM p JOIN light USING (sid, pos)")
def light_indices(spark: SparkSession, d: str) -> DataFrame:
    return classes.updated(_scripts(spark, d), "light", M).select("sid", "pos", "parent")


def _heavy(spark: SparkSession, d: str, every: bool) -> DataFrame:
    return classes.index_classes(_scripts(spark, d), M, every).where("left_heavy or right_heavy").select("sid", "pos", "left_heavy", "right_heavy")


@query("heavy_aperiodic", _HEAVY_ROWS)
def heavy_aperiodic(spark: SparkSession, d: str) -> DataFrame:
    """Heavy indices by every common occurrence of the blocks."""
    return _heavy(spark, d, True)


@query("heavy_general", _HEAVY_ROWS)
def heavy_general(spark: SparkSession, d: str) -> DataFrame:
    """Heavy indices by three occurrences of each cluster: the same rows."""
    return _heavy(spark, d, False)


@query("class_sizes", f"{_CLASSES} SELECT sid, count(*) AS active, {', '.join(f'count(*) FILTER (WHERE {c}) AS {c}' for c in classes.CLASSES)}, count(*) FILTER (WHERE NOT (super_light OR light OR left_heavy OR right_heavy)) AS unclassed FROM c GROUP BY sid")
def class_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Changed indices of each edit by class; none is without class."""
    rows = classes.index_classes(_scripts(spark, d), M)
    none = ~(F.col("super_light") | F.col("light") | F.col("left_heavy") | F.col("right_heavy"))
    return rows.groupBy("sid").agg(F.count(F.lit(1)).alias("active"), *[F.count_if(F.col(c)).alias(c) for c in classes.CLASSES], F.count_if(none).alias("unclassed"))


@query("critical_indices", f"WITH {o.factors(f'SELECT sid, body FROM ({o.ORDERS}) WHERE length(body) > 1')}, t AS ({_BLOCKS}), {_LISTS} SELECT DISTINCT sid, CAST(pos AS BIGINT) AS pos FROM lists")
def critical_indices(spark: SparkSession, d: str) -> DataFrame:
    return classes.critical_indices(_blocks(spread(src.order_strings(spark, d).where("char_length(body) > 1"))))


@query("clean_intervals", f"""WITH {_BOTH}, b AS ({_BLOCKS}), t AS (SELECT 100 * sid + v AS sid, i, j FROM b, range(2) u(v)), {_LISTS},
low AS (SELECT sid // 100 AS sid, max(least_pos) AS floor FROM (SELECT sid, min(pos) AS least_pos FROM lists GROUP BY sid) GROUP BY sid // 100),
cut AS (SELECT DISTINCT l.sid // 100 AS sid, l.pos FROM lists l JOIN low ON low.sid = l.sid // 100 AND l.pos >= low.floor),
span AS (SELECT sid, pos AS lo, coalesce(lead(pos) OVER (PARTITION BY sid ORDER BY pos) - 1, pos) AS hi FROM cut)
SELECT sid, CAST(lo AS BIGINT) AS lo, CAST(hi AS BIGINT) AS hi, before, after FROM span JOIN p ON p.sid = span.sid AND p.pos = span.lo""".replace("SELECT sid, CAST(lo", "SELECT span.sid, CAST(lo"))
def clean_intervals(spark: SparkSession, d: str) -> DataFrame:
    return classes.clean_intervals(_blocks(_scripts(spark, d)))


def _passage_log(spark: SparkSession, d: str) -> DataFrame:
    return classes.transition_log(changes.edit_script(src.passages(spark, d), 6, ("sub",)))


@query("critical_sum")
def critical_sum(spark: SparkSession, d: str) -> DataFrame:
    """Lengths of the critical lists of six substitutions in each passage, by the three parts of the bound, beside n / m."""
    m = F.ceil(F.cbrt(F.col("n")))
    return _passage_log(spark, d).select("sid", "seq", "n", "critical", "critical_starts", "critical_end", "critical_near", F.round(F.col("n") / m, 3).alias("n_over_m"))


@query("moves_per_edit")
def moves_per_edit(spark: SparkSession, d: str) -> DataFrame:
    return _passage_log(spark, d).select("sid", "seq", "n", "moves", "clusters")
