"""URL filter: explicit host/path rules first, then a path-template tree per host.

The tree works on pre-aggregated shapes. A shape is the host and its path segments, each variable-looking segment
(numbers, hexadecimal ids, dates) already written as a wildcard class. Level by level, a branch keeps its literal name
only if its labelled reject rate is significantly above that of its siblings; branches significantly below merge into
``*-``, and all that do not differ from their siblings into ``*``. A template's reject rate is smoothed towards its host's, which is smoothed towards the
rate of all labelled pages; templates at or above a purity are rejected. The tree grows until no branch has a further
segment. Pages below a branch whose labels all agree (or are missing) can't differ any more and are named to their end
at once, so deep paths take further levels only where labels differ.

Labels come from the caller (``bad`` true, false or null) or, as in the registered query, from the rules: a URL that a
rule decides is a labelled example for its template.

Defined cases: a null URL, or one without ``://``, has an empty host and path; empty tables give empty results;
repeated rows count as often as they occur; paths of any depth are read whole; columns of the input other than the key
and the URL are not read.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from phraseloom.llm.common import durable

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
AFTER_SCHEME = r"(?s)^.*?://([^/?#]*)([^?#]*)"

#: Rule text -> verdict; the text is a host, then the start of the path.
DEFAULT_RULES = {"org/": "allow", "example.org/es/": "block", "example.org/en/1": "block", "com/fr/": "allow", "com/de/": "block"}


def host_and_path(url: str = "url") -> tuple[Column, Column]:
    text = F.coalesce(F.col(url), F.lit(""))
    return F.translate(F.regexp_extract(text, AFTER_SCHEME, 1), UPPER, LOWER), F.regexp_extract(text, AFTER_SCHEME, 2)


def rule_column(rules: dict[str, str], host: Column, path: Column) -> Column:
    """The longest rule that fits, or null."""

    def fits(rule: str) -> Column:
        name, slash, rest = rule.partition("/")
        return ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)

    ordered = sorted(rules, key=len, reverse=True)
    return reduce(lambda chain, rule: chain.when(fits(rule), F.lit(rule)), ordered[1:], F.when(fits(ordered[0]), F.lit(ordered[0]))) if ordered else F.lit(None).cast("string")


def _segment_class(segment: Column) -> Column:
    extension = F.regexp_extract(segment, r"(\.[A-Za-z]{1,5})$", 1)
    stem = F.regexp_replace(segment, r"\.[A-Za-z]{1,5}$", "")
    return (
        F.when(stem.rlike(r"^[0-9]+$"), F.concat(F.lit("<n>"), extension))
        .when(stem.rlike(r"^[0-9]{1,4}[-_.][0-9]{1,2}([-_.][0-9]{1,4})?$"), F.concat(F.lit("<date>"), extension))
        .when(stem.rlike(r"^(?=.*[0-9])[0-9A-Fa-f-]{8,}$"), F.concat(F.lit("<hex>"), extension))
        .otherwise(segment)
    )


def _shape(path: Column) -> Column:
    return F.transform(F.filter(F.split(path, "/"), lambda s: s != ""), _segment_class)


def template_rates(shapes: DataFrame, z_least: float = 2.576, prior_weight: float = 5.0) -> DataFrame:
    """Add ``template`` and its smoothed ``purity`` (share of rejects) to distinct shapes ``(host, shape, n, lab, bad)``."""
    tree, level = durable(shapes.withColumns({"_at": F.col("host"), "_done": F.lit(False)})), 0
    while tree.where(~F.col("_done")).limit(1).count():
        level += 1
        child = F.when(~F.col("_done"), F.get("shape", F.lit(level - 1)))
        grown = tree.withColumn("_child", child)
        branches = grown.where(F.col("_child").isNotNull()).groupBy("_at", "_child").agg(F.sum("lab").alias("lab_c"), F.sum("bad").alias("bad_c"))
        parents = branches.groupBy("_at").agg(F.sum("lab_c").alias("lab_p"), F.sum("bad_c").alias("bad_p"))
        rest, pooled = F.col("lab_p") - F.col("lab_c"), F.col("bad_p") / F.greatest(F.col("lab_p"), F.lit(1))
        gap = F.col("bad_c") / F.greatest(F.col("lab_c"), F.lit(1)) - (F.col("bad_p") - F.col("bad_c")) / F.greatest(rest, F.lit(1))
        spread = F.sqrt(pooled * (1 - pooled) * (1 / F.greatest(F.col("lab_c"), F.lit(1)) + 1 / F.greatest(rest, F.lit(1))))
        apart = (F.col("lab_c") > 0) & (rest > 0) & (F.abs(gap) > z_least * spread)
        mixed = (F.col("bad_p") > 0) & (F.col("bad_p") < F.col("lab_p"))
        own = branches.join(parents.where(mixed), "_at").select("_at", "_child", F.when(apart & (gap > 0), F.col("_child")).when(apart, F.lit("*-")).otherwise("*").alias("_own"))
        left = F.size("shape") - level + 1
        named = F.when(F.col("_child").isNull(), F.col("_at")).when(F.col("_own").isNull(), F.concat("_at", F.repeat(F.lit("/*"), left))).otherwise(F.concat_ws("/", "_at", "_own"))
        tree = durable(grown.join(own, ["_at", "_child"], "left").select("host", "shape", "n", "lab", "bad", named.alias("_at"), F.col("_own").isNull().alias("_done")))
    tree = tree.drop("_done")
    tree = tree.withColumnRenamed("_at", "template")
    every = tree.agg(((F.sum("bad") + 1) / (F.sum("lab") + 2)).alias("rate_all"))
    by_host = tree.groupBy("host").agg(F.sum("lab").alias("lab_h"), F.sum("bad").alias("bad_h")).join(F.broadcast(every))  # one row
    by_host = by_host.select("host", ((F.col("bad_h") + prior_weight * F.coalesce("rate_all", F.lit(0.5))) / (F.col("lab_h") + prior_weight)).alias("rate_h"))
    by_template = tree.groupBy("host", "template").agg(F.sum("lab").alias("lab_t"), F.sum("bad").alias("bad_t")).join(by_host, "host")
    rate = (F.col("bad_t") + prior_weight * F.col("rate_h")) / (F.col("lab_t") + prior_weight)
    return tree.join(by_template.select("host", "template", rate.alias("purity")), ["host", "template"]).select("host", "shape", "template", "purity")


def judge_urls(
    pages: DataFrame, key: str = "page_id", url: str = "url", rules: dict[str, str] | None = None, bad: Column | None = None, reject_purity: float = 0.8
) -> DataFrame:
    """``(key, host, path, rule, verdict, template, purity)`` for each page. ``bad`` labels pages; by default the rules do."""
    rules = DEFAULT_RULES if rules is None else rules
    host, path = host_and_path(url)
    seen = pages.select(F.col(key), host.alias("host"), path.alias("path"), *([bad.alias("_bad")] if bad is not None else []))
    seen = seen.withColumn("rule", rule_column(rules, F.col("host"), F.col("path")))
    ruled = reduce(lambda c, r: c.when(F.col("rule") == r, F.lit(rules[r])), rules, F.when(F.lit(False), F.lit(""))) if rules else F.lit(None).cast("string")
    seen = seen.withColumns({"_ruled": ruled, "shape": _shape(F.col("path"))})
    label = F.col("_bad") if bad is not None else F.col("_ruled") == "block"
    shapes = seen.groupBy("host", "shape").agg(F.count(F.lit(1)).alias("n"), F.count(label).alias("lab"), F.count_if(F.coalesce(label, F.lit(False))).alias("bad"))
    rates = template_rates(shapes)
    verdict = F.coalesce("_ruled", F.when(F.col("purity") >= reject_purity, F.lit("block")).otherwise("allow"))
    return seen.join(rates, ["host", "shape"], "left").select(key, "host", "path", "rule", verdict.alias("verdict"), "template", "purity")
