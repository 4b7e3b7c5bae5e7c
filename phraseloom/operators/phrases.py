"""The greedy parse and what follows from it: factors, reach forest, phrase queries, codes, checks, variants."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from phraseloom.functions import kernels as k
from phraseloom.operators.per_string import flat_map, flat_map_parsed

PHRASES = "sid long, ord long, lo long, hi long, src long, sym string"


def lpf(strings: DataFrame) -> DataFrame:
    """``(sid, pos, lpf_raw, lpf)``."""
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, i, x, max(1, x)) for i, x in enumerate(k.lpf(s), 1)], "sid long, pos long, lpf_raw long, lpf long")


def lpf_witness(strings: DataFrame) -> DataFrame:
    """Rightmost earlier start of each place's longest previous factor (null: fresh)."""
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, i, w) for i, w in enumerate(k.witnesses(s, k.lpf(s)), 1)], "sid long, pos long, witness long")


def lpf_by_grams(strings: DataFrame) -> DataFrame:
    """JVM-side for short strings: every substring with its first start, by a window (rows grow with the square of n)."""
    cores = strings.sparkSession.sparkContext.defaultParallelism
    dealt = strings.where("body != ''").repartition(4 * cores, "sid")  # windows and groups below find their keys together: grams stay in their task
    starts = dealt.select("sid", "body", F.explode(F.sequence(F.lit(1), F.char_length("body"))).alias("pos"))
    grams = starts.select("sid", "pos", F.explode(F.sequence(F.lit(1), F.char_length("body") - F.col("pos") + 1)).alias("size"), "body")
    named = grams.select("sid", "pos", "size", F.substring("body", F.col("pos"), F.col("size")).alias("gram"))
    first = named.withColumn("first", F.min("pos").over(Window.partitionBy("sid", "gram")))
    raw = F.coalesce(F.max(F.when(F.col("first") < F.col("pos"), F.col("size"))), F.lit(0)).cast("long")
    return first.groupBy("sid", F.col("pos").cast("long").alias("pos")).agg(raw.alias("lpf_raw")).select("sid", "pos", "lpf_raw", F.greatest("lpf_raw", F.lit(1)).alias("lpf"))


def reach(factors: DataFrame) -> DataFrame:
    """``(sid, pos, reach)``."""
    return factors.select("sid", "pos", (F.col("pos") + F.col("lpf")).alias("reach"))


def forest(reaches: DataFrame) -> DataFrame:
    """The reach forest as intervals ``(sid, lo, hi, parent)``: the children of a node are consecutive places."""
    return reaches.groupBy("sid", F.col("reach").alias("parent")).agg(F.min("pos").alias("lo"), F.max("pos").alias("hi")).select("sid", "lo", "hi", "parent")


def parse(strings: DataFrame) -> DataFrame:
    """Phrases; a copy's source is its rightmost earlier start."""

    def kernel(sid: int, s: str, parsed: list[tuple]) -> list[tuple]:
        return [(sid, o, lo, hi, *((s.rfind(s[lo - 1 : hi], 0, hi - 1) + 1, None) if length else (None, s[lo - 1]))) for o, (lo, hi, length, _) in enumerate(parsed, 1)]

    return flat_map_parsed(strings, kernel, PHRASES)


def parse_stats(strings: DataFrame) -> DataFrame:
    """``(sid, n, phrases, copies, literals, ints)``; the phrases themselves never leave the task."""

    def kernel(sid: int, s: str, parsed: list[tuple]) -> list[tuple]:
        phrases, copies = len(parsed), sum(length > 0 for _, _, length, _ in parsed)
        return [(sid, len(s), phrases, copies, phrases - copies, 2 * copies + phrases - copies)]

    return flat_map_parsed(strings, kernel, "sid long, n long, phrases long, copies long, literals long, ints long")


def parse_no_overlap(strings: DataFrame) -> DataFrame:
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, o, lo, hi) for o, (lo, hi, _) in enumerate(k.parse(s, overlap=False), 1)], "sid long, ord long, lo long, hi long")


def parse_trie(strings: DataFrame) -> DataFrame:
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, o, *p) for o, p in enumerate(k.trie_parse(s), 1)], "sid long, ord long, lo long, hi long, parent_ord long")


def parse_source_end(strings: DataFrame) -> DataFrame:
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, o, lo, hi) for o, (lo, hi, _) in enumerate(k.parse_to_phrase_ends(s), 1)], "sid long, ord long, lo long, hi long")


def bwt_runs(strings: DataFrame) -> DataFrame:
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, k.bwt_runs(s))], "sid long, runs long")


def substring_complexity(strings: DataFrame) -> DataFrame:
    return flat_map(strings.select("sid", "body"), lambda sid, s: [(sid, *k.substring_complexity(s))], "sid long, k_best long, delta double")


def select_phrase(phrases: DataFrame, ordinals: DataFrame) -> DataFrame:
    """Phrase number ``ord`` of each requested ``(sid, ord)``."""
    return phrases.join(ordinals, ["sid", "ord"]).select("sid", "ord", "lo", "hi")


def containing_phrase(phrases: DataFrame, positions: DataFrame) -> DataFrame:
    """The phrase that holds each requested ``(sid, pos)``: an as-of look-up of the last phrase start, without a range join."""
    points = phrases.select("sid", F.col("lo").alias("at"), F.lit(0).alias("kind"), "ord", "lo", "hi")
    asked = positions.select("sid", F.col("pos").alias("at"), F.lit(1).alias("kind"), *[F.lit(None).cast("long").alias(c) for c in ("ord", "lo", "hi")])
    w = Window.partitionBy("sid").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    filled = points.unionByName(asked).select("sid", "at", "kind", *[F.last(c, ignorenulls=True).over(w).alias(c) for c in ("ord", "lo", "hi")])
    return filled.where("kind = 1 and hi >= at").select("sid", F.col("at").alias("pos"), "ord", "lo", "hi")


def prefix_parse_length(phrases: DataFrame, positions: DataFrame) -> DataFrame:
    """Phrases of the prefix up to ``pos``: a prefix's parse is the whole parse cut there."""
    return containing_phrase(phrases, positions).select("sid", "pos", F.col("ord").alias("phrases"))


def valid_factorization(strings: DataFrame, phrases: DataFrame) -> DataFrame:
    """JVM-side: is every factor a single symbol or a substring with an earlier start, and do they tile the string?"""
    checked = phrases.join(strings, "sid")
    gram = F.substring("body", F.col("lo"), F.col("hi") - F.col("lo") + 1)
    single = F.col("lo") == F.col("hi")
    tiles = F.sum(F.col("hi") - F.col("lo") + 1) == F.max(F.char_length("body"))
    return checked.select("sid", "lo", "hi", "body", (single | (F.instr("body", gram) < F.col("lo"))).alias("ok")).groupBy("sid").agg((F.bool_and("ok") & tiles).alias("valid"))


def roundtrip(strings: DataFrame) -> DataFrame:
    """Digest of the decoded code of each string; any earlier start is a source here."""
    import hashlib

    def kernel(sid: int, s: str, parsed: list[tuple]) -> list[tuple]:
        back = k.decode((lo, hi, source or None, None if length else s[lo - 1]) for lo, hi, length, source in parsed)
        return [(sid, len(back), hashlib.md5(back.encode("utf-8", "surrogatepass")).hexdigest())]

    return flat_map_parsed(strings, kernel, "sid long, n long, digest string")


def _parent_lists(parents: DataFrame) -> DataFrame:
    """``(sid, up)``: the parents of a string's places in order, one row a string, so that no edge leaves its row."""
    pairs = parents.groupBy("sid").agg(F.array_sort(F.collect_list(F.struct("pos", "reach"))).alias("p"))
    return pairs.select("sid", F.transform("p", lambda e: e["reach"]).alias("up"))


def _at(values, node):
    """Entry of a node; 0 for the root, which lies behind the last place, and for 0 (a state's lists can hold no nulls)."""
    return F.coalesce(F.get(values, (node - 1).cast("int")), F.lit(0).cast("long"))


def _exploded(rows: DataFrame, values: str, name: str) -> DataFrame:
    return rows.select("sid", F.posexplode(values).alias("at", name)).select("sid", (F.col("at") + 1).cast("long").alias("node"), name)


def forest_depths(parents: DataFrame, longest: int) -> DataFrame:
    """Depth of every node by pointer doubling inside each string's list of parents: log2(longest) rounds, no join."""

    def double(state, _):
        up = F.transform(state["up"], lambda u: F.greatest(_at(state["up"], u), u))
        return F.struct(up.alias("up"), F.zip_with(state["depth"], state["up"], lambda d, u: d + _at(state["depth"], u)).alias("depth"))

    # one expression with its state as a variable: as columns of their own, the rounds would be written into one another
    start = F.struct("up", F.transform("up", lambda _: F.lit(1).cast("long")).alias("depth"))
    rounds = F.sequence(F.lit(1), F.lit(max(1, longest).bit_length()))
    return _exploded(_parent_lists(parents).select("sid", F.aggregate(rounds, start, double, lambda state: state["depth"]).alias("depth")), "depth", "depth")


def forest_ancestor(parents: DataFrame, steps: int) -> DataFrame:
    """The ancestor ``steps`` edges above each node that has one: jumps of 1, 2, 4, ... edges inside each string's list of parents."""

    def jump(state, bit):
        here = F.when(bit, F.transform(state["here"], lambda x: _at(state["up"], x))).otherwise(state["here"])
        return F.struct(here.alias("here"), F.transform(state["up"], lambda u: _at(state["up"], u)).alias("up"))

    start = F.struct(F.sequence(F.lit(1).cast("long"), F.size("up").cast("long")).alias("here"), "up")
    bits = F.array(*[F.lit(bool(steps >> b & 1)) for b in range(steps.bit_length())])
    found = _parent_lists(parents).select("sid", F.aggregate(bits, start, jump, lambda state: state["here"]).alias("here"))
    return _exploded(found, "here", "ancestor").where("ancestor > 0")


def greedy_optimal(strings: DataFrame) -> DataFrame:
    """``(sid, phrases, fewest)``: the greedy parse against the least number of phrases of all valid factorizations."""
    return flat_map(strings.where("body != ''").select("sid", "body"), lambda sid, s: [(sid, sum(1 for _ in k.parse(s)), k.fewest_phrases(s))], "sid long, phrases long, fewest long")


def relative_phrases(pairs: DataFrame) -> DataFrame:
    """``(doc_id, item_id, alone, phrases)`` for rows ``(doc_id, item_id, body, passage)``: phrases of the body, by itself and behind the passage and a separator that occurs nowhere else."""

    def kernel(doc: int, item: int, s: str, passage: str) -> list[tuple]:
        used = set(s) | set(passage)
        text = passage + next(c for c in map(chr, range(0x10FFFF, 0, -1)) if c not in used) + s
        at, count = len(passage) + 1, 0
        while at < len(text):
            at, count = at + max(1, k.earlier_factor(text, at)[0]), count + 1
        return [(doc, item, sum(1 for _ in k.parse(s)), count)]

    return flat_map(pairs.select("doc_id", "item_id", "body", "passage"), kernel, "doc_id long, item_id long, alone long, phrases long")
