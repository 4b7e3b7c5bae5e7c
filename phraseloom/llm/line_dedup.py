"""Line deduplication as an exact set-similarity join, with DataFrame functions only.

A line is its set of distinct lower-case words. A line goes when an earlier line (by key, text hash, line number) has
Jaccard similarity of at least ``percent`` / 100 with it, whether or not that earlier line itself stays. Lines without a
word always stay.

1. Word counts over all texts give the rarity order: frequency class of the most frequent word in the word's bucket (one
   of 2^18), then word hash. The classes are a constant of a fixed size in one job only.
2. A table of the distinct lines, one row each: first place, size, parity signature, and the rare end of the ordered words,
   which is all that the join needs. Texts are split into words twice in all, here and for the counts.
3. Lines that agree on the least and greatest hash of their prefix words, under one of a few hash functions, first meet the
   earliest of them, then what is left the few just before it. What that proves gone has its earlier match already, and is only looked
   at as a possible match from then on. So a group of near copies is not paired out.
4. Prefix filter: similar sets meet in their ``m - ceil(t m) + 1`` rarest words, and in two of the next-longer prefix. So
   rare words of the prefix are keys by themselves, frequent ones only in pairs (unless one common word can do), and a
   tile of a rare word is no larger than the frequency limit. The length filter, the positional filter (a pair counts at
   its first common word, so the words from there on must suffice) and the parity signature (differing bits never exceed
   differing words; longer lines have longer ones) are part of the join's condition.
5. What passes is verified on the full sets, which are built for those lines alone.

Defined cases: null texts have no lines to lose and stay null; rows with equal key and text are one document and get the
same result; null keys sort first; a line of any length is compared whole; a later line that is equal always goes; empty
tables give no rows; columns besides key and text are kept as they are. Distinct lines are told apart by 128 bits of hash.
"""

from __future__ import annotations

import math
import uuid
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from phraseloom.llm.common import bit_set, drop_finished_shuffles, durable, ensure_checkpoint_dir, is_lit, let

BUCKET_BITS = 18
FREQUENT = 511
CLASS_STEP = 4
LEAST = -(1 << 63)
LOW = (1 << 56) - 1
#: Least number of words -> longs in the longer signature (each twice the one before; sizes that pass the length filter are neighbours).
WIDE = {101: 4, 241: 8, 481: 16}
OTHER_SPACE = "\t\x0b\x0c\r"
NAME = ["h1", "h2"]
ENTRY = ["key", "id", "doc", "shape", "sig", "wide"]
SHAPE = ["id", "m", "sig", "wide"]
#: Bands of a line, earlier lines of a band that what is left by then is compared with, and lines in a part of a band.
BANDS = 4
BEFORE = 4
PART = 16384


def _saved(df: DataFrame) -> tuple[DataFrame, str]:
    """``df`` as a written table in the shared folder, and its path."""
    spark = df.sparkSession
    ensure_checkpoint_dir(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/lines-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def _drop(spark: SparkSession, path: str) -> None:
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def _words(text: Column) -> Column:
    """Lower-case runs between white space, which a search for one character is enough to find."""
    blank = reduce(lambda c, x: F.replace(c, F.lit(x), F.lit(" ")), OTHER_SPACE, F.lower(text))
    return F.array_remove(F.split(blank, " "), "")


def _bucket(name: Column) -> Column:
    return name.bitwiseAND(F.lit((1 << BUCKET_BITS) - 1))


def _class_of(hits: float) -> int:
    return min(127, 1 + math.floor(math.log2(hits + 1) * CLASS_STEP))


def _frequency_classes(docs: DataFrame) -> Column:
    """A constant array of bytes: the frequency class (0 to 127) of each bucket of words."""
    words = docs.select(F.explode(_words(F.replace("_text", F.lit("\n"), F.lit(" ")))).alias("w"))
    counts = words.groupBy(F.xxhash64("w").alias("w")).agg(F.count(F.lit(1)).alias("hits"))
    none = docs.sparkSession.range(1 << BUCKET_BITS).select("id", F.lit(0).cast("long").alias("hits"))
    most = counts.select(_bucket(F.col("w")).alias("id"), "hits").unionByName(none).groupBy("id").agg(F.max("hits").alias("hits"))
    every = most.select("id", F.when(F.col("hits") > 0, F.least(F.lit(127), 1 + F.floor(F.log2(F.col("hits") + 1) * CLASS_STEP))).otherwise(F.lit(0)).alias("c"))
    joined = every.agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("id", "c"))), lambda e: e["c"].cast("string")), ",").alias("classes"))
    return F.split(F.lit(joined.first()[0]), ",").cast("array<tinyint>")


def _value(classes: Column):
    """A word as a long: the order of values is the order of rarity."""
    return lambda w: F.shiftleft(F.get(classes, _bucket(F.xxhash64(w)).cast("int")).cast("long"), 56).bitwiseOR(F.xxhash64(w).bitwiseAND(F.lit(LOW)))


def _parity(words: Column) -> Column:
    """Parities of the words' slots as bits of a long."""
    return F.aggregate(words, F.lit(0).cast("long"), lambda acc, w: acc.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), w.bitwiseAND(63).cast("int"))))


def _wide(words: Column, m: Column) -> Column:
    """The same words' parities dealt to several longs; their XOR is ``_parity``, and halves fold into the next-shorter form."""
    longs = reduce(lambda c, least: c.when(m >= least, F.lit(WIDE[least])), sorted(WIDE, reverse=True)[1:], F.when(m >= max(WIDE), F.lit(WIDE[max(WIDE)])))
    lane = lambda w: F.shiftright(w, 6).cast("long").bitwiseAND((longs - 1).cast("long"))
    return F.when(m >= min(WIDE), F.transform(F.sequence(F.lit(0), longs - 1), lambda k: _parity(F.filter(words, lambda w: lane(w) == k))))


def _prefix(percent: int) -> Column:
    m = F.col("m")
    return m - F.floor((F.lit(percent) * m + 99) / 100).cast("int") + 1


def _lines(docs: DataFrame) -> DataFrame:
    line = docs.select("doc", "th", F.posexplode(F.split("_text", "\n")).alias("pos", "line")).where(F.col("line").rlike(r"[^\x20\x09-\x0D]"))
    return line.select("doc", "th", "pos", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(1), "line").alias("h2"), "line")


def _distinct_lines(docs: DataFrame, classes: Column, percent: int) -> tuple[DataFrame, str]:
    """One row for each distinct line with a word: ``id``, name, first place, copies, and what the join needs."""
    sets = _lines(docs).select("doc", "th", "pos", *NAME, F.array_distinct(F.transform(_words(F.col("line")), _value(classes))).alias("words"))
    sets = sets.select("doc", "th", "pos", *NAME, F.sort_array("words").alias("words"), F.size("words").alias("m"))
    shaped = sets.select(
        *NAME, F.struct("doc", "th", "pos").alias("first"), "m", _parity(F.col("words")).alias("sig"), _wide(F.col("words"), F.col("m")).alias("wide"),
        F.slice("words", 1, _prefix(percent) + 1).alias("prefix"),
    )
    one = shaped.groupBy(*NAME).agg(F.min("first").alias("first"), F.count(F.lit(1)).alias("copies"), *[F.first(c).alias(c) for c in ("m", "sig", "wide", "prefix")])
    return _saved(one.select(F.monotonically_increasing_id().alias("id"), *NAME, "first.*", "copies", "m", "sig", "wide", "prefix"))


def _enough(common: Column, m: Column, n: Column, percent: int) -> Column:
    """Can sets of ``m`` and ``n`` words with at most ``common`` in both be similar? In whole numbers."""
    return percent * (m + n) <= (100 + percent) * common


def _size(side: str) -> Column:
    return F.col(f"m{side}")


def _sizes_fit(a: str, b: str, percent: int, size=_size) -> Column:
    return 100 * F.least(size(a), size(b)) >= percent * F.greatest(size(a), size(b))


def _alike(a: str, b: str, percent: int, size=_size) -> Column:
    """Signature filter for columns whose names end in ``a`` and ``b``."""
    m, n, x, y = size(a), size(b), F.col(f"wide{a}"), F.col(f"wide{b}")
    room = lambda apart: _enough(F.shiftright(m + n - apart, 1), m, n, percent)
    longs = F.least(F.size(x), F.size(y))
    fold = lambda v, k: F.get(v, k).bitwiseXOR(F.when(F.size(v) > longs, F.get(v, k + longs)).otherwise(F.lit(0).cast("long")))
    apart = F.aggregate(F.sequence(F.lit(0), longs - 1), F.lit(0), lambda acc, k: acc + F.bit_count(fold(x, k).bitwiseXOR(fold(y, k))))
    comparable = x.isNotNull() & y.isNotNull() & (F.greatest(F.size(x), F.size(y)) <= 2 * longs)
    return room(F.bit_count(F.col(f"sig{a}").bitwiseXOR(F.col(f"sig{b}")))) & F.when(comparable, room(apart)).otherwise(F.lit(True))


def _recurring(nodes: DataFrame) -> DataFrame:
    """``nodes`` by ``band``, for bands that recur: hashes of the least and greatest hash of the prefix words."""
    band = lambda k: let(F.transform("prefix", lambda w: F.xxhash64(w, F.lit(k))), lambda hashes: F.xxhash64(F.lit(k), F.array_min(hashes), F.array_max(hashes)))
    bands = F.explode(F.array(*[band(k) for k in range(BANDS)])).alias("band")
    shared = durable(nodes.select(bands).groupBy("band").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("band"))
    return nodes.select(*[c for c in nodes.columns if c != "prefix"], bands).where(is_lit(bit_set(shared), F.col("band")))


def _fitting(met: DataFrame, percent: int) -> DataFrame:
    return met.where(_sizes_fit("1", "2", percent) & (F.col("id1") != F.col("id2")) & _alike("1", "2", percent)).select("id1", "id2")


def _led(met: DataFrame, percent: int) -> DataFrame:
    """Each line with the earliest one of each of its bands, as pairs of ids."""
    lead = met.groupBy("band").agg(F.min(F.struct("doc", "th", "pos", *SHAPE)).alias("l"), F.count(F.lit(1)).alias("n")).where("n > 1")
    lead = lead.select("band", *[F.col(f"l.{c}").alias(f"{c}2") for c in SHAPE])
    return _fitting(met.select("band", *[F.col(c).alias(f"{c}1") for c in SHAPE]).join(lead, "band"), percent)


def _followed(met: DataFrame, percent: int) -> DataFrame:
    """Each line that is not gone with the few before it in its bands; a large band is cut into parts."""
    parts = met.groupBy("band").agg((1 + F.floor(F.count(F.lit(1)) / PART)).alias("parts"))
    dealt = met.join(parts, "band").withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")))
    order = Window.partitionBy("band", "part").orderBy("doc", "th", "pos")
    before = [F.lag(F.struct(*SHAPE), k).over(order) for k in range(1, BEFORE + 1)]
    met = dealt.select("gone", *[F.col(c).alias(f"{c}2") for c in SHAPE], F.array(*before).alias("before")).where("not gone")
    met = met.select("*", F.explode(F.filter("before", lambda e: e.isNotNull())).alias("e")).select(*[F.col(f"e.{c}").alias(f"{c}1") for c in SHAPE], *[f"{c}2" for c in SHAPE])
    return _fitting(met, percent)


def _entries(nodes: DataFrame, percent: int) -> DataFrame:
    """``ENTRY`` rows: the rare words of each prefix, and the pairs of frequent ones. ``shape`` holds size, place, and ``gone``.

    At its first common word a pair has at most the words from there on in common; at its first two, one and those from
    the second on, as if it had met just before the second.
    """
    limit = _class_of(FREQUENT) << 56
    m, prefix = F.col("m"), _prefix(percent)
    entry = lambda key, at: F.struct(key.alias("key"), at.alias("at"))
    rare = F.size(F.filter(F.slice("prefix", 1, prefix), lambda w: w < limit))
    words = F.transform(F.slice("prefix", 1, F.when(F.lit(percent) * m <= 100, prefix).otherwise(rare)), entry)
    often = F.filter(F.transform("prefix", lambda w, i: F.struct(w.alias("w"), i.alias("at"))), lambda e: e["w"] >= limit)
    pairs = let(often, lambda fs: F.flatten(F.transform(fs, lambda x, i: F.transform(F.slice(fs, i + 2, F.size(fs)), lambda y: entry(F.xxhash64(x["w"], y["w"]), y["at"] - 1)))))
    some = (F.size("prefix") > 1) & (F.get("prefix", F.size("prefix") - 2) >= limit)
    each = nodes.select("id", "doc", "m", "sig", "wide", "gone", F.explode(F.when(some, F.concat(words, pairs)).otherwise(words)).alias("e"))
    shape = F.shiftleft(F.col("m").cast("long"), 32).bitwiseOR(2 * F.col("e.at").cast("long") + F.col("gone").cast("long"))
    return each.select("e.key", "id", "doc", shape.alias("shape"), "sig", "wide")


def _joined(nodes: DataFrame, percent: int) -> DataFrame:
    """Pairs of ids that meet in a key and pass all filters, the later one not known to be gone."""
    entries = _entries(nodes, percent)
    # Both sides are renamed alike, so that their plans are equal and one exchange serves both.
    a, b = (entries.select("key", *[F.col(c).alias(f"{c}{k}") for c in ENTRY[1:]]) for k in "12")
    size = lambda k: F.shiftright(F.col(f"shape{k}"), 32).cast("int")
    rest = lambda k: size(k) - F.shiftright(F.col(f"shape{k}").bitwiseAND(F.lit((1 << 32) - 1)), 1).cast("int")
    reach = _enough(F.least(rest("1"), rest("2")), size("1"), size("2"), percent)
    gone = lambda shape: shape.bitwiseAND(F.lit(1)) == 1
    later = (F.col("doc1") < F.col("doc2")) & ~gone(F.col("shape2"))
    beside = (F.col("doc1") == F.col("doc2")) & (F.col("id1") < F.col("id2")) & ~gone(F.col("shape1").bitwiseAND(F.col("shape2")))  # either may be the later one
    fits = _sizes_fit("1", "2", percent, size) & (later | beside) & reach & _alike("1", "2", percent, size)
    return a.join(b, "key").where(fits).select("id1", "id2")


def _marked(nodes: DataFrame, gone: DataFrame) -> DataFrame:
    """``nodes`` with a column that says whether the id is in ``gone``; only rows that may be are joined."""
    maybe = is_lit(bit_set(gone), F.col("id"))
    found = nodes.where(maybe).join(gone.withColumn("gone", F.lit(True)), "id", "left").withColumn("gone", F.coalesce("gone", F.lit(False)))
    return found.unionByName(nodes.where(~maybe).withColumn("gone", F.lit(False)))


def _wanted(rows: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows whose ``id`` is listed."""
    return rows.where(is_lit(bit_set(ids), F.col("id"))).join(ids, "id", "left_semi")


def _place(doc: str, th: str, pos: str) -> Column:
    return F.xxhash64(doc, th, pos).alias("place")


def _verified(docs: DataFrame, pairs: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """Ids of lines that an earlier line matches, among candidate pairs ``(id1, id2)``."""
    pairs = durable(pairs.distinct())
    names = durable(_wanted(nodes.select("id", *NAME, F.struct("doc", "th", "pos").alias("first")), pairs.select(F.col("id1").alias("id")).unionByName(pairs.select(F.col("id2").alias("id"))).distinct()))
    # Each line is built where it is first; only rows of equal key and text can bring one twice.
    lines = _lines(docs).where(is_lit(bit_set(names.select(_place("first.doc", "first.th", "first.pos"))), _place("doc", "th", "pos")))
    words = lines.select(*NAME, F.array_distinct(F.transform(_words(F.col("line")), lambda w: F.xxhash64(w))).alias("words"))
    sets = durable(words.join(names, NAME).dropDuplicates(NAME).select("id", "first", "words"))
    one, two = (sets.select(*[F.col(c).alias(f"{c}{k}") for c in ("id", "first", "words")]) for k in "12")
    common = F.size(F.array_intersect("words1", "words2"))
    close = pairs.join(one, "id1").join(two, "id2").where(100 * common >= percent * (F.size("words1") + F.size("words2") - common))
    return durable(close.select(F.when(F.col("first1") < F.col("first2"), F.col("id2")).otherwise(F.col("id1")).alias("id")).distinct())


def removed_lines(docs: DataFrame, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc, th, pos)`` of every line that goes; ``th`` is the hash of its document's text."""
    spark = docs.sparkSession
    docs = docs.where(F.col(text).isNotNull()).select(F.coalesce(F.col(key).cast("long"), F.lit(LEAST)).alias("doc"), F.xxhash64(text).alias("th"), F.col(text).alias("_text"))
    nodes, path = _distinct_lines(docs, _frequency_classes(docs), percent)
    drop_finished_shuffles(spark)
    banded, banded_path = _saved(_recurring(nodes).select("band", "doc", "th", "pos", *SHAPE))
    gone = _verified(docs, _led(banded, percent), nodes, percent)
    drop_finished_shuffles(spark)
    gone = durable(gone.unionByName(_verified(docs, _followed(_marked(banded, gone), percent), nodes, percent)).distinct())
    _drop(spark, banded_path)
    drop_finished_shuffles(spark)
    gone = durable(gone.unionByName(_verified(docs, _joined(_marked(nodes, gone), percent), nodes, percent)).distinct())
    drop_finished_shuffles(spark)

    # Only lines with copies and lines that are gone have anything to lose.
    losing = durable(_marked(nodes.select("id", *NAME, F.struct("doc", "th", "pos").alias("first"), "copies"), gone).where("gone or copies > 1").drop("id", "copies"))
    places = _lines(docs).where(is_lit(bit_set(losing.select("h1")), F.col("h1"))).select("doc", "th", "pos", *NAME)
    lost = durable(places.join(losing, NAME).where(F.col("gone") | (F.struct("doc", "th", "pos") != F.col("first"))).select("doc", "th", "pos").distinct())
    _drop(spark, path)
    return lost


def _per_document(removed: DataFrame) -> DataFrame:
    return removed.groupBy("doc", "th").agg(F.sort_array(F.collect_list("pos")).alias("_gone"))


def _identity(key: str, text: str) -> dict[str, Column]:
    return {"_doc": F.coalesce(F.col(key).cast("long"), F.lit(LEAST)), "_th": F.xxhash64(text)}


def line_report(docs: DataFrame, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, n_lines, n_removed, removed_lines)`` per row; line numbers start at 0."""
    gone = _per_document(removed_lines(docs, percent, key, text)).select(F.col("doc").alias("_doc"), F.col("th").alias("_th"), "_gone")
    lines = F.coalesce(F.size(F.split(text, "\n")), F.lit(0))
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), lines.cast("long").alias("n_lines"), *[c.alias(n) for n, c in _identity(key, text).items()])
    none = F.array().cast("array<int>")
    return rows.join(gone, ["_doc", "_th"], "left").select("doc_id", "n_lines", F.size(F.coalesce("_gone", none)).cast("long").alias("n_removed"), F.coalesce("_gone", none).alias("removed_lines"))


def deduplicate_lines(docs: DataFrame, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns kept, with the text's removed lines taken out. Untouched rows are not shuffled."""
    gone = durable(_per_document(removed_lines(docs, percent, key, text)).select(F.col("doc").alias("_doc"), F.col("th").alias("_th"), "_gone"))
    marked = docs.withColumns(_identity(key, text))
    touched = is_lit(bit_set(gone.select("_th")), F.col("_th"))
    numbers = lambda lines: F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("_gone"))
    stays = let(F.split(text, "\n"), lambda lines: F.array_join(F.transform(numbers(lines), lambda i: F.get(lines, i)), "\n"))
    kept = F.when(F.col("_gone").isNull(), F.col(text)).otherwise(stays)
    changed = marked.where(touched).join(gone, ["_doc", "_th"], "left").withColumn(text, kept).select(*docs.columns)
    return marked.where(~touched | F.col("_th").isNull()).select(*docs.columns).unionByName(changed)
