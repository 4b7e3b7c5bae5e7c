"""Quality rules: a threshold table compiled into one projection (no user functions).

Base measures per text: words (maximal runs of non-white-space), code points in words, symbol characters, repeated
lines, words inside repeated eight-word windows. A row fails the base rules when it has too few words or when too
large a share of its words lies in repeated windows; it is kept when it passes those and every row of the table.

Defined cases: a null text counts as an empty one (no words: it fails); ties and repeated rows are judged one by
one; an empty table gives an empty result; further columns of the input are ignored by name, so clashes are harmless.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from phraseloom.llm.common import let, text_or_empty, word_array

WINDOW = 8
MIN_WORDS = 20
MAX_REPEAT_PERCENT = 30
SYMBOLS = "#*$%&|<>"
WHITE = " \t\n\x0b\f\r"

#: Frequent function words of English, French, German and Spanish.
STOP_WORDS = """
a an and are as at be by for from had has have he her his in is it its not of on or she that the their they this to
was we were which will with you
au aux avec ce ces dans de des du elle en est et il je la le les leur mais ne nous ou par pas pour qu que qui sa se
ses son sur un une vous
als am auch auf aus bei das dass dem den der des die durch ein eine einem einen einer er es hat ich ihr im in ist
mit nach nicht noch nur oder sich sie sind so um und von vor war wie wird zu zum zur
al como con de del el ella en entre es esta este fue ha han la las lo los más me no o para pero por que se sin sobre
su sus también un una y ya
""".split()


@dataclass(frozen=True)
class Threshold:
    """Keep a text when ``least`` <= measure <= ``most`` (either bound may be open)."""

    name: str
    measure: str
    least: float | None = None
    most: float | None = None

    def passes(self) -> Column:
        value = F.col(self.measure)
        checks = [value >= self.least] * (self.least is not None) + [value <= self.most] * (self.most is not None)
        out = F.lit(True)
        for check in checks:
            out = out & check
        return out


#: Name, measure, least, most.
DEFAULT_TABLE = (
    Threshold("length", "n_words", MIN_WORDS, 2_000_000),
    Threshold("word length", "mean_word_chars", 2.0, 14.0),
    Threshold("symbols", "symbols_per_word", None, 0.25),
    Threshold("stop words", "stop_word_ratio", 0.01, None),
    Threshold("repeated lines", "dup_line_ratio", None, 0.5),
)


def _repeat_words(words: Column) -> Column:
    """Words covered by eight-word windows that occur at least twice, by sorting window digests next to their places."""

    def covered(places: Column) -> Column:
        gaps = F.transform(places, lambda v, k: F.least(F.lit(WINDOW), F.coalesce(F.get(places, k + 1) - v, F.lit(WINDOW))))
        return F.aggregate(gaps, F.lit(0).cast("long"), lambda acc, g: acc + g)

    def repeated_places(ordered: Column) -> Column:
        same = lambda k, e: (F.get(ordered, k - 1)["h"] == e["h"]) | (F.get(ordered, k + 1)["h"] == e["h"])
        picked = F.transform(ordered, lambda e, k: F.when(F.coalesce(same(k, e), F.coalesce(F.get(ordered, k + 1)["h"] == e["h"], F.lit(False))), e["at"]))
        return F.array_sort(F.filter(picked, lambda v: v.isNotNull()))

    def of_windows(digests: Column) -> Column:
        entries = F.array_sort(F.transform(digests, lambda h, k: F.struct(h.alias("h"), k.alias("at"))))
        slow = let(let(entries, repeated_places), covered)
        return F.when(F.size(F.array_distinct(digests)) == F.size(digests), F.lit(0).cast("long")).otherwise(slow)

    def of_hashes(hashes: Column) -> Column:
        starts = F.sequence(F.lit(1), F.size(hashes) - (WINDOW - 1))
        return let(F.transform(starts, lambda i: F.xxhash64(F.slice(hashes, i, WINDOW))), of_windows)

    hashed = F.transform(words, lambda w: F.xxhash64(w))
    return F.when(F.size(words) <= WINDOW, F.lit(0).cast("long")).otherwise(let(hashed, of_hashes))


def measures(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Key and base measures, one row per input row."""
    stops = sorted({form for w in STOP_WORDS for form in (w, w.capitalize())})
    body = text_or_empty(text)
    lines = F.filter(F.split(body, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    base = docs.select(F.col(key), body.alias("_body"), word_array(body).alias("_words"), lines.alias("_lines"))
    counted = base.select(
        F.col(key),
        F.size("_words").cast("long").alias("n_words"),
        F.char_length(F.translate("_body", WHITE, "")).cast("long").alias("word_chars"),
        F.regexp_count("_body", F.lit("[#*$%&|<>]")).cast("long").alias("n_symbols"),
        F.size("_lines").cast("long").alias("n_lines"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
        F.size(F.filter("_words", lambda w: w.isin(*stops))).cast("long").alias("n_stop_words"),
        _repeat_words(F.col("_words")).alias("n_repeat_words"),
    )
    words, rows = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("n_lines"), F.lit(1))
    return counted.withColumns(
        {
            "mean_word_chars": F.col("word_chars") / words,
            "symbols_per_word": F.col("n_symbols") / words,
            "stop_word_ratio": F.col("n_stop_words") / words,
            "dup_line_ratio": F.col("n_dup_lines") / rows,
        }
    )


def judge(docs: DataFrame, rules: tuple[Threshold, ...] = DEFAULT_TABLE, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Measures plus ``base_failed``, ``failed_rules`` (names, in table order) and ``kept``."""
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    names = F.array_compact(F.array(*[F.when(~r.passes(), F.lit(r.name)) for r in rules])) if rules else F.array().cast("array<string>")
    judged = measures(docs, key, text).withColumns({"base_failed": failed, "failed_rules": names})
    return judged.withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))
