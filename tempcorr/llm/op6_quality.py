"""Line-first cleaning, by SQL expressions alone.

Lines are judged one by one, by rules of punctuation, navigation and boilerplate: a line goes when it has neither closing
punctuation nor five words, when it is navigation (words between separators, or separators alone, in any language), or a
short line with one of a list of English phrases of legal and cookie notices. Then the document is judged: it goes when too
small a part of its words is left. All of it is done inside a row, by higher-order functions, so that nothing is shuffled.

Defined results: null or empty text has no words and fails the base rules; repeated rows are judged each; an empty table
gives no rows; other columns are ignored, whatever their names. A very long text is an array of its words inside its row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tempcorr.llm.common import WORD

WINDOW = 8
LEAST_WORDS = 20
MOST_REPEATED = 30
#: Percent of a document's words that its kept lines must have.
LEAST_KEPT = 50
#: Words of a line of boilerplate at most: a phrase inside a longer line, or a text of one line, is prose.
NOTICE = 20
BOILERPLATE = r"(?i)(^|[^A-Za-z0-9])(all rights reserved|terms of (use|service)|privacy policy|cookie policy|we use cookies|accept (all )?cookies|powered by|sign (in|up)|log ?in|subscribe (now|to)|click here|read more|share (this|on)|skip to (main )?content|javascript is (disabled|required))([^A-Za-z0-9]|$)"
NAVIGATION = r"^\s*(([^\s|>»·•]+\s*[|>»·•]\s*){3,}|[-*#=_~.|>»·•\s]+$)"
CLOSED = r"[.!?…:;\"')\]”’»。！？]\s*$"


def words_of(text: Column) -> Column:
    return F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != "")


def repeated_words(words: Column) -> Column:
    """Words inside windows of eight that the text has twice or more.

    The hashes of all windows are compared first; only where two agree are they sorted with their places, the places of
    those that agree with a neighbour put in order, and the words counted that their windows cover.
    """
    n = F.size(words)
    hashes = F.when(n >= WINDOW, F.transform(F.sequence(F.lit(1), n - (WINDOW - 1)), lambda i: F.xxhash64(F.slice(words, i, WINDOW)))).otherwise(F.array().cast("array<bigint>"))
    return hashes


def _sorted(hashes: Column) -> Column:
    return F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))


def _again(pairs: Column) -> Column:
    """pairs must be a column of its own: an expression would be evaluated anew for every element."""
    size = F.size(pairs)
    again = F.filter(
        F.transform(pairs, lambda p, j: F.when(((j > 0) & (F.get(pairs, j - 1)["h"] == p["h"])) | ((j < size - 1) & (F.get(pairs, j + 1)["h"] == p["h"])), p["i"])),
        lambda i: i.isNotNull(),
    )
    return F.sort_array(again)


def _length(places: Column) -> Column:
    return F.aggregate(
        places,
        F.struct(F.lit(0).cast("long").alias("n"), F.lit(-WINDOW).alias("last")),
        lambda a, i: F.struct((a["n"] + F.least(F.lit(WINDOW), i - a["last"])).cast("long").alias("n"), i.alias("last")),
        lambda a: a["n"],
    )


def measured(docs: DataFrame) -> DataFrame:
    """The base measures of every document, and its lines."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    out = out.withColumn("words", words_of(F.col("text")))
    out = out.withColumn("lines", F.filter(F.split("text", "\n"), lambda x: x.rlike(WORD)))
    out = out.withColumn("hashes", repeated_words(F.col("words")))
    out = out.withColumn("pairs", F.when(F.size(F.array_distinct("hashes")) < F.size("hashes"), _sorted(F.col("hashes"))))
    out = out.withColumn("places", _again(F.col("pairs")))
    return out.select(
        "doc_id",
        "lines",
        F.size("words").cast("long").alias("n_words"),
        F.char_length(F.regexp_replace("text", r"[\x20\x09-\x0D]+", "")).cast("long").alias("word_chars"),
        F.char_length(F.regexp_replace("text", r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.coalesce(_length(F.col("places")), F.lit(0)).cast("long").alias("n_repeat_words"),
    )


def line_kept(line: Column) -> Column:
    """Does a line stay: no short notice, no navigation, and closed by punctuation or of five words or more."""
    n = F.size(words_of(line))
    return ((n > NOTICE) | ~line.rlike(BOILERPLATE)) & ~line.rlike(NAVIGATION) & (line.rlike(CLOSED) | (n >= 5))


def clean(docs: DataFrame) -> DataFrame:
    """Measures and verdict of every document, and the text of its kept lines."""
    out = measured(docs)
    out = out.withColumn("kept_lines", F.filter("lines", line_kept))
    out = out.withColumn("kept_words", F.aggregate("kept_lines", F.lit(0), lambda a, x: a + F.size(words_of(x))))
    n = F.col("n_words")
    base = (n < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED * n)
    symbols = 10 * F.col("n_symbols") > n  # prose has few of them
    short = (F.col("word_chars") < 2 * n) | (F.col("word_chars") > 15 * n)
    out = out.withColumn("base_failed", base)
    return out.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed",
        (~base & ~symbols & ~short & (100 * F.col("kept_words") >= LEAST_KEPT * n)).alias("kept"),
        F.concat_ws("\n", "kept_lines").alias("kept_text"),
    )
