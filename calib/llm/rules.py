"""Quality rules: a table of thresholds, compiled into one projection of built-in functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from calib.llm.shared import BLANKS, words_of

SYMBOLS = "#*$%&|<>"
WINDOW = 8
#: Fixed word list: frequent function words of the four languages of the corpus.
STOP_WORDS = [
    "the", "be", "to", "of", "and", "a", "in", "that", "is", "it", "for", "on", "with", "as", "was",
    "der", "die", "das", "und", "ist", "ein", "eine", "in", "zu", "den", "mit", "von", "auf", "dem", "im",
    "le", "la", "les", "de", "des", "et", "un", "une", "en", "que", "qui", "du", "est", "dans", "pour",
    "el", "los", "las", "y", "una", "por", "con", "no", "su", "al", "lo", "se", "del", "es",
]

#: name, measure, least and most value (null: open). A document is kept if every measure that it has lies within.
THRESHOLDS: list[tuple[str, str, float | None, float | None]] = [
    ("length", "n_words", 20, None),
    ("word_length", "mean_word_length", 2, 14),
    ("symbols", "symbols_per_word", None, 0.2),
    ("upper", "upper_ratio", None, 0.6),
    ("stop_words", "stop_word_ratio", 0.005, None),
    ("repeats", "repeat_word_ratio", None, 0.3),
    ("lines", "dup_line_ratio", None, 0.6),
]


def repeat_words(words: Column, window: int = WINDOW) -> Column:
    """How many words lie in a window of `window` words that occurs twice or more in the array.

    Windows are compared by 64-bit hashes. Only an array in which some hash repeats is sorted; the windows that
    repeat are then put in order of place, and each adds the words up to the next one, `window` at most.
    """
    hashes = F.transform(F.sequence(F.lit(1), F.size(words) - (window - 1)), lambda i: F.xxhash64(F.slice(words, i, window)))

    def covered(h: Column) -> Column:
        ranked = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

        def places(s: Column) -> Column:
            same = lambda x, k: F.get(s, k)["h"].eqNullSafe(x["h"])
            return F.array_sort(F.transform(F.filter(s, lambda x, k: same(x, k - 1) | same(x, k + 1)), lambda x: x["i"]))

        def total(p: Column) -> Column:
            return F.aggregate(F.transform(p, lambda x, k: F.least(F.lit(window), F.coalesce(F.get(p, k + 1) - x, F.lit(window)))), F.lit(0), lambda a, b: a + b)

        return _bound(_bound(ranked, places), total)

    found = _bound(hashes, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(covered(h)))
    return F.when(F.size(words) < window, F.lit(0)).otherwise(found).cast("long")


def _bound(value: Column, use) -> Column:
    """use(value), with the value computed once."""
    return F.transform(F.array(value), use)[0]


def measures(docs: DataFrame) -> DataFrame:
    """docs with the counts and ratios of each whole text; null counts as empty, and a ratio over nothing is null."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.withColumn("_words", words_of(text)).withColumn("_lines", F.filter(F.split(text, "\n"), lambda x: F.length(F.translate(x, BLANKS, "")) > 0))
    letters = F.length(F.regexp_replace(text, r"[^\p{L}]+", ""))
    upper = F.length(F.regexp_replace(text, r"[^\p{Lu}]+", ""))
    rows = rows.select(
        *docs.columns,
        F.size("_words").cast("long").alias("n_words"),
        F.length(F.translate(text, BLANKS, "")).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long").alias("n_symbols"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
        repeat_words(F.col("_words")).alias("n_repeat_words"),
        F.size("_lines").alias("_n_lines"),
        F.size(F.filter("_words", lambda w: F.lower(w).isin(STOP_WORDS))).alias("_n_stop"),
        letters.alias("_letters"),
        upper.alias("_upper"),
    )
    per = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b))
    return rows.withColumns({
        "mean_word_length": per("word_chars", "n_words"), "symbols_per_word": per("n_symbols", "n_words"), "stop_word_ratio": per("_n_stop", "n_words"),
        "repeat_word_ratio": per("n_repeat_words", "n_words"), "dup_line_ratio": per("n_dup_lines", "_n_lines"), "upper_ratio": per("_upper", "_letters"),
    }).drop("_n_lines", "_n_stop", "_letters", "_upper")


def verdict(thresholds=THRESHOLDS) -> Column:
    """The table as one predicate."""
    out = F.lit(True)
    for _, measure, least, most in thresholds:
        if least is not None:
            out &= F.coalesce(F.col(measure) >= least, F.lit(True))
        if most is not None:
            out &= F.coalesce(F.col(measure) <= most, F.lit(True))
    return out


def judge(docs: DataFrame, thresholds=THRESHOLDS) -> DataFrame:
    """doc_id, the counts, base_failed and kept for every row. Null and empty texts have no words and fail the base."""
    base = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    rows = measures(docs.select("doc_id", "text"))
    out = F.struct("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), (~base & verdict(thresholds)).alias("kept"))
    return rows.select(F.explode(F.array(out)).alias("r")).select("r.*")  # a generator, so that filters of the caller are not pushed below the measures


def keep_good(spark, docs: DataFrame, thresholds=THRESHOLDS) -> DataFrame:
    """The rows of docs that pass base and thresholds, with their columns.

    Rows leave by a generator: a filter would be pushed below the measures, and each of its terms would
    compute its measure anew.
    """
    base = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    rows = measures(docs.withColumn("_row", F.struct(*docs.columns)).select("_row", "text"))
    return rows.select(F.explode(F.when(~base & verdict(thresholds), F.array("_row"))).alias("_row")).select("_row.*")
