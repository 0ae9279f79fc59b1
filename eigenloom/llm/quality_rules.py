"""Line-first quality rules, in DataFrame functions only.

Rules on punctuation, navigation and boilerplate judge each line; failing lines go, and a document that loses too much of its text is
rejected. Statistics of whole documents (symbols, repeated lines, words in repeated 5-word windows) stand beside them.

Null texts count as empty and fail as too short; an empty table gives an empty result; repeated rows are judged alike, so there are no ties to settle; every rule reads a
line in linear time, however long it is; `cleaned` passes all columns as they came, `judged` and `measured` replace given columns of their results' names.
A window is compared by the 64-bit hash of its five words.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE

#: Line rules.
SYMBOLS = "#*$%&|<>"
NAVIGATION = r"( \| [^|]* \| )|( > [^>]* > )|( » [^»]* » )"
BOILERPLATE = r"(?i)(cookie policy|privacy policy|terms of (use|service)|all rights reserved|javascript (is|must be)|sign up|log ?in to|click here|subscribe to|share (this|on) )"
MARKED_WORD = r"[\p{L}\d.,]+(###|\$\$\$|%%%|&&&|\*\*\*|!!)( |$)"
SHOUT = r"^[^\p{Ll}]*\p{Lu}{4,}[^\p{Ll}]*!![^\p{Ll}]*$"
WINDOW, LEAST_WORDS, MOST_REPEATED, LEAST_LEFT = 5, 10, 20, 0.5


def _words(text: Column) -> Column:
    trimmed = F.btrim(text, F.lit(SPACE))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, "[\\x20\\x09-\\x0D]+"))


#: The phrases of BOILERPLATE in lower case, and the marks of MARKED_WORD.
PHRASES = ("cookie policy", "privacy policy", "terms of use", "terms of service", "all rights reserved", "javascript is", "javascript must be", "sign up", "log in to", "login to", "click here", "subscribe to", "share this", "share on ")
MARKS = ("###", "$$$", "%%%", "&&&", "***", "!!")


def _any(text: Column, parts) -> Column:
    return reduce(Column.__or__, [text.contains(p) for p in parts])


def _shouts(line: Column) -> Column:
    """SHOUT in linear time: no small letter, and four capitals in a row before the last `!!`."""
    before = F.left(line, F.length(line) - F.length(F.substring_index(line, "!!", -1)) - 2)
    return line.contains("!!") & ~line.rlike(r"\p{Ll}") & before.rlike(r"\p{Lu}{4}")


def _marked(line: Column) -> Column:
    """How often MARKED_WORD occurs: the last character before the mark is enough to find it, so no run of letters is read twice."""
    return F.regexp_count(line, F.lit(r"[\p{L}\d.,](###|\$\$\$|%%%|&&&|\*\*\*|!!)( |\z)"))


def line_passes(line: Column, low: Column | None = None) -> Column:
    """Whether a line holds prose: no navigation bar, no boilerplate phrase, no words marked with symbols, no shouting, few symbols; blank lines pass. low: the line in lower case."""
    symbols = F.length(line) - F.length(F.translate(line, SYMBOLS, ""))
    return ~(line.rlike(NAVIGATION) | _any(F.lower(line) if low is None else low, PHRASES) | _shouts(line) | (_any(line, MARKS) & (_marked(line) >= 3)) | (symbols * 10 > F.length(line)))


def _good_lines(lines: Column) -> Column:
    both = F.transform(lines, lambda x: F.struct(x.alias("line"), F.lower(x).alias("low")))
    return F.transform(F.filter(both, lambda x: line_passes(x["line"], x["low"])), lambda x: x["line"])


MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
VERDICTS = ("n_lines", "n_lines_failed", "share_left", "kept")


def measured(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with the counts of the contract (MEASURES) beside every row; given columns of these names give way."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    lined = docs.drop(*MEASURES).withColumns({"_words": _words(text), "_lines": F.filter(F.split(text, "\n"), lambda x: F.btrim(x, F.lit(SPACE)) != "")})
    counted = lined.withColumns(
        {
            "n_words": F.size("_words").cast("long"),
            "word_chars": F.length(F.translate(text, SPACE, "")).cast("long"),
            "n_symbols": (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long"),
            "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
            "_hashes": F.transform("_words", lambda w: F.xxhash64(w)),
        }
    )
    size = F.size("_hashes")
    at = lambda i, k: F.get("_hashes", i + k)
    windows = F.when(size >= WINDOW, F.transform(F.sequence(F.lit(0), size - WINDOW), lambda i: F.xxhash64(*(at(i, k) for k in range(WINDOW))))).otherwise(F.array().cast("array<bigint>"))
    windowed = counted.withColumn("_windows", windows).withColumn("_some", F.size(F.array_distinct("_windows")) < F.size("_windows"))
    # Only texts with a repeated window are sorted: equal windows become neighbours, and their places say which words they cover.
    ordered = windowed.withColumn("_sorted", F.when(F.col("_some"), F.sort_array(F.transform("_windows", lambda w, i: F.struct(w.alias("w"), i.alias("i"))))))
    same = lambda x, k, i: F.coalesce(F.get("_sorted", i + k).getField("w") == x.getField("w"), F.lit(False))
    marked = ordered.withColumn("_places", F.sort_array(F.transform(F.filter("_sorted", lambda x, i: same(x, -1, i) | same(x, 1, i)), lambda x: x.getField("i"))))
    covered = F.aggregate(F.transform("_places", lambda p, j: F.least(F.lit(WINDOW), F.coalesce(F.get("_places", j + 1) - p, F.lit(WINDOW)))), F.lit(0), lambda a, x: a + x)
    done = marked.withColumn("n_repeat_words", F.when(F.col("_some"), covered).otherwise(0).cast("long"))
    return done.withColumn("base_failed", (F.col("n_words") < LEAST_WORDS) | (F.col("n_repeat_words") * 100 > F.col("n_words") * MOST_REPEATED)).drop("_words", "_hashes", "_windows", "_some", "_sorted", "_places", "_lines")


def judged(docs: DataFrame, text_col: str = "text", least_left: float = LEAST_LEFT) -> DataFrame:
    """`measured` plus VERDICTS: n_lines, n_lines_failed, share_left (of the characters) and kept; given columns of these names give way."""
    return _judged(docs.drop(*VERDICTS), text_col, least_left).drop("_good")


def _judged(docs: DataFrame, text_col: str, least_left: float) -> DataFrame:
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = measured(docs, text_col).withColumns({"_lines": F.split(text, "\n"), "_low": F.lower(text)})
    # Only texts that hold a symbol, phrase or mark that a rule looks for are read line by line.
    suspect = _any(text, (" » ", *MARKS)) | (F.col("n_symbols") > 0) | _any(F.col("_low"), PHRASES)
    rows = rows.withColumn("_suspect", suspect).drop("_low").withColumn("_good", F.when(F.col("_suspect"), _good_lines(F.col("_lines"))).otherwise(F.col("_lines")))
    rows = rows.withColumns({"n_lines": F.size("_lines").cast("long"), "n_lines_failed": (F.size("_lines") - F.size("_good")).cast("long")})
    total = F.length(text) - F.col("n_lines") + 1
    left = F.when(F.col("n_lines_failed") == 0, total).otherwise(F.aggregate("_good", F.lit(0).cast("long"), lambda a, x: a + F.length(x)))
    rows = rows.withColumn("share_left", F.when(total > 0, left / total).otherwise(0.0))
    return rows.withColumn("kept", ~F.col("base_failed") & (F.col("share_left") >= least_left)).drop("_lines", "_suspect")


def cleaned(docs: DataFrame, text_col: str = "text", least_left: float = LEAST_LEFT) -> DataFrame:
    """Kept documents with their failing lines removed; all other columns as they came, whatever their names."""
    held = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_given"), F.col(text_col).alias("text"))
    # A row that is not kept explodes to none: a filter would be pushed below the projections, which spells out their expressions many times over.
    rows = _judged(held, "text", least_left).select("_given", F.explode(F.when(F.col("kept"), F.array("_good"))).alias("_good"))
    return rows.select(*(F.array_join("_good", "\n").alias(c) if c == text_col else F.col(f"_given.`{c}`").alias(c) for c in docs.columns))
