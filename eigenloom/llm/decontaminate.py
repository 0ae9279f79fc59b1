"""Benchmark decontamination by a positional inverted index, in DataFrame functions only.

`build_index` stores the postings (row, pos, term) of all words of whole texts, and beside them each row's words; both tables are bucketed by row, so postings of one
row meet without an exchange. Each query window takes its rarest terms by collection frequency. Their postings are intersected in stretches of positions: shifted by
the terms' offsets they give candidate starts, which are compared with the row's words (`phrase_hits`, exact matches); unshifted they give the rows that hold
all rarest terms within a distance (`proximity_hits`). Words of a window that occur nowhere rule out an exact match only.

Words are runs of ASCII digits, ASCII letters (lower-cased) and non-ASCII characters. Null or empty texts have no words and no hits; texts of any length are indexed whole. Repeated rows are
told apart by an internal row number; items with a null id hit words but are never named; items without words are ignored; repeated items count once; terms of one frequency
are ordered by their text; an empty table gives an empty result, an empty benchmark no hits; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

from functools import reduce
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common
from .common import ascii_lower, bucketed, stored

WORD_GAP = "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"
WIDTH, RAREST, DISTANCE = 10, 3, 20
#: Bytes of text in a bucket of the index, and parts into which the postings of a term are dealt where the query terms are too many to broadcast.
BUCKET_BYTES, SALTS = 6 << 20, 64


class Index(NamedTuple):
    """postings (row, pos, term) and texts (row, doc_id, n_words, words), both bucketed by row."""

    postings: DataFrame
    texts: DataFrame
    buckets: int


def words_of(text: Column) -> Column:
    return F.filter(F.split(ascii_lower(F.coalesce(text, F.lit(""))), WORD_GAP), lambda w: w != "")


def _small(rows: DataFrame) -> bool:
    return rows.count() <= common.BROADCAST_ROWS


def query_windows(items: DataFrame, width: int = WIDTH, id_col: str = "item_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """(window, words) of all distinct windows, and (window, item_id); a window of an item without an id has no owner."""
    words = items.select(F.col(id_col).alias("item_id"), words_of(F.col(text_col)).alias("words")).filter(F.size("words") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("words") - width + 1))
    owned = stored(words.select("item_id", F.explode(F.transform(starts, lambda i: F.slice("words", i, width))).alias("words")).distinct(), "owned-windows")
    windows = stored(owned.select("words").distinct().withColumn("window", F.monotonically_increasing_id()), "windows").select("window", "words")
    return windows, stored(owned.filter("item_id is not null").join(windows, "words").select("window", "item_id"), "owners")


def build_index(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Index:
    """The stored index of all words of all rows. One exchange of the texts; what follows on rows needs none."""
    text = F.col(text_col)
    buckets = common.bucket_count(docs, docs.agg(F.sum(F.octet_length(text))).first()[0] or 0, BUCKET_BYTES)
    rows = docs.select(F.col(id_col).alias("doc_id"), text.alias("text"), F.monotonically_increasing_id().alias("row")).repartition(buckets, "row")
    texts = bucketed(rows.select("row", "doc_id", words_of(F.col("text")).alias("words")).withColumn("n_words", F.size("words")), "texts", "row", buckets)
    return Index(bucketed(texts.select("row", F.posexplode("words").alias("pos", "term")), "postings", "row", buckets), texts, buckets)


def probes_of(index: Index, windows: DataFrame, rarest: int = RAREST) -> DataFrame:
    """(window, need, whole, terms array of (frequency, term, offset)): of each window the rarest of its different terms that occur, with their first offsets; whole: all its terms occur.

    need is `rarest`, or the number of different terms of a window that has fewer; a window of which fewer than `need` terms occur is left out.
    """
    terms = windows.select("window", "words", F.explode(F.array_distinct("words")).alias("term"))
    vocabulary = stored(terms.select("term").distinct(), "vocabulary")
    held = index.postings.join(F.broadcast(vocabulary) if _small(vocabulary) else vocabulary, "term", "left_semi")
    frequency = stored(held.groupBy("term").agg(F.count(F.lit(1)).alias("frequency")), "frequency")
    found = terms.join(F.broadcast(frequency) if _small(frequency) else frequency, "term").withColumn("offset", F.array_position("words", F.col("term")).cast("int") - 1)
    lists = found.groupBy("window", "words").agg(F.sort_array(F.collect_list(F.struct("frequency", "term", "offset"))).alias("terms"))
    distinct, need = F.size(F.array_distinct("words")), F.least(F.lit(rarest), F.size(F.array_distinct("words")))
    return lists.filter(F.size("terms") >= need).select("window", need.alias("need"), (F.size("terms") == distinct).alias("whole"), F.slice("terms", F.lit(1), need).alias("terms"))


def _met(index: Index, probes: DataFrame, distance: int) -> DataFrame:
    """(row, window, stretch, m0, m1, ...): where all probes of a window occur in two stretches of `distance` words, as bits of their places from the first one's begin."""
    probe_rows = stored(probes.select("window", F.posexplode("terms").alias("rank", "one")).select("window", "rank", F.col("one.term").alias("term")), "probe-terms")
    rarest = (probe_rows.agg(F.max("rank")).first()[0] or 0) + 1
    if _small(probe_rows):
        shared = index.postings.join(F.broadcast(probe_rows), "term")
    else:  # a common term is dealt to SALTS tasks, whichever row holds it
        salts = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))
        shared = index.postings.withColumn("salt", F.pmod("row", F.lit(SALTS)).cast("int")).join(probe_rows.withColumn("salt", salts), ["term", "salt"])
    at = F.floor(F.col("pos") / distance).cast("int")
    placed = shared.select("row", "window", "rank", "pos", F.explode(F.array(at, at - 1)).alias("stretch")).filter("stretch >= 0")
    bit = F.expr(f"shiftleft(1L, pos - stretch * {distance})")
    masks = [F.bit_or(F.when(F.col("rank") == r, bit).otherwise(F.lit(0).cast("long"))).alias(f"m{r}") for r in range(rarest)]
    need = F.broadcast(probes.select("window", "need")) if _small(probes) else probes.select("window", "need")
    held = placed.groupBy("row", "window", "stretch").agg(*masks)
    some = held.filter(reduce(Column.__or__, [F.col(f"m{r}") != 0 for r in range(rarest)]) & (F.col("m0") != 0))
    return some.join(need, "window").filter(reduce(Column.__and__, [(F.col("m%d" % r) != 0) | (F.col("need") <= r) for r in range(rarest)])).drop("need")


def _masks(met: DataFrame) -> list[str]:
    return [c for c in met.columns if c[0] == "m" and c[1:].isdigit()]


def meetings(index: Index, windows: DataFrame, distance: int = DISTANCE, rarest: int = RAREST) -> tuple[DataFrame, DataFrame]:
    """(probes, stretches where all probes of a window meet): what exact and proximity matches are both read off."""
    if not 1 <= distance <= 31:
        raise ValueError("the distance is 1 to 31 words")
    probes = stored(probes_of(index, windows, rarest), "probes")
    return probes, bucketed(_met(index, probes, distance), "meetings", "row", index.buckets)


def phrase_hits(index: Index, windows: DataFrame, met: tuple[DataFrame, DataFrame] | None = None, distance: int = DISTANCE, rarest: int = RAREST) -> DataFrame:
    """(row, doc_id, hits array of (start, window, n_terms)): for every row that has one, every occurrence of every window of at most distance + 1 words."""
    probes, stretches = met or meetings(index, windows, distance, rarest)
    asked = probes.filter("whole").join(windows, "window").select("window", "need", "words", F.transform("terms", lambda t: t["offset"]).alias("offsets"))
    both = stretches.join(F.broadcast(asked) if _small(asked) else asked, "window")
    shifted = [F.expr(f"case when need > {r} then shiftrightunsigned({m}, offsets[{r}]) else -1L end") for r, m in enumerate(_masks(stretches))]
    both = both.withColumn("begins", reduce(Column.bitwiseAND, shifted)).filter(F.col("begins").bitwiseAND(F.lit((1 << distance) - 1)) != 0)
    starts = F.expr(f"transform(filter(sequence(0, {distance - 1}), o -> (shiftrightunsigned(begins, o) & 1L) = 1L), o -> stretch * {distance} + o)")
    candidates = both.select("row", "window", "words", F.explode(starts).alias("start")).groupBy("row").agg(F.collect_list(F.struct("start", "window", "words")).alias("candidates"))
    joined = index.texts.join(candidates.hint("shuffle_hash"), "row").select("row", "doc_id", F.col("words").alias("held"), "candidates")
    true = F.expr("filter(candidates, c -> slice(held, c.start + 1, size(c.words)) = c.words)")
    return joined.select("row", "doc_id", F.transform(true, lambda c: F.struct(c["start"].alias("start"), c["window"].alias("window"), F.size(c["words"]).alias("n_terms"))).alias("hits")).filter(F.size("hits") > 0)


def proximity_hits(index: Index, windows: DataFrame, distance: int = DISTANCE, rarest: int = RAREST, met: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """(row, window): rows where all rarest terms of a window, among those that occur, lie within `distance` words, in any order."""
    probes, stretches = met or meetings(index, windows, distance, rarest)
    need = probes.select("window", "need")
    both = stretches.join(F.broadcast(need) if _small(need) else need, "window")
    span = (1 << (distance + 1)) - 1
    inside = lambda o: reduce(Column.__and__, [(F.col("need") <= r) | (F.shiftrightunsigned(m, o).bitwiseAND(F.lit(span)) != 0) for r, m in enumerate(_masks(stretches))])
    return both.filter(reduce(Column.__or__, [inside(o) for o in range(distance)])).select("row", "window").distinct()


def _named(hits: DataFrame, owners: DataFrame) -> DataFrame:
    """(row, items) of (row, window): the ids of the windows' items as sorted strings."""
    named = hits.join(F.broadcast(owners) if _small(owners) else owners, "window").select("row", F.col("item_id").cast("string").alias("item"))
    return named.groupBy("row").agg(F.sort_array(F.collect_set("item")).alias("items"))


def contamination(docs: DataFrame, items: DataFrame, width: int = WIDTH, id_col: str = "doc_id", text_col: str = "text", distance: int = DISTANCE, rarest: int = RAREST) -> DataFrame:
    """One row per row of docs: doc_id, row, n_words, n_hit, n_items, items (sorted strings) of exact matches, and n_near (windows), n_near_items, near_items of proximity matches."""
    windows, owners = query_windows(items, width)
    index = build_index(docs, id_col, text_col)
    met = meetings(index, windows, distance, rarest)
    hits = bucketed(phrase_hits(index, windows, met, distance, rarest).select("row", "hits"), "hits", "row", index.buckets)
    covered = F.size(F.array_distinct(F.flatten(F.transform("hits", lambda h: F.sequence(h["start"], h["start"] + h["n_terms"] - 1)))))
    named = _named(hits.select("row", F.explode(F.array_distinct(F.transform("hits", lambda h: h["window"]))).alias("window")), owners)
    near = proximity_hits(index, windows, distance, rarest, met)
    near = bucketed(near.join(_named(near, owners), "row", "left").groupBy("row").agg(F.count(F.lit(1)).alias("n_near"), F.first("items").alias("near_items")), "near", "row", index.buckets)
    out = index.texts.select("row", "doc_id", F.col("n_words").cast("long").alias("n_words")).join(hits.select("row", covered.alias("n_hit")), "row", "left").join(named, "row", "left").join(near, "row", "left")
    many = lambda c: F.coalesce(F.size(c), F.lit(0)).cast("long")
    none = F.array().cast("array<string>")
    return out.select(
        "doc_id", "row", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), many("items").alias("n_items"), F.coalesce("items", none).alias("items"),
        F.coalesce("n_near", F.lit(0)).cast("long").alias("n_near"), many("near_items").alias("n_near_items"), F.coalesce("near_items", none).alias("near_items"),
    )
