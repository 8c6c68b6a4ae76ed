"""Benchmark decontamination with a distributed positional inverted index.

Postings (document, position, term) of the training texts are stored for the terms of the test items. A test phrase is
looked up from its rarest terms: their posting lists, moved back by each term's place in the phrase, are intersected on
(document, start); what is left is intersected with the lists of the phrase's other terms. Nothing but the postings of
candidate documents takes part in the second step. With a slop, terms may stray from their places (proximity).

Only DataFrame functions are used. Texts are read where they lie and never shuffled. The index is written in the order
of the scan, so building it shuffles nothing either.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .shared import cut, text_or_empty, unused

#: Words of a window; at most 63.
WINDOW = 10
#: Rarest places of a window whose lists are intersected first.
RAREST = 3
#: A side is broadcast only up to so many rows (tens of megabytes); beyond that it is shuffled.
BROADCAST_ROWS = 500_000

_BREAKS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_KEY = ["did", "th"]


def words(text: Column) -> Column:
    """Words in their order, letter case as in the text."""
    return F.filter(F.split(text, _BREAKS), lambda w: w != "")


def folded(word: Column) -> Column:
    """A-Z in lower case; other letters stay as they are."""
    plain = F.octet_length(word) == F.char_length(word)
    return F.when(plain, F.lower(word)).otherwise(F.translate(word, _UPPER, _LOWER))


def keyed(docs: DataFrame, *more: Column) -> DataFrame:
    """A key for each document that also tells apart rows of one id (or none) with different texts."""
    return docs.select(
        F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63))).alias("did"), F.xxhash64(text_or_empty()).alias("th"), *more
    )


def small(df: DataFrame) -> DataFrame:
    """``df`` with a broadcast hint if its counted rows are few enough. ``df`` must be cheap to count."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


@dataclass(frozen=True)
class PhraseWindows:
    """Distinct windows of the test items.

    terms: term, word. places: win, offset, term, length. items: win, item_id.
    """

    terms: DataFrame
    places: DataFrame
    items: DataFrame


def phrase_windows(benchmark: DataFrame, width: int = WINDOW) -> PhraseWindows:
    """Raises ValueError for a width that is no number from 1 to 63: places in a window are bits of a long."""
    if not 1 <= width <= 63:
        raise ValueError(f"windows are of 1 to 63 words, not {width}")
    items = benchmark.select("item_id", F.transform(words(text_or_empty()), folded).alias("ws")).where(F.size("ws") > 0)
    starts = F.sequence(F.lit(0), F.greatest(F.size("ws") - width, F.lit(0)))
    each = items.select("item_id", F.explode(F.transform(starts, lambda s: F.slice(F.col("ws"), s + 1, width))).alias("ws"))
    each = cut(each.distinct(), "windows")
    # Numbers of distinct windows and terms: within a table of the size of the test set.
    windows = cut(each.select("ws").distinct().withColumn("win", F.monotonically_increasing_id()), "windows-numbered")
    terms = cut(windows.select(F.explode("ws").alias("word")).distinct().withColumn("term", F.monotonically_increasing_id()), "terms")
    places = windows.select("win", F.size("ws").alias("length"), F.posexplode("ws").alias("offset", "word")).join(terms, "word").select("win", "offset", "term", "length")
    return PhraseWindows(terms, cut(places, "places"), cut(each.join(windows, "ws").select("win", "item_id"), "window-items"))


def build_index(docs: DataFrame, terms: DataFrame) -> DataFrame:
    """Stored postings did, th, pos, term of the given terms in all documents."""
    placed = keyed(docs, F.posexplode(words(text_or_empty())).alias("pos", "word"))
    return cut(placed.withColumn("word", folded(F.col("word"))).join(small(terms), "word").select(*_KEY, "pos", "term"), "postings")


def phrase_matches(index: DataFrame, windows: PhraseWindows, slop: int = 0) -> DataFrame:
    """did, th, win, start, length of each place where a window occurs.

    With ``slop`` 0 the window's words stand there exactly. Else ``start`` is where the window would begin going by its
    rarest term, and every other term stands within ``slop`` words of its place.
    """
    rarity = index.groupBy("term").agg(F.count(F.lit(1)).alias("cf"))
    # A window with a term the corpus lacks cannot occur: the left join gives it a null rarity, and it is dropped.
    rated = windows.places.join(rarity, "term", "left")
    by_rarity = W.partitionBy("win").orderBy("cf", "offset")
    ranked = rated.select("*", F.row_number().over(by_rarity).alias("nth"), F.min(F.coalesce("cf", F.lit(0))).over(W.partitionBy("win")).alias("least"))
    first = 1 if slop else RAREST
    ranked = cut(ranked.where("least > 0").select("win", "offset", "term", "length", (F.col("nth") <= first).alias("rare")), "places-rated")
    lists = index.join(small(ranked.where("rare").drop("rare")), "term")
    # A set of places as bits: postings of repeated rows count once.
    places = F.bit_count(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("offset"))))
    met = lists.select(*_KEY, "win", (F.col("pos") - F.col("offset")).alias("start"), "offset", "length").where(F.lit(slop > 0) | (F.col("start") >= 0))
    met = met.groupBy(*_KEY, "win", "start").agg(places.alias("n"), F.first("length").alias("length"))
    candidates = cut(met.where(F.col("n") == F.least(F.col("length"), F.lit(first))).drop("n"), "candidates")
    rest = small(ranked.where(~F.col("rare")).select("win", "offset", "term"))
    wanted = candidates.where(F.col("length") > first).join(rest, "win")
    near = F.explode(F.sequence(F.col("start") + F.col("offset") - slop, F.col("start") + F.col("offset") + slop)) if slop else F.col("start") + F.col("offset")
    wanted = wanted.select(*_KEY, "win", "start", "length", "offset", "term", near.alias("pos"))
    kept = index.join(small(candidates.where(F.col("length") > first).select(*_KEY).distinct()), _KEY, "left_semi")
    found = wanted.join(kept, [*_KEY, "pos", "term"]).groupBy(*_KEY, "win", "start", "length")
    found = found.agg(places.alias("n"))
    whole = found.where(F.col("n") == F.col("length") - first).drop("n")
    return candidates.where(F.col("length") <= first).unionByName(whole)


def decontaminate(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, slop: int = 0) -> DataFrame:
    """One row for each document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated.

    A null or wordless text has no words and no hits; an item without words is in no document; an item of fewer words
    than ``width`` is one window. Items of equal text both count; a null item_id is left out of the digest and count.
    Rows of one doc_id with different texts are judged apart, repeated rows alike; a null doc_id is carried. Clashing
    or further columns are not read. An empty benchmark hits nothing.

    With ``slop`` there are also n_near and near_sha256: items none of whose windows stands there exactly, but one with
    its words within ``slop`` words of their places. The other columns stay those of exact matches.
    """
    windows = phrase_windows(benchmark, width)
    index = build_index(docs, windows.terms)
    matches = cut(phrase_matches(index, windows), "matches")
    covered = matches.select(*_KEY, F.explode(F.sequence(F.col("start"), F.col("start") + F.col("length") - 1)).alias("pos"))
    hits = covered.distinct().groupBy(*_KEY).agg(F.count(F.lit(1)).alias("n_hit"))

    def named_in(found: DataFrame, name: str) -> DataFrame:
        inside = found.select(*_KEY, "win").distinct().join(small(windows.items), "win").select(*_KEY, F.col("item_id").cast("string").alias("item"))
        return inside.groupBy(*_KEY).agg(F.array_sort(F.collect_set("item")).alias(name))

    named = named_in(matches, "items")
    rows = keyed(docs, "doc_id", F.size(words(text_or_empty())).cast("long").alias("n_words"))
    joined = rows.join(hits, _KEY, "left").join(named, _KEY, "left")
    items = F.coalesce("items", F.array().cast("array<string>"))
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    more = []
    if slop:
        joined = joined.join(named_in(cut(phrase_matches(index, windows, slop), "near-matches"), "near"), _KEY, "left")
        near = F.array_except(F.coalesce("near", F.array().cast("array<string>")), items)
        more = [F.size(near).cast("long").alias("n_near"), F.sha2(F.array_join(near, ","), 256).alias("near_sha256")]
    return joined.select(
        "doc_id",
        "n_words",
        n_hit.alias("n_hit"),
        F.size(items).cast("long").alias("n_items"),
        F.sha2(F.array_join(items, ","), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"),
        *more,
    )


def clean_documents(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, width: int = WINDOW) -> DataFrame:
    """The documents, all columns, in which no window of the benchmark occurs."""
    windows = phrase_windows(benchmark, width)
    dirty = cut(phrase_matches(build_index(docs, windows.terms), windows).select(*_KEY).distinct(), "contaminated")
    did, th = F.coalesce(docs["doc_id"].cast("long"), F.lit(-(2**63))), F.xxhash64(text_or_empty(docs["text"]))
    names = {c: unused(f"_{c}", docs) for c in _KEY}
    dirty = small(dirty.withColumnsRenamed(names))
    return docs.join(dirty, (did == dirty[names["did"]]) & (th == dirty[names["th"]]), "left_anti")
