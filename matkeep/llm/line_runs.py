"""Line dedup with a suffix array over line numbers, built by distributed prefix doubling.

Every document is its sequence of lines that have a word; each distinct repeated line gets its rank in one global order
as its number. Doubling then ranks, for each place, its first 2, 4, 8, ... lines, from the ranks of the two halves: the
places in rank order are the suffix array to that depth, and places of one rank form an interval whose longest common
prefix is at least that long. Places whose rank is nobody else's can be in no longer run and drop out at once, so only
repeated text takes part. Any run of m lines is named by two ranks that overlap, so runs of every length are compared
exactly. Of a repeated run the first copy stays and the later ones are deleted.

Only DataFrame functions are used. Texts meet their deletions in one join; all else moves short rows of numbers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .shared import cut, global_index, text_or_empty, unused

#: A repeated run is deleted if its lines have so many words or more together.
MIN_WORDS = 10
#: A side is broadcast only up to so many counted rows.
BROADCAST_ROWS = 300_000

_KEY = ["did", "th"]
_BLANKS = r"[\x20\x09-\x0D]+"


def _did(doc_id: Column) -> Column:
    return F.coalesce(doc_id.cast("long"), F.lit(-(2**63)))


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def line_table(docs: DataFrame) -> DataFrame:
    """did, th, seq (among lines with a word), pos (among all lines), h1 and h2 (128 bits of the line), n_words."""
    lines = F.transform(F.split(text_or_empty(), "\n"), lambda x, i: F.struct(i.alias("pos"), x.alias("line")))
    worded = F.filter(lines, lambda x: x["line"].rlike(r"[^\x20\x09-\x0D]"))
    rows = docs.select(_did(F.col("doc_id")).alias("did"), F.xxhash64(text_or_empty()).alias("th"), F.posexplode(worded).alias("seq", "l"))
    n_words = F.size(F.filter(F.split("l.line", _BLANKS), lambda w: w != ""))
    return rows.select(
        *_KEY, "seq", "l.pos", F.xxhash64("l.line").alias("h1"), F.xxhash64(F.lit("second"), "l.line").alias("h2"), n_words.alias("n_words")
    )


def repeated_places(docs: DataFrame) -> DataFrame:
    """The places of lines that occur twice or more: did, th, seg, seq, pos, n_words, r0. A segment has no gap."""
    lines = line_table(docs).repartition(*_KEY).dropDuplicates([*_KEY, "seq"])
    lines = cut(lines, "lines")
    often = lines.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h1", "h2")
    numbered, _ = global_index(often, ["h1", "h2"], "r0")
    places = lines.join(_small(numbered), ["h1", "h2"]).drop("h1", "h2")
    seg = F.col("seq") - F.row_number().over(W.partitionBy(*_KEY).orderBy("seq"))
    return cut(places.withColumn("seg", seg.cast("int")), "places")


def candidate_runs(places: DataFrame, min_words: int) -> DataFrame:
    """did, th, start, m: from each place the least run forwards, and the least run backwards, of ``min_words`` words.

    Whatever longer run is repeated, each of its lines lies in one of these that lies in it.
    """
    # A line has a word at least, so min_words lines are enough to look at.
    order = W.partitionBy(*_KEY, "seg").orderBy("seq")
    ahead, behind = order.rowsBetween(0, min_words - 1), order.rowsBetween(-(min_words - 1), 0)

    def least(counts: Column) -> Column:
        state = F.struct(F.lit(0).alias("n"), F.lit(0).alias("m"))
        done = F.aggregate(
            counts, state, lambda s, c: F.when(s["n"] >= min_words, s).otherwise(F.struct((s["n"] + c).alias("n"), (s["m"] + 1).alias("m")))
        )
        return F.when(done["n"] >= min_words, done["m"])

    sized = places.select(*_KEY, "seq", F.collect_list("n_words").over(ahead).alias("a"), F.collect_list("n_words").over(behind).alias("b"))
    sized = sized.select(*_KEY, "seq", least(F.col("a")).alias("fwd"), least(F.reverse("b")).alias("bwd"))
    run = lambda start, m: F.struct(start.alias("start"), m.alias("m"))
    both = F.filter(F.array(run(F.col("seq"), F.col("fwd")), run(F.col("seq") - F.col("bwd") + 1, F.col("bwd"))), lambda r: r["m"].isNotNull())
    return sized.select(*_KEY, F.explode(F.array_distinct(both)).alias("r")).select(*_KEY, "r.start", "r.m")


def doubled(places: DataFrame, k: int) -> DataFrame:
    """Adds the rank of the first 2**(k+1) lines from the rank of the first 2**k; null where no other place shares them."""
    half = W.partitionBy(*_KEY, "seg").orderBy("seq")
    pairs = places.withColumn("_next", F.lead(f"r{k}", 2**k).over(half))
    pairs = cut(pairs, "pairs")
    often = pairs.where(F.col(f"r{k}").isNotNull() & F.col("_next").isNotNull()).groupBy(f"r{k}", "_next").agg(F.count(F.lit(1)).alias("n"))
    numbered, _ = global_index(often.where("n > 1").drop("n"), [f"r{k}", "_next"], f"r{k + 1}")
    return pairs.join(_small(numbered), [f"r{k}", "_next"], "left").drop("_next")


def later_copies(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """did, th, pos of every line that lies in a later copy of a repeated run of ``min_words`` words or more.

    The first copy is that of the smallest doc_id (null first), then text hash, then line.
    """
    places = repeated_places(docs)
    runs = cut(candidate_runs(places, min_words), "runs")
    longest = runs.agg(F.max("m")).first()[0] or 1
    top = longest.bit_length() - 1
    for k in range(top):
        places = doubled(places, k)
    if top:
        places = cut(places, "ranked-places")
    level = F.floor(F.log2(F.col("m") + F.lit(0.5))).cast("int")
    named = runs.select("*", level.alias("k"))
    tail = (F.col("start") + F.col("m") - F.call_function("shiftleft", F.lit(1), F.col("k"))).alias("tail")
    named = named.select("*", tail)
    ranks = places.select(*_KEY, "seq", F.array(*[F.col(f"r{k}") for k in range(top + 1)]).alias("r"))
    at = lambda seq, name: ranks.select(*_KEY, F.col("seq").alias(seq), F.col("r").alias(name))
    named = named.join(at("start", "ra"), [*_KEY, "start"]).join(at("tail", "rb"), [*_KEY, "tail"])
    named = named.select(*_KEY, "start", "m", F.element_at("ra", F.col("k") + 1).alias("x"), F.element_at("rb", F.col("k") + 1).alias("y"))
    named = cut(named.where("x IS NOT NULL AND y IS NOT NULL"), "named-runs")
    groups = named.groupBy("m", "x", "y").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct(*_KEY, "start")).alias("first")).where("n > 1").drop("n")
    later = named.join(_small(cut(groups, "intervals")), ["m", "x", "y"]).where(F.struct(*_KEY, "start") != F.col("first"))
    covered = later.select(*_KEY, F.explode(F.sequence(F.col("start"), F.col("start") + F.col("m") - 1)).alias("seq")).distinct()
    return covered.join(places.select(*_KEY, "seq", "pos"), [*_KEY, "seq"]).select(*_KEY, "pos")


def _with_counts(docs: DataFrame, min_words: int) -> tuple[DataFrame, str, str]:
    """The documents with the text that is left, and two more columns, whose names come with them: lines before, lines deleted."""
    gone = later_copies(docs, min_words).groupBy(*_KEY).agg(F.collect_list("pos").alias("_gone"))
    # Deleted lines grow with the table, so they are never broadcast: the same plan at every size.
    gone = cut(gone.withColumnsRenamed({"did": "_did", "th": "_th"}), "deleted-lines").hint("shuffle_hash")
    text, dead = docs["text"], gone["_gone"]
    met = docs.join(gone, (_did(docs["doc_id"]) == gone["_did"]) & (F.xxhash64(text_or_empty(text)) == gone["_th"]), "left")
    lines = F.split(text, "\n")
    left = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), dead)
    kept = F.when(dead.isNull(), text).otherwise(F.array_join(F.transform(left, lambda i: F.get(lines, i)), "\n"))
    n_lines = F.size(F.filter(F.split(text_or_empty(text), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))).cast("long")
    n_removed = F.when(dead.isNull(), 0).otherwise(F.size(dead)).cast("long")
    before, deleted = unused("n_lines", docs), unused("n_removed", docs)
    own = [kept.alias(c) if c == "text" else docs[c] for c in docs.columns]
    return met.select(*own, n_lines.alias(before), n_removed.alias(deleted)), before, deleted


def dedup_lines(spark: SparkSession, docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """The documents with their columns, ``text`` without the deleted lines, and n_lines and n_removed besides.

    n_lines counts lines with a word before, n_removed those deleted. Blank lines are no part of runs and stay. A null
    text stays null. Rows with equal doc_id and text are one document and get the same text. An empty table stays
    empty. Other columns of ``docs`` are carried, whatever their names; where ``docs`` has a column n_lines or n_removed,
    the new one gets an underscore in front.
    """
    return _with_counts(docs, min_words)[0]


def documents_left(spark: SparkSession, docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """The documents, their columns and no more, without the deleted lines; those of which nothing but blank lines is left go.

    A column n_chars is counted anew where lines went.
    """
    done, before, deleted = _with_counts(docs, min_words)
    left = done.where((F.col(deleted) == 0) | (F.col(deleted) < F.col(before)))
    if "n_chars" in docs.columns:
        length = F.char_length("text").cast(docs.schema["n_chars"].dataType)
        left = left.withColumn("n_chars", F.when(F.col(deleted) > 0, length).otherwise(F.col("n_chars")))
    return left.select(*docs.columns)
