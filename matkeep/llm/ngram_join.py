"""N-gram Jaccard join by prefix filters under several global token orders.

A document is the set of its 5-word shingles. Under any order of all shingles, two sets of Jaccard similarity t share one
of their first ``size - ceil(t * size) + 1`` shingles. This holds under each of several orders at once, so candidates must
share a prefix shingle under the first order and one under the second; only then are the texts compared, exactly.

The first order goes from shingles of rare words to those of common ones and puts shingles found to be frequent last, so
that lists stay short and begin with what is a text's own; the second is by a hash. How far in front the first common shingle must be, and how many two prefixes must share, follows from the sizes.

Copies: documents of one set are a class, of which the smallest id takes part. In a group of near copies no pairs are
listed: each member is first compared with leaders of its lists; pairs between what that left in different
components, and only these, follow, so no link that could join two components is lost. Lists that are long even then are
split by the shingles of the second order: a pair is listed where both orders name a shingle that the two share.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .components import components
from .shared import cut, list_column, sliced, unused
from .shingling import Slots, counted, distinct, lowered, mixed, shingles_of, sums, word_hashes

WIDTH = 5
#: Similarity in hundredths: linked if 100 * intersection >= SHARE * union.
SHARE = 80
#: Frequent shingles and common words that the first order knows, at most; this changes speed, not results.
FREQUENT_KEPT = 300_000
COMMON_KEPT = 50_000
#: A side is broadcast only up to so many counted rows.
BROADCAST_ROWS = 300_000
#: Rounds of comparisons with leaders, at most, before the remaining pairs are listed.
LEADER_ROUNDS = 2
#: The remaining pairs are listed as soon as they are no more than this many for each row of the lists.
PAIRS_PER_ROW = 0.25
#: Lists of shingles counted so often are not gathered in one task.
HOT_LIST = 2_000
#: Pairs of one set that meet it under one salt.
SPREAD = 2_000
#: A list with more rows is split by the shingles of the second order before its pairs are listed.
LONG_LIST = 64


class Shingler:
    """Distinct 64-bit shingles of the texts of a slice, and how common their words are together."""

    def __init__(self, rates: Slots | None = None, width: int = WIDTH):
        self.rates, self.width = rates, width

    def sets(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray | None, np.ndarray]:
        """Shingles of all texts, bounds of each text's, rates of the shingles, and the hashes of all words."""
        words, bounds = word_hashes(*lowered(texts))
        found, bounds, rate = shingles_of(words, bounds, self.width, None if self.rates is None else self.rates.get(words))
        keep, bounds = distinct(found, bounds)
        if keep is not None:
            found, rate = found[keep], None if rate is None else rate[keep]
        return found, bounds, rate, words


def prefix_length(size: int) -> int:
    return size - -(-SHARE * size // 100) + 1


def first_keys(shingles: np.ndarray, rates: np.ndarray, frequent: Slots) -> np.ndarray:
    """The first order: those of rare words first, ties by hash; then the frequent ones by how frequent they are."""
    keys = (np.minimum(rates, 1023).astype(np.uint64) << np.uint64(53)) | (mixed(shingles, 1) >> np.uint64(11))
    ranks = frequent.get(shingles)
    hot = np.flatnonzero(ranks)
    keys[hot] = np.uint64(1 << 63) + ranks[hot].astype(np.uint64)
    return keys


def set_hashes(shingles: np.ndarray, bounds: np.ndarray) -> list[np.ndarray]:
    """128 bits of each set, in two halves."""
    return [sums(mixed(shingles, salt), bounds).view(np.int64) for salt in (5, 6)]


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


@dataclass(frozen=True)
class FrequentParts:
    """Frequent shingles and their ranks; hashes of the common words and how common these are, in eighths of a doubling; and
    ``hot``, a frame of one column, ``tok``, with the shingles whose lists may be too long for one task."""

    shingles: np.ndarray
    ranks: np.ndarray
    words: np.ndarray
    rates: np.ndarray
    hot: DataFrame


class _Counts:
    """Sums of how often values occur; what a stretch of input has once only is not counted."""

    def __init__(self) -> None:
        self.values, self.n = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
        self.parts, self.held = [], 0

    def add(self, values: np.ndarray) -> None:
        self.parts.append(values)
        self.held += len(values)
        if self.held > 2_000_000:
            self.fold()

    def fold(self) -> None:
        values, n = counted(np.concatenate([*self.parts, np.zeros(0, dtype=np.uint64)]))
        self.parts, self.held = [], 0
        both, where = np.unique(np.concatenate([self.values, values]), return_inverse=True)
        self.values, self.n = both, np.bincount(where.reshape(-1), np.concatenate([self.n, n]), len(both)).astype(np.int64)


def frequent_parts(docs: DataFrame) -> FrequentParts:
    """Counted in each partition and summed where a partition has a shingle twice or a word sixteen times; equal texts of a
    partition count once. At most FREQUENT_KEPT shingles and COMMON_KEPT words come to the driver.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler, seen = Shingler(), set()
        sets, common = _Counts(), _Counts()
        for _, texts in sliced(batches):
            data, bounds = lowered(texts)
            fresh = np.zeros(len(texts), dtype=bool)
            for k, (lo, hi) in enumerate(pairwise(bounds.tolist())):
                if hi > lo and (h := hash(data[lo:hi])) not in seen:
                    seen.add(h)
                    fresh[k] = True
            found, _, _, words = shingler.sets(texts if fresh.all() else texts.filter(pa.array(fresh)))
            sets.add(found)
            common.add(words)
        sets.fold()
        common.fold()
        often = common.n >= 16
        kept = common.values[often]
        columns = [
            pa.array(np.arange(len(sets.values) + len(kept)) >= len(sets.values)),
            pa.array(np.concatenate([sets.values, kept]).view(np.int64)),
            pa.array(np.concatenate([sets.n, common.n[often]])),
        ]
        yield pa.RecordBatch.from_arrays(columns, names=["word", "s", "n"])

    totals = docs.select("doc_id", "text").mapInArrow(count, "word boolean, s long, n long").groupBy("word", "s").agg(F.sum("n").alias("n"))
    totals = cut(totals, "frequencies")
    most = lambda part, kept: totals.where(part).orderBy(F.desc("n"), "s").limit(kept).select("s", "n").toArrow()
    (s, n), (words, often) = ([t[c].to_numpy() if t.num_rows else np.zeros(0, dtype=np.int64) for c in ("s", "n")] for t in (most("NOT word AND n > 2", FREQUENT_KEPT), most("word", COMMON_KEPT)))
    ranks = np.empty(len(s), dtype=np.int64)
    ranks[np.lexsort((s.view(np.uint64), -n))] = np.arange(len(s), 0, -1)  # the most frequent last
    rates = (8 * np.log2(np.maximum(often, 1))).astype(np.int64)
    hot = totals.where(f"NOT word AND n >= {HOT_LIST}").select(F.col("s").alias("tok"))
    return FrequentParts(s.view(np.uint64), ranks, words.view(np.uint64), rates, hot)


def signatures(spark: SparkSession, docs: DataFrame, parts: FrequentParts) -> DataFrame:
    """doc_id, n_shingles, ha and hb (128 bits of the set), p1 and p2 (prefixes; p2 cut to 32 bits: values that became equal are allowed for in the counts)."""
    sent = spark.sparkContext.broadcast((parts.shingles, parts.ranks, parts.words, parts.rates))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        frequent, ranks, words, rates = sent.value
        frequent, shingler = Slots(frequent, ranks), Shingler(Slots(words, rates))
        for ids, texts in sliced(batches):
            s, bounds, rate, _ = shingler.sets(texts)
            first, second = first_keys(s, rate, frequent), mixed(s, 2)
            p1, p2 = [], []
            for lo, hi in pairwise(bounds.tolist()):
                p = prefix_length(hi - lo) if hi > lo else 0
                keys, other = first[lo:hi], second[lo:hi]
                at = np.argpartition(keys, p - 1)[:p] if p < hi - lo else np.arange(p)
                p1.append(s[lo + at[np.argsort(keys[at])]])
                other.sort()
                p2.append(other[:p])
            p1, p2 = list_column([x.view(np.int64) for x in p1], pa.int64()), list_column([x.astype(np.uint32).view(np.int32) for x in p2], pa.int32())
            n = np.diff(bounds).astype(np.int64)
            yield pa.RecordBatch.from_arrays([ids.cast(pa.int64()), *map(pa.array, (n, *set_hashes(s, bounds))), p1, p2], names=["doc_id", "n_shingles", "ha", "hb", "p1", "p2"])

    return docs.select("doc_id", "text").mapInArrow(sign, "doc_id long, n_shingles long, ha long, hb long, p1 array<long>, p2 array<int>")


def shingle_sets(docs: DataFrame) -> DataFrame:
    """doc_id, ha, hb and the set itself of each row; a partition names a repeated row once."""

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler, seen = Shingler(), set()
        for ids, texts in sliced(batches):
            s, bounds, _, _ = shingler.sets(texts)
            rows = []
            for lo, hi, *key in zip(*(x.tolist() for x in (bounds[:-1], bounds[1:])), ids.to_pylist(), *(h.tolist() for h in set_hashes(s, bounds)), strict=True):
                if (key := tuple(key)) not in seen and hi > lo:
                    if len(seen) > 100_000:
                        seen.clear()
                    seen.add(key)
                    rows.append((key, np.sort(s[lo:hi])))
            lists = list_column([s.view(np.int64) for _, s in rows], pa.int64())
            yield pa.RecordBatch.from_arrays([*(pa.array([k[i] for k, _ in rows], pa.int64()) for i in range(3)), lists], names=["doc_id", "ha", "hb", "s"])

    return docs.select("doc_id", "text").mapInArrow(sets, "doc_id long, ha long, hb long, s array<long>")


def heavy_keys(pairs: DataFrame, key: str) -> DataFrame:
    """key, ways: keys of more than SPREAD pairs, and over how many salts they are spread."""
    ways = F.ceil(F.count(F.lit(1)) / SPREAD).cast("int")
    return cut(pairs.groupBy(key).agg(ways.alias("ways")).where("ways > 1"), "heavy")


def joined_on(pairs: DataFrame, key: str, other: str, side: DataFrame, heavy: DataFrame) -> DataFrame:
    """``pairs`` with the columns of ``side``; pairs of a heavy key meet copies of its row under several salts."""
    heavy = _small(heavy)
    salted = pairs.join(heavy, key, "left").withColumn("_salt", F.pmod(F.xxhash64(other), F.coalesce("ways", F.lit(1))).cast("int")).drop("ways")
    copies = F.explode(F.sequence(F.lit(0), F.coalesce("ways", F.lit(1)) - 1)).alias("_salt")
    spread = side.join(heavy, key, "left").select(*side.columns, copies)
    return salted.join(spread, [key, "_salt"]).drop("_salt")


def verified(pairs: DataFrame, reps: DataFrame, docs: DataFrame) -> DataFrame:
    """Of the pairs a, b those whose prefixes agree enough under each order, and whose sets then are similar enough.

    Sets meet in the JVM one pair at a time, so what a task holds is two sets, however many pairs a set is in.
    """
    merged = lambda p: F.size(p) - F.size(F.array_distinct(p))
    side = lambda c: reps.select(F.col("doc_id").alias(c), *[F.col(x).alias(f"{x}{c}") for x in ("n", "p1", "p2")], *[merged(p).alias(f"m{p}{c}") for p in ("p1", "p2")])
    heavy = {c: heavy_keys(pairs, c) for c in "ab"}
    both = joined_on(joined_on(pairs, "b", "a", side("b"), heavy["b"]), "a", "b", side("a"), heavy["a"])
    both = cut(both.where(_enough("p1") & _enough("p2")).select("a", "b").distinct(), "pairs")
    ids = cut(both.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct(), "pair-ids")
    sets = cut(shingle_sets(docs.select("doc_id", "text").join(_small(ids), "doc_id", "left_semi")), "pair-sets")
    of = lambda c: sets.select(F.col("doc_id").alias(c), F.col("s").alias(f"s{c}"))
    heavy = {c: heavy_keys(both, c) for c in "ab"}
    met = joined_on(joined_on(both, "b", "a", of("b"), heavy["b"]), "a", "b", of("a"), heavy["a"])
    common = F.size(F.array_intersect("sa", "sb"))
    return met.where(100 * common >= SHARE * (F.size("sa") + F.size("sb") - common)).select("a", "b").distinct()


def _enough(prefix: str):
    """Whether two prefixes of one order share as many shingles as similar sets must.

    Common shingles up to where the first of the two prefixes ends are in both prefixes; beyond it there are no more than
    that set has left. Similar sets have ``SHARE / (100 + SHARE)`` of their summed sizes in common. Shortened values may
    coincide: what is in common loses no more distinct values by that than either prefix does (``m``).
    """
    needed = F.ceil(SHARE * (F.col("na") + F.col("nb")) / (100 + SHARE))
    beyond = F.greatest(F.col("na") - F.size(f"{prefix}a"), F.col("nb") - F.size(f"{prefix}b"))
    return F.size(F.array_intersect(f"{prefix}a", f"{prefix}b")) >= F.greatest(needed - beyond - F.least(f"m{prefix}a", f"m{prefix}b"), F.lit(1))


def _pair(x: str, y: str) -> list:
    return [F.least(x, y).alias("a"), F.greatest(x, y).alias("b")]


def _fits(n: str, m: str):
    return (100 * F.least(n, m) >= SHARE * F.greatest(n, m))


def similar_components(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable over links) for each document.

    A null text, or one without words, has no shingles and stands alone. Rows of one doc_id are one node, linked by
    what any of their texts is similar to. A row with a null doc_id takes no part and has a null component. Extra columns
    are not read; an empty table gives an empty result. All links that decide components are found; none is capped.
    """
    known_parts = frequent_parts(docs)
    signed = cut(signatures(spark, docs, known_parts), "signatures")
    known = signed.where("doc_id IS NOT NULL AND n_shingles > 0")
    of_set = ["n_shingles", "ha", "hb"]
    classes = known.groupBy(*of_set).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n"))
    classes = cut(classes.where("n > 1").drop("n"), "classes")
    members = signed.select("doc_id", *of_set).join(_small(classes), of_set, "left")
    members = cut(members.withColumn("rep", F.when(F.col("doc_id").isNotNull(), F.coalesce("rep", "doc_id"))), "members")
    # An id whose rows have several sets joins their classes.
    ties = members.where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    twice = members.where("doc_id IS NOT NULL").groupBy(F.col("doc_id").alias("a")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("a")
    tied = ties.join(_small(cut(twice, "doubled")), "a", "left_semi")
    # Of a class its representative's row; rows, not ids, are left out, as another text of the id may represent its own class.
    placed = known.join(_small(classes), of_set, "left")
    row = ["doc_id", F.col("n_shingles").cast("int").alias("n"), "p1", "p2"]
    alone, first = placed.where("rep IS NULL").select(*row), placed.where("rep = doc_id").dropDuplicates(["doc_id", *of_set]).select(*row)
    reps = alone.unionByName(first)
    lists = cut(_lists(reps.select(F.col("doc_id").alias("d"), "n", F.posexplode("p1").alias("i", "tok")), known_parts.hot), "lists")
    taking = cut(lists.groupBy(F.col("d").alias("doc_id")).agg(F.count(F.lit(1)).alias("shared")), "in-lists")
    short = F.transform("p1", lambda x: x.bitwiseAND(F.lit(0x7FFFFFFF).cast("long")).cast("int"))
    reps = cut(reps.join(_small(taking.select("doc_id")), "doc_id", "left_semi").select("doc_id", "n", short.alias("p1"), "p2"), "prefixes")
    links = cut(tied.distinct(), "ties")
    tried: DataFrame | None = None
    # Of a group of near copies the original shares most of its prefix: it makes the best leader.
    lists = cut(lists.join(_small(taking.withColumnRenamed("doc_id", "d")), "d").select("tok", "d", "n", "i", (F.col("shared") * 1000 / F.col("n")).cast("int").alias("central")), "lists")
    open_lists, room = lists.withColumn("c", F.col("d")), PAIRS_PER_ROW * max(1, lists.count())
    for turn in range(LEADER_ROUNDS + 1):
        left = _pairs_between(open_lists)
        if not left:
            break
        if last := turn == LEADER_ROUNDS or left <= room:
            pairs = _all_between(_split_by_second(open_lists, reps))
        else:
            pairs = _to_leaders(open_lists, turn)
        if tried is not None:
            pairs = pairs.join(tried, ["a", "b"], "left_anti")
        pairs = cut(pairs, "candidate-pairs")
        links = cut(links.union(verified(pairs, reps, docs)), "links")
        if last:
            break
        tried = pairs if tried is None else tried.union(pairs)
        open_lists = _between_components(lists, links)
    found = components(links).withColumnRenamed("node", "rep")
    joined = members.join(_small(cut(found, "components")), "rep", "left")
    return joined.select("doc_id", "n_shingles", F.coalesce("component", "rep").alias("component_id"))


def _lists(spread: DataFrame, hot: DataFrame) -> DataFrame:
    """Rows d, n, i, tok of those that may be similar to another of their list, and near enough to the front for it.

    The list of a common shingle may be most of the table: it is judged by counts for each step of a scale of sizes,
    which are summed before the shuffle; sizes that fit one another lie in one step or in steps side by side.
    """
    hot = _small(cut(hot, "hot-shingles"))
    by_size = W.partitionBy("tok").orderBy("n", "d")
    short = spread.join(hot, "tok", "left_anti")
    short = short.select("*", F.lag("n").over(by_size).alias("_p"), F.lead("n").over(by_size).alias("_s"), F.first("n").over(by_size).alias("least"))
    short = short.where((F.col("_p").isNotNull() & _fits("n", "_p")) | (F.col("_s").isNotNull() & _fits("n", "_s"))).drop("_p", "_s")
    long = spread.join(hot, "tok", "left_semi").withColumn("step", F.floor(F.log(F.col("n").cast("double")) / math.log(100 / SHARE) + F.lit(1e-9)).cast("int"))
    steps = long.groupBy("tok", "step").agg(F.count(F.lit(1)).alias("rows"), F.min("n").alias("least"))
    near = steps.select("tok", F.explode(F.array(F.col("step") - 1, F.col("step"), F.col("step") + 1)).alias("step"), "rows", "least")
    near = near.groupBy("tok", "step").agg(F.sum("rows").alias("rows"), F.min("least").alias("least")).where("rows > 1").drop("rows")
    long = long.join(_small(cut(near, "hot-sizes")), ["tok", "step"]).select(*short.columns)
    smallest = F.greatest(F.col("least"), F.ceil(SHARE * F.col("n") / 100))
    front = F.col("i") <= F.col("n") - F.ceil(SHARE * (F.col("n") + smallest) / (100 + SHARE))
    return short.unionByName(long).where(front).select("tok", "d", "n", "i")


def _near_front(n: str, i: str, m: str, j: str):
    """Whether places i and j can be those of the first common shingle of similar sets of n and m shingles.

    What is in common then comes at or after these places in both.
    """
    needed = F.ceil(SHARE * (F.col(n) + F.col(m)) / (100 + SHARE))
    return (F.col(i) <= F.col(n) - needed) & (F.col(j) <= F.col(m) - needed)


def _pairs_between(lists: DataFrame) -> int:
    """About how many pairs of different components the lists bring up, summed over lists; zero only if there are none."""
    # Sets of about one size must meet within the first ninth or so.
    early = lists.where((100 + SHARE) * F.col("i") <= (100 - SHARE) * F.col("n"))
    by_component = early.groupBy("tok", "c").agg(F.count(F.lit(1)).cast("double").alias("n"))
    by_list = by_component.groupBy("tok").agg(((F.sum("n") * F.sum("n") - F.sum(F.col("n") * F.col("n"))) / 2).alias("pairs"))
    found = int(by_list.agg(F.coalesce(F.sum("pairs"), F.lit(0.0))).first()[0])
    return found or int(not lists.isEmpty())


def _to_leaders(lists: DataFrame, turn: int) -> DataFrame:
    """Pairs of each member with one member of its list: the one that shares most of itself, later another each turn."""
    pick = [-F.col("central"), F.col("n"), F.col("d")] if turn == 0 else [F.xxhash64("d", F.lit(turn)), F.col("d")]
    best = F.min_by(F.struct("d", "n", "c", "i"), F.struct(*[x.alias(f"k{i}") for i, x in enumerate(pick)])).alias("lead")
    leaders = lists.groupBy("tok").agg(best).select("tok", *[F.col(f"lead.{x}").alias(f"l{x}") for x in ("d", "n", "c", "i")])
    led = lists.join(leaders, "tok")
    return led.where((F.col("c") != F.col("lc")) & _fits("n", "ln") & _near_front("n", "i", "ln", "li")).select(*_pair("d", "ld")).distinct()


def _split_by_second(lists: DataFrame, reps: DataFrame) -> DataFrame:
    """Lists of more than LONG_LIST rows are split: rows stay together only if they share a shingle of the second order too.

    What is similar shares a prefix shingle under either order, so every pair still meets, in a list of such a couple.
    Couples of rows of one component only are left out. ``before`` is the row's list before this one, ``beside`` its
    couple before this one; see ``_all_between``.
    """
    size = lists.groupBy("tok").agg(F.count(F.lit(1)).alias("rows"))
    long = _small(cut(size.where(F.col("rows") > LONG_LIST).select("tok"), "long-lists"))
    lists = lists.withColumn("before", F.lag("tok").over(W.partitionBy("d").orderBy("i", "tok")))
    # The first common shingle of the second order stands no further behind than that of the first may.
    reach = F.col("n") - F.ceil(SHARE * (F.col("n") + F.ceil(SHARE * F.col("n") / 100)) / (100 + SHARE))
    second = reps.select(F.col("doc_id").alias("d"), F.slice("p2", F.lit(1), F.greatest(reach, F.lit(0)).cast("int") + 1).alias("p2"))
    couple = F.transform("p2", lambda x, j: F.struct(F.xxhash64("tok", x).alias("tok"), F.when(j > 0, F.get("p2", j - 1)).alias("beside")))
    inside = lists.join(long, "tok", "left_semi").join(second, "d").select("d", "n", "i", "c", "before", F.explode(couple).alias("couple"))
    couples = cut(inside.select(F.col("couple.tok").alias("tok"), "d", "n", "i", "c", "before", F.col("couple.beside").alias("beside")), "couples")
    mixed_ones = couples.groupBy("tok").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("tok")
    rest = lists.join(long, "tok", "left_anti").select("tok", "d", "n", "i", "c", "before", F.lit(None).cast("int").alias("beside"))
    return rest.unionByName(couples.join(mixed_ones, "tok", "left_semi"))


def _all_between(lists: DataFrame) -> DataFrame:
    """All pairs of members of one list and of different components whose sizes allow a link.

    A pair that has met in the list before this one, the same for both rows, is not brought up again: near copies share
    long stretches of their prefixes, and would meet in each list of these.
    """
    columns = ("d", "n", "c", "i", "before", "beside")
    x, y = (lists.select("tok", *[F.col(c).alias(f"{c}{s}") for c in columns]) for s in "xy")
    again = F.coalesce(F.col("beforex") == F.col("beforey"), F.lit(False)) | F.coalesce(F.col("besidex") == F.col("besidey"), F.lit(False))
    fits = (F.col("dx") < F.col("dy")) & (F.col("cx") != F.col("cy")) & _fits("nx", "ny") & _near_front("nx", "ix", "ny", "iy")
    return x.join(y, "tok").where(fits & ~again).select(*_pair("dx", "dy")).distinct()


def _between_components(lists: DataFrame, links: DataFrame) -> DataFrame:
    """The lists whose members are not all in one component by now, with each member's component ``c``."""
    now = components(links).withColumnsRenamed({"node": "d", "component": "c"})
    placed = lists.join(_small(cut(now, "components")), "d", "left").select("tok", "d", "n", "i", "central", F.coalesce("c", "d").alias("c"))
    placed = cut(placed, "placed")
    mixed_lists = placed.groupBy("tok").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("tok")
    return cut(placed.join(_small(cut(mixed_lists, "mixed-lists")), "tok", "left_semi"), "open-lists")


def one_of_each_group(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The documents, all columns, but for those whose component has a smaller doc_id.

    Rows of a null doc_id stay. Of rows that share the smallest doc_id one of each text stays.
    """
    grouped = cut(similar_components(spark, docs), "grouped")
    away, twice = unused("gone", docs), unused("twice", docs)
    gone = cut(grouped.where("doc_id <> component_id").select(F.col("doc_id").alias(away)).distinct(), "near-copies")
    kept = docs.join(_small(gone), docs["doc_id"] == F.col(away), "left_anti")
    again = grouped.where("doc_id = component_id").groupBy(F.col("doc_id").alias(twice)).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(twice)
    again = _small(cut(again, "repeated-ids"))
    # Only rows of repeated ids are shuffled.
    once, more = (kept.join(again, kept["doc_id"] == F.col(twice), how) for how in ("left_anti", "left_semi"))
    return once.unionByName(more.dropDuplicates(["doc_id", "text"]))
