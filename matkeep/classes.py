"""Symmetric and transitive predicates, kept by class instead of by pair.

Where the recursive rules of a stratum say just that its one predicate is symmetric and transitive, its facts are all pairs
within the connected components of what the other rules give. A class of k nodes stands for k * k facts, each with k + 1
recursive instances: one of the symmetric rule and k of the transitive one. So only nodes with their class are written,
and what the nonrecursive rules give where counters are kept; pairs come from a join of the nodes with themselves.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lang import Rule, Var
from .plans.firing import minus
from .store import settle
from .strata import Stratification

#: Up to so many edges are joined by one task; more are brought down by star contractions first.
ONE_TASK = 300_000
ENDS = ["a0", "a1"]


def _ends(args: tuple) -> tuple[str, ...]:
    return tuple(a.name for a in args if isinstance(a, Var))


def _symmetric(rule: Rule) -> bool:
    (x, y), body = _ends(rule.head.args), [_ends(a.args) for a in rule.atoms]
    return x != y and body == [(y, x)]


def _transitive(rule: Rule) -> bool:
    (x, z), body = _ends(rule.head.args), [_ends(a.args) for a in rule.atoms]
    if len(body) != 2 or x == z:
        return False
    first, second = sorted(body, key=lambda b: b[0] != x)
    return first[0] == x and second[1] == z and first[1] == second[0] and first[1] not in (x, z)


def closed_predicate(strat: Stratification, s: int) -> str | None:
    """The predicate of a stratum whose recursive rules are one of symmetry and one of transitivity, else None."""
    preds, rec = strat.preds(s), strat.recursive(s)
    if len(preds) != 1 or len(rec) != 2 or any(r.builtins or r.negative or r.body_preds != {preds[0]} for r in rec):
        return None
    if any(len(a.args) != 2 or len(_ends(a.args)) != 2 for r in rec for a in (r.head, *r.atoms)):
        return None
    return preds[0] if sum(map(_symmetric, rec)) == 1 and sum(map(_transitive, rec)) == 1 else None


def _dealt(rows: DataFrame) -> DataFrame:
    """The few rows of nodes spread over all cores, as each of them stands for many pairs."""
    spark = rows.sparkSession
    return rows.repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))), "a")


@dataclass
class Classes:
    """``members``: a (node), c (the smallest node of its class), k (the size of its class), settled. ``support``: a0, a1, c_nr
    of what has nonrecursive support, settled; None where no counters are kept."""

    members: DataFrame
    support: DataFrame | None = None

    def pairs(self) -> DataFrame:
        return pairs_of(self.members)

    def counters(self, both: bool) -> DataFrame:
        if not both:
            return self.support
        every = pairs_of(self.members, (F.col("k") + 1).alias("c_r")).join(self.support, ENDS, "left")
        return every.select(*ENDS, F.coalesce("c_nr", F.lit(0).cast("bigint")).alias("c_nr"), "c_r")


def pairs_of(members: DataFrame, *more) -> DataFrame:
    """All pairs within the classes of a, c."""
    return _dealt(members).select(F.col("a").alias("a0"), "c", *more).join(members.select(F.col("a").alias("a1"), "c"), "c").drop("c")


def with_sizes(nodes: DataFrame) -> DataFrame:
    """The members of classes from a, c; settled."""
    return settle(nodes.join(nodes.groupBy("c").agg(F.count(F.lit(1)).alias("k")), "c").select("a", "c", "k"))[0]


# Components -----------------------------------------------------------------------------------------------------------


def _least_reached():
    """For one task; made by value, so that workers need not find this module."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = list(batches)
        if not got:
            return
        table = pa.Table.from_batches(got)
        u, v = (table.column(i).to_numpy() for i in (0, 1))
        nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
        x, y, label = at[: len(u)], at[len(u) :], np.arange(len(nodes))
        while True:
            least, new = np.minimum(label[x], label[y]), label.copy()
            for place in (x, y, label[x], label[y]):
                np.minimum.at(new, place, least)
            new = new[new]
            if np.array_equal(new, label):
                break
            label = new
        kind = table.schema.field(0).type
        yield pa.RecordBatch.from_arrays([pa.array(n, kind) for n in (nodes, nodes[label])], names=["a", "c"])

    return run


def _contracted(edges: DataFrame) -> DataFrame:
    """Larger neighbours are tied to the smallest neighbour, then smaller ones: components stay, paths get shorter."""
    both = edges.unionByName(edges.select(F.col("a1").alias("a0"), F.col("a0").alias("a1")))
    least = both.groupBy("a0").agg(F.least(F.min("a1"), F.col("a0")).alias("m"))
    up = both.join(least, "a0").where("a1 > a0").select(F.col("a1").alias("a0"), F.col("m").alias("a1")).distinct()
    up = settle(up.where("a0 <> a1"))[0]
    least = up.groupBy("a0").agg(F.min("a1").alias("m"))
    moved = up.join(least, "a0").where("a1 <> m").select(F.col("a1").alias("a0"), F.col("m").alias("a1"))
    return moved.unionByName(least.withColumnRenamed("m", "a1")).distinct()


def reached(edges: DataFrame) -> DataFrame:
    """a, c: each end of the edges (a0, a1) with the smallest node it reaches; settled."""
    edges, n = settle(edges.select(*ENDS))
    kind = edges.dtypes[0][1]
    now, state = edges.where("a0 <> a1") if n > ONE_TASK else edges, None
    while n > ONE_TASK:
        now, n = settle(_contracted(now))
        last, state = state, tuple(now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64(*ENDS)), F.sum(F.hash(*ENDS).cast("bigint"))).first())
        if state == last:
            roots = now.select(F.col("a1").alias("a"), F.col("a1").alias("c")).distinct()
            found = now.select(F.col("a0").alias("a"), F.col("a1").alias("c")).unionByName(roots)
            break
    else:
        found = now.coalesce(1).mapInArrow(_least_reached(), f"a {kind}, c {kind}")
    if now is edges:
        return settle(found)[0]
    found = settle(found)[0]
    alone = edges.where("a0 = a1").select(F.col("a0").alias("a")).join(found, "a", "left_anti").distinct()
    return settle(found.unionByName(alone.select("a", F.col("a").alias("c"))))[0]


# Changes --------------------------------------------------------------------------------------------------------------


@dataclass
class ClassChange:
    """The classes after an update, and pairs that are no more, new, and there before and after."""

    classes: Classes
    lost: DataFrame | None
    gained: DataFrame | None
    surviving: DataFrame


def without_loss(support: DataFrame, lost: DataFrame) -> DataFrame:
    """The nonrecursive counters after the losses, those left above zero."""
    rows = support.join(lost.select(*ENDS, F.col("m").alias("_m")), ENDS, "left")
    return rows.select(*ENDS, (F.col("c_nr") - F.coalesce("_m", F.lit(0))).cast("bigint").alias("c_nr")).where("c_nr > 0")


def with_gain(support: DataFrame | None, gained: DataFrame) -> DataFrame:
    """The nonrecursive counters after the gains; only rows that gain are summed."""
    more = gained.select(*ENDS, F.col("m").alias("c_nr"))
    if support is None:
        return more
    met = support.join(gained.select(*ENDS), ENDS, "left_semi").unionByName(more)
    return minus(support, gained).unionByName(met.groupBy(*ENDS).agg(F.sum("c_nr").alias("c_nr")))


def merged(state: DataFrame | None, gained: DataFrame) -> DataFrame:
    """a, c0, c2 from a, c0, c1 and new edges: classes that an edge ties become one, new ends come in."""
    if state is None:
        return reached(gained).select("a", F.lit(None).cast(gained.dtypes[0][1]).alias("c0"), F.col("c").alias("c2"))
    label = lambda end: state.where("c1 IS NOT NULL").select(F.col("a").alias(end), F.col("c1").alias(f"{end}_c"))
    ends = gained.select(*ENDS).join(label("a0"), "a0", "left").join(label("a1"), "a1", "left")
    tied = reached(ends.select(*[F.coalesce(f"{e}_c", e).alias(e) for e in ENDS]))
    nodes = gained.select(F.col("a0").alias("a")).union(gained.select(F.col("a1").alias("a"))).distinct().join(state, "a", "left_anti")
    none = F.lit(None).cast(state.dtypes[0][1])
    every = state.unionByName(nodes.select("a", none.alias("c0"), none.alias("c1"))).withColumn("_key", F.coalesce("c1", "a"))
    rows = every.join(tied.select(F.col("a").alias("_key"), "c"), "_key", "left")
    return rows.select("a", "c0", F.coalesce("c", "c1").alias("c2"))


# A state has a, c0, c2: a node's class before and after, null if it has none.


def crossing(state: DataFrame, one: str, other: str) -> DataFrame | None:
    """The pairs that are in one class by column ``one`` and not by ``other``; None if there are none.

    Groups that differ are found first, so that no pair is listed in vain.
    """
    rows = state.where(F.col(one).isNotNull()).select("a", F.col(one).alias("o"), F.coalesce(other, one).alias("g"), F.col(other).isNull().alias("h"))
    groups = rows.select("o", "g", "h").distinct()
    apart = groups.join(groups.select("o", F.col("g").alias("g2"), F.col("h").alias("h2")), "o").where("g <> g2 OR h OR h2")
    apart, n = settle(apart)
    if not n:
        return None
    left = _dealt(rows).select(F.col("a").alias("a0"), "o", "g", "h").join(apart, ["o", "g", "h"])
    right = rows.select(F.col("a").alias("a1"), "o", F.col("g").alias("g2"), F.col("h").alias("h2"))
    return left.join(right, ["o", "g2", "h2"]).select(*ENDS)


def standing(state: DataFrame) -> DataFrame:
    """The pairs in one class before and after."""
    rows = state.where("c0 IS NOT NULL AND c2 IS NOT NULL")
    right = rows.select(F.col("a").alias("a1"), "c0", "c2")
    return _dealt(rows).select(F.col("a").alias("a0"), "c0", "c2").join(right, ["c0", "c2"]).select(*ENDS)
