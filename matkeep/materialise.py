"""Materialisation from scratch: naive (as a check), semi-naive, and semi-naive with counters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .classes import Classes, closed_predicate, reached, with_sizes
from .lang import Program
from .plans.firing import View, bag_affected, bag_all, bag_union, columns_of, keys_below, minus, together
from . import store
from .plans.folding import foldable, folded
from .store import Growing, Materialisation, add_counts, arranged, fold_counts, mark, settle, settle_all, settle_marked, size_of
from .strata import Stratification, stratify


class RoundLimit(RuntimeError):
    """The fixpoint took more rounds than allowed."""


def as_facts(df: DataFrame) -> DataFrame:
    """Columns renamed a0.., whole numbers as BIGINT, rows with a null left out, duplicates removed."""
    cols = []
    for i, (name, kind) in enumerate(df.dtypes):
        c = F.col(f"`{name}`")
        cols.append((c.cast("bigint") if kind in ("tinyint", "smallint", "int") else c).alias(f"a{i}"))
    return df.select(*cols).na.drop().distinct()


class Facts(dict):
    """Settled explicit facts; ``types`` has the column types of the predicates without facts too."""

    def __init__(self, facts: dict[str, DataFrame], types: dict[str, list[str]]):
        super().__init__(facts)
        self.types = types


def types_of(facts: dict[str, DataFrame]) -> dict[str, list[str]]:
    return {p: [kind for _, kind in df.dtypes] for p, df in facts.items()} | getattr(facts, "types", {})


def load(tables: dict[str, DataFrame]) -> Facts:
    """Explicit facts, made duplicate-free and settled."""
    made = {p: as_facts(df) for p, df in tables.items()}
    return Facts(settle_all(made)[0], types_of(made))


def materialise(
    spark: SparkSession, program: Program, explicit: dict[str, DataFrame], counters: int = 0, policy="finest", max_rounds: int = 10_000, work: list | None = None
) -> Materialisation:
    """All consequences, stratum by stratum; each rule instance is enumerated once.

    ``counters``: 0 keeps none, 1 keeps c_nr, 2 keeps c_nr and c_r. ``explicit`` holds fact frames as ``load`` makes them.
    """
    strat = policy if isinstance(policy, Stratification) else stratify(program, policy)
    facts = Growing({p: df for p, df in explicit.items() if strat.level.get(p, 0) == 0})
    out = Materialisation(spark, strat, dict(explicit), facts, types=types_of(explicit))
    none = lambda p: None
    for s in range(1, strat.count + 1):
        view = View(out.facts.get, out.facts.get)
        own = {p: explicit[p].withColumn("m", F.lit(1).cast("bigint")) for p in strat.preds(s) if p in explicit}
        base, sizes = settle_all(bag_union(own, bag_all(spark, strat.nonrecursive(s), view)))
        closed = closed_predicate(strat, s)
        if closed in base and len({kind for name, kind in base[closed].dtypes if name != "m"}) == 1:
            support = base[closed].withColumnRenamed("m", "c_nr") if counters else None
            keep_classes(out, closed, Classes(with_sizes(reached(base[closed])), support), counters)
            if work is not None:
                work.append((s, "nonrecursive", 0, "facts", sum(sizes.values())))
            continue
        parts = [(base, 1, 0)]
        delta = {p: df.drop("m") for p, df in base.items()}
        facts.grow(delta)
        rounds = 0
        rules = strat.recursive(s)
        kept, held = {}, []
        if delta and rules:
            below = lambda p, s=s: strat.level.get(p, 0) < s
            rules, fixed = folded(rules, below, view, "_fixed")
            kept = dict(zip(fixed, (settle(df)[0] for df in fixed.values()), strict=True))
            for p, cols in keys_below([r for r in rules if not foldable(r, below)], below).items():
                df = kept.get(p, facts.get(p))
                if df is not None and p not in out.classes and size_of(df) >= store.ARRANGED:
                    kept[p] = arranged(df, cols)
                    held.append(kept[p])
        steps = View(lambda p, kept=kept: kept[p] if p in kept else out.facts.get(p), out.facts.get)
        if work is not None:
            work.append((s, "nonrecursive", 0, "facts", sum(sizes.values())))
        while delta and rules:
            rounds += 1
            if rounds > max_rounds:
                raise RoundLimit(f"stratum {s}")
            heads = bag_affected(spark, rules, steps, delta.get, none)
            bag, delta, n, _ = settle_marked({p: mark(df, out.facts.get(p), "old").select(*df.columns, (~F.col("old")).alias("fresh")) for p, df in heads.items()})
            if counters > 1:
                parts = fold_counts([*parts, (bag, 0, 1)])
            facts.grow(delta)
            if work is not None:
                work.append((s, "recursive", rounds, "heads", n))
        for df in held:
            df.unpersist()
        if counters:
            out.counters |= settle_all({p: df if counters > 1 else df.drop("c_r") for p, df in add_counts(parts).items()})[0]
    out.facts = dict(facts)
    return out


def keep_classes(mat: Materialisation, p: str, classes: Classes, counters: int) -> None:
    """Facts and counters of a predicate that is kept by class."""
    mat.classes[p], mat.facts[p] = classes, classes.pairs()
    if counters:
        mat.counters[p] = classes.counters(counters > 1)


def naive(spark: SparkSession, program: Program, explicit: dict[str, DataFrame], policy="finest") -> Materialisation:
    """Applies whole strata until nothing is new; for tests."""
    strat = stratify(program, policy)
    out = Materialisation(spark, strat, dict(explicit), dict(explicit))
    for s in range(1, strat.count + 1):
        while True:
            bag = bag_all(spark, strat.rules(s), View(out.facts.get, out.facts.get))
            new = settle_all({p: minus(df.drop("m"), out.facts.get(p)) for p, df in bag.items()})[0]
            if not new:
                break
            for p, df in new.items():
                out.facts[p] = together(out.facts.get(p), df)
    return out


def audit_counters(spark: SparkSession, mat: Materialisation) -> dict[str, DataFrame]:
    """Rows whose counters differ from a recount over the facts, for each derived predicate; empty frames if all are right."""
    view = View(mat.facts.get, mat.facts.get)
    parts = []
    for s in range(1, mat.strat.count + 1):
        own = {p: mat.explicit[p].withColumn("m", F.lit(1).cast("bigint")) for p in mat.strat.preds(s) if p in mat.explicit}
        parts += [(own, 1, 0), (bag_all(spark, mat.strat.nonrecursive(s), view), 1, 0), (bag_all(spark, mat.strat.recursive(s), view), 0, 1)]
    true = add_counts(parts)
    wrong = {}
    for p in set(true) | set(mat.counters):
        if p in true and p in mat.counters:
            kept = mat.counters[p]
            names = [c for c in ("c_nr", "c_r") if c in kept.columns]
            t = true[p].select(*columns_of(true[p]), *names)
            if names == ["c_nr"]:
                t, kept = t.where("c_nr > 0"), kept.where("c_nr > 0")
            wrong[p] = t.exceptAll(kept).unionByName(kept.exceptAll(t))
        else:
            wrong[p] = true.get(p, mat.counters.get(p))
    return wrong
