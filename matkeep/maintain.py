"""Keeping a materialisation up to date under deletions and insertions: all strategies behind one entry point.

=========  =====================================================================================
odr        overdelete, then rederive in one step by backward matching, then insert; no counters
odr_2c     the same with two counters: a fact with nonrecursive support is not overdeleted, and
           facts are rederived by their recursive counter without evaluating a rule
pbd        prove before deleting: backward and forward chaining for each candidate; no counters
pbd_1c     the same with a nonrecursive counter, so proofs go backwards over recursive rules only
counting   derivation counts; programs without recursion only
remat*     from scratch, with 0, 1 or 2 counters
=========  =====================================================================================

Facts deleted (D) and added (A) so far are kept as overlays beside the old facts; the three views a phase may need are
``old``, ``surviving`` and ``new``. Each round of a loop is one set of Spark jobs whose results are settled.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .classes import ClassChange, Classes, closed_predicate, crossing, merged, pairs_of, reached, standing, with_gain, with_sizes, without_loss
from .lang import Rule, RuleError
from .materialise import RoundLimit, as_facts, keep_classes, materialise
from .plans.firing import Bag, Changed, View, bag_affected, bag_union, columns_of, fire, head_of, keys_below, match_backward, meet, minus, together
from . import store
from .plans.folding import foldable, folded
from .store import Growing, Layers, Materialisation, add_counts, arranged, fold_counts, mark, settle, settle_all, settle_bag, settle_marked, size_of
from .strata import Stratification

STRATEGIES = ("odr", "odr_2c", "pbd", "pbd_1c", "counting", "remat", "remat_1c", "remat_2c")
#: Counters a strategy needs from the materialisation it updates.
COUNTERS = {"odr": 0, "odr_2c": 2, "pbd": 0, "pbd_1c": 1, "counting": 1, "remat": 0, "remat_1c": 1, "remat_2c": 2}


@dataclass(frozen=True)
class Options:
    rederive_plan: str = "head_first"
    early_stop: bool = True
    collect_work: bool = False
    max_rounds: int = 10_000
    #: Parts of a sum that stand side by side before they are written as one.
    checkpoint_every: int = 8


@dataclass
class UpdateReport:
    mat: Materialisation
    seconds: float
    work: list[tuple[int, str, int, str, int]] = field(default_factory=list)
    overdeleted: dict[str, DataFrame] = field(default_factory=dict)
    rederived: dict[str, DataFrame] = field(default_factory=dict)
    deleted: dict[str, DataFrame] = field(default_factory=dict)
    added: dict[str, DataFrame] = field(default_factory=dict)
    #: For each predicate the counters' losses of the deletion phase, as negative numbers; none for those kept by class.
    losses: dict[str, DataFrame] = field(default_factory=dict)

    def measure(self, phase: str, name: str) -> int:
        return sum(v for _, p, _, m, v in self.work if p == phase and m == name)

    def as_frame(self, spark: SparkSession, strategy: str) -> DataFrame:
        rows = [(strategy, *w) for w in self.work] or [(strategy, 0, "none", 0, "rows", 0)]
        return spark.createDataFrame(rows, "strategy string, stratum int, phase string, round int, measure string, value bigint")


def normalise(explicit: dict[str, DataFrame], removed: dict[str, DataFrame], added: dict[str, DataFrame]) -> tuple[dict, dict]:
    """Deletions of facts that are there and are not asserted anew; insertions of facts that are not there; each once."""
    removed, added = ({p: as_facts(df) for p, df in side.items()} for side in (removed, added))
    gone = {p: minus(meet(df, explicit.get(p)), added.get(p)) for p, df in removed.items()}
    new = {p: minus(df, explicit.get(p)) for p, df in added.items()}
    return settle_all(gone)[0], settle_all(new)[0]


class _Update:
    """State of one update: old facts, overlays, and the change of each counter."""

    def __init__(self, mat: Materialisation, removed: dict, added: dict, strategy: str, options: Options):
        self.spark, self.mat, self.strat, self.options, self.strategy = mat.spark, mat, mat.strat, options, strategy
        self.gone, self.new_explicit = removed, added
        self.D = Growing()
        self.A = Growing()
        self.report = UpdateReport(mat, 0.0)
        self.signed: list[tuple[Bag, int, int]] = []
        self._net: dict[tuple[str, int], DataFrame | None] = {}
        #: What has become of the predicates kept by class.
        self.closed: dict[str, ClassChange] = {}
        #: Large sets the steps of a loop join, arranged for that: finished predicates with what has become of each fact,
        #: and the old facts and counters of the own stratum.
        self.below: dict[str, DataFrame] = {}
        self.own: dict[str, DataFrame] = {}
        self.counts: dict[str, DataFrame] = dict(mat.counters)
        #: The recursive rules of the stratum as the loops apply them, over what survives and over what is new.
        self._rules: dict[str, list[Rule]] = {}
        self._fixed: dict[str, DataFrame] = {}
        self._held: list[DataFrame] = []

    # Large sets ----------------------------------------------------------------------------------------------------

    def _arrange(self, s: int) -> None:
        """Arranges what the loops of the stratum join in every step, where it is large."""
        rec = self.strat.recursive(s)
        below = lambda p: self.strat.level.get(p, 0) < s
        large = lambda df: df is not None and size_of(df) >= store.ARRANGED
        for p, keys in keys_below([r for r in rec if not foldable(r, below)], below).items():
            own, gained = self.old(p), self.gained(p)
            if large(own) and p not in self.closed:
                cols = columns_of(own)
                rows = mark(own, self.lost(p), "_lost").withColumn("_more", F.lit(False))
                if gained is not None:
                    rows = rows.unionByName(gained.select(*cols, F.lit(False).alias("_lost"), F.lit(True).alias("_more")))
                self.below[p] = self._hold(rows, keys)
        for p in self.strat.preds(s) if rec else ():
            own, kept = self.old(p), self.mat.counters.get(p)
            if large(own):
                cols = columns_of(own)
                if kept is not None:
                    self.counts[p] = self._hold(kept, cols)
                # With both counters each fact has a row there, and no other has.
                self.own[p] = self.counts[p].select(*cols) if kept is not None and "c_r" in kept.columns else self._hold(own, cols)

    def _hold(self, df: DataFrame, keys: list[str]) -> DataFrame:
        self._held.append(arranged(df, keys))
        return self._held[-1]

    def rules_left(self) -> list[Rule]:
        """The recursive rules for steps over what survives, finished atoms folded into one."""
        return self._folded("_left", View(self.surviving_parts, self.old_or_added))

    def rules_new(self) -> list[Rule]:
        """The same for steps over the new facts."""
        return self._folded("_new", View(self.new_parts, self.new))

    def _folded(self, name: str, view: View) -> list[Rule]:
        if name not in self._rules:
            below = lambda p: self.strat.level.get(p, 0) < self.stratum
            self._rules[name], frames = folded(self.strat.recursive(self.stratum), below, view, name)
            keys = keys_below([r for r in self._rules[name] if any(a.pred in frames for a in r.atoms)], below)
            for p, df in frames.items():
                df, _ = settle(df)
                self._fixed[p] = self._hold(df, keys[p]) if p in keys and size_of(df) >= store.ARRANGED else df
        return self._rules[name]

    def let_go(self) -> None:
        for df in self._held:
            df.unpersist()

    # Views ---------------------------------------------------------------------------------------------------------

    def old(self, p: str) -> DataFrame | None:
        return self.own.get(p, self.mat.facts.get(p))

    def lost(self, p: str) -> DataFrame | None:
        """D without A."""
        d = self.D.get(p)
        return d if d is None or p in self.closed or p not in self.A else self._settled(("lost", p), lambda: minus(d, self.A[p]))

    def gained(self, p: str) -> DataFrame | None:
        """A without D."""
        a = self.A.get(p)
        return a if a is None or p in self.closed or p not in self.D else self._settled(("gained", p), lambda: minus(a, self.D[p]))

    def _settled(self, key: tuple, make) -> DataFrame | None:
        """Differences of finished strata are computed once."""
        done = self.strat.level.get(key[1], 0) < self.stratum
        if not done:
            return make()
        if key not in self._net:
            df, n = settle(make())
            self._net[key] = df if n else None
        return self._net[key]

    def surviving(self, p: str) -> DataFrame | None:
        own = self.old(p)
        if p in self.closed:
            return None if own is None else self.closed[p].surviving
        return None if own is None else minus(own, self.lost(p))

    def old_or_added(self, p: str) -> DataFrame | None:
        own, more = self.old(p), self.A.get(p)
        if p in self.closed:
            return together(own, more)
        return own if more is None else more if own is None else own.unionByName(minus(more, own))

    def new(self, p: str) -> DataFrame | None:
        if p in self.closed:
            return self.closed[p].classes.pairs()
        own = self.old(p)
        left = None if own is None else minus(own, self.D.get(p))
        return together(left, self.A.get(p))

    # The same for positive atoms, which may leave the differences of finished predicates until after their join.

    def _finished(self, p: str) -> bool:
        return self.strat.level.get(p, 0) < self.stratum and p not in self.closed

    def surviving_parts(self, p: str) -> DataFrame | Changed | None:
        if p in self._fixed:
            return self._fixed[p]
        if p in self.below:
            return self.below[p].where("NOT _lost AND NOT _more").drop("_lost", "_more")
        own, lost = self.old(p), self.lost(p)
        return self.surviving(p) if own is None or lost is None or not self._finished(p) else Changed(own, lost)

    def new_parts(self, p: str) -> DataFrame | Changed | None:
        if p in self._fixed:
            return self._fixed[p]
        if p in self.below:
            return self.below[p].where("NOT _lost").drop("_lost", "_more")
        own, gone = self.old(p), self.D.get(p)
        return self.new(p) if own is None or gone is None or not self._finished(p) else Changed(own, gone, self.A.get(p))

    # Bookkeeping ---------------------------------------------------------------------------------------------------

    def note(self, phase: str, step: int, measure: str, value: int) -> None:
        self.report.work.append((self.stratum, phase, step, measure, value))

    def settled_bag(self, bag: Bag, phase: str, step: int) -> Bag:
        """Settles a bag and notes how many instances it stands for."""
        out, heads, instances = settle_bag(bag)
        self.note(phase, step, "heads", heads)
        self.note(phase, step, "instances", instances)
        return out

    def settled_marked(self, frames: Bag, phase: str, step: int) -> tuple[Bag, dict[str, DataFrame]]:
        """Settles bags whose ``fresh`` rows are the next step's facts; notes as ``settled_bag`` does."""
        out, fresh, heads, instances = settle_marked(frames)
        self.note(phase, step, "heads", heads)
        self.note(phase, step, "instances", instances)
        return out, fresh

    stratum = 0

    def explicit_bag(self, facts: dict[str, DataFrame], s: int) -> Bag:
        return {p: facts[p].withColumn("m", F.lit(1).cast("bigint")) for p in self.strat.preds(s) if p in facts}

    def affected(self, rules: list[Rule], view: View, gone, blocked) -> Bag:
        return bag_affected(self.spark, rules, view, gone, blocked)

    def touches(self, rules: list[Rule]) -> bool:
        """Whether any change below reaches these rules."""
        changed = set(self.D) | set(self.A)
        return any(r.body_preds & changed for r in rules)

    # Deletion ------------------------------------------------------------------------------------------------------

    def lost_below(self, rules: list[Rule], phase: str) -> Bag:
        if not self.touches(rules):
            return {}
        low = self._below
        bag = self.affected(rules, View(self.old, self.old), low(self.lost), low(self.gained))
        return self.settled_bag(bag, phase, 0)

    def gained_below(self, rules: list[Rule], phase: str) -> Bag:
        if not self.touches(rules):
            return {}
        low = self._below
        bag = self.affected(rules, View(self.new_parts, self.new), low(self.gained), low(self.lost))
        return self.settled_bag(bag, phase, 0)

    def _below(self, facts):
        """Changes of lower strata only."""
        return lambda p: facts(p) if self.strat.level.get(p, 0) < self.stratum else None

    def spread(self, delta: dict[str, DataFrame]) -> Bag:
        """Recursive consequences of facts about to go, over what survives."""
        return self.affected(self.rules_left(), View(self.surviving_parts, self.old_or_added), delta.get, lambda p: None)

    def outside(self, overlay: dict[str, DataFrame], bag: Bag) -> Bag:
        """The bag with a column ``fresh``: not in the overlay."""
        return {p: mark(df, overlay.get(p), "_in").withColumn("fresh", ~F.col("_in")).drop("_in") for p, df in bag.items()}

    def not_in(self, overlay: dict[str, DataFrame], bag: dict[str, DataFrame]) -> dict[str, DataFrame]:
        return {p: minus(df.select(*columns_of(df)), overlay.get(p)) for p, df in bag.items()}

    # Insertion -----------------------------------------------------------------------------------------------------

    def insert(self, s: int, again: dict[str, DataFrame], nr: bool, r: bool) -> None:
        """``again``: overdeleted facts that hold; ``nr`` and ``r``: which counters to raise."""
        base = bag_union(self.explicit_bag(self.new_explicit, s), self.gained_below(self.strat.nonrecursive(s), "insert_seed"))
        rec = self.gained_below(self.strat.recursive(s), "insert_seed")
        self._raise(base, rec, nr, r)
        heads = {p: df.select(*columns_of(df)) for p, df in again.items()}
        for bag in (base, rec):
            for p, df in bag.items():
                own = df.select(*columns_of(df))
                heads[p] = heads[p].unionByName(own) if p in heads else own
        delta = self._fresh(heads)
        rules = self.strat.recursive(s)
        step = 0
        while delta:
            step += 1
            self._limit(step)
            self.A.grow(delta)
            if not rules:
                break
            heads = self.affected(self.rules_new(), View(self.new_parts, self.new), delta.get, lambda p: None)
            bag, delta = self.settled_marked({p: self._mark_fresh(p, df) for p, df in heads.items()}, "insert", step)
            self._raise({}, bag, nr, r)

    def _fresh(self, heads: dict[str, DataFrame]) -> dict[str, DataFrame]:
        """Distinct heads that are not in the new view."""
        out = {}
        for p, df in heads.items():
            left = minus(df.distinct(), self.A.get(p))
            own = self.old(p)
            if own is not None:
                d = self.D.get(p)
                left = minus(left, own) if d is None else minus(left, own).unionByName(meet(left, d))
            out[p] = left
        return settle_all(out)[0]

    def _mark_fresh(self, p: str, bag: DataFrame) -> DataFrame:
        """The same as a column."""
        rows = mark(mark(mark(bag, self.A.get(p), "_more"), self.old(p), "_old"), self.D.get(p), "_gone")
        return rows.select(*bag.columns, (~F.col("_more") & (~F.col("_old") | F.col("_gone"))).alias("fresh"))

    def _raise(self, base: Bag, rec: Bag, nr: bool, r: bool) -> None:
        if nr and base:
            self.sign(base, 1, 0)
        if r and rec:
            self.sign(rec, 0, 1)

    def sign(self, bag: Bag, nr: int, r: int) -> None:
        """Notes a change of counters."""
        self.signed = fold_counts([*self.signed, (bag, nr, r)], self.options.checkpoint_every)

    def _limit(self, step: int) -> None:
        if step > self.options.max_rounds:
            raise RoundLimit(f"stratum {self.stratum}")

    # Strategies ----------------------------------------------------------------------------------------------------

    def odr(self, s: int) -> None:
        rules, rec = self.strat.rules(s), self.strat.recursive(s)
        seed = bag_union({p: self.gone[p].withColumn("m", F.lit(1).cast("bigint")) for p in self.strat.preds(s) if p in self.gone}, self.lost_below(rules, "delete_seed"))
        delta = settle_all(self.not_in(self.D, seed))[0]
        self._overdelete(delta, rec, lambda p, marked: marked)
        mine = {p: self.D[p] for p in self.strat.preds(s) if p in self.D}
        self.report.overdeleted |= mine
        again = {}
        for p, d in mine.items():
            held = self.mat.explicit.get(p)
            parts = [] if held is None else [meet(d, minus(held, self.gone.get(p)))]
            for rule in (*self.strat.nonrecursive(s), *self.rules_left()):
                if rule.head.pred == p:
                    rows = match_backward(self.spark, rule, d, View(self.surviving_parts, self.old_or_added), self.options.rederive_plan)
                    if rows is not None:
                        parts.append(head_of(rule, rows))
            if parts:
                again[p] = meet(d, together(*parts))
        again, sizes = settle_all(again)
        self.note("rederive", 0, "facts", sum(sizes.values()))
        self.report.rederived |= again
        self.insert(s, again, False, False)

    def _overdelete(self, delta: dict[str, DataFrame], rec: list[Rule], gate) -> None:
        step = 0
        while delta:
            step += 1
            self._limit(step)
            heads = self.spread(delta) if rec else {}
            self.D.grow(delta)
            bag, delta = self.settled_marked({p: gate(p, df) for p, df in self.outside(self.D, heads).items()}, "overdelete", step)
            self.after_spread(bag)

    def after_spread(self, bag: Bag) -> None:
        if self.strategy == "odr_2c" and bag:
            self.sign(bag, 0, -1)
            self._lost_r.append(bag)
            if len(self._lost_r) > self.options.checkpoint_every:
                self._lost_r = [settle_all(bag_union(*self._lost_r))[0]]

    def nonrecursive_left(self, p: str, facts: DataFrame, lost_nr: Bag) -> DataFrame:
        """The facts whose nonrecursive counter is zero after the losses."""
        return self.with_support(p, facts, lost_nr).where("_nr <= 0").select(*columns_of(facts))

    def with_support(self, p: str, facts: DataFrame, lost_nr: Bag) -> DataFrame:
        """The rows with the nonrecursive counter after the losses, ``_nr``."""
        cols, kept = columns_of(facts), self.counts.get(p)
        if kept is None:
            return facts.withColumn("_nr", F.lit(0).cast("bigint"))
        rows = facts.join(kept.select(*cols, "c_nr"), cols, "left")
        count = F.coalesce("c_nr", F.lit(0))
        if p in lost_nr:
            rows = rows.join(lost_nr[p].select(*cols, F.col("m").alias("_lost")), cols, "left")
            count = count - F.coalesce("_lost", F.lit(0))
        return rows.select(*facts.columns, count.alias("_nr"))

    def _nonrecursive_losses(self, s: int) -> Bag:
        lost = bag_union(self.explicit_bag(self.gone, s), self.lost_below(self.strat.nonrecursive(s), "delete_seed"))
        lost = settle_all(lost)[0]
        if lost:
            self.sign(lost, -1, 0)
        return lost

    def odr_2c(self, s: int) -> None:
        rec = self.strat.recursive(s)
        lost_nr = self._nonrecursive_losses(s)
        lost_r = self.lost_below(rec, "delete_seed")
        self._lost_r = [lost_r] if lost_r else []
        if lost_r:
            self.sign(lost_r, 0, -1)
        gate = lambda p, marked: self.with_support(p, marked, lost_nr).withColumn("fresh", F.col("fresh") & (F.col("_nr") <= 0)).drop("_nr")
        seed = self.not_in(self.D, bag_union(lost_nr, lost_r))
        self._overdelete(settle_all({p: self.nonrecursive_left(p, df, lost_nr) for p, df in seed.items()})[0], rec, gate)
        mine = {p: self.D[p] for p in self.strat.preds(s) if p in self.D}
        self.report.overdeleted |= mine
        self.report.losses |= add_counts([(lost_nr, -1, 0), *((b, 0, -1) for b in self._lost_r)])
        losses = bag_union(*self._lost_r)
        again = {}
        for p, d in mine.items() if rec else ():
            cols = columns_of(d)
            rows = d.join(self.counts[p].select(*cols, "c_r"), cols, "left")
            left = F.coalesce("c_r", F.lit(0))
            if p in losses:
                rows = rows.join(losses[p].select(*cols, F.col("m").alias("_lost")), cols, "left")
                left = left - F.coalesce("_lost", F.lit(0))
            again[p] = rows.where(left > 0).select(*cols)
        again, sizes = settle_all(again)
        self.note("rederive", 0, "facts", sum(sizes.values()))
        self.report.rederived |= again
        self.insert(s, again, True, True)

    def counting(self, s: int) -> None:
        if self.strat.recursive(s):
            raise RuleError("counting refuses recursive rules")
        lost = self._nonrecursive_losses(s)
        gained = settle_all(bag_union(self.explicit_bag(self.new_explicit, s), self.gained_below(self.strat.nonrecursive(s), "insert_seed")))[0]
        if gained:
            self.sign(gained, 1, 0)
        for p in dict.fromkeys((*lost, *gained)):
            touched = together(*[b[p].select(*columns_of(b[p]), (F.col("m") * w).alias("m")) for b, w in ((lost, -1), (gained, 1)) if p in b])
            cols = columns_of(touched)
            kept = self.mat.counters.get(p)
            net = touched.groupBy(*cols).agg(F.sum("m").alias("m"))
            if kept is None:
                net = net.withColumn("c_nr", F.lit(0).cast("bigint"))
            else:
                net = net.join(kept.select(*cols, "c_nr"), cols, "left").withColumn("c_nr", F.coalesce("c_nr", F.lit(0)))
            net, _ = settle(net)
            for overlay, test in ((self.D, "c_nr > 0 AND c_nr + m <= 0"), (self.A, "c_nr <= 0 AND c_nr + m > 0")):
                got, n = settle(net.where(test).select(*cols))
                if n:
                    overlay.grow({p: got})

    def _prove_then_delete(self, s: int, counted: bool) -> None:
        from .prove import Prover

        rec, non = self.strat.recursive(s), self.strat.nonrecursive(s)
        if counted:
            lost_nr = self._nonrecursive_losses(s)
        else:
            lost_nr = bag_union(self.explicit_bag(self.gone, s), self.lost_below(non, "delete_seed"))
        seed = bag_union(lost_nr, self.lost_below(rec, "delete_seed"))
        prover = Prover(self, s, lost_nr if counted else None)
        candidates = settle_all({p: df.select(*columns_of(df)) for p, df in seed.items()})[0]
        step = 0
        while candidates:
            step += 1
            self._limit(step)
            delta = prover.unproved(candidates)
            heads = self.spread(delta) if delta and rec else {}
            self.D.grow(delta)
            _, candidates = self.settled_marked(self.outside(self.D, heads), "delete", step)
        prover.finish()
        self.insert(s, {}, counted, False)

    def pbd(self, s: int) -> None:
        self._prove_then_delete(s, False)

    def pbd_1c(self, s: int) -> None:
        self._prove_then_delete(s, True)

    def by_class(self, s: int, p: str) -> None:
        """Any of the strategies where the recursive rules say that ``p`` is symmetric and transitive.

        Without counters ``odr`` opens each class that loses a nonrecursive instance and ``pbd`` those whose loss is not
        proved by another one; with counters only a fact whose nonrecursive counter falls to zero opens its class. An open
        class falls into the components of the nonrecursive instances that are left in it; then new ones tie classes.
        """
        non, kept, counters = self.strat.nonrecursive(s), self.mat.classes.get(p), COUNTERS[self.strategy]
        lost = settle_all(bag_union(self.explicit_bag(self.gone, s), self.lost_below(non, "delete_seed")))[0].get(p)
        support = kept.support if kept and counters else None
        state = kept.members.select("a", F.col("c").alias("c0"), F.col("c").alias("c1")) if kept else None
        if lost is not None:
            state, support = self._opened(s, p, kept, lost, counters)
        gained = settle_all(bag_union(self.explicit_bag(self.new_explicit, s), self.gained_below(non, "insert_seed")))[0].get(p)
        if gained is not None:
            if counters:
                support = settle(with_gain(support, gained))[0]
            state = merged(state, gained)
        elif lost is None:
            return
        else:
            state = state.withColumnRenamed("c1", "c2")
        state, _ = settle(state)
        classes = Classes(with_sizes(state.where("c2 IS NOT NULL").select("a", F.col("c2").alias("c"))), support)
        self.closed[p] = ClassChange(classes, crossing(state, "c0", "c2"), crossing(state, "c2", "c0"), standing(state))
        for overlay, change in ((self.D, self.closed[p].lost), (self.A, self.closed[p].gained)):
            if change is not None:
                overlay.grow({p: change})

    def _opened(self, s: int, p: str, kept: Classes, lost: DataFrame, counters: int) -> tuple[DataFrame, DataFrame | None]:
        """a, c0, c1 and the nonrecursive counters after the losses; c1 is null where a node is left without a fact."""
        hit, support = lost.select("a0", "a1"), None
        if counters:
            hit = lost.join(kept.support, ["a0", "a1"]).where("c_nr <= m").select("a0", "a1")
            support = settle(without_loss(kept.support, lost))[0]
        elif self.strategy == "pbd":
            hit = minus(hit, self._nonrecursive_instances(s, p, hit))
        nodes = kept.members.select("a", "c")
        open_, n = settle(nodes.join(hit.select(F.col("a0").alias("a")), "a", "left_semi").select("c").distinct())
        if not n:
            return nodes.select("a", F.col("c").alias("c0"), F.col("c").alias("c1")), support
        own = settle(nodes.join(open_, "c", "left_semi").select("a", "c"))[0]
        left = support if counters else self._nonrecursive_instances(s, p)
        now = None
        if left is not None:
            left = left.select("a0", "a1").join(own.select(F.col("a").alias("a0")), "a0", "left_semi")
            now = reached(left if counters else left.distinct())
        self._report_opened(p, own, now, left)
        then = own.withColumn("c1", F.lit(None).cast(own.dtypes[0][1])) if now is None else own.join(now.withColumnRenamed("c", "c1"), "a", "left")
        still = nodes.join(open_, "c", "left_anti").select("a", F.col("c").alias("c0"), F.col("c").alias("c1"))
        return still.unionByName(then.select("a", F.col("c").alias("c0"), "c1")), support

    def _report_opened(self, p: str, own: DataFrame, now: DataFrame | None, left: DataFrame | None) -> None:
        """What ``odr`` and ``odr_2c`` take out of open classes and what of it holds: facts, not yet listed."""
        if self.strategy in ("odr", "odr_2c"):
            base = left if self.strategy == "odr_2c" else None
            self.report.overdeleted[p] = minus(pairs_of(own), base)
            if now is not None:
                self.report.rederived[p] = minus(pairs_of(now), base)

    def _nonrecursive_instances(self, s: int, p: str, wanted: DataFrame | None = None) -> DataFrame | None:
        """Facts (of those wanted) that an assertion or a nonrecursive rule gives over what survives."""
        held, view = self.mat.explicit.get(p), View(self.surviving_parts, self.old_or_added)
        held = None if held is None else minus(held, self.gone.get(p))
        parts = [] if held is None else [held if wanted is None else meet(wanted, held)]
        for rule in self.strat.nonrecursive(s):
            rows = fire(self.spark, rule, view) if wanted is None else match_backward(self.spark, rule, wanted, view, self.options.rederive_plan)
            if rows is not None:
                parts.append(head_of(rule, rows))
        return together(*parts)

    # Whole update --------------------------------------------------------------------------------------------------

    def run(self) -> Materialisation:
        for p in set(self.gone) | set(self.new_explicit):
            if self.strat.level.get(p, 0) == 0:
                if p in self.gone:
                    self.D.grow({p: self.gone[p]})
                if p in self.new_explicit:
                    self.A.grow({p: self.new_explicit[p]})
        for s in range(1, self.strat.count + 1):
            self.stratum = s
            here = [r for r in self.strat.rules(s)]
            if not self.touches(here) and not any(p in self.gone or p in self.new_explicit for p in self.strat.preds(s)):
                continue
            closed = closed_predicate(self.strat, s)
            if closed and (closed in self.mat.classes or closed not in self.mat.facts) and self.strategy != "counting":
                self.by_class(s, closed)
            else:
                self._arrange(s)
                getattr(self, self.strategy)(s)
                self.below, self._rules, self._fixed = {}, {}, {}
        self.stratum = self.strat.count + 1
        return self._commit()

    def _commit(self) -> Materialisation:
        mat = self.mat
        out = Materialisation(self.spark, self.strat, dict(mat.explicit), dict(mat.facts), dict(mat.counters), mat.types, dict(mat.layers), dict(mat.classes))
        for p in set(self.gone) | set(self.new_explicit):
            out.explicit[p] = self._layered(out, "explicit", p, mat.explicit.get(p), self.gone.get(p), self.new_explicit.get(p))
        lost, gained = ({p: df for p in set(self.D) | set(self.A) if (df := side(p)) is not None} for side in (self.lost, self.gained))
        of_classes = [{p: df for p, df in side.items() if p in self.closed} for side in (lost, gained)]
        lost, gained = (settle_all({p: df for p, df in side.items() if p not in self.closed})[0] for side in (lost, gained))
        self.report.deleted, self.report.added = lost | of_classes[0], gained | of_classes[1]
        for p, change in self.closed.items():
            keep_classes(out, p, change.classes, COUNTERS[self.strategy])
        for p in set(lost) | set(gained):
            out.facts[p] = self._layered(out, "facts", p, mat.facts.get(p), lost.get(p), gained.get(p))
        for p, change in settle_all(add_counts(self.signed))[0].items():
            cols, kept = columns_of(change), mat.counters.get(p)
            names = ["c_nr", "c_r"] if COUNTERS[self.strategy] == 2 else ["c_nr"]
            change = change.select(*cols, *names)
            alive = " OR ".join(f"{c} > 0" for c in names)
            if kept is None:
                out.counters[p] = self._layered(out, "counters", p, None, None, change.where(alive))
            else:  # only touched rows are summed anew
                before = settle(meet(self.counts[p], change))[0]
                touched = before.unionByName(change).groupBy(*cols).agg(*[F.sum(c).alias(c) for c in names])
                # A row that changes is taken out and put in again, in two steps.
                without = self._layered(out, "counters", p, kept, before, None)
                out.counters[p] = self._layered(out, "counters", p, without, None, touched.where(alive))
        return out

    def _layered(self, out: Materialisation, what: str, p: str, own: DataFrame | None, lost: DataFrame | None, gained: DataFrame | None) -> DataFrame:
        """The set after the change: its stored base and one settled net change beside it, however many updates there were."""
        if own is None:
            layers = Layers(*settle(gained))
        else:
            layers = out.layers.get((what, p)) or Layers(own, own.count())
            layers = layers.changed(lost, gained, whole=what != "counters")
        out.layers[what, p] = layers
        return layers.now()


def maintain(
    mat: Materialisation,
    removed: dict[str, DataFrame] | None = None,
    added: dict[str, DataFrame] | None = None,
    strategy: str = "odr_2c",
    options: Options = Options(),
) -> UpdateReport:
    """Brings ``mat`` up to date; the result is a new materialisation, ``mat`` stays as it is.

    Changes are bags: repeated rows and rows with a null do not matter. ``auto`` chooses a strategy that keeps the
    counters ``mat`` has.
    """
    if strategy not in (*STRATEGIES, "auto"):
        raise ValueError(f"no strategy {strategy}")
    began = time.time()
    removed, added = normalise(mat.explicit, removed or {}, added or {})
    if strategy == "auto":
        strategy = suited_strategy(mat, removed, added)
    if strategy.startswith("remat"):
        explicit = dict(mat.explicit)
        for p in set(removed) | set(added):
            left = None if p not in explicit else minus(explicit[p], removed.get(p))
            explicit[p] = together(left, added.get(p))
        explicit = settle_all(explicit)[0]
        work: list = []
        out = materialise(mat.spark, mat.strat.program, explicit, COUNTERS[strategy], mat.strat, options.max_rounds, work)
        return UpdateReport(out, time.time() - began, work)
    update = _Update(mat, removed, added, strategy, options)
    try:
        out = update.run()
    finally:
        update.let_go()
    update.report.mat, update.report.seconds = out, time.time() - began
    return update.report


def suited_strategy(mat: Materialisation, removed: dict[str, DataFrame], added: dict[str, DataFrame]) -> str:
    """The choice among the strategies that keep the counters there are, for this change."""
    count = lambda facts: sum(df.count() for df in facts.values())
    share = (count(removed) + count(added)) / max(1, count(mat.explicit))
    kept = max((2 if "c_r" in df.columns else 1 for df in mat.counters.values()), default=0)
    best = choose_strategy(mat.strat, share)
    if best.startswith("remat"):
        return ("remat", "remat_1c", "remat_2c")[kept]
    if COUNTERS[best] == kept:
        return best
    return ("odr" if best == "odr_2c" else "pbd", "pbd_1c", "odr_2c")[kept]


def choose_strategy(strat: Stratification, share: float, break_even: float = 0.3, builtins_in_recursion: bool | None = None) -> str:
    """A strategy for a change of this share of the explicit facts, from the program alone.

    Counting where nothing is recursive, rebuilding beyond the break-even share, two counters where recursive rules
    compute values (going backwards through those is costly), else proving with one counter.
    """
    rec = [r for s in range(1, strat.count + 1) for r in strat.recursive(s)]
    if share > break_even:
        return "remat_2c"
    if not rec:
        return "counting"
    computed = any(r.builtins for r in rec) if builtins_in_recursion is None else builtins_in_recursion
    return "odr_2c" if computed else "pbd_1c"
