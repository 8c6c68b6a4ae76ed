"""The proof search of the prove-before-delete strategies, for all candidates of a round together.

Facts are *checked* when a proof of them is wanted, *expanded* when their recursive instances have been followed
backwards, *proved* when they surely hold, *delayed* when they would be proved the moment someone checks them. Checked and
expanded are kept apart: the search may stop before every checked fact is expanded, and goes on from there next time.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lang import Const
from .plans.firing import Bag, View, bag_affected, columns_of, head_of, literal, match_backward, meet, minus, together
from .store import Growing, mark, settle, settle_all, settle_flagged

Sets = dict[str, DataFrame]


class Prover:
    def __init__(self, update, stratum: int, lost_nr: Bag | None):
        self.u, self.s, self.lost_nr = update, stratum, lost_nr
        self.non = update.strat.nonrecursive(stratum)
        self.checked, self.expanded, self.proved, self.delayed = Growing(), Growing(), Growing(), Growing()
        #: Checked facts that are neither expanded nor proved.
        self.pending: Sets = {}
        self.waves = 0

    def _without(self, facts: Sets, *sets: Sets) -> Sets:
        """Facts in none of the sets; where no set has facts of a predicate there is nothing to run."""
        known = {p: [other[p] for other in sets if p in other] for p in facts}
        same = {p: df for p, df in facts.items() if not known[p]}
        return same | settle_all({p: reduce(minus, known[p], df) for p, df in facts.items() if known[p]})[0]

    def unproved(self, candidates: Sets) -> Sets:
        """The candidates that do not hold, or not surely, without the facts deleted so far. They are settled."""
        front, waiting = self._ask(candidates)
        while True:
            self._pend(waiting)
            # One step forwards and one backwards at a time: what is proved in one is followed with what the next proves, so
            # the steps are about as many as both ways are long, not a way forwards for each step backwards.
            if front:
                front = self._follow(front)
                if self.u.options.early_stop and not (left := self._without(candidates, self.proved, front)):
                    self.proved.grow(front)  # no candidate is left to ask for, so nothing more is followed
                    return left
                self.pending = self._without(self.pending, self.proved, front)
            if not self.pending:
                self._follow_all(front)
                return self._without(candidates, self.proved)
            self.waves += 1
            wanted, self.pending = self.pending, {}
            self.expanded.grow(wanted)
            based, waiting = self._ask(self._bodies(wanted))
            front = self._apart(front, based)

    def _apart(self, front: Sets, based: Sets) -> Sets:
        """Both together: what is proved was checked before the step, what is based only in it."""
        return {p: together(front.get(p), based.get(p)) for p in dict.fromkeys((*front, *based))}

    def _follow_all(self, front: Sets) -> None:
        while front:
            front = self._follow(front)

    def _pend(self, more: Sets) -> None:
        """Checked facts, neither expanded nor proved, that are to be expanded next."""
        self.pending = self.pending | {p: together(self.pending.get(p), df) for p, df in more.items()}

    def _ask(self, facts: Sets) -> tuple[Sets, Sets]:
        """Checks the facts not checked before: those that need no recursive rule (delayed, explicit, or nonrecursively
        supported), and the others. With a counter one job for each predicate finds both."""
        if self.lost_nr is None:
            fresh = self._without(facts, self.checked)
            self.checked.grow(fresh)
            based = self._based(fresh) if fresh else {}
            return based, self._without(fresh, based)
        based, waiting = {}, {}
        for p, df in facts.items():
            cols = columns_of(df)
            rows = mark(self.u.with_support(p, minus(df, self.checked.get(p)), self.lost_nr), self.delayed.get(p), "_later")
            kept, n, yes, _ = settle_flagged(rows.select(*cols, (F.col("_later") | (F.col("_nr") > 0)).alias("held")), "held")
            if n:
                self.checked.grow({p: kept.select(*cols)})
            if yes:
                based[p] = kept.where("held").select(*cols)
            if yes < n:
                waiting[p] = kept.where("NOT held").select(*cols)
        return based, waiting

    def _based(self, fresh: Sets) -> Sets:
        """Newly checked facts that need no recursive rule, found without a counter."""
        out: Sets = {}
        for p, df in fresh.items():
            parts = [meet(df, self.delayed[p])] if p in self.delayed else []
            held = self.u.mat.explicit.get(p)
            if held is not None:
                parts.append(meet(df, minus(held, self.u.gone.get(p))))
            for rule in self.non:
                if rule.head.pred == p:
                    rows = match_backward(self.u.spark, rule, df, View(self.u.surviving_parts, self.u.old_or_added), self.u.options.rederive_plan)
                    if rows is not None:
                        parts.append(meet(df, head_of(rule, rows)))
            if parts:
                out[p] = together(*parts).distinct()
        return settle_all(out)[0]

    def _follow(self, new: Sets) -> Sets:
        """Takes the facts as proved; their consequences that are proved by that, over proved facts here and surviving
        facts below."""
        level = self.u.strat.level
        pos = lambda p: self.proved.get(p) if level.get(p, 0) == self.s else self.u.surviving_parts(p)
        self.proved.grow(new)
        bag = bag_affected(self.u.spark, self.u.rules_left(), View(pos, self.u.old_or_added), new.get, lambda p: None)
        found, later = {}, {}
        for p, df in bag.items():
            # Only old facts that still stand matter: what insertion adds comes later.
            heads = minus(minus(meet(df.drop("m"), self.u.surviving(p)), self.proved.get(p)), self.delayed.get(p))
            cols = columns_of(heads)
            marked, n, asked, _ = settle_flagged(mark(heads, self.checked.get(p), "asked"), "asked")
            self.u.note("prove", self.waves, "heads", n)
            if asked:
                found[p] = marked.where("asked").select(*cols)
            if asked < n:
                later[p] = marked.where("NOT asked").select(*cols)
        self.delayed.grow(later)
        return found

    def _bodies(self, facts: Sets) -> Sets:
        """Facts of this stratum in the bodies of recursive instances of these facts, over what survives."""
        found: Sets = {}
        for rule in self.u.rules_left():
            wanted = facts.get(rule.head.pred)
            if wanted is None:
                continue
            rows = match_backward(self.u.spark, rule, wanted, View(self.u.surviving_parts, self.u.old_or_added), self.u.options.rederive_plan)
            if rows is None:
                continue
            own = [atom for atom in rule.positive if self.u.strat.level.get(atom.pred, 0) == self.s]
            if len(own) > 1 or self.u.options.collect_work:  # else the rows are used once
                rows, n = settle(rows)
                self.u.note("backward", self.waves, "instances", n)
                if not n:
                    continue
            for atom in own:
                body = rows.select(*[(literal(a.value) if isinstance(a, Const) else F.col(a.name)).alias(f"a{i}") for i, a in enumerate(atom.args)])
                found[atom.pred] = together(found.get(atom.pred), body)
        return {p: df.distinct() for p, df in found.items()}

    def finish(self) -> None:
        for name in ("checked", "expanded", "proved", "delayed"):
            if self.u.options.collect_work:
                sets = getattr(self, name)
                self.u.note("prove", self.waves, name, sum(df.count() for df in sets.values()))
        self.u.note("prove", self.waves, "waves", self.waves)
