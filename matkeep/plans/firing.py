"""Rule bodies as DataFrame plans: firing over views, affected instances, bags of consequences, backward matching.

A view gives for each predicate a duplicate-free DataFrame of columns a0, a1, ...; one row of a joined body is one rule
instance, with one column for each variable.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..lang import Assign, Atom, Const, Program, Rule, Var, names_in

#: For a predicate its facts, or None if it has none.
Facts = Callable[[str], DataFrame | None]
Bag = dict[str, DataFrame]


@dataclass(frozen=True)
class Changed:
    """The facts ``(base without less) and more`` in parts, ``more`` apart from the rest.

    A join with few rows meets the base as it is and looks for ``less`` among what came out, so that the base is not
    gone through once more for the difference.
    """

    base: DataFrame
    less: DataFrame
    more: DataFrame | None = None

    def now(self) -> DataFrame:
        return together(minus(self.base, self.less), self.more)

    def met_by(self, rows: DataFrame, atom: Atom, shared: list[str]) -> DataFrame:
        """The join of the rows with what matches the atom."""
        base, less = matched(atom, self.base), matched(atom, self.less)
        if self.more is None:
            return rows.join(base, shared).join(less, less.columns, "left_anti")
        both = base.withColumn("_late", F.lit(False)).unionByName(matched(atom, self.more).withColumn("_late", F.lit(True)))
        return rows.join(both, shared).join(less.withColumn("_late", F.lit(False)), [*less.columns, "_late"], "left_anti").drop("_late")


@dataclass(frozen=True)
class View:
    """Facts that positive atoms match, and facts that negated atoms must miss. The former may be ``Changed`` ones."""

    positive: Callable[[str], DataFrame | Changed | None]
    negative: Facts


def columns_of(df: DataFrame) -> list[str]:
    return [c for c in df.columns if c[0] == "a" and c[1:].isdigit()]


def literal(value) -> Column:
    return F.lit(value).cast("bigint") if isinstance(value, int) and not isinstance(value, bool) else F.lit(value)


def matched(atom: Atom, facts: DataFrame) -> DataFrame:
    """Facts that match the atom, one column for each variable: filters, projection, renaming."""
    at: dict[str, int] = {}
    test: Column | None = None
    for i, arg in enumerate(atom.args):
        if isinstance(arg, Const):
            cond = F.col(f"a{i}") == literal(arg.value)
        elif arg.name in at:
            cond = F.col(f"a{i}") == F.col(f"a{at[arg.name]}")
        else:
            at[arg.name] = i
            continue
        test = cond if test is None else test & cond
    chosen = facts if test is None else facts.where(test)
    return chosen.select(*[F.col(f"a{i}").alias(v) for v, i in at.items()])


def _bind(rows: DataFrame, waiting: list, bound: set[str]) -> DataFrame:
    """Applies the built-ins whose inputs are bound, each as soon as it can be."""
    again = True
    while again:
        again = False
        for b in list(waiting):
            if not names_in(b.expr) <= bound:
                continue
            value = F.expr(b.expr)
            if isinstance(b, Assign) and b.var not in bound:
                rows = rows.withColumn(b.var, value)
                if dict(rows.dtypes)[b.var] in ("int", "smallint", "tinyint"):
                    rows = rows.withColumn(b.var, F.col(b.var).cast("bigint"))
                rows = rows.where(F.col(b.var).isNotNull())
                bound.add(b.var)
            else:
                rows = rows.where(F.col(b.var) == value if isinstance(b, Assign) else value)
            waiting.remove(b)
            again = True
    return rows


def order_atoms(rule: Rule, first: int | None, bound: Iterable[str] = ()) -> list[int]:
    """Places of positive atoms: the changed one first, then always one that shares most variables with what is bound."""
    left = list(range(len(rule.positive)))
    bound = set(bound)
    out: list[int] = []

    def shared(i: int) -> tuple:
        atom = rule.positive[i]
        const = sum(isinstance(a, Const) for a in atom.args)
        hits = len(bound & set(atom.vars))
        return (-hits, -const, i)

    while left:
        pick = first if first in left and not out else min(left, key=shared)
        out.append(pick)
        left.remove(pick)
        bound |= set(rule.positive[pick].vars)
    return out


def keys_below(rules: Iterable[Rule], below: Callable[[str], bool]) -> dict[str, list[str]]:
    """For predicates below the rules' stratum the columns by which a step's new facts, or what comes of them, meet them."""
    out: dict[str, list[str]] = {}
    for rule in rules:
        for first, atom in enumerate(rule.positive):
            if below(atom.pred):
                continue
            bound: set[str] = set()
            for i in order_atoms(rule, first):
                at = rule.positive[i]
                cols = [f"a{k}" for k, arg in enumerate(at.args) if isinstance(arg, Var) and arg.name in bound]
                if cols and below(at.pred):
                    out.setdefault(at.pred, cols)
                bound |= set(at.vars)
    return out


def joined_body(
    spark: SparkSession,
    rule: Rule,
    atom_facts: Callable[[int], DataFrame | Changed | None],
    negated: Callable[[int, DataFrame], DataFrame],
    first: int | None = None,
    start: DataFrame | None = None,
    watched: Callable[[DataFrame], DataFrame] | None = None,
) -> DataFrame | None:
    """Instances of a rule: ``atom_facts`` gives the facts for each positive atom, ``negated`` applies a negated one.

    ``start`` has rows with some variables bound already; ``watched`` is put around the rows after each atom. None if an
    atom has no facts.
    """
    rows = start
    bound = set(start.columns) if start is not None else set()
    waiting = list(rule.builtins)
    for i in order_atoms(rule, first, bound):
        facts = atom_facts(i)
        if facts is None:
            return None
        names = list(dict.fromkeys(rule.positive[i].vars))
        shared = [c for c in names if c in bound]
        if isinstance(facts, Changed) and rows is not None and shared:
            rows = facts.met_by(rows, rule.positive[i], shared)
        else:
            own = matched(rule.positive[i], facts.now() if isinstance(facts, Changed) else facts)
            rows = own if rows is None else rows.join(own, shared) if shared else rows.crossJoin(own)
        bound |= set(names)
        rows = _bind(watched(rows) if watched else rows, waiting, bound)
    if rows is None:
        rows = _bind(spark.range(1).select(), waiting, bound)
    for j in range(len(rule.negative)):
        rows = negated(j, rows)
    return rows


def missing_from(atom: Atom, rows: DataFrame, facts: DataFrame | None, how: str = "left_anti") -> DataFrame:
    """Rows whose instance of the atom is not (``left_anti``) or is (``left_semi``) among the facts."""
    if facts is None:
        return rows if how == "left_anti" else rows.where(F.lit(False))
    own = matched(atom, facts)
    if not own.columns:  # no variable: the fact is there or not
        own = own.limit(1).select(F.lit(1).alias("_there"))
        return rows.withColumn("_there", F.lit(1)).join(own, "_there", how).drop("_there")
    return rows.join(own, own.columns, how)


def fire(spark: SparkSession, rule: Rule, view: View) -> DataFrame | None:
    """All instances of the rule over the view."""
    return joined_body(
        spark, rule, lambda i: view.positive(rule.positive[i].pred), lambda j, rows: missing_from(rule.negative[j], rows, view.negative(rule.negative[j].pred))
    )


def minus(a: DataFrame, b: DataFrame | None) -> DataFrame:
    cols = columns_of(a)
    if b is None:
        return a
    return a.join(b.select(*cols), cols, "left_anti") if cols else a.where(F.lit(b.isEmpty()))


def meet(a: DataFrame, b: DataFrame | None) -> DataFrame:
    cols = columns_of(a)
    if b is None:
        return a.where(F.lit(False))
    return a.join(b.select(*cols), cols, "left_semi") if cols else a.where(F.lit(not b.isEmpty()))


def together(*dfs: DataFrame | None) -> DataFrame | None:
    """Union of fact sets that share no fact."""
    found = [d for d in dfs if d is not None]
    return reduce(lambda x, y: x.unionByName(y), found) if found else None


def _without(facts: DataFrame | Changed, gone: DataFrame | None) -> DataFrame | Changed:
    if gone is None:
        return facts
    return minus(facts.now() if isinstance(facts, Changed) else facts, gone)


def fire_affected(spark: SparkSession, rule: Rule, view: View, gone: Facts, blocked: Facts) -> DataFrame | None:
    """Instances over the view with a positive atom in ``gone`` or a negated atom in ``blocked``; each once.

    There is one plan for each place that can be the first affected one. ``gone`` is within the positive view and
    ``blocked`` apart from the negative one.
    """
    plans = []
    pos, neg = rule.positive, rule.negative
    for i, atom in enumerate(pos):
        if gone(atom.pred) is None:
            continue

        def facts(k: int, i: int = i) -> DataFrame | Changed | None:
            own = view.positive(pos[k].pred)
            if k == i:
                return gone(pos[k].pred)
            return _without(own, gone(pos[k].pred)) if k < i and own is not None else own

        rest = lambda j, rows: missing_from(neg[j], rows, view.negative(neg[j].pred))
        plans.append(joined_body(spark, rule, facts, rest, first=i))
    for j, atom in enumerate(neg):
        if blocked(atom.pred) is None:
            continue

        def facts_below(k: int) -> DataFrame | Changed | None:
            own = view.positive(pos[k].pred)
            return _without(own, gone(pos[k].pred)) if own is not None else None

        def negated(k: int, rows: DataFrame, j: int = j) -> DataFrame:
            if k == j:
                return missing_from(neg[k], rows, blocked(neg[k].pred), "left_semi")
            rows = missing_from(neg[k], rows, view.negative(neg[k].pred))
            return missing_from(neg[k], rows, blocked(neg[k].pred)) if k < j else rows

        plans.append(joined_body(spark, rule, facts_below, negated))
    plans = [p for p in plans if p is not None]
    if not plans:
        return None
    names = sorted(plans[0].columns)
    return reduce(lambda x, y: x.unionByName(y), [p.select(*names) for p in plans])


def head_of(rule: Rule, rows: DataFrame) -> DataFrame:
    return rows.select(*[(literal(a.value) if isinstance(a, Const) else F.col(a.name)).alias(f"a{i}") for i, a in enumerate(rule.head.args)])


def bag_of(instances: Iterable[tuple[Rule, DataFrame | None]]) -> Bag:
    """For each head predicate the consequences with their number of instances, ``m``; counted before the shuffle."""
    by_pred: dict[str, list[DataFrame]] = {}
    for rule, rows in instances:
        if rows is not None:
            by_pred.setdefault(rule.head.pred, []).append(head_of(rule, rows))
    return {p: counted(together(*dfs)) for p, dfs in by_pred.items()}


def counted(heads: DataFrame) -> DataFrame:
    return heads.groupBy(*columns_of(heads)).agg(F.count(F.lit(1)).alias("m"))


def bag_union(*bags: Bag) -> Bag:
    """Additive union."""
    out: Bag = {}
    for p in dict.fromkeys(p for b in bags for p in b):
        parts = [b[p] for b in bags if p in b]
        out[p] = parts[0] if len(parts) == 1 else together(*parts).groupBy(*columns_of(parts[0])).agg(F.sum("m").alias("m"))
    return out


def bag_all(spark: SparkSession, rules: Iterable[Rule], view: View) -> Bag:
    return bag_of((r, fire(spark, r, view)) for r in rules)


def bag_affected(spark: SparkSession, rules: Iterable[Rule], view: View, gone: Facts, blocked: Facts) -> Bag:
    return bag_of((r, fire_affected(spark, r, view, gone, blocked)) for r in rules)


#: Ways of matching backward.
PLANS = ("head_first", "body_first", "auto")


def match_backward(spark: SparkSession, rule: Rule, facts: DataFrame, view: View, plan: str = "head_first", watched=None) -> DataFrame | None:
    """Instances over the view whose head is among ``facts``.

    ``head_first`` binds the head's variables from the facts and then joins the body; ``body_first`` evaluates the body
    and keeps instances with such a head. ``auto`` goes head first where the head binds some body atom wholly, so that
    a fact has one match there at most, and body first elsewhere: the matches of a half-bound atom may be as many as
    the wanted facts times the facts of a hub, the body's instances are no more than building took.
    """
    if plan not in PLANS:
        raise ValueError(f"no backward plan {plan}")
    if plan == "auto":
        bound = set(rule.head.vars) - {b.var for b in rule.builtins if isinstance(b, Assign)}
        plan = "head_first" if any(set(a.vars) <= bound for a in rule.positive) else "body_first"
    wanted = matched(rule.head, facts)
    body_vars = {v for a in rule.positive for v in a.vars}
    assigned = {b.var for b in rule.builtins if isinstance(b, Assign)} - body_vars
    start = wanted.select(*[c for c in wanted.columns if c not in assigned]).distinct() if assigned else wanted
    usable = plan == "head_first" and bool(start.columns) and all(isinstance(a, Var) for a in rule.head.args)
    rows = joined_body(
        spark,
        rule,
        lambda i: view.positive(rule.positive[i].pred),
        lambda j, r: missing_from(rule.negative[j], r, view.negative(rule.negative[j].pred)),
        start=start if usable else None,
        watched=watched,
    )
    if rows is None or (usable and not assigned):
        return rows
    return rows.join(wanted, wanted.columns, "left_semi") if wanted.columns else (rows if not facts.isEmpty() else None)


def observed_matches(spark: SparkSession, rule: Rule, facts: DataFrame, view: View, plan: str) -> tuple[int, int]:
    """Rows that the joins of backward matching make, atom by atom, and the instances confirmed; counted as the plan runs."""
    seen: list[Observation] = []

    def watched(rows: DataFrame) -> DataFrame:
        seen.append(Observation())
        return rows.observe(seen[-1], F.count(F.lit(1)).alias("n"))

    rows = match_backward(spark, rule, facts, view, plan, watched)
    if rows is None:
        return 0, 0
    last = Observation()
    rows.observe(last, F.count(F.lit(1)).alias("n")).write.format("noop").mode("overwrite").save()
    return sum(o.get.get("n", 0) for o in seen), last.get["n"]


def dependencies(program: Program) -> dict[str, set[str]]:
    return {p: {a.pred for r in program.rules if r.head.pred == p for a in r.atoms} for p in program.preds}
