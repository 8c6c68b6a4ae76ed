"""What is the same in every step of a loop, joined once: the finished part of a recursive rule's body as one relation."""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lang import Atom, Rule, Var
from .firing import Changed, View, matched, missing_from

#: A join is left to the steps if it has more rows than this many times the larger of its sides.
GROWTH = 4


def foldable(rule: Rule, below: Callable[[str], bool]) -> bool:
    """Two finished atoms or more, one of them positive."""
    low = sum(below(a.pred) for a in rule.positive)
    return low > 0 and low + len(rule.negative) > 1


def _grows(rows: DataFrame, own: DataFrame, shared: list[str]) -> bool:
    """Whether the join has far more rows than its sides; from the counts of each key, not by joining rows."""
    n, m = (df.groupBy(*shared).agg(F.count(F.lit(1)).alias(c)) for df, c in ((rows, "_n"), (own, "_m")))
    both = n.join(m, shared, "full_outer").select(F.col("_n").cast("double"), F.col("_m").cast("double"))
    made, left, right = both.agg(F.sum(F.col("_n") * F.col("_m")), F.sum("_n"), F.sum("_m")).first()
    return (made or 0) > GROWTH * max(left or 0, right or 0)


def folded(rules: Iterable[Rule], below: Callable[[str], bool], view: View, name: str) -> tuple[list[Rule], dict[str, DataFrame]]:
    """The rules with finished atoms put together as one atom over a relation of its own, and these relations, unsettled.

    A row of such a relation has all variables of the atoms it stands for, so a rule has the same instances as before.
    """
    out, frames = [], {}
    for rule in rules:
        low = [a for a in rule.positive if below(a.pred)]
        facts = {a.pred: view.positive(a.pred) for a in low} if foldable(rule, below) else {}
        if not facts or any(df is None for df in facts.values()):
            out.append(rule)
            continue
        own = lambda a: matched(a, df.now() if isinstance(df := facts[a.pred], Changed) else df)  # noqa: E731, B023
        rows, done, rest = own(low[0]), [low[0]], low[1:]
        while linked := [a for a in rest if set(a.vars) & set(rows.columns)]:
            rest.remove(atom := linked[0])
            shared = [c for c in dict.fromkeys(atom.vars) if c in rows.columns]
            if not _grows(rows, other := own(atom), shared):
                rows = rows.join(other, shared)
                done.append(atom)
        for atom in rule.negative:
            if set(atom.vars) <= set(rows.columns):
                rows = missing_from(atom, rows, view.negative(atom.pred))
                done.append(atom)
        if len(done) < 2:
            out.append(rule)
            continue
        names, pred = rows.columns, f"{name}{len(frames)}"
        frames[pred] = rows.select(*[F.col(c).alias(f"a{i}") for i, c in enumerate(names)])
        out.append(Rule(rule.head, (*[a for a in rule.atoms if a not in done], Atom(pred, tuple(map(Var, names)))), rule.builtins))
    return out, frames
