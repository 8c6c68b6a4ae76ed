"""Independent SQL for what the workloads derive: recursive queries over the changed inputs, and counts over the result."""

from __future__ import annotations

from .programs import WORKLOADS, Workload

#: For each workload the derived relations in SQL over e_<predicate>, each as a common table expression.
DERIVED = {
    "cooc": {"pair": "SELECT DISTINCT x.a1 AS a0, y.a1 AS a1 FROM e_inCart x JOIN e_inCart y ON x.a0 = y.a0"},
    "path": {"dist": "SELECT a1 AS a0, a2 AS a1 FROM e_hop WHERE a0 = -1 UNION SELECT h.a1, d.a1 + h.a2 FROM d_dist d JOIN e_hop h ON h.a0 = d.a0"},
    "seed": {"reach": "SELECT a0 FROM e_reach UNION SELECT e.a1 FROM d_reach r JOIN e_edge e ON e.a0 = r.a0"},
    "clique": {
        "both": "SELECT a0, a1 FROM e_linked UNION SELECT a0, a1 FROM e_endorsed UNION SELECT a1, a0 FROM e_linked UNION SELECT a1, a0 FROM e_endorsed",
        "related": "SELECT a0, a1 FROM d_both UNION SELECT r.a0, b.a1 FROM d_related r JOIN d_both b ON b.a0 = r.a1",
    },
    "taint": {
        "blocked": "SELECT a0 FROM e_kind WHERE a1 = 'purchase'",
        "tainted": "SELECT a0 FROM e_severe UNION SELECT n.a1 FROM d_tainted t JOIN e_next n ON n.a0 = t.a0 WHERE n.a1 NOT IN (SELECT a0 FROM d_blocked)",
        "dirty": "SELECT DISTINCT a.a1 AS a0 FROM d_tainted t JOIN e_actor a ON a.a0 = t.a0",
        "cleanUser": "SELECT DISTINCT a1 AS a0 FROM e_actor WHERE a1 NOT IN (SELECT a0 FROM d_dirty)",
    },
    "copy": {
        "toxicDoc": "SELECT a0 FROM e_markedToxic UNION SELECT s.a1 FROM d_toxicDoc t JOIN e_sameText s ON s.a0 = t.a0",
        "safeDoc": "SELECT a0 FROM e_judged WHERE a0 NOT IN (SELECT a0 FROM d_toxicDoc)",
        "leaked": "SELECT DISTINCT a1 AS a0 FROM e_passage",
    },
    "host": {"zone": "SELECT a1 AS a0 FROM e_host UNION SELECT substr(a0, strpos(a0, '.') + 1) FROM d_zone WHERE strpos(a0, '.') > 0"},
    "thread": {
        "heard": "SELECT a0, CAST(0 AS BIGINT) AS a1 FROM e_turn WHERE a1 = 0 AND a2 = 'user' UNION SELECT h.a0, r.a2 FROM d_heard h JOIN e_reply r ON r.a0 = h.a0 AND r.a1 = h.a1 "
        "WHERE NOT EXISTS (SELECT 1 FROM e_silent s WHERE s.a0 = h.a0 AND s.a1 = r.a2)"
    },
    "class": {
        "buys": "SELECT DISTINCT o.a0, h.a1 FROM e_ordered o JOIN e_holds h ON h.a0 = o.a1",
        "trades": "SELECT DISTINCT c.a1 AS a0, s.a1 FROM e_custNation c JOIN e_ordered o ON o.a0 = c.a0 JOIN e_shippedBy b ON b.a0 = o.a1 JOIN e_suppNation s ON s.a0 = b.a1",
        "regionTrade": "SELECT DISTINCT x.a1 AS a0, y.a1 FROM d_trades t JOIN e_nationIn x ON x.a0 = t.a0 JOIN e_nationIn y ON y.a0 = t.a1",
        "sub": "SELECT a0, a1 FROM e_subDirect UNION SELECT s.a0, d.a1 FROM d_sub s JOIN e_subDirect d ON d.a0 = s.a1",
        "typed": "SELECT DISTINCT p.a0, s.a1 FROM e_partType p JOIN d_sub s ON s.a0 = p.a1",
        "active": "SELECT DISTINCT o.a0 FROM e_ordered o JOIN e_urgentRecent u ON u.a0 = o.a1",
        "dormant": "SELECT DISTINCT a0 FROM e_custNation WHERE a0 NOT IN (SELECT a0 FROM d_active)",
        "returner": "SELECT DISTINCT o.a0 FROM e_ordered o JOIN e_bigReturn b ON b.a0 = o.a1",
        "loyal": "SELECT a0 FROM d_active WHERE a0 NOT IN (SELECT a0 FROM d_returner)",
        "rushTrades": "SELECT DISTINCT c.a1 AS a0, s.a1 FROM e_custNation c JOIN e_ordered o ON o.a0 = c.a0 JOIN e_rush r ON r.a0 = o.a1 JOIN e_rushShip b ON b.a0 = o.a1 JOIN e_suppNation s ON s.a0 = b.a1",
        "noRush": "SELECT x.a0, y.a0 AS a1 FROM e_nationIn x CROSS JOIN e_nationIn y WHERE NOT EXISTS (SELECT 1 FROM d_rushTrades t WHERE t.a0 = x.a0 AND t.a1 = y.a0)",
        "likes23": "SELECT DISTINCT b.a0 FROM d_buys b JOIN e_partBrand p ON p.a0 = b.a1 WHERE p.a1 = 'Brand#23'",
        "stocksPromo": "SELECT DISTINCT b.a1 AS a0 FROM e_shippedBy b JOIN e_holds h ON h.a0 = b.a0 JOIN e_partType t ON t.a0 = h.a1 WHERE t.a1 = 'PROMO'",
    },
    "mutual": {
        "begun": " UNION ALL ".join(f"SELECT {b} AS a0, a0 AS a1 FROM e_start{b}" for b in range(25)),
        "seen": "SELECT CAST(a0 AS BIGINT) AS a0, a1 FROM d_begun UNION SELECT b.a1, e.a1 FROM d_seen s JOIN e_edge e ON e.a0 = s.a1 JOIN e_brand b ON b.a0 = e.a1 WHERE (b.a1 - s.a0 + 25) % 25 IN (1, 2, 3)",
    },
}

#: Statements that list one row for each instance: nonrecursive support (assertions included), then recursive.
SUPPORT = {
    ("cooc", "pair"): ("SELECT x.a1 AS a0, y.a1 AS a1 FROM e_inCart x JOIN e_inCart y ON x.a0 = y.a0", ""),
    ("path", "dist"): ("SELECT a1 AS a0, a2 AS a1 FROM e_hop WHERE a0 = -1", "SELECT h.a1 AS a0, d.a1 + h.a2 AS a1 FROM d_dist d JOIN e_hop h ON h.a0 = d.a0"),
    ("seed", "reach"): ("SELECT a0 FROM e_reach", "SELECT e.a1 AS a0 FROM d_reach r JOIN e_edge e ON e.a0 = r.a0"),
    ("clique", "related"): (
        "SELECT a0, a1 FROM e_linked UNION ALL SELECT a0, a1 FROM e_endorsed",
        "SELECT a1 AS a0, a0 AS a1 FROM d_related UNION ALL SELECT x.a0, y.a1 FROM d_related x JOIN d_related y ON y.a0 = x.a1",
    ),
    ("taint", "tainted"): (
        "SELECT a0 FROM e_severe",
        "SELECT n.a1 AS a0 FROM d_tainted t JOIN e_next n ON n.a0 = t.a0 WHERE n.a1 NOT IN (SELECT a0 FROM d_blocked)",
    ),
    ("copy", "toxicDoc"): ("SELECT a0 FROM e_markedToxic", "SELECT s.a1 AS a0 FROM d_toxicDoc t JOIN e_sameText s ON s.a0 = t.a0"),
    ("host", "zone"): ("SELECT a1 AS a0 FROM e_host", "SELECT substr(a0, strpos(a0, '.') + 1) AS a0 FROM d_zone WHERE strpos(a0, '.') > 0"),
    ("thread", "heard"): (
        "SELECT a0, CAST(0 AS BIGINT) AS a1 FROM e_turn WHERE a1 = 0 AND a2 = 'user'",
        "SELECT h.a0, r.a2 AS a1 FROM d_heard h JOIN e_reply r ON r.a0 = h.a0 AND r.a1 = h.a1 WHERE NOT EXISTS (SELECT 1 FROM e_silent s WHERE s.a0 = h.a0 AND s.a1 = r.a2)",
    ),
    ("class", "buys"): ("SELECT o.a0, h.a1 FROM e_ordered o JOIN e_holds h ON h.a0 = o.a1", ""),
}

SUPPORT[("mutual", "seen")] = (
    "SELECT CAST(a0 AS BIGINT) AS a0, a1 FROM d_begun",
    "SELECT b.a1 AS a0, e.a1 FROM d_seen s JOIN e_edge e ON e.a0 = s.a1 JOIN e_brand b ON b.a0 = e.a1 WHERE (b.a1 - s.a0 + 25) % 25 IN (1, 2, 3)",
)

#: Columns of a derived relation.
ARITY = {"pair": 2, "dist": 2, "related": 2, "heard": 2, "buys": 2, "trades": 2, "regionTrade": 2, "sub": 2, "typed": 2, "noRush": 2, "seen": 2}


def condition(w: Workload, pred: str, state: str) -> str:
    """What of a predicate's facts is there: ``all``, ``less`` (removed), ``held`` (withheld not yet there), ``mixed`` (after both)."""
    gone, late = w.removed.get(pred, "FALSE"), w.withheld.get(pred, "FALSE")
    return {"all": "TRUE", "less": f"NOT ({gone})", "held": f"NOT ({late})", "mixed": f"NOT (({gone}) AND NOT ({late}))"}[state]


def with_clause(w: Workload, state: str, more: dict[str, str] | None = None) -> str:
    facts = [f"e_{p} AS (SELECT DISTINCT * FROM ({sql}) AS f WHERE {condition(w, p, state)})" for p, sql in w.facts.items()]
    for t in ("nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "pages", "benchmark", "labels", "conversations"):
        facts = [f.replace(f"{{{t}}}", t) for f in facts]
    derived = [f"d_{p} AS ({sql})" for p, sql in {**DERIVED[w.name], **(more or {})}.items()]
    return "WITH RECURSIVE " + ", ".join(facts + derived)


def columns(pred: str) -> str:
    return ", ".join(f"a{i}" for i in range(ARITY.get(pred, 1)))


def facts_sql(name: str, pred: str, state: str) -> str:
    cols = ", ".join(f"CAST(a{i} AS BIGINT) AS a{i}" for i in range(ARITY[pred])) if pred in ("trades", "regionTrade", "noRush") else columns(pred)
    return f"{with_clause(WORKLOADS[name], state)} SELECT {cols} FROM d_{pred}"


def counters_sql(name: str, pred: str, state: str, both: bool = True) -> str:
    nr, r = SUPPORT[(name, pred)]
    cols = columns(pred)
    rows = f"SELECT {cols}, 1 AS nr, 0 AS r FROM ({nr}) AS s" + (f" UNION ALL SELECT {cols}, 0, 1 FROM ({r}) AS s" if r else "")
    counted = f"SELECT {cols}, CAST(sum(nr) AS BIGINT) AS c_nr, CAST(sum(r) AS BIGINT) AS c_r FROM ({rows}) AS u GROUP BY {cols}"
    with_ = with_clause(WORKLOADS[name], state)
    return f"{with_} {counted}" if both else f"{with_} SELECT {cols}, c_nr FROM ({counted}) AS c WHERE c_nr > 0"


def deleted_sql(name: str, pred: str) -> str:
    return f"SELECT * FROM ({facts_sql(name, pred, 'all')}) AS before EXCEPT SELECT * FROM ({facts_sql(name, pred, 'less')}) AS after"


def _gone(name: str, pred: str) -> str:
    return condition(WORKLOADS[name], pred, "less").removeprefix("NOT ")


def overdeleted_sql(name: str, gated: bool) -> str:
    """Reachability from the seeds over surviving inputs; ``gated`` stops at facts with nonrecursive support left."""
    if name == "seed":
        keep = f"NOT EXISTS (SELECT 1 FROM e_reach k WHERE k.a0 = x.a0 AND NOT ({_gone('seed', 'reach').replace('a0', 'k.a0')}))" if gated else "TRUE"
        more = {
            "lost": f"SELECT a0 FROM e_reach WHERE {_gone('seed', 'reach')} UNION SELECT e.a1 FROM d_reach r JOIN (SELECT * FROM e_edge WHERE {_gone('seed', 'edge')}) e ON e.a0 = r.a0",
            "over": f"SELECT x.a0 FROM d_lost x WHERE {keep} UNION SELECT x.a0 FROM (SELECT e.a1 AS a0 FROM d_over o JOIN (SELECT * FROM e_edge WHERE NOT {_gone('seed', 'edge')}) e ON e.a0 = o.a0) x WHERE {keep}",
        }
        return f"{with_clause(WORKLOADS['seed'], 'all', more)} SELECT a0 FROM d_over"
    gone = _gone("path", "hop")
    keep = f"NOT EXISTS (SELECT 1 FROM (SELECT * FROM e_hop WHERE NOT {gone}) k WHERE k.a0 = -1 AND k.a1 = x.a0 AND k.a2 = x.a1)" if gated else "TRUE"
    more = {
        "lost": f"SELECT a1 AS a0, a2 AS a1 FROM e_hop WHERE a0 = -1 AND {gone} UNION SELECT h.a1, d.a1 + h.a2 FROM d_dist d JOIN (SELECT * FROM e_hop WHERE {gone}) h ON h.a0 = d.a0",
        "over": f"SELECT x.a0, x.a1 FROM d_lost x WHERE {keep} UNION SELECT x.a0, x.a1 FROM (SELECT h.a1 AS a0, o.a1 + h.a2 AS a1 FROM d_over o JOIN (SELECT * FROM e_hop WHERE NOT {gone}) h ON h.a0 = o.a0) x WHERE {keep}",
    }
    return f"{with_clause(WORKLOADS['path'], 'all', more)} SELECT a0, a1 FROM d_over"


def rederived_sql(name: str, gated: bool) -> str:
    """Overdeleted facts that one instance over what was not overdeleted still gives, or an assertion."""
    over = overdeleted_sql(name, gated)
    if name == "seed":
        left, gone_r = f"SELECT a0, a1 FROM e_edge WHERE NOT {_gone('seed', 'edge')}", _gone("seed", "reach")
        again = f"SELECT e.a1 AS a0 FROM d_reach r JOIN ({left}) e ON e.a0 = r.a0 WHERE r.a0 NOT IN (SELECT a0 FROM d_over) UNION SELECT a0 FROM e_reach WHERE NOT ({gone_r})"
        return over.replace(" SELECT a0 FROM d_over", f" SELECT a0 FROM d_over WHERE a0 IN ({again})")
    left = f"SELECT * FROM e_hop WHERE NOT {_gone('path', 'hop')}"
    kept = "SELECT d.* FROM d_dist d WHERE NOT EXISTS (SELECT 1 FROM d_over o WHERE o.a0 = d.a0 AND o.a1 = d.a1)"
    again = f"SELECT h.a1 AS a0, d.a1 + h.a2 AS a1 FROM ({kept}) d JOIN ({left}) h ON h.a0 = d.a0 UNION SELECT a1, a2 FROM ({left}) WHERE a0 = -1"
    return over.removesuffix(" SELECT a0, a1 FROM d_over") + f" SELECT a0, a1 FROM d_over INTERSECT SELECT a0, a1 FROM ({again}) AS g"


def instances_sql(gained: bool) -> str:
    """Instances of the pair rule that a deletion takes (or an insertion brings), with all their variables."""
    w = WORKLOADS["cooc"]
    body = "SELECT x.a0 AS o, x.a1 AS y, z.a1 AS z FROM e_inCart x JOIN e_inCart z ON x.a0 = z.a0"
    first, second = ("all", "held") if gained else ("all", "less")
    return f"SELECT * FROM ({with_clause(w, first)} {body}) AS p EXCEPT SELECT * FROM ({with_clause(w, second)} {body}) AS q"
