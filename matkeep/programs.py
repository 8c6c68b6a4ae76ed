"""Workloads on the given tables: rules, how facts come out of the tables, and changes to apply.

Fact extraction is SQL text so that other engines can run it too; each statement yields columns a0, a1, ...
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from .lang import Program, parse
from .materialise import as_facts
from .plans.batching import Batched, batch
from .store import settle_all

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@dataclass(frozen=True)
class Workload:
    """``removed`` and ``withheld`` are conditions on a predicate's columns: what a deletion takes, what an insertion brings."""

    name: str
    rules: str
    facts: dict[str, str]
    outputs: tuple[str, ...]
    removed: dict[str, str] = field(default_factory=dict)
    withheld: dict[str, str] = field(default_factory=dict)
    families: dict[str, list[str]] = field(default_factory=dict)

    def program(self, output: str | None = None) -> Program:
        program = parse(self.rules, set(self.facts))
        return relevant(program, output) if output else program

    def batched(self) -> Batched:
        return batch(self.program(), self.families)

    def explicit(self, spark: SparkSession, sf_dir: str, preds: set[str] | None = None, keep: dict[str, str] | None = None) -> dict[str, DataFrame]:
        """Settled facts; ``keep`` has a condition a predicate's facts must meet."""
        out = {}
        for p, sql in self.facts.items():
            if preds is None or p in preds:
                used = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES if f"{{{t}}}" in sql}
                df = as_facts(spark.sql(sql, **used))
                out[p] = df.where(keep[p]) if keep and p in keep else df
        return settle_all(out)[0]


def relevant(program: Program, output: str) -> Program:
    """The rules the output depends on."""
    need, more = {output}, True
    while more:
        reach = need | {a.pred for r in program.rules if r.head.pred in need for a in r.atoms}
        more, need = reach != need, reach
    return Program(tuple(r for r in program.rules if r.head.pred in need))


_LINES = "(SELECT DISTINCT l_orderkey, l_linenumber, l_partkey, l_quantity FROM {lineitem})"
_NEXT_PART = (
    f"SELECT DISTINCT x.l_partkey AS a0, y.l_partkey AS a1 FROM {_LINES} x JOIN {_LINES} y "
    "ON x.l_orderkey = y.l_orderkey AND y.l_linenumber = x.l_linenumber + 1"
)

COOC = Workload(
    "cooc",
    "pair(y, z) <- inCart(o, y), inCart(o, z).",
    {
        "inCart": "SELECT l_orderkey AS a0, l_partkey AS a1 FROM {lineitem} UNION "
        "SELECT l_orderkey, CAST(CASE l_returnflag WHEN 'A' THEN -1 WHEN 'N' THEN -2 ELSE -3 END AS BIGINT) FROM {lineitem}"
    },
    ("pair",),
    {"inCart": "a0 % 11 = 3 AND a1 >= 0"},
    {"inCart": "a0 % 13 = 5"},
)
PATH = Workload(
    "path",
    "dist(t, n) <- hop(-1, t, n). dist(t, n) <- dist(s, p), hop(s, t, q), n := p + q.",
    {
        "hop": "SELECT DISTINCT x.l_partkey * 8 + x.l_linenumber AS a0, y.l_partkey * 8 + y.l_linenumber AS a1, 1 + CAST(x.l_quantity AS BIGINT) % 5 AS a2 "
        f"FROM {_LINES} x JOIN {_LINES} y ON x.l_orderkey = y.l_orderkey AND y.l_linenumber > x.l_linenumber "
        "UNION SELECT -1, l_partkey * 8 + 1, 1 FROM {lineitem} WHERE l_linenumber = 1"
    },
    ("dist",),
    {"hop": "(a0 * 31 + a1 * 17 + a2) % 50 = 7"},
    {"hop": "(a0 * 31 + a1 * 17 + a2) % 50 = 11"},
)
SEED = Workload(
    "seed",
    "reach(q) <- reach(p), edge(p, q).",
    {"edge": _NEXT_PART, "reach": "SELECT p_partkey AS a0 FROM {part} WHERE p_size = 1"},
    ("reach",),
    {"edge": "(a0 * 31 + a1) % 7 < 6", "reach": "a0 % 3 = 0"},
    {"edge": "(a0 * 31 + a1) % 7 > 0", "reach": "a0 % 5 = 1"},
)
CLIQUE = Workload(
    "clique",
    "related(x, y) <- linked(x, y). related(x, y) <- endorsed(x, y). related(x, y) <- related(y, x). related(x, z) <- related(x, y), related(y, z).",
    {
        "linked": "SELECT a0, a1 FROM (SELECT s_suppkey AS a0, lead(s_suppkey) OVER (PARTITION BY s_nationkey ORDER BY s_suppkey) AS a1 FROM {supplier}) t WHERE a1 IS NOT NULL",
        "endorsed": "SELECT x.s_suppkey AS a0, y.s_suppkey AS a1 FROM {supplier} x JOIN {supplier} y ON x.s_nationkey = y.s_nationkey AND x.s_suppkey < y.s_suppkey "
        "WHERE x.s_acctbal > 5000 AND y.s_acctbal > 5000",
    },
    ("related",),
    {"linked": "a0 % 5 = 0"},
    {"linked": "a0 % 7 = 1"},
)
_SUCC = "SELECT a0, a1 FROM (SELECT event_id AS a0, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS a1 FROM {events}) t WHERE a1 IS NOT NULL"
TAINT = Workload(
    "taint",
    "blocked(f) <- kind(f, 'purchase'). tainted(e) <- severe(e). tainted(f) <- tainted(e), next(e, f), not blocked(f). "
    "dirty(u) <- tainted(e), actor(e, u). cleanUser(u) <- actor(e, u), not dirty(u).",
    {
        "next": _SUCC,
        "kind": "SELECT event_id AS a0, event_type AS a1 FROM {events}",
        "actor": "SELECT event_id AS a0, user_id AS a1 FROM {events}",
        "severe": "SELECT event_id AS a0 FROM {events} WHERE event_type = 'error' AND value > 150",
    },
    ("tainted", "cleanUser"),
    {"severe": "a0 % 3 = 1", "kind": "a0 % 17 = 3"},
    {"severe": "a0 % 4 = 2", "kind": "a0 % 19 = 5"},
)
COPY = Workload(
    "copy",
    "toxicDoc(d) <- markedToxic(d). toxicDoc(e) <- toxicDoc(d), sameText(d, e). safeDoc(d) <- judged(d), not toxicDoc(d). leaked(d) <- passage(b, d).",
    {
        "sameText": "SELECT x.doc_id AS a0, y.doc_id AS a1 FROM (SELECT doc_id, md5(text) AS h FROM {documents}) x JOIN (SELECT doc_id, md5(text) AS h FROM {documents}) y ON x.h = y.h AND x.doc_id <> y.doc_id",
        "markedToxic": "SELECT doc_id AS a0 FROM {labels} WHERE toxic = 1",
        "judged": "SELECT doc_id AS a0 FROM {labels}",
        "passage": "SELECT b.item_id AS a0, d.doc_id AS a1 FROM {benchmark} b JOIN {documents} d ON contains(d.text, b.text)",
    },
    ("toxicDoc", "safeDoc", "leaked"),
    {"markedToxic": "a0 % 3 = 0", "passage": "a1 % 4 = 1"},
    {"markedToxic": "a0 % 3 = 1"},
)
HOST = Workload(
    "host",
    "zone(h) <- host(p, h). zone(g) <- zone(h), locate('.', h) > 0, g := substring(h, locate('.', h) + 1).",
    {"host": "SELECT page_id AS a0, regexp_extract(url, '://([^/?#]+)', 1) AS a1 FROM {pages}"},
    ("zone",),
    {"host": "a0 % 4 <> 1"},
    {"host": "a0 % 4 = 2"},
)
THREAD = Workload(
    "thread",
    "heard(c, 0) <- turn(c, 0, 'user'). heard(c, u) <- heard(c, t), reply(c, t, u), not silent(c, u).",
    {
        "reply": "SELECT x.conv_id AS a0, x.turn AS a1, y.turn AS a2 FROM {conversations} x JOIN {conversations} y ON x.conv_id = y.conv_id AND y.turn = x.turn + 1",
        "turn": "SELECT conv_id AS a0, turn AS a1, role AS a2 FROM {conversations}",
        "silent": "SELECT conv_id AS a0, turn AS a1 FROM {conversations} WHERE role = 'system'",
    },
    ("heard",),
    {"reply": "a0 % 6 = 1 AND a1 = 2", "turn": "a0 % 7 = 3"},
    {"reply": "a0 % 5 = 1"},
)

#: The part types of the given tables.
PART_TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")
_BRAND_GROUPS = "SELECT DISTINCT p_type AS a0, substr(p_brand, 1, 7) AS a1 FROM {part} UNION SELECT DISTINCT substr(p_brand, 1, 7), 'any' FROM {part}"
CLASS = Workload(
    "class",
    """
    buys(c, p) <- ordered(c, o), holds(o, p).
    trades(n, m) <- custNation(c, n), ordered(c, o), shippedBy(o, s), suppNation(s, m).
    regionTrade(r, q) <- trades(n, m), nationIn(n, r), nationIn(m, q).
    sub(a, b) <- subDirect(a, b). sub(a, c) <- sub(a, b), subDirect(b, c).
    typed(p, b) <- partType(p, a), sub(a, b).
    active(c) <- ordered(c, o), urgentRecent(o).
    dormant(c) <- custNation(c, n), not active(c).
    returner(c) <- ordered(c, o), bigReturn(o).
    loyal(c) <- active(c), not returner(c).
    rushTrades(n, m) <- custNation(c, n), ordered(c, o), rush(o), rushShip(o, s), suppNation(s, m).
    noRush(n, m) <- nationIn(n, r), nationIn(m, q), not rushTrades(n, m).
    """
    + " ".join(f"likes{i}(c) <- buys(c, p), partBrand(p, 'Brand#{i}')." for i in range(1, 26))
    + " " + " ".join(f"stocks{t.title()}(s) <- shippedBy(o, s), holds(o, p), partType(p, '{t}')." for t in PART_TYPES),
    {
        "ordered": "SELECT o_custkey AS a0, o_orderkey AS a1 FROM {orders}",
        "holds": "SELECT l_orderkey AS a0, l_partkey AS a1 FROM {lineitem}",
        "shippedBy": "SELECT l_orderkey AS a0, l_suppkey AS a1 FROM {lineitem}",
        "custNation": "SELECT c_custkey AS a0, c_nationkey AS a1 FROM {customer}",
        "suppNation": "SELECT s_suppkey AS a0, s_nationkey AS a1 FROM {supplier}",
        "nationIn": "SELECT n_nationkey AS a0, n_regionkey AS a1 FROM {nation}",
        "partType": "SELECT p_partkey AS a0, p_type AS a1 FROM {part}",
        "partBrand": "SELECT p_partkey AS a0, p_brand AS a1 FROM {part}",
        "subDirect": _BRAND_GROUPS,
        "urgentRecent": "SELECT o_orderkey AS a0 FROM {orders} WHERE o_orderpriority = '1-URGENT' AND o_orderdate >= TIMESTAMP '2000-01-01 00:00:00'",
        "bigReturn": "SELECT l_orderkey AS a0 FROM {lineitem} WHERE l_returnflag = 'R' AND l_quantity >= 45",
        "rush": "SELECT o_orderkey AS a0 FROM {orders} WHERE o_orderpriority = '1-URGENT'",
        "rushShip": "SELECT l_orderkey AS a0, l_suppkey AS a1 FROM {lineitem} WHERE l_quantity = 50",
    },
    ("buys", "trades", "regionTrade", "sub", "typed", "dormant", "loyal", "noRush", "likes23", "stocksPromo"),
    {"ordered": "a1 % 10 = 3", "urgentRecent": "a0 % 7 = 2", "bigReturn": "a0 % 5 = 1", "subDirect": "a1 = 'Brand#3'"},
    {"ordered": "a1 % 10 = 4"},
)

_RING = 25
MUTUAL = Workload(
    "mutual",
    " ".join(
        [f"seen{b}(p) <- start{b}(p)." for b in range(_RING)]
        + [f"seen{b}(q) <- seen{(b - k) % _RING}(p), edge(p, q), brand(q, {b})." for b in range(_RING) for k in (1, 2, 3)]
    ),
    {
        "edge": _NEXT_PART,
        "brand": "SELECT p_partkey AS a0, CAST(substr(p_brand, 7) AS BIGINT) - 1 AS a1 FROM {part}",
    }
    | {
        f"start{b}": f"SELECT p_partkey AS a0 FROM {{part}} WHERE p_size = 1 AND p_brand = 'Brand#{b + 1}'" for b in range(_RING)
    },
    ("seen",),
    {"edge": "(a0 * 31 + a1) % 9 = 4"},
    {"edge": "(a0 * 31 + a1) % 9 = 5"},
    {"seen": [f"seen{b}" for b in range(_RING)], "start": [f"start{b}" for b in range(_RING)]},
)

WORKLOADS = {w.name: w for w in (COOC, PATH, SEED, CLIQUE, TAINT, COPY, HOST, THREAD, CLASS, MUTUAL)}

# Examples with a size parameter --------------------------------------------------------------------------------------


def hub_example(spark: SparkSession, n: int) -> tuple[Program, dict[str, DataFrame], dict[str, DataFrame]]:
    """n nodes each tied to one hub and to a node of their own; the change takes away the own nodes."""
    own = spark.sql(f"SELECT concat('a', id) AS a0, concat('c', id) AS a1 FROM range(1, {n + 1})")
    hub = spark.sql(f"SELECT concat('a', id) AS a0, 'b' AS a1 FROM range(1, {n + 1})")
    return parse("s(x, y) <- r(z, x), r(z, y).", {"r"}), {"r": hub.unionByName(own)}, {"r": own}


def path_example(spark: SparkSession, n: int) -> tuple[Program, dict[str, DataFrame], dict[str, DataFrame]]:
    """A root with n children more, each with n grandchildren in common; the change takes away one child that leads on."""
    cut = spark.sql("SELECT 'a' AS a0, 'b1' AS a1, 1L AS a2")
    kids = spark.sql(f"SELECT 'a' AS a0, concat('c', id) AS a1, 1L AS a2 FROM range(1, {n + 1})")
    deep = spark.sql(f"SELECT concat('b', x.id) AS a0, concat('d', y.id) AS a1, 1L AS a2 FROM range(1, {n + 1}) x CROSS JOIN range(1, {n + 1}) y")
    text = "dist(t, n) <- hop('a', t, n). dist(t, n) <- dist(s, p), hop(s, t, q), n := p + q."
    return parse(text, {"hop"}), {"hop": cut.unionByName(kids).unionByName(deep)}, {"hop": cut}


def trace_example(spark: SparkSession) -> tuple[Program, dict[str, DataFrame], dict[str, DataFrame]]:
    """Seeds a, b, d on a small graph; the change takes away seed a."""
    t = spark.sql("SELECT * FROM VALUES ('a'), ('b'), ('d') AS t(a0)")
    edge = spark.sql("SELECT * FROM VALUES ('a', 'c'), ('b', 'c'), ('c', 'd'), ('d', 'e') AS t(a0, a1)")
    return parse("t(x) <- t(y), edge(y, x).", {"t", "edge"}), {"t": t, "edge": edge}, {"t": t.where("a0 = 'a'")}
