"""One query for each method, variant, baseline and measure on the workloads, with its SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles
from .operators.relational import OPERATORS, SQL
from .maintain import COUNTERS, Options, UpdateReport, maintain
from .materialise import Materialisation, load, materialise
from .plans.firing import View, columns_of, fire_affected, match_backward, minus, observed_matches
from .programs import CLASS, COOC, MUTUAL, WORKLOADS, Workload, hub_example, path_example, trace_example
from .store import settle
from .strata import stratify

Query = Callable[[SparkSession, str], DataFrame]


def _built(spark: SparkSession, sf_dir: str, w: Workload, output: str, counters: int, late: bool = False, policy: str = "finest"):
    """The workload materialised; its removed and withheld facts. ``late``: withheld facts are not there yet."""
    if w is MUTUAL:
        batched = w.batched()
        facts = batched.tagged(w.explicit(spark, sf_dir))
        explicit = facts | {p: df.distinct() for p, df in batched.rule_tables(spark).items()}
        program = batched.program
    else:
        program = w.program(output)
        explicit = w.explicit(spark, sf_dir, program.preds)
    gone = {p: explicit[p].where(c) for p, c in w.removed.items() if p in explicit}
    new = {p: explicit[p].where(c) for p, c in w.withheld.items() if p in explicit}
    start = {p: df.where(f"NOT ({w.withheld[p]})") if late and p in w.withheld else df for p, df in explicit.items()}
    return materialise(spark, program, start, counters, policy), gone, new


def _none(mat: Materialisation, pred: str, more: str = "") -> DataFrame:
    """The empty relation."""
    arity = next(len(r.head.args) for r in mat.strat.program.rules if r.head.pred == pred)
    return mat.spark.createDataFrame([], ", ".join(f"a{i} bigint" for i in range(arity)) + more)


def _facts(mat: Materialisation, pred: str) -> DataFrame:
    df = mat.of(pred)
    return _none(mat, pred) if df is None else df.select(*columns_of(df))


def _counters(mat: Materialisation, pred: str, both: bool) -> DataFrame:
    df = mat.counters.get(pred)
    if df is None:
        return _none(mat, pred, ", c_nr bigint" + (", c_r bigint" if both else ""))
    return df.select(*columns_of(df), "c_nr", *(["c_r"] if both else []))


def mat_query(w: Workload, pred: str, policy: str = "finest") -> Query:
    return lambda spark, d: _facts(_built(spark, d, w, pred, 0, policy=policy)[0], pred)


def counters_query(w: Workload, pred: str, counters: int = 2) -> Query:
    return lambda spark, d: _counters(_built(spark, d, w, pred, counters)[0], pred, counters == 2)


def update(spark: SparkSession, sf_dir: str, w: Workload, pred: str, strategy: str, kind: str, options: Options = Options(), policy: str = "finest") -> UpdateReport:
    """``kind``: delete, insert, or mixed."""
    mat, gone, new = _built(spark, sf_dir, w, pred, COUNTERS[strategy], kind != "delete", policy)
    return maintain(mat, gone if kind != "insert" else {}, new if kind != "delete" else {}, strategy, options)


def update_query(w: Workload, pred: str, strategy: str, kind: str, policy: str = "finest", options: Options = Options()) -> Query:
    return lambda spark, d: _facts(update(spark, d, w, pred, strategy, kind, options, policy).mat, pred)


def counters_after_query(w: Workload, pred: str, strategy: str, kind: str) -> Query:
    return lambda spark, d: _counters(update(spark, d, w, pred, strategy, kind).mat, pred, COUNTERS[strategy] == 2)


def part_query(w: Workload, pred: str, strategy: str, part: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        report = update(spark, d, w, pred, strategy, "delete")
        df = getattr(report, part).get(pred)
        return df if df is not None else _facts(report.mat, pred).limit(0)

    return run


def work_query(w: Workload, pred: str, strategy: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        return update(spark, d, w, pred, strategy, "delete", Options(collect_work=True)).as_frame(spark, strategy)

    return run


def _pair_instances(gained: bool) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        explicit = COOC.explicit(spark, d)
        rule = COOC.program().rules[0]
        change = {"inCart": explicit["inCart"].where((COOC.withheld if gained else COOC.removed)["inCart"])}
        view = View(explicit.get, explicit.get)
        return fire_affected(spark, rule, view, change.get, lambda p: None).select("o", "y", "z")

    return run


def backward_candidates(spark: SparkSession, d: str) -> DataFrame:
    """Matches the first body atom offers when overdeleted pairs are looked up head first, and instances confirmed."""
    explicit = COOC.explicit(spark, d)
    rule = COOC.program().rules[0]
    facts = materialise(spark, COOC.program(), explicit).facts["pair"]
    left = explicit["inCart"].where("a1 < 0")
    gone, _ = settle(facts.where("NOT (a0 < 0 AND a1 < 0)"))
    fan = left.groupBy("a1").agg(F.count(F.lit(1)).alias("n"))
    tried = gone.join(fan, gone["a0"] == fan["a1"], "left").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("tried"))
    found = match_backward(spark, rule, gone, View({"inCart": left}.get, {"inCart": left}.get), "body_first")
    return tried.crossJoin(found.agg(F.count(F.lit(1)).alias("confirmed")))  # one row each


BACKWARD_SQL = (
    oracles.with_clause(COOC, "all")
    + """, gone AS (SELECT * FROM d_pair WHERE NOT (a0 < 0 AND a1 < 0)), hubs AS (SELECT * FROM e_inCart WHERE a1 < 0)
SELECT CAST((SELECT count(*) FROM gone g JOIN hubs h ON h.a1 = g.a0) AS BIGINT) AS tried,
  (SELECT count(*) FROM gone g JOIN hubs x ON x.a1 = g.a0 JOIN hubs y ON y.a1 = g.a1 AND y.a0 = x.a0) AS confirmed"""
)


def profile(spark: SparkSession, d: str) -> DataFrame:
    """Facts, strata and rules of every workload."""
    out = None
    for w in WORKLOADS.values():
        program = w.program()
        strat = stratify(program)
        rec = sum(strat.is_recursive(r) for r in program.rules)
        # Duplicate-free counts of all predicates in one plan each.
        parts = None
        for p, sql in w.facts.items():
            used = {t: spark.read.parquet(f"{d}/{t}.parquet") for t in _tables(sql)}
            one = spark.sql(sql, **used).distinct().agg(F.count(F.lit(1)).alias("n"))
            parts = one if parts is None else parts.unionByName(one)
        row = parts.agg(F.sum("n").cast("bigint").alias("facts")).select(
            F.lit(w.name).alias("workload"), "facts", *[F.lit(v).cast("bigint").alias(n) for n, v in (("strata", strat.count), ("nonrecursive", len(program.rules) - rec), ("recursive", rec))]
        )
        out = row if out is None else out.unionByName(row)
    return out


def hub_cost(n: int) -> Query:
    """What backward matching tries after the hub's deletion, against what building took: rows n, plan, built, tried, confirmed."""
    return _cost(hub_example, "s", n)


def path_cost(n: int) -> Query:
    """The same where a rule computes lengths: the recursive rule alone."""
    return _cost(path_example, "dist", n)


def _cost(example, pred: str, n: int) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        program, facts, gone = example(spark, n)
        mat = materialise(spark, program, load(facts), 2)
        built = mat.counters[pred].agg(F.sum(F.col("c_nr") + F.col("c_r"))).first()[0]
        report = maintain(mat, gone, {}, "odr_2c")
        over, rule = report.overdeleted[pred], mat.strat.program.rules[-1]
        left = {p: minus(df, over if p == pred else report.deleted.get(p)) for p, df in mat.facts.items()}
        rows = [(n, plan, built, *observed_matches(spark, rule, over, View(left.get, left.get), plan)) for plan in ("head_first", "body_first", "auto")]
        return spark.createDataFrame(rows, "n bigint, plan string, built bigint, tried bigint, confirmed bigint")

    return run


def _cost_sql(n: int, built: int, head: int, body: int) -> str:
    """Closed formulas in n, worked out by hand."""
    rows = ", ".join(f"({n}, '{plan}', {built}, {tried}, 0)" for plan, tried in (("head_first", head), ("body_first", body), ("auto", body)))
    return f"SELECT CAST(n AS BIGINT) AS n, plan, CAST(built AS BIGINT) AS built, CAST(tried AS BIGINT) AS tried, CAST(confirmed AS BIGINT) AS confirmed FROM (VALUES {rows}) AS t(n, plan, built, tried, confirmed)"


def counter_trace(spark: SparkSession, d: str) -> DataFrame:
    """Counters of the small graph before the update, after overdeletion, and after it; zeros are left out."""
    program, facts, gone = trace_example(spark)
    mat = materialise(spark, program, load(facts), 2)
    report = maintain(mat, gone, {}, "odr_2c")
    before, cols = mat.counters["t"], ["a0", "c_nr", "c_r"]
    midway = before.select(*cols).unionByName(report.losses["t"].select(*cols)).groupBy("a0").agg(F.sum("c_nr").alias("c_nr"), F.sum("c_r").alias("c_r")).where("c_nr > 0 OR c_r > 0")
    parts = [df.select(F.lit(at).alias("moment"), *cols) for at, df in (("1 before", before), ("2 overdeleted", midway), ("3 after", report.mat.counters["t"]))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


#: Worked out by hand: fact, nonrecursive and recursive counter.
TRACE = {"1 before": "a10 b10 c02 d11 e01", "2 overdeleted": "b10 c01 d10 e01", "3 after": "b10 c01 d11 e01"}
TRACE_SQL = "SELECT moment, a0, CAST(x AS BIGINT) AS c_nr, CAST(y AS BIGINT) AS c_r FROM (VALUES " + ", ".join(
    f"('{at}', '{f[0]}', {f[1]}, {f[2]})" for at, row in TRACE.items() for f in row.split()
) + ") AS t(moment, a0, x, y)"


def _tables(sql: str) -> list[str]:
    from .programs import TABLES

    return [t for t in TABLES if f"{{{t}}}" in sql]


def _profile_sql() -> str:
    parts = []
    for w in WORKLOADS.values():
        program = w.program()
        strat = stratify(program)
        rec = sum(strat.is_recursive(r) for r in program.rules)
        total = " + ".join(f"(SELECT count(*) FROM e_{p})" for p in w.facts)
        parts.append(
            f"SELECT * FROM ({oracles.with_clause(w, 'all')} SELECT '{w.name}' AS workload, CAST({total} AS BIGINT) AS facts, CAST({strat.count} AS BIGINT) AS strata, "
            f"CAST({len(program.rules) - rec} AS BIGINT) AS nonrecursive, CAST({rec} AS BIGINT) AS recursive) AS w_{w.name}"
        )
    return " UNION ALL ".join(parts)


def why(spark: SparkSession, d: str) -> DataFrame:
    """Supports of all tainted events: instances behind each fact."""
    w = WORKLOADS["taint"]
    mat, _, _ = _built(spark, d, w, "tainted", 0)
    rule = next(r for r in mat.strat.program.rules if r.head.pred == "tainted" and len(r.atoms) > 1)
    return match_backward(spark, rule, mat.facts["tainted"], View(mat.facts.get, mat.facts.get)).select("e", "f")


WHY_SQL = oracles.with_clause(WORKLOADS["taint"], "all") + (
    " SELECT t.a0 AS e, n.a1 AS f FROM d_tainted t JOIN e_next n ON n.a0 = t.a0 WHERE n.a1 NOT IN (SELECT a0 FROM d_blocked)"
)


def goal(spark: SparkSession, d: str) -> DataFrame:
    """A conjunctive query over a maintained materialisation."""
    mat = update(spark, d, WORKLOADS["taint"], "cleanUser", "odr_2c", "delete").mat
    return mat.sql("SELECT a.a1 AS user_id, count(*) AS n_events FROM actor a JOIN cleanUser c ON c.a0 = a.a1 GROUP BY a.a1")


GOAL_SQL = oracles.with_clause(WORKLOADS["taint"], "less") + (
    " SELECT a.a1 AS user_id, count(*) AS n_events FROM e_actor a JOIN d_cleanUser c ON c.a0 = a.a1 GROUP BY a.a1"
)

MAIN = {"cooc": "pair", "path": "dist", "seed": "reach", "clique": "related", "taint": "tainted", "copy": "toxicDoc", "host": "zone", "thread": "heard"}


def catalogue() -> tuple[dict[str, Query], dict[str, str]]:
    q: dict[str, Query] = {}
    o: dict[str, str] = {}

    def add(name: str, query: Query, sql: str | None = None) -> None:
        q[name] = query
        if sql:
            o[name] = sql

    for name, pred in MAIN.items():
        w = WORKLOADS[name]
        add(f"mat_{name}", mat_query(w, pred), oracles.facts_sql(name, pred, "all"))
        add(f"counters_{name}", counters_query(w, pred), oracles.counters_sql(name, pred, "all"))
        for x in ("odr", "odr_2c", "pbd", "pbd_1c"):
            if name == "clique" and x == "pbd":
                options = Options(rederive_plan="body_first")
                add(f"{x}_delete_{name}", update_query(w, pred, x, "delete", options=options), oracles.facts_sql(name, pred, "less"))
            elif name == "cooc" and x in ("odr", "pbd"):  # head first would try the square of the hub's rows
                add(f"{x}_delete_{name}", update_query(w, pred, x, "delete", options=Options(rederive_plan="body_first")), oracles.facts_sql(name, pred, "less"))
            else:
                add(f"{x}_delete_{name}", update_query(w, pred, x, "delete"), oracles.facts_sql(name, pred, "less"))
        for x in ("odr_2c",) if name == "path" else ("odr_2c", "pbd_1c"):
            add(f"{x}_counters_after_{name}", counters_after_query(w, pred, x, "mixed"), oracles.counters_sql(name, pred, "mixed", x == "odr_2c"))
        add(f"odr_2c_insert_{name}", update_query(w, pred, "odr_2c", "insert"), oracles.facts_sql(name, pred, "all"))
        add(f"odr_2c_mixed_{name}", update_query(w, pred, "odr_2c", "mixed"), oracles.facts_sql(name, pred, "mixed"))
    for name in ("path", "seed", "taint", "thread"):
        for x in ("odr",) if name == "path" else ("odr", "pbd", "pbd_1c"):
            add(f"{x}_mixed_{name}", update_query(WORKLOADS[name], MAIN[name], x, "mixed"), oracles.facts_sql(name, MAIN[name], "mixed"))
            add(f"{x}_insert_{name}", update_query(WORKLOADS[name], MAIN[name], x, "insert"), oracles.facts_sql(name, MAIN[name], "all"))
    for x, gated in (("odr", False), ("odr_2c", True)):
        for name in ("seed", "path"):
            add(f"{x}_overdeleted_{name}", part_query(WORKLOADS[name], MAIN[name], x, "overdeleted"), oracles.overdeleted_sql(name, gated))
            add(f"{x}_rederived_{name}", part_query(WORKLOADS[name], MAIN[name], x, "rederived"), oracles.rederived_sql(name, gated))
    for name in ("seed", "taint", "copy", "host", "thread"):
        add(f"pbd_1c_deleted_{name}", part_query(WORKLOADS[name], MAIN[name], "pbd_1c", "deleted"), oracles.deleted_sql(name, MAIN[name]))
    add("counting_delete_cooc", update_query(COOC, "pair", "counting", "delete"), oracles.facts_sql("cooc", "pair", "less"))
    add("counting_counters_after_cooc", counters_after_query(COOC, "pair", "counting", "mixed"), oracles.counters_sql("cooc", "pair", "mixed", False))
    for name, pred in (("taint", "cleanUser"), ("copy", "safeDoc"), ("copy", "leaked")):
        for x in ("odr", "odr_2c", "pbd", "pbd_1c"):
            add(f"{x}_mixed_{name}_{pred}", update_query(WORKLOADS[name], pred, x, "mixed"), oracles.facts_sql(name, pred, "mixed"))
    for pred in CLASS.outputs:
        add(f"mat_class_{pred}", mat_query(CLASS, pred), oracles.facts_sql("class", pred, "all"))
        add(f"odr_2c_mixed_class_{pred}", update_query(CLASS, pred, "odr_2c", "mixed"), oracles.facts_sql("class", pred, "mixed"))
    for pred in ("loyal", "dormant", "noRush"):
        add(f"counting_mixed_class_{pred}", update_query(CLASS, pred, "counting", "mixed"), oracles.facts_sql("class", pred, "mixed"))
    for pred in ("loyal", "regionTrade", "typed"):
        for x in ("odr", "pbd", "pbd_1c"):
            add(f"{x}_mixed_class_{pred}", update_query(CLASS, pred, x, "mixed"), oracles.facts_sql("class", pred, "mixed"))
    for pred in ("loyal", "dormant"):
        add(f"counting_delete_class_{pred}", update_query(CLASS, pred, "counting", "delete"), oracles.facts_sql("class", pred, "less"))
    for name in ("cooc", "clique", "copy", "host"):
        body = Options(rederive_plan="body_first") if name in ("cooc", "clique") else Options()
        for x in ("odr", "pbd", "pbd_1c"):
            add(f"{x}_mixed_{name}", update_query(WORKLOADS[name], MAIN[name], x, "mixed", options=body), oracles.facts_sql(name, MAIN[name], "mixed"))
            add(f"{x}_insert_{name}", update_query(WORKLOADS[name], MAIN[name], x, "insert", options=body), oracles.facts_sql(name, MAIN[name], "all"))
    add("counters_mutual", counters_query(MUTUAL, "seen"), oracles.counters_sql("mutual", "seen", "all"))
    for x in ("odr_2c", "pbd_1c"):
        add(f"{x}_mixed_mutual", update_query(MUTUAL, "seen", x, "mixed"), oracles.facts_sql("mutual", "seen", "mixed"))
    add("pbd_delete_mutual", update_query(MUTUAL, "seen", "pbd", "delete"), oracles.facts_sql("mutual", "seen", "less"))
    add("auto_delete_cooc", update_query(COOC, "pair", "odr", "delete", options=Options(rederive_plan="auto")), oracles.facts_sql("cooc", "pair", "less"))
    for n in (20, 60):
        add(f"cost_hub_{n}", hub_cost(n), _cost_sql(n, 4 * n, n * n, 2 * n))
        add(f"cost_path_{n}", path_cost(n), _cost_sql(n, 2 * n + 1, n * n, n))
    add("counter_trace", counter_trace, TRACE_SQL)
    add("counters_class_buys", counters_query(CLASS, "buys"), oracles.counters_sql("class", "buys", "all"))
    add("mat_mutual", mat_query(MUTUAL, "seen"), oracles.facts_sql("mutual", "seen", "all"))
    add("mat_mutual_coarsest", mat_query(MUTUAL, "seen", "coarsest"), oracles.facts_sql("mutual", "seen", "all"))
    for x in ("odr", "odr_2c", "pbd_1c"):
        add(f"{x}_delete_mutual", update_query(MUTUAL, "seen", x, "delete"), oracles.facts_sql("mutual", "seen", "less"))
    add("odr_2c_delete_taint_coarsest", update_query(WORKLOADS["taint"], "cleanUser", "odr_2c", "delete", "coarsest"), oracles.facts_sql("taint", "cleanUser", "less"))
    for name in ("path", "seed"):
        w, pred = WORKLOADS[name], MAIN[name]
        add(f"remat_{name}", update_query(w, pred, "remat", "delete"), oracles.facts_sql(name, pred, "less"))
        add(f"remat_1c_{name}", counters_after_query(w, pred, "remat_1c", "delete"), oracles.counters_sql(name, pred, "less", False))
        add(f"remat_2c_{name}", counters_after_query(w, pred, "remat_2c", "delete"), oracles.counters_sql(name, pred, "less"))
        for x in ("odr", "odr_2c") if name == "path" else ("odr", "odr_2c", "pbd", "pbd_1c"):
            add(f"work_{x}_{name}", work_query(w, pred, x))
    add("instances_lost_cooc", _pair_instances(False), oracles.instances_sql(False))
    add("instances_gained_cooc", _pair_instances(True), oracles.instances_sql(True))
    add("backward_candidates_cooc", backward_candidates, BACKWARD_SQL)
    add("workload_profile", profile, _profile_sql())
    add("why_support", why, WHY_SQL)
    add("goal_sql", goal, GOAL_SQL)
    return q | OPERATORS, o | SQL


QUERIES, ORACLE_SQL = catalogue()
