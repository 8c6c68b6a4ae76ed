"""Parsing, checks, stratification, delta plans, batching, storage, streams, sources."""

from __future__ import annotations

from datetime import datetime, timedelta

import pytest
from pure import closure

from matkeep.lang import RuleError, parse, validate
from matkeep.maintain import choose_strategy, maintain
from matkeep.materialise import load, materialise, naive
from matkeep.measures import differences, pick_facts, pick_fraction
from matkeep.plans.batching import batch
from matkeep.plans.firing import View, fire_affected
from matkeep.programs import WORKLOADS, hub_example, path_example, trace_example
from matkeep.sources.tables import FactLines, read_facts, write_facts
from matkeep.store import FactStore
from matkeep.strata import stratify
from matkeep.streaming.changes import CHANGES, Journal, Keeper, deduplicated, last_change_state, net, split_late, taken_back, with_details


def test_parser_and_safety():
    p = parse("h(x, 'a.b') <- p(x, _), not q(x), y := x + 1, y < 5. # note\n f(1).", {"p", "q"})
    assert len(p.rules) == 2 and p.rules[0].negative[0].pred == "q" and len(p.rules[0].builtins) == 2
    for bad in ("h(x) <- p(y).", "h(x) <- p(x), not q(y).", "h(x) <- p(x), y < 2.", "h(x) <- p(x). h(x, y) <- p(x), p(y).", "h(x) <- p(x)"):
        with pytest.raises(RuleError):
            parse(bad, {"p", "q"})
    with pytest.raises(RuleError):
        validate(parse("h(x) <- p(x).", {"p"}), {"p": 2})


def test_stratification():
    p = parse("a(x) <- b(x). b(x) <- a(x). b(x) <- e(x). c(x) <- e(x), not a(x). d(x) <- c(x).", {"e"})
    fine, coarse = stratify(p), stratify(p, "coarsest")
    assert fine.level["a"] == fine.level["b"] == 1 and fine.level["c"] < fine.level["d"] and fine.level["e"] == 0
    assert coarse.count == 2 and coarse.level["c"] == coarse.level["d"] == 2
    assert [fine.is_recursive(r) for r in p.rules] == [True, True, False, False, False]
    with pytest.raises(RuleError):
        stratify(parse("a(x) <- e(x), not b(x). b(x) <- a(x).", {"e"}))
    assert stratify(p, coarse.level).level == coarse.level
    for bad in (coarse.level | {"a": 0, "b": 0}, {q: n for q, n in coarse.level.items() if q != "d"}):
        with pytest.raises(RuleError):
            stratify(p, bad)


def test_every_affected_instance_once(spark):
    rule = parse("h(x) <- p(x, y), p(y, z), not r(x, z).", {"p", "r"}).rules[0]
    p = {(a, b) for a in range(4) for b in range(4) if (a * b + a) % 3}
    r, gone, blocked = {(0, 1), (2, 2)}, {q for q in p if sum(q) % 2}, {(1, 3), (3, 0)}
    frame = lambda rows: spark.createDataFrame(sorted(rows), "a0 bigint, a1 bigint")
    view = View({"p": frame(p)}.get, {"r": frame(r)}.get)
    got = sorted((x["x"], x["y"], x["z"]) for x in fire_affected(spark, rule, view, {"p": frame(gone)}.get, {"r": frame(blocked)}.get).collect())
    want = sorted((a, b, d) for a, b in p for c, d in p if b == c and (a, d) not in r and ((a, b) in gone or (c, d) in gone or (a, d) in blocked))
    assert got == want


def test_naive_agrees(spark):
    edges = {(1, 2), (2, 3), (3, 1), (4, 4)}
    program = parse("t(x, y) <- e(x, y). t(x, z) <- t(x, y), t(y, z). s(x) <- n(x), not t(x, x).", {"e", "n"})
    facts = load({"e": spark.createDataFrame(sorted(edges), "a bigint, b bigint"), "n": spark.range(6)})
    a, b = materialise(spark, program, facts), naive(spark, program, facts)
    assert not any(differences(a, b).values())
    assert {r[0] for r in a.facts["s"].collect()} == {x[0] for x in closure(program, {"e": edges, "n": {(i,) for i in range(6)}})[0]["s"]}


def test_batched_rules_agree(spark):
    text = " ".join(f"seen{b}(p) <- start{b}(p). seen{b}(q) <- seen{(b - 1) % 3}(p), edge(p, q), brand(q, {b})." for b in range(3))
    inputs = {"edge", "brand", "start0", "start1", "start2"}
    program = parse(text, inputs)
    batched = batch(program, {"seen": [f"seen{b}" for b in range(3)], "start": [f"start{b}" for b in range(3)]})
    assert len(batched.program.rules) == 2
    rows = {"edge": {(i, (i * 5 + 1) % 12) for i in range(12)}, "brand": {(i, i % 3) for i in range(12)}, "start0": {(3,)}, "start1": {(1,)}, "start2": {(2,)}}
    facts = load({p: spark.createDataFrame(sorted(f), ", ".join(f"a{i} bigint" for i in range(len(next(iter(f)))))) for p, f in rows.items()})
    mat = materialise(spark, batched.program, batched.tagged(facts) | batched.rule_tables(spark))
    want = closure(program, rows)[0]
    for b in range(3):
        assert {r[0] for r in batched.member(mat.facts["seen"], f"seen{b}").collect()} == {x[0] for x in want[f"seen{b}"]}


def test_store(spark, tmp_path):
    store = FactStore(spark, f"{tmp_path}/s", buckets=4)
    frame = lambda rows: spark.createDataFrame(sorted(rows), "a0 bigint, a1 bigint")
    rows = {(i, i * i) for i in range(20)}
    store.create(frame(rows))
    assert store.apply(1, frame({(3, 9), (4, 16)}), frame({(50, 1)}))
    assert not store.apply(1, frame({(5, 25)}), None)
    now = rows - {(3, 9), (4, 16)} | {(50, 1)}
    assert set(map(tuple, store.read().collect())) == now
    part = store.read(frame({(7, 0)}))
    assert (7, 49) in set(map(tuple, part.collect())) and part.count() < len(now)
    assert store.compact() > 0 and set(map(tuple, store.read().collect())) == now
    assert store.apply(2, frame({(50, 1)}), None) and set(map(tuple, store.read().collect())) == now - {(50, 1)}


def test_stream_of_changes(spark, tmp_path):
    program = parse("t(y) <- t(x), e(x, y). t(x) <- s(x).", {"e", "s"})
    facts = load({"e": spark.createDataFrame([(1, 2), (2, 3)], "a bigint, b bigint"), "s": spark.createDataFrame([(1,)], "a bigint")})
    at = datetime(2024, 1, 1)
    log = [("-", "e", ["1", "2"], at, 1), ("+", "e", ["1", "5"], at, 2), ("-", "e", ["1", "5"], at + timedelta(seconds=1), 3), ("+", "e", ["1", "5"], at + timedelta(seconds=2), 4)]
    spark.createDataFrame(log, CHANGES).write.parquet(f"{tmp_path}/log")
    keeper = Keeper(materialise(spark, program, facts, 2))
    stream = spark.readStream.schema(CHANGES).parquet(f"{tmp_path}/log")
    keeper.attach(deduplicated(stream), f"{tmp_path}/cp").awaitTermination()
    assert {r[0] for r in keeper.mat.facts["t"].collect()} == {1, 5}
    assert not keeper.apply(spark.createDataFrame(log, CHANGES), next(iter(keeper.done)))
    assert net(spark.createDataFrame(log, CHANGES)).count() == 2
    in_time, late = split_late(spark.createDataFrame(log, CHANGES), at + timedelta(seconds=2), 1)
    assert (in_time.count(), late.count()) == (2, 2)
    q = last_change_state(stream).writeStream.format("memory").queryName("last").outputMode("update").trigger(availableNow=True).option("checkpointLocation", f"{tmp_path}/cp2").start()
    q.awaitTermination()
    assert {(r["fact"], r["op"]) for r in spark.table("last").collect()} == {('["1","2"]', "-"), ('["1","5"]', "+")}


def test_stream_into_an_empty_predicate_and_after_a_restart(spark, tmp_path):
    program = parse("t(y) <- t(x), e(x, y). t(x) <- s(x).", {"e", "s"})
    facts = load({"e": spark.createDataFrame([(1, 2)], "a bigint, b bigint"), "s": spark.createDataFrame([], "a int")})
    at = datetime(2024, 1, 1)
    rows = [("+", "s", ["1"], at, 1), ("+", "zzz", ["1"], at, 2), ("+", "e", ["1"], at, 3), ("+", "e", ["2", "x"], at, 4), ("?", "s", ["2"], at, 5), ("+", "e", ["2", "3"], at, 6)]
    log = spark.createDataFrame(rows, CHANGES)
    journal = Journal(spark, f"{tmp_path}/journal")
    keeper = Keeper(materialise(spark, program, facts, 2), journal=journal, dead_letters=f"{tmp_path}/dead")
    assert keeper.apply(log, 7)
    assert {r[0] for r in keeper.mat.facts["t"].collect()} == {1, 2, 3}
    assert {r["change_id"] for r in spark.read.parquet(f"{tmp_path}/dead").collect()} == {2, 3, 4, 5}
    again = Keeper.reopen(spark, program, Journal(spark, f"{tmp_path}/journal"))
    assert not again.apply(log, 7) and {r[0] for r in again.mat.facts["t"].collect()} == {1, 2, 3}
    assert again.apply(spark.createDataFrame([("-", "s", ["1"], at, 8)], CHANGES), 8) and again.mat.facts["t"].isEmpty()
    assert Keeper.reopen(spark, program, journal).mat.of("t") is None


def test_joins_of_streams(spark, tmp_path):
    at = datetime(2024, 1, 1)
    rows = [("+", "e", ["a,b"], at, 1), ("-", "e", ["a,b"], at + timedelta(minutes=1), 2), ("-", "e", ["a", "b"], at + timedelta(minutes=1), 3), ("-", "e", ["a,b"], at + timedelta(minutes=9), 4)]
    spark.createDataFrame(rows, CHANGES).write.parquet(f"{tmp_path}/log")
    details = spark.createDataFrame([("e", '["a,b"]', "note")], "pred string, fact string, note string")

    def run(make, name):
        stream = spark.readStream.schema(CHANGES).parquet(f"{tmp_path}/log")
        make(stream).writeStream.format("memory").queryName(name).outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{tmp_path}/{name}").start().awaitTermination()
        return spark.table(name).collect()

    assert sorted((r["change_id"], r["note"]) for r in run(lambda s: with_details(s, details), "detailed")) == [(1, "note"), (2, "note"), (3, None), (4, "note")]
    assert [(r["fact"], r["deleted"]) for r in run(taken_back, "back")] == [('["a,b"]', at + timedelta(minutes=1))]


def test_sources(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "a0 bigint, a1 string")
    for fmt in ("parquet", "csv", "json", "orc"):
        write_facts(df, f"{tmp_path}/{fmt}", fmt)
        assert sorted(read_facts(spark, f"{tmp_path}/{fmt}", fmt, "a0 bigint, a1 string").collect()) == sorted(df.collect())
    spark.dataSource.register(FactLines)
    rows = spark.read.format("facts").option("lines", "e(1, 'a').\nf(2)\ng('a,b', \"(c)\", 2).").load().collect()
    assert sorted((r["pred"], r["args"]) for r in rows) == [("e", ["1", "a"]), ("f", ["2"]), ("g", ["a,b", "(c)", "2"])]


def test_samples_are_nested(spark):
    df = spark.range(500).select(("id")).toDF("a0")
    small, large = (set(r[0] for r in pick_fraction(df, s, 3).collect()) for s in (0.1, 0.4))
    assert small < large and abs(len(large) - 200) < 50
    assert pick_facts(df, 10, 1).count() == 10


def test_examples(spark):
    for program, facts, gone in (hub_example(spark, 5), path_example(spark, 3), trace_example(spark)):
        mat = materialise(spark, program, load(facts), 2)
        report = maintain(mat, load(gone), {}, "odr_2c")
        again = maintain(mat, load(gone), {}, "remat")
        assert not any(differences(report.mat, again.mat).values())


def test_strategy_choice():
    strat = lambda w: stratify(WORKLOADS[w].program())
    assert choose_strategy(strat("cooc"), 0.01) == "counting"
    assert choose_strategy(strat("path"), 0.01) == "odr_2c"
    assert choose_strategy(strat("seed"), 0.01) == "pbd_1c"
    assert choose_strategy(strat("seed"), 0.9) == "remat_2c"


def test_scan_is_pruned(spark):
    from matkeep.operators.relational import scan_pruned

    plan = scan_pruned(spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(o_orderdate" in plan and "o_custkey" not in plan


def test_entry_without_operators(tmp_path):
    """The entry module imports and answers where the operator subpackage is gone."""
    import os
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{root}/matkeep", f"{tmp_path}/matkeep", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'mat_seed' in q and not any(n[:2] == 'op' and n[2].isdigit() for n in q) and set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
