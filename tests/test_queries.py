"""Registered queries against plain versions."""

from __future__ import annotations

from matkeep.queries import QUERIES

def test_why_support_has_every_tainted_event(spark, tmp_path):
    kinds = ("error", "view", "purchase", "view", "click", "view", "error", "view")
    rows = [(i, i % 3, kinds[i * 7 % 8], 200.0 if i % 5 else 10.0) for i in range(60)]
    values = ", ".join(f"({e}L, {u}L, timestamp_seconds({e}), '{k}', {v}D)" for e, u, k, v in rows)
    spark.sql(f"SELECT * FROM VALUES {values} AS t(event_id, user_id, ts, event_type, value)").write.parquet(f"{tmp_path}/events.parquet")
    tainted, last, want = set(), {}, set()
    for e, u, k, v in rows:
        if k == "error" and v > 150:
            tainted.add(e)
        if last.get(u) in tainted and k != "purchase":
            tainted.add(e)
            want.add((last[u], e))
        last[u] = e
    got = [tuple(r) for r in QUERIES["why_support"](spark, str(tmp_path)).collect()]
    assert sorted(got) == sorted(want) and {f % 10 for _, f in want} > {3}
