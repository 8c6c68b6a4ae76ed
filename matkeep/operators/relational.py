"""Relational operators a user of the rule engine needs around it, each with the SQL that says the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.builtins import Suffixes, after_first_dot, fingerprint, nearest
from ..lang import parse
from ..materialise import load
from ..plans.firing import View, fire, head_of
from ..programs import WORKLOADS
from ..sources.tables import read_table

OPERATORS: dict = {}
SQL: dict[str, str] = {}


def operator(sql: str | None = None):
    def put(fn):
        OPERATORS[fn.__name__] = fn
        if sql:
            SQL[fn.__name__] = sql
        return fn

    return put


def as_of(left: DataFrame, right: DataFrame, by: str, left_ts: str, right_ts: str, value: str) -> DataFrame:
    """For each left row the value of the last right row of the same key not after it, by one window over both."""
    cols = left.columns
    l_ = left.select(*cols, F.col(left_ts).alias("_ts"), F.lit(1).alias("_side"), F.lit(None).cast(dict(right.dtypes)[value]).alias(value))
    r_ = right.select(*[F.col(by).alias(c) if c == by else F.lit(None).cast(t).alias(c) for c, t in left.dtypes], F.col(right_ts).alias("_ts"), F.lit(0).alias("_side"), value)
    w = W.partitionBy(by).orderBy("_ts", "_side").rowsBetween(W.unboundedPreceding, 0)
    return l_.unionByName(r_).withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_side = 1").select(*cols, value)


def range_join(points: DataFrame, intervals: DataFrame, key: str, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points inside half-open intervals of the same key, by bins of ``width``: an equi-join and a filter."""
    p = points.withColumn("_bin", F.floor(F.col(at) / width))
    i = intervals.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width))))
    return p.join(i, [key, "_bin"]).where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_bin")


def _rule(spark: SparkSession, facts: dict[str, DataFrame], text: str, names: list[str]) -> DataFrame:
    facts = load(facts)
    rule = parse(text, set(facts)).rules[0]
    return head_of(rule, fire(spark, rule, View(facts.get, facts.get))).distinct().toDF(*names)


def _order_lines(spark, d):
    return {
        "ordered": read_table(spark, d, "orders", ["o_custkey", "o_orderkey"]),
        "holds": read_table(spark, d, "lineitem", ["l_orderkey", "l_partkey"]).distinct(),
    }


@operator("SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderdate >= TIMESTAMP '2000-01-01' AND o_orderpriority = '1-URGENT'")
def scan_pruned(spark, d):
    return read_table(spark, d, "orders", ["o_orderkey", "o_totalprice"], "o_orderdate >= TIMESTAMP '2000-01-01' AND o_orderpriority = '1-URGENT'")


def _facts(name: str, pred: str):
    return lambda spark, d: WORKLOADS[name].explicit(spark, d, {pred})[pred]


for _name, _w, _p in (("facts_incart", "cooc", "inCart"), ("facts_hop", "path", "hop"), ("facts_edge", "seed", "edge"), ("facts_host", "host", "host"), ("facts_next", "taint", "next")):
    OPERATORS[_name] = _facts(_w, _p)
    _sql = WORKLOADS[_w].facts[_p]
    for _t in ("lineitem", "pages", "events"):
        _sql = _sql.replace(f"{{{_t}}}", _t)
    SQL[_name] = f"SELECT DISTINCT * FROM ({_sql}) AS f"


@operator("SELECT DISTINCT p_partkey + 1 AS p, 'part' AS tag FROM part WHERE p_size < 10")
def rule_projection(spark, d):
    return _rule(spark, {"part": read_table(spark, d, "part", ["p_partkey", "p_size"])}, "h(q, 'part') <- part(p, s), s < 10, q := p + 1.", ["p", "tag"])


@operator("SELECT DISTINCT CAST(n_nationkey AS BIGINT) AS n_nationkey FROM nation WHERE n_regionkey = 2")
def rule_constant(spark, d):
    return _rule(spark, {"nation": read_table(spark, d, "nation", ["n_nationkey", "n_regionkey"])}, "h(n) <- nation(n, 2).", ["n_nationkey"])


@operator("SELECT DISTINCT l_partkey FROM lineitem WHERE l_partkey = l_suppkey")
def rule_repeatvar(spark, d):
    return _rule(spark, {"line": read_table(spark, d, "lineitem", ["l_partkey", "l_suppkey"])}, "h(x) <- line(x, x).", ["l_partkey"])


@operator("SELECT DISTINCT p_partkey FROM part WHERE p_size BETWEEN 5 AND 9 AND p_brand LIKE 'Brand#1%' AND p_type IN ('PROMO', 'SMALL')")
def rule_compare(spark, d):
    text = "h(p) <- part(p, s, b, t), s BETWEEN 5 AND 9, b LIKE 'Brand#1%', t IN ('PROMO', 'SMALL')."
    return _rule(spark, {"part": read_table(spark, d, "part", ["p_partkey", "p_size", "p_brand", "p_type"])}, text, ["p_partkey"])


@operator("SELECT DISTINCT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
def rule_negation(spark, d):
    facts = {"cust": read_table(spark, d, "customer", ["c_custkey"]), "done": read_table(spark, d, "orders", ["o_custkey"], "o_orderstatus = 'F'")}
    return _rule(spark, facts, "h(c) <- cust(c), not done(c).", ["c_custkey"])


@operator("SELECT DISTINCT o_custkey AS c, l_partkey AS p FROM orders JOIN lineitem ON l_orderkey = o_orderkey")
def join_two_atoms(spark, d):
    return _rule(spark, _order_lines(spark, d), "h(c, p) <- ordered(c, o), holds(o, p).", ["c", "p"])


@operator("SELECT DISTINCT x.l_partkey AS p, y.l_partkey AS q FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey WHERE x.l_partkey < y.l_partkey")
def join_self(spark, d):
    return _rule(spark, {"holds": _order_lines(spark, d)["holds"]}, "h(p, q) <- holds(o, p), holds(o, q), p < q.", ["p", "q"])


@operator("SELECT DISTINCT c_nationkey AS n, p_brand AS b FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey")
def join_three_atoms(spark, d):
    facts = _order_lines(spark, d) | {"cust": read_table(spark, d, "customer", ["c_custkey", "c_nationkey"]), "brand": read_table(spark, d, "part", ["p_partkey", "p_brand"])}
    out = _rule(spark, facts, "h(n, b) <- cust(c, n), ordered(c, o), holds(o, p), brand(p, b).", ["n", "b"])
    return out.withColumn("n", F.col("n").cast("int"))


@operator("SELECT x.n_nationkey AS a, y.n_nationkey AS b FROM nation x JOIN nation y ON x.n_regionkey < y.n_regionkey")
def join_theta(spark, d):
    n = read_table(spark, d, "nation", ["n_nationkey", "n_regionkey"])
    # 25 rows in the model at any scale; the smaller side is broadcast.
    x, y = n.toDF("a", "ra"), n.toDF("b", "rb")
    return x.join(F.broadcast(y), F.col("ra") < F.col("rb")).select("a", "b")


@operator("SELECT b.item_id, d.doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def join_contains(spark, d):
    b, t = read_table(spark, d, "benchmark", ["item_id", "text"]).withColumnRenamed("text", "phrase"), read_table(spark, d, "documents", ["doc_id", "text"])
    return t.join(b, F.col("text").contains(F.col("phrase"))).select("item_id", "doc_id")


_SPANS = "SELECT user_id, event_id AS start_id, (epoch_us(ts) // 1000000) AS lo, (epoch_us(ts) // 1000000) + 3600 AS hi FROM events WHERE event_type = 'error'"


@operator(f"SELECT e.event_id, s.start_id FROM events e JOIN ({_SPANS}) s ON s.user_id = e.user_id WHERE (epoch_us(e.ts) // 1000000) >= s.lo AND (epoch_us(e.ts) // 1000000) < s.hi")
def join_range(spark, d):
    e = read_table(spark, d, "events", ["event_id", "user_id", "ts", "event_type"]).withColumn("at", F.col("ts").cast("timestamp").cast("bigint"))
    spans = e.where("event_type = 'error'").select("user_id", F.col("event_id").alias("start_id"), F.col("at").alias("lo"), (F.col("at") + 3600).alias("hi"))
    return range_join(e.select("event_id", "user_id", "at"), spans, "user_id", "at", "lo", "hi", 3600).select("event_id", "start_id")


@operator(
    "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_id <> y.event_id "
    "WHERE x.event_type = 'error' AND y.event_type = 'purchase' AND abs((epoch_us(x.ts) // 1000000) - (epoch_us(y.ts) // 1000000)) <= 86400"
)
def join_interval(spark, d):
    e = read_table(spark, d, "events", ["event_id", "user_id", "ts", "event_type"]).withColumn("at", F.col("ts").cast("timestamp").cast("bigint"))
    x = e.where("event_type = 'error'").select("user_id", F.col("event_id").alias("a"), (F.col("at") - 86400).alias("lo"), (F.col("at") + 86401).alias("hi"))
    y = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), "at")
    return range_join(y, x, "user_id", "at", "lo", "hi", 86400).select("a", "b")


@operator(
    "SELECT e.event_id, p.event_id AS last_purchase FROM (SELECT * FROM events WHERE event_type = 'error') e "
    "ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts >= p.ts"
)
def join_asof(spark, d):
    e = read_table(spark, d, "events", ["event_id", "user_id", "ts", "event_type"])
    left = e.where("event_type = 'error'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("last_purchase"))
    return as_of(left, right, "user_id", "ts", "ts", "last_purchase").select("event_id", "last_purchase")


@operator("SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity >= 49)")
def join_semi(spark, d):
    return read_table(spark, d, "part", ["p_partkey"]).join(read_table(spark, d, "lineitem", ["l_partkey"], "l_quantity >= 49"), F.col("p_partkey") == F.col("l_partkey"), "left_semi")


@operator(
    "SELECT coalesce(a.p, b.p) AS p, coalesce(a.n, 0) AS c_nr, coalesce(b.n, 0) AS c_r FROM (SELECT l_partkey AS p, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1) a "
    "FULL JOIN (SELECT l_partkey AS p, count(*) AS n FROM lineitem WHERE l_returnflag = 'A' GROUP BY 1) b ON a.p = b.p"
)
def join_outer_counters(spark, d):
    count = lambda flag, n: read_table(spark, d, "lineitem", ["l_partkey"], f"l_returnflag = '{flag}'").groupBy(F.col("l_partkey").alias("p")).agg(F.count(F.lit(1)).alias(n))
    both = count("R", "c_nr").join(count("A", "c_r"), "p", "full_outer")
    return both.select("p", F.coalesce("c_nr", F.lit(0)).alias("c_nr"), F.coalesce("c_r", F.lit(0)).alias("c_r"))


@operator("SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross(spark, d):
    return read_table(spark, d, "region", ["r_name"]).crossJoin(read_table(spark, d, "nation", ["n_name"]))


@operator("SELECT o_custkey AS c, l_partkey AS p, count(*) AS m FROM orders JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) ON l_orderkey = o_orderkey GROUP BY 1, 2")
def count_derivations(spark, d):
    f = _order_lines(spark, d)
    both = f["ordered"].join(f["holds"], F.col("o_orderkey") == F.col("l_orderkey"))
    return both.groupBy(F.col("o_custkey").alias("c"), F.col("l_partkey").alias("p")).agg(F.count(F.lit(1)).alias("m"))


@operator("SELECT l_returnflag, count(DISTINCT l_partkey) AS n_parts, count(DISTINCT l_suppkey) AS n_supps FROM lineitem GROUP BY 1")
def agg_distinct(spark, d):
    return read_table(spark, d, "lineitem", ["l_returnflag", "l_partkey", "l_suppkey"]).groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("n_parts"), F.count_distinct("l_suppkey").alias("n_supps"))


@operator()
def agg_approx_distinct(spark, d):
    return read_table(spark, d, "lineitem", ["l_returnflag", "l_partkey"]).groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("n_parts"))


@operator(
    "SELECT l_returnflag, l_linestatus, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS sum_qty, round(avg(l_quantity), 4) AS avg_qty, min(l_shipdate) AS first_ship, max(l_quantity) AS max_qty, "
    "count(*) FILTER (l_discount > 0.05) AS n_discounted FROM lineitem GROUP BY 1, 2"
)
def agg_basic(spark, d):
    t = read_table(spark, d, "lineitem", ["l_returnflag", "l_linestatus", "l_quantity", "l_shipdate", "l_discount"])
    return t.groupBy("l_returnflag", "l_linestatus").agg(
        F.sum(F.col("l_quantity").cast("bigint")).alias("sum_qty"),
        F.round(F.avg("l_quantity"), 4).alias("avg_qty"),
        F.min("l_shipdate").alias("first_ship"),
        F.max("l_quantity").alias("max_qty"),
        F.expr("count(*) FILTER (WHERE l_discount > 0.05)").alias("n_discounted"),
    )


_CUBED = "SELECT p_type, p_brand, count(*) AS n FROM part GROUP BY {}"


@operator(_CUBED.format("ROLLUP (p_type, p_brand)"))
def agg_rollup(spark, d):
    return read_table(spark, d, "part", ["p_type", "p_brand"]).rollup("p_type", "p_brand").agg(F.count(F.lit(1)).alias("n"))


@operator(_CUBED.format("CUBE (p_type, p_brand)"))
def agg_cube(spark, d):
    return read_table(spark, d, "part", ["p_type", "p_brand"]).cube("p_type", "p_brand").agg(F.count(F.lit(1)).alias("n"))


@operator(_CUBED.format("GROUPING SETS ((p_type), (p_brand), ())"))
def agg_grouping_sets(spark, d):
    t = read_table(spark, d, "part", ["p_type", "p_brand"])
    return t.groupingSets([[F.col("p_type")], [F.col("p_brand")], []], "p_type", "p_brand").agg(F.count(F.lit(1)).alias("n"))


@operator(
    "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'error') AS error, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1"
)
def agg_pivot(spark, d):
    t = read_table(spark, d, "events", ["user_id", "event_type"])
    return t.groupBy("user_id").pivot("event_type", ["click", "error", "purchase"]).agg(F.count(F.lit(1))).na.fill(0)


@operator("SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY 1")
def agg_percentile(spark, d):
    t = read_table(spark, d, "lineitem", ["l_returnflag", "l_extendedprice"])
    return t.groupBy("l_returnflag").agg(F.round(F.percentile("l_extendedprice", 0.5), 4).alias("median"), F.round(F.percentile("l_extendedprice", 0.9), 4).alias("p90"))


def _by_user():
    return W.partitionBy("user_id").orderBy("ts", "event_id")


@operator("SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events")
def win_successor(spark, d):
    return read_table(spark, d, "events").select("event_id", F.lead("event_id").over(_by_user()).alias("nxt"), F.lag("event_type").over(_by_user()).alias("before"))


@operator(
    "SELECT c_custkey, CAST(rank() OVER w AS BIGINT) AS r, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(row_number() OVER v AS BIGINT) AS rn, CAST(ntile(4) OVER v AS BIGINT) AS q FROM customer "
    "WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment), v AS (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey)"
)
def win_rank(spark, d):
    w, v = W.partitionBy("c_nationkey").orderBy("c_mktsegment"), W.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")
    ranks = {"r": F.rank().over(w), "dr": F.dense_rank().over(w), "rn": F.row_number().over(v), "q": F.ntile(4).over(v)}
    return read_table(spark, d, "customer").select("c_custkey", *[c.cast("bigint").alias(n) for n, c in ranks.items()])


@operator("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS upto, CAST(sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 2 PRECEDING) AS BIGINT) AS last3 FROM events")
def win_running(spark, d):
    return read_table(spark, d, "events").select("event_id", F.count(F.lit(1)).over(_by_user()).alias("upto"), F.sum("event_id").over(_by_user().rowsBetween(-2, 0)).alias("last3"))


@operator("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY (epoch_us(ts) // 1000000) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS in_day FROM events")
def win_range(spark, d):
    w = W.partitionBy("user_id").orderBy(F.col("ts").cast("timestamp").cast("bigint")).rangeBetween(-86400, 0)
    return read_table(spark, d, "events").select("event_id", F.count(F.lit(1)).over(w).alias("in_day"))


_KEYED = "md5(concat(CAST(o_orderkey AS VARCHAR), '/', '7'))"


@operator(f"SELECT o_orderkey FROM orders ORDER BY {_KEYED}, o_orderkey LIMIT 1000")
def topk_md5(spark, d):
    return read_table(spark, d, "orders", ["o_orderkey"]).orderBy(F.md5(F.concat(F.col("o_orderkey").cast("string"), F.lit("/7"))), "o_orderkey").limit(1000)


@operator(f"SELECT o_orderkey FROM orders WHERE substr({_KEYED}, 1, 1) < '4'")
def sample_hash(spark, d):
    return read_table(spark, d, "orders", ["o_orderkey"]).where(F.substring(F.md5(F.concat(F.col("o_orderkey").cast("string"), F.lit("/7"))), 1, 1) < "4")


_A, _B = "SELECT l_partkey AS p FROM lineitem WHERE l_quantity < 3", "SELECT l_partkey AS p FROM lineitem WHERE l_discount > 0.09"


def _sets(spark, d):
    t = read_table(spark, d, "lineitem", ["l_partkey", "l_quantity", "l_discount"])
    return t.where("l_quantity < 3").select(F.col("l_partkey").alias("p")), t.where("l_discount > 0.09D").select(F.col("l_partkey").alias("p"))


@operator(f"{_A} UNION {_B}")
def set_union(spark, d):
    a, b = _sets(spark, d)
    return a.union(b).distinct()


@operator(f"{_A} INTERSECT {_B}")
def set_intersect(spark, d):
    a, b = _sets(spark, d)
    return a.intersect(b)


@operator(f"{_A} EXCEPT {_B}")
def set_except(spark, d):
    a, b = _sets(spark, d)
    return a.subtract(b)


@operator(f"{_A} EXCEPT ALL {_B}")
def set_exceptall(spark, d):
    a, b = _sets(spark, d)
    return a.exceptAll(b)


@operator("SELECT c_custkey FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)")
def sub_exists(spark, d):
    sql = "SELECT c_custkey FROM {customer} c WHERE NOT EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)"
    return spark.sql(sql, customer=read_table(spark, d, "customer"), orders=read_table(spark, d, "orders"))


@operator(
    "SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) AS host, upper(substr(url, 1, 5)) AS head, length(url) AS n, md5(url) AS h, replace(url, 'http', 'x') AS r, split_part(url, '/', 4) AS part FROM pages"
)
def fn_string(spark, d):
    u = F.col("url")
    return read_table(spark, d, "pages", ["page_id", "url"]).select(
        "page_id",
        F.regexp_extract(u, "://([^/?#]+)", 1).alias("host"),
        F.upper(F.substring(u, 1, 5)).alias("head"),
        F.length(u).cast("bigint").alias("n"),
        F.md5(u).alias("h"),
        F.replace(u, F.lit("http"), F.lit("x")).alias("r"),
        F.split_part(u, F.lit("/"), F.lit(4)).alias("part"),
    )


@operator(
    "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS month, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(dayofyear(o_orderdate) AS BIGINT) AS doy, strftime(o_orderdate, '%Y-%m-%d') AS day, "
    "CAST(date_diff('day', DATE '1990-01-01', o_orderdate::DATE) AS BIGINT) AS days FROM orders"
)
def fn_date(spark, d):
    o = F.col("o_orderdate")
    return read_table(spark, d, "orders", ["o_orderkey", "o_orderdate"]).select(
        "o_orderkey",
        F.date_trunc("month", o).cast("timestamp_ntz").alias("month"),
        F.year(o).cast("bigint").alias("y"),
        F.dayofyear(o).cast("bigint").alias("doy"),
        F.date_format(o, "yyyy-MM-dd").alias("day"),
        F.datediff(F.to_date(o), F.lit("1990-01-01").cast("date")).cast("bigint").alias("days"),
    )


@operator(
    "SELECT c_custkey, CAST(floor(c_acctbal) AS BIGINT) AS f, abs(c_acctbal) AS a, round(c_acctbal / 7, 3) AS r, c_custkey % 7 AS m, greatest(c_custkey, 100) AS g, least(c_custkey, 100) AS l, CAST(pow(c_nationkey, 2) AS BIGINT) AS p FROM customer"
)
def fn_math(spark, d):
    b = F.col("c_acctbal")
    return read_table(spark, d, "customer", ["c_custkey", "c_acctbal", "c_nationkey"]).select(
        "c_custkey",
        F.floor(b).alias("f"),
        F.abs(b).alias("a"),
        F.round(b / 7, 3).alias("r"),
        (F.col("c_custkey") % 7).alias("m"),
        F.greatest("c_custkey", F.lit(100).cast("bigint")).alias("g"),
        F.least("c_custkey", F.lit(100).cast("bigint")).alias("l"),
        F.pow("c_nationkey", F.lit(2)).cast("bigint").alias("p"),
    )


@operator("SELECT l_orderkey, l_linenumber, CASE l_returnflag WHEN 'A' THEN -1 WHEN 'N' THEN -2 ELSE -3 END AS hub, coalesce(nullif(l_linestatus, 'O'), 'open') AS s FROM lineitem")
def fn_case(spark, d):
    t = read_table(spark, d, "lineitem", ["l_orderkey", "l_linenumber", "l_returnflag", "l_linestatus"])
    hub = F.when(F.col("l_returnflag") == "A", -1).when(F.col("l_returnflag") == "N", -2).otherwise(-3)
    return t.select("l_orderkey", "l_linenumber", hub.alias("hub"), F.coalesce(F.nullif("l_linestatus", F.lit("O")), F.lit("open")).alias("s"))


@operator(
    "SELECT vec_id, CAST(len(embedding) AS BIGINT) AS n, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS n_pos, round(CAST(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))) AS DOUBLE), 4) AS sq FROM embeddings"
)
def fn_array(spark, d):
    e = F.col("embedding")
    return read_table(spark, d, "embeddings", ["vec_id", "embedding"]).select(
        "vec_id",
        F.size(e).cast("bigint").alias("n"),
        F.size(F.filter(e, lambda x: x > 0)).cast("bigint").alias("n_pos"),
        F.round(F.aggregate(e, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")), 4).alias("sq"),
    )


@operator("SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY 1")
def fn_map(spark, d):
    each = read_table(spark, d, "events", ["user_id", "event_type"]).groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = each.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.size(F.map_keys("m")).cast("bigint").alias("kinds"))


@operator("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(spark, d):
    return read_table(spark, d, "events", ["event_id", "props"]).select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@operator(
    "WITH s AS (SELECT x.vec_id AS i, y.vec_id AS j, list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) AS c FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) "
    "SELECT i, arg_max(j, ROW(c, -j)) AS j FROM s GROUP BY i"
)
def near_edges(spark, d):
    return nearest(read_table(spark, d, "embeddings", ["vec_id", "embedding"]), "vec_id", "embedding")


@operator("SELECT page_id, CASE WHEN strpos(h, '.') > 0 THEN substr(h, strpos(h, '.') + 1) ELSE '' END AS g FROM (SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) AS h FROM pages)")
def udf_builtin(spark, d):
    f = F.pandas_udf(after_first_dot, "string")
    return read_table(spark, d, "pages", ["page_id", "url"]).select("page_id", f(F.regexp_extract("url", "://([^/?#]+)", 1)).alias("g"))


@operator("SELECT s_nationkey, CAST(sum(s_suppkey * 2654435761 % 4294967291) % 4611686018427387904 AS BIGINT) AS fp FROM supplier GROUP BY 1")
def udaf_fingerprint(spark, d):
    return read_table(spark, d, "supplier", ["s_nationkey", "s_suppkey"]).groupBy("s_nationkey").agg(fingerprint("s_suppkey").alias("fp"))


@operator(
    "WITH RECURSIVE s(page_id, suffix) AS (SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) FROM pages UNION ALL "
    "SELECT page_id, substr(suffix, strpos(suffix, '.') + 1) FROM s WHERE strpos(suffix, '.') > 0) SELECT page_id, suffix FROM s WHERE suffix <> ''"
)
def udtf_suffixes(spark, d):
    spark.udtf.register("host_suffixes", Suffixes)
    hosts = read_table(spark, d, "pages", ["page_id", "url"]).select("page_id", F.regexp_extract("url", "://([^/?#]+)", 1).alias("h"))
    return spark.sql("SELECT page_id, suffix FROM {hosts} p, LATERAL host_suffixes(p.h)", hosts=hosts)


def _events(spark, d):
    return read_table(spark, d, "events", ["event_id", "user_id", "event_type", "ts"]).withColumn("ts", F.col("ts").cast("timestamp"))


@operator("SELECT (epoch_us(time_bucket(INTERVAL 1 DAY, ts)) // 1000000) AS start_s, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    """Written with windows, so that the same plan runs on a stream."""
    w = F.window("ts", "1 day")
    return _events(spark, d).groupBy(w, "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("bigint").alias("start_s"), "event_type", "n")


@operator(
    "SELECT ((epoch_us(ts) // 1000000) // 21600) * 21600 - k * 21600 AS start_s, count(*) AS n FROM events, unnest(range(4)) AS t(k) GROUP BY 1"
)
def stream_sliding(spark, d):
    w = F.window("ts", "1 day", "6 hours")
    return _events(spark, d).groupBy(w).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("bigint").alias("start_s"), "n")


@operator(
    "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 1 DAY THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), "
    "s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM g) SELECT user_id, count(*) AS n, (epoch_us(min(ts)) // 1000000) AS start_s FROM s GROUP BY user_id, sid"
)
def stream_session(spark, d):
    w = F.session_window("ts", "1 day")
    return _events(spark, d).groupBy("user_id", w).agg(F.count(F.lit(1)).alias("n")).select("user_id", "n", F.col("session_window.start").cast("bigint").alias("start_s"))
