"""Queries for the general operators around the methods (§2.13, §2.14): joins, windows, sets, functions."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from relmodel.catalog import load
from relmodel.functions import vec
from relmodel.operators import graph, slices
from relmodel.plans import dispatch
from relmodel.session import shared_folder
from relmodel.streaming import stream
from relmodel.workloads import ORDER_CUTOFFS, TASKS, label_sql

QUERIES, SQL = {}, {}
T = ORDER_CUTOFFS[2]


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


_money = "CAST(sum(CAST({} AS DECIMAL(18,2))) AS DOUBLE)"


def money(c):
    return F.sum(F.col(c).cast("decimal(18,2)")).cast("double")


# ---- dispatcher ---------------------------------------------------------------------------------

_labels = label_sql(TASKS["customer_churn"], T)


@query("probe_batch", f"SELECT entity_id, y FROM (SELECT *, row_number() OVER (PARTITION BY y > 0 ORDER BY md5('0:' || entity_id), entity_id) AS rn FROM ({_labels})) WHERE rn <= 128")
def probe_batch(spark, sf):
    labels = slices.horizon_labels(TASKS["customer_churn"], load(spark, sf, ["customer", "orders"]), T)
    return dispatch.probe_batch(labels).select("entity_id", "y")


_raw = "SELECT 'm' || user_id AS model_id, event_type AS proxy, sum(event_id)::DOUBLE AS raw FROM events GROUP BY ALL"


def _proxies(spark, sf):
    e = load(spark, sf, ["events"])["events"]
    return e.groupBy(F.concat(F.lit("m"), F.col("user_id").cast("string")).alias("model_id"), F.col("event_type").alias("proxy")).agg(F.sum("event_id").cast("double").alias("raw"))


@query("proxy_rank_combine", f"SELECT model_id, round(avg(r), 9) AS score FROM (SELECT *, percent_rank() OVER (PARTITION BY proxy ORDER BY raw) AS r FROM ({_raw}) WHERE proxy IN ('click', 'view')) GROUP BY model_id")
def proxy_rank_combine(spark, sf):
    return dispatch.combine_proxies(_proxies(spark, sf), ("click", "view"))


@query("proxy_calibrated", f"WITH x AS (SELECT proxy, raw, count(*) AS n FROM ({_raw}) GROUP BY ALL), r AS (SELECT proxy, raw, (sum(n) OVER (PARTITION BY proxy ORDER BY raw) - n / 2e0) / sum(n) OVER (PARTITION BY proxy) AS share FROM x) SELECT a.model_id, a.proxy, round(r.share, 9) AS score FROM ({_raw}) a JOIN r ON r.proxy = a.proxy AND r.raw = a.raw")
def proxy_calibrated(spark, sf):
    x = _proxies(spark, sf)
    return dispatch.calibrate(x, x).select("model_id", "proxy", F.round("score", 9).alias("score"))


@query("select_base", f"SELECT model_id, score FROM (SELECT model_id, round(avg(r), 9) AS score FROM (SELECT *, percent_rank() OVER (PARTITION BY proxy ORDER BY raw) AS r FROM ({_raw}) WHERE proxy IN ('click', 'view')) GROUP BY model_id) ORDER BY score DESC, model_id LIMIT 1")
def select_base(spark, sf):
    return dispatch.select_base(dispatch.combine_proxies(_proxies(spark, sf), ("click", "view")))


_ledger = "SELECT event_type AS model_id, 'u' || user_id AS task_key, event_id AS step, value / 97.3e0 AS perf FROM events"


def _obs(spark, sf):
    return load(spark, sf, ["events"])["events"].select(F.col("event_type").alias("model_id"), F.concat(F.lit("u"), F.col("user_id").cast("string")).alias("task_key"), F.col("event_id").alias("step"), (F.col("value") / 97.3).alias("perf"))


_ema = f"""WITH RECURSIVE o AS (SELECT *, row_number() OVER (PARTITION BY model_id, task_key ORDER BY step) AS k, count(*) OVER (PARTITION BY model_id, task_key) AS n FROM ({_ledger})),
r AS (SELECT model_id, task_key, step, k, n, perf AS ema FROM o WHERE k = 1 UNION ALL SELECT o.model_id, o.task_key, o.step, o.k, o.n, r.ema * (1 - 0.3e0) + o.perf * 0.3e0 FROM r JOIN o ON o.model_id = r.model_id AND o.task_key = r.task_key AND o.k = r.k + 1)"""


@query("ema_ledger", f"{_ema} SELECT model_id, task_key, round(ema, 8) AS ema FROM r WHERE k = n")
def ema_ledger(spark, sf):
    return dispatch.ema(_obs(spark, sf)).select("model_id", "task_key", F.round("ema", 8).alias("ema"))


@query("cte_recursive_ema", f"{_ema} SELECT model_id, task_key, step, round(ema, 8) AS ema FROM r")
def cte_recursive_ema(spark, sf):
    return dispatch.ema_running(_obs(spark, sf)).select("model_id", "task_key", "step", F.round("ema", 8).alias("ema"))


@query("threshold_decision", f"{_ema}, b AS (SELECT 'click' AS model_id, 'u' || user_id AS task_key, avg(value) / 100e0 AS score FROM events GROUP BY user_id), e AS (SELECT * FROM r WHERE k = n) SELECT b.model_id, b.task_key, CASE WHEN e.ema IS NULL THEN 'augment' WHEN score >= (1 - 0.05e0) * e.ema THEN 'direct' ELSE 'augment' END AS decision, CASE WHEN e.ema IS NULL THEN 'no_history' WHEN score >= (1 - 0.05e0) * e.ema THEN 'direct' ELSE 'augment' END AS reason FROM b LEFT JOIN e ON e.model_id = b.model_id AND e.task_key = b.task_key")
def threshold_decision(spark, sf):
    e = load(spark, sf, ["events"])["events"]
    best = e.groupBy(F.lit("click").alias("model_id"), F.concat(F.lit("u"), F.col("user_id").cast("string")).alias("task_key")).agg((F.avg("value") / 100).alias("score"))
    return dispatch.decisions(best, dispatch.ema(_obs(spark, sf))).select("model_id", "task_key", "decision", "reason")


# ---- report ---------------------------------------------------------------------------------------

_pred = "SELECT c_custkey AS entity_id, c_mktsegment, n_name, floor(c_acctbal) / 10000e0 AS score FROM customer JOIN nation ON n_nationkey = c_nationkey"


def _preds(spark, sf):
    t = load(spark, sf, ["customer", "nation"])
    c = t["customer"].join(F.broadcast(t["nation"]), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 rows
    return c.select(F.col("c_custkey").alias("entity_id"), "c_mktsegment", "n_name", (F.floor("c_acctbal") / 10000).alias("score"))


for _kind, _method in (("cube", "cube"), ("rollup", "rollup")):
    query(f"report_{_kind}", f"SELECT c_mktsegment, n_name, count(*) AS n, round(avg(score), 6) AS mean_score FROM ({_pred}) GROUP BY {_kind.upper()} (c_mktsegment, n_name)")(
        lambda spark, sf, m=_method: getattr(_preds(spark, sf), m)("c_mktsegment", "n_name").agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("mean_score")))


@query("report_grouping_sets", f"SELECT c_mktsegment, n_name, count(*) AS n FROM ({_pred}) GROUP BY GROUPING SETS ((c_mktsegment), (n_name), ())")
def report_grouping_sets(spark, sf):
    return _preds(spark, sf).groupingSets([["c_mktsegment"], ["n_name"], []], "c_mktsegment", "n_name").agg(F.count("*").alias("n"))


@query("report_distribution", f"SELECT count(*) AS n, " + ", ".join(f"round(quantile_cont(score, {q}), 6) AS q{int(100 * q):02d}" for q in (0.05, 0.25, 0.5, 0.75, 0.95)) + f" FROM ({_pred})")
def report_distribution(spark, sf):
    from relmodel.plans.report import score_distribution

    return score_distribution(_preds(spark, sf))


@query("report_top", f"SELECT entity_id, round(score, 6) AS score FROM ({_pred}) ORDER BY score DESC, entity_id LIMIT 5")
def report_top(spark, sf):
    from relmodel.plans.report import top_entities

    return top_entities(_preds(spark, sf))


# ---- joins ------------------------------------------------------------------------------------------


@query("join_inner", "SELECT o_orderpriority, count(*) AS n, " + _money.format("l_extendedprice") + " AS price FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_inner(spark, sf):
    t = load(spark, sf, ["orders", "lineitem"])
    return t["orders"].select("o_orderkey", "o_orderpriority").join(t["lineitem"].select("l_orderkey", "l_extendedprice"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), money("l_extendedprice").alias("price"))


@query("join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def join_broadcast(spark, sf):
    t = load(spark, sf, ["customer", "nation", "region"])
    dims = t["nation"].join(F.broadcast(t["region"]), F.col("n_regionkey") == F.col("r_regionkey"))  # fixed, 25 rows
    return t["customer"].join(F.broadcast(dims), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND o_totalprice > 400000 GROUP BY 1")
def join_left(spark, sf):
    t = load(spark, sf, ["customer", "orders"])
    return t["customer"].join(t["orders"].where("o_totalprice > 400000"), F.col("o_custkey") == F.col("c_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


for _how, _not in (("semi", ""), ("anti", "NOT ")):
    query(f"join_{_how}", f"SELECT c_custkey FROM customer WHERE {_not}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 450000)")(
        lambda spark, sf, how=_how: load(spark, sf, ["customer"])["customer"].join(load(spark, sf, ["orders"])["orders"].where("o_totalprice > 450000"), F.col("o_custkey") == F.col("c_custkey"), f"left_{how}").select("c_custkey"))


@query("join_cross", "SELECT count(*) AS n FROM region a CROSS JOIN nation b")
def join_cross(spark, sf):
    t = load(spark, sf, ["region", "nation"])
    return t["region"].crossJoin(t["nation"]).agg(F.count("*").alias("n"))  # 5 × 25 rows


@query("join_range", "SELECT o.o_orderkey, count(l.l_orderkey) AS n FROM orders o LEFT JOIN lineitem l ON l.l_orderkey = o.o_orderkey AND l.l_shipdate > o.o_orderdate AND l.l_shipdate <= o.o_orderdate + INTERVAL 180 DAY GROUP BY 1")
def join_range(spark, sf):
    t = load(spark, sf, ["orders", "lineitem"])
    inside = F.expr("l_orderkey = o_orderkey AND l_shipdate > o_orderdate AND l_shipdate <= o_orderdate + INTERVAL 180 DAYS")
    return t["orders"].select("o_orderkey", "o_orderdate").join(t["lineitem"].select("l_orderkey", "l_shipdate"), inside, "left").groupBy("o_orderkey").agg(F.count("l_orderkey").alias("n"))


@query("join_asof", "SELECT e.event_id, max(p.event_id) AS view_id FROM events e JOIN events p ON p.user_id = e.user_id AND p.event_type = 'view' AND p.event_id <= e.event_id WHERE e.event_type = 'purchase' GROUP BY 1")
def join_asof(spark, sf):
    e = load(spark, sf, ["events"])["events"]
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = e.select("event_id", "event_type", F.max(F.when(F.col("event_type") == "view", F.col("event_id"))).over(w).alias("view_id"))
    return last.where("event_type = 'purchase' AND view_id IS NOT NULL").select("event_id", "view_id")


@query("join_lateral", "SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM customer JOIN orders ON o_custkey = c_custkey) WHERE rn <= 2")
def join_lateral(spark, sf):
    t = load(spark, sf, ["customer", "orders"])
    best = t["orders"].where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")
    return t["customer"].select("c_custkey").lateralJoin(best)


# ---- windows, sets, top-k ------------------------------------------------------------------------


@query("window_rank", "SELECT o_orderkey, rank() OVER w::INT AS r, dense_rank() OVER w::INT AS d, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)::INT AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice)".replace("OVER w::INT", "OVER w"))
def window_rank(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice")
    return load(spark, sf, ["orders"])["orders"].select("o_orderkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("d"), F.ntile(4).over(Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")).alias("q"))


@query("window_lag", "SELECT o_orderkey, coalesce(date_diff('day', lag(o_orderdate) OVER w, o_orderdate), -1)::BIGINT AS gap, first_value(o_orderkey) OVER w AS first_order FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def window_lag(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    gap = F.datediff("o_orderdate", F.lag("o_orderdate").over(w))
    return load(spark, sf, ["orders"])["orders"].select("o_orderkey", F.coalesce(gap, F.lit(-1)).cast("long").alias("gap"), F.first_value("o_orderkey").over(w).alias("first_order"))


@query("window_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS n, coalesce(max(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING), -1) AS s FROM events")
def window_frame(spark, sf):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return load(spark, sf, ["events"])["events"].select("event_id", F.count("*").over(w.rangeBetween(-1000, 0)).alias("n"), F.coalesce(F.max("event_id").over(w.rowsBetween(-3, -1)), F.lit(-1)).alias("s"))


_a, _b = "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45", "SELECT l_partkey AS k FROM lineitem WHERE l_discount > 0.08"
for _name, _op in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    def _sets(spark, sf, name=_name):
        li = load(spark, sf, ["lineitem"])["lineitem"]
        a, b = (li.where(p).select(F.col("l_partkey").alias("k")) for p in ("l_quantity > 45", "l_discount > 0.08"))
        return {"union": lambda: a.union(b).distinct(), "union_all": lambda: a.unionAll(b), "intersect": lambda: a.intersect(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[name]()

    query(f"set_{_name}", f"{_a} {_op} {_b}")(_sets)


@query("topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def topk(spark, sf):
    return load(spark, sf, ["orders"])["orders"].select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("predicates", "SELECT p_partkey FROM part WHERE (p_brand IN ('Brand#11', 'Brand#12') OR p_name LIKE '%a%') AND p_size BETWEEN 10 AND 30 AND NOT p_type IS NULL")
def predicates(spark, sf):
    p = load(spark, sf, ["part"])["part"]
    return p.where((F.col("p_brand").isin("Brand#11", "Brand#12") | F.col("p_name").like("%a%")) & F.col("p_size").between(10, 30) & F.col("p_type").isNotNull()).select("p_partkey")


@query("aggregates", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS d, round(quantile_cont(o_totalprice, 0.5), 4) AS median, mode(o_orderpriority ORDER BY o_orderpriority) IS NOT NULL AS has_mode, round(stddev_pop(o_totalprice), 3) AS sd FROM orders GROUP BY 1")
def aggregates(spark, sf):
    return load(spark, sf, ["orders"])["orders"].groupBy("o_orderstatus").agg(F.count_distinct("o_custkey").alias("d"), F.round(F.expr("percentile(o_totalprice, 0.5)"), 4).alias("median"), F.mode("o_orderpriority").isNotNull().alias("has_mode"), F.round(F.stddev_pop("o_totalprice"), 3).alias("sd"))


# ---- functions ----------------------------------------------------------------------------------


@query("json_props", "SELECT CAST(regexp_extract(props, '([0-9]+)', 1) AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
def json_props(spark, sf):
    return load(spark, sf, ["events"])["events"].groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("string_tokens", "SELECT token, count(*) AS n FROM (SELECT unnest(string_split(lower(p_name), ' ')) AS token FROM part) GROUP BY 1")
def string_tokens(spark, sf):
    return load(spark, sf, ["part"])["part"].select(F.explode(F.split(F.lower("p_name"), " ")).alias("token")).groupBy("token").agg(F.count("*").alias("n"))


@query("date_functions", "SELECT year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, count(*) AS n, max(date_diff('day', TIMESTAMP '1995-01-01', o_orderdate))::INT AS last_day FROM orders GROUP BY 1, 2")
def date_functions(spark, sf):
    return load(spark, sf, ["orders"])["orders"].groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("n"), F.max(F.datediff("o_orderdate", F.to_date(F.lit("1995-01-01")))).alias("last_day"))


@query("math_functions", "SELECT o_orderkey, round(ln(o_totalprice + 1), 9) AS l, round(sqrt(o_totalprice), 9) AS s, greatest(o_totalprice, 200000) AS g, round(exp(-o_totalprice / 100000), 9) AS e FROM orders")
def math_functions(spark, sf):
    p = F.col("o_totalprice")
    return load(spark, sf, ["orders"])["orders"].select("o_orderkey", F.round(F.log1p(p), 9).alias("l"), F.round(F.sqrt(p), 9).alias("s"), F.greatest(p, F.lit(200000.0)).alias("g"), F.round(F.exp(-p / 100000), 9).alias("e"))


@query("null_functions", "SELECT c_custkey, coalesce(CASE WHEN c_acctbal < 0 THEN NULL ELSE c_acctbal END, -1) AS b, nullif(c_mktsegment, 'BUILDING') IS NULL AS building FROM customer")
def null_functions(spark, sf):
    c = load(spark, sf, ["customer"])["customer"]
    return c.select("c_custkey", F.coalesce(F.when(F.col("c_acctbal") < 0, None).otherwise(F.col("c_acctbal")), F.lit(-1.0)).alias("b"), F.nullif(F.col("c_mktsegment"), F.lit("BUILDING")).isNull().alias("building"))


@query("array_functions", "SELECT l_orderkey, list_sort(list(DISTINCT l_linenumber))[1]::INT AS first_line, len(list(DISTINCT l_linenumber))::INT AS n FROM lineitem GROUP BY 1")
def array_functions(spark, sf):
    own = load(spark, sf, ["lineitem"])["lineitem"].groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_linenumber")).alias("a"))
    return own.select("l_orderkey", F.element_at("a", 1).alias("first_line"), F.size("a").alias("n"))


@query("vec_ops", "SELECT vec_id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 5) AS norm2, round(list_cosine_similarity(embedding::DOUBLE[], list_transform(range(64), lambda i: (i + 1)::DOUBLE)), 5) AS cos FROM embeddings")
def vec_ops(spark, sf):
    e = spark.read.parquet(f"{sf}/embeddings.parquet").withColumn("d", F.transform("embedding", lambda x: x.cast("double")))
    line = F.transform(F.sequence(F.lit(1), F.lit(64)), lambda i: i.cast("double"))
    return e.select("vec_id", F.round(vec.dot(F.col("d"), F.col("d")), 5).alias("norm2"), F.round(vec.cosine(F.col("d"), line), 5).alias("cos"))


@query("vector_mean", "SELECT label, (i - 1)::INT AS dim, round(avg(embedding[i]::DOUBLE), 6) AS v FROM embeddings, range(1, 65) t(i) GROUP BY ALL")
def vector_mean(spark, sf):
    """U4: mean vector per group as exploded sums, cheap to combine."""
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    return e.select("label", F.posexplode("embedding").alias("dim", "x")).groupBy("label", "dim").agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("v"))


@query("unpivot_pivot", "SELECT event_type, count(*) FILTER (user_id % 2 = 0) AS even, count(*) FILTER (user_id % 2 = 1) AS odd FROM events GROUP BY 1")
def unpivot_pivot(spark, sf):
    e = load(spark, sf, ["events"])["events"].select("event_type", F.when(F.col("user_id") % 2 == 0, "even").otherwise("odd").alias("side"))
    wide = e.groupBy("event_type").pivot("side", ["even", "odd"]).count()
    back = wide.unpivot("event_type", ["even", "odd"], "side", "n")
    return back.groupBy("event_type").pivot("side", ["even", "odd"]).agg(F.coalesce(F.sum("n"), F.lit(0)))


@query("binning", "SELECT least(greatest(floor((o_totalprice - 0) / 50000) + 1, 0), 11)::BIGINT AS b, count(*) AS n FROM orders GROUP BY 1")
def binning(spark, sf):
    return load(spark, sf, ["orders"])["orders"].groupBy(F.expr("width_bucket(o_totalprice, 0, 500000, 10)").alias("b")).agg(F.count("*").alias("n"))


@query("sql_args", "SELECT count(*) AS n FROM orders WHERE o_totalprice > 123456 AND o_orderstatus = 'F'")
def sql_args(spark, sf):
    """Literals are bound, not pasted."""
    return spark.sql("SELECT count(*) AS n FROM {orders} WHERE o_totalprice > :low AND o_orderstatus = :status", args={"low": 123456.0, "status": "F"}, orders=load(spark, sf, ["orders"])["orders"])


# ---- windows of time, streams -------------------------------------------------------------------


def _batch_events(spark, sf):
    return load(spark, sf, ["events"])["events"].withColumn("at", F.col("ts").cast("timestamp"))


_w = "epoch({})::BIGINT"


def _start(df):
    return df.select(F.unix_timestamp(F.col("w.start")).alias("start"), "user_id", "n")


@query("tumbling_windows", "SELECT epoch(time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01'))::BIGINT AS start, user_id, count(*) AS n FROM events GROUP BY ALL")
def tumbling_windows(spark, sf):
    return _start(stream.activity(_batch_events(spark, sf)))


@query("sliding_windows", "SELECT epoch(time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - to_hours(12 * k))::BIGINT AS start, user_id, count(*) AS n FROM events, range(2) t(k) GROUP BY ALL")
def sliding_windows(spark, sf):
    return _start(stream.activity(_batch_events(spark, sf), "1 day", "12 hours"))


@query("session_windows_batch", "SELECT floor(epoch(min(ts)))::BIGINT AS start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def session_windows_batch(spark, sf):
    return _start(stream.activity(_batch_events(spark, sf), gap="6 hours"))


def replay(spark, sf, build, mode: str = "append", key: list[str] | None = None):
    """Runs a streaming query over the event files to the end and returns what it wrote; in update
    mode the last row of each key."""
    base = shared_folder(spark)
    path = f"{base}/relmodel-stream-{uuid.uuid4().hex}"
    out = build(stream.event_stream(spark, f"{sf}/events.parquet"))

    def keep(df, i):
        df.withColumn("batch_", F.lit(i)).write.mode("append").parquet(f"{path}/out")

    out.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    got = spark.read.parquet(f"{path}/out")
    if key:
        got = got.groupBy(*key).agg(*(F.max_by(c, "batch_").alias(c) for c in got.columns if c not in (*key, "batch_")))
        return got
    return got.drop("batch_")


_spark_schema_path = "event_stream reads a folder or a file of Parquet"


@query("stream_ingest", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_ingest(spark, sf):
    return replay(spark, _folder(spark, sf), lambda s: s.select("event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


def _folder(spark, sf):
    """Streams read folders; a single Parquet file is copied into one in the shared folder."""
    base = shared_folder(spark)
    path = f"{base}/relmodel-events-{uuid.uuid4().hex}"
    load(spark, sf, ["events"])["events"].write.parquet(f"{path}/events.parquet")
    return path


@query("stream_latest_k", "SELECT user_id, list(event_id ORDER BY ts DESC, event_id)[1:4]::VARCHAR AS ids FROM events GROUP BY 1")
def stream_latest_k(spark, sf):
    got = replay(spark, _folder(spark, sf), lambda s: stream.latest_k(s, 4), "update", ["user_id"])
    return got.select("user_id", F.concat(F.lit("["), F.array_join(F.transform("event_ids", lambda x: x.cast("string")), ", "), F.lit("]")).alias("ids"))


@query("stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedup(spark, sf):
    return replay(spark, _folder(spark, sf), stream.deduplicated).agg(F.count("*").alias("n"))


@query("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(spark, sf):
    c = load(spark, sf, ["customer"])["customer"].select("c_custkey", "c_mktsegment")
    return replay(spark, _folder(spark, sf), lambda s: stream.enriched(s, c).select("c_mktsegment")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("stream_ema", None)
def stream_ema(spark, sf):
    got = replay(spark, _folder(spark, sf), lambda s: stream.ema_state(s.select(F.col("event_type").alias("model_id"), F.col("event_id").alias("step"), (F.col("value") / 97.3).alias("perf"))), "update", ["model_id"])
    return got.select("model_id", F.round("ema", 8).alias("ema"))


SQL["stream_ema"] = f"""WITH RECURSIVE o AS (SELECT event_type AS model_id, value / 97.3e0 AS perf, row_number() OVER (PARTITION BY event_type ORDER BY event_id) AS k, count(*) OVER (PARTITION BY event_type) AS n FROM events),
r AS (SELECT model_id, k, n, perf AS ema FROM o WHERE k = 1 UNION ALL SELECT o.model_id, o.k, o.n, r.ema * (1 - 0.3e0) + o.perf * 0.3e0 FROM r JOIN o ON o.model_id = r.model_id AND o.k = r.k + 1)
SELECT model_id, round(ema, 8) AS ema FROM r WHERE k = n"""


@query("stream_stream_join", "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def stream_stream_join(spark, sf):
    return replay(spark, _folder(spark, sf), lambda s: stream.purchases_after_clicks(s.where("event_type = 'click'"), s.where("event_type = 'purchase'"), "6 HOURS"))


@query("source_round_trip", " UNION ALL ".join(f"SELECT '{f}' AS format, count(*) AS n FROM part" for f in ("csv", "json", "orc", "parquet", "text")))
def source_round_trip(spark, sf):
    """O2: every format gives the rows back."""
    path, p, out = f"{shared_folder(spark)}/relmodel-formats-{uuid.uuid4().hex}", load(spark, sf, ["part"])["part"], None
    for f in ("csv", "json", "orc", "parquet"):
        p.write.format(f).save(f"{path}/{f}")
        same = spark.read.schema(p.schema).format(f).load(f"{path}/{f}").intersectAll(p)
        row = same.agg(F.count("*").alias("n")).select(F.lit(f).alias("format"), "n")
        out = row if out is None else out.unionAll(row)
    lines = p.select(F.to_json(F.struct(*p.columns)).alias("value"))
    lines.write.text(f"{path}/text")
    same = spark.read.text(f"{path}/text").select(F.from_json("value", p.schema).alias("r")).select("r.*").intersectAll(p)
    return out.unionAll(same.agg(F.count("*").alias("n")).select(F.lit("text").alias("format"), "n"))


@query("asof_cogroup", "SELECT event_id, (SELECT o_orderkey FROM orders o WHERE o.o_custkey = e.user_id AND o.o_orderdate <= e.ts ORDER BY o_orderdate DESC, o_orderkey LIMIT 1) AS o_orderkey FROM events e")
def asof_cogroup(spark, sf):
    """The last order before each event, by cogrouped frames of one customer."""
    import pandas as pd

    t = load(spark, sf, ["events", "orders"])
    e = t["events"].select("event_id", "user_id", "ts")
    o = t["orders"].select("o_orderkey", F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts"))

    def last(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        right = right.sort_values(["ts", "o_orderkey"], ascending=[True, False])
        out = pd.merge_asof(left.sort_values("ts"), right[["ts", "o_orderkey"]], on="ts")
        return out[["event_id", "o_orderkey"]].astype({"o_orderkey": "Int64"})

    return e.groupBy("user_id").cogroup(o.groupBy("user_id")).applyInPandas(last, "event_id long, o_orderkey long").where("event_id IS NOT NULL")


#: Widths for layers that gather n rows: 16 times the power of two that holds them, 32 to 512.
WIDTH = "CASE WHEN n <= 2 THEN '32' WHEN n <= 4 THEN '64' WHEN n <= 8 THEN '128' WHEN n <= 16 THEN '256' ELSE '512' END"


@query("architecture_space", f"WITH w AS (SELECT DISTINCT {WIDTH} AS x FROM (SELECT count(*) AS n FROM orders GROUP BY o_custkey)) SELECT 'w' || x AS model_id, x AS widths, 1 AS depth FROM w UNION ALL SELECT 'w' || a.x || '-' || b.x, a.x || '-' || b.x, 2 FROM w a, w b UNION ALL SELECT 'w' || a.x || '-' || b.x || '-' || c.x, a.x || '-' || b.x || '-' || c.x, 3 FROM w a, w b, w c")
def architecture_space(spark, sf):
    """Every choice of widths for one to three layers, from the data source. Widths are those
    that the numbers of orders of the customers ask for."""
    from relmodel.sources.registry import GridSource

    n = load(spark, sf, ["orders"])["orders"].groupBy("o_custkey").agg(F.count("*").alias("n"))
    widths = [r.x for r in n.select(F.expr(WIDTH).alias("x")).distinct().collect()]  # at most five
    spark.dataSource.register(GridSource)
    return spark.read.format("model_grid").option("widths", ",".join(sorted(widths, key=int))).load()


@query("feature_transformers", None)
def feature_transformers(spark, sf):
    """Quantile bins of a number and hashed words of a text, as counts per bin and text length."""
    from pyspark.ml.feature import HashingTF, QuantileDiscretizer
    from pyspark.ml.functions import vector_to_array

    p = load(spark, sf, ["part"])["part"].select("p_partkey", "p_retailprice", F.split("p_name", " ").alias("words"))
    bins = QuantileDiscretizer(inputCol="p_retailprice", outputCol="bin", numBuckets=8).fit(p)
    own = HashingTF(inputCol="words", outputCol="tf", numFeatures=64).transform(bins.transform(p))
    total = F.aggregate(vector_to_array("tf"), F.lit(0.0), lambda s, v: s + v)
    return own.groupBy(F.col("bin").cast("int").alias("bin")).agg(F.count("*").alias("n"), F.sum(total - F.size("words")).alias("lost"))


@query("table_round_trip", "SELECT s_nationkey, count(*) AS n, round(sum(s_acctbal), 2) AS balance FROM supplier GROUP BY s_nationkey")
def table_round_trip(spark, sf):
    """O3: a slice saved as a table of the catalog and read by its name."""
    name = f"relmodel_{uuid.uuid4().hex}"
    load(spark, sf, ["supplier"])["supplier"].write.option("path", f"{shared_folder(spark)}/{name}").saveAsTable(name)
    return spark.table(name).groupBy("s_nationkey").agg(F.count("*").alias("n"), F.round(F.sum("s_acctbal"), 2).alias("balance"))


@query("bucketed_join", "SELECT o_custkey, count(*) AS n, max(c_acctbal) AS balance FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY o_custkey")
def bucketed_join(spark, sf):
    """Two tables bucketed by the key join and aggregate without a shuffle."""
    from relmodel.sources.registry import bucketed

    t, names = load(spark, sf, ["orders", "customer"]), []
    for n, key in (("orders", "o_custkey"), ("customer", "c_custkey")):
        names.append(f"relmodel_{n}_{uuid.uuid4().hex}")
        bucketed(t[n], names[-1], key, 8, f"{shared_folder(spark)}/{names[-1]}")
    o, c = (spark.table(n) for n in names)
    both = o.hint("merge").join(c, o.o_custkey == c.c_custkey)
    return both.groupBy("o_custkey").agg(F.count("*").alias("n"), F.max("c_acctbal").alias("balance"))


@query("online_scoring", "SELECT event_id, round(1 / (1 + exp(-(value - 50e0) / 10e0)), 6) AS score FROM events")
def online_scoring(spark, sf):
    """ST8: a stream of events scored batch by batch and appended."""
    out = f"{shared_folder(spark)}/relmodel-online-{uuid.uuid4().hex}"
    source = stream.event_stream(spark, f"{_folder(spark, sf)}/events.parquet")
    rule = F.round(1 / (1 + F.exp(-(F.col("value") - 50.0) / 10.0)), 6)
    stream.online_scores(source, lambda df: df.select("event_id", rule.alias("score")), f"{out}/rows", f"{out}/checkpoint").awaitTermination()
    return spark.read.schema("event_id long, score double").parquet(f"{out}/rows")


EMBED_WORDS = "SELECT p_partkey, unnest(list_filter(regexp_split_to_array(lower(p_name), '[^a-z0-9]+'), lambda x: x <> '')) AS w FROM part"


@query("embed_text", f"""WITH c AS (SELECT p_partkey, ('0x' || substr(md5('p_name:' || w), 1, 6))::INT AS h FROM ({EMBED_WORDS})),
s AS (SELECT p_partkey, (h // 2) % 16 AS i, sum(2 * (h % 2) - 1)::DOUBLE AS v FROM c GROUP BY ALL)
SELECT p_partkey, i::INT AS i, round(v / sqrt(sum(v * v) OVER (PARTITION BY p_partkey)), 6) AS v FROM s WHERE v <> 0""")
def embed_text(spark, sf):
    """The frozen vector of a text column, as (key, place, value) without zeros."""
    from relmodel.functions.embed import text_vector

    p = load(spark, sf, ["part"])["part"]
    return p.select("p_partkey", F.posexplode(text_vector(F.col("p_name"), "p_name")).alias("i", "v")).where("v <> 0").select("p_partkey", "i", F.round("v", 6).alias("v"))


@query("plan_limits", None)
def plan_limits(spark, sf):
    """What the sampling plan costs: the group limit must come before the shuffle; and the rows
    it reads and keeps when it runs."""
    from relmodel.operators.metrics import plan_costs

    o = load(spark, sf, ["orders"])["orders"].select(F.col("o_custkey").alias("node_id"), F.col("o_orderkey").alias("nbr_id"), F.col("o_orderdate").alias("ts"))
    kept = graph.sample_neighbours(o, 8, "latest")
    costs = spark.createDataFrame([(k, v) for k, v in plan_costs(kept).items()], "operator string, n long")
    for name, rows in (("rows_in", o.where("node_id IS NOT NULL")), ("rows_kept", kept.where("node_id IS NOT NULL"))):
        costs = costs.unionAll(rows.agg(F.count("*").alias("n")).select(F.lit(name).alias("operator"), "n"))
    return costs
