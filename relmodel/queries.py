"""Queries over the given tables by inventory id, each with its DuckDB twin where SQL can say it."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from relmodel.catalog import CATALOG, LINE_ID, check_keys, load, node_id
from relmodel.functions import embed, vec
from relmodel.operators import fusion, graph, metrics, passing, slices
from relmodel.workloads import ORDER_CUTOFFS, SHORT_CUTOFFS, TASKS, label_sql, planted

QUERIES, SQL = {}, {}
T = ORDER_CUTOFFS[2]
TS = f"TIMESTAMP '{T}'"
LINE = LINE_ID.replace("concat_ws('|', ", "concat_ws('|', ")


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# ---- sources, slices, states, labels -------------------------------------------------------

NAMES = ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "labels"]


@query("scan_counts", " UNION ALL ".join(f"SELECT '{n}' AS table_name, count(*) AS n FROM {n}" for n in NAMES))
def scan_counts(spark, sf):
    out = None
    for n, df in load(spark, sf, NAMES).items():
        row = df.agg(F.count("*").alias("n")).select(F.lit(n).alias("table_name"), "n")
        out = row if out is None else out.unionAll(row)
    return out


@query("key_check", " UNION ALL ".join(
    f"SELECT '{k.name}' AS relation, (SELECT count(*) FROM {k.child}) AS children, (SELECT count(*) FROM {k.child} c WHERE {k.child_col} IS NOT NULL AND NOT EXISTS (SELECT 1 FROM {k.parent} p WHERE p.{k.parent_col} = c.{k.child_col})) AS orphans"
    for k in CATALOG.keys))
def key_check(spark, sf):
    return check_keys(load(spark, sf))


@query("catalog_columns", "SELECT table_name, column_name FROM information_schema.columns WHERE table_name IN (" + ", ".join(f"'{n}'" for n in CATALOG.tables) + ")")
def catalog_columns(spark, sf):
    """Each column is listed once all its values were read."""
    out = None
    for n, df in load(spark, sf).items():
        read = [F.struct(F.lit(n).alias("table_name"), F.lit(c).alias("column_name"), F.count(c).alias("n")) for c in df.columns]
        rows = df.agg(F.array(*read).alias("read")).select(F.inline("read")).where("n >= 0").drop("n")
        out = rows if out is None else out.unionAll(rows)
    return out


@query("data_slice_customer_churn", "SELECT o.o_orderkey, o.o_custkey, o.o_totalprice FROM orders o WHERE o_totalprice > 100000 AND o_orderstatus IN ('F', 'O')")
def data_slice_customer_churn(spark, sf):
    s = slices.data_slice(load(spark, sf, ["customer", "orders"]), "customer", {"orders": ["o_orderkey", "o_custkey", "o_totalprice"]}, {"orders": "o_totalprice > 100000 AND o_orderstatus IN ('F', 'O')"})
    return s.tables["orders"]


@query("close_slice_semi", """SELECT count(*) AS n, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS price FROM lineitem WHERE l_orderkey IN
(SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING'))""")
def close_slice_semi(spark, sf):
    s = slices.data_slice(load(spark, sf, ["customer", "orders", "lineitem"]), "customer", filters={"customer": "c_mktsegment = 'BUILDING'"})
    s = slices.close_slice(s, "semi_reduce")
    return s.tables["lineitem"].agg(F.count("*").alias("n"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("price"))


@query("state_at_orders", f"SELECT o_custkey, count(*) AS n FROM orders WHERE o_orderdate <= {TS} GROUP BY o_custkey")
def state_at_orders(spark, sf):
    s = slices.state_at(slices.data_slice(load(spark, sf, ["customer", "orders"]), "customer"), T)
    return s.tables["orders"].groupBy("o_custkey").agg(F.count("*").alias("n"))


@query("state_at_strict", f"SELECT count(*) AS n FROM lineitem WHERE l_shipdate <= {TS} AND l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderdate <= {TS})")
def state_at_strict(spark, sf):
    s = slices.state_at(slices.data_slice(load(spark, sf, ["orders", "lineitem"]), "orders"), T, strict_parents=True)
    return s.tables["lineitem"].agg(F.count("*").alias("n"))


def _label(task):
    t = task.cutoffs[2]

    @query(f"labels_{task.name}", f"SELECT entity_id, round(y, 6) AS y FROM ({label_sql(task, t)})")
    def run(spark, sf):
        return slices.horizon_labels(task, load(spark, sf), t).select("entity_id", F.round("y", 6).alias("y"))


for _task in TASKS.values():
    _label(_task)

_net = "CAST(l_extendedprice AS DECIMAL(18,2)) * (1 - CAST(l_discount AS DECIMAL(4,2)))"
_planted = {
    "pl1": f"WITH n AS (SELECT c_custkey AS entity_id, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey AND o_orderdate <= {TS} GROUP BY 1) SELECT entity_id, CASE WHEN n > (SELECT quantile_cont(n, 0.5) FROM n) THEN 1.0 ELSE 0.0 END::DOUBLE AS y FROM n",
    "pl2": f"SELECT c_custkey AS entity_id, round(ln(1 + coalesce(s, 0)), 6) AS y FROM customer LEFT JOIN (SELECT o_custkey, CAST(sum({_net}) AS DOUBLE) AS s FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderdate <= {TS} AND l_shipdate <= {TS} GROUP BY 1) ON o_custkey = c_custkey",
    "pl3": f"SELECT l_partkey AS entity_id, round(CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) / count(*), 6) AS y FROM (SELECT *, row_number() OVER (PARTITION BY l_partkey ORDER BY l_shipdate DESC, {LINE}) AS rn FROM lineitem WHERE l_shipdate <= {TS}) WHERE rn <= 4 GROUP BY 1",
    "pl4": f"SELECT l_orderkey AS entity_id, max(l_extendedprice) AS y FROM lineitem WHERE l_shipdate <= {TS} GROUP BY 1",
    "pl5": "SELECT c_custkey AS entity_id, CASE WHEN c_acctbal > (SELECT quantile_cont(c_acctbal, 0.5) FROM customer) THEN 1.0 ELSE 0.0 END::DOUBLE AS y FROM customer",
}
for _name, _sql in _planted.items():
    query(f"labels_planted_{_name}", _sql)(lambda spark, sf, n=_name: planted(n, load(spark, sf, ["customer", "orders", "lineitem"])))


@query("time_split_customer_churn", " UNION ALL ".join(f"SELECT '{s}' AS split, entity_id, y FROM ({label_sql(TASKS['customer_churn'], t)})" for s, t in zip(("train", "valid", "test"), ORDER_CUTOFFS)))
def time_split_customer_churn(spark, sf):
    return slices.time_split(TASKS["customer_churn"], load(spark, sf, ["customer", "orders"])).select("split", "entity_id", "y")


@query("seeds_md5", f"SELECT entity_id, y FROM ({label_sql(TASKS['customer_churn'], T)}) ORDER BY md5('7:' || entity_id), entity_id LIMIT 256")
def seeds_md5(spark, sf):
    return slices.sample_seeds(slices.horizon_labels(TASKS["customer_churn"], load(spark, sf, ["customer", "orders"]), T), 256, 7).select("entity_id", "y")


@query("label_stats", "SELECT split, count(*) AS n, round(avg(y), 6) AS mean_y, round(quantile_cont(y, 0.5), 6) AS median_y FROM (" + " UNION ALL ".join(f"SELECT '{s}' AS split, y FROM ({label_sql(TASKS['customer_active'], t)})" for s, t in zip(("train", "valid", "test"), ORDER_CUTOFFS)) + ") GROUP BY split")
def label_stats(spark, sf):
    return slices.label_stats(slices.time_split(TASKS["customer_active"], load(spark, sf, ["customer", "orders"])))


@query("leak_guard", "SELECT 'orders' AS table_name, 0::BIGINT AS late UNION ALL SELECT 'lineitem', 0::BIGINT")
def leak_guard(spark, sf):
    return slices.leak_guard(slices.state_at(slices.data_slice(load(spark, sf, ["orders", "lineitem"]), "orders"), T), T)


_cs = ["o_orderstatus", "o_totalprice", "o_orderpriority", "o_custkey"]


@query("column_stats", " UNION ALL ".join(f"SELECT '{c}' AS column_name, count(*) AS n_rows, count(DISTINCT {c}) AS n_distinct, count(*) - count({c}) AS n_null FROM orders" for c in _cs))
def column_stats(spark, sf):
    return slices.column_stats(load(spark, sf, ["orders"])["orders"], _cs)


@query("dataset_stats", " UNION ALL ".join(f"SELECT '{n}' AS table_name, (SELECT count(*) FROM {n}) AS instances, {len(s.columns)}::BIGINT AS columns_, {len(s.of_kind('categorical', 'numerical', 'text', 'timestamp', 'nested'))}::BIGINT AS attributes, {len(CATALOG.links(n))}::BIGINT AS relations" for n, s in CATALOG.tables.items()))
def dataset_stats(spark, sf):
    out = None
    for n, df in load(spark, sf).items():
        s = CATALOG.tables[n]
        nums = [len(s.columns), len(s.of_kind("categorical", "numerical", "text", "timestamp", "nested")), len(CATALOG.links(n))]
        row = df.agg(F.count("*").alias("instances")).select(F.lit(n).alias("table_name"), "instances", *(F.lit(v).cast("long").alias(c) for v, c in zip(nums, ("columns_", "attributes", "relations"))))
        out = row if out is None else out.unionAll(row)
    return out


# ---- graph and sampling ----------------------------------------------------------------------

SMALL = ["customer", "orders", "lineitem"]


def _slice(spark, sf, names=SMALL, t=T):
    return slices.state_at(slices.data_slice(load(spark, sf, names), "customer"), t)


@query("graph_nodes", f"SELECT 'customer' AS type, CAST(c_custkey AS VARCHAR) AS node_id FROM customer UNION ALL SELECT 'orders', CAST(o_orderkey AS VARCHAR) FROM orders WHERE o_orderdate <= {TS} UNION ALL SELECT 'lineitem', {LINE} FROM lineitem WHERE l_shipdate <= {TS}")
def graph_nodes(spark, sf):
    return graph.graph_nodes(_slice(spark, sf)).select("type", "node_id")


_edges_sql = f"SELECT 'order_customer' AS relation, CAST(o_orderkey AS VARCHAR) AS child_id, CAST(o_custkey AS VARCHAR) AS parent_id, o_orderdate AS ts FROM orders WHERE o_orderdate <= {TS} UNION ALL SELECT 'line_order', {LINE}, CAST(l_orderkey AS VARCHAR), l_shipdate FROM lineitem WHERE l_shipdate <= {TS}"


@query("graph_edges", f"SELECT relation, child_id, parent_id FROM ({_edges_sql})")
def graph_edges(spark, sf):
    return graph.graph_edges(_slice(spark, sf)).select("relation", "child_id", "parent_id")


@query("graph_degrees", f"SELECT relation, parent_id AS node_id, count(*) AS degree FROM ({_edges_sql}) GROUP BY ALL")
def graph_degrees(spark, sf):
    return graph.degrees(graph.graph_edges(_slice(spark, sf)))


@query("node_relations", f"SELECT CASE relation WHEN 'order_customer' THEN 'customer' ELSE 'orders' END AS type, parent_id AS node_id, count(DISTINCT relation) AS n_relations FROM ({_edges_sql}) GROUP BY ALL")
def node_relations(spark, sf):
    return graph.node_relations(graph.graph_edges(_slice(spark, sf)), {"order_customer": "customer", "line_order": "orders"})


def _orders_of(spark, sf):
    return graph.neighbours(graph.graph_edges(_slice(spark, sf, ["customer", "orders"])), "order_customer")


_own = f"SELECT CAST(o_custkey AS VARCHAR) AS node_id, CAST(o_orderkey AS VARCHAR) AS nbr_id, o_orderdate AS ts FROM orders WHERE o_orderdate <= {TS}"
_rank = {"latest": "ts DESC, nbr_id", "uniform": "md5('0:' || nbr_id || ':' || node_id), nbr_id"}
for _k in (8, 16, 32, 64, 128, 256):
    for _how, _order in _rank.items():
        query(f"sample_{_how}_k{_k}", f"SELECT node_id, nbr_id, rn FROM (SELECT *, row_number() OVER (PARTITION BY node_id ORDER BY {_order})::INT AS rn FROM ({_own})) WHERE rn <= {_k}")(
            lambda spark, sf, k=_k, how=_how: graph.sample_neighbours(_orders_of(spark, sf), k, how).select("node_id", "nbr_id", "rn"))


@query("sample_full", f"SELECT node_id, nbr_id FROM ({_own})")
def sample_full(spark, sf):
    return graph.sample_neighbours(_orders_of(spark, sf), None).select("node_id", "nbr_id")


_lines_of = f"SELECT CAST(l_orderkey AS VARCHAR) AS node_id, {LINE} AS nbr_id, l_shipdate AS ts FROM lineitem WHERE l_shipdate <= {TS}"


def _hops_sql(k, how):
    pick = lambda rel: f"(SELECT node_id, nbr_id FROM (SELECT *, row_number() OVER (PARTITION BY node_id ORDER BY {_rank[how]}) AS rn FROM ({rel})) WHERE rn <= {k})"
    return f"WITH a AS (SELECT DISTINCT node_id AS seed_id, nbr_id FROM {pick(_own)}), b AS (SELECT DISTINCT a.seed_id, p.nbr_id FROM a JOIN {pick(_lines_of)} p ON p.node_id = a.nbr_id) SELECT seed_id, 1 AS hop, nbr_id FROM a UNION ALL SELECT seed_id, 2, nbr_id FROM b"


for _k in (8, 32):
    for _how in _rank:
        def _two(spark, sf, k=_k, how=_how):
            e = graph.graph_edges(_slice(spark, sf))
            seeds = load(spark, sf, ["customer"])["customer"].select(F.col("c_custkey").cast("string").alias("seed_id"))
            return graph.sample_hops(seeds, [graph.neighbours(e, "order_customer"), graph.neighbours(e, "line_order")], k, how)

        query(f"sample_two_hop_{_how}_k{_k}", _hops_sql(_k, _how))(_two)


@query("asof_latest_order", "SELECT node_id, price FROM (SELECT e.user_id AS node_id, o_totalprice AS price, row_number() OVER (PARTITION BY e.user_id ORDER BY o_orderdate DESC, o_totalprice DESC) AS rn FROM (SELECT DISTINCT user_id FROM events) e JOIN orders ON o_custkey = e.user_id WHERE o_orderdate <= TIMESTAMP '2000-07-01') WHERE rn = 1")
def asof_latest_order(spark, sf):
    t = load(spark, sf, ["events", "orders"])
    seeds = t["events"].select(F.col("user_id").alias("node_id")).distinct().withColumn("t", slices.at("2000-07-01"))
    facts = t["orders"].select(F.col("o_custkey").alias("node_id"), F.col("o_orderdate").alias("ts"), F.col("o_totalprice").alias("price"))
    return graph.asof_latest(seeds, facts, "price").select("node_id", "price")


@query("ego_graphs")
def ego_graphs(spark, sf):
    t = load(spark, sf, ["customer", "orders"])
    seeds = t["customer"].select(F.col("c_custkey").cast("string").alias("seed_id"))
    nbrs = t["orders"].select(F.col("o_custkey").cast("string").alias("node_id"), F.col("o_orderkey").cast("string").alias("nbr_id"), F.col("o_orderdate").alias("ts"), "o_totalprice")
    return graph.ego_graphs(seeds, {"order_customer": (nbrs, ["o_totalprice"])}, 8, as_of=T)


# ---- embeddings --------------------------------------------------------------------------------


@query("fit_vocab", "SELECT value, row_number() OVER (ORDER BY n DESC, value)::INT AS idx, n AS count FROM (SELECT p_brand AS value, count(*) AS n FROM part GROUP BY 1) ORDER BY idx LIMIT 20")
def fit_vocab(spark, sf):
    return embed.fit_vocab(load(spark, sf, ["part"])["part"], "p_brand", 20)


@query("embed_categorical", "WITH v AS (SELECT value, row_number() OVER (ORDER BY n DESC, value) AS idx FROM (SELECT p_brand AS value, count(*) AS n FROM part GROUP BY 1) ORDER BY idx LIMIT 20) SELECT p_partkey, " + ", ".join(f"round(sin(1 + 7 * coalesce(idx, 0) + {j}) / 4, 9) AS e{j}" for j in range(4)) + " FROM part LEFT JOIN v ON value = p_brand")
def embed_categorical(spark, sf):
    df = load(spark, sf, ["part"])["part"]
    return embed.embed_categorical(df, "p_brand", embed.fit_vocab(df, "p_brand", 20)).select("p_partkey", "e0", "e1", "e2", "e3")


@query("embed_numerical", "SELECT c_custkey, " + ", ".join(f"round((c_acctbal - 4500e0) / 3000e0 * {vec.number(vec.fixed_weight(0, 0, j))} + {vec.number(vec.fixed_weight(1, 0, j))}, 9) AS e{j}" for j in range(4)) + " FROM customer")
def embed_numerical(spark, sf):
    return load(spark, sf, ["customer"])["customer"].select("c_custkey", *embed.embed_numerical(F.col("c_acctbal"), 4500.0, 3000.0))


@query("time_features", "SELECT event_id, (year(ts) - 2024)::INT AS year_offset, " + ", ".join(f"round({f}({part}(ts) * 6.283185307179586e0 / {n}e0), 9) + 0e0 AS {part.replace('day', 'day')}_{f}" for part, n in (("month", 12), ("day", 31), ("hour", 24)) for f in ("sin", "cos")) + " FROM events")
def time_features(spark, sf):
    return load(spark, sf, ["events"])["events"].select("event_id", *embed.time_features(F.col("ts"), 2024))


@query("serialise_part", "SELECT p_partkey, concat_ws(', ', 'brand ' || p_brand, 'type ' || p_type, 'size ' || p_size) AS text FROM part")
def serialise_part(spark, sf):
    return load(spark, sf, ["part"])["part"].select("p_partkey", embed.serialise({"brand": "p_brand", "type": "p_type", "size": "p_size"}).alias("text"))


@query("ordered_target_stats", "SELECT c_custkey, round((coalesce(sum(y) OVER w, 0) + 0.5e0) / (coalesce(count(*) OVER w, 0) + 1), 9) AS stat FROM (SELECT c_custkey, c_mktsegment, CASE WHEN c_acctbal > 4500 THEN 1e0 ELSE 0e0 END AS y, md5(CAST(c_custkey AS VARCHAR)) AS h FROM customer) WINDOW w AS (PARTITION BY c_mktsegment ORDER BY h ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)")
def ordered_target_stats(spark, sf):
    from relmodel.nn.boost import ordered_target_statistic

    df = load(spark, sf, ["customer"])["customer"].select("c_custkey", "c_mktsegment", F.when(F.col("c_acctbal") > 4500, 1.0).otherwise(0.0).alias("y"), F.md5(F.col("c_custkey").cast("string").cast("binary")).alias("h"))
    return ordered_target_statistic(df, "c_mktsegment", "y", "h").select("c_custkey", F.round("stat", 9).alias("stat"))


@query("leaf_histogram", "SELECT least(floor(o_totalprice / 50000), 9)::INT AS bin, o_orderpriority AS leaf, count(*) AS n, sum(CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END)::BIGINT AS g FROM orders GROUP BY ALL")
def leaf_histogram(spark, sf):
    df = load(spark, sf, ["orders"])["orders"]
    return df.groupBy(F.least(F.floor(F.col("o_totalprice") / 50000), F.lit(9)).cast("int").alias("bin"), F.col("o_orderpriority").alias("leaf")).agg(F.count("*").alias("n"), F.sum(F.when(F.col("o_orderstatus") == "F", 1).otherwise(0)).alias("g"))


# ---- message passing with fixed weights, width 4 ------------------------------------------------

STATES = {
    "customer": ("CAST(c_custkey AS STRING)", ["c_acctbal / 9973e0", "c_nationkey / 23e0", "length(c_mktsegment) / 10e0", "1e0"]),
    "orders": ("CAST(o_orderkey AS STRING)", ["o_totalprice / 499979e0", "length(o_orderpriority) / 15e0", "CASE WHEN o_orderstatus = 'F' THEN 1e0 ELSE 0e0 END", "1e0"]),
    "lineitem": (LINE_ID, ["l_quantity / 49e0", "l_extendedprice / 99991e0", "l_discount / 0.0937e0", "1e0"]),
}


def _states(s):
    return {n: s.tables[n].select(F.expr(i).alias("node_id"), *(F.expr(x).alias(f"h{j}") for j, x in enumerate(xs))) for n, (i, xs) in STATES.items() if n in s.tables}


def _relations(s):
    e = graph.graph_edges(s)
    of = lambda r: e.where(F.col("relation") == r).select("child_id", "parent_id")
    out = [passing.Relation("order_customer", "orders", "customer", of("order_customer"), 0)]
    return out + ([passing.Relation("line_order", "lineitem", "orders", of("line_order"), 1)] if "lineitem" in s.tables else [])


def _state_sql(n, where=""):
    i, xs = STATES[n]
    i = i.replace("STRING", "VARCHAR")
    return f"(SELECT {i} AS node_id, {', '.join(f'{x} AS h{j}' for j, x in enumerate(xs))} FROM {n} {where})"


_W = {"customer": "", "orders": f"WHERE o_orderdate <= {TS}", "lineitem": f"WHERE l_shipdate <= {TS}"}
_E = {"order_customer": f"(SELECT CAST(o_orderkey AS VARCHAR) AS child_id, CAST(o_custkey AS VARCHAR) AS parent_id FROM orders {_W['orders']})", "line_order": f"(SELECT {LINE} AS child_id, CAST(l_orderkey AS VARCHAR) AS parent_id FROM lineitem {_W['lineitem']})"}


def _agg_sql(h, e, agg):
    f = {"mean": "avg"}.get(agg, agg)
    return f"(SELECT parent_id AS node_id, {', '.join(f'{f}(h{j}) AS s{j}' for j in range(4))} FROM {e} JOIN {h} x ON x.node_id = child_id GROUP BY parent_id)"


def _down_sql(h, e):
    return f"(SELECT child_id AS node_id, {', '.join(f'h{j} AS s{j}' for j in range(4))} FROM {e} JOIN {h} x ON x.node_id = parent_id)"


def _update_sql(h, s, r):
    own, nbr = vec.linear_sql(2 * r, ["h0", "h1", "h2", "h3"]), vec.linear_sql(2 * r + 1, ["s0", "s1", "s2", "s3"])
    return f"(SELECT node_id, {', '.join(f'{a} + {b} AS u{i}' for i, (a, b) in enumerate(zip(own, nbr)))} FROM {h} JOIN {s} USING (node_id))"


def _merge_sql(h, parts):
    every = " UNION ALL ".join(f"SELECT * FROM {p}" for p in parts)
    raw = f"(SELECT node_id, {', '.join(f'greatest(coalesce(m.u{i}, h{i}), 0) AS a{i}' for i in range(4))} FROM {h} LEFT JOIN (SELECT node_id, {', '.join(f'avg(u{i}) AS u{i}' for i in range(4))} FROM ({every}) GROUP BY node_id) m USING (node_id))"
    return f"(SELECT node_id, {', '.join(f'{x} AS h{i}' for i, x in enumerate(vec.norm_sql(['a0', 'a1', 'a2', 'a3'])))} FROM {raw})"


_r6 = lambda df, c="h": df.select("node_id", *(F.round(f"{c}{j}", 8).alias(f"{c}{j}") for j in range(4)))
_r6_sql = lambda q, c="h": f"SELECT node_id, {', '.join(f'round({c}{j}, 8) AS {c}{j}' for j in range(4))} FROM {q}"
_c, _o, _l = (_state_sql(n, _W[n]) for n in STATES)
for _agg in passing.AGGS:
    def _aggregate(spark, sf, agg=_agg):
        s = _slice(spark, sf)
        return _r6(passing.aggregate_neighbours(_states(s)["lineitem"], _relations(s)[1].edges, agg), "s")

    query(f"aggregate_{_agg}", _r6_sql(_agg_sql(_l, _E["line_order"], _agg), "s"))(_aggregate)


@query("aggregate_salted", _r6_sql(_agg_sql(_l, _E["line_order"], "sum"), "s"))
def aggregate_salted(spark, sf):
    s = _slice(spark, sf)
    return _r6(passing.salted_sum(_states(s)["lineitem"], _relations(s)[1].edges), "s")


@query("relation_update_d4", _r6_sql(_update_sql(_c, _agg_sql(_o, _E["order_customer"], "sum"), 0), "u"))
def relation_update_d4(spark, sf):
    s = _slice(spark, sf)
    h, r = _states(s), _relations(s)[0]
    return _r6(passing.relation_update(h["customer"], passing.aggregate_neighbours(h["orders"], r.edges), 0), "u")


_o1 = _merge_sql(_o, [_update_sql(_o, _down_sql(_c, _E["order_customer"]), 0), _update_sql(_o, _agg_sql(_l, _E["line_order"], "sum"), 1)])
_c1 = _merge_sql(_c, [_update_sql(_c, _agg_sql(_o, _E["order_customer"], "sum"), 0)])


@query("merge_relations_d4", _r6_sql(_o1))
def merge_relations_d4(spark, sf):
    s = _slice(spark, sf)
    return _r6(passing.message_layers(_states(s), _relations(s), 1)["orders"])


@query("message_two_layers_d4", f"WITH o1 AS {_o1}, c1 AS {_c1} " + _r6_sql(_merge_sql("c1", [_update_sql("c1", _agg_sql("o1", _E["order_customer"], "sum"), 0)])))
def message_two_layers_d4(spark, sf):
    s = _slice(spark, sf)
    return _r6(passing.message_layers(_states(s), _relations(s), 2, target="customer")["customer"])


# ---- signals and importance ---------------------------------------------------------------------

_exact = "CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE)"
_price_signals = f"max(o_totalprice) AS orders_max_o_totalprice, min(o_totalprice) AS orders_min_o_totalprice, {_exact} AS orders_sum_o_totalprice, {_exact} / count(o_totalprice) AS orders_mean_o_totalprice"


def _order_signals(spark, sf):
    o = load(spark, sf, ["orders"])["orders"].where(F.col("o_orderdate") <= slices.at(T))
    return fusion.context_signals(o.select(F.col("o_custkey").alias("node_id"), "o_totalprice"), ["o_totalprice"], "orders", exact=True)


@query("context_signals", f"SELECT o_custkey AS node_id, count(*) AS orders_n, {_price_signals} FROM orders WHERE o_orderdate <= {TS} GROUP BY 1")
def context_signals(spark, sf):
    return _order_signals(spark, sf)


@query("relational_features", f"SELECT c_custkey AS node_id, c_acctbal, coalesce(orders_n, 0) AS orders_n, s.* EXCLUDE (node_id, orders_n) FROM customer LEFT JOIN (SELECT o_custkey AS node_id, count(*) AS orders_n, {_price_signals} FROM orders WHERE o_orderdate <= {TS} GROUP BY 1) s ON s.node_id = c_custkey")
def relational_features(spark, sf):
    c = load(spark, sf, ["customer"])["customer"].select(F.col("c_custkey").alias("node_id"), "c_acctbal")
    return fusion.relational_features(c, [_order_signals(spark, sf)]).withColumn("orders_n", F.coalesce("orders_n", F.lit(0)))


@query("signal_sequence", f"""WITH c AS (SELECT c_custkey AS node_id, EXISTS (SELECT 1 FROM events e WHERE user_id = c_custkey) AS e, EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderdate <= {TS}) AS o FROM customer),
s AS (SELECT node_id, ['self'] || CASE WHEN e THEN ['events(max)','events(min)','events(sum)','events(mean)'] ELSE [] END || CASE WHEN o THEN ['orders(max)','orders(min)','orders(sum)','orders(mean)'] ELSE [] END AS l FROM c)
SELECT node_id, (unnest(range(len(l))))::INT AS pos, unnest(l) AS signal FROM s""")
def signal_sequence(spark, sf):
    t = load(spark, sf, ["customer", "orders", "events"])
    c = t["customer"].select(F.col("c_custkey").alias("node_id"))
    return fusion.signal_sequence(c, {"orders": t["orders"].where(F.col("o_orderdate") <= slices.at(T)).select(F.col("o_custkey").alias("node_id")), "events": t["events"].select(F.col("user_id").alias("node_id"))})


_alpha = "SELECT event_id AS node_id, event_type AS signal, (event_id % 5 + 1) AS n, value / 200e0 AS alpha FROM events"
_importance = f"SELECT node_id, signal, CASE WHEN n > 1 THEN greatest((alpha - 1e0 / n) / (1 - 1e0 / n), 0) ELSE 0 END AS importance FROM ({_alpha})"


def _weights(spark, sf):
    e = load(spark, sf, ["events"])["events"].select(F.col("event_id").alias("node_id"), F.col("event_type").alias("signal"), (F.col("event_id") % 5 + 1).alias("n"), (F.col("value") / 200).alias("alpha"))
    return e.select("node_id", "signal", fusion.recalibrate(F.col("alpha"), F.col("n")).alias("importance"))


@query("importance_recalibrated", f"SELECT node_id, signal, round(importance, 9) AS importance FROM ({_importance})")
def importance_recalibrated(spark, sf):
    return _weights(spark, sf).select("node_id", "signal", F.round("importance", 9).alias("importance"))


@query("signal_ranking", f"SELECT * FROM (SELECT *, dense_rank() OVER (ORDER BY mean_importance DESC)::INT AS place FROM (SELECT signal, count(*) AS n, round(avg(importance), 6) AS mean_importance, round(quantile_cont(importance, 0.25), 6) AS q25, round(quantile_cont(importance, 0.75), 6) AS q75 FROM ({_importance}) GROUP BY signal)) WHERE place <= 4")
def signal_ranking(spark, sf):
    return fusion.rank_signals(_weights(spark, sf))


# ---- measures -------------------------------------------------------------------------------------

_scored = "SELECT o_orderkey, CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END AS y, floor(o_totalprice / 1000) / 500e0 AS score FROM orders"


def _scores(spark, sf):
    return load(spark, sf, ["orders"])["orders"].select("o_orderkey", F.when(F.col("o_orderstatus") == "F", 1).otherwise(0).alias("y"), (F.floor(F.col("o_totalprice") / 1000) / 500).alias("score"))


@query("metric_roc_area", f"WITH r AS (SELECT y, rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2e0 AS k FROM ({_scored})) SELECT round((sum(CASE WHEN y = 1 THEN k END) - sum(y) * (sum(y) + 1) / 2e0) / (sum(y) * sum(1 - y)), 9) AS area FROM r")
def metric_roc_area(spark, sf):
    return metrics.roc_area(_scores(spark, sf)).select(F.round("area", 9).alias("area"))


@query("metric_mae", f"SELECT round(avg(abs(score - y)), 9) AS mae FROM ({_scored})")
def metric_mae(spark, sf):
    return metrics.mae(_scores(spark, sf)).select(F.round("mae", 9).alias("mae"))


@query("metric_bce", f"SELECT round(avg(greatest(z, 0) - z * y + ln(1 + exp(-abs(z)))), 9) AS bce FROM (SELECT y, score * 4 - 2 AS z FROM ({_scored}))")
def metric_bce(spark, sf):
    return metrics.bce(_scores(spark, sf).withColumn("logit", F.col("score") * 4 - 2)).select(F.round("bce", 9).alias("bce"))


@query("metric_l1", f"SELECT y AS label, round(avg(abs(score - y)), 9) AS l1 FROM ({_scored}) GROUP BY y")
def metric_l1(spark, sf):
    return _scores(spark, sf).groupBy(F.col("y").alias("label")).agg(F.round(F.avg(F.abs(F.col("score") - F.col("y"))), 9).alias("l1"))


@query("relative_gain", "SELECT event_id, round(CASE WHEN event_type = 'click' THEN (value + 1 - value / 2) / (value / 2 + 1) ELSE (value + 2 - value / 2) / (value + 2) END, 9) AS gain FROM events")
def relative_gain(spark, sf):
    e = load(spark, sf, ["events"])["events"]
    click, v = F.col("event_type") == "click", F.col("value")
    base, aug = F.when(click, v / 2 + 1).otherwise(v + 2), F.when(click, v + 2).otherwise(v / 2)
    return e.select("event_id", F.round(metrics.relative_gain(base, aug, click), 9).alias("gain"))


_runs = "SELECT event_type AS model_id, 'task' || (user_id % 3) AS task, value AS metric FROM events"


@query("runs_mean", f"SELECT model_id, task, count(*) AS n_runs, round(avg(metric), 6) AS mean_metric, round(stddev_pop(metric), 6) AS sd_metric FROM ({_runs}) GROUP BY ALL")
def runs_mean(spark, sf):
    return metrics.mean_of_runs(load(spark, sf, ["events"])["events"].select(F.col("event_type").alias("model_id"), F.concat(F.lit("task"), (F.col("user_id") % 3).cast("string")).alias("task"), F.col("value").alias("metric")))


@query("gain_summary", f"SELECT model_id AS grp, task AS kind, count(*) AS n, round(avg(metric), 6) AS mean_gain, round(quantile_cont(metric, 0.5), 6) AS median_gain FROM ({_runs}) GROUP BY ALL")
def gain_summary(spark, sf):
    return metrics.gain_summary(load(spark, sf, ["events"])["events"].select(F.col("event_type").alias("grp"), F.concat(F.lit("task"), (F.col("user_id") % 3).cast("string")).alias("kind"), F.col("value").alias("gain")))


@query("budget_curve", "SELECT event_type AS search, event_id AS trial, max(value) OVER (PARTITION BY event_type ORDER BY event_id) AS best FROM events")
def budget_curve(spark, sf):
    return metrics.budget_curve(load(spark, sf, ["events"])["events"].select(F.col("event_type").alias("search"), F.col("event_id").alias("trial"), F.col("value").alias("skill")))


@query("one_hot_width", "SELECT (SELECT count(DISTINCT p_brand) FROM part) + (SELECT count(DISTINCT p_type) FROM part) + 2 AS width")
def one_hot_width(spark, sf):
    stats = slices.column_stats(load(spark, sf, ["part"])["part"], ["p_brand", "p_type", "p_size", "p_retailprice"])
    return metrics.one_hot_width(stats.withColumn("kind", F.when(F.col("column_name").isin("p_brand", "p_type"), "categorical").otherwise("numerical")))


@query("dispatch_report", "SELECT round(avg(CASE WHEN user_id % 2 = 0 THEN 1e0 ELSE 0e0 END), 6) AS augment_rate, round(avg(greatest(value, 50) - CASE WHEN user_id % 2 = 0 THEN 50 ELSE value END), 6) AS regret FROM events")
def dispatch_report(spark, sf):
    e = load(spark, sf, ["events"])["events"]
    return metrics.dispatch_report(e.select(F.col("value").alias("direct"), F.lit(50.0).alias("augmented"), F.when(F.col("user_id") % 2 == 0, "augment").otherwise("direct").alias("decision")))
