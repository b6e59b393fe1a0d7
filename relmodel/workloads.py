"""Prediction tasks on the given tables (W1-W10) and planted-signal tasks (PL1-PL5).

The value expressions are plain SQL over the window's rows, so the oracle twins share the task
definition but not the plan.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.operators.slices import at

ORDER_CUTOFFS = ("1999-07-01", "2000-07-01", "2001-01-01")
SHORT_CUTOFFS = ("2024-01-15", "2024-01-19", "2024-01-23")
WEEK_CUTOFFS = ("2024-01-09", "2024-01-16", "2024-01-23")
ITEM = "CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT)"


@dataclass(frozen=True)
class Task:
    name: str
    kind: str  # binary or regression
    home: str
    home_key: str
    table: str
    entity: str
    time: str
    value: str  # aggregate over the rows of the window
    needs: tuple[str, ...]
    absent: float
    eligible: str  # predicate on earlier rows, or "all" entities, or "window"
    days: int
    cutoffs: tuple[str, str, str]


_orders = dict(home="customer", home_key="c_custkey", table="orders", entity="o_custkey", time="o_orderdate", needs=("o_orderstatus",), days=180, cutoffs=ORDER_CUTOFFS)
_lines = dict(table="lineitem", time="l_shipdate", days=180, cutoffs=ORDER_CUTOFFS)
_users = dict(home="customer", home_key="c_custkey", table="events", entity="user_id", time="ts", needs=("event_type",))
TASKS = {t.name: t for t in (
    Task("customer_churn", "binary", value="0", absent=1, eligible="true", **_orders),
    Task("part_sales", "regression", home="part", home_key="p_partkey", entity="l_partkey", needs=("l_extendedprice", "l_discount"), value="sum(CAST(l_extendedprice AS DECIMAL(18,2)) * (1 - CAST(l_discount AS DECIMAL(4,2))))", absent=0, eligible="all", **_lines),
    Task("user_click", "binary", value="CASE WHEN count(CASE WHEN event_type = 'click' THEN 1 END) > 1 THEN 1 ELSE 0 END", absent=0, eligible="true", days=4, cutoffs=SHORT_CUTOFFS, **_users),
    Task("item_ctr", "regression", home="events", home_key="event_id", table="events", entity=ITEM, time="ts", needs=("event_type",), value="count(CASE WHEN event_type = 'click' THEN 1 END) * 1e0 / nullif(count(CASE WHEN event_type IN ('click', 'view') THEN 1 END), 0)", absent=0, eligible="window", days=4, cutoffs=SHORT_CUTOFFS),
    Task("user_repeat", "binary", value="max(CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END)", absent=0, eligible="event_type = 'purchase'", days=2, cutoffs=SHORT_CUTOFFS, **_users),
    Task("user_attend", "regression", value="count(CASE WHEN event_type = 'purchase' THEN 1 END)", absent=0, eligible="true", days=7, cutoffs=WEEK_CUTOFFS, **_users),
    Task("customer_active", "binary", value="CASE WHEN count(*) > 1 THEN 1 ELSE 0 END", absent=0, eligible="true", **_orders),
    Task("part_positive", "regression", home="part", home_key="p_partkey", entity="l_partkey", needs=("l_returnflag",), value="count(CASE WHEN l_returnflag <> 'R' THEN 1 END) * 1e0 / count(*)", absent=0, eligible="window", **_lines),
    Task("order_outcome", "binary", **(_orders | dict(entity="o_orderkey", home="orders", home_key="o_orderkey")), value="max(CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END)", absent=0, eligible="window"),
    Task("supplier_success", "regression", home="supplier", home_key="s_suppkey", entity="l_suppkey", needs=("l_linestatus",), value="count(CASE WHEN l_linestatus = 'F' THEN 1 END) * 1e0 / count(*)", absent=0, eligible="window", **_lines),
)}


def label_sql(task: Task, t: str) -> str:
    """DuckDB twin of S5, as a subquery per entity instead of a join."""
    facts = f"(SELECT CAST({task.entity} AS BIGINT) AS entity_id, {task.time} AS ts, {', '.join(task.needs)} FROM {task.table})"
    inside = f"SELECT entity_id, CAST({task.value} AS DOUBLE) AS y FROM {facts} WHERE ts > TIMESTAMP '{t}' AND ts <= TIMESTAMP '{t}' + INTERVAL {task.days} DAY GROUP BY entity_id"
    if task.eligible == "window":
        return f"SELECT entity_id, y FROM ({inside}) WHERE y IS NOT NULL"
    who = f"SELECT CAST({task.home_key} AS BIGINT) AS entity_id FROM {task.home}" if task.eligible == "all" else f"SELECT DISTINCT entity_id FROM {facts} WHERE ts <= TIMESTAMP '{t}' AND {task.eligible}"
    return f"SELECT w.entity_id, coalesce(i.y, {float(task.absent)}::DOUBLE) AS y FROM ({who}) w LEFT JOIN ({inside}) i ON w.entity_id = i.entity_id"


def planted(name: str, tables: dict[str, DataFrame], t: str = ORDER_CUTOFFS[2]) -> DataFrame:
    """(entity_id, y): labels that are exact functions of the state at t."""
    orders = tables["orders"].where(F.col("o_orderdate") <= at(t))
    lines = tables["lineitem"].where(F.col("l_shipdate") <= at(t))
    who = tables["customer"].select(F.col("c_custkey").alias("entity_id"), "c_acctbal")
    if name == "pl1":  # degree
        n = who.join(orders.groupBy(F.col("o_custkey").alias("entity_id")).agg(F.count("*").alias("n")), "entity_id", "left").select("entity_id", F.coalesce("n", F.lit(0)).alias("n"))
        middle = n.agg(F.expr("percentile(n, 0.5)").alias("m"))
        return n.crossJoin(F.broadcast(middle)).select("entity_id", F.when(F.col("n") > F.col("m"), 1.0).otherwise(0.0).alias("y"))
    if name == "pl2":  # two hops
        value = F.expr("CAST(l_extendedprice AS DECIMAL(18,2)) * (1 - CAST(l_discount AS DECIMAL(4,2)))")
        own = orders.join(lines, orders.o_orderkey == lines.l_orderkey).groupBy(F.col("o_custkey").alias("entity_id")).agg(F.sum(value).cast("double").alias("s"))
        return who.join(own, "entity_id", "left").select("entity_id", F.round(F.log1p(F.coalesce("s", F.lit(0.0))), 6).alias("y"))
    if name == "pl3":  # recency
        from relmodel.catalog import LINE_ID
        from relmodel.operators.graph import latest_rows

        last = latest_rows(lines, 4, "l_partkey", "l_shipdate", LINE_ID)
        return last.groupBy(F.col("l_partkey").alias("entity_id")).agg(F.round(F.sum(F.col("l_quantity").cast("decimal(18,2)")).cast("double") / F.count("*"), 6).alias("y"))
    if name == "pl4":  # extreme
        return lines.groupBy(F.col("l_orderkey").alias("entity_id")).agg(F.max("l_extendedprice").alias("y"))
    if name == "pl5":  # own column
        middle = who.agg(F.expr("percentile(c_acctbal, 0.5)").alias("m"))
        return who.crossJoin(F.broadcast(middle)).select("entity_id", F.when(F.col("c_acctbal") > F.col("m"), 1.0).otherwise(0.0).alias("y"))
    raise KeyError(name)
