"""All queries of the library and their SQL twins in one place."""

from __future__ import annotations

from pyspark.sql import functions as F

from relmodel import learned as _learned
from relmodel import operators_queries as _more
from relmodel import queries as _base
from relmodel.catalog import load
from relmodel.operators import fusion, graph, slices
from relmodel.workloads import ORDER_CUTOFFS, TASKS

QUERIES = _base.QUERIES | _more.QUERIES | _learned.QUERIES
SQL = _base.SQL | _more.SQL


def entry(spark, sf_dir):
    """Churn labels beside the signals of each customer's latest 32 orders, as of the test cutoff."""
    tables, t = load(spark, sf_dir, ["customer", "orders"]), ORDER_CUTOFFS[2]
    s = slices.state_at(slices.data_slice(tables, "customer"), t)
    nbrs = s.tables["orders"].select(F.col("o_custkey").alias("node_id"), F.col("o_orderkey").cast("string").alias("nbr_id"), F.col("o_orderdate").alias("ts"), "o_totalprice")
    picked = graph.sample_neighbours(nbrs, 32, "latest")
    signals = fusion.context_signals(picked, ["o_totalprice"], "orders", exact=True)
    labels = slices.horizon_labels(TASKS["customer_churn"], tables, t)
    return labels.select(F.col("entity_id").alias("node_id"), "y").join(signals, "node_id", "left")
