"""Relational graph and neighbour sampling (G1-G12): plans over declared links, no graph library."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmodel.catalog import node_id
from relmodel.operators.slices import DataSlice, at


def graph_nodes(s: DataSlice) -> DataFrame:
    """G1: (type, node_id, ts) of every row of the slice."""
    out = None
    for n, df in s.tables.items():
        time = s.catalog.tables[n].time
        stamp = F.col(time) if time in df.columns else F.lit(None).cast("timestamp_ntz")
        part = df.select(F.lit(n).alias("type"), F.expr(node_id(n, s.catalog)).alias("node_id"), stamp.alias("ts"))
        out = part if out is None else out.unionAll(part)
    return out


def graph_edges(s: DataSlice) -> DataFrame:
    """(relation, child_id, parent_id, ts). A child holds its parent's key: a projection per
    link, no join."""
    out = None
    for k in s.catalog.keys:
        if k.child in s.tables and k.parent in s.tables:
            time = s.catalog.tables[k.child].time
            df = s.tables[k.child].where(F.col(k.child_col).isNotNull())
            stamp = F.col(time) if time in df.columns else F.lit(None).cast("timestamp_ntz")
            part = df.select(F.lit(k.name).alias("relation"), F.expr(node_id(k.child, s.catalog)).alias("child_id"), F.col(k.child_col).cast("string").alias("parent_id"), stamp.alias("ts"))
            out = part if out is None else out.unionAll(part)
    return out


def neighbours(edges: DataFrame, relation: str, down: bool = True) -> DataFrame:
    """(node_id, nbr_id, ts): from a parent to its children, or back."""
    own = edges.where(F.col("relation") == relation)
    a, b = ("parent_id", "child_id") if down else ("child_id", "parent_id")
    return own.select(F.col(a).alias("node_id"), F.col(b).alias("nbr_id"), "ts")


def degrees(edges: DataFrame) -> DataFrame:
    """(relation, node_id, degree) on the parent's side."""
    return edges.groupBy("relation", F.col("parent_id").alias("node_id")).agg(F.count("*").alias("degree"))


def node_relations(edges: DataFrame, tables: dict[str, str]) -> DataFrame:
    """(type, node_id, n_relations); ``tables`` gives the parent type of each relation."""
    kind = F.create_map(*(F.lit(x) for kv in tables.items() for x in kv))
    return edges.select(kind[F.col("relation")].alias("type"), F.col("parent_id").alias("node_id"), "relation").distinct().groupBy("type", "node_id").agg(F.count("*").alias("n_relations"))


def sample_neighbours(nbrs: DataFrame, k: int | None, strategy: str = "latest", seed: int = 0, as_of: str | None = None) -> DataFrame:
    """At most k neighbours of each node, visible at ``as_of``.

    ``latest`` takes the most recent (ties by id), ``uniform`` without replacement in a fixed
    pseudo-random order, so a sample of k is contained in one of 2k. The shape of the filter lets
    the planner keep only k rows a node before the shuffle, however large a hub is."""
    nbrs = nbrs.where(F.col("ts") <= at(as_of)) if as_of else nbrs
    if k is None:
        return nbrs
    if strategy == "latest":
        order = [F.desc("ts"), F.asc("nbr_id")]
    elif strategy == "uniform":
        order = [F.md5(F.concat_ws(":", F.lit(str(seed)), "nbr_id", "node_id").cast("binary")), F.asc("nbr_id")]
    else:
        raise ValueError(strategy)
    return nbrs.withColumn("rn", F.row_number().over(Window.partitionBy("node_id").orderBy(*order))).where(F.col("rn") <= k)


def latest_rows(df: DataFrame, k: int, by: str, time: str, row_id: str) -> DataFrame:
    """The k latest rows of each value of ``by``, numbered in ``rn`` with ties by id, as ``sample_neighbours``
    takes them. The id (SQL over the row) is computed only for rows that share their time with another."""
    own = Window.partitionBy(by)
    times = own.orderBy(F.desc(time))
    df = df.withColumn("_place", F.rank().over(times)).where(F.col("_place") <= k)
    tied = [F.coalesce(f("_place").over(times) == F.col("_place"), F.lit(False)) for f in (F.lag, F.lead)]
    df = df.withColumn("_tied", tied[0] | tied[1]).withColumn("_tie", F.when(F.col("_tied"), F.expr(row_id)))
    return df.withColumn("rn", F.row_number().over(own.orderBy("_place", "_tie"))).where(F.col("rn") <= k).drop("_place", "_tied", "_tie")


def sample_hops(seeds: DataFrame, steps: list[DataFrame], k: int, strategy: str = "latest", seed: int = 0, as_of: str | None = None) -> DataFrame:
    """(seed_id, hop, nbr_id): hop after hop from (seed_id); a node reached twice counts once."""
    front, out = seeds.select("seed_id", F.col("seed_id").alias("at")), None
    for hop, step in enumerate(steps, 1):
        picked = sample_neighbours(step, k, strategy, seed, as_of).select(F.col("node_id").alias("at"), "nbr_id")
        front = front.join(picked, "at").select("seed_id", F.col("nbr_id").alias("at")).distinct()
        part = front.select("seed_id", F.lit(hop).alias("hop"), F.col("at").alias("nbr_id"))
        out = part if out is None else out.unionAll(part)
    return out


def asof_latest(seeds: DataFrame, facts: DataFrame, value: str) -> DataFrame:
    """Per (node_id, t) the value of the latest fact (node_id, ts, value) at or before t."""
    own = seeds.join(facts, "node_id").where("ts <= t")
    return own.groupBy("node_id", "t").agg(F.max_by(value, F.struct("ts", value)).alias(value))


def ego_graphs(seeds: DataFrame, children: dict[str, tuple[DataFrame, list[str]]], k: int, strategy: str = "latest", as_of: str | None = None) -> DataFrame:
    """One row per seed with an array of its sampled neighbours' columns per relation.

    ``children`` gives (node_id, nbr_id, ts, columns…) per relation. Written once, then trained and
    scored without any shuffle."""
    out = seeds
    for name, (nbrs, columns) in sorted(children.items()):
        own = sample_neighbours(nbrs, k, strategy, as_of=as_of)
        packed = own.groupBy(F.col("node_id").alias("seed_id")).agg(F.sort_array(F.collect_list(F.struct("rn", *(F.col(c).cast("double").alias(c) for c in columns)))).alias(name))
        out = out.join(packed, "seed_id", "left")
    return out
