"""Message passing along relations as plans (P1-P7): joins down, grouped sums up, one column per
dimension so that partial aggregation keeps hubs cheap."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.functions.vec import linear_sql, norm_sql
from relmodel.session import saved

AGGS = {"sum": F.sum, "mean": F.avg, "max": F.max, "min": F.min}


@dataclass(frozen=True)
class Relation:
    """Edges (child_id, parent_id) of one link between two node types; ``index`` picks its weights."""

    name: str
    child: str
    parent: str
    edges: DataFrame
    index: int


def dims(df: DataFrame) -> list[str]:
    return sorted((c for c in df.columns if c[0] == "h" and c[1:].isdigit()), key=lambda c: int(c[1:]))


def aggregate_neighbours(h: DataFrame, edges: DataFrame, agg: str = "sum", up: bool = True) -> DataFrame:
    """(node_id, s0…): children's states gathered at their parent, or the parent's state at each
    child (exactly one, so no aggregate)."""
    cols = dims(h)
    if not up:
        return edges.join(h.withColumnRenamed("node_id", "parent_id"), "parent_id").select(F.col("child_id").alias("node_id"), *(F.col(c).alias(f"s{c[1:]}") for c in cols))
    met = edges.join(h.withColumnRenamed("node_id", "child_id"), "child_id")
    return met.groupBy(F.col("parent_id").alias("node_id")).agg(*(AGGS[agg](c).alias(f"s{c[1:]}") for c in cols))


def salted_sum(h: DataFrame, edges: DataFrame, salts: int = 64) -> DataFrame:
    """P2 for hubs whose partial aggregates still meet in one task: summed per salt, then per node."""
    cols = dims(h)
    met = edges.join(h.withColumnRenamed("node_id", "child_id"), "child_id").withColumn("salt", F.pmod(F.xxhash64("child_id"), F.lit(salts)))
    part = met.groupBy("parent_id", "salt").agg(*(F.sum(c).alias(c) for c in cols))
    return part.groupBy(F.col("parent_id").alias("node_id")).agg(*(F.sum(c).alias(f"s{c[1:]}") for c in cols))


def relation_update(h: DataFrame, s: DataFrame, index: int) -> DataFrame:
    """Own state times the relation's own weights plus gathered state times its neighbour weights,
    for nodes that have a neighbour."""
    cols = dims(h)
    own, nbr = linear_sql(2 * index, cols), linear_sql(2 * index + 1, [f"s{c[1:]}" for c in cols])
    return h.join(s, "node_id").select("node_id", *(F.expr(f"{a} + {b}").alias(f"u{i}") for i, (a, b) in enumerate(zip(own, nbr))))


def merge_relations(h: DataFrame, parts: list[DataFrame]) -> DataFrame:
    """Mean over the relations a node has, rectified and normalised; a node without any keeps its
    own state, rectified and normalised."""
    cols = dims(h)
    every = parts[0]
    for p in parts[1:]:
        every = every.unionAll(p)
    mean = every.groupBy("node_id").agg(*(F.avg(f"u{i}").alias(f"u{i}") for i in range(len(cols))))
    raw = h.join(mean, "node_id", "left").select("node_id", *(F.greatest(F.coalesce(f"u{i}", c), F.lit(0.0)).alias(f"a{i}") for i, c in enumerate(cols)))
    return raw.select("node_id", *(F.expr(x).alias(f"h{i}") for i, x in enumerate(norm_sql([f"a{i}" for i in range(len(cols))]))))


def message_layers(states: dict[str, DataFrame], relations: list[Relation], layers: int, agg: str = "sum", target: str | None = None, cut=saved) -> dict[str, DataFrame]:
    """``layers`` rounds over all node types. With a target, types too far away to matter in
    the rounds left are skipped. ``cut`` (a function of a DataFrame) writes the states of each round but
    the last, which every relation of the next round reads; None plans all rounds as one."""
    far = {n: 0 if target in (None, n) else 99 for n in states}
    for _ in states:
        for r in relations:
            for a, b in ((r.child, r.parent), (r.parent, r.child)):
                far[a] = min(far[a], far[b] + 1)
    for layer in range(1, layers + 1):
        new = {}
        for kind, h in states.items():
            if far[kind] > layers - layer:
                continue
            parts = []
            for r in relations:
                if r.parent == kind:
                    parts.append(relation_update(h, aggregate_neighbours(states[r.child], r.edges, agg), r.index))
                if r.child == kind:
                    parts.append(relation_update(h, aggregate_neighbours(states[r.parent], r.edges, agg, up=False), r.index))
            new[kind] = merge_relations(h, parts) if parts else h
        states = states | {k: cut(v) if cut and layer < layers else v for k, v in new.items()}
    return states


def choose_mode(seeds: int, k: int, relations: int, hops: int, edges: int, layers: int) -> str:
    """Packed ego graphs while they touch fewer tuples than whole-graph rounds (§4 of the survey)."""
    return "packed" if seeds * (k * relations) ** hops < edges * layers else "layerwise"
