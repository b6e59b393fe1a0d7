"""Data slices, states at a time, labels and splits (S1-S9, DM5-DM7)."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relmodel.catalog import CATALOG, Catalog
from relmodel.functions.quantile import quantiles


def at(t: str) -> Column:
    """A time literal without zone, so that comparisons with such columns reach the scan."""
    return F.expr(f"TIMESTAMP_NTZ'{t}'")


@dataclass(frozen=True)
class DataSlice:
    """The part of a database a question needs; plans only, nothing is read yet (DM5)."""

    tables: dict[str, DataFrame]
    catalog: Catalog
    target: str
    cutoff: str | None = None


def table_slice(df: DataFrame, predicate: str | None = None, columns: list[str] | None = None) -> DataFrame:
    """Selection and projection, both pushed into the scan."""
    df = df.where(predicate) if predicate else df
    return df.select(*columns) if columns else df


def data_slice(tables: dict[str, DataFrame], target: str, columns=None, filters=None, catalog: Catalog = CATALOG, cutoff: str | None = None) -> DataSlice:
    """Table slices of all chosen tables."""
    columns, filters = columns or {}, filters or {}
    return DataSlice({n: table_slice(df, filters.get(n), columns.get(n)) for n, df in tables.items()}, catalog, target, cutoff)


def close_slice(s: DataSlice, mode: str = "keep_parents") -> DataSlice:
    """S3: with ``semi_reduce`` children whose parent is filtered away go too, parents first; with
    ``keep_parents`` every kept child keeps its row and dangling links stay harmless."""
    if mode == "keep_parents":
        return s
    tables, done = dict(s.tables), set()
    while len(done) < len(tables):
        ready = [n for n in tables if n not in done and all(k.parent in done or k.parent not in tables or k.parent == n for k in s.catalog.keys if k.child == n)]
        if not ready:
            raise ValueError("foreign keys form a cycle")
        for n in ready:
            for k in s.catalog.keys:
                if k.child == n and k.parent in tables and k.parent != n:
                    parent = tables[k.parent].select(F.col(k.parent_col).alias(k.child_col)).distinct()
                    tables[n] = tables[n].join(parent, k.child_col, "left_semi")
            done.add(n)
    return replace(s, tables=tables)


def state_at(s: DataSlice, t: str, strict_parents: bool = False) -> DataSlice:
    """Rows stamped at or before t; tables without time stay whole."""
    spec = s.catalog.tables
    out = replace(s, tables={n: df.where(F.col(spec[n].time) <= at(t)) if n in spec and spec[n].time in df.columns else df for n, df in s.tables.items()}, cutoff=t)
    return close_slice(out, "semi_reduce") if strict_parents else out


def horizon_labels(task, tables: dict[str, DataFrame], t: str) -> DataFrame:
    """(entity_id, t, y) of a workload at one cutoff: one aggregate over (t, t + horizon]."""
    facts = tables[task.table].selectExpr(f"CAST({task.entity} AS BIGINT) AS entity_id", f"{task.time} AS ts", *task.needs)
    end = F.expr(f"TIMESTAMP_NTZ'{t}' + INTERVAL {task.days} DAYS")
    inside = facts.where((F.col("ts") > at(t)) & (F.col("ts") <= end))
    agg = inside.groupBy("entity_id").agg(F.expr(task.value).cast("double").alias("y"))
    if task.eligible == "window":
        return agg.where("y IS NOT NULL").select("entity_id", at(t).alias("t"), "y")
    if task.eligible == "all":
        who = tables[task.home].selectExpr(f"CAST({task.home_key} AS BIGINT) AS entity_id")
    else:
        who = facts.where(F.col("ts") <= at(t)).where(task.eligible).select("entity_id").distinct()
    return who.join(agg, "entity_id", "left").select("entity_id", at(t).alias("t"), F.coalesce("y", F.lit(float(task.absent))).alias("y"))


def time_split(task, tables: dict[str, DataFrame]) -> DataFrame:
    """Labels at the three cutoffs, train before valid before test."""
    out = None
    for split, t in zip(("train", "valid", "test"), task.cutoffs):
        part = horizon_labels(task, tables, t).withColumn("split", F.lit(split))
        out = part if out is None else out.unionByName(part)
    return out


def sample_seeds(labels: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """A bounded set in a fixed pseudo-random order (the same in any engine)."""
    return labels.orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col("entity_id").cast("string")).cast("binary")), "entity_id").limit(n)


def leak_guard(s: DataSlice, t: str) -> DataFrame:
    """(table_name, late): rows stamped after t in each time-bearing table; all must be 0."""
    out = None
    for n, df in s.tables.items():
        time = s.catalog.tables[n].time if n in s.catalog.tables else None
        if time in df.columns:
            row = df.agg(F.count(F.when(F.col(time) > at(t), 1)).alias("late")).select(F.lit(n).alias("table_name"), "late")
            out = row if out is None else out.unionAll(row)
    return out


def label_stats(labels: DataFrame) -> DataFrame:
    """Base rate and centre of the labels per split."""
    own = labels.groupBy("split").agg(F.count("*").alias("n"), F.round(F.avg("y"), 6).alias("mean_y"))
    middle = quantiles(labels, "y", {"median_y": 0.5}, ("split",)).withColumnRenamed("split", "part")
    return own.join(middle, own.split.eqNullSafe(middle.part), "left").select("split", "n", "mean_y", F.round("median_y", 6).alias("median_y"))


def column_stats(df: DataFrame, columns: list[str]) -> DataFrame:
    """One pass; rows, distinct values and nulls per column, as rows."""
    aggs = [x for c in columns for x in (F.count_distinct(c).alias(f"d_{c}"), F.count(F.when(F.col(c).isNull(), 1)).alias(f"n_{c}"))]
    one = df.agg(F.count("*").alias("rows"), *aggs)
    rows = [F.struct(F.lit(c).alias("column_name"), F.col("rows").alias("n_rows"), F.col(f"d_{c}").alias("n_distinct"), F.col(f"n_{c}").alias("n_null")) for c in columns]
    return one.select(F.inline(F.array(*rows)))
