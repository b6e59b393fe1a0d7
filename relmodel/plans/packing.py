"""Encoding of tables and packing of ego graphs (E1-E5, G8, G10, G12): everything before the model.

All of it is plans: samples are cut to k before each shuffle, a packed row is written once and then
trained on and scored without any shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmodel.catalog import CATALOG, Catalog, TableSpec, node_id
from relmodel.functions.embed import text_vector
from relmodel.nn.layers import Schema
from relmodel.nn.relational import Step
from relmodel.operators.graph import latest_rows, sample_neighbours
from relmodel.operators.slices import at
from relmodel.session import saved

TEXT_WIDTH = 16


@dataclass(frozen=True)
class Encoder:
    """How a table's attributes become numbers: statistics of the training state only."""

    numerical: tuple[tuple[str, float, float], ...] = ()
    times: tuple[tuple[str, int], ...] = ()
    categorical: tuple[tuple[str, tuple[str, ...]], ...] = ()
    texts: tuple[str, ...] = ()

    @property
    def columns(self) -> list[str]:
        return [x[0] for x in (*self.numerical, *self.times, *self.categorical)] + list(self.texts)

    @property
    def schema(self) -> Schema:
        vectors = [(c, 7) for c, _ in self.times] + [(c, TEXT_WIDTH) for c in self.texts]
        parts = [f"{c}.{i}" for c, n in vectors for i in range(n)]
        return Schema([c for c, _, _ in self.numerical] + parts or ["one"], [(c, len(v)) for c, v in self.categorical], vectors)

    def x(self):
        """Numbers, then a vector per timestamp (E5: years since the base in tens; month, day and hour as
        sine and cosine) and per text (E4)."""
        out = [(F.col(c).cast("double") - F.lit(m)) / F.lit(s) for c, m, s in self.numerical]
        for c, base in self.times:
            out.append((F.year(c) - base) / F.lit(10.0))
            for part, n in ((F.month(c), 12.0), (F.dayofmonth(c), 31.0), (F.hour(c), 24.0)):
                out += [F.sin(part * F.lit(6.283185307179586 / n)), F.cos(part * F.lit(6.283185307179586 / n))]
        own = F.array(*(out or ([] if self.texts else [F.lit(1.0)]))).cast("array<double>")
        return F.concat(own, *(text_vector(F.col(c), c, TEXT_WIDTH) for c in self.texts)) if self.texts else own

    def c(self):
        """Vocabulary places from 1 on, 0 for unknown values."""
        out = [F.coalesce(F.array_position(F.array(*map(F.lit, v)), F.col(c).cast("string")).cast("int"), F.lit(0)) if v else F.lit(0) for c, v in self.categorical]
        return F.array(*out) if out else F.array().cast("array<int>")


def fit_encoder(df: DataFrame, spec: TableSpec, skip: tuple[str, ...] = (), cap: int = 64) -> Encoder:
    """One pass for the numbers, one bounded count per categorical column. Texts that name their row
    (nearly all distinct) are left out."""
    have = [c for c in df.columns if c in spec.columns and c not in skip]
    num = [c for c in have if spec.columns[c] == "numerical"]
    tim = [c for c in have if spec.columns[c] == "timestamp"]
    cat = [c for c in have if spec.columns[c] == "categorical"]
    txt = [c for c in have if spec.columns[c] == "text"]
    row = df.agg(F.count("*"), *(f(c) for c in num for f in (F.avg, F.stddev_pop)), *(F.min(F.year(c)) for c in tim), *(F.approx_count_distinct(c) for c in txt)).first()
    numbers = tuple((c, float(row[1 + 2 * i] or 0), float(row[2 + 2 * i] or 0) or 1.0) for i, c in enumerate(num))
    times = tuple((c, int(row[1 + 2 * len(num) + i] or 2000)) for i, c in enumerate(tim))
    words = []
    for c in cat:
        top = df.where(F.col(c).isNotNull()).groupBy(F.col(c).cast("string").alias("v")).count().orderBy(F.desc("count"), "v").limit(cap)
        words.append((c, tuple(r.v for r in top.collect())))
    texts = tuple(c for c, n in zip(txt, row[1 + 2 * len(num) + len(tim) :]) if n < 0.8 * row[0])
    return Encoder(numbers, times, tuple(words), texts)


@dataclass(frozen=True)
class PackPlan:
    target: str
    steps: tuple[Step, ...]
    encoders: dict[str, Encoder]
    k: int = 32
    strategy: str = "latest"
    seed: int = 0
    catalog: Catalog = field(default_factory=lambda: CATALOG)

    def schemas(self) -> dict[str, Schema]:
        return {n: e.schema for n, e in self.encoders.items()}


def fit_plan(tables: dict[str, DataFrame], target: str, steps: list[Step], skip=(), **more) -> PackPlan:
    names = [target, *(s.table for s in steps)]
    return PackPlan(target, tuple(steps), {n: fit_encoder(tables[n], CATALOG.tables[n], tuple(skip)) for n in dict.fromkeys(names)}, **more)


def pack(seeds: DataFrame, tables: dict[str, DataFrame], plan: PackPlan, as_of: str | None = None, few: bool = False) -> DataFrame:
    """seeds (seed_id string, y, split, …) with x, c of the target row and, per step's relation, an
    array of (at, x, c) of the sampled neighbours visible at ``as_of``. ``few``: the seeds are a bounded
    sample, so they and the nodes met are sent to the tables' rows, which are not shuffled. Seeds, and
    neighbours that a later step starts from, are written, since several joins read them."""
    cat, enc = plan.catalog, plan.encoders
    sent = F.broadcast if few else lambda df: df
    seeds = saved(seeds)
    own = tables[plan.target].select(F.expr(node_id(plan.target, cat)).alias("seed_id"), _raw(enc[plan.target]))
    out = own.join(sent(seeds), "seed_id").select(*seeds.columns, "own")
    front = {plan.target: seeds.select("seed_id", F.lit(0).alias("pos"), F.col("seed_id").alias("node_id"))}
    for i, s in enumerate(plan.steps):
        later = any(x.source == s.table for x in plan.steps[i + 1 :])
        key = next(k for k in cat.keys if k.name == s.relation)
        here = front[s.source]
        other = tables[s.table]
        body = _raw(enc[s.table])
        if s.down:
            time = cat.tables[s.table].time
            rows = other.where(F.col(time) <= at(as_of)) if as_of and time in other.columns else other
            stamp = F.col(time) if time in other.columns else F.lit(None).cast("timestamp_ntz")
            nodes = here.select("node_id").distinct()
            nodes = sent(nodes) if few else nodes.hint("shuffle_hash")  # the rows are sorted once, for the window
            if plan.strategy == "latest" and not cat.tables[s.table].key and not later:  # the id only breaks ties
                nbrs = rows.withColumn("node_id", F.col(key.child_col).cast("string")).join(nodes, "node_id", "left_semi").withColumn("ts", stamp)
                nbrs = latest_rows(nbrs, plan.k, "node_id", "ts", node_id(s.table, cat)).select("node_id", F.lit(None).cast("string").alias("nbr_id"), "rn", body)
            else:
                nbrs = rows.select(F.col(key.child_col).cast("string").alias("node_id"), F.expr(node_id(s.table, cat)).alias("nbr_id"), stamp.alias("ts"), body)
                nbrs = sample_neighbours(nbrs.join(nodes, "node_id", "left_semi"), plan.k, plan.strategy, plan.seed)
        else:
            fk = tables[s.source].select(F.expr(node_id(s.source, cat)).alias("node_id"), F.col(key.child_col).alias("fk"))
            parent = other.select(F.col(key.parent_col).alias("fk"), F.expr(node_id(s.table, cat)).alias("nbr_id"), body)
            nbrs = parent.join(sent(fk.join(sent(here.select("node_id").distinct()), "node_id")), "fk").select("node_id", "nbr_id", "own", F.lit(1).alias("rn"))
        if s.source == plan.target:  # the node is the seed: its neighbours are numbered already
            met = nbrs.select(F.col("node_id").alias("seed_id"), F.lit(0).alias("at"), "nbr_id", "own", (F.col("rn") - 1).alias("pos"))
        else:
            met = here.join(nbrs, "node_id").select("seed_id", F.col("pos").alias("at"), "nbr_id", "rn", "own")
            place = F.row_number().over(Window.partitionBy("seed_id").orderBy("at", "rn")) - 1  # one row a place
            met = met.withColumn("pos", place)
        met = saved(met) if later else met
        front[s.table] = met.select("seed_id", "pos", F.col("nbr_id").alias("node_id"))
        coded = met.select("seed_id", "pos", "at", "own.*").select("seed_id", "pos", "at", enc[s.table].x().alias("x"), enc[s.table].c().alias("c"))
        array = coded.groupBy("seed_id").agg(F.sort_array(F.collect_list(F.struct("pos", "at", "x", "c"))).alias(s.relation))
        array = array.select("seed_id", F.transform(s.relation, lambda g: F.struct(g["at"].alias("at"), g["x"].alias("x"), g["c"].alias("c"))).alias(s.relation))
        out = out.join(array, "seed_id", "left")
    relations = [s.relation for s in plan.steps]
    out = out.select(*seeds.columns, "own.*", *relations)
    return out.select(*seeds.columns, enc[plan.target].x().alias("x"), enc[plan.target].c().alias("c"), *relations)


def _raw(e: Encoder):
    """The attributes of a row as they are: they are encoded after their last join, for the rows that are left."""
    return F.struct(*(e.columns or [F.lit(None).alias("none")])).alias("own")
