"""Boosted trees from grouped histograms (B3, B4): one aggregate a level or split, trees as SQL.

Histograms have at most leaves × features × bins rows whatever the table; they come to the driver,
which picks the split. A fitted model is one SQL expression over the raw columns, so scoring stays in
the engine.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

LAMBDA, PRIOR = 1.0, 0.5


def ordered_target_statistic(df: DataFrame, column: str, y: str, order: str, prior: float = 0.5, weight: float = 1.0, name: str = "stat") -> DataFrame:
    """Each row's category as the mean label of the rows before it in a random order. ``order`` is a
    string such as a hash; its first two characters cut a category into slots with prefix sums, so a
    category of most rows is spread over as many tasks."""
    own = df.withColumn("_slot", F.substring(order, 1, 2))
    sums = own.groupBy(F.col(column).alias("_c"), F.col("_slot").alias("_s")).agg(F.sum(y).alias("_y0"), F.count("*").alias("_n0"))
    before = Window.partitionBy("_c").orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select("_c", "_s", *(F.coalesce(F.sum(c).over(before), F.lit(0)).alias(c) for c in ("_y0", "_n0")))
    w = Window.partitionBy(column, "_slot").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    own = own.withColumn("_y1", F.coalesce(F.sum(y).over(w), F.lit(0.0))).withColumn("_n1", F.count("*").over(w))
    own = own.join(sums, F.col(column).eqNullSafe(F.col("_c")) & F.col("_slot").eqNullSafe(F.col("_s")))
    stat = (F.col("_y0") + F.col("_y1") + weight * prior) / (F.col("_n0") + F.col("_n1") + weight)
    return own.withColumn(name, stat).drop("_slot", "_c", "_s", "_y0", "_n0", "_y1", "_n1")


def target_table(df: DataFrame, column: str, y: str, name: str, prior: float = 0.5, weight: float = 1.0) -> DataFrame:
    """The statistic of whole categories, for rows that are scored."""
    return df.groupBy(F.col(column).alias(f"{name}_key")).agg(((F.coalesce(F.sum(y), F.lit(0.0)) + weight * prior) / (F.count("*") + weight)).alias(name))


@dataclass(frozen=True)
class Boosted:
    expression: str
    task: str
    tables: tuple[tuple[str, str, DataFrame], ...] = ()  # (column, statistic, its table)

    def predict(self, df: DataFrame) -> DataFrame:
        raw, own = F.expr(self.expression), df
        for column, name, table in self.tables:
            own = own.join(table, F.col(column).eqNullSafe(F.col(f"{name}_key")), "left").withColumn(name, F.coalesce(name, F.lit(PRIOR)))
        return own.select(*df.columns, (1 / (1 + F.exp(-raw)) if self.task == "binary" else raw).alias("score"))


def _tree_sql(tree) -> str:
    """A tree (condition, yes, no) or leaf number as one expression, linear in its leaves."""
    return str(tree) if isinstance(tree, int) else f"CASE WHEN {tree[0]} THEN {_tree_sql(tree[1])} ELSE {_tree_sql(tree[2])} END"


def _grown(tree, leaf: int, condition: str, new: int):
    """The tree with ``leaf`` split: ``new`` where the condition holds."""
    if isinstance(tree, int):
        return (condition, new, leaf) if tree == leaf else tree
    return (tree[0], _grown(tree[1], leaf, condition, new), _grown(tree[2], leaf, condition, new))


def _number(x: float) -> str:
    return f"CAST({float(x)!r} AS DOUBLE)"


def _histogram(work: DataFrame, leaf, edges: dict[str, list[float]]):
    def place(i, name, cuts):
        return F.struct(F.lit(i).alias("f"), F.size(F.filter(F.array(*map(F.lit, cuts)), lambda c: c < F.col(name))).alias("b"))

    bins = F.array(*(place(i, name, cuts) for i, (name, cuts) in enumerate(edges.items())))
    own = work.select(leaf.alias("leaf"), "g", "h", F.explode(bins).alias("x"))
    rows = own.groupBy("leaf", "x.f", "x.b").agg(F.sum("g").alias("g"), F.sum("h").alias("h")).collect()
    out: dict[int, dict[int, dict[int, tuple[float, float]]]] = {}
    for r in rows:
        out.setdefault(r.leaf, {}).setdefault(r.f, {})[r.b] = (r.g, r.h)
    return out


def _splits(bins: dict[int, tuple[float, float]], n: int):
    """(cut index, score after the split minus before) for every cut of one leaf and feature."""
    G, H = sum(g for g, _ in bins.values()), sum(h for _, h in bins.values())
    a = b = 0.0
    for i in range(n):
        g, h = bins.get(i, (0.0, 0.0))
        a, b = a + g, b + h
        yield i, a * a / (b + LAMBDA) + (G - a) ** 2 / (H - b + LAMBDA) - G * G / (H + LAMBDA)


def boost(df: DataFrame, features: list[str], y: str, task: str = "binary", kind: str = "symmetric", rounds: int = 8, depth: int = 3, leaves: int = 6, bins: int = 16, rate: float = 0.3, top: float = 1.0, rest: float = 0.0, categorical: tuple[str, ...] = ()) -> Boosted:
    """B3 (``symmetric``: one split for all leaves of a level) and B4 (``leafwise``: the leaf with the
    greatest gain is split; with ``top`` < 1 rows with large gradients and a weighted share ``rest`` of
    the others are used). ``categorical`` columns enter as target statistics: ordered ones in training,
    those of whole categories in scoring."""
    tables = tuple((c, f"{c}__stat", target_table(df, c, y, f"{c}__stat")) for c in categorical)
    if categorical:
        df = df.withColumn("_order", F.md5(F.concat_ws("|", *(F.col(c).cast("string") for c in df.columns)).cast("binary")))
        for c, name, _ in tables:
            df = ordered_target_statistic(df, c, y, "_order", name=name)
        features, df = [*features, *(name for _, name, _ in tables)], df.persist()
    q = [i / bins for i in range(1, bins)]
    cuts = df.agg(*(F.percentile_approx(f, q, 1000).alias(f) for f in features)).first()
    edges = {f: sorted({float(x) for x in cuts[f] or []}) for f in features}
    edges = {f: c for f, c in edges.items() if c}
    raw = _number(0.0)
    names = list(edges)
    for k in range(rounds):
        p = F.expr(raw)
        s = 1 / (1 + F.exp(-p))
        resid = F.col(y) - (s if task == "binary" else p)
        work = df.select(*names, F.col(y).alias("_y"), p.alias("_p"), (resid if task == "binary" else F.signum(resid)).alias("g"), (s * (1 - s) if task == "binary" else F.lit(1.0)).alias("h"))
        if kind == "leafwise" and top < 1:
            limit = work.agg(F.percentile_approx(F.abs("g"), 1 - top, 1000)).first()[0]
            big = F.abs("g") >= F.lit(limit)
            luck = F.pmod(F.xxhash64(*names, F.lit(k)), F.lit(1000)) < int(1000 * rest / (1 - top))
            work = work.where(big | luck)
            by = F.when(big, 1.0).otherwise((1 - top) / rest)
            work = work.withColumn("g", F.col("g") * by).withColumn("h", F.col("h") * by)
        leaf, tree = "0", 0
        if kind == "symmetric":
            for level in range(depth):
                gain: dict[tuple[int, int], float] = {}
                for per in _histogram(work, F.expr(leaf), edges).values():
                    for f, b in per.items():
                        for i, x in _splits(b, len(edges[names[f]])):
                            gain[f, i] = gain.get((f, i), 0.0) + x
                (f, i), best = max(gain.items(), key=lambda x: (x[1], -x[0][0], -x[0][1]))
                if best <= 1e-9:
                    break
                leaf = f"{leaf} + CASE WHEN {names[f]} > {_number(edges[names[f]][i])} THEN {1 << level} ELSE 0 END"
        else:
            for n in range(1, leaves):
                choice = [(x, lf, f, i) for lf, per in _histogram(work, F.expr(leaf), edges).items() for f, b in per.items() for i, x in _splits(b, len(edges[names[f]]))]
                x, lf, f, i = max(choice, key=lambda c: (c[0], -c[1], -c[2], -c[3]))
                if x <= 1e-9:
                    break
                tree = _grown(tree, lf, f"{names[f]} > {_number(edges[names[f]][i])}", n)
                leaf = _tree_sql(tree)
        own = work.groupBy(F.expr(leaf).alias("leaf"))
        value = F.sum("g") / (F.sum("h") + LAMBDA) if task == "binary" else F.percentile_approx(F.col("_y") - F.col("_p"), 0.5, 1000)
        rows = own.agg(value.alias("v")).collect()
        raw = f"{raw} + CASE {leaf} " + " ".join(f"WHEN {r.leaf} THEN {_number(rate * r.v)}" for r in rows) + f" ELSE {_number(0.0)} END"
    return Boosted(raw, task, tables)
