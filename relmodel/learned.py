"""Queries that train or run models (no SQL twin): bases, augmentation, dispatch, studies, search."""

from __future__ import annotations

import uuid
from dataclasses import dataclass, replace
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.catalog import load
from relmodel.nn.relational import Config, Step
from relmodel.operators import slices
from relmodel.plans.packing import PackPlan, fit_plan, pack
from relmodel.session import saved, shared_folder
from relmodel.workloads import ORDER_CUTOFFS, TASKS, planted

QUERIES = {}
T = ORDER_CUTOFFS[2]
STEPS = (Step("order_customer", "customer", "orders"), Step("line_order", "orders", "lineitem"))
TABLES = ["nation", "customer", "supplier", "orders", "lineitem", "part", "events"]
TRAIN = {"epochs": 12, "batch": 64, "rate": 0.01}


def query(f):
    QUERIES[f.__name__] = f
    return f


def split_column(entity):
    """Three parts in a fixed pseudo-random order, for rows without time (documents)."""
    h = F.pmod(F.xxhash64(entity), F.lit(10))
    return F.when(h < 6, "train").when(h < 8, "valid").otherwise("test")


SPLITS = ("train", "valid", "test")


def cutoffs_of(name: str) -> tuple[str, str, str]:
    return TASKS[name].cutoffs if name in TASKS else ORDER_CUTOFFS


def kind_of(name: str) -> str:
    return "regression" if name in ("pl2", "pl3", "pl4") or (name in TASKS and TASKS[name].kind == "regression") else "binary"


def task_labels(name: str, t):
    """(entity_id, y, split) at the three cutoffs of a task, train before valid before test. Labels
    of regressions are in units of the train part's deviation from its mean."""
    if name in TASKS:
        labels = slices.time_split(TASKS[name], t).select("entity_id", "y", "split")
    else:
        labels = None
        for split, cut in zip(SPLITS, ORDER_CUTOFFS):
            part = planted(name, t, cut).withColumn("split", F.lit(split))
            labels = part if labels is None else labels.unionByName(part)
    if kind_of(name) == "regression":
        labels = saved(labels)  # read twice
        m = labels.where("split = 'train'").agg(F.avg("y"), F.stddev_pop("y")).first()
        labels = labels.withColumn("y", (F.col("y") - F.lit(m[0] or 0.0)) / F.lit(m[1] or 1.0))
    return labels


@dataclass(frozen=True)
class Prepared:
    """Tables, labels and encoders of a task, for all its packings."""

    tables: dict
    labels: DataFrame
    plan: PackPlan


def prepared(spark, sf, name: str, steps=STEPS, target: str = "customer", skip=()) -> Prepared:
    """Labels are computed once and written: every part and every hop of a packing reads them."""
    t = load(spark, sf, TABLES)
    state = slices.state_at(slices.data_slice(t, target), cutoffs_of(name)[0]).tables
    return Prepared(t, saved(task_labels(name, t)), fit_plan(state, target, list(steps), skip))


def packed_parts(spark, sf, name: str, parts, seeds: int = 500, k: int = 16, strategy: str = "latest", steps=STEPS, target: str = "customer", skip=(), known: Prepared | None = None):
    """([packed rows per part], plan) of a task. Each split is packed at its own cutoff from the state
    at it, and the encoder is fitted on the state at the train cutoff, so nothing later than a cutoff
    reaches its rows. Parts: ``sample`` (at most ``seeds`` of the three splits), ``fit`` (at most
    ``seeds`` of train and valid), ``past`` (train and valid as an earlier round: the valid cutoff is its
    test, a fifth of train its valid part) and ``test``, ``all`` (every entity of the test cutoff)."""
    known = known or prepared(spark, sf, name, steps, target, skip)
    t, labels, cuts = known.tables, known.labels, dict(zip(SPLITS, cutoffs_of(name)))
    plan = replace(known.plan, k=k, strategy=strategy)

    def packed(split: str, most: int | None, marked=None):
        own = labels.where(F.col("split") == split)
        own = own if most is None else slices.sample_seeds(own, most)
        mark = F.col("split") if marked is None else marked
        return pack(own.select(F.col("entity_id").cast("string").alias("seed_id"), "y", mark.alias("split")), t, plan, as_of=cuts[split], few=most is not None)

    def part(p: str):
        if p in ("test", "all"):
            return packed("test", None)
        if p == "past":
            early = F.when(F.pmod(F.xxhash64("entity_id"), F.lit(5)) == 0, "valid").otherwise("train")
            return packed("train", seeds * 2 // 3, early).unionByName(packed("valid", seeds - seeds * 2 // 3, F.lit("test")))
        out = packed("train", seeds * (3 if p == "sample" else 4) // 5).unionByName(packed("valid", seeds // 5))
        return out.unionByName(packed("test", seeds // 5)) if p == "sample" else out

    return [part(p) for p in parts], plan


def packed_task(spark, sf, name: str, **more):
    """(packed rows, plan) of a bounded sample of a task's entities."""
    (packed,), plan = packed_parts(spark, sf, name, ["sample"], **more)
    return packed, plan


def study(spark, sf, name: str, specs: list[dict], **more):
    """Fitted on a bounded sample of the train and valid cutoffs, measured on every entity of the test cutoff."""
    from relmodel.nn.grid import run_grid

    (packed, test), plan = packed_parts(spark, sf, name, ["fit", "test"], **more)
    specs = [{"target": plan.target, "d": 4, "layers": 1, "task": kind_of(name), "train": TRAIN} | s for s in specs]
    return run_grid(packed, specs, plan.schemas(), plan.steps, test).withColumn("task", F.lit(name))


@query
def w11_overall(spark, sf):
    """Bases alone and augmented on a planted task, with tabular baselines and the floor."""
    from relmodel.nn.bases import NEURAL

    specs = [{"base": b, "augmented": a} for b in NEURAL for a in (False, True)] + [{"base": b} for b in ("constant", "incontext", "two_stage_incontext")]
    return study(spark, sf, "pl1", specs)


#: The way each natural task is answered: its target table and hops. W9 labels the target row itself,
#: and W4's entity has no table, so neither has a packed form here.
WAYS = {
    "customer_churn": ("customer", STEPS), "customer_active": ("customer", STEPS),
    "user_click": ("customer", (Step("event_customer", "customer", "events"), Step("order_customer", "customer", "orders"))),
    "part_sales": ("part", (Step("line_part", "part", "lineitem"),)), "part_positive": ("part", (Step("line_part", "part", "lineitem"),)),
    "supplier_success": ("supplier", (Step("line_supplier", "supplier", "lineitem"),)),
} | {n: ("customer", (Step("event_customer", "customer", "events"),)) for n in ("user_repeat", "user_attend")}


def _natural(name):
    def run(spark, sf):
        target, steps = WAYS[name]
        specs = [{"base": "constant"}, {"base": "residual", "augmented": False}, {"base": "residual"}]
        return study(spark, sf, name, specs, seeds=300, target=target, steps=steps)

    run.__doc__ = f"W11 on the natural task {name}: the floor, a base alone and augmented."
    QUERIES[f"w11_{name}"] = run


for _name in WAYS:
    _natural(_name)


@query
def w12_ablation(spark, sf):
    return study(spark, sf, "pl1", [{}, {"use_passing": False}, {"use_fusion": False}, {"use_relations": False}, {"augmented": False}])


@query
def w13_cost(spark, sf):
    """Parameters of the base and of its augmentation (without embedding tables) at width 128 on
    slices of 2 to 7 tables, whose attributes are those of the given tables."""
    from relmodel.nn.relational import BaseModel, RelationalModel, param_count, passing_params

    t = load(spark, sf, TABLES)
    state = slices.state_at(slices.data_slice(t, "customer"), ORDER_CUTOFFS[0]).tables
    hops = [*STEPS, Step("customer_nation", "customer", "nation", False), Step("event_customer", "customer", "events"), Step("line_part", "lineitem", "part", False), Step("line_supplier", "lineitem", "supplier", False)]
    every, out = fit_plan(state, "customer", hops).schemas(), []
    for n in range(1, len(hops) + 1):
        steps = tuple(hops[:n])
        c = Config("customer", {x: every[x] for x in ["customer", *(s.table for s in steps)]}, steps, d=128)
        base, both = param_count(BaseModel(c).start()), param_count(RelationalModel(c).start())
        out.append((n + 1, base, both - base, both / base, passing_params(128, n, c.layers)))
    return spark.createDataFrame(out, "tables int, base_params long, extra_params long, ratio double, passing_params long")


@query
def w14_encoder(spark, sf):
    return study(spark, sf, "pl1", [{"encoder_layers": n, "heads": h} for n in (1, 2, 3) for h in (1, 2, 4)], seeds=300)


@query
def w15_depth_aggregator(spark, sf):
    return study(spark, sf, "pl1", [{"layers": n, "agg": a, "use_fusion": False} for n in (1, 2, 3) for a in ("min", "max", "sum", "mean")], seeds=300, k=8)


@query
def w16_sampling(spark, sf):
    """Sample size and strategy on the recency task; messages pass over the sampled rows. One hop only."""
    way = {"steps": (Step("line_part", "part", "lineitem"),), "target": "part"}
    known, sizes, got = prepared(spark, sf, "pl3", **way), (8, 32), {}
    for how in ("latest", "uniform"):  # the larger sample begins with the smaller one, so both come of one packing
        runs = study(spark, sf, "pl3", [{"first": k} for k in sizes], seeds=300, k=max(sizes), strategy=how, known=known, **way)
        got |= {(k, how): runs.where(F.get_json_object("config", "$.first") == k).withColumn("k", F.lit(k)).withColumn("strategy", F.lit(how)) for k in sizes}
    return reduce(DataFrame.unionAll, (got[k, how] for k in sizes for how in ("latest", "uniform")))


@query
def w17_importance(spark, sf):
    """The four strongest signals per planted task."""
    return study(spark, sf, "pl1", [{"use_passing": False}]).select("task", "metric", "top")


@query
def w22_schema_richness(spark, sf):
    """The same task with no, one and two related tables."""
    return study(spark, sf, "pl1", [{"augmented": False}, {"hops": 1}, {"hops": 2}])


@query
def w21_variability(spark, sf):
    """Gain of augmentation by group of bases and task type, on PL1 and PL2."""
    import json

    from relmodel.operators.metrics import gain_summary, relative_gain

    groups = {"mlp": "plain", "residual": "plain", "tokens": "attention", "ensemble": "ensemble"}
    rows = []
    for name in ("pl1", "pl2"):
        got = {}
        for r in study(spark, sf, name, [{"base": b, "augmented": a} for b in groups for a in (False, True)], seeds=200).collect():  # one row a run
            c = json.loads(r.config)
            got[c["base"], c["augmented"]] = float(r.metric)
        rows += [(groups[b], kind_of(name), got[b, False], got[b, True]) for b in groups]
    runs = spark.createDataFrame(rows, "grp string, kind string, base double, augmented double")
    return gain_summary(runs.withColumn("gain", relative_gain(F.col("base"), F.col("augmented"), F.col("kind") == "binary")))


@query
def latency_ratio(spark, sf):
    """Seconds to score every entity with the base alone and augmented, and their ratio."""
    from relmodel.nn.train import model_of, score
    from relmodel.operators.metrics import latency

    (every,), plan = packed_parts(spark, sf, "pl1", ["all"])
    path = f"{shared_folder(spark)}/relmodel-packed-{spark.sparkContext.applicationId}-{uuid.uuid4().hex}"
    every.write.parquet(path)  # ego graphs are packed once; scoring them is what is timed
    every, c = spark.read.parquet(path), Config(plan.target, plan.schemas(), plan.steps, d=4, layers=1)
    base, both = (latency(score(every, c, model_of(c, a).start(), a), 2) for a in (False, True))
    return spark.createDataFrame([(base, both, both / base)], "base_s double, augmented_s double, ratio double")


@query
def predict_mlp(spark, sf):
    return _trained(spark, sf, augmented=False, base="mlp")


@query
def predict_augmented(spark, sf):
    return _trained(spark, sf, augmented=True, base="residual")


def _trained(spark, sf, augmented, base, backend="grouped", signals=False):
    """Fitted on a bounded sample; every entity of the cutoff is scored."""
    from relmodel.nn.train import TrainConfig, fit_grouped, fit_local_sgd, fit_sync, score
    import pickle

    (packed, every), plan = packed_parts(spark, sf, "pl1", ["fit", "all"], seeds=300)
    packed = saved(packed.withColumn("run", F.lit(0).cast("long")))  # bounded, and read once an epoch
    c = Config("customer", plan.schemas(), plan.steps, d=4, layers=1, base=base)
    cfg = TrainConfig(epochs=6, batch=64)
    if backend == "grouped":
        params = pickle.loads(fit_grouped(packed, c, cfg, augmented).first().params)
    else:
        params, _ = (fit_sync if backend == "sync" else fit_local_sgd)(packed.where("split = 'train'").repartition(4, "seed_id"), c, cfg, augmented)
    out = score(every, c, params, augmented).withColumn("score", F.round("score", 6))
    return out if signals else out.select("seed_id", "score", F.size("signals").alias("n_signals"))


@query
def train_sync(spark, sf):
    return _trained(spark, sf, True, "residual", "sync")


@query
def train_local_sgd(spark, sf):
    return _trained(spark, sf, True, "residual", "local_sgd")


def _tabular(spark, sf):
    """Own columns of customers with labels of the train and the test cutoff."""
    t = load(spark, sf, ["customer", "orders"])
    own = task_labels("customer_active", t).join(t["customer"], F.col("entity_id") == F.col("c_custkey"))
    own = own.select("entity_id", "y", "c_acctbal", "c_nationkey", "c_mktsegment", "split")
    return own.where("split = 'train'"), own.where("split = 'test'")


def _library(kind):
    def run(spark, sf):
        from relmodel.nn.spark_bases import fit_predict

        train, test = _tabular(spark, sf)
        return fit_predict(train, test, ["c_acctbal"], ["c_nationkey", "c_mktsegment"], kind, "binary").select("entity_id", F.round("score", 6).alias("score"))

    QUERIES[f"base_{kind}"] = run


_library("linear")
_library("forest")


def _own_boost(name, **how):
    def run(spark, sf):
        from relmodel.nn.boost import boost

        train, test = _tabular(spark, sf)
        return boost(train, ["c_acctbal"], "y", rounds=3, categorical=("c_nationkey", "c_mktsegment"), **how).predict(test).select("entity_id", F.round("score", 6).alias("score"))

    QUERIES[name] = run


_own_boost("base_ordered_boost", kind="symmetric")
_own_boost("base_leafwise_boost", kind="leafwise", top=0.3, rest=0.3)


@query
def base_text(spark, sf):
    """Frozen text vectors of serialised rows with a linear head (B15-B18, W19). The head is fitted on
    at most 400 documents of the train part; every labelled document is encoded and scored, and the
    area is that of the whole test part. ``n_null``: documents too long for a kind."""
    from relmodel.operators.metrics import roc_area

    out = None
    scores = base_text_scores(spark, sf).cache()
    for kind in TEXT_KINDS:
        own = scores.where((F.col("kind") == kind) & (F.col("split") == "test"))
        row = own.agg(F.count("*").alias("n"), F.count(F.when(F.col("score").isNull(), 1)).alias("n_null"))
        row = roc_area(own.where("score IS NOT NULL").select("y", F.round("score", 9).alias("score"))).crossJoin(row).select(F.lit(kind).alias("kind"), "area", "n", "n_null")  # one row each
        out = row if out is None else out.unionAll(row)
    return out


TEXT_KINDS = ("general_text", "pooled_text", "magnitude_text")
TEXT_SCHEMA = "doc_id long, split string, y double, kind string, score double"


def base_text_scores(spark, sf):
    """(doc_id, split, y, kind, score) of every labelled document; score is null over the limit."""
    import numpy as np
    import pyarrow as pa

    from relmodel.functions.embed import serialise
    from relmodel.nn.bases import TextBase, magnitude_edges

    d = load(spark, sf, ["documents", "labels"])
    own = d["documents"].join(d["labels"], "doc_id").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("double").alias("y"), split_column("doc_id").alias("split"), "lang", "source", F.col("n_chars").cast("double").alias("n_chars"), "text", serialise({"lang": "lang", "source": "source", "text": "text"}).alias("s"))
    fitted = own.where("split = 'train' AND y IS NOT NULL").orderBy(F.md5(F.col("doc_id").cast("string").cast("binary")), "doc_id").limit(400).toPandas()  # bounded

    def inputs(kind, rows):
        if kind != "magnitude_text":
            return [r["s"] for r in rows]
        return [{k: r[k] for k in ("lang", "source", "n_chars", "text")} for r in rows]

    models, rows = {}, fitted.to_dict("records")
    for kind in TEXT_KINDS:
        m = TextBase(kind, edges=magnitude_edges({"n_chars": fitted["n_chars"]}))
        models[kind] = m.fit(m.encode(inputs(kind, rows)), fitted["y"].to_numpy())
    shared = spark.sparkContext.broadcast(models)

    def run(batches):
        for b in batches:
            for i in range(0, b.num_rows, 256):
                part = b.slice(i, 256)
                rows = part.to_pylist()
                for kind, m in shared.value.items():
                    score = m.predict(m.encode(inputs(kind, rows)))
                    cols = [part.column(c) for c in ("doc_id", "split", "y")] + [pa.array([kind] * len(rows)), pa.array(score, mask=np.isnan(score))]
                    yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "split", "y", "kind", "score"])

    return own.mapInArrow(run, TEXT_SCHEMA)


SPACE = {"d": [2, 4, 8, 16], "base": ["mlp", "residual", "tokens"]}


def _search(find):
    def run(spark, sf):
        packed, plan = packed_task(spark, sf, "pl1", seeds=200)
        base = {"target": "customer", "layers": 1, "train": {"epochs": 4, "batch": 64}, "augmented": False}
        out = find(packed.cache(), base, SPACE, plan.schemas(), plan.steps)
        return spark.createDataFrame([(i, c["d"], c["base"], v) for i, (c, v) in enumerate(out)], "place int, width int, base string, valid double")

    return run


@query
def search_tpe(spark, sf):
    """B13 over widths and kinds of base."""
    from relmodel.nn.grid import tpe_search

    return _search(lambda *a: tpe_search(*a, rounds=2, width=4))(spark, sf)


@query
def search_two_phase(spark, sf):
    """B14 over the same space."""
    from relmodel.nn.grid import two_phase_search

    return _search(lambda *a: two_phase_search(*a, sample=8, keep=2))(spark, sf)


@query
def shared_encoder(spark, sf):
    """One encoder, pre-trained on masked attributes, starts two tasks (frozen or not) beside a
    start from nothing; one training a task of Spark."""
    from relmodel.nn.train import TrainConfig, fit, model_of, pretrain, rows_of

    rows, c = {}, None
    for name in ("pl1", "pl5"):
        packed, plan = packed_task(spark, sf, name, seeds=240)
        rows[name] = rows_of(packed.collect())  # bounded
        c = c or Config(plan.target, plan.schemas(), plan.steps, d=4, layers=1)
    shared = spark.sparkContext.broadcast(rows)
    encoder = ("customer.", "orders.", "lineitem.", "enc", "tuple")

    def run(frames):
        for pdf in frames:
            for name, start in zip(pdf["task"], pdf["start"]):
                own, model = shared.value[name], model_of(c)
                part = {k: [r for r in own if r["split"] == k] for k in learned_splits}
                began = None
                if start != "nothing":
                    began, _ = pretrain(model, [r for r in shared.value["pl1"] if r["split"] == "train"], TrainConfig(epochs=4, batch=64))
                _, hist = fit(model, part["train"], part["valid"], TrainConfig(epochs=8, batch=64, freeze=encoder if start == "frozen" else ()), began)
                yield pd.DataFrame([{"task": name, "start": start, "first": hist[0], "best": min(hist)}])

    learned_splits = SPLITS
    todo = [(n, s) for n in rows for s in ("nothing", "frozen", "tuned")]
    return spark.createDataFrame(todo, "task string, start string").repartition(len(todo), "task", "start").mapInPandas(run, "task string, start string, first double, best double")


@query
def proxy_scores(spark, sf):
    """All proxies of a pool on one batch."""
    from relmodel.nn.bases import NEURAL
    from relmodel.nn.train import rows_of
    from relmodel.plans.dispatch import score_pool

    packed, plan = packed_task(spark, sf, "pl1", seeds=128)
    rows = rows_of(packed.collect())  # the probe batch, bounded
    return score_pool(spark, [(b, Config("customer", plan.schemas(), plan.steps, d=4, base=b)) for b in NEURAL], rows)


POOL, RUNS = ("mlp", "residual"), 2


def earlier_round(spark, sf, name: str, seeds: int = 240, known: Prepared | None = None, past=None):
    """What a task's earlier round left: (runs, raws). ``runs``: rows (model_id, run, augmented, perf) of
    the pool trained at the first cutoff and measured at the second; ``raws``: their proxies
    (model_id, proxy, raw) on that round's batch. ``past``: the round's packed rows, if there are some."""
    import json

    from relmodel.nn.grid import run_grid
    from relmodel.nn.train import rows_of
    from relmodel.plans import dispatch as d

    (past,), plan = packed_parts(spark, sf, name, ["past"], seeds=seeds, known=known) if past is None else ((past,), known.plan)
    past = past.cache()
    specs = [{"target": plan.target, "d": 4, "layers": 1, "task": kind_of(name), "train": TRAIN, "base": b, "seed": i, "augmented": a} for b in POOL for i in range(RUNS) for a in (False, True)]
    got = [(json.loads(r.config), r.metric) for r in run_grid(past, specs, plan.schemas(), plan.steps).collect()]  # one row a run
    runs = spark.createDataFrame([(c["base"], c["seed"], c["augmented"], float(v)) for c, v in got], "model_id string, run int, augmented boolean, perf double")
    batch = rows_of(slices.sample_seeds(past.withColumn("entity_id", F.col("seed_id")).where("split <> 'test'"), d.PROBE).drop("entity_id").collect())  # bounded
    pool = [(f"{b}#{i}", Config(plan.target, plan.schemas(), plan.steps, d=4, base=b, seed=i)) for b in POOL for i in range(RUNS)]
    raws = d.score_pool(spark, pool, batch).withColumn("model_id", F.substring_index("model_id", "#", 1))
    return runs, raws.where(F.col("proxy").isin("grad_norm", "naswot")).cache()


def dispatched(spark, sf, name: str, known: Prepared | None = None, past=None):
    """(decision, runs of the earlier round) of one task: the pool's proxies at the starting weights on
    the present batch, calibrated by the earlier round's, give the skill to expect of each base alone;
    the ledger holds what augmented runs reached; the threshold decides."""
    from relmodel.nn.train import rows_of
    from relmodel.plans import dispatch as d

    known = known or prepared(spark, sf, name)
    runs, raws = earlier_round(spark, sf, name, known=known, past=past)
    (now,), plan = packed_parts(spark, sf, name, ["fit"], seeds=d.PROBE, known=known)
    pool = [(b, Config(plan.target, plan.schemas(), plan.steps, d=4, base=b)) for b in POOL]
    raw = d.score_pool(spark, pool, rows_of(now.collect())).where(F.col("proxy").isin("grad_norm", "naswot")).cache()  # the probe batch, bounded
    scores = d.expected_skill(d.calibrate(raw, raws), runs.where("NOT augmented"))
    best = d.select_base(scores).withColumn("task_key", F.lit(name))
    ledger = runs.where("augmented").select("model_id", F.lit(name).alias("task_key"), F.col("run").alias("step"), "perf")
    return d.decisions(best, d.ema(ledger)), runs


@query
def dispatch_end_to_end(spark, sf):
    """Calibrated proxies of a pool, best model, moving average of earlier runs, decision."""
    out = None
    for name in ("pl1", "pl5"):
        got = dispatched(spark, sf, name)[0]
        out = got if out is None else out.unionAll(got)
    return out


@query
def intent_profiles(spark, sf):
    """Questions to checked profiles and SQL fragments that run."""
    from relmodel.plans.intent import RuleAgent, data_profile, join_clauses, parse_task, to_sql

    t = load(spark, sf, ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"])
    for n, df in t.items():
        df.createOrReplaceTempView(n)
    rows = []
    for q in ("Which customers will churn in the next 180 days?", "How many purchases will each user make next week?", "What value of each product will be sold in the next month?"):
        task, problems = parse_task(q, RuleAgent())
        d, more = data_profile(task, t)
        for n, sql in to_sql(d).items():
            rows.append((q, task.task_type, n, sql, len(spark.sql(sql).columns), len(problems) + len(more)))
        for n, clause in join_clauses(d).items():
            sql = f"SELECT * {clause}"
            rows.append((q, task.task_type, n, sql, len(spark.sql(sql).columns), len(problems) + len(more)))
    return spark.createDataFrame(rows, "question string, task_type string, table_name string, sql string, n_columns int, n_problems int")


@query
def report_document(spark, sf):
    """R1-R3 over an augmented prediction."""
    from relmodel.plans.report import report_evidence, write_report

    train, test = _tabular(spark, sf)
    preds = test.select("entity_id", (F.col("c_acctbal") / 10000).alias("score"), "c_mktsegment", "c_nationkey")
    e = report_evidence(preds, ["c_mktsegment"], question="Which customers stay active?", task="customer_active", cutoff=T, strategy={"action": "direct", "reason": "direct"}, metric={"name": "area"}, caveats=["scores are a stand-in"])
    return spark.createDataFrame([(i, line) for i, line in enumerate(write_report(e).markdown.split("\n"))], "line int, text string")


@query
def explain_udtf(spark, sf):
    """Every entity's signals as rows of a table function, from a fitted model's predictions."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="signal string, importance double, rank int")
    class ExpandSignals:
        def eval(self, signals: list):
            ranked = sorted(((r["importance"], r["signal"]) for r in signals or []), key=lambda x: (-x[0], x[1]))
            for i, (v, name) in enumerate(ranked):
                yield name, v, i + 1

    spark.udtf.register("expand_signals", ExpandSignals)
    preds = _trained(spark, sf, augmented=True, base="residual", signals=True)
    return spark.sql("SELECT seed_id, s.signal, round(s.importance, 6) AS importance, s.rank FROM {p}, LATERAL expand_signals(signals) s", p=preds)


@query
def model_registry(spark, sf):
    """Two versions saved, listed, and loaded again: the loaded weights equal the saved ones."""
    import numpy as np

    from relmodel.nn.layers import Schema
    from relmodel.nn.relational import BaseModel
    from relmodel.sources.registry import list_models, load_model, save_model

    path = f"{shared_folder(spark)}/relmodel-registry-{spark.sparkContext.applicationId}-{uuid.uuid4().hex}"
    same = 0
    for seed in (0, 1):
        c = Config("t", {"t": Schema(["a"])}, (), d=4, seed=seed)
        made = BaseModel(c).start()
        version = save_model(spark, path, "residual", "residual", "neural", made, {"d": 4, "seed": seed})
        back, config = load_model(spark, path, "residual", version)
        same += config["seed"] == seed and all(np.array_equal(made[k], back[k]) for k in made)
    return list_models(spark, path).withColumn("loaded_equal", F.lit(same))


@query
def preprocess_cost(spark, sf):
    """Columns of a one-hot coding and the seconds before a library model can fit."""
    from pyspark.ml import Pipeline

    from relmodel.nn.spark_bases import prepare
    from relmodel.operators.metrics import latency

    train, _ = _tabular(spark, sf)
    own = train.withColumn("c_acctbal", F.col("c_acctbal").cast("double"))
    out = Pipeline(stages=prepare(["c_acctbal"], ["c_nationkey", "c_mktsegment"])).fit(own).transform(own)
    width = int(out.schema["features"].metadata["ml_attr"]["num_attrs"]) if "ml_attr" in out.schema["features"].metadata else len(out.first()["features"])
    return spark.createDataFrame([(width, latency(out.select("features"), 2))], "width int, seconds double")


@query
def score_sql_udf(spark, sf):
    """A fitted model as an Arrow function callable from SQL."""
    import numpy as np
    from pyspark.sql.functions import pandas_udf

    train, test = _tabular(spark, sf)
    rows = train.select("y", "c_acctbal", "c_nationkey").orderBy(F.md5(F.col("c_acctbal").cast("string").cast("binary"))).limit(500).collect()  # bounded
    x = np.array([[1.0, r.c_acctbal / 1e4, r.c_nationkey / 25] for r in rows])
    w = np.linalg.lstsq(x.T @ x + 1e-6 * np.eye(3), x.T @ np.array([r.y for r in rows]), rcond=None)[0].tolist()

    @pandas_udf("double")
    def score_customer_active(balance: pd.Series, nation: pd.Series) -> pd.Series:
        return w[0] + w[1] * balance / 1e4 + w[2] * nation / 25

    spark.udf.register("score_customer_active", score_customer_active)
    return spark.sql("SELECT entity_id, round(score_customer_active(c_acctbal, c_nationkey), 6) AS score FROM {t}", t=test)


@query
def dispatch_strategies(spark, sf):
    """The share of tasks augmented, the skill and the loss against the better choice of
    never, always, conditional and best, of one model trained anew for each task, and of a stored pool."""
    import json

    from relmodel.nn.grid import fitted, tested
    from relmodel.plans.dispatch import strategies

    runs = decided = static = None
    for name in ("pl1", "pl5"):
        known = prepared(spark, sf, name)
        (old, test), plan = packed_parts(spark, sf, name, ["past", "test"], seeds=240, known=known)
        old = saved(old)  # bounded, and read by both rounds
        choice, past = dispatched(spark, sf, name, known, old)
        (now,), _ = packed_parts(spark, sf, name, ["fit"], seeds=300, known=known)
        spec = {"target": plan.target, "d": 4, "layers": 1, "task": kind_of(name), "train": TRAIN}
        models = fitted(old, [spec | {"base": b, "augmented": False} for b in POOL], plan.schemas(), plan.steps)
        models += fitted(now, [spec | {"base": b, "augmented": a} for b in POOL for a in (False, True)], plan.schemas(), plan.steps)
        done = tested(spark, models, test).collect()  # one row a run; the test rows are packed once for all of them
        stale, fresh = [(name, json.loads(r.config)["base"], float(r.metric)) for r in done[: len(POOL)]], done[len(POOL) :]
        got = {(json.loads(r.config)["base"], json.loads(r.config)["augmented"]): float(r.metric) for r in fresh}
        parts = (
            spark.createDataFrame([(name, b, got[b, False], got[b, True]) for b in POOL], "task_key string, model_id string, direct double, augmented double"),
            saved(choice.select("task_key", "model_id", "decision")),  # one row, read for every strategy
            spark.createDataFrame(stale, "task_key string, model_id string, stale double").join(past.where("NOT augmented").groupBy("model_id").agg(F.avg("perf").alias("past")), "model_id"),
        )
        runs, decided, static = parts if runs is None else (x.unionByName(y) for x, y in zip((runs, decided, static), parts))
    every = strategies(runs, decided, static, "residual").cache()
    top = every.groupBy("task_key").agg(F.max("skill").alias("top"))
    out = every.join(top, "task_key").groupBy("strategy")
    return out.agg(F.avg(F.when(F.col("decision") == "augment", 1.0).otherwise(0.0)).alias("augment_rate"), F.round(F.avg("skill"), 6).alias("skill"), F.round(F.avg(F.col("top") - F.col("skill")), 6).alias("regret"), F.sum("trained").cast("int").alias("trainings"))


@query
def holdout_probes(spark, sf):
    """Probes of bases without gradients, fitted on half of the probe batch."""
    import numpy as np

    from relmodel.nn.bases import InContext, TwoStage
    from relmodel.nn.grid import flat_features
    from relmodel.nn.train import rows_of
    from relmodel.plans.dispatch import holdout_probe

    packed, _ = packed_task(spark, sf, "pl5", seeds=256)
    rows = rows_of(packed.orderBy("seed_id").collect())  # the probe batch, bounded
    x, y = flat_features(rows), np.array([r["y"] for r in rows])
    out = [(m.kind, float(holdout_probe(lambda a, b, c, m=m: m().fit(a, b).predict(c), x, y, "binary"))) for m in (InContext, TwoStage)]
    return spark.createDataFrame(out, "model_id string, skill double")
