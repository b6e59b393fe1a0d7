"""Shapes of plans, slices, decisions, profiles, reports, training on Spark and streams."""

import json
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from relmodel.catalog import CATALOG, load
from relmodel.nn.relational import Config, Step
from relmodel.operators import fusion, graph, metrics, passing, slices
from relmodel.plans import dispatch, intent, report
from relmodel.plans.profiles import Horizon, Target, TaskProfile, check_profile, parse_profile_json
from relmodel.workloads import ORDER_CUTOFFS, TASKS

T = ORDER_CUTOFFS[2]


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_sampling_limits_groups_before_the_shuffle(spark, sf):
    o = load(spark, sf, ["orders"])["orders"].select(F.col("o_custkey").alias("node_id"), F.col("o_orderkey").alias("nbr_id"), F.col("o_orderdate").alias("ts"))
    text = plan(graph.sample_neighbours(o, 8, as_of=T))
    assert text.count("WindowGroupLimit") == 2 and text.count("Exchange") == 1 and "PushedFilters: [IsNotNull(o_orderdate), LessThanOrEqual(o_orderdate" in text


def test_slice_reads_only_its_columns(spark, sf):
    s = slices.data_slice(load(spark, sf, ["orders"]), "orders", {"orders": ["o_orderkey"]}, {"orders": "o_totalprice > 10"})
    assert "ReadSchema: struct<o_orderkey:bigint,o_totalprice:double>" in plan(s.tables["orders"])


def test_edges_need_no_join(spark, sf):
    s = slices.data_slice(load(spark, sf, ["customer", "orders", "lineitem"]), "customer")
    assert "Join" not in plan(graph.graph_edges(s)) and "Exchange" not in plan(graph.graph_edges(s))


def test_no_future_row_changes_a_label_state(spark, sf):
    t = load(spark, sf, ["customer", "orders", "lineitem"])
    late = t["orders"].limit(20).withColumn("o_orderdate", F.expr("TIMESTAMP_NTZ'2002-01-01'")).withColumn("o_orderkey", F.col("o_orderkey") + 10**9)
    more = t | {"orders": t["orders"].union(late)}
    a, b = (graph.graph_edges(slices.state_at(slices.data_slice(x, "customer"), T)) for x in (t, more))
    assert a.exceptAll(b).count() == b.exceptAll(a).count() == 0


def test_samples_are_nested_and_symmetric(spark, sf):
    s = slices.data_slice(load(spark, sf, ["customer", "orders"]), "customer")
    e = graph.graph_edges(s)
    down, up = graph.neighbours(e, "order_customer"), graph.neighbours(e, "order_customer", down=False)
    small, large = (graph.sample_neighbours(down, k, "uniform").select("node_id", "nbr_id") for k in (2, 4))
    assert small.exceptAll(large).count() == 0
    assert down.select("node_id", "nbr_id").exceptAll(up.select("nbr_id", "node_id")).count() == 0


def test_layerwise_passing_keeps_isolated_nodes(spark):
    h = spark.createDataFrame([("a", 1.0, 2.0), ("b", 3.0, -1.0)], "node_id string, h0 double, h1 double")
    kids = spark.createDataFrame([("x", 1.0, 0.0)], "node_id string, h0 double, h1 double")
    edges = spark.createDataFrame([("x", "a")], "child_id string, parent_id string")
    out = passing.message_layers({"p": h, "c": kids}, [passing.Relation("r", "c", "p", edges, 0)], 1)
    assert {x.node_id for x in out["p"].collect()} == {"a", "b"}
    sums = passing.aggregate_neighbours(kids, edges).collect()
    assert sums[0].s0 == 1.0 and passing.salted_sum(kids, edges).collect()[0].s0 == 1.0


def test_measures(spark):
    df = spark.createDataFrame([(1, 0.9), (0, 0.8), (1, 0.8), (0, 0.1)], "y int, score double")
    assert metrics.roc_area(df).first().area == 0.875 and metrics.roc_area(df.where("y = 1")).first().area is None
    assert metrics.mae(spark.createDataFrame([(1.0, 1.0), (2.0, 3.0), (3.0, 5.0)], "y double, score double")).first().mae == 1.0
    z = spark.createDataFrame([(1, 0.0), (0, 0.0), (1, 1000.0), (0, -1000.0)], "y int, logit double")
    assert abs(metrics.bce(z.limit(2)).first().bce - 0.693147) < 1e-6 and metrics.bce(z).first().bce < 1
    imp = spark.createDataFrame([(1.0, 1), (0.5, 3), (1 / 3, 3), (1.0, 4)], "a double, n int").select(fusion.recalibrate(F.col("a"), F.col("n")).alias("i"))
    assert [round(r.i, 6) for r in imp.collect()] == [0, 0.25, 0, 1]


def test_ledger_and_threshold(spark):
    ledger = spark.createDataFrame([("m", "t", i, p) for i, p in enumerate((0.8, 0.6, 0.7))], "model_id string, task_key string, step int, perf double")
    assert abs(dispatch.ema(ledger).first().ema - 0.728) < 1e-9
    assert [round(r.ema, 6) for r in dispatch.ema_running(ledger).orderBy("step").collect()] == [0.8, 0.74, 0.728]
    assert dispatch.decide(0.70, 0.728).action == "direct" and dispatch.decide(0.69, 0.728).action == "augment" and dispatch.decide(0.9, None).reason == "no_history"
    assert dispatch.decide(0.5, 0.9, epsilon=1.0).action == "direct"


def bad(**more):
    base = dict(name="x", question="q", entity_table="customer", entity_key="c_custkey", task_type="regression", target=Target("aggregate", "orders", "o_totalprice", "sum"), horizon=Horizon(7, "days"))
    return TaskProfile(**(base | more))


def test_profile_checks():
    assert check_profile(bad()) == []
    rules = lambda p: {v.rule for v in check_profile(p)}
    assert rules(bad(entity_table="nope")) == {"entity_table"} and rules(bad(entity_key="z")) == {"entity_key"}
    assert rules(bad(target=Target("column", "orders", "o_orderstatus"))) == {"target_type"}
    assert rules(bad(target=Target("aggregate", "part", "p_size", "sum"))) == {"no_time"}
    assert rules(bad(target=Target("aggregate", "documents", "n_chars", "sum"), horizon=None)) == {"unreachable"}
    assert rules(bad(target=Target("column", "orders", "zz"))) == {"target_column"}
    assert parse_profile_json("{broken")[1][0].rule == "syntax"
    again, problems = parse_profile_json(bad().json())
    assert again == bad() and not problems


QUESTIONS = {
    ("binary", "orders", 180): ["Which customers will churn in the next 180 days?", "Predict customers that stop ordering within 180 days", "Customers with no orders in the next 180 days"],
    ("regression", "lineitem", 7): ["What will be the sales of each item next week?", "Revenue per product in the next week", "Value sold per article in the next 7 days"],
    ("binary", "events", 4): ["Will a user click more than 1 ad in the next 4 days?", "Users who click over 1 time within 4 days", "Which users click more than one ad in the next 4 days?"],
    ("regression", "events", 7): ["How many purchases will each user make next week?", "Number of events a user attends in the next 7 days", "How many times will visitors attend in the next week?"],
}


def test_questions_become_profiles():
    for (kind, table, days), forms in QUESTIONS.items():
        for q in forms:
            p, problems = intent.parse_task(q, intent.RuleAgent())
            assert p is not None and (p.task_type, p.target.table, p.horizon.value) == (kind, table, days), (q, p, problems)


def test_repair_loop_gives_up():
    class Stubborn:
        asked = 0

        def complete(self, messages):
            self.asked += 1
            return "{}"

    a = Stubborn()
    p, problems = intent.parse_task("?", a)
    assert p is None and problems and a.asked == 3


def test_fragments_run(spark, sf):
    t = load(spark, sf, ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"])
    for n, df in t.items():
        df.createOrReplaceTempView(n)
    task, _ = intent.parse_task("Which customers will churn in the next 180 days?", intent.RuleAgent())
    d, problems = intent.data_profile(task, t)
    assert not problems and "orders" in d.related_tables
    for sql in intent.to_sql(d).values():
        spark.sql(sql).schema
    joins = intent.join_clauses(d)
    assert joins["order_customer"] == "FROM orders JOIN customer ON orders.o_custkey = customer.c_custkey"
    assert spark.sql(f"SELECT count(*) {joins['order_customer']}").first()[0] == t["orders"].count()
    assert json.loads(CATALOG.json())["tables"]["orders"]["time"] == "o_orderdate"


def test_data_rounds_feed_violations_back(spark, sf):
    """An agent that names what is not there is told so and asked again in the same conversation."""
    t = load(spark, sf, ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"])
    task, _ = intent.parse_task("Which customers will churn in the next 180 days?", intent.RuleAgent())

    class Careless(intent.RuleAgent):
        def __init__(self, mends):
            super().__init__()
            self.mends, self.seen = mends, []

        def complete(self, messages):
            asked = json.loads(messages[-1]["content"])
            self.seen.append((asked["round"], len(messages), asked.get("fix")))
            if "fix" in asked and self.mends:
                return super().complete(messages)
            return json.dumps({"tables": ["orders", "moon"]}) if asked["round"] == "tables" else "{not json"

    agent = Careless(True)
    d, problems = intent.data_profile(task, t, agent=agent)
    assert not problems and d == intent.data_profile(task, t)[0]
    assert agent.seen[1][0] == "tables" and agent.seen[1][2] == ["table: moon"] and agent.seen[3][2][0].startswith("syntax")
    assert [n for _, n, _ in agent.seen] == list(range(1, 2 * len(agent.seen), 2))  # one conversation
    d, problems = intent.data_profile(task, t, agent=Careless(False))
    assert {v.rule for v in problems} >= {"table", "syntax"} and d.related_tables == ()


def test_late_rows_are_dropped_by_the_watermark(spark, tmp_path):
    """ST2: the second file holds a row within the watermark of a day, the third one beyond it (rows are
    judged by the watermark of the batch before)."""
    import time

    from relmodel.streaming import stream

    rows = [("2024-01-05 10:00:00", 1), ("2024-01-05 11:00:00", 1)], [("2024-01-04 12:00:00", 1), ("2024-01-08 00:00:00", 1)], [("2024-01-02 12:00:00", 1), ("2024-01-12 00:00:00", 2)]
    for i, part in enumerate(rows):
        df = spark.createDataFrame([(i * 10 + j, ts, u, "view", 1.0, "{}") for j, (ts, u) in enumerate(part)], "event_id long, ts string, user_id long, event_type string, value double, props string")
        df.withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.mode("append").parquet(f"{tmp_path}/events")
        time.sleep(1.1)
    got = stream.activity(stream.event_stream(spark, f"{tmp_path}/events", 1), "1 day").select(F.date_format("w.start", "dd").alias("day"), "user_id", "n")
    got.writeStream.format("memory").queryName("late_rows").outputMode("append").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start().awaitTermination()
    out = {(r.day, r.user_id): r.n for r in spark.table("late_rows").collect()}
    assert out[("05", 1)] == 2 and out[("04", 1)] == 1 and ("02", 1) not in out


def test_report_quotes_only_evidence(spark):
    preds = spark.createDataFrame([(i, i / 10, "a" if i % 2 else "b") for i in range(10)], "entity_id int, score double, seg string")
    e = report.report_evidence(preds, ["seg"], question="Who?", task="t", cutoff=T, strategy={"action": "augment", "reason": "augment"}, metric={"name": "area"}, signals=[{"name": "orders(sum)", "mean_importance": 0.5}])
    assert "orders(sum)" in report.write_report(e).markdown

    class Liar:
        def complete(self, messages):
            return "there were 987654321 of them"

    with pytest.raises(ValueError):
        report.write_report(e, Liar())


def test_packed_training_backends_agree(spark, sf):
    """T9 with all rows equals the driver's own full-batch steps; packing keeps hop order."""
    import numpy as np

    from relmodel.learned import packed_task
    from relmodel.nn.relational import unroll
    from relmodel.nn.train import AdamW, TrainConfig, fit_sync, gradients, model_of, rows_of

    packed, p = packed_task(spark, sf, "pl1", seeds=40, k=4)
    packed = packed.repartition(3, "seed_id").cache()
    c = Config("customer", p.schemas(), p.steps, d=2, layers=1)
    cfg = TrainConfig(epochs=3)
    params, _ = fit_sync(packed, c, cfg)
    rows = rows_of(packed.collect())
    model = model_of(c)
    want, opt = model.start(), AdamW(cfg.rate, cfg.decay)
    for _ in range(3):
        want = opt.step(want, gradients(model, want, unroll(rows, c))[1])
    assert all(np.allclose(params[k], want[k], atol=1e-6) for k in want)
    orders = {r["seed_id"]: r["order_customer"] for r in rows}
    assert all(o is None or len(o) <= 4 for o in orders.values())


def test_workloads_have_both_classes(spark, sf):
    t = load(spark, sf)
    for task in TASKS.values():
        y = slices.horizon_labels(task, t, task.cutoffs[2])
        assert y.count() > 0 and (task.kind != "binary" or y.select("y").distinct().count() == 2), task.name


def test_step_order():
    s = Step("a", "b", "c")
    assert s.down


def test_text_vector_hashes_each_word_once(spark):
    from hashlib import md5

    from relmodel.functions.embed import text_vector

    texts = ["Blue steel, blue-green 7", "", None, "?!", "one " * 40, "Ärger straße"]
    df = spark.createDataFrame(list(enumerate(texts)), "i int, s string")
    for width in (16, 5):
        out = df.select("i", text_vector(F.col("s"), "s", width).alias("v"))
        assert out._jdf.queryExecution().executedPlan().toString().count("md5(") == 1
        for r in out.collect():
            want = np.zeros(width)
            for w in re.findall(r"[^\W_]+", (texts[r.i] or "").lower()):
                h = int(md5(f"s:{w}".encode()).hexdigest()[:6], 16)
                want[h // 2 % width] += 2 * (h % 2) - 1
            assert np.allclose(r.v, want / max(np.sqrt((want**2).sum()), 1.0))


@pytest.mark.parametrize("name", ["architecture_space", "catalog_columns", "plan_limits"])
def test_tables_are_read(spark, tmp_path, sf, name):
    """The query meets a table that cannot be read to its end."""
    import os
    import shutil

    from relmodel.all_queries import QUERIES

    for f in os.listdir(sf):
        if f.endswith(".parquet"):
            shutil.copyfile(f"{sf}/{f}", tmp_path / f)
    assert QUERIES[name](spark, str(tmp_path)).count() > 0
    whole = (tmp_path / "orders.parquet").read_bytes()
    with open(tmp_path / "orders.parquet", "r+b") as f:  # the footer stays as it was
        f.seek(4)
        f.write(b"\xff" * (len(whole) // 2))
    with pytest.raises(Exception):
        QUERIES[name](spark, str(tmp_path)).collect()


def test_architecture_space_follows_the_orders(spark, tmp_path):
    from relmodel.all_queries import QUERIES

    orders = [(c,) for c, n in ((1, 1), (2, 3), (3, 40)) for _ in range(n)]
    spark.createDataFrame(orders, "o_custkey long").write.parquet(str(tmp_path / "orders.parquet"))
    got = QUERIES["architecture_space"](spark, str(tmp_path)).collect()
    assert len(got) == 3 + 9 + 27 and {r.widths for r in got if r.depth == 1} == {"32", "64", "512"}
