"""From a question to checked profiles.

The agent is an interface; no language model can be called here, so ``RuleAgent`` reads questions with
a small keyword grammar and stands in for one. Its answers go through the same checks.
"""

from __future__ import annotations

import json
import re
from typing import Protocol

from pyspark.sql import functions as F

from relmodel.catalog import CATALOG, Catalog
from relmodel.plans.profiles import DataProfile, Horizon, Target, TaskProfile, Violation, check_data, check_profile, fk_path, parse_profile_json


class Agent(Protocol):
    def complete(self, messages: list[dict[str, str]]) -> str: ...


GUIDE = "Return one JSON object with the fields of the example. Use only tables and columns of the catalog."
EXAMPLE = '{"name": "customer_churn", "question": "…", "entity_table": "customer", "entity_key": "c_custkey", "task_type": "binary", "target": {"kind": "aggregate", "table": "orders", "expr": "*", "agg": "count", "compare": "=", "threshold": 0, "default": 1}, "horizon": {"value": 180, "unit": "days"}, "metric": "area"}'


def task_prompt(question: str, catalog: Catalog = CATALOG, examples: tuple[str, ...] = (EXAMPLE,)) -> list[dict[str, str]]:
    """Guidance, catalog, examples and the question."""
    return [{"role": "system", "content": "\n".join([GUIDE, catalog.json(), *examples])}, {"role": "user", "content": question}]


#: Words for the entities, most specific first: (pattern, table).
ENTITIES = ((r"\b(customers?|shoppers?|buyers?)\b", "customer"), (r"\b(users?|visitors?)\b", "customer"), (r"\b(parts?|products?|items?|articles?)\b", "part"), (r"\b(suppliers?|sites?|vendors?)\b", "supplier"), (r"\borders?\b", "orders"), (r"\bdocuments?\b", "documents"))
UNITS = {"day": 1, "week": 7, "month": 30, "season": 90, "quarter": 90, "year": 365}


class RuleAgent:
    """Reads the last message and answers as JSON; deterministic."""

    def __init__(self, catalog: Catalog = CATALOG):
        self.catalog = catalog

    def complete(self, messages):
        """A data round carries a JSON object with ``round``; anything else is a question."""
        try:
            asked = json.loads(messages[-1]["content"])
        except ValueError:
            asked = None
        if not isinstance(asked, dict) or "round" not in asked:
            return json.dumps(self.read(messages[-1]["content"]))
        return json.dumps(self.tables(asked) if asked["round"] == "tables" else self.columns(asked))

    def tables(self, asked: dict) -> dict:
        return {"tables": [n for n, hops in asked["candidates"].items() if hops <= asked["hops"] or n == asked["target"]]}

    def columns(self, asked: dict) -> dict:
        """Leaves out constants, names of rows, the second of two columns that say the same, and targets."""
        keep = []
        for c, x in asked["columns"].items():
            like_id = x["kind"] == "categorical" and asked["rows"] > 50 and x["distinct"] > 0.9 * asked["rows"]
            if x["distinct"] > 1 and not like_id and not x["target"] and not set(x["alike"]) & set(keep):
                keep.append(c)
        return {"columns": keep}

    def read(self, question: str) -> dict:
        q = question.lower()
        found = sorted((m.start(), table) for pattern, table in ENTITIES if (m := re.search(pattern, q)))
        entity = found[0][1] if found else "customer"
        days = self.horizon(q)
        users = bool(re.search(r"\b(users?|visitors?|click|attend|event|view)", q))
        fact, target = self.target(q, entity, users)
        regression = target.get("compare") is None and not (target["kind"] == "column")
        return {
            "name": f"{entity}_{fact}", "question": question, "entity_table": entity, "entity_key": self.catalog.tables[entity].key,
            "task_type": "regression" if regression else "binary", "target": target,
            "horizon": {"value": days, "unit": "days"} if days else None, "metric": "mae" if regression else "area",
        }

    def horizon(self, q: str) -> int | None:
        m = re.search(r"(?:next|coming|following|in|within)\s+(\d+)?\s*(day|week|month|season|quarter|year)s?", q)
        return int(m[1] or 1) * UNITS[m[2]] if m else None

    def target(self, q: str, entity: str, users: bool) -> tuple[str, dict]:
        events = dict(kind="aggregate", table="events")
        more = re.search(r"(?:more than|over|at least)\s+(\d+|one|two|ten)", q)
        words = {"one": 1, "two": 2, "ten": 10}
        limit = (float(words.get(more[1], 0) or more[1]) if more else 0.0)
        if re.search(r"\b(churn|stop|leave|no (?:orders?|transactions?|purchases?)|not (?:buy|order))", q):
            return "churn", dict(kind="aggregate", table="events" if users and entity == "customer" and "order" not in q else "orders", expr="*", agg="count", compare="=", threshold=0.0, default=1.0)
        if re.search(r"\b(click-?through|ctr|rate|ratio|share)\b", q):
            if re.search(r"click|ctr", q):
                return "ctr", events | dict(expr="CASE WHEN event_type = 'click' THEN 1.0 WHEN event_type = 'view' THEN 0.0 END", agg="avg")
            flag = "l_linestatus = 'F'" if entity == "supplier" else "l_returnflag <> 'R'"
            return "rate", dict(kind="aggregate", table="lineitem", expr=f"CASE WHEN {flag} THEN 1.0 ELSE 0.0 END", agg="avg")
        if re.search(r"\b(sales|spend|revenue|value sold)\b", q):
            return "sales", dict(kind="aggregate", table="lineitem", expr="l_extendedprice * (1 - l_discount)", agg="sum", default=0.0)
        if re.search(r"\b(outcome|succeed|fulfil|status)\b", q) and entity == "orders":
            return "outcome", dict(kind="column", table="orders", expr="o_orderstatus", compare="=", threshold=None)
        verb = "click" if "click" in q else "purchase" if users else "order"
        base = events | dict(expr=f"CASE WHEN event_type = '{verb}' THEN 1 END", agg="count") if users else dict(kind="aggregate", table="orders", expr="*", agg="count")
        if re.search(r"\bhow many|number of|count of\b", q):
            return f"n_{verb}", base | dict(default=0.0)
        return f"{verb}_active", base | dict(compare=">", threshold=limit, default=0.0)


class AgentSession:
    """The conversation goes on over rounds."""

    def __init__(self, agent: Agent):
        self.agent, self.messages = agent, []

    def ask(self, *messages: dict[str, str]) -> str:
        self.messages += messages
        answer = self.agent.complete(self.messages)
        self.messages.append({"role": "assistant", "content": answer})
        return answer


def parse_task(question: str, agent: Agent, catalog: Catalog = CATALOG, max_rounds: int = 3) -> tuple[TaskProfile | None, list[Violation]]:
    """Ask, check, feed violations back, at most ``max_rounds`` times."""
    session, problems = AgentSession(agent), []
    prompt = task_prompt(question, catalog)
    for _ in range(max_rounds):
        profile, problems = parse_profile_json(session.ask(*prompt))
        if profile:
            problems = check_profile(profile, catalog)
            if not problems:
                return profile, []
        prompt = [{"role": "user", "content": question + "\nFix: " + "; ".join(f"{v.rule}: {v.detail}" for v in problems)}]
    return None, problems


def _answered(session: AgentSession, asked: dict, field: str, check, max_rounds: int) -> tuple[list[str], list[Violation]]:
    """One data round: the answer's names, asked again with the violations at most ``max_rounds`` times."""
    problems: list[Violation] = []
    for _ in range(max_rounds):
        try:
            names = json.loads(session.ask({"role": "user", "content": json.dumps(asked)}))[field]
            problems = check(names) if isinstance(names, list) and all(isinstance(n, str) for n in names) else [Violation("syntax", field)]
        except (ValueError, TypeError, KeyError) as e:
            names, problems = [], [Violation("syntax", f"{type(e).__name__}: {e}")]
        if not problems:
            return names, []
        asked = asked | {"fix": [f"{v.rule}: {v.detail}" for v in problems]}
    return [], problems


def select_tables(task: TaskProfile, catalog: Catalog = CATALOG, hops: int = 2, session: AgentSession | None = None, max_rounds: int = 3) -> tuple[tuple[str, ...], list[Violation]]:
    """The agent chooses among the tables that links reach, each shown with its distance."""
    session = session or AgentSession(RuleAgent(catalog))
    ways = {n: fk_path(catalog, task.entity_table, n) for n in catalog.tables if n != task.entity_table}
    near = {n: len(p) for n, p in ways.items() if p is not None}
    asked = {"round": "tables", "question": task.question, "entity": task.entity_table, "target": task.target.table, "hops": hops, "candidates": near}

    def check(names):
        out = [Violation("unreachable" if n in catalog.tables else "table", n) for n in names if n not in near]
        if task.target.table not in (task.entity_table, *names):
            out.append(Violation("target_table", task.target.table))
        return out

    names, problems = _answered(session, asked, "tables", check, max_rounds)
    return tuple(dict.fromkeys(names)), problems


def select_columns(task: TaskProfile, names: tuple[str, ...], tables, catalog: Catalog = CATALOG, most_alike: float = 0.99, session: AgentSession | None = None, max_rounds: int = 3) -> tuple[dict[str, list[str]], list[Violation]]:
    """One statistics pass a table; the agent sees each column's kind, distinct values and the
    columns it nearly equals, and names those to keep."""
    session, out, problems = session or AgentSession(RuleAgent(catalog)), {}, []
    for n in (task.entity_table, *names):
        spec, df = catalog.tables[n], tables[n]
        cols = [c for c in spec.columns if spec.columns[c] in ("numerical", "categorical", "timestamp") and c in df.columns]
        num = [c for c in cols if spec.columns[c] == "numerical"]
        pairs = [(a, b) for i, a in enumerate(num) for b in num[i + 1 :]]
        row = df.agg(F.count("*"), *(F.approx_count_distinct(c) for c in cols), *(F.corr(a, b) for a, b in pairs)).first()
        alike = [p for p, r in zip(pairs, row[1 + len(cols) :]) if r is not None and abs(r) > most_alike]
        hidden = {task.target.expr} if task.target.kind == "column" and n == task.target.table else set()
        seen = {c: {"kind": spec.columns[c], "distinct": d, "alike": [a for a, b in alike if b == c], "target": c in hidden} for c, d in zip(cols, row[1 : 1 + len(cols)])}
        asked = {"round": "columns", "question": task.question, "table": n, "rows": row[0], "columns": seen}

        def check(names, cols=cols, hidden=hidden, n=n):
            return [Violation("leak" if c in hidden else "column", f"{n}.{c}") for c in names if c not in cols or c in hidden]

        out[n], bad = _answered(session, asked, "columns", check, max_rounds)
        problems += bad
    return out, problems


def data_profile(task: TaskProfile, tables, catalog: Catalog = CATALOG, filters: dict[str, str] | None = None, agent: Agent | None = None) -> tuple[DataProfile, list[Violation]]:
    """Tables, then columns table by table, in one conversation with the agent."""
    session = AgentSession(agent or RuleAgent(catalog))
    names, problems = select_tables(task, catalog, session=session)
    columns, more = select_columns(task, names, tables, catalog, session=session)
    columns = {n: c for n, c in columns.items() if c}
    names = tuple(n for n in names if n in columns)
    keep = {task.entity_table, *names}
    d = DataProfile(task.entity_table, task.target.expr, names, columns, tuple(k.name for k in catalog.keys if k.child in keep and k.parent in keep), filters or {})
    return d, problems + more + check_data(d, task, catalog)


def join_clauses(d: DataProfile, catalog: Catalog = CATALOG) -> dict[str, str]:
    """FROM and JOIN of each link of the profile, child to parent."""
    keys = {k.name: k for k in catalog.keys}
    return {n: f"FROM {k.child} JOIN {k.parent} ON {k.child}.{k.child_col} = {k.parent}.{k.parent_col}" for n in d.joins for k in [keys[n]]}


def to_sql(d: DataProfile, catalog: Catalog = CATALOG) -> dict[str, str]:
    """One SELECT per table, with its keys, kept columns and filter."""
    out = {}
    for n in (d.target_table, *d.related_tables):
        spec = catalog.tables[n]
        cols = list(dict.fromkeys([*spec.of_kind("key"), *([spec.time] if spec.time else []), *d.columns.get(n, [])]))
        where = f" WHERE {d.filters[n]}" if n in d.filters else ""
        out[n] = f"SELECT {', '.join(cols)} FROM {n}{where}"
    return out
