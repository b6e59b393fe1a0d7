"""Task and data profiles, their JSON form and the rule checker (DM8, DM9, I4, I5)."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field

from relmodel.catalog import CATALOG, Catalog

TYPES = ("binary", "regression", "multiclass")
SCHEMA = (
    "name string, question string, entity_table string, entity_key string, task_type string, "
    "target struct<kind:string,table:string,expr:string,agg:string,compare:string,threshold:double,default:double>, "
    "horizon struct<value:int,unit:string>, cutoff string, entity_filter string, metric string"
)


@dataclass(frozen=True)
class Target:
    """What is predicted: a column of the entity's table, or an aggregate over a table in the window."""

    kind: str
    table: str
    expr: str
    agg: str | None = None
    compare: str | None = None
    threshold: float | None = None
    default: float | None = None


@dataclass(frozen=True)
class Horizon:
    value: int
    unit: str


@dataclass(frozen=True)
class TaskProfile:
    name: str
    question: str
    entity_table: str
    entity_key: str
    task_type: str
    target: Target
    horizon: Horizon | None = None
    cutoff: str | None = None
    entity_filter: str | None = None
    metric: str = "area"

    def json(self) -> str:
        return json.dumps(asdict(self))


@dataclass(frozen=True)
class DataProfile:
    target_table: str
    target_attribute: str
    related_tables: tuple[str, ...]
    columns: dict[str, list[str]]
    joins: tuple[str, ...]
    filters: dict[str, str] = field(default_factory=dict)

    def json(self) -> str:
        return json.dumps(asdict(self))


@dataclass(frozen=True)
class Violation:
    rule: str
    detail: str


def parse_profile_json(text: str) -> tuple[TaskProfile | None, list[Violation]]:
    """I4: JSON to a profile; problems come back as violations, never as exceptions."""
    try:
        d = json.loads(text)
        target, horizon = Target(**d.pop("target")), d.pop("horizon", None)
        return TaskProfile(target=target, horizon=Horizon(**horizon) if horizon else None, **d), []
    except (ValueError, TypeError, KeyError) as e:
        return None, [Violation("syntax", f"{type(e).__name__}: {e}")]


def fk_path(catalog: Catalog, start: str, end: str) -> list[str] | None:
    """Relations that lead from one table to another, shortest first."""
    front, seen = [(start, [])], {start}
    while front:
        here, path = front.pop(0)
        if here == end:
            return path
        for k in catalog.links(here):
            nxt = k.parent if k.child == here else k.child
            if nxt not in seen:
                seen.add(nxt)
                front.append((nxt, path + [k.name]))
    return None


def check_profile(p: TaskProfile, catalog: Catalog = CATALOG, tables=None) -> list[Violation]:
    """Names, types, links and times. With ``tables`` the target expression is analysed by the
    engine (no job runs)."""
    out = []
    if p.entity_table not in catalog.tables:
        return [Violation("entity_table", f"no table {p.entity_table}")]
    if p.entity_key not in catalog.tables[p.entity_table].columns:
        out.append(Violation("entity_key", f"no column {p.entity_key} in {p.entity_table}"))
    if p.task_type not in TYPES:
        out.append(Violation("task_type", p.task_type))
    if p.target.table not in catalog.tables:
        return out + [Violation("target_table", f"no table {p.target.table}")]
    spec = catalog.tables[p.target.table]
    if fk_path(catalog, p.entity_table, p.target.table) is None:
        out.append(Violation("unreachable", f"{p.target.table} has no path of keys from {p.entity_table}"))
    if p.horizon and not spec.time:
        out.append(Violation("no_time", f"{p.target.table} has no time column for a horizon"))
    if p.target.kind == "column":
        kind = spec.columns.get(p.target.expr)
        if kind is None:
            out.append(Violation("target_column", f"no column {p.target.expr} in {p.target.table}"))
        elif p.task_type == "regression" and kind != "numerical":
            out.append(Violation("target_type", f"{p.target.expr} is {kind}, regression needs numbers"))
        elif p.task_type == "binary" and kind == "numerical" and not p.target.compare:
            out.append(Violation("target_type", "a binary task on a number needs a comparison"))
    if p.target.kind == "aggregate" and p.task_type == "binary" and not p.target.compare:
        out.append(Violation("target_type", "a binary task on an aggregate needs a comparison"))
    if tables and p.target.table in tables and not any(v.rule.startswith("target") for v in out):
        try:
            tables[p.target.table].selectExpr(f"{p.target.agg}({p.target.expr})" if p.target.agg else p.target.expr)
        except Exception as e:  # the analyser's message is the finding
            out.append(Violation("target_expr", str(e).split("\n")[0][:200]))
    return out


def check_data(d: DataProfile, task: TaskProfile, catalog: Catalog = CATALOG) -> list[Violation]:
    out = []
    for n in d.related_tables:
        if n not in catalog.tables:
            out.append(Violation("table", n))
        elif fk_path(catalog, d.target_table, n) is None:
            out.append(Violation("unreachable", n))
    for n, cols in d.columns.items():
        if n in catalog.tables:
            out += [Violation("column", f"{n}.{c}") for c in cols if c not in catalog.tables[n].columns]
            if not cols:
                out.append(Violation("empty", n))
            if task.target.kind == "column" and n == task.target.table and task.target.expr in cols:
                out.append(Violation("leak", f"{n}.{task.target.expr}"))
    return out
