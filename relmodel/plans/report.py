"""Evidence tables and a grounded report (R1-R3). Only aggregates leave the cluster."""

from __future__ import annotations

import json
import re
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.functions.quantile import quantiles


def score_distribution(preds: DataFrame) -> DataFrame:
    """Count and quantiles of the scores."""
    q = {f"q{int(100 * x):02d}": x for x in (0.05, 0.25, 0.5, 0.75, 0.95)}
    spread = quantiles(preds, "score", q).select(*(F.round(n, 6).alias(n) for n in q))
    return preds.agg(F.count("*").alias("n")).join(spread, F.lit(True), "left")  # one row each


def segments(preds: DataFrame, dims: list[str]) -> DataFrame:
    """Mean score of every combination of the dimensions and their totals."""
    return preds.cube(*dims).agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("mean_score"))


def top_entities(preds: DataFrame, n: int = 5) -> DataFrame:
    return preds.orderBy(F.desc("score"), "entity_id").limit(n).select("entity_id", F.round("score", 6).alias("score"))


@dataclass(frozen=True)
class Report:
    markdown: str
    json: str


class TemplateAgent:
    """Deterministic prose from the evidence alone."""

    def complete(self, messages):
        e = json.loads(messages[-1]["content"])
        d = e["distribution"]
        lines = [f"# {e['question']}", f"Task: {e['task']}, as of {e['cutoff']}; {e['n_scored']} entities scored with strategy {e['strategy']['action']} ({e['strategy']['reason']})."]
        lines.append(f"Scores: median {d['q50']}, middle half from {d['q25']} to {d['q75']}.")
        lines += [f"- Segment {s['dims']}: {s['n']} entities, mean {s['mean']}." for s in e["segments"]]
        lines += [f"- Signal {s['name']}: mean importance {s['mean_importance']}." for s in e["signals"]]
        lines += [f"Note: {c}" for c in e["caveats"]]
        return "\n".join(lines)


def report_evidence(preds: DataFrame, dims: list[str], *, question: str, task: str, cutoff: str, strategy: dict, metric: dict, signals: list[dict] = (), caveats: list[str] = ()) -> dict:
    """R1 as one object: a few hundred numbers at most."""
    d = score_distribution(preds).first().asDict()
    seg = [{"dims": " / ".join(str(r[c]) if r[c] is not None else "all" for c in dims), "n": r.n, "mean": r.mean_score} for r in segments(preds, dims).orderBy(F.desc("n"), *dims).limit(20).collect()]
    top = [r.asDict() for r in top_entities(preds).collect()]
    return {"question": question, "task": task, "cutoff": cutoff, "n_scored": d["n"], "strategy": strategy, "metric": metric, "distribution": d, "segments": seg, "top_entities": top, "signals": list(signals), "caveats": list(caveats)}


def numbers(text: str) -> set[str]:
    return set(re.findall(r"\d+(?:\.\d+)?", text))


def write_report(evidence: dict, agent=None) -> Report:
    """R2: prose whose every number is in the evidence; others raise ValueError."""
    body = json.dumps(evidence, default=str)
    text = (agent or TemplateAgent()).complete([{"role": "user", "content": body}])
    if extra := numbers(text) - numbers(body):
        raise ValueError(f"numbers without evidence: {sorted(extra)}")
    return Report(text, body)
