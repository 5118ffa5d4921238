"""What a physical plan does: exchanges, broadcasts, Python nodes, what reaches the scans."""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

from pyspark.sql import DataFrame

PYTHON = ("MapInArrow", "MapInPandas", "FlatMapGroupsInArrow", "FlatMapGroupsInPandas", "BatchEvalPython", "ArrowEvalPython", "FlatMapCoGroupsInPandas", "AggregateInPandas", "WindowInPandas")


@dataclass
class PlanFacts:
    nodes: Counter
    pushed: list[str]
    read: list[str]

    @property
    def exchanges(self) -> int:
        return self.nodes["Exchange"]

    @property
    def broadcasts(self) -> int:
        return self.nodes["BroadcastExchange"]

    @property
    def python(self) -> int:
        return sum(self.nodes[k] for k in PYTHON)

    @property
    def nested_loops(self) -> int:
        return self.nodes["CartesianProduct"] + self.nodes["BroadcastNestedLoopJoin"]


def facts(df: DataFrame) -> PlanFacts:
    """Counts of the nodes of the plan that Spark would run, the filters its scans take over and the columns they read."""
    text = df._jdf.queryExecution().executedPlan().toString()
    text = text.split("== Initial Plan ==")[0]
    nodes = Counter(m[1] for m in re.finditer(r"(?m)^[\s:+\-*()\d]*([A-Z][A-Za-z]+)", text))
    return PlanFacts(nodes, re.findall(r"PushedFilters: \[([^\]]*)\]", text), re.findall(r"ReadSchema: (struct<[^\n]*>)", text))
