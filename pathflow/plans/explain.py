"""What a walk will do: steps, rules that fire, design cost, Spark's plan."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..sources.graph import PropertyGraph
from .lower import run
from .rewrite import cost, optimize
from .traversal import Walk, kind_after


def exchanges(graph: PropertyGraph, spark: SparkSession, walk: Walk, ids: list[int]) -> int:
    return run(graph, spark, walk, ids)._jdf.queryExecution().executedPlan().toString().count("Exchange ")


def explain(graph: PropertyGraph, spark: SparkSession, walk: Walk, ids: list[int]) -> str:
    better, fired = optimize(walk, graph)
    plan = run(graph, spark, walk, ids)._jdf.queryExecution().simpleString()
    lines = [f"ends in {kind_after(walk)}", *(f"  {s}" for s in walk.steps), "rewritten by " + (", ".join(fired) or "nothing"), *(f"  {s}" for s in better.steps), str(cost(better)), plan]
    return "\n".join(lines)
