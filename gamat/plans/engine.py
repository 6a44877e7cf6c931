"""Dispatch: rewrite the plan, choose a strategy, emit DataFrames, explain all of it."""

from __future__ import annotations

from ..operators import features
from ..types import GraphMatrix, Strategy, VertexState
from . import backends, ir, mapper, rewrite


def first_graph(node: ir.PlanNode) -> GraphMatrix | None:
    if isinstance(node, ir.Load):
        return node.graph
    return next((g for c in node.children() if (g := first_graph(c)) is not None), None)


def operation(node: ir.PlanNode) -> str:
    kinds = {type(n) for n in walk(node)}
    return "chain" if ir.Contract in kinds and any(isinstance(n, ir.Contract) and len(n.parts) > 2 for n in walk(node)) else "mm" if ir.Contract in kinds else "add" if ir.MergeEdges in kinds and ir.Gather not in kinds else "mv"


def walk(node: ir.PlanNode):
    yield node
    for c in node.children():
        yield from walk(c)


def run(node: ir.PlanNode, strategy: Strategy | None = None, platform: str = "jvm", tree: mapper.Tree | None = None) -> GraphMatrix | VertexState:
    """With no strategy given, the profile of the plan's first matrix and the tree (or the rules) choose one."""
    node = rewrite.rewrite(node)
    if strategy is None:
        gm = first_graph(node)
        strategy = mapper.choose(operation(node), features.profile(gm).first(), platform, tree) if gm is not None else Strategy()
    return backends.emit(node, strategy)


def explain(node: ir.PlanNode, platform: str = "jvm", tree: mapper.Tree | None = None) -> str:
    """Plan before and after rewriting, the branch taken, the strategy, and Spark's formatted plan."""
    new = rewrite.rewrite(node)
    gm, op = first_graph(new), operation(new)
    row = features.profile(gm).first()
    values = features.vector(row, op, platform)
    strategy = mapper.choose(op, row, platform, tree)
    out = backends.emit(new, strategy)
    df = out.edges if isinstance(out, GraphMatrix) else out.df
    spark_plan = df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")
    branch = tree.branch(values) if tree else ["rules"]
    return "\n".join(["-- plan", node.text(), "-- rewritten", new.text(), "-- decided by", *branch, f"-- strategy {strategy.name}: {strategy}", "-- spark", spark_plan])
