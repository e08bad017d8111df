"""Plans as text: the logical plan before and after rewriting, and Spark's physical plan below."""

from __future__ import annotations

import contextlib
import io

from pyspark.sql import DataFrame

from ..result import NLResult
from .nodes import Node
from .rewrite import rewrite


def explain_program(node: Node) -> str:
    return f"== Logical ==\n{node.tree()}\n== Rewritten ==\n{rewrite(node).tree()}"


def physical_plan(df: DataFrame, mode: str = "formatted") -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain(mode)
    return out.getvalue()


def explain_result(result: NLResult) -> str:
    notes = "\n".join(f"  {k}: {v}" for k, v in result.plan.items())
    calls = "\n".join(f"  {k}: {v}" for k, v in sorted(result.calls.items()))
    return f"== Plan ==\n{notes}\n== Calls ==\n{calls}"
