"""A digest of what a query shows to an observer: operators, plan shape and public sizes, not contents (L263)."""

from __future__ import annotations

import hashlib
import re

from ..core.frame import SealedFrame


def trace_digest(frame: SealedFrame) -> str:
    """Equal for equal queries over inputs of equal sizes, whatever they hold."""
    plan = frame.df._jdf.queryExecution().optimizedPlan().toString()
    plan = re.sub(r"#\d+L?", "", plan)
    plan = re.sub(r"_common_expr_\d+", "_common_expr", plan)  # numbered through the session
    plan = re.sub(r"(LocalRelation|LogicalRDD|Relation)[^\n]*", r"\1", plan)
    text = "\n".join([plan, *frame.public.trace, str(frame.public.rows)])
    return hashlib.sha256(text.encode()).hexdigest()
