"""What users call."""

from __future__ import annotations

from pyspark.sql import DataFrame

from pathweave import regex
from pathweave.graph import PathGraph
from pathweave.modes import parse_mode
from pathweave.plans import planner
from pathweave.query import PathQuery, parse
from pathweave.result import Result


def paths(g: PathGraph, mode: str, pattern: str, start=None, end=None, k: int | None = None, limit: int | None = None, max_length: int | None = None, timeout_s: float | None = None, **how) -> Result:
    """The paths of a mode; start may be a node or a DataFrame of nodes. how: strategy, order, local_edges."""
    starts = start if isinstance(start, DataFrame) else None
    q = PathQuery(parse_mode(mode, k), regex.parse(pattern), None if starts is not None else start, end, limit, max_length, timeout_s)
    return planner.run(g, q, starts=starts, **how)


def endpoints(g: PathGraph, pattern: str, start=None, end=None, limit: int | None = None, **how) -> Result:
    starts = start if isinstance(start, DataFrame) else None
    return planner.run(g, PathQuery(None, regex.parse(pattern), None if starts is not None else start, end, limit), starts=starts, **how)


def query(g: PathGraph, text: str, k: int | None = None, **how) -> Result:
    """A query in text form."""
    return planner.run(g, parse(text, k), **how)
