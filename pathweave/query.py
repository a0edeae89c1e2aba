"""Path queries: as values, and as text."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pathweave import regex
from pathweave.modes import PathMode, parse_mode


class QueryError(ValueError):
    pass


@dataclass(frozen=True)
class PathQuery:
    mode: PathMode | None  # None: endpoints only
    pattern: object
    start: object = None
    end: object = None
    limit: int | None = None
    max_length: int | None = None
    timeout_s: float | None = None


_TEXT = re.compile(r"^\s*(?P<mode>[A-Za-z0-9 ]*?)\s*\(\s*(?P<x>[^()]*?)\s*\)\s*-\[(?P<regex>.*)\]->\s*\(\s*(?P<y>[^()]*?)\s*\)\s*(?:LIMIT\s+(?P<limit>\d+))?\s*$", re.S | re.I)


def _end(text: str):
    """?name is a variable; 'text' and bare words are node names, digits numbers."""
    if not text or text.startswith("?"):
        return None
    if text[0] == text[-1] == "'" and len(text) > 1:
        return text[1:-1]
    return int(text) if re.fullmatch(r"-?\d+", text) else text


def parse(text: str, k: int | None = None) -> PathQuery:
    """[mode] (x) -[regex]-> (y) [LIMIT n]; without a mode, or with ENDPOINTS, endpoints only."""
    m = _TEXT.match(text)
    if not m:
        raise QueryError(f"not a path query: {text!r}")
    mode = m["mode"].strip().upper()
    return PathQuery(None if mode in ("", "ENDPOINTS") else parse_mode(mode, k), regex.parse(m["regex"]), _end(m["x"]), _end(m["y"]), int(m["limit"]) if m["limit"] else None)


def parse_triple(text: str) -> PathQuery:
    """The triple-like form: SELECT mode ?p WHERE x regex y."""
    m = re.match(r"^\s*SELECT\s+(?P<mode>[A-Z0-9 ]*?)\s*(?:\?\w+\s+)?WHERE\s*\{?\s*(?P<x>\S+)\s+(?P<regex>.+?)\s+(?P<y>\S+?)\s*\}?\s*$", text, re.S | re.I)
    if not m:
        raise QueryError(f"not a triple path query: {text!r}")
    return parse(f"{m['mode']} ({m['x']}) -[{m['regex']}]-> ({m['y']})")
