"""Path queries inside SQL: path_query('graph', 'query') stands for a table.

A table function of Python can't run jobs, so the call is answered before the text is parsed: its result becomes a view and the
call its name. Conditions on start, end and length that stand right after the call, as FROM path_query(...) t WHERE t.start = ..., are
moved into the search."""

from __future__ import annotations

import re
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession

from pathweave.graph import PathGraph
from pathweave.plans import planner
from pathweave.query import parse

_CALL = re.compile(r"path_query\s*\(\s*'(?P<graph>[^']+)'\s*,\s*'(?P<text>(?:[^']|'')+)'\s*\)", re.I)
#: What may follow a call for its conditions to be moved: an alias, then WHERE, up to the next clause or the end of the SELECT.
_WHERE = re.compile(
    r"\s*(?:(?:AS\s+)?(?P<alias>(?!WHERE\b)[A-Za-z_]\w*)\s+)?WHERE\b(?P<where>.*?)"
    r"(?=\b(?:GROUP|ORDER|SORT|CLUSTER|DISTRIBUTE|HAVING|WINDOW|LIMIT|OFFSET|UNION|EXCEPT|MINUS|INTERSECT|LATERAL)\b|;|$)", re.I | re.S,
)
_NOT_PLAIN = re.compile(r"[()]|\b(?:OR|NOT|BETWEEN|CASE|SELECT|IN)\b", re.I)


class Engine:
    def __init__(self, spark: SparkSession):
        self.spark, self.graphs, self._n = spark, {}, 0

    def register(self, name: str, graph: PathGraph) -> Engine:
        self.graphs[name] = graph
        return self

    def sql(self, text: str, **how) -> DataFrame:
        out, at = [], 0
        for m in _CALL.finditer(text):
            pushed = self._pushed(text[: m.start()], text[m.end() :])
            q = parse(m["text"].replace("''", "'"))
            if q.start is None and "start" in pushed:
                q = replace(q, start=pushed["start"])
            if q.end is None and "end" in pushed:
                q = replace(q, end=pushed["end"])
            if "length" in pushed and q.mode is not None:
                q = replace(q, max_length=pushed["length"])
            self._n += 1
            view = f"__path_query_{self._n}"
            planner.run(self.graphs[m["graph"]], q, **how).df.createOrReplaceTempView(view)
            out += [text[at : m.start()], view]
            at = m.end()
        return self.spark.sql("".join([*out, text[at:]]))

    @staticmethod
    def _pushed(before: str, after: str) -> dict:
        """start = constant, end = constant and length <= number among the conditions of a WHERE that belongs to the call alone: the call is
        all that its FROM has, and the conditions are joined by AND. They stay in the text too; others are left to Catalyst."""
        m = _WHERE.match(after)
        if not m or not re.search(r"\bFROM\s*$", before, re.I):
            return {}
        # Up to the parenthesis that closes a subselect.
        where = re.split(r"\)", m["where"])[0] if m["where"].count(")") > m["where"].count("(") else m["where"]
        if _NOT_PLAIN.search(re.sub(r"'[^']*'", "''", where)):
            return {}
        found: dict = {}
        name = rf"(?:{re.escape(m['alias'])}\.)?" if m["alias"] else ""
        for part in re.split(r"\bAND\b", where, flags=re.I):
            if c := re.fullmatch(rf"\s*{name}`?(start|end)`?\s*=\s*(?:'([^']*)'|(-?\d+))\s*", part, re.I):
                found[c[1].lower()] = c[2] if c[2] is not None else int(c[3])
            elif c := re.fullmatch(rf"\s*{name}`?length`?\s*(<=|<)\s*(\d+)\s*", part, re.I):
                found["length"] = int(c[2]) - (c[1] == "<")
        return found
