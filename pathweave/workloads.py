"""The experiment workloads, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pathweave import engine
from pathweave.metrics import LIMIT, spread, timed
from pathweave.result import Result
from pathweave.sources import catalog


def social(spark: SparkSession, sf_dir: str, mode: str | None, k: int, exact: bool = False, paths: int | None = None, limit: int | None = LIMIT, **how) -> Result:
    """From the node of median degree over one label: lengths 1 to k, or exactly k. mode None: endpoints. paths: the k of the mode."""
    g = catalog.hop(spark, sf_dir, "follows")
    pattern = f"follows{{{k}}}" if exact else f"follows{{1,{k}}}"
    start = g.median_node()
    if mode is None:
        return engine.endpoints(g, pattern, start, **how)
    return engine.paths(g, mode, pattern, start, k=paths, limit=limit, **how)


#: key, graph, pattern, start, end: shapes of logged queries over the tables. "?": every node.
PATTERNS = (
    ("p01", "star", "placed/contains", "C:{c}", "?"),
    ("p02", "star", "^supplies*", "P:{p}", "?"),
    ("p03", "star", "(supplies/^supplies)+", "S:1", "?"),
    ("p04", "star", "livesin/^livesin/placed", "C:{c}", "?"),
    ("p05", "star", "(livesin|basedin)/partof", "?", "R:1"),
    ("p06", "star", "placed/contains/^supplies/basedin/partof?", "C:{c}", "?"),
    ("p07", "star", "livesin/^basedin", "?", "?"),
    ("p08", "star", "(placed/contains/^contains/^placed){1,2}", "C:{c}", "C:2"),
    ("p09", "hop", "purchase{1,3}", "{u}", "?"),
    ("p09a", "hop", "purchase*", "{u}", "?"),
    ("p09b", "hop", "purchase+", "{u}", "?"),
    ("p10", "hop", "click*/purchase", "{u}", "?"),
    ("p11", "hop", "(click|view)+/purchase", "{u}", "?"),
    ("p12", "hop", "(click+/view)*/purchase", "{u}", "?"),
    ("p13", "hop", "click*/view*/error*", "{u}", "3"),
    ("p14", "hop", "click*/click*", "{u}", "?"),
    ("p15", "hop", "^purchase/click", "?", "{u}"),
    ("p16", "trade", "(A|N|R)+", "1", "?"),
    ("p16a", "trade", "A/N*/R", "1", "?"),
    ("p17", "link", "(links/^links)+", "g:0", "?"),
    ("p18", "link", "links/^links/on", "?", "?"),
    ("p19", "turn", "system?/(user/assistant)*", "0:0", "?"),
    ("p21", "triples", "livesin/partof", "C:{c}", "?"),
)


def _node(text: str, k: int):
    if text == "?":
        return None
    text = text.format(c=1 + 13 * k, p=1 + 7 * k, u=k % 15)
    return int(text) if text.isdigit() else text


def patterns(spark: SparkSession, sf_dir: str, modes: list[str], variants: int = 1, limit: int = LIMIT, timeout_s: float = 60.0, only: list[str] | None = None, **how) -> DataFrame:
    """Every pattern, with so many choices of its constants, under every mode: the spread of times and the time-outs by mode."""
    made: dict = {}
    runs = []
    for key, graph, pattern, start, end in PATTERNS:
        if only and key not in only:
            continue
        if graph not in made:
            g = catalog.PathGraph.from_triples(catalog.triples(spark, sf_dir)) if graph == "triples" else getattr(catalog, graph)(spark, sf_dir)
            made[graph] = g.cached()
        for v in range(variants if "{" in start + end else 1):
            for mode in modes:
                if graph == "triples" and mode.endswith("TRAIL"):
                    continue
                s, e = _node(start, v), _node(end, v)
                if mode == "ENDPOINTS":
                    make = lambda: engine.endpoints(made[graph], pattern, s, e, **how).df  # noqa: E731, B023
                else:
                    make = lambda: engine.paths(made[graph], mode, pattern, s, e, limit=limit, timeout_s=timeout_s, **how).df  # noqa: E731, B023
                r = timed(spark, make, timeout_s, limit)
                runs.append((mode, f"{key}.{v}", float(r["wall_s"]), bool(r["timed_out"])))
    return spread(spark, runs)


def diamond(spark: SparkSession, n: int, mode: str, order: str | None = None, limit: int | None = LIMIT, timeout_s: float | None = None, **how) -> Result:
    """From the first to the last node of n diamonds: 2**n paths of length 2n, all of them shortest, trails and simple."""
    return engine.paths(catalog.diamond(spark, n), mode, "a*", 0, 3 * n, limit=limit, timeout_s=timeout_s, order=order, **how)
