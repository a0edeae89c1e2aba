"""Every method, variant and baseline as a query over the given tables, with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathweave import baselines, engine, oracles, workloads
from pathweave.functions import paths as P
from pathweave.graph import PathGraph
from pathweave.result import Result
from pathweave.sources import catalog

MODES = {"all": "{r}", "any": "ANY {r}", "any_shortest": "ANY SHORTEST {r}", "all_shortest": "ALL SHORTEST {r}", "any_k": "ANY 2 {r}", "shortest_k": "SHORTEST 3 {r}", "groups": "SHORTEST 2 GROUPS {r}"}


def graph(spark: SparkSession, sf_dir: str, name: str) -> PathGraph:
    kind, _, arg = name.partition(":")
    if kind == "hop":
        return catalog.hop(spark, sf_dir, arg or None)
    if kind == "slice":
        return catalog.hop_slice(spark, sf_dir, int(arg))
    if kind == "diamond":
        return catalog.diamond(spark, int(arg))
    if kind == "order_diamond":
        return catalog.order_diamond(spark, sf_dir, int(arg))
    if kind == "triples":
        return PathGraph.from_triples(catalog.triples(spark, sf_dir))
    return getattr(catalog, kind)(spark, sf_dir)


def _start(g: PathGraph, v):
    if v in ("source", "sink"):
        a, b = ("src", "dst") if v == "source" else ("dst", "src")
        return g.edges.join(g.edges.select(F.col(b).alias(a)), a, "left_anti").agg(F.min(a)).first()[0]
    return g.median_node() if v == "median" else v


def _shown(r: Result) -> DataFrame:
    return r.df.select(F.col("start").alias("src"), F.col("end").alias("dst"), "length", P.path_text("eids").alias("path"))


def _ends(r: Result) -> DataFrame:
    return r.df.select(F.col("start").alias("src"), F.col("end").alias("dst"))


#: name: (graph, mode, pattern, start, end, how). Mode None: endpoints.
SPECS: dict[str, tuple] = {
    **{f"ep_hop_k{k}": ("hop:follows", None, f"follows{{1,{k}}}", "median", None, {}) for k in (1, 2, 3, 4)},
    "ep_star_2way": ("star", None, "(supplies/^supplies)+", "S:1", None, {}),
    "ep_link_copage": ("link", None, "(links/^links)+", "g:0", None, {}),
    "ep_turn_nested_star": ("turn", None, "system?/(user/assistant)*", None, None, {}),
    "ep_both_const": ("star", None, "(placed/contains/^contains/^placed){1,2}", "C:1", "C:2", {}),
    "ep_end_const": ("star", None, "(livesin|basedin)/partof", None, "R:1", {}),
    "ep_free_free": ("star", None, "livesin/^basedin", None, None, {}),
    "ep_nullable": ("hop", None, "click*/view*/error*", 0, None, {}),
    "ep_rounds": ("hop", None, "(click+/view)*/purchase", 0, None, {"strategy": "rounds"}),
    "any_walk_hop": ("hop", "ANY WALK", "purchase*", "median", None, {}),
    "any_shortest_hop": ("hop", "ANY SHORTEST WALK", "purchase*", "median", None, {}),
    "all_shortest_hop": ("hop", "ALL SHORTEST WALK", "purchase*", "median", None, {}),
    "all_shortest_click_purchase": ("hop", "ALL SHORTEST WALK", "click*/purchase", 0, None, {}),
    "any_shortest_union": ("hop", "ANY SHORTEST WALK", "(click|view)+/purchase", 0, None, {}),
    "any_shortest_end_const": ("hop", "ANY SHORTEST WALK", "^purchase/click", None, 0, {}),
    "all_shortest_trade": ("trade", "ALL SHORTEST WALK", "A/N*/R", 1, None, {}),
    "all_shortest_end_const": ("trade", "ALL SHORTEST WALK", "A/N*/R", None, 2, {}),
    "any_shortest_copage": ("link", "ANY SHORTEST WALK", "links/^links/on", "g:0", None, {}),
    "any_shortest_turns": ("turn", "ANY SHORTEST WALK", "system?/(user/assistant)*", None, None, {}),
    **{f"shortest_k_hop_{k}": ("hop", f"SHORTEST {k} WALK", "purchase{1,3}", "median", None, {}) for k in (1, 5, 100)},
    "any_k_hop": ("hop", "ANY 3 WALK", "purchase{1,3}", "median", None, {}),
    **{f"groups_hop_{k}": ("hop", f"SHORTEST {k} GROUPS WALK", "purchase{1,3}", "median", None, {}) for k in (1, 2, 3)},
    "exact_any_shortest": ("hop", "ANY SHORTEST WALK", "purchase{3}", "median", None, {}),
    "exact_all_shortest": ("hop", "ALL SHORTEST WALK", "purchase{2}", "median", None, {}),
    "exact_trail": ("hop", "TRAIL", "purchase{2}", "median", None, {}),
    "trail_hop": ("hop", "TRAIL", "purchase{1,3}", "median", None, {}),
    "any_shortest_diamond": ("diamond:10", "ANY SHORTEST WALK", "a*", 0, 30, {}),
    "all_shortest_diamond": ("diamond:10", "ALL SHORTEST WALK", "a*", 0, 30, {}),
    "shortest_k_diamond": ("diamond:6", "SHORTEST 7 WALK", "a{0,12}", 0, None, {}),
    "groups_diamond": ("diamond:6", "SHORTEST 2 GROUPS WALK", "a{0,12}", 0, None, {}),
    "trail_diamond": ("diamond:8", "TRAIL", "a*", 0, 24, {}),
    "trail_diamond_dfs": ("diamond:8", "TRAIL", "a*", 0, 24, {"order": "dfs"}),
    **{f"{m}_{r}_slice": ("slice:1", text.format(r=r.upper()), "purchase+", None, None, {}) for m, text in MODES.items() for r in ("trail", "simple", "acyclic")},
    # Over the whole graph a star has too many paths; a bounded expression has all of its own.
    **{f"{m}_{r}_hop": ("hop", text.format(r=r.upper()), "purchase{1,3}", None, None, {}) for m, text in MODES.items() for r in ("trail", "simple", "acyclic")},
    "all_trail_slice_2": ("slice:2", "TRAIL", "purchase/click*", None, None, {}),
    "two_way_star": ("star", "ANY SHORTEST WALK", "placed/contains/^supplies/basedin/partof?", "C:1", None, {}),
    "two_way_both_const": ("star", "ANY SHORTEST WALK", "(placed/contains/^contains/^placed){1,2}", "C:1", "C:4", {}),
    "triples_any_shortest": ("triples", "ANY SHORTEST WALK", "livesin/partof", "C:1", None, {}),
    "ambiguous_all_shortest": ("hop", "ALL SHORTEST WALK", "purchase*/purchase*", "median", None, {}),
    "ambiguous_trail": ("slice:1", "TRAIL", "purchase*/purchase*", None, None, {}),
    "csr_all_shortest": ("hop", "ALL SHORTEST WALK", "view*/error", 1, None, {"strategy": "local"}),
    "rounds_any_shortest": ("hop", "ANY SHORTEST WALK", "view*/error", 1, None, {"strategy": "rounds"}),
    "rounds_all_shortest": ("hop", "ALL SHORTEST WALK", "view*/error", 1, None, {"strategy": "rounds"}),
    "rounds_shortest_k": ("hop", "SHORTEST 3 WALK", "signup{1,2}", 1, None, {"strategy": "rounds"}),
    "rounds_groups": ("hop", "SHORTEST 2 GROUPS WALK", "signup{1,3}", 1, None, {"strategy": "rounds"}),
    "rounds_trail": ("slice:1", "TRAIL", "error/view*", None, None, {"strategy": "rounds"}),
    # The social series: lengths up to k, exactly k, from the node of median degree.
    **{f"ep_hop_k{k}": ("hop:follows", None, f"follows{{1,{k}}}", "median", None, {}) for k in range(5, 13)},
    **{f"ep_exact_k{k}": ("hop:follows", None, f"follows{{{k}}}", "median", None, {}) for k in (1, 2, 3, 4, 8, 12)},
    **{f"any_shortest_social_k{k}": ("hop:follows", "ANY SHORTEST WALK", f"follows{{1,{k}}}", "median", None, {}) for k in range(1, 13)},
    **{f"all_shortest_social_k{k}": ("hop:follows", "ALL SHORTEST WALK", f"follows{{1,{k}}}", "median", None, {}) for k in range(1, 13)},
    **{f"trail_social_{o}_k{k}": ("hop:follows", "TRAIL", f"follows{{1,{k}}}", "median", None, {"order": o}) for k in (1, 2) for o in ("bfs", "dfs")},
    "shortest_k_hop_1000": ("hop", "SHORTEST 1000 WALK", "purchase{1,3}", "median", None, {}),
    **{f"shortest_k_trail_{k}": ("hop", f"SHORTEST {k} TRAIL", "purchase{1,3}", "median", None, {}) for k in (1, 100, 1000)},
    **{f"groups_trail_{k}": ("hop", f"SHORTEST {k} GROUPS TRAIL", "purchase{1,3}", "median", None, {}) for k in (1, 2, 3)},
    # Shapes of logged queries.
    "p01_any_shortest": ("star", "ANY SHORTEST WALK", "placed/contains", "C:1", None, {}),
    "p02_any_shortest": ("star", "ANY SHORTEST WALK", "^supplies*", "P:1", None, {}),
    "p04_any_shortest": ("star", "ANY SHORTEST WALK", "livesin/^livesin/placed", "C:1", None, {}),
    "p13_both_const": ("hop", "ANY SHORTEST WALK", "click*/view*/error*", 0, 3, {}),
    "p16_all_shortest": ("trade", "ALL SHORTEST WALK", "(A|N|R)+", 1, None, {}),
    "p18_free_ends": ("link", None, "links/^links/on", None, None, {}),
    **{f"any_trail_diamond_bfs_{n}": (f"diamond:{n}", "ANY TRAIL", "a*", 0, 3 * n, {"order": "bfs"}) for n in (4, 8)},
    "any_trail_diamond_bfs_1": ("order_diamond:1", "ANY TRAIL", "a*", "source", "sink", {"order": "bfs"}),
    "rounds_shortest_k_simple": ("slice:1", "SHORTEST 2 SIMPLE", "(error|view)+", None, None, {"strategy": "rounds"}),
}
_STAR = ("any_walk_hop", "any_shortest_hop", "all_shortest_hop", "all_shortest_click_purchase", "any_shortest_union", "all_shortest_trade", "all_shortest_end_const", "any_shortest_turns", "any_shortest_diamond", "all_shortest_diamond", "ambiguous_all_shortest", "csr_all_shortest", "rounds_any_shortest", "rounds_all_shortest")
_STAR += (*(f"{m}_shortest_social_k{k}" for m in ("any", "all") for k in range(1, 13)), "p02_any_shortest", "p13_both_const", "p16_all_shortest")
_DEPTH = {"any_shortest_diamond": 20, "all_shortest_diamond": 20, **{f"{m}_shortest_social_k{k}": k for m in ("any", "all") for k in range(1, 13)}}


def _query(spec: tuple):
    name, mode, pattern, start, end, how = spec

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = graph(spark, sf_dir, name)
        s, t = _start(g, start), _start(g, end)
        return _ends(engine.endpoints(g, pattern, s, t, **how)) if mode is None else _shown(engine.paths(g, mode, pattern, s, t, **how))

    return run


def _sql(key: str, spec: tuple) -> str:
    name, mode, pattern, start, end, _ = spec
    if mode is None:
        return oracles.endpoints(name, pattern, start, end)
    if "_social_k" in key and key in _STAR:
        # Up to k steps of one label: the shortest walks of a plus, as far as k; a bounded expression has all walks in its product.
        return oracles.shortest(name, mode, "follows+", start, end, _DEPTH[key])
    if key in _STAR:
        return oracles.shortest(name, mode, pattern, start, end, _DEPTH.get(key, 8))
    return oracles.paths(name, mode, pattern, start, end)


QUERIES = {k: _query(v) for k, v in SPECS.items()}
SQL = {k: _sql(k, v) for k, v in SPECS.items()}


# ------------------------------------------------------------------ against words of labels, with no automaton in the SQL
_WORDS = {
    **{f"{m}_{r}": text.format(r=r.upper()) for m, text in MODES.items() for r in ("trail", "simple", "acyclic")},
    "any_shortest_walk": "ANY SHORTEST WALK", "all_shortest_walk": "ALL SHORTEST WALK", "shortest_k_walk": "SHORTEST 3 WALK", "groups_walk": "SHORTEST 2 GROUPS WALK",
}
for _name, _mode in _WORDS.items():
    # From one node over the whole graph, where pairs have many paths, so selectors differ.
    _spec = ("hop", _mode, "(purchase|click){1,2}", "median", None, {})
    QUERIES[f"words_{_name}"], SQL[f"words_{_name}"] = _query(_spec), oracles.words("hop", _mode, "(p|c){1,2}", 2, "median")
    # By rounds of joins, from all nodes.
    _spec = ("slice:1", _mode, "error/(view|click)?/purchase?", None, None, {"strategy": "rounds"})
    QUERIES[f"rounds_words_{_name}"], SQL[f"rounds_words_{_name}"] = _query(_spec), oracles.words("slice:1", _mode, "e(v|c)?p?", 3)


def _add(name: str, sql: str | None = None):
    def take(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return take


# ------------------------------------------------------------------ graph views
def _view(kind: str):
    def run(spark, sf_dir):
        return graph(spark, sf_dir, kind).edges.select("src", "label", "dst", "eid")

    return run


for _name, _kind in (("g_hop_edges", "hop"), ("g_star_edges", "star"), ("g_trade_edges", "trade"), ("g_link_edges", "link"), ("g_turn_edges", "turn"), ("g_diamond_edges", "order_diamond:25"), ("g_triples_edges", "triples"), ("g_hop_slice_edges", "slice:2")):
    QUERIES[_name] = _view(_kind)
    SQL[_name] = f"WITH {oracles.graph_sql(_kind)} SELECT src, label, dst, eid FROM edges"


@_add("degree_median_start", f"WITH {oracles.hop()} SELECT {oracles.MEDIAN} AS node")
def degree_median_start(spark, sf_dir):
    g = graph(spark, sf_dir, "hop")
    return spark.createDataFrame([(g.median_node(),)], "node long")


@_add("degrees", f"WITH {oracles.hop()} SELECT id, coalesce(c, 0) AS degree FROM nodes LEFT JOIN (SELECT v, count(*) AS c FROM (SELECT src AS v FROM edges UNION ALL SELECT dst FROM edges) GROUP BY v) ON v = id")
def degrees(spark, sf_dir):
    return graph(spark, sf_dir, "hop").degrees()


@_add("label_histogram", f"WITH {oracles.hop()} SELECT label, count(*) AS edges FROM edges GROUP BY ROLLUP (label)")
def label_histogram(spark, sf_dir):
    return graph(spark, sf_dir, "hop").labels()


@_add("session_edges", """SELECT src, dst, eid FROM (SELECT user_id AS src, lead(user_id) OVER w AS dst, lead(ts) OVER w - ts AS gap, event_id AS eid FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)) WHERE gap <= INTERVAL 30 MINUTE""")
def session_edges(spark, sf_dir):
    return PathGraph.from_sessions(catalog.read(spark, sf_dir, "events"), "user_id", "ts", "event_id", "event_type").edges.select("src", "dst", "eid")


@_add("asof_edges", """SELECT l.event_id AS src, r.event_id AS dst FROM (SELECT * FROM events WHERE event_type = 'purchase') l ASOF JOIN (SELECT * FROM events WHERE event_type = 'click') r ON l.user_id = r.user_id AND l.ts >= r.ts""")
def asof_edges(spark, sf_dir):
    e = catalog.read(spark, sf_dir, "events")
    g = PathGraph.from_asof(e.filter("event_type = 'purchase'"), e.filter("event_type = 'click'"), "user_id", "ts", "ts", "event_id", "event_id", "event_id")
    return g.edges.select("src", "dst")


@_add("semi_anti_seed", "SELECT 'C:' || c_custkey AS id, EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) AS placed FROM customer")
def semi_anti_seed(spark, sf_dir):
    g = graph(spark, sf_dir, "star")
    c = catalog.read(spark, sf_dir, "customer").select(F.concat(F.lit("C:"), F.col("c_custkey").cast("string")).alias("id"))
    orders = g.subgraph(labels=["placed"])
    orders = PathGraph.of(orders.edges)
    return orders.has(c).withColumn("placed", F.lit(True)).unionByName(orders.missing(c).withColumn("placed", F.lit(False)))


# ------------------------------------------------------------------ around the paths
_TRAILS = SQL["trail_hop"]


@_add("path_join_attributes", f"SELECT t.src, t.dst, t.length, t.path, e.n FROM ({_TRAILS}) t JOIN (SELECT user_id, count(*) AS n FROM events GROUP BY user_id) e ON e.user_id = t.dst")
def path_join_attributes(spark, sf_dir):
    g = graph(spark, sf_dir, "hop")
    r = engine.paths(g, "TRAIL", "purchase{1,3}", g.median_node())
    n = catalog.read(spark, sf_dir, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    j = r.with_attributes(n, "user_id")
    return j.select(F.col("start").alias("src"), F.col("end").alias("dst"), "length", P.path_text("eids").alias("path"), "n")


@_add("path_length_rollup", f"SELECT mode, length, count(*) AS paths, CAST(grouping_id(mode, length) AS BIGINT) AS grouping FROM (SELECT 'TRAIL' AS mode, * FROM ({_TRAILS})) GROUP BY CUBE (mode, length)")
def path_length_rollup(spark, sf_dir):
    g = graph(spark, sf_dir, "hop")
    return engine.paths(g, "TRAIL", "purchase{1,3}", g.median_node()).length_cube("TRAIL")


@_add("path_functions", SQL["shortest_k_hop_100"].replace("SELECT s AS src", "SELECT len = len(list_distinct(eids)) AS trail, s AS src"))
def path_functions(spark, sf_dir):
    g = graph(spark, sf_dir, "hop")
    r = engine.paths(g, "SHORTEST 100 WALK", "purchase{1,3}", g.median_node()).df
    return r.select(P.path_start("nodes").alias("src"), P.path_end("nodes").alias("dst"), P.path_length("eids").alias("length"), P.path_text("eids").alias("path"), P.is_trail("eids").alias("trail"))


@_add("path_unnest", f"SELECT src, dst, path, CAST(pos AS INTEGER) AS pos, CAST(str_split(path, '>')[pos] AS BIGINT) AS eid FROM (SELECT *, unnest(range(1, length + 1)) AS pos FROM ({_TRAILS}))")
def path_unnest(spark, sf_dir):
    g = graph(spark, sf_dir, "hop")
    r = engine.paths(g, "TRAIL", "purchase{1,3}", g.median_node()).df
    out = r.select(F.col("start").alias("src"), F.col("end").alias("dst"), P.path_text("eids").alias("path"), F.posexplode("eids").alias("pos", "eid"))
    return out.withColumn("pos", F.col("pos") + 1)


@_add("path_set_ops", f"({SQL['all_trail_slice']}) EXCEPT ({SQL['all_acyclic_slice']})")
def path_set_ops(spark, sf_dir):
    g = graph(spark, sf_dir, "slice:1").cached()
    t, a = engine.paths(g, "TRAIL", "purchase+"), engine.paths(g, "ACYCLIC", "purchase+")
    return _shown(Result(t.minus(a)))


@_add("path_containment", f"({SQL['all_acyclic_slice']}) INTERSECT ({SQL['all_simple_slice']})")
def path_containment(spark, sf_dir):
    g = graph(spark, sf_dir, "slice:1").cached()
    return _shown(Result(engine.paths(g, "ACYCLIC", "purchase+").intersect(engine.paths(g, "SIMPLE", "purchase+"))))


@_add("path_top", f"SELECT src, dst, length, path FROM (SELECT *, dense_rank() OVER (PARTITION BY src, dst ORDER BY length) AS g FROM ({_TRAILS})) WHERE g <= 1")
def path_top(spark, sf_dir):
    g = graph(spark, sf_dir, "hop")
    return _shown(Result(engine.paths(g, "TRAIL", "purchase{1,3}", g.median_node()).top(1, groups=True)))


@_add("path_cost", f"SELECT t.src, t.dst, t.path, CAST(round(sum(e.value), 4) AS DOUBLE) AS cost FROM (SELECT *, CAST(unnest(str_split(path, '>')) AS BIGINT) AS eid FROM ({_TRAILS})) t JOIN events e ON e.event_id = t.eid GROUP BY ALL")
def path_cost(spark, sf_dir):
    g = graph(spark, sf_dir, "hop")
    r = engine.paths(g, "TRAIL", "purchase{1,3}", g.median_node()).df
    costs = catalog.read(spark, sf_dir, "events").select(F.col("event_id").alias("eid"), "value")
    return P.path_cost(r, costs, "value").select(F.col("start").alias("src"), F.col("end").alias("dst"), P.path_text("eids").alias("path"), F.round("cost", 4).alias("cost"))


@_add("word_acceptance", "SELECT conv_id, regexp_full_match(w, 's?(ua)*') AS ok FROM (SELECT conv_id, string_agg(left(role, 1), '' ORDER BY turn) AS w FROM conversations GROUP BY conv_id)")
def word_acceptance(spark, sf_dir):
    from pathweave import automaton, regex

    c = catalog.read(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]).alias("w"))
    return c.select("conv_id", P.accepts("w", automaton.glushkov(regex.parse("system?/(user/assistant)*"))).alias("ok"))


@_add("sql_path_query", f"SELECT dst, count(*) AS n FROM ({SQL['trail_hop'].replace(oracles.MEDIAN, '0')}) GROUP BY dst")
def sql_path_query(spark, sf_dir):
    from pathweave.sqlapi import Engine

    return Engine(spark).register("hop", graph(spark, sf_dir, "hop")).sql("SELECT `end` AS dst, count(*) AS n FROM path_query('hop', 'TRAIL (?x) -[purchase{1,3}]-> (?y)') WHERE start = 0 GROUP BY `end`")


# ------------------------------------------------------------------ baselines and strategies
@_add("bl_reach", oracles.endpoints("hop", "click*/purchase", 0))
def bl_reach(spark, sf_dir):
    return baselines.reach(graph(spark, sf_dir, "hop"), "click*/purchase", 0).select(F.col("start").alias("src"), F.col("end").alias("dst"))


@_add("bl_enumerate_trails", oracles.paths("slice:1", "TRAIL", "(purchase|click){1,3}", 0))
def bl_enumerate_trails(spark, sf_dir):
    return _shown(Result(baselines.enumerate_trails(spark, graph(spark, sf_dir, "slice:1").cached(), "(purchase|click){1,3}", 0, 3)))


@_add("bl_enumerate_filter", oracles.paths("hop", "ALL SHORTEST WALK", "purchase{1,2}", 0))
def bl_enumerate_filter(spark, sf_dir):
    return _shown(Result(baselines.enumerate_then_filter(graph(spark, sf_dir, "hop"), "purchase{1,2}", 0, 2)))


@_add("bl_bounded_walks", oracles.paths("slice:1", "ANY 1000000 WALK", "(click|view|error|signup|purchase){1,3}", 0))
def bl_bounded_walks(spark, sf_dir):
    return _shown(Result(baselines.bounded_walks(graph(spark, sf_dir, "slice:1"), "(click|view|error|signup|purchase){1,3}", 0, 30)))


@_add("bl_eager_product", oracles.endpoints("hop", "click*/purchase", 0))
def bl_eager_product(spark, sf_dir):
    return baselines.eager_reach(graph(spark, sf_dir, "hop"), "click*/purchase", 0).select(F.col("start").alias("src"), F.col("end").alias("dst"))


@_add("bl_per_start", oracles.paths("slice:1", "TRAIL", "purchase+").replace("FROM nodes )", "FROM nodes WHERE id < 5)"))
def bl_per_start(spark, sf_dir):
    return _shown(Result(baselines.per_start_loop(graph(spark, sf_dir, "slice:1").cached(), "TRAIL", "purchase+", [0, 1, 2, 3, 4])))


def _by_mask(g: PathGraph, pattern: str) -> DataFrame:
    from pathweave.operators import product, rounds, seeds
    from pathweave.plans.planner import compiled
    from pathweave.query import PathQuery

    a = compiled(g, PathQuery(None, pattern))
    r = rounds.Rounds(g, a, seeds.resolve(g, a, product.adjacency(g, a), None))
    return _ends(Result(r.endpoints_by_mask()))


@_add("bitmask_endpoints", oracles.endpoints("slice:2", "purchase/click*"))
def bitmask_endpoints(spark, sf_dir):
    return _by_mask(graph(spark, sf_dir, "slice:2"), "purchase/click*")


@_add("bitmask_endpoints_hop", oracles.endpoints("hop", "purchase/click*"))
def bitmask_endpoints_hop(spark, sf_dir):
    return _by_mask(graph(spark, sf_dir, "hop"), "purchase/click*")


@_add("dfs_any_trail_diamond", "SELECT CAST(0 AS BIGINT) AS src, CAST(90 AS BIGINT) AS dst, CAST(60 AS INTEGER) AS length")
def dfs_any_trail_diamond(spark, sf_dir):
    return workloads.diamond(spark, 30, "ANY TRAIL", order="dfs").df.select(F.col("start").alias("src"), F.col("end").alias("dst"), "length")


@_add("all_trail_diamond_limit", "SELECT CAST(100000 AS BIGINT) AS paths, CAST(80 AS INTEGER) AS length")
def all_trail_diamond_limit(spark, sf_dir):
    return workloads.diamond(spark, 40, "TRAIL").df.agg(F.count_distinct("eids").alias("paths"), F.max("length").alias("length"))


@_add("all_shortest_diamond_limit", "SELECT CAST(100000 AS BIGINT) AS paths, CAST(80 AS INTEGER) AS length")
def all_shortest_diamond_limit(spark, sf_dir):
    return workloads.diamond(spark, 40, "ALL SHORTEST WALK").df.agg(F.count_distinct("eids").alias("paths"), F.max("length").alias("length"))


@_add("any_shortest_diamond_1000", "SELECT CAST(0 AS BIGINT) AS src, CAST(3000 AS BIGINT) AS dst, CAST(2000 AS INTEGER) AS length")
def any_shortest_diamond_1000(spark, sf_dir):
    return workloads.diamond(spark, 1000, "ANY SHORTEST WALK").df.select(F.col("start").alias("src"), F.col("end").alias("dst"), "length")


@_add("rounds_limit_unrank", "SELECT CAST(200 AS BIGINT) AS paths, CAST(200 AS BIGINT) AS distinct_paths, CAST(20 AS INTEGER) AS length")
def rounds_limit_unrank(spark, sf_dir):
    r = workloads.diamond(spark, 10, "ALL SHORTEST WALK", limit=200, strategy="rounds")
    return r.df.agg(F.count(F.lit(1)).alias("paths"), F.count_distinct("eids").alias("distinct_paths"), F.max("length").alias("length"))


@_add("waves_trail", oracles.paths("slice:1", "TRAIL", "purchase+"))
def waves_trail(spark, sf_dir):
    from pathweave.modes import parse_mode
    from pathweave.operators import product, seeds, waves
    from pathweave.plans.planner import compiled
    from pathweave.query import PathQuery

    g, m = graph(spark, sf_dir, "slice:1"), parse_mode("TRAIL")
    a = compiled(g, PathQuery(m, "purchase+"))
    return _shown(Result(waves.run(g, a, seeds.resolve(g, a, product.adjacency(g, a), None), m)))


@_add("stream_edges_batch_equal")
def stream_edges_batch_equal(spark, sf_dir):
    """Edges that the batch form has and the stream lacks, or the other way round: none."""
    from pathweave.storage import shared_dir
    from pathweave.streaming import edges as S
    import uuid

    src = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    catalog.read(spark, sf_dir, "events").repartitionByRange(3, "ts", "event_id").sortWithinPartitions("ts", "event_id").write.parquet(src)
    out, log = f"{src}-edges", f"{src}-log"
    q = S.sequence_pieces(S.events(spark, src, files_per_batch=1000)).writeStream.format("parquet").option("path", out).option("checkpointLocation", log).outputMode("append").start()
    q.processAllAvailable()
    q.stop()
    got, want = S.joined(spark.read.schema(S.PIECES).parquet(out)), graph(spark, sf_dir, "hop").edges
    cols = ["src", "label", "dst", "eid"]
    both = got.select(*cols, F.lit(1).alias("n")).unionByName(want.select(*cols, F.lit(-1).alias("n")))
    return both.groupBy(*cols).agg(F.sum("n").alias("n")).filter("n <> 0").withColumn("n", F.explode(F.sequence(F.lit(1), F.abs("n").cast("int")))).select(*cols)
