"""Graphs over the given tables, and the literal ones."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathweave.graph import PathGraph
from pathweave.storage import settle


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def hop(spark: SparkSession, sf_dir: str, label: str | None = None) -> PathGraph:
    """User to the user of the next event (by time, then id); labelled by the first event's type, or all alike."""
    g = PathGraph.from_sequence(read(spark, sf_dir, "events"), ["ts", "event_id"], "user_id", "event_type", "event_id")
    return g if label is None else PathGraph(g.edges.withColumn("label", F.lit(label)), g.nodes)


def hop_slice(spark: SparkSession, sf_dir: str, days: int) -> PathGraph:
    """hop's edges of the first days: sparse enough for all trails."""
    e = read(spark, sf_dir, "events").filter(F.col("ts") < F.lit("2024-01-01").cast("timestamp_ntz") + F.expr(f"interval {days} days")).select(F.col("event_id").alias("eid"))
    g = hop(spark, sf_dir)
    return PathGraph(g.edges.join(e, "eid", "left_semi").select("src", "label", "dst", "eid"), g.nodes)


def star(spark: SparkSession, sf_dir: str) -> PathGraph:
    """Customers, orders, parts, suppliers, nations and regions."""
    t = lambda n: read(spark, sf_dir, n)
    name = lambda p, c: F.concat(F.lit(p + ":"), F.col(c).cast("string"))

    def edges(df, kind, s, sc, label, d, dc):
        src, dst = name(s, sc), name(d, dc)
        return df.select(src.alias("src"), F.lit(label).alias("label"), dst.alias("dst"), F.concat(F.lit(kind + "|"), src, F.lit("|"), dst).alias("eid"))

    li = t("lineitem")
    contains = li.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").distinct()
    contains = contains.select(name("O", "l_orderkey").alias("src"), F.lit("contains").alias("label"), name("P", "l_partkey").alias("dst"), F.concat_ws("|", F.lit("contains"), "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("eid"))
    parts = [
        edges(t("orders"), "placed", "C", "o_custkey", "placed", "O", "o_orderkey"),
        contains,
        edges(li.select("l_suppkey", "l_partkey").distinct(), "supplies", "S", "l_suppkey", "supplies", "P", "l_partkey"),
        edges(t("customer"), "livesin", "C", "c_custkey", "livesin", "N", "c_nationkey"),
        edges(t("supplier"), "basedin", "S", "s_suppkey", "basedin", "N", "s_nationkey"),
        edges(t("nation"), "partof", "N", "n_nationkey", "partof", "R", "n_regionkey"),
    ]
    e = parts[0]
    for p in parts[1:]:
        e = e.unionByName(p)
    return PathGraph.of(e)


def trade(spark: SparkSession, sf_dir: str) -> PathGraph:
    """Nation of the customer to nation of the supplier, by return flag: small and dense."""
    li, o, c, s = (read(spark, sf_dir, n) for n in ("lineitem", "orders", "customer", "supplier"))
    j = li.join(o, li.l_orderkey == o.o_orderkey).join(c, F.col("o_custkey") == c.c_custkey).join(s, li.l_suppkey == s.s_suppkey)
    e = j.select(F.col("c_nationkey").cast("long").alias("src"), F.col("l_returnflag").alias("label"), F.col("s_nationkey").cast("long").alias("dst")).distinct()
    return PathGraph.of(e.withColumn("eid", F.concat_ws("|", "label", F.lpad(F.col("src").cast("string"), 2, "0"), F.lpad(F.col("dst").cast("string"), 2, "0"))))


def link(spark: SparkSession, sf_dir: str) -> PathGraph:
    """Pages to the targets they link to, and to their host."""
    p = read(spark, sf_dir, "pages").select(F.concat(F.lit("g:"), F.col("page_id").cast("string")).alias("src"), "url", "html")
    links = p.select("src", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("t")).select("src", F.lit("links").alias("label"), F.concat(F.lit("t:"), "t").alias("dst")).distinct()
    hosts = p.select("src", F.lit("on").alias("label"), F.concat(F.lit("h:"), F.regexp_extract("url", "://([^/?#]*)", 1)).alias("dst")).distinct()
    e = links.unionByName(hosts)
    return PathGraph.of(e.withColumn("eid", F.concat_ws("|", "label", "src", "dst")))


def turn(spark: SparkSession, sf_dir: str) -> PathGraph:
    """A turn of a conversation to the next, labelled by who spoke first."""
    c = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.concat_ws(":", "conv_id", "turn").alias("node"))
    return PathGraph.from_sequence(c.withColumn("eid", F.col("node")), ["turn"], "node", "role", "eid", partition=["conv_id"])


def diamond(spark: SparkSession, n: int) -> PathGraph:
    """A chain of n blocks, each with two ways through: 2**n paths of length 2n from node 0 to node 3n."""
    b = spark.range(n)
    one = lambda s, d, k: b.select((F.col("id") * 3 + s).alias("src"), F.lit("a").alias("label"), (F.col("id") * 3 + d).alias("dst"), (F.col("id") * 4 + k).alias("eid"))
    return PathGraph.of(one(0, 1, 0).unionByName(one(0, 2, 1)).unionByName(one(1, 3, 2)).unionByName(one(2, 3, 3)), spark.range(3 * n + 1))


def order_diamond(spark: SparkSession, sf_dir: str, n: int) -> PathGraph:
    """The same shape out of lineitem: the first n + 1 orders (by key) with two line numbers or more as a chain, each reaching the next
    one through its first and its last line."""
    li = read(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("k")).agg(F.min("l_linenumber").alias("x"), F.max("l_linenumber").alias("y"))
    chain = settle(li.filter("x < y").orderBy("k").limit(n + 1), "chain")
    # n + 1 rows.
    chain = chain.withColumn("nxt", F.lead("k").over(Window.orderBy("k"))).filter("nxt is not null")
    here, there = F.concat(F.lit("O:"), F.col("k").cast("string")), F.concat(F.lit("O:"), F.col("nxt").cast("string"))
    ways = [F.concat_ws(":", F.lit("L"), F.col("k").cast("string"), F.col(c).cast("string")) for c in ("x", "y")]
    e = chain.select(F.explode(F.array(*[F.struct(s.alias("src"), d.alias("dst")) for w in ways for s, d in ((here, w), (w, there))])).alias("e")).select("e.src", F.lit("a").alias("label"), "e.dst")
    return PathGraph.of(e.withColumn("eid", F.concat_ws("|", "label", "src", "dst")))


#: The example graph.
EXAMPLE = (
    ("John", "follows", "Joe", "e1"), ("Joe", "follows", "John", "e2"), ("Joe", "follows", "Paul", "e3"), ("Joe", "follows", "Lily", "e4"),
    ("Paul", "follows", "Anne", "e5"), ("Paul", "follows", "Jane", "e6"), ("Lily", "follows", "Jane", "e7"), ("John", "lives", "Rome", "e8"),
    ("Anne", "lives", "Rome", "e9"), ("Jane", "works", "ENS", "e10"), ("Anne", "works", "ENS", "e11"), ("Lily", "follows", "Paul", "e12"),
)


def example(spark: SparkSession) -> PathGraph:
    return PathGraph.of(spark.createDataFrame(EXAMPLE, "src string, label string, dst string, eid string"))


def triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triples of customers, suppliers, nations and regions."""
    e = star(spark, sf_dir).edges.filter(F.col("label").isin("livesin", "basedin", "partof"))
    return e.select(F.col("src").alias("s"), F.col("label").alias("p"), F.col("dst").alias("o"))


def near(spark: SparkSession, sf_dir: str, m: int = 5) -> PathGraph:
    """Each vector to its m nearest by cosine, labelled by the class of the target; blocks of vectors meet, not pairs of rows."""
    import numpy as np
    import pandas as pd

    v = read(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label").filter("embedding is not null")
    if v.count() > 200_000:
        raise ValueError("near() is for small tables: the vectors are broadcast")
    rows = v.toPandas()
    mat = np.stack(rows["embedding"].to_numpy()).astype(np.float32)
    mat /= np.maximum(np.linalg.norm(mat, axis=1, keepdims=True), 1e-12)
    sent = spark.sparkContext.broadcast((rows["vec_id"].to_numpy(), mat, rows["label"].astype(str).to_numpy()))

    def nearest(batches):
        ids, mat, labels = sent.value
        for pdf in batches:
            q = np.stack(pdf["embedding"].to_numpy()).astype(np.float32)
            q /= np.maximum(np.linalg.norm(q, axis=1, keepdims=True), 1e-12)
            sim = q @ mat.T
            sim[pdf["vec_id"].to_numpy()[:, None] == ids[None, :]] = -2
            top = np.argsort(-sim, axis=1, kind="stable")[:, :m]
            src = np.repeat(pdf["vec_id"].to_numpy(), m)
            yield pd.DataFrame({"src": src, "label": labels[top.reshape(-1)], "dst": ids[top.reshape(-1)], "eid": [f"{s}|{d}" for s, d in zip(src, ids[top.reshape(-1)])]})

    return PathGraph.of(v.mapInPandas(nearest, "src long, label string, dst long, eid string"), v.select(F.col("vec_id").alias("id")))


def documents(spark: SparkSession, sf_dir: str) -> PathGraph:
    """Documents to their source, language and quality."""
    d = read(spark, sf_dir, "documents").select("doc_id", "source", "lang")
    q = read(spark, sf_dir, "labels").select("doc_id", F.col("quality").cast("string").alias("quality"))
    name = F.concat(F.lit("d:"), F.col("doc_id").cast("string"))
    e = d.select(name.alias("src"), F.lit("from").alias("label"), F.concat(F.lit("s:"), "source").alias("dst"))
    e = e.unionByName(d.select(name.alias("src"), F.lit("in").alias("label"), F.concat(F.lit("l:"), "lang").alias("dst")))
    e = e.unionByName(q.select(name.alias("src"), F.lit("rated").alias("label"), F.concat(F.lit("q:"), "quality").alias("dst")))
    e = e.filter("dst is not null").distinct()
    return PathGraph.of(e.withColumn("eid", F.concat_ws("|", "label", "src", "dst")))
