"""Edges out of an event stream, and answers that grow with it."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathweave import automaton, regex
from pathweave.graph import next_in_order
from pathweave.storage import settle

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str, watermark: str = "1 hour", files_per_batch: int = 1) -> DataFrame:
    """The event files of a folder as a stream; ts as a timestamp with a watermark."""
    s = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return s.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def sequence_edges(stream: DataFrame, key: str = "all") -> DataFrame:
    """src, label, dst, eid between consecutive events of each key, across micro-batches: the state of a key is its last event.
    key "all" is one sequence; name a column to have as many as it has values. Events are ordered within a batch; one that is older
    than its key's last event comes after it in no batch and is left out."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    keyed = stream.withColumn("__key", F.lit("all") if key == "all" else F.col(key).cast("string"))

    def link(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        last = state.get if state.exists else None
        out = []
        for ts, eid, user, kind in zip(rows["ts"], rows["event_id"], rows["user_id"], rows["event_type"]):
            stamp = int(pd.Timestamp(ts).value)
            if last is not None:
                if (stamp, eid) < (last[0], last[1]):
                    continue
                out.append((int(last[2]), last[3], int(user), int(last[1])))
            last = (stamp, int(eid), int(user), kind)
        if last is not None:
            state.update(last)
        yield pd.DataFrame(out, columns=["src", "label", "dst", "eid"])

    return keyed.groupBy("__key").applyInPandasWithState(link, "src long, label string, dst long, eid long", "ts long, eid long, user long, kind string", "append", GroupStateTimeout.NoTimeout)


PIECES = "bucket long, kind string, src long, label string, dst long, eid long, ts long"


def sequence_pieces(stream: DataFrame, width_s: int = 3600) -> DataFrame:
    """The one sequence of all events in pieces that no single task holds: for each span of time the edges inside it ("edge") and,
    for each batch, its first and last events ("first", "last", with ts). The state of a span is its last event; an event that is
    older than its span's last is left out. joined() makes the whole of what a sink has written."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def whole(x):
        return None if pd.isna(x) else int(x)

    def link(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches))
        rows = pd.DataFrame({"ts": rows["ts"].astype("datetime64[ns]").astype("int64"), "eid": rows["event_id"].astype("int64"), "src": rows["user_id"].astype("Int64"), "label": rows["event_type"].astype(object)})
        rows = rows.sort_values(["ts", "eid"], ignore_index=True)
        last = state.get if state.exists else None
        if last is not None:
            rows = rows[(rows["ts"] > last[0]) | (rows["ts"] == last[0]) & (rows["eid"] >= last[1])]
            rows = pd.concat([pd.DataFrame({"ts": [last[0]], "eid": [last[1]], "src": pd.array([last[2]], "Int64"), "label": pd.Series([last[3]], dtype=object)}), rows], ignore_index=True)
        dst = rows["src"].shift(-1)
        edges = rows.assign(dst=dst, kind="edge")[:-1]
        ends = [rows[-1:].assign(dst=pd.array([pd.NA], "Int64"), kind="last")]
        if last is None:
            ends.append(rows[:1].assign(dst=pd.array([pd.NA], "Int64"), kind="first"))
        end = rows.iloc[-1]
        state.update((int(end["ts"]), int(end["eid"]), whole(end["src"]), end["label"]))
        yield pd.concat([edges[edges["dst"].notna()], *ends]).assign(bucket=int(k[0]))[["bucket", "kind", "src", "label", "dst", "eid", "ts"]]

    keyed = stream.withColumn("__bucket", F.floor(F.unix_micros("ts") / (width_s * 1_000_000)))
    return keyed.groupBy("__bucket").applyInPandasWithState(link, PIECES, "ts long, eid long, user long, kind string", "append", GroupStateTimeout.NoTimeout)


def joined(pieces: DataFrame) -> DataFrame:
    """src, label, dst, eid of all pieces: the edges inside spans, and one from each span's last event to the next span's first."""
    at = F.struct("ts", "eid")
    spans = pieces.filter("kind <> 'edge'").groupBy("bucket").agg(
        F.max_by(F.struct("src", "label", "eid"), F.when(F.col("kind") == "last", at)).alias("last"),
        F.min_by(F.struct("src"), F.when(F.col("kind") == "first", at)).alias("first"),
    )
    between = next_in_order(spans, ["bucket"], "first", "to").select("last.src", "last.label", F.col("to.src").alias("dst"), "last.eid")
    return pieces.filter("kind = 'edge'").select("src", "label", "dst", "eid").unionByName(between.filter("dst is not null"))


def counts_by_window(stream: DataFrame, window: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events by window and label; late ones are dropped by the watermark."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return stream.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Sessions of each user: start, end, events."""
    return stream.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("s.start").alias("s_start"), F.col("s.end").alias("s_end"), "n")


class IncrementalEndpoints:
    """Endpoints of a pattern over a growing graph: a batch of edges seeds a frontier from product keys that were reached
    before, so each batch does the work of what is new. Use as the function of foreachBatch."""

    def __init__(self, spark: SparkSession, pattern: str, starts: DataFrame):
        self.spark, self.a = spark, automaton.glushkov(regex.parse(pattern))
        self.delta = spark.createDataFrame([(q, s[0], s[1], r) for q, s, r in self.a.delta], "state int, label string, inverse boolean, to int")
        self.starts = starts.select(F.col(starts.columns[0]).alias("start"))
        self.seen = settle(self.starts.select("start", F.col("start").alias("node"), F.lit(self.a.initial).alias("state")).distinct(), "incremental")
        self.edges = None

    def _adjacency(self, e: DataFrame) -> DataFrame:
        ahead = e.select(F.col("src").alias("node"), "label", F.lit(False).alias("inverse"), F.col("dst").alias("next"))
        return ahead.unionByName(e.select(F.col("dst").alias("node"), "label", F.lit(True).alias("inverse"), F.col("src").alias("next")))

    def __call__(self, batch: DataFrame, number: int) -> None:
        new = settle(batch.select("src", "label", "dst", "eid"), "incremental-edges")
        self.edges = new if self.edges is None else settle(self.edges.unionByName(new), "incremental-edges")
        frontier, adj = self.seen, self._adjacency(new)
        while True:
            step = frontier.join(F.broadcast(self.delta), "state").join(adj, ["node", "label", "inverse"]).select("start", F.col("next").alias("node"), F.col("to").alias("state")).distinct()
            frontier = settle(step.join(self.seen, ["start", "node", "state"], "left_anti"), "incremental")
            if not frontier.limit(1).count():
                return
            self.seen = settle(self.seen.unionByName(frontier), "incremental")
            adj = self._adjacency(self.edges)

    def endpoints(self) -> DataFrame:
        return self.seen.filter(F.col("state").isin(list(self.a.finals))).select("start", F.col("node").alias("end")).distinct()
