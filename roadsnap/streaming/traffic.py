"""Traffic observations as a stream: windows, walks, dedup, and matching per micro-batch."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.shared import cut, drop, shared_dir
from ..sources.tables import SCHEMAS

DELAY = "10 minutes"


def read(spark: SparkSession, sf_dir: str, name: str = "events") -> DataFrame:
    """The events file as a stream; event time is cast to a zoned timestamp, which watermarks ask for."""
    raw = spark.readStream.schema(SCHEMAS[name]).option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def run(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Run over all that is there; the result is what the sink holds at the end.

    complete: each batch replaces the result; append and update: batches are kept side by side under their
    number, so a repeated batch replaces itself.
    """
    spark = stream.sparkSession
    from pyspark.sql.types import StructType

    schema: StructType = stream.schema
    place = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def sink(batch: DataFrame, number: int) -> None:
        target = f"{place}/out" if mode == "complete" else f"{place}/out/batch={number}"
        batch.write.mode("overwrite").parquet(target)

    query = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.schema(schema).parquet(f"{place}/out")
    return out.select([f.name for f in schema])


def tumbling(events: DataFrame, width: str = "5 minutes") -> DataFrame:
    """(start, n, total_ms): observations of every window; late ones beyond the delay are dropped."""
    w = F.window("ts", width)
    return events.withWatermark("ts", DELAY).groupBy(w).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 1000).cast("bigint")).alias("total_ms")).select(F.unix_timestamp("window.start").alias("start"), "n", "total_ms")


def sliding(events: DataFrame, width: str = "15 minutes", step: str = "5 minutes") -> DataFrame:
    w = F.window("ts", width, step)
    return events.withWatermark("ts", DELAY).groupBy(w).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 1000).cast("bigint")).alias("total_ms")).select(F.unix_timestamp("window.start").alias("start"), "n", "total_ms")


def sessions(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    """(user_id, start, n): a user's events cut to trips where nothing happens for `gap`."""
    w = F.session_window("ts", gap)
    return events.withWatermark("ts", DELAY).groupBy("user_id", w).agg(F.count("*").alias("n")).select("user_id", F.unix_timestamp("session_window.start").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    """(event_id, user_id): one row per event, however often it is sent within the delay."""
    return events.unionAll(events).withWatermark("ts", DELAY).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def with_labels(events: DataFrame, places: DataFrame) -> DataFrame:
    """Stream-static join: observations with what is known about their bucket."""
    return events.withColumn("bucket", F.expr("cast(get_json_object(props, '$.k') as bigint) div 10")).join(places, "bucket").select("event_id", "bucket", "label")


def pairs_within(clicks: DataFrame, buys: DataFrame, span: str = "10 minutes") -> DataFrame:
    """Stream-stream join (user_id, a, b): events of a user that follow one another within `span`."""
    x = clicks.select(F.col("user_id"), F.col("event_id").alias("a"), F.col("ts").alias("ta")).withWatermark("ta", DELAY)
    y = buys.select(F.col("user_id").alias("u"), F.col("event_id").alias("b"), F.col("ts").alias("tb")).withWatermark("tb", DELAY)
    return x.join(y, F.expr(f"user_id = u and tb > ta and tb <= ta + interval {span}")).select("user_id", "a", "b")


def placed(events: DataFrame) -> DataFrame:
    """What walks need of events: the bucket as place, and the observed time in whole milliseconds."""
    return events.selectExpr("user_id", "event_id", "ts", "cast(get_json_object(props, '$.k') as bigint) div 10 as bucket", "cast(round(value * 1000) as bigint) as obs_ms")


def walk(events: DataFrame) -> DataFrame:
    """(pid, eid, obs_ms): edge observations of users' walks; the state is a user's last bucket.

    Rows of a micro-batch are ordered by (ts, event_id); streams have no lag().
    """
    return observations(placed(events).withColumn("snap", F.lit(0))).select("pid", "eid", "obs_ms")


def observations(places: DataFrame) -> DataFrame:
    """(pid, eid, obs_ms, snap) of a stream (user_id, event_id, ts, bucket, obs_ms, snap), as walk() tells."""

    def step(key, frames, state):
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"], kind="stable")
        last = state.get[0] if state.exists else None
        out = []
        for bucket, obs, snap in zip(rows["bucket"], rows["obs_ms"], rows["snap"]):
            if last is not None and bucket != last:
                out.append((key[0], int(last) * 10 + int(bucket), int(obs), int(snap)))
            last = int(bucket)
        state.update((last,))
        yield pd.DataFrame(out, columns=["pid", "eid", "obs_ms", "snap"]).astype("int64")

    moves = places.groupBy("user_id").applyInPandasWithState(step, "pid bigint, eid bigint, obs_ms bigint, snap bigint", "last bigint", "append", "NoTimeout")
    return moves.withColumn("snap", F.col("snap").cast("int"))


class SnapshotMatcher:
    """Per micro-batch: the decision on each new snapshot, an index for each that becomes typical, and answers from it.

    All that lasts is under `folder`, which every executor and a restarted driver can read: version N of the model is
    what batch N left (version -1 is the initial one), with the labels of the snapshots that it opened beside it, its
    decisions and its answers.  A batch that is run again reads the version before its own number and overwrites what it
    wrote.  The snapshots of a batch are decided in the order of their numbers, and meet those that became
    typical before them in the batch too, so decisions do not depend on how snapshots are cut to batches.
    """

    def __init__(self, typical: DataFrame, tau: float, edges: DataFrame | None = None, weights: DataFrame | None = None, folder: str | None = None):
        """`edges` and the `weights` of the initial typical snapshots are asked for where queries are to be answered."""
        from ..operators import matching

        self.spark, self.tau, self.edges = typical.sparkSession, tau, edges
        self.folder = folder or f"{shared_dir(self.spark)}/match-{uuid.uuid4().hex}"
        if -1 not in self._versions():
            if edges is not None:
                self._index(weights, -1)
            matching.save_model(self.spark, f"{self.folder}/model", -1, typical, tau=tau)  # the manifest comes last

    def _versions(self) -> list[int]:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/model")
        files = path.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not files.exists(path):
            return []
        return sorted(int(f.getPath().getName().split("=")[1]) for f in files.listStatus(path) if files.exists(self.spark._jvm.org.apache.hadoop.fs.Path(f.getPath(), "manifest/_SUCCESS")))

    def _index(self, weights: DataFrame, number: int) -> None:
        from ..operators import routing

        routing.hub_labels(self.edges, weights).write.mode("overwrite").partitionBy("typ").parquet(f"{self.folder}/index/version={number}")

    def index(self, below: int) -> DataFrame:
        """(typ, v, hub, dist, side): labels of all typical snapshots that batches before `below` know."""
        read = self.spark.read.schema("v bigint, hub bigint, dist bigint, side string, version int, typ int").option("basePath", f"{self.folder}/index")
        return read.parquet(f"{self.folder}/index").filter(F.col("version") < below).drop("version")

    def batch(self, rep: DataFrame, number: int, weights: DataFrame | None = None, queries: DataFrame | None = None) -> None:
        """rep: (snap, dim, val) of the snapshots that this batch closes, with their weights and queries (snap, s, t)."""
        from ..operators import matching, routing

        before, _ = matching.load_model(self.spark, f"{self.folder}/model", max(v for v in self._versions() if v < number))
        decided = matching.decide_in_order(rep, before, self.tau)
        decided.write.mode("overwrite").parquet(f"{self.folder}/decisions/batch={number}")
        decided = self.spark.read.schema(decided.schema).parquet(f"{self.folder}/decisions/batch={number}")
        new = decided.filter("is_new").select("snap")
        if self.edges is not None:
            self._index(weights.join(F.broadcast(new), "snap", "left_semi"), number)  # a row per new snapshot of a batch
            asked = queries.join(decided.select("snap", "typ", "is_new"), "snap")
            found = routing.answer(asked.select("typ", "s", "t").distinct(), self.index(number + 1))
            asked.join(found, ["typ", "s", "t"], "left").write.mode("overwrite").parquet(f"{self.folder}/answers/batch={number}")
        matching.save_model(self.spark, f"{self.folder}/model", number, before.unionByName(rep.join(F.broadcast(new), "snap", "left_semi")), tau=self.tau)

    @property
    def decisions(self) -> dict[int, DataFrame]:
        """(snap, typ, dist, is_new) by batch."""
        read = self.spark.read.schema("snap int, typ int, dist double, is_new boolean")
        return {v: read.parquet(f"{self.folder}/decisions/batch={v}") for v in self._versions() if v >= 0}

    def answers(self) -> DataFrame:
        """(snap, typ, is_new, s, t, dist) of all queries so far."""
        read = self.spark.read.schema("typ int, s bigint, t bigint, snap int, is_new boolean, dist bigint, batch int")
        return read.parquet(f"{self.folder}/answers").select("snap", "typ", "is_new", "s", "t", "dist")


def _drain(stream: DataFrame, each, folder: str) -> None:
    query = stream.writeStream.foreachBatch(each).option("checkpointLocation", f"{folder}/state").start()
    query.processAllAvailable()  # a replayed source tells batch by batch what is left
    query.stop()


def match_stream(rep_stream: DataFrame, typical: DataFrame, tau: float, folder: str | None = None) -> DataFrame:
    """(snap, typ, dist, is_new) of a stream of represented snapshots (snap, dim, val)."""
    matcher = SnapshotMatcher(typical, tau, folder=folder)
    _drain(rep_stream, matcher.batch, matcher.folder)
    out = None
    for d in matcher.decisions.values():
        out = d if out is None else out.unionByName(d)
    return out


def answer_stream(places: DataFrame, net, of_edge: DataFrame, of_net: DataFrame, tau: float, first: int = 0, folder: str | None = None) -> DataFrame:
    """From a stream of placed events to answers: (snap, typ, is_new, s, t, dist).

    places: (user_id, event_id, ts, bucket, obs_ms, snap), whole snapshots per micro-batch.  Users' walks give edge
    observations; a snapshot's mean observations, filled where an edge was not seen, are its weights and its
    representation; it is matched or opened and indexed; and its moves' ends are the queries that are answered.
    `net` has the topology and, as snapshot `first`, the weights of the initial typical one.
    """
    from ..operators import edgevec, snapshots

    edges, start = cut(net.edges), cut(net.weights.filter(F.col("snap") == first))
    matcher = SnapshotMatcher(edgevec.weights(start), tau, edges, start, folder)
    of_edge, of_net = cut(of_edge), cut(of_net)

    def each(moves: DataFrame, number: int) -> None:
        moves = cut(moves)
        if moves.isEmpty():
            return
        weights = cut(snapshots.fill(snapshots.profile(moves), edges, moves.select("snap").distinct(), of_edge, of_net))
        queries = moves.selectExpr("snap", "eid div 10 as s", "eid % 10 as t").distinct()
        matcher.batch(edgevec.weights(weights), number, weights, queries)
        drop(moves, weights)

    _drain(observations(places), each, matcher.folder)
    return matcher.answers()
