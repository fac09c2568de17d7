"""Streams of events: windows, deduplication, joins, training by micro-batches, and per-worker anchors in state."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQueryListener

from terse.sources.tables import SCHEMAS, read, shared_folder

QUERIES: dict = {}
SQL: dict[str, str] = {}


def _raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.readStream.schema(SCHEMAS["events"]).parquet(f"{sf_dir}/event[s].parquet")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as a stream of files; the time as an instant, as watermarks need it."""
    return _raw(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over what is there and returns its table, from files of the shared folder: batch by batch, one that runs again overwrites its own, and nothing
    gathers on the driver.  In complete mode the last batch is the table."""
    spark, folder, done = stream.sparkSession, shared_folder(stream.sparkSession), set()

    def keep(batch: DataFrame, k: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/drained/{k}")
        done.add(k)

    stream.writeStream.foreachBatch(keep).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{folder}/stream").start().awaitTermination()
    batches = sorted(done)[-1:] if mode == "complete" else sorted(done)
    if not batches:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*[f"{folder}/drained/{k}" for k in batches])


def _merged(rows: pa.Table, gap: int) -> pa.Table:
    """Sessions (first and last time, n) of rows that are sessions themselves, a user's in a row by first time, those without a time last and each alone."""
    numbers = lambda c: pc.fill_null(rows[c].cast(pa.int64()), 0).to_numpy()
    empty = lambda c: rows[c].is_null().to_numpy()
    user, first, last, timeless = numbers("user_id"), numbers("first"), numbers("last"), empty("first")
    other = np.ones(len(user), bool)
    other[1:] = (user[1:] != user[:-1]) | (empty("user_id")[1:] != empty("user_id")[:-1])
    until = pd.Series(last).groupby(np.cumsum(other)).cummax().to_numpy()
    opens = other | timeless
    opens[1:] |= first[1:] - until[:-1] >= gap
    at = np.flatnonzero(opens)
    ends = pa.array(np.maximum.reduceat(last, at), mask=timeless[at]).cast(pa.timestamp("us"))
    return pa.table({"user_id": rows["user_id"].take(at), "first": rows["first"].take(at), "last": ends, "n": np.add.reduceat(numbers("n"), at)})


def sessions(stream: DataFrame, hours: int) -> DataFrame:
    """Sessions of every user over what a stream of events holds: user_id, first and last time, n.  An event opens one if the user's last is that many hours back or
    more, or if it has no time.

    Their table is the state, in files of the shared folder by batch, not in the executors' memory: a batch adds its events to the table of the batch before, and one that
    runs again overwrites its own.  Events that Python is given together are merged before users are dealt out, so a frequent user's come as few rows.
    """
    spark, folder, done, gap = stream.sparkSession, shared_folder(stream.sparkSession), set(), hours * 3_600_000_000
    schema = "user_id long, first timestamp_ntz, last timestamp_ntz, n long"

    def parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if len(b):
                rows = pa.table({"user_id": b["user_id"], "first": b["ts"], "last": b["ts"], "n": np.ones(len(b), np.int64)})
                yield from _merged(rows.sort_by([("user_id", "ascending"), ("first", "ascending")]), gap).to_batches()

    def wholes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = None  # the last session may go on in the next rows
        for b in batches:
            if len(b):
                found = _merged(pa.concat_tables([*([] if rest is None else [rest]), pa.Table.from_batches([b])]), gap)
                yield from found[:-1].to_batches()
                rest = found[-1:]
        if rest is not None:
            yield from rest.to_batches()

    def merge(batch: DataFrame, k: int) -> None:
        rows = batch.mapInArrow(parts, schema)
        if k:
            rows = rows.union(batch.sparkSession.read.schema(schema).parquet(f"{folder}/sessions/{k - 1}"))
        out = rows.repartition("user_id").sortWithinPartitions("user_id", F.col("first").asc_nulls_last()).mapInArrow(wholes, schema)
        out.write.mode("overwrite").parquet(f"{folder}/sessions/{k}")
        done.add(k)

    stream.select("user_id", "ts").writeStream.foreachBatch(merge).trigger(availableNow=True).option("checkpointLocation", f"{folder}/stream").start().awaitTermination()
    return spark.read.schema(schema).parquet(f"{folder}/sessions/{max(done)}") if done else spark.createDataFrame([], schema)


class Progress(StreamingQueryListener):
    """Rows and seconds of every micro-batch, as the driver is told of them."""

    def __init__(self):
        self.batches: list[tuple[str, int, int, float]] = []

    def onQueryStarted(self, event) -> None:
        pass

    def onQueryProgress(self, event) -> None:
        p = event.progress
        self.batches.append((p.name, p.batchId, p.numInputRows, p.durationMs.get("triggerExecution", 0) / 1000))

    def onQueryIdle(self, event) -> None:
        pass

    def onQueryTerminated(self, event) -> None:
        pass


def query(name, sql):
    def keep(build):
        QUERIES[name] = build
        if sql:
            SQL[name] = sql
        return build

    return keep


_stamp = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")


@query("stream_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(s, d):
    out = events(s, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drained(out.select(_stamp("w.start").alias("day"), "event_type", "n"), "complete")


@query("stream_sliding", "SELECT strftime(date_trunc('day', ts) - i * INTERVAL 1 DAY, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM events, (VALUES (0), (1)) v(i) GROUP BY 1")
def _(s, d):
    return drained(events(s, d).groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(_stamp("w.start").alias("start"), "n"), "complete")


@query(
    "stream_session",
    "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, g",
)
def _(s, d):
    return sessions(_raw(s, d), 6).select("user_id", F.substring(F.col("first").cast("string"), 1, 19).alias("start"), "n")


@query("stream_dedupe", "SELECT DISTINCT user_id, event_type FROM events")
def _(s, d):
    return drained(events(s, d).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]), "append")


@query("stream_dedupe_watermark", "SELECT DISTINCT user_id, event_type, props FROM events")
def _(s, d):
    """Keys are forgotten once the watermark has passed them, so the state stays bounded on an endless stream."""
    return drained(events(s, d).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["user_id", "event_type", "props"]).select("user_id", "event_type", "props"), "append")


@query(
    "stream_interval_join",
    "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'",
)
def _(s, d):
    """Clicks with the purchases of the same user within an hour: both sides are streams, and watermarks bound what is kept of either."""
    side = lambda kind: events(s, d).where(F.col("event_type") == kind).select(F.col("event_id").alias(f"{kind}_id"), F.col("user_id").alias(f"{kind}_user"), F.col("ts").alias(f"{kind}_ts")).withWatermark(f"{kind}_ts", "2 hours")
    near = F.expr("click_user = purchase_user and purchase_ts >= click_ts and purchase_ts <= click_ts + interval 1 hour")
    return drained(side("click").join(side("purchase"), near).select("click_id", "purchase_id"), "append")


@query("stream_static_join", "SELECT event_type, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY event_type")
def _(s, d):
    joined = events(s, d).join(read(s, d, "customer", "c_custkey"), F.col("user_id") == F.col("c_custkey"))
    return drained(joined.groupBy("event_type").agg(F.count("*").alias("n")), "complete")


def _staged(s, d, files: int = 4) -> str:
    """Events in several files, one after the other by event_id modulo their number, so that micro-batches have something to follow."""
    path = f"{shared_folder(s)}/events"
    for k in range(files):
        read(s, d, "events").where(F.col("event_id") % files == k).coalesce(1).write.mode("append").parquet(path)
    return path


def _trickled(s, d, files: int = 4) -> DataFrame:
    return s.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", 1).parquet(_staged(s, d, files))


@query("stream_train", None)
def _(s, d):
    """One step of the two-way method per micro-batch: value by kind of event; the model's table of a batch is written by id, so a repeated one changes nothing, and a
    run that starts again goes on from the last table."""
    kinds = sorted(r[0] for r in read(s, d, "events", "event_type").distinct().collect())
    rows = train(s, _trickled(s, d), kinds, shared_folder(s))
    return s.createDataFrame(rows, "batch long, events double, model array<double>")


def train(s: SparkSession, stream: DataFrame, kinds: list[str], folder: str) -> list[tuple]:
    """Trains over what the stream holds; state and model are in the folder, by batch."""
    from terse.plans import methods as M
    from terse.plans.engine import Fit, resume, save

    method, rows = M.two_way_residual(4), []
    store = f"{folder}/states"

    def known(k: int):
        try:
            return resume(s, f"{store}/{k}")
        except AnalysisException:
            return None

    def step(batch: DataFrame, k: int) -> None:
        state = known(k - 1) if k else M.State.start(np.zeros(len(kinds)), 4)
        sums = batch.groupBy(F.pmod("user_id", F.lit(4)).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("v")).collect()
        g, n = np.zeros((4, len(kinds))), np.ones(4)
        for r in sums:
            i = kinds.index(r["event_type"])
            g[r["w"], i] += r["n"] * state.shared[i] - r["v"] / 50
            n[r["w"]] += r["n"]
        M.iterate(method, state, g / n[:, None], 0.5, 1, k)
        state.iteration = k + 1
        save(Fit(state.shared, [], state), s, f"{store}/{k}")
        rows.append((k, float(sum(r["n"] for r in sums)), [float(x) for x in state.shared]))

    stream.writeStream.foreachBatch(step).trigger(availableNow=True).option("checkpointLocation", f"{folder}/train").start().awaitTermination()
    return rows


_CENTS = "CAST(floor(value * 100 + 0.5) AS BIGINT)"
_PER = f"SELECT user_id % 4 AS worker, event_id % 4 AS k, CAST(floor(CAST(sum({_CENTS}) AS DOUBLE) / count(*) + 0.5) AS BIGINT) AS mean FROM events GROUP BY ALL"


def _anchor_sql() -> str:
    a = "0"
    for k in range(4):
        m = f"coalesce(m{k}, {a})"
        a = f"({a} + CAST(floor(({m} - {a}) / 10.0::DOUBLE + 0.5) AS BIGINT))"
    means = ", ".join(f"max(mean) FILTER (k = {k}) AS m{k}" for k in range(4))
    return f"SELECT worker, CAST({a} AS BIGINT) AS anchor FROM (SELECT worker, {means} FROM ({_PER}) GROUP BY worker)"


@query("stream_stateful_anchor", _anchor_sql())
def _(s, d):
    """Per worker an anchor, in cents, that moves by a tenth towards the mean value of each micro-batch; it is kept in the state store."""

    def follow(key, frames, state):
        anchor, k = state.get if state.exists else (0, 0)
        cents = np.concatenate([np.floor(f.value.to_numpy() * 100 + 0.5) for f in frames])
        mean = int(np.floor(cents.sum() / len(cents) + 0.5))
        anchor += int(np.floor((mean - anchor) / 10.0 + 0.5))
        state.update((anchor, k + 1))
        yield pd.DataFrame({"worker": [key[0]], "anchor": [anchor], "batch": [k + 1]})

    stream = _trickled(s, d).select(F.pmod("user_id", F.lit(4)).alias("worker"), "value")
    out = stream.groupBy("worker").applyInPandasWithState(follow, "worker long, anchor long, batch long", "anchor long, batches long", "update", "NoTimeout")
    return drained(out, "update").groupBy("worker").agg(F.max_by("anchor", "batch").alias("anchor"))


_LATE = "SELECT count(*) FILTER (late) AS late, count(*) FILTER (NOT late) AS kept FROM (SELECT event_id % 3 = 2 AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events WHERE event_id % 3 = 0) - INTERVAL 1 HOUR AS late FROM events)"


@query("stream_late_count", _LATE)
def _(s, d):
    """Rows that come after the watermark has passed their window are dropped; what the windows hold in the end says how many.

    A micro-batch drops by the watermark that its predecessor began with, so of three the last drops by what the first has seen.
    """
    path = _staged(s, d, 3)
    out = s.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", 1).parquet(path).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    told = drained(out.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n"), "update")
    kept = told.groupBy("start").agg(F.max("n").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept"))
    return kept.crossJoin(s.read.parquet(path).agg(F.count("*").alias("all"))).select((F.col("all") - F.col("kept")).alias("late"), "kept")


@query("stream_to_table", "SELECT user_id, count(*) AS n, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY user_id")
def _(s, d):
    """Into files of the shared folder, batch by batch: nothing gathers on the driver."""
    folder = shared_folder(s)
    keep = lambda batch, k: batch.withColumn("batch", F.lit(k)).write.mode("overwrite").parquet(f"{folder}/out/batch={k}")
    part = _trickled(s, d).select("user_id", F.floor(F.col("value") * 100 + 0.5).cast("long").alias("cents"))
    part.writeStream.foreachBatch(lambda b, k: keep(b.groupBy("user_id").agg(F.count("*").alias("n"), F.sum("cents").alias("cents")), k)).trigger(availableNow=True).option("checkpointLocation", f"{folder}/stream").start().awaitTermination()
    return s.read.parquet(f"{folder}/out").groupBy("user_id").agg(F.sum("n").alias("n"), F.sum("cents").alias("cents"))
