"""Evidence that arrives over time, with batch twins that return the same rows.

Streams read Parquet files, drop repeated events within a watermark (rows that come later are counted), and window,
sessionise or join them. Micro-batches of new evidence mark the components they touch; those alone are searched again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleworld.plans import grow
from ruleworld.plans.ground import Atoms, Field
from ruleworld.plans.solve import MapResult
from ruleworld.sources.scratch import table

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_each: int = 1, late: str = "1 hour") -> DataFrame:
    """Events from files of a folder, each event once within the watermark."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_each).parquet(folder)
    raw = raw.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks take no timestamps without a zone
    return raw.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def rates(events: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w, "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("value")).select(F.col("window.start").alias("start"), "event_type", "n", "value")


def sessions(events: DataFrame, gap: str = "60 minutes") -> DataFrame:
    """Runs of a user's events with gaps under ``gap``: the components that neighbour rules make."""
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"), F.min("event_id").alias("first_id")).select("user_id", F.col("session_window.start").alias("start"), "n", "first_id")


OPEN = "user_id bigint, start timestamp, n bigint, first_id bigint"
_HELD = "start array<timestamp>, last array<timestamp>, n array<bigint>, first_id array<bigint>"


def open_sessions(events: DataFrame, gap_minutes: int = 60) -> DataFrame:
    """``OPEN``: sessions of a watermarked stream, each once the watermark is past its end and the gap.

    A user's state is the list of sessions still open; events in any order within the watermark join or merge them.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    gap = pd.Timedelta(minutes=gap_minutes)

    def step(key, parts, state):
        spans = list(zip(*state.get, strict=True)) if state.exists else []
        for part in parts:
            spans += [(t, t, 1, i) for t, i in zip(part["ts"], part["event_id"], strict=True)]
        merged: list[tuple] = []
        for start, last, n, first in sorted(spans, key=lambda x: (x[0], x[3])):
            if merged and start < merged[-1][1] + gap:
                a, b, m, f = merged[-1]
                merged[-1] = (a, max(b, last), m + n, min(f, first))
            else:
                merged.append((start, last, n, first))
        mark = pd.Timestamp(state.getCurrentWatermarkMs(), unit="ms")
        left = [x for x in merged if pd.Timestamp(x[1]).tz_localize(None) + gap >= mark]
        done = [x for x in merged if pd.Timestamp(x[1]).tz_localize(None) + gap < mark]
        if left:
            state.update(tuple(list(c) for c in zip(*left, strict=True)))
            close = min(pd.Timestamp(x[1]).tz_localize(None) for x in left) + gap
            state.setTimeoutTimestamp(max(int(close.timestamp() * 1000), state.getCurrentWatermarkMs()) + 1)
        elif state.exists:
            state.remove()
        yield pd.DataFrame({"user_id": [key[0]] * len(done), "start": [x[0] for x in done], "n": [x[2] for x in done], "first_id": [x[3] for x in done]})

    return events.select("user_id", "ts", "event_id").groupBy("user_id").applyInPandasWithState(step, OPEN, _HELD, "append", GroupStateTimeout.EventTimeTimeout)


def pairs_within(events: DataFrame, others: DataFrame, gap: str = "60 minutes") -> DataFrame:
    """``e1, e2``: events of one stream and later ones of another by the same user within the gap.

    Both streams carry watermarks, which bound what is kept for the join; on batches it is the plain join.
    """
    a = events.select(F.col("event_id").alias("e1"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    b = others.select(F.col("event_id").alias("e2"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    return a.join(b, F.expr(f"u1 = u2 AND t2 > t1 AND t2 <= t1 + INTERVAL {gap}")).select("e1", "e2")


def with_domain(events: DataFrame, domain: DataFrame, key: str) -> DataFrame:
    """Events whose ``key`` a rule's static domain holds, with the domain's columns."""
    return events.join(domain, key)


def late_rows(query) -> int:
    """Rows that a streaming query has dropped for coming after the watermark."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in _plain(p).get("stateOperators", []))


def _plain(progress) -> dict:
    import json

    return progress if isinstance(progress, dict) else json.loads(progress.json)


def rates_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rates(table(spark, sf_dir, "events"))


def sessions_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sessions(table(spark, sf_dir, "events"))


def touched(clauses: DataFrame, comps: DataFrame, atoms: DataFrame) -> DataFrame:
    """Components that new evidence on ``atoms`` (column ``aid``) makes dirty."""
    return comps.join(atoms.select("aid"), "aid", "left_semi").select("comp").distinct()


class LiveWorld:
    """A solved program that follows a stream of evidence on one relation.

    Pass ``apply`` to ``foreachBatch``. Each batch is folded into the field and the components it touches are searched
    again. With a ``home``, a folder all executors share, every batch's field and world are written there and the batch is
    marked done last; a driver that starts anew goes on from the last batch so marked. A batch that comes a second time
    changes nothing.
    """

    def __init__(self, result: MapResult, pred: str, home: str | None = None, **how):
        self.field, self.world, self.pred, self.how, self.home = result.field, result.world, pred, how, home
        self.spark, self.last = result.world.sparkSession, -1
        if home is not None:
            self._resume()

    def _marks(self) -> DataFrame | None:
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.home}/done")
        there = path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(path)
        return self.spark.read.schema("batch bigint").parquet(f"{self.home}/done") if there else None

    def _resume(self) -> None:
        marks = self._marks()
        last = marks.agg(F.max("batch")).first()[0] if marks is not None else None
        if last is None:
            return
        where, read = f"{self.home}/batch-{last}", self.spark.read.parquet
        tables = {n: read(f"{where}/atoms-{n}") for n in self.field.atoms.program.predicates}
        self.field = Field(Atoms(self.field.atoms.program, tables), read(f"{where}/clauses"), read(f"{where}/constants"))
        self.world, self.last = read(f"{where}/world"), last

    def _keep(self, batch_id: int) -> None:
        where = f"{self.home}/batch-{batch_id}"
        parts = {f"atoms-{n}": t for n, t in self.field.atoms.tables.items()} | {"clauses": self.field.clauses, "constants": self.field.constants, "world": self.world}
        for name, rows in parts.items():
            rows.write.mode("overwrite").parquet(f"{where}/{name}")
        self.last = batch_id
        self.spark.createDataFrame([(batch_id,)], "batch bigint").coalesce(1).write.mode("append").parquet(f"{self.home}/done")
        self._resume()  # what follows reads what was kept

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        step = grow.reground(self.field, {self.pred: batch})
        self.world = grow.resolve(step, self.world, **self.how)
        self.field, self.last = step.field, batch_id
        if self.home is not None:
            self._keep(batch_id)


def oracle_sql() -> dict[str, str]:
    return {
        "windowed_rates": "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n, round(sum(value), 2) AS value FROM events GROUP BY ALL",
        "session_components": "WITH s AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 60 MINUTES THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM s) SELECT user_id, min(ts) AS start, count(*) AS n, min(event_id) AS first_id FROM g GROUP BY user_id, k",
    }
