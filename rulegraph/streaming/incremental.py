"""Streams: closures kept up to date by micro-batches, sessions, and interval joins of factors.

Only monotone rules can follow a stream: a fact that arrives later may undo an
absence. Each micro-batch of edges joins what is known on both sides, its results
are written under the batch's number, and a batch that is run again replaces its own
folder, so restarts change nothing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.plans.reason import clauses_of, positive_uses, uses
from rulegraph.sources.vocabulary import tables_graph
from rulegraph.storage import new_path


class NonMonotoneStreamingRule(ValueError):
    """A rule that later facts could undo."""


def check_monotone(rules) -> None:
    for c in clauses_of(rules):
        if any(not positive for _, positive in uses(c.body)):
            raise NonMonotoneStreamingRule(c.name)
        positive_uses(c.body, set())


class IncrementalClosure:
    """The transitive closure of a growing edge set, as a folder of batches."""

    def __init__(self, spark: SparkSession, path: str | None = None, schema: str = "s bigint, o bigint", max_rounds: int = 500):
        self.spark, self.path, self.schema, self.max_rounds = spark, path or new_path(spark, "stream"), schema, max_rounds
        self.batches: list[int] = []

    def _read(self, kind: str, batches: list[int]) -> DataFrame:
        if not batches:
            return self.spark.createDataFrame([], self.schema)
        return self.spark.read.schema(self.schema).parquet(*[f"{self.path}/{kind}/batch={b}" for b in batches])

    def result(self) -> DataFrame:
        return self._read("closure", self.batches)

    def __call__(self, batch: DataFrame, number: int) -> None:
        """One micro-batch of edges (s, o), for foreachBatch."""
        before = [b for b in self.batches if b != number]
        known = self._read("closure", before)
        new = batch.select("s", "o").distinct().join(known, ["s", "o"], "left_anti")
        work = f"{self.path}/work/batch={number}"
        new.write.mode("overwrite").parquet(f"{work}/0")
        steps = [f"{work}/0"]
        delta = self.spark.read.schema(self.schema).parquet(steps[0])
        for k in range(1, self.max_rounds):
            if delta.limit(1).count() == 0:
                break
            whole = known.unionByName(self.spark.read.schema(self.schema).parquet(*steps))
            a = delta.alias("a").join(whole.alias("b"), F.col("a.o") == F.col("b.s")).select(F.col("a.s").alias("s"), F.col("b.o").alias("o"))
            b = whole.alias("b").join(delta.alias("a"), F.col("b.o") == F.col("a.s")).select(F.col("b.s").alias("s"), F.col("a.o").alias("o"))
            found = a.unionByName(b).distinct().join(whole, ["s", "o"], "left_anti")
            found.write.mode("overwrite").parquet(f"{work}/{k}")
            steps.append(f"{work}/{k}")
            delta = self.spark.read.schema(self.schema).parquet(steps[-1])
        self.spark.read.schema(self.schema).parquet(*steps).write.mode("overwrite").parquet(f"{self.path}/closure/batch={number}")
        if number not in self.batches:
            self.batches.append(number)

    def follow(self, edges: DataFrame, checkpoint: str, **trigger):
        """Start following a stream of edges."""
        trigger = trigger or {"availableNow": True}
        return edges.writeStream.foreachBatch(self).option("checkpointLocation", checkpoint).trigger(**trigger).start()


def replayed_closure(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reply edges written as four files and followed as a stream: the closure equals that of all edges."""
    edges = tables_graph(spark, sf_dir).view("ex:repliesTo").df
    folder = new_path(spark, "edges")
    for k in range(4):
        edges.where(F.pmod(F.col("s"), F.lit(4)) == k).coalesce(1).write.mode("append").parquet(folder)
    closure = IncrementalClosure(spark)
    stream = spark.readStream.schema("s bigint, o bigint").option("maxFilesPerTrigger", 1).parquet(folder)
    query = closure.follow(stream, new_path(spark, "progress"))
    query.awaitTermination()
    return closure.result().select(F.col("s").alias("turn"), F.col("o").alias("ancestor"))


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of users' events with gaps of at most half an hour."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    w = e.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.min("ts").alias("first"))
    return w.select("user_id", F.col("first").cast("timestamp_ntz").alias("first"), "n")


def session_stream(events: DataFrame, late: str = "1 hour", gap: str = "30 minutes") -> DataFrame:
    """The same over a stream, late events dropped behind the watermark."""
    e = events.withWatermark("ts", late)
    return e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def factor_windows(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Counts of each kind of event in tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def symptomatic_after_exposure(symptoms: DataFrame, exposures: DataFrame, days: int = 14, late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: a symptom within so many days after an exposure of the same user."""
    s = symptoms.select(F.col("user_id"), F.col("ts").alias("symptom_ts")).withWatermark("symptom_ts", late)
    e = exposures.select(F.col("user_id").alias("exposed_id"), F.col("ts").alias("exposure_ts")).withWatermark("exposure_ts", late)
    return s.join(e, F.expr(f"user_id = exposed_id and symptom_ts >= exposure_ts and symptom_ts <= exposure_ts + interval {days} days"))


SESSIONS_SQL = """
with e as (select user_id, ts, lag(ts) over (partition by user_id order by ts) as before from events),
m as (select user_id, ts, sum(case when before is null or ts >= before + interval 30 minutes then 1 else 0 end) over (partition by user_id order by ts rows unbounded preceding) as g from e)
select user_id, min(ts) as "first", count(*) as n from m group by user_id, g
"""


STATE = "exposed timestamp, symptom timestamp, tested boolean"


def patient_updates(events: DataFrame, days: int = 14) -> DataFrame:
    """Per-patient screening state over a stream of (user_id, kind, ts), kind being exposure, symptom or tested.

    A custom stateful operator: the latest exposure and symptom and whether a test
    was seen are kept for each user; a row comes out whenever the decision changes.
    Late events only ever add to the state, so replays end in the same decisions.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        exposed, symptom, tested = state.get if state.exists else (None, None, False)

        def positive() -> bool:
            return bool(not tested and exposed is not None and symptom is not None and pd.Timedelta(0) <= symptom - exposed <= pd.Timedelta(days=days))

        before = positive()
        for f in frames:
            for kind, ts in zip(f["kind"], f["ts"], strict=True):
                if kind == "exposure":
                    exposed = ts if exposed is None else max(exposed, ts)
                elif kind == "symptom":
                    symptom = ts if symptom is None else max(symptom, ts)
                elif kind == "tested":
                    tested = True
        state.update((exposed, symptom, tested))
        if positive() != before:
            yield pd.DataFrame({"user_id": [key[0]], "positive": [positive()]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id bigint, positive boolean", STATE, "update", GroupStateTimeout.NoTimeout)
