"""Facts that arrive continuously: reading, checking against the graph, rates, sessions, running verdicts."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.granule import Interval, instant, micros
from ..plans.kg import KnowledgeGraph
from ..sources.tables import shared_root, written

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, name: str = "events.parquet", files_per_trigger: int | None = None) -> DataFrame:
    """Event files of a folder as a stream; `at` is the arrival time that watermarks run on."""
    r = spark.readStream.schema(EVENTS).option("pathGlobFilter", name)
    if files_per_trigger:
        r = r.option("maxFilesPerTrigger", files_per_trigger)
    return r.parquet(folder).withColumn("at", F.col("ts").cast("timestamp"))


def event_facts(events: DataFrame) -> DataFrame:
    """Instant facts (user, event type, k); `at` stays for watermarks."""
    k = F.from_json("props", "k long")["k"]
    g = instant(micros(F.col("ts")))
    return events.where(k.isNotNull()).select(
        F.concat_ws(":", F.lit("K10"), F.col("event_id").cast("string")).alias("fact_id"), F.concat_ws(":", F.lit("U"), F.col("user_id").cast("string")).alias("s"),
        F.col("event_type").alias("p"), F.concat_ws(":", F.lit("K"), k.cast("string")).alias("o"), F.lit("res").alias("o_kind"), *Interval(g, g).named(),
        F.lit(True).alias("is_temporal"), F.lit("events").alias("src"), "at",
    )


def _folder(spark: SparkSession) -> str:
    return f"{shared_root(spark)}/streams/{uuid.uuid4().hex}"


def drain(stream: DataFrame, mode: str = "append", batch: Callable[[DataFrame, int], None] | None = None, schema=None) -> DataFrame:
    """Run a stream over all that is there now, and read what it wrote.

    Update and complete modes are written batch by batch; the last batch's row of a key is the caller's to choose by `batch_id`.
    """
    spark = stream.sparkSession
    base = _folder(spark)
    out = f"{base}/out"
    w = stream.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
    if batch is not None:
        w = w.foreachBatch(batch)
    elif mode == "append":
        w = w.format("parquet").option("path", out).outputMode("append")
    else:
        # a batch that is run again replaces what it wrote
        w = w.outputMode(mode).foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(f"{out}/batch_id={i}"))
    w.start().awaitTermination()
    if batch is not None:
        return None
    fields = stream.schema if mode == "append" else stream.withColumn("batch_id", F.lit(0).cast("int")).schema
    if mode != "append":
        spark.createDataFrame([], stream.schema).write.parquet(f"{out}/batch_id=-1")
    return spark.read.schema(fields).parquet(out).select(*fields.names)


def stream_conflicts(stream: DataFrame, kg: KnowledgeGraph, rules: DataFrame) -> DataFrame:
    """Conflicts of arriving facts with the graph, found batch by batch and collected in a table."""
    from ..operators.detect import check_new_facts

    spark = kg.facts.sparkSession
    out = f"{_folder(spark)}/conflicts"

    def one(df: DataFrame, i: int) -> None:
        fresh = written(df.drop("at"), "batch")
        # a batch that is run again replaces what it wrote
        check_new_facts(kg, fresh, rules).write.mode("overwrite").parquet(f"{out}/batch_id={i}")

    drain(stream, batch=one)
    fields = "new_fact string, cid string, x string, fact1 string, fact2 string, link_fact string, verdict tinyint"
    spark.createDataFrame([], fields).write.parquet(f"{out}/batch_id=-1")
    return spark.read.schema(f"{fields}, batch_id int").parquet(out).drop("batch_id")


def stream_stream_conflicts(first: DataFrame, second: DataFrame, delay: str = "1 hour", horizon: str = "1 hour") -> DataFrame:
    """Pairs of arriving facts of one subject, the second no later than the horizon after the first; state is bounded by watermarks."""
    a = first.withWatermark("at", delay).select(F.col("s").alias("x"), F.col("p").alias("p1"), F.col("o").alias("o1"), F.col("fact_id").alias("fact1"), F.col("at").alias("at1"))
    b = second.withWatermark("at", delay).select(F.col("s").alias("x2"), F.col("p").alias("p2"), F.col("o").alias("o2"), F.col("fact_id").alias("fact2"), F.col("at").alias("at2"))
    on = F.expr(f"x = x2 and at2 > at1 and at2 <= at1 + interval {horizon}")
    return a.join(b, on).select("x", "p1", "o1", "fact1", "p2", "o2", "fact2", "at1", "at2")


def rates(facts: DataFrame, width: str = "1 day", slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """Facts per property and time window; late ones beyond the watermark don't count."""
    w = F.window("at", width, slide) if slide else F.window("at", width)
    return facts.withWatermark("at", delay).groupBy(w.alias("w"), "p").agg(F.count("*").alias("n")).select(F.col("w.start").alias("lo"), F.col("w.end").alias("hi"), "p", "n")


def session_facts(events: DataFrame, gap: str = "6 hours", delay: str = "1 day") -> DataFrame:
    """Interval facts from runs of point events of a user and type."""
    w = F.session_window("at", gap)
    return events.withWatermark("at", delay).groupBy("user_id", "event_type", w.alias("w")).agg(F.min("at").alias("lo"), F.max("at").alias("hi"), F.count("*").alias("n")).select("user_id", "event_type", "lo", "hi", "n")


def without_repeats(facts: DataFrame, delay: str = "1 day") -> DataFrame:
    return facts.withWatermark("at", delay).dropDuplicatesWithinWatermark(["fact_id"])


def running_verdicts(facts: DataFrame, first: str, second: str) -> DataFrame:
    """Subjects as they turn negative for before(first, second), both of instant facts: emitted once, with the fact that did it.

    State per subject: least time of `second` seen, greatest of `first` seen, and whether it has been reported.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        late, early, told = state.get if state.exists else (None, None, False)
        hit = None
        for f in frames:
            for r in f.sort_values(["ts_lo", "fact_id"]).itertuples():
                if r.p == first:
                    late = r.ts_lo if late is None else max(late, r.ts_lo)
                if r.p == second:
                    early = r.ts_lo if early is None else min(early, r.ts_lo)
                if hit is None and late is not None and early is not None and late > early:
                    hit = r.fact_id
        if hit is not None and not told:
            told = True
            yield pd.DataFrame({"x": [key[0]], "fact_id": [hit]})
        state.update((late, early, told))

    used = facts.where(F.col("p").isin(first, second)).select("s", "p", "ts_lo", "fact_id")
    return used.groupBy("s").applyInPandasWithState(step, "x string, fact_id string", "late long, early long, told boolean", "append", GroupStateTimeout.NoTimeout)
