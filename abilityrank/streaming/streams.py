"""Answers that arrive over time: windows as items, sessions, late rows, warm-started rankings."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.draws import micros
from ..model import Opts
from ..operators.spectral import diffprop_power
from ..plans.storage import shared_root, written

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def stream_events(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", files).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def _folder(spark: SparkSession, d: str) -> str:
    """The events in a folder of their own: file streams read folders."""
    path = f"{shared_root(spark)}/events-{uuid.uuid4().hex[:12]}"
    spark.read.parquet(f"{d}/events.parquet").repartition(2).write.parquet(path)
    return path


def run_to_end(df: DataFrame, mode: str, schema: str) -> DataFrame:
    """All that is there, through the stream, into a table in the shared folder."""
    spark = df.sparkSession
    root = f"{shared_root(spark)}/stream-{uuid.uuid4().hex[:12]}"

    def keep(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/out/epoch={epoch}")

    query = df.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").foreachBatch(keep).trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.option("basePath", f"{root}/out").schema(schema + ", epoch int").parquet(f"{root}/out/epoch=*")
    return out


def final_answers(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Each user's last event of each day, updated as events come."""
    known = events.withWatermark("ts", watermark)
    return known.groupBy(F.window("ts", "1 day").alias("w"), "user_id").agg(F.max_by("event_type", F.struct("ts", "event_id")).alias("option_id")).select("user_id", F.to_date("w.start").cast("string").alias("item_id"), "option_id")


def sliding_counts(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", watermark).groupBy(F.window("ts", "7 days", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.to_date("w.start").cast("string").alias("window_start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n_events")).select("user_id", micros("w.start").alias("start_us"), "n_events")


def deduplicated(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def correct_counts(answers: DataFrame, key: DataFrame) -> DataFrame:
    """Stream-static join: running numbers of correct answers."""
    return answers.join(key.withColumnRenamed("option_id", "right_option"), "item_id").where("option_id = right_option").groupBy("user_id").agg(F.count("*").alias("correct"))


def answered_within(questions: DataFrame, replies: DataFrame, minutes: int = 60) -> DataFrame:
    """Stream-stream interval join: a reply by the same user within so many minutes of a question."""
    q = questions.withWatermark("ts", "1 hour").select(F.col("user_id").alias("q_user"), F.col("ts").alias("q_ts"), F.col("event_id").alias("question"))
    r = replies.withWatermark("ts", "1 hour").select(F.col("user_id").alias("r_user"), F.col("ts").alias("r_ts"), F.col("event_id").alias("reply"))
    return q.join(r, F.expr(f"q_user = r_user AND r_ts > q_ts AND r_ts <= q_ts + INTERVAL {minutes} MINUTES"))


def last_answers_stateful(answers: DataFrame) -> DataFrame:
    """user_id, item_id (string), ts, option_id: the last answer of each user and item, kept as state."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, batches, state):
        best = tuple(state.get) if state.exists else (None, None)
        for pdf in batches:
            top = pdf.sort_values("ts").iloc[-1]
            us = int(top["ts"].value // 1000)
            if best[0] is None or us >= best[0]:
                best = (us, top["option_id"])
        state.update(best)
        yield pd.DataFrame({"user_id": [key[0]], "item_id": [key[1]], "option_id": [best[1]]})

    return answers.groupBy("user_id", "item_id").applyInPandasWithState(update, "user_id long, item_id string, option_id string", "us long, option_id string", "update", GroupStateTimeout.NoTimeout)


class Refresher:
    """foreachBatch sink: merges changed answers and re-ranks from the scores of the version before."""

    def __init__(self, opts: Opts = Opts(rounds=5, path="sql")):
        self.opts, self.answers, self.scores, self.versions = opts, None, None, 0

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        new = batch.select("user_id", "item_id", "option_id")
        if self.answers is not None:
            new = self.answers.join(new, ["user_id", "item_id"], "left_anti").unionByName(new)
        self.answers = written(new, "answers")
        start = None
        if self.scores is not None:
            start = self.answers.select("user_id").distinct().join(self.scores, "user_id", "left").select("user_id", F.coalesce("score", F.lit(0.0)).alias("score"))
        self.scores = written(diffprop_power(self.answers, self.opts, init=start).scores, "ranking")
        self.versions += 1
