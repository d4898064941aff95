"""Streams of edge events and belief operations.

Late data is belief revision: what arrives behind the watermark goes into a correction batch with a transaction time of its own
instead of changing what was told before.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


EDGE = "eid long, src long, dst long, t long, w double, etype string"


def edge_stream(spark: SparkSession, folder: str, files_a_batch: int = 1) -> DataFrame:
    """Edge events from a folder that Parquet files arrive in, with event time ``ts``."""
    return spark.readStream.schema(EDGE).option("maxFilesPerTrigger", files_a_batch).parquet(folder).withColumn("ts", F.timestamp_micros("t"))


def deduplicated(stream: DataFrame, delay: str = "1 day") -> DataFrame:
    """Each eid once, as long as copies come within the watermark."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["eid"])


def windowed_counts(stream: DataFrame, width: str = "1 day", slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """(bucket_s, edges) of tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.withWatermark("ts", delay).groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("edges")).select(F.unix_micros("w.start").alias("bucket"), "edges")


def user_sessions(stream: DataFrame, gap: str = "2 hours", delay: str = "1 day") -> DataFrame:
    """(src, start, end, edges): stretches of a user's activity without a gap."""
    return stream.withWatermark("ts", delay).groupBy("src", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("edges")).select("src", F.unix_micros("w.start").alias("start"), F.unix_micros("w.end").alias("end"), "edges")


def reply_pairs(stream_a: DataFrame, stream_b: DataFrame, within: str = "1 hour", delay: str = "1 day") -> DataFrame:
    """Stream-stream join: an edge of ``b`` that answers one of ``a`` in reverse within a time."""
    a = stream_a.withWatermark("ts", delay).select(F.col("eid").alias("a_eid"), F.col("src").alias("x"), F.col("dst").alias("y"), F.col("ts").alias("a_ts"))
    b = stream_b.withWatermark("ts", delay).select(F.col("eid").alias("b_eid"), F.col("src").alias("p"), F.col("dst").alias("q"), F.col("ts").alias("b_ts"))
    return a.join(b, F.expr(f"x = q AND y = p AND b_ts > a_ts AND b_ts <= a_ts + INTERVAL {within}")).select("a_eid", "b_eid")


def burst_stream(counts: DataFrame, lookback: int = 8, threshold: float = 2.0) -> DataFrame:
    """Bursts by z-score as buckets come: ``counts(key, bucket, value)``; state is a key's last ``lookback`` values.

    Buckets of a key must come in order, as closed windows in append mode do.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        (past,) = state.get if state.exists else ([],)
        past, rows = list(past), []
        for frame in frames:
            for bucket, value in sorted(zip(frame["bucket"], frame["value"])):
                score = None
                if len(past) == lookback:
                    mean = sum(past) / lookback
                    spread = (sum((x - mean) ** 2 for x in past) / lookback) ** 0.5
                    score = round((value - mean) / spread, 9) if round(spread, 9) > 0 else None
                rows.append((key[0], bucket, value, score, score is not None and score >= threshold))
                past = [*past, float(value)][-lookback:]
        state.update((past,))
        yield pd.DataFrame(rows, columns=["key", "bucket", "value", "score", "is_burst"])

    return counts.groupBy("key").applyInPandasWithState(step, "key string, bucket long, value double, score double, is_burst boolean", "past array<double>", "append", GroupStateTimeout.NoTimeout)


class EpochTable:
    """A table in a folder of the shared store, written by epoch: writing an epoch again replaces it, so a repeated micro-batch changes nothing."""

    def __init__(self, spark: SparkSession, folder: str, schema: str):
        self.spark, self.folder, self.schema = spark, folder, schema

    def write(self, df: DataFrame, epoch: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.folder}/epoch={epoch}")

    def epochs(self) -> list[int]:
        """The epochs written so far, by Spark's own listing of the folder."""
        context = self.spark.sparkContext
        path = context._jvm.org.apache.hadoop.fs.Path(self.folder)
        files = path.getFileSystem(context._jsc.hadoopConfiguration())
        names = [s.getPath().getName() for s in files.listStatus(path)] if files.exists(path) else []
        # without the mark of a finished write an epoch does not count
        done = [n for n in names if n.startswith("epoch=") and files.exists(context._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{n}/_SUCCESS"))]
        return sorted(int(n[6:]) for n in done)

    def read(self, epochs: list[int]) -> DataFrame:
        if not epochs:
            return self.spark.createDataFrame([], self.schema)
        return self.spark.read.schema(self.schema).parquet(*[f"{self.folder}/epoch={e}" for e in epochs])


class BeliefIngest:
    """``foreachBatch`` writer of a belief log: idempotent by batch id, transaction times go on from the last one, and each batch commits or fails.

    What is believed now is kept beside the log, one table an epoch, so outcomes are decided without the log's history: the pieces
    believed of the identities at hand stand before the new operations as assertions at their own times. Of the log, the batch ids and
    the greatest time are read. Batches of an epoch may span identities.
    """

    BELIEVED = "ident string, vt_s long, vt_e long, tt_s long, w double"
    LOG = "log_shard int, batch_id long, seq int, phys long, tt long, op string, ident string, vt_s long, vt_e long, w double, outcome string, fail_code string"
    HELD = -(1 << 62)  # stands for the batch of what is believed; no batch has it

    def __init__(self, spark: SparkSession, folder: str, require_existing: bool = True):
        self.spark, self.require_existing = spark, require_existing
        self.rows, self.believed = EpochTable(spark, f"{folder}/log", self.LOG), EpochTable(spark, f"{folder}/believed", self.BELIEVED)

    def log(self) -> DataFrame:
        return self.rows.read(self.rows.epochs())

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        from ..lineage import cut
        from ..substrate.clock import log_shard, stamp_transaction_time
        from ..substrate.fold import decide_outcomes, fold_identities
        from ..substrate.log import new_only

        held = self.rows.read([e for e in self.rows.epochs() if e < epoch])
        believed = self.believed.read([e for e in self.believed.epochs() if e < epoch][-1:])
        high = held.agg(F.max("tt")).first()[0] or 0
        stamped = cut(stamp_transaction_time(new_only(batch, held).withColumn("log_shard", log_shard("ident")), high_water=high))
        touched = stamped.select("ident").distinct()
        before = believed.join(touched, "ident", "left_semi").select(
            F.lit(self.HELD).alias("batch_id"), F.lit(0).alias("seq"), F.lit("assert").alias("op"), "ident", "vt_s", "vt_e", "w", F.col("tt_s").alias("phys"), F.col("tt_s").alias("tt")
        )
        both = before.unionByName(stamped.select(*before.columns))
        outcomes = cut(decide_outcomes(both, self.require_existing).where(F.col("batch_id") != self.HELD))
        self.rows.write(stamped.join(outcomes, "batch_id").selectExpr("int(log_shard)", "batch_id", "seq", "phys", "tt", "op", "ident", "vt_s", "vt_e", "w", "outcome", "fail_code"), epoch)
        committed = before.unionByName(stamped.join(outcomes.where("outcome = 'committed'").select("batch_id"), "batch_id", "left_semi").select(*before.columns))
        live = fold_identities(committed, False).select("ident", F.explode("state.live").alias("p")).select("ident", "p.vt_s", "p.vt_e", "p.tt_s", "p.w")
        self.believed.write(believed.join(touched, "ident", "left_anti").select("ident", "vt_s", "vt_e", "tt_s", "w").unionByName(live), epoch)


def route_late(batch: DataFrame, watermark: int, tt: int) -> tuple[DataFrame, DataFrame]:
    """(on time, correction batch) of a batch: late events are believed from ``tt`` on."""
    late = F.col("t") < watermark
    return batch.where(~late), batch.where(late).withColumn("tt", F.lit(tt).cast("long"))


class ArrivalState:
    """Incremental earliest arrival: each batch of time-ordered edges extends (node, first, latest), which is all that is kept.

    The state lies in a folder, one table an epoch, so a restarted stream goes on from the epoch before the one it repeats.
    """

    SCHEMA = "node long, first long, latest long"

    def __init__(self, spark: SparkSession, source: int, t_from: int, max_wait: int | None = None, folder: str | None = None):
        from ..lineage import shared_folder

        self.spark, self.source, self.t_from, self.max_wait = spark, source, t_from, max_wait
        self.held = EpochTable(spark, folder or f"{shared_folder(spark)}/arrivals-{uuid.uuid4().hex}", self.SCHEMA)

    @property
    def state(self) -> DataFrame:
        return self._at(self.held.epochs())

    def _at(self, epochs: list[int]) -> DataFrame:
        return self.held.read(epochs[-1:]) if epochs else self.spark.createDataFrame([(self.source, self.t_from, self.t_from)], self.SCHEMA)

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        from pyspark.sql import Window

        from ..lineage import cut

        part = batch.where("src != dst").select("src", "dst", "t")
        before = self._at([e for e in self.held.epochs() if e < epoch])
        arrivals = before.select("node", F.col("latest").alias("at"))
        while True:
            both = part.select(F.col("src").alias("node"), F.col("t").alias("at"), "dst", F.lit(None).cast("long").alias("arr")).unionByName(arrivals.select("node", "at", F.lit(None).cast("long").alias("dst"), F.col("at").alias("arr")))
            last = F.last("arr", ignorenulls=True).over(Window.partitionBy("node").orderBy("at").rangeBetween(Window.unboundedPreceding, -1))
            live = both.withColumn("last", last).where("dst is not null and last is not null")
            if self.max_wait is not None:
                live = live.where((F.col("at") - F.col("last") <= self.max_wait) | (F.col("node") == self.source))
            new = cut(live.select(F.col("dst").alias("node"), "at").distinct().join(arrivals, ["node", "at"], "left_anti"))
            if new.isEmpty():
                break
            arrivals = cut(arrivals.unionByName(new))
        merged = arrivals.groupBy("node").agg(F.min("at").alias("f"), F.max("at").alias("l"))
        self.held.write(merged.join(before, "node", "left").select("node", F.least("first", "f").alias("first"), F.greatest("latest", "l").alias("latest")), epoch)


def withdrawn_notes(corrections: DataFrame, notes: DataFrame) -> DataFrame:
    """Stream-static join: ids of notes whose window a streamed correction overlaps."""
    c = corrections.where("op = 'correct'")
    hit = (F.col("vt_s") < F.col("window_e")) & (F.col("vt_e") > F.col("window_s")) & (F.col("tt") > F.col("created_tt"))
    return c.join(notes.select("note_id", "window_s", "window_e", "created_tt"), hit).select("note_id", "tt")


def run_to_end(stream: DataFrame, sink, checkpoint: str, mode: str = "append"):
    """Process what is there and stop; ``sink`` is a function of (batch, epoch) or a Parquet folder."""
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    started = writer.foreachBatch(sink).start() if callable(sink) else writer.format("parquet").option("path", sink).start()
    started.awaitTermination()
    return started


