"""The append-only log of attempted batches, and stores that replay it.

A log row is an operation with its shard, transaction time and its batch's outcome. Writing decides outcomes once; replaying trusts
them, so a replay is one fold without rounds, and failed batches are skipped as they were at first.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import Protocol

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.canon import store_digest
from .clock import log_shard, stamp_transaction_time
from .fold import decide_outcomes, fold_versions

OPS = "batch_id long, seq int, op string, ident string, vt_s long, vt_e long, w double, phys long"


def operation(batch_id: int, op: str, ident: str, vt_s: int, vt_e: int | None = None, w: float | None = None, phys: int | None = None, seq: int = 0) -> tuple:
    from ..functions.timeaxis import OPEN_END

    return (batch_id, seq, op, ident, vt_s, OPEN_END if vt_e is None else vt_e, w, batch_id if phys is None else phys)


def assert_fact(batch_id: int, ident: str, vt_s: int, vt_e: int, w: float, **more) -> tuple:
    return operation(batch_id, "assert", ident, vt_s, vt_e, w, **more)


def retract_fact(batch_id: int, ident: str, at: int, **more) -> tuple:
    return operation(batch_id, "retract", ident, at, **more)


def correct_fact(batch_id: int, ident: str, vt_s: int, vt_e: int, w: float, **more) -> tuple:
    return operation(batch_id, "correct", ident, vt_s, vt_e, w, **more)


def operations(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, OPS)


def attempt(ops: DataFrame, shards: int = 1, require_existing: bool = True) -> DataFrame:
    """Log rows of attempted operations: stamped, with every batch's outcome. With one shard, batches may span identities."""
    shard = F.lit(0) if shards == 1 else log_shard("ident", shards)
    stamped = stamp_transaction_time(ops.withColumn("log_shard", shard))
    return stamped.join(decide_outcomes(stamped, require_existing), "batch_id").select("log_shard", "batch_id", "seq", "phys", "tt", "op", "ident", "vt_s", "vt_e", "w", "outcome", "fail_code")


def new_only(batch: DataFrame, log: DataFrame) -> DataFrame:
    """Operations whose batch the log does not hold yet: appending twice changes nothing."""
    return batch.join(log.select("batch_id").distinct(), "batch_id", "left_anti")


class StoreBackend(Protocol):
    """What a store needs; belief semantics lie above it."""

    def append(self, name: str, df: DataFrame) -> None: ...

    def read(self, name: str) -> DataFrame: ...


@dataclass
class FileStore:
    """Tables as files of one format in a folder that all executors reach."""

    spark: SparkSession
    folder: str
    format: str = "parquet"
    partitions: tuple[str, ...] = ()

    def append(self, name: str, df: DataFrame) -> None:
        writer = df.write.mode("append").format(self.format)
        (writer.partitionBy(*self.partitions) if self.partitions else writer).save(f"{self.folder}/{name}")

    def read(self, name: str) -> DataFrame:
        return self.spark.read.format(self.format).load(f"{self.folder}/{name}")


class MemoryStore:
    """Tables as views of the session."""

    def __init__(self, spark: SparkSession):
        self.spark, self.tables = spark, {}

    def append(self, name: str, df: DataFrame) -> None:
        self.tables[name] = self.tables[name].unionByName(df) if name in self.tables else df

    def read(self, name: str) -> DataFrame:
        return self.tables[name]


def replay(log: DataFrame, backend: StoreBackend, name: str = "versions") -> str:
    """Build the versions of a log's committed batches in a backend; returns the store's digest."""
    versions = fold_versions(log.where("outcome = 'committed'"), require_existing=False)
    backend.append(name, versions)
    return store_digest(backend.read(name).select("ident", "vt_s", "vt_e", "tt_s", "tt_e", "w"))


def read_log(backend: StoreBackend, from_tt: int = 0, shards: list[int] | None = None) -> DataFrame:
    log = backend.read("log").where(F.col("tt") >= from_tt)
    return log if shards is None else log.where(F.col("log_shard").isin(shards))


def build_adjacency(edges: DataFrame, name: str, buckets: int = 64, by: str = "src") -> DataFrame:
    """Time-ordered adjacency: a table bucketed by a node and sorted by (node, t, eid), so that frontier joins move the frontier alone."""
    edges.write.mode("overwrite").bucketBy(buckets, by).sortBy(by, "t", "eid").saveAsTable(name)
    return edges.sparkSession.table(name)


def packed_adjacency(edges: DataFrame, slice_us: int) -> DataFrame:
    """One row for each node and slice of time with its out-edges in order."""
    sliced = edges.withColumn("slice", F.floor(F.col("t") / F.lit(slice_us)).cast("long"))
    return sliced.groupBy("src", "slice").agg(F.sort_array(F.collect_list(F.struct("t", "eid", "dst", "w"))).alias("out"))
