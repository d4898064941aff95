"""Corpora: temporal graphs and belief logs derived from the given tables.

Edge events are (eid, src, dst, t, w, etype); belief operations are (batch_id, seq, op, ident, vt_s, vt_e, w, phys) with op one
of assert, correct, retract.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.timeaxis import DAY, OPEN_END, day_floor, micros
from .tables import load_table

COMMUNITY = 15


def message_edges(spark: SparkSession, sf_dir: str, self_loops: bool = False) -> DataFrame:
    """Message graph: every event links its user to one of the same community of 15, signups to anyone."""
    events = load_table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value", "props")
    users = events.agg((F.max("user_id") + 1).alias("n")).select("n").scalar()
    src, k = F.col("user_id"), F.get_json_object("props", "$.k").cast("long")
    far = (src * 17 + k) % users
    near = (src - src % COMMUNITY + k % COMMUNITY) % users
    edges = events.select(
        F.col("event_id").alias("eid"), src.alias("src"), F.when(F.col("event_type") == "signup", far).otherwise(near).alias("dst"),
        micros("ts").alias("t"), F.col("value").alias("w"), F.col("event_type").alias("etype"),
    )
    return edges if self_loops else edges.where("src != dst")


def row_number_hash(*columns: Column) -> Column:
    """60 bits of the md5 of whole-numbered or string columns, joined by bars: an edge id from a whole row."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in columns]).cast("binary")), 1, 15), 16, 10).cast("long")


def trade_edges(spark: SparkSession, sf_dir: str, by: str = "nation") -> DataFrame:
    """Trade graph: each line item links its supplier to its customer, or their nations; ids come from the whole row."""
    items = load_table(spark, sf_dir, "lineitem")
    orders = load_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    customers = load_table(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    suppliers = load_table(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    cents = lambda c: F.round(F.col(c) * 100).cast("long")
    eid = row_number_hash(
        F.col("l_orderkey"), F.col("l_linenumber"), F.col("l_partkey"), F.col("l_suppkey"), cents("l_quantity"), cents("l_extendedprice"), cents("l_discount"), cents("l_tax"),
        F.col("l_returnflag"), F.col("l_linestatus"), micros("l_shipdate"),
    )
    ends = ("s_nationkey", "c_nationkey") if by == "nation" else ("l_suppkey", "o_custkey")
    # ids are made before the joins, which then carry few columns, and items, the most rows, are dealt out by their orders once
    sent = items.select("l_orderkey", "l_suppkey", eid.alias("eid"), micros("l_shipdate").alias("t"), F.col("l_quantity").alias("w"), F.col("l_returnflag").alias("etype")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    taken = orders.join(customers, F.col("o_custkey") == F.col("c_custkey"))
    return sent.join(taken, F.col("l_orderkey") == F.col("o_orderkey")).select("eid", F.col(ends[0]).cast("long").alias("src"), F.col(ends[1]).cast("long").alias("dst"), "t", "w", "etype")


def user_beliefs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Belief log on users: one operation for each event, by its type."""
    events = load_table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value")
    at, kind = micros("ts"), F.col("event_type")
    return events.select(
        F.col("event_id").alias("batch_id"), F.lit(0).alias("seq"),
        F.when(kind == "purchase", "correct").when(kind == "error", "retract").otherwise("assert").alias("op"),
        F.col("user_id").cast("string").alias("ident"),
        F.when(kind.isin("click", "view"), day_floor(at)).when(kind == "purchase", at - 3 * DAY).otherwise(at).alias("vt_s"),
        F.when(kind.isin("click", "view"), day_floor(at) + 10 * DAY).when(kind == "purchase", at - DAY).otherwise(F.lit(OPEN_END)).alias("vt_e"),
        F.when(kind != "error", F.col("value")).alias("w"), at.alias("phys"),
    )


def order_beliefs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Belief log on orders: the status from the order date on; every returned item corrects thirty days from its shipping."""
    orders = load_table(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus", "o_totalprice", "o_orderdate")
    items = load_table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_extendedprice", "l_shipdate", "l_returnflag").where("l_returnflag = 'R'")
    begun, shipped = micros("o_orderdate"), micros("l_shipdate")
    asserted = orders.select(F.lit("assert").alias("op"), F.col("o_orderkey").alias("ident"), begun.alias("vt_s"), F.lit(OPEN_END).alias("vt_e"), F.col("o_totalprice").alias("w"), begun.alias("phys"))
    corrected = items.select(F.lit("correct").alias("op"), F.col("l_orderkey").alias("ident"), shipped.alias("vt_s"), (shipped + 30 * DAY).alias("vt_e"), F.col("l_extendedprice").alias("w"), shipped.alias("phys"))
    both = asserted.unionByName(corrected)
    order = Window.partitionBy("ident").orderBy("phys", "op", "w", "vt_s")
    return both.withColumn("n", F.row_number().over(order)).select((F.col("ident") * 1000 + F.col("n")).alias("batch_id"), F.lit(0).alias("seq"), "op", F.col("ident").cast("string").alias("ident"), "vt_s", "vt_e", "w", "phys")


def label_beliefs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Belief log on documents: quality 1 is assumed at first, then labels correct it."""
    docs, labels = load_table(spark, sf_dir, "documents", "doc_id"), load_table(spark, sf_dir, "labels", "doc_id", "quality")
    common = lambda df, op, at, w: df.select((F.col("doc_id") * 2 + (at - 1)).alias("batch_id"), F.lit(0).alias("seq"), F.lit(op).alias("op"), F.col("doc_id").cast("string").alias("ident"), F.lit(0).cast("long").alias("vt_s"), F.lit(OPEN_END).alias("vt_e"), w.cast("double").alias("w"), F.lit(at).cast("long").alias("phys"))
    return common(docs, "assert", 1, F.lit(1)).unionByName(common(labels, "correct", 2, F.col("quality")))


def replies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reply graph of conversations: consecutive turns, nodes are conversation and role."""
    turns = load_table(spark, sf_dir, "conversations", "conv_id", "turn", "role")
    after = Window.partitionBy("conv_id").orderBy("turn", "role")
    linked = turns.withColumn("next_role", F.lead("role").over(after)).where("next_role is not null")
    node = lambda role: F.concat_ws(":", F.col("conv_id").cast("string"), F.col(role))
    return linked.select("conv_id", "turn", node("role").alias("src"), node("next_role").alias("dst"), F.col("turn").cast("long").alias("t"))


def session_intervals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Intervals (id, src, kind, i_s, i_e): an event's activity lasts its value in minutes, at least a microsecond."""
    events = load_table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value")
    start = micros("ts")
    length = F.greatest(F.lit(1).cast("long"), F.floor(F.col("value") * 60_000_000).cast("long"))
    return events.select(F.col("event_id").alias("id"), F.col("user_id").alias("src"), F.col("event_type").alias("kind"), start.alias("i_s"), (start + length).alias("i_e"))


#: Planted structures: (kind, [(offset in seconds, from, to), …]) on nodes that no other event uses.
PLANTS = (
    ("cyclic", [(0, 0, 1), (60, 1, 2), (120, 2, 0)]),
    ("feed_forward", [(0, 0, 1), (60, 1, 2), (120, 0, 2)]),
    ("ping_pong", [(0, 0, 1), (30, 1, 0)]),
    ("path", [(0, 0, 1), (600, 1, 2), (1200, 2, 3)]),
    ("burst", [(i, 0, 1 + i % 5) for i in range(60)]),
)


def planted(spark: SparkSession, base: DataFrame, copies: int = 3, first_node: int = 10_000_000) -> tuple[DataFrame, DataFrame]:
    """(edges with planted ones of negative eid, manifest (pattern_id, kind, nodes, eids)). Deterministic."""
    start = base.agg(F.min("t")).first()[0] or 0
    rows, manifest, eid = [], [], -1
    for c in range(copies):
        for p, (kind, steps) in enumerate(PLANTS):
            node = first_node + (c * len(PLANTS) + p) * 100
            eids = []
            for at, a, b in steps:
                rows.append((eid, node + a, node + b, start + (c + 1) * DAY + at * 1_000_000, 1.0, "planted"))
                eids.append(eid)
                eid -= 1
            manifest.append((f"{kind}-{c}", kind, sorted({node + x for s in steps for x in s[1:]}), eids))
    plants = spark.createDataFrame(rows, "eid long, src long, dst long, t long, w double, etype string")
    return base.unionByName(plants), spark.createDataFrame(manifest, "pattern_id string, kind string, nodes array<long>, eids array<long>")


def scale_store(spark: SparkSession, edges: int, nodes: int | None = None, days: int = 365, seed: int = 1) -> DataFrame:
    """Generated edge events of any number, evenly over time, nodes skewed by a square law."""
    nodes = nodes or max(2, edges // 20)
    unit = lambda salt: F.pmod(F.xxhash64("id", F.lit(seed * 100 + salt)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    span = days * DAY
    return spark.range(edges).select(
        F.col("id").alias("eid"), F.floor(unit(1) * unit(2) * nodes).cast("long").alias("src"), F.floor(unit(3) * nodes).cast("long").alias("dst"),
        (F.lit(1_704_067_200_000_000) + F.floor(unit(4) * span).cast("long")).alias("t"), F.round(unit(5) * 100, 2).alias("w"), F.lit("e").alias("etype"),
    ).where("src != dst")
