"""Queries over the given tables, one for each method, variant, baseline, measure or workload, and their DuckDB equivalents.

Each query reads whole tables. Instants and windows are fixed parameters of the corpora, stated below.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.text import approx_tokens, fence
from .functions.timeaxis import ALLEN, DAY, HOUR, WEEK
from .operators import compute as arithmetic
from .operators import diff, evolution, history, intervals, motifs, neighbourhood, paths, reach, resolve, selection, series
from .sources import corpora
from .sources.tables import load_table
from .substrate.clock import log_shard, stamp_transaction_time
from .substrate.log import attempt
from .substrate.fold import fold_versions
from .substrate.segments import belief_at, segment_versions
from .substrate.snapshots import overlap_violations, snapshot

T0 = 1_704_067_200_000_000  # 2024-01-01
VALID_AT, PINNED = T0 + 11 * DAY, T0 + 12 * DAY  # the probe of user beliefs: 2024-01-12, known by 2024-01-13
TTL = 7 * DAY  # how long an edge event counts as live in a snapshot

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return keep


# ---- corpora ----------------------------------------------------------------------------------------------------------------------

C1 = """
c1 AS (
  SELECT event_id AS eid, user_id AS src,
    CASE WHEN event_type = 'signup' THEN (user_id * 17 + k) % n ELSE (user_id - user_id % 15 + k % 15) % n END AS dst,
    epoch_us(ts) AS t, value AS w, event_type AS etype
  FROM (SELECT *, CAST(json_extract(props, '$.k') AS BIGINT) AS k, (SELECT max(user_id) + 1 FROM events) AS n FROM events) e),
g AS (SELECT * FROM c1 WHERE src != dst)"""
C2 = """
c2 AS (
  SELECT CAST('0x' || substr(md5(concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_quantity * 100) AS BIGINT), CAST(round(l_extendedprice * 100) AS BIGINT),
      CAST(round(l_discount * 100) AS BIGINT), CAST(round(l_tax * 100) AS BIGINT), l_returnflag, l_linestatus, epoch_us(l_shipdate))), 1, 15) AS BIGINT) AS eid,
    CAST(s_nationkey AS BIGINT) AS src, CAST(c_nationkey AS BIGINT) AS dst, epoch_us(l_shipdate) AS t, l_quantity AS w, l_returnflag AS etype
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey)"""
OPEN = str(1 << 62)
C3 = f"""
c3 AS (
  SELECT event_id AS batch_id, CAST(user_id AS VARCHAR) AS ident, epoch_us(ts) AS tt,
    CASE event_type WHEN 'purchase' THEN 'correct' WHEN 'error' THEN 'retract' ELSE 'assert' END AS op,
    CASE WHEN event_type IN ('click', 'view') THEN epoch_us(ts) - epoch_us(ts) % {DAY} WHEN event_type = 'purchase' THEN epoch_us(ts) - {3 * DAY} ELSE epoch_us(ts) END AS vt_s,
    CASE WHEN event_type IN ('click', 'view') THEN epoch_us(ts) - epoch_us(ts) % {DAY} + {10 * DAY} WHEN event_type = 'purchase' THEN epoch_us(ts) - {DAY} ELSE {OPEN} END AS vt_e,
    CASE WHEN event_type = 'error' THEN NULL ELSE value END AS w
  FROM events)"""
#: Versions as stretches of equal belief.
SEG = f"""{C3},
cuts AS (SELECT DISTINCT ident, unnest([vt_s, vt_e]) AS pos FROM c3),
stretch AS (SELECT * FROM (SELECT ident, pos, lead(pos) OVER (PARTITION BY ident ORDER BY pos) AS nxt FROM cuts) s WHERE nxt IS NOT NULL),
chained AS (
  SELECT s.ident, pos, nxt, batch_id, op, w, tt AS tt_s, coalesce(lead(tt) OVER (PARTITION BY s.ident, pos ORDER BY tt, batch_id), {OPEN}) AS tt_e
  FROM stretch s JOIN c3 o ON s.ident = o.ident AND vt_s <= pos AND vt_e >= nxt),
runs AS (
  SELECT *, sum(CASE WHEN before IS NOT DISTINCT FROM pos THEN 0 ELSE 1 END) OVER (PARTITION BY ident, batch_id, tt_s, tt_e ORDER BY pos) AS run
  FROM (SELECT *, lag(nxt) OVER (PARTITION BY ident, batch_id, tt_s, tt_e ORDER BY pos) AS before FROM chained WHERE op != 'retract' AND tt_s < tt_e) c),
seg AS (SELECT ident, min(pos) AS vt_s, max(nxt) AS vt_e, tt_s, tt_e, any_value(w) AS w FROM runs GROUP BY ident, batch_id, tt_s, tt_e, run)"""


def c1(spark: SparkSession, d: str) -> DataFrame:
    return corpora.message_edges(spark, d)


def c2(spark: SparkSession, d: str) -> DataFrame:
    return corpora.trade_edges(spark, d)


def c3(spark: SparkSession, d: str) -> DataFrame:
    """Stamped operations on users; corrections that find nothing still state a belief, so the greatest time decides."""
    return stamp_transaction_time(corpora.user_beliefs(spark, d).withColumn("log_shard", log_shard("ident")))


query("c1_edges", f"WITH {C1} SELECT * FROM g")(c1)
query("c2_edges", f"WITH {C2} SELECT * FROM c2")(c2)


@query("c4_order_beliefs", f"""
WITH a AS (SELECT 'assert' AS op, o_orderkey AS ident, epoch_us(o_orderdate) AS vt_s, {OPEN} AS vt_e, o_totalprice AS w, epoch_us(o_orderdate) AS phys FROM orders
  UNION ALL SELECT 'correct', l_orderkey, epoch_us(l_shipdate), epoch_us(l_shipdate) + {30 * DAY}, l_extendedprice, epoch_us(l_shipdate) FROM lineitem WHERE l_returnflag = 'R')
SELECT op, CAST(ident AS VARCHAR) AS ident, vt_s, CAST(vt_e AS BIGINT) AS vt_e, w, phys, ident * 1000 + row_number() OVER (PARTITION BY ident ORDER BY phys, op, w, vt_s) AS batch_id FROM a""")
def c4_order_beliefs(spark, d):
    return corpora.order_beliefs(spark, d).drop("seq")


@query("c5_label_beliefs", """
SELECT 'assert' AS op, CAST(doc_id AS VARCHAR) AS ident, CAST(1.0 AS DOUBLE) AS w, CAST(1 AS BIGINT) AS phys FROM documents
UNION ALL SELECT 'correct', CAST(doc_id AS VARCHAR), CAST(quality AS DOUBLE), 2 FROM labels""")
def c5_label_beliefs(spark, d):
    return corpora.label_beliefs(spark, d).select("op", "ident", "w", "phys")


@query("c6_replies", """
SELECT conv_id, turn, concat_ws(':', conv_id, role) AS src, concat_ws(':', conv_id, next_role) AS dst, CAST(turn AS BIGINT) AS t
FROM (SELECT *, lead(role) OVER (PARTITION BY conv_id ORDER BY turn, role) AS next_role FROM conversations) c WHERE next_role IS NOT NULL""")
def c6_replies(spark, d):
    return corpora.replies(spark, d)


# ---- substrate --------------------------------------------------------------------------------------------------------------------


@query("hlc_stamp", """
WITH s AS (SELECT event_id AS batch_id, epoch_us(ts) - epoch_us(ts) % 3600000000 AS phys, user_id % 4 AS log_shard, row_number() OVER (PARTITION BY user_id % 4 ORDER BY event_id) AS n FROM events)
SELECT batch_id, log_shard, phys, n + max(phys - n) OVER (PARTITION BY log_shard ORDER BY batch_id ROWS UNBOUNDED PRECEDING) AS tt FROM s""")
def hlc_stamp(spark, d):
    """Clock over hourly physical times, so that most batches of a shard tie and the clock must move on by itself."""
    log = corpora.user_beliefs(spark, d).select("batch_id", (F.col("phys") - F.pmod("phys", F.lit(HOUR))).alias("phys"), (F.col("ident").cast("long") % 4).alias("log_shard"))
    return stamp_transaction_time(log)


POINT = """SELECT ident, w FROM (SELECT ident, arg_max(struct_pack(op := op, w := w), tt) AS b FROM c3 WHERE vt_s <= {v} AND vt_e > {v} {pin} GROUP BY ident) x, LATERAL (SELECT b.w AS w, b.op AS op) y WHERE op != 'retract'"""


@query("belief_point", f"WITH {C3} {POINT.format(v=VALID_AT, pin='')}")
def belief_point(spark, d):
    return belief_at(c3(spark, d), VALID_AT).select("ident", "w")


@query("belief_point_pinned", f"WITH {C3} {POINT.format(v=VALID_AT, pin=f'AND tt <= {PINNED}')}")
def belief_point_pinned(spark, d):
    return belief_at(c3(spark, d), VALID_AT, PINNED).select("ident", "w")


@query("belief_segments", f"WITH {SEG} SELECT * FROM seg")
def belief_segments(spark, d):
    return segment_versions(c3(spark, d))


@query("snapshot_pinned", f"WITH {SEG} SELECT ident, w FROM seg WHERE vt_s <= {VALID_AT} AND vt_e > {VALID_AT} AND tt_s <= {PINNED} AND tt_e > {PINNED}")
def snapshot_pinned(spark, d):
    """The same beliefs as ``belief_point_pinned``, through versions."""
    return snapshot(segment_versions(c3(spark, d)), VALID_AT, PINNED).select("ident", "w")


@query("version_fold_snapshot", f"WITH {C3} {POINT.format(v=VALID_AT, pin=f'AND tt <= {PINNED}')}")
def version_fold_snapshot(spark, d):
    """And through the sequential fold."""
    return snapshot(fold_versions(c3(spark, d), require_existing=False), VALID_AT, PINNED).select("ident", "w")


@query("version_fold_worked_example", f"""
SELECT CAST(c_custkey AS VARCHAR) AS ident, vt_s, vt_e, 2 * c_custkey + a AS tt_s, CASE WHEN b THEN 2 * c_custkey + 1 ELSE {OPEN} END AS tt_e, c_acctbal + more AS w
FROM customer, (VALUES (CAST(0 AS BIGINT), CAST(100 AS BIGINT), 0, true, CAST(0.0 AS DOUBLE)), (0, 40, 1, false, 0.0), (40, 60, 1, false, 1.0), (60, 100, 1, false, 0.0)) v(vt_s, vt_e, a, b, more)""")
def version_fold_worked_example(spark, d):
    """Of each customer a balance is asserted over [0, 100), then corrected over [40, 60): one piece closes and three follow it."""
    key, balance = F.col("c_custkey").cast("long"), F.col("c_acctbal").cast("double")
    step = lambda op, n, s, e, w: F.struct(F.lit(op).alias("op"), (2 * key + n).alias("batch_id"), F.lit(s).cast("long").alias("vt_s"), F.lit(e).cast("long").alias("vt_e"), w.alias("w"))
    both = F.explode(F.array(step("assert", 0, 0, 100, balance), step("correct", 1, 40, 60, balance + 1)))
    ops = load_table(spark, d, "customer", "c_custkey", "c_acctbal").select(key.cast("string").alias("ident"), both.alias("o"))
    log = attempt(ops.select("ident", "o.*", F.lit(0).alias("seq"), F.col("o.batch_id").alias("phys")), shards=16)
    return fold_versions(log.where("outcome = 'committed'")).select("ident", "vt_s", "vt_e", "tt_s", "tt_e", "w")


@query("version_disjoint_violations", "SELECT CAST(0 AS BIGINT) AS violations")
def version_disjoint_violations(spark, d):
    return overlap_violations(fold_versions(c3(spark, d), require_existing=False)).agg(F.count(F.lit(1)).alias("violations"))


@query("log_outcomes")
def log_outcomes(spark, d):
    """Outcomes of strict corrections on orders: those before the order fail."""
    from .substrate.fold import fold_identities, outcomes_of

    stamped = stamp_transaction_time(corpora.order_beliefs(spark, d).withColumn("log_shard", log_shard("ident")))
    codes = outcomes_of(fold_identities(stamped))
    return codes.groupBy(F.coalesce("code", F.lit("committed")).alias("outcome")).agg(F.count(F.lit(1)).alias("batches"))


ORACLES["log_outcomes"] = """
WITH a AS (SELECT o_orderkey AS k, epoch_us(o_orderdate) AS p, 0 AS kind, o_totalprice AS w FROM orders
  UNION ALL SELECT l_orderkey, epoch_us(l_shipdate), 1, l_extendedprice FROM lineitem WHERE l_returnflag = 'R')
SELECT CASE WHEN kind = 1 AND NOT coalesce(known, false) THEN 'F_NOTHING_TO_CORRECT' ELSE 'committed' END AS outcome, count(*) AS batches
FROM (SELECT *, bool_or(kind = 0) OVER (PARTITION BY k ORDER BY p, kind, w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS known FROM a) x
GROUP BY 1"""

# ---- O1 to O3 ---------------------------------------------------------------------------------------------------------------------


@query("o1_history", f"WITH {SEG} SELECT vt_s, vt_e, tt_s, tt_e, w FROM seg WHERE ident = '3' AND tt_e = {OPEN}")
def o1_history(spark, d):
    return history.version_history(segment_versions(c3(spark, d)), "3").drop("ident")


@query("o1_history_pinned", f"WITH {SEG} SELECT vt_s, vt_e, tt_s, CASE WHEN tt_e > {PINNED} THEN {OPEN} ELSE tt_e END AS tt_e, w FROM seg WHERE ident = '3' AND tt_s <= {PINNED} AND tt_e > {PINNED}")
def o1_history_pinned(spark, d):
    return history.version_history(segment_versions(c3(spark, d)), "3", PINNED).drop("ident")


@query("o1_history_audit", f"WITH {SEG} SELECT vt_s, vt_e, tt_s, tt_e, w FROM seg WHERE ident = '3'")
def o1_history_audit(spark, d):
    return history.version_history(segment_versions(c3(spark, d)), "3", audit=True).drop("ident")


def _khop(k: int, spark: SparkSession, d: str, direction: str = "out") -> DataFrame:
    live = neighbourhood.snapshot_edges(c1(spark, d), T0 + 10 * DAY, TTL)
    return neighbourhood.khop_neighbourhood(live, spark.range(1).select(F.col("id").alias("node")), k, direction)


def _khop_sql(k: int, both: bool = False) -> str:
    links = f"SELECT DISTINCT src, dst FROM g WHERE t <= {T0 + 10 * DAY} AND t > {T0 + 10 * DAY - TTL}"
    links = f"{links} UNION SELECT DISTINCT dst, src FROM g WHERE t <= {T0 + 10 * DAY} AND t > {T0 + 10 * DAY - TTL}" if both else links
    return f"""WITH RECURSIVE {C1}, l AS ({links}), walk(node, hop) AS (SELECT CAST(0 AS BIGINT), 0 UNION SELECT l.dst, hop + 1 FROM walk JOIN l ON node = l.src WHERE hop < {k})
SELECT node, CAST(min(hop) AS INTEGER) AS hop FROM walk GROUP BY node"""


for _n, _k in (("one", 1), ("two", 2), ("three", 3)):
    query(f"o2_{_n}_hop", _khop_sql(_k))(partial(_khop, _k))
query("o2_two_hop_both", _khop_sql(2, True))(partial(_khop, 2, direction="both"))

D1, D2, D3 = T0 + 8 * DAY, T0 + 12 * DAY, T0 + 16 * DAY
DIFF = """SELECT coalesce(a.ident, b.ident) AS ident, CASE WHEN a.ident IS NULL THEN 'added' WHEN b.ident IS NULL THEN 'removed' ELSE 'changed' END AS change, a.w AS before, b.w AS after
FROM (SELECT ident, round(w, 9) AS w FROM seg WHERE {one}) a FULL JOIN (SELECT ident, round(w, 9) AS w FROM seg WHERE {two}) b ON a.ident = b.ident
WHERE a.ident IS NULL OR b.ident IS NULL OR a.w IS DISTINCT FROM b.w"""
_now = lambda t: f"vt_s <= {t} AND vt_e > {t} AND tt_e = {OPEN}"


@query("o3_diff", f"WITH {SEG} {DIFF.format(one=_now(D1), two=_now(D3))}")
def o3_diff(spark, d):
    return diff.diff_states(segment_versions(c3(spark, d)), D1, D3)


@query("o3_diff_composition", f"WITH {SEG} {DIFF.format(one=_now(D1), two=_now(D3))}")
def o3_diff_composition(spark, d):
    """The same through the state between: the composition law."""
    versions = segment_versions(c3(spark, d))
    return diff.compose(diff.diff_states(versions, D1, D2), diff.diff_states(versions, D2, D3))


@query("o3_diff_beliefs", f"WITH {SEG} {DIFF.format(one=f'vt_s <= {VALID_AT} AND vt_e > {VALID_AT} AND tt_s <= {PINNED} AND tt_e > {PINNED}', two=f'vt_s <= {VALID_AT} AND vt_e > {VALID_AT} AND tt_s <= {T0 + 20 * DAY} AND tt_e > {T0 + 20 * DAY}')}")
def o3_diff_beliefs(spark, d):
    return diff.diff_beliefs(segment_versions(c3(spark, d)), VALID_AT, PINNED, T0 + 20 * DAY)


@query("o3_diff_edges", f"""WITH {C1}, p AS (
  SELECT src, dst, count(*) FILTER (t <= {D1} AND t > {D1 - TTL}) AS before, count(*) FILTER (t <= {D3} AND t > {D3 - TTL}) AS after FROM g GROUP BY src, dst)
SELECT src, dst, CASE WHEN before = 0 THEN 'added' WHEN after = 0 THEN 'removed' ELSE 'changed' END AS change, before, after FROM p WHERE before != after""")
def o3_diff_edges(spark, d):
    return diff.diff_edges(c1(spark, d), D1, D3, TTL)


# ---- O4 and O5 --------------------------------------------------------------------------------------------------------------------

START = "(SELECT min(t) FROM g)"


def _start(edges: DataFrame) -> int:
    return edges.agg(F.min("t")).first()[0] or T0


def _sources(spark: SparkSession, *nodes: int) -> DataFrame:
    return spark.createDataFrame([(n,) for n in nodes], "node long")


def _reach(spark: SparkSession, d: str, days: int = 10, max_wait: int | None = None, sources: tuple[int, ...] = (0,), **more) -> DataFrame:
    edges = c1(spark, d)
    t0 = _start(edges)
    return reach.earliest_arrival(edges, _sources(spark, *sources), t0, t0 + days * DAY, max_wait, **more)


def _reach_sql(days: int = 10, max_wait: int | None = None, sources: tuple[int, ...] = (0,), max_hops: int | None = None, strict: bool = True) -> str:
    """Labels by recursion; a label's depth is part of it only under a hop limit."""
    wait = f"AND (r.first OR g.t - r.arrival <= {max_wait})" if max_wait is not None else ""
    hops, more = ("r.hops + 1", f"AND r.hops < {max_hops}") if max_hops is not None else ("0", "")
    return f"""WITH RECURSIVE {C1}, r(source, node, arrival, first, hops) AS (
  SELECT CAST(unnest([{', '.join(map(str, sources))}]) AS BIGINT), CAST(unnest([{', '.join(map(str, sources))}]) AS BIGINT), {START}, true, 0
  UNION SELECT r.source, g.dst, g.t, false, {hops} FROM r JOIN g ON g.src = r.node AND g.t {'>' if strict else '>='} r.arrival AND g.t >= {START} AND g.t <= {START} + {days * DAY} {wait} {more})
SELECT source, node, min(arrival) AS arrival FROM r GROUP BY source, node"""


query("o4_reach", _reach_sql(3))(lambda s, d: _reach(s, d, 3))
query("o4_reach_wait", _reach_sql(10, 24 * HOUR))(lambda s, d: _reach(s, d, 10, 24 * HOUR))
query("o4_reach_hops", _reach_sql(3, None, max_hops=2))(lambda s, d: _reach(s, d, 3, max_hops=2))
query("o4_reach_multi", _reach_sql(2, None, (0, 5, 9)))(lambda s, d: _reach(s, d, 2, sources=(0, 5, 9)))
query("o4_reach_loose", _reach_sql(2, None, strict=False))(lambda s, d: _reach(s, d, 2, strict=False))
query("o4_reach_targets", _reach_sql(10) + " HAVING node IN (1, 7, 12)")(lambda s, d: _reach(s, d, targets=[1, 7, 12]))


@query("o4_reach_sweep", f"SELECT node, arrival FROM ({_reach_sql(10, 24 * HOUR)}) x")
def o4_reach_sweep(spark, d):
    """The wait-limited search by slices of time; equal to the label search."""
    edges = c1(spark, d)
    t0 = _start(edges)
    return reach.sweep_arrivals(edges, 0, t0, t0 + 10 * DAY, 24 * HOUR, 5 * DAY)


GREEDY = f"""WITH RECURSIVE {C1}, live AS (SELECT src, dst, t, {START} AS t0 FROM g WHERE t <= {START} + {10 * DAY}),
r(round, node, arrival) AS (
  SELECT 0, CAST(0 AS BIGINT), {START}
  UNION ALL
  SELECT round, node, min(arrival) FROM (
    SELECT r.round + 1 AS round, l.dst AS node, l.t AS arrival FROM r JOIN live l ON l.src = r.node AND l.t > r.arrival AND (r.node = 0 OR l.t - r.arrival <= {12 * HOUR})
    UNION ALL SELECT r.round + 1, r.node, (SELECT min(t) FROM g) FROM r WHERE r.node = 0) s
  WHERE round <= 100 GROUP BY round, node)
SELECT node, arrival FROM r WHERE round = 100"""


@query("o4_greedy_errors", f"SELECT a.node, a.arrival, coalesce(b.arrival, -1) AS greedy FROM ({_reach_sql(10, 12 * HOUR)}) a LEFT JOIN ({GREEDY}) b ON a.node = b.node WHERE a.arrival IS DISTINCT FROM b.arrival")
def o4_greedy_errors(spark, d):
    """Nodes where the rule of one label a node is wrong under a wait limit of 12 hours; -1 where it does not arrive."""
    edges = c1(spark, d)
    t0 = _start(edges)
    right = reach.earliest_arrival(edges, _sources(spark, 0), t0, t0 + 10 * DAY, 12 * HOUR)
    wrong = reach.earliest_arrival_greedy(edges, _sources(spark, 0), t0, t0 + 10 * DAY, 12 * HOUR).select("node", F.col("arrival").alias("greedy"))
    return right.join(wrong, "node", "left").where(~F.col("arrival").eqNullSafe(F.col("greedy"))).select("node", "arrival", F.coalesce("greedy", F.lit(-1).cast("long")).alias("greedy"))


@query("o5_paths", f"""WITH RECURSIVE {C1}, p(nodes, eids, departs, arrives, node) AS (
  SELECT [src, dst], [eid], t, t, dst FROM g WHERE src = 0 AND t > {START} AND t <= {START} + {2 * DAY}
  UNION ALL SELECT list_append(nodes, dst), list_append(eids, eid), departs, t, dst FROM p JOIN g ON src = node AND t > arrives AND t <= {START} + {2 * DAY} AND NOT list_contains(nodes, dst) AND node != 7 AND len(eids) < 3)
SELECT CAST(row_number() OVER (ORDER BY arrives, len(eids), eids) AS INTEGER) AS rank, array_to_string(nodes, '>') AS nodes, array_to_string(eids, '>') AS eids, departs, arrives, CAST(len(eids) AS INTEGER) AS hops
FROM p WHERE node = 7 ORDER BY arrives, len(eids), eids LIMIT 20""")
def o5_paths(spark, d):
    edges = c1(spark, d)
    t0 = _start(edges)
    found = paths.time_respecting_paths(edges, 0, 7, t0, t0 + 2 * DAY, 20, 3)
    line = lambda c: F.concat_ws(">", F.col(c).cast("array<string>")).alias(c)
    return found.select("rank", line("nodes"), line("eids"), "departs", "arrives", "hops")


# ---- O6 and O7 --------------------------------------------------------------------------------------------------------------------


def _motif_sql(pattern: motifs.Pattern, delta: int, graph: str = "g") -> str:
    nodes: dict[int, str] = {}
    conditions = []
    for i, (a, b) in enumerate(pattern):
        for x, side in ((a, "src"), (b, "dst")):
            here = f"e{i}.{side}"
            if x in nodes:
                conditions.append(f"{here} = {nodes[x]}")
            else:
                conditions += [f"{here} != {other}" for other in nodes.values()]
                nodes[x] = here
        if i:
            conditions.append(f"(e{i}.t > e{i - 1}.t OR (e{i}.t = e{i - 1}.t AND e{i}.eid > e{i - 1}.eid)) AND e{i}.t - e0.t <= {delta}")
    tables = ", ".join(f"{graph} e{i}" for i in range(len(pattern)))
    return f"FROM {tables} WHERE e0.src != e0.dst AND {' AND '.join(conditions)}"


def _count_sql(pattern: motifs.Pattern, delta: int) -> str:
    return f"WITH {C1} SELECT count(*) AS count {_motif_sql(pattern, delta)}"


MOTIF_DELTA = 6 * HOUR
for _name in ("cyclic", "feed_forward", "ping_pong", "repeat", "out_star", "in_star", "path", "return", "convey", "out_burst", "in_burst"):
    query(f"o6_{_name}", _count_sql(motifs.NAMED[_name], MOTIF_DELTA))(lambda s, d, p=motifs.NAMED[_name]: motifs.count_motifs(c1(s, d), p, MOTIF_DELTA))


@query("o6_all36", f"WITH {C1} SELECT * FROM (" + " UNION ALL ".join(f"SELECT '{n}' AS pattern, count(*) AS count {_motif_sql(p, MOTIF_DELTA)}" for n, p in motifs.three_edge_patterns().items()) + ") x WHERE count > 0")
def o6_all36(spark, d):
    return motifs.count_all_three_edge(c1(spark, d), MOTIF_DELTA)


@query("o6_cyclic_trade", f"WITH {C2}, x AS (SELECT * FROM c2 WHERE t >= epoch_us(TIMESTAMP '1995-01-01') AND t < epoch_us(TIMESTAMP '1995-01-01') + {60 * DAY}) SELECT count(*) AS count {_motif_sql(motifs.NAMED['cyclic'], DAY, 'x')}")
def o6_cyclic_trade(spark, d):
    """Day-granular times with many ties: the order is (t, eid)."""
    start = 788_918_400_000_000
    return motifs.count_motifs(selection.select_edges(c2(spark, d), selection.EdgeFilter(t_from=start, t_to=start + 60 * DAY)), motifs.NAMED["cyclic"], DAY)


@query("o6_cyclic_trade_whole")
def o6_cyclic_trade_whole(spark, d):
    """Over the whole trade graph; no SQL, which would join too many rows. ``o6_cyclic_trade`` compares 60 days of it with SQL."""
    return motifs.count_motifs(c2(spark, d), motifs.NAMED["cyclic"], DAY)


@query("o7_cyclic_rows", f"WITH {C1} SELECT e0.src AS n0, e1.src AS n1, e2.src AS n2, e0.eid AS e0, e1.eid AS e1, e2.eid AS e2, e0.t AS t_first, e2.t AS t_last {_motif_sql(motifs.NAMED['cyclic'], 24 * HOUR)}")
def o7_cyclic_rows(spark, d):
    rows = motifs.motif_rows(c1(spark, d), motifs.NAMED["cyclic"], 24 * HOUR)
    return rows.select(*[F.col("nodes")[i].alias(f"n{i}") for i in range(3)], *[F.col("eids")[i].alias(f"e{i}") for i in range(3)], "t_first", "t_last")


# ---- O8 to O11 --------------------------------------------------------------------------------------------------------------------

SERIES_END = T0 + 30 * DAY


def _series_sql(graph: str, start: int, end: int, width: int) -> str:
    return f"""frame AS (SELECT {start} + i * {width} AS bucket FROM range({-(-(end - start) // width)}) r(i)),
b AS (SELECT t - (t - {start}) % {width} AS bucket, src, dst FROM {graph} WHERE t >= {start} AND t < {end} AND src != dst),
deg AS (SELECT bucket, node, count(*) AS degree FROM (SELECT bucket, src AS node FROM b UNION ALL SELECT bucket, dst FROM b) x GROUP BY bucket, node),
d AS (SELECT bucket, count(*) AS nodes, sum(degree) AS ends, max(degree) AS deg_max FROM deg GROUP BY bucket),
pr AS (SELECT DISTINCT bucket, src, dst FROM b),
m AS (SELECT p.bucket, count(*) AS pairs, count(q.src) AS mutual FROM pr p LEFT JOIN pr q ON p.bucket = q.bucket AND p.src = q.dst AND p.dst = q.src GROUP BY p.bucket),
n AS (SELECT bucket, count(*) AS edges FROM b GROUP BY bucket)
SELECT bucket, coalesce(nodes, 0) AS nodes, coalesce(edges, 0) AS edges, coalesce(round(ends / nodes, 9), 0.0) AS deg_mean, coalesce(deg_max, 0) AS deg_max, coalesce(round(mutual / pairs, 9), 0.0) AS reciprocity
FROM frame LEFT JOIN d USING (bucket) LEFT JOIN m USING (bucket) LEFT JOIN n USING (bucket)"""


@query("o8_series", f"WITH {C1}, {_series_sql('g', T0, SERIES_END, DAY)}")
def o8_series(spark, d):
    return series.metric_series(c1(spark, d), T0, SERIES_END, DAY)


TRADE_START, TRADE_END = 788_918_400_000_000, 788_918_400_000_000 + 52 * WEEK


@query("o8_series_trade", f"WITH {C2}, {_series_sql('c2', TRADE_START, TRADE_END, WEEK)}")
def o8_series_trade(spark, d):
    return series.metric_series(c2(spark, d), TRADE_START, TRADE_END, WEEK)


@query("o8_reciprocity", f"SELECT bucket, reciprocity FROM (WITH {C1}, {_series_sql('g', T0, SERIES_END, WEEK)}) x")
def o8_reciprocity(spark, d):
    return series.metric_series(c1(spark, d), T0, SERIES_END, WEEK).select("bucket", "reciprocity")


BURST_WIDTH = 6 * HOUR
COUNTS = f"""{C1}, s AS (
  SELECT bucket, CAST(coalesce(n, 0) AS DOUBLE) AS value FROM (SELECT {T0} + i * {BURST_WIDTH} AS bucket FROM range({30 * DAY // BURST_WIDTH}) r(i)) f
  LEFT JOIN (SELECT t - (t - {T0}) % {BURST_WIDTH} AS bucket, count(*) AS n FROM g WHERE t >= {T0} AND t < {SERIES_END} GROUP BY 1) c USING (bucket))"""


@query("o9_zscore", f"""WITH {COUNTS}, z AS (
  SELECT *, CASE WHEN count(*) OVER w = 8 THEN round(avg(value) OVER w, 9) END AS baseline, CASE WHEN count(*) OVER w = 8 THEN round(stddev_pop(value) OVER w, 9) END AS sd FROM s WINDOW w AS (ORDER BY bucket ROWS BETWEEN 8 PRECEDING AND 1 PRECEDING))
SELECT bucket, value, baseline, round(CASE WHEN sd > 0 THEN round((value - baseline) / sd, 9) END, 6) AS score, coalesce(CASE WHEN sd > 0 THEN round((value - baseline) / sd, 9) END >= 2, false) AS is_burst FROM z""")
def o9_zscore(spark, d):
    found = series.detect_bursts(series.event_counts(c1(spark, d), T0, SERIES_END, BURST_WIDTH), "zscore", 8, 2.0)
    return found.withColumn("score", F.round("score", 6))


@query("o9_median", f"""WITH {COUNTS}, z AS (
  SELECT *, CASE WHEN count(*) OVER w = 8 THEN round(quantile_cont(value, 0.5) OVER w, 9) END AS baseline FROM s WINDOW w AS (ORDER BY bucket ROWS BETWEEN 8 PRECEDING AND 1 PRECEDING))
SELECT bucket, value, baseline, CASE WHEN baseline > 0 THEN round(value / baseline, 9) END AS score, coalesce(CASE WHEN baseline = 0 THEN value >= 1 ELSE round(value / baseline, 9) >= 1.5 END, false) AS is_burst FROM z""")
def o9_median(spark, d):
    return series.detect_bursts(series.event_counts(c1(spark, d), T0, SERIES_END, BURST_WIDTH), "median", 8, 1.5)


W1, W2 = (T0 + 5 * DAY, T0 + 10 * DAY), (T0 + 10 * DAY, T0 + 15 * DAY)
NEIGHBOURS = f"{C1}, m AS (SELECT CASE WHEN src = 3 THEN dst ELSE src END AS neighbour, t FROM g WHERE src = 3 OR dst = 3)"


@query("o10_gain_loss", f"""WITH {NEIGHBOURS}, s AS (SELECT neighbour, bool_or(t >= {W1[0]} AND t < {W1[1]}) AS was, bool_or(t >= {W2[0]} AND t < {W2[1]}) AS now FROM m GROUP BY neighbour)
SELECT neighbour, CASE WHEN NOT was THEN 'gained' WHEN NOT now THEN 'lost' ELSE 'kept' END AS change FROM s WHERE was OR now""")
def o10_gain_loss(spark, d):
    return evolution.neighbour_changes(c1(spark, d), 3, W1, W2)


@query("o10_degree_series", f"""WITH {NEIGHBOURS}, p AS (SELECT t - (t - {T0}) % {DAY} AS bucket, count(*) AS degree, count(DISTINCT neighbour) AS neighbours FROM m WHERE t >= {T0} AND t < {SERIES_END} GROUP BY 1)
SELECT {T0} + i * {DAY} AS bucket, coalesce(degree, 0) AS degree, coalesce(neighbours, 0) AS neighbours FROM range(30) r(i) LEFT JOIN p ON p.bucket = {T0} + i * {DAY}""")
def o10_degree_series(spark, d):
    return evolution.degree_series(c1(spark, d), 3, T0, SERIES_END, DAY)


C9 = """c9 AS (SELECT event_id AS id, user_id AS src, event_type AS kind, epoch_us(ts) AS i_s, epoch_us(ts) + greatest(1, CAST(floor(value * 60000000) AS BIGINT)) AS i_e FROM events),
a AS (SELECT * FROM c9 WHERE kind = 'click'), b AS (SELECT * FROM c9 WHERE kind = 'purchase')"""
ALLEN_SQL = {
    "before": "a.i_e < b.i_s", "meets": "a.i_e = b.i_s", "overlaps": "a.i_s < b.i_s AND a.i_e > b.i_s AND a.i_e < b.i_e", "starts": "a.i_s = b.i_s AND a.i_e < b.i_e",
    "during": "a.i_s > b.i_s AND a.i_e < b.i_e", "finishes": "a.i_e = b.i_e AND a.i_s > b.i_s", "equals": "a.i_s = b.i_s AND a.i_e = b.i_e", "finished_by": "a.i_e = b.i_e AND a.i_s < b.i_s",
    "contains": "a.i_s < b.i_s AND a.i_e > b.i_e", "started_by": "a.i_s = b.i_s AND a.i_e > b.i_e", "overlapped_by": "b.i_s < a.i_s AND b.i_e > a.i_s AND b.i_e < a.i_e", "met_by": "b.i_e = a.i_s", "after": "b.i_e < a.i_s",
}


def _sides(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    held = corpora.session_intervals(spark, d)
    return held.where("kind = 'click'"), held.where("kind = 'purchase'")


for _r in ALLEN:
    query(f"o11_{_r}", f"WITH {C9} SELECT a.id AS a_id, b.id AS b_id, '{_r}' AS relation FROM a JOIN b ON a.src = b.src AND {ALLEN_SQL[_r]}")(
        lambda s, d, r=_r: intervals.interval_pairs(*_sides(s, d), relations=(r,), keys=("src",))
    )


@query("o11_any", f"WITH {C9} SELECT relation, count(*) AS pairs FROM (SELECT CASE " + " ".join(f"WHEN {c} THEN '{r}'" for r, c in ALLEN_SQL.items()) + " END AS relation FROM a JOIN b ON a.src = b.src) x GROUP BY relation")
def o11_any(spark, d):
    return intervals.relation_counts(*_sides(spark, d), keys=("src",))


# ---- O12 and O13 ------------------------------------------------------------------------------------------------------------------

NAMES = """names AS (SELECT 'customer' AS type, CAST(c_custkey AS BIGINT) AS ident, c_name AS name FROM customer UNION ALL SELECT 'supplier', s_suppkey, s_name FROM supplier
UNION ALL SELECT 'nation', n_nationkey, n_name FROM nation UNION ALL SELECT 'region', r_regionkey, r_name FROM region UNION ALL SELECT 'part', p_partkey, p_name FROM part)"""


def _resolve_sql(where: str, score: str) -> str:
    return f"WITH {NAMES}, h AS (SELECT *, {score} AS score FROM names WHERE {where}) SELECT ident, type, name, score, score = max(score) OVER () AND count(*) OVER (PARTITION BY score) > 1 AS ambiguous FROM h"


FOLD = "trim(regexp_replace(lower(name), '\\s+', ' ', 'g'))"
query("o12_exact", _resolve_sql("name = 'Customer#000000012'", "CAST(1.0 AS DOUBLE)"))(lambda s, d: resolve.resolve_names(resolve.names_table(s, d), "Customer#000000012", "exact"))
query("o12_id", _resolve_sql("CAST(ident AS VARCHAR) = '3' AND type IN ('nation', 'region')", "CAST(1.0 AS DOUBLE)"))(lambda s, d: resolve.resolve_names(resolve.names_table(s, d), "3", "id", ["nation", "region"]))
query("o12_folded", _resolve_sql(f"{FOLD} = 'customer#000000012'", "CAST(1.0 AS DOUBLE)"))(lambda s, d: resolve.resolve_names(resolve.names_table(s, d), " CUSTOMER#000000012 ", "folded"))
query("o12_prefix", _resolve_sql(f"starts_with({FOLD}, 'supplier#00000000')", f"round(17 / length({FOLD}), 6)"))(lambda s, d: resolve.resolve_names(resolve.names_table(s, d), "Supplier#00000000", "prefix"))
query("o12_fuzzy", _resolve_sql(f"levenshtein({FOLD}, 'customer#000000x12') <= 2", f"round(1 - levenshtein({FOLD}, 'customer#000000x12') / greatest(18, length({FOLD})), 6)"))(lambda s, d: resolve.resolve_names(resolve.names_table(s, d), "Customer#000000x12", "fuzzy"))

query("o13_count", "SELECT count(*) AS value FROM orders")(lambda s, d: arithmetic.compute(load_table(s, d, "orders"), "count"))
query("o13_sum", "SELECT CAST(sum(CAST(round(o_totalprice, 9) AS DECIMAL(38, 9))) AS DOUBLE) AS value FROM orders")(lambda s, d: arithmetic.compute(load_table(s, d, "orders"), "sum", "o_totalprice"))
query("o13_min", "SELECT min(o_totalprice) AS value FROM orders")(lambda s, d: arithmetic.compute(load_table(s, d, "orders"), "min", "o_totalprice"))
query("o13_max", "SELECT max(o_totalprice) AS value FROM orders")(lambda s, d: arithmetic.compute(load_table(s, d, "orders"), "max", "o_totalprice"))
query("o13_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")(lambda s, d: arithmetic.compute(load_table(s, d, "orders", "o_orderkey", "o_totalprice"), "topk", "o_totalprice", k=10, ties=("o_orderkey",)))
query("o13_filter", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice >= 400000")(lambda s, d: arithmetic.compute(load_table(s, d, "orders", "o_orderkey", "o_totalprice"), "filter", "o_totalprice", test=(">=", 400000)))


@query("o13_relation", f"WITH {SEG} SELECT ident, vt_s, vt_e FROM seg WHERE tt_e = {OPEN} AND vt_s < {VALID_AT} AND vt_e > {VALID_AT} AND vt_e < {VALID_AT + DAY}")
def o13_relation(spark, d):
    held = history.scope(segment_versions(c3(spark, d))).withColumns({"q_s": F.lit(VALID_AT), "q_e": F.lit(VALID_AT + DAY)})
    return arithmetic.compute(held, "relation", ends=("vt_s", "vt_e", "q_s", "q_e"), relation="overlaps").select("ident", "vt_s", "vt_e")


# ---- text -------------------------------------------------------------------------------------------------------------------------


@query("fence_documents", """
SELECT doc_id, '<<data>>' || chr(10) || replace(replace(replace(regexp_replace(substr(text, 1, 500), '[\\x00-\\x08\\x0B-\\x1F\\x7F]', ' ', 'g'), '\\', '\\\\'), '<<', '\\<\\<'), '>>', '\\>\\>') || chr(10) || '<</data>>' AS fenced,
CAST(ceil(length(text) * 0.65) AS BIGINT) AS tokens FROM documents""")
def fence_documents(spark, d):
    docs = load_table(spark, d, "documents", "doc_id", "text")
    return docs.select("doc_id", fence("text", 500).alias("fenced"), approx_tokens("text").alias("tokens"))


__all__ = ["ORACLES", "QUERIES"]
