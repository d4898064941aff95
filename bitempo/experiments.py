"""Queries for plans, claims, measures, baselines, notes, streams and studies; they join those of :mod:`bitempo.queries`."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads
from .baselines import latest, retrieval
from .claims.verifier import check_claims_table
from .eval import scoring
from .eval.costs import guard_calibration, tokens_per_task
from .functions.canon import canonical_row
from .functions.timeaxis import DAY, HOUR, WEEK, covers
from .lineage import cut, shared_folder
from .memory import notes
from .plans import guard, paging
from .plans.executor import execute_plan
from .plans.ir import Plan, ref
from .queries import C1, C3, COUNTS, OPEN, POINT, SEG, START, TTL, VALID_AT, PINNED, T0, _motif_sql, c1, c3, query
from .operators import motifs
from .sources.tables import load_table
from .streaming import streams
from .substrate.log import FileStore, packed_adjacency, replay
from .substrate.segments import belief_at, segment_versions
from .substrate.snapshots import scope, snapshot

# ---- pages ------------------------------------------------------------------------------------------------------------------------

PAGE = "SELECT o_orderkey, o_custkey, o_totalprice FROM orders ORDER BY o_custkey, o_orderkey LIMIT 100"


def _orders(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice")


def _rows(spark: SparkSession, page: paging.ResultPage) -> DataFrame:
    return spark.createDataFrame([tuple(r[c] for c in ("o_orderkey", "o_custkey", "o_totalprice")) for r in page.rows], "o_orderkey long, o_custkey long, o_totalprice double")


@query("page_first", PAGE)
def page_first(spark, d):
    return _rows(spark, paging.page(_orders(spark, d), ["o_custkey", "o_orderkey"]))


@query("page_next", PAGE + " OFFSET 100")
def page_next(spark, d):
    orders, order = _orders(spark, d), ["o_custkey", "o_orderkey"]
    return _rows(spark, paging.page(orders, order, cursor=paging.page(orders, order).cursor))


# ---- plans ------------------------------------------------------------------------------------------------------------------------


def _answer(spark: SparkSession, d: str, steps: list[dict], answer: dict) -> DataFrame:
    done = execute_plan(Plan.parse({"steps": steps, "answer": answer}), workloads.message_store(spark, d), consume="full")
    return spark.createDataFrame([(float(done.answer),)], "value double")


_step = lambda i, op, **args: {"id": i, "op": op, "args": args}


@query("plan_m01", f"""WITH RECURSIVE {C1}, r(node, arrival) AS (
  SELECT CAST(0 AS BIGINT), CAST({T0} AS BIGINT) UNION SELECT g.dst, g.t FROM r JOIN g ON g.src = r.node AND g.t > r.arrival AND g.t >= {T0} AND g.t <= {T0 + 2 * DAY}),
h AS (SELECT * FROM g WHERE src IN (SELECT node FROM r) AND dst IN (SELECT node FROM r))
SELECT CAST(count(*) AS DOUBLE) AS value {_motif_sql(motifs.NAMED['cyclic'], 6 * HOUR, 'h')}""")
def plan_m01(spark, d):
    """Reachable nodes, then the triangles among them; the node set stays distributed."""
    return _answer(spark, d, [_step("s1", "earliest_arrival", sources=[0], t_from=T0, t_to=T0 + 2 * DAY), _step("s2", "count_motifs", pattern="cyclic", delta=6 * HOUR, nodes=ref("s1.rows[*].node"))], {"from": "s2", "field": "rows[0].count"})


@query("plan_m02", f"WITH {SEG} SELECT max(w) AS value FROM seg WHERE ident = '3'")
def plan_m02(spark, d):
    return _answer(spark, d, [_step("s1", "resolve_names", text="3", mode="exact", types=["user"]), _step("s2", "version_history", ident=ref("s1.rows[0].ident"), audit=True), _step("s3", "compute", fn="max", input=ref("s2.rows[*]"), field="w")], {"from": "s3", "field": "rows[0].value"})


@query("plan_m03", f"""WITH {COUNTS}, z AS (
  SELECT *, CASE WHEN count(*) OVER w = 8 THEN round(quantile_cont(value, 0.5) OVER w, 9) END AS baseline FROM s WINDOW w AS (ORDER BY bucket ROWS BETWEEN 8 PRECEDING AND 1 PRECEDING))
SELECT CAST(count(*) AS DOUBLE) AS value FROM z WHERE coalesce(CASE WHEN baseline = 0 THEN value >= 1 ELSE round(value / baseline, 9) >= 1.2 END, false) AND value >= 5""")
def plan_m03(spark, d):
    return _answer(spark, d, [_step("s1", "detect_bursts", t_from=T0, t_to=T0 + 30 * DAY, width=6 * HOUR, rule="median", lookback=8, threshold=1.2, only_bursts=True), _step("s2", "compute", fn="filter", input=ref("s1.rows[*]"), field="value", test=[">=", 5])], {"from": "s2", "field": "rows_total"})


@query("plan_m04", """WITH c9 AS (SELECT event_id AS id, user_id AS src, event_type AS kind, epoch_us(ts) AS s, epoch_us(ts) + greatest(1, CAST(floor(value * 60000000) AS BIGINT)) AS e FROM events)
SELECT CAST(count(*) AS DOUBLE) AS value FROM c9 a JOIN c9 b ON a.src = b.src AND a.kind = 'click' AND b.kind = 'purchase'
WHERE (a.s < b.s AND a.e > b.s AND a.e < b.e) OR (b.s < a.s AND b.e > a.s AND b.e < a.e) OR (a.s > b.s AND a.e < b.e) OR (a.s < b.s AND a.e > b.e)""")
def plan_m04(spark, d):
    return _answer(spark, d, [_step("s1", "interval_pairs", a={"kind": "click"}, b={"kind": "purchase"}, relations=["overlaps", "overlapped_by", "during", "contains"], match="src"), _step("s2", "compute", fn="count", input=ref("s1.rows[*]"))], {"from": "s2", "field": "rows[0].value"})


@query("cost_estimates")
def cost_estimates(spark, d):
    """Estimates of the guard, which bound the rows that operators touch, with the rows that they then make."""
    store = workloads.message_store(spark, d)
    cases = {"count_motifs": {"pattern": "cyclic", "delta": 6 * HOUR}, "earliest_arrival": {"sources": [0], "t_from": T0, "t_to": T0 + 3 * DAY}, "khop_neighbourhood": {"seeds": [0], "k": 2, "t": T0 + 10 * DAY}, "metric_series": {"t_from": T0, "t_to": T0 + 30 * DAY, "width": DAY}}
    made = {op: n for op, _, n in guard_calibration(store, list(cases.items()))}
    rows = [(op, guard.estimate(op, a, store.stats), guard.refuse(op, a, store.stats) is not None, made[op]) for op, a in cases.items()]
    rows.append(("count_motifs, refused", guard.estimate("count_motifs", {"pattern": "cyclic", "delta": 10**13}, store.stats), guard.refuse("count_motifs", {"pattern": "cyclic", "delta": 10**13}, store.stats, 1000) is not None, None))
    return spark.createDataFrame(rows, "operator string, estimate long, refused boolean, rows_made long")


# ---- measures ---------------------------------------------------------------------------------------------------------------------

PROBES = f"""p AS ({POINT.format(v=VALID_AT, pin=f'AND tt <= {PINNED}')}), n AS ({POINT.format(v=VALID_AT, pin='')}),
probes AS (SELECT p.ident, p.w AS was, n.w AS now FROM p JOIN n ON p.ident = n.ident WHERE p.w != n.w)"""
ANSWERS = f"""{SEG}, {PROBES},
halves AS (SELECT ident, 'before' AS side, was AS gold, now FROM probes UNION ALL SELECT ident, 'current', now, now FROM probes),
held AS (
  SELECT ident, 'before' AS side, w FROM seg WHERE vt_s <= {VALID_AT} AND vt_e > {VALID_AT} AND tt_s <= {PINNED} AND tt_e > {PINNED}
  UNION ALL SELECT ident, 'current', w FROM seg WHERE vt_s <= {VALID_AT} AND vt_e > {VALID_AT} AND tt_e = {OPEN}),
scores AS (SELECT 'full' AS system, side, CAST(CAST(ident AS BIGINT) % 3 AS VARCHAR) AS family, coalesce(abs(round(w, 9) - round(gold, 9)) <= 1e-9, false) AS correct FROM halves LEFT JOIN held USING (ident, side) UNION ALL SELECT 'latest_state', side, CAST(CAST(ident AS BIGINT) % 3 AS VARCHAR), abs(round(now, 9) - round(gold, 9)) <= 1e-9 FROM halves)"""


def _probes(spark: SparkSession, d: str) -> DataFrame:
    ops = c3(spark, d)
    was, now = belief_at(ops, VALID_AT, PINNED).select("ident", F.col("w").alias("was")), belief_at(ops, VALID_AT).select("ident", F.col("w").alias("now"))
    return was.join(now, "ident").where("was != now")


def _scores(spark: SparkSession, d: str) -> DataFrame:
    """Both halves of every probe, with gold from the operations; the full system answers by snapshots of stored versions, the latest state by what is believed now."""
    side = F.explode(F.array(*[F.struct(F.lit(s).alias("side"), F.col(g).alias("gold")) for s, g in (("before", "was"), ("current", "now"))]))
    halves = _probes(spark, d).select("ident", "was", "now", side.alias("h")).select("ident", "was", "now", "h.*")
    versions = segment_versions(c3(spark, d))
    held = snapshot(versions, VALID_AT, PINNED).select("ident", F.lit("before").alias("side"), F.col("w").alias("full"))
    held = held.unionByName(snapshot(versions, VALID_AT).select("ident", F.lit("current").alias("side"), F.col("w").alias("full")))
    halves, full = halves.join(held, ["ident", "side"], "left"), F.col("full")
    said = halves.withColumn("s", F.explode(F.array(F.struct(F.lit("full").alias("system"), full.alias("answer")), F.struct(F.lit("latest_state").alias("system"), F.col("now").alias("answer")))))
    return said.select("ident", "side", (F.col("ident").cast("long") % 3).cast("string").alias("family"), "s.system", scoring.number_correct(F.col("s.answer"), F.col("gold")).alias("correct"))


@query("probe_pairs", f"WITH {C3}, {PROBES} SELECT * FROM probes")
def probe_pairs(spark, d):
    return _probes(spark, d)


@query("score_accuracy", f"WITH {ANSWERS} SELECT system, side, count(*) AS tasks, CAST(sum(CASE WHEN correct THEN 1 ELSE 0 END) AS BIGINT) AS correct, round(avg(CASE WHEN correct THEN 1.0 ELSE 0.0 END), 9) AS accuracy FROM scores GROUP BY system, side")
def score_accuracy(spark, d):
    return scoring.accuracy(_scores(spark, d), ["system", "side"])


@query("score_rollup", f"WITH {ANSWERS} SELECT system, side, family, count(*) AS tasks, round(avg(CASE WHEN correct THEN 1.0 ELSE 0.0 END), 9) AS accuracy FROM scores GROUP BY CUBE (system, side, family)")
def score_rollup(spark, d):
    return scoring.accuracy_cube(_scores(spark, d), ["system", "side", "family"])


@query("bootstrap_ci")
def bootstrap_ci(spark, d):
    """Paired difference of the full system and the latest state over all probe halves."""
    wide = _scores(spark, d).groupBy(F.concat_ws(":", "ident", "side").alias("task")).agg(F.max(F.when(F.col("system") == "full", F.col("correct").cast("int"))).alias("a"), F.max(F.when(F.col("system") == "latest_state", F.col("correct").cast("int"))).alias("b"))
    return scoring.paired_bootstrap(wide)


@query("interval_scores", """WITH o AS (SELECT o_orderkey, epoch_us(o_orderdate) AS s, epoch_us(max(l_shipdate)) AS e, epoch_us(min(l_shipdate)) AS m FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey, o_orderdate)
SELECT count(*) AS answers, count(*) FILTER (CAST(greatest(0, least(e, e) - greatest(s, m)) AS DOUBLE) / ((e - s) + (e - m) - greatest(0, least(e, e) - greatest(s, m))) >= 0.5) AS correct FROM o WHERE e > s AND e > m""")
def interval_scores(spark, d):
    """Interval answers by their overlap: time from first to last shipping against time from order to last shipping."""
    from .functions.timeaxis import micros

    o = load_table(spark, d, "orders", "o_orderkey", "o_orderdate").join(load_table(spark, d, "lineitem", "l_orderkey", "l_shipdate"), F.col("o_orderkey") == F.col("l_orderkey"))
    per = o.groupBy("o_orderkey", micros("o_orderdate").alias("s")).agg(F.max(micros("l_shipdate")).alias("e"), F.min(micros("l_shipdate")).alias("m")).where("e > s and e > m")
    return per.agg(F.count(F.lit(1)).alias("answers"), F.count(F.when(scoring.interval_correct("s", "e", "m", "e"), 1)).alias("correct"))


# ---- claims -----------------------------------------------------------------------------------------------------------------------


@query("claims_verdicts", f"""WITH {C3}, {PROBES}
SELECT ident AS answer_id, kind, CASE WHEN (kind = 'value' AND CAST(ident AS BIGINT) % 5 = 0) OR (kind = 'entity' AND CAST(ident AS BIGINT) % 4 = 0) OR (kind = 'count' AND CAST(ident AS BIGINT) % 3 = 0) THEN 'unsupported' WHEN CAST(ident AS BIGINT) % 7 = 0 THEN 'weak' ELSE 'supported' END AS level
FROM probes, (VALUES ('value'), ('entity'), ('count')) k(kind)""")
def claims_verdicts(spark, d):
    """Three claims for each probe: a value that every fifth answer takes from the wrong belief, an identifier that every fourth makes up, and a
    right count whose pointer every third sets to an uncited step; every seventh trace is incomplete."""
    p = _probes(spark, d).withColumn("u", F.col("ident").cast("long"))
    none_ids, none = F.array().cast("array<string>"), F.lit(None)
    evidence = p.select(F.lit("r").alias("run_id"), F.col("ident").alias("step_id"), F.col("was").alias("number"), F.array("ident").alias("ids"), (F.col("u") % 7 != 0).alias("complete"), F.lit(False).alias("tainted"))
    claim = lambda i, kind, pointer, number, ids: F.struct(F.lit(i).alias("claim_id"), F.lit(kind).alias("kind"), pointer.cast("string").alias("pointer"), number.cast("double").alias("number"), ids.alias("ids"))
    three = F.array(
        claim(0, "value", F.col("ident"), F.when(F.col("u") % 5 == 0, F.col("now")).otherwise(F.col("was")), none_ids),
        claim(1, "entity", none, none, F.when(F.col("u") % 4 == 0, F.array("ident", F.lit("nobody"))).otherwise(F.array("ident"))),
        claim(2, "count", F.when(F.col("u") % 3 == 0, F.lit("elsewhere")), F.col("was"), none_ids),
    )
    claims = p.select(F.lit("r").alias("run_id"), F.col("ident").alias("answer_id"), F.array("ident").alias("cites"), F.explode(three).alias("c")).select("run_id", "answer_id", "cites", "c.*")
    return check_claims_table(claims, evidence).select("answer_id", "kind", "level")


@query("taint_closure", """WITH RECURSIVE e AS (SELECT conv_id, turn AS a, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM (SELECT DISTINCT conv_id, turn FROM conversations) d),
t(conv_id, turn) AS (SELECT DISTINCT conv_id, turn FROM conversations WHERE (conv_id + turn) % 11 = 0 UNION SELECT e.conv_id, e.b FROM t JOIN e ON e.conv_id = t.conv_id AND e.a = t.turn WHERE e.b IS NOT NULL)
SELECT conv_id, turn FROM t""")
def taint_closure(spark, d):
    """Steps that depend on a cut page, directly or not: turns stand for steps, each reading the one before."""
    from pyspark.sql import Window

    steps = load_table(spark, d, "conversations", "conv_id", "turn").distinct()
    links = cut(steps.withColumn("b", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))).where("b is not null"))
    tainted = frontier = cut(steps.where((F.col("conv_id") + F.col("turn")) % 11 == 0))
    while not frontier.isEmpty():
        after = frontier.join(links, ["conv_id", "turn"]).select("conv_id", F.col("b").alias("turn"))
        frontier = cut(after.join(tainted, ["conv_id", "turn"], "left_anti"))
        tainted = tainted.unionByName(frontier)
    return tainted


# ---- baselines --------------------------------------------------------------------------------------------------------------------

SAID = f"""{C1}, said AS (SELECT eid // 24 AS chunk, eid, concat_ws(' ', 'user', src, etype, 'user', dst, 'on', strftime(make_timestamp(t), '%Y-%m-%d %H:%M:%S'), 'weight', format('{{:,.2f}}', w)) AS sentence FROM g),
held AS (SELECT chunk, count(*) AS events, string_agg(sentence, '. ' ORDER BY eid) AS text FROM said GROUP BY chunk)"""


@query("baseline_chunks", f"WITH {SAID} SELECT chunk, events, CAST(ceil(length(text) * 0.65) AS BIGINT) AS tokens FROM held")
def baseline_chunks(spark, d):
    from .functions.text import approx_tokens

    return retrieval.chunks(c1(spark, d), 24).select("chunk", "events", approx_tokens("text").alias("tokens"))


@query("baseline_chunk_topk", f"""WITH {SAID}, tf AS (SELECT chunk, term, count(*) AS n FROM (SELECT chunk, unnest(regexp_extract_all(lower(text), '[a-z0-9]+')) AS term FROM held) x GROUP BY chunk, term),
x AS (SELECT chunk, term, n * ln(((SELECT count(*) FROM held) + 1) / CAST(df + 1 AS DOUBLE)) AS x FROM tf JOIN (SELECT term, count(*) AS df FROM tf GROUP BY term) d USING (term)),
w AS (SELECT chunk, term, CASE WHEN norm > 0 THEN x / norm ELSE 0 END AS weight FROM x JOIN (SELECT chunk, sqrt(sum(x * x)) AS norm FROM x GROUP BY chunk) n USING (chunk))
SELECT chunk, round(sum(weight), 6) AS score FROM w WHERE term IN ('user', '3', 'purchase') GROUP BY chunk ORDER BY round(sum(weight), 9) DESC, chunk LIMIT 20""")
def baseline_chunk_topk(spark, d):
    weights = retrieval.term_weights(retrieval.chunks(c1(spark, d), 24))
    return retrieval.retrieve_chunks(weights, "user 3 purchase", 20).withColumn("score", F.round("score", 6))


@query("baseline_admission", f"""WITH {C1}, p AS (SELECT * FROM (VALUES (256, 1), (256, 2), (256, 20), (24, 20)) v(n, k)),
said AS (SELECT eid, length(concat_ws(' ', 'user', src, etype, 'user', dst, 'on', strftime(make_timestamp(t), '%Y-%m-%d %H:%M:%S'), 'weight', format('{{:,.2f}}', w))) AS size FROM g),
held AS (SELECT n, eid // n AS chunk, sum(size) + 2 * (count(*) - 1) AS size FROM said, (SELECT DISTINCT n FROM p) q GROUP BY 1, 2),
means AS (SELECT n, avg(size) AS mean FROM held GROUP BY n),
found AS (SELECT CAST(k AS BIGINT) AS k, CAST(n AS BIGINT) AS n, CAST(floor(mean * k * CAST(0.65 AS DOUBLE)) AS BIGINT) AS tokens FROM p JOIN means USING (n))
SELECT *, tokens <= 32768 AS admitted FROM found""")
def baseline_admission(spark, d):
    """Which retrieval breadths fit a serving window of 32,768 tokens."""
    edges = c1(spark, d)
    rows = []
    for n, ks in ((256, (1, 2, 20)), (24, (20,))):
        held = retrieval.chunks(edges, n)
        rows += [(a.k, a.n, a.tokens, a.admitted) for a in (retrieval.admit(held, k, n) for k in ks)]
    return spark.createDataFrame(rows, "k long, n long, tokens long, admitted boolean")


LIVE = "live AS (SELECT DISTINCT src, dst FROM g WHERE t > (SELECT max(t) FROM g) - {ttl})"


@query("baseline_two_hop", f"""WITH {C1}, {LIVE.format(ttl=TTL)}, b AS (SELECT src, dst FROM live UNION SELECT dst, src FROM live),
n1 AS (SELECT CAST(3 AS BIGINT) AS node UNION SELECT dst FROM b WHERE src = 3), n2 AS (SELECT node FROM n1 UNION SELECT b.dst FROM b JOIN n1 ON b.src = n1.node)
SELECT src, dst FROM live WHERE src IN (SELECT node FROM n2) AND dst IN (SELECT node FROM n2)""")
def baseline_two_hop(spark, d):
    return latest.latest_two_hop(c1(spark, d), [3], TTL)


@query("baseline_latest_pattern", f"WITH {C1} SELECT count(*) AS value FROM g e0, g e1 WHERE e0.dst = e1.src AND e0.src = e1.dst AND e0.eid != e1.eid AND e0.src = 3 AND e1.t > {T0 + 10 * DAY}")
def baseline_latest_pattern(spark, d):
    return latest.run_latest_pattern(latest.Match((("a", "b"), ("b", "a")), (("a", "id", "=", 3), ("e1", "t", ">", T0 + 10 * DAY))), c1(spark, d))


# ---- notes ------------------------------------------------------------------------------------------------------------------------

FACTS = f"""{C1}, k AS (SELECT t - t % {WEEK} AS window_s, src AS node, count(*) AS n FROM g GROUP BY 1, 2),
facts AS (SELECT window_s, window_s + {WEEK} AS window_e, CAST(sum(n) AS BIGINT) AS edges, (SELECT count(DISTINCT x) FROM (SELECT unnest([src, dst]) AS x, t FROM g) y WHERE t - t % {WEEK} = window_s) AS nodes,
  arg_max(node, n * 1000000000 - node) AS top_node, max(n) AS top_edges FROM k GROUP BY window_s)"""


@query("notes_weekly", f"WITH {FACTS} SELECT window_s, window_e, 'In this week ' || nodes || ' nodes exchanged ' || edges || ' events; node ' || top_node || ' sent ' || top_edges || '.' AS text FROM facts")
def notes_weekly(spark, d):
    return notes.admitted(notes.write_notes(notes.weekly_facts(c1(spark, d)), T0 + 20 * DAY)).select("window_s", "window_e", "text")


@query("notes_quarantine", f"WITH {FACTS}, {C3.strip()} SELECT window_s, EXISTS (SELECT 1 FROM c3 WHERE op = 'correct' AND vt_s < window_e AND vt_e > window_s AND tt > {T0 + 20 * DAY}) AS quarantined FROM facts")
def notes_quarantine(spark, d):
    made = notes.write_notes(notes.weekly_facts(c1(spark, d)), T0 + 20 * DAY)
    return notes.quarantine(made, c3(spark, d)).select("window_s", "quarantined")


# ---- streams ----------------------------------------------------------------------------------------------------------------------


def _event_stream(spark: SparkSession, d: str) -> DataFrame:
    """The events table as a stream of its file, linked like the message graph."""
    from .functions.timeaxis import micros
    from .sources.corpora import COMMUNITY

    schema = load_table(spark, d, "events").schema
    users = load_table(spark, d, "events", "user_id").agg(F.max("user_id")).first()[0] + 1
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(d)
    src, k = F.col("user_id"), F.get_json_object("props", "$.k").cast("long")
    dst = F.when(F.col("event_type") == "signup", (src * 17 + k) % users).otherwise((src - src % COMMUNITY + k % COMMUNITY) % users)
    edges = raw.select(F.col("event_id").alias("eid"), src.alias("src"), dst.alias("dst"), micros("ts").alias("t"), F.col("value").alias("w"), F.col("event_type").alias("etype"))
    return edges.withColumn("ts", F.timestamp_micros("t")).where("src != dst")


def _collected(spark: SparkSession, stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream over what is there and read what it wrote."""
    import uuid

    at = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    streams.run_to_end(stream, lambda b, n: b.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{at}/out"), f"{at}/checkpoint", mode)
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


@query("stream_daily_counts", f"WITH {C1} SELECT t - t % {DAY} AS bucket, count(*) AS edges FROM g GROUP BY 1")
def stream_daily_counts(spark, d):
    return _collected(spark, streams.windowed_counts(_event_stream(spark, d)), "complete")


@query("stream_deduplicated", f"WITH {C1} SELECT count(*) AS edges, CAST(sum(eid) AS BIGINT) AS eids FROM g")
def stream_deduplicated(spark, d):
    """Every edge sent twice, kept once."""
    once = _event_stream(spark, d)
    twice = once.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    return _collected(spark, streams.deduplicated(twice, "40 days").select("eid"), "append").agg(F.count(F.lit(1)).alias("edges"), F.sum("eid").alias("eids"))


@query("stream_reach", f"""WITH RECURSIVE {C1}, r(node, arrival) AS (
  SELECT CAST(0 AS BIGINT), {START} UNION SELECT g.dst, g.t FROM r JOIN g ON g.src = r.node AND g.t > r.arrival AND g.t <= {START} + {2 * DAY})
SELECT node, min(arrival) AS arrival FROM r GROUP BY node""")
def stream_reach(spark, d):
    """Earliest arrival kept up by micro-batches of time-ordered edges."""
    t0 = c1(spark, d).agg(F.min("t")).first()[0] or T0
    import uuid

    state = streams.ArrivalState(spark, 0, t0)
    streams.run_to_end(_event_stream(spark, d).where((F.col("t") <= t0 + 2 * DAY)), state, f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}")
    return state.state.select("node", F.col("first").alias("arrival"))


@query("stream_sessions", f"""WITH {C1}, x AS (SELECT *, CASE WHEN coalesce(t - lag(t) OVER (PARTITION BY src ORDER BY t, eid) < {2 * HOUR}, false) THEN 0 ELSE 1 END AS fresh FROM g),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY src ORDER BY t, eid) AS n FROM x)
SELECT src, min(t) AS session_start, max(t) + {2 * HOUR} AS session_end, count(*) AS edges FROM s GROUP BY src, n""")
def stream_sessions(spark, d):
    """Stretches of a user's activity without a gap of two hours."""
    found = _collected(spark, streams.user_sessions(_event_stream(spark, d)), "complete")
    return found.select("src", F.col("start").alias("session_start"), F.col("end").alias("session_end"), "edges")


@query("stream_reply_pairs", f"WITH {C1} SELECT a.eid AS a_eid, b.eid AS b_eid FROM g a JOIN g b ON a.src = b.dst AND a.dst = b.src AND b.t > a.t AND b.t <= a.t + {HOUR}")
def stream_reply_pairs(spark, d):
    """Edges answered in reverse within an hour, by a join of two streams."""
    return _collected(spark, streams.reply_pairs(_event_stream(spark, d), _event_stream(spark, d)), "append")


@query("stream_beliefs", f"WITH {C3} {POINT.format(v=VALID_AT, pin='')}")
def stream_beliefs(spark, d):
    """What is believed after the operations on users came as three micro-batches, from the table of live pieces that the writer keeps."""
    import uuid

    from .sources import corpora

    ops = corpora.user_beliefs(spark, d)
    lo, hi = ops.agg(F.min("batch_id"), F.max("batch_id")).first()
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    for i in range(3):
        part = F.floor((F.col("batch_id") - lo) * 3 / (hi - lo + 1)) == i
        ops.where(part).coalesce(1).write.mode("append").parquet(f"{folder}/in")
    arriving = spark.readStream.schema(ops.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    ingest = streams.BeliefIngest(spark, f"{folder}/log", require_existing=False)
    streams.run_to_end(arriving, ingest, f"{folder}/checkpoint")
    return ingest.believed.read(ingest.believed.epochs()[-1:]).where(covers("vt_s", "vt_e", F.lit(VALID_AT))).select("ident", "w")


# ---- stores and digests -----------------------------------------------------------------------------------------------------------

PINNED_POINT = POINT.format(v=VALID_AT, pin=f"AND tt <= {PINNED}")


@query("replay_stores", f"WITH {C3}, b AS ({PINNED_POINT}) SELECT store, ident, w FROM b, (VALUES ('parquet'), ('orc')) s(store)")
def replay_stores(spark, d):
    """The log replayed into stores of two formats; a pinned snapshot read from each."""
    import uuid

    log, out = cut(c3(spark, d).withColumn("outcome", F.lit("committed"))), None
    for kind in ("parquet", "orc"):
        store = FileStore(spark, f"{shared_folder(spark)}/store-{uuid.uuid4().hex}", kind)
        replay(log, store)
        seen = snapshot(store.read("versions"), VALID_AT, PINNED).select(F.lit(kind).alias("store"), "ident", "w")
        out = seen if out is None else out.unionByName(seen)
    return out


@query("pinned_immutable", f"WITH {C3}, b AS ({PINNED_POINT}) SELECT ident, w, CAST(2 AS BIGINT) AS seen FROM b")
def pinned_immutable(spark, d):
    """The pinned snapshot, from the operations known a day after the pin and from all: each belief is seen twice, the same."""
    ops = c3(spark, d)
    both = [snapshot(segment_versions(o), VALID_AT, PINNED).select("ident", "w") for o in (ops.where(F.col("tt") <= PINNED + DAY), ops)]
    return both[0].unionByName(both[1]).groupBy("ident", "w").agg(F.count(F.lit(1)).alias("seen"))


@query("canonical_digests", f"""WITH {C3}, b AS ({PINNED_POINT}), l AS (SELECT ident, concat('{{"ident":"', ident, '","w":"', format('{{:,.9f}}', w), '"}}') AS line FROM b)
SELECT ident, line, sha256(line) AS digest FROM l""")
def canonical_digests(spark, d):
    """Canonical rows of a pinned belief and their digests."""
    line = canonical_row(belief_at(c3(spark, d), VALID_AT, PINNED).select("ident", "w"))
    return belief_at(c3(spark, d), VALID_AT, PINNED).select("ident", "w").select("ident", line.alias("line")).withColumn("digest", F.sha2("line", 256))


@query("adjacency_rows", f"WITH {C1} SELECT src, t // {DAY} AS slice, CAST(row_number() OVER (PARTITION BY src, t // {DAY} ORDER BY t, eid) - 1 AS INTEGER) AS place, eid, dst FROM g")
def adjacency_rows(spark, d):
    """Time-ordered out-edges of each node and day."""
    packed = packed_adjacency(c1(spark, d), DAY)
    return packed.select("src", "slice", F.posexplode("out").alias("place", "edge")).select("src", "slice", "place", "edge.eid", "edge.dst")


@query("scoped_versions", f"WITH {SEG} SELECT ident, vt_s, vt_e, tt_s, CASE WHEN tt_e > {PINNED} THEN {OPEN} ELSE tt_e END AS tt_e, w FROM seg WHERE tt_s <= {PINNED} AND tt_e > {PINNED}")
def scoped_versions(spark, d):
    """All versions believed at the pin, with ends that were not known then hidden."""
    return scope(segment_versions(c3(spark, d)), PINNED)


@query("tokens_per_task", f"WITH {SAID} SELECT count(*) AS tasks, round(avg(ceil(length(text) * 0.65)), 3) AS tokens FROM held")
def prompt_tokens(spark, d):
    """Tokens of prompts that each hold one chunk."""
    return tokens_per_task(retrieval.chunks(c1(spark, d), 24), "text")


# ---- studies ----------------------------------------------------------------------------------------------------------------------

query("study_main")(lambda s, d: workloads.main_study(s, d))
query("study_second_corpus")(lambda s, d: workloads.second_corpus_study(s, d))
query("study_probes")(lambda s, d: workloads.probe_study(s, d))
query("study_planted")(lambda s, d: workloads.planted_study(s, d))
query("study_ablations")(lambda s, d: workloads.ablation_study(s, d))
query("study_gate")(lambda s, d: workloads.gate_study(s, d))
query("study_planner_noise")(lambda s, d: workloads.sweep_study(s, d))
query("study_retrieval_breadth")(lambda s, d: workloads.breadth_study(s, d))
query("study_scale")(lambda s, d: workloads.scale_study(s, d))
query("mutation_rates")(lambda s, d: workloads.fault_study(s, d))

