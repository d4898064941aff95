"""Five hundred random (store, arguments) cases an operator against independent brute force, batched as one keyed table.

Cases share no node, identity or key, so one call answers all cases of one argument set. Stores hold ties in time, repeated edges, self loops,
negative node numbers, nulls and open ends.
"""

import random
from collections import Counter, defaultdict

import oracles
import pytest
from pyspark.sql import functions as F

from bitempo.operators import bandjoin, diff, history, intervals, motifs, neighbourhood, reach, series
from bitempo.substrate.fold import fold_versions
from bitempo.substrate.segments import belief_at, segment_versions
from bitempo.substrate.snapshots import snapshot

EDGE = "eid long, src long, dst long, t long, w double, etype string"
OPEN, STEP = 1 << 62, 100


def graphs(cases, seed, n=16, nodes=6, times=14):
    """{case: edges}; nodes of case c lie around c * STEP, so case 0 has node -1 and negative ones."""
    rnd, out, eid = random.Random(seed), {}, 0
    for c in range(cases):
        base, edges = (c - cases // 2) * STEP, []
        for _ in range(rnd.randrange(n)):
            eid += 1
            edges.append((eid, base - 1 + rnd.randrange(nodes), base - 1 + rnd.randrange(nodes), rnd.randrange(1, times)))
        out[c] = base, edges
    return out


def union(spark, cases):
    return spark.createDataFrame([(*e, 1.0, "e") for _, edges in cases.values() for e in edges], EDGE).repartition(4)


def case_of(node):
    return (node + STEP // 2) // STEP * STEP


@pytest.mark.parametrize("seed,kwargs", [(1, {}), (2, {"max_wait": 2}), (3, {"max_wait": 3, "strict": False}), (4, {"strict": False}), (5, {"max_hops": 2})])
def test_earliest_arrival(spark, seed, kwargs):
    cases = graphs(100, seed)
    starts = spark.createDataFrame([(base,) for base, _ in cases.values()], "node long")
    got = defaultdict(dict)
    for r in reach.earliest_arrival(union(spark, cases), starts, 0, 14, **kwargs).collect():
        got[r["source"]][r["node"]] = r["arrival"]
    for base, edges in cases.values():
        assert got[base] == oracles.reach(edges, base, 0, 14, **kwargs)


@pytest.mark.parametrize("k", [1, 2, 3])
def test_khop(spark, k):
    cases = graphs(170, 10 + k)
    seeds = spark.createDataFrame([(base + i,) for base, _ in cases.values() for i in (0, 1)], "node long")
    got = {r["node"]: r["hop"] for r in neighbourhood.khop_neighbourhood(union(spark, cases), seeds, k).collect()}
    wanted = {}
    for base, edges in cases.values():
        wanted |= oracles.khop(edges, [base, base + 1], k)
    assert got == wanted


@pytest.mark.parametrize("name", ["cyclic", "feed_forward", "path", "out_star", "in_star", "ping_pong"])
def test_motifs(spark, name):
    cases = graphs(84, hash(len(name)) + 20, n=11, nodes=5, times=8)
    rows = motifs.motif_rows(union(spark, cases), motifs.NAMED[name], 4).collect()
    got = Counter(case_of(r["nodes"][0]) for r in rows)
    for base, edges in cases.values():
        assert got[base] == oracles.motif_count(edges, motifs.NAMED[name], 4)
    assert motifs.count_motifs(union(spark, cases), motifs.NAMED[name], 4).first()[0] == len(rows)


def test_all_three_edge_motifs_with_a_node_minus_one(spark):
    cases = graphs(60, 31, n=9, nodes=4, times=6)
    got = {r["pattern"]: r["count"] for r in motifs.count_all_three_edge(union(spark, cases), 3).collect()}
    for name, pattern in motifs.three_edge_patterns().items():
        assert got.get(name, 0) == sum(oracles.motif_count(edges, pattern, 3) for _, edges in cases.values()), name
    four = spark.createDataFrame([(1, 0, 1, 1, 1.0, "e"), (2, 1, -1, 2, 1.0, "e"), (3, 1, 5, 3, 1.0, "e")], EDGE)
    assert motifs.count_all_three_edge(four, 10).count() == 0


def histories(cases, seed):
    rnd, rows, batch = random.Random(seed), {}, 0
    for c in range(cases):
        held, tt = [], 0
        for _ in range(rnd.randrange(1, 9)):
            batch += 1
            tt += rnd.randrange(1, 4)
            s = rnd.randrange(-3, 12)
            op = rnd.choice(("assert", "assert", "correct", "retract"))
            end = OPEN if op == "retract" or rnd.random() < 0.2 else s + rnd.randrange(-1, 8)
            held.append((batch, op, s, end, None if rnd.random() < 0.1 else float(rnd.randrange(4)), tt))
        rows[f"i{c}"] = held
    return rows


def operations(spark, cases):
    rows = [(b, 0, op, ident, s, e, w, tt) for ident, held in cases.items() for b, op, s, e, w, tt in held]
    return spark.createDataFrame(rows, "batch_id long, seq int, op string, ident string, vt_s long, vt_e long, w double, tt long").repartition(4)


def believed(versions, vt, tt):
    return [w for s, e, a, b, w in versions if s <= vt < e and a <= tt < b]


def test_history_snapshots_and_differences(spark):
    """Versions, history, diff and segments of 500 identities against writing one operation after the other."""
    cases = histories(500, 41)
    ops = operations(spark, cases)
    versions = fold_versions(ops).cache()
    wanted = {i: oracles.fold(held)[0] for i, held in cases.items()}
    got = defaultdict(list)
    for r in versions.select("ident", "vt_s", "vt_e", "tt_s", "tt_e", "w").collect():
        got[r["ident"]].append(tuple(r)[1:])
    key = lambda rows: sorted(rows, key=str)
    assert {i: key(v) for i, v in got.items()} == {i: key(v) for i, v in wanted.items() if v}
    for tt in (3, 8, None):
        now = OPEN - 1 if tt is None else tt
        for ident in ("i1", "i7", "i250"):
            seen = [(r["vt_s"], r["vt_e"], r["w"]) for r in history.version_history(versions, ident, tt).collect()]
            assert key(seen) == key([(s, e, w) for s, e, a, b, w in wanted[ident] if a <= now < b])
        changes = {r["ident"]: (r["change"], r["before"], r["after"]) for r in diff.diff_states(versions, 2, 7, tt).collect()}
        brute = {}
        for i, v in wanted.items():
            x, y = believed(v, 2, now), believed(v, 7, now)
            if bool(x) != bool(y):
                brute[i] = ("added", None, y[0]) if y else ("removed", x[0], None)
            elif x and x[0] != y[0]:
                brute[i] = ("changed", x[0], y[0])
        assert changes == brute
    # belief as sets takes operations that the fold admits
    strict = {i: {b for b, code in oracles.fold(held)[1] if code is None} for i, held in cases.items()}
    fine = operations(spark, {i: [o for o in held if o[0] in strict[i]] for i, held in cases.items()})
    for vt, tt in ((2, 4), (7, 9), (0, 30)):
        wanted_w = {i: believed(v, vt, tt)[0] for i, v in wanted.items() if believed(v, vt, tt)}
        assert {r["ident"]: r["w"] for r in belief_at(fine, vt, tt).collect()} == wanted_w
        assert {r["ident"]: r["w"] for r in snapshot(segment_versions(fine), vt, tt).collect()} == wanted_w


def test_interval_pairs_with_open_ends(spark):
    rnd, rows = random.Random(51), {"a": [], "b": []}
    for c in range(500):
        for side in "ab":
            for _ in range(rnd.randrange(4)):
                s = rnd.randrange(-5, 20)
                rows[side].append((len(rows[side]), c, s, OPEN if rnd.random() < 0.15 else s + rnd.randrange(0, 7)))
    df = lambda side: spark.createDataFrame(rows[side], "id long, src long, i_s long, i_e long")
    widened = {side: defaultdict(list) for side in "ab"}
    for side in "ab":
        for i, c, s, e in rows[side]:
            widened[side][c].append((i, (s, max(e, s + 1))))
    wanted = sorted((i, j, oracles.relation(x, y)) for c in range(500) for i, x in widened["a"][c] for j, y in widened["b"][c])
    got = sorted((r["a_id"], r["b_id"], r["relation"]) for r in intervals.interval_pairs(df("a"), df("b"), keys=("src",), width=3).collect())
    assert got == wanted
    with pytest.raises(ValueError, match="exceed"):
        bandjoin.interval_join(*[df(x).select(F.col("i_s").alias(f"{x}_s"), F.col("i_e").alias(f"{x}_e")) for x in "ab"], [], ("before",), 3, budget=1000)


def test_series_and_bursts(spark):
    """A bucket is a case: its statistics depend on its own edges, its score on the buckets before it."""
    rnd, edges = random.Random(61), []
    for b in range(500):
        for _ in range(rnd.randrange(6)):
            edges.append((len(edges), rnd.randrange(-2, 3), rnd.randrange(-2, 3), b * 10 + rnd.randrange(10)))
    df = spark.createDataFrame([(*e, 1.0, "e") for e in edges], EDGE)
    got = {r["bucket"]: r for r in series.metric_series(df, 0, 5000, 10).collect()}
    assert sorted(got) == list(range(0, 5000, 10))
    for b, r in got.items():
        mine = [(x, y) for _, x, y, t in edges if b <= t < b + 10 and x != y]
        assert r["nodes"] == len({n for e in mine for n in e}) and r["edges"] == len(mine)
        pairs = set(mine)
        assert abs(r["reciprocity"] - (round(sum((y, x) in pairs for x, y in pairs) / len(pairs), 9) if pairs else 0.0)) < 1e-8
    values = [(b, float(rnd.randrange(9))) for b in range(500)]
    found = {r["bucket"]: r["score"] for r in series.detect_bursts(spark.createDataFrame(values, "bucket long, value double"), "zscore", 6, 2.0).collect()}
    for b, v in values[6:]:
        past = [x for _, x in values[b - 6 : b]]
        mean = sum(past) / 6
        spread = (sum((x - mean) ** 2 for x in past) / 6) ** 0.5
        assert (found[b] is None) == (round(spread, 9) == 0) and (found[b] is None or abs(found[b] - (v - mean) / spread) < 1e-6)


def test_a_chain_of_seventy_edges_is_reached(spark):
    chain = spark.createDataFrame([(i, i, i + 1, i + 1, 1.0, "e") for i in range(70)], EDGE)
    assert reach.earliest_arrival(chain, spark.createDataFrame([(0,)], "node long"), 0, 100).agg(F.count("node"), F.max("arrival")).first() == (71, 70)
