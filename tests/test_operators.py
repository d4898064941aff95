import random

import oracles
import pytest
from pyspark.sql import functions as F

from bitempo.functions.timeaxis import ALLEN, DAY, HOUR
from bitempo.operators import bandjoin, compute, diff, intervals, motifs, neighbourhood, paths, reach, resolve, series
from bitempo.sources import corpora

EDGE = "eid long, src long, dst long, t long, w double, etype string"


def graph(seed, n=40, nodes=7, times=30):
    rnd = random.Random(seed)
    return [(i, rnd.randrange(nodes), rnd.randrange(nodes), rnd.randrange(1, times)) for i in range(n)]


def frame(spark, edges):
    return spark.createDataFrame([(*e, 1.0, "e") for e in edges], EDGE)


def start(spark, *nodes):
    return spark.createDataFrame([(n,) for n in nodes], "node long")


def as_map(df):
    return {r["node"]: r["arrival"] for r in df.collect()}


@pytest.mark.parametrize("seed,wait,strict", [(1, None, True), (2, 3, True), (3, 5, True), (4, 4, False), (5, None, False)])
def test_reach_equals_label_search(spark, seed, wait, strict):
    edges = graph(seed)
    got = as_map(reach.earliest_arrival(frame(spark, edges), start(spark, 0), 0, 30, wait, strict=strict))
    assert got == oracles.reach(edges, 0, 0, 30, wait, strict)


def test_sweep_equals_label_search(spark):
    edges = graph(11)
    got = as_map(reach.sweep_arrivals(frame(spark, edges), 0, 0, 30, 3, 11))
    assert got == oracles.reach(edges, 0, 0, 30, 3)


def test_hop_limit(spark):
    edges = graph(12)
    assert as_map(reach.earliest_arrival(frame(spark, edges), start(spark, 0), 0, 30, max_hops=2)) == oracles.reach(edges, 0, 0, 30, max_hops=2)


def test_one_label_a_node_is_wrong_under_a_wait_limit(spark):
    edges = frame(spark, [(1, 0, 1, 1), (2, 0, 1, 5), (3, 1, 2, 8)])
    assert as_map(reach.earliest_arrival(edges, start(spark, 0), 0, 10, 4)) == {0: 0, 1: 1, 2: 8}
    assert 2 not in as_map(reach.earliest_arrival_greedy(edges, start(spark, 0), 0, 10, 4))


def test_reach_grows_with_window_and_wait(spark):
    edges = frame(spark, graph(13))
    sizes = [reach.earliest_arrival(edges, start(spark, 0), 0, end, wait).count() for end, wait in ((10, 2), (30, 2), (30, 6), (30, None))]
    assert sizes == sorted(sizes)


@pytest.mark.parametrize("seed", [1, 2])
def test_paths_equal_enumeration(spark, seed):
    edges = graph(seed, 30)
    got = [(r["arrives"], r["hops"], r["eids"], r["nodes"]) for r in paths.time_respecting_paths(frame(spark, edges), 0, 3, 0, 30, 10, 3).orderBy("rank").collect()]
    assert got == oracles.paths(edges, 0, 3, 0, 30, 10, 3)


def test_path_bounds(spark):
    with pytest.raises(ValueError):
        paths.time_respecting_paths(frame(spark, []), 0, 1, 0, 1, k=21)
    with pytest.raises(ValueError):
        neighbourhood.khop_neighbourhood(frame(spark, []), start(spark, 0), 4)


@pytest.mark.parametrize("seed", [1, 2])
def test_all_three_edge_motifs_equal_enumeration(spark, seed):
    edges = graph(seed, 22, 4, 12)  # many ties in time
    got = {r["pattern"]: r["count"] for r in motifs.count_all_three_edge(frame(spark, edges), 5).collect()}
    for name, pattern in motifs.three_edge_patterns().items():
        assert got.get(name, 0) == oracles.motif_count(edges, pattern, 5), name


@pytest.mark.parametrize("name", list(motifs.NAMED))
def test_named_motifs(spark, name):
    edges = graph(3, 18, 5, 10)
    pattern = motifs.NAMED[name]
    wanted = oracles.motif_count(edges, pattern, 4)
    assert motifs.count_motifs(frame(spark, edges), pattern, 4).first()["count"] == wanted == motifs.motif_rows(frame(spark, edges), pattern, 4).count()


def test_motif_counts_do_not_change_when_nodes_are_renamed(spark):
    edges = graph(4, 25, 5, 12)
    renamed = [(e, 100 - a, 100 - b, t) for e, a, b, t in edges]
    count = lambda g: motifs.count_motifs(frame(spark, g), motifs.NAMED["cyclic"], 5).first()["count"]
    assert count(edges) == count(renamed)


@pytest.mark.parametrize("k", [1, 2, 3])
def test_khop(spark, k):
    edges = graph(5, 12, 9)
    got = {r["node"]: r["hop"] for r in neighbourhood.khop_neighbourhood(frame(spark, edges), start(spark, 0, 1), k).collect()}
    assert got == oracles.khop(edges, [0, 1], k)


def test_interval_pairs_of_every_relation(spark):
    rnd = random.Random(3)
    make = lambda n, at: [(at + i, rnd.randrange(3), s := rnd.randrange(20), s + rnd.randrange(0, 6)) for i in range(n)]  # noqa: E731, F841
    a, b = make(30, 0), make(30, 100)
    df = lambda rows: spark.createDataFrame(rows, "id long, src long, i_s long, i_e long")
    wanted = sorted((x[0], y[0], oracles.relation((x[2], max(x[3], x[2] + 1)), (y[2], max(y[3], y[2] + 1)))) for x in a for y in b if x[1] == y[1])
    got = intervals.interval_pairs(df(a), df(b), ALLEN, ("src",), width=4)
    assert sorted((r["a_id"], r["b_id"], r["relation"]) for r in got.collect()) == wanted
    counts = {r["relation"]: r["pairs"] for r in intervals.relation_counts(df(a), df(b), ("src",), width=4).collect()}
    assert counts == {r: n for r in ALLEN if (n := sum(w[2] == r for w in wanted))}


def test_band_join_meets_each_pair_once(spark):
    a = spark.createDataFrame([(1, t) for t in range(0, 30, 3)], "k int, x long")
    b = spark.createDataFrame([(1, t) for t in range(30)], "k int, y long")
    got = sorted((r["x"], r["y"]) for r in bandjoin.band_join(a, b, ["k"], 7, "x", "y").collect())
    assert got == sorted((x, y) for x in range(0, 30, 3) for y in range(30) if 0 <= y - x <= 7)
    assert sorted((r["x"], r["y"]) for r in bandjoin.salted_join(a, b, ["k"], 3).collect()) == sorted((x, y) for x in range(0, 30, 3) for y in range(30))


def test_series_has_empty_buckets_and_reciprocity(spark):
    edges = frame(spark, [(1, 0, 1, 1), (2, 1, 0, 2), (3, 0, 2, 3), (4, 0, 2, 25)])
    got = [tuple(r) for r in series.metric_series(edges, 0, 40, 10).orderBy("bucket").collect()]
    assert got == [(0, 3, 3, 2.0, 3, round(2 / 3, 9)), (10, 0, 0, 0.0, 0, 0.0), (20, 2, 1, 1.0, 1, 0.0), (30, 0, 0, 0.0, 0, 0.0)]


def test_bursts_do_not_see_themselves(spark):
    values = [1.0, 2.0, 1.0, 2.0, 9.0, 1.0, 1.0, 1.0, 1.0, 1.0]
    s = spark.createDataFrame(list(enumerate(values)), "bucket long, value double")
    z = {r["bucket"]: r for r in series.detect_bursts(s, "zscore", 4, 3.0).collect()}
    assert [b for b, r in z.items() if r["is_burst"]] == [4] and z[4]["baseline"] == 1.5 and z[0]["score"] is None and z[9]["score"] is None
    m = series.detect_bursts(s, "median", 4, 3.0)
    assert [r["bucket"] for r in m.where("is_burst").collect()] == [4]


def test_diff_composition(spark, sf):
    from bitempo import queries

    rows = lambda df: sorted(map(tuple, df.collect()), key=str)
    assert rows(queries.o3_diff(spark, sf)) == rows(queries.o3_diff_composition(spark, sf))


def test_names(spark, sf):
    names = resolve.names_table(spark, sf)
    assert resolve.resolve_names(names, "FRANCE", "folded").count() <= 1
    assert resolve.resolve_names(names, "no such name", "fuzzy").count() == 0
    part = names.where("type = 'part'").groupBy("name").count().where("count > 1").first()
    assert all(r["ambiguous"] for r in resolve.resolve_names(names, part["name"], "exact").collect())


def test_sums_do_not_depend_on_partitions(spark):
    df = spark.range(1000).select((F.col("id") * 0.1).alias("x"))
    assert compute.compute(df, "sum", "x").first()[0] == compute.compute(df.repartition(9).orderBy(F.desc("x")), "sum", "x").first()[0]


def test_corpus_figures(spark, sf):
    edges = corpora.message_edges(spark, sf)
    assert (edges.select("src", "dst").distinct().count(), motifs.count_motifs(edges, motifs.NAMED["cyclic"], 6 * HOUR).first()[0], motifs.count_motifs(edges, motifs.NAMED["cyclic"], 24 * HOUR).first()[0]) == (208, 9, 119)
    t0 = edges.agg(F.min("t")).first()[0]
    for wait, wanted in ((12 * HOUR, (14, 1704723688153455)), (24 * HOUR, (15, 1704317452463880)), (None, (15, 1704281032769993))):
        assert tuple(reach.earliest_arrival(edges, start(spark, 0), t0, t0 + 10 * DAY, wait).agg(F.count(F.lit(1)), F.max("arrival")).first()) == wanted


def test_diff_edges_against_sets(spark):
    edges = graph(8, 40, 5, 40)
    got = {(r["src"], r["dst"]): r["change"] for r in diff.diff_edges(frame(spark, edges), 10, 30, 8).collect()}
    live = lambda t: {(a, b) for _, a, b, x in edges if t - 8 < x <= t}
    assert {p for p, c in got.items() if c == "added"} == live(30) - live(10) and {p for p, c in got.items() if c == "removed"} == live(10) - live(30)


def test_trade_queries_read_the_whole_graph(spark, sf):
    from bitempo import workloads
    from bitempo.functions.timeaxis import DAY
    from bitempo.queries import QUERIES
    from bitempo.sources import corpora

    edges = sorted(tuple(r) for r in corpora.trade_edges(spark, sf).select("t", "eid", "src", "dst").collect())
    wanted = 0
    for i, (t0, _, a, b) in enumerate(edges):
        near = []
        for e in edges[i + 1 :]:
            if e[0] - t0 > DAY:
                break
            near.append(e)
        for j, (_, _, x, c) in enumerate(near):
            if x == b and len({a, b, c}) == 3:
                wanted += sum(y == c and z == a for _, _, y, z in near[j + 1 :])
    assert QUERIES["o6_cyclic_trade_whole"](spark, sf).first()["count"] == wanted > 0
    store = workloads.trade_store(spark, sf)
    assert store.edges.count() == len(edges) == spark.read.parquet(f"{sf}/lineitem.parquet").count()


def test_cycles_are_counted_without_making_them(spark):
    n = 3000
    edges = spark.range(3 * n).selectExpr("id as eid", "id div 3000 as src", "(id div 3000 + 1) % 3 as dst", "id as t")
    assert motifs.count_motifs(edges, motifs.NAMED["cyclic"], 3 * n).first()["count"] == n**3  # 27 thousand million triples of 9,000 edges
    # the last of the first edges is alone in reaching the last edge when delta is short by its time
    assert motifs.count_motifs(edges, motifs.NAMED["cyclic"], 2 * n).first()["count"] == n * sum(range(1, n + 1))


def test_cycles_over_slices_and_ties(spark):
    from bitempo.operators.cycles import count_cycles

    rnd = random.Random(5)
    rows = [(rnd.randrange(60), rnd.randrange(4), rnd.randrange(4), rnd.randrange(12) * HOUR // 2) for _ in range(120)]
    edges = spark.createDataFrame(rows, "eid long, src long, dst long, t long")
    for delta in (0, HOUR // 2, HOUR, 3 * HOUR):
        assert count_cycles(edges, delta).first()["count"] == motifs.motif_rows(edges, motifs.NAMED["cyclic"], delta).count()
    assert count_cycles(edges.where("false"), HOUR).first()["count"] == 0
