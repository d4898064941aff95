import hashlib
import random

import numpy as np
import pytest
from conftest_odd import ODD
from pyspark.sql import functions as F

from bitempo.llm import components, html_text, matroska, mixing, simhash, topk
from bitempo.llm import queries as llm_queries


# ---- SimHash ------------------------------------------------------------------------------------------------------------------------


def slow_print(text):
    import xxhash

    words = (text or "").encode().lower().split()
    shingles = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    hashes = [xxhash.xxh64(s, seed=42).intdigest() for s in shingles]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes)) if hashes else 0


def test_fingerprints():
    for t in [t for _, t, _, _ in ODD if len(t or "") < 6000] + ["A b", "É À b", "a b c d", "a\x0bb\x0cc\xa0d"]:
        assert simhash.text_fingerprint(t) == slow_print(t), t


def brute_classes(values, bits=2):
    parent = {v: v for v in values}

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    held = sorted(parent)
    for i, a in enumerate(held):
        for b in held[i + 1 :]:
            if (a ^ b).bit_count() <= bits:
                parent[root(a)] = root(b)
    groups = {}
    for v in held:
        groups.setdefault(root(v), set()).add(v)
    return sorted(map(sorted, groups.values()))


def signed(v):
    return v - (1 << 64) if v >> 63 else v


@pytest.mark.parametrize("seed", [7, 8])
def test_links_give_the_classes_of_all_pairs(spark, seed):
    rnd, values = random.Random(seed), set()
    for _ in range(12):
        v = rnd.getrandbits(64)
        for _ in range(rnd.choice((1, 4, 40))):  # some dense groups, with chains
            values.add(v)
            for _ in range(rnd.choice((1, 2, 2, 3))):
                v ^= 1 << rnd.randrange(64)
    values |= {0, 1, (1 << 64) - 1, 1 << 63}
    prints = spark.createDataFrame([(signed(v),) for v in values], "fp long")
    links = [(r["u"] % (1 << 64), r["v"] % (1 << 64)) for r in simhash.fingerprint_links(prints).collect()]
    assert sorted({tuple(sorted(p)) for p in links}) == sorted((a, b) for a in values for b in values if a < b and (a ^ b).bit_count() <= 2) and len(links) == len(set(links))
    found = {r["node"]: r["root"] for r in components.components(spark.createDataFrame([(signed(a), signed(b)) for a, b in links], "u long, v long")).collect()}
    groups = {}
    for v in values:
        groups.setdefault(found.get(signed(v), signed(v)), set()).add(v)
    assert sorted(map(sorted, groups.values())) == brute_classes(values)


def test_index_tallies_shared_bytes():
    """A pair meets in as many lists as six positions can be chosen from the bytes that it shares."""
    rnd, index = random.Random(9), simhash.Index()
    for flips in ((3,), (3, 5), (3, 60), (63,), (0, 63)):
        a = rnd.getrandbits(64)
        b = a ^ sum(1 << f for f in flips)
        lists, left = index.postings(np.array([a, b], np.uint64))
        assert [int(x) % (1 << 64) for x in index.fingerprints(lists, left)] == [a, b] * 28
        order = np.lexsort((left, lists))
        u, v = index.near(lists[order], left[order])
        shared = sum((a >> 8 * i & 255) == (b >> 8 * i & 255) for i in range(8))
        assert len(u) == len(v) == (7 if shared == 7 else 1)


def test_one_list_of_all_its_members():
    """65,536 fingerprints of one list are linked without pairing all with all."""
    index = simhash.Index()
    lists, left = index.postings(np.arange(1 << 16, dtype=np.uint64) << np.uint64(16))
    chosen = lists == lists[np.flatnonzero(np.bincount(np.unique(lists, return_inverse=True)[1])[np.unique(lists, return_inverse=True)[1]] == 1 << 16)[0]]
    order = np.argsort(left[chosen])
    u, _ = index.near(lists[chosen][order], left[chosen][order])
    assert len(u) == (1 << 16) * (16 + 120) // 2


def test_copies_of_one_text_are_dealt_over_tasks(spark, docs):
    rows = [(i, "one two three four" if i % 3 else f"text {i} of its own", "en", "a") for i in range(300)]
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicate_classes(docs(rows)).collect()}
    assert len(got) == 300 and {got[i] for i in range(300) if i % 3} == {1} and all(got[i] <= i for i in got)


def test_components_of_a_long_chain_and_a_hub(spark):
    rows = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 300)] + [(5, 5), (7, 6)]
    found = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(rows, "u long, v long")).collect()}
    assert all(found[i] == 0 for i in range(201)) and all(found[1000 + i] == 1000 for i in range(300)) and len(found) == 501
    assert components.components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_near_duplicates_of_odd_texts(spark, docs):
    got = simhash.near_duplicate_classes(docs(ODD)).collect()
    assert len(got) == len(ODD)
    same = {r["component_id"] for r in got if r["fp"] == signed(slow_print("one two three"))}
    assert same == {8}
    assert {r["component_id"] for r in got if r["fp"] == 0} == {1}
    assert simhash.near_duplicate_classes(docs([])).count() == 0


def test_one_of_each_class_keeps_columns_and_rows(spark, docs):
    df = docs(ODD)
    kept = simhash.one_of_each_class(df)
    assert kept.columns == df.columns
    rows = kept.collect()
    assert sorted(r["doc_id"] for r in rows if r["doc_id"] is not None) == [1, 3, 5, 6, 7, 8, 9, 10]
    assert len(rows) == 8 and simhash.one_of_each_class(docs([])).count() == 0


# ---- mixing -------------------------------------------------------------------------------------------------------------------------


def brute_targets(sizes):
    """Reshare the excess until no source is above three times its size."""
    names = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: i % 3 + 1 for i, s in enumerate(names)}
    total, fixed = sum(sizes.values()), {}
    while True:
        open_names = [s for s in names if s not in fixed]
        left = total - sum(fixed.values())
        if not open_names:
            return fixed
        share = {s: left * weight[s] / sum(weight[x] for x in open_names) for s in open_names}
        above = [s for s in open_names if share[s] > 3 * sizes[s]]
        if not above:
            return fixed | share
        fixed |= {s: 3 * sizes[s] for s in above}


@pytest.mark.parametrize("sizes", [{"a": 100, "b": 10, "c": 1, None: 4000}, {"a": 5}, {"a": 0, "b": 7}, {"x": 900, "y": 900, "z": 900, "é": 2, "Z": 50}])
def test_targets(spark, sizes):
    rows = spark.createDataFrame([(i, s, n) for i, (s, n) in enumerate(sizes.items())], "doc_id long, source string, size long")
    got = {r["source"]: r["target"] for r in mixing.source_targets(rows).collect()}
    wanted = brute_targets(sizes)
    assert set(got) == set(wanted) and all(abs(got[s] - wanted[s]) < 1e-6 for s in wanted)


def test_mix_of_odd_rows(spark, docs):
    df = docs(ODD)
    got = mixing.mixed(df, block=8, shard=256).collect()
    assert len(got) == len(ODD)
    import re

    size = {(i, len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))) for i, t, _, _ in ODD}
    assert {(r["doc_id"], r["size"]) for r in got} == size
    assert all(0 <= r["taken"] <= 3 * r["size"] for r in got)
    again = mixing.mixed(df.repartition(3), block=8, shard=256).collect()
    key = lambda rows: sorted((str(r["doc_id"]), r["size"], r["taken"]) for r in rows)
    assert key(got) == key(again)
    assert mixing.mixed(docs([])).count() == 0


def test_shards_and_permutations(spark):
    rnd = random.Random(3)
    rows = [(i, f"w{i} " * rnd.randrange(1, 60), "en", rnd.choice("aaaabbc")) for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    sizes = mixing.document_sizes(df)
    sources = mixing.source_targets(sizes, 4).cache()
    counts = mixing.shard_counts(sources, 100)
    per = {r["shard"]: r["n"] for r in counts.groupBy("shard").agg(F.sum("slots").alias("n")).collect()}
    assert all(n == 100 for s, n in per.items() if s < max(per))
    expected = {r["no"]: r["share"] for r in sources.collect()}
    total = sum(expected.values())
    spread = {}
    for r in counts.where(F.col("shard") < max(per)).collect():
        spread.setdefault(r["no"], []).append(r["slots"])
    for no, seen in spread.items():  # multinomial: shards differ, about as much as draws do
        p = expected[no] / total
        assert np.var(seen) > 0.2 * 100 * p * (1 - p) and abs(np.mean(seen) - 100 * p) < 5 * (100 * p * (1 - p) / len(seen)) ** 0.5
    whole = spark.createDataFrame([(0, r["no"], 2 * r["blocks"]) for r in sources.collect()], "shard long, no long, slots long")
    for r in mixing.mix_slots(whole, sources).groupBy("no", "epoch").agg(F.collect_list("block").alias("b")).collect():
        assert sorted(r["b"]) == list(range(len(r["b"]))) and (len(r["b"]) < 9 or r["b"] != sorted(r["b"]))
    mix = mixing.mixed(df, 4, 100)
    for r in mix.groupBy("source_size", "target").agg(F.sum("taken").alias("t")).collect():
        assert abs(r["t"] - r["target"]) <= 0.1 * r["target"] + 40


def test_every_size_is_permuted(spark):
    keys = [123_456_789, 987_654, 31_337, 2_000_000_011, 77, 1_234]
    rows = spark.createDataFrame([(n, n, i, keys) for n in [*range(1, 40), 97, 1000] for i in range(n)], "size long, n long, index long, keys array<long>")
    found = mixing.permuted(rows).groupBy("size").agg(F.sort_array(F.collect_list("block")).alias("p")).collect()
    assert len(found) == 41 and all(r["p"] == list(range(r["size"])) for r in found)
    wide = mixing.permuted(spark.range(2000).select(F.col("id").alias("index"), F.lit(10**13).alias("n"), F.lit(keys).cast("array<long>").alias("keys"))).agg(F.countDistinct("block"), F.max("block"), F.min("block")).first()
    assert wide[0] == 2000 and wide[1] < 10**13 and wide[1] - wide[2] > 9 * 10**12


def test_mixed_documents_keep_columns(spark, docs):
    df = docs([(i, f"word{i} " * 50, "en", "ab"[i % 2]) for i in range(60)])
    out = mixing.mixed_documents(df, block=8, shard=64)
    assert out.columns == df.columns and 0 < out.count() <= 180


# ---- top-k --------------------------------------------------------------------------------------------------------------------------


def brute_top(rows, queries, k=5):
    ready = [(i, [int(np.floor(256 * float(x))) for x in v]) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    width = max((len(v) for _, v in ready), default=0)
    ready = [(i, v + [0] * (width - len(v))) for i, v in ready]
    out = set()
    for q, qv in ready:
        if q in queries:
            scored = sorted(((-sum(a * b for a, b in zip(qv, v)), i) for i, v in ready if i != q))[:k]
            out |= {(q, n + 1, i, -s) for n, (s, i) in enumerate(scored)}
    return out


@pytest.mark.parametrize("case", ["plain", "ties", "large"])
def test_top_k_equals_brute_force(spark, case):
    rnd = random.Random(case)
    scale = {"plain": 1.0, "ties": 0.02, "large": 3e6}[case]
    rows = [(i, [float(np.float32(rnd.gauss(0, scale))) for _ in range(6)]) for i in range(120)]
    rows += [(200, None), (201, [1.0, None, 2.0, 0.0, 0.0, 0.0]), (202, [float("nan")] * 6), (203, [float("inf")] * 6), (204, [0.5]), (None, [1.0] * 6), (205, [0.0] * 6)]
    df = spark.createDataFrame([(i, v, 9.0) for i, v in rows], "vec_id long, embedding array<float>, score double").repartition(4)
    queries = {i for i in range(0, 120, 7)} | {200, 204, 205}
    got = topk.top_k(df, df.where(F.col("vec_id").isin(*queries)), at_once=9, block=16).collect()
    assert {tuple(r) for r in got} == brute_top(rows, queries)


def test_repeated_query_rows_have_results_of_their_own(spark):
    """Also against DuckDB with the registered SQL."""
    import duckdb

    rnd = random.Random(6)
    rows = [(i, [rnd.gauss(0, 1) for _ in range(8)]) for i in range(1, 60)] + [(50, [rnd.gauss(0, 1) for _ in range(8)])] * 2 + [(7, [0.5] * 8)] * 2
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3)
    got = sorted(tuple(r) for r in topk.top_k(df, df.where("vec_id % 50 = 0"), block=8).collect())
    embeddings = df.toPandas()  # noqa: F841  read by DuckDB
    assert got == sorted(duckdb.sql(topk.ORACLE).fetchall()) and len(got) == 15


def test_reading_stops_before_the_ends_of_skewed_lists():
    rnd = np.random.default_rng(2)
    x = np.floor(rnd.pareto(1.0, (4096, 8)) * 100)
    lists, q = topk.SortedLists(x, np.float64), np.ones((3, 8))
    at, c, scores, depth = topk.block_top_k(lists, np.arange(4096), q, np.full(3, -1), 5, np.full(3, -np.inf))
    assert depth < 4096 and all(sorted(scores[at == i])[-5:] == sorted((q[i] * x).sum(axis=1))[-5:] for i in range(3))


def test_top_k_of_few_rows(spark):
    one = spark.createDataFrame([(0, [1.0, 2.0])], "vec_id long, embedding array<float>")
    assert topk.top_k(one, one).count() == 0 and topk.top_k(one.limit(0), one.limit(0)).count() == 0


def test_bounds_hold_at_every_depth():
    rnd = np.random.default_rng(1)
    x, q = rnd.integers(-40, 40, (50, 7)).astype(float), rnd.integers(-40, 40, (9, 7)).astype(float)
    lists, exact = topk.SortedLists(x, np.float64), q @ x.T
    for depth in (1, 5, 20, 50):
        low, high = lists.lower(np.maximum(q, 0), np.minimum(q, 0), depth), lists.upper(np.maximum(q, 0), np.minimum(q, 0), depth)
        assert (low <= exact).all() and (exact <= high).all()
    assert (low == exact).all() and (high == exact).all()


# ---- media --------------------------------------------------------------------------------------------------------------------------


def test_audio_round_trip_of_odd_texts(spark, docs):
    df = docs(ODD).select("doc_id", "text", matroska.audio(F.col("text")).alias("m"))
    for r in df.select("text", "m", matroska.read_back(F.col("m")).alias("d")).collect():
        payload, n = matroska.padded(r["text"])
        assert len(payload) % 64 == 0 and len(payload) >= max(64, n) and payload[:n] == (r["text"] or "").encode()
        assert r["d"]["payload_sha256"] == hashlib.sha256(payload).hexdigest() and r["d"]["media_bytes"] == len(r["m"])
        media = matroska.read_file(bytes(r["m"]))
        assert all(r["m"][media.segment + c : media.segment + c + 4] == b"\x1f\x43\xb6\x75" for _, _, c in media.cues) and media.tracks[1]["codec"] == "A_PCM/INT/LIT"


def xiph(frames):
    head = bytes([len(frames) - 1])
    for f in frames[:-1]:
        head += b"\xff" * (len(f) // 255) + bytes([len(f) % 255])
    return head + b"".join(frames)


def test_every_lacing():
    rnd = random.Random(5)
    for _ in range(200):
        frames = [rnd.randbytes(rnd.randrange(1, rnd.choice((3, 300, 20000)))) for _ in range(rnd.randrange(1, 9))]
        flag, data = matroska.lace(frames)
        assert [data[a : a + n] for a, n in matroska._frames(data, 0, len(data), flag >> 1)] == frames
        if len(frames) > 1:
            data = xiph(frames)
            assert [data[a : a + n] for a, n in matroska._frames(data, 0, len(data), 1)] == frames


def test_unknown_sizes_block_groups_and_broken_files():
    block = matroska.element(matroska.BLOCK, b"\x81\x00\x05\x00" + b"abc")
    cluster = lambda at: matroska.CLUSTER.to_bytes(4, "big") + b"\xff" + matroska.number(matroska.TIMESTAMP, at) + matroska.element(matroska.BLOCK_GROUP, block)
    data = matroska._HEAD + matroska.SEGMENT.to_bytes(4, "big") + b"\x01" + b"\xff" * 7 + matroska._SETUP + cluster(10) + cluster(900)
    found = matroska.read_file(data)
    assert [(p[0], p[1], data[p[2] : p[2] + p[3]]) for p in found.packets] == [(1, 15.0, b"abc"), (1, 905.0, b"abc")]
    whole = matroska.write_audio(bytes(range(256)) * 80)
    n = len(matroska.read_file(whole).packets)
    assert n == 20 and all(len(matroska.read_file(whole[:cut]).packets) <= n for cut in range(0, len(whole), 997))
    assert matroska.read_file(None).packets == [] and matroska.read_file(b"").packets == []
    times = [p[1] for p in matroska.read_file(whole).packets]
    assert times == [i * 128.0 for i in range(20)]


# ---- pages --------------------------------------------------------------------------------------------------------------------------

ROUND = (
    '<html><head><title>t</title><script>var a="</p>";</script></head><body><header><h1>Site</h1></header><nav><a href=x>Home</a></nav><div class="cookie-notice">ok?</div>{0}'
    '<div class="sidebar">More</div><form>f<input></form><section id="comments"><p>nice</p></section><footer>&copy; c</footer></body></html>'
)


def test_article_text():
    page = ROUND.format("<article><header><h1>Ti&amp;tle</h1></header><p>One <b>b</b>old<p>Two&nbsp;x <br>three<!-- no --></article>")
    assert html_text.main_text(page) == "Ti&tle One bold Two x three"
    assert html_text.main_text(page[: page.index("three") + 5]) == "Ti&tle One bold Two x three"
    for odd in (None, "", "<", "<!--", "<p", "<script>x"):
        assert html_text.main_text(odd) in ("", "<")


def test_templates_fill_slots_without_an_article(spark):
    pages = [(i, f"http://h.example/{i}", ROUND.format(f"<div class=lead>Always the same words here</div><div class=body><p>Page {i} tells of number {i * 7}.</p></div>")) for i in range(12)]
    pages += [(50, None, None), (51, "http://h.example/51", ""), (52, "http://other.example/", "<p>alone</p>"), (52, "http://other.example/", "<p>alone</p>")]
    df = spark.createDataFrame([(*p, "x") for p in pages], "page_id long, url string, html string, text string")
    got = {r["page_id"]: (r["text"], r["n_chars"]) for r in html_text.extracted(df).collect()}
    for i in range(12):
        assert got[i][0] == f"Page {i} tells of number {i * 7}." and got[i][1] == len(got[i][0])
    assert got[50] == ("", 0) == got[51] and got[52] == ("alone", 5)
    assert html_text.extracted(df.limit(0)).count() == 0


def test_templates_decide_inside_articles(spark):
    """Unnamed repeats in an article go, also if a cut-off page lacks them; copies are no template; link-heavy slots stay."""
    notice, links = "<p>Read our terms before you write.</p>", "<p><a href=y>Linked words of page {0}</a></p>"
    body = "<article><h1>Title {0}</h1>" + notice + "<p>Page {0} tells this.</p><div>All rights are with us.</div></article>"
    pages = [(i, f"http://h.example/{i}", ROUND.format(body.format(i))) for i in range(9)] + [(9, "http://h.example/9", ROUND.format("<article><h1>Title 9</h1><p>Page 9 tel"))]
    pages += [(20 + i, f"http://copies.example/{i}", ROUND.format("<article><p>The very same text of a page.</p></article>")) for i in range(5)]
    pages += [(30 + i, f"http://versions.example/{i}", ROUND.format(f"<article><p>The same text in both versions.</p><p>Version {i}</p></article>")) for i in range(2)]
    pages += [(40 + i, f"http://links.example/{i}", ROUND.format(f"<div class=body><p>Page {i} tells this.</p>{links.format(i)}</div>")) for i in range(4)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in html_text.extracted(df).collect()}
    assert [got[i] for i in range(9)] == [f"Title {i} Page {i} tells this." for i in range(9)] and got[9].startswith("Title 9 Page 9 tel")
    assert all(got[20 + i] == "The very same text of a page." for i in range(5))
    assert all(got[30 + i] == f"The same text in both versions. Version {i}" for i in range(2))
    assert all(got[40 + i] == f"Page {i} tells this. Linked words of page {i}" for i in range(4))


def test_given_pages_equal_their_articles(spark, sf):
    import re
    from html import unescape

    for r in spark.read.parquet(f"{sf}/pages.parquet").collect():
        inner = re.search(r"<article>(.*?)(?:</article>|$)", r["html"], re.S)[1]
        assert html_text.main_text(r["html"]) == " ".join(unescape(re.sub(r"<[^>]*(?:>|$)", " ", inner)).split())


def test_registered_queries_run(spark, sf):
    assert {int(n[2:].split("_")[0]) for n in llm_queries.QUERIES} == set(range(1, 11))
    import duckdb

    c = duckdb.connect()
    for t in ("documents", "embeddings"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')").fetchall()
    for name, sql in llm_queries.ORACLES.items():
        got, wanted = llm_queries.QUERIES[name](spark, sf).toPandas(), c.execute(sql).df()
        columns = sorted(wanted.columns)
        assert sorted(got.columns) == columns
        assert sorted(map(tuple, got[columns].values.tolist())) == sorted(map(tuple, wanted[columns].values.tolist()))


def brute_template(pages):
    """Fixed tokens of one host: classes of equal occurrence vectors over its different pages, straight from their definition."""
    distinct = sorted(set(p for p in pages if any(html_text.blocks_of(p))))
    counts, words, inside = {}, {}, {}
    for i, page in enumerate(distinct):
        blocks, boxes = html_text.blocks_of(page)
        for path, n in boxes.items():
            counts.setdefault(("box", path), [0] * len(distinct))[i] = n
        for path, text, _, article in blocks:
            key = ("text", path, text)
            counts.setdefault(key, [0] * len(distinct))[i] += 1
            words[key], inside[key] = len(text.split()), inside.get(key, False) or article
    classes = {}
    for key, vector in counts.items():
        held = sum(n > 0 for n in vector)
        if held > 1 and held >= 0.5 * len(distinct) and held >= (3 if inside.get(key) else 2):
            classes.setdefault(tuple(vector), []).append(key)
    every = tuple([1] * len(distinct))  # the root, which every page has once, is a container too
    fixed = set()
    for vector, keys in classes.items():
        texts = [k for k in keys if k[0] == "text"]
        if texts and (vector == every or any(k[0] == "box" for k in keys) or sum(words[k] for k in texts) >= html_text.LARGE):
            fixed |= {html_text.block_token(k[1], k[2]) for k in texts}
    return fixed


def test_templates_equal_brute_force_classes_on_random_pages(spark):
    rnd, rows = random.Random(12), []
    wrap = ("<div class='x'>{}</div>", "<article>{}</article>", "<div class='promo-box'>{}</div>", "<section><p>{}</p></section>", "<ul><li>{}</li></ul>")
    for host in range(8):
        fixed = [rnd.choice(wrap).format(" ".join(rnd.choice("abcdefg") * 3 for _ in range(rnd.randrange(1, 5)))) for _ in range(5)]
        for n in range(rnd.randrange(1, 9)):
            parts = [p for p in fixed if rnd.random() < 0.8] * rnd.choice((1, 1, 2)) + [rnd.choice(wrap).format(f"own words of {host} {n} {rnd.random()}") for _ in range(rnd.randrange(3))]
            rnd.shuffle(parts)
            page = "<html><body>" + "".join(parts) + "</body></html>"
            rows += [(f"h{host}", page)] * rnd.choice((1, 1, 3))  # repeated rows are one page
    df = spark.createDataFrame(rows, "host string, html string")
    got = {r["host"]: set(r["fixed"]) for r in html_text.templates(df).collect()}
    wanted = {h: brute_template([p for x, p in rows if x == h]) for h in {h for h, _ in rows}}
    assert got == {h: f for h, f in wanted.items() if f} and len(got) > 3


def test_media_of_an_empty_table(spark, docs):
    assert docs([]).select(matroska.read_back(matroska.audio(F.col("text"))).alias("d")).count() == 0
