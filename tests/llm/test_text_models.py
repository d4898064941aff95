import random
import zlib

import numpy as np
import pytest
from conftest_odd import ODD
from pyspark.sql import functions as F

from bitempo.llm import language, lm_score, toxicity
from bitempo.llm.common import fold_of, table


def brute_rank_order(text, profiles, top):
    """Out-of-place distance straight from its definition."""
    counts = {}
    for w in "".join([c if c.isalpha() else " " for c in text.lower()]).split():
        p = f" {w} "
        for gram in [*w, *[p[i : i + 2] for i in range(len(p) - 1)], *[p[i : i + 3] for i in range(len(p) - 2)]]:
            counts[gram] = counts.get(gram, 0) + 1
    own = sorted(counts, key=lambda g: (-counts[g], [ord(c) for c in g]))[:top]
    away = {lang: sum(min(abs(i - known.index(g)), top) if g in known else top for i, g in enumerate(own)) for lang, known in profiles.items()}
    return (min(away, key=lambda k: (away[k], k)) if own else "und"), away


def test_distances_equal_brute_force(spark, sf):
    docs = table(spark, sf, "documents")
    profiles = language.train(docs, top=60)
    one = language.Identifier(profiles, 60)
    for r in docs.limit(25).collect():
        assert one.identify(r["text"])[0] == brute_rank_order(r["text"], profiles, 60)[0]


def test_forgetting_does_not_change_results(spark, sf):
    docs = table(spark, sf, "documents")
    profiles = language.train(docs, top=60)
    texts = [r["text"] for r in docs.limit(40).collect()]
    a, b = language.Identifier(profiles, 60), language.Identifier(profiles, 60)
    b.counter.most_grams = 200
    assert [a.identify(t) for t in texts] == [b.identify(t) for t in texts]


def test_language_held_out(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    profiles = language.train(docs.where(fold_of("doc_id", 4) != 2))
    held = docs.where(fold_of("doc_id", 4) == 2).select("lang", language.predicted(F.col("text"), profiles).alias("p"))
    right, n = held.agg(F.sum((F.col("lang") == F.col("p.lang_pred")).cast("int")), F.count(F.lit(1))).first()
    assert right / n > 0.98


def test_language_of_odd_texts(spark, docs):
    df = docs(ODD)
    found = df.select("doc_id", "text", language.predicted(F.col("text"), language.train(df)).alias("p")).collect()
    assert len(found) == len(ODD)
    for r in found:
        letters = any(c.isalpha() for c in r["text"] or "")
        assert (r["p"]["lang_pred"] == "und") == (not letters) and 0 <= r["p"]["score"] <= 1
    assert language.train(docs([])) == {}
    assert df.limit(1).select(language.predicted(F.lit("abc"), {}).alias("p")).first()["p"]["lang_pred"] == "und"


@pytest.mark.parametrize("text,letters", [("½ ² ③", False), ("Ⅷ ² 12 _", False), ("x² + y³", True), ("ab½cd", True), ("", False), ("日本", True)])
def test_numbers_that_are_no_digits_are_no_letters(text, letters):
    profiles = {"aa": ["a", "b", "ab"], "xx": ["x", "y", "日"]}
    wanted = brute_rank_order(text, profiles, 10)[0]
    assert language.Identifier(profiles, 10).identify(text)[0] == wanted and (wanted != "und") == letters


def brute_marginals(model, words):
    """Forward-backward over every word."""
    if not words:
        return []
    step = np.exp(np.array(model.moves))
    local = [np.array([1.0, np.exp(np.clip(model.emission(w.lower()) + model.capitals * (len(w) > 1 and w.isupper()), -40, 40))]) for w in words]
    ahead = [local[0] / local[0].sum()]
    for x in local[1:]:
        row = (ahead[-1] @ step) * x
        ahead.append(row / row.sum())
    back = [np.ones(2)]
    for x in reversed(local[1:]):
        col = step @ (x * back[0])
        back.insert(0, col / col.sum())
    return [float((a * b)[1] / (a * b).sum()) for a, b in zip(ahead, back)]


def toy_model():
    rnd = random.Random(2)
    clean = ["the", "of", "house", "tree", "water", "blue", "stone", "river"]
    rows = []
    for i in range(400):
        words = [rnd.choice(clean) + rnd.choice(("", "s", "ing")) for _ in range(rnd.randrange(5, 40))]
        if i % 4 == 0:
            for _ in range(2):
                words.insert(rnd.randrange(len(words)), rnd.choice(("badword", "nastier", "NASTIER")))
        rows.append((" ".join(words), int(i % 4 == 0)))
    return toxicity.fit(rows, rounds=60)


@pytest.fixture(scope="module")
def model():
    return toy_model()


def test_collapsed_marginals_equal_full_forward_backward(model):
    rnd, tagger = random.Random(4), toxicity.Tagger(model)
    for _ in range(60):
        words = [rnd.choice(("tree", "badword", "NASTIER", "waters", "blue", "x")) if rnd.random() < 0.3 else "stone" for _ in range(rnd.randrange(1, 60))]
        p = brute_marginals(model, words)
        evidence, spans = tagger.evidence(" ".join(words))
        wanted = -sum(np.log(1 - x) for w, x in zip(words, p) if any(f in model.weights for f in toxicity.features(w.lower())))
        assert abs(evidence - wanted) < 1e-6 * max(1, wanted)
        assert len(spans) == sum(x >= 0.5 and (i == 0 or p[i - 1] < 0.5) for i, x in enumerate(p))


def test_capitals_without_a_feature_bear_on_their_neighbours():
    model = toxicity.Model({"w=bad": 9.0}, -4.0, ((0.5, -0.5), (-0.5, 1.0)), 0.0, 1.5, (1.0, 0.0))
    rnd, tagger = random.Random(5), toxicity.Tagger(model)
    for _ in range(80):
        words = [rnd.choice(("stone", "STONE", "Tree", "X", "bad", "BAD", "ÉTÉ")) for _ in range(rnd.randrange(1, 40))]
        p = brute_marginals(model, words)
        wanted = -sum(np.log(1 - x) for w, x in zip(words, p) if w.lower() == "bad")
        evidence, spans = tagger.evidence(" ".join(words))
        assert abs(evidence - wanted) < 1e-6 * max(1, wanted)
        if wanted:
            assert len(spans) == sum(x >= 0.5 and (i == 0 or p[i - 1] < 0.5) for i, x in enumerate(p))


def test_windows_cover_every_marked_word():
    words = [f"w{i}" if i % 7 else "bad" for i in range(500)]
    windows = toxicity._windows([words, words], [1, 0], {"w=bad"}, 24, random.Random(1))
    seen = {w for part, ys in windows for w in part}
    assert {"bad"} < seen and sum(sum(ys) for _, ys in windows) >= sum(w == "bad" for w in words)
    assert len(windows) <= 2 * (500 // 10 + 2)


def test_spans_are_offsets_of_the_words(model):
    text = "The river,  badword!! of NASTIER stone"
    score, spans = toxicity.Tagger(model).tag(text)
    assert score > 0.7 and [text[a:b] for a, b, _ in spans] == ["badword", "NASTIER"]
    assert toxicity.Tagger(model).tag("The river of stone")[0] < 0.3


def test_toxicity_of_odd_texts(spark, docs, model):
    found = docs(ODD).select("doc_id", toxicity.tagged(F.col("text"), model).alias("t")).collect()
    assert len(found) == len(ODD) and all(0 <= r["t"]["score"] < 0.5 and r["t"]["spans"] == [] for r in found)
    empty = toxicity.train(docs([]), spark.createDataFrame([], "doc_id long, toxic int"))
    assert toxicity.Tagger(empty).tag("badword") == (0.0, [])


def test_copies_of_one_text_are_one_piece_of_evidence():
    rows = [["rare", "words", "of", "one", "page", "badword"]] * 40 + [["stone", "badword", str(i)] for i in range(40)] + [["stone", "tree", str(i)] for i in range(80)]
    found = toxicity.telling_features(rows, [1] * 80 + [0] * 80)
    assert "w=badword" in found and "w=rare" not in found


def test_toxicity_held_out(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    trained = toxicity.train(docs, labels.where(fold_of("doc_id", 3) != 1))
    held = docs.join(labels, "doc_id").where(fold_of("doc_id", 3) == 1).select("toxic", toxicity.tagged(F.col("text"), trained)["score"].alias("s")).toPandas()
    flagged = held.s >= toxicity.THRESHOLD
    assert (held.toxic[flagged] == 1).mean() > 0.98 and flagged[held.toxic == 1].mean() > 0.9


def brute_counts(texts):
    out = np.zeros(lm_score.SIZE, np.int64)
    for t in texts:
        for places, spans in lm_score.packs([t]):
            np.add.at(out, lm_score.counted_places(places, spans), 1)
    return out


def test_counts_cover_all_texts_and_rows(spark, docs):
    df = docs(ODD).select("text", (F.col("source") == "a").alias("is_target")).fillna({"is_target": False})
    got = lm_score.ngram_counts(df.repartition(4)).toPandas()
    background, target = np.zeros(lm_score.SIZE, np.int64), np.zeros(lm_score.SIZE, np.int64)
    background[got["place"]], target[got["place"]] = got["background"], got["target"]
    assert (background == brute_counts([t for _, t, _, _ in ODD])).all()
    assert (target == brute_counts([t for _, t, _, s in ODD if s == "a"])).all()


def test_scores_do_not_depend_on_packing(spark, sf):
    texts = [r["text"] for r in table(spark, sf, "documents").limit(60).collect()]
    models = lm_score.Models(brute_counts(texts).astype(float), brute_counts(texts[:20]).astype(float))
    together = models.score(texts)
    alone = [models.score([t])[0] for t in texts]
    assert all(abs(a[3] - b[3]) < 1e-4 and a[0] == b[0] for a, b in zip(together, alone))
    assert models.score([None, ""]) == [(0, 0.0, 0.0, 0.0)] * 2
    assert lm_score.Models(brute_counts(texts).astype(float), np.zeros(lm_score.SIZE)).score(["abc"])[0][3] == 0.0


def test_lower_scores_are_more_like_the_target(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    german = docs.where("lang = 'de'").select("doc_id")
    found = lm_score.scored(docs, lm_score.train(docs, german)).join(docs.select("doc_id", "lang"), "doc_id").groupBy("lang").agg(F.avg("score").alias("s")).collect()
    by = {r["lang"]: r["s"] for r in found}
    assert by["de"] < min(v for k, v in by.items() if k != "de") and labels.count() > 0


def test_table_holds_every_ngram_and_scores_follow_the_definition(spark, docs):
    """Also where hashed places would run out: more distinct characters than places for them, more 4-grams than in any one script."""
    import math
    from collections import Counter

    wide = "".join(chr(c) for c in range(0x4E00, 0x4E00 + 6000))
    rows = [*ODD[:6], *ODD[8:], (20, wide, "zh", "a"), (21, wide[::-1], "zh", "b"), (22, "a\x00b", "en", "a")]
    df = docs(rows)
    models = lm_score.train(df, df.where("source = 'a'").select("doc_id"))
    ids = {i for i, _, _, s in rows if s == "a" and i is not None}
    counts = [Counter(), Counter()]
    clean = [(i, (t or "").lower().replace("\x00", "\x01")) for i, t, _, _ in rows]
    for i, t in clean:
        line = "\0\0\0" + t
        found = [line[e - k : e] for e in range(4, len(line) + 1) for k in (1, 2, 3, 4)] + ["\0", "\0\0", "\0\0\0"]
        counts[0].update(found)
        counts[1].update(found if i in ids else [])
    got = {}
    for r in models.counts.collect():
        codes = [r["high"] & 0x1FFFFF, *[r["low"] >> s & 0x1FFFFF for s in (42, 21, 0)]]
        got["".join(chr(c - 1) for c in codes if c)] = (r["background"], r["target"])
    assert got == {g: (n, counts[1][g]) for g, n in counts[0].items()} and sum(len(g) == 1 for g in got) > 1 << lm_score.PLACES[0]
    sizes = [sum(n for g, n in c.items() if len(g) == 1) for c in counts]
    letters, scale = sum(len(g) == 1 for g in counts[0]), sizes[1] / sizes[0]

    def loss(line, e, which):
        n = (lambda g: counts[0][g] * scale) if which == 0 else (lambda g: counts[1][g])
        p = (n(line[e - 1 : e]) + 4 / letters) / (sizes[1] + 4)
        for k in (2, 3, 4):
            p = (n(line[e - k : e]) + 4 * p) / (n(line[e - k : e - 1]) + 4)
        return -math.log(p)

    wanted = []
    for i, t in clean:
        line = "\0\0\0" + t
        means = [sum(loss(line, e, w) for e in range(4, len(line) + 1)) / max(len(t), 1) for w in (1, 0)]
        wanted.append((i or -1, len(t), *[round(x, 6) for x in (*means, means[0] - means[1])]))
    for again in (df, docs(rows)):  # the counted texts themselves, and others
        found = [(r["doc_id"] or -1, r["n_tokens"], *[round(r[c], 6) for c in ("target_loss", "background_loss", "score")]) for r in lm_score.scored(again, models).collect()]
        assert [x[:2] for x in sorted(found)] == [x[:2] for x in sorted(wanted)] and np.allclose(sorted(found), sorted(wanted), atol=2e-6)
    assert lm_score.scored(df, lm_score.train(df, df.limit(0).select("doc_id"))).where("score != 0 or target_loss != 0").count() == 0
    assert lm_score.scored(df.limit(0), lm_score.train(df.limit(0), df.select("doc_id"))).count() == 0


def test_fold(spark):
    df = spark.createDataFrame([(i,) for i in range(50)] + [(None,)], "doc_id long").select("doc_id", fold_of("doc_id", 3).alias("f"))
    assert all(r["f"] == (0 if r["doc_id"] is None else zlib.crc32(str(r["doc_id"]).encode()) % 3) for r in df.collect())


def test_scores_of_an_empty_table(spark, docs):
    none = spark.createDataFrame([], "doc_id long")
    assert lm_score.scored(docs([]).select("doc_id", "text"), lm_score.train(docs([]).select("doc_id", "text"), none)).count() == 0
