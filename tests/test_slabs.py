import random

import pytest

from bitempo.functions.timeaxis import OPEN_END
from bitempo.operators import slabs
from bitempo.substrate.fold import fold_in_batches
from bitempo.substrate.segments import segment_versions
from bitempo.substrate.snapshots import overlap_violations

OPS = "ident string, batch_id long, seq int, op string, vt_s long, vt_e long, tt long, w double"


def history(n: int, seed: int, ident: str, span: int) -> list[tuple]:
    rng, rows = random.Random(seed), []
    for i in range(n):
        s = rng.randrange(-span, span)
        op = rng.choice(["assert", "assert", "correct", "retract"])
        rows.append((ident, i, 0, op, s, rng.choice([s + rng.randrange(1, 9), OPEN_END]) if op != "retract" else s + 1, 100 + i, float(i)))
    return rows


@pytest.mark.parametrize("per", [1, 3, 64])
def test_versions_do_not_depend_on_slabs(spark, monkeypatch, per):
    monkeypatch.setattr(slabs, "PER_SLAB", per)
    rows = history(90, per, "long", 60) + history(1, 1, "one", 5) + history(7, 2, "tie", 2)
    ops = spark.createDataFrame(rows, OPS)
    got = segment_versions(ops).collect()
    want = fold_in_batches(ops, require_existing=False).collect()
    for ident in ("long", "one", "tie"):
        for vt in range(-70, 80, 3):
            for tt in (100, 120, 150, 189, 400):
                held = lambda v: sorted(r["w"] for r in v if r["ident"] == ident and r["vt_s"] <= vt < r["vt_e"] and r["tt_s"] <= tt < r["tt_e"])  # noqa: B023, E731
                assert held(got) == held(want)
    # neighbours of one operation and time are one version, whatever slabs cut them
    seen = {(r["ident"], r["w"], r["tt_s"], r["tt_e"], r["vt_s"]) for r in got}
    assert len(seen) == len(got) and not [r for r in got if (r["ident"], r["w"], r["tt_s"], r["tt_e"], r["vt_e"]) in seen]


def test_a_hot_identity_is_dealt(spark, monkeypatch):
    monkeypatch.setattr(slabs, "PER_SLAB", 16)
    df = spark.range(4000).selectExpr("'hot' as ident", "id * 10 as s", "id * 10 + 25 as e")
    layout = slabs.slab_layout(df, "ident", "s", "e")
    sizes = [r["count"] for r in slabs.over_slabs(df, layout, "ident", "s", "e").groupBy("slab").count().collect()]
    assert 240 <= len(sizes) <= 250 and max(sizes) < 24 and sum(sizes) >= 4000


@pytest.mark.parametrize("per", [1, 4, 64])
def test_violations_against_all_pairs(spark, monkeypatch, per):
    monkeypatch.setattr(slabs, "PER_SLAB", per)
    rng, rows = random.Random(per), set()
    while len(rows) < 60:
        s, t = rng.randrange(40), rng.randrange(40)
        rows.add((rng.choice("ab"), s, rng.choice([s + rng.randrange(1, 8), OPEN_END]), t, rng.choice([t + rng.randrange(1, 8), OPEN_END])))
    got = sorted(tuple(r) for r in overlap_violations(spark.createDataFrame(list(rows), "ident string, vt_s long, vt_e long, tt_s long, tt_e long")).collect())
    order = lambda r: (r[1], r[3], r[2], r[4])
    want = sorted((a[0], a[1], a[3], b[1], b[3]) for a in rows for b in rows if a[0] == b[0] and order(a) < order(b) and max(a[1], b[1]) < min(a[2], b[2]) and max(a[3], b[3]) < min(a[4], b[4]))
    assert got == want and want


def test_empty_histories(spark):
    assert segment_versions(spark.createDataFrame([], OPS)).count() == 0
    assert overlap_violations(spark.createDataFrame([], "ident string, vt_s long, vt_e long, tt_s long, tt_e long")).count() == 0
