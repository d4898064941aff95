import collections
import random

import pytest
from conftest_odd import ODD
from tokenizers import Tokenizer

from bitempo.llm import packing, token_files
from bitempo.llm.common import WordTokenizer, crc_of_ids, default_vocabulary


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(default_vocabulary())


def ids_of(library, text):
    return library.encode(text or "", add_special_tokens=False).ids


def test_word_tokenizer_equals_the_library(library):
    rnd = random.Random(1)
    letters = "aAbBéÉß ñ.,,.!'’\n\t  0123٣<|endoftext|>_-ΣσςİıÅKÉ̸ 日本🙂\x1c\x85ſǅ×÷'s't'LL"
    texts = ["".join(rnd.choice(letters) for _ in range(rnd.randrange(1, 40))) for _ in range(4000)] + ["<|ENDOFTEXT|>", "a'S.b", "a'.", "İ", "x<|startoftext|>y", None, ""]
    small = WordTokenizer(default_vocabulary(), remember=50)  # forgets all the time
    for text, got in zip(texts, small.encode(texts)):
        assert got.tolist() == ids_of(library, text), text


def test_token_files_round_trip(spark, docs, library, tmp_path):
    rows = ODD + [(i, f"text number {i} " * (i % 90), "en", "s") for i in range(20, 300)]
    got = token_files.token_index(docs(rows).repartition(5), str(tmp_path / "f"), length=64).collect()
    assert len(got) == len(rows)
    start, expected = 0, collections.Counter((i, crc_of_ids(ids_of(library, t) + [1])) for i, t, _, _ in rows)
    assert collections.Counter((r["doc_id"], r["ids_crc32"]) for r in got) == expected
    for r in sorted(got, key=lambda r: r["start"]):
        assert r["start"] == start
        start += r["n_tokens"]
    order = [r["doc_id"] for r in sorted(got, key=lambda r: r["start"])]
    assert order == sorted(order, key=lambda i: (i is not None, i or 0))


def test_documents_of_one_id_keep_their_order(spark, docs):
    rows = [(5 if i % 2 else None, f"text {i % 37} " * (i % 11), "en", "s") for i in range(200)]
    key = lambda n, length: [(r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) for r in token_files.token_index(docs(rows).repartition(n), length=length).orderBy("start").collect()]
    assert key(3, 64) == key(7, 16)


def test_sequences_are_zero_copy_slices(tmp_path):
    import numpy as np

    uri = str(tmp_path / "x.arrows")
    w = token_files.SequenceWriter(uri, 8, batch=3)
    for i in range(7):
        w.add(i, np.arange(i * 3 + 1, dtype=np.uint16))
    w.close()
    flat = np.concatenate([np.arange(i * 3 + 1) for i in range(7)])
    for n in range(-(-len(flat) // 8)):
        ids, mask = token_files.sequence_at(uri, n)
        assert ids[mask].tolist() == flat[n * 8 : n * 8 + 8].tolist() and ids.base is not None
    with pytest.raises(IndexError):
        token_files.sequence_at(uri, 99)
    known, walked = token_files.SequenceReader(uri, w.offsets), token_files.SequenceReader(uri)
    assert known.offsets == walked.offsets and len(known.offsets) == -(-w.sequences // 3)
    order = list(range(w.sequences))
    random.Random(1).shuffle(order)
    for n in order:
        ids, bits = known.ids(n), known.mask_bits(n)
        assert not ids.flags.owndata and not bits.flags.owndata and not ids.flags.writeable
        assert ids[known.mask(n)].tolist() == flat[n * 8 : n * 8 + 8].tolist() and bits.size == 1
    with pytest.raises(ValueError):
        token_files.SequenceWriter(str(tmp_path / "y.arrows"), 12)
    assert [(i, d.tolist()) for i, d in token_files.documents_of(uri)] == [(i, list(range(i * 3 + 1))) for i in range(7)]


def test_empty_tables(spark, docs):
    assert token_files.token_index(docs([])).count() == 0
    assert packing.packed(docs([])).count() == 0


def test_packing_is_whole_and_gapless(spark, docs, library):
    rows = ODD + [(i, "word " * (i * 7 % 2500), "en", "s") for i in range(100, 220)]
    got = packing.packed(docs(rows), length=256, pool=50).collect()
    by_doc, by_sequence = collections.defaultdict(list), collections.defaultdict(list)
    for r in got:
        by_doc[r["doc_id"]].append(r)
        by_sequence[r["sequence_id"]].append(r)
    for held in by_sequence.values():
        at = 0
        for r in sorted(held, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 256
    for i, t, _, _ in rows:
        ids = ids_of(library, t) + [0]
        pieces = [(n, s, len(ids[s : s + 256]), crc_of_ids(ids[s : s + 256])) for n, s in enumerate(range(0, len(ids), 256))]
        mine = collections.Counter((r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in by_doc[i])
        assert all(mine[p] >= 1 for p in pieces)
    assert len(got) == sum(-(-(len(ids_of(library, t)) + 1) // 256) for _, t, _, _ in rows)


@pytest.mark.parametrize("seed", range(4))
def test_local_search_never_worsens_and_often_saves(seed):
    rnd = random.Random(seed)
    lengths = [rnd.randrange(20, 70) for _ in range(300)]
    bins = packing.Bins(lengths, 100)
    # a poor start: each item into the first bin with room, in the order given
    for i, n in enumerate(lengths):
        at = next((b for b, f in enumerate(bins.fill) if f + n <= 100), None)
        if at is None:
            bins.held.append([i])
            bins.fill.append(n)
        else:
            bins.held[at].append(i)
            bins.fill[at] += n
    before, squares = len(bins.held), sum(f * f for f in bins.fill)
    made = bins.improve()
    assert sorted(i for h in bins.held for i in h) == list(range(300))
    assert all(sum(lengths[i] for i in h) == f <= 100 for h, f in zip(bins.held, bins.fill))
    assert len(bins.held) <= before and sum(f * f for f in bins.fill) >= squares and made > 0


def test_best_fit_matches_the_best_of_small_cases():
    assert len(packing.pack_lengths([6, 4, 5, 5, 7, 3], 10)) == 3
    assert len(packing.pack_lengths([4, 4, 4, 3, 3, 3, 3, 3, 3], 10)) == 3  # longest first alone takes four
    assert packing.pack_lengths([], 10) == []


@pytest.mark.parametrize(("low", "high", "size", "n"), [(300, 900, 2048, 700), (1, 60, 512, 600), (20, 70, 100, 400)])
def test_local_search_ends_where_no_pair_of_bins_can_exchange(low, high, size, n):
    rnd = random.Random(n)
    lengths = [rnd.randint(low, high) for _ in range(n)]
    held = packing.pack_lengths(lengths, size)
    assert sorted(i for h in held for i in h) == list(range(n))
    under = [[lengths[i] for i in h] for h in held if sum(lengths[i] for i in h) < size]

    def sums(h):
        return set(h), {x + y for i, x in enumerate(h) for y in h[i + 1 :]}

    for taker in under:
        room, (one, two) = size - sum(taker), sums(taker)
        for giver in under:
            if giver is not taker:
                gives, pairs = sums(giver)
                gains = {a - b for a in gives for b in {0} | one | two} | {a - b for a in pairs for b in one}
                assert not any(0 < g <= room and g > sum(giver) - sum(taker) for g in gains)
