"""Words, texts and rows are told apart by their bytes, not by fingerprints that can be made to agree."""

import random
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest

from pagesketch.llm import exact_dedup, packing, ppm, quality, superminhash
from pagesketch.llm.common import SIP_BYTES, Texts, fingerprints, run_codes, siphash
from pagesketch.llm.queries import tokenizer_path

#: Two words whose polynomial hashes modulo 2^64 agree for every base: the parity sequence and its complement.
PARITY = ["".join("ab"[(i.bit_count() + k) % 2] for i in range(1024)) for k in range(2)]
DOCS = "doc_id bigint, text string"


def test_siphash_vectors():
    key, body = bytes(range(16)), bytes(range(15))
    got = siphash(np.frombuffer(body + body[:8], np.uint8), np.array([0, 15, 15, 23]), key)
    assert [hex(int(x)) for x in got] == ["0xa129ca6149be45e5", "0x726fdb47dd0e0e31", "0x93f5f5799a932462"]


def test_fingerprints_of_short_and_long_words():
    words = [b"", b"a", b"x" * SIP_BYTES, b"x" * (SIP_BYTES + 1), *(w.encode() for w in PARITY), b"tail"]
    whole = fingerprints(pa.array(words, pa.large_binary()))
    assert len(set(whole.tolist())) == len(words)
    for i, w in enumerate(words):
        assert fingerprints(pa.array([w], pa.large_binary()))[0] == whole[i]


def test_run_codes():
    rng = random.Random(4)
    texts = [[rng.randrange(4) for _ in range(rng.randrange(9))] for _ in range(60)]
    codes = np.array([c for t in texts for c in t])
    text_of = np.repeat(np.arange(len(texts)), [len(t) for t in texts])
    for width in (1, 2, 3, 5):
        at, got = run_codes(codes, text_of, width)
        want = [tuple(codes[i : i + width]) for i in range(len(codes) - width + 1) if text_of[i] == text_of[i + width - 1]]
        assert len(at) == len(want) and len(set(zip(got.tolist(), want, strict=True))) == len(set(want)) == len(set(got.tolist()))


def test_exact_sets():
    rng = random.Random(6)
    texts = [" ".join(rng.choice("abc") for _ in range(rng.randrange(8))) for _ in range(80)] + [""]
    for width in (1, 3, 5):
        sets, bounds = superminhash.exact_sets(Texts(pa.array(texts)), width)
        names = {}
        for text, lo, hi in zip(texts, bounds, bounds[1:], strict=False):
            words = text.split()
            want = {tuple(words)} if 0 < len(words) < width else {tuple(words[i : i + width]) for i in range(len(words) - width + 1)} - {()}
            own = set(sets[lo:hi].tolist())
            assert len(own) == hi - lo == len(want)
            for other, numbers in names.items():
                assert len(own & numbers) == len(want & other)
            names[frozenset(want)] = own


@pytest.mark.parametrize("width", [4, 5])
def test_colliding_words_link_nothing(spark, width):
    docs = [(i, " ".join(PARITY[i] if k % 3 else PARITY[1 - i] for k in range(30))) for i in range(2)] + [(2 + i, PARITY[i]) for i in range(2)]
    got = superminhash.near_groups(spark.createDataFrame(docs, DOCS), width=width)
    assert {r["doc_id"]: r["component_id"] for r in got.collect()} == {i: i for i in range(4)}


def test_colliding_words_are_packed_apart():
    path = tokenizer_path()
    from tokenizers import Tokenizer

    texts = [" ".join(PARITY), " ".join(PARITY[::-1])]
    want = [x.ids for x in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]
    assert want[0] != want[1]
    assert [np.frombuffer(x, "<u2").tolist() for x in packing.WordTokenizer(path).encode(Texts(pa.array(texts)))] == want


def test_colliding_words_are_no_repeats():
    a, b = PARITY
    base = quality.base_measures(Texts(pa.array([f"{a} x {a} {b} x {b}", f"{a} x y {a} x y"])))
    assert base["n_repeat_words"].tolist() == [0, 6]


def test_colliding_words_are_known_apart(spark):
    from pyspark.sql import functions as F

    docs = spark.createDataFrame([(0, PARITY[0]), (1, PARITY[1])], DOCS)
    got = {r["doc_id"]: r["n_known"] for r in ppm.corpus_scores(docs, F.col("doc_id") == 0, F.col("doc_id") == 1).collect()}
    assert got == {0: 2, 1: 1}


def test_repeat_words_against_plain_count():
    rng = random.Random(8)
    texts = [" ".join(rng.choice("abcde") for _ in range(rng.randrange(40))) for _ in range(50)]
    want = []
    for text in texts:
        words, seen, marks = text.split(), defaultdict(list), set()
        for i in range(len(words) - 2):
            seen[tuple(words[i : i + 3])].append(i)
        for places in seen.values():
            if len(places) > 1:
                marks |= {i + k for i in places for k in range(3)}
        want.append(len(marks))
    assert quality.base_measures(Texts(pa.array(texts)))["n_repeat_words"].tolist() == want


TWICE = [(5, "text one is here"), (5, "text two is there"), (5, "text one is here"), (6, "text  two is there"), (7, None), (7, ""), (7, "seven"), (None, "null id"), (None, "null id")]


def test_exact_dedup_keeps_texts_that_share_an_id(spark):
    got = sorted(((r["doc_id"], r["text"] or "") for r in exact_dedup.keep_one(spark.createDataFrame(TWICE, DOCS)).collect()), key=repr)
    assert got == sorted([(5, "text one is here"), (5, "text two is there"), (7, ""), (7, "seven"), (None, "null id"), (None, "null id")], key=repr)


def test_near_dedup_keeps_texts_that_share_an_id(spark):
    words = [f"w{i}" for i in range(60)]
    a, b, c = " ".join(words), " ".join([*words[:-1], "end"]), " ".join(words[::-1])
    docs = [(5, a), (5, c), (5, a), (3, b), (4, c + " tail"), (9, "other words that stand alone here"), (9, "and some more of them"), (2, ""), (None, a)]
    got = superminhash.near_groups(spark.createDataFrame(docs, DOCS)).collect()
    assert sorted((r["component_id"], r["doc_id"]) for r in got if r["doc_id"] is not None) == [(2, 2), (3, 3), (3, 5), (3, 5), (4, 4), (4, 5), (9, 9), (9, 9)]
    kept = superminhash.keep_one(spark.createDataFrame(docs, DOCS)).collect()
    assert sorted(((r["doc_id"], r["text"]) for r in kept), key=repr) == sorted([(3, b), (4, c + " tail"), docs[5], docs[6], (2, ""), (None, a)], key=repr)


def test_near_groups_compare_every_estimate_on_request(spark):
    from tests.llm.test_dedup import brute_components, planted

    docs = planted(random.Random(12), 150)
    got = superminhash.near_groups(spark.createDataFrame(docs, DOCS), slack=1.0)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got.collect()} == brute_components(docs, 5)


def test_tries_spill_subtrees_and_lose_nothing():
    rng = random.Random(2)
    rows = [(bytes(rng.choice(b"ab") for _ in range(rng.randrange(12))), rng.randrange(500)) for _ in range(3000)]

    def run(rows, ordered):
        trie, out = exact_dedup.SpillingTrie(True, 20_000), []
        for text, doc in sorted(rows) if ordered else rows:
            trie.insert(text, doc, 1)
            if trie.full():
                out += [b for b in (trie.spill_complete(text) if ordered else trie.spill_largest())]
                assert trie.held < 20_000
        out += list(trie.spill_all())
        return [tuple(r.values()) for b in out for r in b.to_pylist()]

    want = defaultdict(list)
    for text, doc in rows:
        want[text].append(doc)
    for ordered in (False, True):
        got = defaultdict(list)
        for n, _, smallest, count, text in run(rows, ordered):
            assert n == len(text)
            got[text].append((smallest, count))
        assert {t: (min(x[0] for x in v), sum(x[1] for x in v)) for t, v in got.items()} == {t: (min(d), len(d)) for t, d in want.items()}
        assert not ordered or max(map(len, got.values())) == 1


def test_ratios_do_not_move_with_the_size_of_the_corpus():
    rng = np.random.default_rng(3)
    share = rng.dirichlet(np.full(4096, 0.3))
    trusted = rng.multinomial(200_000, share).astype(float)
    raw = trusted + rng.multinomial(2_000_000, share)
    once, often = quality.ratios(trusted, raw), quality.ratios(trusted, raw * 1000)
    assert np.abs(once - often)[raw > 0].max() < 1e-3
    assert np.std(once[raw > 0]) < 0.2


def test_ids_of_words_that_repeat_in_a_chunk():
    path = tokenizer_path()
    from tokenizers import Tokenizer

    rng = random.Random(1)
    words = ["It's", "we'll", "end.", "ﬁ", "日本", "x" * 300, "a.b", "12.5"]
    texts = [" ".join(rng.choice(words) for _ in range(rng.randrange(30))) for _ in range(40)]
    want = [x.ids for x in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]
    got = packing.WordTokenizer(path).encode(Texts(pa.array(texts)))
    assert [zlib.crc32(x) for x in got] == [zlib.crc32(np.array(i, "<u2").tobytes()) for i in want]
