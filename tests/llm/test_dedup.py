import hashlib
import itertools
import random
import re
from collections import defaultdict

import numpy as np
import pyarrow as pa

from pagesketch.llm import exact_dedup, superminhash
from pagesketch.llm.common import Texts, one_space
from pagesketch.llm.components import components

BLANKS = re.compile(rb"[\x20\x09-\x0D]+")


def test_trie_holds_prefixes_and_smallest_ids():
    rng = random.Random(5)
    trie, want = exact_dedup.PatriciaTrie(), {}
    for _ in range(3000):
        key = bytes(rng.choice(b"ab") for _ in range(rng.randrange(8)))
        doc = rng.randrange(1000)
        assert trie.insert(key, doc) == (key not in want)
        old = want.get(key, (doc, 0))
        want[key] = (min(old[0], doc), old[1] + 1)
    assert {k: (t.smallest, t.count) for k, t in trie.terminals()} == want


def brute(rows):
    groups = defaultdict(list)
    for doc, text, *_ in rows:
        groups[BLANKS.sub(b" ", (text or "").encode())].append(doc)
    out = []
    for body, ids in groups.items():
        keep = min((i for i in ids if i is not None), default=None)
        out += [(i, keep, len(ids), i == keep, hashlib.sha256(body).hexdigest()) for i in ids]
    return sorted(out, key=repr)


def test_exact_groups(odd, odd_rows, none):
    for spill in (1, 1 << 20):
        assert sorted(map(tuple, exact_dedup.exact_groups(odd, spill_bytes=spill).collect()), key=repr) == brute(odd_rows)
    assert exact_dedup.exact_groups(none).count() == 0
    assert exact_dedup.keep_one(none).count() == 0


def test_keep_one(odd, odd_rows):
    kept = exact_dedup.keep_one(odd)
    assert kept.columns == odd.columns
    ids = sorted((r["doc_id"] for r in kept.collect()), key=repr)
    assert ids == sorted({d for d, k, *_ in brute(odd_rows) if d == k and d is not None} | {None}, key=repr)


def test_one_space():
    assert one_space(b" a \t\x0b b\n\nc ") == b" a b c "


def shingles(text, width):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().lower())
    if not words:
        return set()
    return {tuple(words)} if len(words) < width else {tuple(words[i : i + width]) for i in range(len(words) - width + 1)}


def brute_components(docs, width, percent=80):
    sets = {d: shingles(t, width) for d, t in docs}
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        x, y = sets[a], sets[b]
        if x and y and 100 * len(x & y) >= percent * len(x | y):
            a, b = sorted((find(a), find(b)))
            parent[b] = a
    return {d: (len(s), find(d)) for d, s in sets.items()}


def planted(rng, n=120):
    """Bases with edited copies of many degrees, chains among them, and a passage that many share."""
    words = lambda k: [f"w{rng.randrange(4000)}" for _ in range(k)]
    passage, docs = words(60), []
    while len(docs) < n:
        base = words(rng.randrange(3, 150))
        for _ in range(rng.randrange(1, 8)):
            text = list(base)
            for _ in range(rng.randrange(0, 1 + len(text) // 25)):
                text[rng.randrange(len(text))] = f"e{rng.randrange(10**6)}"
            docs.append(" ".join(text if rng.random() < 0.7 else passage + text))
            base = text if rng.random() < 0.4 else base
    return list(enumerate(docs))


def test_near_groups_against_all_pairs(spark):
    docs = planted(random.Random(3), 260)
    for width in (4, 5):
        got = superminhash.near_groups(spark.createDataFrame(docs, "doc_id bigint, text string"), width=width)
        assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got.collect()} == brute_components(docs, width)


def test_near_groups_of_odd_rows(odd, odd_rows, none):
    got = superminhash.near_groups(odd, width=4)
    assert got.count() == len(odd_rows)
    want = brute_components({(r[0], r[1]) for r in odd_rows if r[0] is not None}, 4)
    for r in got.collect():
        if r["doc_id"] is not None:
            assert (r["n_shingles"], r["component_id"]) == want[r["doc_id"]] and r["kept"] == (r["component_id"] == r["doc_id"])
    assert superminhash.near_groups(none, width=4).count() == 0
    assert superminhash.keep_one(odd).columns == odd.columns
    assert superminhash.keep_one(none).count() == 0


def test_signatures_estimate_similarity():
    rng, errors = np.random.default_rng(1), []
    for _ in range(150):
        n, both = int(rng.integers(5, 300)), 0.6
        a = rng.integers(0, 2**63, n, dtype=np.uint64)
        c = int(n * 2 * both / (1 + both))
        b = np.concatenate([a[:c], rng.integers(0, 2**63, n - c, dtype=np.uint64)])
        s = superminhash.signatures(np.concatenate([np.sort(a), np.sort(b)]), np.array([0, n, 2 * n]), 252)
        assert (s >> np.uint64(48)).max() < 252
        errors.append((s[0] == s[1]).mean() - c / (2 * n - c))
    assert abs(np.mean(errors)) < 0.006 and np.std(errors) < (0.6 * 0.4 / 252) ** 0.5


def test_places_of_one_element_are_a_permutation():
    s = superminhash.signatures(np.array([12345], np.uint64), np.array([0, 1]), 64)
    assert sorted((s[0] >> np.uint64(48)).tolist()) == list(range(64))


def test_common_counts():
    rng = np.random.default_rng(2)
    sets = [np.unique(rng.integers(0, 300, rng.integers(1, 200))).astype(np.uint64) for _ in range(30)]
    got = superminhash.common_counts(sets, step=64)
    for i, j in itertools.combinations(range(30), 2):
        assert got[i, j] == len(np.intersect1d(sets[i], sets[j]))


def test_components(spark):
    rng = random.Random(9)
    chain = [(i, i + 1) for i in range(60)]
    star = [(100, 100 + i) for i in range(1, 40)]
    noise = [(rng.randrange(200, 400), rng.randrange(200, 400)) for _ in range(90)]
    edges = [*chain, *star, *noise, (7, 7), (None, 3), (1, 0)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "src bigint, dst bigint")).collect()}
    parent = {}
    find = lambda x: x if parent.setdefault(x, x) == x else find(parent[x])
    for a, b in edges:
        if a is not None and a != b:
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    assert got == {x: find(x) for x in parent}
    assert components(spark.createDataFrame([], "src bigint, dst bigint")).count() == 0


def test_word_positions():
    column = pa.array(["ab cd  ab", None, "", "x", "  yy zz ", "ab"])
    texts = Texts(column)
    starts, ends, bounds = texts.words()
    assert [bytes(texts.data[i:j]) for i, j in zip(starts, ends, strict=True)] == [b"ab", b"cd", b"ab", b"x", b"yy", b"zz", b"ab"]
    assert bounds.tolist() == [0, 3, 3, 3, 4, 6, 7]
    hashes = texts.hashes(starts, ends)
    assert len(set(hashes.tolist())) == 5 and hashes[0] == hashes[2] == hashes[6]
