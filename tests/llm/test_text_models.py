import math
import re
import time
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from pagesketch.llm import cotraining, language_id, ppm, quality
from pagesketch.llm.common import Texts, table

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def base_of(text):
    """The base measures of one text, by their definitions."""
    text = text or ""
    words, lines = WORD.findall(text), [x for x in text.split("\n") if WORD.search(x)]
    grams = Counter(zip(words, words[1:], words[2:], strict=False))
    marked = {i + k for i in range(len(words) - 2) if grams[tuple(words[i : i + 3])] > 1 for k in range(3)}
    return len(words), sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(marked)


def test_base_measures(spark, sf, odd_rows):
    texts = [r[1] for r in odd_rows] + ["a b c a b c", "x\ny\nx\n \n \nx", "p q r s p q r"] + [r["text"] for r in table(spark, sf, "documents").limit(60).collect()]
    got = quality.base_measures(Texts(pa.array(texts, pa.string())))
    assert list(zip(*(got[k].tolist() for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")), strict=True)) == [base_of(t) for t in texts]


def test_quality_verdicts(spark, sf):
    docs, marks = table(spark, sf, "documents"), table(spark, sf, "labels")
    got = quality.Judge(docs, marks).verdicts()
    rows = {r["doc_id"]: r for r in got.collect()}
    assert len(rows) == docs.count()
    for r in docs.collect():
        n, _, _, _, repeats = base_of(r["text"])
        assert rows[r["doc_id"]]["base_failed"] == (n < 50 or 100 * repeats > 50 * n)
        assert not (rows[r["doc_id"]]["base_failed"] and rows[r["doc_id"]]["kept"])
    clean = [rows[r["doc_id"]] for r in marks.where("quality = 1 and toxic = 0").collect()]
    assert np.mean([r["kept"] or r["base_failed"] for r in clean]) > 0.95
    kept = quality.Judge(docs, marks).kept_rows()
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(d for d, r in rows.items() if r["kept"])


def test_ratio_against_plain_counts(spark):
    docs = spark.createDataFrame([(i, f"good words here number {i} " * 20) for i in range(8)] + [(i, f"## bad || {i} stuff " * 30) for i in range(8, 16)], "doc_id bigint, text string")
    marks = spark.createDataFrame([(i, 1, 0) for i in range(8)], "doc_id bigint, quality int, toxic int")
    judge = quality.Judge(docs, marks)
    assert len(judge.trusted.value) == 8
    rows = {r["doc_id"]: r["llr"] for r in judge.verdicts().collect()}
    assert min(rows[i] for i in range(8)) > max(rows[i] for i in range(8, 16))


def test_threshold_covers_all_trusted_rows(spark):
    """The bound on labelled rows holds for the multinomial alone: every other trusted row sets the threshold."""
    rng = np.random.default_rng(0)
    rows = [(i, " ".join(f"w{j}" for j in rng.integers(0, 20 + 10 * i, 200))) for i in range(120)]
    docs = spark.createDataFrame([*rows, (None, rows[0][1])], "doc_id bigint, text string").repartition(3)
    marks = spark.createDataFrame([(i, 1, 0) for i in range(100)], "doc_id bigint, quality int, toxic int")
    judge = quality.Judge(docs, marks, trusted_rows=6, trusted_loss=0.1)
    scored = judge._scored().collect()
    ids = judge.trusted.value
    learned = set(ids[quality.mix(ids.view(np.uint64)) % np.uint64(2) == 0].tolist())
    assert 0 < len(learned) < 6 == len(judge.trusted.value)
    held_out = sorted(r["llr_grid"] for r in scored if r["doc_id"] is not None and r["doc_id"] < 100 and r["doc_id"] not in learned and not r["base_failed"])
    assert len(held_out) > 30
    limit = max(x for x in held_out if sum(y < x for y in held_out) <= 0.1 * len(held_out))
    kept = {r["doc_id"] for r in scored if not r["base_failed"] and r["llr_grid"] >= limit}
    assert {r["doc_id"] for r in judge.verdicts().where("kept").collect()} == kept
    assert {r["doc_id"] for r in judge.kept_rows().collect()} == kept


def test_quality_of_odd_rows(odd, odd_rows, none, labels):
    got = quality.Judge(odd, labels).verdicts()
    assert got.count() == len(odd_rows)
    assert got.where("kept and n_words < 50").count() == 0
    assert quality.Judge(odd, labels.where("false")).verdicts().where("llr <> 0").count() == 0
    assert quality.Judge(none, labels).verdicts().count() == 0
    assert quality.Judge(odd, labels).kept_rows().columns == odd.columns


def test_language_accuracy(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    got = language_id.identify(docs).join(docs.select("doc_id", "lang", "text"), "doc_id")
    rows = got.where("held_out").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in rows]) > 0.97
    assert all(0 <= r["score"] <= 1 and r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got.collect())


def test_gradients_of_the_network():
    rng = np.random.default_rng(0)
    net = language_id.ByteGru(["a", "b", "c"], hidden=3)
    ids = rng.integers(0, 256, (7, 4)).astype(np.int16)
    ids[5:, 1] = language_id.PAD
    labels = np.array([0, 1, 2, 1])
    for w in net.arrays():
        w[...] = w.astype(np.float64)
    _, grads = net.gradients(ids, labels)
    for w, g in zip(net.arrays(), grads, strict=True):
        flat = np.argsort(-np.abs(g).ravel())[:4]
        for k in flat:
            at = np.unravel_index(k, w.shape)
            old, step = w[at], 2e-2
            w[at] = old + step
            up = net.gradients(ids, labels)[0]
            w[at] = old - step
            down = net.gradients(ids, labels)[0]
            w[at] = old
            assert abs((up - down) / (2 * step) - g[at]) < 2e-3 + 0.05 * abs(g[at])


def test_windows_label_every_position_once():
    sizes = np.array([0, 5, 384, 385, 2000])
    owner, begin, low, high, length = language_id.centred_windows(sizes, 384, 32)
    first = np.cumsum(sizes) - sizes
    seen = [np.zeros(n, int) for n in sizes]
    for o, b, lo, hi, n in zip(owner, begin, low, high, length, strict=True):
        at = b - first[o]
        seen[o][at + lo : at + hi] += 1
        assert 0 <= at and at + n <= sizes[o] and (lo == 32 or at == 0) and (n - hi == 32 or at + n == sizes[o])
    assert all((x == 1).all() for x in seen)


def test_pooling_against_one_text_at_a_time():
    """The pooled probabilities of a batch are the means over positions of windows run one by one."""
    net = language_id.ByteGru(["a", "b", "c"], hidden=3)
    rng = np.random.default_rng(0)
    raw = [bytes(rng.integers(97, 123, n).astype(np.uint8)) for n in (1, 3, 400, 1000, 40)]
    got = language_id.pooled(net, raw)
    for text, mean in zip(raw, got, strict=True):
        want = np.zeros(3)
        for lo in range(0, len(text), language_id.STEPS):
            a, b = max(0, lo - language_id.MARGIN), min(len(text), lo + language_id.STEPS + language_id.MARGIN)
            p = net.probabilities(np.frombuffer(text[a:b], np.uint8).astype(np.int16)[:, None])[:, 0]
            want += p[lo - a : min(lo + language_id.STEPS, len(text)) - a].sum(axis=0)
        assert np.abs(mean - want / len(text)).max() < 0.1


def test_pooling_does_not_depend_on_other_texts():
    """A short text beside long ones has the probabilities that it has alone."""
    net = language_id.ByteGru(["a", "b", "c"], hidden=3)
    rng = np.random.default_rng(0)
    raw = [bytes(rng.integers(97, 123, n).astype(np.uint8)) for n in (1, 3, 40, 400, 528, 529, 1000, 2000)]
    alone = np.vstack([language_id.pooled(net, [text]) for text in raw])
    assert np.abs(language_id.pooled(net, raw) - alone).max() < 1e-5
    assert np.abs(alone.sum(axis=1) - 1).max() < 1e-5


def test_pooling_of_closed_gates_against_the_network():
    """Weights so large that exponentials overflow give the states of the plain recurrence."""
    net = language_id.ByteGru(["a", "b", "c"], hidden=3)
    for direction in (net.forward, net.backward):
        direction.table *= 300
    text = bytes(np.random.default_rng(0).integers(0, 256, 300).astype(np.uint8))
    want = net.probabilities(np.frombuffer(text, np.uint8).astype(np.int16)[:, None])[:, 0].mean(axis=0)
    assert np.abs(language_id.pooled(net, [text])[0] - want).max() < 1e-4


def test_pooling_takes_less_time_than_the_plain_recurrence():
    """CPU seconds of a window's bytes are well under those of the recurrence that is kept for training."""
    net = language_id.ByteGru(["a", "b", "c", "d"])
    ids = np.random.default_rng(0).integers(97, 123, (language_id.STEPS, language_id.BLOCK)).astype(np.int16)
    raw = [bytes(x.astype(np.uint8)) for x in ids.T]

    def seconds(work):
        began = time.process_time()
        work()
        return time.process_time() - began

    plain, fast = [], []
    for _ in range(3):
        plain.append(seconds(lambda: net.probabilities(ids)))
        fast.append(seconds(lambda: language_id.pooled(net, raw)))
    assert min(fast) < 0.85 * min(plain)


def test_language_of_odd_rows(odd, odd_rows, none):
    got = {(r["doc_id"], r["lang_pred"], r["score"]) for r in language_id.identify(odd).collect()}
    by_id = {d: (p, s) for d, p, s in got}
    assert all(by_id[i] == ("und", 0.0) for i in (0, 1, 2, 12)) and by_id[5][0] in ("en", "de")
    assert language_id.identify(odd).count() == len(odd_rows)
    assert language_id.identify(none).count() == 0
    assert {r["lang_pred"] for r in language_id.identify(odd.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}


@pytest.mark.parametrize(("batch_bytes", "hot_keys"), [(1, 1 << 20), (1 << 20, 60)])
def test_ppm_against_a_trie(spark, sf, batch_bytes, hot_keys):
    """The distributed model and the base score against a trie and a dictionary in memory."""
    docs = table(spark, sf, "documents").select("doc_id", "text").limit(60).union(spark.createDataFrame([(-1, None), (-2, ""), (-3, "Ünï ß 日本"), (-3, "Ünï ß 日本")], "doc_id bigint, text string"))
    rows = docs.collect()
    rest = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5))
    got = ppm.corpus_scores(docs, rest != 1, rest == 1, batch_bytes=batch_bytes, hot_keys=hot_keys)
    trie, counts = ppm.PpmTrie(), Counter()
    for r in rows:
        if zlib.crc32(str(r["doc_id"]).encode()) % 5 != 1:
            trie.train((r["text"] or "").encode())
            counts.update((r["text"] or "").encode().lower().split())
            counts["end"] += 1
    n, v = sum(counts.values()), len(counts)
    want = {}
    for r in rows:
        text = (r["text"] or "").encode()
        tokens = [*text.lower().split(), "end"]
        want[r["doc_id"]] = (len(tokens), sum(counts[t] > 0 for t in tokens), n, sum(math.log10((counts[t] + 0.5) / (n + 0.5 * (v + 1))) for t in tokens), trie.score(text))
    assert got.count() == len(rows)
    for r in got.collect():
        tokens, known, total, base, score = want[r["doc_id"]]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (tokens, known, total)
        assert math.isclose(r["base_score"], base, rel_tol=1e-9) and math.isclose(r["score"], score, rel_tol=1e-5)


def test_ppm_probabilities_add_up():
    trie = ppm.PpmTrie(order=2)
    for t in (b"abracadabra", b"abc abd", b"a"):
        trie.train(t)
    for context in (b"ab", b"zz", b" a", b"ra"):
        total = sum(10 ** trie.log10(context, s) for s in range(ppm.SYMBOLS))
        assert 0.5 < total <= 1 + 1e-9
    fresh = ppm.PpmTrie(order=2)
    assert fresh.score(b"abababababababab", adaptive=True) > ppm.PpmTrie(order=2).score(b"abababababababab")
    assert not ppm.PpmTrie().nodes and fresh.nodes


def test_ppm_of_odd_rows(odd, odd_rows, none):
    got = ppm.held_out_scores(odd)
    assert got.count() == len(odd_rows)
    assert got.where("score > 0 or n_tokens < 1").count() == 0
    assert ppm.held_out_scores(none).count() == 0
    untrained = ppm.corpus_scores(odd.limit(3), F.lit(None).cast("boolean"), F.lit(None).cast("boolean"))
    assert untrained.where("n_known > 0 or train_tokens > 0 or held_out").count() == 0


def test_packed_numbers():
    keys = np.sort(np.random.default_rng(3).integers(-(2**62), 2**62, 500))
    assert (ppm.unpack_sorted(ppm.pack_sorted(keys)) == keys).all()
    counts = np.array([0, 1, 254, 255, 256, 10**12])
    assert (ppm.unpack_counts(ppm.pack_counts(counts), 6) == counts).all()


def test_cotraining_accuracy(spark):
    docs, marks = (table(spark, "/root/testdata/sf0.01", t) for t in ("documents", "labels"))
    got = cotraining.score_quality(docs, marks).join(marks, "doc_id").collect()
    assert np.mean([r["kept"] == (r["quality"] == 1) for r in got]) > 0.97


def test_pseudo_labels_teach_the_other_view():
    """One view sees the class on few labelled rows; the other needs the pool."""
    rng = np.random.default_rng(0)
    n = 3000
    y = rng.integers(0, 2, n)
    text = np.stack([y + rng.normal(0, 0.05, n), rng.normal(0, 1, n)], axis=1)
    meta = np.stack([y * rng.random(n), rng.normal(0, 1, n)], axis=1)
    known = np.arange(n) < 200
    calibrate = known & (np.arange(n) % 4 == 0)
    used = [set(), set()]

    def propose(*models):
        out = []
        for k, (model, x) in enumerate(zip(models, (text, meta), strict=True)):
            p = 1 / (1 + np.exp(-model.logit(x)))
            free = [i for i in np.argsort(-np.abs(p - 0.5)) if not known[i] and i not in used[k]]
            mine = [i for c in (0, 1) for i in [i for i in free if (p[i] >= 0.5) == c][:100]]
            used[k] |= set(mine)
            out.append((text[mine], meta[mine], (p[mine] >= 0.5).astype(int)))
        return out

    fit = lambda labels: cotraining.CoTrained.fit(text[known], meta[known], labels[known], calibrate[known], propose)
    p = fit(y).scores(text, meta)[2]
    assert np.mean((p >= 0.5) == y) > 0.95
    assert fit(np.zeros(n, int)) is None


def test_pseudo_labels_come_from_all_unlabelled_rows(spark, sf):
    """Against the scores of every row, one by one; labelled rows, rows handed over before and unsure rows are never taken."""
    docs, marks = (table(spark, sf, t) for t in ("documents", "labels"))
    docs = docs.unionByName(docs.limit(20))
    rows = docs.select("doc_id", "text", "lang", "source")
    views = cotraining.kept_views(rows).cache()
    rng = np.random.default_rng(5)
    models = [cotraining.Logistic(rng.normal(0, 6, n), 0.0) for n in (cotraining.TEXT_VIEW, cotraining.META_BUCKETS)]
    labelled = {r["doc_id"] for r in cotraining.marked(marks).collect()}
    want = []
    batch = pa.Table.from_pylist([r.asDict() for r in rows.dropDuplicates(["doc_id"]).collect()]).combine_chunks().to_batches()[0]
    ids = batch.column("doc_id").to_pylist()
    used = [{i for i in ids if i % 7 == k} for k in (0, 1)]
    for k, (model, x) in enumerate(zip(models, cotraining.as_numbers(*cotraining._views(batch)), strict=True)):
        p = 1 / (1 + np.exp(-model.logit(x)))
        for c in (0, 1):
            own = [(round(max(q, 1 - q) * 1e6), i) for q, i in zip(p, ids, strict=True) if max(q, 1 - q) >= cotraining.CONFIDENT and (q >= 0.5) == c and i not in labelled and i not in used[k]]
            want += [(k, c, min(len(own), 5), sorted(s for s, _ in sorted(own, reverse=True)[:5]))]
    got = cotraining.sure_rows(views, cotraining.marked(marks), models, used, per_class=5)
    assert len(got) == sum(n for *_, n, _ in want) > 5
    assert not {d for _, d, _ in got} & labelled and all(d not in used[k] for k, d, _ in got)
    assert {(k, c): sum(v == k and y == c for v, _, y in got) for k, c, *_ in want} == {(k, c): n for k, c, n, _ in want}


def test_cotraining_of_odd_rows(odd, odd_rows, none, labels):
    got = cotraining.score_quality(odd, labels)
    assert got.count() == len(odd_rows)
    assert cotraining.score_quality(none, labels).count() == 0
    assert cotraining.score_quality(odd, labels.where("false")).where("kept and score is null").count() == len(odd_rows)
