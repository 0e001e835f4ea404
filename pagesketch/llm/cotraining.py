"""Quality classifier by co-training of a text view and a metadata view.

Two logistic models learn from a bounded sample of labelled rows, each from its own view. The features of all rows are kept once, in
compressed chunks. In each round both models score all unlabelled rows; of each class the most confident ones become pseudo-labels of the
other view. A last model on labelled rows that neither learned from calibrates and combines their logits, and scores every document over its
whole text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import GOLDEN, LOWER, Texts, chunks, cut, mix, over_chunks
from pagesketch.llm.quality import IS_SYMBOL, base_measures, grams

#: Hash buckets of the text view and of the metadata view.
TEXT_BUCKETS, META_BUCKETS = 1024, 256
#: Columns of the text view.
TEXT_VIEW = TEXT_BUCKETS + 7
#: Most labelled rows that are learned from; every unlabelled row may get a pseudo-label.
LABELLED_ROWS = 4000
#: Rounds, and pseudo-labels of each class that each view hands over in one.
ROUNDS, PER_CLASS = 4, 100
CONFIDENT = 0.97
META_COLUMNS = ("lang", "source")


def text_view(texts: Texts) -> np.ndarray:
    """Share of each hashed n-gram, square-rooted, then shares of symbols, capitals, repeats and digits, and sizes; all in steps of 1/255 as bytes."""
    keys, owner = grams(texts, TEXT_BUCKETS)
    n = len(texts)
    counts = np.bincount(owner * TEXT_BUCKETS + keys, minlength=n * TEXT_BUCKETS).reshape(n, TEXT_BUCKETS).astype(np.float32)
    counts = np.sqrt(counts / np.maximum(counts.sum(axis=1, keepdims=True), 1))
    grid = lambda x: np.round(np.clip(x, 0, 1) * 255).astype(np.uint8)
    base = base_measures(texts)
    words, chars = np.maximum(base["n_words"], 1), np.maximum(base["word_chars"], 1)
    inside = lambda flags: np.diff(np.concatenate([[0], np.cumsum(flags)])[texts.offsets])
    upper, digits, symbols = inside(LOWER[texts.data] != texts.data), inside((texts.data >= 48) & (texts.data < 58)), inside(IS_SYMBOL[texts.data])
    extra = [upper / chars, digits / chars, symbols / chars, base["n_repeat_words"] / words, base["n_dup_lines"] / words, np.log1p(base["n_words"]) / 10, chars / words / 10]
    return np.hstack([grid(counts), grid(np.stack(extra, axis=1))])


def meta_view(columns: list[pa.Array], n_bytes: np.ndarray) -> np.ndarray:
    """Hashed values of the metadata columns and of the size class, one in each column."""
    n = len(n_bytes)
    out = np.zeros((n, META_BUCKETS), np.uint8)
    for k, column in enumerate([*columns, pa.array(np.log2(n_bytes + 1).astype(np.int64))]):
        texts = Texts(column.cast(pa.string()))
        hashes = _each_hash(texts)
        out[np.arange(n), (mix(hashes + np.uint64(k) * np.uint64(977)) % np.uint64(META_BUCKETS)).astype(np.int64)] = 1
    return out


def _each_hash(texts: Texts) -> np.ndarray:
    out = np.zeros(len(texts), np.uint64) + GOLDEN
    full = np.flatnonzero(np.diff(texts.offsets) > 0)
    out[full] = texts.hashes(texts.offsets[:-1][full], texts.offsets[1:][full])
    return out


@dataclass
class Logistic:
    weights: np.ndarray
    bias: float

    @staticmethod
    def fit(x: np.ndarray, y: np.ndarray, penalty: float = 1e-4, rounds: int = 200) -> Logistic:
        """Accelerated gradient descent on the mean logistic loss, from zero."""
        w, b = np.zeros(x.shape[1]), 0.0
        step = 4.0 / (float((x * x).sum(axis=1).mean()) + 1)
        last_w, last_b = w, b
        for t in range(rounds):
            pull = t / (t + 3)
            at_w, at_b = w + pull * (w - last_w), b + pull * (b - last_b)
            error = (_sigmoid(x @ at_w + at_b) - y) / len(y)
            last_w, last_b = w, b
            w, b = at_w - step * (x.T @ error + penalty * at_w), at_b - step * float(error.sum())
        return Logistic(w, b)

    def logit(self, x: np.ndarray) -> np.ndarray:
        return np.clip(x @ self.weights + self.bias, -30, 30)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


@dataclass
class CoTrained:
    text: Logistic
    meta: Logistic
    joint: Logistic

    def scores(self, x_text: np.ndarray, x_meta: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        a, b = self.text.logit(x_text), self.meta.logit(x_meta)
        return _sigmoid(a), _sigmoid(b), _sigmoid(self.joint.logit(np.stack([a, b], axis=1) / 10))

    @staticmethod
    def fit(x_text: np.ndarray, x_meta: np.ndarray, y: np.ndarray, calibrate: np.ndarray, propose, rounds: int = ROUNDS) -> CoTrained | None:
        """Learns from labelled rows; those marked calibrate are kept for the last model. None unless both classes are in either part.

        propose(text model, meta model) gives, for each view, (x_text, x_meta, y) of new unlabelled rows of which that view is sure.
        """
        learn = ~calibrate
        if len(np.unique(y[learn])) < 2 or len(np.unique(y[calibrate])) < 2:
            return None
        views = (x_text, x_meta)
        own = [(v[learn], y[learn].astype(float)) for v in views]  # what each view learns from
        for turn in range(rounds + 1):
            models = [Logistic.fit(x, t) for x, t in own]
            if turn == rounds:
                break
            for k, (new_text, new_meta, new_y) in enumerate(propose(*models)):
                x, t = own[1 - k]
                own[1 - k] = (np.concatenate([x, (new_text, new_meta)[1 - k]]), np.concatenate([t, new_y.astype(float)]))
        logits = np.stack([m.logit(v[calibrate]) for m, v in zip(models, views, strict=True)], axis=1) / 10
        return CoTrained(*models, Logistic.fit(logits, y[calibrate].astype(float), rounds=1500))


def marked(labels: DataFrame) -> DataFrame:
    """(doc_id, y) of every id with a quality; good if all its rows are."""
    return labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("bigint").alias("doc_id")).agg((F.min("quality") > 0).cast("int").alias("y"))


def sampled(marks: DataFrame, labelled: int = LABELLED_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """Ids, ascending, and labels of the labelled sample: the rows with the smallest hashes."""
    rows = marks.orderBy(F.xxhash64("doc_id", F.lit(13)), "doc_id").limit(labelled).toPandas().sort_values("doc_id")
    return rows["doc_id"].to_numpy(np.int64), rows["y"].to_numpy(np.int64)


def _views(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    texts = Texts(part.column("text"))
    return text_view(texts), meta_view([part.column(c).fill_null("") for c in META_COLUMNS], np.diff(texts.offsets))


def as_numbers(x_text: np.ndarray, x_meta: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return x_text.astype(np.float32) / 255, x_meta.astype(np.float32)


def kept_views(rows: DataFrame) -> DataFrame:
    """(ids, body): both views of the rows with an id, a chunk of texts in each row, compressed."""

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        part = part.filter(part.column("doc_id").is_valid())
        body = np.hstack(_views(part)).tobytes()
        ids = part.column("doc_id").to_numpy().astype("<i8").tobytes()
        return pa.RecordBatch.from_arrays([pa.array([ids], pa.binary()), pa.array([pa.compress(body, codec="zstd", asbytes=True)], pa.binary())], ["ids", "body"])

    return rows.mapInArrow(over_chunks(run), "ids binary, body binary")


def unpacked_views(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Ids, text view and metadata view of every chunk."""
    width = TEXT_VIEW + META_BUCKETS
    for batch in batches:
        for ids, body in zip(batch.column("ids"), batch.column("body"), strict=True):
            own = np.frombuffer(ids.as_py(), "<i8")
            cells = np.frombuffer(pa.decompress(body.as_py(), decompressed_size=len(own) * width, codec="zstd", asbytes=True), np.uint8).reshape(len(own), width)
            yield own, cells[:, :TEXT_VIEW], cells[:, TEXT_VIEW:]


def fetched(views: DataFrame, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, ascending, and both views of the rows that the ids name, one of each id."""
    wanted = views.sparkSession.sparkContext.broadcast(np.sort(ids))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for own, a, b in unpacked_views(batches):
            at = np.flatnonzero(np.isin(own, wanted.value))
            cells = np.hstack([a[at], b[at]])
            yield pa.RecordBatch.from_arrays([pa.array(own[at]), pa.array([x.tobytes() for x in cells], pa.binary())], ["doc_id", "cells"])

    found = views.mapInArrow(run, "doc_id bigint, cells binary").groupBy("doc_id").agg(F.min("cells").alias("cells")).toPandas().sort_values("doc_id")
    cells = np.frombuffer(b"".join(found["cells"]), np.uint8).reshape(len(found), TEXT_VIEW + META_BUCKETS)
    return found["doc_id"].to_numpy(np.int64), *as_numbers(cells[:, :TEXT_VIEW], cells[:, TEXT_VIEW:])


def sure_rows(views: DataFrame, marks: DataFrame, models: tuple[Logistic, Logistic], used: list[set[int]], per_class: int = PER_CLASS) -> list[tuple[int, int, int]]:
    """(view, doc_id, y): of all unlabelled rows, those of which a view is surest, so many of each class, but for rows it handed over before.

    Only ids and scores of sure rows are shuffled.
    """
    shared = views.sparkSession.sparkContext.broadcast((models, [np.array(sorted(x), np.int64) for x in used]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        both, gone = shared.value
        for own, *cells in unpacked_views(batches):
            parts = []
            for k, (model, x) in enumerate(zip(both, as_numbers(*cells), strict=True)):
                p = _sigmoid(model.logit(x))
                at = np.flatnonzero((np.maximum(p, 1 - p) >= CONFIDENT) & ~np.isin(own, gone[k]))
                parts.append((np.full(len(at), k), own[at], (p[at] >= 0.5).astype(np.int64), np.round(np.maximum(p, 1 - p)[at] * 1e6).astype(np.int64)))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*parts, strict=True)], ["view", "doc_id", "y", "sure"])

    found = views.mapInArrow(run, "view bigint, doc_id bigint, y bigint, sure bigint")
    found = found.groupBy("view", "doc_id").agg(F.max("y").alias("y"), F.min("sure").alias("sure")).join(marks, "doc_id", "left_anti")
    found = cut(found)
    order = [F.desc("sure"), F.xxhash64("doc_id"), F.col("doc_id")]
    parts = [found.where((F.col("view") == k) & (F.col("y") == c)).orderBy(*order).limit(per_class) for k in (0, 1) for c in (0, 1)]
    return [(r["view"], r["doc_id"], r["y"]) for part in parts for r in part.collect()]


def learn(rows: DataFrame, labels: DataFrame) -> CoTrained | None:
    marks = marked(labels)
    ids, y = sampled(marks)
    if not len(ids):
        return None
    views = cut(kept_views(rows))
    own, x_text, x_meta = fetched(views, ids)
    y = y[np.searchsorted(ids, own)]
    used: list[set[int]] = [set(), set()]

    def propose(*models: Logistic) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        chosen = sure_rows(views, marks, models, used)
        found, new_text, new_meta = fetched(views, np.array(sorted({d for _, d, _ in chosen}), np.int64))
        out = []
        for k in (0, 1):
            mine = [(d, c) for view, d, c in chosen if view == k]
            used[k] |= {d for d, _ in mine}
            at = np.searchsorted(found, np.array([d for d, _ in mine], np.int64))
            out.append((new_text[at], new_meta[at], np.array([c for _, c in mine], np.int64)))
        return out

    return CoTrained.fit(x_text, x_meta, y, mix(own.view(np.uint64)) % np.uint64(4) == 0, propose)


def score_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", limit: float = 0.5) -> DataFrame:
    """doc_id, p_text, p_meta, score and kept (score at least limit) of every row.

    labels has doc_id and quality; any quality over 0 in all rows of an id is good. Null texts are empty; null metadata are
    values of their own. If the labels have fewer than two classes, all scores are null and all rows are kept. Repeated rows are scored each.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"), *(F.col(c).cast("string").alias(c) for c in META_COLUMNS))
    shared = docs.sparkSession.sparkContext.broadcast(learn(rows, labels))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            for part in chunks(batch, "text"):
                n = part.num_rows
                if model is None:
                    cells = [pa.nulls(n, pa.float64())] * 3 + [pa.array(np.ones(n, bool))]
                else:
                    p = model.scores(*as_numbers(*_views(part)))
                    cells = [*map(pa.array, p), pa.array(p[2] >= limit)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *cells], ["doc_id", "p_text", "p_meta", "score", "kept"])

    return rows.mapInArrow(run, "doc_id bigint, p_text double, p_meta double, score double, kept boolean")
