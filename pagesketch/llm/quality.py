"""Quality rules: base measures, then a hashed n-gram log-likelihood ratio.

A multinomial over hashed word unigrams and bigrams is counted over trusted
documents, another over the whole raw corpus. A document's score is the mean, over
its n-grams, of the logarithm of trusted over raw probability. The threshold is a
fixed quantile of the scores of trusted documents that the model did not learn from,
found from an exact histogram.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import GOLDEN, Texts, chunks, cut, mix, over_chunks, run_codes

#: Characters counted as symbols.
SYMBOLS = b"#*$%&|<>"
IS_SYMBOL = np.zeros(256, bool)
IS_SYMBOL[list(SYMBOLS)] = True

#: Hash buckets of the multinomials, a parameter of the model and not of the data.
BUCKETS = 1 << 16
#: Most labelled rows of which the trusted multinomial is learned; the raw one counts every row, and the threshold every other trusted row.
TRUSTED_ROWS = 20_000
#: Share of trusted documents that the threshold may reject.
TRUSTED_LOSS = 0.0005
#: Scores are compared on a grid, so that every run gives the same verdicts.
GRID = 1000


def _repeats(codes: np.ndarray, text_of: np.ndarray) -> np.ndarray:
    """Marks words in 3-word windows found twice or more in their text; codes tells words apart exactly."""
    marks = np.zeros(len(codes), bool)
    at, found = run_codes(codes, text_of, 3)
    if len(at):
        some = np.bincount(found)[found] > 1  # others are alone in the whole chunk
        at, found = at[some], found[some]
        own = pd.factorize(found * (int(text_of[-1]) + 1) + text_of[at])[0]
        twice = at[np.bincount(own, minlength=1)[own] > 1]
        for shift in range(3):
            marks[twice + shift] = True
    return marks


def _per_text(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
    return total[bounds[1:]] - total[bounds[:-1]]


def base_measures(texts: Texts) -> dict[str, np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words of each text."""
    starts, ends, bounds = texts.words()
    n = len(texts)
    data, offsets = texts.data, texts.offsets
    n_words = np.diff(bounds)
    head = (data & 0xC0) != 0x80
    blank = np.isin(data, np.frombuffer(b" \t\n\v\f\r", np.uint8))
    marks = _repeats(texts.ranges(starts, ends)[0], np.repeat(np.arange(n), n_words)) if len(starts) else np.zeros(0, bool)
    dup = np.zeros(n, np.int64)
    breaks = np.flatnonzero(data == 10)
    many = np.flatnonzero(np.diff(np.searchsorted(breaks, offsets)) > 0)
    for i in many:
        lines = [x for x in bytes(data[offsets[i] : offsets[i + 1]]).split(b"\n") if x and not x.isspace()]
        dup[i] = len(lines) - len(set(lines))
    return {
        "n_words": n_words.astype(np.int64),
        "word_chars": _per_text(head & ~blank, offsets),
        "n_symbols": _per_text(IS_SYMBOL[data], offsets),
        "n_dup_lines": dup,
        "n_repeat_words": _per_text(marks, bounds),
    }


def grams(texts: Texts, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all lower-cased unigrams and bigrams, with the text of each."""
    texts = texts.lowered()
    starts, ends, bounds = texts.words()
    hashes = texts.hashes(starts, ends)
    text_of = np.repeat(np.arange(len(texts)), np.diff(bounds))
    pair = np.flatnonzero(text_of[1:] == text_of[:-1])
    both = mix(hashes[pair] * GOLDEN + hashes[pair + 1]) if len(pair) else hashes[:0]
    keys = np.concatenate([hashes, both]) % np.uint64(buckets)
    return keys.astype(np.int64), np.concatenate([text_of, text_of[pair]])


def trusted_rows_of(labels: DataFrame) -> DataFrame:
    """The doc_id of every labelled row that is good and never toxic, once each."""
    marks = labels.groupBy(F.col("doc_id").cast("bigint").alias("doc_id")).agg((F.min("quality") == 1).alias("good"), (F.max(F.coalesce("toxic", F.lit(0))) == 1).alias("bad"))
    return marks.where("doc_id is not null and good and not bad").select("doc_id")


def trusted_ids(labels: DataFrame, most: int = TRUSTED_ROWS) -> np.ndarray:
    """Ids of trusted rows for the multinomial: all, or those with the smallest hashes if there are more than most."""
    rows = trusted_rows_of(labels).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most).toPandas()
    return np.sort(rows["doc_id"].to_numpy(np.int64))


def _learned(part: pa.RecordBatch, ids: np.ndarray) -> np.ndarray:
    """Marks rows that the multinomial learns from: half of the ids. All other trusted rows set the threshold."""
    column = part.column("doc_id")
    own = column.fill_null(0).to_numpy()
    return np.isin(own, ids) & column.is_valid().to_numpy(zero_copy_only=False) & (mix(own.view(np.uint64)) % np.uint64(2) == np.uint64(0))


def ngram_counts(rows: DataFrame, trusted, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    """Counts of the hashed n-grams of the rows that half the ids in the broadcast array trusted name, and of all rows.

    Each task sends one vector of at most a fixed length, added up by bucket before it reaches the driver.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((2, buckets), np.int64)
        for batch in batches:
            for part in chunks(batch, "text"):
                keys, text_of = grams(Texts(part.column("text")), buckets)
                sums[1] += np.bincount(keys, minlength=buckets)
                sums[0] += np.bincount(keys[_learned(part, trusted.value)[text_of]], minlength=buckets)
        found = np.flatnonzero(sums[1])
        yield pa.RecordBatch.from_arrays([pa.array(found), pa.array(sums[0][found]), pa.array(sums[1][found])], ["bucket", "trusted", "raw"])

    parts = rows.mapInArrow(run, "bucket bigint, trusted bigint, raw bigint")
    table = parts.groupBy("bucket").agg(F.sum("trusted").alias("trusted"), F.sum("raw").alias("raw")).toPandas()
    out = np.zeros((2, buckets))
    out[0][table["bucket"]] = table["trusted"]
    out[1][table["bucket"]] = table["raw"]
    return out[0], out[1]


#: Occurrences added to every bucket of both multinomials.
PSEUDO_COUNTS = 16.0


def ratios(trusted: np.ndarray, raw: np.ndarray, weight: float = PSEUDO_COUNTS) -> np.ndarray:
    """log of smoothed trusted over raw probability of each bucket.

    The raw counts are brought to the number of trusted n-grams before both are smoothed with the same pseudo-counts: buckets that the
    trusted rows hardly can have say nothing, and a corpus that is repeated gives the same ratios.
    """
    if not trusted.any():
        return np.zeros(len(raw))
    return np.log((trusted + weight) / (raw * (trusted.sum() / raw.sum()) + weight))


class Judge:
    """The ratio model of a corpus: measures and verdicts for its rows.

    Null and empty texts have no word, so that they fail the base rules; their ratio is 0. Without trusted rows
    every ratio is 0 and the base rules decide. Repeated rows are judged each. Other columns are ignored by verdicts and
    carried along by kept_rows.
    """

    def __init__(self, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", buckets: int = BUCKETS, trusted_rows: int = TRUSTED_ROWS, trusted_loss: float = TRUSTED_LOSS):
        self.docs, self.labels, self.id_col, self.text_col, self.loss = docs, labels, id_col, text_col, trusted_loss
        context = docs.sparkSession.sparkContext
        self.trusted = context.broadcast(trusted_ids(labels, trusted_rows))
        self.table = context.broadcast(ratios(*ngram_counts(self._rows(), self.trusted, buckets)))

    def _rows(self) -> DataFrame:
        return self.docs.select(F.col(self.id_col).cast("bigint").alias("doc_id"), F.col(self.text_col).alias("text"))

    def _scored(self) -> DataFrame:
        table, trusted = self.table, self.trusted

        def run(part: pa.RecordBatch) -> pa.RecordBatch:
            texts = Texts(part.column("text"))
            base, llr = base_measures(texts), grid_ratio(texts, table.value)
            cells = {"doc_id": part.column("doc_id"), "learned": pa.array(_learned(part, trusted.value))} | {k: pa.array(v) for k, v in base.items()}
            cells |= {"llr_grid": pa.array(llr), "base_failed": pa.array(base_failed(base))}
            return pa.RecordBatch.from_arrays(list(cells.values()), list(cells))

        kinds = "doc_id bigint, learned boolean, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, llr_grid bigint, base_failed boolean"
        return self._rows().mapInArrow(over_chunks(run), kinds)

    def _limit(self, scored: DataFrame) -> int:
        """The threshold over all trusted rows that were not learned from. Only their ids and grid scores are joined to the ids of all labels."""
        held_out = scored.where("not learned and not base_failed").select("doc_id", "llr_grid")
        return threshold(held_out.join(trusted_rows_of(self.labels), "doc_id", "left_semi"), self.loss)

    def verdicts(self) -> DataFrame:
        """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, llr, base_failed and kept of every row."""
        scored = cut(self._scored())
        limit = self._limit(scored)
        out = scored.withColumn("kept", ~F.col("base_failed") & (F.col("llr_grid") >= F.lit(limit)))
        return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", (F.col("llr_grid") / GRID).alias("llr"), "base_failed", "kept")

    def kept_rows(self) -> DataFrame:
        """The rows of docs that are kept, with all their columns; the texts are never shuffled."""
        limit = self._limit(self._scored())
        table, text_col = self.table, self.text_col

        def run(part: pa.RecordBatch) -> pa.RecordBatch:
            texts = Texts(part.column(text_col))
            return part.filter(pa.array(~base_failed(base_measures(texts)) & (grid_ratio(texts, table.value) >= limit)))

        return self.docs.mapInArrow(over_chunks(run, text_col), self.docs.schema)


def base_failed(base: dict[str, np.ndarray]) -> np.ndarray:
    return (base["n_words"] < 50) | (100 * base["n_repeat_words"] > 50 * base["n_words"])


def grid_ratio(texts: Texts, table: np.ndarray) -> np.ndarray:
    """Mean ratio of each text's n-grams, as a whole number of grid steps."""
    keys, text_of = grams(texts, len(table))
    sums = np.bincount(text_of, table[keys], len(texts))
    sizes = np.maximum(np.bincount(text_of, minlength=len(texts)), 1)
    return np.round(sums / sizes * GRID).astype(np.int64)


def threshold(scored: DataFrame, loss: float) -> int:
    """The largest grid score under which at most that share of the rows lies.

    The histogram has one row per grid value; its size is bounded by the range of a ratio.
    """
    found = sorted(map(tuple, scored.groupBy("llr_grid").count().collect()))
    total, below = sum(n for _, n in found), 0
    for value, n in found:
        if below + n > loss * total:
            return value
        below += n
    return found[-1][0] if found else -(1 << 60)
