"""Packing by concatenation and cutting, with prefix sums over partition totals.

The first pass tokenizes every document once, keeps the ids in the shared
checkpoint folder and sums the tokens of each partition. The prefix sums of these
totals give each partition its global offset; the second pass cuts the stream at
multiples of the window and records the pieces.
"""

from __future__ import annotations

import itertools
import os
import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import ARROW_BYTES, Texts, cut, over_chunks

WINDOW = 2048
END_ID = 1
#: Words whose ids one task keeps; others are tokenized when they come.
CACHED_WORDS = 400_000


#: Marks before which a run of letters surely ends.
MARKS = np.zeros(256, bool)
MARKS[list(b".,!?;:")] = True
LETTERS = np.zeros(256, bool)
LETTERS[97:123] = True


def pieces(texts: Texts) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of white-space separated words, also cut between an ASCII letter and a mark, and their number before each text.

    The tokenizer lower-cases, and never joins what it finds on both sides of such a place.
    """
    starts, ends, _ = texts.words()
    data = texts.data
    at = np.flatnonzero(MARKS[data[1:]] & LETTERS[data[:-1]]) + 1
    at = at[~np.isin(at, starts)]
    starts, ends = np.sort(np.concatenate([starts, at])), np.sort(np.concatenate([ends, at]))
    return starts, ends, np.searchsorted(starts, texts.offsets)


class WordTokenizer:
    """Tokenizes each distinct word of a chunk once and keeps the ids of as many words as its limit says."""

    def __init__(self, path: str, cached_words: int = CACHED_WORDS):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.cache: dict[bytes, bytes] = {}
        self.limit = cached_words
        self.ends = np.zeros(self.model.get_vocab_size(), bool)
        self.ends[[i for w, i in self.model.get_vocab().items() if w.endswith("</w>")]] = True

    def _one_by_one(self, words: list[str]) -> list[bytes]:
        return [np.array(x.ids, "<u2").tobytes() for x in self.model.encode_batch_fast(words, add_special_tokens=False)]

    def _learn(self, words: list[bytes], step: int = 256) -> None:
        """Put the ids of new words into the cache.

        Words of letters alone are one unit with one end each, so that many are tokenized as one text and cut after the ends; where the number of ends is
        another than that of words, and for all other words, each is a text.
        """
        plain, other = [], []
        for w in words:
            text = w.decode("utf-8")
            (plain if text.isalpha() and text == text.lower() and unicodedata.is_normalized("NFC", text) else other).append(text)
        blocks = [plain[lo : lo + step] for lo in range(0, len(plain), step)]
        for block, found in zip(blocks, self.model.encode_batch_fast([" ".join(x) for x in blocks], add_special_tokens=False), strict=True):
            ids = np.array(found.ids, "<u2")
            cuts = (np.flatnonzero(self.ends[ids]) + 1) * 2
            if len(cuts) == len(block) and (not len(cuts) or cuts[-1] == 2 * len(ids)):
                raw, lo = ids.tobytes(), 0
                for text, hi in zip(block, cuts.tolist(), strict=True):
                    self.cache[text.encode()] = raw[lo:hi]
                    lo = hi
            else:
                other += block
        for lo in range(0, len(other), 2000):
            part = other[lo : lo + 2000]
            self.cache.update(zip((x.encode() for x in part), self._one_by_one(part), strict=True))

    def encode(self, texts: Texts) -> list[bytes]:
        """Little-endian uint16 ids of each text; one that may have the name of a special token is tokenized as a whole."""
        raw = texts.data.tobytes()
        special = [i for i, (lo, hi) in enumerate(itertools.pairwise(texts.offsets.tolist())) if raw.find(b"<|", lo, hi) >= 0] if b"<|" in raw else []
        whole = self._one_by_one([raw[texts.offsets[i] : texts.offsets[i + 1]].decode() for i in special])
        texts = texts.lowered()
        starts, ends, bounds = pieces(texts)
        codes, distinct = texts.ranges(starts, ends)
        cache, words = self.cache, distinct.to_pylist()
        new = [w for w in words if w not in cache]
        self._learn(new)
        known = [cache[w] for w in words]
        for w in new[: max(0, len(cache) - self.limit)]:
            del cache[w]
        flat = np.frombuffer(b"".join(known), "<u2")
        sizes = np.fromiter(map(len, known), np.int64, len(known)) // 2
        own = sizes[codes]
        after = np.concatenate([[0], np.cumsum(own)])
        place = np.repeat((np.cumsum(sizes) - sizes)[codes] - after[:-1], own) + np.arange(after[-1])
        ids = flat[place].tobytes()
        cuts = (after[bounds] * 2).tolist()
        out = [ids[lo:hi] for lo, hi in itertools.pairwise(cuts)]
        for i, found in zip(special, whole, strict=True):
            out[i] = found
        return out


#: Tokenizers of this Python worker, which serves many tasks.
_MODELS: dict[str, WordTokenizer] = {}


def tokenized(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", end_id: int = END_ID) -> DataFrame:
    """(doc_id, ids): the ids of every document with the end id, as packed uint16."""
    end = np.array([end_id], "<u2").tobytes()

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        model = _MODELS.get(tokenizer_path) or _MODELS.setdefault(tokenizer_path, WordTokenizer(tokenizer_path))
        ids = model.encode(Texts(part.column("text")))
        return pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([x + end for x in ids], pa.binary())], ["doc_id", "ids"])

    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(over_chunks(run, limit=ARROW_BYTES), "doc_id bigint, ids binary")


def pack(docs: DataFrame, tokenizer_path: str, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A null or empty text is the end id alone. Rows are packed in the order of the input's partitions, so that
    every sequence but the last is full; repeated rows are packed as often as they are there.
    A null doc_id stays null.
    """
    ids = cut(tokenized(docs, tokenizer_path, id_col, text_col)).withColumn("part", F.spark_partition_id())
    totals = ids.groupBy("part").agg(F.sum(F.length("ids") / 2).cast("bigint").alias("n")).collect()
    offsets, at = {}, 0
    for part, n in sorted((r["part"], r["n"]) for r in totals):
        offsets[part] = at
        at += n

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        position = None
        for batch in batches:
            rows: list[tuple] = []
            for doc_id, part, raw in zip(batch.column("doc_id").to_pylist(), batch.column("part").to_pylist(), batch.column("ids"), strict=True):
                position = offsets[part] if position is None else position
                own = np.frombuffer(raw.as_py(), "<u2").astype("<u4")
                start = 0
                while start < len(own):
                    take = min(len(own) - start, window - position % window)
                    rows.append((doc_id, start, take, zlib.crc32(own[start : start + take].tobytes()), len(own), position // window, position % window))
                    start += take
                    position += take
            kinds = {"doc_id": pa.int64(), "start": pa.int64(), "length": pa.int64(), "ids_crc32": pa.int64(), "doc_tokens": pa.int64(), "sequence_id": pa.int64(), "offset": pa.int64()}
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds.values())], list(kinds))

    return ids.mapInArrow(run, "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint")
