"""Language-model scoring by prediction by partial matching over bytes.

A text is coded as its words, A-Z in lower case, joined by single spaces, and one end symbol. The symbol after the last
ORDER bytes is coded in the longest context that has it; every shorter one is reached by an escape (method D: each symbol of a context
gives half a count to the escape), and symbols of the longer context are excluded there.

PpmTrie is the model as a trie in memory; it also codes adaptively. corpus_scores trains on a corpus of any size: a trie's
nodes are the distinct (context, symbol) keys, counted in hash buckets, completed context group by context group,
and looked up for the distinct keys of each batch of documents. No task holds more than a bucket, a context group or a batch,
and no part of the model is broadcast but the counts of single bytes after single bytes.
"""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import GOLDEN, Texts, chunks, crc_of_id, cut, mix

ORDER = 5
#: Part of a count that each symbol of a context gives to the escape.
DISCOUNT = 0.5
SYMBOLS = 257
END = 256
#: Keys from which on the contexts that end with one pair of bytes are split by the byte before it.
HOT_KEYS = 1 << 20
#: Bytes of text that a batch has on average, and batches whose keys one bucket holds.
BATCH_BYTES = 8 << 20
BATCHES_PER_BUCKET = 8


def stream(text: bytes) -> bytes:
    return b" ".join(text.lower().split())


class PpmTrie:
    """Context trie with escape estimation and symbol exclusion, for one process."""

    def __init__(self, order: int = ORDER):
        self.order = order
        self.nodes: dict[bytes, dict[int, int]] = defaultdict(dict)

    def _symbols(self, text: bytes):
        body = b" " * self.order + stream(text)
        for i in range(self.order, len(body)):
            yield body[i - self.order : i], body[i]
        yield body[len(body) - self.order :], END

    def _count(self, context: bytes, symbol: int) -> None:
        for k in range(self.order + 1):
            node = self.nodes[context[k:]]
            node[symbol] = node.get(symbol, 0) + 1

    def train(self, text: bytes) -> None:
        for context, symbol in self._symbols(text):
            self._count(context, symbol)

    def log10(self, context: bytes, symbol: int) -> float:
        out, excluded = 0.0, {}
        for k in range(self.order + 1):
            node = self.nodes.get(context[k:], {})
            total = sum(c for s, c in node.items() if s not in excluded)
            kinds = sum(1 for s in node if s not in excluded)
            if kinds:
                if symbol in node:
                    return out + math.log10((node[symbol] - DISCOUNT) / total)
                out += math.log10(DISCOUNT * kinds / total)
            excluded = node or excluded
        return out - math.log10(SYMBOLS - len(self.nodes.get(b"", {})))

    def score(self, text: bytes, adaptive: bool = False) -> float:
        """log10 probability of a text; an adaptive model learns each symbol once it is coded."""
        total = 0.0
        for context, symbol in self._symbols(text):
            total += self.log10(context, symbol)
            if adaptive:
                self._count(context, symbol)
        return total


# --- distinct keys of a batch ---------------------------------------------------


def gram_keys(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """For texts that stream() made: key (context bytes over symbol) of each coded symbol and the text it is in; an int64 has up to 6 context bytes and 9 bits."""
    pad, bodies = b" " * ORDER, texts
    data = np.frombuffer(b"".join(pad + b + b"\0" for b in bodies), np.uint8).astype(np.int64)
    sizes = np.array([len(b) + 1 for b in bodies], np.int64)
    first = np.cumsum(sizes + ORDER) - sizes
    owner = np.repeat(np.arange(len(texts)), sizes)
    at = np.arange(len(owner)) + np.repeat(first - (np.cumsum(sizes) - sizes), sizes)
    symbols = data[at]
    symbols[np.cumsum(sizes) - 1] = END
    keys = symbols
    for k in range(1, ORDER + 1):
        keys = keys | data[at - k] << (1 + 8 * k)
    return keys, owner


def bucket_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    return (mix(keys.astype(np.int64).view(np.uint64) + GOLDEN) % np.uint64(buckets)).astype(np.int64)


def spans_of(keys: np.ndarray, buckets: int) -> tuple[np.ndarray, list[tuple[int, int, int]]]:
    """The order of keys by bucket, and (bucket, from, to) of the buckets that have some; work and rows follow the keys, not the number of buckets."""
    bucket = bucket_of(keys, buckets)
    order = np.argsort(bucket, kind="stable")
    bucket = bucket[order]
    first = np.flatnonzero(np.diff(bucket, prepend=-1))
    return order, list(zip(bucket[first].tolist(), first.tolist(), [*first[1:].tolist(), len(bucket)], strict=False))


GRAMS, WORDS = 0, 1
#: Bytes of text whose keys are in memory together.
SLICE_BYTES = 2 << 20


def _keys(kind: int, rows: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """Keys of all symbols or words of the texts, and the text each is in."""
    if kind == GRAMS:
        return gram_keys(rows.column("text").to_pylist())
    texts = Texts(rows.column("text"))
    starts, ends, bounds = texts.words()
    return texts.hashes(starts, ends).view(np.int64), np.repeat(np.arange(len(texts)), np.diff(bounds))


@dataclass
class BatchKeys:
    """Distinct keys of a batch, ascending, their order by bucket, and where its texts have them, slice by slice."""

    kind: int
    rows: pa.RecordBatch
    buckets: int

    def __post_init__(self) -> None:
        self.slices, first = [], 0
        for part in chunks(self.rows, "text", SLICE_BYTES):
            keys, owner = _keys(self.kind, part)
            codes, own = pd.factorize(keys)
            order = np.argsort(own)
            rank = np.empty(len(order), np.int32)
            rank[order] = np.arange(len(order), dtype=np.int32)
            self.slices.append((rank[codes], np.asarray(own, np.int64)[order], (owner + first).astype(np.int32)))
            first += part.num_rows
        found = [own for _, own, _ in self.slices]
        self.distinct = np.unique(np.concatenate(found)) if found else np.zeros(0, np.int64)
        self.order, self.spans = spans_of(self.distinct, self.buckets)

    def counts(self, chosen: np.ndarray) -> np.ndarray:
        """Occurrences of the distinct keys in the chosen texts."""
        out = np.zeros(len(self.distinct), np.int64)
        for codes, own, owner in self.slices:
            out[np.searchsorted(self.distinct, own)] += np.bincount(codes[chosen[owner]], minlength=len(own))
        return out

    def sums(self, values: np.ndarray) -> np.ndarray:
        """Per text, the sum of the values of its keys; values belong to the distinct keys."""
        out = np.zeros(self.rows.num_rows)
        for codes, own, owner in self.slices:
            out += np.bincount(owner, values[np.searchsorted(self.distinct, own)][codes], len(out))
        return out

    def requests(self, batch: int, chosen: np.ndarray) -> list[tuple]:
        keys, counts = self.distinct[self.order], self.counts(chosen)[self.order]
        return [(batch, self.kind, b, pack_sorted(keys[lo:hi]), pack_counts(counts[lo:hi])) for b, lo, hi in self.spans]

    def replies(self, parts: list[np.ndarray]) -> np.ndarray:
        """Values that came bucket by bucket, in the order of the distinct keys."""
        out = np.empty(len(self.distinct))
        out[self.order] = np.concatenate(parts) if parts else []
        return out


def pack_counts(counts: np.ndarray) -> bytes:
    """Small counts as one byte each; those of 255 and more follow in 8 bytes; compressed."""
    return _squeeze(np.minimum(counts, 255).astype(np.uint8).tobytes() + counts[counts >= 255].astype(np.int64).tobytes())


def unpack_counts(packed: bytes, n: int) -> np.ndarray:
    raw = _expand(packed)
    out = np.frombuffer(raw, np.uint8, n).astype(np.int64)
    out[out == 255] = np.frombuffer(raw, np.int64, offset=n)
    return out


def pack_sorted(keys: np.ndarray) -> bytes:
    """Ascending keys as differences, their bytes by significance, compressed."""
    gaps = np.diff(keys, prepend=0).astype("<i8")
    return _squeeze(gaps.view(np.uint8).reshape(-1, 8).T.tobytes())


def unpack_sorted(packed: bytes) -> np.ndarray:
    planes = np.frombuffer(_expand(packed), np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view("<i8").ravel())


def _squeeze(raw: bytes) -> bytes:
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def _expand(packed: bytes) -> bytes:
    return pa.decompress(packed[8:], decompressed_size=int.from_bytes(packed[:8], "little"), codec="zstd", asbytes=True)


def packed_batches(source: DataFrame, batch_bytes: int) -> DataFrame:
    """(batch, body): rows in batches of about so many bytes of text, the texts as streams, in compressed Arrow form.

    A batch is cut where its rows are read, so that no text is shuffled for it.
    """

    def run(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first, number = TaskContext.get().partitionId() << 32, 0
        held: list[pa.RecordBatch] = []
        size = 0

        def out() -> pa.RecordBatch:
            body = pa.BufferOutputStream()
            whole = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            with pa.ipc.new_stream(body, whole.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as sink:
                sink.write_batch(whole)
            return pa.RecordBatch.from_arrays([pa.array([first + number]), pa.array([body.getvalue().to_pybytes()], pa.binary())], ["batch", "body"])

        for part in parts:
            for rows in chunks(part, "text"):
                texts = pa.array([stream(x or b"") for x in rows.column("text").to_pylist()], pa.binary())
                held.append(pa.RecordBatch.from_arrays([*rows.columns[:3], texts], ["doc_id", "held_out", "train", "text"]))
                size += texts.nbytes
                if size >= batch_bytes:
                    yield out()
                    held, size, number = [], 0, number + 1
        if held:
            yield out()

    return source.select("doc_id", "held_out", "train", "text").mapInArrow(run, "batch bigint, body binary")


def unpacked(body: bytes) -> pa.RecordBatch:
    return pa.ipc.open_stream(pa.py_buffer(body)).read_next_batch()


def _table(kinds: dict[str, pa.DataType], rows: list[tuple]) -> pa.Table:
    return pa.table({name: pa.array([r[i] for r in rows], kind) for i, (name, kind) in enumerate(kinds.items())})


# --- counting -------------------------------------------------------------------

REQUESTS = {"batch": pa.int64(), "kind": pa.int64(), "bucket": pa.int64(), "keys": pa.binary(), "counts": pa.binary()}
REQUESTS_SQL = "batch bigint, kind bigint, bucket bigint, keys binary, counts binary"


def requests(batches: DataFrame, buckets: int) -> DataFrame:
    """For each batch and bucket, the distinct keys of the batch's texts and their counts in training texts."""

    def run(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts:
            for batch, body in zip(part.column("batch").to_pylist(), part.column("body"), strict=True):
                rows = unpacked(body.as_py())
                train = rows.column("train").to_numpy(zero_copy_only=False)
                out = [x for kind in (GRAMS, WORDS) for x in BatchKeys(kind, rows, buckets).requests(batch, train)]
                yield _table(REQUESTS, out).combine_chunks().to_batches()[0]

    return batches.mapInArrow(run, REQUESTS_SQL)


WORD_REPLY, WORD_TOTAL, CONTEXTS, PAIRS = 0, 1, 2, 3
COUNTED = {"role": pa.int64(), "batch": pa.int64(), "bucket": pa.int64(), "keys": pa.binary(), "counts": pa.binary(), "n": pa.int64(), "v": pa.int64()}
COUNTED_SQL = "role bigint, batch bigint, bucket bigint, keys binary, counts binary, n bigint, v bigint"


def counted(asked: DataFrame) -> DataFrame:
    """Sums each bucket's keys.

    Words are answered at once, with totals; symbol keys go on by the two bytes before the symbol
    (batch holds those), with sums for one byte before it.
    """

    def run(group: pa.Table) -> pa.Table:
        kind, bucket = group.column("kind")[0].as_py(), group.column("bucket")[0].as_py()
        keys = [unpack_sorted(x.as_py()) for x in group.column("keys")]
        counts = [unpack_counts(x.as_py(), len(k)) for x, k in zip(group.column("counts"), keys, strict=True)]
        distinct, at = np.unique(np.concatenate(keys), return_inverse=True)
        sums = np.bincount(at, np.concatenate(counts).astype(np.float64), len(distinct)).astype(np.int64)
        rows: list[tuple] = []
        if kind == WORDS:
            rows.append((WORD_TOTAL, None, bucket, None, None, int(sums.sum()), int((sums > 0).sum())))
            lo = 0
            for batch, own in zip(group.column("batch").to_pylist(), keys, strict=True):
                rows.append((WORD_REPLY, batch, bucket, None, pack_counts(sums[at[lo : lo + len(own)]]), None, None))
                lo += len(own)
            return _table(COUNTED, rows)
        pair = distinct & 0x1FFFF
        one, back = np.unique(pair, return_inverse=True)
        for k, n in zip(one.tolist(), np.bincount(back, sums).astype(np.int64).tolist(), strict=True):
            if n:
                rows.append((PAIRS, k, bucket, None, None, n, None))
        context = distinct >> 9 & 0xFFFF
        order = np.argsort(context, kind="stable")
        distinct, sums, context = distinct[order], sums[order], context[order]
        first = np.flatnonzero(np.diff(context, prepend=-1))
        for lo, hi in zip(first, np.append(first[1:], len(context)), strict=True):
            rows.append((CONTEXTS, int(context[lo]), bucket, pack_sorted(distinct[lo:hi]), pack_counts(sums[lo:hi]), int(hi - lo), None))
        return _table(COUNTED, rows)

    return asked.groupBy("kind", "bucket").applyInArrow(run, COUNTED_SQL)


# --- the model ------------------------------------------------------------------


@dataclass
class ShortContexts:
    """Counts of symbols after each single byte, and after nothing."""

    after: np.ndarray
    alone: np.ndarray

    @staticmethod
    def of(pairs: list[tuple[int, int]]) -> ShortContexts:
        after = np.zeros((256, SYMBOLS), np.int64)
        for key, n in pairs:
            after[key >> 9, key & 0x1FF] += n
        return ShortContexts(after, after.sum(axis=0))


def _by(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Per row, the sum of counts over rows with its key, and the number of its key among distinct ones."""
    distinct, at = np.unique(keys, return_inverse=True)
    return np.bincount(at, counts, len(distinct))[at], at


def group_log10(keys: np.ndarray, counts: np.ndarray, short: ShortContexts, pair_counts: np.ndarray | None = None) -> np.ndarray:
    """log10 probabilities of keys (distinct; counts may be 0) that share the last two bytes before the symbol.

    The keys must be all that training texts have with these two bytes, or, if pair_counts has the counts of all symbols after them, all
    with the last three.
    """
    symbol = keys & 0x1FF
    last = int(keys[0] >> 9 & 0xFF)
    seen = counts > 0
    full = np.ones(len(keys))
    pair_counts = np.bincount(symbol, counts, SYMBOLS) if pair_counts is None else pair_counts
    levels = []  # per order, from the longest: symbol's count, total, kinds, all per row
    for mask_bits in range(8 * ORDER, 16, -8):
        context = keys >> 9 & ((1 << mask_bits) - 1)
        of_symbol, pair = _by(context << 9 | symbol, counts)
        total, node = _by(context, counts)
        owners = np.flatnonzero(seen)[np.unique(pair[seen], return_index=True)[1]]
        kinds = np.bincount(node[owners], minlength=node.max() + 1)
        levels.append({"c": of_symbol, "n": total, "t": kinds[node], "node": node, "owners": owners})
    levels.append({"c": pair_counts[symbol].astype(np.float64), "n": full * pair_counts.sum(), "t": full * (pair_counts > 0).sum()})
    # symbols of a longer context, counted in the next shorter one
    for longer, shorter in zip(levels, levels[1:], strict=False):
        held = np.bincount(longer["node"][longer["owners"]], shorter["c"][longer["owners"]], longer["node"].max() + 1)
        shorter["n_out"], shorter["t_out"] = held[longer["node"]], longer["t"]
    levels[0]["n_out"] = levels[0]["t_out"] = np.zeros(len(keys))
    two = pair_counts > 0
    after, alone = short.after[last], short.alone
    levels.append({"c": after[symbol], "n": full * after.sum(), "t": full * (after > 0).sum(), "n_out": full * after[two].sum(), "t_out": full * two.sum()})
    one = after > 0
    levels.append({"c": alone[symbol], "n": full * alone.sum(), "t": full * (alone > 0).sum(), "n_out": full * alone[one].sum(), "t_out": full * one.sum()})
    out, open_rows = np.zeros(len(keys)), np.ones(len(keys), bool)
    for level in levels:
        n, t = level["n"] - level["n_out"], level["t"] - level["t_out"]
        live = open_rows & (t > 0)
        hit = live & (level["c"] > 0)
        miss = live & ~hit
        out[hit] += np.log10((level["c"][hit] - DISCOUNT) / n[hit])
        out[miss] += np.log10(DISCOUNT * t[miss] / n[miss])
        open_rows &= ~hit
    out[open_rows] -= math.log10(max(1, SYMBOLS - int((alone > 0).sum())))
    return out


REPLIES = {"batch": pa.int64(), "kind": pa.int64(), "bucket": pa.int64(), "body": pa.binary()}
REPLIES_SQL = "batch bigint, kind bigint, bucket bigint, body binary"


def split_hot(contexts: DataFrame, hot) -> DataFrame:
    """(context, keys, counts) of (batch, keys, counts), batch being the last two bytes; pairs in the broadcast hot are split by the byte before them.

    With three bytes fixed a context has at most 65536 * 257 keys, whatever the corpus.
    """

    def run(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts:
            rows: list[tuple] = []
            for pair, packed, packed_counts in zip(part.column("batch").to_pylist(), part.column("keys").to_pylist(), part.column("counts").to_pylist(), strict=True):
                if pair not in hot.value:
                    rows.append((pair, packed, packed_counts))
                    continue
                keys = unpack_sorted(packed)
                counts, third = unpack_counts(packed_counts, len(keys)), keys >> 25 & 0xFF
                for byte in np.unique(third).tolist():
                    own = third == byte
                    rows.append((1 << 16 | byte << 17 | pair << 25, pack_sorted(keys[own]), pack_counts(counts[own])))
            yield _table({"context": pa.int64(), "keys": pa.binary(), "counts": pa.binary()}, rows).combine_chunks().to_batches()[0] if rows else _NO_CONTEXTS

    return contexts.mapInArrow(run, "context bigint, keys binary, counts binary")


_NO_CONTEXTS = pa.RecordBatch.from_arrays([pa.array([], pa.int64()), pa.array([], pa.binary()), pa.array([], pa.binary())], ["context", "keys", "counts"])


def pair_tables(contexts: DataFrame, hot) -> dict[int, np.ndarray]:
    """For each hot pair of bytes, the training counts of all symbols after it."""

    def run(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for part in parts:
            for pair, packed, counts in zip(part.column("batch").to_pylist(), part.column("keys").to_pylist(), part.column("counts").to_pylist(), strict=True):
                keys = unpack_sorted(packed)
                found = np.bincount(keys & 0x1FF, unpack_counts(counts, len(keys)), SYMBOLS)
                sums[pair] = sums[pair] + found if pair in sums else found
        rows = [(pair, s, int(n)) for pair, own in sums.items() for s, n in enumerate(own) if n]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in range(3)], ["pair", "symbol", "n"])

    out = {pair: np.zeros(SYMBOLS) for pair in hot}
    if hot:
        for r in contexts.where(F.col("batch").isin(sorted(hot))).mapInArrow(run, "pair bigint, symbol bigint, n bigint").groupBy("pair", "symbol").agg(F.sum("n").alias("n")).collect():
            out[r["pair"]][r["symbol"]] = r["n"]
    return out


def modelled(contexts: DataFrame, short, hot, buckets: int) -> DataFrame:
    """(bucket, keys, body): log10 probabilities of all keys, back in their buckets. hot has the tables of pairs that are split."""

    def run(group: pa.Table) -> pa.Table:
        keys = [unpack_sorted(x.as_py()) for x in group.column("keys")]
        counts = np.concatenate([unpack_counts(x.as_py(), len(k)) for x, k in zip(group.column("counts"), keys, strict=True)])
        keys = np.concatenate(keys)
        order = np.argsort(keys)
        keys, counts = keys[order], counts[order]
        values = group_log10(keys, counts, short.value, hot.value.get(int(keys[0] >> 9 & 0xFFFF))).astype(np.float32)
        order, spans = spans_of(keys, buckets)
        rows = [(b, pack_sorted(keys[order[lo:hi]]), values[order[lo:hi]].tobytes()) for b, lo, hi in spans]
        return _table({"bucket": pa.int64(), "keys": pa.binary(), "body": pa.binary()}, rows)

    return split_hot(contexts, hot).groupBy("context").applyInArrow(run, "bucket bigint, keys binary, body binary")


def answered(asked: DataFrame, model: DataFrame) -> DataFrame:
    """Log10 probabilities for every batch's distinct symbol keys, bucket by bucket."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        keys = np.concatenate([unpack_sorted(x.as_py()) for x in right.column("keys")])
        values = np.concatenate([np.frombuffer(x.as_py(), np.float32) for x in right.column("body")])
        order = np.argsort(keys)
        keys, values = keys[order], values[order]
        rows = [(batch, GRAMS, bucket, values[np.searchsorted(keys, unpack_sorted(raw.as_py()))].tobytes()) for batch, bucket, raw in zip(left.column("batch").to_pylist(), left.column("bucket").to_pylist(), left.column("keys"), strict=True)]
        return _table(REPLIES, rows)

    return asked.groupBy("bucket").cogroup(model.groupBy("bucket")).applyInArrow(run, REPLIES_SQL)


def corpus_scores(docs: DataFrame, train: Column, held_out: Column, id_col: str = "doc_id", text_col: str = "text", batch_bytes: int = BATCH_BYTES, hot_keys: int = HOT_KEYS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of every row.

    The model learns from all rows where train is true (null is false); every row is scored over its whole text. A null text is
    empty: the end symbol alone. Tokens are the words and one end. Without training rows every symbol is coded uniformly.
    Rows that repeat an id are scored each. Words are told apart by their bytes in a slice, and by 64-bit keyed hashes between slices.
    """
    source = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held_out"), F.coalesce(train, F.lit(False)).alias("train"), F.col(text_col).cast("binary").alias("text"))
    n_train = source.agg(F.coalesce(F.sum(F.col("train").cast("int")), F.lit(0))).first()[0]
    batches = cut(packed_batches(source, batch_bytes))
    buckets = max(1, -(-batches.count() // BATCHES_PER_BUCKET))
    asked = cut(requests(batches, buckets))
    sums = cut(counted(asked))
    totals = sums.where(f"role <> {WORD_REPLY}").groupBy("role", "batch").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).collect()
    words, kinds = next(((r["n"], r["v"]) for r in totals if r["role"] == WORD_TOTAL), (0, 0))
    context = docs.sparkSession.sparkContext
    short = context.broadcast(ShortContexts.of([(r["batch"], r["n"]) for r in totals if r["role"] == PAIRS]))
    contexts = sums.where(f"role = {CONTEXTS}").select("batch", "keys", "counts")
    hot = context.broadcast(pair_tables(contexts, {r["batch"] for r in totals if r["role"] == CONTEXTS and r["n"] > hot_keys}))
    model = modelled(contexts, short, hot, buckets)
    replies = answered(asked.where(f"kind = {GRAMS}").select("batch", "bucket", "keys"), model)
    word_replies = sums.where(f"role = {WORD_REPLY}").select("batch", F.lit(WORDS).cast("bigint").alias("kind"), "bucket", F.col("counts").alias("body"))
    replies = replies.unionByName(word_replies)
    train_tokens = words + n_train
    scale = math.log10(train_tokens + 0.5 * (kinds + (n_train > 0) + 1))
    end_log = math.log10(n_train + 0.5) - scale

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return empty
        rows = unpacked(left.column("body")[0].as_py())
        n = rows.num_rows
        body = {(k, b): x for k, b, x in zip(right.column("kind").to_pylist(), right.column("bucket").to_pylist(), right.column("body").to_pylist(), strict=True)}
        keys = BatchKeys(GRAMS, rows, buckets)
        score = keys.sums(keys.replies([np.frombuffer(body[GRAMS, b], np.float32) for b, _, _ in keys.spans]))
        keys = BatchKeys(WORDS, rows, buckets)
        counts = keys.replies([unpack_counts(body[WORDS, b], hi - lo) for b, lo, hi in keys.spans])
        base = keys.sums(np.log10(counts + 0.5) - scale) + end_log
        known = keys.sums(counts > 0).astype(np.int64) + int(n_train > 0)
        tokens = keys.sums(np.ones(len(counts))).astype(np.int64) + 1
        cells = [rows.column("doc_id"), rows.column("held_out"), tokens, known, np.full(n, train_tokens), base, score]
        return pa.Table.from_arrays([pa.array(c) if isinstance(c, np.ndarray) else c for c in cells], names)

    kind = source.schema["doc_id"].dataType.simpleString()
    names = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]
    empty = pa.Table.from_arrays([pa.array([], pa.int64() if kind == "bigint" else pa.string()), pa.array([], pa.bool_()), *[pa.array([], pa.int64())] * 3, *[pa.array([], pa.float64())] * 2], names)
    return batches.groupBy("batch").cogroup(replies.groupBy("batch")).applyInArrow(run, f"doc_id {kind}, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double")


def held_out_scores(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """corpus_scores learned from the rows whose crc32 of the id as text is not 1 modulo 5."""
    rest = F.pmod(crc_of_id(F.col(id_col)), F.lit(5))
    return corpus_scores(docs, rest != 1, rest == 1, id_col, text_col)
