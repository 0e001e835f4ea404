"""Exact duplicates by Patricia tries over partitions of equal length and content hash.

Every task inserts its normalised byte strings into one compressed radix trie; a terminal node keeps the smallest identifier and
the number of rows. The first round of tries runs where the rows are read, so that a text with a third of all rows reaches the second
round once per task and spill; a trie that passes its bound spills its largest subtrees. The second round has
a trie for each partition by length and leading bytes of the content hash, and inserts the full strings again in their order. There
every subtree beside the path of the last string is complete, so that a trie that passes its bound spills these and no string is handed out twice.
Strings are equal if they end in one node: hashes deal them out and name the results, but decide nothing.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import cut, join_with_hot_keys, one_space, rows_that_stay

#: Bytes of strings and nodes that the trie of one task holds before subtrees are spilled.
SPILL_BYTES = 32 << 20
#: Leading bytes of the content hash that deal strings of one length to partitions.
PREFIX_BYTES = 2


class Terminal:
    __slots__ = ("count", "smallest")

    def __init__(self) -> None:
        self.smallest: int | None = None
        self.count = 0

    def add(self, doc_id: int | None, count: int) -> None:
        self.count += count
        if doc_id is not None and (self.smallest is None or doc_id < self.smallest):
            self.smallest = doc_id


class PatriciaTrie:
    """A compressed radix trie over byte strings."""

    __slots__ = ("children", "label", "terminal")

    def __init__(self, label: bytes = b"") -> None:
        self.label = label
        self.children: dict[int, PatriciaTrie] = {}
        self.terminal: Terminal | None = None

    def insert(self, key: bytes, doc_id: int | None, count: int = 1) -> bool:
        """Add a row; true if the key is new."""
        node, at = self, 0
        while at < len(key):
            child = node.children.get(key[at])
            if child is None:
                child = node.children[key[at]] = PatriciaTrie(key[at:])
                at = len(key)
            elif key.startswith(child.label, at):
                at += len(child.label)
            else:
                same = _common(child.label, key, at)
                middle = PatriciaTrie(child.label[:same])
                child.label = child.label[same:]
                middle.children[child.label[0]] = child
                node.children[key[at]] = middle
                child, at = middle, at + same
            node = child
        new = node.terminal is None
        if new:
            node.terminal = Terminal()
        node.terminal.add(doc_id, count)
        return new

    def terminals(self) -> Iterator[tuple[bytes, Terminal]]:
        stack = [(self, b"")]
        while stack:
            node, prefix = stack.pop()
            prefix += node.label
            if node.terminal is not None:
                yield prefix, node.terminal
            stack += [(child, prefix) for child in node.children.values()]


def _common(label: bytes, key: bytes, at: int) -> int:
    """Length of the common prefix of label and key[at:], by bisection over slices."""
    low, high = 0, min(len(label), len(key) - at)
    while low < high:
        middle = (low + high + 1) // 2
        if key.startswith(label[:middle], at):
            low = middle
        else:
            high = middle - 1
    return low


#: Bytes that a node takes beside its label.
NODE_BYTES = 300


class SpillingTrie:
    """The trie of one task, which hands out subtrees when it has more bytes than it should."""

    def __init__(self, with_text: bool, spill_bytes: int) -> None:
        self.with_text, self.spill_bytes = with_text, spill_bytes
        self.root = PatriciaTrie()
        self.held = 0

    def insert(self, text: bytes, doc_id: int | None, count: int) -> None:
        if self.root.insert(text, doc_id, count):
            self.held += len(text) + NODE_BYTES

    def full(self) -> bool:
        return self.held >= self.spill_bytes

    def spill_largest(self) -> Iterator[pa.RecordBatch]:
        """Hand out the largest subtrees until at most half of the bound is held."""
        sizes = _sizes(self.root)
        node, prefix = self.root, b""
        while (big := max(node.children.values(), key=lambda c: sizes[id(c)], default=None)) is not None and 2 * sizes[id(big)] > self.spill_bytes and big.children:
            prefix, node = prefix + big.label, big
        order = sorted(node.children, key=lambda c: -sizes[id(node.children[c])])
        held, gone = sizes[id(self.root)], []
        for first in order:
            if 2 * held <= self.spill_bytes:
                break
            gone.append(node.children.pop(first))
            held -= sizes[id(gone[-1])]
        self.held = held
        yield from self._out((prefix, x) for x in gone)

    def spill_complete(self, last: bytes) -> Iterator[pa.RecordBatch]:
        """Hand out every subtree beside the path of the string last, for strings that come in order."""
        gone: list[tuple[bytes, PatriciaTrie]] = []
        node, at = self.root, 0
        while at < len(last):
            gone += [(last[:at], node.children.pop(first)) for first in [c for c in node.children if c != last[at]]]
            node = node.children[last[at]]
            at += len(node.label)
        self.held = len(last) + NODE_BYTES
        yield from self._out(gone)

    def spill_all(self) -> Iterator[pa.RecordBatch]:
        root, self.root, self.held = self.root, PatriciaTrie(), 0
        yield from self._out([(b"", root)])

    def _out(self, subtrees, step: int = 8 << 20) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        size = 0
        for prefix, subtree in subtrees:
            for rest, end in subtree.terminals():
                text = prefix + rest
                rows.append((len(text), hashlib.sha256(text).digest(), end.smallest, end.count, text))
                size += len(text) + NODE_BYTES
                if size >= step:
                    yield self._batch(rows)
                    rows, size = [], 0
        if rows:
            yield self._batch(rows)

    def _batch(self, rows: list[tuple]) -> pa.RecordBatch:
        kinds = {"text_len": pa.int64(), "digest": pa.binary(), "keep_id": pa.int64(), "n_rows": pa.int64(), "body": pa.binary()}
        names = list(kinds)[: 5 if self.with_text else 4]
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], kinds[c]) for i, c in enumerate(names)], names)


def _sizes(root: PatriciaTrie) -> dict[int, int]:
    """Bytes of every subtree, by the identity of its root."""
    order, stack = [], [root]
    while stack:
        node = stack.pop()
        order.append(node)
        stack += node.children.values()
    out: dict[int, int] = {}
    for node in reversed(order):
        out[id(node)] = len(node.label) + NODE_BYTES + sum(out[id(c)] for c in node.children.values())
    return out


def _normal(text: bytes | None) -> tuple[bytes, bytes]:
    body = one_space(text or b"")
    return body, hashlib.sha256(body).digest()


def owners(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", spill_bytes: int = SPILL_BYTES) -> DataFrame:
    """One row per distinct normalised text: text_len, digest, keep_id, n_rows."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = SpillingTrie(True, spill_bytes)
        for batch in batches:
            for doc_id, text in zip(batch.column("id").to_pylist(), batch.column("text"), strict=True):
                trie.insert(one_space(text.as_py() or b""), doc_id, 1)
                if trie.full():
                    yield from trie.spill_largest()
        yield from trie.spill_all()

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = SpillingTrie(False, spill_bytes)
        for batch in batches:
            for body, doc_id, count in zip(batch.column("body"), batch.column("keep_id").to_pylist(), batch.column("n_rows").to_pylist(), strict=True):
                text = body.as_py()
                trie.insert(text, doc_id, count)
                if trie.full():
                    yield from trie.spill_complete(text)
        yield from trie.spill_all()

    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("binary").alias("text"))
    terminals = rows.mapInArrow(local, "text_len bigint, digest binary, keep_id bigint, n_rows bigint, body binary")
    dealt = terminals.repartition("text_len", F.substring("digest", 1, PREFIX_BYTES)).select("keep_id", "n_rows", "body").sortWithinPartitions("body")
    return dealt.mapInArrow(merged, "text_len bigint, digest binary, keep_id bigint, n_rows bigint")


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_len, digest) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [_normal(x.as_py()) for x in batch.column("text")]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([len(b) for b, _ in found], pa.int64()), pa.array([d for _, d in found], pa.binary())], ["doc_id", "text_len", "digest"])

    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("binary").alias("text"))
    return rows.mapInArrow(run, "doc_id bigint, text_len bigint, digest binary")


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", spill_bytes: int = SPILL_BYTES) -> DataFrame:
    """For every row its owner: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when identical after each run of ASCII white space became
    one space. A null text counts as empty. The row with the smallest doc_id
    stays; rows that repeat that doc_id are all marked kept; a null doc_id never
    owns a group with other ids, and a group of null ids only has keep_id null and kept
    true. Other columns are ignored. An empty table gives no rows.
    """
    found = cut(owners(docs, id_col, text_col, spill_bytes))
    total = found.agg(F.coalesce(F.sum("n_rows"), F.lit(0))).first()[0]
    out = join_with_hot_keys(digests(docs, id_col, text_col), found, ["text_len", "digest"], "n_rows", total)
    return out.select(
        "doc_id",
        "keep_id",
        F.col("n_rows").alias("group_size"),
        F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that stay, with all their columns; of rows with the same id and text one stays. Rows without an id all stay."""
    groups = exact_groups(docs, id_col, text_col)
    stay = groups.where("kept").select(F.col("doc_id").alias("stay_id"), F.unhex("text_sha256").alias("stay_key"))
    return rows_that_stay(docs, stay, id_col, text_col, lambda raw: _normal(raw)[1])
