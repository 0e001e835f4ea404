"""Near-duplicate groups: SuperMinHash signatures, banding, verification on full sets, union-find.

Every element of a set draws a random permutation of the signature's places, one place a level, with a value of level plus
fraction. A place keeps its smallest value, so that a set stops at the first level after which all its places are filled.

Rows whose lower-cased words are the same sequence are one representative. In each bucket of equal bands all members are compared
with the bucket's smallest one; that takes a pair a member, and counts the true shingles of both texts. Buckets whose members are then not all in one
component are compared once more across their components, so that no pair of a bucket is left out.
With 42 bands of 6 places, two sets of similarity 0.8 share no bucket with a probability under 3 in a million.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import GOLDEN, Texts, cut, mix, over_chunks, rows_that_stay, run_codes, text_digest
from pagesketch.llm.components import UnionFind, components

BANDS, ROWS = 42, 6
#: Members that one task compares with a copy of a hub's set, at most.
SALT_ROWS = 500
LEVEL_BITS = np.uint64(48)
#: Members and bytes of texts that one block has, and how far under the wanted similarity an estimate may lie (1: any estimate is looked at exactly).
BLOCK_ROWS = 1000
BLOCK_BYTES = 8 << 20
SLACK = 0.15


def shingle_sets(texts: Texts, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct fingerprints of each text's shingles, end to end, and their bounds."""
    texts = texts.lowered()
    starts, ends, bounds = texts.words()
    hashes = texts.hashes(starts, ends)
    joined = hashes.copy()
    for shift in range(1, width):
        joined = joined[:-1] if len(joined) else joined
        joined = mix(joined * GOLDEN + hashes[shift : shift + len(joined)])
    sets, sizes = [], np.zeros(len(texts) + 1, np.int64)
    for i in range(len(texts)):
        lo, hi = bounds[i], bounds[i + 1]
        if hi - lo >= width:
            own = np.unique(joined[lo : hi - width + 1])
        elif hi > lo:
            own = hashes[lo : lo + 1]
            for k in range(lo + 1, hi):
                own = mix(own * GOLDEN + hashes[k : k + 1])
            own = mix(own + np.uint64(hi - lo))
        else:
            continue
        sets.append(own)
        sizes[i + 1] = len(own)
    return (np.concatenate(sets) if sets else np.zeros(0, np.uint64)), np.cumsum(sizes)


def signatures(sets: np.ndarray, bounds: np.ndarray, places: int) -> np.ndarray:
    """SuperMinHash values, one row a set: level in the upper bits, fraction in the lower ones.

    All sets advance level by level; a set's elements drop out as soon as no place can improve.
    """
    n = len(bounds) - 1
    empty = np.uint64(places) << LEVEL_BITS
    best = np.full(n * places, empty, np.uint64)
    elements, owner = sets, np.repeat(np.arange(n), np.diff(bounds))
    swaps: list[np.ndarray] = []
    for level in range(places):
        draw = mix(elements + np.uint64((level + 1) * int(GOLDEN) % (1 << 64)))
        place = level + ((draw & np.uint64(0xFFFF)) * np.uint64(places - level) >> np.uint64(16)).astype(np.int64)
        swaps.append(place)
        for i in range(level - 1, -1, -1):
            place = np.where(place == swaps[i], i, place)
        np.minimum.at(best, owner * places + place, (np.uint64(level) << LEVEL_BITS) | (draw >> np.uint64(16)))
        open_sets = (best.reshape(n, places) >= (np.uint64(level + 1) << LEVEL_BITS)).any(axis=1)
        stay = open_sets[owner]
        if not stay.any():
            break
        if not stay.all():
            elements, owner, swaps = elements[stay], owner[stay], [s[stay] for s in swaps]
    return best.reshape(n, places)


def band_keys(values: np.ndarray, bands: int, rows: int) -> np.ndarray:
    cells = values.reshape(len(values), bands, rows)
    out = np.broadcast_to(mix(np.arange(bands, dtype=np.uint64) + np.uint64(77)), (len(values), bands)).copy()
    for r in range(rows):
        out = mix(out * GOLDEN + cells[:, :, r])
    return out.view(np.int64)


def normal(raw: bytes) -> bytes:
    """The lower-cased words, one space between them."""
    return b" ".join(raw.lower().split())


def text_key(raw: bytes) -> bytes:
    """Digest of a text's word sequence."""
    return text_digest(normal(raw))


def exact_sets(texts: Texts, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingles of each normal text, end to end, and their bounds.

    A shingle is a number that only the same words have among these texts; no fingerprint is used.
    """
    starts, ends, bounds = texts.words()
    n_words = np.diff(bounds)
    codes, _ = texts.ranges(starts, ends) if len(starts) else (np.zeros(0, np.int64), None)
    text_of = np.repeat(np.arange(len(texts)), n_words)
    at, shingle = run_codes(codes, text_of, width)
    short = np.flatnonzero((n_words > 0) & (n_words < width))
    whole, _ = texts.ranges(texts.offsets[:-1][short], texts.offsets[1:][short]) if len(short) else (shingle[:0], None)
    first = int(shingle.max(initial=-1)) + 1
    total = first + int(whole.max(initial=-1)) + 1
    found = np.unique(np.concatenate([text_of[at] * total + shingle, short * total + first + whole]))
    owner = found // max(total, 1)
    return found - owner * total, np.searchsorted(owner, np.arange(len(texts) + 1))


def sketches(docs: DataFrame, width: int, bands: int = BANDS, rows: int = ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, digest of the word sequence, and band keys."""

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        texts = Texts(part.column("text")).lowered()
        body, offsets = texts.data.tobytes(), texts.offsets.tolist()
        digests = [text_key(body[lo:hi]) for lo, hi in zip(offsets, offsets[1:], strict=False)]
        sets, bounds = shingle_sets(texts, width)
        keys = band_keys(signatures(sets, bounds, bands * rows), bands, rows)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(len(keys) + 1, dtype=np.int32) * bands), pa.array(keys.ravel()))
        return pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(np.diff(bounds)), pa.array(digests, pa.binary()), lists], ["doc_id", "n_shingles", "digest", "bands"])

    source = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    return source.mapInArrow(over_chunks(run), "doc_id bigint, n_shingles bigint, digest binary, bands array<bigint>")


def _close_sizes(a: str, b: str, percent: int):
    return F.least(a, b) * 100 >= F.greatest(a, b) * percent


def bodies(docs: DataFrame, names: DataFrame, repeated: bool) -> DataFrame:
    """(rep, body): the normal text of each of names (rep, doc_id, digest). repeated says that rows of docs may share an id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = zip(batch.column("rep").to_pylist(), batch.column("digest").to_pylist(), batch.column("text").cast(pa.binary()), strict=True)
            found = [(rep, body) for rep, digest, raw in rows if text_digest(body := normal(raw.as_py() or b"")) == digest]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in found], pa.int64()), pa.array([r[1] for r in found], pa.binary())], ["rep", "body"])

    found = docs.join(names.select("rep", "doc_id", "digest"), "doc_id").select("rep", "digest", "text").mapInArrow(run, "rep bigint, body binary")
    return found.dropDuplicates(["rep"]) if repeated else found


def verified(texts: DataFrame, pairs: DataFrame, width: int, percent: int, n: int) -> DataFrame:
    """The pairs (hub, member) whose true shingles are similar, as edges (src, dst); texts has their (rep, body).

    A hub's text is copied to as many tasks as its members need; texts stream past it.
    """
    sizes = cut(pairs.groupBy("hub").agg(F.ceil(F.count("*") / SALT_ROWS).cast("int").alias("salts")), n)
    members = pairs.join(sizes, "hub").withColumn("salt", F.pmod(F.xxhash64("member"), F.col("salts")).cast("int"))
    members = members.join(texts.withColumnRenamed("rep", "member"), "member").select("hub", "salt", F.lit(1).alias("kind"), "member", "body")
    hubs = sizes.withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).join(texts.withColumnRenamed("rep", "hub"), "hub")
    hubs = hubs.select("hub", "salt", F.lit(0).alias("kind"), F.col("hub").alias("member"), "body")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            if held is not None:
                batch = pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
            hub, member, head = batch.column("hub").to_numpy(), batch.column("member").to_numpy(), np.flatnonzero(batch.column("kind").to_numpy() == 0)
            sets, bounds = exact_sets(Texts(batch.column("body")), width)
            sizes, marks = np.diff(bounds), np.zeros(int(sets.max(initial=-1)) + 1, bool)
            src, dst = [], []
            for lo, hi in zip(head.tolist(), [*head[1:].tolist(), len(hub)], strict=True):
                own = sets[bounds[lo] : bounds[lo + 1]]
                marks[own] = True
                total = np.concatenate([[0], np.cumsum(marks[sets[bounds[lo + 1] : bounds[hi]]])])
                marks[own] = False
                both = np.diff(total[bounds[lo + 1 : hi + 1] - bounds[lo + 1]])
                like = (100 * both >= percent * (sizes[lo] + sizes[lo + 1 : hi] - both)) & (hub[lo + 1 : hi] == hub[lo])
                src.append(member[lo + 1 : hi][like])
                dst.append(hub[lo + 1 : hi][like])
            held = batch.slice(int(head[-1]), 1)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), pa.int64()) for x in (src, dst)], ["src", "dst"])

    rows = hubs.unionByName(members).repartition("hub", "salt").sortWithinPartitions("hub", "salt", "kind")
    return rows.mapInArrow(run, "src bigint, dst bigint")


def named_classes(full: DataFrame, repeated: bool) -> DataFrame:
    """One row a word sequence: rep, its number among sequences, doc_id, the smallest id that has it, n_shingles, digest and bands.

    rep is doc_id but where ids are repeated with several texts; there all but one get a hash as their number.
    """
    classes = full.groupBy("digest").agg(F.min("doc_id").alias("doc_id"), F.first("n_shingles").alias("n_shingles"), F.first("bands").alias("bands"))
    if not repeated:
        return cut(classes.withColumn("rep", F.col("doc_id")))
    classes = cut(classes)
    several = classes.groupBy("doc_id").agg(F.count("*").alias("n"), F.min("digest").alias("own_digest")).where("n > 1").drop("n")
    rep = F.when(F.coalesce(F.col("own_digest") == F.col("digest"), F.lit(True)), F.col("doc_id")).otherwise(F.xxhash64("doc_id", "digest"))
    return cut(classes.join(several, "doc_id", "left").withColumn("rep", rep).drop("own_digest"))


def _grouped(docs: DataFrame, width: int, percent: int, bands: int, rows: int, id_col: str, text_col: str, slack: float) -> DataFrame:
    """near_groups with the digest of each row's word sequence and the rep that names its group, null for a text without words."""
    source = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    found = cut(sketches(source, width, bands, rows))
    n = found.count()
    cells_n = n * bands
    full = found.where("n_shingles > 0 and doc_id is not null")
    repeated = bool(full.groupBy("doc_id").count().where("count > 1").take(1))
    classes = named_classes(full, repeated)
    names = classes.select("rep", "doc_id", "digest")
    cells = classes.select("rep", "n_shingles", F.explode("bands").alias("bucket"))
    hubs = cells.groupBy("bucket").agg(F.min(F.struct("rep", "n_shingles")).alias("hub"), F.count("*").alias("n")).where("n > 1")
    hubs = cut(hubs, cells_n)  # kept, so that the join can split a hot bucket
    members = cut(cells.join(hubs, "bucket").select("bucket", "rep", "n_shingles", F.col("hub.rep").alias("hub"), F.col("hub.n_shingles").alias("hub_n")), cells_n)
    pairs = members.where((F.col("rep") != F.col("hub")) & _close_sizes("n_shingles", "hub_n", percent)).select("hub", F.col("rep").alias("member")).distinct()
    pairs = cut(pairs, cells_n)
    asked = pairs.select(F.col("hub").alias("rep")).unionByName(pairs.select(F.col("member").alias("rep"))).distinct()
    texts = cut(bodies(source, names.join(asked, "rep", "left_semi"), repeated))
    edges = cut(verified(texts, pairs, width, percent, n))
    links = components(edges, rows=n)
    more = cut(missed_links(source, names, members, links, width, percent, bands * rows, n, slack, repeated))
    if more.take(1):
        links = components(edges.unionByName(more), rows=n)
    owner = names.join(links.withColumnRenamed("node", "rep"), "rep", "left").select("doc_id", "digest", F.coalesce("component", "rep").alias("group_rep"))
    if repeated:
        owner = owner.join(owner.groupBy("group_rep").agg(F.min("doc_id").alias("component")), "group_rep")
    else:
        owner = owner.withColumn("component", F.col("group_rep"))
    out = found.join(owner.select("digest", "component", "group_rep"), "digest", "left")
    component = F.when(F.col("n_shingles") > 0, F.coalesce("component", "doc_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"), "digest", "group_rep")


def near_groups(docs: DataFrame, width: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS, id_col: str = "doc_id", text_col: str = "text", slack: float = SLACK) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row.

    A text without words has the empty set and is linked with nothing; one with fewer words than width has one shingle.
    Documents are linked if 100 * intersection >= percent * union of their sets; component_id is the smallest
    doc_id reachable. Rows that repeat a doc_id are each grouped by their own text; a row is kept if its doc_id is the component's. A null doc_id is
    its own, null, component unless another row has its words. With slack 1 no pair that shares a bucket is left out by an estimate.
    """
    return _grouped(docs, width, percent, bands, rows, id_col, text_col, slack).drop("digest", "group_rep")


def small_signatures(texts: DataFrame, width: int, places: int) -> DataFrame:
    """(rep, bytes): one byte of each signature value of (rep, body)."""

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        sets, bounds = shingle_sets(Texts(part.column("body")), width)
        values = mix(signatures(sets, bounds, places).ravel()).astype(np.uint8).reshape(-1, places)
        return pa.RecordBatch.from_arrays([part.column("rep"), pa.array([x.tobytes() for x in values], pa.binary())], ["rep", "bytes"])

    return texts.mapInArrow(over_chunks(run, "body"), "rep bigint, bytes binary")


def _in_blocks(rows: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """Rows of a key dealt to its blocks, and each block together with every other block of the key.

    Columns: key, low and high (the two blocks), block (the row's own), then the given ones, sorted by the first three.
    """
    rows = rows.withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.select(key, F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", *columns)
    return rows.repartition(key, "low", "high").sortWithinPartitions(key, "low", "high")


def _forests(rows: DataFrame, compare) -> DataFrame:
    """Edges (src, dst) of a forest over the pairs that compare(group) yields, for each key and pair of blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, group = None, []

        def forest() -> list[tuple]:
            sets = UnionFind()
            for a, b in compare(group) if len(group) > 1 else ():
                sets.join(a, b)
            return sets.forest()

        def out(edges: list[tuple]) -> pa.RecordBatch:
            edges = [e for e in edges if e[0] != e[1]]
            return pa.RecordBatch.from_arrays([pa.array([e[i] for e in edges], pa.int64()) for i in range(2)], ["src", "dst"])

        for batch in batches:
            edges: list[tuple] = []
            for *own, block, rep, component, size, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if own != key:
                    edges += forest()
                    key, group = own, []
                group.append((block, rep, component, size, raw))
            yield out(edges)
        yield out(forest())

    return rows.mapInArrow(run, "src bigint, dst bigint")


def _crossing(group: list[tuple], i: int, cells: tuple[np.ndarray, ...], percent: int) -> np.ndarray:
    """Partners of row i: in the other block or after it, in another component, of a close size."""
    block, rep, component, size = cells
    mask = (rep > rep[i]) if block[0] == block[-1] and (block == block[0]).all() else (block > block[i])
    mask = mask & (component != component[i]) & (100 * np.minimum(size, size[i]) >= percent * np.maximum(size, size[i]))
    return np.flatnonzero(mask)


def _cells(group: list[tuple]) -> tuple[np.ndarray, ...]:
    return tuple(np.array([r[i] for r in group]) for i in range(4))


def missed_links(docs: DataFrame, names: DataFrame, members: DataFrame, links: DataFrame, width: int, percent: int, places: int, n: int, slack: float, repeated: bool) -> DataFrame:
    """Links between members of one bucket that the first round left in different components, as edges.

    Members of such a bucket meet in blocks. Signatures whose share of equal values is not more than slack
    under the wanted similarity (SLACK: six standard deviations) give rough clusters; only forests of them are handed out. In a rough cluster the true shingles
    of all texts of different components are compared, in blocks, by counting common ones.
    """
    found = members.join(links.withColumnRenamed("node", "rep"), "rep", "left").select("bucket", "rep", "n_shingles", F.coalesce("component", "rep").alias("component"))
    open_buckets = found.groupBy("bucket").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.ceil(F.count("*") / BLOCK_ROWS).cast("int").alias("blocks"))
    open_buckets = cut(open_buckets.where("low <> high").select("bucket", "blocks"))
    found = cut(found.join(open_buckets, "bucket"))
    texts = cut(bodies(docs, names.join(found.select("rep").distinct(), "rep", "left_semi"), repeated))
    values_of = cut(small_signatures(texts, width, places))
    least = int((percent / 100 - slack) * places)

    def alike(group: list[tuple]) -> Iterator[tuple[int, int]]:
        cells = _cells(group)
        values = np.frombuffer(b"".join(r[4] for r in group), np.uint8).reshape(len(group), places)
        for i in range(len(group)):
            near = _crossing(group, i, cells, percent)
            for k in near[(values[near] == values[i]).sum(axis=1) >= least]:
                yield int(cells[1][i]), int(cells[1][k])

    columns = ["rep", "component", "n_shingles"]
    rough = components(cut(_forests(_in_blocks(found.join(values_of, "rep"), "bucket", [*columns, "bytes"]), alike)), rows=n)
    about = found.select(*columns).distinct().join(rough.withColumnRenamed("node", "rep").withColumnRenamed("component", "cluster"), "rep")
    sizes = about.groupBy("cluster").agg(F.ceil(F.greatest(F.count("*") / BLOCK_ROWS, F.sum("n_shingles") * 8 / BLOCK_BYTES)).cast("int").alias("blocks"))
    sizes = cut(sizes, n)
    about = cut(about.join(sizes, "cluster"), n)

    def similar(group: list[tuple]) -> Iterator[tuple[int, int]]:
        cells = _cells(group)
        sets, bounds = exact_sets(Texts(pa.array([r[4] for r in group], pa.large_binary())), width)
        common = common_counts([sets[lo:hi] for lo, hi in zip(bounds, bounds[1:], strict=False)])
        size = cells[3]
        for i in range(len(group)):
            near = _crossing(group, i, cells, percent)
            for k in near[100 * common[i, near] >= percent * (size[i] + size[near] - common[i, near])]:
                yield int(cells[1][i]), int(cells[1][k])

    return _forests(_in_blocks(about.join(texts, "rep"), "cluster", [*columns, "body"]), similar)


def common_counts(sets: list[np.ndarray], step: int = 4096) -> np.ndarray:
    """Number of common elements of every two sets of a block, by products of slices of the incidence matrix."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, codes, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = counts[codes] > 1
    owner, codes = owner[shared], codes[shared]
    order = np.argsort(codes, kind="stable")
    owner, codes = owner[order], codes[order]
    codes = np.cumsum(np.concatenate([[0], codes[1:] != codes[:-1]])) if len(codes) else codes
    out = np.zeros((len(sets), len(sets)), np.float32)
    for lo in range(0, int(codes[-1]) + 1 if len(codes) else 0, step):
        a, b = np.searchsorted(codes, [lo, lo + step])
        part = np.zeros((len(sets), step), np.float32)
        part[owner[a:b], codes[a:b] - lo] = 1
        out += part @ part.T
    return out.astype(np.int64)


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs of which one per group stays, with all their columns.

    Rows without an id all stay. A text without words is a group of its own id.
    """
    groups = _grouped(docs, width, percent, BANDS, ROWS, id_col, text_col, SLACK).where("kept and doc_id is not null")
    stay = groups.groupBy("component_id", "group_rep").agg(F.min("digest").alias("stay_key"))
    return rows_that_stay(docs, stay.select(F.col("component_id").alias("stay_id"), "stay_key"), id_col, text_col, text_key)
