"""SimHash near-duplicates with bit-sliced comparison.

Fingerprints that differ in at most r bits agree on at least one of r+1 parts
of their bits, so distinct fingerprints meet by the value of a part. What
meets is compared in blocks stored as vertical bit planes: plane i holds bit i
of 64 fingerprints a word. A query xors its bits onto the planes and adds them
to carry-save counters, so 64 distances move at once; after the first planes
only words that still hold a distance within the radius go on.

Rows with equal fingerprints meet before all this and go on as one. A part
value shared by more than BLOCK fingerprints is dealt in pairs of chunks over
many tasks, so no group of near copies lands in one of them. Each comparison
returns a spanning forest of the links it found instead of all pairs.

Near copies go by the Jaccard similarity of sets of shingles. Wide fingerprints
of the sets meet by the value of a part or, where they differ in every part, by
keys made of least hashes. Those that meet are compared by bit planes, and what
is within WIDE_RADIUS is confirmed on the sets themselves.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.llm.common import LOWER, narrow, per_document, whole_id
from linkblock.operators.components import connected_components
from linkblock.runtime import settle

BITS = 64
RADIUS = 2
SHINGLE = 3
SEED = 42
BLOCK = 2048
#: Small cells are packed until they hold so many rows.
PACK = 512
#: Cells with over BLOCK rows are known by name to every task if there are at most so many.
BROADCAST_ROWS = 50_000

#: Near copies: sets of shingles of WIDE_SHINGLE words whose Jaccard similarity is at least SIMILAR[0] / SIMILAR[1].
WIDE_SHINGLE, SIMILAR = 5, (4, 5)
#: A key is KEY_MINS minima of the shingles' hashes, TABLES keys a text. Two texts of similarity s, however long, share
#: none with probability (1 - s**6)**64: under 4e-9 from 0.8 on. Keys only choose which texts are compared.
KEY_MINS, TABLES = 6, 64
#: SimHash of a set over WIDE_BITS bits, cut in WIDE_PARTS parts of which one is equal if fewer bits differ. A bit of two
#: sets of similarity 0.8 differs with probability 3/16 at most (4 of 5 shingles shared; 0.152 for long texts), so more than
#: WIDE_RADIUS bits do with probability under 2e-10; those of unrelated sets differ in half of the bits, 128 +- 8.
WIDE_BITS, WIDE_PARTS, WIDE_RADIUS = 256, 8, 90
#: Candidates are compared in cells of at most two chunks of so many sets.
CHUNK = 256
#: Candidates are known by name to every task if there are at most so many.
BROADCAST_SETS = 500_000
#: Sets that meet in so small a group are compared pair by pair, others by a matrix of so many shingles at a time.
BY_PAIR, COLUMNS = 12, 2048

_RNG = np.random.default_rng(7)
_FACTORS = _RNG.integers(0, 1 << 31, KEY_MINS * TABLES, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_MIX = _RNG.integers(0, 1 << 63, KEY_MINS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_TABLE = _RNG.integers(0, 1 << 63, TABLES, dtype=np.uint64)
_REMIX = _RNG.integers(0, 1 << 63, WIDE_BITS // BITS, dtype=np.uint64)
_PART = _RNG.integers(0, 1 << 63, WIDE_PARTS, dtype=np.uint64)


def _shingle_hashes(raw: bytes, size: int, seed: int) -> np.ndarray:
    words = raw.translate(LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    if len(words) < size:
        words, size = [b" ".join(words)], 1
    digest, join = xxhash.xxh64_intdigest, b" ".join
    return np.fromiter((digest(join(words[i : i + size]), seed) for i in range(len(words) - size + 1)), np.uint64, len(words) - size + 1)


def _ones(hashes: np.ndarray) -> np.ndarray:
    """How many hashes have each bit, bit 0 first; sums of 255 rows fit in bytes."""
    total = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 255):
        bits = np.unpackbits(hashes[at : at + 255].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        total += np.add.reduce(bits, axis=0, dtype=np.uint8)
    return total


def fingerprint(raw: bytes, size: int = SHINGLE, seed: int = SEED) -> int:
    """Signed 64-bit SimHash of a text's word shingles (UTF-8, A-Z lower-cased, repeats counted); no words: 0."""
    hashes = _shingle_hashes(raw, size, seed)
    return int(np.packbits(2 * _ones(hashes) > len(hashes), bitorder="little").view(np.int64)[0])


def shingle_set(raw: bytes, size: int = WIDE_SHINGLE) -> np.ndarray:
    """Sorted hashes of a text's distinct shingles; a shorter text is one shingle, one without words has none."""
    return np.unique(_shingle_hashes(raw, size, SEED))


def set_node(hashes: np.ndarray) -> int:
    """What a set of shingles is known by: a signed 64-bit hash."""
    return xxhash.xxh3_64_intdigest(hashes.tobytes()) - (1 << 63)


def wide_fingerprint(hashes: np.ndarray) -> np.ndarray:
    """SimHash of a set of shingles as WIDE_BITS // 8 bytes: a bit is 1 if set in over half of the remixed hashes, and where it is set in just half, that of the least hash."""
    if not len(hashes):
        return np.zeros(WIDE_BITS // 8, np.uint8)
    bits = []
    for salt in _REMIX:
        x = (hashes ^ salt) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ x >> np.uint64(31)) * np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(29)
        twice = 2 * _ones(x)
        bits.append(np.where(twice == len(x), np.unpackbits(x[:1].view(np.uint8), bitorder="little"), twice > len(x)))
    return np.packbits(np.concatenate(bits).astype(np.uint8), bitorder="little")


def wide_cells(fp: np.ndarray) -> np.ndarray:
    """A cell for the bits of a wide fingerprint in each of its parts."""
    x = np.zeros((WIDE_PARTS, 8), np.uint8)
    x[:, : len(fp) // WIDE_PARTS] = fp.reshape(WIDE_PARTS, -1)
    x = (x.view(np.uint64)[:, 0] ^ _PART) * np.uint64(0xBF58476D1CE4E5B9)
    return (x ^ x >> np.uint64(29)).view(np.int64)


def min_keys(hashes: np.ndarray) -> np.ndarray:
    """A key for each table from the least of the shingles' hashes under KEY_MINS orders."""
    short, least = (hashes >> np.uint64(32)).astype(np.uint32), np.full(len(_FACTORS), (1 << 32) - 1, np.uint32)
    for at in range(0, len(short), 256):
        np.minimum(least, (short[at : at + 256, None] * _FACTORS).min(axis=0), out=least)
    x = (least.reshape(TABLES, KEY_MINS).astype(np.uint64) * _MIX).sum(axis=1, dtype=np.uint64) + _TABLE
    x = (x ^ x >> np.uint64(31)) * np.uint64(0xBF58476D1CE4E5B9)
    return (x ^ x >> np.uint64(29)).view(np.int64)


def alike(shared: np.ndarray | int, a: np.ndarray | int, b: np.ndarray | int) -> np.ndarray | bool:
    """Whether sets of a and b shingles of which so many are shared are similar enough; in whole numbers."""
    return (SIMILAR[0] + SIMILAR[1]) * shared >= SIMILAR[0] * (a + b)


def set_forest(sets: list[np.ndarray]) -> np.ndarray:
    """For each set the index of the least one in its component of links of Jaccard similarity SIMILAR and more."""
    n, label = np.array([len(x) for x in sets]), np.arange(len(sets))
    if len(sets) <= BY_PAIR:
        for j in range(1, len(sets)):
            for i in range(j):
                # The shared shingles are at most the smaller set.
                if label[i] != label[j] and alike(min(n[i], n[j]), n[i], n[j]):
                    both = np.sort(np.concatenate([sets[i], sets[j]]))
                    if alike(np.count_nonzero(both[1:] == both[:-1]), n[i], n[j]):
                        label[(label == label[i]) | (label == label[j])] = min(label[i], label[j])
        return label
    _, column, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row, often = np.repeat(np.arange(len(sets)), n), times > 1
    place = np.cumsum(often) - 1
    row, column = row[often[column]], place[column[often[column]]]
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    shared = np.zeros((len(sets), len(sets)))
    cuts = np.searchsorted(column, np.arange(0, often.sum() + COLUMNS, COLUMNS))
    for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
        part = np.zeros((len(sets), COLUMNS), np.float32)
        part[row[a:b], column[a:b] - k * COLUMNS] = 1
        shared += part @ part.T
    a, b = np.nonzero(np.triu(alike(shared, n[:, None], n[None, :]), 1))
    while a.size:
        low = np.minimum(label[a], label[b])
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        while (label != label[label]).any():
            label = label[label]
        apart = label[a] != label[b]
        a, b = a[apart], b[apart]
    return label


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp bigint) for every row."""
    return per_document(narrow(docs, id_col, text_col), lambda raw: (fingerprint(raw),), "doc_id bigint, fp bigint")


def _bits(rows: np.ndarray) -> np.ndarray:
    return np.unpackbits(rows, axis=1, bitorder="little")


def bit_planes(rows: np.ndarray) -> np.ndarray:
    """(bits, words) from fingerprints as rows of bytes: plane i holds bit i of all, 64 to a word, padded with zeros."""
    bits = _bits(rows)
    padded = np.zeros((bits.shape[1], -(-len(rows) // 64) * 64), np.uint8)
    padded[:, : len(rows)] = bits.T
    return np.packbits(padded, axis=1, bitorder="little").view(np.uint64)


def _add(counters: list[np.ndarray], over: np.ndarray, carry: np.ndarray, limit: int) -> None:
    """Add one bit to every counter; over gets the lanes that reach limit."""
    reached = None
    for i, c in enumerate(counters):
        held = c & carry
        c ^= carry
        carry = held
        part = c if limit >> i & 1 else ~c
        reached = part if reached is None else reached & part
    over |= reached


def within(queries: np.ndarray, planes: np.ndarray, n: int, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """(query index, block index) of all pairs at most radius bits apart. queries: rows of bytes."""
    words, bits, limit = planes.shape[1], planes.shape[0], radius + 1
    masks = (np.uint64(0) - _bits(queries).astype(np.uint64)).T
    shape = (len(queries), words)
    counters = [np.zeros(shape, np.uint64) for _ in range(limit.bit_length())]
    over = np.zeros(shape, np.uint64)
    dense = min(bits, 2 * radius + 12)  # until then nearly every word holds a lane within the radius
    for plane in range(dense):
        _add(counters, over, planes[plane][None, :] ^ masks[plane][:, None], limit)
    q, w = np.indices(shape).reshape(2, -1)
    counters, over = [c.ravel() for c in counters], over.ravel()
    for plane in range(dense, bits):
        if (plane - dense) % 8 == 0:
            alive = np.flatnonzero(~over)
            if not alive.size:
                return np.zeros(0, np.int64), np.zeros(0, np.int64)
            if alive.size < 0.7 * over.size:
                q, w, over = q[alive], w[alive], over[alive]
                counters = [c[alive] for c in counters]
        _add(counters, over, planes[plane][w] ^ masks[plane][q], limit)
    near = np.unpackbits((~over).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(bool)
    row, lane = np.nonzero(near)
    at = w[row] * 64 + lane
    real = at < n
    return q[row[real]], at[real]


def forest(rows: np.ndarray, radius: int = RADIUS) -> np.ndarray:
    """For each fingerprint (rows of bytes) the index of the least one in its component of links within this block."""
    planes, label = bit_planes(rows), np.arange(len(rows))
    step = max(64, (1 << 16) // max(1, planes.shape[1]))
    for at in range(0, len(rows), step):
        a, b = within(rows[at : at + step], planes, len(rows), radius)
        a = a + at
        a, b = a[a != b], b[a != b]
        while a.size:
            low = np.minimum(label[a], label[b])
            np.minimum.at(label, label[a], low)
            np.minimum.at(label, label[b], low)
            label = label[label]
            apart = label[a] != label[b]
            a, b = a[apart], b[apart]
    while (label != label[label]).any():
        label = label[label]
    return label


def _links(radius: int, width: int):
    """Compare what shares a cell: rows (cell, fp of width bytes) sorted by cell in, links (a, b) out."""
    schema = pa.schema([("a", pa.binary()), ("b", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_cell, held = np.zeros(0, np.int64), np.zeros((0, width), np.uint8)

        def compare(cell: np.ndarray, rows: np.ndarray) -> Iterator[pa.RecordBatch]:
            if len(cell) < 2:
                return
            same = np.r_[False, cell[1:] == cell[:-1], False]
            rows = np.unique(rows[same[1:] | same[:-1]], axis=0)  # a row alone in its cell meets nothing
            if len(rows) > 1:
                low = forest(rows, radius)
                moved = np.flatnonzero(low != np.arange(len(rows)))
                if moved.size:
                    yield pa.RecordBatch.from_arrays([pa.array([rows[i].tobytes() for i in x], pa.binary()) for x in (moved, low[moved])], schema=schema)

        for b in batches:
            cell = np.concatenate([held_cell, b.column("cell").to_numpy()])
            came = np.frombuffer(b"".join(b.column("fp").to_pylist()), np.uint8).reshape(-1, width)
            rows = np.concatenate([held, came])
            starts = np.flatnonzero(cell[1:] != cell[:-1]) + 1
            done = 0
            for at in starts:  # a block ends where a cell ends, and holds at least PACK rows
                if at - done >= PACK:
                    yield from compare(cell[done:at], rows[done:at])
                    done = at
            held_cell, held = cell[done:], rows[done:]
        yield from compare(held_cell, held)

    return run


def links(parts: DataFrame, radius: int, width: int, block: int = BLOCK) -> DataFrame:
    """(a, b) binary: links within radius between fingerprints that share a cell, enough to keep all components; some come more than once.

    parts: (cell bigint, fp binary), each fingerprint once a cell. A cell with
    over `block` rows is cut in chunks, and every two chunks meet in a cell of
    their own, so that no task holds it whole.
    """
    hot = settle(parts.groupBy("cell").agg(F.count("*").alias("n")).where(F.col("n") > block).select("cell", F.ceil(F.col("n") / block).cast("int").alias("chunks")))
    dealt = parts.join(F.broadcast(hot) if hot.count() <= BROADCAST_ROWS else hot, "cell", "left")
    own = F.pmod(F.xxhash64("fp"), F.col("chunks")).cast("int")
    meetings = F.transform(F.sequence(F.lit(0), F.col("chunks") - 1), lambda j: F.xxhash64(F.col("cell"), F.least(own, j), F.greatest(own, j)))
    cells = dealt.select(F.explode(F.when(F.col("chunks").isNull(), F.array("cell")).otherwise(meetings)).alias("cell"), "fp")
    return cells.repartition("cell").sortWithinPartitions("cell").mapInArrow(_links(radius, width), "a binary, b binary")


def part_cells(fp: Column, radius: int = RADIUS) -> Column:
    """array<bigint>: a cell for the bits of fp (bigint) in each of radius+1 parts."""
    cuts = [BITS * i // (radius + 1) for i in range(radius + 2)]
    return F.array(*(F.xxhash64(F.lit(i), F.shiftrightunsigned(fp, a).bitwiseAND(F.lit((1 << (b - a)) - 1))) for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))))


def as_number(fp: Column) -> Column:
    """The bigint whose 8 bytes, greatest first, fp is."""
    return F.conv(F.hex(fp), 16, -10).cast("bigint")


def _components(classes: DataFrame, cells: Column, radius: int, width: int, node: Callable[[Column], Column]) -> DataFrame:
    """(node, component_id) for classes (fp binary, least, ...): the least id over each component of links.

    node makes a bigint of a fingerprint: components are found on 8 bytes a
    node, not on the fingerprints.
    """
    found = links(classes.select(F.explode(cells).alias("cell"), "fp"), radius, width)
    edges = found.select(node(F.col("a")).alias("a"), node(F.col("b")).alias("b"))
    roots = connected_components(edges, "a", "b")
    own = classes.select(node(F.col("fp")).alias("own"), "least")
    linked = own.join(roots, F.col("own") == F.col("node"), "left").select("own", "least", F.coalesce("root", "own").alias("root"))
    # Settled, so that adaptive execution can split the rows of a large component.
    named = settle(linked.groupBy("root").agg(F.min("least").alias("component_id")))
    return linked.join(named, "root").select(F.col("own").alias("node"), "component_id")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """(doc_id, fp, component_id) for every row: the least doc_id reachable over links of at most radius bits.

    Null texts and texts without words have fingerprint 0 and link like any
    other. Repeated rows and equal texts share a component; a null id is never
    the least unless its component has no other. An empty table gives no rows.
    """
    marked = settle(fingerprints(docs, id_col, text_col))
    classes = marked.groupBy("fp").agg(F.min("doc_id").alias("least")).select(F.col("fp").alias("number"), F.unhex(hex_digits(F.col("fp"))).alias("fp"), "least")
    named = _components(classes, part_cells(F.col("number"), radius), radius, BITS // 8, as_number)
    return marked.join(named, F.col("fp") == F.col("node")).select("doc_id", "fp", "component_id")


def _stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (cell, node) sorted by cell in; each node of a cell with the first one out."""
    last, head = None, 0
    for b in batches:
        cell, node = b.column("cell").to_numpy(), b.column("node").to_numpy()
        if not len(cell):
            continue
        new = np.r_[last is None or cell[0] != last, cell[1:] != cell[:-1]]
        at = np.maximum.accumulate(np.where(new, np.arange(len(cell)), -1))
        first = np.where(at < 0, head, node[at])
        last, head = cell[-1], first[-1]
        apart = np.flatnonzero(first != node)
        yield pa.RecordBatch.from_arrays([pa.array(node[apart]), pa.array(first[apart])], names=["a", "b"])


def _send_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (text, node, cells) in; the set of shingles for each cell out, once a task."""
    sent: set[int] = set()
    for whole in batches:
        for at in range(0, whole.num_rows, 256):
            part, rows = whole.slice(at, 256), []
            for text, node, cells in zip(part.column("text").to_pylist(), part.column("node").to_pylist(), part.column("cells").to_pylist(), strict=True):
                if node not in sent:
                    hashes = shingle_set(text)
                    if set_node(hashes) == node:
                        sent.add(node)
                        rows += [(cell, node, hashes.tobytes()) for cell in cells]
            for start in range(0, len(rows), 256):
                cell, node, hashes = zip(*rows[start : start + 256], strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(cell, pa.int64()), pa.array(node, pa.int64()), pa.array(hashes, pa.binary())], names=["cell", "node", "hashes"])


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (cell, node, hashes) sorted by cell in; links (a, b) between sets that are alike out."""
    now, held = None, {}

    def compare() -> Iterator[pa.RecordBatch]:
        nodes = np.array(sorted(held), np.int64)
        low = set_forest([held[x] for x in nodes.tolist()])
        moved = np.flatnonzero(low != np.arange(len(nodes)))
        if moved.size:
            yield pa.RecordBatch.from_arrays([pa.array(nodes[moved]), pa.array(nodes[low[moved]])], names=["a", "b"])

    for b in batches:
        for cell, node, hashes in zip(b.column("cell").to_pylist(), b.column("node").to_pylist(), b.column("hashes"), strict=True):
            if cell != now:
                if len(held) > 1:
                    yield from compare()
                now, held = cell, {}
            held[node] = np.frombuffer(hashes.as_buffer(), np.uint64).copy()
    if len(held) > 1:
        yield from compare()


def _simhash_linked(marked: DataFrame) -> DataFrame:
    """(node, root) of nodes whose wide fingerprint is linked to another node's, from rows (node, cells, fp).

    Nodes that share a cell are taken together under a root, and inside of
    what is taken together links are fingerprints at most WIDE_RADIUS bits
    apart. A node without any such link goes no further.
    """
    cells = marked.groupBy("node").agg(F.first("cells").alias("cells")).select(F.explode("cells").alias("cell"), "node")
    met = connected_components(cells.repartition("cell").sortWithinPartitions("cell").mapInArrow(_stars, "a bigint, b bigint"), "a", "b")
    prints = settle(met.join(marked.groupBy("node").agg(F.first("fp").alias("fp")), "node").select("node", F.col("root").alias("cell"), "fp", F.xxhash64("fp").alias("own")))
    found = links(prints.select("cell", "fp").distinct(), WIDE_RADIUS, WIDE_BITS // 8)
    # Nodes of one fingerprint are linked without a comparison.
    same = prints.groupBy("own").agg(F.count("*").alias("n")).where("n > 1").select("own")
    ends = found.select(F.explode(F.array(F.xxhash64("a"), F.xxhash64("b"))).alias("own")).unionByName(same).distinct()
    return prints.join(ends, "own", "left_semi").select("node", F.col("cell").alias("root"))


def _near_groups(docs: DataFrame, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """(rows: doc_id, text_key, node), (classes: node, group, least): least is the (void, doc_id, text_key) to keep of the group.

    Texts with equal sets are one node. Nodes that share a part of their wide
    fingerprints or a key meet, and their fingerprints are compared by bit
    planes (see _simhash_linked). Of those with a link, every two sets that were
    taken together are compared, over CHUNK sets in pairs of chunks over many
    tasks, and links are what is alike.
    """
    own = narrow(docs, id_col, text_col).withColumn("text_key", F.xxhash64(F.coalesce("text", F.lit(""))))

    def work(raw: bytes) -> tuple[int, list[int], bytes]:
        hashes = shingle_set(raw)
        fp = wide_fingerprint(hashes)
        return set_node(hashes), np.concatenate([wide_cells(fp), min_keys(hashes)]).tolist(), fp.tobytes()

    marked = settle(per_document(own, work, "doc_id bigint, text_key bigint, node bigint, cells array<bigint>, fp binary", "text_key"))
    candidates = settle(_simhash_linked(marked))
    large = settle(candidates.groupBy("root").agg(F.count("*").alias("n")).where(F.col("n") > CHUNK).select("root", F.ceil(F.col("n") / CHUNK).cast("int").alias("chunks")))
    mine = F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")
    meetings = F.transform(F.sequence(F.lit(0), F.col("chunks") - 1), lambda j: F.xxhash64(F.col("root"), F.least(mine, j), F.greatest(mine, j)))
    dealt = candidates.join(F.broadcast(large) if large.count() <= BROADCAST_ROWS else large, "root", "left").select("node", F.when(F.col("chunks").isNull(), F.array("root")).otherwise(meetings).alias("cells"))
    wanted = settle(dealt.join(marked.groupBy("node").agg(F.min("text_key").alias("text_key")), "node"))
    texts = own.select("text_key", F.coalesce("text", F.lit("")).cast("binary").alias("text"))
    sent = texts.join(F.broadcast(wanted) if wanted.count() <= BROADCAST_SETS else wanted, "text_key").select("text", "node", "cells").mapInArrow(_send_sets, "cell bigint, node bigint, hashes binary")
    roots = connected_components(sent.repartition("cell").sortWithinPartitions("cell").mapInArrow(_confirm, "a bigint, b bigint"), "a", "b")
    least = F.min(F.struct(F.col("doc_id").isNull().alias("void"), "doc_id", "text_key"))
    linked = marked.groupBy("node").agg(least.alias("least")).join(roots, "node", "left").select("node", F.coalesce("root", "node").alias("group"), "least")
    return marked.select("doc_id", "text_key", "node"), linked


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, component_id) for every row: components of texts whose sets of five-word shingles have a Jaccard similarity of 0.8 and more.

    Links are found by wide fingerprints compared by bit planes and confirmed
    on the sets themselves (see TABLES and WIDE_BITS for what can be missed).
    A set is known by a 64-bit hash, as is each shingle. Nulls, empty texts, repeated rows and
    empty tables as in near_duplicates().
    """
    rows, linked = _near_groups(docs, id_col, text_col)
    named = linked.join(settle(linked.groupBy("group").agg(F.min("least")["doc_id"].alias("component_id"))), "group").select("node", "component_id")
    return rows.select("doc_id", "node").join(named, "node").select("doc_id", "component_id")


def hex_digits(fp: Column) -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of docs, one for each group of near copies: that of the least id.

    A group without any id keeps one row too. Rows that share an id but not a
    group are kept for each group; of rows of one id in a group that of the
    least text hash, and of rows equal in both any one.
    """
    _, linked = _near_groups(docs, id_col, text_col)
    kept = linked.groupBy("group").agg(F.min("least").alias("least")).select(F.col("least.doc_id").alias("_kept_id"), F.col("least.text_key").alias("_kept_key"))
    text_key = F.xxhash64(F.coalesce(docs[text_col].cast("string"), F.lit("")))
    keyed = docs.select(F.struct(*(docs[c] for c in docs.columns)).alias("row"), whole_id(docs, id_col).alias("_id"), text_key.alias("_key"))
    # A text is in one group, so its hash names the group.
    found = keyed.join(kept, keyed["_id"].eqNullSafe(kept["_kept_id"]) & (keyed["_key"] == kept["_kept_key"]), "left_semi").dropDuplicates(["_id", "_key"])
    return found.select(*(F.col(f"row.`{c}`").alias(c) for c in docs.columns))
