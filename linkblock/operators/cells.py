"""Every two groups of records meet in a cell, where their pairs are found by the first table whose keys agree.

A record travels once for each group instead of once for each table, and what
it carries is one set of keys (or the tokens that they are made of) instead of
the keys of all tables before. The number of groups follows from the bytes
that a cell may hold, so that no task holds more, however many records there
are or however many share a key.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bytes of keys in a cell: two groups of records.
CELL = 1 << 26
#: Pairs that are looked at in one step.
SLAB = 1 << 18
#: Runs of so many records are compared as matrices, of so many entries at a time.
LONG, ENTRIES = 512, 1 << 20
#: Fewer records than this are not dealt further to keep all cores busy.
FEW = 1_000


def groups_for(n: int, row_bytes: int, cores: int) -> int:
    """As few groups as the bytes of a cell allow; enough of them for two cells a core."""
    return max(1, math.ceil(n * row_bytes * 2 / CELL), math.ceil(math.sqrt(4 * cores)) if n > FEW else 1)


def deal(rows: DataFrame, groups: int) -> DataFrame:
    """rows (id, ...) with cell and side, in partitions sorted by cell. side: 0 or 1 where two groups meet, 2 where a group meets itself."""
    own = F.pmod(F.xxhash64("id"), F.lit(groups)).cast("int")
    lo, hi = F.least(F.col("own"), F.col("j")), F.greatest(F.col("own"), F.col("j"))
    side = F.when(lo == hi, 2).when(F.col("own") == lo, 0).otherwise(1)
    met = rows.withColumn("own", own).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    cell = (F.expr("greatest(own, j) * (greatest(own, j) + 1) div 2") + lo).cast("int")
    dealt = met.select(cell.alias("cell"), side.cast("int").alias("side"), *rows.columns)
    # A partition a cell: by hash some would hold several.
    return dealt.repartitionById(groups * (groups + 1) // 2, "cell").sortWithinPartitions("cell")


def whole_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows of one cell after the other, from batches sorted by cell."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        cell = b.column("cell").to_numpy()
        cuts = np.flatnonzero(cell[1:] != cell[:-1]) + 1
        for i, j in zip([0, *cuts], [*cuts, b.num_rows], strict=True):
            if i == j:
                continue
            if held and held[0].column("cell")[0].as_py() != cell[i]:
                yield pa.Table.from_batches(held).combine_chunks()
                held = []
            held.append(b.slice(i, j - i))
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def column(cell: pa.Table, name: str) -> pa.Array:
    c = cell.column(name)
    return c.chunk(0) if c.num_chunks == 1 else pa.concat_arrays(c.chunks)


def first_pairs(keys: np.ndarray, side: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(table, p, q) in slabs: rows p and q that agree on the key of that table and of none before. keys: (tables, rows)."""
    tables, m = keys.shape
    codes, across = np.empty((tables, m), np.int32), bool(m) and side[0] != 2
    first = np.argsort(side, kind="stable") if across else np.arange(m)
    for t in range(tables):
        # Stable, so that in a run of equal keys the rows of side 0 come before those of side 1.
        order = first[np.argsort(keys[t][first], kind="stable")]
        k = keys[t][order]
        start = np.flatnonzero(np.r_[True, k[1:] != k[:-1]])
        size = np.diff(np.r_[start, m])
        run = np.repeat(np.arange(len(start), dtype=np.int32), size)
        codes[t][order] = run
        end = (start + size)[run]
        at = np.arange(m)
        lo = (start + np.add.reduceat(side[order] == 0, start))[run] if across else at + 1
        n = np.where(at < lo, end - lo, 0)
        before = codes[:t, order]
        long = size >= LONG
        for a, z in zip(start[long], (start + size)[long], strict=True):
            yield from ((t, order[p], order[q]) for p, q in _of_long_run(before, a, z, lo[a], across))
        rows = np.flatnonzero((n > 0) & ~long[run])
        upto = np.cumsum(n[rows])
        i = 0
        while i < len(rows):
            j = max(i + 1, int(np.searchsorted(upto, (upto[i - 1] if i else 0) + SLAB, "right")))
            r, c = rows[i:j], n[rows[i:j]]
            q = np.arange(c.sum()) + np.repeat(lo[r] - (np.cumsum(c) - c), c)
            seen = np.zeros(len(q), bool)
            for s in range(t):
                seen |= np.repeat(before[s][r], c) == before[s][q]
            yield t, order[np.repeat(r, c)[~seen]], order[q[~seen]]
            i = j


def _of_long_run(before: np.ndarray, a: int, z: int, lo: int, across: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The pairs of a run (a to z) by matrices of some rows against all that come later."""
    i, stop = a, lo if across else z - 1
    while i < stop:
        left = max(lo, i + 1) if across else i + 1
        j = min(stop, i + max(1, ENTRIES // (z - left)))
        seen = np.zeros((j - i, z - left), bool)
        for b in before:
            seen |= b[i:j, None] == b[left:z]
        if not across:
            seen |= np.arange(i, j)[:, None] >= np.arange(left, z)
        p, q = np.nonzero(~seen)
        yield p + i, q + left
        i = j


def key_matrix(cell: pa.Table, name: str) -> np.ndarray:
    """(tables, rows) of an array column of equal lengths."""
    c = column(cell, name)
    return np.ascontiguousarray(c.flatten().to_numpy(zero_copy_only=False).reshape(len(c), -1).T)


def emit(rows: DataFrame, tables: int, n: int, groups: int | None = None) -> DataFrame:
    """(id_lo, id_hi, first_table) of rows (id bigint, ks array<bigint>), each pair once, in no order."""
    groups = groups or groups_for(n, 8 * (tables + 1), rows.sparkSession.sparkContext.defaultParallelism)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cell in whole_cells(batches):
            ids, side, keys = column(cell, "id").to_numpy(), column(cell, "side").to_numpy(), key_matrix(cell, "ks")
            del cell
            for t, p, q in first_pairs(keys, side):
                a, b = ids[p], ids[q]
                if len(a):
                    made = pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(np.full(len(a), t, np.int32))], names=["id_lo", "id_hi", "first_table"])
                    yield made.filter(pa.array(a != b)) if (a == b).any() else made

    return deal(rows, groups).mapInArrow(run, "id_lo bigint, id_hi bigint, first_table int")


def counted(keys: np.ndarray, side: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """How many pairs of different ids each table is the first of."""
    out = np.zeros(len(keys), np.int64)
    for t, p, q in first_pairs(keys, side):
        out[t] += np.count_nonzero(ids[p] != ids[q])
    return out


def count(rows: DataFrame, tables: int, n: int) -> DataFrame:
    """(first_table, n_pairs) of rows (id bigint, ks array<bigint>): the pairs of emit() counted in their cells, so that none leaves its task."""
    groups = groups_for(n, 8 * (tables + 1), rows.sparkSession.sparkContext.defaultParallelism)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cell in whole_cells(batches):
            found = counted(key_matrix(cell, "ks"), column(cell, "side").to_numpy(), column(cell, "id").to_numpy())
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(found), dtype=np.int32)), pa.array(found)], names=["first_table", "n_pairs"])

    return deal(rows, groups).mapInArrow(run, "first_table int, n_pairs bigint").groupBy("first_table").agg(F.sum("n_pairs").alias("n_pairs"))
