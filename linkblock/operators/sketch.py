"""Minhash sketches: classic, one-pass with densified empty bins, and their weighted forms.

All are row-local column expressions over a record's array of token hashes:
a scan needs no shuffle to get from text to signature. wide_kernel() is the
Arrow form of the flagship for records with very many tokens.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.functions.hashing import WIDTH, coefficients, mix, unit
from linkblock.functions.tokens import let

PROBES = 32
#: Probes from and to, made one stage after another.
STAGES = ((1, 2), (3, 6), (7, 14), (15, PROBES))
_NO_BINS = "array<struct<bin:bigint,val:bigint>>"
_FILLED = "array<struct<bin:bigint,val:bigint,dist:bigint>>"


def classic_minhash(hashes: Column, n: int, seed: int = 0) -> Column:
    """array<bigint> of n least remixed hashes, one mixing function each; null for a record without tokens."""
    return let(hashes, lambda h: F.when(F.size(h) > 0, F.transform(F.sequence(F.lit(seed), F.lit(seed + n - 1)), lambda s: F.array_min(F.transform(h, lambda x: mix(x, s))))))


def estimate(a: Column, b: Column) -> Column:
    """Share of equal positions of two signatures."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x) / F.size(a)


def bin_width(n: int) -> int:
    return -(-WIDTH // n)


def one_pass_bins(hashes: Column, n: int) -> Column:
    """array<struct<bin, val>>: the least hash of each of n bins that has any, by bin. hashes: sorted ascending."""
    width = bin_width(n)
    place = lambda x: F.floor(x / F.lit(width)).cast("bigint")
    return let(hashes, lambda h: F.transform(
        F.filter(h, lambda x, i: (i == 0) | (place(F.get(h, i - 1)) != place(x))), lambda x: F.struct(place(x).alias("bin"), x.alias("val"))
    ))


def _filled(bin_: Column, val: Column, dist: Column) -> Column:
    return F.struct(bin_.cast("bigint").alias("bin"), val.alias("val"), dist.cast("bigint").alias("dist"))


def _forward(m: Column, n: int) -> Column:
    """Every bin with the value of the next filled bin in circular order, and how far that is."""
    upto = F.flatten(F.transform(m, lambda x, i: F.transform(
        F.sequence(F.when(i == 0, F.lit(0).cast("bigint")).otherwise(F.get(m, i - 1)["bin"] + 1), x["bin"]), lambda b: _filled(b, x["val"], x["bin"] - b)
    )))
    first, last = F.get(m, F.lit(0)), F.element_at(m, -1)
    wrapped = F.when(last["bin"] < n - 1, F.transform(F.sequence(last["bin"] + 1, F.lit(n - 1).cast("bigint")), lambda b: _filled(b, first["val"], first["bin"] + n - b))).otherwise(F.array().cast(_FILLED))
    return F.concat(upto, wrapped)


def _backward(m: Column, n: int) -> Column:
    """Every bin with the value of the filled bin before it in circular order."""
    onward = F.flatten(F.transform(m, lambda x, i: F.transform(
        F.sequence(x["bin"], F.coalesce(F.get(m, i + 1)["bin"] - 1, F.lit(n - 1).cast("bigint"))), lambda b: _filled(b, x["val"], b - x["bin"])
    )))
    first, last = F.get(m, F.lit(0)), F.element_at(m, -1)
    wrapped = F.when(first["bin"] > 0, F.transform(F.sequence(F.lit(0).cast("bigint"), first["bin"] - 1), lambda b: _filled(b, last["val"], b + n - last["bin"]))).otherwise(F.array().cast(_FILLED))
    return F.concat(wrapped, onward)


def coin(b: Column, seed: int = 77) -> Column:
    """Direction in which an empty bin borrows: the same for all records."""
    return F.floor(mix(b * 7919 + 13, seed) / F.lit(65536)) % 2 == 0


def probe_at(b: Column, t: Column, n: int, seed: int = 78) -> Column:
    """The bin that empty bin b asks at its t-th try: the same for all records."""
    return (F.floor(mix(b * 1009 + t, seed) / F.lit(65536)) % n).cast("int")


def densify(bins: Column, n: int, how: str = "probe") -> Column:
    """array<struct<bin, val, dist>> of all n bins; dist says how the value was found (0: own). Null without filled bins.

    rotate: the next filled bin. coin: the next or the one before, by the
    bin's coin. probe: the first filled bin of the bin's own sequence, after
    PROBES tries the next filled bin (dist from PROBES + 1 on).
    """
    def probed(full: Column) -> Column:
        def first_of(x: Column, a: int, b: int) -> Column:
            tries = F.transform(F.sequence(F.lit(a), F.lit(b)), lambda t: F.struct(F.get(full, probe_at(x["bin"], t, n)).alias("e"), t.alias("t")))
            return F.get(F.filter(tries, lambda y: y["e"]["dist"] == 0), F.lit(0))

        def fill(x: Column) -> Column:
            # Later tries are made only where the earlier ones found nothing.
            hit = F.coalesce(*(first_of(x, a, b) for a, b in STAGES))
            return let(hit, lambda hit: F.when(hit.isNull(), _filled(x["bin"], x["val"], x["dist"] + PROBES)).otherwise(_filled(x["bin"], hit["e"]["val"], hit["t"])))

        return F.transform(full, lambda x: F.when(x["dist"] == 0, x).otherwise(fill(x)))

    if how == "rotate":
        body = lambda m: _forward(m, n)
    elif how == "coin":
        body = lambda m: F.zip_with(_forward(m, n), _backward(m, n), lambda x, y: F.when(coin(x["bin"]), x).otherwise(y))
    elif how == "probe":
        body = lambda m: let(_forward(m, n), probed)
    else:
        raise ValueError(how)
    return let(bins, lambda m: F.when(F.size(m) > 0, body(m)))


def signature(filled: Column) -> Column:
    """array<bigint>: value and distance of each bin in one number, so that a borrowed value never equals an own one."""
    return F.transform(filled, lambda x: x["val"] * 1024 + F.least(x["dist"], F.lit(1023)))


def one_pass_sketch(hashes: Column, n: int, how: str = "probe") -> Column:
    """n values from one permutation of a record's sorted token hashes."""
    return signature(densify(one_pass_bins(hashes, n), n, how))


def per_table_filled(hashes: Column, k: int, tables: int, seed: int | Column = 500) -> Column:
    """array (by table) of densified sketches of k bins each, every table with its own remix of the same hashes."""
    return let(hashes, lambda h: F.transform(F.sequence(F.lit(0), F.lit(tables - 1)), lambda t: densify(one_pass_bins(F.array_sort(F.transform(h, lambda x: mix(x, t + seed))), k), k, "rotate")))


def per_table_sketch(hashes: Column, k: int, tables: int, seed: int | Column = 500) -> Column:
    """The k * tables values of per_table_filled() in a row; table t holds positions t*k to t*k+k-1."""
    return let(hashes, lambda h: F.when(F.size(h) > 0, F.flatten(F.transform(per_table_filled(h, k, tables, seed), signature))))


def per_table_keys(tok: np.ndarray, size: np.ndarray, k: int, tables: int, seed: int = 500) -> np.ndarray:
    """(tables, records): a 64-bit key of the k values that each table of per_table_sketch() holds. Each record's tokens, one at least, lie in a row."""
    out, starts, by_size = np.empty((tables, len(size)), np.uint64), np.cumsum(size) - size, np.argsort(size, kind="stable")
    at = 0
    while at < len(size):
        # As many records as fill a matrix of their tokens, the shorter ones with their first token again, which changes no least value.
        to = at + max(1, (1 << 18) // int(size[by_size[min(len(size), at + 4096) - 1]]))
        rows = by_size[at : min(to, at + 4096)]
        most = int(size[rows].max())
        place = np.arange(most)[:, None]
        h = tok[starts[rows] + np.where(place < size[rows], place, 0)].astype(np.uint32)
        for t in range(tables):
            out[t, rows] = _table_keys(h, k, t + seed)
        at += len(rows)
    return out


def _table_keys(h: np.ndarray, k: int, seed: int) -> np.ndarray:
    """Keys of one table from token hashes (tokens, records); products of 32 bits wrap as the remainder of mix() does."""
    a, b = coefficients(seed)
    x, width = h * np.uint32(a) + np.uint32(b % WIDTH), bin_width(k)
    least = [(x - np.uint32(i * width)).min(axis=0).astype(np.int64) for i in range(k)]
    full = [y < min(width, WIDTH - i * width) for i, y in enumerate(least)]
    key = np.zeros(h.shape[1], np.uint64)
    for i in range(k):
        val, found = np.zeros(h.shape[1], np.int64), np.zeros(h.shape[1], bool)
        for d in range(k):
            j = (i + d) % k
            new = full[j] & ~found
            val[new], found = (least[j][new] + j * width) * 1024 + min(d, 1023), found | full[j]
        key = (key ^ val.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
        key *= np.uint64(0xBF58476D1CE4E5B9)
        key ^= key >> np.uint64(32)
    return key


def per_table_kernel(df: DataFrame, id_col: str, hashes: Column, k: int, tables: int, seed: int = 500) -> DataFrame:
    """(id, ks): per_table_keys() in Arrow batches, one key a table; records without tokens are left out."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            b = b.filter(pc.greater(pc.fill_null(pc.list_value_length(b.column("h")), 0), 0))
            if b.num_rows:
                h = b.column("h")
                keys = per_table_keys(h.flatten().to_numpy(zero_copy_only=False), pc.list_value_length(h).to_numpy(zero_copy_only=False).astype(np.int64), k, tables, seed)
                made = pa.ListArray.from_arrays(pa.array(np.arange(0, keys.size + 1, tables), pa.int32()), pa.array(np.ascontiguousarray(keys.T).ravel().view(np.int64)))
                yield pa.RecordBatch.from_arrays([b.column("id"), made], names=["id", "ks"])

    return df.select(F.col(id_col).cast("bigint").alias("id"), hashes.alias("h")).mapInArrow(run, "id bigint, ks array<bigint>")


def quantize(weight: Column, delta: float) -> Column:
    """Whole multiples of delta nearest to the weight; off by delta/2 at most."""
    return F.round(weight / delta).cast("int")


def expand(counts: Column) -> Column:
    """Sorted hashes of the unary expansion: a token of count c becomes c tokens. counts: array<struct<h, cnt>>."""
    copies = F.transform(counts, lambda e: F.when(e["cnt"] > 0, F.transform(F.sequence(F.lit(1), e["cnt"].cast("int")), lambda j: mix(e["h"], j + 900))).otherwise(F.array().cast("array<bigint>")))
    return F.array_sort(F.array_distinct(F.flatten(copies)))


def sample_tokens(counts: Column, scale: float = 2.0, coordinated: bool = True, rec_id: Column | None = None, seed: int = 31) -> Column:
    """Sorted hashes of the tokens kept with probability min(1, weight / scale).

    Coordinated: the random number belongs to the token, so all records share
    it and the kept sets' similarity follows the weighted one. Otherwise it
    belongs to record and token (only to show what that loses).
    """
    kept = F.filter(counts, lambda e: e["cnt"] / F.lit(float(scale)) > (unit(e["h"], seed) if coordinated else unit(mix(e["h"] + rec_id % 65_521 * 65_537, 17), seed)))
    return F.array_sort(F.array_distinct(F.transform(kept, lambda e: e["h"])))


def weighted_sketch(counts: Column, k: int, tables: int, scale: float = 2.0, how: str = "probe", layout: str = "one_pass") -> Column:
    """k * tables values in one pass over the record: coordinated sampling by weight, then one-pass bins, then filling."""
    kept = sample_tokens(counts, scale)
    return let(kept, lambda h: per_table_sketch(h, k, tables) if layout == "per_table" else one_pass_sketch(h, k * tables, how))


def consistent_weighted_hash(counts: Column, n: int, seed: int = 2_000) -> Column:
    """array<bigint>: for each position the token chosen by consistent weighted sampling (with its quantised level).

    Five uniforms a token and position: two gamma(2,1) draws and a shift, the
    published improved form; records choose alike with probability equal to
    their weighted Jaccard similarity.
    """
    def choose(own: Column, position: Column) -> Column:
        u = lambda e, j: (mix(mix(e["h"], position * 5 + j + seed), position + j + 7) + 1) / F.lit(float(WIDTH + 2))

        def score(e: Column) -> Column:
            r = -F.log(u(e, 0) * u(e, 1))
            c = -F.log(u(e, 2) * u(e, 3))
            beta = u(e, 4)
            level = F.floor(F.log(e["cnt"]) / r + beta)
            return F.struct((F.log(c) - r * (level - beta) - r).alias("a"), e["h"].alias("h"), level.cast("bigint").alias("t"))

        best = F.array_min(F.transform(F.filter(own, lambda e: e["cnt"] > 0), score))
        return let(best, lambda s: s["h"] * 4096 + F.pmod(s["t"], F.lit(4096)))

    return let(counts, lambda c: F.when(F.size(c) > 0, F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda p: choose(c, p))))


def consistent_weighted_values(tok: np.ndarray, weight: np.ndarray, starts: np.ndarray, n: int, seed: int = 2_000) -> np.ndarray:
    """(records, n): what consistent_weighted_hash() chooses, for records whose tokens of positive weight lie in a row from each of starts."""
    def remixed(h: np.ndarray, s: int) -> np.ndarray:
        a, b = coefficients(s)
        return (h * a + b) % WIDTH

    out, of = np.empty((len(starts), n), np.int64), np.repeat(np.arange(len(starts)), np.diff(np.r_[starts, len(tok)]))
    log_weight, most = np.log(weight), np.iinfo(np.int64).max
    for p in range(n):
        u = [(remixed(remixed(tok, p * 5 + j + seed), p + j + 7) + 1) / float(WIDTH + 2) for j in range(5)]
        r, c, beta = -np.log(u[0] * u[1]), -np.log(u[2] * u[3]), u[4]
        level = np.floor(log_weight / r + beta)
        score = np.log(c) - r * (level - beta) - r
        value = tok * 4096 + level.astype(np.int64) % 4096
        # Of equal scores the least token is chosen, as in the column form.
        out[:, p] = np.minimum.reduceat(np.where(score == np.minimum.reduceat(score, starts)[of], value, most), starts)
    return out


def consistent_weighted_kernel(df: DataFrame, id_col: str, counts_col: str, n: int, seed: int = 2_000) -> DataFrame:
    """(rec_id, sig): consistent_weighted_hash() in Arrow batches; ten hash steps a token and position are too many for nested lambdas."""
    def chosen(counts: pa.Array) -> pa.Array:
        size = pc.fill_null(pc.list_value_length(counts), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        flat = counts.flatten()
        tok, weight = flat.field("h").to_numpy(zero_copy_only=False).astype(np.int64), flat.field("cnt").to_numpy(zero_copy_only=False).astype(float)
        kept = weight > 0
        left = np.bincount(np.repeat(np.arange(len(size)), size)[kept], minlength=len(size))
        full = left > 0
        values = np.zeros((len(size), n), np.int64)
        if full.any():
            values[full] = consistent_weighted_values(tok[kept], weight[kept], (np.cumsum(left) - left)[full], n, seed)
        # Tokens without any weight choose nothing at each position; no tokens make no sketch.
        given = size > 0
        made = pa.array(values[given].ravel(), pa.int64(), mask=np.repeat(~full[given], n))
        return pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(given * n)], pa.int32()), made, mask=pa.array(~given))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("rec_id"), chosen(b.column("c"))], names=["rec_id", "sig"])

    return df.select(F.col(id_col).cast("bigint").alias("rec_id"), F.col(counts_col).alias("c")).mapInArrow(run, "rec_id bigint, sig array<bigint>")


def merge_bins(a: Column, b: Column) -> Column:
    """Bins of the union of two records from their undensified bins; densify afterwards."""
    both = F.array_sort(F.concat(a, b))
    return let(both, lambda m: F.filter(m, lambda x, i: (i == 0) | (F.get(m, i - 1)["bin"] != x["bin"])))


def hash_ops(method: str, d: Column, n: int, copies: Column | None = None) -> Column:
    """Hash evaluations a record: classic n*d, one-pass d+n, expanded copies+n."""
    return {"classic": d * n, "one_pass": d + n, "expanded": (copies if copies is not None else d) + n}[method].cast("bigint")


def wide_kernel(df: DataFrame, id_col: str, hashes_col: str, n: int) -> DataFrame:
    """(rec_id, sig): one_pass_sketch(how='rotate') in Arrow batches, for records whose arrays are very long."""
    width = bin_width(n)

    def run(batches):
        for b in batches:
            out = []
            for h in b.column("h").to_pylist():
                if not h:
                    out.append(None)
                    continue
                h = np.asarray(h, np.int64)
                best = np.full(n, WIDTH, np.int64)
                np.minimum.at(best, h // width, h)
                filled = np.flatnonzero(best < WIDTH)
                nxt = filled[np.searchsorted(filled, np.arange(n)) % len(filled)]
                out.append((best[nxt] * 1024 + np.minimum((nxt - np.arange(n)) % n, 1023)).tolist())
            yield pa.RecordBatch.from_arrays([b.column("rec_id"), pa.array(out, pa.list_(pa.int64()))], names=["rec_id", "sig"])

    return df.select(F.col(id_col).cast("bigint").alias("rec_id"), F.col(hashes_col).alias("h")).mapInArrow(run, "rec_id bigint, sig array<bigint>")

