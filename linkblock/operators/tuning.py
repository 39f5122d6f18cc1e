"""Choosing K and L: quality of every cell of a grid, over one or several seeds."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.functions.hashing import mix
from linkblock.operators import bands, measures, pairs, sketch
from linkblock.operators import cells as meet
from linkblock.runtime import settle, spread


def cell(sets: DataFrame, truth: DataFrame, k: int, tables: int, seed: int | None = None, how: str = "probe") -> DataFrame:
    """One row: k, l, recall, rr, prec, max_bin. sets: (rec_id, h); a seed remixes the token hashes for an independent run."""
    h = F.col("h") if seed is None else F.array_sort(F.transform("h", lambda x: mix(x, seed)))
    sig = sets.select("rec_id", sketch.one_pass_sketch(h, k * tables, how).alias("sig"))
    largest = bands.bucketize(sig, "rec_id", F.col("sig"), k, tables).groupBy("table_no", "bucket_key").agg(F.count("*").alias("n")).agg(F.max("n").alias("max_bin"))
    row = measures.quality(pairs.from_signatures(sig, "rec_id", F.col("sig"), k, tables), truth, sets, "x")
    return row.join(F.broadcast(largest)).select(F.lit(k).alias("k"), F.lit(tables).alias("l"), "recall", "rr", "prec", "max_bin")


def grid(sets: DataFrame, truth: DataFrame, cells: Iterable[tuple[int, int]], seeds: Iterable[int | None] = (None,)) -> DataFrame:
    """Mean over seeds for each cell; token hashes are made once and kept in the shared folder."""
    sets, truth = spread(settle(sets)), settle(truth.select("id_lo", "id_hi"))
    seeds = list(seeds)
    rows = reduce(DataFrame.unionByName, (cell(sets, truth, k, t, s) for k, t in cells for s in seeds))
    if len(seeds) == 1:
        return rows
    return rows.groupBy("k", "l").agg(*(F.round(F.avg(c), 6).alias(c) for c in ("recall", "rr", "prec")), F.round(F.stddev_pop("recall"), 6).alias("recall_sd"), F.max("max_bin").alias("max_bin"))


def runs(sets: DataFrame, truth: DataFrame, cells: Iterable[tuple[int, int]], seeds: Iterable[int]) -> DataFrame:
    """(k, l, seed, n_pairs, train_hits, test_hits) of independent runs of the sketch by table. truth: (id_lo, id_hi, train).

    A pair knows the first table that it shares, so one run of the most tables
    a K has serves every smaller L: a pair belongs to L if that table is below
    L. Token sets, not keys, meet in the cells of every two groups of records:
    a set makes its keys there, and pairs are counted by first table where
    they are found. The truth meets the sets of its own records, so no pair is
    ever dealt.
    """
    cells, seeds = list(cells), list(seeds)
    most = {k: max(t for j, t in cells if j == k) for k, _ in cells}
    sets = spread(settle(sets.where("size(h) > 0").select(F.col("rec_id").alias("id"), "h")))
    n, tokens = sets.agg(F.count("*"), F.coalesce(F.sum(F.size("h")), F.lit(0))).first()
    groups = meet.groups_for(n, 8 * (max(most.values()) + 1 + tokens // max(n, 1)), sets.sparkSession.sparkContext.defaultParallelism)

    def pairs_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cell in meet.whole_cells(batches):
            ids, side, (tok, size) = meet.column(cell, "id").to_numpy(), meet.column(cell, "side").to_numpy(), _tokens(meet.column(cell, "h"))
            for k, tables in most.items():
                for seed in seeds:
                    found = meet.counted(sketch.per_table_keys(tok, size, k, tables, seed), side, ids)
                    yield _counts(k, seed, found, np.zeros_like(found), np.zeros_like(found))

    def hits_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            a, z, train = _tokens(b.column("a")), _tokens(b.column("z")), b.column("train").to_numpy(zero_copy_only=False).astype(bool)
            for k, tables in most.items():
                for seed in seeds:
                    same = sketch.per_table_keys(*a, k, tables, seed) == sketch.per_table_keys(*z, k, tables, seed)
                    first, met = same.argmax(axis=0), same.any(axis=0)
                    of = lambda half: np.bincount(first[met & half], minlength=tables).astype(np.int64)  # noqa: B023, E731
                    yield _counts(k, seed, np.zeros(tables, np.int64), of(train), of(~train))

    shape = "k int, seed int, first_table int, p bigint, a bigint, b bigint"
    found = meet.deal(sets, groups).mapInArrow(pairs_of, shape)
    true = truth.select("id_lo", "id_hi", "train").join(sets.select(F.col("id").alias("id_lo"), F.col("h").alias("a")), "id_lo").join(sets.select(F.col("id").alias("id_hi"), F.col("h").alias("z")), "id_hi")
    counted = found.unionByName(true.select("a", "z", "train").mapInArrow(hits_of, shape)).groupBy("k", "seed", "first_table").agg(*(F.sum(c).alias(c) for c in "pab"))
    grid = sets.sparkSession.createDataFrame([(k, t, s) for k, t in cells for s in seeds], "k int, l int, seed int")  # one row a cell and seed
    total = lambda c: F.coalesce(F.sum(F.when(F.col("first_table") < F.col("l"), F.col(c))), F.lit(0)).alias
    return counted.join(F.broadcast(grid), ["k", "seed"], "right").groupBy("k", "l", "seed").agg(total("p")("n_pairs"), total("a")("train_hits"), total("b")("test_hits"))


def _tokens(sets: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(tokens of all sets in a row, sizes)."""
    return sets.flatten().to_numpy(zero_copy_only=False), pc.list_value_length(sets).to_numpy(zero_copy_only=False).astype(np.int64)


def _counts(k: int, seed: int, p: np.ndarray, a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    n = len(p)
    given = [np.full(n, k, np.int32), np.full(n, seed, np.int32), np.arange(n, dtype=np.int32), p, a, b]
    return pa.RecordBatch.from_arrays([pa.array(x) for x in given], names=["k", "seed", "first_table", "p", "a", "b"])


def choose_on_half(sets: DataFrame, truth: DataFrame, train: Column, cells: Iterable[tuple[int, int]], seeds: Iterable[int], pair_budget: int) -> DataFrame:
    """Each cell over several seeds, and which one the training half of the truth picks: most of its pairs kept, within a budget of pairs.

    k, l, n_pairs (mean over seeds), train_recall, test_recall (means), test_sd, chosen.
    train: a condition over truth's columns. Ties go to fewer pairs, then to
    the smaller k and l; no cell is chosen if all are over the budget.
    """
    seeds = list(seeds)
    truth = settle(truth.select("id_lo", "id_hi", train.alias("train")))
    totals = truth.agg(F.count_if("train").alias("nt"), F.count_if(~F.col("train")).alias("nv"))
    share = lambda h, n: F.col(h) / F.nullif(F.col(n), F.lit(0))
    rated = settle(runs(sets, truth, cells, seeds).join(F.broadcast(totals)).groupBy("k", "l").agg(
        F.sum("n_pairs").alias("all_pairs"), F.sum("train_hits").alias("kept"), F.round(F.avg("n_pairs"), 6).alias("n_pairs"),
        F.round(F.avg(share("train_hits", "nt")), 6).alias("train_recall"), F.round(F.avg(share("test_hits", "nv")), 6).alias("test_recall"),
        F.round(F.stddev_pop(share("test_hits", "nv")), 6).alias("test_sd")))
    order = F.struct("kept", -F.col("all_pairs"), -F.col("k"), -F.col("l"))
    best = rated.where(F.col("all_pairs") <= pair_budget * len(seeds)).agg(F.max_by(F.struct("k", "l"), order).alias("best"))
    picked = F.coalesce(F.struct("k", "l") == F.col("best"), F.lit(False)).alias("chosen")
    return rated.join(F.broadcast(best)).select("k", "l", "n_pairs", "train_recall", "test_recall", "test_sd", picked)
