"""Mix sources to target weights by Pareto order sampling.

Each source gets a share of a word budget, stopped at CAP times its size, the
excess reshared by weight (water filling). Inside a source a document of odds
weight v expects min(CAP, rate * v) copies, where the rate makes the expected
words meet the target. The whole part of that is certain; the rest is an
inclusion probability p, and documents are ranked by random odds over
inclusion odds, (u/(1-u)) / (p/(1-p)), and taken in that order until the
words that are left for the source are used up. u is a hash of the id, so
reruns and lost executors give the same mix.

No source is ever gathered in one task: where the order reaches its end is
found by summing sizes in 1,024 buckets of the rank and again inside the
bucket that holds the end. Only the documents around the end (LOOKAHEAD of
them and what shares a bucket of a millionth of the source with it) meet; a
few of them change places so that their sum comes nearest to what is left.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linkblock.llm.common import SPACE, whole_id
from linkblock.runtime import settle

SHARE, CAP, CYCLE = 1.5, 2.0, (3.0, 1.0, 2.0)
COARSE, FINE = 1024, 1024 * 1024
LOOKAHEAD = 512
#: So many of the last documents taken and of the first ones left out may change places to come nearer to the target.
WINDOW = 48
#: Tables up to so many rows are broadcast after their rows were counted; beyond, joins shuffle.
BROADCAST_ROWS = 50_000
BITS = 1 << 30
_NEAR = 1e-9


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(f"[^{SPACE}]+")), F.lit(0)).cast("bigint")


def stub_weight(size: Column) -> Column:
    """Odds weight by size: texts under 50 words count half. A weight must take few values, as rates are set for each."""
    return F.when(size < 50, F.lit(1.0)).otherwise(F.lit(2.0))


def _keyed(docs: DataFrame, id_col: str, source_col: str, size: Column, weight: Callable[[Column], Column]) -> list[Column]:
    source = docs[source_col].cast("string")
    return [
        whole_id(docs, id_col).alias("mix_id"), F.coalesce(whole_id(docs, id_col).cast("string"), F.lit("")).alias("mix_ref"),
        F.coalesce(F.concat(F.lit("s"), source), F.lit("n")).alias("mix_key"), source.isNull().alias("mix_last"),
        size.alias("mix_size"), weight(size).alias("mix_weight"),
    ]


def fill(df: DataFrame, by: list[str], weight: str, cap: str, total: str, out: str) -> DataFrame:
    """Adds out = min(cap, level * weight) with one level for each `by` so that it sums to total (to the caps' sum if that is less)."""
    first = F.when(F.col(weight) > 0, F.col(cap) / F.col(weight)).otherwise(F.lit(0.0))
    order = Window.partitionBy(*by).orderBy("_stop", "_tie")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    onward = order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    level = (F.col(total) - F.coalesce(F.sum(cap).over(before), F.lit(0.0))) / F.sum(weight).over(onward)
    tie = F.xxhash64(*[c for c in df.columns if c not in by])
    ranked = df.withColumn("_stop", first).withColumn("_tie", tie).withColumn("_level", F.when(F.col(weight) > 0, level)).withColumn("_at", F.row_number().over(order))
    # The first row in order that isn't capped at its own level sets the level for all.
    found = F.min(F.when(F.col("_level") <= F.col("_stop"), F.struct("_at", "_level"))).over(Window.partitionBy(*by))["_level"]
    return ranked.withColumn("_found", found).withColumn(
        out, F.when(F.col("_found").isNull(), F.col(cap)).otherwise(F.least(F.col(cap), F.col("_found") * F.col(weight)))
    ).drop("_stop", "_tie", "_level", "_at", "_found")


def _join_small(big: DataFrame, small: DataFrame, on: list[str], how: str = "inner") -> DataFrame:
    return big.join(F.broadcast(small) if small.count() <= BROADCAST_ROWS else small, on, how)


def source_targets(sized: DataFrame, share: float = SHARE, cap: float = CAP, cycle: tuple[float, ...] = CYCLE) -> DataFrame:
    """(mix_key, source_size, target): sources in code point order, null last, weigh cycle, repeating."""
    by = sized.groupBy("mix_last", "mix_key").agg(F.sum("mix_size").cast("double").alias("source_size"))
    ranked = by.select(
        "mix_key", "source_size", (cap * F.col("source_size")).alias("_cap"), F.lit(0).alias("_all"),
        (share * F.sum("source_size").over(Window.partitionBy(F.lit(0)))).alias("_total"),
        F.element_at(F.array(*map(F.lit, cycle)), (F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("mix_last", "mix_key")) - 1) % len(cycle) + 1).alias("_weight"),
    )
    return fill(ranked, ["_all"], "_weight", "_cap", "_total", "target").select("mix_key", "source_size", "target")


def nearest_fill(sizes: list[int], left: float, window: int = WINDOW) -> list[int]:
    """Places in sizes (documents in order of rank) whose sum comes nearest to left.

    Documents are taken in order while they fit. Then the last `window` taken
    and the first `window` not taken are chosen anew, by the sums that their
    subsets can have; of equal sums one that takes earlier documents stays.
    """
    taken, room = [], left
    for i, size in enumerate(sizes):
        if size <= room:
            taken.append(i)
            room -= size
    if room < 1 or not sizes:
        return taken
    own = set(taken)
    # All sums of so many documents take a bit each: at most BITS of them are held.
    while window > 1 and 2 * window * (sum(sizes[i] for i in taken[-window:]) + room + max(sizes)) > BITS:
        window //= 2
    some = sorted(taken[-window:] + [i for i in range(len(sizes)) if i not in own][:window])
    fixed = [i for i in taken if i not in set(some)]
    goal = left - sum(sizes[i] for i in fixed)
    # Bit j of reach[n]: the last n of some have a subset of sum j.
    most = int(goal) + max(sizes) + 1
    reach, mask = [1], (1 << most + 1) - 1
    for i in reversed(some):
        reach.append((reach[-1] | reach[-1] << sizes[i]) & mask)
    low = (reach[-1] & (1 << int(goal) + 1) - 1).bit_length() - 1
    above = reach[-1] >> int(goal) + 1
    high = int(goal) + 1 + (above & -above).bit_length() - 1 if above else None
    best = high if high is not None and high - goal < goal - low else low
    for n, i in enumerate(some):
        rest = reach[len(some) - n - 1]
        if best >= sizes[i] and rest >> best - sizes[i] & 1:
            fixed.append(i)
            best -= sizes[i]
    return sorted(fixed)


def _fill_ends(sizes: pd.Series, left: pd.Series) -> pd.Series:
    return pd.Series([nearest_fill([int(x) for x in s], float(r)) for s, r in zip(sizes, left, strict=True)])


class MixPlan:
    """Small tables that say how many copies each document gets; copies() applies them to any table of documents."""

    def __init__(self, sized: DataFrame, share: float = SHARE, cap: float = CAP, cycle: tuple[float, ...] = CYCLE, seed: int = 42):
        self.seed = seed
        targets = settle(source_targets(sized, share, cap, cycle))
        levels = sized.groupBy("mix_key", "mix_weight").agg(F.sum("mix_size").cast("double").alias("_mass"))
        levels = _join_small(levels, targets, ["mix_key"]).select(
            "mix_key", "mix_weight", "_mass", "source_size", "target", (cap * F.col("_mass")).alias("_cap"), (F.col("mix_weight") * F.col("_mass")).alias("_pull")
        )
        rate = F.when(F.col("_mass") > 0, F.col("_words") / F.col("_mass")).otherwise(F.lit(0.0))
        rates = fill(levels, ["mix_key"], "_pull", "_cap", "target", "_words").withColumn("_rate", rate)
        whole = F.floor(F.col("_rate") + _NEAR)
        part = F.greatest(F.lit(0.0), F.col("_rate") - whole)
        rates = rates.select("mix_key", "mix_weight", "source_size", "target", whole.alias("_whole"), F.when(part > _NEAR, part).otherwise(F.lit(0.0)).alias("_part"), "_mass")
        left = F.col("target") - F.sum(F.col("_whole") * F.col("_mass")).over(Window.partitionBy("mix_key"))
        self.rates = settle(rates.withColumn("_left", left).drop("_mass"))
        self._find_ends(sized)

    def _ranked(self, docs: DataFrame) -> DataFrame:
        """docs with their rates and, for documents in the draw, a rank in (0, 1)."""
        u = (F.xxhash64(F.concat_ws(":", F.lit(self.seed), F.col("mix_id"))).bitwiseAND(F.lit((1 << 52) - 1)) + 0.5) / float(1 << 52)
        odds = (u / (1 - u)) / (F.col("_part") / (1 - F.col("_part")))
        drawn = (F.col("_part") > 0) & (F.col("mix_size") > 0)
        return _join_small(docs, self.rates, ["mix_key", "mix_weight"], "left").withColumn("_rank", F.when(drawn, odds / (1 + odds)))

    def _find_ends(self, sized: DataFrame) -> None:
        ranked = self._ranked(sized).where("_rank IS NOT NULL").select("mix_key", "mix_ref", "mix_size", "_rank", "_left", F.floor(F.col("_rank") * COARSE).alias("_c"), F.floor(F.col("_rank") * FINE).alias("_f"))
        order = Window.partitionBy("mix_key").orderBy("_b")
        before = order.rowsBetween(Window.unboundedPreceding, -1)

        def ends(summed: DataFrame, used: Column) -> DataFrame:
            """The buckets around the one in which the words left run out: WINDOW documents before it, LOOKAHEAD from it on."""
            run = summed.withColumn("_used", used + F.coalesce(F.sum("_size").over(before), F.lit(0))).withColumn("_end", F.col("_used") + F.col("_size") > F.col("_left"))
            past = F.coalesce(F.sum(F.when(F.col("_end"), F.col("_n")).otherwise(0)).over(before), F.lit(0))
            behind = F.coalesce(F.sum(F.when(F.col("_end"), 0).otherwise(F.col("_n"))).over(order.rowsBetween(1, Window.unboundedFollowing)), F.lit(0))
            near = F.when(F.col("_end"), F.col("_past") < LOOKAHEAD).otherwise(F.col("_behind") < WINDOW)
            return run.withColumn("_past", past).withColumn("_behind", behind).where(near).groupBy("mix_key").agg(
                F.min("_b").alias("_from"), F.max("_b").alias("_to"), F.min_by("_used", "_b").alias("_used"), F.first("_left").alias("_left")
            )

        zero = F.lit(0).cast("bigint")
        coarse = settle(ends(ranked.groupBy("mix_key", F.col("_c").alias("_b")).agg(F.sum("mix_size").alias("_size"), F.count("*").alias("_n"), F.first("_left").alias("_left")), zero))
        inside = _join_small(ranked, coarse.select("mix_key", F.col("_from").alias("_cf"), F.col("_to").alias("_ct"), F.col("_used").alias("_cu")), ["mix_key"]).where("_c BETWEEN _cf AND _ct")
        fine = inside.groupBy("mix_key", F.col("_f").alias("_b")).agg(F.sum("mix_size").alias("_size"), F.count("*").alias("_n"), F.first("_left").alias("_left"), F.first("_cu").alias("_cu"))
        self.ends = settle(ends(fine, F.col("_cu")))
        around = _join_small(ranked.drop("_left"), self.ends, ["mix_key"]).where("_f BETWEEN _from AND _to")
        same = around.groupBy("mix_key", "mix_ref", "mix_size", "_rank").agg(F.count("*").alias("_n"), F.first("_left").alias("_left"), F.first("_used").alias("_used"))
        items = F.array_sort(F.collect_list(F.struct("_rank", "mix_ref", "mix_size", "_n")))
        rows = same.groupBy("mix_key").agg(items.alias("a"), (F.first("_left") - F.first("_used")).alias("_left"))
        chosen = F.pandas_udf(_fill_ends, "array<int>")(F.transform("a", lambda x: x["mix_size"] * x["_n"]), F.col("_left"))
        at = rows.select("mix_key", "a", F.explode(chosen).alias("i")).select("mix_key", F.get("a", F.col("i")).alias("x"))
        self.picks = settle(at.select("mix_key", "x.mix_ref", "x.mix_size", F.lit(1).alias("_picked")))

    def copies(self, docs: DataFrame) -> DataFrame:
        """docs (with the mix_ columns) with copies (bigint), source_size and target added."""
        ranked = _join_small(self._ranked(docs).drop("_left"), self.ends.select("mix_key", "_from"), ["mix_key"], "left")
        with_picks = _join_small(ranked, self.picks, ["mix_key", "mix_ref", "mix_size"], "left")
        before = (F.col("_rank").isNotNull()) & (F.col("_from").isNull() | (F.floor(F.col("_rank") * FINE) < F.col("_from")))
        return with_picks.withColumn("copies", (F.coalesce(F.col("_whole"), F.lit(0)) + (before | F.col("_picked").isNotNull()).cast("int")).cast("bigint")).drop("_rank", "_from", "_picked", "_whole", "_part")


def mix_documents(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
    weight: Callable[[Column], Column] = stub_weight, share: float = SHARE, cap: float = CAP, cycle: tuple[float, ...] = CYCLE, seed: int = 42,
) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken for every row.

    Null text has size 0 and takes no words; null source is a source of its
    own, the last. Rows that repeat an id in a source share its random number:
    around the end they are taken together or not at all. An empty table gives
    no rows. What a source takes differs from its target by what no choice
    among the documents around the end (see nearest_fill()) can mend.
    """
    sized = settle(docs.select(*_keyed(docs, id_col, source_col, word_count(docs[text_col].cast("string")), weight)))
    done = MixPlan(sized, share, cap, cycle, seed).copies(sized)
    return done.select(
        F.col("mix_id").alias("doc_id"), F.when(F.col("mix_key") != "n", F.expr("substring(mix_key, 2)")).alias("source"), F.col("mix_size").alias("size"),
        F.col("source_size").cast("bigint").alias("source_size"), F.round("target", 6).alias("target"), "copies", (F.col("copies") * F.col("mix_size")).alias("taken"),
    )


def repeat_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weight: Callable[[Column], Column] = stub_weight) -> DataFrame:
    """The mix itself: rows of docs, each as often as the mix takes it, with the columns of docs."""
    keys = _keyed(docs, id_col, source_col, word_count(docs[text_col].cast("string")), weight)
    plan = MixPlan(settle(docs.select(*keys)))
    packed = docs.select(F.struct(*(docs[c] for c in docs.columns)).alias("row"), *keys)
    return plan.copies(packed).select(F.explode(F.array_repeat(F.struct("row"), F.col("copies").cast("int"))).alias("x")).select("x.row.*")
