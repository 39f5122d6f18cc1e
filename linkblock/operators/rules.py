"""Blocking rules: exact fields, conjunctions, unions of them, and the search for good ones.

A rule tree is rewritten to a union of conjunctions before Spark sees it, so
every part runs as an equi-join; an OR in a join condition would not. A pair
is emitted by the first conjunction it passes, which needs no distinct.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass
from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.sources.tables import train_half

Field = str


@dataclass(frozen=True)
class AllOf:
    parts: tuple

    def __init__(self, *parts):
        object.__setattr__(self, "parts", parts)


@dataclass(frozen=True)
class AnyOf:
    parts: tuple

    def __init__(self, *parts):
        object.__setattr__(self, "parts", parts)


def to_dnf(rule) -> list[frozenset[Field]]:
    """Conjunctions whose union is the rule; supersets of another conjunction are absorbed."""
    def walk(r) -> list[frozenset[Field]]:
        if isinstance(r, str):
            return [frozenset([r])]
        parts = [walk(p) for p in r.parts]
        if isinstance(r, AnyOf):
            return [t for p in parts for t in p]
        return reduce(lambda a, b: [x | y for x in a for y in b], parts)

    terms = list(dict.fromkeys(walk(rule)))
    return [t for t in terms if not any(u < t for u in terms)]


def part(name: str, unit: str) -> Column:
    """year, month (with its year) or day of a date column."""
    return {"year": F.year(name), "month": F.year(name) * 100 + F.month(name), "day": F.dayofmonth(name)}[unit]


def prefix(name: str, n: int) -> Column:
    return F.substring(name, 1, n)


def band(name: str, width: float) -> Column:
    return F.floor(F.col(name) / width)


def exact_field_blocks(df: DataFrame, id_col: str, fields: list[str], nulls: str = "drop") -> DataFrame:
    """(block_id, rec_id): equal on all fields, same block. Missing fields: drop the record, let nulls match, or a block of its own."""
    missing = reduce(lambda a, b: a | b, (F.col(f).isNull() for f in fields))
    key = F.xxhash64(*(F.struct(F.col(f).isNull(), F.col(f)) for f in fields))
    if nulls == "drop":
        df = df.where(~missing)
    elif nulls == "singleton":
        key = F.when(missing, F.xxhash64(F.lit("single"), F.col(id_col))).otherwise(key)
    return df.select(key.alias("block_id"), F.col(id_col).alias("rec_id"))


def rule_pairs(df: DataFrame, id_col: str, rule, carry: Iterable[str] = ()) -> DataFrame:
    """(id_lo, id_hi, first_rule): pairs that pass the rule, with the number of the first conjunction they pass.

    Missing fields agree with nothing. Both sides of each self-join are the
    same plan, so their exchange is shared. Columns to carry come with both
    records as <name>_lo and <name>_hi, so that pairs need not be shuffled to
    fetch them.
    """
    terms, carry = [sorted(t) for t in to_dnf(rule)], list(carry)
    fields = sorted({f for t in terms for f in t})
    base = df.select(F.col(id_col).alias("id"), *fields, *(F.col(c).alias(f"carry_{c}") for c in carry))
    found = []
    for i, term in enumerate(terms):
        known = base.where(reduce(lambda a, b: a & b, (F.col(f).isNotNull() for f in term)))
        rest = [f for f in fields if f not in term]
        a = known.select(F.col("id").alias("id_lo"), *term, *(F.col(f).alias(f"a_{f}") for f in rest), *(F.col(f"carry_{c}").alias(f"{c}_lo") for c in carry))
        b = known.select(F.col("id").alias("id_hi"), *term, *(F.col(f).alias(f"b_{f}") for f in rest), *(F.col(f"carry_{c}").alias(f"{c}_hi") for c in carry))
        same = lambda f, term=term: F.lit(True) if f in term else F.coalesce(F.col(f"a_{f}") == F.col(f"b_{f}"), F.lit(False))
        pairs = a.join(b, term).where("id_lo < id_hi")
        for before in terms[:i]:
            pairs = pairs.where(~reduce(lambda x, y: x & y, map(same, before)))
        found.append(pairs.select("id_lo", "id_hi", F.lit(i).alias("first_rule"), *(f"{c}_{side}" for c in carry for side in ("lo", "hi"))))
    return reduce(DataFrame.unionByName, found)


def scheme_space_lower_bound(m: Column) -> Column:
    """At least m^m ways to combine m fields."""
    return F.pow(m, m)


def candidate_rules(fields: Iterable[str], max_terms: int) -> list[tuple[str, ...]]:
    return [c for n in range(1, max_terms + 1) for c in combinations(fields, n)]


def estimate_pairs(df: DataFrame, rules: list[tuple[str, ...]]) -> DataFrame:
    """(rule, n_pairs): sums of b(b-1)/2 over blocks; no pair is made. One aggregation by (rule, key) for all rules."""
    keyed = df.select(F.explode(F.array(*(
        F.when(reduce(lambda a, b: a & b, (F.col(f).isNotNull() for f in r)), F.struct(F.lit("+".join(r)).alias("rule"), F.xxhash64(*(F.col(f).cast("string") for f in r)).alias("key"))) for r in rules
    ))).alias("e")).where("e IS NOT NULL").select("e.*")
    sized = keyed.groupBy("rule", "key").agg(F.count("*").alias("b"))
    return sized.groupBy("rule").agg(F.sum(F.expr("b * (b - 1) div 2")).alias("n_pairs"))


def truth_hits(df: DataFrame, id_col: str, truth: DataFrame, rules: list[tuple[str, ...]]) -> DataFrame:
    """(id_lo, id_hi, rule): which true pairs each rule keeps."""
    fields = sorted({f for r in rules for f in r})
    side = lambda s: df.select(F.col(id_col).alias(f"id_{s}"), *(F.col(f).alias(f"{f}_{s}") for f in fields))
    both = truth.join(side("lo"), "id_lo").join(side("hi"), "id_hi")
    passed = lambda r: reduce(lambda a, b: a & b, (F.coalesce(F.col(f"{f}_lo") == F.col(f"{f}_hi"), F.lit(False)) for f in r))
    return both.select("id_lo", "id_hi", F.explode(F.array(*(F.when(passed(r), F.lit("+".join(r))) for r in rules))).alias("rule")).where("rule IS NOT NULL")


def counts_of_rules(df: DataFrame, id_col: str, truth: DataFrame, named: dict[str, object]) -> DataFrame:
    """(method, n_pairs, n_hit) of rule trees by name, without making their pairs.

    A pair that passes several conjunctions is counted once: pairs that agree
    on all fields of one are added, of two together taken off, of three added
    again and so on, each from block sizes. Meant for rules of a few
    conjunctions, as n of them have 2^n - 1 sets of fields.
    """
    signed: dict[tuple[str, tuple[str, ...]], int] = {}
    for method, rule in named.items():
        terms = to_dnf(rule)
        for n in range(1, len(terms) + 1):
            for some in combinations(terms, n):
                fields = (method, tuple(sorted(frozenset().union(*some))))
                signed[fields] = signed.get(fields, 0) + (-1) ** (n + 1)
    blocks = estimate_pairs(df, sorted({f for _, f in signed}))
    times = df.sparkSession.createDataFrame([(m, "+".join(f), t) for (m, f), t in signed.items()], "method string, rule string, times int")  # one row a rule and set of fields
    made = times.join(blocks, "rule", "left").groupBy("method").agg(F.sum(F.col("times") * F.coalesce("n_pairs", F.lit(0))).alias("n_pairs"))
    fields = sorted({f for rule in named.values() for t in to_dnf(rule) for f in t})
    side = lambda s: df.select(F.col(id_col).alias(f"id_{s}"), *(F.col(f).alias(f"{f}_{s}") for f in fields))
    same = lambda t: reduce(lambda a, b: a & b, (F.coalesce(F.col(f"{f}_lo") == F.col(f"{f}_hi"), F.lit(False)) for f in sorted(t)))
    passed = [(m, reduce(lambda a, b: a | b, map(same, to_dnf(r)))) for m, r in named.items()]
    hits = truth.select("id_lo", "id_hi").join(side("lo"), "id_lo").join(side("hi"), "id_hi").agg(*(F.count_if(x).alias(f"h{i}") for i, (_, x) in enumerate(passed)))
    by_method = hits.select(F.explode(F.array(*(F.struct(F.lit(m).alias("method"), F.col(f"h{i}").alias("n_hit")) for i, (m, _) in enumerate(passed)))).alias("e")).select("e.*")
    return made.join(F.broadcast(by_method), "method").select("method", "n_pairs", "n_hit")


def search_schemes(df: DataFrame, id_col: str, truth: DataFrame, rules: list[tuple[str, ...]], pair_budget: int, steps: int = 3) -> list[tuple[int, str, int, int]]:
    """(step, rule, new true pairs, its pairs): greedy cover of the truth within a pair budget.

    Only one row a rule meets the driver in each step; the truth stays in
    Spark and loses what the chosen rules cover.
    """
    cost = {r["rule"]: r["n_pairs"] for r in estimate_pairs(df, rules).collect()}
    hits = truth_hits(df, id_col, truth, rules).persist()
    chosen: list[tuple[int, str, int, int]] = []
    spent, left = 0, hits
    for step in range(1, steps + 1):
        options = [(r["n"], r["rule"]) for r in left.groupBy("rule").agg(F.count("*").alias("n")).collect() if spent + cost[r["rule"]] <= pair_budget]
        if not options:
            break
        gain, rule = min(options, key=lambda x: (-x[0], x[1]))
        chosen.append((step, rule, gain, cost[rule]))
        spent += cost[rule]
        covered = hits.where(F.col("rule") == rule).select("id_lo", "id_hi")
        left = left.join(covered, ["id_lo", "id_hi"], "left_anti")
    hits.unpersist()
    return chosen


def holdout_recall(df: DataFrame, id_col: str, entity: str, truth: DataFrame, rules: list[tuple[str, ...]]) -> DataFrame:
    """(rule, train_recall, test_recall): the entities' halves by a hash of their key."""
    half = df.select(F.col(id_col).alias("id_lo"), train_half(F.col(entity)).alias("train"))
    parted = truth.join(half, "id_lo")
    totals = parted.agg(F.sum(F.col("train").cast("bigint")).alias("nt"), F.sum((~F.col("train")).cast("bigint")).alias("nv"))
    hits = truth_hits(df, id_col, truth, rules).join(half, "id_lo").groupBy("rule").agg(F.sum(F.col("train").cast("bigint")).alias("ht"), F.sum((~F.col("train")).cast("bigint")).alias("hv"))
    return hits.join(F.broadcast(totals)).select("rule", F.round(F.col("ht") / F.col("nt"), 6).alias("train_recall"), F.round(F.col("hv") / F.col("nv"), 6).alias("test_recall"))


def choose_on_half(df: DataFrame, id_col: str, entity: str, truth: DataFrame, rules: list[tuple[str, ...]], pair_budget: int, steps: int = 3) -> DataFrame:
    """(step, rule, train_recall, test_recall): search_schemes() sees one half of the entities; recall is that of the rules chosen so far."""
    half = df.select(F.col(id_col).alias("id_lo"), train_half(F.col(entity)).alias("train"))
    parted = truth.select("id_lo", "id_hi").join(half, "id_lo")
    chosen = search_schemes(df, id_col, parted.where("train").select("id_lo", "id_hi"), rules, pair_budget, steps)
    picked = df.sparkSession.createDataFrame([(s, r) for s, r, _, _ in chosen], "step int, rule string")  # at most `steps` rows
    later = picked.select(F.col("step").alias("from"), "rule").join(F.broadcast(picked.select("step")), F.col("from") <= F.col("step")).select("step", "rule")
    kept = truth_hits(df, id_col, truth, rules).join(F.broadcast(later), "rule").select("step", "id_lo", "id_hi").distinct().join(half, "id_lo")
    counted = kept.groupBy("step").agg(F.count_if("train").alias("ht"), F.count_if(~F.col("train")).alias("hv"))
    totals = parted.agg(F.count_if("train").alias("nt"), F.count_if(~F.col("train")).alias("nv"))
    share = lambda h, n: F.round(F.coalesce(F.col(h), F.lit(0)) / F.nullif(F.col(n), F.lit(0)), 6)
    return picked.join(counted, "step", "left").join(F.broadcast(totals)).select("step", "rule", share("ht", "nt").alias("train_recall"), share("hv", "nv").alias("test_recall"))
