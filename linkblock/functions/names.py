"""Letter-aware name distances: phonetic, letter-form and keyboard costs in an edit distance."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkblock.functions.tokens import let

PSI = 12.0
#: An Arabic keyboard, each row with the x of its first key.
KEY_ROWS = ((0.0, 0.0, "ذ"), (1.0, 1.0, "ضصثقفغعهخحجد"), (2.0, 1.5, "شسيبلاتنمكط"), (3.0, 2.0, "ئءؤر"), (3.0, 7.0, "ىةوزظ"))
#: Letters that share a shape, letters that sound alike.
FORM_GROUPS = ("بتثني", "جحخ", "دذ", "رز", "سش", "صض", "طظ", "عغ", "فق", "اأإآى", "هة", "وؤ")
SOUND_PAIRS = ("تط", "سص", "سث", "دض", "ذز", "ذظ", "زظ", "حه", "قك", "غخ", "ءا", "عا")
FORM_LIKENESS, SOUND_LIKENESS = 0.8, 0.7
#: Consonant classes of the phonetic code, by letter; what isn't listed is silent.
SOUND_CLASSES = (("بفو", "1"), ("جخزسصظقكشثذض", "2"), ("تدط", "3"), ("ل", "4"), ("من", "5"), ("ر", "6"), ("حهعغ", "7"))


@dataclass(frozen=True)
class Weights:
    sound: float
    form: float
    key: float

    def __post_init__(self):
        if min(self.sound, self.form, self.key) < 0 or self.sound + self.form + self.key <= 0:
            raise ValueError("weights must be >= 0 and not all 0")


PRESETS = {"phonetic": Weights(1, 0, 0), "equal": Weights(1, 1, 1), "form": Weights(0, 1, 0), "keyboard": Weights(0, 0, 1)}


def key_places() -> dict[str, tuple[float, float]]:
    return {c: (x0 + i, y) for y, x0, row in KEY_ROWS for i, c in enumerate(row)}


def letters() -> list[str]:
    return sorted({c for _, _, row in KEY_ROWS for c in row} | {c for g in FORM_GROUPS + SOUND_PAIRS for c in g})


def sound_likeness(a: str, b: str) -> float:
    return 1.0 if a == b else SOUND_LIKENESS if a + b in SOUND_PAIRS or b + a in SOUND_PAIRS else 0.0


def form_likeness(a: str, b: str) -> float:
    return 1.0 if a == b else FORM_LIKENESS if any(a in g and b in g for g in FORM_GROUPS) else 0.0


def key_likeness(a: str, b: str, psi: float = PSI) -> float:
    places = key_places()
    if a == b:
        return 1.0
    if a not in places or b not in places:
        return 0.0
    (xa, ya), (xb, yb) = places[a], places[b]
    return max(0.0, 1 - ((xa - xb) ** 2 + (ya - yb) ** 2) ** 0.5 / psi)


def replacement_cost(a: str, b: str, w: Weights) -> float:
    """Weighted mean of the three costs (1 - likeness); 0 for equal letters."""
    if a == b:
        return 0.0
    total = w.sound * (1 - sound_likeness(a, b)) + w.form * (1 - form_likeness(a, b)) + w.key * (1 - key_likeness(a, b))
    return total / (w.sound + w.form + w.key)


def letter_table(spark: SparkSession, w: Weights) -> DataFrame:
    """(a, b, cost) for all known letters: under 2,000 rows."""
    known = letters()
    return spark.createDataFrame([(a, b, replacement_cost(a, b, w)) for a in known for b in known], "a string, b string, cost double")


def key_table(spark: SparkSession, psi: float = PSI) -> DataFrame:
    """(a, b, s): keyboard likeness computed in Spark from the coordinates."""
    places = spark.createDataFrame([(c, x, y) for c, (x, y) in sorted(key_places().items())], "c string, x double, y double")
    a, b = places.select(F.col("c").alias("a"), F.col("x").alias("xa"), F.col("y").alias("ya")), places.select(F.col("c").alias("b"), F.col("x").alias("xb"), F.col("y").alias("yb"))
    far = F.sqrt(F.pow(F.col("xa") - F.col("xb"), 2) + F.pow(F.col("ya") - F.col("yb"), 2))
    return a.join(F.broadcast(b)).select("a", "b", F.greatest(F.lit(0.0), 1 - far / psi).alias("s"))


def edit_distance(a: Column, b: Column) -> Column:
    """Plain Levenshtein distance in characters."""
    return F.levenshtein(a, b)


def _costs(w: Weights) -> Column:
    """Literal map from two letters to their cost; pairs of cost 1 are left out."""
    known = letters()
    entries = [(a + b, c) for a in known for b in known if (c := replacement_cost(a, b, w)) < 1]
    return F.map_from_arrays(F.array(*(F.lit(k) for k, _ in entries)), F.array(*(F.lit(c) for _, c in entries)))


def name_cost(a: Column, b: Column, w: Weights, indel_cost: float = 1.0, normalize: bool = True) -> Column:
    """Letter-aware edit distance by built-in functions: one row of the table per letter of a, folded over the name.

    normalize divides by the longer length. Null if either name is null; 0 for
    two empty names.
    """
    costs = _costs(w)

    def table(v: Column) -> Column:
        left, right, cost = v["l"], v["r"], v["c"]
        start = F.transform(F.sequence(F.lit(0), F.size(right)), lambda j: j * F.lit(indel_cost))

        def next_row(row: Column, x: Column) -> Column:
            first = F.array(F.get(row, F.lit(0)) + indel_cost)
            return F.aggregate(
                F.transform(right, lambda y, j: F.struct(
                    (F.get(row, j) + F.when(x == y, F.lit(0.0)).otherwise(F.coalesce(F.try_element_at(cost, F.concat(x, y)), F.lit(1.0)))).alias("swap"),
                    (F.get(row, j + 1) + indel_cost).alias("drop"),
                )),
                first,
                lambda made, s: F.concat(made, F.array(F.least(s["swap"], s["drop"], F.element_at(made, -1) + indel_cost))),
            )

        return F.element_at(F.aggregate(left, start, next_row), -1)

    chars = lambda c: F.filter(F.split(c, ""), lambda x: x != "")
    raw = let(F.struct(chars(a).alias("l"), chars(b).alias("r"), costs.alias("c")), table)
    longer = F.greatest(F.length(a), F.length(b))
    scaled = F.when(longer > 0, raw / longer).otherwise(F.lit(0.0)) if normalize else raw
    return F.when(a.isNull() | b.isNull(), F.lit(None).cast("double")).otherwise(scaled)


def cost_by_hand(a: str, b: str, w: Weights, indel_cost: float = 1.0, normalize: bool = True) -> float:
    """The same on two Python strings; also the body of the Arrow form for very long names."""
    row = [j * indel_cost for j in range(len(b) + 1)]
    for x in a:
        made = [row[0] + indel_cost]
        for j, y in enumerate(b):
            made.append(min(row[j] + replacement_cost(x, y, w), row[j + 1] + indel_cost, made[j] + indel_cost))
        row = made
    return row[-1] / max(len(a), len(b)) if normalize and (a or b) else row[-1]


#: Longer names are compared one by one: a batch is padded to its longest name.
LONGEST = 64


def batch_costs(a: pa.Array, b: pa.Array, w: Weights, indel_cost: float = 1.0, normalize: bool = True) -> np.ndarray:
    """name_cost() of two Arrow arrays of strings without nulls: each cell of the table is made for all pairs at once."""
    n, m = (pc.utf8_length(x).to_numpy(zero_copy_only=False).astype(np.int64) for x in (a, b))
    longer, out = np.maximum(n, m), np.zeros(len(a))
    long = np.flatnonzero(longer > LONGEST)
    for i in long.tolist():
        out[i] = cost_by_hand(a[i].as_py(), b[i].as_py(), w, indel_cost, False)
    some = np.flatnonzero((longer > 0) & (longer <= LONGEST))
    if some.size:
        at = pa.array(some)
        x, y = (np.array(v.take(at).to_pylist(), str) for v in (a, b))
        x, y = (v.view(np.uint32).reshape(len(v), -1).T.copy() for v in (x, y))
        known = np.array([ord(c) for c in letters()], np.uint32)
        cost = np.ones((len(known) + 1, len(known) + 1))
        cost[:-1, :-1] = [[replacement_cost(p, q, w) for q in letters()] for p in letters()]

        def place(v: np.ndarray) -> np.ndarray:
            i = np.searchsorted(known, v)
            return np.where(known[np.minimum(i, len(known) - 1)] == v, i, len(known))

        p, q, n_, m_ = place(x), place(y), n[some], m[some]
        rows = np.arange(len(some))
        row = np.repeat((np.arange(len(y) + 1) * indel_cost)[:, None], len(some), axis=1)
        made = row[m_, rows]
        for i in range(len(x)):
            after = np.empty_like(row)
            after[0] = row[0] + indel_cost
            for j in range(len(y)):
                swap = row[j] + np.where(x[i] == y[j], 0.0, cost[p[i], q[j]])
                after[j + 1] = np.minimum(np.minimum(swap, row[j + 1] + indel_cost), after[j] + indel_cost)
            row, ends = after, np.flatnonzero(n_ == i + 1)
            made[ends] = row[m_[ends], ends]
        out[some] = made
    return out / np.maximum(longer, 1) if normalize else out


def name_cost_udf(w: Weights, indel_cost: float = 1.0, normalize: bool = True):
    """Arrow-batched form of name_cost(), for many pairs and for long strings; equal names cost nothing and aren't compared."""
    @F.arrow_udf("double")
    def cost(a: pa.Array, b: pa.Array) -> pa.Array:
        known = pc.and_(pc.is_valid(a), pc.is_valid(b)).to_numpy(zero_copy_only=False)
        differ = np.flatnonzero(pc.fill_null(pc.not_equal(a, b), False).to_numpy(zero_copy_only=False))
        out = np.zeros(len(a))
        if differ.size:
            at = pa.array(differ)
            out[differ] = batch_costs(a.take(at), b.take(at), w, indel_cost, normalize)
        return pa.array(out, pa.float64(), mask=~known)

    return cost


def pair_cost(cols: list[str], w: Weights, how: str = "mean", indel_cost: float = 1.0) -> Column:
    """Mean, max or min of the costs of the names <col>_lo and <col>_hi of a pair; a null name leaves the others' cost."""
    each = name_cost_udf(w, indel_cost)
    costs = [each(F.col(f"{c}_lo"), F.col(f"{c}_hi")) for c in cols]
    if how != "mean":
        return costs[0] if len(costs) == 1 else (F.greatest if how == "max" else F.least)(*costs)
    known = sum((c.isNotNull().cast("int") for c in costs[1:]), costs[0].isNotNull().cast("int"))
    return sum((F.coalesce(c, F.lit(0.0)) for c in costs[1:]), F.coalesce(costs[0], F.lit(0.0))) / F.nullif(known, F.lit(0))


def refine_pairs(pairs: DataFrame, df: DataFrame, id_col: str, cols: list[str], w: Weights, max_cost: float = 0.25, how: str = "mean", indel_cost: float = 1.0) -> DataFrame:
    """Keep pairs whose names cost at most max_cost; adds cost. A null name makes the pair's cost the other names' alone.

    Two equi-joins fetch the names. Pairs that carry their names already
    (see rule_pairs()) need none: pair_cost() is all there is to do.
    """
    side = lambda s: df.select(F.col(id_col).alias(f"id_{s}"), *(F.col(c).alias(f"{c}_{s}") for c in cols))
    both = pairs.join(side("lo"), "id_lo").join(side("hi"), "id_hi")
    return both.select(*pairs.columns, pair_cost(cols, w, how, indel_cost).alias("cost")).where(F.col("cost") <= max_cost)


def sound_code(name: Column, script: str = "arabic") -> Column:
    """Phonetic key: consonant classes with runs collapsed; for Latin script the built-in code."""
    if script == "latin":
        return F.soundex(name)
    frm, to = "".join(g for g, _ in SOUND_CLASSES), "".join(d * len(g) for g, d in SOUND_CLASSES)
    silent = "".join(sorted(set(letters()) - set(frm)))
    coded = F.split(F.translate(name, frm + silent, to), "")
    return let(coded, lambda c: F.array_join(F.filter(c, lambda x, i: (x != "") & ((i == 0) | (F.get(c, i - 1) != x))), ""))
