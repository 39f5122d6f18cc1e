"""Capture histories over lists and population estimates with standard errors."""

from __future__ import annotations

from itertools import product

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def histories(members: DataFrame, entity: str, list_col: str, lists: list[str]) -> DataFrame:
    """(in_<list>..., n): how many entities are on exactly these lists; at most 2^lists - 1 rows."""
    seen = members.groupBy(entity).agg(*(F.max((F.col(list_col) == x).cast("int")).alias(f"in_{x.lower()}") for x in lists))
    return seen.groupBy(*(f"in_{x.lower()}" for x in lists)).agg(F.count("*").alias("n"))


def two_list(hist: DataFrame, a: str, b: str) -> DataFrame:
    """(n1, n2, m, est, se): Chapman's estimate and its standard error.

    Products of four counts pass 2^63 from some 100,000 entities on, so they are made in doubles.
    """
    n1, n2, m = (F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)) for c in (F.col(a) == 1, F.col(b) == 1, (F.col(a) == 1) & (F.col(b) == 1)))
    t = hist.agg(n1.alias("n1"), n2.alias("n2"), m.alias("m"))
    both = (F.col("n1") + 1).cast("double") * (F.col("n2") + 1)
    est = both / (F.col("m") + 1) - 1
    var = both * (F.col("n1") - F.col("m")) * (F.col("n2") - F.col("m")) / (F.pow(F.col("m") + 1, 2) * (F.col("m") + 2))
    return t.select("n1", "n2", "m", F.round(est, 4).alias("est"), F.round(F.sqrt(var), 4).alias("se"))


def three_list(hist: DataFrame, a: str, b: str, c: str) -> DataFrame:
    """(model, est) by the closed forms of the three-list models: independent lists, or one pair that depends on each other.

    Independent: the greater root of q N^2 - r N + p with q the sum of the
    lists' sizes less the number seen, r the sum of products of two sizes and
    p that of three. A pair x, y: those on z alone, times the odds of not being
    on z among all who are on x or y. Null where a denominator is 0.
    """
    of = lambda where: F.coalesce(F.sum(F.when(where, F.col("n"))), F.lit(0)).cast("double")
    on = {x: F.col(x) == 1 for x in (a, b, c)}
    sums = {"n": of(F.lit(True)), **{f"s{i}": of(on[x]) for i, x in enumerate((a, b, c))}}
    models = [("a:b", a, b, c), ("a:c", a, c, b), ("b:c", b, c, a)]
    for name, x, y, z in models:
        sums |= {f"only {name}": of(on[z] & ~on[x] & ~on[y]), f"off {name}": of(~on[z]), f"on {name}": of(on[z] & (on[x] | on[y]))}
    row = hist.agg(*(v.alias(k) for k, v in sums.items()))
    s0, s1, s2, n = (F.col(k) for k in ("s0", "s1", "s2", "n"))
    q, r, p = s0 + s1 + s2 - n, s0 * s1 + s0 * s2 + s1 * s2, s0 * s1 * s2
    made = [("independent", (r + F.sqrt(r * r - 4 * q * p)) / F.nullif(2 * q, F.lit(0.0)))]
    made += [(name, n + F.col(f"only {name}") * F.col(f"off {name}") / F.nullif(F.col(f"on {name}"), F.lit(0.0))) for name, *_ in models]
    return row.select(F.explode(F.array(*(F.struct(F.lit(m).alias("model"), F.round(e, 4).alias("est")) for m, e in made))).alias("e")).select("e.*")


def log_linear(hist: DataFrame, lists: list[str], pairs: tuple[tuple[str, str], ...] = ()) -> tuple[float, float]:
    """(estimate, se) of the population from a Poisson log-linear model of at most 2^lists cells.

    Main effects of every list and the given two-list interactions, fitted by
    Newton steps on the observed cells; the unseen cell is exp(intercept) and
    its variance comes from the inverse information.
    """
    names = [f"in_{x.lower()}" for x in lists]
    counted = {tuple(int(r[c]) for c in names): int(r["n"]) for r in hist.collect()}  # 2^lists rows at most
    cells = [c for c in product((0, 1), repeat=len(lists)) if any(c)]
    at = {x: i for i, x in enumerate(lists)}
    design = np.array([[1.0, *c, *(c[at[a]] * c[at[b]] for a, b in pairs)] for c in cells])
    y = np.array([counted.get(c, 0) for c in cells], float)
    beta = np.linalg.lstsq(design, np.log(y + 0.5), rcond=None)[0]
    for _ in range(100):
        mu = np.exp(np.clip(design @ beta, -30, 30))
        step = np.linalg.solve(design.T @ (design * mu[:, None]) + 1e-9 * np.eye(design.shape[1]), design.T @ (y - mu))
        beta += step
        if np.abs(step).max() < 1e-10:
            break
    mu = np.exp(np.clip(design @ beta, -30, 30))
    cover = np.linalg.inv(design.T @ (design * mu[:, None]) + 1e-12 * np.eye(design.shape[1]))
    unseen = float(np.exp(beta[0]))
    return float(y.sum() + unseen), float(np.sqrt(unseen + unseen**2 * cover[0, 0]))
