"""Rules, sketches, bands, blocks, linkage and estimates on small fixtures."""

import math
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from linkblock.functions import hashing, similarity
from linkblock.functions.hashing import WIDTH, coefficients
from linkblock.operators import bands, blocks, capture, cluster, joins, linkage, measures, pairs, rules, sketch, tuning
from linkblock.operators.components import connected_components


def pair_set(df):
    return {(r.id_lo, r.id_hi) for r in df.collect()}


# rules


def test_same_date_and_place(spark):
    df = spark.createDataFrame([(1, "d", "Damascus"), (2, "d", "Damascus"), (3, "d", "Homs")], "id bigint, day string, place string")
    assert pair_set(rules.rule_pairs(df, "id", rules.AllOf("day", "place"))) == {(1, 2)}


def test_and_of_ors_equals_its_union_form(spark):
    rng = random.Random(1)
    rows = [(i, *(rng.choice([0, 1, None]) for _ in range(3))) for i in range(30)]
    df = spark.createDataFrame(rows, "id bigint, a int, b int, c int")
    rule = rules.AllOf(rules.AnyOf("a", "b"), rules.AnyOf("b", "c"))
    assert set(rules.to_dnf(rule)) == {frozenset("b"), frozenset("ac")}
    eq = lambda x, y, i: x[i] is not None and x[i] == y[i]
    want = {(x[0], y[0]) for x in rows for y in rows if x[0] < y[0] and (eq(x, y, 1) or eq(x, y, 2)) and (eq(x, y, 2) or eq(x, y, 3))}
    got = rules.rule_pairs(df, "id", rule)
    assert pair_set(got) == want and got.count() == len(want)
    more = pair_set(rules.rule_pairs(df, "id", rules.AnyOf(rule, "c")))
    less = pair_set(rules.rule_pairs(df, "id", rules.AllOf(rule, "c")))
    assert want <= more and less <= want


def test_missing_fields(spark):
    df = spark.createDataFrame([(1, None), (2, None), (3, "x")], "id bigint, day string")
    made = lambda nulls: pair_set(pairs.from_blocks(rules.exact_field_blocks(df, "id", ["day"], nulls)))
    assert made("drop") == set() and made("match_null") == {(1, 2)} and made("singleton") == set()
    assert rules.exact_field_blocks(df, "id", ["day"], "singleton").count() == 3


def test_pair_counts_need_no_pairs(spark):
    df = spark.createDataFrame([(i, i % 3, i % 2) for i in range(20)], "id bigint, a int, b int")
    counted = {r.rule: r.n_pairs for r in rules.estimate_pairs(df, [("a",), ("a", "b")]).collect()}
    assert counted == {"a": rules.rule_pairs(df, "id", "a").count(), "a+b": rules.rule_pairs(df, "id", rules.AllOf("a", "b")).count()}


# sketches


def sets(spark, rows):
    return spark.createDataFrame([(i, sorted(int(x) for x in s)) for i, s in enumerate(rows)], "rec_id bigint, h array<bigint>")


def slow_bins(h, n):
    out = {}
    for x in h:
        b = x // sketch.bin_width(n)
        out[b] = min(out.get(b, WIDTH), x)
    return out


@pytest.mark.parametrize("how", ["rotate", "coin", "probe"])
def test_densified_bins(spark, how):
    rng = np.random.default_rng(3)
    rows = [rng.choice(WIDTH, n, replace=False) for n in (1, 2, 5, 40, 300)] + [[]]
    n = 16
    df = sets(spark, rows)
    out = df.select("rec_id", sketch.densify(sketch.one_pass_bins(F.col("h"), n), n, how).alias("d")).collect()
    for r in out:
        own = slow_bins([int(x) for x in rows[r.rec_id]], n)
        if not own:
            assert r.d is None
            continue
        assert [e.bin for e in r.d] == list(range(n))
        for e in r.d:
            assert (e.dist == 0) == (e.bin in own)
            assert e.val == (own[e.bin] if e.bin in own else own[(e.bin + e.dist) % n] if how == "rotate" else e.val) and e.val in own.values()


def test_one_token_fills_all_bins(spark):
    d = sets(spark, [[5]]).select(sketch.densify(sketch.one_pass_bins(F.col("h"), 8), 8, "rotate").alias("d")).first().d
    assert sorted(e.dist for e in d) == list(range(8)) and {e.val for e in d} == {5}


def test_rotated_neighbours_repeat_one_source(spark):
    df = sets(spark, [[10, WIDTH // 2, WIDTH - 9]])
    values = lambda how: len({e.val for e in df.select(sketch.densify(sketch.one_pass_bins(F.col("h"), 40), 40, how).alias("d")).first().d[8:12]})
    assert values("rotate") == 1


def near_pair(rng, shared, own):
    x = rng.choice(WIDTH, shared + 2 * own, replace=False)
    return x[: shared + own], np.r_[x[:shared], x[shared + own :]]


@pytest.mark.parametrize("make", ["classic", "rotate", "coin", "probe", "per_table"])
def test_collisions_follow_jaccard(spark, make):
    rng = np.random.default_rng(11)
    rows = [s for _ in range(40) for s in near_pair(rng, 120, 60)]  # similarity 0.5
    n = 64
    column = {"classic": lambda h: sketch.classic_minhash(h, n), "per_table": lambda h: sketch.per_table_sketch(h, 4, 16)}.get(make, lambda h: sketch.one_pass_sketch(h, n, make))
    sig = [r.s for r in sets(spark, rows).orderBy("rec_id").select(column(F.col("h")).alias("s")).collect()]
    share = np.mean([[a == b for a, b in zip(sig[i], sig[i + 1], strict=True)] for i in range(0, len(sig), 2)])
    assert abs(share - 0.5) < 0.05


def counts_of(spark, rows):
    return spark.createDataFrame([(i, [(int(h), int(c)) for h, c in sorted(r.items()) if c]) for i, r in enumerate(rows)], "rec_id bigint, c array<struct<h:bigint,cnt:int>>")


def weighted_rows(rng, n):
    out = []
    for _ in range(n):
        base = {int(h): int(c) for h, c in zip(rng.choice(WIDTH, 80, replace=False), rng.integers(1, 5, 80), strict=True)}
        out += [base, {h: max(0, c + int(rng.integers(-1, 2))) for h, c in base.items()}]
    return out


def jw(x, y):
    keys = x.keys() | y.keys()
    return sum(min(x.get(k, 0), y.get(k, 0)) for k in keys) / sum(max(x.get(k, 0), y.get(k, 0)) for k in keys)


@pytest.mark.parametrize("make", ["expanded", "consistent", "sampled"])
def test_weighted_forms_follow_weighted_jaccard(spark, make):
    rng = np.random.default_rng(12)
    rows = weighted_rows(rng, 60)
    column = {"expanded": lambda c: sketch.one_pass_sketch(sketch.expand(c), 32), "consistent": lambda c: sketch.consistent_weighted_hash(c, 24), "sampled": lambda c: sketch.sample_tokens(c, 4.0)}[make]
    made = [r.s for r in counts_of(spark, rows).orderBy("rec_id").select(column(F.col("c")).alias("s")).collect()]
    share = lambda a, b: len(set(a) & set(b)) / len(set(a) | set(b)) if make == "sampled" else np.mean([x == y for x, y in zip(a, b, strict=True)])
    bias = np.mean([share(made[i], made[i + 1]) - jw(rows[i], rows[i + 1]) for i in range(0, len(rows), 2)])
    assert abs(bias) < 0.05


def test_independent_sampling_loses_similarity(spark):
    df = counts_of(spark, [{i * 7919: 1 for i in range(200)}] * 2)
    for coordinated, low, high in ((True, 1.0, 1.0), (False, 0.2, 0.5)):
        a, b = (set(r.s) for r in df.select(sketch.sample_tokens(F.col("c"), 2.0, coordinated, F.col("rec_id")).alias("s")).collect())
        assert low <= len(a & b) / len(a | b) <= high


def test_expansion_identity_by_hand(spark):
    a, b = (set(r.s) for r in counts_of(spark, [{1: 2, 3: 1}, {1: 1, 2: 1, 3: 1}]).orderBy("rec_id").select(sketch.expand(F.col("c")).alias("s")).collect())
    assert len(a & b) / len(a | b) == 0.5


def test_wide_kernel_equals_built_in(spark):
    rng = np.random.default_rng(5)
    df = sets(spark, [rng.choice(WIDTH, n, replace=False) for n in (1, 3, 50, 900)] + [[]])
    want = {r.rec_id: r.s for r in df.select("rec_id", sketch.one_pass_sketch(F.col("h"), 32, "rotate").alias("s")).collect()}
    assert {r.rec_id: r.sig for r in sketch.wide_kernel(df, "rec_id", "h", 32).collect()} == want


def test_merged_bins_are_those_of_the_union(spark):
    df = sets(spark, [[1, 9, 2**31], [2, 2**31 - 5, 2**32 - 1], [1, 2, 9, 2**31 - 5, 2**31, 2**32 - 1]])
    a, b, both = (r.m for r in df.orderBy("rec_id").select(sketch.one_pass_bins(F.col("h"), 4).alias("m")).collect())
    one = spark.createDataFrame([(a, b)], "a array<struct<bin:bigint,val:bigint>>, b array<struct<bin:bigint,val:bigint>>")
    assert one.select(sketch.merge_bins(F.col("a"), F.col("b")).alias("m")).first().m == both


def test_mixers_differ():
    assert len({coefficients(s) for s in range(2000)}) == 2000


# bands and pairs


def test_pairs_once_and_in_the_first_table(spark):
    rows = [(1, [5, 6, 7]), (2, [5, 6, 8]), (3, [0, 6, 7]), (4, None)]
    df = spark.createDataFrame(rows, "id bigint, k array<bigint>")
    found, large = pairs.from_keys(df, "id", F.col("k"))
    assert sorted((r.id_lo, r.id_hi, r.first_table) for r in found.collect()) == [(1, 2, 0), (1, 3, 1), (2, 3, 1)] and large.count() == 0
    found, large = pairs.from_keys(df, "id", F.col("k"), cap=2)
    assert [(r.table_no, r.n) for r in large.collect()] == [(1, 3)]
    assert pair_set(found) <= {(1, 2), (1, 3), (2, 3)}


def test_bands_grow_and_shrink_recall(spark):
    rng = np.random.default_rng(8)
    rows = [s for _ in range(60) for s in near_pair(rng, 100, 30)]
    sig = sets(spark, rows).select("rec_id", sketch.classic_minhash(F.col("h"), 24).alias("sig")).persist()
    made = lambda k, t: pair_set(pairs.from_signatures(sig, "rec_id", F.col("sig"), k, t))
    assert made(4, 2) <= made(4, 6) and made(4, 6) <= made(2, 12)
    direct = pair_set(pairs.from_buckets(bands.bucketize(sig, "rec_id", F.col("sig"), 4, 6)))
    assert direct == made(4, 6)
    stride = bands.bucketize(sig, "rec_id", F.col("sig"), 4, 6, "stride")
    assert stride.count() == 6 * len(rows)
    curve = sig.select(bands.collision_probability(F.lit(0.5), 4, 6).alias("p")).first().p
    assert abs(curve - (1 - (1 - 0.5**4) ** 6)) < 1e-12


def test_empty_records_have_own_buckets_or_none(spark):
    df = spark.createDataFrame([(1, None), (2, None)], "id bigint, s array<bigint>")
    assert bands.bucketize(df, "id", F.col("s"), 1, 2).count() == 0
    own = bands.bucketize(df, "id", F.col("s"), 1, 2, empty="own")
    assert own.count() == 4 and pairs.from_buckets(own).count() == 0


def test_all_pairs_is_guarded(spark):
    df = spark.range(5)
    assert pairs.all_pairs(df, "id").count() == 10
    with pytest.raises(ValueError):
        pairs.all_pairs(df, "id", 4)


# components and blocks


def test_components(spark):
    rng = random.Random(9)
    edges = [(1, 2), (2, 3), (4, 5), (7, 7), (None, 8)] + [(100 + i, 101 + i) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 60)]
    edges += [(rng.randrange(2000, 2100), rng.randrange(2000, 2100)) for _ in range(80)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(edges, "a bigint, b bigint"), "a", "b").collect()}
    root = {}
    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x
    for a, b in edges:
        if a is not None and a != b:
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
    assert got == {x: find(x) for x in root}
    assert connected_components(spark.createDataFrame([], "a bigint, b bigint"), "a", "b").count() == 0


def test_large_blocks_lose_nothing(spark):
    b = spark.createDataFrame([(7, i) for i in range(50)] + [(8, 60)], "block_id bigint, rec_id bigint")
    second = spark.createDataFrame([(i, i % 5) for i in range(50)], "rec_id bigint, sub_key bigint")
    out = blocks.split_large(b, 10, second).collect()
    assert len(out) == 51 and len({(r.block_id, r.sub) for r in out}) == 6
    assert {(r.blocks_per_record, r.n) for r in blocks.overlap(b).collect()} == {(1, 51)}
    assert [r.block_id for r in blocks.top_blocks(b, 1).collect()] == [7]


def test_partition_covers_every_record_once(spark):
    records = spark.range(6).select(F.col("id").alias("rec_id"))
    found = spark.createDataFrame([(1, 2), (2, 3), (4, 5)], "id_lo bigint, id_hi bigint")
    assert {r.rec_id: r.component for r in blocks.to_partition(records, found).collect()} == {0: 0, 1: 1, 2: 1, 3: 1, 4: 4, 5: 4}


def test_measures(spark):
    found = spark.createDataFrame([(1, 2), (1, 3), (2, 3)], "id_lo bigint, id_hi bigint")
    truth = spark.createDataFrame([(1, 2), (4, 5)], "id_lo bigint, id_hi bigint")
    row = measures.quality(found, truth, 5, "m").first()
    assert (row.n_pairs, row.n_true, row.n_hit, row.recall, row.rr, row.prec) == (3, 2, 1, 0.5, 0.7, 0.333333)
    part = spark.createDataFrame([(1, 1), (1, 2), (1, 3), (2, 4), (3, 5)], "block_id bigint, rec_id bigint")
    assert measures.partition_quality(part, truth, "m").first()[1:] == row[1:]
    one = spark.range(1)
    assert one.select(measures.split_rate(F.lit(1), F.lit(4)).alias("x")).first().x == 0.75
    assert one.select(measures.f1(F.lit(1), F.lit(2), F.lit(3)).alias("x")).first().x == 0.4


def test_linkage_and_estimates(spark):
    df = spark.createDataFrame([(1, "a", "x"), (2, "a", "x"), (3, "a", "y"), (4, None, None)], "rec_id bigint, given string, place string")
    found = spark.createDataFrame([(1, 2), (1, 3), (1, 4)], "id_lo bigint, id_hi bigint")
    scored = linkage.score_pairs(found, df, "rec_id", ["given", "place"], 2)
    assert {(r.id_hi, r.agree, r.match) for r in scored.collect()} == {(2, 2, True), (3, 1, False), (4, 0, False)}
    assert {r.rec_id: r.component for r in linkage.entities(df, scored).collect()} == {1: 1, 2: 1, 3: 3, 4: 4}
    hist = spark.createDataFrame([(1, 0, 4), (0, 1, 2), (1, 1, 2)], "in_a int, in_b int, n bigint")
    row = capture.two_list(hist, "in_a", "in_b").first()
    assert (row.n1, row.n2, row.m, row.est) == (6, 4, 2, 10.6667)


def test_two_lists_of_a_million_people_do_not_overflow(spark):
    hist = spark.createDataFrame([(1, 0, 400_000), (0, 1, 200_000), (1, 1, 200_000)], "in_a int, in_b int, n bigint")
    n1, n2, m = 600_000, 400_000, 200_000
    row = capture.two_list(hist, "in_a", "in_b").first()
    assert (row.n1, row.n2, row.m) == (n1, n2, m)
    assert abs(row.est - ((n1 + 1) * (n2 + 1) / (m + 1) - 1)) < 1e-3
    assert abs(row.se - ((n1 + 1) * (n2 + 1) * (n1 - m) * (n2 - m) / ((m + 1) ** 2 * (m + 2))) ** 0.5) < 1e-3


def test_fitted_three_list_models_equal_their_closed_forms(spark):
    rows = [(1, 0, 0, 90), (0, 1, 0, 70), (0, 0, 1, 40), (1, 1, 0, 33), (1, 0, 1, 21), (0, 1, 1, 15), (1, 1, 1, 9)]
    hist = spark.createDataFrame(rows, "in_a int, in_b int, in_c int, n bigint")
    closed = {r.model: r.est for r in capture.three_list(hist, "in_a", "in_b", "in_c").collect()}
    for model, p in (("independent", ()), ("a:b", (("A", "B"),)), ("a:c", (("A", "C"),)), ("b:c", (("B", "C"),))):
        assert abs(capture.log_linear(hist, ["A", "B", "C"], p)[0] - closed[model]) < 0.01
    empty = capture.three_list(hist.limit(0), "in_a", "in_b", "in_c").collect()
    assert len(empty) == 4 and all(r.est is None for r in empty)


def test_hot_buckets_make_every_pair_once(spark):
    rows = [(i, [1, i % 3]) for i in range(60)] + [(100, [2, 7]), (101, [2, 8])]
    df = spark.createDataFrame(rows, "id bigint, k array<bigint>")
    for chunk in (7, 2048):
        found = [(r.id_lo, r.id_hi, r.first_table) for r in pairs.from_keys(df, "id", F.col("k"), chunk=chunk)[0].collect()]
        assert len(found) == len(set(found)) == 60 * 59 // 2 + 1 and all(t == 0 for _, _, t in found)
    later = [(i, [i, 5]) for i in range(30)]
    found = pairs.from_keys(spark.createDataFrame(later, "id bigint, k array<bigint>"), "id", F.col("k"), chunk=4)[0].collect()
    assert len(found) == 30 * 29 // 2 and {r.first_table for r in found} == {1}


def test_fast_sketch_blocks_match_plain_hashes(spark, sf):
    """Token hashes and their counts by plain Python; the steps after them are those of the portable form, which SQL checks."""
    import xxhash

    from linkblock.functions import tokens

    texts = [(1, "a b c d a b c"), (2, "x y"), (3, None), (4, "é É z  z-z"), (5, "")]
    df = spark.createDataFrame(texts, "id bigint, text string")
    got = {r.id: sorted((e.h, e.cnt) for e in r.c) for r in df.select("id", tokens.fast_gram_counts(F.col("text"), 3).alias("c")).collect()}
    for i, text in texts:
        words, want = re.findall(r"[^\W_]+", (text or "").lower()), {}
        for at in range(len(words) - 2):
            h = 42
            for w in words[at : at + 3]:
                h = xxhash.xxh64_intdigest(w.encode(), h)
            want[h & (1 << 32) - 1] = want.get(h & (1 << 32) - 1, 0) + 1
        assert got[i] == sorted(want.items())


def test_log_linear_recovers_independent_lists(spark):
    p, n = {"A": 0.6, "B": 0.4, "C": 0.25}, 10_000
    cells = []
    for c in [(a, b, d) for a in (0, 1) for b in (0, 1) for d in (0, 1)]:
        share = np.prod([q if x else 1 - q for x, q in zip(c, p.values(), strict=True)])
        if any(c):
            cells.append((*c, int(round(n * share))))
    est, se = capture.log_linear(spark.createDataFrame(cells, "in_a int, in_b int, in_c int, n bigint"), ["A", "B", "C"])
    assert abs(est - n) < 20 and 0 < se < 200


def test_cost_of_slow_linkage(spark):
    b = spark.createDataFrame([(1, i) for i in range(500)] + [(2, 999)], "block_id bigint, rec_id bigint")
    row = linkage.linkage_hours(b, "m").first()
    assert (row.hours_low, row.hours_high) == (12.0, 24.0)


def test_joins(spark):
    rng = random.Random(4)
    rows = [(i, rng.randrange(3), f"2020-01-{rng.randrange(1, 29):02d}") for i in range(80)]
    df = spark.createDataFrame(rows, "id bigint, k int, d string").select("id", "k", F.col("d").cast("date").alias("day"))
    got = {(r.id_lo, r.id_hi) for r in joins.date_range_pairs(df, "id", "day", ["k"], 3).collect()}
    day = lambda r: int(r[2][-2:])
    assert got == {(a[0], b[0]) for a in rows for b in rows if a[0] < b[0] and a[1] == b[1] and abs(day(a) - day(b)) <= 3}
    left, right = df.where("id < 40"), df.where("id >= 40")
    prior = {r.id: r.prior_id for r in joins.as_of(left, right, "id", ["k"], "day").collect()}
    for a in rows[:40]:
        options = [(day(b), b[0]) for b in rows[40:] if b[1] == a[1] and day(b) <= day(a)]
        assert prior[a[0]] == (max(options)[1] if options else None)


def test_vectors_of_repeated_and_single_tokens_equal_the_plain_form(spark):
    rng = np.random.default_rng(4)
    rows = [(i, f"t{rng.integers(0, 60)}", int(rng.integers(1, 4))) for i in range(40) for _ in range(5)] + [(99, "alone", 2)]
    long = spark.createDataFrame(rows, "rec_id bigint, tok string, cnt int").dropDuplicates(["rec_id", "tok"])
    plain = {r.rec_id: r.v for r in cluster.project(cluster.tfidf(long, 41), 8).collect()}
    got = {r.rec_id: r.v for r in cluster.tfidf_vectors(long.select("rec_id", hashing.base64bits(F.col("tok")).alias("key"), "cnt"), 41, 8).collect()}
    assert set(got) == set(plain) and all(np.allclose(got[i], plain[i], atol=2e-6) for i in plain)


def test_nearest_centre_by_matrix_and_ties():
    rng = np.random.default_rng(3)
    v, c = rng.normal(size=(300, 5)), rng.normal(size=(40, 5))
    c[7], c[30] = c[3], c[3]
    want = [min(range(40), key=lambda k: (-round(float(x @ c[k] - c[k] @ c[k] / 2), 9), k)) for x in v]
    assert cluster.nearest(v, c).tolist() == want


def test_batches_choose_as_the_column_form_of_consistent_sampling(spark):
    rng = np.random.default_rng(2)
    rows = [(i, [(int(h), float(w)) for h, w in zip(rng.integers(0, WIDTH, i % 7), rng.choice([0.0, 0.5, 1.0, 3.0], i % 7), strict=True)]) for i in range(60)] + [(99, None)]
    df = spark.createDataFrame(rows, "id bigint, c array<struct<h: bigint, cnt: double>>")
    plain = {r.id: r.x for r in df.select("id", sketch.consistent_weighted_hash(F.col("c"), 6).alias("x")).collect()}
    assert {r.rec_id: r.sig for r in sketch.consistent_weighted_kernel(df, "id", "c", 6).collect()} == plain


def test_blocks_have_one_level_at_any_size(spark):
    rng = np.random.default_rng(5)
    df = spark.createDataFrame([(i, [float(x) for x in v]) for i, v in enumerate(rng.normal(size=(4_500, 2)).round(3))], "rec_id long, v array<double>")
    rows = lambda made: sorted((r.rec_id, r.cluster) for r in made.collect())
    assert rows(cluster.blocks(df, 1, 4_500, 1)) == rows(cluster.lloyd(df, 4_500, 1))


def test_nearest_of_many_close_centres():
    rng = np.random.default_rng(6)
    v = rng.normal(size=(300, 32)).round(6)
    c = np.concatenate([v[:100], v[:100], v[:100] + 1e-9, v[:100] + 3e-8, np.zeros((2, 32))])
    half = (c * c).sum(axis=1) / 2
    for scale in (1.0, 1e-4, 0.0):
        want = np.round((v * scale) @ c.T - half, 9).argmax(axis=1)
        assert cluster.nearest(v * scale, c).tolist() == want.tolist()


def test_clusters(spark):
    rng = np.random.default_rng(6)
    centres = rng.normal(size=(4, 6))
    rows = [(i, [float(x) for x in centres[i % 4] * 3 + rng.normal(size=6) * 0.05]) for i in range(80)]
    df = spark.createDataFrame(rows, "rec_id bigint, v array<double>")
    out = {r.rec_id: r.cluster for r in cluster.lloyd(df, 8, 6).collect()}
    assert set(out) == set(range(80)) and 4 <= len(set(out.values())) <= 8
    for c in set(out.values()):
        assert len({i % 4 for i, x in out.items() if x == c}) == 1
    assert cluster.clusters_for(1000, 20) == 50
    fine = {r.rec_id: r.cluster for r in cluster.two_level(df, 10, 80, 2).collect()}
    assert set(fine) == set(range(80))
    for c in set(fine.values()):
        assert len({i % 4 for i, x in fine.items() if x == c}) == 1
    library = {r.rec_id: r.cluster for r in cluster.library_kmeans(df, 4).collect()}
    assert len(set(library.values())) == 4 and all(len({i % 4 for i, x in library.items() if x == c}) == 1 for c in set(library.values()))


def test_tuning_over_seeds(spark):
    rng = np.random.default_rng(2)
    df = sets(spark, [s for _ in range(20) for s in near_pair(rng, 60, 10)])
    truth = spark.createDataFrame([(2 * i, 2 * i + 1) for i in range(20)], "id_lo bigint, id_hi bigint")
    rows = tuning.grid(df, truth, [(2, 8), (6, 2)], [1, 2, 3]).collect()
    by = {(r.k, r.l): r for r in rows}
    assert by[(2, 8)].recall >= by[(6, 2)].recall and by[(2, 8)].recall > 0.9


def test_choice_of_k_and_l_sees_one_half_and_keeps_the_budget(spark):
    rng = np.random.default_rng(3)
    df = sets(spark, [s for _ in range(20) for s in near_pair(rng, 60, 10)])
    truth = spark.createDataFrame([(2 * i, 2 * i + 1) for i in range(20)], "id_lo bigint, id_hi bigint")
    train, cells, seeds = F.col("id_lo") % 4 == 0, [(2, 1), (2, 8), (6, 2)], [1, 2_000]
    rows = {(r.k, r.l): r for r in tuning.choose_on_half(df, truth, train, cells, seeds, 1_000).collect()}
    assert sorted(rows) == sorted(cells) and [c for c, r in rows.items() if r.chosen] == [(2, 8)]
    for (k, tables), r in rows.items():
        found = [pair_set(pairs.from_signatures(df.select("rec_id", sketch.per_table_sketch(F.col("h"), k, tables, s).alias("sig")), "rec_id", F.col("sig"), k, tables)) for s in seeds]
        kept = lambda left: np.mean([sum((i, i + 1) in f for i in range(left, 40, 4)) / 10 for f in found])
        assert (r.n_pairs, r.train_recall, r.test_recall) == pytest.approx((np.mean([len(f) for f in found]), kept(0), kept(2)))
    assert not any(r.chosen for r in tuning.choose_on_half(df, truth, train, cells, seeds, -1).collect())
    tight = {(r.k, r.l): r.chosen for r in tuning.choose_on_half(df, truth, train, cells, seeds, int(rows[(2, 8)].n_pairs) - 1).collect()}
    assert not tight[(2, 8)] and sum(tight.values()) == 1


def test_every_vector_pair_of_a_label_comes_once(spark, monkeypatch):
    import __spark_entry__ as entry
    from linkblock.plans import operators as plans

    monkeypatch.setattr(plans, "_VECTORS", 20)
    by_label = {}
    for r in spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").collect():
        by_label.setdefault(r.label, []).append(r.vec_id)
    got = [(r.id_lo, r.id_hi) for r in entry.queries()["vector_inner"](spark, "/root/testdata/sf0.001").collect()]
    want = {(a, b) for label, ids in by_label.items() if label is not None for a in ids for b in ids if a < b}
    assert len(got) == len(want) and set(got) == want


def test_idf_pairs_of_short_copies_stay(spark):
    import __spark_entry__ as entry

    sf = "/root/testdata/sf0.01"
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    by_text = {}
    for i, t in docs.items():
        if t and len(t.split()) >= 10:
            by_text.setdefault(t, []).append(i)
    want = {(a, b) for ids in by_text.values() for a in ids for b in ids if a % 100 == 0 and a != b}
    got = {(r.query_id, r.rec_id): r.cosine for r in entry.queries()["idf_inner_docs"](spark, sf).collect()}
    assert want <= set(got) and all(got[p] > 0.999 for p in want)


@pytest.mark.parametrize("queries, dealt", [(10_000, 1 << 20), (2, 7)])
def test_inner_products_equal_brute_force(spark, monkeypatch, queries, dealt):
    """Queries against all rows: negative ids, a token of all rows, rows without tokens, queries in blocks."""
    monkeypatch.setattr(similarity, "QUERIES", queries)
    monkeypatch.setattr(similarity, "DEALT", dealt)
    rng = random.Random(5)
    bags = {i: {0: 1} | {rng.randrange(1, 40): rng.randrange(1, 4) for _ in range(rng.randrange(6))} for i in [*range(1, 60), -100, 0, 100, 200, 300, 700, 1 << 40]}
    bags |= {400: {}, 61: {}, 500: {0: 2}}
    df = Counter(t for b in bags.values() for t in b)
    n = df[0]  # the token that all rows with any have weighs nothing
    weight = {i: {t: c * math.log((n + 1) / (df[t] + 1)) for t, c in b.items()} for i, b in bags.items()}
    size = {i: math.sqrt(sum(x * x for x in w.values())) for i, w in weight.items()}
    want = {}
    for a in bags:
        for b in bags:
            if a % 100 == 0 and a != b and set(bags[a]) & set(bags[b]):
                dot = sum(weight[a][t] * weight[b].get(t, 0.0) for t in bags[a])
                want[a, b] = (round(dot, 6), round(dot / (size[a] * size[b]), 6) if size[a] * size[b] else None)
    rows = spark.createDataFrame([(i, list(b.items())) for i, b in bags.items()], "rec_id bigint, c array<struct<tok:bigint,cnt:int>>").repartition(3)
    found = similarity.inner_products(rows, n).collect()
    got = {(r.query_id, r.rec_id): (round(r.dot, 6), None if r.cosine is None else round(r.cosine, 6)) for r in found}
    assert len(found) == len(got) and got == want
    assert similarity.inner_products(rows.where("rec_id % 100 <> 0"), n).count() == similarity.inner_products(rows.limit(0), 0).count() == 0


def test_numpy_keys_of_tables_agree_where_the_sketch_does(spark):
    rng = np.random.default_rng(12)
    rows = [sorted({int(x) for x in rng.integers(0, 40, rng.integers(1, 9))}) for _ in range(60)] + [[0], [WIDTH - 1], [0, WIDTH - 1]]
    rows = [[x * 104_729_001 % WIDTH for x in r] for r in rows[:60]] + rows[60:]
    size, tok = np.array([len(r) for r in rows]), np.concatenate(rows)
    for k, tables, seed in ((2, 5, 500), (3, 6, 1500), (4, 4, 7)):
        df = spark.createDataFrame([(i, sorted(r)) for i, r in enumerate(rows)], "id int, h array<bigint>")
        want = {r.id: r.s for r in df.select("id", sketch.per_table_sketch(F.col("h"), k, tables, seed).alias("s")).collect()}
        got = sketch.per_table_keys(tok, size, k, tables, seed)
        for t in range(tables):
            by_value = {}
            for i in range(len(rows)):
                by_value.setdefault(tuple(want[i][t * k : t * k + k]), set()).add(int(got[t, i]))
            assert all(len(v) == 1 for v in by_value.values()) and len(set.union(*by_value.values())) == len(by_value)


def test_counting_pairs_over_runs_deals_sets_and_no_pairs(spark):
    """Keys of all tables before were dealt with each table of a record, and pairs to meet the truth."""
    df = sets(spark, [[i, i + 1, i + 2] for i in range(40)])
    truth = spark.createDataFrame([(i, i + 1, i % 2 == 0) for i in range(0, 40, 2)], "id_lo bigint, id_hi bigint, train boolean")
    plan = tuning.runs(df, truth, [(2, 4), (3, 2)], [1, 2])._jdf.queryExecution().executedPlan().toString()
    assert "first_table" in plan and "Generate posexplode" not in plan and "id_lo" in plan and not re.search(r"Exchange hashpartitioning\(id_lo#\d+L, id_hi", plan)


def test_pairs_travel_without_the_keys_of_other_tables(spark):
    """A row used to be dealt once a table with all keys before, half the square of the tables; now once a group with its own."""
    df = spark.createDataFrame([(i, [i // 2, i // 3, i // 5]) for i in range(60)], "id bigint, k array<bigint>")
    found = pairs.from_keys(df, "id", F.col("k"), chunk=25)[0]
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "posexplode" not in plan
    first = lambda a, b: next((t for t, d in enumerate((2, 3, 5)) if a // d == b // d), None)
    assert sorted(map(tuple, found.collect())) == [(a, b, first(a, b)) for a in range(60) for b in range(a + 1, 60) if first(a, b) is not None]


def test_long_runs_and_slabs_make_the_same_pairs(monkeypatch):
    from linkblock.operators import cells

    rng = np.random.default_rng(5)
    keys, sides = rng.integers(-3, 3, (4, 90)), (np.full(90, 2), rng.integers(0, 2, 90))
    for side in sides:
        want = {(a, b): t for t in reversed(range(4)) for a in range(90) for b in range(a + 1, 90) if keys[t, a] == keys[t, b] and (side[0] == 2 or side[a] != side[b])}
        for long, slab, entries in ((512, 1 << 18, 1 << 20), (2, 1, 1), (6, 7, 20)):
            monkeypatch.setattr(cells, "LONG", long), monkeypatch.setattr(cells, "SLAB", slab), monkeypatch.setattr(cells, "ENTRIES", entries)
            got = [((min(a, b), max(a, b)), t) for t, p, q in cells.first_pairs(keys, side) for a, b in zip(p.tolist(), q.tolist(), strict=True)]
            assert len(got) == len(want) and dict(got) == want


def test_rules_are_counted_as_their_pairs_are(spark):
    rng = random.Random(4)
    rows = [(i, *(rng.choice([0, 1, 2, None]) for _ in range(4))) for i in range(60)]
    df = spark.createDataFrame(rows, "id bigint, a int, b int, c int, d int")
    truth = spark.createDataFrame([(i, j) for i in range(60) for j in range(i + 1, 60, 3)], "id_lo bigint, id_hi bigint")
    named = {"one": rules.AllOf("a", "b"), "three": rules.AnyOf(rules.AllOf("a", "b"), "c", rules.AllOf("b", "d")), "none": rules.AllOf("a", "b", "c", "d"), "twice": rules.AnyOf(rules.AllOf("a", "b"), rules.AllOf("a", "d"), rules.AllOf("b", "d"))}
    true = pair_set(truth)
    for r in rules.counts_of_rules(df, "id", truth, named).collect():
        want = pair_set(rules.rule_pairs(df, "id", named.pop(r.method)))
        assert (r.n_pairs, r.n_hit) == (len(want), len(want & true))
    assert not named
    nothing = rules.counts_of_rules(df.limit(0), "id", truth, {"x": rules.AllOf("a")}).collect()
    assert [tuple(r) for r in nothing] == [("x", 0, 0)]


def test_comparisons_count_pairs_where_they_meet(spark):
    """Pairs used to be made and dealt again to meet the truth and be counted."""
    from linkblock.plans import sketches

    rng = np.random.default_rng(6)
    keyed = spark.createDataFrame([(i, [int(x) for x in rng.integers(0, 30, 4)]) for i in range(80)], "id bigint, ks array<bigint>")
    truth = spark.createDataFrame([(i, i + 1) for i in range(79)], "id_lo bigint, id_hi bigint")
    counts, sizes = sketches.by_keys("m", keyed, 4, truth, 80)
    assert not re.search(r"Exchange hashpartitioning\(id_lo#\d+L, id_hi", counts._jdf.queryExecution().executedPlan().toString())
    made = pair_set(pairs.from_keys(keyed, "id", F.col("ks"))[0])
    assert tuple(counts.first()) == ("m", len(made), len(made & pair_set(truth)))
    assert sizes.agg(F.sum("n")).first()[0] == 320
