"""Worked examples and identities of tokens, similarities and name distances."""

import math
import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from __spark_entry__ import queries
from linkblock.functions import hashing, names, similarity, tokens
from linkblock.functions.names import PRESETS, Weights


def one(spark, column, **values):
    row = spark.createDataFrame([tuple(values.values())], list(values)) if values else spark.range(1)
    return row.select(column.alias("x")).first().x


def test_toronto(spark):
    assert one(spark, tokens.char_grams(F.lit("TORONTO"), 2)) == ["TO", "OR", "RO", "ON", "NT", "TO"]
    assert {r.tok: r.cnt for r in one(spark, tokens.counts(tokens.char_grams(F.lit("TORONTO"), 2)))} == {"TO": 2, "OR": 1, "RO": 1, "ON": 1, "NT": 1}


@pytest.mark.parametrize("text", ["", "a", "ab"])
def test_short_strings_have_no_shingles(spark, text):
    assert one(spark, tokens.char_grams(F.lit(text), 3)) == []
    assert one(spark, tokens.word_grams(F.lit(text), 2)) == []


def test_words_and_grams(spark):
    assert one(spark, tokens.words(F.lit("Ab1, é-X!"))) == ["ab1", "é", "x"]
    assert one(spark, tokens.word_grams(F.lit("a b c d"), 3)) == ["a b c", "b c d"]
    assert one(spark, tokens.words(F.lit(None).cast("string"))) == []


def test_hash_mixing_stays_in_range_and_matches_its_text_form(spark):
    import duckdb

    for seed in (0, 1, 79, 543, 12_345):
        h = [0, 1, 2**31, 2**32 - 1, 123_456_789]
        got = [one(spark, hashing.mix(F.lit(x).cast("bigint"), seed)) for x in h]
        by_column = [one(spark, hashing.mix(F.lit(x).cast("bigint"), F.lit(seed))) for x in h]
        sql = [duckdb.sql(f"SELECT {hashing.mix_sql(f'{x}::BIGINT', str(seed))}").fetchall()[0][0] for x in h]
        assert got == by_column == sql and all(0 <= v < 2**32 for v in got)


def test_weighted_jaccard_examples(spark):
    long = spark.createDataFrame([(1, "a", 2), (1, "c", 1), (2, "a", 1), (2, "b", 1), (2, "c", 1)], "rec_id bigint, tok string, cnt bigint")
    row = similarity.all_weighted_jaccard(long).first()
    assert (row.sum_min, row.sum_max, row.jw) == (2, 4, 0.5)
    flat = long.withColumn("cnt", F.lit(1).cast("bigint"))
    assert similarity.all_weighted_jaccard(flat).first().jw == similarity.all_jaccard(flat).first().jaccard


def test_similar_pairs_equal_brute_force(spark):
    rng = random.Random(5)
    sets = [(i, sorted(rng.sample(range(40), rng.randrange(0, 12)))) for i in range(60)]
    sets += [(100 + i, sorted(set(s[:-1]))) for i, (_, s) in enumerate(sets) if s]
    df = spark.createDataFrame(sets, "id bigint, h array<bigint>")
    for t in (0.3, 0.5, 0.8, 1.0):
        want = {(a, b) for a, x in sets for b, y in sets if a < b and set(x) | set(y) and len(set(x) & set(y)) / len(set(x) | set(y)) >= t - 1e-12}
        assert {(r.id_lo, r.id_hi) for r in similarity.similar_pairs(df, "id", "h", t).collect()} == want


def test_similar_bags_equal_brute_force_in_any_order_of_tokens(spark, monkeypatch):
    rng = random.Random(9)
    bags = [(i, {rng.randrange(30): rng.randrange(1, 4) for _ in range(rng.randrange(0, 9))}) for i in range(50)]
    bags += [(100 + i, {**c, 99: 1}) for i, c in bags]
    df = spark.createDataFrame([(i, list(c.items())) for i, c in bags], "id bigint, c array<struct<tok: bigint, cnt: int>>")
    for t, hot in ((0.3, 1_000_000), (0.5, 3), (0.5, 0)):
        monkeypatch.setattr(similarity, "HOT", hot)
        want = {}
        for a, x in bags:
            for b, y in bags:
                low, high = (sum(f(x.get(k, 0), y.get(k, 0)) for k in x | y) for f in (min, max))
                if a < b and high and low >= t * high - 1e-12:
                    want[a, b] = (low, high)
        assert {(r.id_lo, r.id_hi): (r.sum_min, r.sum_max) for r in similarity.similar_bags(df, "id", "c", t).collect()} == want


def test_similar_pairs_in_small_pieces_and_blocks(spark, monkeypatch):
    for name, value in (("PIECES", 3), ("SLICE", 40), ("MEETINGS", 8), ("COMPARED", 64), ("DEALT", 100), ("CHUNK", 90), ("BROADCAST_IDS", 0)):
        monkeypatch.setattr(similarity, name, value)
    rng = random.Random(11)
    near = [sorted({t for t in range(50) if rng.random() < 0.8} | {rng.randrange(100, 10_000)}) for _ in range(25)]
    sets = list(enumerate(near + near[:4] + [rng.sample(range(-40, 60), rng.randrange(0, 40)) for _ in range(30)]))
    df = spark.createDataFrame(sets, "id bigint, h array<bigint>")
    want = {(a, b): len(set(x) & set(y)) for a, x in sets for b, y in sets if a < b and len(set(x) & set(y)) >= 0.3 * len(set(x) | set(y)) > 0}
    found = similarity.similar_pairs(df, "id", "h", 0.3).collect()
    assert len(found) == len(want) and {(r.id_lo, r.id_hi): r.n_common for r in found} == want


def test_pairs_of_near_copies_are_not_dealt():
    rng = np.random.default_rng(3)
    base = rng.integers(-(2**62), 2**62, 400)
    sets = [np.delete(base, rng.choice(400, 4)) for _ in range(300)] + [rng.integers(-(2**62), 2**62, 300) for _ in range(100)]
    rows = pa.RecordBatch.from_arrays([pa.array(range(400)), pa.array(sets)], names=["id", "toks"])
    none = np.zeros(0, np.int64)
    packed = pa.Table.from_batches(similarity._prefixes(none, none, 0.3, 4)(iter([rows]))).sort_by("piece")
    assert packed.nbytes < 5 * sum(map(len, sets))
    told = sum(b.num_rows for b in similarity._meetings(4, 0.3)(iter(packed.combine_chunks().to_batches())))
    assert 0 < told < 4 * 50 * 49 / 2


def test_letter_costs():
    for w in PRESETS.values():
        for a in names.letters():
            assert names.replacement_cost(a, a, w) == 0
            for b in names.letters():
                cost = names.replacement_cost(a, b, w)
                assert 0 <= cost <= 1 and cost == names.replacement_cost(b, a, w)
    assert math.isclose(names.replacement_cost("ب", "ت", Weights(1, 1, 1)), names.replacement_cost("ب", "ت", Weights(1 / 3, 1 / 3, 1 / 3)))
    assert names.key_likeness("ض", "ص") == 1 - 1 / 12 and names.key_likeness("ض", "ض") == 1
    assert names.replacement_cost("ت", "ط", PRESETS["phonetic"]) < names.replacement_cost("ت", "م", PRESETS["phonetic"])
    with pytest.raises(ValueError):
        Weights(0, 0, 0)


def test_name_cost_forms_agree(spark):
    rng = random.Random(2)
    letters = names.letters()
    word = lambda: "".join(rng.choice(letters) for _ in range(rng.randrange(0, 9)))
    rows = [(word(), word()) for _ in range(60)] + [("kitten", "sitting"), ("", ""), (None, "a"), ("بتث", "بتن")]
    df = spark.createDataFrame(rows, "a string, b string")
    for w in (PRESETS["equal"], PRESETS["keyboard"]):
        got = df.select("a", "b", names.name_cost(F.col("a"), F.col("b"), w).alias("x"), names.name_cost_udf(w)("a", "b").alias("y")).collect()
        for r in got:
            want = None if r.a is None or r.b is None else names.cost_by_hand(r.a, r.b, w)
            assert (r.x is None and r.y is None) if want is None else abs(r.x - want) < 1e-9 and abs(r.y - want) < 1e-9
    assert one(spark, names.edit_distance(F.lit("kitten"), F.lit("sitting"))) == 3
    assert one(spark, names.name_cost(F.lit("kitten"), F.lit("sitting"), PRESETS["equal"], normalize=False)) == 3


def test_batches_of_names_equal_the_table_by_hand():
    rng = random.Random(8)
    word = lambda most: "".join(rng.choice([*names.letters(), "x", "y"]) for _ in range(rng.randrange(0, most)))
    rows = [(word(9), word(9)) for _ in range(300)] + [("", "بت"), ("", ""), (word(90) + "x" * 70, word(90)), ("😀ب", "ب")]
    a, b = (pa.array(x) for x in zip(*rows, strict=True))
    for w, normalize in ((PRESETS["equal"], True), (PRESETS["phonetic"], False)):
        assert names.batch_costs(a, b, w, 1.0, normalize).tolist() == [names.cost_by_hand(x, y, w, 1.0, normalize) for x, y in rows]


def test_pairs_carry_their_names_without_a_shuffle_of_pairs(spark, sf):
    plan = queries()["name_cost_pairs"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    # Each of the three rules deals both its sides by the fields of the rule; no exchange deals pairs.
    assert not any("id_lo" in x or "given_lo" in x for x in plan.splitlines() if "Exchange" in x)


def test_refine_keeps_cheap_pairs_and_is_a_subset(spark):
    df = spark.createDataFrame([(1, "بتث", "جح"), (2, "بتن", "جح"), (3, "ممم", "كك"), (4, "بتث", None)], "id bigint, given string, family string")
    pairs = spark.createDataFrame([(1, 2), (1, 3), (1, 4)], "id_lo bigint, id_hi bigint")
    kept = {(r.id_lo, r.id_hi) for r in names.refine_pairs(pairs, df, "id", ["given", "family"], PRESETS["equal"], 0.25).collect()}
    assert kept == {(1, 2), (1, 4)}
    for how in ("max", "min"):
        assert names.refine_pairs(pairs, df, "id", ["given", "family"], PRESETS["equal"], 0.25, how).count() >= 1


def test_sound_code(spark):
    assert one(spark, names.sound_code(F.lit("بب"))) == "1"
    assert one(spark, names.sound_code(F.lit("تد"))) == "3"
    assert one(spark, names.sound_code(F.lit("Robert"), "latin")) == "R163"
