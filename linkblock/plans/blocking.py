"""Workloads on the person reports: rules, names, quality, blocks, linkage and population estimates."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkblock.functions import names
from linkblock.functions.names import PRESETS
from linkblock.functions.hashing import WIDTH, mix_sql
from linkblock.operators import bands, blocks, capture, cluster, linkage, measures, pairs, rules, tuning
from linkblock.operators.sketch import classic_minhash, consistent_weighted_kernel, expand, per_table_kernel, per_table_sketch, quantize, sample_tokens
from linkblock.functions.tokens import distinct_hashes, report_tokens
from linkblock.plans import query
from linkblock.plans import sqltext as S
from linkblock.plans.sketches import _cws_u as cws_u
from linkblock.plans.sketches import by_blocks, by_fields, by_keys, by_signature, rated
from linkblock.runtime import settle, spread
from linkblock.sources.tables import clean, load, report_truth, reports

K, TABLES = 3, 30
SCHEMES = (("date+place", ("event_date", "place")), ("given", ("given",)), ("family+place", ("family", "place")))
UNION = rules.AnyOf(rules.AllOf("event_date", "place"), "given", rules.AllOf("family", "place"))
FIELDS = {"all_fields": ["given", "family", "event_date", "place"], "date_place": ["event_date", "place"], "family_place": ["family", "place"], "given": ["given"], "place": ["place"]}
RULES = [("event_date", "place"), ("family", "place"), ("given",), ("given", "place"), ("place",)]
COSTS = (0.1, 0.25, 0.4)
NAMES = ["given", "family"]
_WITH = f"WITH {S.reports()}"
_FAMILY = "nullif(family, '')"
_KNOWN = f"rep AS (SELECT * REPLACE ({_FAMILY} AS family) FROM reports)"
_UNION_SQL = f"""{_KNOWN},
joined AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi, coalesce(a.event_date = b.event_date AND a.place = b.place, false) AS r0, coalesce(a.given = b.given, false) AS r1, coalesce(a.family = b.family AND a.place = b.place, false) AS r2
  FROM rep a JOIN rep b ON a.rec_id < b.rec_id),
union_pairs AS (SELECT id_lo, id_hi, r0, r1, r2 FROM joined WHERE r0 OR r1 OR r2)"""
_NAMED = f"{_UNION_SQL}, named_pairs AS (SELECT id_lo, id_hi, x.given AS given_lo, y.given AS given_hi, x.family AS family_lo, y.family AS family_hi FROM union_pairs JOIN rep x ON id_lo = x.rec_id JOIN rep y ON id_hi = y.rec_id)"


def people(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reports with blank family names as missing."""
    return clean(reports(spark, sf_dir), "family")


def _exact(keys: list[str], table: str) -> str:
    return f"SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM {table} a JOIN {table} b ON a.rec_id < b.rec_id AND " + " AND ".join(f"a.{k} = b.{k}" for k in keys)


@query(f"{_WITH}, {_KNOWN} SELECT given, family, event_date, place, count(*) AS n FROM rep WHERE given IS NOT NULL AND family IS NOT NULL AND event_date IS NOT NULL AND place IS NOT NULL GROUP BY ALL")
def trad_blocks_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir)
    made = rules.exact_field_blocks(df, "rec_id", FIELDS["all_fields"])
    return made.join(df, "rec_id").groupBy("block_id").agg(*(F.first(c).alias(c) for c in FIELDS["all_fields"]), F.count("*").alias("n")).drop("block_id")


@query("SELECT (year(o_orderdate) * 100 + month(o_orderdate))::INT AS order_month, o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ALL")
def trad_blocks_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = load(spark, sf_dir, "orders").select("o_orderkey", rules.part("o_orderdate", "month").alias("order_month"), "o_orderstatus", "o_orderpriority")
    return df.groupBy("order_month", "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


def _union_all(parts: list[str]) -> str:
    return " UNION ALL ".join(f"({p})" for p in parts)


@query(f"{_WITH}, {_KNOWN}, " + ", ".join(f"p_{m} AS ({_exact(f, 'rep')})" for m, f in FIELDS.items()) + " " + _union_all([S.quality(m, f"p_{m}", "truth", "SELECT count(*) FROM reports") for m in FIELDS]))
def trad_quality_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir)
    truth = report_truth(df)
    return reduce(DataFrame.unionByName, (measures.partition_quality(rules.exact_field_blocks(df, "rec_id", f, "singleton"), truth, m) for m, f in FIELDS.items()))


@query(f"{_WITH}, {_KNOWN} {_exact(['event_date', 'place'], 'rep')}")
def conj_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules.rule_pairs(people(spark, sf_dir), "rec_id", rules.AllOf("event_date", "place")).drop("first_rule")


@query(f"{_WITH}, {_UNION_SQL} SELECT id_lo, id_hi, CASE WHEN r0 THEN 0 WHEN r1 THEN 1 ELSE 2 END::INT AS first_rule FROM union_pairs")
def dnf_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules.rule_pairs(people(spark, sf_dir), "rec_id", UNION)


@query(f"""{_WITH}, {_KNOWN} SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM rep a JOIN rep b ON a.rec_id < b.rec_id
WHERE (a.event_date = b.event_date OR a.given = b.given) AND (a.given = b.given OR a.place = b.place)""")
def cnf_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules.rule_pairs(people(spark, sf_dir), "rec_id", rules.AllOf(rules.AnyOf("event_date", "given"), rules.AnyOf("given", "place"))).drop("first_rule")


@query(f"{_WITH} SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM reports a JOIN reports b ON a.rec_id < b.rec_id AND year(a.event_date) = year(b.event_date) AND month(a.event_date) = month(b.event_date) AND a.place = b.place AND substr(a.given, 1, 2) = substr(b.given, 1, 2)")
def date_part_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir).select("rec_id", rules.part("event_date", "month").alias("month"), "place", rules.prefix("given", 2).alias("start"))
    return rules.rule_pairs(df, "rec_id", rules.AllOf("month", "place", "start")).drop("first_rule")


def _rule_name(r: tuple[str, ...]) -> str:
    return "+".join(r)


@query(f"{_WITH}, {_KNOWN}, " + ", ".join(f"p{i} AS ({_exact(list(r), 'rep')})" for i, r in enumerate(RULES))
       + " SELECT method AS rule, n_pairs, n_hit, recall, rr, prec FROM (" + _union_all([S.quality(_rule_name(r), f"p{i}", "truth", "SELECT count(*) FROM reports") for i, r in enumerate(RULES)]) + ")")
def rule_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All rules at once: pairs by block sizes, hits by joining the truth to both records."""
    df = people(spark, sf_dir)
    truth = report_truth(df)
    totals = df.agg(F.count("*").alias("n_rows")).join(F.broadcast(truth.agg(F.count("*").alias("n_true"))))
    hits = rules.truth_hits(df, "rec_id", truth, RULES).groupBy("rule").agg(F.count("*").alias("n_hit"))
    return rules.estimate_pairs(df, RULES).join(hits, "rule", "left").join(F.broadcast(totals)).select(
        "rule", "n_pairs", F.coalesce("n_hit", F.lit(0)).alias("n_hit"), F.round(measures.recall(F.coalesce("n_hit", F.lit(0)), F.col("n_true")), 6).alias("recall"),
        F.round(measures.reduction_ratio(F.col("n_pairs"), F.col("n_rows")), 6).alias("rr"), F.round(measures.precision(F.coalesce("n_hit", F.lit(0)), F.col("n_pairs")), 6).alias("prec"),
    )


_HIT = ", ".join(f"coalesce({' AND '.join(f'x.{f} = y.{f}' for f in r)}, false) AS h{i}" for i, r in enumerate(RULES))
_COST = " UNION ALL ".join(f"SELECT {i} AS i, '{_rule_name(r)}' AS rule, count(*) AS c FROM ({_exact(list(r), 'rep')})" for i, r in enumerate(RULES))
_GAIN = " UNION ALL ".join(f"SELECT {i} AS i, '{_rule_name(r)}' AS rule, id_lo, id_hi FROM hits WHERE h{i}" for i, r in enumerate(RULES))


def _greedy_sql(steps: int, budget: str) -> str:
    out = [f"{_WITH}, {_KNOWN}, hits AS (SELECT id_lo, id_hi, {_HIT} FROM truth JOIN rep x ON id_lo = x.rec_id JOIN rep y ON id_hi = y.rec_id), costs AS ({_COST}), kept AS ({_GAIN}), left0 AS (SELECT * FROM kept), spent0 AS (SELECT 0 AS s), lim AS ({budget})"]
    for i in range(steps):
        out.append(f"""g{i} AS (SELECT k.rule, count(*) AS gained, any_value(c) AS c FROM left{i} k JOIN costs USING (rule) GROUP BY k.rule HAVING any_value(c) + (SELECT s FROM spent{i}) <= (SELECT b FROM lim)),
pick{i} AS (SELECT {i + 1} AS step, rule, gained, c AS added_pairs FROM g{i} ORDER BY gained DESC, rule LIMIT 1),
spent{i + 1} AS (SELECT (SELECT s FROM spent{i}) + coalesce((SELECT added_pairs FROM pick{i}), 0) AS s),
left{i + 1} AS (SELECT l.* FROM left{i} l WHERE NOT EXISTS (SELECT 1 FROM kept k WHERE k.rule = (SELECT rule FROM pick{i}) AND k.id_lo = l.id_lo AND k.id_hi = l.id_hi))""")
    return ", ".join(out) + " " + " UNION ALL ".join(f"SELECT step::INT AS step, rule, gained, added_pairs FROM pick{i}" for i in range(steps))


@query(_greedy_sql(3, "SELECT 2 * count(*) AS b FROM reports"))
def rule_search_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pair budget: two pairs a record."""
    df = people(spark, sf_dir)
    found = rules.search_schemes(df, "rec_id", report_truth(df), RULES, 2 * df.count(), 3)
    return spark.createDataFrame(found, "step int, rule string, gained bigint, added_pairs bigint")


@query(f"{_WITH}, {_KNOWN}, hits AS (SELECT x.k, {_HIT} FROM truth JOIN rep x ON id_lo = x.rec_id JOIN rep y ON id_hi = y.rec_id), halves AS (SELECT *, {S.u32(chr(39) + 'half' + chr(39) + ' || k')} % 2 = 0 AS train FROM hits) "
       + " UNION ALL ".join(f"SELECT '{_rule_name(r)}' AS rule, round(sum((h{i} AND train)::INT) / sum(train::INT), 6) AS train_recall, round(sum((h{i} AND NOT train)::INT) / sum((NOT train)::INT), 6) AS test_recall FROM halves" for i, r in enumerate(RULES)))
def rule_holdout(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir)
    return rules.holdout_recall(df, "rec_id", "k", report_truth(df), RULES)


_KNOWN_FIELDS = "(given IS NOT NULL)::INT + (family IS NOT NULL)::INT + (event_date IS NOT NULL)::INT + (place IS NOT NULL)::INT"


@query(f"{_WITH}, {_KNOWN}, known AS (SELECT {_KNOWN_FIELDS} AS m, count(*) AS n FROM rep GROUP BY 1) SELECT r.m::INT AS m, pow(r.m, r.m)::DOUBLE AS lower_bound, coalesce(n, 0) AS n_reports FROM range(1, 9) r(m) LEFT JOIN known k ON k.m = r.m")
def rule_space(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ways to combine m fields, and how many reports have just m known fields to combine."""
    fields = ("given", "family", "event_date", "place")
    known = people(spark, sf_dir).groupBy(sum((F.col(f).isNotNull().cast("int") for f in fields[1:]), F.col(fields[0]).isNotNull().cast("int")).alias("m")).agg(F.count("*").alias("n"))
    every = spark.range(1, 9).select(F.col("id").cast("int").alias("m"))
    return every.join(known, "m", "left").select("m", rules.scheme_space_lower_bound(F.col("m").cast("double")).alias("lower_bound"), F.coalesce("n", F.lit(0)).alias("n_reports"))


_LETTERS_SQL = "letters AS (SELECT c, count(*) AS n FROM (SELECT unnest(string_split(given || family, '')) AS c FROM reports) WHERE c <> '' GROUP BY c)"


def letter_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(c, n): how often each letter comes in the names of the reports."""
    return reports(spark, sf_dir).select(F.explode(F.split(F.concat("given", "family"), "")).alias("c")).where("c <> ''").groupBy("c").agg(F.count("*").alias("n"))


def with_letters(pairs: DataFrame, counted: DataFrame) -> DataFrame:
    """Pairs (a, b) of letters with how often either comes: n_a, n_b."""
    for side in ("a", "b"):
        pairs = pairs.join(counted.select(F.col("c").alias(side), F.col("n").alias(f"n_{side}")), side, "left").withColumn(f"n_{side}", F.coalesce(f"n_{side}", F.lit(0)))
    return pairs


def _with_letters_sql(pairs: str, value: str) -> str:
    return f"SELECT t.a, t.b, t.{value}, coalesce(x.n, 0) AS n_a, coalesce(y.n, 0) AS n_b FROM ({pairs}) t LEFT JOIN letters x ON x.c = t.a LEFT JOIN letters y ON y.c = t.b"


def _letter_query(preset: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        costs = names.letter_table(spark, PRESETS[preset]).select("a", "b", F.round("cost", 6).alias("cost"))
        return with_letters(costs, letter_counts(spark, sf_dir)).select("a", "b", "cost", "n_a", "n_b")

    query(f"{_WITH}, {_LETTERS_SQL} {_with_letters_sql(f'SELECT a, b, round(cost, 6)::DOUBLE AS cost FROM ({S.letter_costs(preset)})', 'cost')}", f"letter_costs_{preset}")(run)


for _preset in PRESETS:
    _letter_query(_preset)


_KEYS_SQL = "SELECT p.c AS a, q.c AS b, round(greatest(0, 1 - sqrt(pow(p.x - q.x, 2) + pow(p.y - q.y, 2)) / 12.0), 6)::DOUBLE AS s FROM p, p q"


@query(f"{_WITH}, {_LETTERS_SQL}, p(c, x, y) AS (VALUES " + ", ".join(f"('{c}', {x}, {y})" for c, (x, y) in names.key_places().items()) + f") {_with_letters_sql(_KEYS_SQL, 's')}")
def key_similarity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keyboard likeness of every two letters, and how often either comes in the names of the reports."""
    likeness = names.key_table(spark).select("a", "b", F.round("s", 6).alias("s"))
    return with_letters(likeness, letter_counts(spark, sf_dir)).select("a", "b", "s", "n_a", "n_b")


@query(f"WITH RECURSIVE {S.reports()}, {_NAMED}, {S.distances('named_pairs', 'given_lo', 'given_hi', None)} SELECT id_lo, id_hi, d::INT AS cost FROM dist")
def name_edit_distance(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir)
    found = rules.rule_pairs(df, "rec_id", UNION)
    given = lambda s: df.select(F.col("rec_id").alias(f"id_{s}"), F.col("given").alias(f"g_{s}"))
    return found.join(given("lo"), "id_lo").join(given("hi"), "id_hi").select("id_lo", "id_hi", names.edit_distance(F.col("g_lo"), F.col("g_hi")).alias("cost"))


def _both_names(preset: str, out: str) -> str:
    """CTEs up to out(id_lo, id_hi, cost): mean of the known names' costs by length."""
    return f"""lc_{out} AS ({S.letter_costs(preset)}), {S.distances('named_pairs', 'given_lo', 'given_hi', f'lc_{out}', f'dg_{out}')},
fam_{out} AS (SELECT * FROM named_pairs WHERE family_lo IS NOT NULL AND family_hi IS NOT NULL), {S.distances(f'fam_{out}', 'family_lo', 'family_hi', f'lc_{out}', f'df_{out}')},
{out} AS (SELECT n.id_lo, n.id_hi, CASE WHEN f.d IS NULL THEN g.d / greatest(length(given_lo), length(given_hi)) ELSE (g.d / greatest(length(given_lo), length(given_hi)) + f.d / greatest(length(family_lo), length(family_hi))) / 2 END AS cost
  FROM named_pairs n JOIN dg_{out} g ON n.id_lo = g.id_lo AND n.id_hi = g.id_hi LEFT JOIN df_{out} f ON n.id_lo = f.id_lo AND n.id_hi = f.id_hi)"""


def _costed(df: DataFrame, preset: str, max_cost: float) -> DataFrame:
    found = rules.rule_pairs(df, "rec_id", UNION, NAMES)
    return found.select("id_lo", "id_hi", names.pair_cost(NAMES, PRESETS[preset]).alias("cost")).where(F.col("cost") <= max_cost).withColumn("cost", F.round("cost", 6))


@query(f"WITH RECURSIVE {S.reports()}, {_NAMED}, {_both_names('equal', 'nc')} SELECT id_lo, id_hi, round(cost, 6) AS cost FROM nc")
def name_cost_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cost of every pair of the rules, none dropped."""
    return _costed(people(spark, sf_dir), "equal", 2.0)


@query(f"WITH RECURSIVE {S.reports()}, {_NAMED}, {_both_names('equal', 'nc')} SELECT id_lo, id_hi, round(cost, 6) AS cost FROM nc WHERE cost <= 0.25")
def dnf_plus_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _costed(people(spark, sf_dir), "equal", 0.25)


@query(f"WITH RECURSIVE {S.reports()}, {_NAMED}, {_both_names('equal', 'nc1')}, {_both_names('phonetic', 'nc2')} "
       + " UNION ALL ".join(
           f"SELECT '{p}' AS preset, {c}::DOUBLE AS max_cost, count(*) AS n_pairs, count(t.id_lo) AS n_hit, round(count(t.id_lo) / (SELECT count(*) FROM truth), 6) AS recall, round(count(t.id_lo) / nullif(count(*), 0), 6) AS prec FROM {t} n LEFT JOIN truth t ON n.id_lo = t.id_lo AND n.id_hi = t.id_hi WHERE round(n.cost, 6) <= {c}"
           for p, t in (("equal", "nc1"), ("phonetic", "nc2")) for c in COSTS))
def name_cost_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Presets and cut-offs over the same costed pairs."""
    df = people(spark, sf_dir)
    total = report_truth(df).agg(F.count("*").alias("n_true"))
    presets = ("equal", "phonetic")
    # Pairs carry their entities: a pair is true if these are the same, which needs no join.
    found = rules.rule_pairs(df, "rec_id", UNION, [*NAMES, "k"])
    costed = found.select((F.col("k_lo") == F.col("k_hi")).alias("t"), *(F.round(names.pair_cost(NAMES, PRESETS[p]), 6).alias(p) for p in presets))
    cells = [(p, c, F.col(p) <= c) for p in presets for c in COSTS]
    row = costed.agg(*(x for i, (_, _, kept) in enumerate(cells) for x in (F.count_if(kept).alias(f"n{i}"), F.count_if(kept & F.col("t")).alias(f"h{i}"))))
    grid = F.array(*(F.struct(F.lit(p).alias("preset"), F.lit(c).alias("max_cost"), F.col(f"n{i}").alias("n_pairs"), F.col(f"h{i}").alias("n_hit")) for i, (p, c, _) in enumerate(cells)))
    return row.select(F.explode(grid).alias("e")).select("e.*").join(F.broadcast(total)).select(
        "preset", "max_cost", "n_pairs", "n_hit", F.round(measures.recall(F.col("n_hit"), F.col("n_true")), 6).alias("recall"), F.round(measures.precision(F.col("n_hit"), F.col("n_pairs")), 6).alias("prec")
    )


_FRM, _TO = "".join(g for g, _ in names.SOUND_CLASSES), "".join(d * len(g) for g, d in names.SOUND_CLASSES)
_SILENT = "".join(sorted(set(names.letters()) - set(_FRM)))


@query(f"""{_WITH}, coded AS (SELECT rec_id, translate(given, '{_FRM}{_SILENT}', '{_TO}') AS c FROM reports),
chars AS (SELECT rec_id, substr(c, i::INT, 1) AS x, lag(substr(c, i::INT, 1)) OVER (PARTITION BY rec_id ORDER BY i) AS y, i FROM (SELECT rec_id, c, unnest(range(1, length(c) + 1)) AS i FROM coded)),
keys AS (SELECT rec_id, string_agg(x, '' ORDER BY i) AS code FROM chars WHERE y IS NULL OR x <> y GROUP BY rec_id)
SELECT coalesce(code, '') AS code, count(*) AS n FROM coded LEFT JOIN keys USING (rec_id) GROUP BY 1""")
def sound_code_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return people(spark, sf_dir).groupBy(names.sound_code(F.col("given")).alias("code")).agg(F.count("*").alias("n"))


def report_signatures(df: DataFrame) -> DataFrame:
    return df.select("rec_id", distinct_hashes(report_tokens()).alias("h")).select("rec_id", per_table_sketch(F.col("h"), K, TABLES).alias("sig"))


_RSKETCH = f"{S.reports()}, {S.report_toks()}, {S.per_table(K, TABLES, 'rtoks')}, {S.band_keys(K, tables=TABLES)}, {S.band_pairs()}"


@query(f"WITH {_RSKETCH} SELECT id_lo, id_hi, first_table::INT AS first_table FROM band_pairs")
def band_pairs_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs.from_signatures(report_signatures(reports(spark, sf_dir)), "rec_id", F.col("sig"), K, TABLES)


_BLOCKS = f"{_KNOWN}, place_date AS (SELECT list_sort(list(rec_id)) AS ids FROM rep WHERE event_date IS NOT NULL GROUP BY event_date, place), sized AS (SELECT len(ids) AS b FROM place_date)"
_PLACE = "by_place AS (SELECT count(*) AS b FROM reports GROUP BY place)"


def _profile_sql(method: str, table: str) -> str:
    return f"SELECT '{method}' AS method, count(*) AS n_blocks, round(avg(b), 6) AS mean, quantile_cont(b, 0.5)::DOUBLE AS p50, quantile_cont(b, 0.99)::DOUBLE AS p99, max(b) AS max, round(max(b * (b - 1) // 2) / nullif(sum(b * (b - 1) // 2), 0), 6) AS top_share FROM {table}"


@query(f"{_WITH}, {_BLOCKS}, {_PLACE} {_profile_sql('date_place', 'sized')} UNION ALL {_profile_sql('place', 'by_place')}")
def block_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir)
    return measures.block_profile(rules.exact_field_blocks(df, "rec_id", ["event_date", "place"]), "date_place").unionByName(measures.block_profile(rules.exact_field_blocks(df, "rec_id", ["place"]), "place"))


def _sketch_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = bands.bucketize(report_signatures(reports(spark, sf_dir)), "rec_id", F.col("sig"), K, TABLES)
    sizes = b.groupBy("table_no", "bucket_key").agg(F.count("*").alias("n")).where("n > 1")
    return b.join(sizes, ["table_no", "bucket_key"], "left_semi").select(F.xxhash64("table_no", "bucket_key").alias("block_id"), "rec_id")


@query(f"WITH {_RSKETCH}, full_buckets AS (SELECT table_no, key FROM bands GROUP BY 1, 2 HAVING count(*) > 1), per AS (SELECT rec_id, count(*) AS c FROM bands JOIN full_buckets USING (table_no, key) GROUP BY rec_id) SELECT c AS blocks_per_record, count(*) AS n FROM per GROUP BY c")
def block_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """In how many buckets of two or more records the records are."""
    return blocks.overlap(_sketch_buckets(spark, sf_dir))


@query(f"{_WITH}, sized AS (SELECT place, count(*) AS b FROM reports GROUP BY place) SELECT r.place, (CASE WHEN b > 50 THEN month(event_date) ELSE 0 END)::BIGINT AS sub, count(*) AS n FROM reports r JOIN sized s ON r.place = s.place WHERE event_date IS NOT NULL GROUP BY ALL")
def split_large_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir)
    parts = blocks.split_large(df.select(F.col("place").alias("block_id"), "rec_id"), 50, df.select("rec_id", F.month("event_date").alias("sub_key")))
    return parts.join(df.where("event_date IS NOT NULL").select("rec_id"), "rec_id").groupBy(F.col("block_id").alias("place"), "sub").agg(F.count("*").alias("n"))


_MATCH = f"""{_KNOWN}, dp AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM rep a JOIN rep b ON a.rec_id < b.rec_id AND a.event_date = b.event_date AND a.place = b.place)"""
_REACH = """edge AS (SELECT id_lo AS x, id_hi AS y FROM {pairs} UNION SELECT id_hi, id_lo FROM {pairs}),
reach AS (SELECT rec_id AS x, rec_id AS y FROM reports UNION SELECT r.x, e.y FROM reach r JOIN edge e ON r.y = e.x),
comp AS (SELECT x AS rec_id, min(y) AS component FROM reach GROUP BY x)"""


@query(f"WITH RECURSIVE {S.reports()}, {_MATCH}, {_REACH.format(pairs='dp')} SELECT rec_id, component FROM comp")
def cover_to_partition(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir)
    return blocks.to_partition(df, rules.rule_pairs(df, "rec_id", rules.AllOf("event_date", "place")))


@query(f"{_WITH}, {_BLOCKS} SELECT 'date_place' AS method, round(coalesce(sum(b), 0) / 500 * 12.0, 6)::DOUBLE AS hours_low, round(coalesce(sum(b), 0) / 500 * 24.0, 6)::DOUBLE AS hours_high FROM sized WHERE b > 1")
def linkage_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linkage.linkage_hours(rules.exact_field_blocks(people(spark, sf_dir), "rec_id", ["event_date", "place"]), "date_place")


_AGREE = " + ".join(f"coalesce((x.{f} = y.{f})::INT, 0)" for f in ("given", "family", "event_date", "place"))
_SCORED = f"{_UNION_SQL}, matched AS (SELECT id_lo, id_hi FROM union_pairs JOIN rep x ON id_lo = x.rec_id JOIN rep y ON id_hi = y.rec_id WHERE {_AGREE} >= 3)"


def linked(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(reports, their components) after matching pairs of the rules on three of four fields."""
    df = people(spark, sf_dir)
    scored = linkage.score_pairs(rules.rule_pairs(df, "rec_id", UNION), df, "rec_id", ["given", "family", "event_date", "place"], 3)
    return df, linkage.entities(df, scored)


@query(f"{_WITH}, {_UNION_SQL} SELECT id_lo, id_hi, ({_AGREE})::INT AS agree, ({_AGREE}) >= 3 AS match FROM union_pairs JOIN rep x ON id_lo = x.rec_id JOIN rep y ON id_hi = y.rec_id")
def score_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = people(spark, sf_dir)
    return linkage.score_pairs(rules.rule_pairs(df, "rec_id", UNION), df, "rec_id", ["given", "family", "event_date", "place"], 3)


@query(f"WITH RECURSIVE {S.reports()}, {_SCORED}, {_REACH.format(pairs='matched')} SELECT (SELECT count(*) FROM reports) AS n_records, (SELECT count(DISTINCT component) FROM comp) AS n_entities, (SELECT count(DISTINCT k) FROM reports) AS n_true")
def unique_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, found = linked(spark, sf_dir)
    return df.join(found, "rec_id").agg(F.count("*").alias("n_records"), F.count_distinct("component").alias("n_entities"), F.count_distinct("k").alias("n_true"))


_HISTORY = "seen AS (SELECT component, max((list = 'A')::INT) AS in_a, max((list = 'B')::INT) AS in_b, max((list = 'C')::INT) AS in_c FROM comp JOIN reports USING (rec_id) GROUP BY component)"


def _history(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, found = linked(spark, sf_dir)
    return capture.histories(df.join(found, "rec_id"), "component", "list", ["A", "B", "C"])


@query(f"WITH RECURSIVE {S.reports()}, {_SCORED}, {_REACH.format(pairs='matched')}, {_HISTORY} SELECT in_a, in_b, in_c, count(*) AS n FROM seen GROUP BY ALL")
def capture_histories(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _history(spark, sf_dir)


@query(f"""WITH RECURSIVE {S.reports()}, {_SCORED}, {_REACH.format(pairs='matched')}, {_HISTORY}, c AS (SELECT sum(in_a)::BIGINT AS n1, sum(in_b)::BIGINT AS n2, sum(in_a * in_b)::BIGINT AS m FROM seen)
SELECT n1, n2, m, round((n1 + 1) * (n2 + 1) / (m + 1) - 1, 4) AS est, round(sqrt((n1 + 1)::DOUBLE * (n2 + 1) * (n1 - m) * (n2 - m) / (pow(m + 1, 2) * (m + 2))), 4) AS se FROM c""")
def two_list_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return capture.two_list(_history(spark, sf_dir), "in_a", "in_b")


@query()
def three_list_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Independence and one-interaction models, beside the number of people there are."""
    hist = _history(spark, sf_dir)
    truth = load(spark, sf_dir, "customer").count()
    models = (("independent", ()), ("a:b", (("A", "B"),)), ("a:c", (("A", "C"),)), ("b:c", (("B", "C"),)))
    rows = [(name, *map(lambda x: round(x, 4), capture.log_linear(hist, ["A", "B", "C"], p)), truth) for name, p in models]
    return spark.createDataFrame(rows, "model string, est double, se double, people bigint")


#: Step to which idf weights are rounded before their unary expansion.
DELTA = 0.5


def weighted_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(rec_id, c): tagged tokens of each report with their idf as weight, sorted by token."""
    sets = reports(spark, sf_dir).select("rec_id", distinct_hashes(report_tokens()).alias("h"))
    long = sets.select("rec_id", F.explode("h").alias("h"))
    idf = long.groupBy("h").agg(F.count("*").alias("df"))
    total = sets.agg(F.count("*").alias("n"))
    weighed = long.join(idf, "h").join(F.broadcast(total)).select("rec_id", "h", F.round(F.log((F.col("n") + 1) / (F.col("df") + 1)), 6).alias("cnt"))
    return weighed.groupBy("rec_id").agg(F.array_sort(F.collect_list(F.struct("h", "cnt"))).alias("c"))


_UNITS = f"({mix_sql('h', '31')} / {float(WIDTH)})"
_RWEIGHTS = f"""rw AS (SELECT rec_id, h, round(ln(((SELECT count(*) FROM reports) + 1) / (df + 1)), 6) AS cnt FROM rtoks JOIN (SELECT h, count(*) AS df FROM rtoks GROUP BY h) USING (h)),
rkept AS (SELECT rec_id, h FROM rw WHERE cnt / (SELECT max(cnt) FROM rw) > {_UNITS}),
rcopies AS (SELECT DISTINCT rec_id, {mix_sql('h', 'j + 900')} AS h FROM (SELECT rec_id, h, unnest(range(1, round(cnt / {DELTA})::INT + 1)) AS j FROM rw)), rproj AS (SELECT rec_id, h, cnt AS w FROM rw)"""


@query(f"WITH {S.reports()}, {S.report_toks()}, {_RWEIGHTS} SELECT rec_id, count(*) AS n, sum(round(cnt / {DELTA})::INT)::BIGINT AS copies, round(max(abs(round(cnt / {DELTA}) * {DELTA} - cnt)), 6) AS off FROM rw GROUP BY rec_id")
def quantized_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights as whole multiples of DELTA: how many copies that makes, and the furthest that one is off (at most half a step)."""
    e = weighted_tokens(spark, sf_dir).select("rec_id", F.explode("c").alias("e")).select("rec_id", "e.cnt", quantize(F.col("e.cnt"), DELTA).alias("i"))
    return e.groupBy("rec_id").agg(F.count("*").alias("n"), F.sum("i").cast("bigint").alias("copies"), F.round(F.max(F.abs(F.col("i") * DELTA - F.col("cnt"))), 6).alias("off"))


def _rsketch(source: str, tag: str) -> str:
    return f"{S.per_table(K, TABLES, source, f'filled_{tag}')}, {S.band_keys(K, f'filled_{tag}', f'bands_{tag}', tables=TABLES)}, {S.band_pairs(f'bands_{tag}', f'pairs_{tag}')}"


_RCLASSIC = f"rmh AS (SELECT rec_id, s AS pos, min({mix_sql('h', 's')}) AS val FROM rtoks, range({K * TABLES}) r(s) GROUP BY 1, 2), bands_m AS (SELECT rec_id, pos // {K} AS table_no, string_agg(val::VARCHAR, '-' ORDER BY pos) AS key FROM rmh GROUP BY 1, 2), {S.band_pairs('bands_m', 'pairs_m')}"
_RCWS = f"""draws AS (SELECT rec_id, pos, h, cnt, -ln({cws_u(0)} * {cws_u(1)}) AS r, -ln({cws_u(2)} * {cws_u(3)}) AS c, {cws_u(4)} AS beta FROM rw, range({K * TABLES}) p(pos) WHERE cnt > 0),
levels AS (SELECT *, floor(ln(cnt) / r + beta)::BIGINT AS t FROM draws),
chosen AS (SELECT rec_id, pos, arg_min(h * 4096 + ((t % 4096) + 4096) % 4096, ln(c) - r * (t - beta) - r) AS val FROM levels GROUP BY 1, 2),
bands_c AS (SELECT rec_id, pos // {K} AS table_no, string_agg(val::VARCHAR, '-' ORDER BY pos) AS key FROM chosen GROUP BY 1, 2), {S.band_pairs('bands_c', 'pairs_c')}"""
_NAMES_SQL = f"{_NAMED}, {_both_names('equal', 'nc')}, p_names AS (SELECT id_lo, id_hi FROM nc WHERE round(cost, 6) <= 0.25)"
_MOST = lambda *f: f"(SELECT max(n) FROM (SELECT count(*) AS n FROM rep WHERE {' AND '.join(f'{x} IS NOT NULL' for x in f)} GROUP BY {', '.join(f)}))"
_MOST_IN = lambda t, by="table_no, key": f"(SELECT max(n) FROM (SELECT count(*) AS n FROM {t} GROUP BY {by}))"
_UNION_MOST = f"greatest({_MOST('event_date', 'place')}, {_MOST('given')}, {_MOST('family', 'place')})"
_RROWS = (
    ("exact_fields", "p_exact", _MOST(*FIELDS["all_fields"])), ("date_place", "p_dp", _MOST("event_date", "place")), ("rule_union", "union_pairs", _UNION_MOST), ("rule_union_names", "p_names", _UNION_MOST),
    ("projection_kmeans", "cluster_pairs", _MOST_IN("clusters", "k")), ("classic_minhash", "pairs_m", _MOST_IN("bands_m")), ("sketch", "pairs_s", _MOST_IN("bands_s")),
    ("weighted_sampled", "pairs_k", _MOST_IN("bands_k")), ("weighted_expanded", "pairs_x", _MOST_IN("bands_x")), ("consistent_sampling", "pairs_c", _MOST_IN("bands_c")),
)


@query(f"WITH RECURSIVE {S.reports()}, {S.report_toks()}, {_NAMES_SQL}, p_exact AS ({_exact(FIELDS['all_fields'], 'rep')}), p_dp AS ({_exact(['event_date', 'place'], 'rep')}), {_RWEIGHTS}, "
       f"{S.vectors('rproj', 32)}, {S.kmeans('(SELECT ceil(count(*) / 20.0) FROM reports)', 3)}, cluster_pairs AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM clusters a JOIN clusters b ON a.k = b.k AND a.rec_id < b.rec_id), "
       f"{_RCLASSIC}, {_rsketch('rtoks', 's')}, {_rsketch('rkept', 'k')}, {_rsketch('rcopies', 'x')}, {_RCWS} "
       + _union_all([f"SELECT method, n_pairs, recall, round(1 - recall, 6) AS split, rr, prec, {most} AS max_block FROM ({S.quality(m, t, 'truth', 'SELECT count(*) FROM reports')})" for m, t, most in _RROWS]))
def method_comparison_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules, rules with names, projection with k-means, plain and idf-weighted sketches on the same rows; no order among them is assumed.

    max_block of rule_union_names is that of the rules before names are compared.
    """
    df = spread(settle(people(spark, sf_dir)))
    truth, weighted, n_rows = settle(report_truth(df)), spread(settle(weighted_tokens(spark, sf_dir))), df.count()
    sets = weighted.select("rec_id", F.transform("c", lambda e: e["h"]).alias("h"))
    most = weighted.select(F.explode("c").alias("e")).agg(F.max("e.cnt").alias("most")).first()["most"] or 1.0
    vectors = cluster.project(weighted.select("rec_id", F.explode("c").alias("e")).select("rec_id", "e.h", F.col("e.cnt").alias("w")), 32)
    clusters = settle(cluster.blocks(vectors, 20, n_rows, 3).select(F.col("cluster").alias("block_id"), "rec_id"))
    signed = lambda method, source, sig: by_signature(method, source.select("rec_id", sig.alias("sig")), K, TABLES, truth, n_rows)
    tabled = lambda method, source, tokens: by_keys(method, per_table_kernel(source, "rec_id", tokens, K, TABLES), TABLES, truth, n_rows)
    h, c = F.col("h"), F.col("c")
    copies = expand(F.transform(c, lambda e: F.struct(e["h"].alias("h"), quantize(e["cnt"], DELTA).alias("cnt"))))
    schemes = (["event_date", "place"], ["given"], ["family", "place"])
    # Pairs carry their entities: a pair is true if these are the same, which needs no join.
    kept = F.round(names.pair_cost(NAMES, PRESETS["equal"]), 6) <= 0.25
    named = rules.rule_pairs(df, "rec_id", UNION, [*NAMES, "k"]).select(kept.alias("kept"), (F.col("k_lo") == F.col("k_hi")).alias("t"))
    made = {
        "projection_kmeans": by_blocks("projection_kmeans", clusters, truth),
        "classic_minhash": signed("classic_minhash", sets, classic_minhash(h, K * TABLES)), "sketch": tabled("sketch", sets, h),
        "weighted_sampled": tabled("weighted_sampled", weighted, sample_tokens(c, most)), "weighted_expanded": tabled("weighted_expanded", weighted, copies),
        "consistent_sampling": signed("consistent_sampling", consistent_weighted_kernel(weighted, "rec_id", "c", K * TABLES), F.col("sig")),
        "rule_union_names": (named.agg(F.count_if("kept").alias("n_pairs"), F.count_if(F.col("kept") & F.col("t")).alias("n_hit")).select(F.lit("rule_union_names").alias("method"), "n_pairs", "n_hit"), by_fields(df, *schemes)),
    }
    plain = {"exact_fields": rules.AllOf(*FIELDS["all_fields"]), "date_place": rules.AllOf("event_date", "place"), "rule_union": UNION}
    largest = {"exact_fields": by_fields(df, FIELDS["all_fields"]), "date_place": by_fields(df, ["event_date", "place"]), "rule_union": by_fields(df, *schemes)}
    return rated([rules.counts_of_rules(df, "rec_id", truth, plain), *(x for x, _ in made.values())], largest | {m: x for m, (_, x) in made.items()}, truth.count(), n_rows)


@query(f"""WITH RECURSIVE {S.reports()}, {_NAMED}, {_both_names('equal', 'nc')}, parts AS (SELECT n.id_lo, n.id_hi, g.d / greatest(length(given_lo), length(given_hi)) AS g, f.d / greatest(length(family_lo), length(family_hi)) AS f
  FROM named_pairs n JOIN dg_nc g ON n.id_lo = g.id_lo AND n.id_hi = g.id_hi LEFT JOIN df_nc f ON n.id_lo = f.id_lo AND n.id_hi = f.id_hi)
SELECT id_lo, id_hi, round(greatest(g, f), 6) AS cost_max, round(least(g, f), 6) AS cost_min FROM parts""")
def name_cost_modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dearer and the cheaper of both names' costs for every pair of the rules; a missing name leaves the other's."""
    df = people(spark, sf_dir)
    found = rules.rule_pairs(df, "rec_id", UNION, NAMES)
    return found.select("id_lo", "id_hi", *(F.round(names.pair_cost(NAMES, PRESETS["equal"], how), 6).alias(f"cost_{how}") for how in ("max", "min"))).where("cost_max IS NOT NULL")


_THREE = "t AS (SELECT sum(n) AS n, sum(n * in_a) AS a, sum(n * in_b) AS b, sum(n * in_c) AS c FROM (SELECT in_a, in_b, in_c, count(*) AS n FROM seen GROUP BY ALL))"


def _pair_model(x: str, y: str, z: str) -> str:
    """Lists x and y may depend on each other: who is on z alone, times the odds of not being on z among the others."""
    return f"SELECT '{x}:{y}' AS model, round((SELECT n FROM t) + sum((in_{z} = 1 AND in_{x} + in_{y} = 0)::INT) * sum((in_{z} = 0)::INT) / nullif(sum((in_{z} = 1 AND in_{x} + in_{y} > 0)::INT), 0)::DOUBLE, 4) AS est FROM seen"


@query(f"WITH RECURSIVE {S.reports()}, {_SCORED}, {_REACH.format(pairs='matched')}, {_HISTORY}, {_THREE}, s AS (SELECT (a + b + c - n)::DOUBLE AS q, (a * b + a * c + b * c)::DOUBLE AS r, (a * b * c)::DOUBLE AS p FROM t) "
       f"SELECT 'independent' AS model, round((r + sqrt(r * r - 4 * q * p)) / (2 * q), 4) AS est FROM s UNION ALL {_pair_model('a', 'b', 'c')} UNION ALL {_pair_model('a', 'c', 'b')} UNION ALL {_pair_model('b', 'c', 'a')}")
def three_list_closed_form(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimates of the models of three_list_estimate() that have a closed form, which are all four; tests hold the fitted ones to them."""
    return capture.three_list(_history(spark, sf_dir), "in_a", "in_b", "in_c")


_CHOSEN = _greedy_sql(3, "SELECT 2 * count(*) AS b FROM reports").split(", hits AS (", 1)
_TRAIN = f"{S.u32(chr(39) + 'half' + chr(39) + ' || x.k')} % 2 = 0"
_ON_TRAIN = _CHOSEN[0] + ", hits AS (" + _CHOSEN[1].replace("JOIN rep y ON id_hi = y.rec_id), costs", f"JOIN rep y ON id_hi = y.rec_id WHERE {_TRAIN}), costs", 1)


@query(_ON_TRAIN.rsplit(" SELECT step::INT AS step", 3)[0] + f""", picked AS (SELECT step, rule FROM pick0 UNION ALL SELECT step, rule FROM pick1 UNION ALL SELECT step, rule FROM pick2),
every AS (SELECT id_lo, id_hi, {_TRAIN} AS train, {_HIT} FROM truth JOIN rep x ON id_lo = x.rec_id JOIN rep y ON id_hi = y.rec_id),
kept_by AS ({" UNION ALL ".join(f"SELECT id_lo, id_hi, train, '{_rule_name(r)}' AS rule FROM every WHERE h{i}" for i, r in enumerate(RULES))}),
upto AS (SELECT p.step, k.id_lo, k.id_hi, any_value(k.train) AS train FROM picked p JOIN picked q ON q.step <= p.step JOIN kept_by k ON k.rule = q.rule GROUP BY p.step, k.id_lo, k.id_hi)
SELECT p.step::INT AS step, p.rule, round(count(u.id_lo) FILTER (u.train) / (SELECT count(*) FROM every WHERE train), 6) AS train_recall, round(count(u.id_lo) FILTER (NOT u.train) / (SELECT count(*) FROM every WHERE NOT train), 6) AS test_recall
FROM picked p LEFT JOIN upto u ON u.step = p.step GROUP BY p.step, p.rule""")
def rule_choice_holdout(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules chosen greedily on one half of the entities, and what the union so far keeps of either half."""
    df = people(spark, sf_dir)
    return rules.choose_on_half(df, "rec_id", "k", report_truth(df), RULES, 2 * df.count(), 3)


CELLS, SEEDS = ((2, 5), (2, 10), (3, 10), (3, 20), (3, 30), (4, 20), (4, 40)), (500, 1500, 2500)
_MOST = {k: max(t for j, t in CELLS if j == k) for k, _ in CELLS}
_RUNS = ", ".join(f"{S.per_table(k, t, 'rtoks', f'f{k}_{s}', s)}, {S.band_keys(k, f'f{k}_{s}', f'b{k}_{s}', t)}, {S.band_pairs(f'b{k}_{s}', f'p{k}_{s}')}" for k, t in _MOST.items() for s in SEEDS)
_RATED = " UNION ALL ".join(
    f"SELECT {k}::INT AS k, {t}::INT AS l, count(*) AS p, count(*) FILTER (train) AS a, count(*) FILTER (NOT train) AS b FROM p{k}_{s} LEFT JOIN halves USING (id_lo, id_hi) WHERE first_table < {t}" for k, t in CELLS for s in SEEDS)


@query(f"""WITH {S.reports()}, {S.report_toks()}, {_RUNS}, halves AS (SELECT id_lo, id_hi, {_TRAIN} AS train FROM truth JOIN reports x ON id_lo = x.rec_id), per_run AS ({_RATED}),
sums AS (SELECT count(*) FILTER (train) AS nt, count(*) FILTER (NOT train) AS nv FROM halves),
rated AS (SELECT k, l, sum(p) AS all_p, sum(a) AS kept, round(avg(p), 6) AS n_pairs, round(avg(a / nt), 6) AS train_recall, round(avg(b / nv), 6) AS test_recall, round(stddev_pop(b / nv), 6) AS test_sd FROM per_run, sums GROUP BY k, l),
best AS (SELECT k, l FROM rated WHERE all_p <= {len(SEEDS)} * 2 * (SELECT count(*) FROM reports) ORDER BY kept DESC, all_p, k, l LIMIT 1)
SELECT k, l, n_pairs, train_recall, test_recall, test_sd, (k, l) IN (SELECT (k, l) FROM best) AS chosen FROM rated""")
def kl_choice_holdout(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(K, L) for the reports chosen on one half of the entities over three independent runs, within two pairs a report; both halves' recall."""
    df = people(spark, sf_dir)
    truth = report_truth(df).join(df.select(F.col("rec_id").alias("id_lo"), "k"), "id_lo")
    sets = df.select("rec_id", distinct_hashes(report_tokens()).alias("h"))
    return tuning.choose_on_half(sets, truth, rules.train_half(F.col("k")), CELLS, SEEDS, 2 * df.count())
