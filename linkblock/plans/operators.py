"""Workloads around blocking: sources, sinks, joins, aggregates, windows, functions, user functions, SQL."""

from __future__ import annotations

import uuid
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkblock import sql as surface
from linkblock.functions import names, tokens
from linkblock.functions.hashing import mix_sql
from linkblock.functions.names import PRESETS
from linkblock.operators import blocks, joins, measures, pairs, rules, sketch
from linkblock.operators.bands import bucketize
from linkblock.plans import query
from linkblock.plans import sqltext as S
from linkblock.plans.blocking import K, TABLES, UNION, _UNION_SQL, people, report_signatures
from linkblock.plans.sketches import B, weighted_sets, fast_signature
from linkblock.plans.sketches import K as DK
from linkblock.plans.sketches import TABLES as DT
from linkblock.plans.texts import GRAM, doc_bag, doc_sets, doc_truth, docs
from linkblock.runtime import ensure_checkpoint_dir
from linkblock.sources import tables
from linkblock.sources.tables import clean, load, report_truth, reports

_WITH = f"WITH {S.reports()}"
_REP = "rep AS (SELECT * REPLACE (nullif(family, '') AS family) FROM reports)"
_STAMP = "%Y-%m-%d"


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder that all executors share."""
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


@query("SELECT doc_id, lang, source, n_chars FROM documents WHERE lang = 'en' AND n_chars >= 1000")
def scan_parquet(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four columns and two predicates reach the scan; the texts aren't read."""
    return load(spark, sf_dir, "documents").where("lang = 'en' AND n_chars >= 1000").select("doc_id", "lang", "source", "n_chars")


_FLAT = f"{_WITH} SELECT rec_id, list, given, family, event_date, place FROM reports"


@query(_FLAT)
def scan_csv_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "csv")
    reports(spark, sf_dir).drop("k").write.option("header", True).option("emptyValue", "\"\"").csv(path)
    made = tables.read_csv(spark, path, "rec_id bigint, list string, given string, family string, event_date date, place int")
    return made.withColumn("family", F.coalesce("family", F.lit("")))


@query(_FLAT)
def scan_json_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "json")
    reports(spark, sf_dir).drop("k").write.json(path)
    return tables.read_json(spark, path, "rec_id bigint, list string, given string, family string, event_date date, place int")


@query(f"WITH {S.reports()}, {S.report_toks()}, {S.per_table(K, TABLES, 'rtoks')}, {S.band_keys(K, tables=TABLES)} SELECT table_no::INT AS table_no, count(*) AS rows, count(DISTINCT key) AS buckets FROM bands GROUP BY table_no")
def write_read_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A bucket index partitioned by table: a reader of one table opens one folder."""
    path = scratch(spark, "buckets")
    bucketize(report_signatures(reports(spark, sf_dir)), "rec_id", F.col("sig"), K, TABLES).write.partitionBy("table_no").parquet(path)
    return spark.read.parquet(path).groupBy("table_no").agg(F.count("*").alias("rows"), F.count_distinct("bucket_key").alias("buckets"))


@query(f"{_WITH} SELECT rec_id, upper(list) AS list, trim(given) AS given, nullif(trim(family), '') AS family, coalesce(place, -1)::INT AS place FROM reports")
def clean_fields(spark: SparkSession, sf_dir: str) -> DataFrame:
    return clean(reports(spark, sf_dir), "given", "family").select("rec_id", F.upper("list").alias("list"), "given", "family", F.coalesce("place", F.lit(-1)).alias("place"))


@query(f"{_WITH}, {_REP} SELECT rec_id FROM rep WHERE place IN (1, 3, 5) OR (event_date BETWEEN DATE '1995-01-01' AND DATE '1995-12-31' AND regexp_matches(given, '^[ابت]')) OR family IS NOT DISTINCT FROM NULL")
def filter_predicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    return people(spark, sf_dir).where(c("place").isin(1, 3, 5) | (c("event_date").between(F.lit("1995-01-01").cast("date"), F.lit("1995-12-31").cast("date")) & c("given").rlike("^[ابت]")) | c("family").eqNullSafe(F.lit(None))).select("rec_id")


@query(f"{_WITH} SELECT n_name, r_name, count(*) AS n FROM reports JOIN nation ON place = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def join_broadcast_place(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two lookup tables of fixed size (25 and 5 rows) are broadcast."""
    places = load(spark, sf_dir, "nation").join(F.broadcast(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return reports(spark, sf_dir).join(F.broadcast(places), F.col("place") == F.col("n_nationkey")).groupBy("n_name", "r_name").agg(F.count("*").alias("n"))


@query(f"{_WITH} SELECT a.rec_id AS id_lo, b.rec_id AS id_hi, abs(a.event_date - b.event_date)::INT AS days FROM reports a JOIN reports b ON a.place = b.place AND a.rec_id < b.rec_id AND abs(a.event_date - b.event_date) <= 3")
def join_date_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joins.date_range_pairs(reports(spark, sf_dir), "rec_id", "event_date", ["place"], 3)


@query(f"""{_WITH} SELECT b.rec_id, arg_max(a.rec_id, (a.event_date, a.rec_id)) AS prior_id FROM reports b JOIN reports a ON a.list = 'A' AND b.list = 'B' AND a.place = b.place AND a.event_date <= b.event_date GROUP BY b.rec_id""")
def asof_prior_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each report of list B the latest earlier one of list A at its place, without a range join."""
    df = reports(spark, sf_dir)
    return joins.as_of(df.where("list = 'B'"), df.where("list = 'A'"), "rec_id", ["place"], "event_date").select("rec_id", "prior_id").where("prior_id IS NOT NULL")


_DP = f"{_REP}, dp AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM rep a JOIN rep b ON a.rec_id < b.rec_id AND a.event_date = b.event_date AND a.place = b.place)"


def _dp(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    df = people(spark, sf_dir)
    found = rules.rule_pairs(df, "rec_id", rules.AllOf("event_date", "place"))
    return df, found.select(F.explode(F.array("id_lo", "id_hi")).alias("rec_id"))


@query(f"{_WITH}, {_DP} SELECT rec_id FROM reports WHERE rec_id IN (SELECT id_lo FROM dp UNION SELECT id_hi FROM dp)")
def records_in_pairs_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, used = _dp(spark, sf_dir)
    return df.join(used, "rec_id", "left_semi").select("rec_id")


@query(f"{_WITH}, {_DP} SELECT rec_id FROM reports WHERE rec_id NOT IN (SELECT id_lo FROM dp UNION SELECT id_hi FROM dp)")
def singletons_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    df, used = _dp(spark, sf_dir)
    return df.join(used, "rec_id", "left_anti").select("rec_id")


@query(f"{_WITH} SELECT p.place, l.list, count(r.rec_id) AS n FROM (SELECT DISTINCT place FROM reports) p CROSS JOIN (VALUES ('A'), ('B'), ('C')) l(list) LEFT JOIN reports r ON r.place = p.place AND r.list = l.list GROUP BY ALL")
def outer_list_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = reports(spark, sf_dir)
    every = df.select("place").distinct().select("place", F.explode(F.array(F.lit("A"), F.lit("B"), F.lit("C"))).alias("list"))
    return every.join(df.groupBy("place", "list").agg(F.count("*").alias("m")), ["place", "list"], "left").select("place", "list", F.coalesce("m", F.lit(0)).alias("n"))


@query("SELECT a.n_nationkey::BIGINT AS id_lo, b.n_nationkey::BIGINT AS id_hi FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
def all_pairs_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs.all_pairs(load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("id")), "id", 100)


def _grouped(kind: str, sql: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = reports(spark, sf_dir).select("list", "place")
        if kind == "grouping_sets":
            return df.groupingSets([[F.col("list")], [F.col("place")], []], "list", "place").agg(F.count("*").alias("n"))
        return getattr(df, kind)("list", "place").agg(F.count("*").alias("n"))

    query(f"{_WITH} SELECT list, place, count(*) AS n FROM reports GROUP BY {sql}", f"blocks_{kind}")(run)


for _kind, _text in (("rollup", "ROLLUP (list, place)"), ("cube", "CUBE (list, place)"), ("grouping_sets", "GROUPING SETS ((list), (place), ())")):
    _grouped(_kind, _text)


@query(f"WITH {S.doc_grams(GRAM)} SELECT count(DISTINCT tok) AS n_tokens, sum(cnt)::BIGINT AS n_shingles FROM bag")
def distinct_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counted by (tok) and then summed: two narrow exchanges instead of one distinct in a single task."""
    return doc_bag(spark, sf_dir).groupBy("tok").agg(F.sum("cnt").alias("c")).agg(F.count("*").alias("n_tokens"), F.sum("c").alias("n_shingles"))


@query()
def approx_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return doc_bag(spark, sf_dir).agg(F.approx_count_distinct("tok", 0.01).alias("n_tokens"))


@query(f"{_WITH}, b AS (SELECT count(*) AS b FROM reports GROUP BY place, list) SELECT quantile_cont(b, 0.25)::DOUBLE AS q1, quantile_cont(b, 0.5)::DOUBLE AS q2, quantile_cont(b, 0.75)::DOUBLE AS q3, min(b) AS least, max(b) AS most FROM b")
def size_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = reports(spark, sf_dir).groupBy("place", "list").agg(F.count("*").alias("b"))
    return b.agg(*(F.percentile("b", F.lit(q)).alias(n) for n, q in (("q1", 0.25), ("q2", 0.5), ("q3", 0.75))), F.min("b").alias("least"), F.max("b").alias("most"))


_SIZES = "s AS (SELECT place, list, count(*) AS n FROM reports GROUP BY place, list)"


def _sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return reports(spark, sf_dir).groupBy("place", "list").agg(F.count("*").alias("n"))


@query(f"{_WITH}, {_SIZES} SELECT place, list, n, rank() OVER (PARTITION BY list ORDER BY n DESC) AS r, dense_rank() OVER (PARTITION BY list ORDER BY n DESC) AS d FROM s")
def rank_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("list").orderBy(F.desc("n"))
    return _sizes(spark, sf_dir).select("place", "list", "n", F.rank().over(w).cast("bigint").alias("r"), F.dense_rank().over(w).cast("bigint").alias("d"))


@query(f"{_WITH} SELECT place, rec_id FROM (SELECT *, row_number() OVER (PARTITION BY place ORDER BY event_date, rec_id) AS i FROM reports WHERE event_date IS NOT NULL) WHERE i = 1")
def representative_record(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first report of each place; a least instead of a window, so that only one row a place and task moves."""
    return reports(spark, sf_dir).where("event_date IS NOT NULL").groupBy("place").agg(F.min_by("rec_id", F.struct("event_date", "rec_id")).alias("rec_id"))


@query(f"{_WITH} SELECT rec_id, (event_date - lag(event_date) OVER (PARTITION BY place ORDER BY event_date, rec_id))::INT AS days FROM reports WHERE event_date IS NOT NULL")
def lag_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("place").orderBy("event_date", "rec_id")
    return reports(spark, sf_dir).where("event_date IS NOT NULL").select("rec_id", F.datediff("event_date", F.lag("event_date").over(w)).alias("days"))


@query(f"{_WITH}, {_SIZES} SELECT place, list, sum(n * (n - 1) // 2) OVER (PARTITION BY list ORDER BY n, place ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)::BIGINT AS total FROM s")
def running_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("list").orderBy("n", "place").rowsBetween(Window.unboundedPreceding, 0)
    return _sizes(spark, sf_dir).select("place", "list", F.sum(F.expr("n * (n - 1) div 2")).over(w).alias("total"))


@query(f"{_WITH} SELECT rec_id, count(*) OVER (PARTITION BY place ORDER BY event_date - DATE '1990-01-01' RANGE BETWEEN 7 PRECEDING AND CURRENT ROW) AS week FROM reports WHERE event_date IS NOT NULL")
def range_frame_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("place").orderBy(F.unix_date("event_date")).rangeBetween(-7, 0)
    return reports(spark, sf_dir).where("event_date IS NOT NULL").select("rec_id", F.count("*").over(w).alias("week"))


@query(f"{_WITH}, {_SIZES} SELECT place, list, ntile(4) OVER (PARTITION BY list ORDER BY n, place) AS quarter FROM s")
def size_ntile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sizes(spark, sf_dir).select("place", "list", F.ntile(4).over(Window.partitionBy("list").orderBy("n", "place")).cast("bigint").alias("quarter"))


@query(f"{_WITH} SELECT place AS block_id, count(*) AS n FROM reports GROUP BY place ORDER BY n DESC, place LIMIT 5")
def top_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return blocks.top_blocks(reports(spark, sf_dir).select(F.col("place").alias("block_id"), "rec_id"), 5)


@query(f"WITH {S.doc_grams(GRAM)}, {S.doc_truth(0.3)}, twice AS (SELECT id_lo AS rec_id, id_hi AS other, n_common / n_union AS j FROM scored WHERE n_common >= 0.3 * n_union UNION ALL SELECT id_hi, id_lo, n_common / n_union FROM scored WHERE n_common >= 0.3 * n_union) SELECT rec_id, other, r::INT AS r FROM (SELECT *, row_number() OVER (PARTITION BY rec_id ORDER BY j DESC, other) AS r FROM twice) WHERE r <= 3")
def topk_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    near = doc_truth(spark, sf_dir, 0.3)
    both = near.select(F.explode(F.array(F.struct(F.col("id_lo").alias("rec_id"), F.col("id_hi").alias("other"), "jaccard"), F.struct(F.col("id_hi").alias("rec_id"), F.col("id_lo").alias("other"), "jaccard"))).alias("e")).select("e.*")
    return both.withColumn("r", F.row_number().over(Window.partitionBy("rec_id").orderBy(F.desc("jaccard"), "other"))).where("r <= 3").select("rec_id", "other", "r")


_TWO = f"{_WITH}, {_REP}, x AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM rep a JOIN rep b ON a.rec_id < b.rec_id AND a.given = b.given), y AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM rep a JOIN rep b ON a.rec_id < b.rec_id AND a.family = b.family AND a.place = b.place)"


def _two(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    df = people(spark, sf_dir)
    return rules.rule_pairs(df, "rec_id", "given").drop("first_rule"), rules.rule_pairs(df, "rec_id", rules.AllOf("family", "place")).drop("first_rule")


@query(f"{_TWO} SELECT * FROM x UNION SELECT * FROM y")
def pairs_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = _two(spark, sf_dir)
    return x.unionByName(y).distinct()


@query(f"{_TWO} SELECT * FROM x INTERSECT SELECT * FROM y")
def pairs_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = _two(spark, sf_dir)
    return x.intersect(y)


@query(f"{_TWO} SELECT * FROM x EXCEPT SELECT * FROM y")
def pairs_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = _two(spark, sf_dir)
    return x.exceptAll(y)


@query("SELECT p_partkey, lower(p_name) AS low, upper(p_brand) AS up, length(p_name)::INT AS len, substr(p_name, 1, 3) AS start, replace(p_type, 'A', '*') AS repl, regexp_replace(p_name, '[aeiou]', '', 'g') AS bare, reverse(p_brand) AS rev, string_split(p_name, ' ')[1] AS head, concat_ws('-', p_brand, p_type) AS joined, lpad(p_size::VARCHAR, 4, '0') AS padded FROM part")
def string_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "part").select(
        "p_partkey", F.lower("p_name").alias("low"), F.upper("p_brand").alias("up"), F.length("p_name").alias("len"), F.substring("p_name", 1, 3).alias("start"), F.replace("p_type", F.lit("A"), F.lit("*")).alias("repl"),
        F.regexp_replace("p_name", "[aeiou]", "").alias("bare"), F.reverse("p_brand").alias("rev"), F.split("p_name", " ")[0].alias("head"), F.concat_ws("-", "p_brand", "p_type").alias("joined"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"),
    )


@query("SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, day(o_orderdate)::INT AS d, quarter(o_orderdate)::INT AS q, dayofyear(o_orderdate)::INT AS doy, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first, strftime(o_orderdate::DATE + 30, '%Y-%m-%d') AS later, (o_orderdate::DATE - DATE '1992-01-01')::INT AS since, strftime(last_day(o_orderdate::DATE), '%Y-%m-%d') AS last FROM orders")
def date_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate").cast("date")
    text = lambda c: F.date_format(c, "yyyy-MM-dd")
    return load(spark, sf_dir, "orders").select(
        "o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.dayofmonth(d).alias("d"), F.quarter(d).alias("q"), F.dayofyear(d).alias("doy"), text(F.trunc(d, "month")).alias("first"),
        text(F.date_add(d, 30)).alias("later"), F.datediff(d, F.lit("1992-01-01").cast("date")).alias("since"), text(F.last_day(d)).alias("last"),
    )


@query("SELECT l_orderkey, l_linenumber, round(sqrt(l_extendedprice), 4) AS root, round(pow(l_discount, 2), 6) AS sq, round(ln(l_quantity), 6) AS log, round(exp(l_tax), 6) AS e, floor(l_extendedprice)::BIGINT AS down, ceil(l_extendedprice)::BIGINT AS up, (l_orderkey % 7) AS rest, (l_orderkey // 7) AS whole, (l_orderkey & 255) AS low, abs(l_discount - l_tax) AS gap, greatest(l_discount, l_tax) AS more FROM lineitem")
def math_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    return load(spark, sf_dir, "lineitem").select(
        "l_orderkey", "l_linenumber", F.round(F.sqrt("l_extendedprice"), 4).alias("root"), F.round(F.pow("l_discount", F.lit(2)), 6).alias("sq"), F.round(F.log("l_quantity"), 6).alias("log"), F.round(F.exp("l_tax"), 6).alias("e"),
        F.floor("l_extendedprice").alias("down"), F.ceil("l_extendedprice").alias("up"), (c("l_orderkey") % 7).alias("rest"), F.expr("l_orderkey div 7").alias("whole"), c("l_orderkey").bitwiseAND(255).alias("low"),
        F.abs(c("l_discount") - c("l_tax")).alias("gap"), F.greatest("l_discount", "l_tax").alias("more"),
    )


@query("WITH a AS (SELECT doc_id, list_sort(list_distinct(regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+'))) AS w FROM documents) SELECT doc_id, len(w)::INT AS n, w[1] AS first, w[-1] AS last, len(list_filter(w, lambda x: length(x) > 5))::INT AS longer, list_sum(list_transform(w, lambda x: length(x)))::INT AS chars, list_contains(w, 'the') AS has FROM a WHERE len(w) > 0")
def array_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = docs(spark, sf_dir).select(F.col("rec_id").alias("doc_id"), F.array_sort(F.array_distinct(tokens.words(F.col("text")))).alias("w")).where(F.size("w") > 0)
    return a.select("doc_id", F.size("w").alias("n"), F.get("w", F.lit(0)).alias("first"), F.element_at("w", -1).alias("last"), F.size(F.filter("w", lambda x: F.length(x) > 5)).alias("longer"), F.aggregate("w", F.lit(0), lambda s, x: s + F.length(x)).alias("chars"), F.array_contains("w", "the").alias("has"))


@query(f"WITH {S.doc_words()} SELECT rec_id AS doc_id, count(DISTINCT tok)::INT AS n, max(c)::INT AS most FROM (SELECT rec_id, tok, count(*) AS c FROM words GROUP BY ALL) GROUP BY rec_id")
def map_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = F.map_from_entries(F.transform(tokens.counts(tokens.words(F.col("text"))), lambda e: F.struct(e["tok"], e["cnt"])))
    return docs(spark, sf_dir).select(F.col("rec_id").alias("doc_id"), m.alias("m")).where(F.size("m") > 0).select("doc_id", F.size(F.map_keys("m")).alias("n"), F.array_max(F.map_values("m")).alias("most"))


@query("SELECT k, count(*) AS n FROM (SELECT json_extract_string(props, '$.k') AS k FROM events) GROUP BY k")
def json_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n"))


#: Vectors of a label that meet in one cell: at most about two blocks.
_VECTORS = 512


@query("SELECT a.vec_id AS id_lo, b.vec_id AS id_hi, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS dot FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id < b.vec_id")
def vector_inner(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair within a label. A label of over _VECTORS rows is cut in blocks, and every two blocks meet in a cell of their own."""
    e = load(spark, sf_dir, "embeddings").where("label IS NOT NULL").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("e"))
    sizes = e.groupBy("label").agg(F.ceil(F.count("*") / _VECTORS).cast("int").alias("blocks"))
    own = e.join(F.broadcast(sizes), "label").withColumn("own", F.pmod(F.xxhash64("vec_id"), F.col("blocks")).cast("int"))
    meets = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda j: F.struct(F.least("own", j).alias("i"), F.greatest("own", j).alias("j")))
    dealt = own.select("vec_id", "label", "e", "own", F.explode(meets).alias("m")).select("vec_id", "label", "e", "own", "m.i", "m.j")
    a = dealt.select(F.col("vec_id").alias("id_lo"), "label", "i", "j", F.col("e").alias("x"), F.col("own").alias("p"))
    b = dealt.select(F.col("vec_id").alias("id_hi"), "label", "i", "j", F.col("e").alias("y"), F.col("own").alias("q"))
    dot = F.aggregate(F.zip_with("x", "y", lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    # Rows of one block share all its cells and are paired in the cell of the block with itself only.
    return a.join(b, ["label", "i", "j"]).where("id_lo < id_hi AND (i = j OR p <> q)").select("id_lo", "id_hi", F.round(dot, 4).alias("dot"))


_SIGNS = 8


@query(f"""WITH x AS (SELECT vec_id, unnest(embedding::DOUBLE[]) AS v, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings),
d AS (SELECT vec_id, j, sum(CASE WHEN ({mix_sql('i * 7919 + 11', 'j + 4000')} // 65536) % 2 = 0 THEN v ELSE -v END) AS s FROM x, range({_SIGNS}) r(j) GROUP BY 1, 2),
k AS (SELECT vec_id, sum(CASE WHEN s > 0 THEN (1 << j::INT) ELSE 0 END)::BIGINT AS key FROM d GROUP BY vec_id) SELECT key, count(*) AS n FROM k GROUP BY key""")
def vector_sign_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks of dense vectors by the signs of random projections."""
    from linkblock.operators.cluster import sign

    e = load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    side = lambda j: F.aggregate(F.transform("e", lambda v, i: v * sign(i.cast("bigint") * 7919 + 11, j)), F.lit(0.0), lambda s, x: s + x)
    key = reduce(lambda a, b: a + b, (F.when(side(j) > 0, 1 << j).otherwise(0) for j in range(_SIGNS)))
    return e.groupBy(key.cast("bigint").alias("key")).agg(F.count("*").alias("n"))


_DOC_BANDS = f"{S.bins(B)}, {S.filled(B, 'probe')}, {S.band_keys(DK)}, {S.band_pairs()}"


def _text_pairs(df: DataFrame) -> DataFrame:
    """df: (rec_id, text)."""
    sig = df.select("rec_id", tokens.distinct_hashes(tokens.word_grams(F.col("text"), GRAM)).alias("h")).select("rec_id", sketch.one_pass_sketch(F.col("h"), B).alias("sig"))
    return pairs.from_signatures(sig, "rec_id", F.col("sig"), DK, DT).select("id_lo", "id_hi")


@query(f"WITH bare AS (SELECT page_id AS doc_id, regexp_replace(html, '<[^>]*>', ' ', 'g') AS text FROM pages), {S.doc_grams(GRAM, table='bare')}, {_DOC_BANDS} SELECT id_lo, id_hi FROM band_pairs")
def pages_text_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _text_pairs(load(spark, sf_dir, "pages").select(F.col("page_id").alias("rec_id"), F.regexp_replace("html", "<[^>]*>", " ").alias("text")))


@query(f"WITH turns AS (SELECT conv_id * 1000 + turn AS doc_id, text FROM conversations), {S.doc_grams(GRAM, table='turns')}, {_DOC_BANDS} SELECT count(*) AS n_pairs, count(DISTINCT id_lo) AS n_first FROM band_pairs")
def conversation_dups(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = _text_pairs(load(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("rec_id"), "text"))
    return made.agg(F.count("*").alias("n_pairs"), F.count_distinct("id_lo").alias("n_first"))


@query(f"WITH {S.doc_grams(8)}, items AS (SELECT item_id AS doc_id, text FROM benchmark), {S.doc_grams(8, table='items').replace('word_lists', 'il').replace('words', 'iw').replace('grams', 'ig').replace('bag', 'ib').replace('toks', 'it')}, total AS (SELECT rec_id, count(*) AS n FROM ib GROUP BY rec_id) "
       "SELECT d.rec_id AS doc_id, i.rec_id AS item_id, count(*) AS n_common, round(count(*) / any_value(t.n), 6) AS share FROM bag d JOIN ib i ON d.tok = i.tok JOIN total t ON t.rec_id = i.rec_id GROUP BY 1, 2 HAVING count(*) >= 0.2 * any_value(t.n)")
def benchmark_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that hold a fifth or more of a benchmark item's eight-word shingles."""
    items = tokens.long_form(load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("rec_id"), "text"), "rec_id", tokens.word_grams(F.col("text"), 8))
    long = tokens.long_form(docs(spark, sf_dir), "rec_id", tokens.word_grams(F.col("text"), 8))
    total = items.groupBy("rec_id").agg(F.count("*").alias("n")).select(F.col("rec_id").alias("item_id"), "n")
    hits = long.select(F.col("rec_id").alias("doc_id"), "tok").join(items.select(F.col("rec_id").alias("item_id"), "tok"), "tok").groupBy("doc_id", "item_id").agg(F.count("*").alias("n_common"))
    return hits.join(total, "item_id").where("n_common >= 0.2 * n").select("doc_id", "item_id", "n_common", F.round(F.col("n_common") / F.col("n"), 6).alias("share"))


@query("SELECT lang, source, count(*) AS n, round(avg(quality), 6) AS quality, round(avg(toxic), 6) AS toxic FROM documents JOIN labels USING (doc_id) GROUP BY ALL")
def label_purity(spark: SparkSession, sf_dir: str) -> DataFrame:
    both = load(spark, sf_dir, "documents").select("doc_id", "lang", "source").join(load(spark, sf_dir, "labels"), "doc_id")
    return both.groupBy("lang", "source").agg(F.count("*").alias("n"), F.round(F.avg("quality"), 6).alias("quality"), F.round(F.avg("toxic"), 6).alias("toxic"))


@query(f"WITH RECURSIVE {S.reports()}, {_UNION_SQL}, named_pairs AS (SELECT id_lo, id_hi, x.given AS given_lo, y.given AS given_hi FROM union_pairs JOIN rep x ON id_lo = x.rec_id JOIN rep y ON id_hi = y.rec_id), lc AS ({S.letter_costs('equal')}), {S.distances('named_pairs', 'given_lo', 'given_hi', 'lc')} "
       "SELECT p.id_lo, p.id_hi, round(d / greatest(length(given_lo), length(given_hi)), 6) AS cost FROM named_pairs p JOIN dist USING (id_lo, id_hi)")
def udf_name_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The Arrow form of the name distance."""
    df = people(spark, sf_dir)
    given = lambda s: df.select(F.col("rec_id").alias(f"id_{s}"), F.col("given").alias(f"g_{s}"))
    found = rules.rule_pairs(df, "rec_id", UNION).join(given("lo"), "id_lo").join(given("hi"), "id_hi")
    return found.select("id_lo", "id_hi", F.round(names.name_cost_udf(PRESETS["equal"])("g_lo", "g_hi"), 6).alias("cost"))


@query(f"WITH {S.doc_grams(GRAM)}, per AS (SELECT source, {mix_sql('h', 's')} AS v, s FROM toks JOIN documents ON rec_id = doc_id, range(8) r(s)) SELECT source, s::INT AS pos, min(v) AS val FROM per GROUP BY ALL")
def udaf_merge_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches of documents merged to sketches of sources by a grouped Arrow aggregate over partial merges."""
    sig = doc_sets(spark, sf_dir).select("rec_id", sketch.classic_minhash(F.col("h"), 8).alias("sig")).where("sig IS NOT NULL")

    @F.pandas_udf("bigint")
    def least(v: pd.Series) -> int:
        return int(v.min())

    rows = sig.join(docs(spark, sf_dir).select("rec_id", "source"), "rec_id").select("source", "rec_id", F.posexplode("sig").alias("pos", "v"))
    partial = rows.groupBy("source", "pos", (F.col("rec_id") % 64).alias("part")).agg(F.min("v").alias("v"))  # at most 64 rows a group reach Python
    return partial.groupBy("source", "pos").agg(least("v").alias("val"))


@query("SELECT p_name, substr(p_name, i::INT, 3) AS gram FROM (SELECT DISTINCT p_name FROM part), range(1, 200) r(i) WHERE i + 2 <= length(p_name)")
def udtf_shingles(spark: SparkSession, sf_dir: str) -> DataFrame:
    surface.register(spark)
    load(spark, sf_dir, "part").select("p_name").distinct().createOrReplaceTempView("lb_part_names")
    return spark.sql("SELECT p_name, s.gram FROM lb_part_names, LATERAL shingles(p_name, 3) s")


@query(f"WITH {S.doc_grams(GRAM)}, kept AS (SELECT DISTINCT rec_id, h FROM bag WHERE cnt / 2.0 > ({mix_sql('h', '31')} / 4294967296.0)), {S.bins(B, 'kept')}, {S.filled(B, 'probe')}, {S.band_keys(DK)}, sizes AS (SELECT table_no, key, count(*) AS n FROM bands GROUP BY 1, 2 HAVING count(*) > 1) SELECT n AS bucket_size, count(*) AS buckets FROM sizes GROUP BY n")
def sql_pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Buckets as a view, the rest as SQL."""
    surface.register(spark)
    sig = weighted_sets(spark, sf_dir).select("rec_id", fast_signature(F.col("c")).alias("sig"))
    bucketize(sig, "rec_id", F.col("sig"), DK, DT).createOrReplaceTempView("lb_buckets")
    return spark.sql("SELECT n AS bucket_size, count(*) AS buckets FROM (SELECT table_no, bucket_key, count(*) AS n FROM lb_buckets GROUP BY table_no, bucket_key HAVING count(*) > 1) GROUP BY n")


@query(f"{_WITH}, {_REP}, b AS (SELECT rec_id, event_date, place FROM rep), t AS (SELECT k, max(c) AS held, sum(c) AS size FROM (SELECT k, event_date, place, count(*) AS c FROM reports GROUP BY ALL) GROUP BY k HAVING sum(c) > 1) SELECT count(*) AS n_entities, sum((held < size)::INT)::BIGINT AS n_split FROM t")
def entity_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entities that no block of equal date and place holds whole."""
    df = people(spark, sf_dir)
    return measures.entity_split(rules.exact_field_blocks(df, "rec_id", ["event_date", "place"], "match_null"), df, "rec_id", "k")


__all__ = ["report_truth"]
