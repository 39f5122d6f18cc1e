"""Workloads on minhash sketches, banding, weighted forms and clustering over documents."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkblock.functions import similarity, tokens
from linkblock.functions.hashing import WIDTH, base64bits, mix_sql
from linkblock.operators import bands, cells, cluster, measures, pairs, rules, sketch, tuning
from linkblock.plans import query
from linkblock.plans import sqltext as S
from linkblock.plans.texts import ALIKE, GRAM, doc_bag, doc_counts, doc_sets, doc_truth, docs
from linkblock.runtime import settle
from linkblock.sources.tables import load

K, TABLES = 4, 20
B = K * TABLES
CLASSIC = 20
SCALE = 2.0
GRID = ((2, 10), (4, 10), (4, 20), (5, 8))
_G = f"WITH {S.doc_grams(GRAM)}"
_N = "SELECT count(*) FROM documents"


def weighted_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(rec_id, c): counted token hashes of each document."""
    return docs(spark, sf_dir).select("rec_id", tokens.hashed_counts(tokens.word_grams(F.col("text"), GRAM)).alias("c"))


def minhashes(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    return doc_sets(spark, sf_dir).select("rec_id", sketch.classic_minhash(F.col("h"), n).alias("sig"))


_CLASSIC = lambda n: f"mh AS (SELECT rec_id, s AS pos, min({mix_sql('h', 's')}) AS val FROM toks, range({n}) r(s) GROUP BY 1, 2)"


@query(f"{_G}, {_CLASSIC(CLASSIC)} SELECT rec_id AS doc_id, pos::INT AS pos, val FROM mh")
def minhash_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhashes(spark, sf_dir, CLASSIC).select(F.col("rec_id").alias("doc_id"), F.posexplode("sig").alias("pos", "val"))


@query(f"{_G}, {S.doc_truth(0.3)}, {_CLASSIC(CLASSIC)}, same AS (SELECT t.id_lo, t.id_hi, sum((a.val = b.val)::INT) / {CLASSIC}.0 AS est FROM doc_truth t JOIN mh a ON a.rec_id = t.id_lo JOIN mh b ON b.rec_id = t.id_hi AND a.pos = b.pos GROUP BY 1, 2) "
       "SELECT s.id_lo, s.id_hi, round(est, 6)::DOUBLE AS est, round(n_common / n_union, 6) AS exact, round(est::DOUBLE - n_common / n_union, 6) AS err FROM same s JOIN scored c ON s.id_lo = c.id_lo AND s.id_hi = c.id_hi")
def minhash_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimate, exact similarity and error of pairs of similarity 0.3 and more."""
    near = settle(doc_truth(spark, sf_dir, 0.3))
    met = settle(near.select(F.explode(F.array("id_lo", "id_hi")).alias("met")).distinct())
    sig = settle(similarity.only(minhashes(spark, sf_dir, CLASSIC), "rec_id", met))
    lo, hi = sig.select(F.col("rec_id").alias("id_lo"), F.col("sig").alias("a")), sig.select(F.col("rec_id").alias("id_hi"), F.col("sig").alias("b"))
    est = sketch.estimate(F.col("a"), F.col("b"))
    return near.join(lo, "id_lo").join(hi, "id_hi").select("id_lo", "id_hi", F.round(est, 6).alias("est"), F.round("jaccard", 6).alias("exact"), F.round(est - F.col("jaccard"), 6).alias("err"))


@query(f"{_G}, {_CLASSIC(CLASSIC)}, b AS (SELECT rec_id, pos // {K} AS table_no, md5(string_agg(val::VARCHAR, '-' ORDER BY pos)) AS bucket FROM mh GROUP BY 1, 2) SELECT table_no::INT AS table_no, bucket, count(*) AS n FROM b GROUP BY ALL HAVING count(*) > 1")
def minhash_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    keyed = minhashes(spark, sf_dir, CLASSIC).select(F.posexplode(bands.shown_keys(F.col("sig"), K, CLASSIC // K)).alias("table_no", "key"))
    return keyed.groupBy("table_no", F.md5(F.col("key").cast("binary")).alias("bucket")).agg(F.count("*").alias("n")).where("n > 1")


@query(f"{_G}, {S.bins(B)} SELECT rec_id AS doc_id, bin, val FROM bins")
def onepass_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    return doc_sets(spark, sf_dir).select(F.col("rec_id").alias("doc_id"), F.explode(sketch.one_pass_bins(F.col("h"), B)).alias("e")).select("doc_id", "e.*")


def _densified(how: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = sketch.densify(sketch.one_pass_bins(F.col("h"), B), B, how)
        return doc_sets(spark, sf_dir).select(F.col("rec_id").alias("doc_id"), F.explode(made).alias("e")).select("doc_id", "e.*")

    query(f"{_G}, {S.bins(B)}, {S.filled(B, how)} SELECT rec_id AS doc_id, bin::BIGINT AS bin, val, dist::BIGINT AS dist FROM filled", f"onepass_{how}")(run)


for _how in ("rotate", "coin", "probe"):
    _densified(_how)


@query(f"{_G}, {S.per_table(K, 5, 'toks')} SELECT rec_id AS doc_id, table_no::INT AS table_no, bin::BIGINT AS bin, val, dist::BIGINT AS dist FROM filled")
def onepass_per_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = doc_sets(spark, sf_dir).where(F.size("h") > 0).select(F.col("rec_id").alias("doc_id"), F.posexplode(sketch.per_table_filled(F.col("h"), K, 5)).alias("table_no", "t"))
    return made.select("doc_id", "table_no", F.explode("t").alias("e")).select("doc_id", "table_no", "e.*")


@query(f"{_G} " + " UNION ALL ".join(
    f"SELECT {k}::INT AS k, {t}::INT AS l, round(1 - count(*) / ({k * t} * (SELECT count(DISTINCT rec_id) FROM toks)), 6) AS share FROM (SELECT DISTINCT rec_id, h // {sketch.bin_width(k * t)} AS bin FROM toks)" for k, t in GRID))
def empty_bin_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of bins without a token of their own, by (K, L)."""
    sets = doc_sets(spark, sf_dir).where(F.size("h") > 0)
    shares = [1 - F.sum(F.size(sketch.one_pass_bins(F.col("h"), k * t))) / F.sum(F.lit(k * t)) for k, t in GRID]
    row = sets.agg(*(F.round(s, 6).alias(f"s{i}") for i, s in enumerate(shares)))
    return row.select(F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.lit(t).alias("l"), F.col(f"s{i}").alias("share")) for i, (k, t) in enumerate(GRID)))).alias("e")).select("e.*")


def _probe_pairs(k: int, t: int, name: str) -> str:
    n = k * t
    return f"{S.bins(n, out=f'bins_{name}')}, {S.filled(n, 'probe', f'bins_{name}', f'filled_{name}')}, {S.band_keys(k, f'filled_{name}', f'bands_{name}')}, {S.band_pairs(f'bands_{name}', f'pairs_{name}')}"


@query(f"{_G}, {_probe_pairs(K, TABLES, 'p')} SELECT id_lo, id_hi, first_table::INT AS first_table FROM pairs_p")
def band_pairs_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    sig = doc_sets(spark, sf_dir).select("rec_id", sketch.one_pass_sketch(F.col("h"), B).alias("sig"))
    return pairs.from_signatures(sig, "rec_id", F.col("sig"), K, TABLES)


@query(f"{_G}, {S.doc_truth(ALIKE)}, " + ", ".join(_probe_pairs(k, t, f"{k}_{t}") for k, t in GRID) + " " + " UNION ALL ".join(
    f"SELECT {k}::INT AS k, {t}::INT AS l, recall, rr, prec, (SELECT max(n) FROM (SELECT count(*) AS n FROM bands_{k}_{t} GROUP BY table_no, key)) AS max_bin FROM ({S.quality('x', f'pairs_{k}_{t}', 'doc_truth', _N)})" for k, t in GRID))
def kl_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each (K, L) cell with its own number of bins, from one pass over the tokens."""
    return tuning.grid(doc_sets(spark, sf_dir), doc_truth(spark, sf_dir), GRID)


@query("SELECT q / 50.0::DOUBLE AS s, k::INT AS k, l::INT AS l, round(1 - pow(1 - pow(q / 50.0::DOUBLE, k), l), 6)::DOUBLE AS p, n FROM (SELECT l_quantity::DOUBLE AS q, count(*) AS n FROM lineitem WHERE l_quantity BETWEEN 1 AND 50 GROUP BY 1), (VALUES " + ", ".join(map(str, GRID)) + ") g(k, l)")
def collision_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chance to share a bucket at the similarities that the line items' quantities make as shares of 50, for each (K, L)."""
    grid = spark.createDataFrame(list(GRID), "k int, l int")
    shares = load(spark, sf_dir, "lineitem").where("l_quantity BETWEEN 1 AND 50").groupBy(F.col("l_quantity").cast("double").alias("q")).agg(F.count("*").alias("n")).select((F.col("q") / 50.0).alias("s"), "n")
    return shares.join(F.broadcast(grid)).select("s", "k", "l", F.round(bands.collision_probability(F.col("s"), F.col("k"), F.col("l")), 6).alias("p"), "n")


_EXPANDED = f"copies AS (SELECT DISTINCT rec_id, {mix_sql('h', 'j + 900')} AS h FROM (SELECT rec_id, h, unnest(range(1, cnt + 1)) AS j FROM bag))"


@query(f"""{_G}, ex AS (SELECT rec_id, tok, unnest(range(1, cnt + 1)) AS j FROM bag), es AS (SELECT rec_id, count(*) AS n FROM ex GROUP BY rec_id),
common AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi, count(*) AS c FROM ex a JOIN ex b ON a.tok = b.tok AND a.j = b.j AND a.rec_id < b.rec_id GROUP BY 1, 2),
j AS (SELECT id_lo, id_hi, c, x.n + y.n - c AS u FROM common JOIN es x ON id_lo = x.rec_id JOIN es y ON id_hi = y.rec_id)
SELECT id_lo, id_hi, round(c / u, 6) AS j_expanded, round(c / u, 6) AS jw FROM j WHERE c >= 0.5 * u""")
def expansion_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Jaccard of the expansions and weighted Jaccard of the counts, side by side."""
    both = settle(similarity.similar_bags(doc_counts(spark, sf_dir), "rec_id", "c", 0.5).where("sum_min >= 0.5 * sum_max").select("id_lo", "id_hi", F.col("jw").alias("jaccard")))
    # The pairs are those of the expansions; their weighted similarity is made from the counts themselves.
    met = settle(both.select(F.explode(F.array("id_lo", "id_hi")).alias("met")).distinct())
    bag = settle(similarity.only(doc_counts(spark, sf_dir), "rec_id", met).select("rec_id", F.map_from_entries("c").alias("m")))
    side = lambda s: bag.select(F.col("rec_id").alias(f"id_{s}"), F.col("m").alias(f"m_{s}"))
    every = F.array_union(F.map_keys("m_lo"), F.map_keys("m_hi"))
    of = lambda m, k: F.coalesce(F.try_element_at(F.col(m), k), F.lit(0))
    total = lambda f: F.aggregate(every, F.lit(0), lambda s, k: s + f(of("m_lo", k), of("m_hi", k)))
    return both.join(side("lo"), "id_lo").join(side("hi"), "id_hi").select("id_lo", "id_hi", F.round("jaccard", 6).alias("j_expanded"), F.round(total(F.least) / total(F.greatest), 6).alias("jw"))


@query(f"{_G}, {_EXPANDED}, {S.bins(B, 'copies')} SELECT rec_id AS doc_id, bin, val FROM bins")
def expanded_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weighted_sets(spark, sf_dir).select(F.col("rec_id").alias("doc_id"), F.explode(sketch.one_pass_bins(sketch.expand(F.col("c")), B)).alias("e")).select("doc_id", "e.*")


def _cws_u(j: int) -> str:
    return f"(({mix_sql('(' + mix_sql('h', f'pos * 5 + {j} + 2000') + ')', f'pos + {j} + 7')} + 1) / {float(WIDTH + 2)})"


@query(f"""{_G}, draws AS (SELECT rec_id, pos, h, cnt, -ln({_cws_u(0)} * {_cws_u(1)}) AS r, -ln({_cws_u(2)} * {_cws_u(3)}) AS c, {_cws_u(4)} AS beta FROM bag, range(4) p(pos)),
levels AS (SELECT *, floor(ln(cnt) / r + beta) AS t FROM draws)
SELECT rec_id AS doc_id, pos::INT AS pos, arg_min(h, ln(c) - r * (t - beta) - r) AS tok_h FROM levels GROUP BY 1, 2""")
def cws_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The token that consistent weighted sampling chooses, for four positions."""
    made = sketch.consistent_weighted_kernel(weighted_sets(spark, sf_dir), "rec_id", "c", 4).select(F.col("rec_id").alias("doc_id"), F.posexplode("sig").alias("pos", "v"))
    return made.select("doc_id", "pos", F.floor(F.col("v") / 4096).alias("tok_h"))


_UNIT = f"({mix_sql('h', '31')} / {float(WIDTH)})"
_KEPT = f"kept AS (SELECT DISTINCT rec_id, h FROM bag WHERE cnt / {SCALE} > {_UNIT})"


@query(f"{_G}, {_KEPT} SELECT rec_id AS doc_id, count(*) AS kept FROM kept GROUP BY 1")
def sampled_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = weighted_sets(spark, sf_dir).select(F.col("rec_id").alias("doc_id"), F.size(sketch.sample_tokens(F.col("c"), SCALE)).cast("bigint").alias("kept"))
    return made.where("kept > 0")


_SOLO = f"({mix_sql('(' + mix_sql('(h + rec_id % 65521 * 65537)', '17') + ')', '31')} / {float(WIDTH)})"
_CLIP = "cl AS (SELECT rec_id, h, least(cnt, 2) AS w FROM bag), cm AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi, sum(least(a.w, b.w)) AS m FROM cl a JOIN cl b ON a.h = b.h AND a.rec_id < b.rec_id GROUP BY 1, 2), ct AS (SELECT rec_id, sum(w) AS w FROM cl GROUP BY 1), near AS (SELECT id_lo, id_hi, m / (x.w + y.w - m) AS jw FROM cm JOIN ct x ON id_lo = x.rec_id JOIN ct y ON id_hi = y.rec_id WHERE m >= 0.5 * (x.w + y.w - m))"


def _sampled_j(kept: str, out: str) -> str:
    return f"{out} AS (SELECT n.id_lo, n.id_hi, jw, (SELECT count(*) FROM {kept} a JOIN {kept} b ON a.h = b.h WHERE a.rec_id = n.id_lo AND b.rec_id = n.id_hi) AS c, (SELECT count(*) FROM {kept} WHERE rec_id = n.id_lo) AS x, (SELECT count(*) FROM {kept} WHERE rec_id = n.id_hi) AS y FROM near n)"


@query(f"{_G}, {_CLIP}, {_KEPT}, solo AS (SELECT DISTINCT rec_id, h FROM bag WHERE cnt / {SCALE} > {_SOLO}), {_sampled_j('kept', 'j1')}, {_sampled_j('solo', 'j2')} "
       + " UNION ALL ".join(f"SELECT '{m}' AS mode, count(*) AS n, round(avg(CASE WHEN x + y > c THEN c / (x + y - c) ELSE 0 END - jw), 6) AS bias, round(stddev_pop(CASE WHEN x + y > c THEN c / (x + y - c) ELSE 0 END - jw), 6) AS sd FROM {t}" for m, t in (("coordinated", "j1"), ("independent", "j2"))))
def sampled_error_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of the kept sets' similarity against the clipped weighted similarity, with shared and with own random numbers."""
    sets = weighted_sets(spark, sf_dir)
    clipped = sets.select("rec_id", F.transform("c", lambda e: F.struct(e["h"].alias("tok"), F.least(e["cnt"], F.lit(2)).alias("cnt"))).alias("c"))
    near = settle(similarity.similar_bags(clipped, "rec_id", "c", 0.5).where("sum_min >= 0.5 * sum_max").select("id_lo", "id_hi", "jw"))
    met = settle(near.select(F.explode(F.array("id_lo", "id_hi")).alias("met")).distinct())
    kept = similarity.only(sets, "rec_id", met).select("rec_id", sketch.sample_tokens(F.col("c"), SCALE).alias("one"), sketch.sample_tokens(F.col("c"), SCALE, False, F.col("rec_id")).alias("two"))
    lo = kept.select(F.col("rec_id").alias("id_lo"), F.col("one").alias("a1"), F.col("two").alias("a2"))
    hi = kept.select(F.col("rec_id").alias("id_hi"), F.col("one").alias("b1"), F.col("two").alias("b2"))
    both = near.join(lo, "id_lo").join(hi, "id_hi").select("jw", similarity.jaccard(F.col("a1"), F.col("b1")).alias("coordinated"), similarity.jaccard(F.col("a2"), F.col("b2")).alias("independent"))
    return reduce(DataFrame.unionByName, (measures.sketch_error(both, m, "jw").select(F.lit(m).alias("mode"), "n", "bias", "sd") for m in ("coordinated", "independent")))


def fast_signature(c: Column) -> Column:
    return sketch.weighted_sketch(c, K, TABLES, SCALE)


_FAST = f"{_KEPT}, {S.bins(B, 'kept', 'bins_w')}, {S.filled(B, 'probe', 'bins_w', 'filled_w')}, {S.band_keys(K, 'filled_w', 'bands_w')}, {S.band_pairs('bands_w', 'pairs_w')}"


@query(f"{_G}, {_FAST} SELECT table_no::INT AS table_no, md5(key) AS bucket, count(*) AS n FROM bands_w GROUP BY ALL HAVING count(*) > 1")
def portable_sketch_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship's steps by hashes that another engine can make too, for a check of all of them."""
    sig = weighted_sets(spark, sf_dir).select(fast_signature(F.col("c")).alias("sig"))
    keyed = sig.select(F.posexplode(bands.shown_keys(F.col("sig"), K, TABLES)).alias("table_no", "key"))
    return keyed.groupBy("table_no", F.md5(F.col("key").cast("binary")).alias("bucket")).agg(F.count("*").alias("n")).where("n > 1")


@query()
def fast_sketch_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: sample by weight, one pass of bins, fill, band, group. One exchange, of 64-bit keys only.

    Fast hashes of the words; portable_sketch_blocks is the same by portable ones.
    """
    counted = docs(spark, sf_dir).select(tokens.fast_gram_counts(F.col("text"), GRAM).alias("c"))
    keyed = counted.select(F.posexplode(bands.keys(fast_signature(F.col("c")), K, TABLES)).alias("table_no", "bucket"))
    return keyed.groupBy("table_no", "bucket").agg(F.count("*").alias("n")).where("n > 1")


@query(f"{_G}, {S.doc_truth(ALIKE)}, {_FAST}, {_probe_pairs(K, TABLES, 'p')} SELECT method, n_pairs, recall, rr, prec FROM ({S.quality('weighted', 'pairs_w', 'doc_truth', _N)} UNION ALL {S.quality('plain', 'pairs_p', 'doc_truth', _N)})")
def weighted_vs_plain(spark: SparkSession, sf_dir: str) -> DataFrame:
    truth, rows = settle(doc_truth(spark, sf_dir)), docs(spark, sf_dir)
    weighted = pairs.from_signatures(weighted_sets(spark, sf_dir).select("rec_id", fast_signature(F.col("c")).alias("sig")), "rec_id", F.col("sig"), K, TABLES)
    made = measures.quality(weighted, truth, rows, "weighted").unionByName(measures.quality(band_pairs_docs(spark, sf_dir), truth, rows, "plain"))
    return made.select("method", "n_pairs", "recall", "rr", "prec")


def _vectors(spark: SparkSession, sf_dir: str, p: int = 32) -> DataFrame:
    n = docs(spark, sf_dir).count()
    counted = tokens.counts(tokens.word_grams(F.col("text"), GRAM))
    keyed = F.transform(counted, lambda e: F.struct(base64bits(e["tok"]).alias("key"), e["cnt"].alias("cnt")))
    return cluster.tfidf_vectors(docs(spark, sf_dir).select("rec_id", F.explode(keyed).alias("e")).select("rec_id", "e.key", "e.cnt"), n, p)


_VEC = f"idf_w AS (SELECT tok, ln((({_N}) + 1) / (count(*) + 1)) AS idf FROM bag GROUP BY tok), doc_weights AS (SELECT rec_id, h, cnt * idf AS w FROM bag JOIN idf_w USING (tok)), {S.vectors('doc_weights', 32)}"
_COUNT = lambda size: f"(SELECT ceil(({_N}) / {size}.0))"
_ALL_DOCS = "SELECT d.doc_id AS rec_id, coalesce({c}, -d.doc_id - 1)::BIGINT AS cluster FROM documents d LEFT JOIN clusters c ON d.doc_id = c.rec_id"
_CLUSTER_PAIRS = "cluster_pairs AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM clusters a JOIN clusters b ON a.k = b.k AND a.rec_id < b.rec_id)"


def _every_record(spark: SparkSession, sf_dir: str, clusters: DataFrame) -> DataFrame:
    """A partition covers all records: those without a token get a block of their own, by negative number."""
    return docs(spark, sf_dir).select("rec_id").join(clusters, "rec_id", "left").select("rec_id", F.coalesce("cluster", -F.col("rec_id") - 1).alias("cluster"))


@query(f"{_G}, {_VEC}, {S.kmeans(_COUNT(20), 3)} {_ALL_DOCS.format(c='k')}")
def cluster_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Random projection and k-means, mean block of 20 records."""
    v = _vectors(spark, sf_dir)
    return _every_record(spark, sf_dir, cluster.blocks(v, 20, docs(spark, sf_dir).count(), 3))


@query(f"{_G}, {S.doc_truth(ALIKE)}, {_VEC}, {S.kmeans(_COUNT(20), 3)}, {_CLUSTER_PAIRS} {S.quality('projection_kmeans', 'cluster_pairs', 'doc_truth', _N)}")
def cluster_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = cluster_blocks(spark, sf_dir).select(F.col("cluster").alias("block_id"), "rec_id")
    return measures.partition_quality(made, doc_truth(spark, sf_dir), "projection_kmeans")


@query(f"{_G}, {_VEC}, {S.two_levels(_N, 20, 2)} {_ALL_DOCS.format(c='cluster')}")
def cluster_two_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _every_record(spark, sf_dir, cluster.two_level(_vectors(spark, sf_dir), 20, docs(spark, sf_dir).count(), 2))


@query()
def cluster_library(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _every_record(spark, sf_dir, cluster.library_kmeans(_vectors(spark, sf_dir), cluster.clusters_for(docs(spark, sf_dir).count(), 20)))


def _sweep_sql(size: int) -> str:
    n = f"s{size}"
    shown = S.quality("x", f"{n}_pairs", "doc_truth", f"SELECT count(*) FROM {n}")
    return f"SELECT {_COUNT(size)}::INT AS c, (SELECT round(avg(b), 6) FROM {n}_sizes) AS mean_size, (SELECT max(b) FROM {n}_sizes) AS max_size, recall, rr, prec FROM ({shown})"


@query(f"{_G}, {S.doc_truth(ALIKE)}, {_VEC}, " + ", ".join(
    f"{S.kmeans(_COUNT(n), 2, out=f's{n}')}, s{n}_sizes AS (SELECT k, count(*) AS b FROM s{n} GROUP BY k), s{n}_pairs AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM s{n} a JOIN s{n} b ON a.k = b.k AND a.rec_id < b.rec_id)" for n in (10, 50, 250)
) + " " + " UNION ALL ".join(_sweep_sql(n) for n in (10, 50, 250)))
def cluster_size_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality and block sizes as the mean block size is set to 10, 50 and 250."""
    v, truth, n = settle(_vectors(spark, sf_dir)), settle(doc_truth(spark, sf_dir)), docs(spark, sf_dir).count()
    rows = []
    for size in (10, 50, 250):
        c = cluster.clusters_for(n, size)
        made = cluster.lloyd(v, c, 2, 32).select(F.col("cluster").alias("block_id"), "rec_id")
        sizes = made.groupBy("block_id").agg(F.count("*").alias("b")).agg(F.round(F.avg("b"), 6).alias("mean_size"), F.max("b").alias("max_size"))
        rows.append(measures.partition_quality(made, truth, "projection_kmeans").join(F.broadcast(sizes)).select(F.lit(c).alias("c"), "mean_size", "max_size", "recall", "rr", "prec"))
    return reduce(DataFrame.unionByName, rows)


_CWS_TABLES = 5
_RULES = rules.AnyOf("start", rules.AllOf("lang", "source", "band"))
_KEYED = """keyed AS (SELECT doc_id AS rec_id, lang, source, substr(text, 1, 10) AS start, n_chars // 200 AS band FROM documents),
p_ls AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM keyed a JOIN keyed b ON a.lang = b.lang AND a.source = b.source AND a.rec_id < b.rec_id),
p_con AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM keyed a JOIN keyed b ON a.lang = b.lang AND a.start = b.start AND a.rec_id < b.rec_id),
p_dnf AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM keyed a JOIN keyed b ON a.rec_id < b.rec_id AND (a.start = b.start OR (a.lang = b.lang AND a.source = b.source AND a.band = b.band)))"""


def _largest_sql(fields: str, table: str = "keyed") -> str:
    return f"(SELECT max(n) FROM (SELECT count(*) AS n FROM {table} GROUP BY {fields}))"


_CWS = f"""draws AS (SELECT rec_id, pos, h, cnt, -ln({_cws_u(0)} * {_cws_u(1)}) AS r, -ln({_cws_u(2)} * {_cws_u(3)}) AS c, {_cws_u(4)} AS beta FROM bag, range({K * _CWS_TABLES}) p(pos)),
levels AS (SELECT *, floor(ln(cnt) / r + beta)::BIGINT AS t FROM draws),
chosen AS (SELECT rec_id, pos, arg_min(h * 4096 + ((t % 4096) + 4096) % 4096, ln(c) - r * (t - beta) - r) AS val FROM levels GROUP BY 1, 2),
cws_bands AS (SELECT rec_id, pos // {K} AS table_no, string_agg(val::VARCHAR, '-' ORDER BY pos) AS key FROM chosen GROUP BY 1, 2), {S.band_pairs('cws_bands', 'p_cws')}"""
_BANDED = "table_no, key"
_COMPARED = (
    ("exact_fields", "p_ls", _largest_sql("lang, source")), ("conjunction", "p_con", _largest_sql("lang, start")),
    ("rule_union", "p_dnf", f"greatest({_largest_sql('start')}, {_largest_sql('lang, source, band')})"),
    ("projection_kmeans", "cluster_pairs", _largest_sql("k", "clusters")), ("classic_minhash", "p_mh", _largest_sql(_BANDED, "mh_bands")),
    ("one_pass_rotate", "p_rot", _largest_sql(_BANDED, "bands_r")), ("one_pass_probe", "pairs_p", _largest_sql(_BANDED, "bands_p")),
    ("weighted_sampled", "pairs_w", _largest_sql(_BANDED, "bands_w")), ("weighted_expanded", "pairs_x", _largest_sql(_BANDED, "bands_x")),
    ("consistent_sampling", "p_cws", _largest_sql(_BANDED, "cws_bands")),
)


def rated(counted: list[DataFrame], largest: dict[str, DataFrame], n_true: int, n_rows: int) -> DataFrame:
    """method, n_pairs, recall, split, rr, prec, max_block from counts (method, n_pairs, n_hit). largest: by method, a column n of block sizes."""
    most = reduce(DataFrame.unionByName, (df.agg(F.max("n").alias("max_block")).select(F.lit(m).alias("method"), "max_block") for m, df in largest.items()))
    true, rows = F.lit(n_true).cast("bigint"), F.lit(n_rows).cast("bigint")
    pairs_, hit = F.coalesce("n_pairs", F.lit(0)), F.coalesce("n_hit", F.lit(0))
    rates = {"recall": measures.recall(hit, true), "rr": measures.reduction_ratio(pairs_, rows), "prec": measures.precision(hit, pairs_)}
    made = reduce(DataFrame.unionByName, counted).join(most, "method").select("method", pairs_.alias("n_pairs"), *(F.round(c, 6).alias(m) for m, c in rates.items()), "max_block")
    return made.select("method", "n_pairs", "recall", F.round(1 - F.col("recall"), 6).alias("split"), "rr", "prec", "max_block")


def by_fields(df: DataFrame, *schemes: list[str]) -> DataFrame:
    """Block sizes of records that agree on the fields of any of the schemes; missing fields agree with nothing."""
    return reduce(DataFrame.unionByName, (df.dropna(subset=list(f)).groupBy(*f).agg(F.count("*").alias("n")).select("n") for f in schemes))


def by_signature(method: str, signed: DataFrame, k: int, tables: int, truth: DataFrame, n_rows: int) -> tuple[DataFrame, DataFrame]:
    """by_keys() of a banded signature (rec_id, sig)."""
    return by_keys(method, signed.select(F.col("rec_id").alias("id"), bands.keys(F.col("sig"), k, tables).alias("ks")), tables, truth, n_rows)


def by_keys(method: str, keyed: DataFrame, tables: int, truth: DataFrame, n_rows: int) -> tuple[DataFrame, DataFrame]:
    """(counts (method, n_pairs, n_hit), bucket sizes n) of keys by table (id, ks), which are made once; pairs are counted where they meet."""
    keyed = settle(keyed).where("ks IS NOT NULL")
    sizes = keyed.select(F.posexplode("ks").alias("t", "key")).groupBy("t", "key").agg(F.count("*").alias("n")).select("n")
    return cells.count(keyed, tables, n_rows).agg(F.sum("n_pairs").alias("n_pairs")).join(F.broadcast(hits_of_keys(keyed, truth))).select(F.lit(method).alias("method"), "n_pairs", "n_hit"), sizes


def hits_of_keys(keyed: DataFrame, truth: DataFrame) -> DataFrame:
    """(n_hit): pairs of the truth that share the key of any table; they meet the keys of their own records only."""
    side = lambda s: keyed.select(F.col("id").alias(f"id_{s}"), F.col("ks").alias(s))
    met = F.exists(F.zip_with("lo", "hi", lambda x, y: x == y), lambda e: e)
    return truth.select("id_lo", "id_hi").join(side("lo"), "id_lo").join(side("hi"), "id_hi").agg(F.count_if(met).alias("n_hit"))


def by_blocks(method: str, blocks: DataFrame, truth: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The same of a partition (block_id, rec_id)."""
    return measures.partition_quality(blocks, truth, method).select("method", "n_pairs", "n_hit"), blocks.groupBy("block_id").agg(F.count("*").alias("n")).select("n")


@query(f"{_G}, {S.doc_truth(ALIKE)}, {_KEYED}, {_VEC}, {S.kmeans(_COUNT(20), 3)}, {_CLUSTER_PAIRS}, "
       f"{_CLASSIC(B)}, mh_bands AS (SELECT rec_id, pos // {K} AS table_no, string_agg(val::VARCHAR, '-' ORDER BY pos) AS key FROM mh GROUP BY 1, 2), {S.band_pairs('mh_bands', 'p_mh')}, "
       f"{S.bins(B)}, {S.filled(B, 'rotate', out='filled_r')}, {S.band_keys(K, 'filled_r', 'bands_r')}, {S.band_pairs('bands_r', 'p_rot')}, {_probe_pairs(K, TABLES, 'p')}, {_FAST}, "
       f"{_EXPANDED}, {S.bins(B, 'copies', 'bins_x')}, {S.filled(B, 'probe', 'bins_x', 'filled_x')}, {S.band_keys(K, 'filled_x', 'bands_x')}, {S.band_pairs('bands_x', 'pairs_x')}, {_CWS} "
       + " UNION ALL ".join(f"SELECT method, n_pairs, recall, round(1 - recall, 6) AS split, rr, prec, {most} AS max_block FROM ({S.quality(m, t, 'doc_truth', _N)})" for m, t, most in _COMPARED))
def method_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules, projection with k-means, plain and weighted sketches on the same documents and truth; which wins is what comes out, not what is asserted."""
    truth, rows = settle(doc_truth(spark, sf_dir)), docs(spark, sf_dir)
    n_rows = rows.count()
    sets, weighted = settle(doc_sets(spark, sf_dir)), settle(weighted_sets(spark, sf_dir))
    fields = rows.select("rec_id", "lang", "source", rules.prefix("text", 10).alias("start"), rules.band("n_chars", 200).alias("band"))
    clusters = settle(cluster.blocks(_vectors(spark, sf_dir), 20, n_rows, 3).select(F.col("cluster").alias("block_id"), "rec_id"))
    h, c = F.col("h"), F.col("c")
    named = {"exact_fields": rules.AllOf("lang", "source"), "conjunction": rules.AllOf("lang", "start"), "rule_union": _RULES}
    sketched = lambda method, df, sig, tables=TABLES: by_signature(method, df.select("rec_id", sig.alias("sig")), K, tables, truth, n_rows)
    made = {
        "projection_kmeans": by_blocks("projection_kmeans", clusters, truth),
        "classic_minhash": sketched("classic_minhash", sets, sketch.classic_minhash(h, B)), "one_pass_rotate": sketched("one_pass_rotate", sets, sketch.one_pass_sketch(h, B, "rotate")),
        "one_pass_probe": sketched("one_pass_probe", sets, sketch.one_pass_sketch(h, B, "probe")), "weighted_sampled": sketched("weighted_sampled", weighted, fast_signature(c)),
        "weighted_expanded": sketched("weighted_expanded", weighted, sketch.one_pass_sketch(sketch.expand(c), B)),
        "consistent_sampling": sketched("consistent_sampling", sketch.consistent_weighted_kernel(weighted, "rec_id", "c", K * _CWS_TABLES), F.col("sig"), _CWS_TABLES),
    }
    largest = {"exact_fields": by_fields(fields, ["lang", "source"]), "conjunction": by_fields(fields, ["lang", "start"]), "rule_union": by_fields(fields, ["start"], ["lang", "source", "band"])}
    return rated([rules.counts_of_rules(fields, "rec_id", truth, named), *(x for x, _ in made.values())], largest | {m: x for m, (_, x) in made.items()}, truth.count(), n_rows)


@query(f"{_G}, d AS (SELECT rec_id, count(*) AS d, sum(cnt) AS i FROM bag GROUP BY rec_id) SELECT rec_id AS doc_id, d * {B} AS classic, d + {B} AS one_pass, (i + {B})::BIGINT AS expanded FROM d")
def hash_operations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hash evaluations a record by each kind of sketch."""
    c = weighted_sets(spark, sf_dir).where(F.size("c") > 0)
    d, copies = F.size("c").cast("bigint"), F.aggregate("c", F.lit(0).cast("bigint"), lambda s, e: s + e["cnt"])
    return c.select(F.col("rec_id").alias("doc_id"), *(sketch.hash_ops(m, d, B, copies).alias(m) for m in ("classic", "one_pass", "expanded")))


@query()
def wide_kernel_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The Arrow form of the one-pass sketch; tests hold it equal to the built-in form."""
    return sketch.wide_kernel(doc_sets(spark, sf_dir), "rec_id", "h", B)
