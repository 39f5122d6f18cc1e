"""SimHash, URL filter, classifier, mixing, language model and pipeline against plain Python versions."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from linkblock.llm import bpe, brown, mixing, ordinal, secrets, simhash, urls
from tests.llm.conftest import TEXTS


def keyed(rows):
    return Counter(map(tuple, rows))


# SimHash


def slow_fingerprint(text):
    words = (text or "").encode().lower().split()
    grams = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) >= 3 else [b" ".join(words)] if words else []
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes)) if hashes else 0


def slow_roots(values, radius):
    values = np.array(values, np.uint64)
    near = np.bitwise_count(values[:, None] ^ values[None, :]) <= radius
    root = np.arange(len(values))
    while True:
        new = np.array([root[near[i]].min() for i in range(len(values))])
        if (new == root).all():
            return root
        root = new


def test_simhash_components_match_brute_force(small, odd):
    docs = odd.select("doc_id", "text").unionByName(small[0].select("doc_id", "text")).where("doc_id IS NOT NULL")
    rows = docs.collect()
    prints = [slow_fingerprint(r.text) for r in rows]
    root = slow_roots(prints, 2)
    least = defaultdict(list)
    for r, c in zip(rows, root, strict=True):
        least[c].append(r.doc_id)
    want = keyed((r.doc_id, f"{p:016x}", min(least[c])) for r, p, c in zip(rows, prints, root, strict=True))
    found = simhash.near_duplicates(docs)
    got = keyed((r.doc_id, r.x, r.component_id) for r in found.select("doc_id", simhash.hex_digits(found.fp).alias("x"), "component_id").collect())
    assert got == want


@pytest.mark.parametrize("radius", [0, 1, 2, 3, 5])
def test_bit_sliced_forest_equals_pairs(radius):
    rng = np.random.default_rng(radius)
    base = rng.integers(0, 2**63, 120, dtype=np.uint64)
    flips = [base ^ (np.uint64(1) << rng.integers(0, 64, 120).astype(np.uint64)) for _ in range(5)]
    values = np.unique(np.concatenate([base, *flips, rng.integers(0, 2**63, 300, dtype=np.uint64)]))
    assert (simhash.forest(values.view(np.uint8).reshape(-1, 8), radius) == slow_roots(values, radius)).all()


def test_hot_cells_are_dealt_in_chunks_without_losing_links(spark):
    rng = np.random.default_rng(1)
    values = [int(x) for x in np.unique(rng.integers(0, 1 << 12, 900)).astype(np.int64)]
    parts = spark.createDataFrame([(7, int(v).to_bytes(8, "little")) for v in values], "cell bigint, fp binary")
    edges = [(int.from_bytes(r.a, "little"), int.from_bytes(r.b, "little")) for r in simhash.links(parts, 1, 8, block=100).collect()]
    root = {v: v for v in values}
    def find(x):
        while root[x] != x:
            x = root[x]
        return x
    for a, b in edges:
        assert bin(a ^ b).count("1") <= 12
        root[max(find(a), find(b))] = min(find(a), find(b))
    want = slow_roots(values, 1)
    assert len({find(v) for v in values}) == len(set(want))


def test_near_copies_catch_planted_ones_and_leave_the_rest(spark):
    rng = np.random.default_rng(4)
    vocab = [f"w{i}" for i in range(4000)]
    texts, group = [], []
    for g in range(60):
        words = list(rng.choice(vocab, 300))
        for copy in range(3):
            changed = list(words)
            for at in rng.choice(300, 3 * copy, replace=False):  # 30 of 296 shingles at most: similarity 0.81
                changed[at] = "changed"
            texts.append(" ".join(changed))
            group.append(g)
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id bigint, text string")
    got = {r.doc_id: r.component_id for r in simhash.near_copies(df).collect()}
    whole = sum(len({got[i] for i in range(len(texts)) if group[i] == g}) == 1 for g in range(60))
    assert whole >= 57
    assert all(group[c] == group[i] for i, c in got.items())


def test_near_copies_equal_brute_force_jaccard(spark):
    """Pairs of exactly 0.80 and next below it, short and long, and a group over a chunk; no link is missed or added."""
    rng = np.random.default_rng(6)
    fresh = iter(range(10**9))
    words = lambda n: [f"n{next(fresh)}" for _ in range(n)]
    texts, want = [], []
    for shared, more in [(4, 1), (8, 2), (12, 3), (3, 1), (7, 2), (36, 9), (35, 9), (400, 100), (399, 100), (2400, 600), (2398, 600)]:
        for _ in range(12):
            body = words(shared + 4)
            first, second = more // 2, more - more // 2
            texts += [" ".join(body + words(first)), " ".join(body + words(second))]
            want.append(shared / (shared + more) >= 0.8)
    body = words(60)
    group = [" ".join(body[: int(rng.integers(40, 61))]) for _ in range(300)] + [" ".join(body[:56] + words(int(n))) for n in rng.integers(0, 25, 400)]
    df = spark.createDataFrame(list(enumerate(texts + group)), "doc_id bigint, text string")
    got = [r.component_id for r in simhash.near_copies(df).orderBy("doc_id").collect()]
    assert [got[2 * i] == got[2 * i + 1] for i in range(len(want))] == want
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in map(str.split, group)]
    near = np.array([[5 * len(a & b) >= 4 * len(a | b) for b in sets] for a in sets])
    root = np.arange(len(sets))
    while (new := np.array([root[x].min() for x in near])).tolist() != root.tolist():
        root = new
    assert got[len(texts) :] == [len(texts) + x for x in root.tolist()]


def test_wide_fingerprints_are_simhash_and_close_for_similar_sets():
    rng = np.random.default_rng(8)
    for n in (1, 2, 3, 8, 300):
        hashes = np.unique(rng.integers(0, 1 << 63, n, dtype=np.uint64))
        want = []
        for salt in simhash._REMIX.tolist():
            mixed = []
            for h in hashes.tolist():
                x = (h ^ salt) * 0x9E3779B97F4A7C15 % (1 << 64)
                x = (x ^ x >> 31) * 0xBF58476D1CE4E5B9 % (1 << 64)
                mixed.append(x ^ x >> 29)
            for i in range(64):
                ones = sum(x >> i & 1 for x in mixed)
                want.append(mixed[0] >> i & 1 if 2 * ones == n else int(2 * ones > n))
        assert np.unpackbits(simhash.wide_fingerprint(hashes), bitorder="little").tolist() == want
    far = lambda a, b: int(np.unpackbits(simhash.wide_fingerprint(a) ^ simhash.wide_fingerprint(b)).sum())
    for shared, more in [(4, 1), (8, 2), (12, 3), (400, 100)]:
        for _ in range(200):
            every = np.unique(rng.integers(0, 1 << 63, shared + more, dtype=np.uint64))
            rng.shuffle(every)
            a, b = np.sort(every[: shared + more // 2]), np.sort(np.r_[every[:shared], every[shared + more // 2 :]])
            assert far(a, b) <= simhash.WIDE_RADIUS
            assert far(a, np.sort(rng.integers(0, 1 << 63, shared, dtype=np.uint64))) > simhash.WIDE_RADIUS


def test_near_copies_meet_by_fingerprints_compared_by_bit_planes(spark):
    """What shares a cell goes on only if its fingerprints are linked within the radius."""
    rng = np.random.default_rng(9)
    base = rng.integers(0, 2, (12, 256), dtype=np.uint8)
    bits = []
    for b in base:
        bits.append(b)
        for flips in (0, 60, 91, 150):
            other = b.copy()
            other[rng.choice(256, flips, replace=False)] ^= 1
            bits.append(other)
    fps = [np.packbits(b, bitorder="little").tobytes() for b in bits]
    rows = [(i, [7], bytearray(fp)) for i, fp in enumerate(fps)] + [(1000, [8], bytearray(fps[0])), (1001, [9], bytearray(fps[1]))]
    got = {r.node: r.root for r in simhash._simhash_linked(spark.createDataFrame(rows, "node bigint, cells array<bigint>, fp binary")).collect()}
    root = list(range(len(fps)))
    for i in range(len(fps)):
        for j in range(i):
            if (int.from_bytes(fps[i]) ^ int.from_bytes(fps[j])).bit_count() <= simhash.WIDE_RADIUS:
                low, high = sorted((root[i], root[j]))
                root = [low if x == high else x for x in root]
    size = Counter(root)
    assert set(got) == {i for i, x in enumerate(root) if size[x] > 1}
    assert set(got.values()) == {0} and min(size.values()) == 1


def test_one_of_each_keeps_the_least_id(spark, odd):
    out = simhash.one_of_each(odd)
    assert out.columns == odd.columns
    ids = sorted((r.doc_id is None, r.doc_id) for r in out.collect())
    assert ids == sorted(ids) and len(ids) == len(set(ids))
    assert (False, 6) in ids and (False, 7) not in ids and (False, 2) in ids and (False, 3) not in ids


def test_one_of_each_keeps_a_row_for_each_group(spark):
    a, b, c, d, e = (" ".join(f"{x}{i}" for i in range(40)) for x in "abcde")
    rows = [(None, a, "1"), (None, b, "2"), (None, b, "3"), (None, c, "4"), (5, c, "5"), (7, d, "6"), (7, e, "7"), (7, e + " end", "8"), (9, c, "9"), (None, None, "10"), (None, "", "11")]
    out = simhash.one_of_each(spark.createDataFrame(rows, "doc_id bigint, text string, source string")).collect()
    assert keyed((r.doc_id, (r.text or " ")[0]) for r in out) == Counter([(None, "a"), (None, "b"), (5, "c"), (7, "d"), (7, "e"), (None, " ")])


# URL filter


def test_urls(spark):
    cases = {
        "http://a.example.org/es/x": ("a.example.org", "/es/x", "example.org/es/", "block"), "https://Example.ORG/en/12?q": ("example.org", "/en/12", "example.org/en/1", "block"),
        "http://x.org": ("x.org", "", None, "allow"), "http://x.org/": ("x.org", "/", "org/", "allow"), "ftp://b.com/de/#f": ("b.com", "/de/", "com/de/", "block"),
        "http://b.com/fr/casino-bet": ("b.com", "/fr/casino-bet", "com/fr/", "allow"), "http://b.net/casino": ("b.net", "/casino", None, "allow"), "http://b.net/casino/bet": ("b.net", "/casino/bet", None, "block"),
        "http://b.net/porn": ("b.net", "/porn", None, "block"), "http://b.net/sporn": ("b.net", "/sporn", None, "allow"), "no scheme": ("", "", None, "allow"), None: ("", "", None, "allow"), "": ("", "", None, "allow"),
        "http://b.net/casino/casino": ("b.net", "/casino/casino", None, "allow"), "http://CHEAP-PILLS.example.net/": ("cheap-pills.example.net", "/", None, "block"), "x://É.com/fr/": ("É.com", "/fr/", "com/fr/", "allow"),
    }
    df = spark.createDataFrame([(i, u, "h") for i, u in enumerate(cases)], "page_id bigint, url string, host string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge_urls(df).collect()}
    assert got == dict(enumerate(cases.values()))
    assert urls.judge_urls(df.limit(0)).count() == 0


def test_url_terms_and_rules_from_tables(spark):
    terms = spark.createDataFrame([("Bad", 3), ("soft-a", 1), ("softb", 1), ("softb", 1), ("off", 0), (None, 3), ("", 3)], "term string, weight int")
    strict, soft = urls.load_terms(terms)
    assert strict == ("bad",) and soft == ("soft-a", "softb")
    rules = urls.load_rules(spark.createDataFrame([("net", "/ok/", "allow"), ("a.net", "/ok/no", "block"), ("net", "/ok/", "allow")], "host string, path string, verdict string"))
    cases = {"http://x.a.net/ok/no/bad": "block", "http://x.a.net/ok/bad": "allow", "http://x.org/bad": "block", "http://x.org/softb": "allow", "http://x.org/softb?soft-a": "block", "http://x.org/off/casino/bet": "allow", "http://x.org/" + "softb/" * 200_000: "allow"}
    df = spark.createDataFrame([(i, u) for i, u in enumerate([*cases, *cases])], "page_id bigint, url string")
    got = {(r.page_id, r.verdict) for r in urls.judge_urls(df, rules=rules, strict=strict, soft=soft).collect()}
    assert got == set(enumerate([*cases.values(), *cases.values()]))
    with pytest.raises(ValueError):
        urls.load_rules(spark.createDataFrame([("net", "/", "maybe")], "host string, path string, verdict string"))


def test_text_ids_are_refused_at_once(spark):
    df = spark.createDataFrame([("a1", "text", "s", "http://x.org")], "doc_id string, text string, source string, url string")
    for f in (lambda: simhash.near_duplicates(df), lambda: mixing.mix_documents(df), lambda: brown.train_and_score(df), lambda: urls.judge_urls(df, id_col="doc_id"), lambda: simhash.one_of_each(df)):
        with pytest.raises(TypeError, match="whole numbers"):
            f()


# classifier


def test_classifier_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = ordinal.fit(docs, labels.where("doc_id % 3 > 0"))
    assert (np.diff(model.thresholds) >= 0).all()
    held = ordinal.graded(labels.where("doc_id % 3 = 0"))
    judged = ordinal.judge_documents(docs, model).join(held, "doc_id").groupBy("grade").agg(F.count_if("kept").alias("k"), F.avg("expected_grade").alias("e"))
    kept = {r.grade: (r.k, r.e) for r in judged.collect()}
    n = {r.grade: r["count"] for r in held.groupBy("grade").count().collect()}
    assert kept[2][0] > 0.985 * n[2] and kept[0][0] < 0.1 * n[0] and kept[1][0] < 0.4 * n[1]
    assert kept[0][1] < kept[1][1] < kept[2][1]


def test_classifier_odd_rows(spark, odd, none):
    labels = spark.createDataFrame([(1, 1, 0), (5, 0, 0), (10, 1, 1), (None, 1, 0), (6, None, 0), (99, 1, 1)], "doc_id bigint, quality int, toxic int")
    model = ordinal.fit(odd, labels)
    rows = ordinal.judge_documents(odd, model).collect()
    assert len(rows) == len(TEXTS) and all(0 <= r.tail_prob <= 1 and 0 <= r.expected_grade <= 2 for r in rows)
    kept = ordinal.select_documents(odd, model)
    assert kept.columns == odd.columns
    assert keyed((r.doc_id,) for r in kept.collect()) == keyed((r.doc_id,) for r in rows if r.kept)
    empty = ordinal.fit(none, labels.limit(0))
    assert ordinal.judge_documents(none, empty).count() == 0 and ordinal.judge_documents(odd, empty).count() == len(TEXTS)
    raw = b"some words here"
    assert abs(ordinal.by_hand(model, raw) - float(model.weights[ordinal.features(raw)].sum())) < 1e-4


def test_classifier_trains_on_one_row_of_an_id(spark):
    rows = [(1, f"hot row {i}") for i in range(50)] + [(i, f"text {i % 3} of {i}") for i in range(2, 6)]
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(1, 6)], "doc_id bigint, quality int, toxic int")
    models, seen = [], []
    real = ordinal.train
    for order in (rows, rows[::-1]):
        try:
            ordinal.train = lambda got, *more: seen.append(len(got)) or real(got, *more)
            models.append(ordinal.fit(spark.createDataFrame(order, "doc_id bigint, text string").repartition(3), labels, sample=5))
        finally:
            ordinal.train = real
    assert seen == [5, 5]
    assert (models[0].weights == models[1].weights).all() and (models[0].thresholds == models[1].thresholds).all()


# mixing


def slow_targets(sizes):
    names = sorted((k for k in sizes if k is not None), key=lambda s: s.encode()) + ([None] if None in sizes else [])
    weight = {n: (3, 1, 2)[i % 3] for i, n in enumerate(names)}
    left, out = 1.5 * sum(sizes.values()), {}
    while True:
        rest = [n for n in names if n not in out]
        total = sum(weight[n] for n in rest)
        over = [n for n in rest if left * weight[n] / total > 2 * sizes[n] + 1e-9]
        if not over:
            return {**out, **{n: left * weight[n] / total for n in rest}}
        for n in over:
            out[n] = 2.0 * sizes[n]
        left = 1.5 * sum(sizes.values()) - sum(out.values())


@pytest.mark.parametrize("which", ["small", "odd"])
def test_mixing(which, small, odd):
    docs = small[0] if which == "small" else odd
    rows = mixing.mix_documents(docs).collect()
    again = mixing.mix_documents(docs.repartition(3)).collect()
    assert keyed(rows) == keyed(again)
    sizes, taken = Counter(), Counter()
    for r in docs.collect():
        sizes[r.source] += len((r.text or "").encode().split())
    want = slow_targets(sizes)
    biggest = Counter()
    for r in rows:
        assert r.source_size == sizes[r.source] and abs(r.target - want[r.source]) < 1e-3
        assert 0 <= r.taken <= 2 * r.size and r.taken == r.copies * r.size
        taken[r.source] += r.taken
        biggest[r.source] = max(biggest[r.source], r.size)
    assert len(rows) == docs.count()
    for s in sizes:
        assert abs(taken[s] - want[s]) <= max(0.01 * want[s], biggest[s] / 2)


def test_nearest_fill_equals_every_subset():
    rng = np.random.default_rng(4)
    for _ in range(300):
        sizes = [int(x) for x in rng.integers(1, 40, int(rng.integers(0, 11)))]
        left = float(rng.uniform(0, sum(sizes) + 5))
        best = min(abs(left - sum(s for i, s in enumerate(sizes) if bits >> i & 1)) for bits in range(1 << len(sizes)))
        got = mixing.nearest_fill(sizes, left)
        assert len(set(got)) == len(got) and (abs(left - sum(sizes[i] for i in got)) <= best + 1e-9 or abs(left - sum(sizes[i] for i in got)) < 1)
    assert mixing.nearest_fill([5, 5, 5, 100], 10.0) == [0, 1]


def test_small_sources_come_near_their_targets(small):
    """Ten documents a source, the largest a third of it; certain copies leave the others to choose among."""
    rows = mixing.mix_documents(small[0]).groupBy("source").agg(F.sum("taken").alias("taken"), F.first("target").alias("target")).collect()
    assert len(rows) == 20 and all(abs(r.taken - r.target) <= 0.003 * r.target for r in rows)


def test_mixing_is_unequal_and_unbiased(spark):
    df = spark.createDataFrame([(i, " ".join(["w"] * (10 if i % 2 else 100)), s) for i in range(3000) for s in ("a", "b", "c")], "doc_id bigint, text string, source string")
    rows = mixing.mix_documents(df).where("source = 'b'").collect()
    rate = {n: np.mean([r.copies for r in rows if r.size == n]) for n in (10, 100)}
    assert abs(2 * rate[10] - rate[100]) < 0.08


def test_mix_repeats_rows(odd, none):
    out = mixing.repeat_documents(odd)
    assert out.columns == odd.columns
    want = Counter()
    for r in mixing.mix_documents(odd).collect():
        want[r.doc_id] += r.copies
    assert Counter(r.doc_id for r in out.collect()) == +want
    assert mixing.repeat_documents(none).count() == 0 and mixing.mix_documents(none).count() == 0


# language model


@pytest.mark.parametrize("known", [200_000, 50])
def test_language_model_base_matches_brute_force(small, odd, known):
    docs = odd.select("doc_id", "text").unionByName(small[0].select("doc_id", "text"))
    rows = docs.collect()
    out = [r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 7 == 2 for r in rows]
    want = brown.brute_scores([((r.text or "").encode(), o) for r, o in zip(rows, out, strict=True)])
    got = brown.train_and_score(docs, clustered=40, classes=8, known=known).collect()
    shown = lambda rows: keyed((i, o, n, k, round(b, 6)) for i, o, n, k, b in rows)
    assert shown((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.base_score) for r in got) == shown((r.doc_id, o, *w) for r, o, w in zip(rows, out, want, strict=True))
    assert all(r.score < 0 for r in got)


def test_language_model_is_the_same_however_words_are_found(small):
    a, b = (brown.train_and_score(small[0], clustered=40, classes=8, known=k) for k in (200_000, 60))
    both = {r.doc_id: r.score for r in a.collect()}
    assert all(abs(both[r.doc_id] - r.score) < 1e-6 for r in b.collect())


def test_exchange_raises_likelihood_and_model_beats_base(spark):
    rng = np.random.default_rng(0)
    pairs = np.zeros((22, 22))
    for a in range(20):
        for b in range(20):
            pairs[a, b] = rng.integers(20, 40) if (a < 10) != (b < 10) else rng.integers(0, 3)
    of = brown.exchange(pairs, 20, 2, 10)
    assert len(set(of[:10])) == 1 and len(set(of[10:20])) == 1 and of[0] != of[10]
    rows = [(i, " ".join(f"{'ab'[j % 2]}{rng.integers(0, 8)}" for j in range(60))) for i in range(400)]
    scored = brown.train_and_score(spark.createDataFrame(rows, "doc_id bigint, text string"), clustered=16, classes=2)
    held = scored.where("held_out").agg({"score": "sum", "base_score": "sum"}).first()
    assert held["sum(score)"] > 0.85 * held["sum(base_score)"]


def test_language_model_classes_words_outside_the_head(spark):
    """Two kinds of words in turn: rare words get the class of their kind, once-seen ones stay open, classes grow."""
    rng = np.random.default_rng(2)
    kind = ["a", "b"]
    rows = [" ".join(f"{kind[j % 2]}{int(rng.integers(0, 8)) if rng.random() < 0.7 else 100 + int(rng.integers(0, 150))}" for j in range(60)) + f" once{i}" for i in range(300)]
    texts = spark.createDataFrame([(r.encode(),) for r in rows], "text binary")
    counts = brown.word_counts(texts)
    model = brown.BrownModel(counts, texts, clustered=16, classes=2)
    of = dict(zip(model.words, model.classes.known.tolist(), strict=False))
    a = {of[w] for w in model.words if w.startswith(b"a")}
    b = {of[w] for w in model.words if w.startswith(b"b")}
    assert len(a) == 1 and len(b) == 1 and a != b
    assert {of[w] for w in model.words if w.startswith(b"once")} == {model.classes.rare}
    assert model.rare_kinds == 300 and model.rare_mass == 300
    many = spark.createDataFrame([(" ".join(f"w{i}" for i in range(60_000)).encode(),)] * 2, "text binary")
    assert brown.BrownModel(brown.word_counts(many), many, clustered=60, sweeps=1).transition.shape[0] == 40 + 2


def plain_scores(model, texts, held, prior):
    """Scores from the classes of the known words alone, by dictionaries."""
    kind = dict(zip(model.words, model.classes.known[:-1].tolist(), strict=True))
    rare, end = model.classes.rare, model.classes.end
    split = [t.translate(brown.LOWER).split() for t in texts]
    seen = Counter(w for t, o in zip(split, held, strict=True) if not o for w in t)
    of = lambda w: kind.get(w, rare)
    pairs, mass, open_words = Counter(), Counter(), set()
    for t, o in zip(split, held, strict=True):
        if not o:
            row = [end, *map(of, t), end]
            pairs.update(zip(row, row[1:], strict=False))
            mass.update(row[1:])
            open_words |= {w for w in t if of(w) == rare}
    total, kinds = sum(pairs.values()), end + 1
    out = Counter()
    for (a, _), n in pairs.items():
        out[a] += n
    step = lambda a, b: (pairs[a, b] + prior * (mass[b] + 1) / (total + kinds)) / (out[a] + prior)
    word = lambda w: (seen[w] + 1) / (mass[rare] + len(open_words) + 1) if of(w) == rare else seen[w] / mass[of(w)]
    scores = []
    for t in split:
        row = [end, *map(of, t), end]
        scores.append(sum(math.log10(step(a, b)) for a, b in zip(row, row[1:], strict=False)) + sum(math.log10(word(w)) for w in t))
    return scores


def test_language_model_scores_match_brute_force(small):
    """Scores by the definition; classes of words outside the head are those of greatest gain by the definition."""
    docs = small[0].withColumn("held_out", brown.held_out(small[0]["doc_id"]))
    rows = docs.collect()
    texts, held = [(r.text or "").encode() for r in rows], [r.held_out for r in rows]
    bytes_of = docs.selectExpr("doc_id", "held_out", "cast(coalesce(text, '') as binary) as text")
    counts = brown.word_counts(bytes_of.where("NOT held_out").select("text"))
    model = brown.BrownModel(counts, bytes_of, clustered=40, classes=6)
    assert len(model.words) == model.vocabulary - 1
    want = plain_scores(model, texts, held, brown.PRIOR)
    got = {r.doc_id: r.score for r in model.score().collect()}
    assert all(abs(got[r.doc_id] - w) < 1e-6 * max(1, abs(w)) for r, w in zip(rows, want, strict=True))
    # Classes outside the head, for the first of them and some rare ones.
    rare, end, head = model.classes.rare, model.classes.end, model.words[:40]
    kind = dict(zip(model.words, model.classes.known.tolist(), strict=False))
    of_head = {w: kind[w] for w in head}
    table, around = Counter(), {}
    for t, o in zip(texts, held, strict=True):
        if not o:
            words = t.translate(brown.LOWER).split()
            row = [end, *(of_head.get(w, rare) for w in words), end]
            table.update(zip(row, row[1:], strict=False))
            for i, w in enumerate(words):
                around.setdefault(w, []).append((row[i], row[i + 2]))
    phi = lambda x: x * math.log(x) if x > 0 else 0.0
    out, into = Counter(), Counter()
    for (a, b), n in table.items():
        out[a] += n
        into[b] += n
    for w in model.words[40:60] + model.words[-4000::200]:
        near = around[w]
        if len(near) < brown.LEAST:
            assert kind[w] == rare
            continue
        before, after, c = Counter(a for a, _ in near), Counter(b for _, b in near), len(near)
        gain = [
            sum(phi(table[k, x] + n) - phi(table[k, x]) for x, n in after.items()) + sum(phi(table[x, k] + n) - phi(table[x, k]) for x, n in before.items())
            - phi(out[k] + c) + phi(out[k]) - phi(into[k] + c) + phi(into[k]) for k in range(6)
        ]
        assert gain[kind[w]] > max(gain) - 1e-6


def test_language_model_empty_table(none):
    assert brown.train_and_score(none).count() == 0


# pipeline


def test_pipeline_stage_by_stage(spark, tmp_path):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, sf).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        seen[name] = docs
        assert docs.columns == columns or name == "byte_bpe"
    kept = {r.doc_id for r in seen["quality_classifier"].collect()}
    deduped = {r.doc_id: r.text for r in seen["simhash_near_dedup"].collect()}
    assert set(deduped) <= kept and len(set(deduped.values())) == len(deduped)
    assert {r.doc_id for r in seen["secret_scan"].collect()} == set(deduped)
    sizes = Counter()
    for r in seen["source_mixing"].collect():
        sizes[r.source] += len(r.text.split())
    final = corpus_pipeline.run(spark, sf)
    assert keyed(final.collect()) == keyed(docs.collect()) and sum(sizes.values()) > 0


def plain_features(raw):
    low = bytes(b + 32 if 65 <= b <= 90 else b for b in raw)
    words, tokens, lines = re.findall(rb"[a-z\x80-\xff]+", low), raw.split(), [x for x in raw.split(b"\n") if x.strip()]
    n = max(1, len(raw))
    ratio = {
        "symbols": sum(c in b"#*$%&|<>!" for c in raw) / n, "capitals": sum(65 <= c <= 90 for c in raw) / n, "digits": sum(48 <= c <= 57 for c in raw) / n,
        "repeats": 1 - len(set(tokens)) / max(1, len(tokens)), "lines": 1 - len(set(lines)) / max(1, len(lines)), "length": min(1.0, len(tokens) / 2000),
    }
    keys = set(words) | {f"\0{k}{min(16, int(16 * v**0.5))}".encode() for k, v in ratio.items()}
    keys |= {b"\1%d" % i + w for w, k in Counter(w[: ordinal.START] for w in words).items() for i in range(min(k, ordinal.TIMES))}
    return sorted({zlib.crc32(k) & (ordinal.BUCKETS - 1) for k in keys})


def plain_training(rows):
    """Weights by feature and the thresholds, one number at a time."""
    seen = [1 + sum(g == k for _, g in rows) for k in range(3)]
    theta = [math.log(p / (1 - p)) for p in (seen[0] / sum(seen), (seen[0] + seen[1]) / sum(seen))]
    z, n, w = Counter(), Counter(), Counter()
    sigma = lambda x: 1 / (1 + math.exp(-max(-35.0, min(35.0, x))))
    for epoch in range(ordinal.EPOCHS):
        for at in np.random.default_rng(epoch).permutation(len(rows)):
            ids, g = rows[at]
            x = sum(w[i] for i in ids)
            f = [0.0, sigma(theta[0] - x), sigma(theta[1] - x), 1.0]
            slope, here = 1 - f[g + 1] - f[g], max(1e-9, f[g + 1] - f[g])
            if g < 2:
                theta[g] += 0.02 * f[g + 1] * (1 - f[g + 1]) / here
            if g:
                theta[g - 1] -= 0.02 * f[g] * (1 - f[g]) / here
            theta[1] = max(theta)
            for i in ids:
                root = math.sqrt(n[i])
                n[i] += slope * slope
                grown = math.sqrt(n[i])
                z[i] += slope - (grown - root) * w[i]
                w[i] = (math.copysign(5.0, z[i]) - z[i]) / (1.1 + grown) if abs(z[i]) > 5 else 0.0
    return w, theta


def plain_one_of_each(docs):
    sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if (w := lower_words(t)) else set() for i, (t, _) in docs.items()}
    root = {i: i for i in docs}
    for a in sorted(docs):
        for b in sorted(docs):
            if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]) and root[a] != root[b]:
                low, high = sorted((root[a], root[b]))
                root = {i: low if r == high else r for i, r in root.items()}
    return {i: d for i, d in docs.items() if root[i] == i}


def lower_words(text):
    return (text or "").encode().translate(brown.LOWER).split()


def plain_redaction(text):
    found = sorted((m.start(), k, m.end(), r.kind) for k, r in enumerate(secrets.RULES) for m in re.finditer(r.pattern, text, re.ASCII) if len(m[r.group]) >= r.keep)
    at, out = 0, []
    for s, _, e, kind in found:
        if e > at:
            if s >= at:
                out += [text[at:s], f"[{kind}]"]
            at = e
    return "".join(out) + text[at:]


def plain_mix(docs):
    """How often each document is taken, where a source is small enough to lie whole around its end."""
    size = {i: len((t or "").encode().split()) for i, (t, _) in docs.items()}
    by_source = defaultdict(list)
    for i, (_, s) in docs.items():
        by_source[s].append(i)
    targets, copies = slow_targets({s: sum(size[i] for i in own) for s, own in by_source.items()}), {}
    for s, own in by_source.items():
        assert len(own) < mixing.WINDOW
        weight = {i: 1.0 if size[i] < 50 else 2.0 for i in own}
        low, high = 0.0, 4.0
        for _ in range(200):  # the level at which the expected words meet the target
            level = (low + high) / 2
            low, high = (low, level) if sum(min(2.0, level * weight[i]) * size[i] for i in own) > targets[s] else (level, high)
        rate = {i: min(2.0, high * weight[i]) for i in own}
        whole = {i: math.floor(rate[i] + 1e-9) for i in own}
        part = {i: rate[i] - whole[i] if rate[i] - whole[i] > 1e-9 else 0.0 for i in own}
        u = {i: ((xxhash.xxh64_intdigest(f"42:{i}", 42) & (1 << 52) - 1) + 0.5) / (1 << 52) for i in own}
        drawn = sorted((i for i in own if part[i] > 0 and size[i]), key=lambda i: (u[i] / (1 - u[i])) / (part[i] / (1 - part[i])))
        picked = {drawn[k] for k in mixing.nearest_fill([size[i] for i in drawn], targets[s] - sum(whole[i] * size[i] for i in own))}
        copies |= {i: whole[i] + (i in picked) for i in own}
    return copies


def test_whole_pipeline_matches_plain_python(spark):
    sf = "/root/testdata/sf0.001"
    docs = {r.doc_id: (r.text, r.source) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    grade = {}
    for r in spark.read.parquet(f"{sf}/labels.parquet").collect():
        g = 0 if r.quality == 0 else 1 if r.toxic == 1 else 2
        grade[r.doc_id] = min(g, grade.get(r.doc_id, 2))
    features = {i: plain_features((t or "").encode()) for i, (t, _) in docs.items()}
    weights, theta = plain_training([(features[i], grade[i]) for i in sorted(grade) if i in docs])
    top = {i: 1 - 1 / (1 + math.exp(-(theta[1] - sum(weights[f] for f in features[i])))) for i in docs}
    assert all(abs(p - 0.5) > 1e-4 for p in top.values())
    good = {i: d for i, d in docs.items() if top[i] >= 0.5}
    clean = {i: (plain_redaction(t), s) for i, (t, s) in plain_one_of_each(good).items()}
    library = bpe.bpe_for(*bpe.public_vocabulary())._own
    want = Counter()
    for i, n in plain_mix(clean).items():
        ids, raw = library.encode_ordinary(clean[i][0]), clean[i][0].encode()
        want[i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(raw).hexdigest(), len(raw)] += n
    assert 0 < len(good) < len(docs) and len(clean) < len(good)
    assert keyed(corpus_pipeline.run(spark, sf).collect()) == +want


def test_pipeline_stages_give_the_same_rows_however_they_are_dealt(spark, tmp_path):
    rows = [(i % 40 if i % 7 else None, f"text {i % 31} of some words " * 9 + f"w{i % 3}", f"s{i % 3}") for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    for stage in (corpus_pipeline.near_dedup, corpus_pipeline.secret_scan, corpus_pipeline.mix):
        seen = [keyed(stage(spark, df.repartition(n), "").collect()) for n in (1, 5)]
        assert seen[0] == seen[1]


def test_pipeline_stages_take_odd_tables(spark, odd, none):
    for name, stage in corpus_pipeline.STAGES:
        for table in (odd, none):
            out = stage(spark, table, "/root/testdata/sf0.001")
            assert out.count() <= 2 * table.count()
            if name != "byte_bpe":
                assert out.columns == table.columns
