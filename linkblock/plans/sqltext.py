"""Common table expressions of the SQL twins: definitions over exploded rows, not the array code of the engine."""

from __future__ import annotations

from linkblock.functions.hashing import WIDTH, mix_sql
from linkblock.functions.names import PRESETS, form_likeness, key_places, letters, sound_likeness
from linkblock.operators.sketch import PROBES, bin_width
from linkblock.sources.tables import HEX, LETTERS, MISTAKEN


def u32(x: str) -> str:
    return f"(('0x' || substr(md5({x}), 1, 8))::BIGINT)"


def reports() -> str:
    """CTEs up to `reports` and `truth`."""
    name = lambda x, n: f"translate(substr(md5({x}), 1, {n}), '{HEX}', '{LETTERS}')"
    u = lambda tag, n=100: u32(f"'{tag}' || k") + f" % {n}"
    return f"""
first_order AS (SELECT o_custkey, min(o_orderdate)::DATE AS day FROM orders GROUP BY o_custkey),
people AS (SELECT c_custkey::BIGINT AS k, day, c_nationkey::INT AS place FROM customer LEFT JOIN first_order ON c_custkey = o_custkey),
named AS (SELECT *, {name("k::VARCHAR", 6)} AS given, {name("'f' || (k % 97)", 5)} AS family, ({u('p', 6)})::INT AS slip FROM people),
reports AS (
  SELECT 3 * k AS rec_id, k, 'A' AS list, given, family, day AS event_date, place FROM named WHERE {u('A')} < 60
  UNION ALL SELECT 3 * k + 1, k, 'B', CASE WHEN {u('t')} < 60 THEN substr(given, 1, slip) || translate(substr(given, slip + 1, 1), '{LETTERS}', '{MISTAKEN}') || substr(given, slip + 2) ELSE given END,
    family, CASE WHEN {u('d')} < 25 THEN (day + INTERVAL 1 DAY)::DATE ELSE day END, place FROM named WHERE {u('B')} < 40
  UNION ALL SELECT 3 * k + 2, k, 'C', given, CASE WHEN {u('m')} < 70 THEN family ELSE '' END, day, (CASE WHEN {u('q')} < 20 THEN (place + 1) % 25 ELSE place END)::INT FROM named WHERE {u('C')} < 25),
truth AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi FROM reports a JOIN reports b ON a.k = b.k AND a.rec_id < b.rec_id)"""


def doc_words(table: str = "documents", id_col: str = "doc_id", text: str = "text") -> str:
    """CTE words(rec_id, tok, p)."""
    return f"""
word_lists AS (SELECT {id_col} AS rec_id, regexp_extract_all(lower({text}), '[\\p{{L}}\\p{{N}}]+') AS l FROM {table}),
words AS (SELECT rec_id, unnest(l) AS tok, generate_subscripts(l, 1) AS p FROM word_lists)"""


def doc_grams(n: int = 3, **kw: str) -> str:
    """CTEs up to grams(rec_id, tok), bag(rec_id, tok, cnt), toks(rec_id, tok, h): word n-grams with repeats, counted, distinct."""
    joined = " || ' ' || ".join(["tok", *(f"lead(tok, {i}) OVER (PARTITION BY rec_id ORDER BY p)" for i in range(1, n))])
    return doc_words(**kw) + f""",
grams AS (SELECT rec_id, g AS tok FROM (SELECT rec_id, {joined} AS g FROM words) WHERE g IS NOT NULL),
bag AS (SELECT rec_id, tok, count(*) AS cnt, {u32('tok')} AS h FROM grams GROUP BY rec_id, tok),
toks AS (SELECT DISTINCT rec_id, h FROM bag)"""


def doc_truth(t: float = 0.5) -> str:
    """CTEs after doc_grams(): sizes, shared, doc_truth(id_lo, id_hi)."""
    return f"""
sizes AS (SELECT rec_id, count(*) AS n FROM bag GROUP BY rec_id),
shared AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi, count(*) AS n_common FROM bag a JOIN bag b ON a.tok = b.tok AND a.rec_id < b.rec_id GROUP BY 1, 2),
scored AS (SELECT id_lo, id_hi, n_common, x.n + y.n - n_common AS n_union FROM shared JOIN sizes x ON id_lo = x.rec_id JOIN sizes y ON id_hi = y.rec_id),
doc_truth AS (SELECT id_lo, id_hi FROM scored WHERE n_common >= n_union * {t} - 1e-9)"""


def report_toks() -> str:
    """CTEs after reports(): rtoks(rec_id, h), tagged character pairs of names, month, day and place."""
    pairs = lambda tag, c: f"SELECT rec_id, '{tag}:' || substr({c}, i::INT, 2) AS tok FROM (SELECT rec_id, {c}, unnest(range(1, length({c}))) AS i FROM reports)"
    return f"""
rtagged AS ({pairs('g', 'given')} UNION ALL {pairs('f', 'family')}
  UNION ALL SELECT rec_id, 'm:' || strftime(event_date, '%Y-%m') FROM reports WHERE event_date IS NOT NULL
  UNION ALL SELECT rec_id, 'd:' || day(event_date) FROM reports WHERE event_date IS NOT NULL
  UNION ALL SELECT rec_id, 'p:' || place FROM reports),
rtoks AS (SELECT DISTINCT rec_id, {u32('tok')} AS h FROM rtagged)"""


def bins(n: int, source: str = "toks", out: str = "bins") -> str:
    return f"{out} AS (SELECT rec_id, h // {bin_width(n)} AS bin, min(h) AS val FROM {source} GROUP BY 1, 2)"


def filled(n: int, how: str, source: str = "bins", out: str = "filled") -> str:
    """CTEs up to out(rec_id, bin, val, dist) from bins, by nearest filled bin, coin or probes."""
    every = f"{out}_all AS (SELECT DISTINCT rec_id, b FROM {source}, range({n}) r(b))"
    ahead, behind = f"(s.bin - b + {n}) % {n}", f"(b - s.bin + {n}) % {n}"
    near = lambda d, name: f"{name} AS (SELECT a.rec_id, b AS bin, arg_min(val, {d}) AS val, min({d}) AS dist FROM {out}_all a JOIN {source} s ON a.rec_id = s.rec_id GROUP BY a.rec_id, b)"
    if how == "rotate":
        return f"{every}, {near(ahead, out)}"
    if how == "coin":
        coin = f"({mix_sql('bin * 7919 + 13', '77')} // 65536) % 2 = 0"
        return f"{every}, {near(ahead, out + '_f')}, {near(behind, out + '_b')}, {out} AS (SELECT f.rec_id, f.bin, CASE WHEN {coin.replace('bin', 'f.bin')} THEN f.val ELSE k.val END AS val, CASE WHEN {coin.replace('bin', 'f.bin')} THEN f.dist ELSE k.dist END AS dist FROM {out}_f f JOIN {out}_b k ON f.rec_id = k.rec_id AND f.bin = k.bin)"
    at = f"({mix_sql('b * 1009 + t', '78')} // 65536) % {n}"
    return f"""{every}, {near(ahead, out + '_f')},
{out}_tries AS (SELECT b, t, {at} AS asked FROM range({n}) r(b), range(1, {PROBES + 1}) q(t)),
{out}_hits AS (SELECT s.rec_id, b, arg_min(val, t) AS val, min(t) AS t FROM {out}_tries JOIN {source} s ON s.bin = asked GROUP BY s.rec_id, b),
{out} AS (SELECT f.rec_id, f.bin, CASE WHEN f.dist = 0 THEN f.val ELSE coalesce(h.val, f.val) END AS val, CASE WHEN f.dist = 0 THEN 0 ELSE coalesce(h.t, f.dist + {PROBES}) END AS dist
  FROM {out}_f f LEFT JOIN {out}_hits h ON f.rec_id = h.rec_id AND f.bin = h.b)"""


def per_table(k: int, tables: int, source: str, out: str = "filled", seed: int = 500) -> str:
    """CTEs up to out(rec_id, table_no, bin, val, dist)."""
    return f"""
{out}_mixed AS (SELECT rec_id, t AS table_no, {mix_sql('h', f't + {seed}')} AS h FROM {source}, range({tables}) r(t)),
{out}_bins AS (SELECT rec_id, table_no, h // {bin_width(k)} AS bin, min(h) AS val FROM {out}_mixed GROUP BY 1, 2, 3),
{out} AS (SELECT s.rec_id, s.table_no, b AS bin, arg_min(val, (bin - b + {k}) % {k}) AS val, min((bin - b + {k}) % {k}) AS dist FROM {out}_bins s, range({k}) r(b) GROUP BY 1, 2, 3)"""


def band_keys(k: int, source: str = "filled", out: str = "bands", tables: int | None = None) -> str:
    """out(rec_id, table_no, key): the k values of each table; with tables, source has a table_no of its own."""
    table = "table_no" if tables else f"bin // {k}"
    return f"{out} AS (SELECT rec_id, {table} AS table_no, string_agg((val * 1024 + least(dist, 1023))::VARCHAR, '-' ORDER BY bin) AS key FROM {source} GROUP BY 1, 2)"


def band_pairs(source: str = "bands", out: str = "band_pairs") -> str:
    return f"{out} AS (SELECT a.rec_id AS id_lo, b.rec_id AS id_hi, min(a.table_no) AS first_table FROM {source} a JOIN {source} b ON a.table_no = b.table_no AND a.key = b.key AND a.rec_id < b.rec_id GROUP BY 1, 2)"


def quality(method: str, pairs: str, truth: str, n: str) -> str:
    """A SELECT of one row: method, n_pairs, n_true, n_hit, recall, rr, prec."""
    return f"""SELECT '{method}' AS method, n_pairs, n_true, n_hit, round(n_hit / nullif(n_true, 0), 6) AS recall, round(1 - n_pairs / nullif(n_rows * (n_rows - 1) / 2, 0), 6) AS rr, round(n_hit / nullif(n_pairs, 0), 6) AS prec
FROM (SELECT (SELECT count(*) FROM {pairs}) AS n_pairs, (SELECT count(*) FROM {truth}) AS n_true, (SELECT count(*) FROM {pairs} p JOIN {truth} t ON p.id_lo = t.id_lo AND p.id_hi = t.id_hi) AS n_hit, ({n}) AS n_rows)"""


def vectors(weights: str, p: int, out: str = "vec") -> str:
    """CTEs up to out(rec_id, j, x) from weights(rec_id, h, w): projections by random signs, of length 1."""
    return f"""
{out}_sums AS (SELECT rec_id, j, sum(w * CASE WHEN ({mix_sql('h', '4000 + j')} // 65536) % 2 = 0 THEN 1 ELSE -1 END) AS x FROM {weights}, range({p}) r(j) GROUP BY 1, 2),
{out}_norms AS (SELECT rec_id, sqrt(sum(x * x)) AS n FROM {out}_sums GROUP BY rec_id),
{out} AS (SELECT rec_id, j, round(CASE WHEN n > 0 THEN x / n ELSE 0 END, 6) AS x FROM {out}_sums JOIN {out}_norms USING (rec_id))"""


def _ranked(tag: str, source: str, part: str = "") -> str:
    return f"row_number() OVER ({part} ORDER BY {u32(f"'{tag}' || rec_id")}, rec_id) - 1 AS k FROM {source}"


def _rounds(vec: str, first: str, rounds: int, out: str, group: str = "") -> str:
    """CTEs up to out(rec_id, k and group) by Lloyd rounds from the centres first(k, j, x and group); vec has the group too."""
    g, same = (f", {group}", f" AND v.{group} = c.{group}") if group else ("", "")
    text, centres = [], first
    for i in range(rounds + 1):
        name = out if i == rounds else f"{out}_a{i}"
        text.append(f"""{name} AS (SELECT rec_id{g}, k FROM (SELECT rec_id{g}, k, row_number() OVER (PARTITION BY rec_id ORDER BY s DESC, k) AS place FROM (
  SELECT v.rec_id{', v.' + group if group else ''}, c.k, round(sum(v.x * c.x) - sum(c.x * c.x) / 2, 9) AS s FROM {vec} v JOIN {centres} c ON v.j = c.j{same} GROUP BY ALL)) WHERE place = 1)""")
        if i < rounds:
            text.append(f"""{out}_m{i} AS (SELECT a.k{', a.' + group if group else ''}, v.j, round(avg(v.x), 9) AS x FROM {name} a JOIN {vec} v ON a.rec_id = v.rec_id GROUP BY ALL),
{out}_c{i} AS (SELECT k, j{g}, coalesce(m.x, c.x) AS x FROM {centres} c LEFT JOIN {out}_m{i} m USING (k, j{g}))""")
            centres = f"{out}_c{i}"
    return ", ".join(text)


def kmeans(count: str, rounds: int, vec: str = "vec", out: str = "clusters") -> str:
    """CTEs up to out(rec_id, k): rounds of means from the `count` records of least hashed id."""
    return f"""{out}_first AS (SELECT k, j, x FROM (SELECT rec_id, {_ranked('seed', f'(SELECT DISTINCT rec_id FROM {vec})')}) JOIN {vec} USING (rec_id) WHERE k < {count}), """ + _rounds(vec, f"{out}_first", rounds, out)


def two_levels(n: str, size: int, rounds: int, vec: str = "vec", out: str = "clusters") -> str:
    """CTEs up to out(rec_id, cluster): a coarse partition, and inside each part a share of the rest."""
    return f"""{out}_n AS (SELECT ceil(({n}) / {size}.0) AS c, greatest(1, round(sqrt(ceil(({n}) / {size}.0)))) AS coarse_n), {out}_i AS (SELECT ceil(c / coarse_n)::BIGINT AS inner_n, coarse_n::BIGINT AS coarse_n FROM {out}_n),
{kmeans(f'(SELECT coarse_n FROM {out}_i)', rounds, vec, out + '_co')}, {out}_v AS (SELECT v.rec_id, v.j, v.x, c.k AS part FROM {vec} v JOIN {out}_co c ON v.rec_id = c.rec_id),
{out}_first AS (SELECT f.k, v.j, v.x, v.part FROM (SELECT rec_id, {_ranked('fine', f'(SELECT rec_id, k AS part FROM {out}_co)', 'PARTITION BY part')}) f JOIN {out}_v v USING (rec_id) WHERE f.k < (SELECT inner_n FROM {out}_i)),
{_rounds(out + '_v', out + '_first', rounds, out + '_fine', 'part')}, {out} AS (SELECT rec_id, part * (SELECT inner_n FROM {out}_i) + k AS cluster FROM {out}_fine)"""


def letter_costs(preset: str) -> str:
    """A SELECT of a, b, cost from the three tables of likeness."""
    w = PRESETS[preset]
    known = letters()
    row = lambda *x: "(" + ", ".join(f"'{v}'" if isinstance(v, str) else str(v) for v in x) + ")"
    like = lambda f: ", ".join(row(a, b, f(a, b)) for a in known for b in known if a != b and f(a, b) > 0) or "('', '', 0.0)"
    places = ", ".join(row(c, x, y) for c, (x, y) in key_places().items())
    return f"""SELECT l.a, m.b, CASE WHEN l.a = m.b THEN 0 ELSE ({w.sound} * (1 - coalesce(s.s, 0)) + {w.form} * (1 - coalesce(f.s, 0))
  + {w.key} * (1 - coalesce(greatest(0, 1 - sqrt(pow(p.x - q.x, 2) + pow(p.y - q.y, 2)) / 12.0), 0))) / {w.sound + w.form + w.key} END AS cost
FROM (VALUES {", ".join(row(c) for c in known)}) l(a) CROSS JOIN (VALUES {", ".join(row(c) for c in known)}) m(b)
LEFT JOIN (VALUES {like(sound_likeness)}) s(a, b, s) ON s.a = l.a AND s.b = m.b
LEFT JOIN (VALUES {like(form_likeness)}) f(a, b, s) ON f.a = l.a AND f.b = m.b
LEFT JOIN (VALUES {places}) p(c, x, y) ON p.c = l.a LEFT JOIN (VALUES {places}) q(c, x, y) ON q.c = m.b"""


def distances(pairs: str, a: str, b: str, costs: str | None, out: str = "dist") -> str:
    """Recursive CTE out(id_lo, id_hi, d): edit distance of two columns of `pairs`, a table row a step; costs: a CTE of letter costs."""
    left, right = f"substr({a}, i + 1, 1)", f"substr({b}, t::INT, 1)"
    swap = f"(CASE WHEN {left} = {right} THEN 0.0 ELSE {'1.0' if costs is None else f'coalesce(m[{left} || {right}], 1.0)'} END)"
    table = "MAP {'': 0.0}" if costs is None else f"(SELECT map(list(a || b), list(cost::DOUBLE)) FROM {costs})"
    return f"""
{out}_steps AS (
  SELECT id_lo, id_hi, {a}, {b}, 0 AS i, list_transform(range(0, length({b}) + 1), lambda j: j::DOUBLE) AS row, {table} AS m FROM {pairs}
  UNION ALL
  SELECT id_lo, id_hi, {a}, {b}, i + 1, list_transform(range(0, length({b}) + 1), lambda j: j + list_min(list_transform(range(0, j + 1), lambda t: c[t + 1] - t))), m
  FROM (SELECT id_lo, id_hi, {a}, {b}, i, m, list_transform(range(0, length({b}) + 1), lambda t: CASE WHEN t = 0 THEN row[1] + 1.0 ELSE least(row[t + 1] + 1.0, row[t] + {swap}) END) AS c FROM {out}_steps WHERE i < length({a}))),
{out} AS (SELECT id_lo, id_hi, row[length({b}) + 1] AS d FROM {out}_steps WHERE i = length({a}))"""


__all__ = ["WIDTH"]
