"""URL filter: prefix rules first, then a weighted vocabulary of strict and soft terms.

The longest rule that fits a URL decides it. For the rest, one Aho-Corasick
pass over the lower-cased URL finds every term that stands between boundaries
(no letter or digit next to it); one strict term or SOFT_LIMIT distinct soft
terms block the URL. Rules and terms are a configuration of checked size, so
they travel with the function; load_terms() and load_rules() take them from
tables, and the constants here are what the query uses without such tables.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkblock.llm.common import LOWER, whole_id

#: Fixed values: (host, path, verdict).
RULES: tuple[tuple[str, str, str], ...] = (
    ("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"), ("com", "/de/", "block"),
)
STRICT: tuple[str, ...] = ("spam-farm", "cheap-pills", "viagra", "xxx", "porn", "warez")
SOFT: tuple[str, ...] = ("casino", "bet", "poker", "pills", "cheap", "free", "win", "adult", "dating", "loan", "crack", "spam")
SOFT_LIMIT = 2


#: A vocabulary or rule table that travels with the function has at most so many rows; more is an error, never a cut.
MOST_TERMS = 1_000_000


def load_terms(terms: DataFrame, term_col: str = "term", weight_col: str = "weight", strict_from: int = 2) -> tuple[tuple[str, ...], tuple[str, ...]]:
    """(strict, soft) from a table of terms: strict from weight strict_from on, soft from 1; others are left out.

    Terms are taken in lower case; null and empty ones are skipped, of a term
    that occurs twice the greater weight holds.
    """
    rows = terms.where(F.col(term_col) != "").groupBy(F.lower(F.col(term_col)).alias("term")).agg(F.max(weight_col).alias("weight"))
    found = _bounded(rows.where("weight >= 1"))
    return tuple(sorted(r.term for r in found if r.weight >= strict_from)), tuple(sorted(r.term for r in found if r.weight < strict_from))


def load_rules(rules: DataFrame) -> tuple[tuple[str, str, str], ...]:
    """Rules from a table (host, path, verdict); null hosts or paths and other verdicts than allow and block are errors."""
    found = [(r.host, r.path, r.verdict) for r in _bounded(rules.select("host", "path", "verdict").distinct())]
    if any(h is None or p is None or v not in ("allow", "block") for h, p, v in found):
        raise ValueError("a rule needs a host, a path and allow or block")
    return tuple(sorted(found))


def _bounded(df: DataFrame) -> list:
    found = df.limit(MOST_TERMS + 1).collect()
    if len(found) > MOST_TERMS:
        raise ValueError(f"more than {MOST_TERMS} rows to send to every worker")
    return found


def split_url(url: str | None) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path; both empty for null and without '://'."""
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    for stop in "?#":
        rest = rest.split(stop, 1)[0]
    host, slash, path = rest.partition("/")
    return host.encode().translate(LOWER).decode(), slash + path


def rule_of(host: str, path: str, rules=RULES) -> tuple[str | None, str | None]:
    """(rule as text, its verdict) of the longest rule that fits, else nulls; equal lengths: the first by code point."""
    by_host, fits = _rule_table(rules), []
    for h in ([host] + [host[i + 1 :] for i, c in enumerate(host) if c == "."]) if host else []:
        fits += [(h + p, v) for p, v in by_host.get(h, ()) if path.startswith(p)]
    return min(fits, key=lambda x: (-len(x[0]), x[0]), default=(None, None))


@lru_cache(8)
def _rule_table(rules: tuple[tuple[str, str, str], ...]) -> dict[str, list[tuple[str, str]]]:
    by: dict[str, list[tuple[str, str]]] = {}
    for h, p, v in rules:
        by.setdefault(h, []).append((p, v))
    return by


@lru_cache(8)
def _automaton(strict: tuple[str, ...], soft: tuple[str, ...]):
    import ahocorasick

    a = ahocorasick.Automaton()
    for terms, weight in ((soft, 1), (strict, 2)):
        for t in terms:
            a.add_word(t, (t, weight))
    a.make_automaton()
    return a


def term_hits(url: str, strict=STRICT, soft=SOFT) -> tuple[int, int]:
    """Distinct strict and soft terms that stand between boundaries."""
    low = url.encode().translate(LOWER).decode()
    edge = lambda i: not (0 <= i < len(low) and low[i].isascii() and low[i].isalnum())
    found = {hit for end, hit in _automaton(strict, soft).iter(low) if edge(end + 1) and edge(end - len(hit[0]))} if strict or soft else set()
    return sum(w == 2 for _, w in found), sum(w == 1 for _, w in found)


def judge_urls(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules=RULES, strict=STRICT, soft=SOFT, soft_limit: int = SOFT_LIMIT) -> DataFrame:
    """(page_id, host, path, rule, verdict, n_strict, n_soft) for every row.

    rules, strict, soft: tuples as above or from load_rules() and load_terms().
    Null urls have an empty host and path, no rule and no terms, and are
    allowed. Repeated rows are judged alike; an empty table gives no rows.
    """
    fields = pa.schema([("page_id", pa.int64()), ("host", pa.string()), ("path", pa.string()), ("rule", pa.string()), ("verdict", pa.string()), ("n_strict", pa.int64()), ("n_soft", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = []
            for url in b.column("url").to_pylist():
                host, path = split_url(url)
                rule, verdict = rule_of(host, path, rules)
                hard, mild = term_hits(url or "", strict, soft)
                made.append((host, path, rule, verdict or ("block" if hard or mild >= soft_limit else "allow"), hard, mild))
            columns = list(zip(*made, strict=True)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([b.column("page_id"), *(pa.array(c, f.type) for c, f in zip(columns, list(fields)[1:], strict=True))], schema=fields)

    own = pages.select(whole_id(pages, id_col).alias("page_id"), pages[url_col].cast("string").alias("url"))
    return own.mapInArrow(run, "page_id bigint, host string, path string, rule string, verdict string, n_strict bigint, n_soft bigint")


def oracle(rules=RULES, strict=STRICT, soft=SOFT, soft_limit: int = SOFT_LIMIT) -> str:
    """The same by DuckDB SQL, from the same configuration."""
    text = lambda s: "'" + s.replace("'", "''") + "'"
    fits = ", ".join(f"({text(h)}, {text(p)}, {text(v)})" for h, p, v in rules)
    hit = lambda t: f"(regexp_matches(low, '(^|[^a-z0-9]){t}([^a-z0-9]|$)'))::BIGINT"
    return f"""
WITH r(h, p, v) AS (VALUES {fits}),
u AS (SELECT page_id, row_number() OVER () AS k, coalesce(url, '') AS url,
  translate(coalesce(url, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS low,
  CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
s AS (SELECT *, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  substr(regexp_extract(rest, '^[^?#]*'), length(regexp_extract(rest, '^[^/?#]*')) + 1) AS path FROM u),
f AS (SELECT k, arg_max(h || p, length(h || p)) AS rule, arg_max(v, length(h || p)) AS v FROM s, r
  WHERE (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY k),
t AS (SELECT *, {' + '.join(map(hit, strict))} AS n_strict, {' + '.join(map(hit, soft))} AS n_soft FROM s)
SELECT page_id, host, path, rule, coalesce(v, CASE WHEN n_strict > 0 OR n_soft >= {soft_limit} THEN 'block' ELSE 'allow' END) AS verdict, n_strict, n_soft
FROM t LEFT JOIN f USING (k)"""
