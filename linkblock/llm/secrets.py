"""Secret scan over a content-addressed ledger, by DataFrame functions only.

Every historical version of a path is addressed by the hash of its content. A
ledger holds which (blob, rule, rule version) pairs have been scanned and what
was found. A run keeps only blobs with an unseen pair, runs only the rules that
a blob lacks, once however many paths show it, adds to the ledger, and joins
the findings back to all paths.

Spans come from built-in regular expressions: splitting a text by a pattern
and extracting the pattern's matches walk the same leftmost non-overlapping
matches, so the running lengths of both give every start and end.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkblock.llm.common import let
from linkblock.runtime import settle


@dataclass(frozen=True)
class SecretRule:
    """kind; a pattern; keep: least code points of group `group` (0: the match). Raise version when it changes.

    probe: a pattern that every text with a kept match matches, for a cheaper
    first test. Only the author of a rule can know one; without it the pattern
    itself is tested.
    """

    kind: str
    pattern: str
    group: int = 0
    keep: int = 1
    base: bool = False
    version: int = 1
    probe: str | None = None


#: The contract's three, then formats that issuers publish.
RULES: tuple[SecretRule, ...] = (
    SecretRule("assign", "((?i:password|passwd|secret|token|api_?key))[\"']?\\x20*[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 2, 6, True),
    SecretRule("access", "AKIA[A-Z0-9]+", 0, 20, True, probe="AKIA[A-Z0-9]{16,}"),
    SecretRule("hex", "[0-9a-f]+", 0, 24, True, probe="[0-9a-f]{24,}"),
    SecretRule("private_key", "-----BEGIN [A-Z ]*PRIVATE KEY-----[A-Za-z0-9+/=\\s]+-----END [A-Z ]*PRIVATE KEY-----"),
    SecretRule("forge_token", "gh[pousr]_[A-Za-z0-9]{36,}"),
    SecretRule("chat_token", "xox[abprs]-[A-Za-z0-9-]{10,}"),
    SecretRule("web_token", "eyJ[A-Za-z0-9_-]{8,}\\.eyJ[A-Za-z0-9_-]{8,}\\.[A-Za-z0-9_-]{8,}"),
    SecretRule("pay_key", "sk_live_[A-Za-z0-9]{16,}"),
    SecretRule("map_key", "AIza[A-Za-z0-9_-]{35}"),
)

_SPAN = "array<struct<s:int,e:int,kind:string,version:int>>"
_SCANNED = "array<struct<kind:string,version:int>>"
LEDGER = f"blob string, scanned {_SCANNED}, spans {_SPAN}"
#: Code points that a text is cut into where spans are replaced.
PIECE = 4096


def _sums(values: Column, plus: Callable[[Column, Column], Column]) -> Column:
    """Running totals of an array under plus, by doubling: as many rounds as its length has bits, each one walk."""
    rounds = F.sequence(F.lit(0), F.ceil(F.log2(F.greatest(F.size(values), F.lit(1)))).cast("int"))

    def double(a: Column, i: Column) -> Column:
        far = F.pow(F.lit(2), i).cast("int")
        return F.concat(F.slice(a, F.lit(1), far), F.zip_with(
            F.slice(a, far + 1, F.size(a)), F.slice(a, F.lit(1), F.greatest(F.size(a) - far, F.lit(0))), plus
        ))

    return F.aggregate(rounds, values, double)


def _one_rule(text: Column, rule: SecretRule) -> Column:
    """Spans of one rule; a text without a match costs one search, many matches in it cost in proportion."""
    none = F.array().cast(_SPAN)
    whole = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(0))
    tested = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(rule.group)) if rule.group else whole
    sizes = lambda a: F.transform(a, F.char_length)

    def placed(v: Column) -> Column:
        """v: m and gap, the lengths of matches and of what is before each; t: of the tested groups."""
        ends = _sums(F.zip_with(v["m"], F.slice(v["gap"], F.lit(1), F.size(v["m"])), lambda m, g: m + g), lambda a, b: a + b)
        rows = F.arrays_zip(ends.alias("e"), v["m"].alias("m"), v["t"].alias("t"))
        kept = F.filter(rows, lambda x: x["t"] >= rule.keep)
        return F.transform(kept, lambda x: F.struct((x["e"] - x["m"]).alias("s"), x["e"].alias("e"), F.lit(rule.kind).alias("kind"), F.lit(rule.version).alias("version")))

    found = let(F.struct(sizes(whole).alias("m"), sizes(F.split(text, rule.pattern, -1)).alias("gap"), sizes(tested).alias("t")), placed)
    return F.when(text.rlike(rule.probe or rule.pattern), found).otherwise(none)


def spans_of(text: Column, rules: Sequence[SecretRule] = RULES, wanted: Column | None = None) -> Column:
    """Spans of the rules, one rule after another; wanted: array of (kind, version), only rules in it are run."""
    none = F.array().cast(_SPAN)
    run = lambda r: _one_rule(text, r) if wanted is None else F.when(F.array_contains(wanted, _pair(r)), _one_rule(text, r)).otherwise(none)
    return F.concat(*map(run, rules))


def _pair(rule: SecretRule) -> Column:
    return F.struct(F.lit(rule.kind).alias("kind"), F.lit(rule.version).alias("version"))


def in_order(spans: Column, rules: Sequence[SecretRule] = RULES) -> Column:
    """Spans of the rules as they are now by start, then by the order of the rules: array<struct<s, k, e, kind>>."""
    rank = F.map_from_entries(F.array(*(F.struct(_pair(r), F.lit(i)) for i, r in enumerate(rules))))
    ranked = let(rank, lambda m: F.transform(spans, lambda x: F.struct(x["s"].alias("s"), F.try_element_at(m, F.struct(x["kind"].alias("kind"), x["version"].alias("version"))).alias("k"), x["e"].alias("e"), x["kind"].alias("kind"))))
    return F.when(F.size(spans) > 0, F.array_sort(F.filter(ranked, lambda x: x["k"].isNotNull()))).otherwise(F.array().cast("array<struct<s:int,k:int,e:int,kind:string>>"))


def versions(docs: DataFrame, path_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(path, blob, text): null texts are the empty blob."""
    text = F.coalesce(docs[text_col].cast("string"), F.lit(""))
    return docs.select(docs[path_col].alias("path"), F.sha2(text, 256).alias("blob"), text.alias("text"))


def scan_unseen(history: DataFrame, ledger: DataFrame | None = None, rules: Sequence[SecretRule] = RULES, with_text: bool = False) -> DataFrame:
    """Ledger rows (blob, scanned, spans): of every blob of history the (kind, version) pairs that the ledger lacks, and what they find.

    Equal blobs meet once: copies are cut down on each task before the
    exchange. A blob with all its pairs in the ledger gives no row; of the
    others only the missing rules are run.
    """
    once = history.select("blob", "text").groupBy("blob").agg(F.first("text").alias("text"))
    every = F.array(*map(_pair, rules)).cast(_SCANNED)
    if ledger is None:
        found = once.select("blob", every.alias("scanned"), "text", spans_of(F.col("text"), rules).alias("spans"))
    else:
        done = ledger.groupBy("blob").agg(F.flatten(F.collect_list("scanned")).alias("done"))
        todo = once.join(done, "blob", "left").withColumn("scanned", F.array_except(every, F.coalesce("done", F.array().cast(_SCANNED)))).where(F.size("scanned") > 0)
        found = todo.select("blob", "scanned", "text", spans_of(F.col("text"), rules, F.col("scanned")).alias("spans"))
    return found if with_text else found.select("blob", "scanned", "spans")


def scan_versions(history: DataFrame, ledger: DataFrame | None = None, rules: Sequence[SecretRule] = RULES) -> tuple[DataFrame, DataFrame]:
    """(ledger with what was new, findings by path: path, blob, spans).

    history has one row for each version of each path (see versions()); a
    repeated row gives a repeated finding. An empty history leaves the ledger
    as it is. What was new is written once and serves both results. Findings
    of rules that aren't in `rules` any more, or not in that version, stay in
    the ledger and are not reported.
    """
    fresh = settle(scan_unseen(history, ledger, rules))
    whole = fresh if ledger is None else ledger.unionByName(fresh)
    known = whole.where(F.size("spans") > 0).select("blob", "spans")
    if ledger is not None:
        known = known.groupBy("blob").agg(F.flatten(F.collect_list("spans")).alias("spans"))
    found = history.select("path", "blob").join(known, "blob", "left")
    return whole, found.select("path", "blob", in_order(F.coalesce("spans", F.array().cast(_SPAN)), rules).alias("spans"))


def digest_columns(spans: Column, rules: Sequence[SecretRule] = RULES) -> dict[str, Column]:
    """Counts of the base kinds, digest of base spans, all spans as text."""
    shown = lambda a: F.array_join(F.transform(a, lambda x: F.concat_ws(":", x["kind"], x["s"], x["e"])), ",")
    base = [i for i, r in enumerate(rules) if r.base]
    of_rank = lambda i: lambda x: x["k"] == i  # noqa: E731  one parameter: a second would be the index
    counts = {f"n_{rules[i].kind}": F.size(F.filter(spans, of_rank(i))).cast("bigint") for i in base}
    return counts | {"base_sha256": F.sha2(shown(F.filter(spans, lambda x: x["k"].isin(*base))), 256), "spans": shown(spans)}


def find_secrets(docs: DataFrame, path_col: str = "doc_id", text_col: str = "text", rules: Sequence[SecretRule] = RULES) -> DataFrame:
    """Digest columns for every row of docs. Null and empty texts have no spans; repeated rows give repeated rows."""
    _, found = scan_versions(versions(docs, path_col, text_col), None, rules)
    return found.select(F.col("path").cast("bigint").alias("doc_id"), *(c.alias(n) for n, c in digest_columns(F.col("spans"), rules).items()))


def redacted(text: Column, spans: Column) -> Column:
    """text with every span replaced by its kind in brackets; overlapping spans count as one, named after the first.

    spans as in_order() gives them. The text is cut in pieces of PIECE code
    points, so that reaching a span doesn't take a walk from the text's start.
    """
    def cut(pieces: Column, a: Column, b: Column) -> Column:
        """Code points a to b, from the pieces that hold them."""
        part = lambda i: F.substring(F.get(pieces, i), F.greatest(a - i * PIECE, F.lit(0)) + 1, F.least(b - i * PIECE, F.lit(PIECE)) - F.greatest(a - i * PIECE, F.lit(0)))
        return F.when(b > a, F.array_join(F.transform(F.sequence(F.floor(a / PIECE).cast("int"), F.floor((b - 1) / PIECE).cast("int")), part), "")).otherwise(F.lit(""))

    def made(v: Column) -> Column:
        """v: pieces of the text, its length, spans x, and the furthest end of spans up to each."""
        rows = F.transform(v["x"], lambda x, i: F.struct(x["s"].alias("s"), x["kind"].alias("kind"), F.coalesce(F.get(v["far"], i - 1), F.lit(0)).alias("at")))
        shown = F.transform(F.filter(rows, lambda x: x["s"] >= x["at"]), lambda x: F.concat(cut(v["pieces"], x["at"], x["s"]), F.lit("["), x["kind"], F.lit("]")))
        return F.concat(F.array_join(shown, ""), cut(v["pieces"], F.element_at(v["far"], -1), v["n"]))

    far = _sums(F.transform(spans, lambda x: x["e"]), lambda a, b: F.greatest(a, b))
    pieces = F.regexp_extract_all(text, F.lit(f"(?s).{{1,{PIECE}}}"), F.lit(0))
    return F.when(F.size(spans) == 0, text).otherwise(let(F.struct(pieces.alias("pieces"), F.char_length(text).alias("n"), spans.alias("x"), far.alias("far")), made))


def redact_documents(docs: DataFrame, text_col: str = "text", size_col: str | None = "n_chars", rules: Sequence[SecretRule] = RULES) -> DataFrame:
    """docs with every found span replaced; all columns stay, size_col (if there is one) is counted anew where the text changed.

    Each distinct text is moved and scanned once, and meets its rows again by
    its address. Null texts stay null.
    """
    text = docs[text_col].cast("string")
    rest = F.struct(*(docs[c] for c in docs.columns if c != text_col)).alias("rest")
    blob = F.sha2(F.coalesce(text, F.lit("")), 256).alias("blob")
    rows = docs.select(rest, text.isNull().alias("void"), blob)
    seen = scan_unseen(docs.select(blob, F.coalesce(text, F.lit("")).alias("text")), None, rules, with_text=True)
    clean = seen.select("blob", F.size("spans").alias("hits"), "text", in_order(F.col("spans"), rules).alias("spans")).select("blob", "hits", redacted(F.col("text"), F.col("spans")).alias("clean"))
    joined = rows.join(clean, "blob")
    columns = []
    for name in docs.columns:
        if name == text_col:
            c = F.when(~F.col("void"), F.col("clean"))
        elif name == size_col:
            c = F.when(F.col("hits") > 0, F.char_length("clean")).otherwise(F.col(f"rest.`{name}`")).cast(docs.schema[name].dataType)
        else:
            c = F.col(f"rest.`{name}`")
        columns.append(c.alias(name))
    return joined.select(*columns)
