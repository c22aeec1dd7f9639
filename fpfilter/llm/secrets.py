"""Secret scan with a trigram inverted index, in DataFrame operations only.

Every rule is a regular expression. :func:`trigram_query` derives what trigrams its matches must contain, as a
Boolean query over lower-case trigrams. The index holds, for blocks of documents, the posting list of each trigram of
those queries; lists are intersected and united block by block, and only the documents that remain are matched
against the rule. Rules without mandatory trigrams are matched against every text.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.llm.scratch import written

#: Documents in a block of the index, on average: the bound of a posting list.
BLOCK_DOCS = 4096
_MOST_STRINGS = 64
_MOST_CLASS = 4


@dataclass(frozen=True)
class Rule:
    """``least`` applies to the length of group ``group`` of a match; shorter ones are dropped after matching."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 0
    base: bool = False


def _either_case(word: str) -> str:
    return "".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in word)


_NAMES = "|".join([*map(_either_case, ("password", "passwd", "secret", "token")), _either_case("api") + "_?" + _either_case("key")])
#: Base kinds in the order in which spans that start together are listed, then the kinds this method adds. Loops are over
#: single characters (Java recurses over repeated groups), and what precedes a required character is bounded, so that
#: matching takes time in proportion to the text however often it repeats itself.
RULES = (
    Rule("assign", rf"({_NAMES})[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 2, 6, True),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20, True),
    Rule("hex", r"[0-9a-f]+", 0, 24, True),
    Rule("private_key", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("hub_token", r"gh[oprsu]_[A-Za-z0-9]{36,}"),
    Rule("chat_token", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("web_token", r"eyJ[A-Za-z0-9_-]{1,255}\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+"),
    Rule("map_key", r"AIza[A-Za-z0-9_-]{35}"),
)

# A query is True (anything), a trigram, or ("and" | "or", frozenset of queries).


def _join(how: str, parts: list) -> object:
    parts = {p for p in parts if not (how == "and" and p is True)}
    if how == "or" and True in parts:
        return True
    if not parts:
        return True
    return parts.pop() if len(parts) == 1 else (how, frozenset(parts))


def _require(strings: set[str]) -> object:
    """One of the strings, by trigrams that cover it; what holds another one of them says no more than that one."""
    least = [s for s in strings if not any(t != s and t in s for t in strings)]
    cover = lambda s: sorted({*range(0, len(s) - 2, 3), len(s) - 3}) if len(s) > 2 else []
    return _join("or", [_join("and", [s[i : i + 3] for i in cover(s)]) for s in least])


def _cross(a: set[str], b: set[str]) -> set[str] | None:
    return {x + y for x in a for y in b} if len(a) * len(b) <= _MOST_STRINGS else None


def _sequence(items: list) -> tuple[set[str] | None, object]:
    """The exact strings of a concatenation, where these are few, or else what its matches require."""
    held, parts, exact = {""}, [], True
    for item in items:
        strings, query = _node(*item)
        both = _cross(held, strings) if strings is not None else None
        if both is not None:
            held = both
            continue
        exact = False
        parts += [_require(held), query]
        held = strings if strings is not None else {""}
    return (held, True) if exact else (None, _join("and", [*parts, _require(held)]))


def _node(op: object, arg: object) -> tuple[set[str] | None, object]:
    name = str(op)
    if name == "LITERAL":
        return {chr(arg).lower()}, True
    if name == "IN":
        chars: set[str] = set()
        for kind, value in arg:
            if str(kind) == "LITERAL":
                chars.add(chr(value).lower())
            elif str(kind) == "RANGE" and value[1] - value[0] < _MOST_CLASS:
                chars |= {chr(c).lower() for c in range(value[0], value[1] + 1)}
            else:
                return None, True
        return (chars, True) if len(chars) <= _MOST_CLASS else (None, True)
    if name == "SUBPATTERN":
        return _sequence(list(arg[-1]))
    if name == "BRANCH":
        found = [_sequence(list(x)) for x in arg[1]]
        if all(s is not None for s, _ in found):
            union = set().union(*(s for s, _ in found))
            return (union, True) if len(union) <= _MOST_STRINGS else (None, _require(union))
        return None, _join("or", [_require(s) if s is not None else q for s, q in found])
    if name in ("MAX_REPEAT", "MIN_REPEAT"):
        low, high, body = arg
        strings, query = _sequence(list(body))
        if strings is not None and low == 0 and int(high) == 1:
            return strings | {""}, True
        if low == 0:
            return None, True
        if strings is None:
            return None, query
        power: set[str] | None = {""}
        for _ in range(min(low, 8)):
            power = _cross(power, strings) or power
        return (power, True) if low == int(high) and low <= 8 and len(strings) == 1 else (None, _require(power))
    return None, True  # anchors, any character, look-arounds: nothing is required


def trigram_query(pattern: str) -> object:
    """What every match of ``pattern`` must contain once letters are in lower case; True if nothing is known."""
    strings, query = _sequence(list(re._parser.parse(pattern)))
    return _require(strings) if strings is not None else query


def trigrams(query: object) -> set[str]:
    if query is True:
        return set()
    return {query} if isinstance(query, str) else set().union(*map(trigrams, query[1]))


def _key(id_col: str, text: Column) -> Column:
    return F.coalesce(F.xxhash64(F.col(id_col)) + F.when(F.col(id_col).isNull(), F.lit(None).cast("long")).otherwise(0), F.xxhash64(text))


def build_index(docs: DataFrame, vocabulary: list[str], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Posting lists ``block, trigram, rows``: the keys of a block's documents whose lower-case text has the trigram.

    Blocks are hash ranges of documents of a bounded size, so a list is bounded though its trigram be in every text.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    blocks = -(-docs.count() // BLOCK_DOCS) or 1
    folded = docs.select(_key(id_col, text).alias("key"), F.lower(text).alias("folded"))
    # one expression a trigram: the folded text is used often, so it is made once and not inlined into a lambda
    tests = [F.when(F.contains("folded", F.lit(t)), F.lit(t)) for t in vocabulary]
    held = folded.select("key", F.array_compact(F.array(*tests)).alias("held"))
    pairs = held.select("key", F.pmod("key", F.lit(blocks)).alias("block"), F.explode("held").alias("trigram"))
    return pairs.groupBy("block", "trigram").agg(F.sort_array(F.collect_list("key")).alias("rows"))


def candidates(index: DataFrame, queries: dict[int, object]) -> DataFrame:
    """``key, mask``: the documents that satisfy any of the queries; bit ``i`` for query ``i``."""
    lists = index.groupBy("block").agg(F.map_from_entries(F.collect_list(F.struct("trigram", "rows"))).alias("lists"))
    none = F.array().cast("array<bigint>")

    def rows(query: object) -> Column:
        if isinstance(query, str):
            return F.coalesce(F.try_element_at("lists", F.lit(query)), none)
        how, parts = query
        return reduce(F.array_intersect if how == "and" else F.array_union, [rows(p) for p in sorted(parts, key=str)])

    def marked(i: int) -> Column:
        return F.transform(rows(queries[i]), lambda k: F.struct(k.alias("key"), F.lit(1 << i).alias("bit")))

    found = [marked(i) for i in queries]
    pairs = lists.select(F.explode(F.concat(*found)).alias("p"))
    return pairs.groupBy("p.key").agg(F.bit_or("p.bit").alias("mask"))


def _long_enough(rule: Rule) -> str:
    """The rule's pattern; for a run of one class with the least length in it, which finds the same spans."""
    run = rule.pattern.startswith("[") and rule.pattern.endswith("]+") and rule.pattern.count("[") == 1
    return f"{rule.pattern[:-1]}{{{rule.least},}}" if run and rule.least else rule.pattern


def _spans(text: Column, rule: Rule, order: int) -> Column:
    """The rule's spans ``start, order, end`` in code points, leftmost and non-overlapping.

    The pieces between matches and the matches alternate, so their lengths give every position.
    """
    pattern = F.lit(_long_enough(rule))
    matches = F.regexp_extract_all(text, pattern, F.lit(0))
    gaps = F.split(text, _long_enough(rule), -1)
    groups = F.regexp_extract_all(text, pattern, F.lit(rule.group))
    steps = F.zip_with(F.slice(gaps, 1, F.size(matches)), F.arrays_zip(matches.alias("m"), groups.alias("g")), lambda gap, m: F.struct(F.length(gap).alias("gap"), F.length(m["m"]).alias("n"), F.length(m["g"]).alias("size")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,order:int,end:int>>").alias("out"))

    def put(acc: Column, x: Column) -> Column:
        low = acc["at"] + x["gap"]
        high = low + x["n"]
        span = F.array(F.struct(low.alias("start"), F.lit(order).alias("order"), high.alias("end")))
        return F.struct(high.alias("at"), F.when(x["size"] >= rule.least, F.concat(acc["out"], span)).otherwise(acc["out"]).alias("out"))

    return F.aggregate(steps, start, put, lambda acc: acc["out"])


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs``' ids with ``spans``: an array of ``start, order, end`` by start, then rule; one row per row of ``docs``.

    Whole texts are scanned, of any length and with any repeats; null and empty texts have no spans. Null ids are keyed
    by their text, repeated ids by the id: more rows may be verified, never fewer. Spans that start together come in
    the order of the rules. Extra columns, whatever their names, are not read. An empty table gives no rows.
    """
    none = F.array().cast("array<struct<start:int,order:int,end:int>>")
    queries = {i: trigram_query(r.pattern) for i, r in enumerate(rules)}
    queries = {i: q for i, q in queries.items() if q is not True}
    vocabulary = sorted(set().union(*map(trigrams, queries.values()))) if queries else []
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).alias("id"), text.alias("text"), _key(id_col, text).alias("key"))
    if queries:
        found = written(candidates(build_index(docs, vocabulary, id_col, text_col), queries), "candidates")
        rows = rows.join(found, "key", "left")
    else:
        rows = rows.withColumn("mask", F.lit(0))
    parts = []
    for i, rule in enumerate(rules):
        worth = F.col("text").rlike(_long_enough(rule))
        if i in queries:
            worth = ((F.coalesce("mask", F.lit(0)).bitwiseAND(1 << i)) != 0) & worth
        parts.append(F.when(worth, _spans(F.col("text"), rule, i)).otherwise(none))
    return rows.select("id", F.array_sort(F.concat(*parts)).alias("spans"))


def _listed(spans: Column, rules: tuple[Rule, ...]) -> Column:
    names = F.array(*[F.lit(r.kind) for r in rules])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["order"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def op1_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    base = [i for i, r in enumerate(RULES) if r.base]
    count = lambda i: F.size(F.filter("spans", lambda s: s["order"] == i)).cast("long").alias(f"n_{RULES[i].kind}")
    return found.select(
        F.col("id").alias("doc_id"),
        *map(count, base),
        F.sha2(_listed(F.filter("spans", lambda s: s["order"] < len(base)), RULES).cast("binary"), 256).alias("base_sha256"),
        _listed(F.col("spans"), RULES).alias("spans"),
    )


def sql() -> str:
    """Every rule on every text: the same spans without an index."""
    parts = []
    for i, r in enumerate(RULES):
        p = r.pattern.replace("'", "''")
        parts.append(f"""
    SELECT doc_id, {i} AS o, '{r.kind}' AS kind, m, g, gaps, generate_subscripts(m, 1) AS i FROM (
        SELECT doc_id, regexp_extract_all(text, '{p}') AS m, regexp_extract_all(text, '{p}', {r.group}) AS g, string_split_regex(text, '{p}') AS gaps FROM d)""")
    least = " ".join(f"WHEN {i} THEN {r.least}" for i, r in enumerate(RULES))
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
u AS ({' UNION ALL '.join(parts)}),
s AS (
    SELECT doc_id, o, kind, length(g[i]) AS size, length(m[i]) AS n,
           list_sum(list_transform(gaps[1:i], lambda x: length(x)))::BIGINT + coalesce(list_sum(list_transform(m[1:i - 1], lambda x: length(x))), 0)::BIGINT AS low
    FROM u
), k AS (SELECT *, kind || ':' || low || ':' || (low + n) AS span FROM s WHERE size >= CASE o {least} END),
a AS (
    SELECT doc_id, count(*) FILTER (o = 0) AS n_assign, count(*) FILTER (o = 1) AS n_access, count(*) FILTER (o = 2) AS n_hex,
           string_agg(span, ',' ORDER BY low, o) FILTER (o < 3) AS base, string_agg(span, ',' ORDER BY low, o) AS spans
    FROM k GROUP BY doc_id
)
SELECT d.doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
       sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM d LEFT JOIN a USING (doc_id)
"""
