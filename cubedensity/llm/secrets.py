"""Secret scans with a trigram index, in DataFrame functions only.

Every rule is a regular expression. From its syntax tree a Boolean query over trigrams is derived that each match
must satisfy. An inverted index holds, for every trigram that some query names, the rows whose lower-cased text has
it, in blocks of rows of bounded size; the queries are answered by intersecting and uniting postings, and only the
candidate rows are given to the expression. A rule without mandatory trigrams (a run of hexadecimal digits) is run
over every row.

Spans are in code points, end exclusive. Matches are leftmost and do not overlap within a kind; a match whose
measured group is shorter than the rule's least length is dropped.

Inputs: null texts count as empty and give no spans; texts of any length are read whole; of matches that begin at one place
the rule that is listed first comes first; repeated rows give repeated results; an empty table gives none; extra columns,
of whatever name, are not returned.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubedensity.llm.common import bind, durable, where_marked

ROWS_PER_BLOCK = 4096
MOST_STRINGS = 64


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    group: int = 0
    least: int = 1


#: fixed values: the three base kinds, in their order
BASE = (
    Rule("assign", r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20),
    Rule("hex", r"[0-9a-f]{24,}", 0, 24),
)
#: fixed values: public formats of further credentials
MORE = (
    Rule("private", r"-----BEGIN [A-Z ]{0,30}PRIVATE KEY-----"),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("maps", r"AIza[A-Za-z0-9_-]{35,}"),
    Rule("payment", r"[sr]k_live_[A-Za-z0-9]{16,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("bearer", r"(?i:bearer)\x20+[A-Za-z0-9._~+/-]{20,}"),
    Rule("login", r"[a-z][a-z0-9+]{1,20}://[^\s:@/]{1,64}:[^\s:@/]{1,64}@"),
)

# A query is True (anything may match), a trigram, or ("and" | "or", parts).


def _both(parts):
    kept = list(dict.fromkeys(p for p in parts if p is not True))
    return True if not kept else kept[0] if len(kept) == 1 else ("and", tuple(kept))


def _either(parts):
    parts = list(dict.fromkeys(parts))
    return True if not parts or True in parts else parts[0] if len(parts) == 1 else ("or", tuple(parts))


def _of_strings(strings):
    return _either([_both([s[i : i + 3] for i in range(len(s) - 2)]) for s in sorted(strings)])


def _choices(items) -> set[str] | None:
    """The lower-cased characters of a small character class."""
    from re import _constants as c

    found: set[str] = set()
    for op, value in items:
        if op is c.LITERAL:
            found.add(chr(value).lower())
        elif op is c.RANGE and value[1] - value[0] < 8:
            found |= {chr(x).lower() for x in range(value[0], value[1] + 1)}
        else:
            return None
    return found if len(found) <= 8 else None


def _analyse(tree) -> tuple[set[str] | None, object]:
    """(all strings that can match, if few; query that a match satisfies) of a parsed sequence."""
    from re import _constants as c

    asked, exact, whole = [], {""}, True

    def flush():
        nonlocal exact, whole
        asked.append(_of_strings(exact))
        exact, whole = {""}, False

    for op, value in tree:
        few, query = None, True
        if op is c.LITERAL:
            few = {chr(value).lower()}
        elif op is c.IN:
            few = _choices(value)
        elif op is c.SUBPATTERN:
            few, query = _analyse(value[3])
        elif op is c.BRANCH:
            parts = [_analyse(x) for x in value[1]]
            if all(p[0] is not None for p in parts):
                few = set().union(*(p[0] for p in parts))
            query = _either([p[1] for p in parts])
        elif op in (c.MAX_REPEAT, c.MIN_REPEAT):
            low, high, inner = value
            once, query = _analyse(inner)
            if once is not None and (low, high) == (0, 1):
                few = once | {""}
            elif once is not None and low == high and low <= 8:
                few = reduce(lambda a, _: {x + y for x in a for y in once} if len(a) * len(once) <= MOST_STRINGS else a, range(low), {""})
                few = few if all(len(x) >= low for x in few) else None
            if not low:
                query = True
        elif op is c.AT:
            few = {""}
        if few is not None and len(few) * len(exact) <= MOST_STRINGS:
            exact = {a + b for a in exact for b in few}
        else:
            flush()
            asked.append(query if few is None else _of_strings(few))
    return (exact if whole else None), _both([*asked, _of_strings(exact)])


def trigram_query(pattern: str):
    """The Boolean trigram query of a regular expression; True where it has no mandatory trigram."""
    return _analyse(re._parser.parse(pattern))[1]


def trigrams_of(query) -> set[str]:
    return set() if query is True else {query} if isinstance(query, str) else set().union(*map(trigrams_of, query[1]))


def _answer(query, postings: Column) -> Column:
    """Rows of a block that satisfy a query: intersections and unions of postings."""
    if isinstance(query, str):
        return F.coalesce(F.try_element_at(postings, F.lit(query)), F.array().cast("array<bigint>"))
    return reduce(F.array_intersect if query[0] == "and" else F.array_union, (_answer(q, postings) for q in query[1]))


def index(keyed: DataFrame, trigrams: list[str], blocks: int) -> DataFrame:
    """Inverted index ``(block, trigram, rows)`` of ``keyed(_row, text)`` over the given lower-case trigrams."""
    has = lambda low: F.filter(F.array(*map(F.lit, trigrams)), lambda t: low.contains(t))
    posted = keyed.filter("text is not null").select(
        F.pmod("_row", F.lit(blocks)).alias("block"), "_row", F.explode(bind(F.lower("text"), has)).alias("trigram")
    )
    return posted.groupBy("block", "trigram").agg(F.collect_set("_row").alias("rows"))


def candidates(keyed: DataFrame, rules: list[tuple[int, object]], blocks: int) -> DataFrame:
    """``(_row, rules)``: bit i of ``rules`` is set if the row satisfies the query of rule number i."""
    named = sorted(set().union(*(trigrams_of(q) for _, q in rules)))
    lists = index(keyed, named, blocks).groupBy("block").agg(
        F.map_from_entries(F.collect_list(F.struct("trigram", "rows"))).alias("postings")
    )
    found = lambda p: F.array(*(F.struct(F.lit(1 << i).cast("long").alias("bit"), _answer(q, p).alias("rows")) for i, q in rules))
    flat = lists.select(F.explode(bind(F.col("postings"), found)).alias("f")).select("f.bit", F.explode("f.rows").alias("_row"))
    return flat.groupBy("_row").agg(F.bit_or("bit").alias("rules"))


SPANS = "array<struct<start:int,k:int,end:int>>"


def spans_of(text: Column, rule: Rule, number: int) -> Column:
    """Spans of one rule: lengths of what lies between the matches give their places."""
    pattern = F.lit(rule.pattern)
    parts = F.arrays_zip(
        F.split(text, rule.pattern, -1).alias("gap"),
        F.regexp_extract_all(text, pattern, F.lit(0)).alias("all"),
        F.regexp_extract_all(text, pattern, F.lit(rule.group)).alias("part"),
    )
    none = F.array().cast(SPANS)

    def step(at, x):
        start = at["pos"] + F.length(x["gap"])
        end = start + F.coalesce(F.length(x["all"]), F.lit(0))
        one = F.array(F.struct(start.alias("start"), F.lit(number).alias("k"), end.alias("end")))
        kept = F.when(F.length(x["part"]) >= rule.least, F.concat(at["out"], one)).otherwise(at["out"])
        return F.struct(end.alias("pos"), kept.alias("out"))

    walked = F.aggregate(parts, F.struct(F.lit(0).alias("pos"), none.alias("out")), step, lambda at: at["out"])
    return F.when(text.rlike(rule.pattern), walked).otherwise(none)


def scan(docs: DataFrame, rules: tuple[Rule, ...] = BASE + MORE, rows_per_block: int = ROWS_PER_BLOCK) -> DataFrame:
    """``(doc_id, found)`` for every row: spans as ``(start, k, end)`` by start, then rule number."""
    asked = [(i, trigram_query(r.pattern)) for i, r in enumerate(rules)]
    queried = [(i, q) for i, q in asked if q is not True]
    keyed = docs.select("doc_id", "text").withColumn("_row", F.xxhash64("doc_id", "text"))
    blocks = max(1, -(-docs.count() // rows_per_block))
    marked = keyed.select("doc_id", "text", F.lit(0).cast("long").alias("rules"))
    if queried:
        hits = durable(candidates(keyed, queried, blocks))
        key = [F.lit(0).alias("_kid"), F.col("_row").alias("_kh")]
        held, free = where_marked(keyed.select("doc_id", "text", "_row", *key), hits.select(*key))  # rows without candidates stay where they are
        held = held.join(hits.withColumnRenamed("_row", "_hit"), F.col("_row") == F.col("_hit"), "left")
        marked = held.select("doc_id", "text", "rules").union(free.select("doc_id", "text", F.lit(0).cast("long")))
    found = [
        spans_of(F.col("text"), r, i)
        if asked[i][1] is True
        else F.when(F.coalesce("rules", F.lit(0)).bitwiseAND(1 << i) != 0, spans_of(F.col("text"), r, i)).otherwise(F.array().cast(SPANS))
        for i, r in enumerate(rules)
    ]
    return marked.select("doc_id", F.coalesce(F.array_sort(F.concat(*found)), F.array().cast(SPANS)).alias("found"))


def digest(docs: DataFrame) -> DataFrame:
    """Counts and digest of the base kinds, and all spans as text."""
    kinds = F.array(*(F.lit(r.kind) for r in BASE + MORE))
    written = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(kinds, s["k"]), s["start"], s["end"])), ",")
    count = lambda k: F.size(F.filter("found", lambda s: s["k"] == k)).cast("long")
    return scan(docs).select(
        "doc_id",
        *(count(k).alias(f"n_{r.kind}") for k, r in enumerate(BASE)),
        F.sha2(written(F.filter("found", lambda s: s["k"] < len(BASE))), 256).alias("base_sha256"),
        written(F.col("found")).alias("spans"),
    )
