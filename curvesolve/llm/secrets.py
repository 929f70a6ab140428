"""Secret scans through a trigram inverted index, in DataFrame expressions only.

Each rule's regular expression is reduced to a Boolean query over trigrams that every match must
hold. The index has a posting (trigram, doc_id) for each trigram that some rule asks for; postings
are intersected by counting, which gives candidate documents per rule, and only those are scanned
with the rule. Rules without a mandatory trigram scan every document.

Defined results: a null text is an empty one; rows without a doc_id cannot be indexed and are
scanned with all rules; of repeated rows each is scanned; other columns are ignored.
"""

from __future__ import annotations

import re
import re._constants as sre
import re._parser as sre_parse
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import cut, let, marks_of, span_text, spans


@dataclass(frozen=True)
class Rule:
    """``pattern`` finds the matches; ``check`` must then hold for a match's text; case counts unless written otherwise."""

    kind: str
    pattern: str
    check: str = ""


#: The patterns of the base kinds, then further well-known formats.
RULES = (
    Rule("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]+""",
         r"""^(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]{12,}$"""),
    Rule("access", r"AKIA[A-Z0-9]{14,}"),
    Rule("hex", r"[0-9a-f]{16,}"),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{20,}"),
    Rule("signed", r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"),
    Rule("pem", r"-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----"),
)
BASE = ("assign", "access", "hex")
#: Strings followed at once while a regex is reduced; cells of the table that tells which documents move.
WIDTH, CELLS = 64, 1 << 20
SPANS = "array<struct<s:int,e:int,t:string>>"

Query = frozenset  # of frozensets of trigrams: an "or" of "and"s; {frozenset()} holds for every text
ANY: Query = frozenset([frozenset()])


def _both(a: Query, b: Query) -> Query:
    return frozenset(x | y for x in a for y in b) if len(a) * len(b) <= 4 * WIDTH else a


def _of(strings: set[str]) -> Query:
    """Trigrams that a text holding one of the strings must hold."""
    if any(len(s) < 3 for s in strings):
        return ANY
    return frozenset(frozenset(s[i:i + 3] for i in range(len(s) - 2)) for s in strings)


def _chars(op, arg) -> set[str] | None:
    """The lower-cased characters of a single-character node, if few."""
    if op is sre.LITERAL:
        return {chr(arg).lower()}
    if op is sre.IN:
        got: set[str] = set()
        for o, a in arg:
            if o is sre.LITERAL:
                got.add(chr(a).lower())
            elif o is sre.RANGE and a[1] - a[0] < 8:
                got.update(chr(c).lower() for c in range(a[0], a[1] + 1))
            else:
                return None
        return got if len(got) <= 8 else None
    return None


def _reduce(nodes) -> tuple[set[str] | None, Query]:
    """(all strings a part can match, if few; its trigram query)."""
    exact: set[str] | None = {""}
    run, query = {""}, ANY

    def flush() -> None:
        nonlocal run, query
        query, run = _both(query, _of(run)), {""}

    for op, arg in nodes:
        strings, inner = _chars(op, arg), ANY
        if strings is None and op is sre.SUBPATTERN:
            strings, inner = _reduce(arg[-1])
        elif strings is None and op is sre.BRANCH:
            parts = [_reduce(p) for p in arg[1]]
            inner = frozenset().union(*(q for _, q in parts))
            inner = ANY if frozenset() in inner else inner
            strings = None if any(s is None for s, _ in parts) else set().union(*(s for s, _ in parts))
        elif strings is None and op in (sre.MAX_REPEAT, sre.MIN_REPEAT, sre.POSSESSIVE_REPEAT):
            least, most, part = arg
            s, q = _reduce(part)
            inner = q if least else ANY
            if s is not None and most <= 2:
                strings = {""} if least == 0 else s
                for _ in range(least, most):
                    strings = strings | {a + b for a in strings for b in s}
        elif strings is None and op is sre.AT:
            strings = {""}
        if strings is None or len(run) * len(strings) > WIDTH:
            flush()
            query = _both(query, inner)
            exact = None
            if strings is not None:
                run = set(strings)
        else:
            run = {a + b for a in run for b in strings}
            exact = run if exact is not None else None
    flush()
    return exact, query


def trigram_query(pattern: str) -> Query:
    """Boolean query over lower-cased trigrams that each match of ``pattern`` satisfies."""
    query = _reduce(sre_parse.parse(pattern))[1]
    return frozenset(x for x in query if not any(y < x for y in query))


def postings(docs: DataFrame, trigrams: list[str]) -> DataFrame:
    """The inverted index (trigram, doc_id) for the given trigrams over whole texts."""
    held = let(F.lower("text"), lambda t: F.filter(F.lit(trigrams), lambda g: F.contains(t, g)))
    return docs.where("doc_id is not null").select("doc_id", F.explode(held).alias("trigram"))


def candidates(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(doc_id, rules): for each document the kinds whose trigram query its postings satisfy."""
    terms = [(r.kind, i, t, len(part)) for r in rules if (q := trigram_query(r.pattern)) != ANY
             for i, part in enumerate(sorted(q, key=sorted)) for t in sorted(part)]
    asked = docs.sparkSession.createDataFrame(terms, "kind string, part int, trigram string, size int")
    index = postings(docs, sorted({t[2] for t in terms}))
    # One row for each trigram of a rule: bounded by the rules, whatever the input.
    met = index.distinct().join(F.broadcast(asked), "trigram").groupBy("doc_id", "kind", "part", "size").count().where("count = size")
    return met.groupBy("doc_id").agg(F.collect_set("kind").alias("rules"))


def _holding(found: Column, check: str) -> Column:
    return F.filter(found, lambda x: F.rlike(x["t"], F.lit(check)))


def _found(rule: Rule) -> Column:
    found = spans(F.col("text"), rule.pattern)
    found = _holding(found, rule.check) if rule.check else found
    # One scan for any match at all; most texts end there.
    return F.when(F.rlike("text", F.lit(rule.pattern)), found).otherwise(F.array().cast(SPANS))


def find_secrets(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """One row per document: doc_id and, per kind, the found spans array<struct<s, e, t>>.

    Rules without a mandatory trigram scan each text where it lies. For the others only texts whose
    doc_id falls in a cell that holds a candidate move: a table of at most ``CELLS`` cells is broadcast.
    """
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    open_rules = [r for r in rules if trigram_query(r.pattern) == ANY]
    asked = [r for r in rules if r not in open_rules]
    none = F.array().cast(SPANS)
    likely = cut(candidates(src, rules))
    cells = likely.select(F.pmod(F.xxhash64("doc_id"), F.lit(CELLS)).cast("int").alias("_cell")).distinct()
    moved = src.withColumn("cell", F.pmod(F.xxhash64("doc_id"), F.lit(CELLS)).cast("int")).join(F.broadcast(cells), F.col("cell") == F.col("_cell"), "left_semi")
    met = moved.join(likely.withColumnRenamed("doc_id", "_id"), F.col("doc_id") == F.col("_id"))
    # Repeated rows have equal spans, so rows of one doc_id and text are one here.
    verified = met.select("doc_id", F.xxhash64("text").alias("h"), *[F.when(F.array_contains("rules", r.kind), _found(r)).otherwise(none).alias(r.kind) for r in asked])
    hit = cut(verified.where(F.greatest(*[F.size(r.kind) for r in asked], F.lit(0)) > 0)).dropDuplicates(["doc_id", "h"]) if asked else None
    # Rows that cannot be indexed are scanned with all rules.
    every = src.select("doc_id", F.xxhash64("text").alias("_h"), *[_found(r).alias(r.kind) for r in open_rules],
                       *[F.when(F.col("doc_id").isNull(), _found(r)).otherwise(none).alias(f"_{r.kind}") for r in asked])
    if not asked:
        return every.select("doc_id", *[r.kind for r in rules])
    both = every.join(hit.withColumnRenamed("doc_id", "_id"), (F.col("doc_id") == F.col("_id")) & (F.col("_h") == F.col("h")), "left")
    return both.select("doc_id", *[F.coalesce(r.kind, f"_{r.kind}").alias(r.kind) if r in asked else F.col(r.kind) for r in rules])


def digest(found: DataFrame, kinds: tuple[str, ...] = tuple(r.kind for r in RULES), base: tuple[str, ...] = BASE) -> DataFrame:
    """(doc_id, n_<base kind>, base_sha256, spans)."""
    def text(names: tuple[str, ...]) -> Column:
        return span_text(F.concat(*[marks_of(k, kinds.index(k), F.col(k)) for k in names]))
    return found.select("doc_id", *[F.size(k).cast("long").alias(f"n_{k}") for k in base],
                        F.sha2(text(base), 256).alias("base_sha256"), text(kinds).alias("spans"))


def matches(pattern: str, text: str) -> bool:
    """Whether the trigram query of a pattern holds for a text; for tests."""
    low = text.lower()
    return any(all(t in low for t in part) for part in trigram_query(pattern)) if re.compile(pattern) else False
