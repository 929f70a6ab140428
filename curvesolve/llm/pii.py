"""Personal data by candidate gradient boosting, in DataFrame expressions only.

Generators propose spans with high recall, overlapping each other: the four base kinds without their
checks, and a looser form of each. Candidates get binned format and context features, and boosted
trees score the loose ones. Labels come from elsewhere than the candidate itself: each span of a base
form is rewritten to the loose form, with its surroundings as they stand, and is a positive example if
the span passed its base check, a negative one if it failed; loose candidates met in the texts have no
label and are only scored. Examples are counted by feature combination, a table bounded by the bins. A cutoff per kind is calibrated on held-out documents: the smallest score from which on the
lower confidence bound of precision holds. As features are binned, the trees are tabulated over all
combinations, and candidates of selected combinations are added. Base spans always stay.

Defined results: a null text is an empty one; spans added never overlap a base span; a kind without
enough examples to vouch for the precision adds nothing; repeated rows count as they stand; other
columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import cut, marks_of, span_text, spans


@dataclass(frozen=True)
class Generator:
    """``scan`` matches what ``pattern`` does, written for linear time; texts without any of ``hints`` are not scanned, every match
    holds one. ``loosen``: (pattern, replacement) pairs that rewrite a span of the base form to this loose form of it."""

    kind: str
    scan: str
    hints: tuple[str, ...]
    digits: bool = True
    loosen: tuple[tuple[str, str], ...] = ()


#: The base kinds, then a looser form of each, in the same order.
BASE = ("email", "ip", "card", "phone")
GENERATORS = (
    Generator("email", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", ("@",), False),
    Generator("ip", r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", (".",)),
    Generator("card", r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){13,18}+(?![\x20-]?[0-9])", ()),
    Generator("phone", r"\+[0-9][\x20().0-9-]+[0-9]", ("+",)),
    Generator("loose_email", r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+\x20?(?:@|\(at\)|\[at\])\x20?[A-Za-z0-9-]++\x20?(?:\.|\(dot\)|\[dot\])\x20?[A-Za-z]{2,12}", ("@", "at"), False,
              (("@", "(at)"), (r"^(.*\(at\))[^.]*\.(?:.*\.)?([^.]+\.[^.]+)$", "$1$2"), (r"\.([^.]+)$", "(dot)$1"))),
    Generator("loose_ip", r"(?<![0-9.])[0-9]{1,3}(?:\x20?(?:\[\.\]|\(\.\)|\[dot\]|\(dot\))\x20?[0-9]{1,3}){3}(?![0-9])", ("[.]", "(.)", "[dot]", "(dot)"), True, ((r"\.", "[.]"),)),
    Generator("loose_card", r"(?<![0-9.])[0-9]{4}(?:[./_][0-9]{4}){3}(?![0-9.])", (".", "/", "_"), True, (("[^0-9]", ""), ("^(.{4})(.{4})(.{4})(.{4})$", "$1.$2.$3.$4"))),
    Generator("loose_phone", r"\([0-9]{2,4}\)\x20?[0-9]{3,4}[\x20.-]?[0-9]{3,4}(?![0-9])", ("(",), True, ((r"^\+[0-9]+[\x20.-]*(?=\()", ""),)),
)
KINDS = tuple(g.kind for g in GENERATORS)
#: Bins of each feature: name and number of values. The kind is that of the loose form.
FEATURES = (("kind", len(BASE)), ("digits", 8), ("luhn", 2), ("marks", 4), ("context", 2), ("range", 2), ("ending", 4))
CONTEXT = r"(?i)(mail|phone|tel|call|card|visa|account|address|contact|fax|mobile|kontakt|correo|tél|host|server)"
NEAR = 24
CANDIDATES = "array<struct<kind:int,s:int,e:int,t:string,base:boolean,context:boolean>>"


def digits_of(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def luhn(text: Column) -> Column:
    """Whether the digits of a text pass the Luhn check."""
    figures = F.transform(F.split(F.reverse(digits_of(text)), ""), lambda c: F.coalesce(c.try_cast("int"), F.lit(0)))
    doubled = F.transform(figures, lambda d, i: F.when(i % 2 == 0, d).otherwise(F.when(d > 4, 2 * d - 9).otherwise(2 * d)))
    return F.aggregate(doubled, F.lit(0), lambda a, d: a + d) % 10 == 0


def in_range(text: Column) -> Column:
    """Whether every part between dots is at most 255."""
    return F.forall(F.split(text, r"\."), lambda p: F.rlike(p, F.lit(r"^0*(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[0-9]{1,2})$")))


def passes(kind: str, text: Column) -> Column:
    n = F.length(digits_of(text))
    return {"email": F.lit(True), "ip": in_range(text), "card": n.between(14, 19) & luhn(text), "phone": n.between(10, 15)}.get(kind, F.lit(False))


def _generated(text: Column, number: int, g: Generator) -> Column:
    """The candidates of one generator in a text."""
    found = F.transform(spans(text, g.scan), lambda x: F.struct(
        F.lit(number).alias("kind"), x["s"].alias("s"), x["e"].alias("e"), x["t"].alias("t"), passes(g.kind, x["t"]).alias("base"),
        F.rlike(F.substring(text, F.greatest(x["s"] - NEAR + 1, F.lit(1)), F.least(x["s"], F.lit(NEAR))), F.lit(CONTEXT)).alias("context")))
    likely = F.rlike(text, F.lit(g.scan))
    if g.digits:
        likely = F.rlike(text, F.lit("[0-9]{2}|[0-9][^0-9][0-9]")) & likely
    if g.hints:
        likely = reduce(or_, [F.contains(text, F.lit(h)) for h in g.hints]) & likely
    return F.when(likely, found).otherwise(F.array().cast(CANDIDATES))


def candidates(docs: DataFrame) -> DataFrame:
    """(rid, doc_id, c): a row per document, c the candidates array<struct<kind, s, e, t, base, context>>."""
    text = F.col("text")
    parts = [_generated(text, number, g) for number, g in enumerate(GENERATORS)]
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return src.select("doc_id", F.concat(*parts).cast(CANDIDATES).alias("c"))


def features(kind: Column, t: Column, context: Column) -> list[Column]:
    """Binned features of a loose candidate's text and surroundings."""
    plain = F.regexp_replace(t, r"\[\.\]|\(\.\)|\[dot\]|\(dot\)", ".")
    marks = F.length(plain) - F.length(F.regexp_replace(plain, r"[\x20().@+-]", ""))
    ending = F.length(F.regexp_extract(t, "([A-Za-z]*)$", 1))
    return [kind.alias("kind"), F.least(F.lit(7), (F.length(digits_of(t)) / 3).cast("int")).alias("digits"), luhn(t).cast("int").alias("luhn"),
            F.least(F.lit(3), (marks / 2).cast("int")).alias("marks"), context.cast("int").alias("context"),
            F.coalesce(in_range(F.regexp_replace(plain, " ", "")), F.lit(False)).cast("int").alias("range"),
            F.when(ending < 2, 0).otherwise(F.least(F.lit(3), ending - 1)).cast("int").alias("ending")]


def examples(found: DataFrame) -> DataFrame:
    """(held, good, t, kind, context): spans of base forms rewritten to loose ones."""
    each = found.select((F.pmod(F.xxhash64("doc_id"), F.lit(5)) == 0).alias("held"), F.explode("c").alias("c")).where(F.col("c.kind") < len(BASE))
    text, form = F.lit(None).cast("string"), F.lit(None).cast("boolean")
    for k in range(len(BASE)):
        loose, g = F.col("c.t"), GENERATORS[len(BASE) + k]
        for pattern, new in g.loosen:
            loose = F.regexp_replace(loose, pattern, new)
        text = F.when(F.col("c.kind") == k, loose).otherwise(text)
        form = F.when(F.col("c.kind") == k, F.rlike(loose, F.lit(f"^{g.scan}$"))).otherwise(form)
    return each.where(form).select("held", F.col("c.base").alias("good"), text.alias("t"), F.col("c.kind").alias("kind"), F.col("c.context").alias("context"))


@dataclass(frozen=True)
class Tree:
    """value[(a, b)]: a whether the first test holds, b the second; a test is (feature, largest bin)."""

    first: tuple[str, int]
    second: dict[bool, tuple[str, int]]
    value: dict[tuple[bool, bool], float]

    def score(self, row: dict) -> float:
        a = row[self.first[0]] <= self.first[1]
        f, cutoff = self.second[a]
        return self.value[a, row[f] <= cutoff]


def boost(rows: list[dict], rounds: int = 20, rate: float = 0.3, ridge: float = 1.0) -> tuple[float, list[Tree]]:
    """Second-order boosting of depth-two trees on (features, pos, neg) rows; returns the prior and the trees."""
    pos, neg = sum(r["pos"] for r in rows), sum(r["neg"] for r in rows)
    prior = math.log((pos + 1) / (neg + 1))
    margin, trees = [prior] * len(rows), []
    tests = [(f, b) for f, n in FEATURES for b in range(n - 1)]

    def best(part: list[int], g: list[float], h: list[float]) -> tuple[float, tuple[str, int]]:
        top = (-1.0, tests[0])
        sg, sh = sum(g[i] for i in part), sum(h[i] for i in part)
        for f, b in tests:
            lg = sum(g[i] for i in part if rows[i][f] <= b)
            lh = sum(h[i] for i in part if rows[i][f] <= b)
            gain = lg * lg / (lh + ridge) + (sg - lg) ** 2 / (sh - lh + ridge) - sg * sg / (sh + ridge)
            top = max(top, (gain, (f, b)))
        return top

    for _ in range(rounds):
        p = [1 / (1 + math.exp(-max(-30.0, min(30.0, m)))) for m in margin]
        g = [r["pos"] * (1 - q) - r["neg"] * q for r, q in zip(rows, p)]
        h = [(r["pos"] + r["neg"]) * q * (1 - q) for r, q in zip(rows, p)]
        gain, first = best(list(range(len(rows))), g, h)
        if gain < 1e-6:
            break
        sides = {a: [i for i, r in enumerate(rows) if (r[first[0]] <= first[1]) == a] for a in (True, False)}
        second = {a: best(part, g, h)[1] for a, part in sides.items()}
        value = {}
        for a, part in sides.items():
            for b in (True, False):
                leaf = [i for i in part if (rows[i][second[a][0]] <= second[a][1]) == b]
                value[a, b] = rate * sum(g[i] for i in leaf) / (sum(h[i] for i in leaf) + ridge)
        tree = Tree(first, second, value)
        trees.append(tree)
        margin = [m + tree.score(r) for m, r in zip(margin, rows)]
    return prior, trees


def calibrate(rows: list[dict], prior: float, trees: list[Tree], precision: float) -> float:
    """The smallest margin whose lower bound of precision on held-out rows reaches ``precision``; inf if none."""
    scored = sorted(((prior + sum(t.score(r) for t in trees), r["pos"], r["neg"]) for r in rows), reverse=True)
    cutoff, pos, neg = math.inf, 0, 0
    for i, (m, p, n) in enumerate(scored):
        pos, neg = pos + p, neg + n
        if i + 1 < len(scored) and scored[i + 1][0] == m:
            continue
        total, z = pos + neg, 2.0
        share = pos / total if total else 0.0
        low = (share + z * z / (2 * total) - z * math.sqrt(share * (1 - share) / total + z * z / (4 * total * total))) / (1 + z * z / total) if total else 0
        if low >= precision:
            cutoff = m
    return cutoff


def fit(found: DataFrame, precision: float, rounds: int) -> tuple[float, list[Tree], dict[int, float]]:
    """Prior, trees, and the cutoff of each loose kind, from the candidates of all documents."""
    names = [f for f, _ in FEATURES]
    seen = examples(found).select("held", "good", *features(F.col("kind"), F.col("t"), F.col("context"))).groupBy("held", *names).agg(
        F.count_if("good").alias("pos"), F.count_if(~F.col("good")).alias("neg")).collect()  # as many rows as bins at most
    rows = [r.asDict() for r in seen]
    prior, trees = boost([r for r in rows if not r["held"]], rounds)
    return prior, trees, {k: calibrate([r for r in rows if r["held"] and r["kind"] == k], prior, trees, precision) for k in range(len(BASE))}


def find_personal_data(docs: DataFrame, precision: float = 0.98, rounds: int = 20) -> DataFrame:
    """One row per document: doc_id, base spans per kind, and ``added`` spans; array<struct<s, e, ...>> each."""
    found = cut(candidates(docs))
    prior, trees, cutoffs = fit(found, precision, rounds)

    def base(kind: int) -> Column:
        return F.filter("c", lambda x: (x["kind"] == kind) & x["base"])

    out = found.select("doc_id", *[base(k).alias(kind) for k, kind in enumerate(BASE)], F.filter("c", lambda x: x["kind"] >= len(BASE)).alias("rest"))
    names = [f for f, _ in FEATURES]
    table = [dict(zip(names, x)) for x in _combinations()]
    # The trees as the set of selected feature combinations: one membership test per candidate.
    keys = [_code(r) for r in table if prior + sum(t.score(r) for t in trees) >= cutoffs[r["kind"]]] if trees else []
    if not keys:
        return out.select("doc_id", *BASE, F.filter("rest", lambda x: F.lit(False)).alias("added"))
    known = F.concat(*BASE)

    def selected(x: Column) -> Column:
        code, factor = F.lit(0), 1
        for (_, n), f in zip(FEATURES, features(x["kind"] % len(BASE), x["t"], x["context"])):
            code, factor = code + f * factor, factor * n
        return F.array_contains(F.lit(keys), code)

    added = F.filter("rest", lambda x: ~F.exists(known, lambda b: (b["s"] < x["e"]) & (x["s"] < b["e"])) & selected(x))
    return out.select("doc_id", *BASE, added.alias("added"))


def _combinations() -> list[tuple[int, ...]]:
    rows: list[tuple[int, ...]] = [()]
    for _, n in FEATURES:
        rows = [r + (i,) for r in rows for i in range(n)]
    return rows


def _code(row: dict) -> int:
    code, factor = 0, 1
    for f, n in FEATURES:
        code, factor = code + row[f] * factor, factor * n
    return code


def digest(found: DataFrame) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans)."""
    base = F.concat(*[marks_of(k, i, F.col(k)) for i, k in enumerate(BASE)])
    names = F.array(*[F.lit(k) for k in KINDS])
    added = F.transform("added", lambda x: F.struct(x["s"].alias("s"), x["kind"].alias("k"), x["e"].alias("e"), F.element_at(names, x["kind"] + 1).alias("kind")))
    return found.select("doc_id", *[F.size(k).cast("long").alias(f"n_{k}") for k in BASE],
                        F.sha2(span_text(base), 256).alias("base_sha256"), span_text(F.concat(base, added)).alias("spans"))


def redact(docs: DataFrame, found: DataFrame, mask: str = "[{}]") -> DataFrame:
    """The documents with their spans replaced by the kind's mask; ``found``: rows of find_personal_data, one per doc_id."""
    names = F.array(*[F.lit(mask.format(k)) for k in KINDS])
    marks = F.array_sort(F.transform(F.concat(*BASE, "added"), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["kind"].alias("k"))))
    hits = found.select(F.col("doc_id").alias("id"), marks.alias("marks"))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc"), F.col("text").cast("string").alias("text"), F.struct(*[c for c in docs.columns if c != "text"]).alias("row"))
    both = rows.join(hits, rows["doc"] == hits["id"], "left")

    def step(acc: Column, x: Column) -> Column:
        fresh = x["s"] >= acc["at"]
        return F.struct(F.when(fresh, x["e"]).otherwise(F.greatest(acc["at"], x["e"])).alias("at"), F.when(fresh, F.concat(
            acc["out"], F.array(F.substring("text", acc["at"] + 1, x["s"] - acc["at"]), F.element_at(names, x["k"] + 1)))).otherwise(acc["out"]).alias("out"))

    cleaned = F.aggregate("marks", F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out")), step, lambda acc: F.concat(
        F.array_join(acc["out"], ""), F.substring("text", acc["at"] + 1, F.length("text") - acc["at"])))
    text = F.when(F.size("marks") > 0, cleaned).otherwise(F.col("text"))
    return both.select(*[text.alias("text") if c == "text" else F.col("row").getField(c).alias(c) for c in docs.columns])
