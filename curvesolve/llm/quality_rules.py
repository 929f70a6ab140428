"""Quality rules whose cutoffs are chosen under risk control.

Each document gets text signals, one per rule, on a grid. A quarter of the labelled documents, taken
by hash, only orders the candidates: per rule and grid point, the share of good ones among those at or
beyond it is the point's level, and a document's level is the lowest of its rules. Rejecting all
documents up to a level is thus a vector of cutoffs, one per rule, and levels make one sequence of such
vectors, from lenient to strict; it ends where good documents outnumber bad ones.

On the other labelled documents of each stratum (language) the vectors are tested in that order: one
is certified while the exact binomial (Clopper-Pearson) upper bound on the share of good documents that
all rules together reject stays within the risk, and testing stops at the first that fails. A fixed
sequence needs no correction among its own steps; the confidence is corrected (Bonferroni) for the
strata tested: as many as have enough good documents to certify anything at that correction. The last
certified vector applies. Strata that are not tested reject nothing by the method, which each row of
theirs says in ``certified``.

Defined results: a null text has no words; an empty table gives an empty result; null languages are
a stratum of their own; labels that are null or repeated rows count as they stand; other columns of
the input are ignored.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import cut

SYMBOLS = b"#*$%&|<>"
BLANKS = b" \t\n\x0b\x0c\r"
GRID = 200
RULES = ("symbols", "dup_lines", "repeats", "long_words", "short_words")
COUNTS = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words")


def text_counts(text: str | None) -> tuple[int, ...]:
    """The counts named in COUNTS for one whole text."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = raw.split()
    lines = [x for x in raw.split(b"\n") if x.strip(BLANKS)]
    windows = list(zip(words, words[1:], words[2:]))
    repeated = 0
    if len(set(windows)) < len(windows):
        seen = Counter(windows)
        covered = -1
        for i, w in enumerate(windows):
            if seen[w] > 1:
                repeated += i + 2 - max(covered, i - 1)
                covered = i + 2
    return (len(words), len(text or "") - (len(raw) - len(raw.translate(None, BLANKS))),
            len(raw) - len(raw.translate(None, SYMBOLS)), len(lines), len(lines) - len(set(lines)), repeated)


def _count_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = [text_counts(t.as_py()) for t in b.column(1)]
        cols = list(zip(*rows)) if rows else [[] for _ in COUNTS]
        yield pa.RecordBatch.from_arrays(
            [b.column(0), b.column(2), *(pa.array(c, pa.int64()) for c in cols)], names=["doc_id", "stratum", *COUNTS])


def signals(docs: DataFrame) -> DataFrame:
    """(doc_id, stratum, counts) of every document."""
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"),
                      F.coalesce(F.col("lang").cast("string"), F.lit("")).alias("stratum"))
    return src.mapInArrow(_count_batches, "doc_id long, stratum string, " + ", ".join(f"{c} long" for c in COUNTS))


def binomial_upper(k: int, n: int, delta: float) -> float:
    """Exact upper bound: the rate p at which seeing k or fewer of n has probability delta."""
    if n == 0 or k >= n:
        return 1.0

    def tail(p: float) -> float:
        term = n * math.log1p(-p)
        total = math.exp(term) if term > -745 else 0.0
        for i in range(1, k + 1):
            term += math.log((n - i + 1) / i) + math.log(p) - math.log1p(-p)
            total += math.exp(term) if term > -745 else 0.0
        return total

    lo, hi = k / n, 1.0 - 1e-12
    lo = max(lo, 1e-12)
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if tail(mid) > delta else (lo, mid)
    return hi


def bins() -> list[Column]:
    """Grid point of each rule's signal, 0..GRID; larger is worse."""
    def share(a: str, b: str) -> Column:
        return F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(0.0))
    mean = share("word_chars", "n_words")
    raw = (share("n_symbols", "word_chars"), share("n_dup_lines", "n_lines"), share("n_repeat_words", "n_words"),
           mean / 50, F.greatest(F.lit(0.0), F.lit(1.0) - mean / 20))
    return [F.least(F.lit(GRID), F.floor(x * GRID)).cast("int").alias(r) for r, x in zip(RULES, raw)]


def levels(tails: list[tuple[str, int, bool, int]]) -> dict[str, list[int]]:
    """Level of each rule's grid points, 0..GRID, from (rule, bin, good, documents): the lower, the fewer good ones beyond."""
    out = {}
    for rule in RULES:
        good, bad = [0] * (GRID + 1), [0] * (GRID + 1)
        for r, b, g, n in tails:
            if r == rule:
                (good if g else bad)[b] += n
        level, up, down = [GRID] * (GRID + 1), sum(good), sum(bad)
        for b in range(GRID + 1):
            level[b] = min(level[b - 1] if b else GRID, math.ceil(GRID * (up + 1) / (up + down + 2)))
            up, down = up - good[b], down - bad[b]
        out[rule] = level
    return out


def level_columns(of: dict[str, list[int]]) -> list[Column]:
    return [F.element_at(F.lit(of[r]), b + 1).alias(f"level_{r}") for r, b in zip(RULES, bins())]


def needed(risk: float, delta: float, strata: int) -> int:
    """Good documents from which on a stratum can be certified: with none rejected, the exact bound is 1 - delta ** (1 / n)."""
    return math.ceil(math.log(delta / strata) / math.log1p(-risk))


def fit_cutoffs(labelled: DataFrame, risk: float = 0.02, delta: float = 0.05, fit_parts: int = 4) -> tuple[dict[str, list[int]], dict[str, int]]:
    """(level of each rule's grid points, {stratum: last certified level}); documents up to it are rejected.

    ``labelled``: signals and ``good`` of labelled documents. ``risk`` bounds the share of good documents
    rejected in a stratum, with probability 1 - ``delta`` over all strata; one part in ``fit_parts``
    orders the candidates. Only histograms reach the driver: rules x grid, and for strata of at least
    ``needed`` good documents their grid.
    """
    parted = cut(labelled.select("stratum", "good", (F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(fit_parts)) == 0).alias("fit"), *bins()))
    per = F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.col(r).alias("bin")) for r in RULES]))
    tails = parted.where("fit").select("good", per.alias("x")).groupBy("x.rule", "x.bin", "good").count().collect()
    of = levels([(r["rule"], r["bin"], r["good"], r["count"]) for r in tails])
    test = parted.where(~F.col("fit"))
    ample = test.where("good").groupBy("stratum").agg(F.count("*").alias("n")).where(F.col("n") >= needed(risk, delta, 1))
    sizes = sorted(((r["n"], r["stratum"]) for r in ample.collect()), reverse=True)
    strata = max((m for m in range(1, len(sizes) + 1) if sizes[m - 1][0] >= needed(risk, delta, m)), default=0)
    chosen = {s: n for n, s in sizes[:strata]}
    worst = F.least(*[F.element_at(F.lit(of[r]), F.col(r) + 1) for r in RULES])
    hist = test.where("good").join(ample.select("stratum"), "stratum", "left_semi").groupBy("stratum", worst.alias("level")).count().collect()
    rejected: dict[str, Counter] = defaultdict(Counter)
    for r in hist:
        rejected[r["stratum"]][r["level"]] += r["count"]
    cutoffs = {}
    for stratum, n in chosen.items():
        good, last = 0, -1
        for level in range(GRID // 2 + 1):
            good += rejected[stratum][level]
            if binomial_upper(good, n, delta / strata) > risk:
                break
            last = level
        cutoffs[stratum] = last
    return of, cutoffs


def apply_rules(docs: DataFrame, labels: DataFrame, risk: float = 0.02, delta: float = 0.05,
                min_words: int = 50, repeat_pct: int = 50, few: int = 5000) -> DataFrame:
    """One row per document with its counts, base_failed, the rules it breaks, whether its stratum is certified, and kept.

    The cutoff table has a row per stratum that is certified; up to ``few`` rows it is broadcast, beyond
    that it is joined by shuffle.
    """
    got = cut(signals(docs))
    known = labels.where("quality is not null").select(F.col("doc_id").cast("long").alias("doc_id"), (F.col("quality") == 1).alias("good"))
    of, cutoffs = fit_cutoffs(got.join(known, "doc_id"), risk, delta)
    limits = docs.sparkSession.createDataFrame(sorted(cutoffs.items()), "stratum string, last int")
    scored = got.select("*", *level_columns(of)).join(F.broadcast(limits) if len(cutoffs) <= few else limits, "stratum", "left")
    broken = F.filter(F.array(*[F.when(F.col(f"level_{r}") <= F.col("last"), F.lit(r)) for r in RULES]), lambda x: x.isNotNull())
    failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > repeat_pct * F.col("n_words"))
    return scored.select("doc_id", *[c for c in COUNTS if c != "n_lines"], failed.alias("base_failed"), F.array_join(broken, ",").alias("broken"),
                         F.coalesce(F.col("last") >= 0, F.lit(False)).alias("certified"), (~failed & (F.size(broken) == 0)).alias("kept"))
