"""Line deduplication by winnowing over line hashes, in DataFrame expressions only.

A line is a stretch between newlines, or with ``sentences`` a sentence of it: lines are then also cut
at the space after a full stop, question or exclamation mark. Runs of blanks count as one, blanks at
the ends as none; lines without a word are left alone and skipped in the sequence of hashes.

The window that begins at a line is the shortest run of lines that holds ``long_words`` words, or
``window`` lines if that is shorter; it depends on its own lines alone, so equal runs have equal
windows. Of each window the line of the smallest hash is selected: its fingerprint. Equal windows have
equal fingerprints, so all places of a repeat meet where positions of equal fingerprints are joined.
There windows are matched with the earliest place that holds the same lines, and a match is extended to both sides,
line by line, over short lines that are equal too: a long line, or ``window`` short ones, is a window of
its own, so that short lines beyond an end, fewer than ``window``, are all that is left to compare.
Lines of matched runs that come later than their source, by (doc_id, position), go.

Defined results: a null text stays null; an empty text stays; documents whose lines all go keep an
empty text; rows without a doc_id are returned as they are; of repeated rows with one doc_id each
row is treated alike, as one document. Other columns pass through; n_chars is renewed if present.
"""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame, Row, Window
from pyspark.sql import functions as F

from ._common import cut, let

#: Documents sampled for hot keys, the share of windows and the number from which on a key is hot, and salts. They change no result.
SAMPLE, SHARE, OFTEN, SALTS = 2000, 0.002, 20, 64
#: Blanks within a line, those that make a run of them or are no space, and the ends after which a space begins a sentence.
_BLANKS, _UNEVEN, _STOPS = r"[\x20\x09\x0B-\x0D]+", ("  ", "\t", "\x0b", "\x0c", "\r"), ".!?"


def _stopped(text: Column) -> Column:
    """The text with a newline after each sentence, in place of the space there."""
    for end in _STOPS:
        text = F.replace(text, F.lit(f"{end} "), F.lit(f"{end}\n"))
    return text


def units(text: Column, sentences: bool = False) -> Column:
    """The text's lines, or the sentences of its lines, with single blanks and none at their ends."""
    cut_up = _stopped(text) if sentences else text
    uneven = reduce(or_, [F.contains(text, F.lit(x)) for x in _UNEVEN])
    even = F.when(uneven, F.regexp_replace(cut_up, _BLANKS, " ")).otherwise(cut_up)
    return F.transform(F.split(even, "\n", -1), lambda x: F.trim(x))


def line_marks(text: Column, sentences: bool = False, most: int = 50) -> Column:
    """array<struct<h, words>> of the lines with a word: hash and number of words, counted to ``most`` + 1."""
    worded = F.filter(units(text, sentences), lambda x: x != "")
    return F.transform(worded, lambda x: F.struct(F.xxhash64(x).alias("h"), F.size(F.split(x, " ", most + 1)).alias("words")))


def _at(lines: Column, i: Column) -> Column:
    """The i-th element, null outside the array."""
    return F.when(i >= 0, F.get(lines, F.greatest(i, F.lit(0))))


def _window(h: Column, words: Column, i: Column, window: int, long_words: int) -> Column:
    """The window that begins at line i: n lines, hash f of the selected one, hash g of all; null if the text ends before."""
    total, n = F.get(words, i), F.when(F.get(words, i) >= long_words, 1)
    for k in range(2, window + 1):
        total = total + F.get(words, i + k - 1)
        n = F.coalesce(n, F.when(total.isNotNull() if k == window else total >= long_words, k))
    n = n if window > 1 else F.lit(1)

    def beside(at: list[Column]) -> Column:
        """Hashes of the short lines beside an end, nearest first, as far as they go."""
        near, go = [], F.lit(True)
        for j in at:
            go = go & F.coalesce(_at(words, j) < long_words, F.lit(False))
            near.append(F.when(go, _at(h, j)))
        return F.when(near[0].isNotNull(), F.array(*near)) if near else F.lit(None).cast("array<bigint>")

    def whole(n: Column) -> Column:
        f = F.get(h, i)
        for k in range(1, window):
            f = F.when((n > k) & (F.get(h, i + k) < f), F.get(h, i + k)).otherwise(f)
        return row(n, f, F.xxhash64(n, *[F.when(n > k, F.get(h, i + k)) for k in range(window)]))

    def row(n: Column, f: Column, g: Column) -> Column:
        return F.struct(i.alias("i"), n.alias("n"), f.alias("f"), g.alias("g"), beside([i - k for k in range(1, window)]).alias("before"), beside([i + n + k for k in range(window - 1)]).alias("after"))

    alone = row(F.lit(1), F.get(h, i), F.get(h, i))
    return F.when(F.get(words, i) >= long_words, alone).when(n.isNotNull(), let(n, whole)) if window > 1 else alone


def line_hashes(docs: DataFrame, long_words: int = 50, sentences: bool = False) -> DataFrame:
    """(doc_id, h, words): hashes and numbers of words of each document's lines."""
    marks = docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), line_marks(F.col("text"), sentences, long_words).alias("m"))
    return marks.where(F.size("m") > 0).select("doc_id", F.col("m.h").alias("h"), F.col("m.words").alias("words"))


def fingerprints(lines: DataFrame, window: int = 3, long_words: int = 50, starts: list[int] | None = None) -> DataFrame:
    """(doc_id, i, n, f, g, before, after, h): the windows of each document, f the selected line, g all, h the first; ``starts``: only those that begin so."""
    def one(x: Column, i: Column) -> Column:
        made = _window(F.col("h"), F.col("words"), i, window, long_words)
        return F.struct(x.alias("h"), (made if starts is None else F.when(x.isin(starts), made)).alias("w"))
    out = lines.select("doc_id", F.explode(F.filter(F.transform("h", one), lambda x: x["w"].isNotNull())).alias("x"))
    return out.select("doc_id", "x.w.*", "x.h")


def hot_keys(lines: DataFrame, window: int, long_words: int) -> tuple[list[int], dict[int, int]]:
    """Fingerprints, and contents with the first line of each, that hold over ``SHARE`` of the windows in a bounded sample of documents: 1 / ``SHARE`` at most."""
    some = lines.where(F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(max(1, lines.count() // SAMPLE))) == 0)
    some = cut(fingerprints(some, window, long_words).select("f", "g", "h"))
    least = max(SHARE * some.count(), OFTEN)
    f = [r["f"] for r in some.groupBy("f").count().where(F.col("count") > least).collect()]
    return f, {r["g"]: r["h"] for r in some.groupBy("g", "h").count().where(F.col("count") > least).collect()}


def _looked_up(g: Column, tops: list[Row], window: int) -> Column:
    """The earliest place of a hot content; a literal of at most 1 / ``SHARE`` rows."""
    at = F.array_position(F.lit([r["g"] for r in tops]), g).cast("int")

    def pick(values: list, kind: str) -> Column:
        return F.element_at(F.array(*[F.lit(v).cast(kind) for v in values]), at)

    def side(name: str) -> Column:
        return F.array(*[pick([r["a"][name][k] if r["a"][name] else None for r in tops], "bigint") for k in range(window - 1)]).cast("array<bigint>")
    return F.struct(pick([r["a"]["doc_id"] for r in tops], "bigint").alias("doc_id"), pick([r["a"]["i"] for r in tops], "int").alias("i"), side("before").alias("before"), side("after").alias("after"))


def matches(lines: DataFrame, window: int = 3, long_words: int = 50) -> DataFrame:
    """(doc_id, first, last): runs of lines that occur earlier, extended to both sides.

    Places of equal fingerprints meet by one exchange; there windows of equal lines are matched with
    the earliest of them. A hot fingerprint's places are dealt by their window's content; those of hot
    contents stay where they are, as the earliest place of each is one row of a small literal.
    """
    windows = fingerprints(lines, window, long_words).drop("h")
    hot, contents = hot_keys(lines, window, long_words)
    source = F.struct("doc_id", "i", "before", "after")
    salt = F.when(F.col("f").isin(hot), F.pmod("g", F.lit(SALTS))).otherwise(0).cast("int") if hot else F.lit(0)
    cold = windows.where(~F.col("g").isin(list(contents))) if contents else windows
    order = Window.partitionBy("f", "salt", "g").orderBy("doc_id", "i").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    met = cold.withColumn("salt", salt).repartition("f", "salt").withColumn("a", F.first(source).over(order)).drop("salt")
    if contents:
        same = fingerprints(lines, window, long_words, list(set(contents.values()))).drop("h").where(F.col("g").isin(list(contents)))
        tops = same.groupBy("g").agg(F.min(source).alias("a")).collect()  # one row for each hot content
        met = met.unionByName(same.withColumn("a", _looked_up(F.col("g"), tops, window)))
    later = met.where((F.col("doc_id") > F.col("a.doc_id")) | ((F.col("doc_id") == F.col("a.doc_id")) & (F.col("i") > F.col("a.i"))))

    def extension(side: str) -> Column:
        same, count = F.lit(True), F.lit(0)
        for k in range(window - 1):
            same = same & F.coalesce(F.get(side, F.lit(k)) == F.get(F.col(f"a.{side}"), F.lit(k)), F.lit(False))
            count = count + same.cast("int")
        return count

    return later.select("doc_id", (F.col("i") - extension("before")).alias("first"), (F.col("i") + F.col("n") - 1 + extension("after")).alias("last"))


def repeats(docs: DataFrame, window: int = 3, long_words: int = 50, sentences: bool = False) -> DataFrame:
    """(doc_id, gone): the worded lines, by their order, that later repeats cover; sorted, per document."""
    runs = matches(cut(line_hashes(docs, long_words, sentences)), window, long_words)
    return runs.select("doc_id", F.explode(F.sequence("first", "last")).alias("i")).groupBy("doc_id").agg(F.sort_array(F.collect_set("i")).alias("gone"))


def _rest(text: Column, gone: Column, sentences: bool) -> Column:
    """The text without the worded lines whose numbers are in ``gone``, an ascending array."""
    every = F.transform(F.split(text, "\n", -1), lambda x, i: F.struct(x.alias("t"), i.alias("line")))
    if sentences:
        every = F.flatten(F.transform(F.split(text, "\n", -1), lambda x, i: F.transform(F.split(_stopped(x), "\n", -1), lambda t: F.struct(t.alias("t"), i.alias("line")))))

    def pieces(e: Column) -> Column:
        worded = F.filter(F.transform(e, lambda x, i: F.when(F.rlike(x["t"], F.lit(r"[^\x20\x09-\x0D]")), i)), lambda i: i.isNotNull())
        cut_at = let(worded, lambda w: F.transform(gone, lambda i: F.get(w, i)))
        # Pieces between the lines cut; each line is touched once.
        ends = F.concat(cut_at, F.array(F.size(e)))
        return F.flatten(let(ends, lambda s: F.transform(s, lambda x, k: F.slice(
            e, F.when(k > 0, F.element_at(s, F.greatest(k, F.lit(1))) + 2).otherwise(1),
            x - F.when(k > 0, F.element_at(s, F.greatest(k, F.lit(1))) + 1).otherwise(0)))))

    return let(let(every, pieces), lambda k: F.array_join(F.transform(k, lambda x, i: F.concat(
        F.when(i == 0, "").when(F.get(k, i - 1)["line"] < x["line"], "\n").otherwise(" "), x["t"])), ""))


def dedup_lines(docs: DataFrame, window: int = 3, long_words: int = 50, sentences: bool = False) -> DataFrame:
    """The documents without the lines of later repeated runs, and with n_gone, the number of lines cut."""
    gone = repeats(docs, window, long_words, sentences).withColumnRenamed("doc_id", "id")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc"), F.col("text").cast("string").alias("text"), F.struct(*[c for c in docs.columns if c != "text"]).alias("row"))
    both = rows.join(gone, rows["doc"] == gone["id"], "left")
    kept = F.col("gone").isNull() | F.col("text").isNull()
    out = both.select("row", F.when(kept, F.col("text")).otherwise(_rest(F.col("text"), F.col("gone"), sentences)).alias("text"),
                      F.when(kept, 0).otherwise(F.size("gone")).alias("n"), kept.alias("kept"))

    def column(name: str) -> Column:
        if name == "text":
            return F.col("text")
        old = F.col("row").getField(name)
        return F.when(F.col("kept"), old).otherwise(F.length("text").cast("long")).alias(name) if name == "n_chars" else old.alias(name)

    return out.select(*[column(c) for c in docs.columns], F.col("n").alias("n_gone"))


def dedup_corpus(docs: DataFrame, few_words: int = 5) -> DataFrame:
    """As ``dedup_lines``, by sentences: a window is the shortest run that holds ``few_words`` words, of three at most."""
    return dedup_lines(docs, long_words=few_words, sentences=True)
