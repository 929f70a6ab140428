"""Near copies by SimHash: links where five-word shingle sets have a Jaccard similarity of at least 4/5.

Fingerprints of whole shingle sets are searched by the vantage-point trees of ``simhash``, within the two
differing bits that those trees can prune for; pairs they connect are verified on whole sets. Two sets of
similarity 4/5 differ in ten of 64 bits on average, a radius at which triangle bounds prune nothing, as
random fingerprints differ in 32 with a deviation of 4. Beyond two bits, sets are therefore searched among
those that share a rare shingle: with the shingles of every set in one common order, two sets that similar
share one among the first n - ceil(4n/5) + 1 of each. The order puts shingles that a bounded sample of
documents finds frequent last; any order loses nothing, this one keeps groups of a shingle small. Within a
group, pairs whose sizes allow the similarity and whose fingerprints differ in at most ``REACH`` bits, five
deviations beyond the mean at 4/5, are verified: first on their rarest shingles, whose common ones bound
what whole sets can share, then those left on whole sets. Groups of some size take two rounds against
a few pivots, among them the set nearest to the group's majority of bits, which connects the copies of one
text; then all pairs that nothing has connected, block by block.

Defined results: null, empty and wordless texts have the empty set and are copies of each other; texts
of fewer than five words are one shingle; rows without a doc_id link nothing and stay; repeated rows of
one doc_id are one document; other columns pass through.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import simhash
from ._common import components, cut, tidy

SEED, WIDTH = 42, 5
#: The similarity as a fraction.
NUM, DEN = 4, 5
#: Documents sampled for the order of shingles, most shingles held to be frequent, and from how many documents on.
SAMPLE, FREQUENT, OFTEN = 4000, 200_000, 3
#: Bits in which the fingerprints of a pair may differ; rows of a group that is compared whole; pivots of a larger one.
REACH, SMALL, PIVOTS = 24, 12, 8
#: Rows of a block in a round of pivots, and in the last round; rows of small groups that go through a call together.
WIDE, BLOCK, TOGETHER = 65_536, 4_096, 16_384
#: Bits of the map by which rows of some ids are found; a number of ids beyond it lets more rows through to the exact join.
BITS = 1 << 25
#: Documents whose shingles are handed on together.
CHUNK = 256


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """Sorted distinct hashes of the text's shingles."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    grams = zip(*(words[i:] for i in range(width))) if len(words) >= width else [words] if words else []
    return np.unique(np.array([xxhash.xxh64_intdigest(b" ".join(g), SEED) for g in grams], np.uint64))


def print_of(hashes: np.ndarray) -> int:
    """SimHash fingerprint of a set of shingles, as a signed number."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 15):
        ones += np.unpackbits(hashes[at:at + (1 << 15)].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(hashes), bitorder="little").tobytes(), "little", signed=True)


def prefix(hashes: np.ndarray, frequent: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The shingles of which any set similar enough has one among its own."""
    if not len(hashes):
        return hashes
    rank = np.zeros(len(hashes), np.int64)
    if len(frequent):
        at = np.minimum(np.searchsorted(frequent, hashes), len(frequent) - 1)
        rank = np.where(frequent[at] == hashes, counts[at], 0)
    return hashes[np.lexsort((hashes, rank))][:len(hashes) + (-NUM * len(hashes)) // DEN + 1]


def _texts(docs: DataFrame) -> DataFrame:
    return docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def frequent_shingles(texts: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, documents) of the shingles that a sample finds in several documents, by hash."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for t in b.column(0):
                yield pa.RecordBatch.from_arrays([pa.array(shingles(t.as_py()).view(np.int64))], names=["h"])
    n = max(1, texts.count())
    some = texts.where(F.pmod(F.xxhash64("doc_id"), F.lit(n)) < SAMPLE).select("text").distinct()
    got = some.mapInArrow(run, "h long").groupBy("h").count().where(F.col("count") >= OFTEN) \
        .orderBy(F.desc("count"), "h").limit(FREQUENT).toPandas()
    h, c = got["h"].to_numpy(np.int64).view(np.uint64), got["count"].to_numpy(np.int64)
    order = np.argsort(h)
    return h[order], c[order]


def sets(texts: DataFrame) -> DataFrame:
    """(doc_id, digest, n, fp, keys) of each document's shingle set."""
    frequent, counts = frequent_shingles(texts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (b.slice(at, CHUNK) for b in batches for at in range(0, b.num_rows, CHUNK)):
            every = [shingles(t.as_py()) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([
                b.column(0), pa.array([xxhash.xxh3_128_digest(h.tobytes()) for h in every], pa.binary()), pa.array([len(h) for h in every], pa.int32()),
                pa.array([print_of(h) for h in every], pa.int64()), pa.array([prefix(h, frequent, counts).view(np.int64) for h in every], pa.list_(pa.int64()))],
                names=["doc_id", "digest", "n", "fp", "keys"])
    return texts.mapInArrow(run, "doc_id long, digest binary, n int, fp long, keys array<long>")


def _possible(i: np.ndarray, j: np.ndarray, rep, n, fp, root) -> np.ndarray:
    """Which pairs may be similar and are not connected yet."""
    return ((root[i] != root[j]) & (rep[i] != rep[j]) & (np.minimum(n[i], n[j]) * DEN >= np.maximum(n[i], n[j]) * NUM)
            & (np.bitwise_count(fp[i] ^ fp[j]) <= REACH))


def group_pairs(t: pa.Table, last: bool) -> pa.Table:
    """Pairs to verify in many groups at once: all of small groups and, in the last round, of any; else those with a group's pivots.

    In the last round ``mine`` says in which of two blocks a row is; pairs across them count, or all within one.
    """
    key, rep, n, root, mine = (t.column(c).to_numpy() for c in ("key", "rep", "n", "root", "mine"))
    order = np.lexsort((rep, key))
    key, rep, n, root, mine = key[order], rep[order], n[order].astype(np.int64), root[order], mine[order]
    fp = t.column("fp").to_numpy().astype(np.int64).view(np.uint64)[order]
    facts = rep, n, fp, root
    edge = np.r_[0, np.nonzero(key[1:] != key[:-1])[0] + 1, len(key)]
    size = np.repeat(np.diff(edge), np.diff(edge))
    us, vs = [], []

    def keep(i: np.ndarray, j: np.ndarray) -> None:
        good = _possible(i, j, *facts)
        us.append(rep[i[good]])
        vs.append(rep[j[good]])

    for off in range(1, SMALL):
        i = np.nonzero((key[off:] == key[:-off]) & (size[off:] <= SMALL))[0]
        if len(i):
            keep(i, i + off)
    for a, b in zip(edge[:-1][np.diff(edge) > SMALL], edge[1:][np.diff(edge) > SMALL]):
        every = np.arange(a, b)
        if last:
            halves = [every[mine[a:b] == x] for x in np.unique(mine[a:b])]
            one, two = (halves[0], halves[1]) if len(halves) == 2 else (every, every)
            for k in range(0, len(one), 256):
                i, j = (x.ravel() for x in np.meshgrid(one[k:k + 256], two, indexing="ij"))
                ahead = i < j if len(halves) == 1 else np.ones(len(i), bool)
                keep(i[ahead], j[ahead])
            continue
        bits = np.unpackbits(fp[a:b].view(np.uint8).reshape(-1, 8), axis=1)
        middle = np.packbits(2 * bits.sum(0, dtype=np.int64) > b - a).view(np.uint64)[0]
        by_size = every[np.argsort(n[a:b], kind="stable")]
        pivots = np.unique(np.r_[every[np.argmin(np.bitwise_count(fp[a:b] ^ middle))], by_size[np.linspace(0, b - a - 1, PIVOTS - 1).astype(np.int64)]])
        for x in pivots:
            keep(np.full(b - a, x), every)
    u, v = (np.concatenate(x) if us else np.zeros(0, np.int64) for x in (us, vs))
    return pa.table({"u": np.minimum(u, v), "v": np.maximum(u, v)})


def _likely_in(pairs: DataFrame, rows: DataFrame) -> DataFrame:
    """The rows whose doc_id occurs in the pairs (u, v), and few others: ids meet in a broadcast map of ``BITS`` bits, so no row moves."""
    def bit(c: str) -> Column:
        return F.pmod(F.xxhash64(c), F.lit(BITS))

    ids = pairs.select(F.explode(F.array("u", "v")).alias("_id")).select(bit("_id").alias("_bit"))
    words = cut(ids.groupBy(F.floor(F.col("_bit") / 64).alias("_word")).agg(F.expr("bit_or(shiftleft(1L, cast(_bit % 64 as int)))").alias("_bits")))
    on = F.floor(bit("doc_id") / 64) == F.col("_word")
    return rows.join(F.broadcast(words), on).where(F.getbit("_bits", (bit("doc_id") % 64).cast("int")) == 1).select(*rows.columns)


def possible(pairs: DataFrame, alone: DataFrame) -> DataFrame:
    """The pairs (u, v) that the prefixes of their sets leave possible; no similar pair is lost.

    Of two sets, take the one whose prefix ends earlier in the common order. What it shares with the other is shared
    by the prefixes, or lies beyond its own.
    """
    rows = _likely_in(pairs, alone.select("doc_id", "n", "keys"))
    a, b = (rows.select(F.col("doc_id").alias(x), F.col("n").alias(f"n{x}"), F.col("keys").alias(f"k{x}")) for x in ("u", "v"))
    most = F.size(F.array_intersect("ku", "kv")) + F.greatest(F.col("nu") - F.size("ku"), F.col("nv") - F.size("kv"))
    sized = F.least("nu", "nv") * DEN >= F.greatest("nu", "nv") * NUM
    return cut(pairs.join(a, "u").join(b, "v").where(sized & (most * (NUM + DEN) >= NUM * (F.col("nu") + F.col("nv")))).select("u", "v").distinct())


def verified(pairs: DataFrame, alone: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (u, v) of documents whose whole shingle sets are similar enough; a row at a time, whatever the sets' sizes."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, CHUNK):
                part = b.slice(at, CHUNK)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([shingles(t.as_py()).view(np.int64) for t in part.column(1)], pa.list_(pa.int64()))], names=["id", "s"])

    pairs = possible(pairs, alone)
    whole = cut(_likely_in(pairs, texts).mapInArrow(run, "id long, s array<long>").repartition("id").dropDuplicates(["id", "s"]))
    a, b = (whole.select(F.col("id").alias(x), F.col("s").alias(f"s{x}")) for x in ("u", "v"))
    both = F.size(F.array_intersect("su", "sv"))
    out = cut(pairs.join(a, "u").join(b, "v").where(both * (NUM + DEN) >= NUM * (F.size("su") + F.size("sv"))).select("u", "v").distinct())
    del a, b, whole
    tidy(out)
    return out


def near_copies(docs: DataFrame) -> DataFrame:
    """(doc_id, root) of every document linked to another; root is the smallest doc_id of its class."""
    texts = _texts(docs)
    every = cut(sets(texts))
    equal = every.groupBy("digest").agg(F.min("doc_id").alias("rep"))
    exact = cut(every.select("doc_id", "digest").join(equal, "digest").where("doc_id <> rep").select(F.col("doc_id").alias("u"), F.col("rep").alias("v")).distinct())
    copies = every.select("doc_id", "digest").join(equal, "digest").where("doc_id <> rep").select("doc_id", "digest").distinct()
    alone = cut(every.join(copies, ["doc_id", "digest"], "left_anti").dropDuplicates(["doc_id", "digest"]).select("doc_id", "n", "fp", "keys"))
    del every, equal, copies
    tidy(alone)
    keys = alone.select(F.explode("keys").alias("key"), F.col("doc_id").alias("rep"))
    shared = keys.groupBy(F.bitwise_not("key").alias("k")).count().where("count > 1").select(F.bitwise_not("k").alias("key"))
    keys = cut(keys.join(shared, "key", "left_semi"))
    tidy(keys)
    rows = cut(keys.join(alone.select(F.col("doc_id").alias("rep"), "n", "fp"), "rep"))
    del keys, shared
    tidy(rows)

    def pairs(roots: DataFrame, least: int, last: bool) -> DataFrame:
        """Pairs of one round, in groups of over ``least`` rows that are not connected yet."""
        known = rows.join(roots, F.col("rep") == F.col("node"), "left").select("key", "rep", "n", "fp", F.coalesce("root", "rep").alias("root"))
        width = known.groupBy(F.bitwise_not("key").alias("_k")).agg(F.count("*").alias("m"), F.min("root").alias("low"), F.max("root").alias("high"))
        width = width.where((F.col("low") != F.col("high")) & (F.col("m") > least))
        met = known.join(width.select(F.bitwise_not("_k").alias("_key"), "m"), F.col("key") == F.col("_key"))
        met = met.withColumn("parts", F.ceil(F.col("m") / F.lit(BLOCK if last else WIDE)).cast("int")).withColumn("mine", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int"))
        other = F.explode(F.sequence(F.lit(0), F.col("parts") - 1)) if last else F.col("mine")
        met = met.select("key", "rep", "n", "fp", "root", "mine", "m", other.alias("other"))
        deal = F.struct(F.when(F.col("m") > SMALL * 8, F.col("key")).alias("key"), F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"),
                        F.when(F.col("m") <= SMALL * 8, F.pmod(F.xxhash64("key", F.lit(3)), F.lit(groups))).alias("g"))
        return cut(met.groupBy(deal.alias("deal")).applyInArrow(lambda t: group_pairs(t, last), "u long, v long").distinct())

    groups = max(1, rows.count() // TOGETHER)
    prints = cut(alone.where("n > 0").groupBy("fp").agg(F.min("doc_id").alias("rep")))
    found = simhash.class_edges(prints).select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    same = alone.where("n > 0").select("doc_id", "fp").join(prints, "fp").where("doc_id <> rep").select(F.col("rep").alias("u"), F.col("doc_id").alias("v"))
    edges = verified(cut(found.unionByName(same)), alone, texts)
    roots = components(edges)
    for least, last in ((1, False), (SMALL, False), (SMALL, True)):
        more = verified(pairs(roots, least, last), alone, texts)
        if not more.isEmpty():
            roots = components(more.unionByName(roots.select(F.col("node").alias("u"), F.col("root").alias("v"))))
    # The document that stands for equal sets is the smallest of them, so a root is the smallest of its class.
    copies = exact.join(roots, F.col("v") == F.col("node"), "left").select(F.col("u").alias("doc_id"), F.coalesce("root", "v").alias("root"))
    return copies.unionByName(roots.select(F.col("node").alias("doc_id"), "root"))


def keep_one(docs: DataFrame) -> DataFrame:
    """The documents, one of each class of near copies: that of the smallest doc_id. Rows without doc_id stay."""
    gone = near_copies(docs).where("root <> doc_id").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"].cast("long") == gone["_gone"], "left_anti")
