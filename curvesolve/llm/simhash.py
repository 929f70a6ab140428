"""SimHash fingerprints and exact near-duplicate classes at a small Hamming distance.

Distinct fingerprints are dealt to shards by a vantage-point tree over the Hamming metric: at each
level a fingerprint lies inside or outside a radius around the level's vantage point. By the triangle
inequality two fingerprints within ``radius`` can be parted only if the inner one lies within
``radius`` of the boundary, so inner fingerprints of that rim also go outside. Every linked pair thus
meets in at least one shard, where the same rule goes on locally with vantage points of the shard
until blocks are small enough for exact comparison. A shard yields only edges that connect each of
its linked classes, never all pairs, and classes are joined across shards.

Clusters too dense for triangle bounds to part (all points near any vantage point) are linked through
shared neighbours: two fingerprints differ in at most two bits if and only if some value lies within
one bit of both, so grouping on the 65 values around each fingerprint links them exactly, in a
number of rows in proportion to the input.

Defined results: null, empty and wordless texts have fingerprint zero, linked like any other; rows
without a doc_id get a fingerprint and the class of that fingerprint but link nothing; repeated rows
of one doc_id are one document; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import components, cut, keyed_min, spanning

SEED = 42
#: Fingerprints per shard to aim at, per block of exact comparison, and most per shard in one task.
SHARD, BLOCK, MOST = 4096, 192, 400_000
#: Fingerprints used to place the radius of each level; a fixed bound.
SAMPLE = 8192


def fingerprint(text: str | None, width: int = 3, seed: int = SEED) -> int:
    """64-bit fingerprint: a bit is set if it is set in over half the shingle hashes."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    n = max(1, len(words) - width + 1)
    ones = np.zeros(64, np.int64)
    for at in range(0, n, 1 << 15):
        part = words[at:at + (1 << 15) + width - 1]
        grams = zip(*(part[i:] for i in range(width))) if len(words) >= width else [words]
        hashes = np.array([digest(b" ".join(g), seed) for g in grams], "<u8")
        ones += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > n, bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, width: int = 3, seed: int = SEED) -> DataFrame:
    """(doc_id, fp): fp is the fingerprint's bits as a signed long."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([fingerprint(t.as_py(), width, seed) for t in b.column(1)], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp, pa.int64())], names=["doc_id", "fp"])
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id long, fp long")


def vantage_levels(distinct: DataFrame, n: int, shard: int = SHARD) -> list[tuple[int, int]]:
    """(vantage point, radius) of each level of the shard tree, from a bounded sample of fingerprints."""
    depth = max(0, math.ceil(math.log2(max(1, n) / shard)))
    if not depth:
        return []
    got = distinct.orderBy(F.xxhash64("fp"), "fp").limit(SAMPLE).select("fp").toPandas()["fp"].to_numpy(np.int64).view(np.uint64)
    points = np.random.default_rng(SEED).integers(0, 1 << 64, depth, dtype=np.uint64, endpoint=False)
    return [(int(p), int(np.median(np.bitwise_count(got ^ p)))) for p in points]


def route(fps: np.ndarray, levels: list[tuple[int, int]], radius: int) -> tuple[np.ndarray, np.ndarray]:
    """(index, shard) pairs: each fingerprint's own shard and those whose boundary it may overlap."""
    at, shard = np.arange(len(fps)), np.zeros(len(fps), np.int64)
    for point, reach in levels:
        d = np.bitwise_count(fps[at] ^ np.uint64(point)).astype(np.int64)
        inner, outer = d <= reach, d > reach - radius
        at = np.concatenate([at[inner], at[outer]])
        shard = np.concatenate([shard[inner] * 2, shard[outer] * 2 + 1])
    return at, shard


def neighbour_edges(fps: np.ndarray) -> np.ndarray:
    """Edges (i, j) that connect exactly the classes of distinct fingerprints within two bits."""
    flips = np.concatenate([np.zeros(1, np.uint64), np.uint64(1) << np.arange(64, dtype=np.uint64)])
    keys = (fps[:, None] ^ flips).ravel()
    who = np.repeat(np.arange(len(fps)), len(flips))
    order = np.argsort(keys, kind="stable")
    keys, who = keys[order], who[order]
    first = np.r_[True, keys[1:] != keys[:-1]]
    head = who[np.maximum.accumulate(np.where(first, np.arange(len(keys)), 0))]
    return np.unique(np.stack([who, head], 1)[who != head], axis=0)


def block_edges(fps: np.ndarray, at: np.ndarray, radius: int, rng: np.random.Generator) -> Iterator[np.ndarray]:
    """Edges of a shard by local vantage-point splits and exact comparison in the leaves."""
    todo = [at]
    while todo:
        at = todo.pop()
        if len(at) <= BLOCK:
            i, j = np.nonzero(np.triu(np.bitwise_count(fps[at][:, None] ^ fps[at]) <= radius, 1))
            yield np.stack([at[i], at[j]], 1)
            continue
        d = np.bitwise_count(fps[at] ^ fps[at[rng.integers(len(at))]]).astype(np.int64)
        reach = int(np.median(d))
        inner, outer = at[d <= reach], at[d > reach - radius]
        if max(len(inner), len(outer)) > 0.8 * len(at):
            if radius != 2:
                for k in range(0, len(at), BLOCK):
                    i, j = np.nonzero(np.bitwise_count(fps[at[k:k + BLOCK]][:, None] ^ fps[at]) <= radius)
                    keep = at[k + i] < at[j]
                    yield np.stack([at[k + i][keep], at[j][keep]], 1)
            else:
                yield at[neighbour_edges(fps[at])]
        else:
            todo += [inner, outer]


def _shard_edges(t: pa.Table, radius: int) -> pa.Table:
    fps = t.column("fp").to_numpy().astype(np.int64).view(np.uint64)
    rep = t.column("rep").to_numpy()
    root = spanning(len(fps), block_edges(fps, np.arange(len(fps)), radius, np.random.default_rng(SEED)))
    linked = root != np.arange(len(fps))
    return pa.table({"u": rep[linked], "v": rep[root[linked]]})


def class_edges(distinct: DataFrame, radius: int = 2, shard: int = SHARD) -> DataFrame:
    """Edges (u, v) between representatives (``rep``) of distinct fingerprints (``fp``), enough to connect every class."""
    levels = vantage_levels(distinct, distinct.count(), shard)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at, cell = route(b.column(0).to_numpy().astype(np.int64).view(np.uint64), levels, radius)
            yield pa.RecordBatch.from_arrays([pa.array(cell), b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at))],
                                             names=["cell", "fp", "rep"])

    dealt = distinct.select("fp", "rep").mapInArrow(deal, "cell long, fp long, rep long")
    big = [r["cell"] for r in dealt.groupBy("cell").count().where(F.col("count") > MOST).collect()]
    local = dealt.where(~F.col("cell").isin(big)) if big else dealt
    edges = local.groupBy("cell").applyInArrow(lambda t: _shard_edges(t, radius), "u long, v long")
    if big:
        if radius != 2:
            raise ValueError("shards beyond one task's room are supported for two differing bits")
        around = F.array(F.col("fp"), *[F.col("fp").bitwiseXOR(F.lit((1 << i) - (1 << 64 if i == 63 else 0))) for i in range(64)])
        dense = dealt.where(F.col("cell").isin(big)).select("rep", F.explode(around).alias("key")).distinct()
        edges = edges.unionByName(dense.join(keyed_min(dense, "key", "rep", "v"), "key").where("rep <> v").select(F.col("rep").alias("u"), "v"))
    return edges


def near_duplicates(docs: DataFrame, radius: int = 2, width: int = 3, seed: int = SEED, shard: int = SHARD) -> DataFrame:
    """(doc_id, fingerprint as 16 hex digits, component_id) of every document."""
    prints = cut(fingerprints(docs, width, seed))
    distinct = cut(prints.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")))
    classes = components(class_edges(distinct, radius, shard))
    roots = distinct.join(classes, distinct["rep"] == classes["node"], "left").select(
        F.col("fp").alias("_fp"), F.coalesce("root", "rep").alias("component_id"))
    return prints.join(roots, F.col("fp") == F.col("_fp"), "left").select(
        "doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The documents, one of each near-duplicate class: that of the smallest doc_id. Rows without doc_id stay."""
    gone = near_duplicates(docs, **options).where("component_id <> doc_id").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"].cast("long") == gone["_gone"], "left_anti")
