"""Embedding near-duplicates: binary codes by iterative quantisation, multi-index tables, exact rerank.

Rotations are learned on a bounded sample (principal axes, then alternating sign codes and orthogonal
fits), which balances the bits; for codes longer than a vector several are laid side by side. A code is
cut into substrings, one table each: vectors of one label that agree on a whole substring meet there.
Substrings grow with the number of vectors, and their number follows from their length so that a pair
at the threshold is met with the stated chance. Pairs met are searched by the Hamming radius of the
whole code, four standard deviations beyond what the threshold's angle turns over; only vectors with
a neighbour within it go on, in the first table where the pair meets, and only there the vectors
themselves are looked up and compared in double precision.

Copies are folded into classes first. No list of pairs is made: the search marks vectors, and the
rerank yields link counts and edges that connect a bucket's classes. Buckets beyond a block's size are
compared block by block, each pair of blocks a task of its own.

Defined results: vectors that are null, zero, or hold null or non-finite components, and rows without
label or vec_id, link with nothing; vectors of different length never link; repeated rows are copies
and link; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import components, cut, spanning

#: Vectors the rotations are learned from, at most; rows of a block of comparison; iterations of the fit.
SAMPLE, BLOCK, ROUNDS = 16384, 4096, 25
#: Rows up to which a bucket is small; rows of small buckets per group.
SMALL, GROUP = 256, 8192
BUCKET = ["label", "t", "key"]


def learn(x: np.ndarray, bits: int, seed: int = 7) -> np.ndarray:
    """Projection (dim x bits) of one or more learned rotations, side by side."""
    dim = x.shape[1]
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    axes = np.linalg.eigh(np.cov(x.T) if len(x) > 1 else np.eye(dim))[1][:, ::-1] if dim > 1 else np.eye(1)
    rng, parts = np.random.default_rng(seed), []
    for _ in range(-(-bits // dim)):
        y = x @ axes
        r = np.linalg.qr(rng.standard_normal((dim, dim)))[0]
        for _ in range(ROUNDS if len(x) > dim else 0):
            u, _, vt = np.linalg.svd(np.where(y @ r >= 0, 1.0, -1.0).T @ y)
            r = (u @ vt).T
        parts.append(axes @ r)
    return np.concatenate(parts, 1)[:, :bits]


def plan(n: int, cosine: float, chance: float = 0.97) -> tuple[int, int]:
    """(key bits, tables): keys of about log2(n) - 2 bits; tables enough for ``chance`` at the threshold."""
    bits = min(20, max(6, math.ceil(math.log2(max(2, n))) - 2))
    miss = 1 - (1 - math.acos(min(1.0, cosine)) / math.pi) ** bits
    return bits, max(2, math.ceil(math.log(1 - chance) / math.log(miss)))


def radius(bits: int, cosine: float) -> int:
    """Bits in which the codes of a pair at the threshold may differ: the mean and four standard deviations."""
    p = math.acos(min(1.0, cosine)) / math.pi
    return math.ceil(bits * p + 4 * math.sqrt(bits * p * (1 - p)))


def table_keys(x: np.ndarray, projection: np.ndarray, bits: int) -> np.ndarray:
    """Keys (rows x tables) of vectors."""
    signs = (x @ projection >= 0).reshape(len(x), -1, bits)
    return (signs * (1 << np.arange(bits))).sum(2).astype(np.int32)


def _fresh(ka: np.ndarray, kb: np.ndarray, t: int) -> np.ndarray:
    """Whether pairs agree on no table before t."""
    return ~(ka[..., :t] == kb[..., :t]).any(-1)


def _near(ka: np.ndarray, kb: np.ndarray, t: int, reach: int) -> np.ndarray:
    """Whether codes differ in at most ``reach`` bits and meet first in table t."""
    return (np.bitwise_count(ka ^ kb).sum(-1, dtype=np.int64) <= reach) & _fresh(ka, kb, t)


def _mark_blocks(a: pd.DataFrame, b: pd.DataFrame, same: bool, t: int, reach: int) -> pd.DataFrame:
    """Rows of two blocks of a bucket that have a neighbour in the other."""
    ka, kb = (np.stack([np.frombuffer(v, "<i4") for v in d["keys"]]) for d in (a, b))
    ha, hb = np.zeros(len(a), bool), np.zeros(len(b), bool)
    for k in range(0, len(a), 256):
        part = _near(ka[k:k + 256, None], kb, t, reach)
        if same:
            part &= np.arange(k, k + len(part))[:, None] != np.arange(len(b))
        ha[k:k + 256] |= part.any(1)
        hb |= part.any(0)
    return pd.concat([a[ha], b[hb]])


def _mark_small(d: pd.DataFrame, reach: int) -> pd.DataFrame:
    """The same for many small buckets at once."""
    d = d.sort_values(["label", "t", "key", "rep"])
    where = d[["label", "t", "key"]].to_numpy()
    bucket = np.cumsum(np.r_[True, (where[1:] != where[:-1]).any(1)])
    keys, t = np.stack([np.frombuffer(v, "<i4") for v in d["keys"]]), d["t"].to_numpy()
    hit = np.zeros(len(d), bool)
    for off in range(1, len(d)):
        i = np.nonzero(bucket[off:] == bucket[:-off])[0]
        if not len(i):
            break
        i = i[np.bitwise_count(keys[i] ^ keys[i + off]).sum(1, dtype=np.int64) <= reach]
        i = i[~((keys[i] == keys[i + off]) & (np.arange(keys.shape[1]) < t[i][:, None])).any(1)]
        hit[i] = hit[i + off] = True
    return d[hit]


def _unit(raw: pd.Series) -> np.ndarray:
    """Vectors of unit length in double precision from their bytes, four or eight a component."""
    x = np.stack([np.frombuffer(v[1:], "<f4" if v[0] == 4 else "<f8") for v in raw]).astype(float)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _pair_up(a: pd.DataFrame, b: pd.DataFrame, same: bool, cosine: float, t: int) -> pd.DataFrame:
    """Counts (a = rep, n) and connecting edges (a, b) between two blocks that share table t's key."""
    xa, xb = _unit(a["x"]), _unit(b["x"])
    ka, kb = (np.stack([np.frombuffer(v, "<i4") for v in d["keys"]]) for d in (a, b))
    na, nb = a["copies"].to_numpy(), b["copies"].to_numpy()
    ca, cb = np.zeros(len(a), np.int64), np.zeros(len(b), np.int64)
    link = np.zeros((len(a), len(b)), bool)
    for k in range(0, len(a), 512):
        part = xa[k:k + 512] @ xb.T >= cosine
        if same:
            part &= np.arange(k, k + len(part))[:, None] < np.arange(len(b))
        i, j = np.nonzero(part)
        old = np.zeros(len(i), bool)
        for s in range(t):
            old |= ka[k + i, s] == kb[j, s]
        part[i[old], j[old]] = False
        link[k:k + 512] = part
        ca[k:k + 512] += part @ nb
        cb += na[k:k + 512] @ part
    ra, rb = a["rep"].to_numpy(), b["rep"].to_numpy()
    la, lb, far = ra.copy(), rb.copy(), np.iinfo(np.int64).max
    while link.any():
        nl = np.minimum(la, np.where(link, lb, far).min(1))
        nr = np.minimum(lb, np.where(link, nl[:, None], far).min(0))
        if same:
            nl = nr = np.minimum(nl, nr)
        if (nl == la).all() and (nr == lb).all():
            break
        la, lb = nl, nr
    out = [pd.DataFrame({"a": ra[ca > 0], "b": pd.array([None] * int((ca > 0).sum()), "Int64"), "n": ca[ca > 0]}),
           pd.DataFrame({"a": rb[cb > 0], "b": pd.array([None] * int((cb > 0).sum()), "Int64"), "n": cb[cb > 0]}),
           pd.DataFrame({"a": ra[la != ra], "b": pd.array(la[la != ra], "Int64"), "n": 0}),
           pd.DataFrame({"a": rb[lb != rb], "b": pd.array(lb[lb != rb], "Int64"), "n": 0})]
    return pd.concat(out)


def _small_buckets(d: pd.DataFrame, cosine: float) -> pd.DataFrame:
    """The same for many small buckets at once: neighbours at each distance within a bucket."""
    d = d.sort_values(["label", "t", "key", "rep"])
    where = d[["label", "t", "key"]].to_numpy()
    bucket = np.cumsum(np.r_[True, (where[1:] != where[:-1]).any(1)])
    x, keys = _unit(d["x"]), np.stack([np.frombuffer(v, "<i4") for v in d["keys"]])
    t, copies = d["t"].to_numpy(), d["copies"].to_numpy()
    reps, who = np.unique(d["rep"].to_numpy(), return_inverse=True)
    counts, edges = np.zeros(len(reps), np.int64), []
    for off in range(1, len(d)):
        i = np.nonzero(bucket[off:] == bucket[:-off])[0]
        if not len(i):
            break
        i = i[np.einsum("ij,ij->i", x[i], x[i + off]) >= cosine]
        i = i[~((keys[i] == keys[i + off]) & (np.arange(keys.shape[1]) < t[i][:, None])).any(1)]
        np.add.at(counts, who[i], copies[i + off])
        np.add.at(counts, who[i + off], copies[i])
        edges.append(np.stack([who[i], who[i + off]], 1))
    root = spanning(len(reps), iter(edges))
    far = root != np.arange(len(reps))
    return pd.concat([pd.DataFrame({"a": reps[counts > 0], "b": pd.array([None] * int((counts > 0).sum()), "Int64"), "n": counts[counts > 0]}),
                      pd.DataFrame({"a": reps[far], "b": pd.array(reps[root[far]], "Int64"), "n": 0})])


def links(vectors: DataFrame, cosine: float = 0.98, chance: float = 0.97, seed: int = 7) -> DataFrame:
    """One row per vector: vec_id, n_links, component_id, kept."""
    raw = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"),
                         F.col("embedding").cast("array<double>").alias("v"))
    square = F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)
    sound = F.coalesce((square > 0) & (square < float("inf")) & F.col("label").isNotNull() & F.col("vec_id").isNotNull(), F.lit(False))
    marked = cut(raw.select("vec_id", sound.alias("sound"), F.xxhash64("label", "v").alias("h1"), F.xxhash64("v", "label", F.lit(1)).alias("h2"),
                            F.when(sound, F.col("v")).alias("v"), "label"))
    folded = cut(marked.where("sound").groupBy(F.bitwise_not("h1").alias("k1"), F.bitwise_not("h2").alias("k2")).agg(
        F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.first("v").alias("v"), F.first("label").alias("label")))
    sizes = folded.groupBy(F.size("v").alias("dim")).count().collect()  # one row for each length of vector
    parts = []
    for row in sizes:
        some = folded.where(F.size("v") == row["dim"])
        sample = np.stack(some.orderBy(F.xxhash64("rep")).limit(SAMPLE).select("v").toPandas()["v"].to_numpy()).astype(float)
        bits, tables = plan(row["count"], cosine, chance)
        parts.append(_bucket_links(some, row["count"], learn(sample, bits * tables, seed), bits, tables, cosine))
    if parts:
        found = parts[0]
        for p in parts[1:]:
            found = found.unionByName(p)
        found = cut(found)
    else:
        found = marked.limit(0).select(F.col("vec_id").alias("a"), F.col("vec_id").alias("b"), F.col("vec_id").alias("n"))
    counts = found.where("n > 0").groupBy("a").agg(F.sum("n").alias("n"))
    roots = components(found.where("b is not null").select(F.col("a").alias("u"), F.col("b").alias("v")))
    classes = folded.join(counts, folded["rep"] == counts["a"], "left").join(roots, F.col("rep") == F.col("node"), "left").select(
        F.bitwise_not("k1").alias("_h1"), F.bitwise_not("k2").alias("_h2"),
        (F.col("copies") - 1 + F.coalesce("n", F.lit(0))).alias("_links"), F.coalesce("root", "rep").alias("_root"))
    joined = marked.select("vec_id", "sound", "h1", "h2").join(
        classes, F.col("sound") & (F.col("h1") == F.col("_h1")) & (F.col("h2") == F.col("_h2")), "left")
    root = F.coalesce("_root", "vec_id")
    return joined.select("vec_id", F.coalesce("_links", F.lit(0).cast("long")).alias("n_links"), root.alias("component_id"),
                         F.coalesce(F.col("vec_id") == root, F.lit(False)).alias("kept"))


def _in_blocks(rows: DataFrame, n: int, tables: int) -> DataFrame:
    """Rows of buckets that hold several, with the pair of blocks (i, j) or, for small buckets, the group (g) they are compared in."""
    width = rows.groupBy(*[F.col(c).alias(f"_{c}") for c in BUCKET]).count().where("count > 1").withColumn(
        "parts", F.ceil(F.col("count") / BLOCK).cast("int"))
    groups = max(1, -(-n * tables // GROUP))
    met = rows.join(width, [rows[c] == width[f"_{c}"] for c in BUCKET]).withColumn(
        "mine", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int")).withColumn("big", F.col("count") > SMALL)
    met = met.select(*rows.columns, "mine", "big", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("other"))
    return met.select("*", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"),
                      F.when(~F.col("big"), F.pmod(F.xxhash64(*BUCKET), F.lit(groups))).alias("g"),
                      *[F.when(F.col("big"), F.col(c)).alias(f"big_{c}") for c in BUCKET])


def _compared(rows: DataFrame, n: int, tables: int, small, blocks, schema: str) -> DataFrame:
    def run(d: pd.DataFrame) -> pd.DataFrame:
        if not d["big"].iloc[0]:
            return small(d)
        i, j, t = int(d["i"].iloc[0]), int(d["j"].iloc[0]), int(d["t"].iloc[0])
        a = d[d["mine"] == i].sort_values("rep")
        return blocks(a, a if i == j else d[d["mine"] == j].sort_values("rep"), i == j, t)

    return _in_blocks(rows, n, tables).groupBy("g", *[f"big_{c}" for c in BUCKET], "i", "j").applyInPandas(run, schema)


def _bucket_links(some: DataFrame, n: int, projection: np.ndarray, bits: int, tables: int, cosine: float) -> DataFrame:
    """Link counts (a = rep, n) and connecting edges (a, b) of vectors of one length."""
    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = np.stack(b.column(2).to_numpy(zero_copy_only=False)).astype(float)
            keys = table_keys(x / np.linalg.norm(x, axis=1, keepdims=True), projection, bits)
            rows, t = keys.shape
            take = pa.array(np.repeat(np.arange(rows), t))
            cols = [b.column(0), b.column(1), pa.array([r.tobytes() for r in keys.astype("<i4")], pa.binary())]
            yield pa.RecordBatch.from_arrays([c.take(take) for c in cols] + [
                pa.array(np.tile(np.arange(t, dtype=np.int32), rows)), pa.array(keys.ravel())], names=["rep", "label", "keys", "t", "key"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = np.stack(b.column(2).to_numpy(zero_copy_only=False)).astype(float)
            short = x.astype("<f4")
            raw = [b"\x04" + s.tobytes() if (s == v).all() else b"\x08" + v.astype("<f8").tobytes() for s, v in zip(short, x)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(raw, pa.binary())], names=["_rep", "copies", "x"])

    reach, where = radius(bits * tables, cosine), "rep long, label long, keys binary, t int, key int"
    coded = some.select("rep", "label", "v").mapInArrow(code, where)
    names = [c.split(" ")[0] for c in where.split(", ")]
    marked = cut(_compared(coded, n, tables, lambda d: _mark_small(d, reach)[names], lambda a, b, same, t: _mark_blocks(a, b, same, t, reach)[names], where).dropDuplicates(["rep", "t"]))
    vectors = some.select("rep", "copies", "v").mapInArrow(pack, "_rep long, copies long, x binary")
    met = marked.join(vectors, F.col("rep") == F.col("_rep")).drop("_rep")
    return _compared(met, marked.count(), 1, lambda d: _small_buckets(d, cosine), lambda a, b, same, t: _pair_up(a, b, same, cosine, t), "a long, b long, n long")
