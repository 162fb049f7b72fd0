"""Near-duplicates of embeddings: cross-polytope hashing, multiprobe buckets, verified pairs.

A hash of a vector is the signed axis nearest to it after a fast rotation (three rounds of random
signs and a Hadamard transform).  A table joins several hashes to one bucket key; besides its own
bucket, a vector goes into the buckets where one hash takes its second nearest axis.  How many
hashes a table joins follows from the number of vectors; how many tables there are follows from
the share of pairs exactly at the threshold that one table brings together, measured on random
pairs before the run, so that such a pair is missed with a chance of at most ``MISS``.

Equal vectors form one class.  Classes of a bucket are compared in double precision in groups of
bounded size.  Pairs never leave their group: a pair is counted in the first bucket that its two
classes share, and groups give link counts and the few edges that span their components.
"""

from __future__ import annotations

import hashlib
import math
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import components
from .shared import Workspace, table, work_alone

MISS = 1e-5
#: Vectors of one bucket that meet in one group (from each of two blocks).
BLOCK = 1000
#: Vectors that a bucket holds on average, at most, before a table joins one more hash.
LOAD = 64
#: Components of vectors that go through the transform at once.
HELD = 1 << 18
SEED = 7


def hadamard(x: np.ndarray) -> np.ndarray:
    """Unnormalised fast Hadamard transform of the rows of ``x`` (a power of two wide)."""
    n, width = x.shape
    half = 1
    while half < width:
        y = x.reshape(n, width // (2 * half), 2, half)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], axis=2).reshape(n, width)
        half *= 2
    return x


def signs(count: int, width: int) -> np.ndarray:
    return np.random.Generator(np.random.PCG64(SEED)).choice(np.array([-1.0, 1.0]), size=(count, 3, width))


def bucket_keys(x: np.ndarray, flips: np.ndarray, joined: int) -> np.ndarray:
    """Keys (rows, tables, joined + 1) of unit vectors ``x``: own bucket first, then one probe for each joined hash."""
    n, width = x.shape
    tables = len(flips) // joined
    keys = np.zeros((n, tables, joined + 1), np.int64)
    rows = np.arange(n)
    for t in range(tables):
        first, second = [], []
        for h in range(joined):
            y = x
            for sign in flips[t * joined + h]:
                y = hadamard(y * sign)
            size = np.abs(y)
            best = size.argmax(axis=1)
            first.append(2 * best + (y[rows, best] < 0))
            size[rows, best] = -1
            next_best = size.argmax(axis=1)
            second.append(2 * next_best + (y[rows, next_best] < 0))
        for probe in range(joined + 1):
            key = np.full(n, t, np.int64)
            for h in range(joined):
                key = key * (2 * width) + (second if probe == h + 1 else first)[h]
            keys[:, t, probe] = key
    return keys


def share_found(width: int, joined: int, cosine: float, pairs: int = 4000) -> float:
    """Share of random pairs at ``cosine`` that one table brings into a common bucket."""
    rng = np.random.Generator(np.random.PCG64(SEED + 1))
    a = rng.standard_normal((pairs, width))
    a /= np.linalg.norm(a, axis=1)[:, None]
    b = rng.standard_normal((pairs, width))
    b -= (a * b).sum(axis=1)[:, None] * a
    b /= np.linalg.norm(b, axis=1)[:, None]
    flips = signs(joined * 4, width)
    x, y = (bucket_keys(v, flips, joined) for v in (a, cosine * a + math.sqrt(1 - cosine**2) * b))
    return float((x[:, :, :, None] == y[:, :, None, :]).any(axis=(2, 3)).mean())


def padded(dimension: int) -> int:
    """Width of the transform that a vector of this length goes through."""
    return max(2, 1 << max(0, dimension - 1).bit_length())


def layout(count: int, dimension: int, cosine: float) -> tuple[int, int, int]:
    """(padded width, hashes joined in a table, tables)."""
    width = padded(dimension)
    joined = 1
    while (2 * width) ** joined * LOAD < count and (2 * width) ** (joined + 1) < 1 << 52:
        joined += 1
    found = min(share_found(width, joined, cosine), 1 - 1e-9)
    return width, joined, max(1, math.ceil(math.log(MISS) / math.log(1 - found)))


def unit(raw: bytes) -> np.ndarray:
    x = np.frombuffer(raw, "<f8")
    x = x / np.abs(x).max()
    return x / np.sqrt((x * x).sum())


def _classes(rows: DataFrame, work: Workspace) -> tuple[DataFrame, DataFrame]:
    def run(batches):
        for batch in batches:
            raws, digests = [], []
            for value in batch.column(1).to_pylist():
                raw = None
                if value and None not in value:
                    x = np.array(value, "<f8") + 0.0  # -0.0 becomes 0.0
                    if np.isfinite(x).all() and x.any():
                        raw = x.tobytes()
                raws.append(raw)
                digests.append(hashlib.blake2b(raw, digest_size=16).digest() if raw else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(digests, pa.binary()), pa.array(raws, pa.binary())], names=["id", "digest", "raw"])

    read = work.keep(rows.mapInArrow(run, "id long, digest binary, raw binary"), "vectors")
    classes = read.where("digest is not null and id is not null").groupBy("digest").agg(F.min("id").alias("rep"), F.count("*").alias("copies"), F.first("raw").alias("raw"))
    return read, work.keep(classes, "classes")


def _compare(cosine: float):
    def compare(group: pa.Table) -> pa.Table:
        work_alone()
        ids, copies, side = (group[c].to_numpy() for c in ("id", "copies", "side"))
        here = group["key"][0].as_py()
        x = np.stack([unit(v) for v in group["raw"].to_pylist()])
        keys = np.stack(group["keys"].to_pylist()) if len(ids) else None
        left = np.flatnonzero(side == 0)
        right = np.flatnonzero(side == 1) if (side == 1).any() else left
        near = x[left] @ x[right].T >= cosine
        if right is left:
            near = np.triu(near, 1)
        r, c = np.nonzero(near)
        a, b = left[r], right[c]
        links = np.zeros(len(ids), np.int64)
        for at in range(0, len(a), 50_000):
            p, q = a[at : at + 50_000], b[at : at + 50_000]
            earlier = np.zeros(len(p), bool)
            for j in range(keys.shape[1]):
                own = keys[p, j]
                earlier |= (own < here) & (keys[q] == own[:, None]).any(axis=1)
            p, q = p[~earlier], q[~earlier]
            np.add.at(links, p, copies[q])
            np.add.at(links, q, copies[p])
        root = np.arange(len(ids))
        while len(a):  # smallest row reachable
            low = np.minimum(root[a], root[b])
            before = root.copy()
            np.minimum.at(root, a, low)
            np.minimum.at(root, b, low)
            root = root[root]
            if (root == before).all():
                break
        told = np.flatnonzero((links > 0) | (root != np.arange(len(ids))))
        return pa.table({"id": ids[told], "links": links[told], "to": ids[root[told]]})

    return compare


def near_duplicates(rows: DataFrame, key: str = "vec_id", vector: str = "embedding", cosine: float = 0.95, name: str = "vectors") -> DataFrame:
    """(key, n_links, component_id, kept) of every row.

    Rows link when their cosine in double precision is ``cosine`` or more.  Null, empty and zero
    vectors and those with null or non-finite components link with nothing, nor do vectors of
    different lengths.  ``n_links`` counts the other rows linked directly, equal vectors included;
    ``component_id`` is the smallest key reachable, ``kept`` says that it is the row's own.  Keys are
    distinct integers; a row with a null key links with nothing and is not kept.  No rows: none.
    Other columns are not read.
    """
    work = Workspace(rows.sparkSession, name)
    read, classes = _classes(rows.select(F.col(key).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v")), work)
    # vectors of each padded width have tables of their own: no long vector widens the others
    counts: Counter = Counter()
    for r in classes.groupBy((F.length("raw") / 8).cast("int").alias("d")).count().groupBy(F.ceil(F.log2("d")).alias("power")).agg(F.sum("count").alias("n")).collect():  # some 30 rows at most
        counts[padded(1 << r.power)] += r.n
    plans = {width: layout(n, width, cosine)[1:] for width, n in counts.items()}

    def place(batches):
        work_alone()
        flips = {width: signs(joined * tables, width) for width, (joined, tables) in plans.items()}
        for batch in batches:
            raws = batch.column(1).to_pylist()
            for at in range(0, len(raws), 2000):
                part = raws[at : at + 2000]
                widths = np.array([padded(len(raw) // 8) for raw in part])
                keys: list = [None] * len(part)
                for width in np.unique(widths).tolist():
                    own = np.flatnonzero(widths == width).tolist()
                    step = max(1, HELD // width)
                    for chosen in (own[i : i + step] for i in range(0, len(own), step)):
                        x = np.zeros((len(chosen), width))
                        for i, row in enumerate(chosen):
                            v = unit(part[row])
                            x[i, : len(v)] = v
                        for row, found in zip(chosen, bucket_keys(x, flips[width], plans[width][0]).reshape(len(chosen), -1)):
                            keys[row] = found
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(part)), pa.array(keys, pa.list_(pa.int64()))], names=["id", "keys"])

    placed = work.keep(classes.select(F.col("rep").alias("id"), "raw").mapInArrow(place, "id long, keys array<long>"), "placed")
    vectors = classes.select(F.col("rep").alias("id"), "copies", "raw", F.length("raw").alias("d")).join(placed, "id")
    spread = vectors.select("id", "d", F.explode(F.array_distinct("keys")).alias("key"))
    several = spread.groupBy("d", "key").agg(F.ceil(F.count("*") / BLOCK).alias("blocks"), F.count("*").alias("n")).where("n > 1").drop("n")
    lot = F.pmod(F.xxhash64("id"), F.col("blocks"))
    dealt = spread.join(several, ["d", "key"]).select("id", "d", "key", lot.alias("own"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("other"))
    dealt = dealt.select("id", "d", "key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("own") > F.col("other")).cast("int").alias("side"))
    found = dealt.join(vectors.drop("d"), "id").groupBy("d", "key", "i", "j").applyInArrow(_compare(cosine), "id long, links long, to long")
    found = work.keep(found, "found")
    links = found.groupBy("id").agg(F.sum("links").alias("links"))
    roots = components(found.select(F.col("id").alias("a"), F.col("to").alias("b")), work)
    told = (
        classes.select("digest", F.col("rep").alias("id"), "copies")
        .join(links, "id", "left")
        .join(roots.withColumnRenamed("node", "id"), "id", "left")
        .select("digest", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("root", "id").alias("component_id"))
    )
    component = F.when(F.col("id").isNotNull(), F.coalesce("component_id", "id"))
    return read.drop("raw").join(told, "digest", "left").select(
        F.col("id").alias(key),
        F.when(F.col("id").isNull(), F.lit(0)).otherwise(F.coalesce("n_links", F.lit(0))).cast("long").alias("n_links"),
        component.alias("component_id"),
        F.coalesce(F.col("id") == component, F.lit(False)).alias("kept"),
    )


def op2_embedding_dedup(spark, sf_dir: str) -> DataFrame:
    """Links and components of all embeddings at a cosine of 0.95."""
    return near_duplicates(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), name="op2")


OP2_SQL = """
WITH RECURSIVE
v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings),
g AS (SELECT vec_id, e FROM v WHERE e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0
      AND len(list_filter(e, lambda x: x <> 0)) > 0),
l AS (SELECT a.vec_id AS x, b.vec_id AS y FROM g a JOIN g b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
      WHERE list_cosine_similarity(a.e, b.e) >= 0.95),
r AS (SELECT vec_id AS x, vec_id AS c FROM embeddings UNION SELECT l.y, r.c FROM r JOIN l ON l.x = r.x),
m AS (SELECT x, min(c) AS c FROM r GROUP BY x),
n AS (SELECT x, count(*) AS n FROM l GROUP BY x)
SELECT vec_id, coalesce(n.n, 0)::BIGINT AS n_links, m.c AS component_id, m.c = vec_id AS kept
FROM embeddings JOIN m ON m.x = vec_id LEFT JOIN n ON n.x = vec_id
"""
