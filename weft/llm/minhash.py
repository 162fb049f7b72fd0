"""Near-duplicates of texts by circulant MinHash, banding and exact Jaccard verification.

Every shingle is sent by one permutation to a place on a ring, whose places hold the values of a
second permutation.  Coordinate k of a signature is the least value found k places further on from
a document's shingles: all coordinates come from one table, read in runs of neighbouring places.

Documents with equal shingle sets form one class, of which the smallest id stands for all.
Classes that share a band are candidates.  First, each class of a bucket meets the bucket's hub,
the class that meets others most often; pairs confirmed on full sets join components.  Then come
the families of classes that shared bands tie together and that still hold several components: in
blocks of bounded size, classes outside the largest component meet all others of a different
component.  Those whose signatures could reach the threshold (the chance of a wrong refusal is
below 1e-11) are compared on full sets, so no link that could change a component is lost; only
links leave a block, and pairs inside a component aren't compared at all.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import components
from .shared import Workspace, hashes, mix, parts, shingle_hashes, sift, table, texts_as_bytes, words_of

BANDS, ROWS = 32, 4
COORDINATES = BANDS * ROWS
#: Places of the ring; a document's shingles are few against it.
RING = 1 << 20
#: Signatures with fewer equal coordinates than this cannot reach 0.8 (chance of error 4e-13).
LEAST_EQUAL = 64
#: Classes, and shingles of all of them, that a block of the second look holds on average, at most.
BLOCK, BLOCK_SHINGLES = 1000, 500_000
PLACES, VALUES = np.uint64(0xD6E8FEB86659FD93), 20250101


def _ring() -> np.ndarray:
    """The second permutation, with its first places repeated at the end."""
    values = np.random.Generator(np.random.PCG64(VALUES)).permutation(RING).astype(np.uint32)
    return np.concatenate([values, values[:COORDINATES]])


def signature(shingles: np.ndarray, ring: np.ndarray) -> np.ndarray:
    """Signature of a non-empty set of shingle hashes."""
    places = (mix(shingles * PLACES) & np.uint64(RING - 1)).astype(np.int64)
    runs = np.lib.stride_tricks.sliding_window_view(ring, COORDINATES)
    least = None
    for at in range(0, len(places), 4096):
        part = runs[places[at : at + 4096]].min(axis=0)
        least = part if least is None else np.minimum(least, part)
    return least


def shingle_set(text: bytes | None, size: int) -> np.ndarray:
    """Sorted distinct shingle hashes of a text."""
    return np.unique(shingle_hashes(hashes(words_of(text)), size))


def sketches(docs: DataFrame, key: str, text: str, size: int) -> DataFrame:
    """(id, n_shingles, digest, bands array<long>, sig binary) of every row; digest, bands, sig null for an empty set.

    ``digest`` names the shingle set.  ``sig`` has one byte of each coordinate.
    """

    def run(batches):
        ring = _ring()
        for batch in parts(batches):
            n, digests, bands, sigs = [], [], [], []
            for value in texts_as_bytes(batch.column(1)):
                found = shingle_set(value, size)
                n.append(len(found))
                if len(found):
                    sig = signature(found, ring)
                    folded = sig.astype(np.uint64).reshape(BANDS, ROWS)
                    band = np.arange(1, BANDS + 1, dtype=np.uint64)
                    for j in range(ROWS):
                        band = mix((band + folded[:, j]) * np.uint64(0x9E3779B97F4A7C15))
                    digests.append(hashlib.blake2b(found.tobytes(), digest_size=16).digest())
                    bands.append(band.view(np.int64))
                    sigs.append(mix(sig.astype(np.uint64)).astype(np.uint8).tobytes())
                else:
                    digests.append(None), bands.append(None), sigs.append(None)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n, pa.int64()), pa.array(digests, pa.binary()), pa.array(bands, pa.list_(pa.int64())), pa.array(sigs, pa.binary())],
                names=["id", "n_shingles", "digest", "bands", "sig"],
            )

    return docs.select(F.col(key).cast("long"), text).mapInArrow(run, "id long, n_shingles long, digest binary, bands array<long>, sig binary")


def _sets(docs: DataFrame, key: str, text: str, size: int) -> DataFrame:
    def run(batches):
        for batch in parts(batches):
            sets = [shingle_set(value, size).view(np.int64) for value in texts_as_bytes(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["id", "shingles"])

    return docs.select(F.col(key).cast("long"), text).mapInArrow(run, "id long, shingles array<long>")


def confirm(pairs: DataFrame, sets: DataFrame, percent: int, work: Workspace) -> DataFrame:
    """Those of the distinct pairs (a, b) whose full sets have 100 * intersection >= percent * union; a written table."""
    left = sets.select(F.col("id").alias("a"), F.col("shingles").alias("_x"))
    right = sets.select(F.col("id").alias("b"), F.col("shingles").alias("_y"))
    both = F.size(F.array_intersect("_x", "_y"))
    # two sizes too far apart cannot reach the threshold: no need to intersect them
    sizes = (F.size("_x") * 100 >= F.size("_y") * percent) & (F.size("_y") * 100 >= F.size("_x") * percent)
    links = pairs.join(left, "a").join(right, "b").where(sizes).where(both * 100 >= (F.size("_x") + F.size("_y") - both) * percent)
    return work.keep(links.select("a", "b"), "links")


def _across(members: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) between different components of one family, no more than connect them.

    ``members``: (family, id, root, sig, shingles, top, everyone, rest); ``top`` is the component with
    most members, ``everyone`` and ``rest`` are the numbers of blocks of all members and of those
    outside it.  The rest meets everyone: every pair of blocks is a group of its own, so no task gets
    a whole family, and only links leave a group, not pairs.
    """
    lot = lambda n: F.pmod(F.xxhash64("id"), n)
    count = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), n - 1))
    rows = members.select("family", lot(F.col("everyone")).alias("i"), count(F.col("rest")).alias("j"), F.lit(False).alias("outside"), "id", "root", "sig", "shingles")
    columns = members.where("root <> top").select("family", count(F.col("everyone")).alias("i"), lot(F.col("rest")).alias("j"), F.lit(True).alias("outside"), "id", "root", "sig", "shingles")

    def compare(group: pa.Table) -> pa.Table:
        ids, outside = group["id"].to_numpy(), group["outside"].to_numpy()
        _, root = np.unique(group["root"].to_numpy(), return_inverse=True)
        sigs = np.frombuffer(b"".join(group["sig"].to_pylist()), np.uint8).reshape(-1, COORDINATES)
        lists = group["shingles"].combine_chunks()
        sizes = lists.value_lengths().to_numpy()
        names, codes = np.unique(lists.flatten().to_numpy(), return_inverse=True)
        starts = np.cumsum(sizes) - sizes
        everyone = np.flatnonzero(~outside)
        marked = np.zeros(len(names), bool)
        found = []
        for r in np.flatnonzero(outside):
            apart = everyone[root[everyone] != root[r]]
            apart = apart[(sizes[apart] * 100 >= sizes[r] * percent) & (sizes[r] * 100 >= sizes[apart] * percent)]
            near = apart[(sigs[apart] == sigs[r]).sum(axis=1) >= LEAST_EQUAL]
            if not len(near):
                continue
            own = codes[starts[r] : starts[r] + sizes[r]]
            marked[own] = True
            edges = np.cumsum(sizes[near]) - sizes[near]
            at = np.repeat(starts[near] - edges, sizes[near]) + np.arange(sizes[near].sum())
            both = np.add.reduceat(marked[codes[at]].astype(np.int64), edges)
            marked[own] = False
            for x in near[both * 100 >= (sizes[near] + sizes[r] - both) * percent]:
                if root[x] != root[r]:
                    found.append((min(ids[x], ids[r]), max(ids[x], ids[r])))
                    root[root == root[x]] = root[r]
        a, b = zip(*found) if found else ((), ())
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return rows.union(columns).groupBy("family", "i", "j").applyInArrow(compare, "a long, b long")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", size: int = 5, percent: int = 80, name: str = "minhash") -> DataFrame:
    """(key, n_shingles, component_id, kept) of every row of ``docs``.

    A set holds the distinct ``size``-word shingles of the whole text (fewer words: the whole
    sequence as one shingle; no words or null: empty, linked with nothing).  Rows link when
    100 * intersection >= percent * union; ``component_id`` is the smallest key reachable, and
    ``kept`` says that it is the row's own.  ``percent`` below 80 raises, as bands and refusal are
    laid out for 80 and more.  Keys are integers; a row with a null key has n_shingles alone, takes
    part in no link and is not kept.  Keys are meant to be distinct: rows that repeat a key with the
    same text share one result, with other texts each row has its own.  Other columns are not read.
    """
    if percent < 80:
        raise ValueError("bands are laid out for a threshold of 80 percent or more")
    work = Workspace(docs.sparkSession, name)
    rows = work.keep(sketches(docs, key, text, size), "sketches")
    whole = rows.where("digest is not null and id is not null")
    best = whole.groupBy("digest").agg(F.min("id").alias("rep"), F.first("bands").alias("bands"), F.first("sig").alias("sig"))
    classes = work.keep(best, "classes")
    banded = classes.select(F.col("rep").alias("id"), F.posexplode("bands").alias("band", "value"))
    several = banded.groupBy("band", "value").agg(F.count("*").alias("n")).where("n > 1")
    members = work.keep(banded.join(several, ["band", "value"]), "members")
    # how often a class meets others tells the texts that a bucket's copies derive from
    meetings = work.keep(members.groupBy("id").agg(F.sum("n").alias("meetings")), "meetings")
    own = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))
    found = sift(own, "id", meetings.select("id"))[0].join(meetings, "id", "left_semi")
    sets = work.keep(_sets(found, "id", "text", size).groupBy("id").agg(F.min("shingles").alias("shingles")), "sets")
    hubs = members.join(meetings, "id").groupBy("band", "value").agg(F.max(F.struct("meetings", -F.col("id"))).alias("hub"))
    stars = members.join(hubs.select("band", "value", (-F.col("hub.col2")).alias("hub")), ["band", "value"]).where("hub <> id")
    stars = work.keep(stars.select(F.least("hub", "id").alias("a"), F.greatest("hub", "id").alias("b")).distinct(), "stars")
    first = confirm(stars, sets, percent, work)
    # the second look: families of classes that buckets tie together, where they still hold several components
    families = components(stars, work).select(F.col("node").alias("id"), F.col("root").alias("family"))
    roots = components(first, work).withColumnRenamed("node", "id")
    placed = families.join(roots, "id", "left").join(sets.select("id", F.size("shingles").alias("n")), "id")
    placed = work.keep(placed.withColumn("root", F.coalesce("root", "id")), "placed")
    parts = placed.groupBy("family", "root").agg(F.count("*").alias("k"), F.sum("n").alias("n"))
    mixed = parts.groupBy("family").agg(F.max(F.struct("k", "root", "n")).alias("top"), F.sum("k").alias("k"), F.sum("n").alias("n")).where("k > top.k")
    blocks = lambda k, n: F.ceil(F.greatest(k / BLOCK, n / BLOCK_SHINGLES))
    mixed = mixed.select("family", F.col("top.root").alias("top"), blocks(F.col("k"), F.col("n")).alias("everyone"), blocks(F.col("k") - F.col("top.k"), F.col("n") - F.col("top.n")).alias("rest"))
    open_members = placed.drop("n").join(mixed, "family").join(classes.select(F.col("rep").alias("id"), "sig"), "id").join(sets, "id")
    second = work.keep(_across(open_members, percent), "across")
    final = components(first.union(second), work)
    placed_classes = classes.select("digest", "rep").join(final.withColumnRenamed("node", "rep"), "rep", "left").select("digest", F.coalesce("root", "rep").alias("component_id"))
    work.drop(members, meetings, sets, stars, placed)
    return rows.drop("bands", "sig").join(placed_classes, "digest", "left").select(
        F.col("id").alias(key),
        "n_shingles",
        F.when(F.col("id").isNotNull(), F.coalesce("component_id", "id")).alias("component_id"),
        F.coalesce(F.col("id") == F.coalesce("component_id", "id"), F.lit(False)).alias("kept"),
    )


def op10_minhash(spark, sf_dir: str) -> DataFrame:
    """Components of documents whose 4-word shingle sets are 80 percent alike."""
    return near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"), size=4, name="op10")


OP10_SQL = r"""
WITH RECURSIVE
w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
             ELSE list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) END) AS s FROM w),
e AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM s),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i, any_value(a.n) AS na, any_value(b.n) AS nb
      FROM e a JOIN e b ON a.g = b.g AND a.doc_id < b.doc_id AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n) GROUP BY 1, 2),
l AS (SELECT a, b FROM p WHERE 100 * i >= 80 * (na + nb - i)),
u AS (SELECT a AS x, b AS y FROM l UNION SELECT b, a FROM l),
r AS (SELECT doc_id AS x, doc_id AS c FROM documents UNION SELECT u.y, r.c FROM r JOIN u ON u.x = r.x),
m AS (SELECT x, min(c) AS c FROM r GROUP BY x)
SELECT doc_id, len(s)::BIGINT AS n_shingles, c AS component_id, doc_id = c AS kept FROM s JOIN m ON m.x = doc_id
"""
