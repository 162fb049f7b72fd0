"""Benchmark decontamination: SimHash of item-sized windows, multi-index Hamming blocks, exact verification.

Words are runs of letters and digits of the lower-cased text, so punctuation and case don't hide
a passage.  A window of a document has as many words as a benchmark item.  Its 64-bit fingerprint
(SimHash of its shingles, each counted as often as it occurs) and an item's are cut into eight
blocks of eight bits; fingerprints within a radius of 23 bits have a block in which they differ in
at most two bits, so items are entered under every block value within two bits and an equi-join
finds every fingerprint within the radius.  Candidates are verified by the weighted Jaccard
similarity of the shingles (sum of smaller counts over sum of greater counts).

Which windows get a fingerprint: a window of similarity 0.8 or more holds at least 0.8 times as many
shingles of items of its size as the item has (what both share is no more than what the window has
of it).  Every window that holds so many is laid, at whatever place; one that holds fewer cannot be
a match, so passing over it loses nothing.  DataFrame functions only.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import Workspace, table

SIZE, PERCENT = 5, 80
BLOCKS, BITS, FLIPS = 8, 8, 2
RADIUS = BLOCKS * (FLIPS + 1) - 1
#: Rows about the benchmark that are sent to every executor at most; beyond it, joins shuffle.
BROADCAST_ROWS = 1_000_000
#: Benchmark shingles that are written into the plan at most; beyond it, they are joined.
LITERALS = 50_000


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def once(column: Column) -> Column:
    """The column's value, worked out once for each row: optimiser rules don't copy it into what reads it."""
    return F.explode(F.array(column))


def shingles(words: Column, size: int) -> Column:
    """Hashes of the runs of ``size`` words, in order; none for fewer words."""
    return F.when(
        F.size(words) >= size,
        F.transform(F.sequence(F.lit(0), F.size(words) - size), lambda i: F.xxhash64(*[F.get(words, i + j) for j in range(size)])),
    ).otherwise(F.array().cast("array<long>"))


def fingerprint(hashes: Column) -> Column:
    """Bit b is set when more of the hashes have it than not."""
    bits = F.sequence(F.lit(0), F.lit(63))
    signs = F.transform(bits, lambda b: F.aggregate(hashes, F.lit(0), lambda n, h: n + F.getbit(h, b).cast("int") * 2 - 1))
    return F.aggregate(F.transform(signs, lambda s, b: F.when(s > 0, F.call_function("shiftleft", F.lit(1).cast("long"), b)).otherwise(F.lit(0).cast("long"))), F.lit(0).cast("long"), lambda a, x: a.bitwiseOR(x))


def numbered(hashes: Column) -> Column:
    """The hashes as a set: equal ones are told apart by their number of occurrence."""
    ordered = F.array_sort(hashes)
    return F.transform(ordered, lambda h, i: F.xxhash64(h, i - F.array_position(ordered, h).cast("int")))


def block_values(print_: Column) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(BLOCKS - 1)), lambda b: F.call_function("shiftrightunsigned", print_, b * BITS).bitwiseAND(F.lit((1 << BITS) - 1).cast("long")))


_ROW = ["doc", "tid", "h"]


def _hits_in_place(hashed: DataFrame, anchors: DataFrame, small) -> DataFrame:
    """(doc, tid, h, n, at): ascending places of the shingles that items of ``n`` words have, found without moving the documents.

    The benchmark's shingles, LITERALS at most, are part of the plan; documents without any of them
    are passed over inside the scan.
    """
    by_size: dict[int, list[int]] = {}
    for r in anchors.select("n", "g").distinct().collect():
        by_size.setdefault(r.n, []).append(r.g)
    if not by_size:
        return hashed.select(*_ROW, F.lit(0).alias("n"), F.array().cast("array<int>").alias("at")).limit(0)
    among = lambda places, wanted: F.filter(places, lambda i: F.get("h", i).isin(wanted))
    every = sorted({g for own in by_size.values() for g in own})
    hit = hashed.where(F.size("h") > 0).select(*_ROW, once(among(F.sequence(F.lit(0), F.size("h") - 1), every)).alias("at")).where(F.size("at") > 0)
    sized = F.array(*[F.struct(F.lit(n).alias("n"), among("at", sorted(own)).alias("at")) for n, own in sorted(by_size.items())])
    return hit.select(*_ROW, F.explode(F.filter(sized, lambda x: F.size(x["at"]) > 0)).alias("x")).select(*_ROW, "x.n", "x.at")


def _hits_by_join(hashed: DataFrame, anchors: DataFrame, small) -> DataFrame:
    """The same for a benchmark of any size: shingles meet in a join, then places their documents in another."""
    each = hashed.select("doc", "tid", F.posexplode("h").alias("p", "g"))
    found = each.join(small(anchors.select("n", "g").distinct()), "g").groupBy("doc", "tid", "n").agg(F.array_sort(F.collect_set("p")).alias("at"))
    return hashed.dropDuplicates(["doc", "tid"]).join(found, ["doc", "tid"]).select(*_ROW, "n", "at")


def windows_of(hits: DataFrame, k: int, percent: int) -> DataFrame:
    """(doc, tid, n, k, start, h): each window of ``n`` words that holds enough of the places ``at``, once.

    A window is made from the first of the places that it holds: it starts after the place before
    and early enough to be reached by the last of the places it needs.
    """
    shingles = F.col("n") - k + 1
    need = F.ceil(shingles * percent / 100).cast("int")
    enough = F.transform("at", lambda p, j: F.when(F.get("at", j + need - 1) - shingles + 1 <= p, j))
    first = F.filter(enough, lambda j: j.isNotNull())
    begin = lambda j: F.greatest(F.coalesce(F.get("at", j - 1) + 1, F.lit(0)), F.get("at", j + need - 1) - shingles + 1, F.lit(0))
    laid = F.flatten(F.transform(first, lambda j: F.sequence(begin(j), F.get("at", j))))
    each = hits.select(*_ROW, "n", once(laid).alias("laid")).where(F.size("laid") > 0)
    pieces = F.transform("laid", lambda s: F.struct(s.alias("start"), F.slice("h", s + 1, F.col("n") - k + 1).alias("h")))
    return each.select("doc", "tid", "n", F.explode(pieces).alias("x")).select("doc", "tid", "n", F.lit(k).alias("k"), "x.start", "x.h")


def matches(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", size: int = SIZE, percent: int = PERCENT, name: str = "decontamination") -> DataFrame:
    """(key, item_key, start, n_words, similarity) for each document and item that match, at the best window.

    ``start``: number of the window's first word.  A document matches when one of its windows has
    100 * similarity >= percent; of equally similar windows the first counts.  Items with fewer than
    ``size`` words are one shingle; items and documents without words, null texts and rows with a
    null key match nothing; repeated rows count once.  No rows on either side: no matches.  Other
    columns are not read, whatever their names.
    """
    spark = docs.sparkSession
    work = Workspace(spark, name)
    given = items.select(F.col(item_key).alias("item"), words_of(F.col(item_text)).alias("w")).dropna().where(F.size("w") > 0)
    sizes = [r.k for r in given.select(F.least(F.size("w"), F.lit(size)).alias("k")).distinct().collect()]  # at most ``size`` values
    parts = [
        given.where(F.least(F.size("w"), F.lit(size)) == k).select("item", F.size("w").alias("n"), F.lit(k).alias("k"), shingles(F.col("w"), k).alias("h"))
        for k in sorted(sizes)
    ]
    if not parts:
        parts = [given.select("item", F.size("w").alias("n"), F.lit(size).alias("k"), F.array().cast("array<long>").alias("h"))]
    known = parts[0]
    for part in parts[1:]:
        known = known.union(part)
    known = work.keep(known.distinct().withColumn("print", fingerprint(F.col("h"))), "items")
    bound = known.agg(F.coalesce(F.sum(F.size("h")), F.lit(0)), F.count("*")).first()
    small = lambda frame, rows: F.broadcast(frame) if rows <= BROADCAST_ROWS else frame

    texts = docs.select(F.col(key).alias("doc"), F.col(text).alias("text")).where("doc is not null")
    own = texts.select("doc", F.xxhash64("text").alias("tid"), once(words_of(F.col("text"))).alias("w"))
    anchors = known.select("k", "n", F.explode("h").alias("g")).distinct()
    hits = _hits_in_place if bound[0] <= LITERALS else _hits_by_join
    pieces = None
    for k in sorted(sizes) or [size]:
        hashed = own.select("doc", "tid", once(shingles(F.col("w"), k)).alias("h"))
        cut = windows_of(hits(hashed, anchors.where(F.col("k") == k), lambda frame: small(frame, bound[0])), k, percent)
        pieces = cut if pieces is None else pieces.union(cut)
    windows = work.keep(pieces.withColumn("print", fingerprint(F.col("h"))), "windows")

    flips = [0] + [sum(1 << b for b in chosen) for r in range(1, FLIPS + 1) for chosen in combinations(range(BITS), r)]
    entered = known.select("item", "n", "print", "h", F.posexplode(block_values(F.col("print"))).alias("block", "value"))
    entered = entered.select("item", "n", F.col("print").alias("item_print"), F.col("h").alias("item_h"), "block", F.explode(F.transform(F.array(*[F.lit(x).cast("long") for x in flips]), lambda x: x.bitwiseXOR(F.col("value")))).alias("value"))
    looked = windows.select("doc", "tid", "n", "start", "print", "h", F.posexplode(block_values(F.col("print"))).alias("block", "value"))
    met = looked.join(small(entered, bound[1] * BLOCKS * len(flips)), ["n", "block", "value"])
    near = met.where(F.bit_count(F.col("print").bitwiseXOR(F.col("item_print"))) <= RADIUS).dropDuplicates(["doc", "tid", "start", "n", "item"])
    both = F.size(F.array_intersect(numbered(F.col("h")), numbered(F.col("item_h"))))
    either = F.size("h") + F.size("item_h") - both
    judged = near.select("doc", "item", "start", "n", both.alias("both"), either.alias("either")).where(F.col("both") * 100 >= F.col("either") * percent)
    best = judged.groupBy("doc", "item").agg(F.max(F.struct((F.col("both") / F.col("either")).alias("s"), (-F.col("start")).alias("at"), "n")).alias("b"))
    return best.select(F.col("doc").alias(key), F.col("item").alias(item_key), (-F.col("b.at")).cast("long").alias("start"), F.col("b.n").cast("long").alias("n_words"), F.col("b.s").alias("similarity"))


def op3_decontamination(spark, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item, with the item and the place."""
    return matches(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"), name="op3")


OP3_SQL = r"""
WITH
i AS (SELECT item_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM benchmark),
j AS (SELECT item_id, len(w) AS n, least(len(w), 5) AS k, list_transform(range(1, len(w) - least(len(w), 5) + 2), lambda x: array_to_string(w[x:x + least(len(w), 5) - 1], ' ')) AS h FROM i WHERE len(w) > 0),
d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM documents),
e AS (SELECT doc_id, k, list_transform(range(1, len(w) - k + 2), lambda x: array_to_string(w[x:x + k - 1], ' ')) AS h FROM d, (SELECT DISTINCT k FROM j) WHERE len(w) >= k),
p AS (SELECT doc_id, k, unnest(h) AS g, generate_subscripts(h, 1) - 1 AS p FROM e),
q AS (SELECT item_id, n, k, unnest(h) AS g, generate_subscripts(h, 1) - 1 AS q FROM j),
s AS (SELECT DISTINCT doc_id, item_id, n, p.k AS k, unnest(range(greatest(p - (n - p.k), 0), p + 1)) AS start FROM p JOIN q ON p.g = q.g AND p.k = q.k),
x AS (SELECT s.*, unnest(e.h[s.start + 1:s.start + s.n - s.k + 1]) AS g FROM s JOIN e USING (doc_id, k)),
c AS (SELECT doc_id, item_id, n, k, start, g, count(*) AS c FROM x GROUP BY ALL),
t AS (SELECT doc_id, item_id, n, k, start, sum(c) AS size FROM c GROUP BY ALL),
a AS (SELECT item_id, g, count(*) AS c FROM q GROUP BY ALL),
m AS (SELECT doc_id, item_id, start, sum(least(c.c, a.c)) AS shared FROM c JOIN a USING (item_id, g) GROUP BY ALL),
v AS (SELECT doc_id, item_id, start, n, shared, size + n - k + 1 - shared AS joined FROM m JOIN t USING (doc_id, item_id, start)),
b AS (SELECT *, row_number() OVER (PARTITION BY doc_id, item_id ORDER BY shared / joined DESC, start) AS r FROM v WHERE 100 * shared >= 80 * joined)
SELECT doc_id, item_id, start::BIGINT AS start, n::BIGINT AS n_words, shared / joined AS similarity FROM b WHERE r = 1
"""
