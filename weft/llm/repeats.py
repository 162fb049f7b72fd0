"""Repeated passages by sparse suffix arrays.

Suffixes start at content-selected positions: of every run of ``passage`` words, the position
with the least hash of its first words (a minimiser), so equal passages have suffixes at equal
places.  Suffixes whose first words occur once drop out.  The others carry what surrounds them, as
far as a passage that holds them can reach, and equal surroundings become one suffix of the
earliest document.  Suffixes are then put, by the words to the right and by the words to the left,
in groups that share half a passage on that side (every passage shares half on one side);
within a group every window of a passage's length is compared with those of all earlier documents.
Of two equal passages the one in the document with the smaller key stays, so no content is lost
altogether.

Words are runs of other than ASCII white space, A-Z lower-cased; only repeats across documents
count.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import Workspace, hashes, may_hold, mix, parts, shingle_hashes, sieve_of, sift, table, texts_as_bytes, words_of

#: Least length of a repeat, and number of words whose hash selects and names a suffix.
PASSAGE, GRAM = 50, 8
REACH = PASSAGE - GRAM  # words to the left that a passage can hold
WINDOW = PASSAGE - GRAM + 1
HALF = PASSAGE // 2
#: Bytes that stand for a word in what surrounds a suffix.
WIDE = 3
#: A group of more suffixes is compared by aggregates over several tasks.
GROUP = 1000
#: A group of at most so many is compared pair by pair.
PAIRS = 8
_WORD = re.compile(rb"[^\x20\x09-\x0d]+")


def selected(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(positions, names) of the suffixes of a document given as word hashes."""
    if len(words) < PASSAGE:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    names = shingle_hashes(words, GRAM)
    runs = np.lib.stride_tricks.sliding_window_view(names, WINDOW)
    # a passage's own least name: of equal ones the first
    at = np.unique(np.concatenate([i + runs[i : i + 4096].argmin(axis=1) + np.arange(len(runs[i : i + 4096])) for i in range(0, len(runs), 4096)]))
    return at, names[at]


def _suffixes(docs: DataFrame) -> DataFrame:
    """(doc, name) of the suffixes of (doc, text), each name of a document once."""

    def run(batches):
        for batch in parts(batches):
            ids, names = [], []
            for doc, text in zip(batch.column(0).to_pylist(), texts_as_bytes(batch.column(1))):
                name = np.unique(selected(hashes(words_of(text)))[1])
                ids.append(np.full(len(name), doc, np.int64)), names.append(name.view(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x) if x else np.empty(0, np.int64)) for x in (ids, names)], names=["doc", "name"])

    return docs.mapInArrow(run, "doc long, name long")


def _surroundings(docs: DataFrame, repeated: np.ndarray) -> DataFrame:
    """(name, doc, at, right, left) of the suffixes of (doc, text) whose names the sieve ``repeated`` lets through; left is read backwards from the suffix."""
    sent = docs.sparkSession.sparkContext.broadcast(repeated)

    def run(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 200):
                part = batch.slice(i, 200)
                rows = []
                for doc, text in zip(part.column(0).to_pylist(), texts_as_bytes(part.column(1))):
                    words = hashes(words_of(text))
                    ats, names = selected(words)
                    some = may_hold(sent.value, names)
                    if not some.any():
                        continue
                    small = mix(words).view(np.uint8).reshape(-1, 8)[:, :WIDE]
                    ahead, back = small.tobytes(), small[::-1].tobytes()
                    n = len(words)
                    for at, name in zip(ats[some].tolist(), names[some].view(np.int64).tolist()):
                        rows.append((name, doc, at, ahead[at * WIDE : (at + PASSAGE) * WIDE], back[(n - at) * WIDE : (n - at + REACH) * WIDE]))
                columns = zip(*rows) if rows else ((),) * 5
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=["name", "doc", "at", "right", "left"])

    return docs.mapInArrow(run, "name long, doc long, at long, right binary, left binary")


def common(a: bytes, b: bytes) -> int:
    """Number of words that two surroundings share from the suffix on."""
    n = min(len(a), len(b)) // WIDE
    if a[: n * WIDE] == b[: n * WIDE]:
        return n
    low, high = 0, n  # the first ``low`` words are equal, the first ``high`` are not
    while high - low > 1:
        middle = (low + high) // 2
        if a[low * WIDE : middle * WIDE] == b[low * WIDE : middle * WIDE]:
            low = middle
        else:
            high = middle
    return low


def _neighbours(rows: DataFrame) -> DataFrame:
    """Spans (doc, at, left words, right words, of) of suffixes that repeat windows of earlier documents.

    ``rows`` (side, grouped, doc, at, main, other), those of each (side, grouped) one after another in
    one partition: groups of up to GROUP rows, so memory stays bounded.  Few rows are compared pair by
    pair.  Of more, those that share ``m`` words of the grouped side go on to ``m`` + 1, and the rest of
    a passage on the other side gives the earliest document of each window; a suffix's windows in a
    row are one span.
    """

    def run(batches):
        out: list = []

        def tell(row, main, other, of):
            left, right = (other, main) if row[0] else (main, other)
            out.append((row[2], row[3], left, right, of))

        def pairs(group):
            for i, row in enumerate(group):
                for second in group[:i]:
                    if row[2] != second[2]:
                        here, there = common(row[4], second[4]), common(row[5], second[5])
                        if here + there >= PASSAGE:
                            late, early = (row, second) if row[2] > second[2] else (second, row)
                            tell(late, here, there, early[2])

        def windows(group):
            open_: dict = {}  # row: (first m, last m, of)
            alive = range(len(group))
            for m in range(HALF if group[0][0] else PASSAGE - HALF + 1, PASSAGE + 1):
                long, rest = m * WIDE, (PASSAGE - m) * WIDE
                sharing: dict = {}
                for i in alive:
                    if len(group[i][4]) >= long:
                        sharing.setdefault(group[i][4][:long], []).append(i)
                alive = []
                for same in sharing.values():
                    if len(same) == 1:
                        continue
                    alive += same
                    whole = [(i, group[i][5][:rest]) for i in same if len(group[i][5]) >= rest]
                    least: dict = {}
                    for i, other in whole:
                        least[other] = min(least.get(other, group[i][2]), group[i][2])
                    for i, other in whole:
                        of = least[other]
                        if of < group[i][2]:
                            first, last, known = open_.get(i, (m, m, of))
                            if last < m - 1:
                                tell(group[i], last, PASSAGE - first, known)
                                first, known = m, of
                            open_[i] = (first, m, min(of, known))
                if not alive:
                    break
            for i, (first, last, of) in open_.items():
                tell(group[i], last, PASSAGE - first, of)

        def close(group):
            if len(group) <= PAIRS:
                pairs(group)
            else:
                windows(group)

        def flush():
            columns = zip(*out) if out else ((),) * 5
            batch = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["doc", "at", "left", "right", "of"])
            out.clear()
            return batch

        group, key = [], None
        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(6))):
                if row[:2] != key:
                    close(group)
                    group, key = [], row[:2]
                group.append(row)
            yield flush()
        close(group)
        yield flush()

    return rows.select("side", "grouped", "doc", "at", "main", "other").mapInArrow(run, "doc long, at long, left long, right long, of long")


def _crowded(rows: DataFrame) -> DataFrame:
    """The same spans for groups of any size: (side, grouped, n, doc, at, main, other), n rows in the group.

    Every window of a passage's length that a suffix lies in is a key, split into ``m`` words of the
    grouped side and the rest of the other; the key's earliest document is found by aggregates and
    goes back to the windows in a join.  A group is dealt to n / GROUP parts, which bounds the rows
    that one key brings to one task.  The two sides share no split.
    """
    words = lambda c: (F.length(c) / WIDE).cast("int")
    low = F.greatest(F.when(F.col("side") == 1, HALF).otherwise(PASSAGE - HALF + 1), PASSAGE - words("other"))
    high = F.least(F.lit(PASSAGE), words("main"))
    cut = rows.where(low <= high).withColumn("m", F.explode(F.sequence(low, high)))
    rest = F.lit(PASSAGE) - F.col("m")
    split = F.xxhash64(F.substring("main", F.lit(1), F.col("m") * WIDE), F.substring("other", F.lit(1), rest * WIDE))
    deal = F.pmod(F.xxhash64("doc", "at"), F.ceil(F.col("n") / GROUP))
    windows = cut.select("side", "grouped", "m", split.alias("h"), deal.alias("deal"), "doc", "at")
    keys = ["side", "grouped", "m", "h"]
    dealt = windows.groupBy(*keys, "deal").agg(F.min("doc").alias("a"), F.max("doc").alias("b"))
    least = dealt.groupBy(*keys).agg(F.min("a").alias("of"), F.max("b").alias("last")).where("of < last").drop("last")
    met = windows.join(dealt.join(least, keys).select(*keys, "deal", "of"), [*keys, "deal"]).where("doc > of")
    main, other = F.col("m").cast("long"), rest.cast("long")
    return met.select("doc", "at", F.when(F.col("side") == 1, other).otherwise(main).alias("left"), F.when(F.col("side") == 1, main).otherwise(other).alias("right"), "of")


def find(docs: DataFrame, key: str = "doc_id", text: str = "text", name: str = "repeats") -> DataFrame:
    """(key, start, end, of) for each maximal run of words that repeats passages of earlier documents.

    Words ``start`` to ``end`` - 1 of the document belong to passages of ``PASSAGE`` words or more that
    also stand in a document with a smaller key; ``of`` is the smallest such key.  Texts of fewer
    words, null texts and rows with a null key have no runs; rows that repeat a key are one document
    to each other.  No rows: no runs.  Other columns are not read.
    """
    work = Workspace(docs.sparkSession, name)
    own = docs.select(F.col(key).cast("long").alias("doc"), F.col(text).alias("text")).where("doc is not null and text is not null")
    several = _suffixes(own).groupBy("name").agg(F.min("doc").alias("a"), F.max("doc").alias("b")).where("a < b").select("name")
    several = work.keep(several, "names")
    # texts are read again where they lie, neither exchanged nor joined; a name of one document that the sieve lets through meets nothing
    met = work.keep(_surroundings(own, sieve_of(several)), "surroundings")
    work.drop(several)

    # equal surroundings: all but the earliest document repeat the whole of them
    classes = work.keep(met.groupBy("name", "right", "left").agg(F.min("doc").alias("doc"), F.min_by("at", "doc").alias("at"), F.max("doc").alias("last"), F.count("*").alias("n")), "classes")
    # they meet again by their name and 128 bits of hash, not by hundreds of bytes
    short = [F.col("name"), F.xxhash64("right", "left").alias("h"), F.xxhash64("left", "right").alias("g")]
    copies = classes.where("doc < last or n > 1").select(*short, F.col("doc").alias("of"), F.col("at").alias("own"))
    words = lambda c: (F.length(c) / WIDE).cast("long").alias(c)
    whole = met.select(*short, "doc", "at", words("left"), words("right")).join(copies, ["name", "h", "g"]).where("doc > of or at <> own")
    kept = work.keep(whole.drop("name", "h", "g"), "whole")
    # more places of an earliest document with the surroundings of the one that is compared
    again = kept.where("doc = of").groupBy("doc", F.col("own").alias("at")).agg(F.collect_list("at").alias("more"))
    whole = kept.where("doc > of").drop("own")
    work.drop(met)

    half = HALF * WIDE
    side = lambda right: classes.where(F.length("right" if right else "left") >= half).select(
        F.lit(int(right)).alias("side"),
        F.xxhash64("name", F.substring("right" if right else "left", 1, half)).alias("grouped"),
        "doc", "at", F.col("right" if right else "left").alias("main"), F.col("left" if right else "right").alias("other"),
    )
    sided = side(True).union(side(False))
    groups = sided.groupBy("side", "grouped").agg(F.count("*").alias("n"), (F.min("doc") < F.max("doc")).alias("several"))
    groups = work.keep(groups.where(F.col("several") | (F.col("n") > GROUP)), "groups")
    count = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    large = groups.where(F.col("n") > GROUP)  # a row for more than GROUP suffixes each, so few enough to send around
    # surroundings are exchanged once, to be compared; suffixes alone in their group that the sieve lets through meet nothing there
    few = sift(sided, "grouped", groups.where(F.col("n") <= GROUP).select("grouped"))[0].join(F.broadcast(large), ["side", "grouped"], "left_anti")
    ordered = few.repartition(count, "side", "grouped").sortWithinPartitions("side", "grouped")
    crowded = _crowded(sided.join(F.broadcast(large.where("several")), ["side", "grouped"]))
    places = F.concat(F.array("at"), F.coalesce("more", F.array().cast("array<long>")))
    found = _neighbours(ordered).union(crowded).join(again, ["doc", "at"], "left").select("doc", F.explode(places).alias("at"), "left", "right", "of").union(whole)
    spans = work.keep(found.select("doc", (F.col("at") - F.col("left")).alias("start"), (F.col("at") + F.col("right")).alias("end"), "of").distinct(), "spans")
    work.drop(kept, classes, groups)

    def merge(batches):
        for batch in batches:
            rows = []
            for doc, found in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                begin = end = of = None
                for s in sorted(found, key=lambda s: (s["start"], s["end"])):
                    if end is None or s["start"] > end:
                        if end is not None:
                            rows.append((doc, begin, end, of))
                        begin, end, of = s["start"], s["end"], s["of"]
                    else:
                        end, of = max(end, s["end"]), min(of, s["of"])
                if end is not None:
                    rows.append((doc, begin, end, of))
            columns = zip(*rows) if rows else ((),) * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["doc", "start", "end", "of"])

    # the spans of one document: as many as it has suffixes, at most
    merged = spans.groupBy("doc").agg(F.collect_list(F.struct("start", "end", "of")).alias("found")).mapInArrow(merge, "doc long, start long, end long, of long")
    return merged.select(F.col("doc").alias(key), "start", "end", "of")


def without(text: bytes, runs: list[tuple[int, int]]) -> bytes:
    """A text without runs of its words (sorted, disjoint); white space before a run stays, that after it goes."""
    places = [m.span() for m in _WORD.finditer(text)]
    out, at = [], 0
    for start, end in runs:
        out.append(text[at : places[start][0]])
        at = places[end][0] if end < len(places) else len(text)
    return b"".join([*out, text[at:]])


def remove(docs: DataFrame, runs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with the runs (key, start, end) cut out of its texts; columns and rows as they are.

    Rows without runs, null texts and null keys stay as they are; a text that is all runs becomes
    empty; rows that repeat a key are cut alike.  Other columns stay, whatever their names.
    """
    names = docs.columns
    place, last = names.index(text), len(names)
    # columns are numbered while runs are joined, so that no name of theirs can clash
    plain = docs.toDF(*[f"c{i}" for i in range(last)])
    listed = runs.groupBy(F.col(key).alias("of")).agg(F.sort_array(F.collect_list(F.struct("start", "end"))).alias("runs"))
    own = f"c{names.index(key)}"
    some, others = sift(plain, own, runs.select(key).distinct())
    both = some.join(listed, F.col(own) == F.col("of"), "left").drop("of")

    def run(batches):
        for batch in parts(batches):
            texts, lists = batch.column(place).to_pylist(), batch.column(last).to_pylist()
            if any(lists):
                texts = [without(t.encode(), [(r["start"], r["end"]) for r in found]).decode() if found and t is not None else t for t, found in zip(texts, lists)]
            columns = [pa.array(texts, batch.column(i).type) if i == place else batch.column(i) for i in range(last)]
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return both.mapInArrow(run, docs.schema).union(others.toDF(*names))


def op6_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    """Runs of words that repeat passages of earlier documents."""
    return find(table(spark, sf_dir, "documents", "doc_id", "text"), name="op6")
