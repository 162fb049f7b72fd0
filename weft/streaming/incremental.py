"""Incremental learner.

The state of an element is its pairs and counts: unions, minima, maxima and sums of what batches
hold, so the order of batches doesn't matter.  Sums are kept per batch id, so a batch that is
delivered twice replaces itself.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import precedence
from ..plans import learn

STATE = "kind string, element string, x string, y string, least long, most long, n long, batch_id long"


def batch_state(corpus: DataFrame, batch_id: int = 0) -> DataFrame:
    """State rows of one batch: ``pair`` (x, y, words that have it), ``symbol`` (counts per word), ``words`` (number of words)."""
    signed = precedence.signatures(precedence.profile(corpus))
    none, number = F.lit(None).cast("string"), F.lit(None).cast("long")
    pairs = precedence.pairs_of(signed).select(F.lit("pair").alias("kind"), "element", "x", "y", number.alias("least"), number.alias("most"), F.col("n_words").alias("n"))
    counts = signed.select("element", "n_words", F.explode("prof").alias("p")).groupBy("element", F.col("p.s").alias("x")).agg(F.min("p.c").cast("long").alias("least"), F.max("p.c").cast("long").alias("most"), F.sum("n_words").alias("n"))
    symbols = counts.select(F.lit("symbol").alias("kind"), "element", "x", none.alias("y"), "least", "most", "n")
    words = signed.groupBy("element").agg(F.sum("n_words").alias("n")).select(F.lit("words").alias("kind"), "element", none.alias("x"), none.alias("y"), number.alias("least"), number.alias("most"), "n")
    return pairs.union(symbols).union(words).withColumn("batch_id", F.lit(batch_id).cast("long"))


def fold(state: DataFrame | None, batch: DataFrame) -> DataFrame:
    """The state with a batch's rows in place of any rows of the same batch id."""
    if state is None:
        return batch
    return state.join(batch.select("batch_id").distinct(), "batch_id", "left_anti").select(*batch.columns).union(batch)


def compact(state: DataFrame, up_to: int) -> DataFrame:
    """Batches up to an id as one: their rows merged under that id."""
    old = state.where(F.col("batch_id") <= up_to).groupBy("kind", "element", "x", "y").agg(F.min("least").alias("least"), F.max("most").alias("most"), F.sum("n").alias("n"), F.lit(up_to).cast("long").alias("batch_id"))
    return old.union(state.where(F.col("batch_id") > up_to).select(*old.columns))


def graph_rows(state: DataFrame) -> DataFrame:
    """Graph rows, as the learners take them, from a state."""
    merged = state.groupBy("kind", "element", "x", "y").agg(F.min("least").alias("least"), F.max("most").alias("most"), F.sum("n").alias("n"))
    words = merged.where("kind = 'words'").select("element", F.col("n").alias("words"))
    counts = merged.where("kind = 'symbol'").join(words, "element")
    mult = precedence.mult(F.when(F.col("n") < F.col("words"), 0).otherwise(F.col("least")), F.col("most"))
    symbols = counts.groupBy("element").agg(F.array_sort(F.collect_list(F.struct(F.col("x").alias("symbol"), mult.alias("mult")))).alias("symbols"))
    pairs = precedence.directed(merged.where("kind = 'pair'").select("element", "x", "y"))
    pair = F.struct("x", "y")
    edges = pairs.groupBy("element").agg(F.array_sort(F.collect_list(F.when(F.col("conflict"), pair))).alias("conflicts"), F.array_sort(F.collect_list(F.when(~F.col("conflict"), pair))).alias("stable"))
    none = F.array().cast("array<struct<x:string,y:string>>")
    joined = words.join(symbols, "element", "left").join(edges, "element", "left")
    return joined.select("element", "words", F.coalesce("symbols", F.array().cast("array<struct<symbol:string,mult:string>>")).alias("symbols"), F.coalesce("conflicts", none).alias("conflicts"), F.coalesce("stable", none).alias("stable"))


def schemas(state: DataFrame, learners: tuple[str, ...] = ("is", "exact")) -> DataFrame:
    return learn.from_graph_rows(graph_rows(state), learners)


def changed(before: DataFrame | None, after: DataFrame) -> DataFrame:
    """(element) whose graph rows differ between two states; only these need to be learned again."""
    rows = graph_rows(after).drop("words")
    return rows.select("element") if before is None else rows.exceptAll(graph_rows(before).drop("words")).select("element")


def saturated(state: DataFrame) -> DataFrame:
    """(element, saturated): every pair in conflict and every multiplicity ``*``, so more words of the same symbols change nothing."""
    rows = graph_rows(state)
    n = F.size("symbols")
    return rows.select("element", ((F.size("conflicts") * 2 == n * (n - 1)) & F.forall("symbols", lambda s: s["mult"] == "*")).alias("saturated"))


def session_words(events: DataFrame, gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    """Words of closed user sessions of a stream of events (event_id, ts, user_id, event_type)."""
    timed = events.select(F.col("user_id").cast("string").alias("element"), F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type").withWatermark("ts", late)
    grouped = timed.groupBy("element", F.session_window("ts", gap).alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("s"))
    return grouped.select("element", F.concat_ws("/", "element", F.col("w.start").cast("string")).alias("word_id"), F.transform("s", lambda x: x["event_type"]).alias("symbols"))


def window_words(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Words of tumbling or sliding windows of a stream of events."""
    timed = events.select(F.col("user_id").cast("string").alias("element"), F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type").withWatermark("ts", late)
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    grouped = timed.groupBy("element", window.alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("s"))
    return grouped.select("element", F.concat_ws("/", "element", F.col("w.start").cast("string")).alias("word_id"), F.transform("s", lambda x: x["event_type"]).alias("symbols"))


class StateTable:
    """State as Parquet folders of one batch each; writing a batch again replaces it."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def write(self, corpus: DataFrame, batch_id: int) -> None:
        batch_state(corpus, batch_id).drop("batch_id").write.mode("overwrite").parquet(f"{self.path}/batch_id={batch_id}")

    def read(self) -> DataFrame:
        return self.spark.read.option("basePath", self.path).schema(STATE).parquet(f"{self.path}/batch_id=*")

    def sink(self):
        """Function for ``foreachBatch``."""
        return lambda frame, batch_id: self.write(frame, batch_id)


def learn_stream(words: DataFrame, path: str, learners: tuple[str, ...] = ("exact",)) -> DataFrame:
    """Schemas learned from a stream of words until its input ends; state and checkpoint are kept under ``path``.

    A run that is started again on the same path goes on where the last one ended.
    """
    table = StateTable(words.sparkSession, f"{path.rstrip('/')}/state")
    run = words.writeStream.foreachBatch(table.sink()).option("checkpointLocation", f"{path.rstrip('/')}/checkpoint").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    return schemas(table.read(), learners)
