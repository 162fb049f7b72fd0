"""What the operators share: shared-folder tables, word hashing and table access.

Words, wherever an operator speaks of them without further notice, are the maximal runs of
bytes other than ASCII white space (0x20, 0x09-0x0D) after A-Z has been lower-cased.
"""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import uuid
from functools import cache

import numpy as np
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A-Z to a-z, every other byte as it is.
LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))

UPPER_LETTERS, LOWER_LETTERS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: Names under which the library sets and tells its number of threads.
_BLAS_THREADS = [(f"{a}openblas_set_num_threads{b}", f"{a}openblas_get_num_threads{b}") for a in ("scipy_", "") for b in ("64_", "")]

_M1, _M2, _M3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """The named columns of a given table, read by Spark so that any store works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def shared_folder(spark: SparkSession) -> str:
    """Folder that the driver and every executor see: ``spark.checkpoint.dir``.

    A local session without one (as in tests) gets a folder of its own once; on a cluster, where a
    folder of the driver's machine would be of no use, a session without one raises.
    """
    known = spark.conf.get("spark.checkpoint.dir", None)
    if not known:
        context = spark.sparkContext
        held = context._jsc.sc().getCheckpointDir()
        if held.isEmpty():
            import tempfile

            if not context.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")

            context.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="weft-shared-"))
            held = context._jsc.sc().getCheckpointDir()
        known = held.get()
    return known.rstrip("/")


class Workspace:
    """Tables that an operator writes between its steps, in the shared folder.

    They cut the lineage: a lost executor costs a re-read, not the steps before.  Results read them,
    so they stay until ``Workspace.close`` or the end of the driver's process.
    """

    open: list[Workspace] = []

    def __init__(self, spark: SparkSession, name: str):
        if not Workspace.open:
            atexit.unregister(Workspace.close)
            atexit.register(Workspace.close)
        Workspace.open.append(self)
        self.spark = spark
        self.root = f"{shared_folder(spark)}/weft-{name}-{uuid.uuid4().hex}"
        self.count = 0

    def path(self, name: str) -> str:
        self.count += 1
        return f"{self.root}/{self.count:03d}-{name}"

    def keep(self, frame: DataFrame, name: str) -> DataFrame:
        """Write ``frame`` and return the written table."""
        path = self.path(name)
        frame.write.option("compression", "zstd").parquet(path)
        kept = self.spark.read.schema(frame.schema).parquet(path)
        kept._weft_path = path
        return kept

    def _delete(self, path: str) -> None:
        where = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(where, True)

    def drop(self, *frames: DataFrame) -> None:
        """Delete tables of ``keep`` that nothing reads any more."""
        for frame in frames:
            self._delete(frame._weft_path)

    @staticmethod
    def close(after: int = 0) -> None:
        """Delete all tables of the workspaces opened since there were ``after``."""
        for work in Workspace.open[after:]:
            with contextlib.suppress(Exception):  # at the end, the session may be gone
                work._delete(work.root)
        del Workspace.open[after:]


class one_thread:
    """Numpy's linear algebra on one thread, as a context.

    A task has one core; on small matrices the library's threads mostly wait for each other, and burn
    the cores of other tasks meanwhile.  Does nothing where the library isn't the usual one.
    """

    def __init__(self):
        self.libraries = []
        with contextlib.suppress(OSError), open("/proc/self/maps") as maps:
            for path in {line.split()[-1] for line in maps if "openblas" in line}:
                library = ctypes.CDLL(path)
                for put, get in _BLAS_THREADS:
                    if hasattr(library, put) and hasattr(library, get):
                        self.libraries.append((getattr(library, put), getattr(library, get)()))
                        getattr(library, put)(1)
                        break

    def __enter__(self):
        return self

    def __exit__(self, *_):
        for put, before in self.libraries:
            put(before)


@cache
def work_alone() -> one_thread:
    """One thread for the rest of this worker process."""
    return one_thread()


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser, elementwise on uint64."""
    x = (x ^ (x >> np.uint64(30))) * _M2
    x = (x ^ (x >> np.uint64(27))) * _M3
    return x ^ (x >> np.uint64(31))


def words_of(text: bytes | None) -> list[bytes]:
    """Words of a text in UTF-8; none for null."""
    return text.translate(LOWER).split() if text else []


def hashes(words: list[bytes]) -> np.ndarray:
    """64-bit hash of each word."""
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def shingle_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """Hash of each run of ``size`` word hashes, in order; fewer words: the whole sequence as one; none: none."""
    n = len(words)
    if not n:
        return words
    size = min(size, n)
    out = np.full(n - size + 1, size, np.uint64)
    for j in range(size):
        out = mix((out + words[j : n - size + 1 + j]) * _M1)
    return out


def held_out(modulus: int, remainder: int, key: str = "doc_id"):
    """crc32 of the key as text has this remainder; false for a null key."""
    return F.coalesce(F.crc32(F.col(key).cast("string")) % modulus == remainder, F.lit(False))


#: Bits in one row of a sieve, bits for each key, and the power of two of bits at most.
SIEVE_ROW, SIEVE_SHARE, SIEVE_MOST = 1 << 15, 16, 28


def sift(frame: DataFrame, key: str, ids: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rows of ``frame`` whose key may be in ``ids``, rows whose key isn't), with the columns of ``frame``.

    A join of texts with few ids need exchange the first alone.  Every id sets the bit of its hash in
    a bounded set of bits that is sent around, so no row of an id is ever among the second; about one
    row in ``SIEVE_SHARE`` of the others is among the first, which a join must settle.  ``ids`` (one
    column, integers) is read twice.  Columns of ``frame`` may have any names.
    """
    names, column = frame.columns, ids.columns[0]
    bits = 1 << min(SIEVE_MOST, max(SIEVE_ROW.bit_length() - 1, (SIEVE_SHARE * ids.count()).bit_length()))
    place = lambda c: F.pmod(F.xxhash64(F.col(c).cast("long")), F.lit(bits))
    row = lambda p: F.floor(p / SIEVE_ROW).cast("int")
    known = ids.where(F.col(column).isNotNull()).select(place(column).alias("place"))
    # dealt by rows first, so that no task makes all of the set
    dealt = known.select(row(F.col("place")).alias("row"), (F.col("place") % SIEVE_ROW).alias("bit")).repartition("row")
    sieve = dealt.groupBy("row").agg(F.bitmap_construct_agg("bit").alias("bits"))
    plain = frame.toDF(*[f"c{i}" for i in range(len(names))])
    own = f"c{names.index(key)}"
    at = plain.withColumn("place", F.when(F.col(own).isNotNull(), place(own))).withColumn("row", row(F.col("place")))
    byte = F.expr(f"cast(conv(hex(substring(bits, cast(place % {SIEVE_ROW} div 8 as int) + 1, 1)), 16, 10) as int)")
    held = F.expr("cast(place % 8 as int)")
    met = at.join(F.broadcast(sieve), "row", "left").withColumn("hit", F.coalesce(F.call_function("shiftright", byte, held) % 2 == 1, F.lit(False)))
    back = lambda rows: rows.select(plain.columns).toDF(*names)
    return back(met.where("hit")), back(met.where("not hit"))


def sieve_of(names: DataFrame) -> np.ndarray:
    """A bounded set of bits, as bytes, that ``may_hold`` every one of ``names`` (one column, 64-bit hashes).

    Two bits for each, from the name itself.  ``names`` is read twice; 32 MB come to the driver at most.
    """
    name = F.col(names.columns[0])
    bits = 1 << min(SIEVE_MOST, max(SIEVE_ROW.bit_length() - 1, (SIEVE_SHARE * names.count()).bit_length()))
    places = F.array(name.bitwiseAND(bits - 1), F.shiftrightunsigned(name, SIEVE_MOST).bitwiseAND(bits - 1))
    places = names.where(name.isNotNull()).select(F.explode(places).alias("place"))
    dealt = places.select(F.floor(F.col("place") / SIEVE_ROW).cast("int").alias("row"), (F.col("place") % SIEVE_ROW).alias("bit")).repartition("row")
    sieve = np.zeros((bits // SIEVE_ROW, SIEVE_ROW // 8), np.uint8)
    for row, held in dealt.groupBy("row").agg(F.bitmap_construct_agg("bit")).collect():
        sieve[row] = np.frombuffer(held, np.uint8)
    return sieve.ravel()


def may_hold(sieve: np.ndarray, names: np.ndarray) -> np.ndarray:
    """Whether a set of ``sieve_of`` may hold each of the names (uint64): true of all that it holds, and of about one in 70 others."""
    out, mask = np.ones(len(names), bool), np.uint64(8 * len(sieve) - 1)
    for place in (names & mask, (names >> np.uint64(SIEVE_MOST)) & mask):
        out &= (sieve[place >> np.uint64(3)] >> (place & np.uint64(7)).astype(np.uint8)) & 1 == 1
    return out


def texts_as_bytes(column) -> list[bytes | None]:
    """Values of an Arrow string column as UTF-8 bytes, without decoding them."""
    import pyarrow as pa

    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return column.cast(kind).to_pylist()


def parts(batches, rows: int = 1000):
    """Arrow batches cut to at most so many rows, which bounds what a task holds in Python at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
