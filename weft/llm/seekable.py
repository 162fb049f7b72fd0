"""Token ids in seekable zstandard files: one frame for each document, a trailing seek table.

A file holds, one after another: an independent zstandard frame for each document (its ids as
little-endian unsigned integers of the file's width), a skippable frame with the documents' keys,
and a skippable frame with the seek table: compressed size, plain size and checksum (the low half
of the frame's XXH64) of every frame before it, then a footer of the number of frames, a descriptor
byte and a magic number.  Any zstandard tool can decompress the whole file; a reader of some
documents reads the end of the file and decompresses those documents' frames only.

Fixed values of the format: skippable frame magics 0x184D2A50 (keys) and 0x184D2A5E (seek table),
footer magic 0x8F92EAB1, descriptor 0x80 (with checksums).
"""

from __future__ import annotations

import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .pieces import LibraryEncoder, coder, read_vocabulary
from .shared import Workspace, table

KEYS_MAGIC, TABLE_MAGIC, FOOTER_MAGIC, WITH_CHECKSUMS = 0x184D2A50, 0x184D2A5E, 0x8F92EAB1, 0x80
LEVEL = 3
_COMPRESSOR = zstandard.ZstdCompressor(level=LEVEL, write_checksum=False)
#: Documents of one file, on average.
DOCS_PER_FILE = 8192


def frame_of(ids: np.ndarray, width: int) -> tuple[bytes, int, int]:
    """(frame, plain size, checksum) of a document's ids, each in ``width`` bytes."""
    plain = ids.astype("<u2" if width == 2 else "<u4").tobytes()
    return _COMPRESSOR.compress(plain), len(plain), xxhash.xxh64_intdigest(plain) & 0xFFFFFFFF


def tail_of(keys: list[int], sizes: list[tuple[int, int, int]], width: int) -> bytes:
    """Skippable frames after the documents' frames."""
    packed = struct.pack("<B", width) + zstandard.ZstdCompressor(level=LEVEL).compress(np.array(keys, "<i8").tobytes())
    keys_frame = struct.pack("<II", KEYS_MAGIC, len(packed)) + packed
    entries = [*sizes, (len(keys_frame), 0, 0)]
    rows = np.array(entries, "<u4").tobytes()
    footer = struct.pack("<IBI", len(entries), WITH_CHECKSUMS, FOOTER_MAGIC)
    return keys_frame + struct.pack("<II", TABLE_MAGIC, len(rows) + len(footer)) + rows + footer


class Reader:
    """Documents of one file, read and decompressed one by one."""

    def __init__(self, uri: str):
        store, path = fs.FileSystem.from_uri(uri)
        self.file = store.open_input_file(path)
        size = self.file.size()
        count, descriptor, magic = struct.unpack("<IBI", self.file.read_at(9, size - 9))
        if magic != FOOTER_MAGIC or descriptor != WITH_CHECKSUMS:
            raise ValueError(f"no seek table: {uri}")
        table_at = size - 9 - 12 * count
        self.entries = np.frombuffer(self.file.read_at(12 * count, table_at), "<u4").reshape(count, 3).astype(np.int64)
        self.starts = np.concatenate([[0], np.cumsum(self.entries[:, 0])])
        if self.starts[-1] != table_at - 8:
            raise ValueError(f"damaged seek table: {uri}")
        raw = self.file.read_at(int(self.entries[-1, 0]), int(self.starts[-2]))
        self.width = raw[8]
        self.keys = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw[9:], max_output_size=8 * count + 8), "<i8")
        self.lengths = self.entries[:-1, 1] // self.width

    def __len__(self) -> int:
        return len(self.keys)

    def ids(self, at: int) -> np.ndarray:
        """Ids of document number ``at``; a frame that doesn't match its checksum raises."""
        _, plain, checksum = self.entries[at]
        raw = self.file.read_at(int(self.entries[at, 0]), int(self.starts[at]))
        data = zstandard.ZstdDecompressor().decompress(raw, max_output_size=int(plain))
        if len(data) != plain or xxhash.xxh64_intdigest(data) & 0xFFFFFFFF != checksum:
            raise ValueError(f"frame {at} is damaged")
        return np.frombuffer(data, "<u2" if self.width == 2 else "<u4")

    def close(self) -> None:
        self.file.close()


def encode_frames(docs: DataFrame, vocabulary: str, key: str, text: str, end_id: int, borders: np.ndarray) -> tuple[DataFrame, int]:
    """(file_no, key, frame, plain_size, checksum) of every document, ids followed by ``end_id``; and the ids' width.

    ``file_no`` is the number of ``borders`` (ascending) below the key.
    """
    source = docs.sparkSession.sparkContext.broadcast(read_vocabulary(vocabulary))
    from .pieces import Vocabulary

    width = 2 if max(len(Vocabulary(source.value).bytes), end_id + 1) <= 1 << 16 else 4

    def run(batches):
        own = coder(source, LibraryEncoder)
        end = np.array([end_id], "<u4").tobytes()
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                made = [frame_of(np.frombuffer(ids + end, "<u4"), width) for ids in own.packed_all(part.column(1).to_pylist())]
                frames, sizes, sums = zip(*made)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.searchsorted(borders, part.column(0).to_numpy()), pa.int32()),
                        part.column(0),
                        pa.array(frames, pa.binary()),
                        pa.array(sizes, pa.int64()),
                        pa.array(sums, pa.int64()),
                    ],
                    names=["file_no", "key", "frame", "plain_size", "checksum"],
                )

    kept = docs.where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("key"), F.col(text).alias("text"))
    return kept.mapInArrow(run, "file_no int, key long, frame binary, plain_size long, checksum long"), width


def write(docs: DataFrame, folder: str, vocabulary: str, key: str = "doc_id", text: str = "text", end_id: int = 0) -> DataFrame:
    """Write every document, in ascending key order over the numbered files, and return the manifest.

    The manifest (file_no, uri, documents, tokens, start) is what makes a file part of the data set:
    a task that ran twice leaves a file that no manifest names.  ``start`` is the number of ids in all
    files before.  Null and empty texts hold the end id alone; rows with equal keys stand next to each
    other; rows with a null key have no place in the order and are left out; no documents: no files.
    """
    spark = docs.sparkSession
    work = Workspace(spark, "seekable")
    # borders from the keys alone, so that texts are encoded once and only compressed ids are moved
    keys = docs.select(F.col(key).cast("long").alias("key")).where("key is not null")
    files = max(1, -(-keys.count() // DOCS_PER_FILE))
    borders = keys.stat.approxQuantile("key", [i / files for i in range(1, files)], 0.2 / files) if files > 1 else []
    frames, width = encode_frames(docs, vocabulary, key, text, end_id, np.array(sorted(set(borders)), np.int64))

    def run(batches):
        writer, current, keys, sizes, uri = None, None, [], [], ""
        store = None

        def finish():
            writer.write(tail_of(keys, sizes, width))
            writer.close()
            return (current, uri, len(keys), sum(s[1] for s in sizes) // width)

        done = []
        for batch in batches:
            for no, k, frame, plain, checksum in zip(*(batch.column(i).to_pylist() for i in range(5))):
                if no != current:
                    if writer is not None:
                        done.append(finish())
                    current, keys, sizes = no, [], []
                    uri = f"{folder}/ids-{no:08d}-{uuid.uuid4().hex}.zst"
                    store, path = fs.FileSystem.from_uri(uri)
                    store.create_dir(path.rpartition("/")[0], recursive=True)
                    writer = store.open_output_stream(path, compression=None)
                writer.write(frame)
                keys.append(k)
                sizes.append((len(frame), plain, checksum))
        if writer is not None:
            done.append(finish())
        columns = zip(*done) if done else ([], [], [], [])
        kinds = (pa.int32(), pa.string(), pa.int64(), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=["file_no", "uri", "documents", "tokens"])

    dealt = frames.repartition(files, "file_no").sortWithinPartitions("file_no", "key", "checksum", "frame")
    manifest = work.keep(dealt.mapInArrow(run, "file_no int, uri string, documents long, tokens long"), "manifest")
    # one row for each file
    before = Window.orderBy("file_no").rowsBetween(Window.unboundedPreceding, -1)
    return manifest.withColumn("start", F.coalesce(F.sum("tokens").over(before), F.lit(0)))


def read(manifest: DataFrame, wanted: DataFrame | None = None, digests: bool = False, key: str = "doc_id") -> DataFrame:
    """Documents of the files: (key, start, n_tokens, ids array<int>), or ids_crc32 instead of ids with ``digests``.

    ``wanted``: a data frame of (file_no, documents array<int>), numbers of documents inside their
    files; only these are decompressed.
    """

    def run(batches):
        for batch in batches:
            rows = batch.to_pydict()
            for n, uri in enumerate(rows["uri"]):
                reader = Reader(uri)
                begins = rows["start"][n] + np.concatenate([[0], np.cumsum(reader.lengths)])
                numbers = rows["numbers"][n] if rows["numbers"][n] is not None else range(len(reader))
                for at in range(0, len(numbers), 500):
                    part = numbers[at : at + 500]
                    ids = [reader.ids(i) for i in part]
                    last = pa.array([zlib.crc32(x.astype("<u4").tobytes()) for x in ids], pa.int64()) if digests else pa.array([x.astype(np.int32) for x in ids], pa.list_(pa.int32()))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(reader.keys[list(part)]), pa.array(begins[list(part)], pa.int64()), pa.array([len(x) for x in ids], pa.int64()), last], names=names
                    )
                reader.close()

    names = [key, "start", "n_tokens", "ids_crc32" if digests else "ids"]
    files = manifest.join(wanted.select("file_no", F.col("documents").alias("numbers")), "file_no") if wanted is not None else manifest.withColumn("numbers", F.lit(None).cast("array<int>"))
    # one task for each file
    spread = files.select("uri", "start", "numbers").repartition(max(1, manifest.count()), "uri")
    return spread.mapInArrow(run, f"`{key}` long, start long, n_tokens long, " + ("ids_crc32 long" if digests else "ids array<int>"))


def op8_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write the ids of all documents, read the files back."""
    from .bpe import standard_vocabulary

    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    folder = Workspace(spark, "op8").path("ids")
    return read(write(docs, folder, standard_vocabulary()), digests=True)
