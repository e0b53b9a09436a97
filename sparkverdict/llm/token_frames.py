"""Token ids in files of independent zstandard frames with a trailing seek table.

File layout (the public seekable zstandard format): one zstandard frame per document, then one frame with the document
index, then a skippable frame with the seek table. The seek table has for each frame its compressed size, its raw size and
the low 32 bits of the XXH64 of its raw bytes, and ends with the number of frames, a flag byte and the magic number. A
reader takes the last bytes of a file, then only the frames of the documents that it wants, and checks each frame it
decompresses. Ids are stored in 2 bytes where the vocabulary allows, else in 4; the index frame says which.

Writing: documents are range-partitioned and sorted by doc_id, each task writes one file under a name of its own attempt
and returns one manifest row; only the manifest, a table that Spark commits, says which files count, so a task that is
run again leaves at most an unread file. Files lie in the shared folder, through pyarrow's file systems.

Defined cases: null and empty texts hold the end id alone; a null doc_id sorts first and is stored as null; repeated
rows are stored one by one; rows that tie in doc_id stand in the order of a hash of their texts, and equal ones in any;
a very long text is one frame, so memory follows the longest text; an empty table makes a manifest without rows; extra
columns are ignored.
"""

from __future__ import annotations

import json
import struct
import uuid
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparkverdict.llm.common import materialise, new_path, ship_package

#: Fixed values of the public seekable format.
SKIPPABLE_MAGIC = 0x184D2A5E
SEEKABLE_MAGIC = 0x8F92EAB1
CHECKSUM_FLAG = 0x80
FOOTER = struct.Struct("<IBI")
ENTRY = struct.Struct("<III")
LEVEL = 3
MANIFEST = "file string, part int, first_row long, docs long, tokens long, bytes long"


def checksum(raw: bytes) -> int:
    return xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF


class FrameWriter:
    """Writes documents' ids, one frame each, to an open binary file."""

    def __init__(self, out, width: int) -> None:
        self.out, self.width, self.kind = out, width, f"<u{width}"
        self.entries: list[tuple[int, int, int]] = []
        self.ids: list[int | None] = []
        self.counts: list[int] = []
        self.size = 0
        self.packer = zstandard.ZstdCompressor(level=LEVEL, write_checksum=False)

    def _frame(self, raw: bytes) -> None:
        packed = self.packer.compress(raw)
        self.out.write(packed)
        self.size += len(packed)
        self.entries.append((len(packed), len(raw), checksum(raw)))

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self._frame(ids.astype(self.kind).tobytes())
        self.ids.append(doc_id)
        self.counts.append(len(ids))

    def close(self) -> None:
        index = {"width": self.width, "nulls": [i for i, x in enumerate(self.ids) if x is None]}
        head = json.dumps(index).encode()
        body = np.asarray([0 if x is None else x for x in self.ids], "<i8").tobytes() + np.asarray(self.counts, "<u8").tobytes()
        self._frame(struct.pack("<II", len(head), len(self.ids)) + head + body)
        table = b"".join(ENTRY.pack(*x) for x in self.entries) + FOOTER.pack(len(self.entries), CHECKSUM_FLAG, SEEKABLE_MAGIC)
        self.out.write(struct.pack("<II", SKIPPABLE_MAGIC, len(table)) + table)
        self.size += 8 + len(table)


class FrameReader:
    """Reads single documents of one file; decompresses only their frames."""

    def __init__(self, source) -> None:
        self.source = source
        end = source.size()
        n, flags, magic = FOOTER.unpack(self._at(end - FOOTER.size, FOOTER.size))
        if magic != SEEKABLE_MAGIC or not flags & CHECKSUM_FLAG:
            raise ValueError("no seek table at the end of the file")
        raw = self._at(end - FOOTER.size - n * ENTRY.size, n * ENTRY.size)
        self.entries = np.frombuffer(raw, "<u4").reshape(n, 3)
        self.starts = np.concatenate([[0], np.cumsum(self.entries[:, 0], dtype="i8")])
        self.unpacker = zstandard.ZstdDecompressor()
        index = self._frame(n - 1)
        head, docs = struct.unpack("<II", index[:8])
        said = json.loads(index[8 : 8 + head])
        self.kind = f"<u{said['width']}"
        nulls = set(said["nulls"])
        ids = np.frombuffer(index, "<i8", docs, 8 + head)
        self.doc_ids = [None if i in nulls else int(x) for i, x in enumerate(ids)] if nulls else ids.tolist()
        self.counts = np.frombuffer(index, "<u8", docs, 8 + head + 8 * docs).astype("i8")

    def _at(self, offset: int, size: int) -> bytes:
        self.source.seek(offset)
        return self.source.read(size)

    def _frame(self, i: int) -> bytes:
        packed, size, said = (int(x) for x in self.entries[i])
        raw = self.unpacker.decompress(self._at(int(self.starts[i]), packed), max_output_size=size)
        if len(raw) != size or checksum(raw) != said:
            raise ValueError(f"frame {i} is damaged")
        return raw

    def __len__(self) -> int:
        return len(self.doc_ids)

    def document(self, i: int) -> np.ndarray:
        return np.frombuffer(self._frame(i), self.kind)

    def find(self, doc_id: int) -> Iterator[np.ndarray]:
        for i, x in enumerate(self.doc_ids):
            if x == doc_id:
                yield self.document(i)


def file_system(uri: str) -> tuple[fs.FileSystem, str]:
    """pyarrow's file system of a URI; Hadoop's short form file:/x is a local path too."""
    if uri.startswith("file:/") and not uri.startswith("file://"):
        uri = "file://" + uri[len("file:") :]
    return fs.FileSystem.from_uri(uri)


def _writing(folder: str, vocabulary: str, end_id: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        from sparkverdict.llm import bpe

        coder, out, writer, first = bpe.encoder(vocabulary), None, None, None
        width = 2 if max(coder.tokenizer.get_vocab_size(), end_id + 1) <= 1 << 16 else 4
        end = np.asarray([end_id], "<u4")
        store, root = file_system(folder)
        part = TaskContext.get().partitionId()
        name = f"part-{part:06d}-{uuid.uuid4().hex}.ids.zst"
        for batch in batches:
            encoded = coder.encode_batch(batch.column(2).to_pylist())
            for row, doc_id, ids in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), encoded, strict=True):
                if writer is None:
                    store.create_dir(root, recursive=True)
                    out = store.open_output_stream(f"{root}/{name}", compression=None)
                    writer, first = FrameWriter(out, width), row
                writer.add(doc_id, np.concatenate([np.frombuffer(ids, "<u4"), end]))
        if writer is not None:
            writer.close()
            out.close()
            row = {"file": [f"{folder}/{name}"], "part": [part], "first_row": [first], "docs": [len(writer.ids)], "tokens": [sum(writer.counts)], "bytes": [writer.size]}
            yield pa.RecordBatch.from_pydict(row, schema=pa.schema([("file", pa.string()), ("part", pa.int32()), *((x, pa.int64()) for x in ("first_row", "docs", "tokens", "bytes"))]))

    return run


def write_frames(docs: DataFrame, vocabulary: str, folder: str, end_id: int = 1) -> DataFrame:
    """Encodes every text, appends the end id, writes the files in ascending doc_id order; returns the manifest."""
    spark = docs.sparkSession
    ship_package(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    # the hash of the text orders and spreads rows of one doc_id, were it that of a third of all rows
    tied = rows.withColumn("tie", F.xxhash64("text"))
    ordered = tied.repartitionByRange(parts, "doc_id", "tie").sortWithinPartitions("doc_id", "tie")
    placed = ordered.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text")
    return materialise(placed.mapInArrow(_writing(folder, vocabulary, end_id), MANIFEST), "frame-manifest")


def _reading():
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sparkverdict.llm.token_frames import FrameReader, file_system

        for batch in batches:
            for row in batch.to_pylist():
                store, path = file_system(row["file"])
                with store.open_input_file(path) as source:
                    reader, start = FrameReader(source), row["start"]
                    for low in range(0, len(reader), 4096):
                        at = range(low, min(low + 4096, len(reader)))
                        crc = [zlib.crc32(reader.document(i).astype("<u4").tobytes()) for i in at]
                        counts = reader.counts[at.start : at.stop]
                        starts = start + np.concatenate([[0], np.cumsum(counts)[:-1]]).astype("i8")
                        start += int(counts.sum())
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(reader.doc_ids[at.start : at.stop], pa.int64()), pa.array(starts, pa.int64()), pa.array(counts, pa.int64()), pa.array(crc, pa.int64())],
                            names=["doc_id", "start", "n_tokens", "ids_crc32"],
                        )

    return run


def read_frames(manifest: DataFrame) -> DataFrame:
    """Per document, from the files alone: doc_id, start (ids before it), n_tokens, ids_crc32. One task reads a file."""
    spark = manifest.sparkSession
    ship_package(spark)
    # one row per file: a window over all of them holds a few bytes per file
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    files = manifest.withColumn("start", F.coalesce(F.sum("tokens").over(earlier), F.lit(0)).cast("long")).select("file", "start")
    spread = files.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")))
    return spread.mapInArrow(_reading(), "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_frames(docs: DataFrame, vocabulary: str, end_id: int = 1) -> DataFrame:
    return read_frames(write_frames(docs, vocabulary, new_path(docs.sparkSession, "frames"), end_id))


def documents(spark: SparkSession, manifest: DataFrame, wanted: list[int]) -> dict[int, list[list[int]]]:
    """Ids of a few wanted documents: only their frames are decompressed."""
    found: dict[int, list[list[int]]] = {}
    for row in manifest.select("file").toLocalIterator():
        store, path = file_system(row["file"])
        with store.open_input_file(path) as source:
            reader = FrameReader(source)
            for doc_id in wanted:
                for ids in reader.find(doc_id):
                    found.setdefault(doc_id, []).append(ids.tolist())
    return found
