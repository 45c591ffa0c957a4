"""Token-id files: one zstandard frame for each document, compressed with a shared dictionary.

File, little-endian: MAGIC, bytes an id (1 byte), SHA-256 of the dictionary (32); the frames; the index (doc_id int64,
ids before the document in this file int64, frame's position int64; for each document, and a last row for the end); position of the index and
number of documents (two int64), MAGIC. A reader seeks to the end, reads the index and then any single frame. The dictionary lies
beside the files, named by its hash, and a reader refuses another one.

Files are written whole under a name of the attempt's own and then renamed, so a task that runs again after a loss replaces its file
by an equal one. Files are cut by bytes of text in ranges of doc_ids; rows with the same doc_id follow one another in one file, by their ids.
Null text: no ids but the end id. Rows without a doc_id have no place in the order and aren't written. An empty table gives no file;
other columns are ignored; a text of any length is one frame.
"""

from __future__ import annotations

import hashlib
import zlib
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common, tokens

MAGIC = b"IDFILE01"
END = 2
#: Text bytes that one file's documents have on average.
FILE_BYTES = 32_000_000
#: Tasks that read files at most.
READERS = 100_000
#: Dictionary: its size, the documents it is trained on at most, and bytes taken from each.
DICT_BYTES, SAMPLES, SAMPLE_BYTES = 64_000, 2000, 8192


def train(samples: list[bytes], size: int = DICT_BYTES) -> bytes:
    """A dictionary for serialized id arrays; the samples themselves where they are too few to train on, or nothing."""
    try:
        return zstandard.train_dictionary(size, samples).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[:size]


def _compressor(dictionary: bytes):
    return zstandard.ZstdCompressor(level=3, dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None)


def _decompressor(dictionary: bytes):
    return zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None)


def _opened(folder: str):
    return pafs.FileSystem.from_uri(folder)


def write_file(folder: str, name: str, width: int, dictionary: bytes, doc_ids, frames, counts) -> None:
    fs, base = _opened(folder)
    fs.create_dir(base, recursive=True)
    head = MAGIC + bytes([width]) + hashlib.sha256(dictionary).digest()
    index = np.zeros((len(frames) + 1, 3), "<i8")
    index[:-1, 0] = doc_ids
    index[1:, 1] = np.cumsum(counts)
    index[1:, 2] = np.cumsum([len(f) for f in frames])
    index[:, 2] += len(head)
    own = f"{base}/.{name}-{uuid.uuid4().hex}"
    with fs.open_output_stream(own) as out:
        out.write(head)
        for f in frames:
            out.write(f)
        at = int(index[-1, 2])
        out.write(index.tobytes() + np.array([at, len(frames)], "<i8").tobytes() + MAGIC)
    fs.move(own, f"{base}/{name}")


class IdFile:
    """Reads one document at a time: n documents, doc_ids, starts (ids before each in this file), ids(i)."""

    def __init__(self, folder: str, name: str, dictionary: bytes):
        fs, base = _opened(folder)
        self.file = fs.open_input_file(f"{base}/{name}")
        size = self.file.size()
        tail = self.file.read_at(24, size - 24)
        head = self.file.read_at(len(MAGIC) + 33, 0)
        if tail[16:] != MAGIC or head[: len(MAGIC)] != MAGIC:
            raise ValueError(f"{name} isn't an id file")
        if head[len(MAGIC) + 1 :] != hashlib.sha256(dictionary).digest():
            raise ValueError(f"{name} was written with another dictionary")
        at, self.n = (int(x) for x in np.frombuffer(tail[:16], "<i8"))
        index = np.frombuffer(self.file.read_at(24 * (self.n + 1), at), "<i8").reshape(-1, 3)
        self.doc_ids, self.starts, self.at = index[:-1, 0], index[:, 1], index[:, 2]
        self.dtype = {2: "<u2", 4: "<u4"}[head[len(MAGIC)]]
        self.context = _decompressor(dictionary)

    def ids(self, i: int) -> np.ndarray:
        frame = self.file.read_at(int(self.at[i + 1] - self.at[i]), int(self.at[i]))
        return np.frombuffer(self.context.decompress(frame), self.dtype)

    def read_all(self):
        whole = memoryview(self.file.read_at(int(self.at[-1] - self.at[0]), int(self.at[0])))
        at = (self.at - self.at[0]).tolist()
        for i in range(self.n):
            yield np.frombuffer(self.context.decompress(whole[at[i] : at[i + 1]]), self.dtype)


def write_ids(docs: DataFrame, folder: str, end: int = END, path: str = tokens.DEFAULT, file_bytes: int = FILE_BYTES) -> tuple[DataFrame, bytes]:
    """Write all documents in ascending doc_id order. Returns a row for each file (name, docs, ids, first: ids before it) and the dictionary."""
    spark = docs.sparkSession
    width = 2 if len(tokens.codec(path).token) <= 1 << 16 else 4
    dtype, end_id = f"<u{width}", np.array([end], f"<u{width}").tobytes()
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("doc_id is not null")
    n = rows.count()
    serial = lambda c, t: np.frombuffer(c.encode(t or ""), "<u4").astype(dtype).tobytes() + end_id

    def sample(batches):
        c = tokens.codec(path)
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([serial(c, t)[:SAMPLE_BYTES] for t in b.column(0).to_pylist()], pa.binary())], ["s"])

    some = rows.where(F.pmod(F.xxhash64("doc_id"), F.lit(max(1, n // (SAMPLES // 2)))) == 0).limit(SAMPLES)
    dictionary = train([bytes(r["s"]) for r in some.select("text").mapInArrow(sample, "s binary").collect()])

    def compress(batches):
        c, z = tokens.codec(path), _compressor(dictionary)
        for b in batches:
            frames, counts = [], []
            for t in b.column(1):
                ids = serial(c, t.as_py())
                counts.append(len(ids) // width)
                frames.append(z.compress(ids))
            yield pa.RecordBatch.from_arrays([b.column(2), b.column(0), pa.array(counts, pa.int64()), pa.array(frames, pa.binary())], ["part", "doc_id", "n", "frame"])

    def write(key, t):
        t = t.sort_by([("doc_id", "ascending"), ("frame", "ascending")])
        part = key[0].as_py()
        name = f"ids-{part:012d}"
        write_file(folder, name, width, dictionary, t["doc_id"].to_numpy(), t["frame"].to_pylist(), t["n"].to_numpy())
        return pa.table({"part": pa.array([part], pa.int64()), "name": [name], "docs": pa.array([t.num_rows], pa.int64()), "ids": pa.array([int(t["n"].to_numpy().sum())], pa.int64())})

    dealt = common.in_ranges(rows, "doc_id", F.coalesce(F.octet_length("text"), F.lit(0)) + 1, file_bytes)
    framed = dealt.select("doc_id", "text", "part").mapInArrow(compress, "part long, doc_id long, n long, frame binary")
    files = common.written(framed.groupBy("part").applyInArrow(write, "part long, name string, docs long, ids long"), "id-files-written")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a narrow row for each file
    files = common.written(files.select("name", "docs", "ids", F.coalesce(F.sum("ids").over(before), F.lit(0)).cast("long").alias("first")), "id-files-index")
    fs, base = _opened(folder)
    fs.create_dir(base, recursive=True)
    with fs.open_output_stream(f"{base}/{hashlib.sha256(dictionary).hexdigest()}.dict") as out:
        out.write(dictionary)
    return files, dictionary


def read_ids(folder: str, files: DataFrame, dictionary: bytes) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids_crc32 from the files."""

    def run(batches):
        for b in batches:
            for name, first in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                f = IdFile(folder, name, dictionary)
                crc = [zlib.crc32(ids.astype("<u4").tobytes()) for ids in f.read_all()]
                yield pa.RecordBatch.from_arrays([pa.array(f.doc_ids), pa.array(f.starts[:-1] + first), pa.array(np.diff(f.starts)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return files.select("name", "first").repartition(max(1, min(READERS, files.count()))).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op9_id_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = common.shared_folder(spark, "id-files")
    files, dictionary = write_ids(common.table(spark, sf_dir, "documents"), folder)
    return read_ids(folder, files, dictionary)
