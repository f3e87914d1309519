"""Token files: ids renumbered by frequency, in a byte-aligned variable-length code with separate control bytes.

A file holds a run of documents in ascending doc_id order. The most frequent ids get the smallest numbers, so most take
one byte. Control bytes hold four 2-bit lengths (less one) each and stand before all data bytes, so a reader finds every
length by one table lookup per control byte and gathers the values with numpy.

Layout, little-endian: magic, file number u32, documents u64, ids u64, data bytes u64; doc_id i64 of each, null flag u8
of each, ids u32 of each; control bytes; data bytes.
"""

from __future__ import annotations

import struct

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import id_and_text, new_path, partitions, text_chunks, written
from .pieces import encode_texts, load

MAGIC = b"CWTOKEN1"
HEAD = struct.Struct("<8sIQQQ")
#: ids that are coded or decoded at a time: memory beside a file's own bytes
PART_IDS = 500_000
#: lengths of the four values that a control byte stands for
LENGTHS = ((np.arange(256)[:, None] >> np.array([0, 2, 4, 6])) & 3).astype(np.uint8) + 1


def pack_values(v: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes and data bytes of unsigned 32-bit values."""
    v = v.astype("<u4")
    code = (v > 0xFF).astype(np.uint8) + (v > 0xFFFF) + (v > 0xFFFFFF)
    four = np.concatenate([code, np.zeros(-len(code) % 4, np.uint8)]).reshape(-1, 4)
    control = four[:, 0] | four[:, 1] << 2 | four[:, 2] << 4 | four[:, 3] << 6
    keep = np.arange(4) <= code[:, None]
    return control.astype(np.uint8).tobytes(), v.view(np.uint8).reshape(-1, 4)[keep].tobytes()


def unpack_values(control: np.ndarray, data: np.ndarray, n: int, skip: int = 0) -> tuple[np.ndarray, int]:
    """n values, after `skip` of the first control byte's, and the number of data bytes that they take."""
    lens = LENGTHS[control].ravel()[skip : skip + n]
    ends = np.cumsum(lens, dtype=np.int64)
    at, used = ends - lens, int(ends[-1]) if n else 0
    padded = np.concatenate([data[:used], np.zeros(4, np.uint8)])
    v = padded[at].astype(np.uint32)
    for k in (1, 2, 3):
        more = np.flatnonzero(lens > k)
        if not len(more):
            break
        v[more] |= padded[at[more] + k].astype(np.uint32) << np.uint32(8 * k)
    return v, used


class FileWriter:
    """One file's documents, coded as they come, so that a file of any size needs its own coded bytes and one part of ids."""

    def __init__(self, rank_of: np.ndarray):
        self.rank_of = rank_of
        self.doc, self.n, self.control, self.data, self.rest, self.total = [], [], [], [], np.zeros(0, np.uint32), 0

    def add(self, doc_ids: list, n: np.ndarray, ids: np.ndarray) -> None:
        self.doc.append(np.array([d or 0 for d in doc_ids], "<i8").tobytes() + np.array([d is None for d in doc_ids], np.uint8).tobytes())
        self.n.append(n.astype("<u4"))
        self.total += len(ids)
        for a in range(0, len(ids), PART_IDS):
            v = np.concatenate([self.rest, self.rank_of[ids[a : a + PART_IDS]]])
            whole = len(v) // 4 * 4  # a control byte holds four
            self._pack(v[:whole])
            self.rest = v[whole:]

    def _pack(self, v: np.ndarray) -> None:
        control, data = pack_values(v)
        self.control.append(control)
        self.data.append(data)

    def parts(self, number: int):
        """The file's bytes, in their order."""
        self._pack(self.rest)
        self.rest = self.rest[:0]
        docs = sum(map(len, self.n))
        yield HEAD.pack(MAGIC, number, docs, self.total, sum(map(len, self.data)))
        yield from (x[: 8 * len(k)] for x, k in zip(self.doc, self.n))
        yield from (x[8 * len(k) :] for x, k in zip(self.doc, self.n))
        yield from (k.tobytes() for k in self.n)
        yield from self.control
        yield from self.data


def read_file(content, id_of: np.ndarray):
    """(file number, doc_ids, first id of each in the file, ids of each, all these ids), a part of about PART_IDS ids at a time."""
    magic, number, docs, total, size = HEAD.unpack_from(content)
    if magic != MAGIC:
        raise ValueError("not a token file")
    at = HEAD.size
    held = []
    for dtype, count in (("<i8", docs), ("u1", docs), ("<u4", docs), ("u1", -(-total // 4)), ("u1", size)):
        held.append(np.frombuffer(content, dtype, count, at))
        at += held[-1].nbytes
    doc, null, n, control, data = held
    ends, i, first, pos = np.cumsum(n, dtype=np.int64), 0, 0, 0
    while i < docs:
        j = max(i + 1, min(i + 5000, int(np.searchsorted(ends, first + PART_IDS, side="right"))))
        last = int(ends[j - 1])
        v, used = unpack_values(control[first // 4 : -(-last // 4)], data[pos:], last - first, first % 4)
        yield number, [None if z else d for d, z in zip(doc[i:j].tolist(), null[i:j].tolist())], ends[i:j] - n[i:j], n[i:j].astype(np.int64), id_of[v]
        i, first, pos = j, last, pos + used


def tokenized(docs: DataFrame, path: str, ranks: str | None = None, end_id: int = 0) -> DataFrame:
    """doc_id, row (a number of its own), n, ids (packed, end id included), written to the shared folder: two bytes an id
    where the vocabulary allows."""

    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        kind, row = "<u2" if load(path).get_vocab_size() <= 1 << 16 else "<u4", TaskContext.get().partitionId() << 40
        w = int(kind[2])
        end = np.array([end_id], kind).tobytes()
        for batch in batches:
            for part in text_chunks(batch):
                n, ids = encode_texts(part.column("text").to_pylist(), path, ranks)
                raw, ends = ids.astype(kind).tobytes(), np.cumsum(n)
                packed = [raw[w * (e - k) : w * e] + end for e, k in zip(ends.tolist(), n.tolist())]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(np.arange(row, row + len(n))), pa.array(n + 1), pa.array(packed, pa.binary())], ["doc_id", "row", "n", "ids"])
                row += len(n)

    return written(id_and_text(docs).mapInArrow(run, "doc_id long, row long, n long, ids binary"), "token-ids")


def _flat(batch, width: int):
    """(rows, ids of each, all their ids) for parts of a batch of about PART_IDS ids."""
    n = np.asarray(batch.column("n"), np.int64)
    ends, i = np.cumsum(n), 0
    while i < len(n):
        j = max(i + 1, int(np.searchsorted(ends, ends[i] - n[i] + PART_IDS, side="right")))
        part = batch.slice(i, j - i)
        yield part, n[i:j], np.frombuffer(b"".join(part.column("ids").to_pylist()), f"<u{width}")
        i = j


def frequencies(tokens: DataFrame, size: int, width: int) -> np.ndarray:
    """Count of every id over the whole corpus; what reaches the driver is bounded by the vocabulary."""

    def run(batches):
        import pyarrow as pa

        total = np.zeros(size, np.int64)
        for batch in batches:
            for _, _, ids in _flat(batch, width):
                total += np.bincount(ids, minlength=size)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["id", "c"])

    out = np.zeros(size, np.int64)
    for r in tokens.select("n", "ids").mapInArrow(run, "id long, c long").groupBy("id").agg(F.sum("c").alias("c")).collect():
        out[r["id"]] = r["c"]
    return out


def write_token_files(docs: DataFrame, path: str, ranks: str | None = None, end_id: int = 0, file_ids: int = 16_000_000) -> tuple[str, np.ndarray]:
    """Writes the token files of all documents; the folder, and the id of each frequency rank (ties to the smaller id).

    ranks: the pre-token pattern of a byte-level vocabulary, see pieces.by_library. file_ids: ids in a file, about. A file is written under a temporary name and renamed, so a task that is run again
    replaces its own file by equal content. Beside the files stands a table of each one's first id. Null doc_ids come
    first, and rows that repeat an id or have none may fill several files; repeated rows all stay; null and empty texts:
    the end id only; a text of any length lies in one file, coded in parts; an empty table writes no file."""
    from pyarrow import fs

    spark = docs.sparkSession
    size = load(path).get_vocab_size()
    width = 2 if size <= 1 << 16 else 4
    tokens = tokenized(docs, path, ranks, end_id)
    count = frequencies(tokens, size, width)
    id_of = np.lexsort((np.arange(size), -count)).astype(np.uint32)
    rank_of = np.empty(size, np.uint32)
    rank_of[id_of] = np.arange(size, dtype=np.uint32)
    folder = new_path(spark, "token-files")
    files = max(partitions(spark), int(count.sum() // file_ids) + 1)
    shared = spark.sparkContext.broadcast(rank_of)

    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        number, attempt = TaskContext.get().partitionId(), TaskContext.get().taskAttemptId()
        out = FileWriter(shared.value)
        for batch in batches:
            for part, n, ids in _flat(batch, width):
                out.add(part.column("doc_id").to_pylist(), n, ids)
        if out.total:
            store, at = fs.FileSystem.from_uri(folder)
            store.create_dir(at, recursive=True)
            with store.open_output_stream(f"{at}/.{number}-{attempt}") as f:
                for x in out.parts(number):
                    f.write(x)
            store.move(f"{at}/.{number}-{attempt}", f"{at}/{number:06d}.tokens")
            yield pa.RecordBatch.from_arrays([pa.array([number], pa.int64()), pa.array([out.total], pa.int64())], ["file", "total"])

    order = (F.col("doc_id").asc_nulls_first(), F.col("row").asc())
    totals = written(tokens.repartitionByRange(files, *order).sortWithinPartitions(*order).mapInArrow(run, "file long, total long"), "file-totals")
    # first ids: within a thousand files by a window, of each thousand on the driver
    totals = totals.withColumn("lot", F.expr("file div 1000"))
    lots, at = [], 0
    for r in sorted(totals.groupBy("lot").agg(F.sum("total").alias("total")).collect()):
        lots.append((r["lot"], at))
        at += r["total"]
    before = Window.partitionBy("lot").orderBy("file").rowsBetween(Window.unboundedPreceding, -1)
    first = totals.withColumn("before", F.coalesce(F.sum("total").over(before), F.lit(0))).join(spark.createDataFrame(lots, "lot long, lot_first long"), "lot")
    first.select("file", (F.col("lot_first") + F.col("before")).alias("first")).write.parquet(f"{folder}-first")
    return folder, id_of


def read_token_files(spark: SparkSession, folder: str, id_of: np.ndarray) -> DataFrame:
    """doc_id, start (ids of all documents before), n_tokens, ids (little-endian unsigned 32-bit) from the files."""
    schema = "file long, doc_id long, at long, n_tokens long, ids binary"
    if not _exists(spark, folder):
        return spark.createDataFrame([], "doc_id long, start long, n_tokens long, ids binary")
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.tokens").load(folder)
    table = spark.sparkContext.broadcast(id_of)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for content in batch.column("content"):
                for number, doc, at, n, ids in read_file(content.as_buffer(), table.value):
                    raw, ends = ids.astype("<u4").tobytes(), np.cumsum(n)
                    own = [raw[4 * (e - k) : 4 * e] for e, k in zip(ends.tolist(), n.tolist())]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), number)), pa.array(doc, pa.int64()), pa.array(at), pa.array(n), pa.array(own, pa.binary())], ["file", "doc_id", "at", "n_tokens", "ids"])

    rows = files.select("content").mapInArrow(run, schema)
    first = spark.read.schema("file long, first long").parquet(f"{folder}-first")  # a row a file: Spark sees its size and picks the join
    return rows.join(first, "file").select("doc_id", (F.col("first") + F.col("at")).alias("start"), "n_tokens", "ids")


def _exists(spark: SparkSession, folder: str) -> bool:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    return path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(path)
