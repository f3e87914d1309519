"""Packing: first-fit decreasing over a tournament tree of bin capacities, independently in randomised groups."""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, text_chunks, written
from .pieces import encode_texts

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


class CapacityTree:
    """Tournament tree: the leaves are bins with their free room, each inner node holds the larger of its two children."""

    def __init__(self, bins: int, room: int):
        self.leaves = 1 << max(0, bins - 1).bit_length()
        self.best = [room] * (2 * self.leaves)

    def place(self, size: int) -> int:
        """The first bin with room for size, which is taken from it."""
        best, at = self.best, 1
        while at < self.leaves:
            at *= 2
            if best[at] < size:
                at += 1
        found = at - self.leaves
        best[at] -= size
        while at > 1:
            at //= 2
            best[at] = max(best[2 * at], best[2 * at + 1])
        return found


def first_fit_decreasing(lengths: np.ndarray, room: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each item; longest first, ties in the order given."""
    bins, offsets = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    if not len(lengths):
        return bins, offsets
    tree, used = CapacityTree(len(lengths), room), np.zeros(len(lengths), np.int64)
    for i in np.argsort(-lengths, kind="stable").tolist():
        b = tree.place(int(lengths[i]))
        bins[i], offsets[i] = b, used[b]
        used[b] += lengths[i]
    return bins, offsets


def document_pieces(docs: DataFrame, path: str, ranks: str | None, room: int = 1024, end_id: int = 0) -> DataFrame:
    """Pieces of at most room ids of each document with its end id: all but a document's last piece are full."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for part in text_chunks(batch):
                n, ids = encode_texts(part.column("text").to_pylist(), path, ranks)
                raw, end = ids.astype("<u4").tobytes(), end_id.to_bytes(4, "little")
                doc, start, length, crc, total, at = [], [], [], [], [], 0
                for d, k in zip(part.column("doc_id").to_pylist(), n.tolist()):
                    own = raw[4 * at : 4 * (at + k)] + end
                    at += k
                    for s in range(0, k + 1, room):
                        piece = own[4 * s : 4 * (s + room)]
                        doc.append(d)
                        start.append(s)
                        length.append(len(piece) // 4)
                        crc.append(zlib.crc32(piece))
                        total.append(k + 1)
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (doc, start, length, crc, total)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return id_and_text(docs).mapInArrow(run, PIECES)


def pack(docs: DataFrame, path: str, ranks: str | None = None, room: int = 1024, end_id: int = 0, group_pieces: int = 8192, seed: int = 7) -> DataFrame:
    """Pieces with sequence_id and offset: sequences of at most room ids, first-fit decreasing in groups.

    A piece's group is a hash of doc_id, start and checksum, so groups are even whatever the sources or copies; their
    number grows with the input, and each holds about group_pieces pieces. Null and empty texts give a piece of the end
    id alone; repeated rows are packed each; a null doc_id stays null; an empty table gives no row."""
    pieces = written(document_pieces(docs, path, ranks, room, end_id), "pieces")
    groups = max(1, -(-pieces.count() // group_pieces))
    # rows that repeat a whole document are told apart by their number within the task, so no group is hot
    number = F.monotonically_increasing_id()
    keyed = pieces.withColumn("row", number).withColumn("bin_group", F.pmod(F.xxhash64(F.lit(seed), "doc_id", "start", "ids_crc32", F.col("row") % 1024), F.lit(groups)))

    def run(pdf):
        pdf = pdf.sort_values(["length", "doc_id", "start", "row"], ascending=[False, True, True, True], kind="stable")
        bins, offsets = first_fit_decreasing(pdf["length"].to_numpy(), room)
        return pdf.assign(sequence_id=pdf["bin_group"].to_numpy() * group_pieces * 1024 + bins, offset=offsets)[["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]].astype({"doc_id": "Int64"})

    return keyed.groupBy("bin_group").applyInPandas(run, f"{PIECES}, sequence_id long, offset long")
