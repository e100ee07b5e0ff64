"""Repeated windows across a whole corpus, without moving the corpus.

Texts are packed once into blobs of a few MB, stored bucketed by blob id. In each round every blob names some of its
windows (fingerprints), sorts and de-duplicates them, and sends per range of names one packed message; the task of a range
sorts what all blobs sent, compares neighbours, and answers each message with one bit per name. Answers are joined to the
blobs in place. A window that occurs in a third of all documents costs one name per blob, so no key is hot; a task's memory
is bounded by the blob size and by the number of ranges, which follows the corpus size.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored, stored_in_buckets

BLOB_BYTES = 4 << 20
#: Bytes of the input that one bucket of blobs should hold; a table has 100,000 buckets at most.
BUCKET_BYTES = 1 << 30
#: Names that one range holds on average, at most.
RANGE_NAMES = 2 << 20
#: Stands for a null doc_id inside a blob; such a document counts as the last.
NO_ID = np.int64(2**63 - 1)
BLOB_SCHEMA = "block long, ids binary, lens binary, digests binary, body binary"
_ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93)]


def mixed(h: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finaliser; h is overwritten."""
    h ^= h >> np.uint64(32)
    h *= _ODD[salt % 4]
    h ^= h >> np.uint64(29)
    return h


def planes(a: np.ndarray) -> bytes:
    """Bytes of equal rank together: those of sorted numbers then compress."""
    return a.view(np.uint8).reshape(-1, a.itemsize).T.tobytes()


def from_planes(b: bytes, dtype) -> np.ndarray:
    size = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(size, -1).T).view(dtype).ravel()


def binary_parts(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets and bytes of a binary Arrow column without nulls."""
    column = column.cast(pa.large_binary())
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    return offsets, np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    from pyspark import TaskContext

    block = TaskContext.get().partitionId() << 32
    for batch in batches:
        ids = batch.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False)
        offsets, data = binary_parts(batch.column(1))
        at = 0
        while at < len(ids):
            to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + BLOB_BYTES, "right")) - 1)
            body = data[offsets[at] : offsets[to]].tobytes()
            cuts = offsets[at : to + 1] - offsets[at]
            digests = b"".join(hashlib.blake2b(body[a:b], digest_size=16).digest() for a, b in zip(cuts[:-1], cuts[1:], strict=True))
            row = [block], [ids[at:to].tobytes()], [np.diff(cuts).tobytes()], [digests], [body]
            yield pa.RecordBatch.from_arrays([pa.array(row[0], pa.int64()), *(pa.array(x, pa.binary()) for x in row[1:])], names=["block", "ids", "lens", "digests", "body"])
            block, at = block + 1, to


def blobs_of(docs: DataFrame) -> DataFrame:
    """(doc_id, text) packed into stored blobs. Null texts are empty."""
    spark = docs.sparkSession
    packed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text")).mapInArrow(_pack, BLOB_SCHEMA)
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    # A table that is no file has no known size; the optimizer then assumes a huge one.
    known = size if size < 1 << 50 else 0
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8, min(known // BUCKET_BYTES, 100_000))
    return stored_in_buckets(packed, "blobs", "block", buckets)


class Blob:
    """One row of blobs_of() and the answers joined to it."""

    def __init__(self, row: dict):
        self.ids = np.frombuffer(row["ids"], np.int64)
        self.lens = np.frombuffer(row["lens"], np.int64)
        self.body = np.frombuffer(row["body"], np.uint8)
        self.block = row["block"]
        self.ends = np.cumsum(self.lens)
        self.row = row

    def answer(self, name: str, n: int) -> np.ndarray:
        """The bits of a round for this blob's n sorted names."""
        parts = [np.unpackbits(np.frombuffer(x["bits"], np.uint8), count=x["n"]) for x in sorted(self.row[name] or (), key=lambda x: x["range"])]
        out = np.concatenate([np.zeros(0, np.uint8), *parts]).astype(bool)
        assert len(out) == n, "a blob's names changed between two rounds"
        return out


def ranges_for(names: float) -> int:
    """Bits of a name that choose its range."""
    return max(4, math.ceil(math.log2(max(names, 1) / RANGE_NAMES)))


def messages(block: int, low: np.ndarray, ranges: np.ndarray, docs: np.ndarray | None = None) -> pa.RecordBatch:
    """Names in order of range and low part, one message per range; docs: the smallest document of each name."""
    full, cut = np.unique(ranges, return_index=True)
    cut = np.append(cut, len(low))
    pay = [planes(low[a:b]) for a, b in zip(cut[:-1], cut[1:], strict=True)]
    with_docs = [planes(docs[a:b]) if docs is not None else b"" for a, b in zip(cut[:-1], cut[1:], strict=True)]
    return pa.RecordBatch.from_arrays([pa.array(full.astype(np.int32), pa.int32()), pa.array([block] * len(full), pa.int64()), pa.array(pay, pa.binary()), pa.array(with_docs, pa.binary())], names=["range", "block", "names", "docs"])


def short_messages(block: int, names: np.ndarray) -> pa.RecordBatch:
    """As messages, of sorted names whose last 32 bits are sent and whose other bits are the range."""
    return messages(block, names.astype(np.uint32), names >> np.uint64(32))


def by_range(low: np.ndarray, ranges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of names of range and low part, and where a new name begins in it."""
    order = np.lexsort((low, ranges))
    low, ranges = low[order], ranges[order]
    new = np.concatenate([[True], (low[1:] != low[:-1]) | (ranges[1:] != ranges[:-1])]) if len(low) else np.zeros(0, bool)
    return order, new


def _answers(width: int, smaller: bool) -> Callable[[pa.Table], pa.Table]:
    dtype = np.uint32 if width == 4 else np.uint64

    def answer(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        names = [from_planes(x["names"], dtype) for x in rows]
        sizes = [len(x) for x in names]
        flat = np.concatenate(names)
        order = np.argsort(flat, kind="stable")
        flat = flat[order]
        new = np.concatenate([[True], flat[1:] != flat[:-1]])
        starts = np.flatnonzero(new)
        group = np.cumsum(new) - 1
        bits = np.zeros(len(flat), bool)
        if smaller:
            docs = np.concatenate([from_planes(x["docs"], np.int64) for x in rows])
            bits[order] = docs[order] > np.minimum.reduceat(docs[order], starts)[group]
        else:
            bits[order] = np.diff(np.append(starts, len(flat)))[group] > 1
        cuts = np.cumsum([0, *sizes])
        out = [np.packbits(bits[a:b]).tobytes() for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        return pa.table({"block": table["block"], "range": table["range"], "n": pa.array(sizes, pa.int32()), "bits": pa.array(out, pa.binary())})

    return answer


def asked(blobs: DataFrame, kernel: Callable[[Blob], pa.RecordBatch], name: str, width: int, smaller: bool = False) -> DataFrame:
    """One round: a row per blob with its answers as column name."""

    def send(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                yield kernel(Blob(batch.slice(i, 1).to_pylist()[0]))

    sent = blobs.mapInArrow(send, "range int, block long, names binary, docs binary")
    bits = sent.groupBy("range").applyInArrow(_answers(width, smaller), "block long, range int, n int, bits binary")
    return stored(bits.groupBy("block").agg(F.collect_list(F.struct("range", "n", "bits")).alias(name)), name)


def joined(blobs: DataFrame, answers: DataFrame) -> DataFrame:
    """Blobs with a small table per blob; the blobs stay where they are."""
    return blobs.join(answers.hint("shuffle_hash"), "block", "left")


def covered(starts: np.ndarray, width: int, n: int) -> np.ndarray:
    """Mask of what windows of this width cover."""
    edge = np.zeros(n + 1, np.int32)
    edge[starts] += 1
    edge[starts + width] -= 1
    return np.cumsum(edge[:n]) > 0


def runs_of(mask: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Number of runs of a mask in each of the documents."""
    rise = mask & ~np.concatenate([[False], mask[:-1]])
    rise[starts[starts < ends]] = mask[starts[starts < ends]]
    total = np.concatenate([[0], np.cumsum(rise)])
    return total[ends] - total[starts]
