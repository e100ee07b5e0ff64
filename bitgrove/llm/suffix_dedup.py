"""Suffix-array dedup over a difference cover.

Suffixes that start at positions in a difference cover modulo PERIOD are the sample. For any two positions some shift below
PERIOD puts both into the sample, so two equal windows of `width` bytes imply two sampled suffixes that agree on
width - PERIOD + 1 bytes. Round one names sampled suffixes by that prefix (built from eight-byte words, folded), sorts the
names and compares neighbours. Round two merges the remaining suffixes: only windows that hold a sampled suffix with a
repeated name are named on their full width, sorted, and compared with their neighbours and the smallest document of each
name. Documents equal as a whole to one with a smaller id are settled beforehand, since all their windows repeat.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import repeats as R
from .common import stored

PERIOD, COVER = 21, np.array([0, 1, 4, 14, 16])
RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def _eights(body: np.ndarray) -> np.ndarray:
    """The eight bytes from each position as one number."""
    padded = np.concatenate([body, np.zeros(8, np.uint8)])
    return np.ndarray(len(body) + 1, "<u8", padded, strides=(1,))


def _named(words: np.ndarray, at: np.ndarray, length: int, lane: int = 0) -> np.ndarray:
    """64-bit names of the `length` bytes at each place; lanes are names by other constants."""
    name = np.full(len(at), length + (lane << 32), np.uint64)
    for k, shift in enumerate([*range(0, length - 8, 8), length - 8]):
        name += words[at + shift]
        name = R.mixed(name, k + lane)
        name *= R._ODD[(k + 1 + 2 * lane) % 4]
    return R.mixed(name, 1)


def _marked(blob: R.Blob) -> tuple[np.ndarray, np.ndarray]:
    """Document number of each byte, and whether it belongs to a document still in question."""
    doc = np.repeat(np.arange(len(blob.lens), dtype=np.int32), blob.lens)
    live = np.ones(len(blob.lens), bool)
    live[np.array(blob.row.get("copies") or [], dtype=np.int64)] = False
    return doc, live


def _sampled(blob: R.Blob, width: int, bits: int):
    """Sample positions, their names and where each stands among the sorted distinct names."""
    doc, live = _marked(blob)
    short = width - PERIOD + 1
    at = (np.arange(0, len(blob.body) + PERIOD, PERIOD)[:, None] + COVER).ravel()
    at = at[at < len(blob.body)]
    at = at[(at + short <= blob.ends[doc[at]]) & live[doc[at]]]
    names = _named(_eights(blob.body), at, short) >> np.uint64(32 - bits)
    if len(at) and bits + 32 + len(blob.body).bit_length() <= 64:
        low = np.uint64(len(blob.body).bit_length())
        both = np.sort((names << low) | at.astype(np.uint64))
        names, at = both >> low, (both & ((np.uint64(1) << low) - np.uint64(1))).astype(np.int64)
    else:
        order = np.argsort(names, kind="stable")
        names, at = names[order], at[order]
    new = np.concatenate([[True], names[1:] != names[:-1]]) if len(at) else np.zeros(0, bool)
    return doc, live, at, names[new], np.cumsum(new) - 1, np.flatnonzero(new)


def _candidates(blob: R.Blob, width: int, bits: int):
    """Windows that hold a sampled suffix with a repeated name, as (document numbers, places)."""
    doc, live, at, names, group, starts = _sampled(blob, width, bits)
    hit = np.zeros(len(blob.body) + width + 1, np.int32)
    if len(at):
        ids = blob.ids[doc[at]]
        local = np.minimum.reduceat(ids, starts) != np.maximum.reduceat(ids, starts)
        hit[at[(blob.answer("sample", len(names)) | local)[group]]] = 1
    seen = np.concatenate([[0], np.cumsum(hit)])
    n = len(blob.body)
    ok = (seen[PERIOD : n + PERIOD] > seen[:n]) & (np.arange(n) + width <= blob.ends[doc]) & live[doc]
    return doc, live, np.flatnonzero(ok)


def _windows(blob: R.Blob, width: int, bits: int):
    doc, live, at = _candidates(blob, width, bits)
    words = _eights(blob.body)
    low, ranges = _named(words, at, width), _named(words, at, width, 1) >> np.uint64(64 - bits)
    order, new = R.by_range(low, ranges)
    low, ranges, at = low[order], ranges[order], at[order]
    starts = np.flatnonzero(new)
    first = np.minimum.reduceat(blob.ids[doc[at]], starts) if len(at) else np.zeros(0, np.int64)
    return doc, live, at, (low[new], ranges[new]), np.cumsum(new) - 1, first


def _removed(blob: R.Blob, width: int, bits: int):
    doc, live, at, names, group, first = _windows(blob, width, bits)
    late = (blob.answer("windows", len(names[0]))[group] if len(at) else np.zeros(0, bool)) | (blob.ids[doc[at]] > first[group])
    gone = R.covered(at[late], width, len(blob.body))
    if (~live).any():
        gone |= ((~live) & (blob.lens >= width))[doc]
    return gone


def remove_repeated_bytes(docs: DataFrame, width: int = 50, with_text: bool = False) -> DataFrame:
    """Remove each byte covered by a `width`-byte string that also starts in a document with a smaller doc_id.

    docs: doc_id, text; other columns are ignored. Null texts are empty; texts shorter than `width` bytes keep all;
    repeated rows of one doc_id are one document each and never remove from each other; a null doc_id counts as largest.
    Returns doc_id, n_bytes, n_removed, n_spans, kept_sha256, and kept (binary) if with_text. An empty table gives none.
    """
    if width < PERIOD + 8:
        raise ValueError(f"width must be {PERIOD + 8} or more")
    blobs = R.blobs_of(docs)
    total = blobs.select(F.sum(F.length("body"))).first()[0] or 0
    bits = R.ranges_for(total * len(COVER) / PERIOD)

    def digests(batches):
        for batch in batches:
            for row in batch.to_pylist():
                ids = np.frombuffer(row["ids"], np.int64)
                ds = [row["digests"][i : i + 16] for i in range(0, 16 * len(ids), 16)]
                yield pa.RecordBatch.from_arrays([pa.array([row["block"]] * len(ids), pa.int64()), pa.array(range(len(ids)), pa.int32()), pa.array(ids), pa.array(ds, pa.binary())], names=["block", "i", "id", "digest"])

    each = blobs.select("block", "ids", "digests").mapInArrow(digests, "block long, i int, id long, digest binary")
    groups = each.groupBy("digest").agg(F.min("id").alias("first"), F.count("*").alias("n")).filter("n > 1")
    copies = stored(each.join(groups, "digest").filter("id > first").groupBy("block").agg(F.collect_list("i").alias("copies")), "copies")
    texts = blobs.select("block", "ids", "lens", "body")
    held = R.joined(texts, copies)

    def sample(blob):
        return R.short_messages(blob.block, _sampled(blob, width, bits)[3])

    side = copies.join(R.asked(held, sample, "sample", 4), "block", "full")
    held = R.joined(texts, side)

    def windows(blob):
        _, _, _, names, _, first = _windows(blob, width, bits)
        return R.messages(blob.block, *names, first)

    side = side.join(R.asked(held, windows, "windows", 8, smaller=True), "block", "full")
    held = R.joined(texts, side)

    def finish(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                blob = R.Blob(batch.slice(i, 1).to_pylist()[0])
                gone = _removed(blob, width, bits)
                starts = blob.ends - blob.lens
                total = np.concatenate([[0], np.cumsum(gone)])
                n_removed = total[blob.ends] - total[starts]
                kept, to = blob.body[~gone].tobytes(), np.cumsum(blob.lens - n_removed)
                parts = [kept[b - n : b] for b, n in zip(to, blob.lens - n_removed, strict=True)]
                columns = [pa.array(blob.ids, mask=blob.ids == R.NO_ID), pa.array(blob.lens), pa.array(n_removed.astype(np.int64)), pa.array(R.runs_of(gone, starts, blob.ends).astype(np.int64)), pa.array([hashlib.sha256(x).hexdigest() for x in parts])]
                names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
                yield pa.RecordBatch.from_arrays(columns + [pa.array(parts, pa.binary())] * with_text, names=names + ["kept"] * with_text)

    return held.mapInArrow(finish, RESULT + ", kept binary" * with_text)

