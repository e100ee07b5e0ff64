"""Substring dedup by prefix-partitioned suffix subtrees over words.

A suffix starts at a word; its path from the root of the corpus' suffix tree is its word sequence. The tree's top is cut by
prefixes of growing length: at SHALLOW words, suffixes that are alone below their prefix are leaves of a shallow node and
leave; the others are grouped further at the full window width, where each node with two leaves or more is a deep internal
node, that is a repeat. Groups are ranges of prefix names, their number following the corpus size, so each fits a task.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import repeats as R

SHALLOW = 12
RESULT = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def split_words(texts: list[bytes] | pa.Array, lower: bool = False) -> tuple[pa.Array, np.ndarray]:
    """The words of all texts in turn, and how many each has. The kernel cuts at exactly the operators' white space, byte by byte,
    so texts need not be valid UTF-8."""
    column = pa.array(texts, pa.large_binary()).view(pa.large_string())
    parts = pc.ascii_split_whitespace(pc.ascii_lower(column) if lower else column)
    flat, offsets = parts.values, parts.offsets.to_numpy()
    some = pc.not_equal(pc.binary_length(flat), 0).to_numpy(zero_copy_only=False)
    return flat.filter(pa.array(some)), np.diff(np.concatenate([[0], np.cumsum(some)])[offsets])


def word_numbers(flat: pa.Array) -> tuple[np.ndarray, list[bytes]]:
    """Each word's number among the distinct ones, and these."""
    coded = flat.dictionary_encode()
    return coded.indices.to_numpy().astype(np.int64), coded.dictionary.view(pa.large_binary()).to_pylist()


def word_names(distinct: list[bytes]) -> np.ndarray:
    """128-bit names of words, as two columns of 64 bits, from a digest of the whole word."""
    return np.frombuffer(b"".join(hashlib.blake2b(w, digest_size=16).digest() for w in distinct), np.uint64).reshape(-1, 2)


def window_names(names: np.ndarray, width: int) -> np.ndarray:
    """Names of all runs of `width` words."""
    if len(names) < width:
        return np.zeros(0, np.uint64)
    size, whole = 1, names
    while 2 * size <= width:
        whole, size = R.mixed(whole[:-size] * R._ODD[0] + whole[size:], size), 2 * size
    n = len(names) - width + 1
    return R.mixed(whole[:n] * R._ODD[3] + whole[width - size :][:n], 2)


def texts_of(blob: R.Blob) -> list[bytes]:
    body = blob.body.tobytes()
    return [body[b - n : b] for b, n in zip(blob.ends.tolist(), blob.lens.tolist(), strict=True)]


def _suffixes(blob: R.Blob, width: int):
    """Words, how many each document has, both name columns of each word, and the places where a window starts."""
    flat, sizes = split_words(texts_of(blob))
    numbers, distinct = word_numbers(flat)
    names = word_names(distinct)[numbers]
    ends = np.repeat(np.cumsum(sizes), sizes)
    return flat, sizes, names, np.flatnonzero(np.arange(len(flat)) + width <= ends)


def _shallow(blob: R.Blob, width: int, bits: int):
    flat, sizes, names, fit = _suffixes(blob, width)
    prefixes = window_names(names[:, 0], SHALLOW)[fit] >> np.uint64(32 - bits)
    order = np.argsort(prefixes)
    prefixes, fit = prefixes[order], fit[order]
    new = np.concatenate([[True], prefixes[1:] != prefixes[:-1]]) if len(prefixes) else np.zeros(0, bool)
    return flat, sizes, names, (prefixes[new], fit, *_groups(new))


def _groups(new: np.ndarray):
    """Number of the group of each place, and whether each group has two places or more."""
    return np.cumsum(new) - 1, np.diff(np.append(np.flatnonzero(new), len(new))) > 1


def _deep(blob: R.Blob, width: int, bits: int):
    flat, sizes, names, (prefixes, places, group, local) = _shallow(blob, width, bits)
    stay = places[(blob.answer("shallow", len(prefixes)) | local)[group]] if len(places) else places
    low, ranges = window_names(names[:, 0], width)[stay], window_names(names[:, 1], width)[stay] >> np.uint64(64 - bits)
    order, new = R.by_range(low, ranges)
    return flat, sizes, ((low[order][new], ranges[order][new]), stay[order], *_groups(new))


def remove_repeated_words(docs: DataFrame, width: int = 35, with_text: bool = False) -> DataFrame:
    """Remove each word covered by a window of `width` words that also starts anywhere else, in the same document too.

    docs: doc_id, text; other columns are ignored. Null texts have no words; documents of fewer than `width` words keep all;
    repeated rows are documents of their own, so their windows repeat. Returns doc_id, n_words, n_removed, kept_sha256,
    and kept (string) if with_text. An empty table gives no row.
    """
    if width < SHALLOW:
        raise ValueError(f"width must be {SHALLOW} or more")
    blobs = R.blobs_of(docs)
    texts = blobs.select("block", "ids", "lens", "body")
    total = blobs.select(F.sum(F.length("body"))).first()[0] or 0
    bits = R.ranges_for(total / 5)
    shallow = R.asked(texts, lambda blob: R.short_messages(blob.block, _shallow(blob, width, bits)[3][0]), "shallow", 4)
    held = R.joined(texts, shallow)
    deep = R.asked(held, lambda blob: R.messages(blob.block, *_deep(blob, width, bits)[2][0]), "deep", 8)
    held = R.joined(texts, shallow.join(deep, "block", "full"))

    def finish(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                blob = R.Blob(batch.slice(i, 1).to_pylist()[0])
                flat, sizes, (names, places, group, local) = _deep(blob, width, bits)
                twice = (blob.answer("deep", len(names[0])) | local)[group] if len(places) else np.zeros(0, bool)
                gone = R.covered(places[twice], width, len(flat))
                of = np.concatenate([[0], np.cumsum(sizes)])
                n_removed = np.diff(np.concatenate([[0], np.cumsum(gone)])[of])
                left = np.concatenate([[0], np.cumsum(sizes - n_removed)])
                kept = pa.LargeListArray.from_arrays(pa.array(left), flat.filter(pa.array(~gone)))
                parts = pc.binary_join(kept, pa.scalar(" ", pa.large_string())).view(pa.large_binary()).to_pylist()
                columns = [pa.array(blob.ids, mask=blob.ids == R.NO_ID), pa.array(sizes), pa.array(n_removed.astype(np.int64)), pa.array([hashlib.sha256(x).hexdigest() for x in parts])]
                names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
                yield pa.RecordBatch.from_arrays(columns + [pa.array(parts, pa.binary()).cast(pa.string())] * with_text, names=names + ["kept"] * with_text)

    return held.mapInArrow(finish, RESULT + ", kept string" * with_text)
