"""MinHash near-dedup: one permutation, optimal densification, banded buckets, star edges, exact confirmation.

One pass over the texts hashes each document's word shingles once; the top bits of a hash choose a bin, the smallest hash of a
bin is its value, and an empty bin copies that of a bin found by a fixed sequence of probes. Bands of bins are bucket keys.
Within a bucket every document is compared with one hub; buckets that then still hold several components are compared within,
block by block, and report just the links that connect them. Links count only if confirmed on full sets.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import repeats as R
from .common import stored
from .components import components
from .subtree import split_words, window_names, word_names, word_numbers

BINS, ROWS = 128, 4
#: Documents that are compared with one hub in one task; members of a bucket in a part; shingles counted at a time.
STAR, BLOCK, COLUMNS = 256, 1000, 4096
#: Shingles that a part of a bucket holds on average, at most.
BLOCK_SHINGLES = 1_000_000
SKETCH = "doc_id long, n_shingles long, set_key binary, bands array<long>"
_PROBES = np.random.default_rng(7).integers(0, BINS, (256, BINS))


def numbered_shingles(texts: list[bytes], size: int):
    """Shingles of texts, numbered exactly: equal numbers are equal word sequences. Per text the first place and the number of each
    distinct shingle; and the distinct words with the word number at each place. Shingles grow by pairs of numbers, which are
    numbered anew at each step."""
    flat, sizes = split_words(texts, lower=True)
    numbers, distinct = word_numbers(flat)

    def joined(a, b):
        return np.unique(a * (b.max(initial=0) + 1) + b, return_inverse=True)[1]

    n = max(len(flat) - size + 1, 0)
    step, whole = 1, numbers
    while 2 * step <= size and n:
        whole, step = joined(whole[:-step], whole[step:]), 2 * step
    if step < size and n:
        whole = joined(whole[:n], whole[size - step :][:n])
    short: dict = {}
    out, at = [], 0
    for k in sizes.tolist():
        if k >= size:
            found, first = np.unique(whole[at : at + k - size + 1], return_index=True)
            out.append((at + first, found))
        else:
            # The whole sequence as one shingle, which no longer text has.
            key = tuple(flat[at : at + k].view(pa.large_binary()).to_pylist())
            out.append((np.array([at] * bool(k), np.int64), np.array([len(flat) + short.setdefault(key, len(short))] * bool(k), np.int64)))
        at += k
    return out, sizes, numbers, distinct


def exact_sets(texts: list[bytes], size: int) -> list[np.ndarray]:
    """The sorted distinct shingles of each text as numbers that hold among these texts."""
    return [found for _, found in numbered_shingles(texts, size)[0]]


def named_sets(texts: list[bytes], size: int) -> list[tuple[np.ndarray, bytes]]:
    """Per text the sorted 64-bit names of its distinct shingles, and a digest of their 128-bit names."""
    sets, sizes, numbers, distinct = numbered_shingles(texts, size)
    names = word_names(distinct)[numbers]
    windows = [window_names(names[:, lane], size) for lane in (0, 1)]
    out, at = [], 0
    for (first, _), k in zip(sets, sizes.tolist(), strict=True):
        if k >= size:
            a, b = (w[first] for w in windows)
        else:
            a, b = (window_names(R.mixed(names[at : at + k, lane] + R._ODD[1]), k) if k else names[:0, 0] for lane in (0, 1))
        order = np.argsort(a)
        out.append((a[order], hashlib.blake2b(a[order].tobytes() + b[order].tobytes(), digest_size=16).digest()))
        at += k
    return out


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """One row of BINS values per set; empty sets get zeros."""
    out = np.zeros((len(sets), BINS), np.uint64)
    full = np.zeros((len(sets), BINS), bool)
    for i, s in enumerate(sets):
        bins = (s >> np.uint64(57)).astype(np.int64)
        first = np.flatnonzero(np.diff(bins, prepend=-1)) if len(s) else bins
        out[i, bins[first]] = s[first]
        full[i, bins[first]] = True
    some = full.any(1)
    i, j = np.nonzero(~full & some[:, None])
    for probe in _PROBES:
        if not len(i):
            break
        k = probe[j]
        ok = full[i, k]
        out[i[ok], j[ok]] = out[i[ok], k[ok]]
        i, j = i[~ok], j[~ok]
    for d in np.unique(i):
        filled = np.flatnonzero(full[d])
        own = j[i == d]
        out[d, own] = out[d, filled[np.searchsorted(filled, own) % len(filled)]]
    return out


def _texts(batch: pa.RecordBatch, column: int):
    """Rows (from, to) and their texts, a few MB at a time."""
    offsets, data = R.binary_parts(batch.column(column))
    at = 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + R.BLOB_BYTES, "right")) - 1)
        yield at, to, [data[a:b].tobytes() for a, b in zip(offsets[at:to].tolist(), offsets[at + 1 : to + 1].tolist(), strict=True)]
        at = to


def _sketcher(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, to, texts in _texts(batch, 1):
                named = named_sets(texts, size)
                sets = [names for names, _ in named]
                values = signatures(sets)
                bands = values.reshape(len(sets), BINS // ROWS, ROWS)
                keys = np.arange(BINS // ROWS, dtype=np.uint64)[None, :] * R._ODD[2]
                for r in range(ROWS):
                    keys = R.mixed(keys * R._ODD[3] + bands[:, :, r], r)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(at, to - at), pa.array([len(s) for s in sets], pa.int64()), pa.array([key for _, key in named], pa.binary()), pa.ListArray.from_arrays(np.arange(0, keys.size + 1, BINS // ROWS, dtype=np.int32), pa.array(keys.ravel().view(np.int64)))],
                    names=["doc_id", "n_shingles", "set_key", "bands"],
                )

    return run


def _confirmer(size: int, percent: int):
    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        batch = table.to_batches()[0]
        sets = exact_sets(batch.column(3).to_pylist(), size)
        ids, other = batch.column(0).to_pylist(), batch.column(2).to_pylist()
        hub = sets[other.index(None)]
        a, b = [], []
        for k, (s, o) in enumerate(zip(sets, other, strict=True)):
            if o is not None:
                spot = np.searchsorted(hub, s)
                same = int((hub[np.minimum(spot, len(hub) - 1)] == s).sum())
                if 100 * same >= percent * (len(hub) + len(s) - same):
                    a.append(ids[k])
                    b.append(o)
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return run


def _linker(size: int, percent: int):
    """Exact links within one block of a bucket: enough of them to connect what is connected, never all pairs."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("doc_id").combine_chunks()
        batch = table.to_batches()[0]
        ids, comp = table["doc_id"].to_numpy(), table["comp"].to_numpy()
        sets = exact_sets(table["text"].to_pylist(), size)
        n = np.array([len(s) for s in sets])
        _, column = np.unique(np.concatenate(sets), return_inverse=True)
        row = np.repeat(np.arange(len(sets)), n)
        shared = np.bincount(column)[column] > 1
        row, column = row[shared], column[shared]
        order = np.argsort(column, kind="stable")
        row, column = row[order], np.cumsum(np.diff(column[order], prepend=-1) > 0) - 1
        same = np.zeros((len(sets), len(sets)), np.float32)
        cuts = np.searchsorted(column, np.arange(0, (column[-1] + 1 if len(column) else 0) + COLUMNS, COLUMNS))
        for c, (x, y) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
            part = np.zeros((len(sets), COLUMNS), np.float32)
            part[row[x:y], column[x:y] - c * COLUMNS] = 1
            same += part @ part.T
        i, j = np.nonzero((100 * same >= percent * (n[:, None] + n[None] - same)) & (comp[:, None] < comp[None]))
        top = {c: c for c in comp.tolist()}

        def root(c):
            while top[c] != c:
                c = top[c]
            return c

        out = []
        for x, y in zip(i.tolist(), j.tolist(), strict=True):
            p, q = sorted((root(comp[x].item()), root(comp[y].item())))
            if p != q:
                top[q] = p
                out.append((ids[x], ids[y]))
        return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([y for _, y in out], pa.int64())})

    return run


def confirm(pairs: DataFrame, texts: DataFrame, size: int, percent: int) -> DataFrame:
    """Of pairs (a, b), distinct, those whose full sets are alike. Hubs (a) with many partners are split over tasks."""
    crowd = pairs.groupBy("a").agg(F.ceil(F.count("*") / STAR).alias("parts"))
    dealt = pairs.join(crowd, "a").select("a", F.pmod(F.xxhash64("b"), F.col("parts")).alias("part"), "b")
    others = dealt.join(texts.select(F.col("doc_id").alias("b"), "text"), "b").select("a", "part", "b", "text")
    hubs = dealt.select("a", "part").distinct().join(texts.select(F.col("doc_id").alias("a"), "text"), "a").select("a", "part", F.lit(None).cast("long").alias("b"), "text")
    return stored(others.unionByName(hubs).groupBy("a", "part").applyInArrow(_confirmer(size, percent), "a long, b long"), "links")


def _rest(members: DataFrame, hubs: DataFrame, stars: DataFrame, texts: DataFrame, size: int, percent: int) -> DataFrame:
    """Links that the stars missed: buckets whose members, hub apart, still lie in several components are compared within.
    Buckets with the same members are one; large ones are cut into blocks of pairs of parts."""
    comps = components(stars)
    known = members.join(comps.select(F.col("id").alias("doc_id"), "component_id"), "doc_id", "left").select("key", "doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("comp"))
    aside = known.join(hubs.select("key", F.col("hub.doc_id").alias("hub")), "key")
    split = aside.groupBy("key").agg(F.count("*").alias("m"), F.sum("n_shingles").alias("total"), F.bit_xor(F.xxhash64("doc_id")).alias("x"), F.sum(F.pmod(F.xxhash64(F.col("doc_id") + 1), F.lit(1 << 40))).alias("s"), F.min(F.when(F.col("doc_id") != F.col("hub"), F.col("comp"))).alias("low"), F.max(F.when(F.col("doc_id") != F.col("hub"), F.col("comp"))).alias("high")).filter("low < high")
    split = split.groupBy("m", "x", "s").agg(F.min("key").alias("key"), F.max("total").alias("total")).select("key", F.greatest(F.ceil(F.col("m") / BLOCK), F.ceil(F.col("total") / BLOCK_SHINGLES)).cast("int").alias("parts"))
    own = F.pmod(F.xxhash64("doc_id"), F.col("parts")).cast("int")
    dealt = stored(known.join(split, "key").withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select("key", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"), "doc_id", "comp"), "rest")
    return stored(dealt.join(texts, "doc_id").groupBy("key", "p", "q").applyInArrow(_linker(size, percent), "a long, b long"), "rest-links")


def near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of docs (doc_id, text).

    Words are lower-cased in A-Z; a text of fewer than `size` words is one shingle; texts without words, and null ones, have an
    empty set and link with nothing. Equal sets always link. doc_id names a document: rows that share one count as linked; rows
    without one link with nothing and are kept. Other columns are ignored. An empty table gives no row.
    """
    rows = docs.filter("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text"))
    sketches = stored(rows.mapInArrow(_sketcher(size), SKETCH), "sketches")
    some = sketches.filter("n_shingles > 0")
    firsts = stored(some.groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n_shingles"), F.first("bands").alias("bands")), "sets")
    dealt = firsts.select(F.col("rep").alias("doc_id"), "n_shingles", F.explode("bands").alias("key"))
    crowded = dealt.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1").select("key")
    members = stored(dealt.join(crowded, "key").select("key", "doc_id", "n_shingles"), "members")
    asked = members.select("doc_id").distinct()
    texts = stored(rows.join(asked, "doc_id", "left_semi").dropDuplicates(["doc_id"]), "texts")
    hubs = members.groupBy("key").agg(F.min(F.struct("doc_id", "n_shingles")).alias("hub"))
    near = members.join(hubs, "key").filter("doc_id <> hub.doc_id").filter(100 * F.least("n_shingles", "hub.n_shingles") >= percent * F.greatest("n_shingles", "hub.n_shingles"))
    stars = confirm(stored(near.select(F.col("hub.doc_id").alias("a"), F.col("doc_id").alias("b")).distinct(), "stars"), texts, size, percent)
    links = stars.unionByName(_rest(members, hubs, stars, texts, size, percent))
    parts = components(links)
    named = firsts.select("set_key", "rep").join(parts.withColumnRenamed("id", "rep"), "rep", "left").select("set_key", F.coalesce("component_id", "rep").alias("rep"))
    out = sketches.join(named, "set_key", "left")
    found = F.when(F.col("n_shingles") > 0, F.coalesce("rep", "doc_id")).otherwise(F.col("doc_id"))
    out = out.select("doc_id", "n_shingles", found.alias("component_id"))
    unnamed = docs.filter("doc_id is null").select(F.lit(None).cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text"))
    unnamed = unnamed.mapInArrow(_sketcher(size), SKETCH).select("doc_id", "n_shingles", F.lit(None).cast("long").alias("component_id"))
    return out.unionByName(unnamed).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))
