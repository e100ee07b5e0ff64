"""Hierarchical multi-length packing.

Each document's token ids are cut into full windows and a rest. Rests are routed to the context-size tier that just holds
them, each tier is packed largest first, and what room a sequence has left is filled from shorter tiers, cutting a piece
where that closes the gap. Sequences of a tier are then dealt to step groups so that the tokens of the groups balance.
Packing runs in pools of a bounded number of tokens, in the order of the input, without a shuffle; a pool spans batches.
"""

from __future__ import annotations

import functools
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TIERS = (256, 512, 1024, 2048)
END = 1
#: Tokens of rests that a pool holds before it is packed; and sequences' tokens of a step group.
POOL_TOKENS, STEP_TOKENS = 2_000_000, 65_536
RESULT = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, tier int, step_group long"
_SPLIT, _ODD = re.compile(r"[\x20\x09-\x0D]+"), re.compile("[\x1c-\x1f]")
#: Words and characters that a worker remembers at most; its memory is emptied beyond, which changes no result.
MEMORY_WORDS, MEMORY_CHARS = 1_000_000, 32_000_000


class _Numbers(dict):
    """Numbers words as they are first asked for."""

    def __init__(self):
        super().__init__()
        self.new: list[str] = []

    def __missing__(self, word: str) -> int:
        n = self[word] = len(self)
        self.new.append(word)
        return n


class Tokens:
    """Ids by a tokenizer that drops white space: each blank-separated piece is encoded once and remembered.

    New pieces are encoded many at a time, with a mark between them that no other piece has."""

    MARK, RUN = "\x01", 500

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.mark = self.tokenizer.encode(self.MARK, add_special_tokens=False).ids
        self._forget()

    def _forget(self) -> None:
        self.number, self.chars = _Numbers(), 0
        self.ids, self.cuts, self.used = np.zeros(1 << 16, np.uint32), np.zeros(1 << 14, np.int64), 0

    def _encoded(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words one after another, and how many each has."""
        if len(self.mark) == 1 and not any(self.MARK in w for w in words):
            runs = [f" {self.MARK} ".join(words[a : a + self.RUN]) + f" {self.MARK}" for a in range(0, len(words), self.RUN)]
            flat = np.concatenate([np.array(x.ids, np.uint32) for x in self.tokenizer.encode_batch_fast(runs, add_special_tokens=False)])
            at = np.flatnonzero(flat == self.mark[0])
            if len(at) == len(words):
                return np.delete(flat, at), np.diff(at, prepend=-1) - 1
        each = [x.ids for x in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]
        return np.fromiter((i for x in each for i in x), np.uint32), np.array([len(x) for x in each], np.int64)

    def _learn(self) -> None:
        new, self.number.new = self.number.new, []
        self.chars += sum(map(len, new))
        n = len(self.number) - len(new)
        flat, lens = self._encoded(new)
        need = self.used + len(flat)
        if need > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros(max(need, len(self.ids)), np.uint32)])
        if n + len(new) + 1 > len(self.cuts):
            self.cuts = np.concatenate([self.cuts, np.zeros(max(n + len(new) + 1, len(self.cuts)), np.int64)])
        self.ids[self.used : need] = flat
        self.cuts[n] = self.used
        self.cuts[n + 1 : n + 1 + len(new)] = self.used + np.cumsum(lens)
        self.used = need

    def of(self, texts: list[str]) -> list[np.ndarray]:
        """The ids of each text, with END behind."""
        out = []
        for at in range(0, len(texts), 256):
            if len(self.number) > MEMORY_WORDS or self.chars > MEMORY_CHARS:
                self._forget()
            get = self.number.__getitem__
            # str.split() also cuts at four separators that the tokenizer does not drop.
            split = [t.split() if not _ODD.search(t) else _SPLIT.split(t) for t in texts[at : at + 256]]
            numbers = [np.fromiter(map(get, x), np.int64, len(x)) for x in split]
            if self.number.new:
                self._learn()
            for k in numbers:
                a, n = self.cuts[k], self.cuts[k + 1] - self.cuts[k]
                ends = np.cumsum(n)
                take = np.arange(ends[-1] if len(ends) else 0) + np.repeat(a - (ends - n), n)
                out.append(np.append(self.ids[take], np.uint32(END)))
        return out


@functools.lru_cache(2)
def tokens_of(path: str) -> Tokens:
    """One per worker process, shared by its tasks."""
    return Tokens(path)


def pack(lengths: list[int], tiers=TIERS) -> list[tuple[int, list[tuple[int, int, int]]]]:
    """Packs rests shorter than the largest tier: (tier, [(rest, start, length), ...]) per sequence, each id once.

    Tiers are taken from the largest; a sequence opens with the longest rest of its tier and takes the longest rests of any
    tier that fit its gap; if none fits, the shortest one is cut and its remainder goes back to its own tier. A last sequence
    that stays short moves to the smallest tier that holds it; a smaller gap stays padding.
    """
    # Rests by length, and one bit per length that has some.
    held: list[list[tuple[int, int]]] = [[] for _ in range(tiers[-1] + 1)]
    some = total = 0

    def put(n: int, rest: tuple[int, int]) -> None:
        nonlocal some, total
        held[n].append(rest)
        some |= 1 << n
        total += n

    def take(n: int) -> tuple[int, int]:
        nonlocal some, total
        rest = held[n].pop()
        if not held[n]:
            some ^= 1 << n
        total -= n
        return rest

    for i, n in enumerate(lengths):
        if n:
            put(n, (i, 0))
    out = []
    while some:
        whole, n = total, some.bit_length() - 1
        i, s = take(n)
        tier = next(t for t in tiers if t >= (min(tiers[-1], whole) if n <= tiers[0] and whole < tiers[-1] else n))
        pieces, gap = [(i, s, n)], tier - n
        while gap and some:
            fits = some & ((2 << gap) - 1)
            n = fits.bit_length() - 1 if fits else (some & -some).bit_length() - 1
            i, s = take(n)
            pieces.append((i, s, min(n, gap)))
            if n > gap:
                put(n - gap, (i, s + gap))
            gap -= min(n, gap)
        size = sum(p[2] for p in pieces)
        out.append((next(t for t in tiers if t >= size), pieces))
    return out


def _steps(tiers: list[int], held: list[int], budget: int) -> list[int]:
    """Step group of each sequence: per tier as many groups as the budget asks for, sequences dealt by size to the emptiest."""
    out, base = [0] * len(tiers), 0
    for tier in sorted(set(tiers)):
        own = sorted((k for k, t in enumerate(tiers) if t == tier), key=lambda k: -held[k])
        groups = max(1, round(len(own) * tier / budget))
        for at, k in enumerate(own):
            turn, place = divmod(at, groups)
            out[k] = base + (groups - 1 - place if turn % 2 else place)
        base += groups
    return out


def _packer(path: str, tiers, pool_tokens: int, step_tokens: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        tokens = tokens_of(path)
        base, window = TaskContext.get().partitionId() << 40, tiers[-1]
        state = {"sequence": 0, "group": 0}
        pool: list[tuple] = []
        full: list[tuple] = []

        def emit():
            made = [(window, [(k, 0, window)]) for k in range(len(full))]
            made += [(t, [(len(full) + i, s, n) for i, s, n in p]) for t, p in pack([len(x[2]) for x in pool], tiers)]
            source = full + pool
            groups = _steps([t for t, _ in made], [sum(p[2] for p in ps) for _, ps in made], step_tokens)
            rows = []
            for (tier, pieces), group in zip(made, groups, strict=True):
                offset = 0
                for i, s, n in pieces:
                    doc, start, ids, total = source[i]
                    rows.append((doc, start + s, n, zlib.crc32(ids[s : s + n]), total, base + state["sequence"], offset, tier, base + state["group"] + group))
                    offset += n
                state["sequence"] += 1
            state["group"] += max(groups, default=-1) + 1
            pool.clear()
            full.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), [pa.int64()] * 7 + [pa.int32(), pa.int64()], strict=True)], names=[x.split()[0] for x in RESULT.split(", ")])

        waiting = 0
        for batch in batches:
            docs = batch.column(0).to_pylist()
            for at in range(0, len(docs), 256):
                part = batch.slice(at, 256)
                for doc, ids in zip(docs[at : at + 256], tokens.of(part.column(1).to_pylist()), strict=True):
                    whole = len(ids) - len(ids) % window
                    full.extend((doc, s, ids[s : s + window], len(ids)) for s in range(0, whole, window))
                    if whole < len(ids):
                        pool.append((doc, whole, ids[whole:], len(ids)))
                    waiting += len(ids)
                    if waiting >= pool_tokens:
                        yield emit()
                        waiting = 0
        if pool or full:
            yield emit()

    return run


def pack_documents(docs: DataFrame, tokenizer: str, tiers=TIERS, pool_tokens: int = POOL_TOKENS, step_tokens: int = STEP_TOKENS) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, tier, step_group.

    docs: doc_id, text. tokenizer: path of a tokenizer file that every executor has, of a kind that drops white space. Null and
    empty texts are the end id alone; repeated rows are packed each; a null doc_id stays null; other columns are ignored. A
    sequence is padded up to its tier, a power of two. An empty table gives no row.
    """
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).mapInArrow(_packer(tokenizer, tuple(tiers), pool_tokens, step_tokens), RESULT)
