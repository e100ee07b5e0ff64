import hashlib
import random
import re
from collections import Counter, defaultdict

from bitgrove.llm.subtree import remove_repeated_words
from bitgrove.llm.suffix_dedup import remove_repeated_bytes


def rows_of(seed, n=60):
    rng = random.Random(seed)
    pool = ["".join(rng.choice("abcdé") for _ in range(rng.randint(1, 6))) for _ in range(400)]
    prose = lambda k: " ".join(rng.choice(pool) for _ in range(k))
    shared = [prose(60), prose(36), "x" * 130]
    rows = []
    for i in range(n):
        text = prose(rng.randint(0, 80))
        if rng.random() < 0.5:
            text += rng.choice(["", " ", "\n"]) + rng.choice(shared)[rng.randint(0, 40) :] + prose(5)
        rows.append((i, text))
    rows += [(n, None), (n + 1, ""), (n + 2, rows[3][1]), (n + 3, rows[3][1]), (n + 3, rows[3][1]), (n + 4, "z" * 49), (n + 5, "y" * 300)]
    rng.shuffle(rows)
    return rows


def brute_bytes(rows, width):
    first = {}
    for i, text in rows:
        b = (text or "").encode()
        for p in range(len(b) - width + 1):
            first[b[p : p + width]] = min(i, first.get(b[p : p + width], i))
    out = []
    for i, text in rows:
        b = (text or "").encode()
        gone = [False] * len(b)
        for p in range(len(b) - width + 1):
            if first[b[p : p + width]] < i:
                gone[p : p + width] = [True] * width
        spans = sum(g and not (k and gone[k - 1]) for k, g in enumerate(gone))
        kept = bytes(c for c, g in zip(b, gone, strict=True) if not g)
        out.append((i, len(b), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return Counter(out)


def brute_words(rows, width):
    split = lambda t: re.findall(r"[^\x20\x09-\x0D]+", t or "")
    seen = defaultdict(int)
    for _, text in rows:
        w = split(text)
        for p in range(len(w) - width + 1):
            seen[tuple(w[p : p + width])] += 1
    out = []
    for i, text in rows:
        w = split(text)
        gone = [False] * len(w)
        for p in range(len(w) - width + 1):
            if seen[tuple(w[p : p + width])] > 1:
                gone[p : p + width] = [True] * width
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        out.append((i, len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return Counter(out)


def test_bytes_against_brute_force(spark):
    rows = rows_of(1)
    docs = spark.createDataFrame([(*r, "en", 1) for r in rows], "doc_id long, text string, block string, ids int").repartition(3)
    assert Counter(map(tuple, remove_repeated_bytes(docs).collect())) == brute_bytes(rows, 50)


def test_words_against_brute_force(spark):
    rows = rows_of(2)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert Counter(map(tuple, remove_repeated_words(docs).collect())) == brute_words(rows, 35)


def test_empty_tables_and_null_ids(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert remove_repeated_bytes(none).count() == remove_repeated_words(none).count() == 0
    odd = spark.createDataFrame([(None, "q" * 80), (1, "q" * 80)], "doc_id long, text string")
    assert {r.doc_id: r.n_removed for r in remove_repeated_bytes(odd).collect()} == {1: 0, None: 80}


def test_given_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    assert Counter(map(tuple, remove_repeated_bytes(docs).collect())) == brute_bytes(rows, 50)
    assert Counter(map(tuple, remove_repeated_words(docs).collect())) == brute_words(rows, 35)
