import re
from collections import Counter

import corpus_pipeline as P
import numpy as np
import pytest
from tokenizers import Tokenizer

from bitgrove.llm.queries import tokenizer

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    docs = spark.read.parquet(f"{D}/documents.parquet")
    odd = spark.createDataFrame([(None, None, None, None, None), (None, "few words", None, None, 9), (900, "", "en", "src1", 0), (901, "w " * 70, "en", None, 140)], docs.schema)
    docs = docs.unionByName(odd)
    out = [("documents", docs.toPandas(), docs.columns)]
    for name, stage in P.STAGES:
        docs = P.stored(stage(spark, docs, D), name)
        out.append((name, docs.toPandas(), docs.columns))
    return out


def test_order_and_columns(stages):
    assert [s[0] for s in stages[1:]] == ["quality_rules", "minhash_near_dedup", "pii_surrogates", "source_mix", "packing"]
    assert all(s[2] == stages[0][2] for s in stages[:5])


def test_quality_and_dedup(stages):
    before, kept, one = (s[1] for s in stages[:3])
    words = lambda t: re.findall(r"[^\x20\x09-\x0D]+", t or "")
    for t in kept.text:
        w = words(t)
        tri = Counter(zip(w, w[1:], w[2:], strict=False))
        hit = {k + d for k, x in enumerate(zip(w, w[1:], w[2:], strict=False)) if tri[x] > 1 for d in range(3)}
        assert len(w) >= 50 and 100 * len(hit) <= 50 * len(w)
    sets = {i: set(zip(*(words((t or "").lower())[k:] for k in range(5)), strict=False)) for i, t in zip(kept.doc_id, kept.text, strict=True)}
    alike = lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])
    left = sorted(one.doc_id)
    assert len(left) == len(set(left))
    assert not any(alike(a, b) for k, a in enumerate(left) for b in left[k + 1 :])
    gone = set(sets) - set(left)
    assert gone and all(any(alike(a, b) for b in sets if b != a) for a in gone)


def test_surrogates_mix_and_packing(stages):
    one, safe, mixed, packed = (s[1] for s in stages[2:])
    assert sorted(one.doc_id) == sorted(safe.doc_id)
    pii = re.compile(r"[\w.+-]+@mail\d+\.example\.com|\b\d{16}\b|\+1 \(\d{3}\) \d{3}-\d{4}")
    for a, b in zip(one.sort_values("doc_id").text, safe.sort_values("doc_id").text, strict=True):
        assert not any(v in b for v in pii.findall(a))
        assert pii.search(a) or re.search(r"\d\.\d", a) or a == b
    n = Counter(mixed.doc_id)
    assert set(n) <= set(safe.doc_id) and max(n.values()) <= 2
    size = {i: len(t.split()) for i, t in zip(safe.doc_id, safe.text, strict=True)}
    assert sum(size[i] * c for i, c in n.items()) == pytest.approx(1.5 * sum(size.values()), rel=0.1)
    t = Tokenizer.from_file(tokenizer())
    total = sum(len(t.encode(x, add_special_tokens=False).ids) + 1 for x in mixed.text)
    assert packed.length.sum() == total
    held = packed.groupby("sequence_id").agg(n=("length", "sum"), tier=("tier", "first"))
    assert (held.n <= held.tier).all() and held.n.sum() > 0.97 * held.tier.sum() and set(held.tier) <= {256, 512, 1024, 2048}
    assert np.isin(packed.doc_id, mixed.doc_id).all()


def test_empty_documents(spark):
    none = spark.read.parquet(f"{D}/documents.parquet").limit(0)
    for name, stage in P.STAGES:
        none = P.stored(stage(spark, none, D), name)
        assert none.count() == 0
