"""Queries whose sets are marked, swept and drawn from in the tasks that hold their filters."""

import random

import pytest
from test_whole import equals_sql, folder, long_folder, moved  # noqa: F401

from bitgrove import workloads as W
from bitgrove.oracles import ORACLES
from bitgrove.plans import tree as X
from bitgrove.sources import collections as C

#: By finding.
NAMES = [
    "q_path_probability",
    "q_sample_exact",
    "q_sample_one",
    "q_recover_threshold",
    "q_sample_ops",
    "q_sample_printed",
    "q_sample_prior",
    "q_sample_rejection",
    "q_recover_safe",
    "w_sample_uniform_ops",
    "q_precision_recall",
    "q_sample_many_replace",
    "q_sample_paper",
    "q_sample_many_noreplace",
    "q_membership",
    "q_preimage_unset_bits",
]


@pytest.mark.parametrize("name", NAMES)
def test_only_pairs_and_filters_move(spark, folder, name):  # noqa: F811
    """Besides the tree's words only pairs and filters move; before, words, live nodes, positives and draws moved too."""
    before = moved(spark)
    X.build_tree(C.all_ids(spark, 20_000), W.SPEC, 20_000, W.DEPTH, complete=True)
    tree = moved(spark) - before
    before = moved(spark)
    W.QUERIES[name](spark, folder).count()
    assert moved(spark) - before < tree + 40 * 600 * 1.1


@pytest.mark.parametrize("name", NAMES)
def test_whole_jobs_beyond_one_period(spark, long_folder, name):  # noqa: F811
    equals_sql(spark, long_folder, name)


@pytest.mark.parametrize("family", ["affine_mod_p", "affine_mod_m"])
@pytest.mark.parametrize("top", [90, 1000])
def test_division_and_unset_bits_find_what_a_probe_finds(family, top):
    import numpy as np

    from bitgrove.operators import whole as H

    spec, rng = W.make_spec(130, family=family, domain=1000), random.Random(6)
    top = min(top, H.turns(spec, top))
    place = lambda x: [(a * x + b) % (spec.p if family == "affine_mod_p" else spec.m) % spec.m for a, b in zip(spec.a, spec.b, strict=True)]
    for n in (0, 25, 60, 400):
        held = {p for x in rng.sample(range(1000), n) for p in place(x)}
        bits = np.zeros(spec.words * 64, bool)
        bits[list(held)] = True
        want = [x for x in range(top) if held.issuperset(place(x))]
        assert H._divider(spec, top)(bits).tolist() == want and H._taker(spec, top)(bits).tolist() == want


def test_coins_of_numbers_counted_up():
    """They are those of single keys, whatever stands before and behind the numbers, also where keys are too long for one block."""
    import numpy as np

    from bitgrove.functions import digests as D

    tails = [":3", ":12", ""]
    for low in (100_000, 980_000, 1_000_000, 10**9):
        x, which = np.arange(low, low + D.COUNTED), np.arange(D.COUNTED) % 3
        for head in ("1:7", "1:pick:24", "12:x", "1:" + "s" * 50):
            assert (D.coins_counted(f"{head}:", low, [""]) == D.coins(head, x)).all()
            got = D.coins_counted(f"{head}:", low, tails, which)
            for i, behind in enumerate(("3", "12")):
                assert (got[which == i] == D.coins(head, x[which == i], behind)).all()
            assert (got[which == 2] == D.coins(head, x[which == 2])).all()


@pytest.mark.parametrize("name", ["q_chi_square_floored", "q_chi_square"])
def test_only_counts_of_members_leave_the_draws(spark, tmp_path, name):
    """390,000 draws hit nearly all of 21,000 ids in both sets; before, the counts of all of them moved, and not of 3,000 members."""
    import duckdb

    spark.createDataFrame([(7 * x, x % 2) for x in range(1, 3001)], "c_custkey long, c_nationkey long").write.parquet(f"{tmp_path}/customer.parquet")
    before = moved(spark)
    got = sorted(tuple(r) for r in W.QUERIES[name](spark, str(tmp_path)).collect())
    assert moved(spark) - before < 25_000
    db = duckdb.connect()
    db.execute(f"CREATE VIEW customer AS SELECT * FROM '{tmp_path}/customer.parquet/*.parquet'")
    want = sorted(db.execute(ORACLES[name]).fetchall())
    assert [r[:3] for r in got] == [r[:3] for r in want] and all(a == pytest.approx(b, abs=2e-6) for r, w in zip(got, want, strict=True) for a, b in zip(r[3:], w[3:], strict=True))


def test_start_below_the_levels_of_its_sql(spark, tmp_path):
    """Where levels 0 to 4 are full the sweep starts at level 5, with a row for every supplier: that of the SQL carried on to this level.
    The registered SQL ends at level 3."""
    import duckdb

    from bitgrove import oracles as O

    rng = random.Random(7)
    rows = [(s, x) for s in range(6) for x in rng.sample(range(900_000), 200)]
    spark.createDataFrame(rows, "l_suppkey long, l_orderkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(899_999,)], "o_orderkey long").write.parquet(f"{tmp_path}/orders.parquet")
    db = duckdb.connect()
    for t in ("lineitem", "orders"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
    sql = f"SELECT q.* FROM ({O.base(O.suppliers())}{O.tree(W.SPEC, W.DEPTH)}{O.live(W.SPEC, W.DEPTH, start=5)} {O.sweep_ops('', W.SPEC, W.DEPTH, 5)}) q"
    got = sorted(tuple(r) for r in W.QUERIES["w_start_level"](spark, str(tmp_path)).collect())
    assert len(got) == 6 and got == sorted(db.execute(sql).fetchall())


def test_runs_of_draws_add_up(spark, monkeypatch):
    """130,000 draws of a set dealt in seven runs hit its ids as often as in one; the filters of two sets, one of them empty of draws."""
    from bitgrove.operators import descent as S
    from bitgrove.operators import filters as L
    from bitgrove.operators import held as H

    spec = W.make_spec(400, domain=1000)
    words = L.build_filters(spark.createDataFrame([(str(s), 37 * x % 1000 + s) for s in (0, 1) for x in range(40)], "set_id string, x long"), spec)
    tree = X.build_tree(C.all_ids(spark, 1000), spec, 1000, 3, complete=True)
    draws = spark.createDataFrame([("0", 130_000), ("1", 0)], "set_id string, draws long")
    got = sorted(S.sample_counts(words, tree, draws).collect())
    monkeypatch.setattr(H, "RUN_DRAWS", H.COUNTED)
    assert sum(r.times for r in got) == 130_000 and got == sorted(S.sample_counts(words, tree, draws).collect())
