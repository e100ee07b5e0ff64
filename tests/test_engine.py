import random

import pytest
from pyspark.sql import functions as F

from bitgrove.functions import theory as T
from bitgrove.functions.hashing import make_spec, positions
from bitgrove.functions.sqlfn import register
from bitgrove.operators import baselines as B
from bitgrove.operators import filters as L
from bitgrove.operators import measures as M
from bitgrove.operators.descent import descend, path_probabilities, sample_sets, viability
from bitgrove.operators.sweep import mark, probe_leaves, recover, recover_ops
from bitgrove.plans import tree as X
from bitgrove.sources import collections as C
from bitgrove.sources import store
from bitgrove.streaming.windows import GrowingTree, read_events, tumbling, windowed_words, without_repeats

D = "/root/testdata/sf0.001"
DOMAIN, DEPTH = 300, 4
SPEC = make_spec(211, domain=DOMAIN)


@pytest.fixture(scope="module")
def sets(spark):
    rng = random.Random(4)
    rows = [(s, x) for s, n in (("a", 12), ("b", 30), ("c", 1)) for x in rng.sample(range(DOMAIN), n)]
    return rows


@pytest.fixture(scope="module")
def words(spark, sets):
    return L.build_filters(spark.createDataFrame(sets + sets[:3] + [("a", None)], "set_id string, x long"), SPEC).cache()


@pytest.fixture(scope="module")
def tree(spark):
    return X.complete_tree(spark, SPEC, DOMAIN, DEPTH)


def place(x, spec=SPEC):
    return [(a * x + b) % spec.p % spec.m for a, b in zip(spec.a, spec.b, strict=True)]


def positives(sets):
    out = set()
    for s in {s for s, _ in sets}:
        bits = {p for t, x in sets if t == s for p in place(x)}
        out |= {(s, x) for x in range(DOMAIN) if bits.issuperset(place(x))}
    return out


def test_sizes_of_the_published_tables():
    for d, a, m in ((10**6, 0.5, 28465), (10**6, 0.9, 60870), (10**7, 0.5, 63120), (10**7, 0.9, 132933), (10**5, 0.9, 27340), (10**6, 0.99, 137230)):
        assert T.size_for(1000, d, a) == pytest.approx(m, rel=1e-4)
    with pytest.raises(ValueError):
        T.size_for(1000, 10**6, 1.0)
    assert T.choose_depth(10**6, 120) == 10 and T.choose_depth(10**6, 250) == 9
    assert T.false_path_cost(0.3, 60) == pytest.approx(T.false_path_cost(0.3), rel=1e-6)


def test_membership_is_exact_and_ways_agree(spark, sets, words):
    ids = C.all_ids(spark, DOMAIN)
    want = positives(sets)
    for way in ("each", "division"):
        assert {tuple(r) for r in L.contains(ids, words, SPEC, way).collect()} == want
    assert {(s, x) for s, x in sets} <= want


def test_algebra(spark, sets):
    a = spark.createDataFrame([("s", x) for x in range(0, 40)], "set_id string, x long")
    b = spark.createDataFrame([("s", x) for x in range(20, 60)], "set_id string, x long")
    fa, fb = L.build_filters(a, SPEC), L.build_filters(b, SPEC)
    bits = lambda w: {r.pos for r in L.set_bits(w).collect()}
    assert bits(L.union_filters(fa, fb)) == bits(L.build_filters(a.union(b), SPEC)) == {p for x in range(60) for p in place(x)}
    assert bits(L.intersect_filters(fa, fb)) == bits(fa) & bits(fb) >= {p for x in range(20, 40) for p in place(x)}
    assert L.native_chunks(a, SPEC).first().ones == len(bits(fa))
    with pytest.raises(ValueError):
        L.same_spec(SPEC, make_spec(212, domain=DOMAIN))


def test_tree_is_laminar_and_or_of_children(spark, tree):
    nodes = {(r.level, r.idx): r.occupied for r in tree.nodes.collect()}
    bits = {}
    for r in L.set_bits(tree.words, ("level", "idx")).collect():
        bits.setdefault((r.level, r.idx), set()).add(r.pos)
    for level in range(DEPTH + 1):
        assert sum(n for (at, _), n in nodes.items() if at == level) == DOMAIN
        for idx in range(2**level):
            ids = [x for x in range(DOMAIN) if (x << level) // DOMAIN == idx]
            assert bits[level, idx] == {p for x in ids for p in place(x)}
            if level < DEPTH:
                assert bits[level, idx] == bits[level + 1, 2 * idx] | bits[level + 1, 2 * idx + 1]


def test_small_worked_example(spark):
    spec = make_spec(10, domain=16)
    words = L.build_filters(spark.createDataFrame([("s", 4), ("s", 6)], "set_id string, x long"), spec)
    ids = C.all_ids(spark, 16)
    found = {r.x for r in recover(words, X.complete_tree(spark, spec, 16, 2), ids).collect()}
    assert {4, 6} <= found == {r.x for r in B.probe_recover(ids, words, spec).collect()}


def test_reconstructions_agree(spark, sets, words, tree):
    ids, want = C.all_ids(spark, DOMAIN), positives(sets)
    got = lambda df: {(r.set_id, r.x) for r in df.collect()}
    assert got(recover(words, tree, ids)) == want
    for bits in ("set", "unset", "auto"):
        assert got(B.preimage_recover(words, SPEC, DOMAIN, ids, bits)) == want
    assert got(B.preimage_recover(words, SPEC, DOMAIN, ids, "set", "first")) == want
    assert got(recover(words, tree, ids, tau=1.0, start=0)) <= want
    literal = make_spec(61, family="affine_mod_m", domain=DOMAIN)
    w = L.build_filters(spark.createDataFrame(sets, "set_id string, x long"), literal)
    assert got(B.preimage_recover(w, literal, DOMAIN, ids, "set")) == got(B.probe_recover(ids, w, literal))
    with pytest.raises(ValueError):
        B.preimages(F.col("pos"), make_spec(61, family="md5"), 0, 10)


def test_preimages_partition_the_domain(spark):
    for spec in (SPEC, make_spec(61, family="affine_mod_m", domain=DOMAIN), make_spec(50, domain=DOMAIN, p=97)):
        for i in range(3):
            rows = spark.range(spec.m).select("id", F.explode(B.preimages(F.col("id"), spec, i, DOMAIN)).alias("x"), F.lit(i))
            rows = rows.select("id", "x", positions(F.col("x"), spec)[i].alias("p")).collect()
            assert sorted(r.x for r in rows) == list(range(DOMAIN)) and all(r.p == r.id for r in rows)


def test_occupied_growth_and_rebuild(spark):
    ids = spark.createDataFrame([(x,) for x in range(0, DOMAIN, 7)] + [(None,)], "x long")
    more = spark.createDataFrame([(x,) for x in range(3, 90, 7)], "x long")
    rows = lambda t: sorted(map(tuple, t.words.select("level", "idx", "word_no", "bits").collect()))
    nodes = lambda t: sorted(map(tuple, t.nodes.collect()))
    old = X.build_tree(ids, SPEC, DOMAIN, DEPTH)
    both = X.build_tree(ids.union(more), SPEC, DOMAIN, DEPTH)
    grown = X.grow(old, more)
    assert rows(grown) == rows(both) and nodes(grown) == nodes(both)
    left = ids.union(more).filter("x < 50 or x >= 150 or x % 2 = 0")
    assert rows(X.rebuild_range(both, left, 50, 150)) == rows(X.build_tree(left, SPEC, DOMAIN, DEPTH))
    one = sorted((r.level, r.idx, r.word_no, r.bits) for r in X.one_pass_words(ids, SPEC, DOMAIN, DEPTH).collect())
    assert one == rows(old)


def test_descent_is_the_recursion(spark, sets, words, tree):
    """Leaf and cost of every draw equal those of a literal recursion with the same coins."""
    import hashlib

    ids = C.all_ids(spark, DOMAIN)
    live = mark(words, tree, "floored")
    found = probe_leaves(live, tree, words, ids)
    nodes = viability(live, tree, found)
    got = {(r.set_id, r.draw): (r.idx, r.intersections, r.memberships) for r in descend(nodes, live, tree, 40, 9, "floored").collect()}
    marks = {(r.set_id, r.level, r.idx): (r.weight, r.occupied) for r in live.marks.filter("live").collect()}
    hits = {(r.set_id, r.idx) for r in found.collect()}

    def visit(s, draw, level, idx):
        if level == DEPTH:
            return (idx if (s, idx) in hits else None), 0, marks[s, level, idx][1]
        sides = [c for c in (2 * idx, 2 * idx + 1) if (s, level + 1, c) in marks]
        if not sides:
            return None, 2, 0
        first = sides[0]
        if len(sides) == 2:
            u = int(hashlib.md5(f"9:{s}:{draw}:{level}:{idx}".encode()).hexdigest()[:8], 16) / 2**32
            l, r = (marks[s, level + 1, c][0] for c in sides)
            first = sides[0] if u < l / (l + r) else sides[1]
        ands, probes = 2, 0
        for c in [first, *(x for x in sides if x != first)]:
            leaf, a, p = visit(s, draw, level + 1, c)
            ands, probes = ands + a, probes + p
            if leaf is not None:
                return leaf, ands, probes
        return None, ands, probes

    for (s, draw), out in got.items():
        assert out == visit(s, draw, 0, 0)


def test_samples(spark, sets, words, tree):
    ids, want = C.all_ids(spark, DOMAIN), positives(sets)
    for weights in ("floored", "exact", "paper"):
        got = sample_sets(words, tree, ids, 30, 2, weights).collect()
        assert len(got) == 90 and {(r.set_id, r.x) for r in got if r.x is not None} <= want
    again = sample_sets(words.repartition(5), tree, ids.repartition(7), 30, 2, "exact").collect()
    assert sorted(map(tuple, again)) == sorted(map(tuple, sample_sets(words, tree, ids, 30, 2, "exact").collect()))
    bare = [(r.set_id, r.x) for r in sample_sets(words, tree, ids, 20, 2, "exact", replace=False).collect() if r.x is not None]
    assert len(bare) == len(set(bare)) and {s for s, _ in bare} == {"a", "b", "c"}
    assert sum(s == "c" for s, _ in bare) == min(20, sum(s == "c" for s, _ in want))


def test_exact_weights_are_uniform(spark, sets, words, tree):
    ids = C.all_ids(spark, DOMAIN)
    found = B.probe_recover(ids, words, SPEC)
    off = {r.set_id: r for r in M.distance_to_uniform(path_probabilities(words, tree, ids, "exact"), found).collect()}
    assert all(r.total_variation < 1e-9 and r.reachable == r.n for r in off.values())
    draws = sample_sets(words, tree, ids, 4000, 5, "exact")
    for r in M.chi_square(draws, found).filter("df > 0").collect():
        assert r.p_value > 0.001
        counts = [0] * r.n
        for k, c in enumerate(draws.filter(F.col("set_id") == r.set_id).groupBy("x").count().collect()):
            counts[k] = c["count"]
        q, p = M.chi_square_exact(spark, counts)
        assert q == pytest.approx(r.q, rel=1e-6) and p == pytest.approx(r.p_value, abs=0.02)


def test_empty_and_full_filters(spark, tree):
    ids = C.all_ids(spark, DOMAIN)
    none = spark.createDataFrame([], "set_id string, word_no int, bits long")
    assert recover(none, tree, ids).count() == 0 and sample_sets(none, tree, ids, 3).count() == 0
    full = L.build_filters(spark.range(2000).select(F.lit("f").alias("set_id"), F.col("id").alias("x")), SPEC)
    assert recover(full, tree, ids).count() == DOMAIN
    ops = recover_ops(mark(full, tree), tree).first()
    assert (ops.intersections, ops.memberships) == (2 ** (DEPTH + 1) - 2, DOMAIN)


def test_store_and_sql_functions(spark, tree, words, tmp_path):
    store.save_tree(tree, f"file://{tmp_path}/t")
    back = store.load_tree(spark, f"file://{tmp_path}/t", SPEC)
    ids = C.all_ids(spark, DOMAIN)
    assert sorted(map(tuple, recover(words, back, ids).collect())) == sorted(map(tuple, recover(words, tree, ids).collect()))
    for fmt in ("parquet", "orc", "json", "csv"):
        store.save_filters(words, f"file://{tmp_path}/f-{fmt}", fmt)
        assert sorted(map(tuple, store.load_filters(spark, f"file://{tmp_path}/f-{fmt}", fmt).collect())) == sorted(map(tuple, words.collect()))
    (tmp_path / "ids.txt").write_text("1\nx\n22\n")
    assert {r.x for r in store.read_ids(spark, f"file://{tmp_path}/ids.txt", "text").collect()} == {1, 22}
    register(spark, SPEC)
    row = spark.sql("SELECT positions(17L) AS p, fp_rate(12, 211, 3) AS f, false_overlap(2, 3, 211, 3) AS o, size_estimate(30L) AS s").first()
    assert row.p == place(17) and row.f == pytest.approx(T.fp_rate(12, 211, 3)) and row.o == pytest.approx(T.false_overlap(2, 3, 211, 3))


def test_streams(spark, tmp_path):
    spec = make_spec(500, domain=10_000)
    stream = windowed_words(without_repeats(read_events(spark, D)), spec, tumbling())
    q = stream.writeStream.format("memory").queryName("bitgrove_words").outputMode("append").option("checkpointLocation", str(tmp_path)).trigger(availableNow=True).start()
    q.awaitTermination(120)
    events = C.table(spark, D, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    batch = {tuple(r) for r in windowed_words(events, spec, tumbling()).collect()}
    streamed = {tuple(r) for r in spark.table("bitgrove_words").collect()}
    assert streamed and streamed <= batch
    domain = C.domain_of(spark, D, "events", "user_id")
    first = events.filter("user_id < 5").select(F.col("user_id").alias("x")).distinct()
    growing = GrowingTree(X.build_tree(first, spec, domain, 3))
    growing(events, 0)
    growing(events, 0)
    whole = X.build_tree(events.select(F.col("user_id").alias("x")), spec, domain, 3)
    rows = lambda t: sorted(map(tuple, t.words.select("level", "idx", "word_no", "bits").collect()))
    assert rows(growing.tree) == rows(whole)


def literal_masses(domain, p, drawn):
    """The moving of probability written out over the whole domain."""
    mass = [1.0] * domain
    for x in drawn:
        own, mass[x] = mass[x], 0.0
        gone = set(drawn[: drawn.index(x) + 1])
        near = [v for v in (next((i for i in range(x - 1, -1, -1) if i not in gone), None), next((i for i in range(x + 1, domain) if i not in gone), None)) if v is not None]
        for v in near:
            mass[v] += own / len(near)
        if near and p:
            given = sum(mass) * p / 100
            mass = [m * (1 - p / 100) for m in mass]
            for v in near:
                mass[v] += given / len(near)
    return mass


@pytest.mark.parametrize("p", [0.0, 10.0])
@pytest.mark.parametrize("n", [60, 199])
def test_clustered_draws_against_a_literal_loop(p, n):
    draws = C.ClusteredDraws(200, p, 3)
    drawn = draws.drawn(n)
    assert len(set(drawn)) == n and 0 <= min(drawn) and max(drawn) < 200
    assert [draws.mass(i) for i in range(200)] == pytest.approx(literal_masses(200, p, drawn), abs=1e-9)
    assert sum(draws.mass(i) for i in range(200)) == pytest.approx(200)


def test_clustered_generator(spark):
    def beside(p):
        got = sorted(r.x for r in C.clustered_set(spark, 5000, 500, p=p).collect())
        assert len(set(got)) == 500 and got[0] >= 0 and got[-1] < 5000
        return sum(b - a == 1 for a, b in zip(got, got[1:], strict=False)) / 499

    assert beside(0) < 0.25 and beside(10) > 0.9
    assert sorted(C.ClusteredDraws(50, 10.0, 1).drawn(60)) == list(range(50))
    parts = C.kept_ranges(0.2, "clustered")
    assert len(parts) == 51 and sum(b - a == 1 for a, b in zip(parts, parts[1:], strict=False)) > 30


def test_blocks_of_levels_change_nothing(spark, monkeypatch):
    from bitgrove.operators import sweep as V

    spec = make_spec(300, domain=4000)
    rng = random.Random(4)
    pairs = spark.createDataFrame([(str(s), x) for s in range(6) for x in rng.sample(range(4000), 20)], "set_id string, x long")
    words, ids = L.build_filters(pairs, spec), C.all_ids(spark, 4000)
    tree = X.build_tree(ids, spec, 4000, 6, complete=True)
    counted = X.build_tree(ids, spec, 4000, 6)
    rows = lambda t: sorted(map(tuple, t.nodes.select("level", "idx", "occupied", "ones").collect()))
    assert rows(tree) == rows(counted)
    marks = lambda: sorted((r.set_id, r.level, r.idx, r.both, r.live) for r in V.mark(words, tree, "paper", 1.0).marks.collect())
    many = marks()
    monkeypatch.setattr(V, "BLOCK_ROWS", 0)
    assert marks() == many
    every = {(r.level, r.idx, r.word_no): r.bits for r in X.one_pass_words(ids, spec, 4000, 6).collect()}
    assert every == {(r.level, r.idx, r.word_no): r.bits for r in tree.words.collect()}


def test_draws_per_set_and_printed_flow(spark):
    from bitgrove.operators.descent import sample_sets

    spec = make_spec(200, domain=1000)
    pairs = spark.createDataFrame([("a", x) for x in range(0, 1000, 111)] + [("b", 5)], "set_id string, x long")
    words, ids = L.build_filters(pairs, spec), C.all_ids(spark, 1000)
    tree = X.build_tree(ids, spec, 1000, 5, complete=True)
    draws = spark.createDataFrame([("a", 30), ("b", 3)], "set_id string, draws int")
    strict = {(r.set_id, r.draw): r for r in sample_sets(words, tree, ids, draws, weights="paper", tau=0.0).collect()}
    assert sorted(strict) == [("a", d) for d in range(30)] + [("b", d) for d in range(3)]
    printed = {(r.set_id, r.draw): r for r in sample_sets(words, tree, ids, draws, weights="paper", tau=0.0, printed=True).collect()}
    assert all(printed[k].x == r.x and printed[k].intersections >= r.intersections and printed[k].memberships >= r.memberships for k, r in strict.items())
    ands, probe = X.calibrate_costs(spark, spec, 20_000)
    assert ands > 0 and probe > 0


def test_entry_without_the_training_data_operators(spark):
    import __spark_entry__ as E

    names = set(E.queries())
    assert {"q_recover_safe", "w_recover_ops", "op_asof"} <= names and set(E.oracle_sql()) <= names
    assert E.entry(spark).count() == 10


def test_every_supplier_takes_part(spark, tmp_path):
    from bitgrove import workloads as W

    rng = random.Random(9)
    rows = sorted({(s, x) for s in range(40) for x in rng.sample(range(200), 6)} | {(33, x) for x in range(100)})
    spark.createDataFrame(rows, "l_suppkey long, l_orderkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(x,) for x in range(200)], "o_orderkey long").write.parquet(f"{tmp_path}/orders.parquet")
    sets = [(str(s), x) for s, x in rows]
    bits = {s: {p for t, x in sets if t == s for p in place(x, W.SPEC)} for s, _ in sets}
    found = {(s, x) for s, b in bits.items() for x in range(200) if b.issuperset(place(x, W.SPEC))}
    got = {r.set_id: (r.n_true, r.n_found, r.n_both) for r in W.flagship(spark, str(tmp_path)).collect()}
    assert got == {s: (sum(t == s for t, _ in sets), sum(t == s for t, _ in found), sum(t == s for t, _ in sets)) for s in bits}
    for name in ("q_probe_reservoir", "q_sample_many_noreplace", "q_sample_rejection"):
        out = [(r.set_id, r.x) for r in W.QUERIES[name](spark, str(tmp_path)).collect()]
        # Rejection keeps few draws of a set, perhaps none.
        assert ({s for s, _ in out} == set(bits) or name == "q_sample_rejection") and out and all(p in found for p in out if p[1] is not None), name
    assert {r.set_id for r in W.QUERIES["w_start_level"](spark, str(tmp_path)).collect()} == set(bits)
