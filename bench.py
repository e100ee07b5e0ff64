"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "6g")).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from bitgrove import workloads as W
    from bitgrove.functions.hashing import make_spec
    from bitgrove.functions.theory import size_for
    from bitgrove.operators.baselines import probe_recover, probe_sample
    from bitgrove.operators.descent import sample_sets
    from bitgrove.operators.filters import build_filters
    from bitgrove.operators.sweep import recover
    from bitgrove.plans.tree import complete_tree
    from bitgrove.sources import collections as C

    queries: dict[str, object] = {n: W.QUERIES[n] for n in ("q_filter_ones", "q_membership", "q_tree_complete_ones", "q_recover_safe", "q_probe_recover", "q_preimage_first_function", "q_sample_many_replace", "q_sample_exact", "w_fraction_memory")}
    queries["flagship"] = W.flagship
    domain = 1_000_000
    spec = make_spec(round(size_for(1000, domain, 0.9)), domain=domain)
    trees: dict = {}

    def creation(s, _):
        trees["t"] = complete_tree(s, spec, domain, 9)
        return trees["t"].nodes

    def drawn_by_tree(s, _):
        words = build_filters(C.uniform_set(s, domain, 1000), spec)
        return sample_sets(words, trees["t"], C.all_ids(s, domain), 10_000, 1, "exact")

    def drawn_by_probe(s, _):
        return probe_sample(C.all_ids(s, domain), build_filters(C.uniform_set(s, domain, 1000), spec), spec, 10_000)

    def recovered_by_tree(s, _):
        return recover(build_filters(C.clustered_set(s, domain, 1000, 20), spec), trees["t"], C.all_ids(s, domain))

    def recovered_by_probe(s, _):
        return probe_recover(C.all_ids(s, domain), build_filters(C.clustered_set(s, domain, 1000, 20), spec), spec)

    def by_family(family):
        other = make_spec(spec.m, family=family, domain=domain)
        return lambda s, _: probe_recover(C.all_ids(s, domain), build_filters(C.uniform_set(s, domain, 1000), other), other)

    # Batches of tree and probe are alike: as many draws, the same sets.
    queries |= {"b_tree_creation_1e6": creation, "b_sample_10000_draws_1e6": drawn_by_tree, "b_probe_10000_draws_1e6": drawn_by_probe, "b_recover_tree_1e6": recovered_by_tree, "b_recover_probe_1e6": recovered_by_probe}
    queries |= {f"b_probe_{f}": by_family(f) for f in ("affine_mod_m", "affine_mod_p", "murmur3", "md5")}
    # What takes longest at sf0.1 comes last; past the budget nothing is started and its figure is null.
    queries |= {n: W.QUERIES[n] for n in ("w_recover_ops", "w_tag_filters")}
    queries = {n: q for n, q in queries.items() if n.startswith("b_")} | queries
    budget, start = float(os.environ.get("BENCH_SECONDS", "700")), time.time()
    spark.range(1000).agg(F.sum("id")).collect()
    took: dict[str, float | None] = {}
    for name, q in queries.items():
        began = time.time()
        if began - start > budget:
            took[name] = None
            continue
        try:
            q(spark, sf_dir).write.format("noop").mode("overwrite").save()
            took[name] = round(time.time() - began, 3)
        except Exception:  # a failed query must not hide the others' figures
            took[name] = None
    print(json.dumps({"metric": "total_query_seconds", "value": round(sum(t or 0 for t in took.values()), 3), "unit": "sec", "queries": took, "sf": sf_dir.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
