"""Operators that users of the filters need around them, each as a query with its SQL twin."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .functions.hashing import make_spec, sql_positions
from .functions.sqlfn import register
from .functions.theory import estimate_size
from .operators import filters as L
from .oracles import SPEC, TAGS, base, suppliers
from .sources import collections as C
from .streaming.windows import sessions, tumbling, windowed_words


def _t(spark, sf_dir, name):
    return C.table(spark, sf_dir, name)


def op_scan_prune(spark, sf_dir):
    """Column pruning and a range filter that reaches the Parquet scan."""
    return _t(spark, sf_dir, "orders").filter("o_orderkey between 100 and 199").select("o_orderkey", "o_custkey")


def op_broadcast_join(spark, sf_dir):
    nations = _t(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    return _t(spark, sf_dir, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


def op_merge_join(spark, sf_dir):
    o, li = _t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), _t(spark, sf_dir, "lineitem").select("l_orderkey")
    return o.hint("merge").join(li, o.o_orderkey == li.l_orderkey).groupBy("o_custkey").agg(F.count("*").alias("n"))


def op_theta_join(spark, sf_dir):
    """Pairs of nations by an inequality; for tiny sides only."""
    n = _t(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    m = n.select(F.col("n_nationkey").alias("other"), F.col("n_regionkey").alias("r"))
    return n.join(m, (F.col("n_nationkey") < F.col("other")) & (F.col("n_regionkey") == F.col("r"))).groupBy("n_regionkey").agg(F.count("*").alias("pairs"))


def op_range_join(spark, sf_dir):
    """Ids to the 32 even ranges that hold them: the range condition becomes equality on the leaf number."""
    from .plans.tree import node_of

    domain = C.domain_of(spark, sf_dir)
    ranges = spark.range(32).select(F.col("id").alias("leaf"))
    return _t(spark, sf_dir, "orders").select(node_of(F.col("o_orderkey"), 5, domain).alias("leaf"), "o_totalprice").join(ranges, "leaf").groupBy("leaf").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def op_asof(spark, sf_dir):
    """For each purchase the last earlier view of the user, by one window over both."""
    e = _t(spark, sf_dir, "events").select("user_id", "ts", "event_id", "event_type")
    left, right = e.agg(F.min("event_type"), F.max("event_type")).first()
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.filter(F.col("event_type").isin(left, right)).withColumn("last", F.last(F.when(F.col("event_type") == right, F.col("event_id")), ignorenulls=True).over(before))
    return seen.filter(F.col("event_type") == left).select("event_id", F.col("last").alias("last_id"))


def op_semi_filter(spark, sf_dir):
    return _t(spark, sf_dir, "customer").join(_t(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi").select("c_custkey")


def op_anti_absent(spark, sf_dir):
    return C.all_ids(spark, C.domain_of(spark, sf_dir)).join(_t(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("x")), "x", "left_anti")


def op_filter_semijoin(spark, sf_dir):
    """A filter thins the large side before the exact join: only ids that it holds are shuffled."""
    keys = _t(spark, sf_dir, "orders").filter("o_totalprice > 400000").select(F.lit("k").alias("set_id"), F.col("o_orderkey").alias("x"))
    words = L.build_filters(keys, SPEC)
    thin = _t(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("x"), "l_quantity").withColumn("set_id", F.lit("k"))
    return L.check_pairs(thin, words, SPEC).join(keys, ["set_id", "x"], "left_semi").groupBy("x").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


def op_bit_or_union(spark, sf_dir):
    pairs = C.orders_by_supplier(spark, sf_dir)
    return L.ones(L.build_filters(pairs, SPEC).withColumn("set_id", F.lit("all")).groupBy("set_id", "word_no").agg(F.bit_or("bits").alias("bits")))


def op_bitmap_native(spark, sf_dir):
    return L.native_chunks(C.orders_by_supplier(spark, sf_dir), SPEC).groupBy("set_id").agg(F.sum("ones").alias("ones"))


def op_size_estimate(spark, sf_dir):
    """Sizes from filters beside exact ones; sketches of the engine are within a tenth of both."""
    pairs = C.orders_by_supplier(spark, sf_dir)
    est = L.ones(L.build_filters(pairs, SPEC)).select("set_id", F.round(estimate_size(F.col("ones"), SPEC.m, SPEC.k), 6).alias("by_filter"))
    exact = pairs.groupBy("set_id").agg(F.count_distinct("x").alias("exact"), (F.abs(F.approx_count_distinct("x", 0.02) - F.count_distinct("x")) < 0.1 * F.count_distinct("x")).alias("sketch_near"))
    return est.join(exact, "set_id")


def op_cube_metrics(spark, sf_dir):
    o = _t(spark, sf_dir, "orders")
    return o.cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("g"))


def op_rollup_levels(spark, sf_dir):
    c = _t(spark, sf_dir, "customer").join(_t(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return c.rollup("n_regionkey", "n_nationkey").agg(F.count("*").alias("n"))


def op_grouping_sets(spark, sf_dir):
    _t(spark, sf_dir, "lineitem").createOrReplaceTempView("bitgrove_lineitem")
    return spark.sql("SELECT l_returnflag, l_linenumber, count(*) AS n FROM bitgrove_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linenumber), ())")


def op_pivot_accuracy(spark, sf_dir):
    li = _t(spark, sf_dir, "lineitem")
    return li.groupBy("l_suppkey").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count("l_orderkey")).select("l_suppkey", *(F.coalesce(F.col(c), F.lit(0)).alias(f"n_{c.lower()}") for c in "ANR"))


def op_rank_estimates(spark, sf_dir):
    sizes = C.orders_by_supplier(spark, sf_dir).groupBy("set_id").agg(F.count("*").alias("n"))
    w = Window.orderBy(F.desc("n"), "set_id")
    return sizes.select("set_id", "n", F.row_number().over(w).alias("position"), F.rank().over(Window.orderBy(F.desc("n"))).alias("rank"), F.dense_rank().over(Window.orderBy(F.desc("n"))).alias("dense"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(Window.orderBy(F.desc("n"))), 6).alias("share"), F.round(F.cume_dist().over(Window.orderBy(F.desc("n"))), 6).alias("upto"))


def op_neighbour_gap(spark, sf_dir):
    w = Window.partitionBy("set_id").orderBy("x")
    gaps = C.orders_by_supplier(spark, sf_dir).select("set_id", "x", (F.col("x") - F.lag("x").over(w)).alias("before"), (F.lead("x").over(w) - F.col("x")).alias("after"), F.nth_value("x", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second"))
    return gaps.groupBy("set_id").agg(F.max("before").alias("widest"), F.min("after").alias("closest"), F.max("second").alias("second"))


def op_running_occupancy(spark, sf_dir):
    from .plans.tree import node_of

    domain = C.domain_of(spark, sf_dir)
    held = _t(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("x")).distinct().groupBy(node_of(F.col("x"), 5, domain).alias("leaf")).agg(F.count("*").alias("n"))
    w = Window.orderBy("leaf")
    return held.select("leaf", "n", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("upto"), F.sum("n").over(w.rangeBetween(-2, 2)).alias("around"))


def op_topk_sets(spark, sf_dir):
    return C.pairs(_t(spark, sf_dir, "lineitem"), "l_partkey", "l_orderkey").groupBy("set_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "set_id").limit(10)


def _two(spark, sf_dir):
    li = _t(spark, sf_dir, "lineitem")
    return (li.filter(F.col("l_returnflag") == s).select("l_orderkey") for s in ("A", "R"))


def op_set_union(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.unionByName(b).groupBy("l_orderkey").agg(F.count("*").alias("n"))


def op_set_intersect(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.intersectAll(b).groupBy("l_orderkey").agg(F.count("*").alias("n"))


def op_set_except(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.exceptAll(b).groupBy("l_orderkey").agg(F.count("*").alias("n"))


def op_stratified_sample(spark, sf_dir):
    """Ten orders of each status with the smallest digests: a sample that reruns agree on."""
    o = _t(spark, sf_dir, "orders").select("o_orderstatus", "o_orderkey", F.md5(F.col("o_orderkey").cast("string")).alias("k"))
    return o.withColumn("r", F.row_number().over(Window.partitionBy("o_orderstatus").orderBy("k"))).filter("r <= 10").select("o_orderstatus", "o_orderkey")


def op_tokens(spark, sf_dir):
    return C.docs_by_token(spark, sf_dir).groupBy("set_id").agg(F.count("*").alias("n"))


def op_page_hosts(spark, sf_dir):
    return C.pages_by_host(spark, sf_dir).groupBy("set_id").agg(F.count("*").alias("n"))


def op_day_sets(spark, sf_dir):
    return C.users_by_type_day(spark, sf_dir).groupBy("set_id").agg(F.count("*").alias("n"), F.min("x").alias("low"), F.max("x").alias("high"))


def op_theory_scalars(spark, sf_dir):
    """The registered SQL functions over set sizes."""
    register(spark, SPEC)
    C.orders_by_supplier(spark, sf_dir).groupBy("set_id").agg(F.count("*").cast("double").alias("n")).createOrReplaceTempView("bitgrove_sizes")
    return spark.sql(f"SELECT set_id, round(fp_rate(n, {SPEC.m}, 3), 9) AS fp, round(false_overlap(1, n, {SPEC.m}, 3), 9) AS overlap, round(size_estimate(CAST(n AS BIGINT)), 6) AS size, positions(CAST(n AS BIGINT))[0] AS first FROM bitgrove_sizes")


def op_array_sets(spark, sf_dir):
    sets = C.orders_by_supplier(spark, sf_dir).groupBy("set_id").agg(F.sort_array(F.collect_set("x")).alias("xs"))
    return sets.select("set_id", F.size("xs").cast("long").alias("n"), F.element_at("xs", 1).alias("low"), F.aggregate("xs", F.lit(0).cast("long"), lambda a, x: a + x % 97).alias("checksum"), F.array_contains("xs", 5).alias("has_5"), F.size(F.filter("xs", lambda x: x % 2 == 0)).cast("long").alias("even"))


def op_map_words(spark, sf_dir):
    """Filters as maps from word number to bits: how many words, and how many with more than 32 bits set."""
    words = L.build_filters(C.orders_by_supplier(spark, sf_dir), SPEC)
    maps = words.groupBy("set_id").agg(F.map_from_entries(F.collect_list(F.struct("word_no", "bits"))).alias("m"))
    return maps.select("set_id", F.size(F.map_keys("m")).cast("long").alias("words"), F.size(F.map_filter("m", lambda k, v: F.bit_count(v) > 12)).cast("long").alias("crowded"))


def op_json_sets(spark, sf_dir):
    """Sets keyed by a field of a JSON column."""
    e = _t(spark, sf_dir, "events").select(F.from_json("props", "k int")["k"].alias("k"), "user_id")
    return C.pairs(e, "k", "user_id").groupBy("set_id").agg(F.count("*").alias("n"))


def op_window_filters(spark, sf_dir):
    """One filter per event type and day; the stream of the same events gives the same words."""
    e = _t(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    words = windowed_words(e, TAGS, tumbling())
    return words.groupBy("event_type", F.date_format("start", "yyyy-MM-dd").alias("day")).agg(F.sum(F.bit_count("bits")).cast("long").alias("ones"))


def op_string_keys(spark, sf_dir):
    """Ids that are strings: xxhash64 positions find every page again."""
    spec = make_spec(40_000, family="xxhash64")
    pages = C.pairs(_t(spark, sf_dir, "pages"), F.lit("all"), "page_id").drop("x").distinct()
    rows = _t(spark, sf_dir, "pages").select(F.col("url").alias("x")).distinct()
    words = L.build_filters(rows.join(F.broadcast(pages)), spec)
    return L.check_pairs(rows.withColumn("set_id", F.lit("all")), words, spec).groupBy("set_id").agg(F.count("*").alias("n"))


def op_sessions(spark, sf_dir):
    """Sessions of users: a gap of six hours ends one."""
    e = _t(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return sessions(e, "6 hours").groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"), F.sum("n").alias("events"))


def op_late_rows(spark, sf_dir):
    """Events by type that come, in the order of their ids, more than a day after a later one of their type."""
    seen = Window.partitionBy("event_type").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = _t(spark, sf_dir, "events").withColumn("top", F.max("ts").over(seen))
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.col("ts") < F.col("top") - F.expr("INTERVAL 1 DAY")).alias("late"))


def op_lateral(spark, sf_dir):
    """For each nation its three customers of largest balance, by a correlated subquery."""
    _t(spark, sf_dir, "nation").createOrReplaceTempView("bitgrove_nation")
    _t(spark, sf_dir, "customer").createOrReplaceTempView("bitgrove_customer")
    return spark.sql("SELECT n_nationkey, t.c_custkey FROM bitgrove_nation, LATERAL (SELECT c_custkey FROM bitgrove_customer WHERE c_nationkey = n_nationkey ORDER BY c_custkey DESC LIMIT 3) t")


def op_bernoulli(spark, sf_dir):
    """A tenth of the orders of each status by coins that depend on the key alone, so that every rerun agrees."""
    coin = F.conv(F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 8), 16, 10).cast("double") / 4294967296.0
    return _t(spark, sf_dir, "orders").filter(coin < 0.1).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


def op_recursive_ranges(spark, sf_dir):
    """The ranges of a tree's nodes by a recursive query."""
    domain = C.domain_of(spark, sf_dir)
    return spark.sql(f"WITH RECURSIVE node(level, low, high) AS (SELECT 0, CAST(0 AS BIGINT), CAST({domain} AS BIGINT) UNION ALL SELECT level + 1, CASE WHEN side = 0 THEN low ELSE (low + high) DIV 2 END, CASE WHEN side = 0 THEN (low + high) DIV 2 ELSE high END FROM node CROSS JOIN (SELECT explode(array(0, 1)) AS side) WHERE level < 4) SELECT CAST(level AS BIGINT) AS level, low, high FROM node")


def op_udtf_runs(spark, sf_dir):
    """Runs of consecutive ids of each return flag, by a table function over sorted partitions."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="first: bigint, last: bigint")
    class Runs:
        def __init__(self):
            self.first = self.last = None

        def eval(self, row):
            x = row["x"]
            if self.last is None or x != self.last + 1:
                if self.last is not None:
                    yield self.first, self.last
                self.first = x
            self.last = x

        def terminate(self):
            if self.last is not None:
                yield self.first, self.last

    spark.udtf.register("bitgrove_runs", Runs)
    C.orders_by_flag(spark, sf_dir).createOrReplaceTempView("bitgrove_flags")
    return spark.sql("SELECT last - first + 1 AS length, count(*) AS n FROM bitgrove_runs(TABLE(bitgrove_flags) PARTITION BY set_id ORDER BY x) GROUP BY ALL")


QUERIES = {name: f for name, f in list(globals().items()) if name.startswith("op_")}

_LI = "SELECT l_orderkey FROM lineitem WHERE l_returnflag = '{}'"
_LEAF = "((x << 5) // (SELECT max(o_orderkey) + 1 FROM orders))"
ORACLES = {
    "op_scan_prune": "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderkey BETWEEN 100 AND 199",
    "op_broadcast_join": "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name",
    "op_merge_join": "SELECT o_custkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey",
    "op_theta_join": "SELECT a.n_regionkey, count(*) AS pairs FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey GROUP BY a.n_regionkey",
    "op_range_join": f"SELECT {_LEAF} AS leaf, count(*) AS n, round(sum(p), 2) AS total FROM (SELECT o_orderkey AS x, o_totalprice AS p FROM orders) GROUP BY leaf",
    "op_asof": "WITH k AS (SELECT min(event_type) AS a, max(event_type) AS b FROM events) SELECT event_id, (SELECT arg_max(v.event_id, (v.ts, v.event_id)) FROM events v WHERE v.user_id = e.user_id AND v.event_type = b AND (v.ts < e.ts OR (v.ts = e.ts AND v.event_id < e.event_id))) AS last_id FROM events e, k WHERE event_type = a",
    "op_semi_filter": "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
    "op_anti_absent": "SELECT x FROM (SELECT unnest(range(0, (SELECT max(o_orderkey) + 1 FROM orders)::BIGINT)) AS x) WHERE x NOT IN (SELECT l_orderkey FROM lineitem)",
    "op_filter_semijoin": "SELECT l_orderkey AS x, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_totalprice > 400000) GROUP BY l_orderkey",
    "op_bit_or_union": base(suppliers()) + " SELECT 'all' AS set_id, count(DISTINCT pos) AS ones FROM bits",
    "op_bitmap_native": base(suppliers()) + " SELECT set_id, count(*) AS ones FROM bits GROUP BY set_id",
    "op_cube_metrics": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS g FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "op_rollup_levels": "SELECT n_regionkey, n_nationkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)",
    "op_grouping_sets": "SELECT l_returnflag, l_linenumber, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linenumber), ())",
    "op_pivot_accuracy": "SELECT l_suppkey, count(*) FILTER (l_returnflag = 'A') AS n_a, count(*) FILTER (l_returnflag = 'N') AS n_n, count(*) FILTER (l_returnflag = 'R') AS n_r FROM lineitem GROUP BY l_suppkey",
    "op_rank_estimates": f"SELECT set_id, n, (row_number() OVER (ORDER BY n DESC, set_id))::INT AS position, (rank() OVER (ORDER BY n DESC))::INT AS rank, (dense_rank() OVER (ORDER BY n DESC))::INT AS dense, (ntile(4) OVER (ORDER BY n DESC, set_id))::INT AS quarter, round(percent_rank() OVER (ORDER BY n DESC), 6) AS share, round(cume_dist() OVER (ORDER BY n DESC), 6) AS upto FROM (SELECT set_id, count(*) AS n FROM ({suppliers()}) GROUP BY set_id)",
    "op_neighbour_gap": f"SELECT set_id, max(x - p) AS widest, min(q - x) AS closest, max(s) AS second FROM (SELECT set_id, x, lag(x) OVER w AS p, lead(x) OVER w AS q, nth_value(x, 2) OVER (PARTITION BY set_id ORDER BY x ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS s FROM ({suppliers()}) WINDOW w AS (PARTITION BY set_id ORDER BY x)) GROUP BY set_id",
    "op_running_occupancy": f"SELECT leaf, n, (sum(n) OVER (ORDER BY leaf ROWS UNBOUNDED PRECEDING))::BIGINT AS upto, (sum(n) OVER (ORDER BY leaf RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING))::BIGINT AS around FROM (SELECT {_LEAF} AS leaf, count(*) AS n FROM (SELECT DISTINCT l_orderkey AS x FROM lineitem) GROUP BY leaf)",
    "op_topk_sets": "SELECT l_partkey::VARCHAR AS set_id, count(DISTINCT l_orderkey) AS n FROM lineitem GROUP BY l_partkey ORDER BY n DESC, set_id LIMIT 10",
    "op_set_union": f"SELECT l_orderkey, count(*) AS n FROM ({_LI.format('A')} UNION ALL {_LI.format('R')}) GROUP BY l_orderkey",
    "op_set_intersect": f"SELECT l_orderkey, count(*) AS n FROM ({_LI.format('A')} INTERSECT ALL {_LI.format('R')}) GROUP BY l_orderkey",
    "op_set_except": f"SELECT l_orderkey, count(*) AS n FROM ({_LI.format('A')} EXCEPT ALL {_LI.format('R')}) GROUP BY l_orderkey",
    "op_stratified_sample": "SELECT o_orderstatus, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderstatus ORDER BY md5(o_orderkey::VARCHAR)) <= 10",
    "op_tokens": "SELECT t AS set_id, count(DISTINCT doc_id) AS n FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS t FROM documents) WHERE t <> '' GROUP BY t HAVING count(DISTINCT doc_id) >= 0.05 * (SELECT count(*) FROM documents)",
    "op_page_hosts": "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS set_id, count(DISTINCT page_id) AS n FROM pages GROUP BY 1",
    "op_day_sets": "SELECT event_type || '/' || strftime(ts, '%Y-%m-%d') AS set_id, count(DISTINCT user_id) AS n, min(user_id) AS low, max(user_id) AS high FROM events WHERE user_id IS NOT NULL GROUP BY 1",
    "op_theory_scalars": f"SELECT set_id, round(pow(1 - exp(-3.0::DOUBLE * n / {SPEC.m}), 3), 9) AS fp, round(1 - exp(9.0::DOUBLE * n * ln(1 - 1.0::DOUBLE / {SPEC.m})), 9) AS overlap, round(ln(({SPEC.m}::DOUBLE - n) / {SPEC.m}) / (3 * ln(1 - 1.0::DOUBLE / {SPEC.m})), 6) AS size, {sql_positions(SPEC, 'n')[0]} AS first FROM (SELECT set_id, count(*) AS n FROM ({suppliers()}) GROUP BY set_id)",
    "op_array_sets": f"SELECT set_id, count(*) AS n, min(x) AS low, sum(x % 97)::BIGINT AS checksum, bool_or(x = 5) AS has_5, count(*) FILTER (x % 2 = 0) AS even FROM ({suppliers()}) GROUP BY set_id",
    "op_map_words": base(suppliers()) + " SELECT set_id, count(*) AS words, count(*) FILTER (n > 12) AS crowded FROM (SELECT set_id, pos // 64, count(*) AS n FROM bits GROUP BY ALL) GROUP BY set_id",
    "op_json_sets": "SELECT json_extract_string(props, '$.k') AS set_id, count(DISTINCT user_id) AS n FROM events WHERE user_id IS NOT NULL GROUP BY 1",
    "op_window_filters": f"SELECT event_type, day, count(DISTINCT pos) AS ones FROM (SELECT event_type, strftime(ts, '%Y-%m-%d') AS day, unnest([{', '.join(sql_positions(TAGS, 'user_id'))}]) AS pos FROM events WHERE user_id IS NOT NULL) GROUP BY ALL",
    "op_size_estimate": base(suppliers()) + f" SELECT set_id, round(ln(({SPEC.m}::DOUBLE - ones) / {SPEC.m}) / (3 * ln(1 - 1.0::DOUBLE / {SPEC.m})), 6) AS by_filter, exact, true AS sketch_near FROM (SELECT set_id, count(*) AS ones FROM bits GROUP BY ALL) JOIN (SELECT set_id, count(*) AS exact FROM sets GROUP BY ALL) USING (set_id)",
    "op_sessions": "SELECT user_id, sum(first)::BIGINT AS sessions, max(n) AS longest, sum(n)::BIGINT AS events FROM (SELECT user_id, s, count(*) AS n, 1 AS first FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events WHERE user_id IS NOT NULL)) GROUP BY user_id, s) GROUP BY user_id",
    "op_late_rows": "SELECT event_type, count(*) AS n, count(*) FILTER (ts < top - INTERVAL 1 DAY) AS late FROM (SELECT event_type, ts, max(ts) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM events) GROUP BY event_type",
    "op_lateral": "SELECT n_nationkey, c_custkey FROM nation JOIN customer ON c_nationkey = n_nationkey QUALIFY row_number() OVER (PARTITION BY n_nationkey ORDER BY c_custkey DESC) <= 3",
    "op_bernoulli": "SELECT o_orderstatus, count(*) AS n, sum(o_orderkey)::BIGINT AS keys FROM orders WHERE ('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT / 4294967296::DOUBLE < 0.1 GROUP BY o_orderstatus",
    "op_recursive_ranges": "WITH RECURSIVE node AS (SELECT 0::BIGINT AS level, 0::BIGINT AS low, (SELECT max(o_orderkey) + 1 FROM orders)::BIGINT AS high UNION ALL SELECT level + 1, CASE WHEN side = 0 THEN low ELSE (low + high) // 2 END, CASE WHEN side = 0 THEN (low + high) // 2 ELSE high END FROM node, range(2) s(side) WHERE level < 4) SELECT level, low, high FROM node",
    "op_udtf_runs": "SELECT length, count(*) AS n FROM (SELECT count(*) AS length FROM (SELECT l_returnflag, x, x - row_number() OVER (PARTITION BY l_returnflag ORDER BY x) AS g FROM (SELECT DISTINCT l_returnflag, l_orderkey AS x FROM lineitem)) GROUP BY l_returnflag, g) GROUP BY length",
    "op_string_keys": "SELECT 'all' AS set_id, count(DISTINCT url) AS n FROM pages",
}
