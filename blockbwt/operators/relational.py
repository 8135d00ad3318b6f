"""Relational operators around the methods: what prepares collections and uses transforms.

Where Spark's SQL and the checking engine's agree, one text serves both: it is
declared in SAME with {table} for each table. The others are DataFrame code with
SQL of their own.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockbwt.tables import load

SAME = {
    "rel_scan_pruned": "SELECT l_returnflag, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM {lineitem} WHERE l_shipdate >= TIMESTAMP '1995-01-01 00:00:00' AND l_shipdate < TIMESTAMP '1996-01-01 00:00:00' GROUP BY l_returnflag",
    "rel_filter_predicates": "SELECT p_partkey, p_name, p_size FROM {part} WHERE (p_size IN (1, 3, 7, 15) OR p_name LIKE 'a%') AND p_size BETWEEN 1 AND 30 AND p_brand IS NOT NULL AND NOT p_partkey = 5 AND p_size <> 9",
    "rel_project_expressions": "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(floor(l_extendedprice * (1 - l_discount)) AS BIGINT) AS net, CASE WHEN l_quantity > 25 THEN 'many' ELSE 'few' END AS amount, CAST(l_quantity AS INTEGER) AS quantity FROM {lineitem}",
    "rel_join_broadcast": "SELECT r_name, n_name, count(*) AS suppliers FROM {supplier} JOIN {nation} ON s_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name, n_name",
    "rel_join_outer": "SELECT d.doc_id AS doc_id, l.doc_id AS labelled, l.quality AS quality FROM {documents} d FULL OUTER JOIN (SELECT * FROM {labels} WHERE toxic = 0) l ON d.doc_id = l.doc_id",
    "rel_join_left": "SELECT d.doc_id AS doc_id, l.quality AS quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id",
    "rel_join_right": "SELECT o.o_orderkey AS orderkey, c.c_custkey AS custkey FROM {orders} o RIGHT JOIN {customer} c ON o.o_custkey = c.c_custkey",
    "rel_join_semi": "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderstatus = 'F')",
    "rel_join_anti": "SELECT doc_id FROM {documents} d WHERE NOT EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id)",
    "rel_join_cross_small": "SELECT a.r_name AS a, b.r_name AS b FROM {region} a CROSS JOIN {region} b",
    "rel_join_null_safe": "SELECT a.doc_id AS doc_id, b.quality AS quality FROM (SELECT d.doc_id, l.quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id) a JOIN (SELECT DISTINCT quality FROM {labels} UNION ALL SELECT NULL) b ON a.quality IS NOT DISTINCT FROM b.quality",
    "rel_join_nested_theta": "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM {nation} a JOIN {nation} b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey <> b.n_regionkey",
    "rel_agg_basic": "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity, round(avg(l_extendedprice), 2) AS price, min(l_shipdate) AS first, max(l_shipdate) AS last, round(stddev_samp(l_discount), 6) AS spread FROM {lineitem} GROUP BY l_returnflag, l_linestatus",
    "rel_agg_distinct": "SELECT count(DISTINCT l_partkey) AS parts FROM {lineitem}",
    "rel_agg_multi_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(*) AS n FROM {lineitem} GROUP BY l_returnflag",
    "rel_agg_filter_clause": "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS finished, count(*) AS n FROM {orders} GROUP BY o_orderpriority",
    "rel_agg_having": "SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey HAVING count(*) >= 12",
    "rel_agg_rollup": "SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) AS BIGINT) AS g, count(*) AS n FROM {lineitem} GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "rel_agg_cube": "SELECT l_returnflag, l_linestatus, CAST(grouping(l_linestatus) AS BIGINT) AS g, count(*) AS n FROM {lineitem} GROUP BY CUBE (l_returnflag, l_linestatus)",
    "rel_agg_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "rel_window_rank_family": "SELECT o_orderkey, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER w AS BIGINT) AS rk, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)",
    "rel_window_lag_lead": "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type, 2) OVER w AS later FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "rel_window_rows_frame": "SELECT o_orderkey, count(*) OVER w AS n, min(o_orderkey) OVER w AS least FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING)",
    "rel_window_first_last_nth": "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS s FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "rel_topk_global": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "rel_topk_group": "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM {orders}) x WHERE k <= 3",
    "rel_limit_offset": "SELECT p_partkey, p_name FROM {part} ORDER BY p_retailprice DESC, p_partkey LIMIT 25 OFFSET 50",
    "rel_set_union_all": "SELECT c_nationkey AS k FROM {customer} UNION ALL SELECT s_nationkey AS k FROM {supplier}",
    "rel_set_union": "SELECT c_nationkey AS k FROM {customer} UNION SELECT s_nationkey AS k FROM {supplier}",
    "rel_set_intersect": "SELECT c_nationkey AS k FROM {customer} INTERSECT SELECT s_nationkey AS k FROM {supplier}",
    "rel_set_intersect_all": "SELECT c_nationkey AS k FROM {customer} INTERSECT ALL SELECT s_nationkey AS k FROM {supplier}",
    "rel_set_except": "SELECT n_nationkey AS k FROM {nation} EXCEPT SELECT s_nationkey AS k FROM {supplier} WHERE s_suppkey < 9",
    "rel_set_except_all": "SELECT c_nationkey AS k FROM {customer} EXCEPT ALL SELECT s_nationkey AS k FROM {supplier}",
    "rel_subquery_scalar": "SELECT count(*) AS n FROM {orders} WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {orders})",
    "rel_subquery_exists": "SELECT o_orderkey FROM {orders} o WHERE o_orderkey IN (SELECT l_orderkey FROM {lineitem} WHERE l_quantity >= 49)",
    "rel_subquery_correlated": "SELECT o_orderkey FROM {orders} o WHERE o_totalprice = (SELECT max(i.o_totalprice) FROM {orders} i WHERE i.o_custkey = o.o_custkey)",
    "rel_cte": "WITH big AS (SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey), top AS (SELECT max(n) AS n FROM big) SELECT big.o_custkey AS custkey, big.n AS n FROM big JOIN top ON big.n = top.n",
    "rel_string_functions": "SELECT p_partkey, upper(p_name) AS u, CAST(length(p_name) AS BIGINT) AS len, substr(p_name, 2, 3) AS mid, lpad(CAST(p_size AS VARCHAR(9)), 4, '0') AS padded, replace(p_name, 'e', 'E') AS swapped, reverse(p_name) AS back, translate(p_name, 'aeiou', 'AEIOU') AS vowels, concat_ws('-', p_brand, p_type) AS joined, CAST(levenshtein(p_name, p_type) AS BIGINT) AS apart FROM {part}",
    "rel_date_functions": "SELECT o_orderkey, date_trunc('month', o_orderdate) AS month, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(quarter(o_orderdate) AS BIGINT) AS q, CAST(o_orderdate AS DATE) AS d FROM {orders}",
    "rel_agg_percentile_exact": "SELECT l_returnflag, round(percentile_cont(0.5) WITHIN GROUP (ORDER BY l_extendedprice), 4) AS median FROM {lineitem} GROUP BY l_returnflag",
}


def _same(sql: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(sql, **{t: load(spark, sf_dir, t) for t in set(re.findall(r"\{(\w+)\}", sql))})

    return run


def filter_regex_documents(spark, d):
    t = load(spark, d, "documents")
    return t.where(F.col("text").rlike(r"\d{3}") & ~F.startswith("text", F.lit("A")) & F.contains("text", F.lit("."))).select("doc_id", F.length("text").cast("long").alias("len"))


def join_sort_merge(spark, d):
    o, rows = load(spark, d, "orders"), load(spark, d, "lineitem")
    return o.join(rows.hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def join_shuffle_hash(spark, d):
    c, o = load(spark, d, "customer"), load(spark, d, "orders")
    return o.join(c.hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


def join_range_binned(spark, d):
    """Lines in ranges of 45 days that begin every 30: each range is in all its bins, a line in one."""
    days = F.datediff(F.to_date("l_shipdate"), F.lit("1992-01-01")).alias("day")
    lines = load(spark, d, "lineitem").select(days).withColumn("bin", F.floor(F.col("day") / 30))
    ranges = spark.range(0, 80).select((F.col("id") * 30).alias("lo"), (F.col("id") * 30 + 45).alias("hi"))
    spread = ranges.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / 30), F.floor((F.col("hi") - 1) / 30))))
    return lines.join(spread, "bin").where("day >= lo and day < hi").groupBy("lo").agg(F.count(F.lit(1)).alias("n"))


def join_asof(spark, d):
    """For each purchase the last click before it: one window over both kinds, no join."""
    e = load(spark, d, "events").where(F.col("event_type").isin("purchase", "click"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    return e.withColumn("click", F.last(click, ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "click")


def join_interval(spark, d):
    """Errors within an hour after a click of the user: bins of an hour, an error looks in its own and the one before."""
    e = load(spark, d, "events")
    hour = F.floor(F.unix_timestamp("ts") / 3600)
    clicks = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("t0"), hour.alias("bin"))
    errors = e.where("event_type = 'error'").select("user_id", F.col("event_id").alias("error"), F.col("ts").alias("t1"), F.explode(F.array(hour, hour - 1)).alias("bin"))
    return errors.join(clicks, ["user_id", "bin"]).where("t1 >= t0 and t1 <= t0 + interval 1 hour").select("click", "error")


def join_lateral_topk(spark, d):
    """Each customer's two dearest orders. A key that several rows of customers hold is one customer; orders without a number come last of equal ones."""
    return spark.sql("SELECT c_custkey, x.o_orderkey FROM (SELECT DISTINCT c_custkey FROM {c}) c, LATERAL (SELECT o_orderkey FROM {o} o WHERE o.o_custkey = c.c_custkey ORDER BY o_totalprice DESC NULLS LAST, o_orderkey NULLS LAST LIMIT 2) x", c=load(spark, d, "customer"), o=load(spark, d, "orders"))


def agg_collect_ordered(spark, d):
    e = load(spark, d, "events")
    said = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", F.substring("event_type", 1, 1).alias("c")))), lambda x: x["c"]), "")
    return e.groupBy("user_id").agg(said.alias("s"))


def agg_approx_distinct(spark, d):
    rows = load(spark, d, "lineitem")
    both = rows.agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("b"), F.approx_count_distinct("l_orderkey", 0.02).alias("c"), F.count_distinct("l_orderkey").alias("e"))
    return both.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("parts_close"), (F.abs(F.col("c") - F.col("e")) <= 0.1 * F.col("e")).alias("orders_close"))


def agg_approx_percentile(spark, d):
    rows = load(spark, d, "lineitem")
    both = rows.agg(F.percentile_approx("l_extendedprice", 0.9, 10000).alias("a"), F.percentile("l_extendedprice", 0.9).alias("b"))
    return both.select((F.abs(F.col("a") - F.col("b")) <= 0.01 * F.col("b")).alias("close"))


def agg_kmer_count_min(spark, d):
    """A count-min sketch never counts below the truth and seldom far above."""
    from blockbwt.operators.kmers import kmer_counts
    from blockbwt.tables import reads

    counts = kmer_counts(reads(spark, d), 6)
    total = counts.agg(F.sum("n")).first()[0] or 0
    cells = counts.select("kmer", "n", F.explode(F.array(*[F.struct(F.lit(i).alias("row"), F.pmod(F.xxhash64(F.lit(i), "kmer"), F.lit(4096)).alias("cell")) for i in range(5)])).alias("c")).select("kmer", "n", "c.row", "c.cell")
    sketch = cells.groupBy("row", "cell").agg(F.sum("n").alias("held"))
    estimate = cells.join(F.broadcast(sketch), ["row", "cell"]).groupBy("kmer").agg(F.first("n").alias("n"), F.min("held").alias("m"))
    return estimate.agg(F.count_if(F.col("m") < F.col("n")).alias("below"), (F.count_if(F.col("m") > F.col("n") + 3 * total / 4096) <= 0.02 * F.count(F.lit(1))).alias("seldom_far"))


def pivot_status(spark, d):
    return load(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)


def unpivot(spark, d):
    p = load(spark, d, "part").select("p_partkey", F.col("p_brand").alias("brand"), F.col("p_type").alias("kind"))
    return p.unpivot("p_partkey", ["brand", "kind"], "what", "value")


def window_range_frame(spark, d):
    """Events of the user within the 6 hours before each."""
    seconds = F.unix_timestamp("ts")
    w = Window.partitionBy("user_id").orderBy(seconds).rangeBetween(-6 * 3600, 0)
    return load(spark, d, "events").select("event_id", F.count(F.lit(1)).over(w).alias("n"))


def reverse_complement_reads(spark, d):
    from blockbwt.functions.sqlfuncs import reverse_complement
    from blockbwt.tables import reads

    return reads(spark, d).df.select("sid", reverse_complement("s").alias("s"))


def math_bits(spark, d):
    k = F.col("l_orderkey")
    return load(spark, d, "lineitem").select(k.alias("k"), F.pmod(k, F.lit(7)).alias("m"), k.bitwiseAND(F.lit(255)).alias("low"), F.shiftleft(k, 2).alias("up"), F.floor(F.sqrt(k.cast("double"))).alias("root")).distinct()


def array_functions(spark, d):
    e = load(spark, d, "embeddings")
    v = F.col("embedding")
    return e.select("vec_id", F.size(v).cast("long").alias("n"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"), F.array_max(F.transform(v, lambda x: F.floor(x * 64))).cast("long").alias("most"), F.array_position(v, F.array_max(v)).cast("long").alias("at"))


def map_functions(spark, d):
    e = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = e.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.size(F.map_filter("m", lambda k, v: v > 10)).cast("long").alias("frequent"))


def json_props(spark, d):
    return load(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


def explode_lines(spark, d):
    return load(spark, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("line", "t")).groupBy("doc_id").agg(F.count(F.lit(1)).alias("lines"), F.max(F.length("t")).cast("long").alias("longest"))


def repeated_lines(spark, d):
    lines = load(spark, d, "documents").select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where("length(line) >= 20")
    return lines.groupBy("line").agg(F.count(F.lit(1)).alias("docs")).where("docs > 1").select(F.md5(F.col("line").cast("binary")).alias("line"), "docs")


def sample_invariants(spark, d):
    """A seeded sample is reproducible and near its share."""
    t = load(spark, d, "lineitem")
    n, a, b = t.count(), t.sample(False, 0.2, 5).count(), t.sample(False, 0.2, 5).count()
    return spark.createDataFrame([(a == b, abs(a - 0.2 * n) < 0.05 * n)], "same boolean, near boolean")


def string_more(spark: SparkSession, d: str) -> DataFrame:
    p = load(spark, d, "part")
    return p.select("p_partkey", F.overlay("p_name", F.lit("XX"), 2, 1).alias("laid"), F.array_join(F.regexp_extract_all("p_name", F.lit("[aeiou]"), F.lit(0)), "").alias("vowels"), F.hex(F.encode("p_name", "UTF-8")).alias("bytes"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("second"))


def agg_listagg(spark: SparkSession, d: str) -> DataFrame:
    return spark.sql("SELECT p_brand, listagg(p_name, ',') WITHIN GROUP (ORDER BY p_name) AS names FROM {part} GROUP BY p_brand", part=load(spark, d, "part"))


def agg_mode(spark: SparkSession, d: str) -> DataFrame:
    """The most frequent size of each brand, the least of several."""
    return load(spark, d, "part").groupBy("p_brand").agg(F.mode("p_size", True).alias("size"))


def agg_sketches(spark: SparkSession, d: str) -> DataFrame:
    """Distinct counts from sketches that are made by flag and united, against exact ones."""
    rows = load(spark, d, "lineitem").select("l_returnflag", "l_orderkey")
    made = rows.groupBy("l_returnflag").agg(F.hll_sketch_agg("l_orderkey", F.lit(14)).alias("s"), F.count_distinct("l_orderkey").alias("n"))
    each = made.select(F.abs(F.hll_sketch_estimate("s") - F.col("n")).alias("off"), "n", "s")
    all_rows = rows.agg(F.count_distinct("l_orderkey").alias("all"))
    done = each.agg((F.max(F.col("off") / F.col("n")) < 0.05).alias("parts_close"), F.hll_sketch_estimate(F.hll_union_agg("s")).alias("united"))
    return done.crossJoin(all_rows).select("parts_close", (F.abs(F.col("united") - F.col("all")) < 0.05 * F.col("all")).alias("union_close"), "all")


def json_variant(spark: SparkSession, d: str) -> DataFrame:
    v = F.parse_json("props")
    return load(spark, d, "events").select("event_id", F.variant_get(v, "$.k", "bigint").alias("k"), F.try_variant_get(v, "$.none", "string").alias("none"))


def sample_by(spark: SparkSession, d: str) -> DataFrame:
    """Shares by type, the same for the same seed; each near what was asked."""
    e = load(spark, d, "events")
    shares = {"click": 0.5, "view": 0.25, "error": 1.0}
    one, two = (e.sampleBy("event_type", shares, 11).select("event_id", "event_type") for _ in range(2))
    same = one.exceptAll(two).isEmpty() and two.exceptAll(one).isEmpty()
    asked = e.groupBy("event_type").count().withColumnRenamed("count", "n")
    got = one.groupBy("event_type").count()
    share = F.coalesce(F.element_at(F.create_map(*[F.lit(x) for k, v in shares.items() for x in (k, v)]), F.col("event_type")), F.lit(0.0))
    far = F.abs(F.coalesce("count", F.lit(0)) - F.col("n") * share) > 5 * F.sqrt("n")
    return asked.join(got, "event_type", "left").agg(F.lit(same).alias("same"), (F.count_if(far) == 0).alias("near"))


OWN = {
    "rel_filter_regex_documents": (filter_regex_documents, "SELECT doc_id, length(text) AS len FROM documents WHERE regexp_matches(text, '[0-9]{3}') AND NOT starts_with(text, 'A') AND contains(text, '.')"),
    "rel_join_sort_merge": (join_sort_merge, "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"),
    "rel_join_shuffle_hash": (join_shuffle_hash, "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"),
    "rel_join_range_binned": (join_range_binned, "SELECT CAST(r.i * 30 AS BIGINT) AS lo, count(*) AS n FROM lineitem JOIN (SELECT unnest(range(80)) AS i) r ON date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) >= r.i * 30 AND date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) < r.i * 30 + 45 GROUP BY r.i"),
    "rel_join_asof": (join_asof, "SELECT event_id, (SELECT max(c.event_id) FROM events c WHERE c.user_id = p.user_id AND c.event_type = 'click' AND c.ts < p.ts) AS click FROM events p WHERE event_type = 'purchase'"),
    "rel_join_interval": (join_interval, "SELECT c.event_id AS click, e.event_id AS error FROM events c JOIN events e ON c.user_id = e.user_id AND c.event_type = 'click' AND e.event_type = 'error' AND e.ts >= c.ts AND e.ts <= c.ts + INTERVAL 1 HOUR"),
    "rel_join_lateral_topk": (join_lateral_topk, "SELECT o_custkey AS c_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer)) WHERE k <= 2"),
    "rel_agg_collect_ordered": (agg_collect_ordered, "SELECT user_id, string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id) AS s FROM events GROUP BY user_id"),
    "rel_agg_approx_distinct": (agg_approx_distinct, "SELECT true AS parts_close, true AS orders_close"),
    "rel_agg_approx_percentile": (agg_approx_percentile, "SELECT true AS close"),
    "rel_agg_kmer_count_min": (agg_kmer_count_min, "SELECT CAST(0 AS BIGINT) AS below, true AS seldom_far"),
    "rel_string_more": (string_more, "SELECT p_partkey, substr(p_name, 1, 1) || 'XX' || substr(p_name, 3) AS laid, array_to_string(regexp_extract_all(p_name, '[aeiou]'), '') AS vowels, hex(p_name) AS bytes, split_part(p_name, ' ', 2) AS second FROM part"),
    "rel_agg_listagg": (agg_listagg, "SELECT p_brand, string_agg(p_name, ',' ORDER BY p_name) AS names FROM part GROUP BY p_brand"),
    "rel_agg_mode": (agg_mode, "SELECT p_brand, min(p_size) AS size FROM (SELECT p_brand, p_size, rank() OVER (PARTITION BY p_brand ORDER BY count(*) DESC) AS r FROM part GROUP BY p_brand, p_size) WHERE r = 1 GROUP BY p_brand"),
    "rel_agg_sketches": (agg_sketches, "SELECT true AS parts_close, true AS union_close, count(DISTINCT l_orderkey) AS \"all\" FROM lineitem"),
    "rel_json_variant": (json_variant, "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, CAST(NULL AS VARCHAR) AS none FROM events"),
    "rel_sample_by": (sample_by, "SELECT true AS same, true AS near"),
    "rel_pivot_status": (pivot_status, "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O, count(*) FILTER (WHERE o_orderstatus = 'P') AS P FROM orders GROUP BY 1"),
    "rel_unpivot": (unpivot, "SELECT p_partkey, 'brand' AS what, p_brand AS value FROM part UNION ALL SELECT p_partkey, 'kind', p_type FROM part"),
    "rel_window_range_frame": (window_range_frame, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 21600 PRECEDING AND CURRENT ROW) AS n FROM events"),
    "rel_reverse_complement": (reverse_complement_reads, None),
    "rel_math_bits": (math_bits, "SELECT DISTINCT l_orderkey AS k, l_orderkey % 7 AS m, l_orderkey & 255 AS low, l_orderkey << 2 AS up, CAST(floor(sqrt(l_orderkey)) AS BIGINT) AS root FROM lineitem"),
    "rel_array_functions": (array_functions, "SELECT vec_id, len(embedding) AS n, len(list_filter(embedding, lambda x: x > 0)) AS positive, CAST(list_max(list_transform(embedding, lambda x: floor(x * 64))) AS BIGINT) AS most, CAST(list_position(embedding, list_max(embedding)) AS BIGINT) AS at FROM embeddings"),
    "rel_map_functions": (map_functions, "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, (SELECT count(*) FROM (SELECT event_type FROM events i WHERE i.user_id = e.user_id GROUP BY event_type HAVING count(*) > 10)) AS frequent FROM events e GROUP BY user_id"),
    "rel_json_props": (json_props, "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events"),
    "rel_explode_lines": (explode_lines, "SELECT doc_id, len(string_split(text, chr(10))) AS lines, list_max(list_transform(string_split(text, chr(10)), lambda x: length(x))) AS longest FROM documents"),
    "repeated_lines": (repeated_lines, "SELECT md5(line) AS line, count(*) AS docs FROM (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20 GROUP BY line HAVING count(*) > 1"),
    "rel_sample_invariants": (sample_invariants, "SELECT true AS same, true AS near"),
}


def queries() -> dict:
    return {k: _same(v) for k, v in SAME.items()} | {k: f for k, (f, _) in OWN.items()}


def oracle_sql() -> dict[str, str]:
    from blockbwt.tables import reads_sql

    out = {k: re.sub(r"\{(\w+)\}", r"\1", v) for k, v in SAME.items()} | {k: s for k, (_, s) in OWN.items() if s}
    return out | {"rel_reverse_complement": f"SELECT sid, translate(reverse(s), 'ACGT', 'TGCA') AS s FROM ({reads_sql()})"}
