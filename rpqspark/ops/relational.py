"""The relational operators around the methods, each over whole given tables, with the
SQL that DuckDB runs for the same rows.

An entry is (Spark callable, SQL). Where both dialects agree the Spark side runs the
same text through the SQL API; elsewhere it is a DataFrame expression.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph.sources import table


def _t(spark: SparkSession, sf_dir: str, *names: str) -> list[DataFrame]:
    return [table(spark, sf_dir, n) for n in names]


def _views(text: str):
    """A query that is the same text in both dialects."""
    import re

    names = sorted(set(re.findall(r"\b(region|nation|customer|supplier|part|orders|lineitem|events|pages|conversations)\b", text)))

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        # Views of the caller's catalog are not touched: the names are bound as parameters.
        return spark.sql(re.sub(r"\b(" + "|".join(names) + r")\b", lambda m: "{" + m[1] + "}", text), **{n: table(spark, sf_dir, n) for n in names})

    return run, text


def range_join(spark, sf_dir):
    """Parts by price band; the bands are a small table, so the join is a broadcast range join."""
    part, = _t(spark, sf_dir, "part")
    bands = spark.range(0, 20).select(F.col("id").alias("band"), (F.col("id") * 100).cast("double").alias("lo"), (F.col("id") * 100 + 100).cast("double").alias("hi"))
    return part.join(F.broadcast(bands), (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


def as_of_join(spark, sf_dir):
    """Each purchase with the user's last click before it: clicks and purchases are merged in
    one sorted stream per user, and a running last value replaces a join on inequality."""
    e, = _t(spark, sf_dir, "events")
    e = e.filter(F.col("event_type").isin("click", "purchase"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click", last).filter("event_type = 'purchase'").select("event_id", "user_id", "click")


def salted_join(spark, sf_dir, salts: int = 8):
    """Orders of each customer by a join whose hot keys are dealt over salts."""
    o, c = _t(spark, sf_dir, "orders", "customer")
    left = o.withColumn("salt", F.pmod(F.xxhash64("o_orderkey"), F.lit(salts)))
    right = c.select("c_custkey", "c_mktsegment").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return left.join(right, (left.o_custkey == right.c_custkey) & (left.salt == right.salt)).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def pivot(spark, sf_dir):
    o, = _t(spark, sf_dir, "orders")
    return o.groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0).select("o_orderpriority", *[F.col(k).alias(f"n_{k.lower()}") for k in "FOP"])


def stratified(spark, sf_dir):
    """A sample by a hash of the key, a fixed share of each label; its size is compared only."""
    l, = _t(spark, sf_dir, "lineitem")
    counts = l.groupBy("l_returnflag").agg(F.count("*").alias("all_rows"))
    part = l.sampleBy("l_returnflag", {"A": 0.5, "N": 0.5, "R": 0.5}, 3).groupBy("l_returnflag").agg(F.count("*").alias("k"))
    return counts.join(part, "l_returnflag").select("l_returnflag", ((F.col("k") > 0.3 * F.col("all_rows")) & (F.col("k") < 0.7 * F.col("all_rows"))).alias("near_half"))


def arrays(spark, sf_dir):
    """A host's parts: split, reverse, transform, filter, aggregate, zip_with, exists, slice."""
    p, = _t(spark, sf_dir, "pages")
    h = p.select("page_id", F.split(F.regexp_extract("url", "https?://([^/]+)", 1), r"\.").alias("a"))
    return h.select("page_id", F.array_join(F.reverse("a"), ".").alias("turned"), F.aggregate(F.transform("a", F.length), F.lit(0), lambda s, x: s + x).cast("long").alias("letters"), F.size(F.filter("a", lambda x: F.length(x) > 3)).cast("long").alias("longer"), F.exists("a", lambda x: x == "example").alias("example"), F.array_join(F.slice("a", -2, 2), ".").alias("tail"))


def maps(spark, sf_dir):
    """Counts of a user's event types as a map and back."""
    e, = _t(spark, sf_dir, "events")
    n = e.groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return n.select("user_id", F.coalesce(F.element_at("m", "click"), F.lit(0)).alias("clicks"), F.size("m").cast("long").alias("kinds"))


ENTRIES: dict[str, tuple] = {
    "ops_filter": _views("SELECT o_orderkey, o_orderstatus FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus NOT IN ('P')"),
    "ops_like": _views("SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS kind FROM part WHERE p_brand LIKE 'Brand#1%'"),
    "ops_null_safe": (lambda s, d: table(s, d, "events").select("event_id", F.when(F.col("value") > 50, F.col("event_type")).alias("k")).filter(F.col("k").eqNullSafe(F.lit(None))).select("event_id"), "SELECT event_id FROM (SELECT event_id, CASE WHEN value > 50 THEN event_type END AS k FROM events) WHERE k IS NOT DISTINCT FROM NULL"),
    "ops_inner_join": _views("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name <> 'ASIA' GROUP BY n_name"),
    "ops_left_join": _views("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey"),
    "ops_full_join": _views("SELECT coalesce(a.k, b.k) AS k, a.n AS customers, b.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_custkey % 3 = 0 GROUP BY c_nationkey) a FULL OUTER JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY s_nationkey) b ON a.k = b.k"),
    "ops_semi_join": (lambda s, d: (lambda p, l: p.join(l.filter("l_quantity > 49"), p.p_partkey == l.l_partkey, "left_semi").select("p_partkey"))(*_t(s, d, "part", "lineitem")), "SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 49)"),
    "ops_anti_join": (lambda s, d: (lambda o, l: o.join(l, o.o_orderkey == l.l_orderkey, "left_anti").select("o_orderkey"))(*_t(s, d, "orders", "lineitem")), "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)"),
    "ops_range_join": (range_join, "SELECT band, count(*) AS n FROM part JOIN (SELECT range AS band, range * 100.0 AS lo, range * 100.0 + 100.0 AS hi FROM range(20)) ON p_retailprice >= lo AND p_retailprice < hi GROUP BY band"),
    "ops_as_of_join": (as_of_join, "SELECT p.event_id, p.user_id, (SELECT max_by(c.event_id, (c.ts, c.event_id)) FROM events c WHERE c.user_id = p.user_id AND c.event_type = 'click' AND (c.ts < p.ts OR c.ts = p.ts AND c.event_id < p.event_id)) AS click FROM events p WHERE p.event_type = 'purchase'"),
    "ops_cross_join": _views("SELECT r_name, n_name FROM region CROSS JOIN nation"),
    "ops_self_join": _views("SELECT a.n_name AS x, b.n_name AS y FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey"),
    "ops_salted_join": (salted_join, "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"),
    "ops_bit_aggregates": _views("SELECT l_returnflag, bit_or(l_linenumber) AS ors, bit_and(l_linenumber) AS ands, bit_xor(l_linenumber) AS xors FROM lineitem GROUP BY l_returnflag"),
    "ops_min_by": _views("SELECT user_id, min_by(event_id, ts) AS first_event, max_by(event_id, ts) AS last_event FROM events GROUP BY user_id"),
    "ops_count_distinct": _views("SELECT l_linestatus, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_linestatus"),
    "ops_approx_distinct": (lambda s, d: table(s, d, "lineitem").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) / F.countDistinct("l_partkey") - 1) < 0.1).alias("near")), "SELECT true AS near"),
    "ops_count_if": (lambda s, d: table(s, d, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_totalprice") > 100000).alias("n")), "SELECT o_orderpriority, count(*) FILTER (WHERE o_totalprice > 100000) AS n FROM orders GROUP BY o_orderpriority"),
    "ops_percentile": (lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_quantity", F.lit(0.5)), 6).alias("median")), "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS median FROM lineitem GROUP BY l_returnflag"),
    "ops_collect_set": (lambda s, d: table(s, d, "events").groupBy("user_id").agg(F.array_join(F.sort_array(F.collect_set("event_type")), ",").alias("kinds")), "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS kinds FROM events GROUP BY user_id"),
    "ops_rollup": (lambda s, d: table(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"),
    "ops_cube": (lambda s, d: table(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"),
    "ops_grouping_sets": _views("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"),
    "ops_pivot": (pivot, "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS n_f, count(*) FILTER (WHERE o_orderstatus = 'O') AS n_o, count(*) FILTER (WHERE o_orderstatus = 'P') AS n_p FROM orders GROUP BY o_orderpriority"),
    "ops_ranks": _views("SELECT p_partkey, CAST(row_number() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS BIGINT) AS rn, CAST(rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS BIGINT) AS rk, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS BIGINT) AS dr, CAST(ntile(4) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS BIGINT) AS quarter, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_size), 9) AS share FROM part"),
    "ops_lag_lead": _views("SELECT event_id, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM events"),
    "ops_running": _views("SELECT conv_id, turn, CAST(sum(length(text)) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS letters, first_value(role) OVER (PARTITION BY conv_id ORDER BY turn) AS opener FROM conversations"),
    "ops_range_window": _views("SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM part"),
    "ops_top_k": _views("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
    "ops_offset": _views("SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 20"),
    "ops_top_k_per_group": _views("SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS k FROM part) t WHERE k <= 3"),
    "ops_set_operations": _views("(SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey AS k FROM supplier) EXCEPT SELECT n_nationkey AS k FROM nation WHERE n_regionkey = 1"),
    "ops_except_all": _views("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey AS k FROM supplier"),
    "ops_intersect_all": _views("SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey AS k FROM supplier"),
    "ops_sample": (stratified, "SELECT l_returnflag, true AS near_half FROM lineitem GROUP BY l_returnflag"),
    "ops_bits": (lambda s, d: table(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.col("l_partkey").bitwiseAND(255).alias("a"), F.col("l_partkey").bitwiseOR(16).alias("b"), F.col("l_partkey").bitwiseXOR(7).alias("c"), F.shiftleft("l_partkey", 3).alias("d"), F.shiftright("l_partkey", 2).alias("e"), F.bit_count("l_partkey").cast("long").alias("f")), "SELECT l_orderkey, l_linenumber, l_partkey, l_partkey & 255 AS a, l_partkey | 16 AS b, xor(l_partkey, 7::BIGINT) AS c, l_partkey << 3 AS d, l_partkey >> 2 AS e, bit_count(l_partkey)::BIGINT AS f FROM lineitem"),
    "ops_strings": (lambda s, d: table(s, d, "part").select("p_partkey", F.lower("p_name").alias("a"), F.regexp_replace("p_type", "[AEIOU]", "_").alias("b"), F.substring_index("p_brand", "#", -1).alias("c"), F.translate("p_name", "abc", "xyz").alias("d"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("e")), "SELECT p_partkey, lower(p_name) AS a, regexp_replace(p_type, '[AEIOU]', '_', 'g') AS b, string_split(p_brand, '#')[-1] AS c, translate(p_name, 'abc', 'xyz') AS d, regexp_extract(p_brand, '([0-9]+)', 1) AS e FROM part"),
    "ops_dates": (lambda s, d: table(s, d, "events").groupBy(F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n")), "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY 1"),
    "ops_math": (lambda s, d: table(s, d, "part").select("p_partkey", F.ceil(F.log2(F.col("p_size") + 1)).cast("long").alias("bits"), F.pmod(F.col("p_size") - 25, F.lit(7)).cast("long").alias("m"), F.round("p_retailprice", 1).alias("r")), "SELECT p_partkey, ceil(log2(p_size + 1))::BIGINT AS bits, (((p_size - 25) % 7 + 7) % 7)::BIGINT AS m, round(p_retailprice, 1) AS r FROM part"),
    "ops_arrays": (arrays, "SELECT page_id, array_to_string(list_reverse(a), '.') AS turned, list_sum([length(x) for x in a])::BIGINT AS letters, len([x for x in a if length(x) > 3])::BIGINT AS longer, list_contains(a, 'example') AS example, array_to_string(a[-2:], '.') AS tail FROM (SELECT page_id, string_split(regexp_extract(url, 'https?://([^/]+)', 1), '.') AS a FROM pages)"),
    "ops_maps": (maps, "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id"),
    "ops_json": (lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("j")), """SELECT event_id, CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS INT) AS k, CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS INT) AS j FROM events"""),
}
