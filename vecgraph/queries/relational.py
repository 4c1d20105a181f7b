"""Projections, joins, aggregations, windows, sets and scalar functions around the methods.

Every query runs over whole tables and has its SQL.
"""

from __future__ import annotations

from pyspark.sql import Window, functions as F

from ..sources.tables import load, register_all
from .base import Book

BOOK = Book()
_HASH_PART = "CAST(('0x' || substr(md5(CAST({} AS VARCHAR)), 1, 7))::BIGINT % {} AS BIGINT)"


def _micros():
    """Microseconds of events.ts since 1970; the column has no time zone."""
    return F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)")


def _bucket(c, n):
    """A bucket of an id by its MD5, the same in SQL."""
    return F.conv(F.substring(F.md5(F.col(c).cast("string").cast("binary")), 1, 7), 16, 10).cast("bigint") % n


# --- projections and predicates -----------------------------------------------------


@BOOK.add("p01_projection", "SELECT o_orderkey, o_custkey AS customer, CAST(trunc(o_totalprice) AS BIGINT) AS whole_price, coalesce(TRY_CAST(o_orderstatus AS BIGINT), -1) AS no_number, 'order' AS kind FROM orders")
def p01(spark, d):
    o = load(spark, d, "orders")
    return o.select("o_orderkey", F.col("o_custkey").alias("customer"), F.col("o_totalprice").cast("bigint").alias("whole_price"), F.expr("coalesce(try_cast(o_orderstatus AS BIGINT), -1)").alias("no_number"), F.lit("order").alias("kind"))


@BOOK.add(
    "p02_predicates",
    """SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS size_class,
    coalesce(nullif(p_brand, 'Brand#11'), 'none') AS brand, (p_brand IS NOT DISTINCT FROM 'Brand#12') AS is_12
    FROM part WHERE p_size BETWEEN 3 AND 45 AND p_type LIKE '%E%' AND NOT regexp_matches(p_name, '^z') AND p_brand IN ('Brand#11','Brand#12','Brand#13','Brand#22','Brand#33')""",
)
def p02(spark, d):
    p = load(spark, d, "part").where(
        F.col("p_size").between(3, 45) & F.col("p_type").like("%E%") & ~F.col("p_name").rlike("^z") & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13", "Brand#22", "Brand#33")
    )
    kind = F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large")
    return p.select("p_partkey", kind.alias("size_class"), F.coalesce(F.nullif("p_brand", F.lit("Brand#11")), F.lit("none")).alias("brand"), F.col("p_brand").eqNullSafe("Brand#12").alias("is_12"))


@BOOK.add("p05_explode", "SELECT vec_id, CAST(i - 1 AS INTEGER) AS pos, embedding[i] AS v FROM embeddings, (SELECT unnest(range(1, 65)) AS i)")
def p05(spark, d):
    return load(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "v"))


@BOOK.add("p06_stable_sample", f"SELECT l_orderkey, l_linenumber FROM lineitem WHERE {_HASH_PART.format('l_orderkey', 10)} = 0")
def p06(spark, d):
    """The sampling operator: an order falls in or out as a whole, on every run and engine."""
    return load(spark, d, "lineitem").where(_bucket("l_orderkey", 10) == 0).select("l_orderkey", "l_linenumber")


@BOOK.add("p06_stratified_sample")
def p06b(spark, d):
    rates = {k: r for k, r in enumerate([0.1, 0.2, 0.3, 0.4, 0.5, 0.5, 0.4, 0.3, 0.2, 0.1])}
    return load(spark, d, "embeddings").sampleBy("label", rates, seed=7).select("vec_id", "label")


@BOOK.add("p07_valid_vectors", "SELECT vec_id FROM embeddings WHERE len(embedding) = 64 AND len(list_filter(embedding, lambda v: v IS NULL OR isnan(v) OR isinf(v))) = 0")
def p07(spark, d):
    from ..sources.corpora import valid

    return valid(load(spark, d, "embeddings"), 64).select("vec_id")


# --- joins --------------------------------------------------------------------------


@BOOK.add("j01_broadcast_join", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def j01(spark, d):
    return load(spark, d, "nation").join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")  # 5 rows


@BOOK.add(
    "j02_sort_merge_join",
    "SELECT o_orderkey, count(*) AS lines, round(sum(l_extendedprice * (1 - l_discount)), 4) AS revenue FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey",
)
def j02(spark, d):
    j = load(spark, d, "orders").hint("merge").join(load(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderkey").agg(F.count("*").alias("lines"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 4).alias("revenue"))


@BOOK.add("j02_shuffle_hash_join", "SELECT c_custkey, count(o_orderkey) AS orders_n FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def j02b(spark, d):
    j = load(spark, d, "customer").hint("shuffle_hash").join(load(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"))
    return j.groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders_n"))


@BOOK.add("j05_theta_join", "SELECT a.r_name AS a, b.r_name AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def j05(spark, d):
    r = load(spark, d, "region")
    return r.alias("a").join(F.broadcast(r.alias("b")), F.expr("a.r_regionkey < b.r_regionkey")).select(F.col("a.r_name").alias("a"), F.col("b.r_name").alias("b"))  # 5 rows


@BOOK.add("j06_left_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
def j06(spark, d):
    o = load(spark, d, "orders").where("o_orderpriority = '1-URGENT'")
    return load(spark, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@BOOK.add("j07_left_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def j07(spark, d):
    return load(spark, d, "customer").join(load(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@BOOK.add(
    "j08_full_outer",
    """SELECT coalesce(c.n, s.n) AS nation, coalesce(customers, 0) AS customers, coalesce(suppliers, 0) AS suppliers FROM
    (SELECT c_nationkey AS n, count(*) AS customers FROM customer GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS n, count(*) AS suppliers FROM supplier GROUP BY 1) s ON c.n = s.n""",
)
def j08(spark, d):
    c = load(spark, d, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("customers"))
    s = load(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("suppliers"))
    return c.join(s, "nation", "full_outer").select("nation", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


@BOOK.add("j08_left_outer", "SELECT p_partkey, count(l_orderkey) AS lines FROM part LEFT JOIN lineitem ON p_partkey = l_partkey GROUP BY p_partkey")
def j08b(spark, d):
    return load(spark, d, "part").join(load(spark, d, "lineitem"), F.col("p_partkey") == F.col("l_partkey"), "left").groupBy("p_partkey").agg(F.count("l_orderkey").alias("lines"))


@BOOK.add(
    "j10_interval_join",
    """SELECT a.event_id, count(b.event_id) AS within_hour FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR
    WHERE a.event_type = 'purchase' GROUP BY a.event_id""",
)
def j10(spark, d):
    """Events of the same user within the hour after a purchase: an equi-join on (user, hour bin), each purchase in two bins."""
    e = load(spark, d, "events").withColumn("bin", F.floor(_micros() / 3_600_000_000))
    a = e.where("event_type = 'purchase'").select(F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"), "user_id", F.explode(F.array("bin", F.col("bin") + 1)).alias("bin"))
    j = a.join(e, ["user_id", "bin"]).where("ts > a_ts AND ts <= a_ts + INTERVAL 1 HOUR")
    return j.groupBy(F.col("a_id").alias("event_id")).agg(F.count("*").alias("within_hour"))


@BOOK.add(
    "j11_asof_join",
    """SELECT e.event_id, l.event_id AS view_id FROM events e ASOF JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY 1, 2) l
    ON e.user_id = l.user_id AND e.ts >= l.ts WHERE e.event_type = 'purchase'""",
)
def j11(spark, d):
    """The last view of the user before each purchase: one sort of the union, no join."""
    e = load(spark, d, "events")
    p = e.where("event_type = 'purchase'").select("user_id", "ts", "event_id", F.lit(None).cast("bigint").alias("seen"), F.lit(1).alias("side"))
    i = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("seen")).select("user_id", "ts", F.lit(None).cast("bigint").alias("event_id"), "seen", F.lit(0).alias("side"))
    w = Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return p.unionByName(i).withColumn("view_id", F.last("seen", ignorenulls=True).over(w)).where("side = 1 AND view_id IS NOT NULL").select("event_id", "view_id")


@BOOK.add(
    "j15_salted_join",
    "SELECT l_returnflag, o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
)
def j15(spark, d):
    """A skewed key is dealt over eight salts on one side and copied to all eight on the other."""
    lines = load(spark, d, "lineitem").select("l_orderkey", "l_returnflag", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(8)).alias("salt"))
    orders = load(spark, d, "orders").select("o_orderkey", "o_orderpriority", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(7).cast("bigint"))).alias("salt"))
    j = lines.join(orders, (F.col("l_orderkey") == F.col("o_orderkey")) & (lines["salt"] == orders["salt"]))
    return j.groupBy("l_returnflag", "o_orderpriority").agg(F.count("*").alias("n"))


# --- aggregations -------------------------------------------------------------------


@BOOK.add(
    "g01_pricing_summary",
    """SELECT l_returnflag, l_linestatus, sum(l_quantity) AS sum_qty, round(sum(l_extendedprice), 2) AS sum_base, round(sum(l_extendedprice * (1 - l_discount)), 2) AS sum_disc,
    round(avg(l_quantity), 6) AS avg_qty, round(avg(l_discount), 6) AS avg_disc, count(*) AS n FROM lineitem GROUP BY 1, 2""",
)
def g01(spark, d):
    x = load(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus")
    return x.agg(
        F.sum("l_quantity").alias("sum_qty"),
        F.round(F.sum("l_extendedprice"), 2).alias("sum_base"),
        F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("sum_disc"),
        F.round(F.avg("l_quantity"), 6).alias("avg_qty"),
        F.round(F.avg("l_discount"), 6).alias("avg_disc"),
        F.count("*").alias("n"),
    )


@BOOK.add(
    "g01_statistics",
    """SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_discount), 8) AS vp, round(corr(l_quantity, l_extendedprice), 6) AS cor,
    round(covar_samp(l_quantity, l_tax), 6) AS cov, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem GROUP BY 1""",
)
def g01b(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.round(F.stddev_samp("l_quantity"), 6).alias("sd"),
        F.round(F.var_pop("l_discount"), 8).alias("vp"),
        F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("cor"),
        F.round(F.covar_samp("l_quantity", "l_tax"), 6).alias("cov"),
        F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"),
    )


@BOOK.add("g02_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT date_trunc('day', ts)) AS days FROM events GROUP BY 1")
def g02(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.countDistinct(F.date_trunc("day", "ts")).alias("days"))


@BOOK.add("g02_sketches")
def g02b(spark, d):
    e = load(spark, d, "events").groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s"), F.approx_count_distinct("user_id").alias("approx_users"))
    return e.select("event_type", "approx_users", F.hll_sketch_estimate("s").alias("hll_users"))


@BOOK.add("g02_theta_sketches")
def g02c(spark, d):
    e = load(spark, d, "events").groupBy("event_type").agg(F.theta_sketch_agg("user_id").alias("s"))
    return e.select("event_type", F.theta_sketch_estimate("s").alias("users"))


@BOOK.add("g03_quantile_sketches")
def g03b(spark, d):
    e = load(spark, d, "events").groupBy("event_type").agg(F.kll_sketch_agg_double("value").alias("s"))
    return e.select("event_type", F.kll_sketch_get_quantile_double("s", F.lit(0.5)).alias("p50"), F.kll_sketch_get_quantile_double("s", F.lit(0.99)).alias("p99"))


@BOOK.add("p06_bernoulli_sample")
def p06c(spark, d):
    """The sampling operator: each row falls in or out by itself, with a seed."""
    return load(spark, d, "lineitem").sample(withReplacement=False, fraction=0.05, seed=11).select("l_orderkey", "l_linenumber")


@BOOK.add("g03_percentiles", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.99), 6) AS p99 FROM events GROUP BY 1")
def g03(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("p50"), F.round(F.percentile("value", 0.99), 6).alias("p99"))


@BOOK.add(
    "g04_rollup",
    """SELECT r_name, n_name, count(*) AS customers, CAST(grouping(r_name) * 2 + grouping(n_name) AS BIGINT) AS level FROM customer JOIN nation ON c_nationkey = n_nationkey
    JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)""",
)
def g04(spark, d):
    c = load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 rows
    c = c.join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 5 rows
    return c.rollup("r_name", "n_name").agg(F.count("*").alias("customers"), F.grouping_id().alias("level"))


@BOOK.add("g04_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def g04b(spark, d):
    return load(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@BOOK.add("g04_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def g04c(spark, d):
    register_all(spark, d)
    return spark.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@BOOK.add(
    "g05_pivot",
    "SELECT user_id, " + ", ".join(f"CAST(count(*) FILTER (WHERE event_type = '{t}') AS BIGINT) AS {t}" for t in ("click", "error", "purchase", "signup", "view")) + " FROM events GROUP BY user_id",
)
def g05(spark, d):
    types = ["click", "error", "purchase", "signup", "view"]
    x = load(spark, d, "events").groupBy("user_id").pivot("event_type", types).agg(F.count("event_id"))
    return x.select("user_id", *[F.coalesce(t, F.lit(0)).alias(t) for t in types])


@BOOK.add("g05_unpivot", "SELECT c_custkey, 'bal' AS field, c_acctbal AS v FROM customer UNION ALL SELECT c_custkey, 'nation', CAST(c_nationkey AS DOUBLE) FROM customer")
def g05b(spark, d):
    c = load(spark, d, "customer").select("c_custkey", F.col("c_acctbal").alias("bal"), F.col("c_nationkey").cast("double").alias("nation"))
    return c.unpivot("c_custkey", ["bal", "nation"], "field", "v")


@BOOK.add("g06_extremes", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY 1")
def g06(spark, d):
    key = F.struct("o_totalprice", "o_orderkey")
    return load(spark, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", key).alias("dearest"), F.min_by("o_orderkey", key).alias("cheapest"))


@BOOK.add("g08_centroids", "SELECT label, CAST(i - 1 AS INTEGER) AS pos, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS mean FROM embeddings, (SELECT unnest(range(1, 65)) AS i) GROUP BY 1, 2")
def g08(spark, d):
    return load(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("pos", "v")).groupBy("label", "pos").agg(F.round(F.avg(F.col("v").cast("double")), 6).alias("mean"))


@BOOK.add("g09_histogram", "SELECT CAST(least(10, greatest(0, floor(l_quantity / 5))) AS BIGINT) AS bucket, count(*) AS n FROM lineitem GROUP BY 1")
def g09(spark, d):
    return load(spark, d, "lineitem").groupBy(F.least(F.lit(10), F.greatest(F.lit(0), F.floor(F.col("l_quantity") / 5))).cast("bigint").alias("bucket")).agg(F.count("*").alias("n"))


@BOOK.add(
    "g10_flags",
    "SELECT o_custkey, bool_or(o_orderstatus = 'F') AS any_f, bool_and(o_totalprice > 1000) AS all_big, CAST(count(*) FILTER (WHERE o_orderpriority = '1-URGENT') AS BIGINT) AS urgent FROM orders GROUP BY 1",
)
def g10(spark, d):
    return load(spark, d, "orders").groupBy("o_custkey").agg(
        F.bool_or(F.col("o_orderstatus") == "F").alias("any_f"), F.bool_and(F.col("o_totalprice") > 1000).alias("all_big"), F.count_if(F.col("o_orderpriority") == "1-URGENT").alias("urgent")
    )


@BOOK.add("g11_listagg", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def g11(spark, d):
    register_all(spark, d)
    return spark.sql("SELECT n_regionkey, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")


# --- windows, sorts, sets -----------------------------------------------------------


@BOOK.add(
    "n01_ranks",
    """SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd
    FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)""",
)
def n01(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return load(spark, d, "orders").select(
        "o_orderkey",
        F.row_number().over(w).cast("bigint").alias("rn"),
        F.rank().over(w).cast("bigint").alias("rk"),
        F.dense_rank().over(w).cast("bigint").alias("dr"),
        F.ntile(4).over(w).cast("bigint").alias("quarter"),
        F.round(F.percent_rank().over(w), 9).alias("pr"),
        F.round(F.cume_dist().over(w), 9).alias("cd"),
    )


@BOOK.add(
    "n02_offsets",
    """SELECT event_id, lag(event_id, 1, -1) OVER w AS prev, lead(event_id, 1, -1) OVER w AS next, first_value(event_id) OVER w AS first, coalesce(nth_value(event_id, 2) OVER
    (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), -1) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""",
)
def n02(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, d, "events").select(
        "event_id",
        F.lag("event_id", 1, -1).over(w).alias("prev"),
        F.lead("event_id", 1, -1).over(w).alias("next"),
        F.first("event_id").over(w).alias("first"),
        F.coalesce(F.nth_value("event_id", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)), F.lit(-1)).alias("second"),
    )


@BOOK.add(
    "n03_frames",
    """SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS rolling,
    CAST(count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS BIGINT) AS last_hour FROM events""",
)
def n03(spark, d):
    by = Window.partitionBy("user_id")
    return load(spark, d, "events").select(
        "event_id",
        F.round(F.avg("value").over(by.orderBy("ts", "event_id").rowsBetween(-4, 0)), 6).alias("rolling"),
        F.count("*").over(by.orderBy(_micros()).rangeBetween(-3_600_000_000, 0)).alias("last_hour"),
    )


@BOOK.add("n04_top_per_group", "SELECT * FROM (SELECT o_custkey, o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS BIGINT) AS place FROM orders) WHERE place <= 3")
def n04(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return load(spark, d, "orders").select("o_custkey", "o_orderkey", F.row_number().over(w).cast("bigint").alias("place")).where("place <= 3")


@BOOK.add("n05_take_ordered", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
def n05(spark, d):
    """The top-k report."""
    return load(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100)


@BOOK.add(
    "n06_sets",
    """SELECT 'both' AS part, k FROM (SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL
    SELECT 'customers only', k FROM (SELECT c_nationkey AS k FROM customer EXCEPT SELECT s_nationkey FROM supplier) UNION ALL
    SELECT 'all', k FROM (SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier)""",
)
def n06(spark, d):
    c, s = load(spark, d, "customer").select(F.col("c_nationkey").alias("k")), load(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))
    named = lambda n, x: x.select(F.lit(n).alias("part"), "k")
    return named("both", c.intersect(s)).union(named("customers only", c.subtract(s))).union(named("all", c.union(s).distinct()))


# --- scalar functions ---------------------------------------------------------------


@BOOK.add(
    "f02_math",
    "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS s, round(ln(p_retailprice), 6) AS l, round(log10(p_retailprice), 6) AS g, round(pow(p_size, 2), 2) AS sq, p_size % 7 AS m, round(acos(least(1, p_size / 100.0)), 6) AS a, bit_count(p_partkey) AS bits FROM part",
)
def f02(spark, d):
    return load(spark, d, "part").select(
        "p_partkey",
        F.round(F.sqrt("p_retailprice"), 6).alias("s"),
        F.round(F.ln("p_retailprice"), 6).alias("l"),
        F.round(F.log10("p_retailprice"), 6).alias("g"),
        F.round(F.pow("p_size", F.lit(2)), 2).alias("sq"),
        F.pmod("p_size", F.lit(7)).alias("m"),
        F.round(F.acos(F.least(F.lit(1.0), F.col("p_size") / 100)), 6).alias("a"),
        F.bit_count("p_partkey").cast("tinyint").alias("bits"),
    )


@BOOK.add(
    "f03_arrays",
    """SELECT vec_id, len(list_filter(embedding, lambda v: v > 0)) AS positive, round(list_sum(list_transform(embedding[1:8], lambda v: abs(CAST(v AS DOUBLE)))), 6) AS head,
    len(list_filter(embedding, lambda v: v > 0.3)) > 0 AS some_large FROM embeddings""",
)
def f03(spark, d):
    return load(spark, d, "embeddings").select(
        "vec_id",
        F.size(F.filter("embedding", lambda v: v > 0)).cast("bigint").alias("positive"),
        F.round(F.aggregate(F.transform(F.slice("embedding", 1, 8), lambda v: F.abs(v.cast("double"))), F.lit(0.0), lambda s, v: s + v), 6).alias("head"),
        F.exists("embedding", lambda v: v > F.lit(0.3).cast("float")).alias("some_large"),
    )


@BOOK.add("f04_maps", "SELECT user_id, e.key AS event_type, CAST(e.value AS BIGINT) AS n FROM (SELECT user_id, unnest(map_entries(histogram(event_type))) AS e FROM events GROUP BY user_id)")
def f04(spark, d):
    counts = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.explode("m").alias("event_type", "n"))


@BOOK.add(
    "f06_strings",
    "SELECT c_custkey, lower(c_name) AS low, substr(c_name, 1, 4) AS head, regexp_extract(c_name, '([0-9]+)', 1) AS digits, concat_ws('-', c_mktsegment, CAST(c_nationkey AS VARCHAR)) AS tag, levenshtein(c_mktsegment, 'BUILDING') AS away, md5(c_name) AS h FROM customer",
)
def f06(spark, d):
    return load(spark, d, "customer").select(
        "c_custkey",
        F.lower("c_name").alias("low"),
        F.substring("c_name", 1, 4).alias("head"),
        F.regexp_extract("c_name", "([0-9]+)", 1).alias("digits"),
        F.concat_ws("-", "c_mktsegment", F.col("c_nationkey").cast("string")).alias("tag"),
        F.levenshtein("c_mktsegment", F.lit("BUILDING")).cast("bigint").alias("away"),
        F.md5(F.col("c_name").cast("binary")).alias("h"),
    )


@BOOK.add("f07_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def f07(spark, d):
    return load(spark, d, "events").select("event_id", F.from_json("props", "k bigint").getField("k").alias("k"))


@BOOK.add("f07_variant", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def f07b(spark, d):
    return load(spark, d, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@BOOK.add("f08_dates", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS dow, strftime(o_orderdate + INTERVAL 90 DAY, '%Y-%m-%d') AS due FROM orders")
def f08(spark, d):
    day = F.col("o_orderdate")
    return load(spark, d, "orders").select(
        "o_orderkey", F.year(day).alias("y"), F.date_format(F.date_trunc("month", day), "yyyy-MM-dd").alias("month"), F.dayofweek(day).alias("dow"), F.date_format(day + F.expr("INTERVAL 90 DAY"), "yyyy-MM-dd").alias("due")
    )


@BOOK.add("f09_urls", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, CAST(length(regexp_replace(html, '<[^>]*>', '', 'g')) AS BIGINT) AS text_chars FROM pages")
def f09(spark, d):
    return load(spark, d, "pages").select("page_id", F.expr("parse_url(url, 'HOST')").alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("bigint").alias("text_chars"))


# --- reports ------------------------------------------------------------------------


@BOOK.add("r07_top_customers", "SELECT c_custkey, c_name, round(sum(o_totalprice), 2) AS spent FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY 1, 2 ORDER BY spent DESC, c_custkey LIMIT 20")
def r07(spark, d):
    j = load(spark, d, "customer").join(load(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"))
    return j.groupBy("c_custkey", "c_name").agg(F.round(F.sum("o_totalprice"), 2).alias("spent")).orderBy(F.desc("spent"), "c_custkey").limit(20)


@BOOK.add("r07_priorities", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 40) GROUP BY 1")
def r07b(spark, d):
    big = load(spark, d, "lineitem").where("l_quantity > 40")
    return load(spark, d, "orders").join(big, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").groupBy("o_orderpriority").agg(F.count("*").alias("n"))
