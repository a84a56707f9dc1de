"""Relational, string, time, array and SQL-function queries around the vector engine.

Each is one declarative plan over the tables, beside the SQL that checks it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subvote.functions import udfs
from subvote.operators import exact
from subvote.session import scratch
from subvote.sources import vectors as sources
from subvote.sources.tables import load, read_any, register, save_bucketed, write_any

_LISTED: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    """Register a query and its SQL form."""

    def add(f: Callable) -> Callable:
        _LISTED[f.__name__] = f
        if sql:
            _SQL[f.__name__] = sql
        return f

    return add


@query("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01' AND l_discount BETWEEN 0.05 AND 0.07 AND l_quantity < 24")
def q_filter_lineitem(spark, sf_dir):
    df = load(spark, sf_dir, "lineitem")
    keep = (F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp")) & (F.col("l_shipdate") < F.lit("1996-01-01").cast("timestamp"))
    return df.filter(keep & F.col("l_discount").between(0.05, 0.07) & (F.col("l_quantity") < 24)).select("l_orderkey", "l_linenumber", "l_quantity")


@query("SELECT p_partkey, p_name, p_brand IN ('Brand#11', 'Brand#12') AS listed, p_type IS NULL AS untyped FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_name, '[a-z] [a-z]') AND p_size IS NOT DISTINCT FROM p_size")
def q_like_part(spark, sf_dir):
    df = load(spark, sf_dir, "part")
    keep = F.col("p_name").like("%a%") & F.col("p_name").rlike("[a-z] [a-z]") & F.col("p_size").eqNullSafe(F.col("p_size"))
    return df.filter(keep).select("p_partkey", "p_name", F.col("p_brand").isin("Brand#11", "Brand#12").alias("listed"), F.col("p_type").isNull().alias("untyped"))


@query("SELECT o_orderkey, CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 'high' WHEN o_orderpriority = '3-MEDIUM' THEN 'medium' ELSE 'low' END AS band, coalesce(nullif(o_orderstatus, 'O'), 'open') AS state, greatest(o_totalprice, 1000) AS floor_price, least(o_totalprice, 1000) AS cap_price FROM orders")
def q_case_priority(spark, sf_dir):
    band = F.when(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH"), "high").when(F.col("o_orderpriority") == "3-MEDIUM", "medium").otherwise("low")
    price = F.col("o_totalprice")
    return load(spark, sf_dir, "orders").select("o_orderkey", band.alias("band"), F.coalesce(F.nullif("o_orderstatus", F.lit("O")), F.lit("open")).alias("state"), F.greatest(price, F.lit(1000.0)).alias("floor_price"), F.least(price, F.lit(1000.0)).alias("cap_price"))


@query("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def q_join_broadcast(spark, sf_dir):
    n, r = load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")  # two fixed small tables
    return n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select("n_name", "r_name")


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def q_join_smj(spark, sf_dir):
    o, li = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem")
    return o.hint("merge").join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("SELECT l_orderkey, l_linenumber, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size < 5")
def q_join_shj(spark, sf_dir):
    li, p = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "part").filter("p_size < 5")
    return li.join(p.hint("shuffle_hash"), li.l_partkey == p.p_partkey).select("l_orderkey", "l_linenumber", "p_brand")


@query("SELECT c_custkey, count(o_orderkey) AS orders, o_custkey IS NULL AS none FROM customer FULL JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey, o_custkey IS NULL")
def q_join_outer(spark, sf_dir):
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders")
    out = c.join(o, c.c_custkey == o.o_custkey, "full_outer").withColumn("none", F.col("o_custkey").isNull())
    return out.groupBy("c_custkey", "none").agg(F.count("o_orderkey").alias("orders"))


@query("SELECT 'with' AS kind, count(*) AS n FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) UNION ALL SELECT 'without', count(*) FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def q_semi_anti(spark, sf_dir):
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"))
    count = lambda how, kind: c.join(o, "c_custkey", how).agg(F.count("*").alias("n")).select(F.lit(kind).alias("kind"), "n")
    return count("left_semi", "with").unionByName(count("left_anti", "without"))


@query("SELECT event_id, floor(value / 10) AS band FROM events, range(1000) b WHERE value >= b.range * 10 AND value < (b.range + 1) * 10")
def q_range_join(spark, sf_dir):
    """Bands of width 10, met by bin and not by a nested loop."""
    events = load(spark, sf_dir, "events").withColumn("bin", F.floor(F.col("value") / 10))
    bands = spark.range(1000).select(F.col("id").alias("bin"), (F.col("id") * 10).alias("lo"), ((F.col("id") + 1) * 10).alias("hi"))
    met = events.join(bands, "bin").filter((F.col("value") >= F.col("lo")) & (F.col("value") < F.col("hi")))
    return met.select("event_id", F.col("bin").cast("double").alias("band"))


@query("WITH s AS (SELECT user_id, min(ts) AS t FROM events WHERE event_type = 'purchase' GROUP BY user_id) SELECT e.event_id, s.user_id FROM events e JOIN s ON e.user_id = s.user_id AND e.ts >= s.t AND e.ts <= s.t + INTERVAL 1 HOUR")
def q_interval_join(spark, sf_dir):
    events = load(spark, sf_dir, "events")
    first = events.filter("event_type = 'purchase'").groupBy("user_id").agg(F.min("ts").alias("t"))
    return events.join(first, "user_id").filter((F.col("ts") >= F.col("t")) & (F.col("ts") <= F.col("t") + F.expr("INTERVAL 1 HOUR"))).select("event_id", "user_id")


@query("""SELECT p.event_id, coalesce((SELECT max_by(v.event_id, (v.ts, v.event_id)) FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts), -1) AS view_id
FROM events p WHERE p.event_type = 'purchase'""")
def q_asof_join(spark, sf_dir):
    """Last view at or before each purchase: one sorted pass per user, no pairs."""
    events = load(spark, sf_dir, "events").filter("event_type IN ('view', 'purchase')")
    is_view = F.col("event_type") == "view"
    order = Window.partitionBy("user_id").orderBy("ts", F.when(is_view, 0).otherwise(1), "event_id")
    last = F.last(F.when(is_view, F.col("event_id")), ignorenulls=True).over(order)
    return events.withColumn("view_id", last).filter(~is_view).select("event_id", F.coalesce("view_id", F.lit(-1).cast("long")).alias("view_id"))


@query("SELECT c_custkey, o_orderkey, o_totalprice FROM (SELECT c_custkey, o_orderkey, o_totalprice, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM customer JOIN orders ON c_custkey = o_custkey) WHERE r <= 2")
def q_lateral_topk(spark, sf_dir):
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders")
    order = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    top = o.withColumn("r", F.row_number().over(order)).filter("r <= 2")
    return c.join(top, c.c_custkey == top.o_custkey).select("c_custkey", "o_orderkey", "o_totalprice")


@query("SELECT event_type, count(*) AS n, round(sum(value), 4) AS total FROM events e JOIN (SELECT user_id FROM events GROUP BY user_id) u ON e.user_id = u.user_id GROUP BY event_type")
def q_salted_join(spark, sf_dir):
    """A join whose key may be hot: rows are salted, the small side is repeated per salt."""
    salts = 8
    events = load(spark, sf_dir, "events").withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(salts)))
    users = events.select("user_id").distinct().withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return events.join(users, ["user_id", "salt"]).groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("""SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS avg_disc, count(*) AS n,
  min(l_quantity) AS min_qty, max(l_quantity) AS max_qty, round(stddev_samp(l_quantity), 6) AS sd_qty, round(var_pop(l_quantity), 6) AS var_qty FROM lineitem GROUP BY l_returnflag, l_linestatus""")
def q_pricing_summary(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.round(F.sum("l_quantity"), 2).alias("sum_qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"),
        F.round(F.avg("l_discount"), 6).alias("avg_disc"), F.count("*").alias("n"), F.min("l_quantity").alias("min_qty"), F.max("l_quantity").alias("max_qty"),
        F.round(F.stddev_samp("l_quantity"), 6).alias("sd_qty"), F.round(F.var_pop("l_quantity"), 6).alias("var_qty"),
    )


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def q_distinct_users(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query()
def q_approx_users(spark, sf_dir):
    """Approximate counts beside the exact one: HyperLogLog and a mergeable sketch."""
    events = load(spark, sf_dir, "events")
    return events.groupBy("event_type").agg(
        F.count_distinct("user_id").alias("exact"), F.approx_count_distinct("user_id", 0.02).alias("hll"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("sketch")
    )


@query("SELECT lang, source, count(*) AS n, grouping_id(lang, source)::BIGINT AS level FROM documents GROUP BY ROLLUP (lang, source)")
def q_rollup_docs(spark, sf_dir):
    return load(spark, sf_dir, "documents").rollup("lang", "source").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query("SELECT event_type, coalesce(h, -1) AS h, n FROM (SELECT event_type, hour(ts) AS h, count(*) AS n FROM events GROUP BY CUBE (event_type, hour(ts)))")
def q_cube_events(spark, sf_dir):
    return load(spark, sf_dir, "events").withColumn("h", F.hour("ts").cast("long")).cube("event_type", "h").agg(F.count("*").alias("n")).withColumn("h", F.coalesce("h", F.lit(-1).cast("long")))


@query("SELECT o_orderstatus, o_orderpriority, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def q_grouping_sets(spark, sf_dir):
    load(spark, sf_dir, "orders").createOrReplaceTempView("sets_orders")
    return spark.sql("SELECT o_orderstatus, o_orderpriority, round(sum(o_totalprice), 2) AS total FROM sets_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@query("SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY user_id")
def q_pivot_events(spark, sf_dir):
    wide = load(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "purchase"]).count()
    return wide.na.fill(0, ["click", "purchase"])


@query("SELECT s_suppkey, unnest(['s_acctbal', 's_nationkey']) AS field, unnest([round(s_acctbal, 2), s_nationkey::DOUBLE]) AS value FROM supplier")
def q_unpivot_supplier(spark, sf_dir):
    df = load(spark, sf_dir, "supplier").select("s_suppkey", F.round("s_acctbal", 2).alias("s_acctbal"), F.col("s_nationkey").cast("double").alias("s_nationkey"))
    return df.unpivot(["s_suppkey"], ["s_acctbal", "s_nationkey"], "field", "value")


@query("SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY o_custkey")
def q_arg_extremes(spark, sf_dir):
    key = F.struct("o_totalprice", "o_orderkey")
    return load(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", key).alias("dearest"), F.min_by("o_orderkey", key).alias("cheapest"))


@query("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.99), 6) AS p99, round(median(value), 6) AS med FROM events GROUP BY event_type")
def q_percentiles(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").agg(*[F.round(F.percentile("value", p), 6).alias(n) for p, n in ((0.5, "p50"), (0.99, "p99"))], F.round(F.median("value"), 6).alias("med"))


@query()
def q_quantile_sketches(spark, sf_dir):
    """Exact quantiles beside an approximate one and a mergeable sketch."""
    exact_ = F.percentile("value", 0.9).alias("exact")
    sketch = F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.9D)").alias("sketch")
    return load(spark, sf_dir, "events").groupBy("event_type").agg(exact_, F.percentile_approx("value", 0.9, 1000).alias("approx"), sketch)


@query("SELECT event_type, floor(value / 50) AS bucket, count(*) AS n FROM events GROUP BY ALL")
def q_histogram(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type", F.floor(F.col("value") / 50).cast("double").alias("bucket")).agg(F.count("*").alias("n"))


@query("SELECT round(corr(embedding[1]::DOUBLE, embedding[2]::DOUBLE), 6) AS c, round(covar_samp(embedding[1]::DOUBLE, embedding[2]::DOUBLE), 9) AS v, round(regr_slope(embedding[2]::DOUBLE, embedding[1]::DOUBLE), 6) AS slope FROM embeddings")
def q_corr_dims(spark, sf_dir):
    x, y = (F.element_at("embedding", j).cast("double") for j in (1, 2))
    return load(spark, sf_dir, "embeddings").agg(F.round(F.corr(x, y), 6).alias("c"), F.round(F.covar_samp(x, y), 9).alias("v"), F.round(F.regr_slope(y, x), 6).alias("slope"))


@query("SELECT l_returnflag, count(*) FILTER (l_discount > 0.05) AS discounted, sum(CASE WHEN l_tax > 0.04 THEN 1 ELSE 0 END)::BIGINT AS taxed FROM lineitem GROUP BY l_returnflag")
def q_conditional_agg(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_discount") > 0.05).alias("discounted"), F.sum(F.when(F.col("l_tax") > 0.04, 1).otherwise(0)).alias("taxed"))


@query("SELECT label, bit_or(1::BIGINT << (vec_id % 60)) AS held, bit_xor(vec_id) AS folded, count(DISTINCT vec_id) AS ids FROM embeddings GROUP BY label")
def q_bit_aggs(spark, sf_dir):
    """A bitmap holds the positions of one bucket of ids only, so buckets are counted apart and added up."""
    rows = load(spark, sf_dir, "embeddings").withColumn("bucket", F.bitmap_bucket_number("vec_id"))
    parts = rows.groupBy("label", "bucket").agg(
        F.bit_or(F.expr("shiftleft(CAST(1 AS BIGINT), CAST(vec_id % 60 AS INT))")).alias("held"), F.bit_xor("vec_id").alias("folded"), F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position("vec_id"))).alias("ids")
    )
    return parts.groupBy("label").agg(F.bit_or("held").alias("held"), F.bit_xor("folded").alias("folded"), F.sum("ids").alias("ids"))


@query("SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12 UNION ALL SELECT -1, (SELECT count(*) FROM orders WHERE o_orderkey < 0)")
def q_having(spark, sf_dir):
    o = load(spark, sf_dir, "orders")
    empty = o.filter("o_orderkey < 0").agg(F.count("*").alias("n")).select(F.lit(-1).cast("long").alias("o_custkey"), "n")
    return o.groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n > 12").unionByName(empty)


@query("""SELECT s_suppkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd
FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)""")
def q_rank_functions(spark, sf_dir):
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")
    return load(spark, sf_dir, "supplier").select("s_suppkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("""SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first, nth_value(value, 2) OVER w AS second
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def q_lag_lead(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf_dir, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.first("value").over(w).alias("first"), F.nth_value("value", 2).over(w).alias("second"))


@query("""SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last3,
  count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS day, count(*) OVER (PARTITION BY event_type ORDER BY value RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS near FROM events""")
def q_sliding_window(spark, sf_dir):
    by_user = Window.partitionBy("user_id")
    events = load(spark, sf_dir, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    day = by_user.orderBy("s").rangeBetween(-86_400_000_000, 0)
    near = Window.partitionBy("event_type").orderBy("value").rangeBetween(-5, 5)
    rows = by_user.orderBy("ts", "event_id").rowsBetween(-2, 0)
    return events.select("event_id", F.round(F.sum("value").over(rows), 4).alias("last3"), F.count("*").over(day).alias("day"), F.count("*").over(near).alias("near"))


@query("""WITH m AS (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER w > INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
n AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM m)
SELECT user_id, s::BIGINT AS session, count(*) AS n FROM n GROUP BY user_id, s""")
def q_sessions_batch(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp"))
    marked = load(spark, sf_dir, "events").withColumn("cut", F.when(gap.isNull() | (gap > 1_800_000_000), 1).otherwise(0))
    return marked.withColumn("session", F.sum("cut").over(w)).groupBy("user_id", "session").agg(F.count("*").alias("n"))


@query("SELECT label, vec_id FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY vec_id DESC) AS r FROM embeddings) WHERE r <= 3")
def q_topk_per_label(spark, sf_dir):
    w = Window.partitionBy("label").orderBy(F.desc("vec_id"))
    return load(spark, sf_dir, "embeddings").select("label", "vec_id").withColumn("r", F.row_number().over(w)).filter("r <= 3").drop("r")


@query("SELECT c_custkey, c_nationkey, row_number() OVER (ORDER BY CASE WHEN c_nationkey > 20 THEN NULL ELSE c_nationkey END DESC NULLS LAST, c_custkey) AS place FROM customer")
def q_sort_nulls(spark, sf_dir):
    """Global order: ranks inside ranges of keys and the offset of every range.

    The ranges are a function of the row (nation, then customers about 100,000 keys at a time),
    so the plan may be evaluated anew for the offsets.
    """
    df = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey").withColumn("k", F.when(F.col("c_nationkey") <= 20, F.col("c_nationkey")))
    size = df.agg(F.count("*").alias("n"), F.min("c_custkey").alias("lo"), F.max("c_custkey").alias("hi")).first()
    width = max(1, ((size["hi"] or 0) - (size["lo"] or 0)) // max(1, size["n"] // 100_000))
    ranges = [F.col("k").desc_nulls_last(), F.col("part").asc_nulls_last()]
    dealt = df.withColumn("part", F.expr(f"c_custkey div {min(width, (1 << 63) - 1)}L"))
    inside = dealt.withColumn("r", F.row_number().over(Window.partitionBy("k", "part").orderBy(F.col("c_custkey").asc_nulls_last())))
    sizes = dealt.groupBy("k", "part").agg(F.count("*").alias("n"))
    starts = sizes.select(F.col("k").alias("_k"), F.col("part").alias("_part"), F.coalesce(F.sum("n").over(Window.orderBy(*ranges).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    placed = inside.join(F.broadcast(starts), F.col("k").eqNullSafe(F.col("_k")) & F.col("part").eqNullSafe(F.col("_part")))
    return placed.select("c_custkey", "c_nationkey", (F.col("start") + F.col("r")).cast("long").alias("place"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25 OFFSET 5")
def q_topk_global(spark, sf_dir):
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(25)


@query("SELECT 'base' AS part, count(*) AS n, sum(vec_id)::BIGINT AS total FROM embeddings WHERE vec_id % 10 <> 0 UNION ALL SELECT 'query', count(*), sum(vec_id)::BIGINT FROM embeddings WHERE vec_id % 10 = 0")
def q_union_shards(spark, sf_dir):
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    sums = lambda df, name: df.agg(F.count("*").alias("n"), F.sum("id").alias("total")).withColumn("part", F.lit(name))
    return sums(base, "base").unionByName(sums(queries, "query"), allowMissingColumns=True)


@query("SELECT DISTINCT l_suppkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT DISTINCT l_suppkey FROM lineitem WHERE l_returnflag = 'A'")
def q_intersect_hits(spark, sf_dir):
    li = load(spark, sf_dir, "lineitem").select("l_suppkey", "l_returnflag")
    return li.filter("l_returnflag = 'R'").select("l_suppkey").intersect(li.filter("l_returnflag = 'A'").select("l_suppkey"))


@query("SELECT p_partkey FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 48")
def q_except_misses(spark, sf_dir):
    return load(spark, sf_dir, "part").select("p_partkey").exceptAll(load(spark, sf_dir, "lineitem").filter("l_quantity > 48").select(F.col("l_partkey").alias("p_partkey")).distinct())


@query("SELECT min(doc_id) AS doc_id, md5(text) AS digest, count(*) AS copies FROM documents GROUP BY md5(text)")
def q_dedup_docs(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select("doc_id", F.md5(F.encode("text", "utf-8")).alias("digest"))
    return docs.groupBy("digest").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"))


@query("SELECT doc_id, len(list_filter(regexp_split_to_array(lower(trim(text)), '\\s+'), lambda t: t <> ''))::BIGINT AS tokens, md5(lower(text)) AS digest, substr(text, 1, 5) AS head, length(replace(text, 'e', '')) AS without_e FROM documents")
def q_tokens(spark, sf_dir):
    text = F.col("text")
    tokens = F.size(F.filter(F.split(F.lower(F.trim(text)), "\\s+"), lambda t: t != "")).cast("long")
    return load(spark, sf_dir, "documents").select("doc_id", tokens.alias("tokens"), F.md5(F.encode(F.lower(text), "utf-8")).alias("digest"), F.substring(text, 1, 5).alias("head"), F.length(F.replace(text, F.lit("e"), F.lit(""))).alias("without_e"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/]+(/[^?#]*)', 1) AS path, length(regexp_replace(html, '<[^>]*>', ' ', 'g')) AS bare FROM pages")
def q_url_parts(spark, sf_dir):
    return load(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.regexp_extract("url", "^[a-z]+://[^/]+(/[^?#]*)", 1).alias("path"), F.length(F.regexp_replace("html", "<[^>]*>", " ")).alias("bare"))


@query("""SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, month(o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month_start, isodow(o_orderdate) AS dow,
  date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS days, strftime(o_orderdate + INTERVAL 2 MONTH, '%Y-%m-%d') AS later FROM orders""")
def q_dates(spark, sf_dir):
    d = F.col("o_orderdate")
    return load(spark, sf_dir, "orders").select(
        "o_orderkey", *[f(d).cast("long").alias(n) for f, n in ((F.year, "y"), (F.quarter, "q"), (F.month, "m"))], F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month_start"),
        (F.weekday(d) + 1).cast("long").alias("dow"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"), F.date_format(F.add_months(d.cast("date"), 2), "yyyy-MM-dd").alias("later"),
    )


@query("SELECT p_partkey, round(sqrt(p_retailprice), 6) AS root, round(ln(p_retailprice), 6) AS log, floor(p_retailprice / 100) AS hundreds, p_size % 7 AS r, sign(p_size - 25)::DOUBLE AS side, round(sin(p_size), 6) AS wave FROM part")
def q_math(spark, sf_dir):
    p = F.col("p_retailprice")
    return load(spark, sf_dir, "part").select("p_partkey", F.round(F.sqrt(p), 6).alias("root"), F.round(F.log(p), 6).alias("log"), F.floor(p / 100).cast("double").alias("hundreds"), F.pmod("p_size", F.lit(7)).alias("r"), F.signum(F.col("p_size") - 25).alias("side"), F.round(F.sin("p_size"), 6).alias("wave"))


@query("""SELECT vec_id, round(list_max(embedding)::DOUBLE, 6) AS top, list_position(embedding, list_max(embedding)) AS at, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_sum(embedding[1:4])::DOUBLE, 5) AS head, round(list_sort(embedding)[1]::DOUBLE, 6) AS low FROM embeddings""")
def q_array_functions(spark, sf_dir):
    e = F.col("embedding")
    head = F.aggregate(F.slice(e, 1, 4), F.lit(0.0), lambda a, x: a + x)
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(F.array_max(e).cast("double"), 6).alias("top"), F.array_position(e, F.array_max(e)).alias("at"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.round(head, 5).alias("head"), F.round(F.element_at(F.array_sort(e), 1).cast("double"), 6).alias("low"))


@query("SELECT user_id, event_type, round(2 * sum(value), 4) AS doubled FROM events GROUP BY user_id, event_type HAVING sum(value) > 100")
def q_map_functions(spark, sf_dir):
    sums = load(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.sum("value").alias("v"))
    maps = sums.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "v"))).alias("m"))
    kept = F.transform_values(F.map_filter("m", lambda k, v: v > 100), lambda k, v: F.round(v * 2, 4))
    return maps.select("user_id", F.explode(kept).alias("event_type", "doubled"))


@query("SELECT event_id, len(json_keys(props)) AS keys, props AS again FROM events")
def q_json_props(spark, sf_dir):
    return load(spark, sf_dir, "events").select("event_id", F.json_object_keys("props").alias("k"), F.col("props").alias("again")).select("event_id", F.size("k").cast("long").alias("keys"), "again")


@query("SELECT n_nationkey, unnest(['name', 'region']) AS field, unnest([n_name, n_regionkey::VARCHAR]) AS value FROM nation")
def q_struct_inline(spark, sf_dir):
    pair = lambda name, c: F.struct(F.lit(name).alias("field"), c.cast("string").alias("value"))
    return load(spark, sf_dir, "nation").select("n_nationkey", F.inline(F.array(pair("name", F.col("n_name")), pair("region", F.col("n_regionkey")))))


@query("SELECT l_returnflag, sum(l_extendedprice::DECIMAL(18,2))::VARCHAR AS total, sum((l_extendedprice::DECIMAL(18,2) * l_quantity::DECIMAL(4,0)))::VARCHAR AS weighted FROM lineitem GROUP BY l_returnflag")
def q_decimal_sum(spark, sf_dir):
    price = F.col("l_extendedprice").cast("decimal(18,2)")
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.sum(price).cast("string").alias("total"), F.sum(price * F.col("l_quantity").cast("decimal(4,0)")).cast("string").alias("weighted"))


@query("SELECT event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY event_type")
def q_format_round_trip(spark, sf_dir):
    """CSV, JSON and ORC out and in again; the three agree or nothing comes back."""
    folder = scratch(spark, "round")
    schema = "event_id long, event_type string, value double"
    df, out = load(spark, sf_dir, "events").select("event_id", "event_type", "value"), None
    for fmt in ("csv", "json", "orc"):
        path = f"{folder}/{fmt}"
        write_any(df, path, fmt, **({"header": "true"} if fmt == "csv" else {}))
        back = read_any(spark, path, fmt, schema if fmt != "orc" else None, **({"header": "true"} if fmt == "csv" else {}))
        sums = back.groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
        out = sums if out is None else out.intersect(sums)
    return out


@query("SELECT vec_id AS id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x))), 5) AS norm FROM embeddings")
def q_vector_file_round_trip(spark, sf_dir):
    """Vectors written as length-prefixed float records and read back."""
    folder = scratch(spark, "records")
    files = sources.write_vector_files(sources.embeddings(spark, sf_dir), folder, 4)
    # Ids are places in a file; files hold ranges of ids, so each adds the rows before it.
    back = sources.read_vector_files(spark, folder, with_path=True)
    names = files.select(F.element_at(F.split("path", "/"), -1).alias("name"), "first")
    back = back.withColumn("name", F.element_at(F.split("path", "/"), -1)).join(F.broadcast(names), "name")  # a row per file
    from subvote.functions.vectors import norm

    return back.select((F.col("first") + F.col("id")).alias("id"), F.round(norm(F.col("vec")), 5).alias("norm"))


@query("SELECT o_custkey, count(*) AS n, round(sum(l_extendedprice), 2) AS spend FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey")
def q_bucket_join(spark, sf_dir):
    """Both sides bucketed by the order key: the join itself needs no exchange."""
    import uuid

    tag = uuid.uuid4().hex[:8]
    save_bucketed(load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), f"orders_b_{tag}", "o_orderkey", 8, "o_orderkey")
    save_bucketed(load(spark, sf_dir, "lineitem").select("l_orderkey", "l_extendedprice"), f"lineitem_b_{tag}", "l_orderkey", 8, "l_orderkey")
    o, li = spark.table(f"orders_b_{tag}"), spark.table(f"lineitem_b_{tag}")
    return o.join(li.hint("merge"), o.o_orderkey == li.l_orderkey).groupBy("o_custkey").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("spend"))


@query("SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_acctbal > 100 GROUP BY n_name")
def q_sql_views(spark, sf_dir):
    """Registered views and a named parameter."""
    register(spark, sf_dir, ["customer", "nation"])
    return spark.sql("SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_acctbal > :least GROUP BY n_name", args={"least": 100})


@query("""WITH d AS (SELECT vec_id AS id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS j FROM embeddings)
SELECT a.id, round(sum((a.x - b.x) * (a.x - b.x)), 6) AS d2, round(sum((a.x - b.x) * (a.x - b.x)), 6) AS d2_sql, round(sum(a.x * b.x), 6) AS p FROM d a JOIN d b ON b.id = 0 AND a.j = b.j GROUP BY a.id""")
def q_udf_scalars(spark, sf_dir):
    """Arrow functions and the SQL function of the same distance, called from SQL."""
    udfs.register(spark)
    sources.embeddings(spark, sf_dir).createOrReplaceTempView("udf_points")
    return spark.sql("SELECT a.id, round(vec_l2sq(a.vec, b.vec), 6) AS d2, round(sql_l2sq(a.vec, b.vec), 6) AS d2_sql, round(vec_dot(a.vec, b.vec), 6) AS p FROM udf_points a CROSS JOIN (SELECT vec FROM udf_points WHERE id = 0) b")


@query("WITH d AS (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS j FROM embeddings) SELECT label, j::BIGINT AS j, round(avg(x), 6) AS mean FROM d GROUP BY label, j")
def q_udaf_means(spark, sf_dir):
    udfs.register(spark)
    load(spark, sf_dir, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("vec")).createOrReplaceTempView("udaf_points")
    means = spark.sql("SELECT label, vec_mean(vec) AS m FROM udaf_points GROUP BY label")
    return means.select("label", F.posexplode("m").alias("j", "mean")).select("label", F.col("j").cast("long").alias("j"), F.round("mean", 6).alias("mean"))


@query("SELECT * FROM (VALUES (1, 0, 0, 1.1), (2, 1, 0, 1.6), (3, 0, 1, 2.1), (4, 1, 1, 2.6), (5, 2, 0, 4.1)) t(rank, left_code, right_code, cost)")
def q_udtf_traverse(spark, sf_dir):
    udfs.register(spark)
    return spark.sql("SELECT rank, left_code, right_code, round(cost, 6) AS cost FROM traverse(array(0.1D, 0.6D, 3.1D), array(1.0D, 2.0D), 5)")


@query("""WITH d AS (SELECT vec_id AS id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS j FROM embeddings),
m AS (SELECT a.id AS query_id, b.id, round(sum((a.x - b.x) * (a.x - b.x)), 6) AS dist2 FROM d a JOIN d b ON a.j = b.j WHERE a.id % 100 = 0 GROUP BY a.id, b.id)
SELECT query_id, rank::INT AS rank, id, dist2 FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist2, id) AS rank FROM m) WHERE rank <= 3""")
def q_udtf_knn(spark, sf_dir):
    """k-NN as a table function in a lateral join: k of every block of at most 64 ids, then merged."""
    udfs.register(spark)
    df = sources.embeddings(spark, sf_dir)
    df.filter("id % 100 = 0").createOrReplaceTempView("udtf_queries")
    blocks = df.groupBy(F.floor(F.col("id") / 64).alias("block")).agg(F.collect_list(F.struct("id", "vec")).alias("rows"))
    blocks.select(F.col("rows.id").alias("ids"), F.col("rows.vec").alias("vecs")).createOrReplaceTempView("udtf_base")
    parts = spark.sql("SELECT /*+ BROADCAST(q) */ q.id AS query_id, n.id, n.dist2 FROM udtf_queries q CROSS JOIN udtf_base b, LATERAL nearest(q.vec, b.ids, b.vecs, 3) n")
    return exact.merge(parts, 3)


@query()
def q_udaf_lid(spark, sf_dir):
    udfs.register(spark)
    base, queries = sources.split(sources.embeddings(spark, sf_dir))
    exact.knn_relational(base, queries, 20).select("query_id", F.sqrt("dist2").alias("r")).createOrReplaceTempView("udaf_truth")
    return spark.sql("SELECT query_id, round(vec_lid(r), 4) AS lid FROM udaf_truth GROUP BY query_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_LISTED)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
