"""Registered queries of the relational operators around the forests, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.math import rounded
from ..operators import relational as R
from ..session import table

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def _t(spark, sf_dir, name):
    return table(spark, sf_dir, name)


@query("SELECT l_orderkey, l_quantity, l_discount FROM lineitem WHERE l_quantity < 5 AND l_discount BETWEEN 0.05 AND 0.07 AND l_returnflag IN ('A', 'R')")
def q_scan_filter(spark, sf_dir):
    x = _t(spark, sf_dir, "lineitem").where((F.col("l_quantity") < 5) & F.col("l_discount").between(0.05, 0.07) & F.col("l_returnflag").isin("A", "R"))
    return x.select("l_orderkey", "l_quantity", "l_discount")


@query("SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'high' WHEN o_totalprice > 100000 THEN 'middle' ELSE 'low' END AS price_band, o_orderpriority LIKE '1%' AS urgent FROM orders")
def q_project_case(spark, sf_dir):
    p = F.col("o_totalprice")
    band = F.when(p > 300000, "high").when(p > 100000, "middle").otherwise("low")
    return _t(spark, sf_dir, "orders").select("o_orderkey", band.alias("price_band"), F.col("o_orderpriority").like("1%").alias("urgent"))


@query("SELECT n_nationkey, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def q_join_broadcast(spark, sf_dir):
    return _t(spark, sf_dir, "nation").join(F.broadcast(_t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")


@query("SELECT o_orderpriority, count(*) AS lines, round(sum(l_quantity), 2) + 0.0 AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
def q_join_merge(spark, sf_dir):
    x = _t(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity").hint("merge").join(_t(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey"))
    return x.groupBy("o_orderpriority").agg(F.count("*").alias("lines"), rounded(F.sum("l_quantity"), 2).alias("quantity"))


@query("SELECT c_mktsegment, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL")
def q_join_hash(spark, sf_dir):
    c = _t(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment").hint("shuffle_hash")
    return _t(spark, sf_dir, "orders").select("o_custkey").join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("orders"))


_BANDS = [(0, 0.0, 1000.0), (1, 1000.0, 1400.0), (2, 1400.0, 1800.0), (3, 1800.0, 1e9)]


@query(f"SELECT band, count(*) AS parts FROM part JOIN (VALUES {', '.join(map(str, _BANDS))}) b(band, lo, hi) ON p_retailprice >= lo AND p_retailprice < hi GROUP BY ALL")
def q_join_theta(spark, sf_dir):
    bands = spark.createDataFrame(_BANDS, "band int, lo double, hi double")
    p = _t(spark, sf_dir, "part")
    return p.join(F.broadcast(bands), (p.p_retailprice >= bands.lo) & (p.p_retailprice < bands.hi)).groupBy("band").agg(F.count("*").alias("parts"))


@query("SELECT w AS week, count(*) AS orders FROM orders JOIN (SELECT range AS w, range * 604800 + 694224000 AS a, range * 604800 + 694224000 + 2 * 604800 AS b FROM range(300)) ON epoch(o_orderdate)::BIGINT >= a AND epoch(o_orderdate)::BIGINT < b GROUP BY ALL")
def q_join_range(spark, sf_dir):
    """Overlapping two-week spans: points meet spans by a shared bucket first, then by the bounds."""
    spans = spark.range(300).select(F.col("id").alias("week"), (F.col("id") * 604800 + 694224000).alias("a")).withColumn("b", F.col("a") + 2 * 604800)
    at = F.unix_timestamp(F.col("o_orderdate").cast("timestamp"))
    return R.range_join(_t(spark, sf_dir, "orders").select(at.alias("at")), "at", spans, "a", "b", 604800).groupBy("week").agg(F.count("*").alias("orders"))


@query("SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events")
def q_join_asof(spark, sf_dir):
    e = _t(spark, sf_dir, "events")
    return e.select("event_id", F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("before"))


@query(
    "SELECT l.event_id, max(r.ts)::VARCHAR AS click FROM (SELECT * FROM events WHERE event_type = 'purchase') l LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') r ON r.user_id = l.user_id AND r.ts <= l.ts GROUP BY l.event_id"
)
def q_join_asof_two(spark, sf_dir):
    """The last click before each purchase of a user, by one sort of both sides."""
    e = _t(spark, sf_dir, "events")
    left = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'click'").select("user_id", "ts", F.col("ts").alias("click"))
    x = R.asof_join(left, right, ["user_id"], "ts", ["click"])
    return x.select("event_id", R.plain_time(F.col("click")).alias("click"))


@query("SELECT a.event_type AS one, b.event_type AS two, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY ALL")
def q_join_interval(spark, sf_dir):
    e = _t(spark, sf_dir, "events").select("user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    return R.within(e, e, ["user_id"], "t", 3_600_000_000).groupBy(F.col("event_type").alias("one"), F.col("event_type_r").alias("two")).agg(F.count("*").alias("pairs"))


@query("SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")
def q_join_semi(spark, sf_dir):
    rich = _t(spark, sf_dir, "orders").where("o_totalprice > 400000")
    return _t(spark, sf_dir, "customer").join(rich, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey", "c_name")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def q_join_anti(spark, sf_dir):
    return _t(spark, sf_dir, "customer").join(_t(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NOT NULL AS has_text, l.doc_id IS NOT NULL AS has_label FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def q_join_full(spark, sf_dir):
    d, lab = _t(spark, sf_dir, "documents").select(F.col("doc_id").alias("d")), _t(spark, sf_dir, "labels").select(F.col("doc_id").alias("l"))
    return d.join(lab, F.col("d") == F.col("l"), "full").select(F.coalesce("d", "l").alias("doc_id"), F.col("d").isNotNull().alias("has_text"), F.col("l").isNotNull().alias("has_label"))


@query("SELECT r_name, range AS tree FROM region, range(4)")
def q_join_cross(spark, sf_dir):
    return _t(spark, sf_dir, "region").select("r_name").crossJoin(spark.range(4).withColumnRenamed("id", "tree"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) + 0.0 AS sum_qty, round(avg(l_extendedprice), 4) + 0.0 AS avg_price, min(l_discount) AS low, max(l_discount) AS high FROM lineitem GROUP BY ALL")
def q_agg_basic(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), rounded(F.sum("l_quantity"), 2).alias("sum_qty"), rounded(F.avg("l_extendedprice"), 4).alias("avg_price"), F.min("l_discount").alias("low"), F.max("l_discount").alias("high")
    )


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY ALL")
def q_agg_distinct(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def q_agg_cube(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderpriority, o_orderstatus)")
def q_agg_rollup(spark, sf_dir):
    return _t(spark, sf_dir, "orders").rollup("o_orderpriority", "o_orderstatus").agg(F.count("*").alias("n"))


@query("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus))")
def q_agg_grouping_sets(spark, sf_dir):
    p, s = F.col("o_orderpriority"), F.col("o_orderstatus")
    return _t(spark, sf_dir, "orders").groupingSets([[p], [s]], p, s).agg(F.count("*").alias("n"))


@query("SELECT o_orderpriority, sum((o_orderstatus = 'F')::BIGINT)::BIGINT AS f, sum((o_orderstatus = 'O')::BIGINT)::BIGINT AS o, sum((o_orderstatus = 'P')::BIGINT)::BIGINT AS p FROM orders GROUP BY ALL")
def q_agg_pivot(spark, sf_dir):
    x = _t(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().fillna(0)
    return x.toDF("o_orderpriority", "f", "o", "p")


@query(
    "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) + 0.0 AS spread, round(corr(l_quantity, l_extendedprice), 6) + 0.0 AS r, round(quantile_cont(l_extendedprice, 0.5), 4) + 0.0 AS median, "
    "round(regr_slope(l_extendedprice, l_quantity), 4) + 0.0 AS slope, arg_max(l_orderkey, l_extendedprice * 1e6 + l_orderkey) AS dearest FROM lineitem GROUP BY ALL"
)
def q_agg_stats(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        rounded(F.stddev_samp("l_quantity")).alias("spread"),
        rounded(F.corr("l_quantity", "l_extendedprice")).alias("r"),
        rounded(F.percentile("l_extendedprice", 0.5), 4).alias("median"),
        rounded(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"),
        F.max_by("l_orderkey", F.col("l_extendedprice") * 1e6 + F.col("l_orderkey")).alias("dearest"),
    )


def _by(*order):
    return Window.partitionBy("c_nationkey").orderBy(*order)


@query(
    "SELECT c_custkey, row_number() OVER w AS place, rank() OVER w AS rank, dense_rank() OVER w AS dense, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 6) + 0.0 AS share, round(cume_dist() OVER w, 6) + 0.0 AS dist "
    "FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)"
)
def q_win_rank(spark, sf_dir):
    w = _by(F.desc("c_acctbal"), "c_custkey")
    return _t(spark, sf_dir, "customer").select(
        "c_custkey", F.row_number().over(w).alias("place"), F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.ntile(4).over(w).alias("quarter"), rounded(F.percent_rank().over(w)).alias("share"), rounded(F.cume_dist().over(w)).alias("dist")
    )


@query("SELECT c_custkey, lag(c_custkey) OVER w AS before, lead(c_custkey, 2) OVER w AS after, first_value(c_custkey) OVER w AS first, nth_value(c_custkey, 2) OVER w AS second FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)")
def q_win_analytic(spark, sf_dir):
    w = _by(F.desc("c_acctbal"), "c_custkey")
    return _t(spark, sf_dir, "customer").select(
        "c_custkey", F.lag("c_custkey").over(w).alias("before"), F.lead("c_custkey", 2).over(w).alias("after"), F.first("c_custkey").over(w).alias("first"), F.nth_value("c_custkey", 2).over(w).alias("second")
    )


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 4) + 0.0 AS running FROM events")
def q_win_rows_frame(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    return _t(spark, sf_dir, "events").select("event_id", rounded(F.sum("value").over(w), 4).alias("running"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM events")
def q_win_range_frame(spark, sf_dir):
    at = F.round(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("bigint")
    e = _t(spark, sf_dir, "events").withColumn("at", at)
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("at").rangeBetween(-3600, 0)).alias("recent"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def q_topk(spark, sf_dir):
    return _t(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def q_topk_per_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(spark, sf_dir, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2").select("o_custkey", "o_orderkey")


@query("SELECT n_name AS name FROM nation UNION ALL SELECT r_name FROM region")
def q_union(spark, sf_dir):
    return _t(spark, sf_dir, "nation").select(F.col("n_name").alias("name")).union(_t(spark, sf_dir, "region").select("r_name"))


@query("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def q_intersect(spark, sf_dir):
    return _t(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).intersect(_t(spark, sf_dir, "supplier").select("s_nationkey"))


@query("SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders")
def q_except(spark, sf_dir):
    return _t(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k")).exceptAll(_t(spark, sf_dir, "orders").select("o_custkey")).distinct()


@query("SELECT p_partkey, 'size' AS name, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def q_unpivot(spark, sf_dir):
    p = _t(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "name", "value")


@query("SELECT vec_id, (unnest(range(len(embedding))))::INTEGER AS place, round(unnest(embedding)::DOUBLE, 5) + 0.0 AS x FROM embeddings WHERE label = 3")
def q_explode(spark, sf_dir):
    e = _t(spark, sf_dir, "embeddings").where("label = 3")
    return e.select("vec_id", F.posexplode("embedding").alias("place", "x")).withColumn("x", rounded(F.col("x").cast("double"), 5))


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > 2.5 * (SELECT avg(o_totalprice) FROM orders)")
def q_subquery_scalar(spark, sf_dir):
    _t(spark, sf_dir, "orders").createOrReplaceTempView("orders_view")
    return spark.sql("SELECT o_orderkey FROM orders_view WHERE o_totalprice > 2.5 * (SELECT avg(o_totalprice) FROM orders_view)")


_EXISTS = "SELECT s_suppkey FROM {0} s WHERE EXISTS (SELECT 1 FROM {1} l WHERE l.l_suppkey = s.s_suppkey AND l.l_quantity >= 50 AND l.l_discount >= 0.1)"


@query(_EXISTS.format("supplier", "lineitem"))
def q_subquery_exists(spark, sf_dir):
    for n in ("supplier", "lineitem"):
        _t(spark, sf_dir, n).createOrReplaceTempView(f"{n}_view")
    return spark.sql(_EXISTS.format("supplier_view", "lineitem_view"))


_CTE = "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS s FROM {0} GROUP BY o_custkey), top AS (SELECT max(s) AS m FROM big) SELECT o_custkey, round(s, 2) + 0.0 AS total FROM big, top WHERE s >= 0.8 * m"


@query(_CTE.format("orders"))
def q_cte(spark, sf_dir):
    _t(spark, sf_dir, "orders").createOrReplaceTempView("orders_view")
    return spark.sql(_CTE.format("orders_view"))


_WALK = "WITH RECURSIVE up(node, place, steps) AS (SELECT CAST(n_nationkey + 500 AS BIGINT), CAST(n_nationkey + 500 AS BIGINT), 0 FROM {0} UNION ALL SELECT node, (place - 1) {1} 9, steps + 1 FROM up WHERE place > 0) SELECT node, max(steps) AS depth FROM up GROUP BY node"


@query(_WALK.format("nation", "//"))
def q_recursive_walk(spark, sf_dir):
    """From node numbers of nine-way trees up to the root."""
    _t(spark, sf_dir, "nation").createOrReplaceTempView("nation_view")
    return spark.sql(_WALK.format("nation_view", "DIV"))


@query("SELECT n_nationkey, upper(n_name) AS up, substr(n_name, 2, 3) AS part, length(n_name)::INTEGER AS n, replace(n_name, 'A', '*') AS starred, lpad(n_name, 12, '.') AS padded, md5(n_name) AS h, contains(n_name, 'AN') AS has FROM nation")
def q_str_fns(spark, sf_dir):
    c = F.col("n_name")
    return _t(spark, sf_dir, "nation").select(
        "n_nationkey", F.upper(c).alias("up"), F.substring(c, 2, 3).alias("part"), F.length(c).alias("n"), F.replace(c, F.lit("A"), F.lit("*")).alias("starred"), F.lpad(c, 12, ".").alias("padded"), F.md5(c).alias("h"), F.contains(c, F.lit("AN")).alias("has")
    )


@query("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, quarter(o_orderdate)::INTEGER AS q, month(o_orderdate)::INTEGER AS m, isodow(o_orderdate)::INTEGER AS d, datediff('day', DATE '1970-01-01', o_orderdate::DATE)::INTEGER AS days FROM orders")
def q_date_fns(spark, sf_dir):
    from ..functions.features import date_parts

    p = date_parts(F.col("o_orderdate"))
    return _t(spark, sf_dir, "orders").select("o_orderkey", p["year"].alias("y"), p["quarter"].alias("q"), p["month"].alias("m"), p["weekday"].alias("d"), p["epoch_day"].alias("days"))


@query("SELECT p_partkey, round(ln(p_retailprice), 6) + 0.0 AS ln, round(sqrt(p_retailprice), 6) + 0.0 AS root, (p_partkey % 7)::INTEGER AS m, floor(p_retailprice / 100)::BIGINT AS hundreds, greatest(p_size, 25) AS at_least, round(log2(p_retailprice) * p_retailprice, 4) + 0.0 AS xl FROM part")
def q_math_fns(spark, sf_dir):
    from ..functions.math import xlog2x

    p = F.col("p_retailprice")
    return _t(spark, sf_dir, "part").select(
        "p_partkey", rounded(F.ln(p)).alias("ln"), rounded(F.sqrt(p)).alias("root"), (F.col("p_partkey") % 7).cast("int").alias("m"), F.floor(p / 100).alias("hundreds"), F.greatest("p_size", F.lit(25)).alias("at_least"), rounded(xlog2x(p), 4).alias("xl")
    )


@query("SELECT vec_id, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 5) + 0.0 AS norm, round(list_max(embedding)::DOUBLE, 5) + 0.0 AS top, list_position(embedding, list_max(embedding))::INTEGER - 1 AS argmax FROM embeddings")
def q_array_fns(spark, sf_dir):
    from ..functions.features import array_features

    a = array_features(F.col("embedding"))
    return _t(spark, sf_dir, "embeddings").select("vec_id", rounded(a["norm"], 5).alias("norm"), rounded(a["top"], 5).alias("top"), a["argmax"].alias("argmax"))


@query("SELECT l_linenumber, string_agg(l_returnflag || '=' || n, ',' ORDER BY l_returnflag) AS counts FROM (SELECT l_linenumber, l_returnflag, count(*) AS n FROM lineitem GROUP BY ALL) GROUP BY ALL")
def q_map_fns(spark, sf_dir):
    n = _t(spark, sf_dir, "lineitem").groupBy("l_linenumber", "l_returnflag").agg(F.count("*").alias("n"))
    m = n.groupBy("l_linenumber").agg(F.map_from_entries(F.collect_list(F.struct("l_returnflag", "n"))).alias("m"))
    pairs = F.transform(F.array_sort(F.map_entries("m")), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string")))
    return m.select("l_linenumber", F.array_join(pairs, ",").alias("counts"))


@query("SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS k FROM events GROUP BY ALL")
def q_json_fns(spark, sf_dir):
    return _t(spark, sf_dir, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("bigint")).alias("k"))


@query(SQL["q_agg_basic"].replace("GROUP BY ALL", "GROUP BY l_returnflag, l_linestatus"))
def q_sql_text(spark, sf_dir):
    _t(spark, sf_dir, "lineitem").createOrReplaceTempView("lineitem_view")
    return spark.sql(SQL["q_sql_text"].replace("FROM lineitem", "FROM lineitem_view"))


@query("SELECT page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang, regexp_extract(url, '://([^/?#:]+)', 1) AS host FROM pages")
def q_page_features(spark, sf_dir):
    from ..functions.features import page_features

    p = page_features(F.col("url"), F.col("html"))
    return _t(spark, sf_dir, "pages").select("page_id", p["lang"].alias("lang"), p["host"].alias("host"))
