"""Relational, window, array, text, time and stream operators around the factorization."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..functions.init import start_value
from ..model import FactorModel, dot, norm
from ..operators.tensor import portable, portable_sql
from ..sources.catalog import cells_sql, tensor
from ..sources.tables import load
from ..streaming.windows import sessions, sliding, tumbling
from .common import quotient, rounded, union

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None):
    def add(run):
        QUERIES[run.__name__] = run
        if sql:
            ORACLE_SQL[run.__name__] = sql
        return run

    return add


@query("SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_shipdate >= TIMESTAMP '1998-01-01'")
def scan_filter_project(spark, sf):
    return load(spark, sf, "lineitem").where((F.col("l_quantity") > 45) & (F.col("l_shipdate") >= F.lit("1998-01-01").cast("timestamp_ntz"))).select("l_orderkey", "l_partkey", "l_quantity")


@query("SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS size_class FROM part WHERE p_brand IN ('Brand#11', 'Brand#12', 'Brand#13') AND p_retailprice BETWEEN 900 AND 1500 AND p_type NOT LIKE '%X' AND p_name IS NOT NULL AND regexp_matches(p_brand, '^Brand#1[0-9]$')")
def filter_predicates(spark, sf):
    p = load(spark, sf, "part")
    size = F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large")
    return p.where(F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13") & F.col("p_retailprice").between(900, 1500) & ~F.col("p_type").like("%X") & F.col("p_name").isNotNull() & F.col("p_brand").rlike("^Brand#1[0-9]$")).select("p_partkey", size.alias("size_class"))


@query("SELECT k, dense_rank() OVER (ORDER BY k) - 1 AS idx, nnz FROM (SELECT event_type AS k, CAST(count(*) AS BIGINT) AS nnz FROM (SELECT DISTINCT user_id, event_type, hour(ts) AS h FROM events) GROUP BY 1)")
def encode_modes(spark, sf):
    return tensor(spark, sf, "events3").dictionaries[1].select(F.col("key").alias("k"), "idx", "nnz")


@query("SELECT n_name, r_name, count(*) AS customers, round(sum(c_acctbal), 2) + 0.0 AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def join_broadcast_star(spark, sf):
    dims = load(spark, sf, "nation").join(F.broadcast(load(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return load(spark, sf, "customer").join(F.broadcast(dims), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name", "r_name").agg(F.count("*").alias("customers"), rounded(F.sum("c_acctbal"), 2).alias("balance"))


@query("SELECT o_orderstatus, count(*) AS lines, round(sum(l_quantity), 2) + 0.0 AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_sortmerge(spark, sf):
    return load(spark, sf, "orders").hint("merge").join(load(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("lines"), rounded(F.sum("l_quantity"), 2).alias("quantity"))


@query("SELECT coalesce(a.u, b.u) AS user_id, a.n AS early, b.n AS late FROM (SELECT user_id AS u, count(*) AS n FROM events WHERE ts < TIMESTAMP '2024-01-02' GROUP BY 1) a FULL JOIN (SELECT user_id AS u, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-29' GROUP BY 1) b ON a.u = b.u")
def join_outer_cold_rows(spark, sf):
    e = load(spark, sf, "events")
    early = e.where(F.col("ts") < F.lit("2024-01-02").cast("timestamp_ntz")).groupBy("user_id").agg(F.count("*").alias("early"))
    late = e.where(F.col("ts") >= F.lit("2024-01-29").cast("timestamp_ntz")).groupBy("user_id").agg(F.count("*").alias("late"))
    return early.join(late, "user_id", "full")


@query("SELECT 'bought' AS kind, count(*) AS customers FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders) UNION ALL SELECT 'never', count(*) FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey IS NOT NULL)")
def semi_anti(spark, sf):
    c, o = load(spark, sf, "customer"), load(spark, sf, "orders").select("o_custkey")
    on = F.col("c_custkey") == F.col("o_custkey")
    return union([c.join(o, on, how).agg(F.count("*").alias("customers")).select(F.lit(kind).alias("kind"), "customers") for kind, how in (("bought", "left_semi"), ("never", "left_anti"))])


@query("SELECT n_nationkey, t.event_type FROM nation, (SELECT DISTINCT event_type FROM events) t")
def cross_candidates(spark, sf):
    return load(spark, sf, "nation").select("n_nationkey").crossJoin(F.broadcast(load(spark, sf, "events").select("event_type").distinct()))


@query("SELECT b.block, count(*) AS parts, round(sum(p_retailprice), 2) + 0.0 AS price FROM part JOIN (SELECT * FROM (VALUES (0, 1, 10), (1, 11, 25), (2, 26, 50)) v(block, low, high)) b ON p_size BETWEEN low AND high GROUP BY 1")
def range_join_blocks(spark, sf):
    blocks = spark.createDataFrame([(0, 1, 10), (1, 11, 25), (2, 26, 50)], "block int, low int, high int")
    return load(spark, sf, "part").join(F.broadcast(blocks), F.col("p_size").between(F.col("low"), F.col("high"))).groupBy("block").agg(F.count("*").alias("parts"), rounded(F.sum("p_retailprice"), 2).alias("price"))


@query("SELECT event_id, (SELECT max_by(d.value, d.event_id) FROM events d WHERE d.user_id = e.user_id AND d.event_type = 'purchase' AND (d.ts < e.ts OR (d.ts = e.ts AND d.event_id < e.event_id)) AND d.ts = (SELECT max(f.ts) FROM events f WHERE f.user_id = e.user_id AND f.event_type = 'purchase' AND (f.ts < e.ts OR (f.ts = e.ts AND f.event_id < e.event_id)))) AS last_value FROM events e WHERE event_type = 'click'")
def asof_order_event(spark, sf):
    """The user's latest earlier purchase value at each click: an as-of join by one ordered pass per user."""
    before = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    e = load(spark, sf, "events").withColumn("last_value", F.last(F.when(F.col("event_type") == "purchase", F.col("value")), ignorenulls=True).over(before))
    return e.where("event_type = 'click'").select("event_id", "last_value")


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def interval_join_events(spark, sf):
    """Pairs of a user's events within ten minutes: time buckets make the band an equi-join."""
    e = load(spark, sf, "events").select("event_id", "user_id", "ts")
    bucket = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 600)
    a = e.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("ta"), F.explode(F.array(bucket, bucket + 1)).alias("slot"))
    b = e.select(F.col("event_id").alias("second_id"), "user_id", F.col("ts").alias("tb"), bucket.alias("slot"))
    return a.join(b, ["user_id", "slot"]).where("tb > ta AND tb <= ta + INTERVAL 10 MINUTES").select("first_id", "second_id")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) + 0.0 AS revenue, round(avg(l_quantity), 6) + 0.0 AS quantity, min(l_tax) AS low, max(l_tax) AS high FROM lineitem GROUP BY 1, 2")
def agg_basic(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), rounded(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), rounded(F.avg("l_quantity")).alias("quantity"), F.min("l_tax").alias("low"), F.max("l_tax").alias("high"))


@query("SELECT r_name, string_agg(n_name, ',' ORDER BY n_name) AS nations, max_by(n_name, n_nationkey) AS last_nation FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def agg_collect(spark, sf):
    joined = load(spark, sf, "nation").join(F.broadcast(load(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return joined.groupBy("r_name").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("nations"), F.max_by("n_name", "n_nationkey").alias("last_nation"))


@query("SELECT count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS kinds, count(DISTINCT CAST(ts AS DATE)) AS days FROM events")
def count_distinct(spark, sf):
    return load(spark, sf, "events").agg(F.countDistinct("user_id").alias("users"), F.countDistinct("event_type").alias("kinds"), F.countDistinct(F.to_date("ts")).alias("days"))


def _errors(spark, sf):
    c = load(spark, sf, "customer").join(F.broadcast(load(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(load(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return c.withColumn("e", F.col("c_acctbal") / 1000 - portable(F.col("c_custkey"), 1))


@query(f"SELECT r_name, n_name, round(sqrt(avg(e * e)), 6) + 0.0 AS rmse FROM (SELECT *, c_acctbal / 1000 - {portable_sql('c_custkey', 1)} AS e FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey) GROUP BY ROLLUP (r_name, n_name)")
def rmse_rollup(spark, sf):
    return _errors(spark, sf).rollup("r_name", "n_name").agg(rounded(F.sqrt(F.avg(F.col("e") * F.col("e")))).alias("rmse"))


@query("SELECT event_type, hour(ts) AS h, round(sum(value), 3) + 0.0 AS total, count(*) AS n FROM events GROUP BY CUBE (event_type, hour(ts))")
def marginals_cube(spark, sf):
    return load(spark, sf, "events").withColumn("h", F.hour("ts").cast("long")).cube("event_type", "h").agg(rounded(F.sum("value"), 3).alias("total"), F.count("*").alias("n"))


@query("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderpriority, o_orderstatus), (o_orderpriority), ())")
def grouping_sets(spark, sf):
    return spark.sql("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((o_orderpriority, o_orderstatus), (o_orderpriority), ())", orders=load(spark, sf, "orders"))


@query(f"SELECT nnz, count(*) AS rows FROM (SELECT i2, count(*) AS nnz FROM ({cells_sql('supply3')}) GROUP BY 1) GROUP BY 1")
def count_histogram(spark, sf):
    return tensor(spark, sf, "supply3").cells.groupBy("i2").agg(F.count("*").alias("nnz")).groupBy("nnz").agg(F.count("*").alias("rows"))


@query("SELECT round(var_pop(value), 4) + 0.0 AS variance, round(stddev_samp(value), 6) + 0.0 AS deviation, round(corr(value, user_id), 6) + 0.0 AS correlation, round(quantile_cont(value, 0.5), 6) + 0.0 AS median FROM events")
def value_stats(spark, sf):
    return load(spark, sf, "events").agg(rounded(F.var_pop("value"), 4).alias("variance"), rounded(F.stddev("value")).alias("deviation"), rounded(F.corr("value", F.col("user_id").cast("double"))).alias("correlation"), rounded(F.percentile("value", F.lit(0.5))).alias("median"))


@query("SELECT event_type, 'low' AS measure, min(value) AS amount FROM events GROUP BY 1 UNION ALL SELECT event_type, 'high', max(value) FROM events GROUP BY 1")
def unpivot_measures(spark, sf):
    wide = load(spark, sf, "events").groupBy("event_type").agg(F.min("value").alias("low"), F.max("value").alias("high"))
    return wide.unpivot("event_type", ["low", "high"], "measure", "amount")


@query("SELECT o_orderstatus, count(*) FILTER (o_orderpriority LIKE '1%') AS urgent, count(*) FILTER (o_orderpriority LIKE '5%') AS low FROM orders GROUP BY 1")
def pivot_counts(spark, sf):
    o = load(spark, sf, "orders").withColumn("p", F.substring("o_orderpriority", 1, 1))
    return o.groupBy("o_orderstatus").pivot("p", ["1", "5"]).count().select("o_orderstatus", F.coalesce("1", F.lit(0)).cast("long").alias("urgent"), F.coalesce("5", F.lit(0)).cast("long").alias("low"))


@query("SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS dr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)")
def window_rank(spark, sf):
    w = W.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return load(spark, sf, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(W.partitionBy("c_nationkey").orderBy("c_mktsegment")).alias("dr"))


@query("SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS quarter FROM part")
def window_ntile(spark, sf):
    return load(spark, sf, "part").select("p_partkey", F.ntile(4).over(W.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).alias("quarter"))


@query("SELECT event_id, round(value - lag(value) OVER w, 6) + 0.0 AS change, round(value / first_value(value) OVER w, 6) + 0.0 AS against_first, lead(event_type) OVER w AS following FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_lag(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf, "events").select("event_id", rounded(F.col("value") - F.lag("value").over(w)).alias("change"), rounded(quotient(F.col("value"), F.first("value").over(w))).alias("against_first"), F.lead("event_type").over(w).alias("following"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) + 0.0 AS moving FROM events")
def window_rows_frame(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    return load(spark, sf, "events").select("event_id", rounded(F.avg("value").over(w)).alias("moving"))


@query("SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS close_in_size FROM part")
def window_range_frame(spark, sf):
    return load(spark, sf, "part").select("p_partkey", F.count("*").over(W.partitionBy("p_brand").orderBy("p_size").rangeBetween(-2, 2)).alias("close_in_size"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def topk_global(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query(f"SELECT i1, i3, rank FROM (SELECT i1, i3, row_number() OVER (PARTITION BY i1 ORDER BY x DESC, i3) AS rank FROM ({cells_sql('events3')}) WHERE i2 = 0) WHERE rank <= 3")
def topk_per_user(spark, sf):
    c = tensor(spark, sf, "events3").cells.where("i2 = 0")
    return c.select("i1", "i3", F.row_number().over(W.partitionBy("i1").orderBy(F.desc("x"), "i3")).alias("rank")).where("rank <= 3")


@query("SELECT 'both' AS part, count(*) AS n FROM (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O') UNION ALL SELECT 'first only', count(*) FROM (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' EXCEPT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O') UNION ALL SELECT 'either', count(*) FROM (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' UNION SELECT o_custkey FROM orders WHERE o_orderstatus = 'O')")
def setops_support(spark, sf):
    o = load(spark, sf, "orders")
    a, b = (o.where(F.col("o_orderstatus") == s).select("o_custkey") for s in ("F", "O"))
    return union([f.agg(F.count("*").alias("n")).select(F.lit(k).alias("part"), "n") for k, f in (("both", a.intersect(b)), ("first only", a.subtract(b)), ("either", a.union(b).distinct()))])


@query("SELECT lang, token, count(*) AS n FROM (SELECT lang, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS token FROM documents) WHERE length(token) > 3 GROUP BY 1, 2 HAVING count(*) >= 5")
def token_cells(spark, sf):
    words = load(spark, sf, "documents").select("lang", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("token")).where(F.length("token") > 3)
    return words.groupBy("lang", "token").agg(F.count("*").alias("n")).where("n >= 5")


@query("SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def url_modes(spark, sf):
    return load(spark, sf, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("n"))


@query("SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n, CAST(max(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS INT) AS last_day FROM orders GROUP BY 1, 2")
def time_modes(spark, sf):
    days = F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date"))
    return load(spark, sf, "orders").groupBy(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).agg(F.count("*").alias("n"), F.max(days).alias("last_day"))


_NORM = "sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE))))"


@query(f"SELECT vec_id, round({_NORM}, 5) + 0.0 AS length, round(list_max(embedding), 5) + 0.0 AS largest FROM embeddings")
def embed_norm(spark, sf):
    doubles = F.col("embedding").cast("array<double>")
    return load(spark, sf, "embeddings").select("vec_id", rounded(norm(doubles), 5).alias("length"), (F.round(F.array_max("embedding"), 5) + F.lit(0.0)).alias("largest"))


@query("SELECT b.vec_id, round(list_sum(list_transform(range(1, 65), lambda i: CAST(a.embedding[i] AS DOUBLE) * CAST(b.embedding[i] AS DOUBLE))), 5) + 0.0 AS product FROM embeddings a, embeddings b WHERE a.vec_id = 0")
def array_dot(spark, sf):
    e = load(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    return e.crossJoin(F.broadcast(e.where("vec_id = 0").select(F.col("v").alias("q")))).select("vec_id", rounded(dot(F.col("v"), F.col("q")), 5).alias("product"))


_FACTOR = lambda n, k: f"({portable_sql('idx', n, k)})"


@query(
    f"WITH rows AS MATERIALIZED (SELECT DISTINCT i1 AS idx FROM ({cells_sql('events3')})), f AS MATERIALIZED (SELECT idx, {_FACTOR(1, 0)} AS a, {_FACTOR(1, 1)} AS b, {_FACTOR(1, 2)} AS c FROM rows), q AS (SELECT a AS qa, b AS qb, c AS qc FROM f WHERE idx = 3) "
    "SELECT idx, round((a * qa + b * qb + c * qc) / (sqrt(a * a + b * b + c * c) * sqrt(qa * qa + qb * qb + qc * qc)), 6) + 0.0 AS cosine FROM f, q WHERE idx <> 3 ORDER BY (a * qa + b * qb + c * qc) / (sqrt(a * a + b * b + c * c) * sqrt(qa * qa + qb * qb + qc * qc)) DESC, idx LIMIT 10"
)
def similar_rows(spark, sf):
    """Users nearest to one of them, by the starting values of the users that have cells."""
    t = tensor(spark, sf, "events3")
    users = t.cells.select(F.lit(1).alias("mode"), F.col("i1").alias("idx")).distinct()
    factors = users.withColumn("f", F.array(*(start_value(F.col("idx"), 1, k, 42, "random") for k in range(3))))
    return FactorModel(factors, 3, t.dims).similar(1, 3, 10).select("idx", rounded("cosine").alias("cosine"))


@query("SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
def json_mode(spark, sf):
    return load(spark, sf, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def map_cells(spark, sf):
    """Counts kept as a map per user and exploded again: maps as a source of cells."""
    counts = load(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.explode("m").alias("event_type", "n"))


@query("SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY AS stop, count(*) AS n, round(avg(value), 6) + 0.0 AS mean FROM events GROUP BY 1, 2")
def tumbling_events(spark, sf):
    return tumbling(load(spark, sf, "events")).withColumn("mean", rounded("mean"))


@query("SELECT d AS start, d + INTERVAL 2 DAY AS stop, count(*) AS n, round(avg(value), 6) + 0.0 AS mean FROM (SELECT value, unnest([date_trunc('day', ts) - INTERVAL 1 DAY, date_trunc('day', ts)]) AS d FROM events) GROUP BY 1, 2")
def sliding_events(spark, sf):
    return sliding(load(spark, sf, "events")).withColumn("mean", rounded("mean"))


@query("WITH g AS (SELECT *, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS session FROM g) SELECT min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS stop, user_id, count(*) AS n, round(avg(value), 6) + 0.0 AS mean FROM s GROUP BY user_id, session")
def session_events(spark, sf):
    return sessions(load(spark, sf, "events")).withColumn("mean", rounded("mean"))


@query(f"SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, round(sqrt(avg(power(value / 100 - {portable_sql('user_id', 1)}, 2))), 6) + 0.0 AS rmse FROM events GROUP BY 1")
def rmse_by_window(spark, sf):
    e = load(spark, sf, "events").withColumn("e", F.col("value") / 100 - portable(F.col("user_id"), 1))
    return e.groupBy(F.window("ts", "1 day").alias("w")).agg(rounded(F.sqrt(F.avg(F.col("e") * F.col("e")))).alias("rmse")).select(F.col("w.start").alias("start"), "rmse")
