"""The relational operators around the methods, each on the given tables and in SQL for a second engine."""

from __future__ import annotations

import zlib

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import udfs
from ..functions.stats import esd_critical
from ..functions.vectors import register as register_vectors
from ..operators.joins import as_of, interval_join
from ..sources.tables import events, read, stored

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


@query("SELECT l_orderkey, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'")
def scan_prune(spark, sf_dir):
    l = read(spark, sf_dir, "lineitem")  # noqa: E741
    return l.filter("l_quantity >= 45 and l_returnflag = 'R'").select("l_orderkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("SELECT doc_id, lang, source FROM documents WHERE n_chars BETWEEN 500 AND 2000 AND lang IN ('fr', 'de') AND text LIKE '%er%' AND lang IS NOT DISTINCT FROM 'fr' AND NOT regexp_matches(text, '[0-9]{6}')")
def filter_predicates(spark, sf_dir):
    d = read(spark, sf_dir, "documents")
    return d.filter(F.col("n_chars").between(500, 2000) & F.col("lang").isin("fr", "de") & F.col("text").like("%er%") & F.col("lang").eqNullSafe("fr") & ~F.col("text").rlike("[0-9]{6}")).select("doc_id", "lang", "source")


@query("SELECT o_orderkey, o_orderstatus, l_partkey, l_quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderpriority = '1-URGENT'")
def join_inner(spark, sf_dir):
    o = read(spark, sf_dir, "orders", ["o_orderkey", "o_orderstatus"], F.col("o_orderpriority") == "1-URGENT")
    return o.join(read(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"]), F.col("o_orderkey") == F.col("l_orderkey")).drop("l_orderkey")


@query("SELECT d.doc_id, d.lang, l.quality FROM documents d LEFT JOIN labels l USING (doc_id)")
def join_left(spark, sf_dir):
    return read(spark, sf_dir, "documents", ["doc_id", "lang"]).join(read(spark, sf_dir, "labels", ["doc_id", "quality"]), "doc_id", "left")


@query("SELECT k, a, b FROM (SELECT c_nationkey AS k, count(*) AS a FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey AS k, count(*) AS b FROM supplier GROUP BY 1) USING (k)")
def join_full(spark, sf_dir):
    c = read(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("a"))
    s = read(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("b"))
    return c.join(s, "k", "full")


@query("SELECT 'labelled' AS side, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) UNION ALL SELECT 'not labelled', count(*) FROM documents WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = documents.doc_id)")
def join_semi_anti(spark, sf_dir):
    d, l = read(spark, sf_dir, "documents", ["doc_id"]), read(spark, sf_dir, "labels", ["doc_id"])  # noqa: E741
    n = lambda side, how: d.join(l, "doc_id", how).agg(F.lit(side).alias("side"), F.count(F.lit(1)).alias("n"))
    return n("labelled", "left_semi").unionAll(n("not labelled", "left_anti"))


@query("SELECT e.event_id AS error_id, count(*) AS near, round(sum(p.value), 4) AS value FROM events e JOIN events p ON e.user_id = p.user_id AND p.event_type = 'click' AND abs(epoch_us(p.ts) - epoch_us(e.ts)) <= 3600000000 WHERE e.event_type = 'error' GROUP BY 1")
def join_interval(spark, sf_dir):
    e = events(spark, sf_dir)
    left = e.filter("event_type = 'error'").select("user_id", F.col("event_id").alias("error_id"), F.col("ts").alias("t"))
    right = e.filter("event_type = 'click'").select("user_id", "ts", "value")
    return interval_join(left, right, ["user_id"], "t", "ts", 3600).groupBy("error_id").agg(F.count(F.lit(1)).alias("near"), F.round(F.sum("value"), 4).alias("value"))


@query("SELECT e.event_id, c.value AS last_click FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON e.user_id = c.user_id AND e.ts >= c.ts")
def join_asof(spark, sf_dir):
    e = events(spark, sf_dir)
    return as_of(e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id"), e.filter("event_type = 'click'").select("user_id", "ts", F.col("value").alias("last_click")), ["user_id"], "ts").select("event_id", "last_click")


_TOP = "SELECT n_name, c_custkey, c_acctbal FROM (SELECT n_name, c_custkey, c_acctbal, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer JOIN nation ON n_nationkey = c_nationkey) WHERE r <= 3"


@query(_TOP)
def lateral_topk(spark, sf_dir):
    read(spark, sf_dir, "nation").createOrReplaceTempView("lateral_nation")
    read(spark, sf_dir, "customer").createOrReplaceTempView("lateral_customer")
    return spark.sql("SELECT n_name, c_custkey, c_acctbal FROM lateral_nation, LATERAL (SELECT c_custkey, c_acctbal FROM lateral_customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)")


@query("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS sum_qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS avg_disc, count(*) AS n FROM lineitem GROUP BY 1, 2")
def agg_basic(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("sum_qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), F.round(F.avg("l_discount"), 6).alias("avg_disc"), F.count(F.lit(1)).alias("n"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders, arg_max(l_orderkey, (l_extendedprice, l_orderkey)) AS dearest FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_orderkey").alias("orders"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("dearest"))


@query("SELECT event_type, round(median(value), 6) AS median, round(quantile_cont(value, 0.05), 6) AS p05, round(quantile_cont(value, 0.95), 6) AS p95 FROM events GROUP BY 1")
def agg_percentile(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.median("value"), 6).alias("median"), F.round(F.percentile("value", F.lit(0.05)), 6).alias("p05"), F.round(F.percentile("value", F.lit(0.95)), 6).alias("p95"))


@query("SELECT event_type, TRUE AS users_within_5_percent, quantile_disc(value, 0.5) AS median FROM events GROUP BY 1")
def agg_approximate(spark, sf_dir):
    """The sketches beside exact counts; a percentile of fewer values than its accuracy is exact."""
    g = read(spark, sf_dir, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("about"), F.count_distinct("user_id").alias("users"), F.percentile_approx("value", F.lit(0.5), F.lit(10_000)).alias("median"))
    return g.select("event_type", (F.abs(F.col("about") - F.col("users")) <= 0.05 * F.col("users")).alias("users_within_5_percent"), "median")


_RESULTS = "SELECT lang, source, CAST(quality AS INT) AS quality FROM documents JOIN labels USING (doc_id)"


def _results(spark, sf_dir):
    return read(spark, sf_dir, "documents", ["doc_id", "lang", "source"]).join(read(spark, sf_dir, "labels", ["doc_id", "quality"]), "doc_id")


@query(f"SELECT lang, source, CAST(grouping(lang, source) AS BIGINT) AS gid, count(*) AS n, round(avg(quality), 6) AS quality FROM ({_RESULTS}) GROUP BY ROLLUP (lang, source)")
def results_rollup(spark, sf_dir):
    return _results(spark, sf_dir).rollup("lang", "source").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n"), F.round(F.avg("quality"), 6).alias("quality"))


@query(f"SELECT lang, quality, count(*) AS n FROM ({_RESULTS}) GROUP BY CUBE (lang, quality)")
def results_cube(spark, sf_dir):
    return _results(spark, sf_dir).withColumn("quality", F.col("quality").cast("int")).cube("lang", "quality").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT lang, count(CASE WHEN quality = 0 THEN 1 END) AS q0, count(CASE WHEN quality = 1 THEN 1 END) AS q1 FROM ({_RESULTS}) GROUP BY lang")
def results_pivot(spark, sf_dir):
    return _results(spark, sf_dir).groupBy("lang").pivot("quality", [0, 1]).agg(F.count(F.lit(1))).select("lang", F.coalesce("0", F.lit(0)).alias("q0"), F.coalesce("1", F.lit(0)).alias("q1"))


@query("SELECT nation, measure, value FROM (SELECT c_nationkey AS nation, 'least' AS measure, min(c_acctbal) AS value FROM customer GROUP BY 1 UNION ALL SELECT c_nationkey, 'most', max(c_acctbal) FROM customer GROUP BY 1)")
def results_unpivot(spark, sf_dir):
    return read(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.min("c_acctbal").alias("least"), F.max("c_acctbal").alias("most")).unpivot("nation", ["least", "most"], "measure", "value")


@query("SELECT c_custkey, rank() OVER w AS rnk, dense_rank() OVER w AS dense, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS quarter, round(percent_rank() OVER w, 6) AS pr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)")
def win_rank(spark, sf_dir):
    w, u = Window.partitionBy("c_nationkey").orderBy("c_mktsegment"), Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return read(spark, sf_dir, "customer").select("c_custkey", F.rank().over(w).alias("rnk"), F.dense_rank().over(w).alias("dense"), F.row_number().over(u).alias("rn"), F.ntile(4).over(u).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("SELECT event_id, lag(value) OVER w AS before, lead(value, 2) OVER w AS after, first_value(value) OVER w AS first, last_value(value) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read(spark, sf_dir, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value", 2).over(w).alias("after"), F.first("value").over(w).alias("first"), F.last("value").over(whole).alias("last"))


@query("SELECT event_id, round(sum(value) OVER (w ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 4) AS last_five, count(*) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS so_far FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_rows(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read(spark, sf_dir, "events").select("event_id", F.round(F.sum("value").over(w.rowsBetween(-4, 0)), 4).alias("last_five"), F.count(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day_events FROM events")
def win_range(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros("ts")).rangeBetween(-86_400_000_000, 0)
    return events(spark, sf_dir).select("event_id", F.count(F.lit(1)).over(w).alias("day_events"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_global(spark, sf_dir):
    return read(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("SELECT o_custkey, o_orderkey, o_totalprice FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def topk_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return read(spark, sf_dir, "orders").withColumn("r", F.row_number().over(w)).filter("r <= 2").select("o_custkey", "o_orderkey", "o_totalprice")


_A = "SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'R'"
_B = "SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'A'"


def _keys(spark, sf_dir, flag):
    return read(spark, sf_dir, "lineitem", None, F.col("l_returnflag") == flag).select(F.col("l_partkey").alias("k"))


@query(f"SELECT 'distinct' AS kind, count(*) AS n FROM ({_A} UNION {_B}) UNION ALL SELECT 'all', count(*) FROM ({_A} UNION ALL {_B})")
def set_union(spark, sf_dir):
    both = _keys(spark, sf_dir, "R").union(_keys(spark, sf_dir, "A"))
    n = lambda df, kind: df.agg(F.lit(kind).alias("kind"), F.count(F.lit(1)).alias("n"))
    return n(both.distinct(), "distinct").unionAll(n(both, "all"))


@query(f"SELECT 'distinct' AS kind, count(*) AS n FROM ({_A} INTERSECT {_B}) UNION ALL SELECT 'all', count(*) FROM ({_A} INTERSECT ALL {_B})")
def set_intersect(spark, sf_dir):
    a, b = _keys(spark, sf_dir, "R"), _keys(spark, sf_dir, "A")
    n = lambda df, kind: df.agg(F.lit(kind).alias("kind"), F.count(F.lit(1)).alias("n"))
    return n(a.intersect(b), "distinct").unionAll(n(a.intersectAll(b), "all"))


@query(f"SELECT 'distinct' AS kind, count(*) AS n FROM ({_A} EXCEPT {_B}) UNION ALL SELECT 'all', count(*) FROM ({_A} EXCEPT ALL {_B})")
def set_except(spark, sf_dir):
    a, b = _keys(spark, sf_dir, "R"), _keys(spark, sf_dir, "A")
    n = lambda df, kind: df.agg(F.lit(kind).alias("kind"), F.count(F.lit(1)).alias("n"))
    return n(a.subtract(b), "distinct").unionAll(n(a.exceptAll(b), "all"))


@query("SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 48) AND o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 0)")
def subq_exists(spark, sf_dir):
    for t in ("orders", "lineitem", "customer"):
        read(spark, sf_dir, t).createOrReplaceTempView(f"subq_{t}")
    return spark.sql("SELECT o_orderkey FROM subq_orders WHERE EXISTS (SELECT 1 FROM subq_lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 48) AND o_totalprice > (SELECT avg(o_totalprice) FROM subq_orders) AND o_custkey IN (SELECT c_custkey FROM subq_customer WHERE c_acctbal > 0)")


@query("SELECT p_partkey, upper(p_brand) AS brand, length(p_name) AS size, string_split(p_type, ' ')[1] AS head, md5(p_name) AS mark, levenshtein(p_brand, p_type) AS gap, p_brand || '/' || p_type AS both, regexp_replace(p_name, '[0-9]+', '#', 'g') AS masked FROM part")
def fn_string(spark, sf_dir):
    return read(spark, sf_dir, "part").select(
        "p_partkey", F.upper("p_brand").alias("brand"), F.length("p_name").cast("long").alias("size"), F.split("p_type", " ")[0].alias("head"), F.md5("p_name").alias("mark"),
        F.levenshtein("p_brand", "p_type").cast("long").alias("gap"), F.concat_ws("/", "p_brand", "p_type").alias("both"), F.regexp_replace("p_name", "[0-9]+", "#").alias("masked"),
    )


@query("SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, CAST(datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INT) AS days, CAST(dayofweek(o_orderdate) + 1 AS INT) AS dow, CAST(o_orderdate + INTERVAL 30 DAY AS DATE) AS due FROM orders")
def fn_date(spark, sf_dir):
    o = read(spark, sf_dir, "orders")
    day = F.col("o_orderdate").cast("date")
    return o.select("o_orderkey", F.trunc(day, "month").alias("month"), F.datediff(day, F.lit("1992-01-01").cast("date")).alias("days"), F.dayofweek(day).alias("dow"), F.date_add(day, 30).alias("due"))


@query("SELECT p_partkey, round(sqrt(p_retailprice), 6) AS root, round(ln(p_retailprice), 6) AS logged, round(exp(-p_size / 10.0), 6) AS decay, CAST(sign(p_size - 25) AS INT) AS side, greatest(p_size, 20) AS floor20, round(pow(p_size, 1.5), 4) AS powered FROM part")
def fn_math(spark, sf_dir):
    return read(spark, sf_dir, "part").select(
        "p_partkey", F.round(F.sqrt("p_retailprice"), 6).alias("root"), F.round(F.log("p_retailprice"), 6).alias("logged"), F.round(F.exp(-F.col("p_size") / 10.0), 6).alias("decay"),
        F.signum(F.col("p_size") - 25).cast("int").alias("side"), F.greatest("p_size", F.lit(20)).alias("floor20"), F.round(F.pow("p_size", F.lit(1.5)), 4).alias("powered"),
    )


_PARTS = "SELECT l_orderkey, list_sort(list(DISTINCT l_partkey)) AS parts FROM lineitem GROUP BY 1"


@query(f"SELECT l_orderkey, len(parts) AS n, list_sum(list_transform(parts, lambda x: x % 7)) AS s, len(list_filter(parts, lambda x: x % 2 = 0)) AS even, array_to_string(parts[1:2], ',') AS head FROM ({_PARTS})")
def fn_array(spark, sf_dir):
    p = read(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_set("l_partkey")).alias("parts"))
    return p.select("l_orderkey", F.size("parts").cast("long").alias("n"), F.aggregate("parts", F.lit(0).cast("long"), lambda s, x: s + x % 7).alias("s"), F.size(F.filter("parts", lambda x: x % 2 == 0)).cast("long").alias("even"), F.concat_ws(",", F.transform(F.slice("parts", 1, 2), lambda x: x.cast("string"))).alias("head"))


@query("SELECT c_nationkey, string_agg(c_mktsegment || '=' || n, ',' ORDER BY c_mktsegment) AS segments, count(*) AS kinds FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY 1, 2) WHERE n > 1 GROUP BY 1")
def fn_map(spark, sf_dir):
    n = read(spark, sf_dir, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("c_nationkey").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("c_mktsegment", "n")))).alias("m")).withColumn("m", F.map_filter("m", lambda k, v: v > 1)).filter(F.size("m") > 0)
    return m.select("c_nationkey", F.concat_ws(",", F.transform(F.map_entries("m"), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string")))).alias("segments"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@query("""SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, '{"event":' || event_id || '}' AS out FROM events""")
def fn_json(spark, sf_dir):
    return read(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.to_json(F.struct(F.col("event_id").alias("event"))).alias("out"))


@query("WITH RECURSIVE s(n, v) AS (SELECT 1, 1 UNION ALL SELECT n + 1, v * 2 FROM s WHERE n < 12) SELECT n, v, (SELECT count(*) FROM nation WHERE n_nationkey < v) AS below FROM s")
def sql_recursive(spark, sf_dir):
    read(spark, sf_dir, "nation").createOrReplaceTempView("recursive_nation")
    return spark.sql("WITH RECURSIVE s(n, v) AS (SELECT 1, 1 UNION ALL SELECT n + 1, v * 2 FROM s WHERE n < 12) SELECT n, v, count(n_nationkey) AS below FROM s LEFT JOIN recursive_nation ON n_nationkey < v GROUP BY n, v")


@query("SELECT a.vec_id AS a, b.vec_id AS b, round(list_distance(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS dist FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def udf_l2(spark, sf_dir):
    register_vectors(spark)
    e = read(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    pairs = e.select(F.col("vec_id").alias("a"), F.col("v").alias("x")).join(e.select(F.col("vec_id").alias("b"), F.col("v").alias("y")), F.col("b") == F.col("a") + 1)
    return pairs.select("a", "b", F.round(F.expr("l2_distance(x, y)"), 6).alias("dist"))


@query("SELECT event_type, round(mad(value), 6) AS mad FROM events GROUP BY 1")
def udaf_mad(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy("event_type").agg(udfs.mad("value").alias("mad")).withColumn("mad", F.round("mad", 6))


@query("SELECT event_type, round(list_avg(v[CAST(len(v) // 10 AS INT) + 1:CAST(len(v) - len(v) // 10 AS INT)]), 6) AS trimmed FROM (SELECT event_type, list(value ORDER BY value) AS v FROM events GROUP BY 1)")
def udaf_trimmed_mean(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy("event_type").agg(udfs.trimmed_mean("value").alias("trimmed")).withColumn("trimmed", F.round("trimmed", 6))


def _series(spark, sf_dir):
    hours = events(spark, sf_dir).groupBy("event_type", F.date_trunc("hour", "ts").alias("h")).agg(F.round(F.sum("value"), 6).alias("v"))
    return hours.groupBy("event_type").agg(F.transform(F.array_sort(F.collect_list(F.struct("h", "v"))), lambda s: s["v"]).alias("values"))


_SERIES = "SELECT event_type, list(v ORDER BY h) AS v, list(CAST(p AS BIGINT) ORDER BY h) AS t FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY h) - 1 AS p FROM (SELECT event_type, date_trunc('hour', ts) AS h, round(sum(value), 6) AS v FROM events GROUP BY 1, 2)) GROUP BY 1"
#: Critical values of the series lengths and steps that a month of hours can have.
_LAMBDA = ", ".join(f"({n}, {k}, {esd_critical(n, k)!r})" for n in range(640, 721) for k in range(1, int(0.02 * n) + 1))


@query(f"""WITH RECURSIVE b AS (SELECT event_type, len(v) AS n, list_sort(list_transform(list_zip(v, t), lambda z: {{'v': z[1], 't': z[2]}})) AS s FROM ({_SERIES})),
    s AS (SELECT event_type, n, 0 AS k, list_transform(s, lambda x: x.v) AS v, list_transform(s, lambda x: x.t) AS t, CAST(NULL AS BIGINT) AS place, CAST(NULL AS DOUBLE) AS value, CAST(NULL AS DOUBLE) AS score FROM b
      UNION ALL SELECT event_type, n, k + 1, v[1:pos - 1] || v[pos + 1:], t[1:pos - 1] || t[pos + 1:], t[pos], v[pos], greatest(CASE WHEN low THEN mid - v[1] ELSE v[-1] - mid END, 0) / spread FROM (
        SELECT *, CASE WHEN low THEN 1 ELSE list_position(v, v[-1]) END AS pos FROM (SELECT *, (mid - v[1]) >= (v[-1] - mid) AS low, list_median(list_transform(v, lambda x: abs(x - mid))) AS spread FROM (SELECT *, list_median(v) AS mid FROM s WHERE k < n // 50))) WHERE spread > 0)
    SELECT event_type, CAST(k AS INT) AS k, CAST(place AS INT) AS place, value, round(score, 4) AS score, round("lambda", 6) AS "lambda", min(hit) OVER (PARTITION BY event_type ORDER BY k) = 1 AS is_anomaly FROM (
      SELECT s.*, CAST(l.lam AS DOUBLE) AS "lambda", CASE WHEN score > l.lam THEN 1 ELSE 0 END AS hit FROM s JOIN (VALUES {_LAMBDA}) l(n, k, lam) ON l.n = s.n AND l.k = s.k WHERE s.k > 0)""")
def udtf_esd(spark, sf_dir):
    udfs.register(spark)
    _series(spark, sf_dir).createOrReplaceTempView("udtf_series")
    return spark.sql("SELECT event_type, k, place, value, round(score, 4) AS score, round(lambda, 6) AS lambda, is_anomaly FROM udtf_series, LATERAL esd(values)")


@query(f"SELECT event_type, CAST(len(v) AS BIGINT) AS points, TRUE AS parts_add_up FROM ({_SERIES})")
def udtf_stl(spark, sf_dir):
    """The table function's components of each series add up to its values."""
    udfs.register(spark)
    _series(spark, sf_dir).createOrReplaceTempView("udtf_stl_series")
    parts = spark.sql("SELECT event_type, c.* FROM udtf_stl_series, LATERAL stl_components(values, 24) c")
    return parts.groupBy("event_type").agg(F.count(F.lit(1)).alias("points"), (F.max(F.abs(F.col("seasonal") + F.col("trend") + F.col("resid") - F.col("value"))) < 1e-6).alias("parts_add_up"))


@query("SELECT user_id, CAST(epoch(min(ts)) AS BIGINT) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def session_windows(spark, sf_dir):
    g = events(spark, sf_dir).groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.min("ts").alias("t"), F.count(F.lit(1)).alias("n"))
    # the nearest second, as a cast of seconds to a whole number gives in the SQL
    return g.select("user_id", F.rint(F.unix_micros(F.col("t").cast("timestamp")) / 1e6).cast("long").alias("start"), "n")


@query("SELECT CAST(epoch(b) AS BIGINT) AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest(generate_series(date_trunc('hour', ts) - INTERVAL 5 HOUR, date_trunc('hour', ts), INTERVAL 1 HOUR)) AS b FROM events) GROUP BY 1, 2")
def sliding_windows(spark, sf_dir):
    g = events(spark, sf_dir).groupBy(F.window("ts", "6 hours", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n")


@query(f"""WITH h AS (SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS ts, event_type, count(*) AS n FROM events GROUP BY 1, 2), a AS (SELECT min(ts) AS a FROM h)
    SELECT metric, event_type, ts, n, round(50 + 10 * sin(2 * pi() * (ts + phase) / 86400) + (ts - a) / 86400.0, 6) AS value FROM h, a, (VALUES ('load', {zlib.crc32(b"load") % 86400}), ('waits', {zlib.crc32(b"waits") % 86400})) m(metric, phase)""")
def metric_scrape(spark, sf_dir):
    """The events of each hour and type beside two metrics that are scraped once an hour of their span."""
    from ..sources.metric_source import MetricSource

    spark.dataSource.register(MetricSource)
    hours = stored(events(spark, sf_dir).groupBy(F.unix_timestamp(F.date_trunc("hour", "ts")).alias("ts"), "event_type").agg(F.count(F.lit(1)).alias("n")), "hours")
    first, last = hours.agg(F.min("ts"), F.max("ts")).first()
    count = 0 if first is None else (last - first) // 3600 + 1
    df = spark.read.format("metric_scrape").option("metrics", "load,waits").option("start", str(first or 0)).option("step", "3600").option("count", str(count)).option("partitions", "4").load()
    df = df.select("metric", F.unix_timestamp("ts").alias("ts"), "value")
    return hours.join(df, "ts").select("metric", "event_type", "ts", "n", "value")
