"""Operators and functions around the methods, on the star-schema and event tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import fold, tokens
from ..functions.timegrid import month_date, month_ix, months
from ..operators.joins import asof_join, checked_broadcast, checked_cross, cosine, interval_join, salted_count, salted_join
from ..sources.tables import table
from ..streaming import histograms
from . import setup as s

QUERIES, ORACLE_SQL = {}, {}


def query(sql: str | None):
    """Registers a query with its SQL."""
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


@query("SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_shipdate < TIMESTAMP '1998-01-01'")
def scan_prune(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two columns and two filters, all of which reach the scan."""
    return table(spark, sf_dir, "lineitem").where("l_quantity > 45 and l_shipdate < timestamp_ntz '1998-01-01'").select("l_orderkey", "l_quantity")


@query("SELECT p_partkey FROM part WHERE (p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#21')) OR p_name LIKE '%a%' OR regexp_matches(p_type, '^S.*L$') OR p_retailprice IS NOT DISTINCT FROM 900.0")
def filter_mix(spark, sf_dir):
    c = F.col
    return table(spark, sf_dir, "part").where((c("p_size").between(5, 20) & c("p_brand").isin("Brand#11", "Brand#12", "Brand#21")) | c("p_name").like("%a%") | c("p_type").rlike("^S.*L$") | c("p_retailprice").eqNullSafe(900.0)).select("p_partkey")


@query("SELECT c_custkey, upper(c_mktsegment) AS segment, round(c_acctbal * 1.1, 2) AS balance, c_acctbal < 0 AS negative FROM customer")
def project_mix(spark, sf_dir):
    made = table(spark, sf_dir, "customer").select(F.struct("c_custkey", F.upper("c_mktsegment").alias("segment"), F.round(F.col("c_acctbal") * 1.1, 2).alias("balance")).alias("s"), (F.col("c_acctbal") < 0).alias("negative"))
    return made.select("s.c_custkey", "s.segment", "s.balance", "negative")


_JOIN = "SELECT o_orderkey, count(*) AS lines, CAST(sum(CAST(l_extendedprice * (1 - l_discount) AS DECIMAL(18, 4))) AS DOUBLE) AS revenue FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1"


def _revenue(spark, sf_dir, hint=None):
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_extendedprice", "l_discount")
    orders = table(spark, sf_dir, "orders", "o_orderkey")
    met = (orders.hint(hint) if hint else orders).join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    return met.groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("lines"), F.sum((F.col("l_extendedprice") * (1 - F.col("l_discount"))).cast("decimal(18,4)")).cast("double").alias("revenue"))


@query(_JOIN)
def join_inner(spark, sf_dir):
    return _revenue(spark, sf_dir)


@query(_JOIN)
def join_shuffle_hash(spark, sf_dir):
    return _revenue(spark, sf_dir, "shuffle_hash")


@query("SELECT n_name, r_name, count(*) AS customers FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY 1, 2")
def join_broadcast(spark, sf_dir):
    nations = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("r_regionkey") == F.col("n_regionkey"))
    return table(spark, sf_dir, "customer", "c_nationkey").join(checked_broadcast(nations), F.col("n_nationkey") == F.col("c_nationkey")).groupBy("n_name", "r_name").agg(F.count(F.lit(1)).alias("customers"))


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def join_left(spark, sf_dir):
    return table(spark, sf_dir, "customer", "c_custkey").join(table(spark, sf_dir, "orders", "o_custkey", "o_orderkey"), F.col("o_custkey") == F.col("c_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def join_semi(spark, sf_dir):
    big = table(spark, sf_dir, "orders", "o_custkey", "o_totalprice").where("o_totalprice > 300000")
    return table(spark, sf_dir, "customer", "c_custkey").join(big, F.col("o_custkey") == F.col("c_custkey"), "left_semi")


@query("SELECT doc_id FROM documents WHERE NOT EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = documents.doc_id)")
def join_anti(spark, sf_dir):
    return table(spark, sf_dir, "documents", "doc_id").join(table(spark, sf_dir, "labels", "doc_id"), "doc_id", "left_anti")


@query("SELECT coalesce(c_nationkey, s_nationkey) AS nation, coalesce(customers, 0) AS customers, coalesce(suppliers, 0) AS suppliers FROM (SELECT c_nationkey, count(*) AS customers FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS suppliers FROM supplier GROUP BY 1) ON c_nationkey = s_nationkey")
def join_full(spark, sf_dir):
    c = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("customers"))
    return c.join(table(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("suppliers")), "nation", "full").na.fill(0)


_SPANS = f"spans AS (SELECT o_custkey, min({s.MONTH}) AS a, max({s.MONTH}) AS b FROM orders GROUP BY 1)"


@query(f"WITH {_SPANS}, g AS (SELECT unnest(range(0, 80, 7)) AS m) SELECT m AS month_ix, count(*) AS active FROM spans JOIN g ON a <= m AND m <= b GROUP BY 1")
def join_interval(spark, sf_dir):
    """Customers active in sampled months: months inside spans, bucketed by year."""
    at = table(spark, sf_dir, "orders").select("o_custkey", month_ix(F.col("o_orderdate")).alias("m"))
    spans = at.groupBy("o_custkey").agg(F.min("m").alias("a"), F.max("m").alias("b")).withColumn("all", F.lit(1))
    grid = months(spark, 79, 7).withColumn("all", F.lit(1))
    return interval_join(grid, spans, ["all"], "month_ix", "a", "b", 12).groupBy("month_ix").agg(F.count(F.lit(1)).alias("active"))


@query(f"WITH o AS (SELECT o_custkey, {s.MONTH} AS m, max(o_totalprice) AS price FROM orders GROUP BY 1, 2), g AS (SELECT c_custkey, unnest(range(0, 80, 10)) AS m FROM customer) SELECT c_custkey, g.m AS month_ix, price FROM g ASOF LEFT JOIN o ON o.o_custkey = g.c_custkey AND g.m >= o.m")
def join_asof(spark, sf_dir):
    """Each customer's latest monthly top order at or before sampled months."""
    o = table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("c_custkey"), month_ix(F.col("o_orderdate")).alias("month_ix")).agg(F.max("o_totalprice").alias("price"))
    g = checked_cross(table(spark, sf_dir, "customer", "c_custkey"), months(spark, 79, 10))
    return asof_join(g, o, ["c_custkey"], "month_ix", ["price"])


@query("SELECT r_name, month_ix FROM region CROSS JOIN (SELECT unnest(range(0, 80)) AS month_ix)")
def join_cross(spark, sf_dir):
    return checked_cross(table(spark, sf_dir, "region", "r_name"), months(spark))


@query("SELECT a.n_name AS one, b.n_name AS other FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_theta(spark, sf_dir):
    n = table(spark, sf_dir, "nation")
    return n.alias("a").join(n.alias("b"), F.expr("a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("one"), F.col("b.n_name").alias("other"))


@query("SELECT source, count(*) AS documents, sum(quality) AS good FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def join_salted(spark, sf_dir):
    met = salted_join(table(spark, sf_dir, "documents", "doc_id", "source"), table(spark, sf_dir, "labels", "doc_id", "quality"), "doc_id", 4)
    return met.groupBy("source").agg(F.count(F.lit(1)).alias("documents"), F.sum("quality").alias("good"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, round(stddev_samp(l_discount), 6) AS spread, min(l_shipdate) AS first FROM lineitem GROUP BY 1, 2")
def agg_basic(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.round(F.stddev("l_discount"), 6).alias("spread"), F.min("l_shipdate").alias("first"))


@query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders"))


@query("SELECT source, lang, count(*) AS n FROM documents GROUP BY 1, 2")
def agg_salted(spark, sf_dir):
    return salted_count(table(spark, sf_dir, "documents", "source", "lang"), ["source", "lang"])


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, TRUE AS parts_near, count(DISTINCT l_orderkey) AS orders, TRUE AS orders_near, TRUE AS median_near FROM lineitem GROUP BY 1")
def agg_approx(spark, sf_dir):
    """Sketches beside exact answers: distinct counts within a tenth, the median between the 49th and 51st percentile."""
    lines = table(spark, sf_dir, "lineitem").groupBy("l_returnflag")
    c = F.col
    sketched = lines.agg(F.approx_count_distinct("l_partkey", 0.02).alias("p"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("o"), F.percentile_approx("l_extendedprice", 0.5).alias("m"))
    exact = lines.agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders"), F.percentile("l_extendedprice", F.array(F.lit(0.49), F.lit(0.51))).alias("around"))
    near = lambda got, want: F.abs(c(got) - c(want)) <= 0.1 * c(want)
    return sketched.join(exact, "l_returnflag").select("l_returnflag", "parts", near("p", "parts").alias("parts_near"), "orders", near("o", "orders").alias("orders_near"), c("m").between(c("around")[0], c("around")[1]).alias("median_near"))


_SETS = "grouping(lang) AS no_lang, count(*) AS n FROM documents GROUP BY"


@query(f"SELECT source, lang, {_SETS} CUBE (source, lang)")
def agg_cube(spark, sf_dir):
    return table(spark, sf_dir, "documents").cube("source", "lang").agg(F.grouping("lang").cast("long").alias("no_lang"), F.count(F.lit(1)).alias("n"))


@query(f"SELECT source, lang, {_SETS} ROLLUP (source, lang)")
def agg_rollup(spark, sf_dir):
    return table(spark, sf_dir, "documents").rollup("source", "lang").agg(F.grouping("lang").cast("long").alias("no_lang"), F.count(F.lit(1)).alias("n"))


@query(f"SELECT source, lang, {_SETS} GROUPING SETS ((source), (lang))")
def agg_gsets(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return docs.groupingSets([[F.col("source")], [F.col("lang")]], "source", "lang").agg(F.grouping("lang").cast("long").alias("no_lang"), F.count(F.lit(1)).alias("n"))


@query("SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr, count(*) FILTER (lang = 'de') AS de FROM documents GROUP BY 1")
def agg_pivot(spark, sf_dir):
    wide = table(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["en", "fr", "de"]).agg(F.count(F.lit(1)))
    return wide.na.fill(0)


@query("SELECT s_suppkey, 'nation' AS field, CAST(s_nationkey AS DOUBLE) AS value FROM supplier UNION ALL SELECT s_suppkey, 'balance', s_acctbal FROM supplier")
def agg_unpivot(spark, sf_dir):
    return table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance")).unpivot("s_suppkey", ["nation", "balance"], "field", "value")


_W = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"


@query(f"SELECT o_orderkey, row_number() {_W} AS rn, rank() {_W} AS rk, dense_rank() {_W} AS dr, round(percent_rank() {_W}, 6) AS pr, ntile(4) {_W} AS nt FROM orders")
def win_rank(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.ntile(4).over(w).alias("nt"))


_F = "(PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"


@query(f"SELECT o_orderkey, lag(o_totalprice) {_W} AS before, lead(o_totalprice, 2) {_W} AS later, first_value(o_totalprice) OVER {_F} AS first, last_value(o_totalprice) OVER {_F} AS last, nth_value(o_totalprice, 2) OVER {_F} AS second FROM orders")
def win_lag(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    p = "o_totalprice"
    return table(spark, sf_dir, "orders").select("o_orderkey", F.lag(p).over(w).alias("before"), F.lead(p, 2).over(w).alias("later"), F.first(p).over(full).alias("first"), F.last(p).over(full).alias("last"), F.nth_value(p, 2).over(full).alias("second"))


_MONTHLY = f"monthly AS (SELECT {s.MONTH} AS month_ix, count(*) AS n FROM orders GROUP BY 1)"


@query(f"WITH {_MONTHLY} SELECT month_ix, CAST(sum(n) OVER (ORDER BY month_ix ROWS UNBOUNDED PRECEDING) AS BIGINT) AS total, round(avg(n) OVER (ORDER BY month_ix RANGE BETWEEN 1 PRECEDING AND 1 FOLLOWING), 6) AS smooth FROM monthly")
def win_frame(spark, sf_dir):
    """Prefix sums and three-month smoothing over the calendar (80 rows)."""
    m = table(spark, sf_dir, "orders").groupBy(month_ix(F.col("o_orderdate")).alias("month_ix")).agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy("month_ix")
    return m.select("month_ix", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("total"), F.round(F.avg("n").over(w.rangeBetween(-1, 1)), 6).alias("smooth"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def topk_global(spark, sf_dir):
    return table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


@query("SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def topk_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, sf_dir, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@query("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def set_union(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).union(table(spark, sf_dir, "supplier").select("s_nationkey")).distinct()


@query("SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def set_intersect(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(table(spark, sf_dir, "supplier").select("s_nationkey"))


@query("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def set_except(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(table(spark, sf_dir, "supplier").select("s_nationkey"))


_SUBQ = "SELECT c_custkey, (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) AS orders FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer) AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F') AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey < 3)"


@query(_SUBQ)
def subq_mix(spark, sf_dir):
    """Scalar, correlated, EXISTS and IN subqueries, as SQL."""
    for t in ("customer", "orders", "nation"):
        table(spark, sf_dir, t).createOrReplaceTempView(f"sub_{t}")
    sql = _SUBQ
    for t in ("customer", "orders", "nation"):
        sql = sql.replace(f"FROM {t}", f"FROM sub_{t}")
    return spark.sql(sql)


@query(f"SELECT doc_id, length({s.sql_fold('text')}) AS chars, substr({s.sql_fold('text')}, 1, 12) AS head, sha256(text) AS digest, concat_ws('/', source, lang) AS place, len({s.sql_tokens('text')}) AS words, levenshtein(substr({s.sql_fold('text')}, 1, 40), substr({s.sql_fold('text')}, 21, 40)) AS shift FROM documents")
def fn_string(spark, sf_dir):
    t = fold(F.col("text"))
    return table(spark, sf_dir, "documents").select("doc_id", F.char_length(t).cast("long").alias("chars"), F.substring(t, 1, 12).alias("head"), F.sha2("text", 256).alias("digest"), F.concat_ws("/", "source", "lang").alias("place"), F.size(tokens(F.col("text"))).cast("long").alias("words"), F.levenshtein(F.substring(t, 1, 40), F.substring(t, 21, 40)).cast("long").alias("shift"))


@query(f"SELECT o_orderkey, {s.MONTH} AS month_ix, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS first_day, year(o_orderdate) AS y, CAST(CAST(o_orderdate + INTERVAL 2 MONTH AS DATE) AS VARCHAR) AS later, dayofyear(o_orderdate) AS doy FROM orders")
def fn_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders").select("o_orderkey", month_ix(d).alias("month_ix"), month_date(month_ix(d)).cast("string").alias("first_day"), F.year(d).alias("y"), F.add_months(d.cast("date"), 2).cast("string").alias("later"), F.dayofyear(d).alias("doy"))


@query("SELECT l_orderkey, l_linenumber, l_partkey, round(ln(l_extendedprice), 6) AS a, round(exp(l_discount), 6) AS b, greatest(l_quantity, 10.0) AS c, round(pow(l_tax, 2), 6) AS d, round(log2(l_quantity), 6) AS e, l_partkey % 7 AS f FROM lineitem")
def fn_math(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.log("l_extendedprice"), 6).alias("a"), F.round(F.exp("l_discount"), 6).alias("b"), F.greatest("l_quantity", F.lit(10.0)).alias("c"), F.round(F.pow("l_tax", F.lit(2)), 6).alias("d"), F.round(F.log2("l_quantity"), 6).alias("e"), (F.col("l_partkey") % 7).alias("f"))


@query(f"WITH t AS (SELECT doc_id, {s.sql_tokens('text')} AS w FROM documents) SELECT doc_id, len(list_distinct(w)) AS kinds, array_to_string(list_sort(w[1:5]), ' ') AS head, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS chars, len(list_filter(w, lambda x: length(x) > 8)) AS long, len(list_intersect(w[1:50], w[51:100])) AS both FROM t")
def fn_array(spark, sf_dir):
    t = table(spark, sf_dir, "documents").select("doc_id", tokens(F.col("text")).alias("w"))
    total = F.aggregate("w", F.lit(0).cast("long"), lambda a, x: a + F.char_length(x))
    return t.select("doc_id", F.size(F.array_distinct("w")).cast("long").alias("kinds"), F.array_join(F.array_sort(F.slice("w", 1, 5)), " ").alias("head"), total.alias("chars"), F.size(F.filter("w", lambda x: F.char_length(x) > 8)).cast("long").alias("long"), F.size(F.array_intersect(F.slice("w", 1, 50), F.slice("w", 51, 50))).cast("long").alias("both"))


@query("SELECT source, count(*) FILTER (lang = 'en') AS en, count(DISTINCT lang) AS langs FROM documents GROUP BY 1")
def fn_map(spark, sf_dir):
    per = table(spark, sf_dir, "documents").groupBy("source", "lang").agg(F.count(F.lit(1)).alias("n"))
    m = per.groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"))
    return m.select("source", F.coalesce(F.try_element_at("m", F.lit("en")), F.lit(0).cast("long")).alias("en"), F.size(F.map_keys("m")).cast("long").alias("langs"))


@query("SELECT event_type, count(*) AS n, CAST(sum(CAST(json_extract_string(props, '$.k') AS INTEGER)) AS BIGINT) AS total FROM events GROUP BY 1")
def fn_json(spark, sf_dir):
    k = F.from_json("props", "k int")["k"]
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(k).alias("total"))


@query("WITH f AS (SELECT embedding AS e FROM embeddings ORDER BY vec_id LIMIT 1) SELECT vec_id, round(list_cosine_similarity(CAST(embedding AS DOUBLE[]), CAST(e AS DOUBLE[])), 6) AS cosine FROM embeddings, f")
def fn_vector(spark, sf_dir):
    """Cosine of every vector to the first one: semantic twins of one text."""
    v = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    first = v.orderBy("vec_id").limit(1).select(F.col("embedding").alias("e"))
    return v.crossJoin(F.broadcast(first)).select("vec_id", F.round(cosine(F.col("embedding"), F.col("e")), 6).alias("cosine"))


@query("SELECT CAST(time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS VARCHAR) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return histograms.tumbling(table(spark, sf_dir, "events")).withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query("WITH d AS (SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS day FROM events), w AS (SELECT day AS start FROM d UNION ALL SELECT day - INTERVAL 1 DAY FROM d) SELECT CAST(start AS VARCHAR) AS start, count(*) AS n FROM w GROUP BY 1")
def stream_sliding(spark, sf_dir):
    return histograms.sliding(table(spark, sf_dir, "events")).withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query("WITH m AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS opens FROM events), k AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM m) SELECT user_id, epoch_us(min(ts)) AS start, epoch_us(max(ts)) AS last, count(*) AS n FROM k GROUP BY user_id, no")
def stream_session(spark, sf_dir):
    out = histograms.sessions(table(spark, sf_dir, "events"))
    return out.select("user_id", F.unix_micros(F.col("start").cast("timestamp")).alias("start"), F.unix_micros(F.col("end").cast("timestamp") - F.expr("INTERVAL 6 HOURS")).alias("last"), "n")


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf_dir):
    return histograms.distinct_copies(table(spark, sf_dir, "events", "user_id", "event_type"), ["user_id", "event_type"])
