"""Relational operators that users of the corpora need around the methods, each on given tables and each with a SQL oracle."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pairbundle.sources.corpora import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def op(oracle: str | None = None):
    def add(f):
        QUERIES[f"op_{f.__name__}"] = f
        if oracle:
            ORACLES[f"op_{f.__name__}"] = oracle
        return f

    return add


def _t(name: str):
    return lambda spark, sf_dir: table(spark, sf_dir, name)


orders, lineitem, customer, nation, region, part, supplier, events, documents, conversations, labels, benchmark, embeddings, pages = map(_t, ("orders", "lineitem", "customer", "nation", "region", "part", "supplier", "events", "documents", "conversations", "labels", "benchmark", "embeddings", "pages"))


# Sources and sinks: written to the shared folder and read again


def _through(df: DataFrame, label: str, write, read) -> DataFrame:
    from pairbundle.sources.shared import shared_path

    path = shared_path(df.sparkSession, label)
    write(df.write, path)
    return read(df.sparkSession.read, path)


@op("SELECT p_partkey, p_brand FROM part")
def scan_parquet(s, d):
    return part(s, d).select("p_partkey", "p_brand")


@op("SELECT page_id, url FROM pages")
def scan_jsonl(s, d):
    return _through(pages(s, d).select("page_id", "url"), "jsonl", lambda w, p: w.json(p), lambda r, p: r.schema("page_id long, url string").json(p))


@op("SELECT c_custkey, c_name, c_acctbal FROM customer")
def scan_csv(s, d):
    return _through(customer(s, d).select("c_custkey", "c_name", "c_acctbal"), "csv", lambda w, p: w.option("header", True).csv(p), lambda r, p: r.schema("c_custkey long, c_name string, c_acctbal double, _bad string").option("header", True).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_bad").csv(p)).select("c_custkey", "c_name", "c_acctbal")


@op("SELECT item_id, text FROM benchmark")
def scan_orc(s, d):
    return _through(benchmark(s, d), "orc", lambda w, p: w.orc(p), lambda r, p: r.orc(p)).select("item_id", "text")


@op("SELECT r_name AS value FROM region")
def scan_text(s, d):
    return _through(region(s, d).select(F.col("r_name").alias("value")), "text", lambda w, p: w.text(p), lambda r, p: r.text(p))


@op("SELECT r_name AS media, strlen(r_name)::BIGINT AS bytes FROM region")
def scan_binary(s, d):
    return _through(region(s, d).repartition(5, "r_name").select(F.col("r_name").alias("value")), "binary", lambda w, p: w.option("lineSep", "\n").text(p), lambda r, p: r.format("binaryFile").option("pathGlobFilter", "part-*").load(p)).select(F.explode(F.filter(F.split(F.decode("content", "UTF-8"), "\n"), lambda x: x != "")).alias("media")).select("media", F.octet_length("media").cast("long").alias("bytes"))


@op("SELECT event_type, count(*)::BIGINT AS n FROM events WHERE event_type = 'click' GROUP BY 1")
def sink_partitioned(s, d):
    out = _through(events(s, d), "partitioned", lambda w, p: w.partitionBy("event_type").parquet(p), lambda r, p: r.parquet(p))
    return out.where("event_type = 'click'").groupBy("event_type").agg(F.count("*").alias("n"))


@op("SELECT o_orderkey, o_custkey FROM orders")
def sink_sized(s, d):
    return _through(orders(s, d).select("o_orderkey", "o_custkey"), "sized", lambda w, p: w.option("maxRecordsPerFile", 5000).parquet(p), lambda r, p: r.parquet(p))


@op("SELECT o_custkey, count(*)::BIGINT AS n FROM orders GROUP BY 1")
def sink_bucketed(s, d):
    name = f"pb_bucketed_{abs(hash((d, id(s)))) % 10**8}"
    s.sql(f"DROP TABLE IF EXISTS {name}")
    orders(s, d).select("o_orderkey", "o_custkey").write.bucketBy(8, "o_custkey").sortBy("o_custkey").mode("overwrite").saveAsTable(name)
    return s.table(name).groupBy("o_custkey").agg(F.count("*").alias("n"))


# Projection and filters


@op("SELECT o_orderkey AS order_id, o_totalprice FROM orders")
def project(s, d):
    return orders(s, d).select(F.col("o_orderkey").alias("order_id"), "o_totalprice")


@op("SELECT o_orderkey, o_custkey AS customer_id FROM orders")
def rename(s, d):
    return orders(s, d).select("o_orderkey", "o_custkey").withColumnRenamed("o_custkey", "customer_id")


@op("SELECT p_partkey, p_size::VARCHAR AS size_text, floor(p_retailprice)::BIGINT AS whole FROM part")
def cast(s, d):
    return part(s, d).select("p_partkey", F.col("p_size").cast("string").alias("size_text"), F.floor("p_retailprice").cast("long").alias("whole"))


@op("SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'middle' ELSE 'low' END AS band FROM orders")
def case_when(s, d):
    p = F.col("o_totalprice")
    return orders(s, d).select("o_orderkey", F.when(p > 200000, "high").when(p > 100000, "middle").otherwise("low").alias("band"))


@op("SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND NOT l_discount > 0.05")
def filter_range(s, d):
    return lineitem(s, d).where(F.col("l_quantity").between(10, 20) & ~(F.col("l_discount") > 0.05)).select("l_orderkey", "l_quantity")


@op("SELECT c_custkey FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY') OR c_nationkey = 3")
def filter_in(s, d):
    return customer(s, d).where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") | (F.col("c_nationkey") == 3)).select("c_custkey")


@op("SELECT p_partkey FROM part WHERE p_type LIKE '%STEEL%'")
def filter_like(s, d):
    return part(s, d).where(F.col("p_type").like("%STEEL%")).select("p_partkey")


@op("SELECT doc_id FROM documents WHERE text IS NOT NULL AND lang IS NOT NULL")
def filter_null(s, d):
    return documents(s, d).where("text IS NOT NULL AND lang IS NOT NULL").select("doc_id")


@op("SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3}-[0-9]{4}')")
def filter_regex(s, d):
    return documents(s, d).where(F.col("text").rlike("[0-9]{3}-[0-9]{4}")).select("doc_id")


@op("SELECT conv_id, first_role, text FROM (SELECT conv_id, role AS first_role, text, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS k FROM conversations) WHERE k = 1")
def nested_access(s, d):
    turns = conversations(s, d).groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    return turns.select("conv_id", F.element_at("turns", 1).getField("role").alias("first_role"), F.col("turns")[0]["text"].alias("text"))


# Joins

_CO = "c_custkey, o_orderkey FROM customer {} JOIN orders ON c_custkey = o_custkey"


def _customer_orders(s, d, how):
    c, o = customer(s, d).select("c_custkey"), orders(s, d).select("o_orderkey", "o_custkey")
    return c.join(o, c.c_custkey == o.o_custkey, how).select("c_custkey", "o_orderkey")


for _how in ("inner", "left", "right", "full"):
    QUERIES[f"op_join_{_how}"] = lambda s, d, how=_how: _customer_orders(s, d, how)
    ORACLES[f"op_join_{_how}"] = "SELECT " + _CO.format(_how.upper())


@op("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def join_broadcast(s, d):
    """25 nations: the side is bounded by its meaning."""
    return customer(s, d).join(F.broadcast(nation(s, d)), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


_OL = "SELECT o_orderkey, count(*)::BIGINT AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def _lines(s, d, hint):
    o, l = orders(s, d).select("o_orderkey"), lineitem(s, d).select("l_orderkey")  # noqa: E741
    return o.hint(hint).join(l, o.o_orderkey == l.l_orderkey).groupBy("o_orderkey").agg(F.count("*").alias("lines"))


@op(_OL)
def join_shuffle_hash(s, d):
    return _lines(s, d, "shuffle_hash")


@op(_OL)
def join_sort_merge(s, d):
    return _lines(s, d, "merge")


@op("SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(s, d):
    return documents(s, d).join(labels(s, d), "doc_id", "left_semi").select("doc_id", "source")


@op("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_anti(s, d):
    l = lineitem(s, d).select("l_orderkey")  # noqa: E741
    return orders(s, d).join(l, F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@op("SELECT r_name, n_name FROM region JOIN nation ON n_regionkey > r_regionkey")
def join_theta(s, d):
    return region(s, d).join(nation(s, d), F.col("n_regionkey") > F.col("r_regionkey")).select("r_name", "n_name")


@op("SELECT e.event_id, e.user_id, (SELECT max(v.event_id) FROM events v WHERE v.user_id = e.user_id AND v.event_type = 'view' AND (v.ts, v.event_id) < (e.ts, e.event_id)) AS last_view FROM events e WHERE e.event_type = 'purchase'" if False else "SELECT event_id, user_id, last_view FROM (SELECT event_id, user_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_view FROM events) WHERE event_type = 'purchase'")
def join_asof(s, d):
    """The last view before each purchase of a user."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = events(s, d).withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", "user_id", "last_view")


@op("SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def join_interval(s, d):
    """Purchases within six hours of a click: bins of six hours on both sides, then the condition."""
    e = events(s, d).withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    span = 6 * 3600 * 1_000_000
    cell = F.floor(F.col("t") / span)
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("t").alias("ta"), F.explode(F.array(cell, cell + 1)).alias("cell"))
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("t").alias("tb"), cell.alias("cell"))
    return a.join(b, ["user_id", "cell"]).where((F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + span)).select("click_id", "purchase_id")


@op("SELECT n_nationkey, share FROM nation, range(10, 101, 10) s(share)")
def join_cross(s, d):
    shares = s.range(10, 101, 10).withColumnRenamed("id", "share")
    return nation(s, d).select(F.col("n_nationkey")).crossJoin(F.broadcast(shares))


@op("SELECT a.doc_id AS first_id, b.doc_id AS second_id FROM documents a JOIN documents b ON md5(a.text) = md5(b.text) AND a.doc_id < b.doc_id")
def join_self(s, d):
    """Pairs of copies, within groups that are small here; the dedup operators work without pairs."""
    x = documents(s, d).select("doc_id", F.md5("text").alias("h"))
    return x.alias("a").join(x.alias("b"), (F.col("a.h") == F.col("b.h")) & (F.col("a.doc_id") < F.col("b.doc_id"))).select(F.col("a.doc_id").alias("first_id"), F.col("b.doc_id").alias("second_id"))


@op("SELECT o_custkey AS c_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 2 AND o_custkey IN (SELECT c_custkey FROM customer)")
def join_lateral(s, d):
    """The two largest orders of each customer."""
    customer(s, d).createOrReplaceTempView("pb_customer")
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    orders(s, d).withColumn("k", F.row_number().over(w)).createOrReplaceTempView("pb_ranked")
    return s.sql("SELECT c_custkey, o_orderkey FROM pb_customer, LATERAL (SELECT o_orderkey FROM pb_ranked WHERE o_custkey = c_custkey AND k <= 2)")


# Aggregation


@op("SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, sum(l_quantity::BIGINT)::BIGINT AS quantity, round(avg(l_discount), 6) AS discount, max(l_extendedprice) AS most FROM lineitem GROUP BY 1, 2")
def agg_group(s, d):
    return lineitem(s, d).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"), F.max("l_extendedprice").alias("most"))


@op("SELECT count(*)::BIGINT AS n, min(o_totalprice) AS least, round(stddev_samp(o_totalprice), 4) AS deviation, round(skewness(o_totalprice), 4) AS skew FROM orders")
def agg_global(s, d):
    """Spark's skewness is the population's; the sample's adjusts it by the number of rows, as the SQL does."""
    n = F.count("*")
    sample = F.skewness("o_totalprice") * F.sqrt(n * (n - 1)) / (n - 2)
    return orders(s, d).agg(n.alias("n"), F.min("o_totalprice").alias("least"), F.round(F.stddev("o_totalprice"), 4).alias("deviation"), F.round(sample, 4).alias("skew"))


@op("SELECT lang, count(DISTINCT md5(text))::BIGINT AS texts, count(DISTINCT source)::BIGINT AS sources FROM documents GROUP BY 1")
def agg_distinct(s, d):
    return documents(s, d).groupBy("lang").agg(F.countDistinct(F.md5("text")).alias("texts"), F.countDistinct("source").alias("sources"))


@op("SELECT lang, true AS close FROM documents GROUP BY 1")
def agg_approx_distinct(s, d):
    x = documents(s, d).groupBy("lang").agg(F.approx_count_distinct("text", 0.02).alias("a"), F.countDistinct("text").alias("e"))
    return x.select("lang", (F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e") + 2).alias("close"))


@op("SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles FROM conversations GROUP BY 1")
def agg_collect_ordered(s, d):
    turns = F.array_sort(F.collect_list(F.struct("turn", "role")))
    return conversations(s, d).groupBy("conv_id").agg(F.array_join(F.transform(turns, lambda t: t["role"]), ",").alias("roles"))


@op("SELECT source, arg_min(doc_id, (n_chars, doc_id)) AS shortest, arg_max(doc_id, (n_chars, doc_id)) AS longest FROM documents GROUP BY 1")
def agg_argmin(s, d):
    key = F.struct("n_chars", "doc_id")
    return documents(s, d).groupBy("source").agg(F.min_by("doc_id", key).alias("shortest"), F.max_by("doc_id", key).alias("longest"))


@op("SELECT user_id, count(*) FILTER (WHERE event_type = 'click')::BIGINT AS clicks, count(*) FILTER (WHERE value > 50)::BIGINT AS large FROM events GROUP BY 1")
def agg_filtered(s, d):
    return events(s, d).groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.expr("count(1) FILTER (WHERE value > 50)").alias("large"))


@op("SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS median FROM documents GROUP BY 1")
def agg_percentile(s, d):
    return documents(s, d).groupBy("lang").agg(F.round(F.percentile("n_chars", F.lit(0.5)), 4).alias("median"))


@op("SELECT n_regionkey, string_agg(n_name, ';' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def agg_listagg(s, d):
    nation(s, d).createOrReplaceTempView("pb_nation")
    return s.sql("SELECT n_regionkey, listagg(n_name, ';') WITHIN GROUP (ORDER BY n_name) AS names FROM pb_nation GROUP BY n_regionkey")


_G = "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n FROM lineitem GROUP BY {}"


@op(_G.format("GROUPING SETS ((l_returnflag), (l_linestatus), ())"))
def agg_grouping_sets(s, d):
    lineitem(s, d).createOrReplaceTempView("pb_lineitem")
    return s.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM pb_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


@op(_G.format("CUBE (l_returnflag, l_linestatus)"))
def agg_cube(s, d):
    return lineitem(s, d).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@op(_G.format("ROLLUP (l_returnflag, l_linestatus)"))
def agg_rollup(s, d):
    return lineitem(s, d).rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@op("SELECT user_id, count(*) FILTER (WHERE event_type = 'click')::BIGINT AS click, count(*) FILTER (WHERE event_type = 'view')::BIGINT AS view FROM events GROUP BY 1")
def agg_pivot(s, d):
    return events(s, d).groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).fillna(0)


@op("SELECT p_partkey, unnest(['p_brand', 'p_type']) AS field, unnest([p_brand, p_type]) AS value FROM part")
def agg_unpivot(s, d):
    return part(s, d).unpivot("p_partkey", ["p_brand", "p_type"], "field", "value")


@op("SELECT lines, count(*)::BIGINT AS orders FROM (SELECT l_orderkey, count(*)::BIGINT AS lines FROM lineitem GROUP BY 1) GROUP BY 1")
def agg_ratio_histogram(s, d):
    return lineitem(s, d).groupBy("l_orderkey").agg(F.count("*").alias("lines")).groupBy("lines").agg(F.count("*").alias("orders"))


# Windows

_W = "OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)"


@op(f"SELECT o_orderkey, row_number() {_W}::INTEGER AS rn, rank() {_W}::INTEGER AS rk, dense_rank() {_W}::INTEGER AS dr, ntile(3) {_W}::INTEGER AS nt, round(percent_rank() {_W}, 6) AS pr, round(cume_dist() {_W}, 6) AS cd FROM orders")
def win_rank(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return orders(s, d).select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(3).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


_E = "OVER (PARTITION BY user_id ORDER BY ts, event_id"


@op(f"SELECT event_id, lag(event_id) {_E}) AS before, lead(event_id) {_E}) AS after, first_value(event_id) {_E}) AS first_id, nth_value(event_id, 2) {_E} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_id FROM events")
def win_offset(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return events(s, d).select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(whole).alias("second_id"))


@op("SELECT o_orderkey, sum(round(o_totalprice * 100)::BIGINT) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING)::BIGINT AS running FROM orders")
def win_running_rows(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return orders(s, d).select("o_orderkey", F.sum(F.round(F.col("o_totalprice") * 100).cast("long")).over(w).alias("running"))


@op("SELECT o_orderkey, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving FROM orders")
def win_moving_rows(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return orders(s, d).select("o_orderkey", F.round(F.avg("o_totalprice").over(w), 4).alias("moving"))


@op("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY datediff('day', DATE '1970-01-01', o_orderdate::DATE) RANGE BETWEEN 30 PRECEDING AND CURRENT ROW)::BIGINT AS recent FROM orders")
def win_range_days(s, d):
    day = F.unix_date(F.col("o_orderdate").cast("date"))
    w = Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-30, 0)
    return orders(s, d).withColumn("day", day).select("o_orderkey", F.count("*").over(w).alias("recent"))


@op("SELECT doc_id, (sum(n_chars) OVER (ORDER BY doc_id) - n_chars)::BIGINT AS before FROM documents")
def win_global_prefix(s, d):
    from pairbundle.operators.addressing import prefix_sum

    return prefix_sum(documents(s, d).select("doc_id", "n_chars"), ["doc_id"], {"before": "n_chars"}).select("doc_id", "before")


# Sort, limit, top-k


@op("SELECT l_orderkey, l_extendedprice FROM lineitem")
def sort_global(s, d):
    return lineitem(s, d).select("l_orderkey", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey")


@op("SELECT l_orderkey, l_shipdate::DATE AS day FROM lineitem")
def sort_local(s, d):
    return lineitem(s, d).select("l_orderkey", F.col("l_shipdate").cast("date").alias("day")).sortWithinPartitions("day", "l_orderkey")


@op("SELECT md5(text) AS fingerprint, count(*)::BIGINT AS copies FROM documents GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10")
def top_k(s, d):
    return documents(s, d).groupBy(F.md5("text").alias("fingerprint")).agg(F.count("*").alias("copies")).orderBy(F.desc("copies"), "fingerprint").limit(10)


@op("SELECT source, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS k FROM documents) WHERE k <= 3")
def top_k_per_group(s, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return documents(s, d).withColumn("k", F.row_number().over(w)).where("k <= 3").select("source", "doc_id", "n_chars")


@op("SELECT c_custkey FROM customer ORDER BY 1 LIMIT 20 OFFSET 40")
def limit_offset(s, d):
    return customer(s, d).select("c_custkey").orderBy("c_custkey").offset(40).limit(20)


# Set operations

_NATIONS = ("SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier")


def _set(name: str, sql: str, f):
    QUERIES[f"op_{name}"] = lambda s, d: f(customer(s, d).select(F.col("c_nationkey").alias("k")), supplier(s, d).select(F.col("s_nationkey").alias("k")))
    ORACLES[f"op_{name}"] = f"{_NATIONS[0]} {sql} {_NATIONS[1]}"


_set("set_union", "UNION", lambda a, b: a.union(b).distinct())
_set("set_union_all", "UNION ALL", lambda a, b: a.unionByName(b))
_set("set_intersect", "INTERSECT", lambda a, b: a.intersect(b))
_set("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b))
_set("set_except", "EXCEPT", lambda a, b: a.subtract(b))
_set("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))


# Sampling


@op("SELECT doc_id FROM documents WHERE substr(md5(doc_id::VARCHAR), 1, 1) < '4'")
def sample_hash(s, d):
    """A quarter of the rows, by the first digit of a hash."""
    return documents(s, d).where(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 1) < "4").select("doc_id")


@op()
def sample_stratified(s, d):
    return documents(s, d).sampleBy("lang", {"en": 0.2, "de": 0.5, "fr": 0.5, "es": 1.0}, seed=7).select("doc_id", "lang")


@op("SELECT doc_id, (row_number() OVER (ORDER BY md5('42|1|' || doc_id), doc_id) - 1)::BIGINT AS step FROM documents")
def shuffle_epoch(s, d):
    from pairbundle.operators.sampler import permute

    return permute(documents(s, d).select(F.col("doc_id").alias("sample_id")), 1).select(F.col("sample_id").alias("doc_id"), "step")


# Subqueries


def _views(s, d):
    for name in ("orders", "lineitem", "customer"):
        table(s, d, name).createOrReplaceTempView(f"pb_{name}")


@op("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)")
def sub_scalar(s, d):
    _views(s, d)
    return s.sql("SELECT o_orderkey FROM pb_orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM pb_orders)")


@op("SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45)")
def sub_exists(s, d):
    _views(s, d)
    return s.sql("SELECT o_orderkey FROM pb_orders o WHERE EXISTS (SELECT 1 FROM pb_lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45)")


@op("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
def sub_in(s, d):
    _views(s, d)
    return s.sql("SELECT c_custkey FROM pb_customer WHERE c_custkey NOT IN (SELECT o_custkey FROM pb_orders WHERE o_totalprice > 300000)")


@op("SELECT o_orderkey FROM orders o WHERE o_totalprice = (SELECT max(i.o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
def sub_correlated(s, d):
    _views(s, d)
    return s.sql("SELECT o_orderkey FROM pb_orders o WHERE o_totalprice = (SELECT max(i.o_totalprice) FROM pb_orders i WHERE i.o_custkey = o.o_custkey)")


@op("WITH big AS (SELECT o_custkey, count(*)::BIGINT AS n FROM orders GROUP BY 1) SELECT n, count(*)::BIGINT AS customers FROM big GROUP BY 1")
def cte(s, d):
    _views(s, d)
    return s.sql("WITH big AS (SELECT o_custkey, count(*) AS n FROM pb_orders GROUP BY o_custkey) SELECT n, count(*) AS customers FROM big GROUP BY n")


@op("WITH RECURSIVE t(level, least, most) AS (SELECT 1, 0::BIGINT, max(o_orderkey) FROM orders UNION ALL SELECT level + 1, 2 * least + 1, most FROM t WHERE least < most - least) SELECT level, count(*)::BIGINT AS width FROM t JOIN orders ON o_orderkey >= least AND o_orderkey - least <= least GROUP BY level")
def cte_recursive(s, d):
    """Orders as a binary tree by key, where 2k + 1 and 2k + 2 are the children of k: the walk goes down as far as there are keys, each level is
    a stretch of them. A level is one row of the recursion, 64 at most: these are broadcast, and the orders are counted where they lie."""
    orders(s, d).createOrReplaceTempView("pb_orders")
    return s.sql("WITH RECURSIVE t(level, least, most) AS (SELECT 1, CAST(0 AS BIGINT), max(o_orderkey) FROM pb_orders UNION ALL SELECT level + 1, 2 * least + 1, most FROM t WHERE least < most - least) SELECT /*+ BROADCAST(t) */ level, count(*) AS width FROM t JOIN pb_orders ON o_orderkey >= least AND o_orderkey - least <= least GROUP BY level")


# Scalar functions


@op("SELECT doc_id, strlen(text)::INTEGER AS bytes, length(text)::INTEGER AS chars, md5(substr(upper(lang), 1, 2)) AS h, lpad(doc_id::VARCHAR, 8, '0') AS padded, replace(source, 'src', 's') AS short, concat_ws('-', lang, source) AS both, sha256(source) AS s, hex(lang) AS x FROM documents")
def fn_string(s, d):
    return documents(s, d).select("doc_id", F.octet_length("text").alias("bytes"), F.length("text").alias("chars"), F.md5(F.substring(F.upper("lang"), 1, 2)).alias("h"), F.lpad(F.col("doc_id").cast("string"), 8, "0").alias("padded"), F.replace("source", F.lit("src"), F.lit("s")).alias("short"), F.concat_ws("-", "lang", "source").alias("both"), F.sha2("source", 256).alias("s"), F.hex("lang").alias("x"))


@op("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, datediff('day', o_orderdate::DATE, DATE '2000-01-01')::INTEGER AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month_start FROM orders")
def fn_date(s, d):
    return orders(s, d).select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff(F.lit("2000-01-01").cast("date"), F.col("o_orderdate").cast("date")).alias("days"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month_start"))


@op("SELECT p_partkey, floor(p_retailprice)::BIGINT AS f, ceil(p_retailprice)::BIGINT AS c, p_partkey % 7 AS m, p_partkey // 7 AS q, round(log2(p_size + 1), 6) AS l, power(p_size, 2) AS p, greatest(p_size, 10) AS g, least(p_size, 10) AS k FROM part")
def fn_math(s, d):
    return part(s, d).select("p_partkey", F.floor("p_retailprice").cast("long").alias("f"), F.ceil("p_retailprice").cast("long").alias("c"), F.pmod("p_partkey", F.lit(7)).alias("m"), F.expr("p_partkey div 7").alias("q"), F.round(F.log2(F.col("p_size") + 1), 6).alias("l"), F.pow("p_size", F.lit(2)).alias("p"), F.greatest("p_size", F.lit(10)).alias("g"), F.least("p_size", F.lit(10)).alias("k"))


@op("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm, len(embedding)::INTEGER AS n, round(list_max(embedding)::DOUBLE, 4) AS most FROM embeddings")
def fn_array(s, d):
    e = F.col("embedding")
    return embeddings(s, d).select("vec_id", F.round(F.aggregate(F.zip_with(e, e, lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda a, x: a + x), 4).alias("norm"), F.size(e).alias("n"), F.round(F.array_max(e).cast("double"), 4).alias("most"))


@op("SELECT doc_id, lang AS v, 2 AS n, 'lang,source' AS ks FROM documents")
def fn_map(s, d):
    m = F.map_from_entries(F.array(F.struct(F.lit("lang").alias("k"), F.col("lang").alias("v")), F.struct(F.lit("source").alias("k"), F.col("source").alias("v"))))
    return documents(s, d).select("doc_id", F.element_at(m, "lang").alias("v"), F.size(F.map_keys(m)).alias("n"), F.array_join(F.array_sort(F.map_keys(m)), ",").alias("ks"))


@op("SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM events")
def fn_json(s, d):
    return events(s, d).select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@op("SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM events")
def fn_variant(s, d):
    return events(s, d).select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@op("SELECT doc_id, coalesce(nullif(lang, 'en'), 'xx') AS l, CASE WHEN lang = 'de' THEN 1 ELSE 0 END AS de, try_cast(source AS INTEGER) AS bad FROM documents")
def fn_null(s, d):
    return documents(s, d).select("doc_id", F.coalesce(F.nullif("lang", F.lit("en")), F.lit("xx")).alias("l"), F.when(F.col("lang") == "de", 1).otherwise(0).alias("de"), F.col("source").try_cast("int").alias("bad"))


# Time windows: batch twins of the streams


@op("SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def ts_tumbling(s, d):
    from pairbundle.streaming.windows import tumbling

    return tumbling(events(s, d))


@op("SELECT strftime(b + to_minutes(CAST(-15 * k AS BIGINT)), '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n FROM (SELECT time_bucket(INTERVAL 15 MINUTE, ts) AS b FROM events), range(0, 4) r(k) GROUP BY 1")
def ts_sliding(s, d):
    from pairbundle.streaming.windows import sliding

    return sliding(events(s, d))


@op("SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, g")
def ts_session(s, d):
    from pairbundle.streaming.windows import sessions

    return sessions(events(s, d))
