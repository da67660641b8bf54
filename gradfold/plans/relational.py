"""The operators around the methods: filters, joins, aggregates, windows, sets, functions, features."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..functions import vectors as V
from ..sources import files
from ..sources.tables import table
from . import fixtures as X
from .registry import query


def r(c, n=4):
    return F.round(c, n)


# sources and sinks


@query("SELECT r_regionkey, r_name FROM region")
def scan_parquet(spark, sf):
    return table(spark, sf, "region").select("r_regionkey", "r_name")


def _customers(spark, sf):
    return table(spark, sf, "customer").select("c_custkey", "c_name", "c_mktsegment", "c_acctbal")


for _f in ("csv", "json", "orc"):

    @query("SELECT c_custkey, c_name, c_mktsegment, c_acctbal FROM customer", name=f"scan_{_f}_roundtrip")
    def _scan(spark, sf, form=_f):
        return files.round_trip(_customers(spark, sf), form, **({"header": "true"} if form == "csv" else {}))


@query("SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY 1")
def write_partitioned(spark, sf):
    return files.partitioned(_customers(spark, sf), "c_mktsegment").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


# filters


@query("SELECT l_orderkey, l_partkey, round(l_extendedprice * (1 - l_discount), 4) AS revenue FROM lineitem WHERE l_quantity < 10 AND l_discount >= 0.05")
def project_filter(spark, sf):
    return table(spark, sf, "lineitem").where("l_quantity < 10 and l_discount >= 0.05").select("l_orderkey", "l_partkey", r(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"))


@query("SELECT o_orderkey, o_orderstatus FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 20000")
def filter_in_between(spark, sf):
    return table(spark, sf, "orders").where(F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 20000)).select("o_orderkey", "o_orderstatus")


@query("SELECT p_partkey, p_name FROM part WHERE p_type LIKE '%A%' OR regexp_matches(p_brand, '#[1-3]')")
def filter_like_rlike(spark, sf):
    return table(spark, sf, "part").where(F.col("p_type").like("%A%") | F.col("p_brand").rlike("#[1-3]")).select("p_partkey", "p_name")


@query("SELECT doc_id, lang FROM documents WHERE lang IS NOT DISTINCT FROM 'fr' OR lang IS NULL")
def filter_null_safe(spark, sf):
    return table(spark, sf, "documents").where(F.col("lang").eqNullSafe("fr") | F.col("lang").isNull()).select("doc_id", "lang")


@query("SELECT vec_id, CASE WHEN label < 5 THEN 1 ELSE -1 END AS y FROM embeddings")
def binarize_label(spark, sf):
    return table(spark, sf, "embeddings").select("vec_id", F.when(F.col("label") < 5, 1).otherwise(-1).alias("y"))


# joins


@query("SELECT o_orderkey, o_custkey, count(*) AS n, round(sum(l_quantity), 4) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2")
def join_orders_lineitem(spark, sf):
    lines = table(spark, sf, "lineitem").select("l_orderkey", "l_quantity")
    return table(spark, sf, "orders").select("o_orderkey", "o_custkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey", "o_custkey").agg(F.count("*").alias("n"), r(F.sum("l_quantity")).alias("q"))


@query("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast_nation(spark, sf):
    nation, region = table(spark, sf, "nation"), table(spark, sf, "region")  # 25 and 5 rows at every scale
    return table(spark, sf, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "n_name", "r_name")


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left_outer(spark, sf):
    return table(spark, sf, "customer").join(table(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT coalesce(a.k, b.k) AS k, a.n AS customers, b.n AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 5000 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) b ON a.k = b.k")
def join_full_outer(spark, sf):
    a = table(spark, sf, "customer").where("c_acctbal > 5000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    b = table(spark, sf, "supplier").where("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "k", "full")


@query("SELECT doc_id, n_chars FROM documents SEMI JOIN labels USING (doc_id)")
def docs_labelled(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "n_chars").join(table(spark, sf, "labels"), "doc_id", "left_semi")


@query("SELECT doc_id, n_chars FROM documents ANTI JOIN labels USING (doc_id)")
def docs_unlabelled(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "n_chars").join(table(spark, sf, "labels"), "doc_id", "left_anti")


@query("SELECT r_name, n_name FROM region, nation")
def join_cross_small(spark, sf):
    return table(spark, sf, "region").select("r_name").crossJoin(table(spark, sf, "nation").select("n_name"))  # 5 x 25 rows at every scale


def containing(docs, items):
    """(doc_id, item_id): documents whose text contains an item's text verbatim.

    Keys and texts are joined apart.  An item of three or more words is found by its
    longest inner word, which stands as a whole word wherever the item stands; a
    shorter one by its first three characters, which may be anywhere, and one of
    less than that is tried on every document.  Null texts contain nothing, and an
    empty item is in every text.
    """
    words = lambda c: F.filter(F.split(c, r"\s+"), lambda w: w != "")
    # the ends of an item may be parts of longer words, whether or not white space is next to them inside
    inner = F.slice(F.col("w"), F.lit(2), F.greatest(F.size("w") - 2, F.lit(0)))
    longest = F.array_max(F.transform(inner, lambda w: F.struct(F.length(w).alias("n"), w.alias("w"))))["w"]
    kind = F.when(longest.isNotNull(), "word").when(F.length("passage") >= 3, "gram").otherwise("any")
    item = items.select("item_id", F.col("text").alias("passage")).where("passage is not null").withColumn("w", words("passage"))
    key = F.when(F.col("kind") == "word", longest).when(F.col("kind") == "gram", F.substring("passage", 1, 3)).otherwise("")
    item = item.withColumn("kind", kind).select("item_id", "passage", "kind", key.alias("key"))
    kinds = {row[0] for row in item.select("kind").distinct().collect()}  # three at most
    text = docs.select("doc_id", "text").where("text is not null")
    of = {"word": words("text"), "gram": F.transform(F.sequence(F.lit(1), F.greatest(F.length("text") - 2, F.lit(1))), lambda i: F.col("text").substr(i, F.lit(3))), "any": F.array(F.lit(""))}
    found = None
    for name in sorted(kinds):
        met = text.select("doc_id", F.explode(F.array_distinct(of[name])).alias("key")).join(item.where(F.col("kind") == name).select("item_id", "key"), "key").select("doc_id", "item_id").distinct()
        found = met if found is None else found.union(met)
    if found is None:
        return text.select("doc_id").crossJoin(item.select("item_id")).where("false")
    return found.join(item.select("item_id", "passage"), "item_id").join(text, "doc_id").where(F.contains("text", "passage")).select("doc_id", "item_id")


@query("SELECT doc_id, item_id FROM documents JOIN benchmark ON contains(documents.text, benchmark.text)")
def passage_contains(spark, sf):
    return containing(table(spark, sf, "documents"), table(spark, sf, "benchmark"))


@query("SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON b.p_retailprice > a.p_retailprice AND b.p_retailprice <= a.p_retailprice + 0.15 AND a.p_size = b.p_size")
def join_range_price(spark, sf):
    """A range join: prices are cut into bins as wide as the range, and equal or neighbouring bins meet."""
    part = table(spark, sf, "part")
    width = 0.15
    a = part.select(F.col("p_partkey").alias("a"), F.col("p_size").alias("sa"), F.col("p_retailprice").alias("pa")).withColumn("bin", F.explode(F.array(F.floor(F.col("pa") / width), F.floor(F.col("pa") / width) + 1)))
    b = part.select(F.col("p_partkey").alias("b"), F.col("p_size").alias("sb"), F.col("p_retailprice").alias("pb")).withColumn("bin", F.floor(F.col("pb") / width))
    b = b.withColumnRenamed("bin", "bin_b")
    b2 = b.select("b", "sb", "pb", F.explode(F.array(F.col("bin_b"), F.col("bin_b") - 1)).alias("bin_b"))
    return a.select("a", "sa", "pa", F.floor(F.col("pa") / width).alias("bin")).distinct().join(b2, (F.col("bin") == F.col("bin_b")) & (F.col("sa") == F.col("sb"))).where((F.col("pb") > F.col("pa")) & (F.col("pb") <= F.col("pa") + width)).select("a", "b").distinct()


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'click' AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 1 HOUR")
def events_within_window(spark, sf):
    """Hours are part of the key: a purchase meets the clicks of its hour and of the one before, not all of its user's."""
    e = table(spark, sf, "events").select("event_id", "user_id", "event_type", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000).alias("hour"))
    a = e.where("event_type = 'purchase'").select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array("hour", F.col("hour") - 1)).alias("hour"))
    b = e.where("event_type = 'click'").select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), "hour")
    return a.join(b, ["user_id", "hour"]).where((F.col("tb") < F.col("ta")) & (F.col("tb") >= F.col("ta") - F.expr("interval 1 hour"))).select("a", "b")


@query("SELECT a.event_id, b.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') b ON a.user_id = b.user_id AND a.ts > b.ts")
def asof_last_event(spark, sf):
    """The last earlier view of the same user, from one sorted pass over each user's events."""
    e = table(spark, sf, "events").select("event_id", "user_id", "event_type", "ts")
    view = F.when(F.col("event_type") == "view", F.col("event_id"))
    seen = F.last(view, ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1))
    return e.withColumn("last_view", seen).where("event_type = 'purchase'").select("event_id", "last_view")


# aggregates


@query("""SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS sum_qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS avg_disc
 FROM lineitem WHERE l_shipdate <= TIMESTAMP '2000-06-01' GROUP BY 1, 2""")
def agg_pricing(spark, sf):
    return table(spark, sf, "lineitem").where(F.col("l_shipdate") <= F.lit("2000-06-01").cast("timestamp_ntz")).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), r(F.sum("l_quantity"), 2).alias("sum_qty"), r(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), r(F.avg("l_discount"), 6).alias("avg_disc"))


@query("SELECT user_id, count(DISTINCT event_type) AS kinds, count(DISTINCT ts::DATE) AS days FROM events GROUP BY 1")
def agg_distinct(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").agg(F.countDistinct("event_type").alias("kinds"), F.countDistinct(F.to_date("ts")).alias("days"))


@query("SELECT event_type, count(*) FILTER (value > 1) AS big, count(*) AS n FROM events GROUP BY 1")
def agg_filter_clause(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 1).alias("big"), F.count("*").alias("n"))


_GROUPED = "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY "


def _n_q():
    return F.count("*").alias("n"), r(F.sum("l_quantity"), 2).alias("q")


@query(_GROUPED + "ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup(spark, sf):
    return table(spark, sf, "lineitem").rollup("l_returnflag", "l_linestatus").agg(*_n_q())


@query(_GROUPED + "CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark, sf):
    return table(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(*_n_q())


@query(_GROUPED + "GROUPING SETS ((l_returnflag), (l_linestatus))")
def agg_grouping_sets(spark, sf):
    df = table(spark, sf, "lineitem")
    return df.groupingSets([[F.col("l_returnflag")], [F.col("l_linestatus")]], "l_returnflag", "l_linestatus").agg(*_n_q())


@query("SELECT l_returnflag, round(covar_pop(l_quantity, l_extendedprice), 2) AS cov, round(corr(l_quantity, l_extendedprice), 6) AS cor, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(stddev_pop(l_quantity), 6) AS sd FROM lineitem GROUP BY 1")
def agg_stats(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(r(F.covar_pop("l_quantity", "l_extendedprice"), 2).alias("cov"), r(F.corr("l_quantity", "l_extendedprice"), 6).alias("cor"), r(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), r(F.stddev_pop("l_quantity"), 6).alias("sd"))


@query("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
def agg_percentile(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(r(F.percentile("value", 0.5), 6).alias("median"), r(F.percentile("value", 0.9), 6).alias("p90"))


@query()
def agg_approx_distinct(spark, sf):
    return table(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("SELECT user_id, arg_max(event_type, event_id) AS last_type FROM events GROUP BY 1")
def agg_max_by(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").agg(F.max_by("event_type", "event_id").alias("last_type"))


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, round(avg(value) FILTER (event_type = 'click'), 6) AS click, round(avg(value) FILTER (event_type = 'purchase'), 6) AS purchase FROM events GROUP BY 1")
def pivot_returns(spark, sf):
    p = table(spark, sf, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).pivot("event_type", ["click", "purchase"]).agg(F.avg("value"))
    return p.select("day", r("click", 6).alias("click"), r("purchase", 6).alias("purchase"))


# windows

def _user():
    return W.partitionBy("user_id").orderBy("event_id")


@query("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr, round(percent_rank() OVER w, 6) AS pr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def win_rank(spark, sf):
    w, p = W.partitionBy("o_custkey").orderBy("o_orderkey"), W.partitionBy("o_custkey").orderBy("o_orderpriority")
    return table(spark, sf, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"), r(F.percent_rank().over(w), 6).alias("pr"))


@query("SELECT event_id, lag(value) OVER w AS before, lead(event_type) OVER w AS next FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def win_lag(spark, sf):
    return table(spark, sf, "events").select("event_id", F.lag("value").over(_user()).alias("before"), F.lead("event_type").over(_user()).alias("next"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS ma FROM events")
def win_moving_avg(spark, sf):
    return table(spark, sf, "events").select("event_id", r(F.avg("value").over(_user().rowsBetween(-2, 0)), 6).alias("ma"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id), 6) AS total FROM events")
def win_cumsum(spark, sf):
    return table(spark, sf, "events").select("event_id", r(F.sum("value").over(_user().rowsBetween(W.unboundedPreceding, 0)), 6).alias("total"))


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM orders")
def win_range(spark, sf):
    w = W.partitionBy("o_orderpriority").orderBy("o_totalprice").rangeBetween(-100, 100)
    return table(spark, sf, "orders").select("o_orderkey", F.count("*").over(w).alias("near"))


@query("SELECT c_custkey, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey) AS quarter FROM customer")
def win_ntile(spark, sf):
    return table(spark, sf, "customer").select("c_custkey", F.ntile(4).over(W.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")).alias("quarter"))


@query("SELECT event_id, first_value(event_type) OVER w AS first, last_value(event_type) OVER w AS last, nth_value(event_type, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(spark, sf):
    w = _user().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(spark, sf, "events").select("event_id", F.first("event_type").over(w).alias("first"), F.last("event_type").over(w).alias("last"), F.nth_value("event_type", 2).over(w).alias("second"))


# sorting, sets


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk_orders(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("SELECT c_mktsegment, c_custkey, c_acctbal FROM customer QUALIFY row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) <= 3")
def topk_per_group(spark, sf):
    rn = F.row_number().over(W.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey"))
    return table(spark, sf, "customer").withColumn("rn", rn).where("rn <= 3").select("c_mktsegment", "c_custkey", "c_acctbal")


@query("SELECT s_suppkey, s_name FROM supplier ORDER BY s_suppkey LIMIT 5 OFFSET 3")
def limit_offset(spark, sf):
    return table(spark, sf, "supplier").select("s_suppkey", "s_name").orderBy("s_suppkey").offset(3).limit(5)


def _two(spark, sf):
    return table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))


_TWO = "(SELECT c_nationkey AS k FROM customer) {op} (SELECT s_nationkey AS k FROM supplier)"


@query(_TWO.format(op="UNION"))
def set_union(spark, sf):
    a, b = _two(spark, sf)
    return a.union(b).distinct()


@query(_TWO.format(op="UNION ALL"))
def set_union_all(spark, sf):
    a, b = _two(spark, sf)
    return a.unionByName(b)


@query(_TWO.format(op="INTERSECT ALL"))
def set_intersect(spark, sf):
    a, b = _two(spark, sf)
    return a.intersectAll(b)


@query(_TWO.format(op="EXCEPT ALL"))
def set_except(spark, sf):
    a, b = _two(spark, sf)
    return a.exceptAll(b)


# functions


@query("SELECT p_partkey, lower(p_name) AS low, substr(p_brand, 1, 5) AS pre, md5(p_name) AS h, len(string_split(p_type, ' ')) AS words, regexp_replace(p_brand, '[0-9]', 'd', 'g') AS masked FROM part")
def fn_string(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.lower("p_name").alias("low"), F.substring("p_brand", 1, 5).alias("pre"), F.md5("p_name").alias("h"), F.size(F.split("p_type", " ")).alias("words"), F.regexp_replace("p_brand", "[0-9]", "d").alias("masked"))


@query("SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS d, year(o_orderdate) AS y, strftime(o_orderdate::DATE + INTERVAL 30 DAY, '%Y-%m-%d') AS due FROM orders")
def fn_date(spark, sf):
    o = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", o), "yyyy-MM-dd").alias("m"), F.datediff(F.to_date(o), F.lit("1995-01-01").cast("date")).alias("d"), F.year(o).alias("y"), F.date_format(F.date_add(F.to_date(o), 30), "yyyy-MM-dd").alias("due"))


@query("SELECT event_id, round(ln(value + 1), 6) AS l, round(exp(-value / 100), 6) AS e, round(pow(value, 2), 4) AS p, round(sqrt(value), 6) AS s, sign(value - 1)::INT AS g FROM events")
def fn_math(spark, sf):
    v = F.col("value")
    return table(spark, sf, "events").select("event_id", r(F.log(v + 1), 6).alias("l"), r(F.exp(-v / 100), 6).alias("e"), r(F.pow(v, 2), 4).alias("p"), r(F.sqrt(v), 6).alias("s"), F.signum(v - 1).cast("int").alias("g"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding[1:4]::DOUBLE[], lambda v: v * 2)), 6) AS t, len(list_filter(embedding, lambda v: v > 0)) AS pos, round(list_max(embedding)::DOUBLE, 6) AS top FROM embeddings")
def fn_array(spark, sf):
    e = F.col("embedding").cast("array<double>")
    return table(spark, sf, "embeddings").select("vec_id", r(V.total(F.transform(F.slice(e, 1, 4), lambda v: v * 2)), 6).alias("t"), F.size(F.filter(e, lambda v: v > 0)).alias("pos"), r(F.array_max(e), 6).alias("top"))


@query("SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY 1")
def fn_map(spark, sf):
    """A map from type to count for each user."""
    counts = table(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0).cast("long")).alias("clicks"), F.size(F.map_filter("m", lambda k, v: v > 0)).cast("long").alias("kinds"))


@query("SELECT event_id, (props::JSON->>'k')::BIGINT AS k FROM events")
def fn_json(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'mid' ELSE 'high' END AS band, coalesce(nullif(c_mktsegment, 'BUILDING'), 'other') AS seg, greatest(c_acctbal, 0) AS g FROM customer")
def fn_conditional(spark, sf):
    b = F.col("c_acctbal")
    return table(spark, sf, "customer").select("c_custkey", F.when(b < 0, "debt").when(b < 5000, "mid").otherwise("high").alias("band"), F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("other")).alias("seg"), F.greatest(b, F.lit(0.0)).alias("g"))


# vectors

_E = "embedding::DOUBLE[]"


def _emb(spark, sf):
    return table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))


@query(f"SELECT vec_id, round(list_dot_product({_E}, list_reverse({_E})), 6) AS d FROM embeddings")
def vec_dot(spark, sf):
    return _emb(spark, sf).select("vec_id", r(V.dot(F.col("e"), F.reverse("e")), 6).alias("d"))


@query(f"SELECT vec_id, round(list_sum(list_transform({_E}, lambda v: abs(v))), 6) AS n1, round(sqrt(list_dot_product({_E}, {_E})), 6) AS n2 FROM embeddings")
def vec_norms(spark, sf):
    return _emb(spark, sf).select("vec_id", r(V.norm1(F.col("e")), 6).alias("n1"), r(V.norm2(F.col("e")), 6).alias("n2"))


@query(f"SELECT vec_id, round(list_sum(list_transform(list_zip({_E}, list_reverse({_E})), lambda z: abs(z[1] + 0.5 * z[2]))), 6) AS s FROM embeddings")
def vec_axpy(spark, sf):
    return _emb(spark, sf).select("vec_id", r(V.norm1(V.axpy(F.col("e"), F.lit(0.5), F.reverse("e"))), 6).alias("s"))


@query("SELECT j::INT AS j, round(avg(v), 6) + 0.0 AS m FROM (SELECT unnest(range(0, 64)) AS j, unnest(embedding)::DOUBLE AS v FROM embeddings) GROUP BY j")
def vec_mean(spark, sf):
    return _emb(spark, sf).select(F.posexplode("e").alias("j", "v")).groupBy("j").agg((r(F.avg("v"), 6) + F.lit(0.0)).alias("m"))


@query(f"SELECT vec_id, round(list_cosine_similarity({_E}, list_reverse({_E})), 6) AS c FROM embeddings")
def vec_cosine(spark, sf):
    return _emb(spark, sf).select("vec_id", r(V.cosine(F.col("e"), F.reverse("e")), 6).alias("c"))


@query(f"SELECT id, round(sum(value * ((feature % 7 - 3) / 10.0::DOUBLE)), 6) AS d FROM ({X.SQL_SPARSE}) GROUP BY id")
def sparse_dot(spark, sf):
    return X.doc_sparse(spark, sf).groupBy("id").agg(r(F.sum(F.col("value") * ((F.col("feature") % 7 - 3) / 10.0)), 6).alias("d"))


# features


@query("SELECT p_partkey, round((p_size - avg(p_size) OVER ()) / stddev_pop(p_size) OVER (), 6) AS z FROM part")
def feat_standardize(spark, sf):
    df = table(spark, sf, "part").select("p_partkey", F.col("p_size").cast("double").alias("z"))
    return X.standard(df, ["z"]).select("p_partkey", r("z", 6).alias("z"))


@query("SELECT p_partkey, round((p_size - min(p_size) OVER ()) / (max(p_size) OVER () - min(p_size) OVER ())::DOUBLE, 6) AS m FROM part")
def feat_minmax(spark, sf):
    df = table(spark, sf, "part").select("p_partkey", "p_size")
    ends = df.agg(F.min("p_size").alias("lo"), F.max("p_size").alias("hi"))
    return df.crossJoin(F.broadcast(ends)).select("p_partkey", r((F.col("p_size") - F.col("lo")) / (F.col("hi") - F.col("lo")), 6).alias("m"))


@query("WITH c AS (SELECT DISTINCT c_mktsegment AS s FROM customer), i AS (SELECT s, row_number() OVER (ORDER BY s) - 1 AS i FROM c) SELECT c_custkey, i::INT AS idx, list_transform(range(0, (SELECT count(*) FROM c)), lambda j: (j = i)::INT) AS hot FROM customer JOIN i ON s = c_mktsegment")
def feat_onehot(spark, sf):
    df = table(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    names = df.agg(F.array_sort(F.collect_set("c_mktsegment")).alias("names"))
    idx = (F.array_position("names", F.col("c_mktsegment")) - 1).cast("int")
    return df.crossJoin(F.broadcast(names)).select("c_custkey", idx.alias("idx"), F.transform("names", lambda n: (n == F.col("c_mktsegment")).cast("int")).alias("hot"))


@query(f"SELECT id, token, count(*) AS n FROM ({X.SQL_TOKENS}) GROUP BY 1, 2")
def feat_bow(spark, sf):
    return X.tokens(spark, sf).groupBy("id", "token").agg(F.count("*").alias("n"))


@query(f"WITH t AS (SELECT id, token, count(*)::DOUBLE AS n FROM ({X.SQL_TOKENS}) GROUP BY 1, 2), d AS (SELECT token, count(*) AS df FROM t GROUP BY 1) SELECT id, token, round(n * ln((SELECT count(DISTINCT id) FROM t) / df::DOUBLE), 6) AS w FROM t JOIN d USING (token) WHERE df >= 2")
def feat_tfidf(spark, sf):
    # the counts are read three times, so they are written once
    path = files.scratch(spark, "term-counts")
    X.tokens(spark, sf).groupBy("id", "token").agg(F.count("*").cast("double").alias("n")).write.parquet(path)
    counts = spark.read.schema("id long, token string, n double").parquet(path)
    df = counts.groupBy("token").agg(F.count("*").alias("df")).where("df >= 2")
    size = counts.agg(F.countDistinct("id").cast("double").alias("docs"))
    return counts.join(df, "token").crossJoin(F.broadcast(size)).select("id", "token", r(F.col("n") * F.log(F.col("docs") / F.col("df")), 6).alias("w"))


@query(f"SELECT id, feature, round(value, 9) AS value FROM ({X.SQL_SPARSE})")
def feat_hash(spark, sf):
    return X.doc_sparse(spark, sf).select("id", "feature", F.round("value", 9).alias("value"))


@query(r"SELECT doc_id, count(*) AS n FROM (SELECT doc_id, unnest(regexp_split_to_array(text, '[.!?\n]+')) AS s FROM documents) WHERE regexp_matches(s, '[^ ]') GROUP BY 1")
def feat_sentences(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.explode(F.split("text", r"[.!?\n]+")).alias("s")).where(F.col("s").rlike("[^ ]")).groupBy("doc_id").agg(F.count("*").alias("n"))


@query(f"SELECT {H.sql_number('99', 'o_orderkey')} % 10 AS part, count(*) AS n FROM orders GROUP BY 1")
def split_hash(spark, sf):
    return table(spark, sf, "orders").groupBy((H.number(99, F.col("o_orderkey")) % 10).alias("part")).agg(F.count("*").alias("n"))


# subqueries


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
def sub_scalar(spark, sf):
    o = table(spark, sf, "orders")
    mean = o.agg((F.avg("o_totalprice") * 1.5).alias("m"))
    return o.crossJoin(F.broadcast(mean)).where("o_totalprice > m").select("o_orderkey")


@query("SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
def sub_in(spark, sf):
    n = table(spark, sf, "nation").where("n_regionkey = 1").select(F.col("n_nationkey").alias("c_nationkey"))
    return table(spark, sf, "customer").join(n, "c_nationkey", "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 10000)")
def sub_exists(spark, sf):
    table(spark, sf, "customer").createOrReplaceTempView("gf_customer")
    table(spark, sf, "orders").createOrReplaceTempView("gf_orders")
    return spark.sql("SELECT c_custkey FROM gf_customer c WHERE EXISTS (SELECT 1 FROM gf_orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 10000)")
