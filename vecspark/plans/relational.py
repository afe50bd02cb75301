"""Relational operators around the methods: scans, sinks, joins, aggregates, windows, sets, collections, strings, dates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecspark.functions import columns as vc
from vecspark.operators.assign import assign_full
from vecspark.operators.seeding import start_matrix
from vecspark.plans.vector_queries import V, assign_cte, start_sql
from vecspark.sources.files import round_trip, write_bucketed, write_partitioned
from vecspark.sources.vectors import embeddings, read_table

QUERIES: dict = {}
ORACLES: dict = {}
K = 22

ASSIGNED = f"WITH {V}, {start_sql()}, {assign_cte(0)}"


def keep(name: str, sql: str | None = None):
    def to(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return to


def assigned(spark, sf_dir) -> DataFrame:
    import numpy as np

    v = embeddings(spark, sf_dir)
    return assign_full(v, start_matrix(v, K, 0), dtype=np.float64).join(read_table(spark, sf_dir, "embeddings").select("vec_id", "label"), "vec_id")


# ---- operators of general use -----------------------------------------------------------------------------------

def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """For each left row the value of the last right row of its key at or before its time; one shuffle by key.

    Both sides are put in one stream in time order (right rows first on equal times) and the last value is carried.
    """
    a = left.select(key, time, F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.lit(1).alias("__side"), F.struct(*left.columns).alias("__row"))
    b = right.select(key, time, F.col(value).alias("__v"), F.lit(0).alias("__side"), F.lit(None).cast(a.schema["__row"].dataType).alias("__row"))
    order = Window.partitionBy(key).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, 0)
    carried = a.union(b).withColumn("__last", F.last("__v", ignorenulls=True).over(order))
    return carried.where("__side = 1").select("__row.*", F.col("__last").alias(f"last_{value}"))


def interval_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of a key with 0 <= right_time - left_time <= seconds, by buckets of that length: a left row meets two buckets."""
    bucket = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.withColumn("__b", F.explode(F.array(bucket(F.col(left_time)), bucket(F.col(left_time)) + 1)))
    b = right.withColumn("__b", bucket(F.col(right_time)))
    gap = F.unix_timestamp(right_time) - F.unix_timestamp(left_time)
    return a.join(b, [key, "__b"]).where(gap.between(0, seconds)).drop("__b")


def band_join(left: DataFrame, right: DataFrame, a: str, b: str, width: float) -> DataFrame:
    """Pairs with |a - b| <= width, by buckets of the width: an equi-join, never a product."""
    x = left.withColumn("__b", F.floor(F.col(a) / width))
    y = right.withColumn("__b", F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda i: F.floor(F.col(b) / width) + i)))
    return x.join(y, "__b").where(F.abs(F.col(a) - F.col(b)) <= width).drop("__b")


def salted_count(df: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Counts by a key that may be skewed: partial counts by key and salt, then by key."""
    return df.withColumn("__s", F.pmod(F.monotonically_increasing_id(), F.lit(salts))).groupBy(key, "__s").agg(F.count(F.lit(1)).alias("n")).groupBy(key).agg(F.sum("n").alias("n"))


def rounded(c: Column, n: int = 6) -> Column:
    return F.round(c, n)


# ---- scans and sinks --------------------------------------------------------------------------------------------

@keep("scan_embeddings", "SELECT vec_id, label FROM embeddings WHERE label IN (1, 2)")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "embeddings").where(F.col("label").isin(1, 2)).select("vec_id", "label")


ORDERS = "SELECT o_orderkey, o_custkey, o_totalprice FROM orders"


def orders(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_totalprice")


for kind in ("csv", "json", "orc", "parquet"):

    @keep(f"scan_{kind}_roundtrip", ORDERS)
    def _(spark, sf_dir, kind=kind):
        return round_trip(orders(spark, sf_dir), kind)


@keep("scan_text_roundtrip", "SELECT CAST(o_orderkey AS VARCHAR) AS value FROM orders")
def _(spark, sf_dir):
    return round_trip(orders(spark, sf_dir).select(F.col("o_orderkey").cast("string").alias("value")), "text")


@keep("sink_partitioned_roundtrip", "SELECT vec_id, label FROM embeddings WHERE label = 3")
def _(spark, sf_dir):
    return write_partitioned(read_table(spark, sf_dir, "embeddings").select("vec_id", "label"), "label").where("label = 3").select("vec_id", F.col("label").cast("int").alias("label"))


@keep("sink_bucketed_roundtrip", "SELECT o_orderkey, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark, sf_dir):
    a = write_bucketed(orders(spark, sf_dir), "o_orderkey", 8)
    b = write_bucketed(read_table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_quantity"), "o_orderkey", 8)
    return a.join(b, "o_orderkey").groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("n"))


# ---- projection, predicates -------------------------------------------------------------------------------------

@keep("proj_head_tail", f"WITH {V} SELECT vec_id, round(v[1], 6) AS first, round(v[9], 6) AS ninth, len(v[9:]) AS n_tail FROM v")
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    return v.select("vec_id", rounded(F.element_at(vc.head("vec", 8), 1).cast("double")).alias("first"), rounded(F.element_at(vc.tail("vec", 8, 64), 1).cast("double")).alias("ninth"), F.size(vc.tail("vec", 8, 64)).cast("long").alias("n_tail"))


@keep("filter_label", "SELECT vec_id, CASE WHEN label < 3 THEN 'low' WHEN label < 7 THEN 'mid' ELSE 'high' END AS band FROM embeddings WHERE label IS NOT DISTINCT FROM label AND label <> 5")
def _(spark, sf_dir):
    band = F.when(F.col("label") < 3, "low").when(F.col("label") < 7, "mid").otherwise("high")
    return read_table(spark, sf_dir, "embeddings").where(F.col("label").eqNullSafe(F.col("label")) & (F.col("label") != 5)).select("vec_id", band.alias("band"))


@keep("filter_lang", "SELECT doc_id FROM documents WHERE regexp_matches(lang, '^(en|de)$')")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "documents").where(F.col("lang").rlike("^(en|de)$")).select("doc_id")


# ---- joins ------------------------------------------------------------------------------------------------------

JOINED = "SELECT o_custkey, count(*) AS n, round(sum(l_quantity), 2) AS q FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1"


def order_lines(spark, sf_dir, hint):
    o, li = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity")
    return o.hint(hint).join(li, o.o_orderkey == li.l_orderkey).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@keep("join_hash_orders_lineitem", JOINED)
def _(spark, sf_dir):
    return order_lines(spark, sf_dir, "shuffle_hash")


@keep("join_smj_orders_lineitem", JOINED)
def _(spark, sf_dir):
    return order_lines(spark, sf_dir, "merge")


@keep("join_bcast_nation", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def _(spark, sf_dir):
    c, n = read_table(spark, sf_dir, "customer"), read_table(spark, sf_dir, "nation")
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


@keep("join_full_outer", "SELECT coalesce(a.doc_id, b.doc_id) AS doc_id, a.doc_id IS NULL AS no_doc, b.doc_id IS NULL AS no_label FROM documents a FULL JOIN labels b ON a.doc_id = b.doc_id")
def _(spark, sf_dir):
    a, b = read_table(spark, sf_dir, "documents").select("doc_id", F.lit(True).alias("a")), read_table(spark, sf_dir, "labels").select("doc_id", F.lit(True).alias("b"))
    return a.join(b, "doc_id", "full").select("doc_id", F.col("a").isNull().alias("no_doc"), F.col("b").isNull().alias("no_label"))


@keep("join_range_norm", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON abs(a.p_retailprice - b.p_retailprice) <= 0.05 AND a.p_partkey < b.p_partkey")
def _(spark, sf_dir):
    p = read_table(spark, sf_dir, "part")
    return band_join(p.select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("x")), p.select(F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("y")), "x", "y", 0.05).where("a < b").select("a", "b")


@keep("join_interval_events", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND epoch(date_trunc('second', b.ts)) - epoch(date_trunc('second', a.ts)) BETWEEN 0 AND 600")
def _(spark, sf_dir):
    e = read_table(spark, sf_dir, "events").select("user_id", "event_id", F.col("ts").cast("timestamp").alias("ts"))
    return interval_join(e.select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta")), e.select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb")), "user_id", "ta", "tb", 600).where("a <> b").select("a", "b")


@keep("join_asof_events", "SELECT a.event_id, (SELECT b.value FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'view' AND b.ts <= a.ts ORDER BY b.ts DESC, b.event_id DESC LIMIT 1) AS last_value FROM events a WHERE a.event_type <> 'view'")
def _(spark, sf_dir):
    e = read_table(spark, sf_dir, "events").select("user_id", "event_id", "ts", "event_type", "value")
    kinds = e.where("event_type <> 'view'").select("user_id", "ts", "event_id")
    return asof_join(kinds, e.where("event_type = 'view'"), "user_id", "ts", "value").select("event_id", "last_value")


@keep("join_skew_salted", "SELECT source, count(*) AS n FROM documents GROUP BY 1")
def _(spark, sf_dir):
    return salted_count(read_table(spark, sf_dir, "documents"), "source")


# ---- aggregates, grouping sets, pivots --------------------------------------------------------------------------

@keep("aggregate_lineitem", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS s, round(avg(l_discount), 6) AS a, min(l_quantity) AS lo, max(l_quantity) AS hi, round(stddev_pop(l_quantity), 6) AS sd, round(var_pop(l_tax), 6) AS vp, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1, 2")
def _(spark, sf_dir):
    q = F.col("l_quantity")
    return read_table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), rounded(F.sum(q), 2).alias("s"), rounded(F.avg("l_discount")).alias("a"), F.min(q).alias("lo"), F.max(q).alias("hi"), rounded(F.stddev_pop(q)).alias("sd"), rounded(F.var_pop("l_tax")).alias("vp"), F.count_distinct("l_suppkey").alias("suppliers"))


@keep("min_by_max_by", "SELECT o_custkey, arg_min(o_orderkey, o_totalprice) AS cheapest, arg_max(o_orderkey, o_totalprice) AS dearest FROM orders GROUP BY 1")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", "o_totalprice").alias("cheapest"), F.max_by("o_orderkey", "o_totalprice").alias("dearest"))


@keep("collect_lists", "SELECT label, len(list(vec_id)) AS n, list_sum(list(vec_id))::BIGINT AS s FROM embeddings GROUP BY 1")
def _(spark, sf_dir):
    held = read_table(spark, sf_dir, "embeddings").groupBy("label").agg(F.collect_list("vec_id").alias("ids"))
    return held.select("label", F.size("ids").cast("long").alias("n"), F.aggregate("ids", F.lit(0).cast("long"), lambda a, x: a + x).alias("s"))


@keep("bit_xor_ids", "SELECT label, bit_xor(vec_id) AS x FROM embeddings GROUP BY 1")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "embeddings").groupBy("label").agg(F.bit_xor("vec_id").alias("x"))


@keep("dist_percentiles", ASSIGNED + " SELECT round(quantile_cont(d, 0.5), 6) AS p50, round(quantile_cont(d, 0.9), 6) AS p90 FROM a0")
def _(spark, sf_dir):
    return assigned(spark, sf_dir).agg(rounded(F.percentile("dist", 0.5)).alias("p50"), rounded(F.percentile("dist", 0.9)).alias("p90"))


@keep("approx_measures")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_extendedprice", [0.5, 0.9]).alias("prices"))


@keep("cluster_label_rollup", ASSIGNED + " SELECT cid, label, count(*) AS n FROM a0 GROUP BY ROLLUP (cid, label)")
def _(spark, sf_dir):
    return assigned(spark, sf_dir).rollup("cid", "label").agg(F.count(F.lit(1)).alias("n"))


@keep("cluster_label_cube", ASSIGNED + " SELECT cid, label, count(*) AS n FROM a0 GROUP BY CUBE (cid, label)")
def _(spark, sf_dir):
    return assigned(spark, sf_dir).cube("cid", "label").agg(F.count(F.lit(1)).alias("n"))


@keep("grouping_sets_lineitem", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def _(spark, sf_dir):
    li = read_table(spark, sf_dir, "lineitem")
    return li.groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@keep("pivot_label", "SELECT lang, count(*) FILTER (source = 'src1') AS src1, count(*) FILTER (source = 'src2') AS src2 FROM documents WHERE source IN ('src1', 'src2') GROUP BY 1")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "documents").where(F.col("source").isin("src1", "src2")).groupBy("lang").pivot("source", ["src1", "src2"]).agg(F.count(F.lit(1))).fillna(0)


@keep("unpivot_prices", "SELECT p_partkey, 'size' AS name, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def _(spark, sf_dir):
    p = read_table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "name", "value")


# ---- windows, sorts ---------------------------------------------------------------------------------------------

@keep("topk_window", "SELECT o_custkey, o_orderkey, rk, dr FROM (SELECT *, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, row_number() OVER w AS rn FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)) WHERE rn <= 2")
def _(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    o = read_table(spark, sf_dir, "orders").withColumn("rn", F.row_number().over(w)).where("rn <= 2")
    return o.withColumn("rk", F.rank().over(w)).withColumn("dr", F.dense_rank().over(w)).select("o_custkey", "o_orderkey", "rk", "dr")


@keep("ntile_dist", ASSIGNED + " SELECT vec_id, CAST(ntile(4) OVER w AS INTEGER) AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM a0 WINDOW w AS (PARTITION BY cid ORDER BY round(d, 9), vec_id)")
def _(spark, sf_dir):
    w = Window.partitionBy("cid").orderBy(F.round("dist", 9), "vec_id")
    return assigned(spark, sf_dir).select("vec_id", F.ntile(4).over(w).alias("quarter"), rounded(F.percent_rank().over(w)).alias("pr"), rounded(F.cume_dist().over(w)).alias("cd"))


@keep("iter_lag", "SELECT event_id, value, value - lag(value, 2) OVER w AS gain, lead(event_id) OVER w AS following FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read_table(spark, sf_dir, "events").select("event_id", "value", (F.col("value") - F.lag("value", 2).over(w)).alias("gain"), F.lead("event_id").over(w).alias("following"))


@keep("first_last_nth", "SELECT DISTINCT o_custkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS n2 FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read_table(spark, sf_dir, "orders").select("o_custkey", F.first("o_orderkey").over(w).alias("f"), F.last("o_orderkey").over(w).alias("l"), F.nth_value("o_orderkey", 2).over(w).alias("n2")).distinct()


@keep("range_frame_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM (SELECT *, CAST(epoch(date_trunc('second', ts)) AS BIGINT) AS s FROM events)")
def _(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return read_table(spark, sf_dir, "events").withColumn("s", F.unix_timestamp(F.col("ts").cast("timestamp"))).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@keep("init_topk_md5", "SELECT vec_id FROM embeddings ORDER BY md5(vec_id || ':9'), vec_id LIMIT 7")
def _(spark, sf_dir):
    from vecspark.operators.seeding import hash_order

    return read_table(spark, sf_dir, "embeddings").orderBy(*hash_order(9)).limit(7).select("vec_id")


@keep("sort_dist_limit", ASSIGNED + " SELECT vec_id, cid FROM a0 ORDER BY round(d, 9) DESC, vec_id LIMIT 10 OFFSET 5")
def _(spark, sf_dir):
    return assigned(spark, sf_dir).orderBy(F.desc(F.round("dist", 9)), "vec_id").offset(5).limit(10).select("vec_id", "cid")


# ---- sets, collections, text, dates -----------------------------------------------------------------------------

@keep("union_vectors", "SELECT 'd' AS t, count(*) AS n FROM documents UNION ALL SELECT 'b', count(*) FROM benchmark")
def _(spark, sf_dir):
    n = lambda t, name: read_table(spark, sf_dir, name).agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("t"), "n")
    return n("d", "documents").unionByName(n("b", "benchmark"))


@keep("distinct_sources", "SELECT DISTINCT source, lang FROM documents")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "documents").select("source", "lang").dropDuplicates()


@keep("array_functions", f"WITH {V} SELECT vec_id, len(list_filter(v, lambda x: x > 0)) AS positive, list_position(v, list_max(v)) - 1 AS top, round(list_max(list_transform(v, lambda x: abs(x))), 6) AS sup FROM v")
def _(spark, sf_dir):
    v = embeddings(spark, sf_dir)
    return v.select("vec_id", F.size(F.filter("vec", lambda x: x > 0)).cast("long").alias("positive"), (F.array_position("vec", F.array_max("vec")) - 1).cast("int").alias("top"), rounded(F.array_max(F.transform("vec", lambda x: F.abs(x.cast("double"))))).alias("sup"))


ORACLES["array_functions"] = ORACLES["array_functions"].replace("list_position(v, list_max(v)) - 1 AS top", "CAST(list_position(v, list_max(v)) - 1 AS INTEGER) AS top")


@keep("json_props", "SELECT event_id, json_extract_string(props, '$.device') AS device, len(json_keys(props)) AS n_keys FROM events".replace("len(json_keys(props))", "CAST(len(json_keys(props)) AS INTEGER)"))
def _(spark, sf_dir):
    e = read_table(spark, sf_dir, "events")
    return e.select("event_id", F.get_json_object("props", "$.device").alias("device"), F.size(F.map_keys(F.from_json("props", "map<string,string>"))).alias("n_keys"))


@keep("map_label_counts", "SELECT CAST(label AS VARCHAR) AS label, count(*) AS n FROM embeddings GROUP BY 1")
def _(spark, sf_dir):
    counted = read_table(spark, sf_dir, "embeddings").groupBy("label").agg(F.count(F.lit(1)).alias("n"))
    held = counted.agg(F.map_from_entries(F.collect_list(F.struct(F.col("label").cast("string"), "n"))).alias("m"))
    return held.select(F.explode("m").alias("label", "n"))


@keep("md5_sample", "SELECT doc_id, md5(text) AS digest, CAST(length(text) AS INTEGER) AS n FROM documents WHERE text IS NOT NULL")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "documents").where("text IS NOT NULL").select("doc_id", F.md5("text").alias("digest"), F.length("text").alias("n"))


@keep("string_functions", "SELECT p_partkey, lower(p_brand) AS b, regexp_replace(p_brand, '[0-9]+', '#', 'g') AS r, split_part(p_type, ' ', 1) AS t FROM part")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "part").select("p_partkey", F.lower("p_brand").alias("b"), F.regexp_replace("p_brand", "[0-9]+", "#").alias("r"), F.split("p_type", " ")[0].alias("t"))


@keep("event_hour_features", "SELECT user_id, CAST(hour(ts) AS INTEGER) AS h, count(*) AS n, round(avg(value), 6) AS v FROM events GROUP BY 1, 2")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "events").groupBy("user_id", F.hour("ts").alias("h")).agg(F.count(F.lit(1)).alias("n"), rounded(F.avg("value")).alias("v"))


@keep("order_month_agg", "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1, 2")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count(F.lit(1)).alias("n"), rounded(F.sum("o_totalprice"), 2).alias("total"))


@keep("date_arithmetic", "SELECT o_orderkey, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "orders").select("o_orderkey", F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).alias("days"))


@keep("sql_assign_label", ASSIGNED + " SELECT cid, mode(label) IS NOT NULL AS labelled, count(*) AS n FROM a0 GROUP BY 1")
def _(spark, sf_dir):
    assigned(spark, sf_dir).createOrReplaceTempView("vecspark_assigned")
    return spark.sql("SELECT cid, mode(label) IS NOT NULL AS labelled, count(*) AS n FROM vecspark_assigned GROUP BY cid")


@keep("sample_strata")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "embeddings").sampleBy("label", {i: 0.5 for i in range(10)}, seed=1).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@keep("random_split")
def _(spark, sf_dir):
    a, b = read_table(spark, sf_dir, "embeddings").select("vec_id").randomSplit([0.7, 0.3], seed=1)
    return a.agg(F.count(F.lit(1)).alias("a")).join(F.broadcast(b.agg(F.count(F.lit(1)).alias("b"))))


@keep("correlation", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem")
def _(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem").agg(rounded(F.corr("l_quantity", "l_extendedprice")).alias("r"))


SHRINKING = """WITH RECURSIVE t(l_suppkey, i, d1) AS (
  SELECT l_suppkey, 1, CAST(count(*) AS INT) FROM {lines} GROUP BY l_suppkey
  UNION ALL SELECT l_suppkey, i + 1, CAST(floor(d1 * 0.8) AS INT) FROM t WHERE i < 6
) SELECT l_suppkey, i, d1 FROM t"""


@keep("recursive_iter_table", SHRINKING.format(lines="lineitem"))
def _(spark, sf_dir):
    """Widths that begin with a supplier's number of lines and shrink by a fifth each round."""
    read_table(spark, sf_dir, "lineitem").createOrReplaceTempView("vecspark_lines")
    return spark.sql(SHRINKING.format(lines="vecspark_lines"))
