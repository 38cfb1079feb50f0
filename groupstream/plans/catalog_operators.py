"""Queries on the operators, functions, sources and streams around the methods, with their SQL."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..functions.register import register
from ..model import groups as G
from ..operators.joins import asof, interval_join, positions, salted_join, top_n
from ..sources.arrivals import ItemArrivals
from ..index import lsh
from ..sources.storage import round_trip, save_bucketed, settle, shared_dir
from ..sources.tables import Tables, seconds
from ..streaming import jobs
from .cte import compose

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None, **extra: str):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = compose(sql, extra)
        return f

    return add


_SECOND = "floor(epoch({}))::BIGINT"


def _epoch(column: str):
    """Seconds of a TIMESTAMP in UTC, whatever the session's zone showed when NTZ was cast: both casts cancel out."""
    return F.expr(f"timestampdiff(SECOND, timestamp_ntz'1970-01-01 00:00:00', cast({column} as timestamp_ntz))")


def _events(spark, d) -> DataFrame:
    return jobs.with_time(Tables(spark, d).events)


@query("events_tumbling", f"SELECT {_SECOND.format('date_trunc(' + chr(39) + 'day' + chr(39) + ', ts)')} AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def _(spark, d):
    t = Tables(spark, d).events.withColumn("start", F.date_trunc("day", "ts"))
    return t.groupBy(_epoch("start").alias("start"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("events_sliding", "SELECT start, event_type, count(*) AS n FROM (SELECT event_type, date_diff('day', DATE '1970-01-01', ts::DATE) - k AS start FROM events, (SELECT unnest(range(7)) AS k)) GROUP BY 1, 2")
def _(spark, d):
    day = F.datediff("ts", F.lit("1970-01-01").cast("date"))
    rows = Tables(spark, d).events.select("event_type", F.explode(F.array(*[(day - k).cast("long") for k in range(7)])).alias("start"))
    return rows.groupBy("start", "event_type").agg(F.count("*").alias("n"))


@query("events_session", f"SELECT user_id, min(s) AS start, max(s) + 1800 AS end, count(*) AS n FROM (SELECT user_id, s, sum(new) OVER (PARTITION BY user_id ORDER BY s, event_id ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT user_id, event_id, {_SECOND.format('ts')} AS s, CASE WHEN {_SECOND.format('ts')} - lag({_SECOND.format('ts')}) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= 1800 THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, k")
def _(spark, d):
    rows = Tables(spark, d).events.select("user_id", "event_id", seconds("ts").alias("s"))
    order = Window.partitionBy("user_id").orderBy("s", "event_id")
    rows = rows.withColumn("new", F.when(F.col("s") - F.lag("s").over(order) <= 1800, 0).otherwise(1))
    rows = rows.withColumn("k", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return rows.groupBy("user_id", "k").agg(F.min("s").alias("start"), (F.max("s") + 1800).alias("end"), F.count("*").alias("n")).drop("k")


@query("json_props", "SELECT json_extract_string(props, '$.k')::BIGINT AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    return Tables(spark, d).events.groupBy(F.from_json("props", "k long")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("asof_last_event", f"SELECT u.user_id, u.s, e.value AS last_value FROM (SELECT DISTINCT user_id, {_SECOND.format('ts')} AS s FROM events WHERE event_type = 'purchase') u ASOF LEFT JOIN (SELECT {_SECOND.format('ts')} AS s, min(value) AS value FROM events WHERE event_type = 'signup' GROUP BY 1) e ON u.s >= e.s")
def _(spark, d):
    events = Tables(spark, d).events.select("user_id", "event_type", seconds("ts").alias("s"), "value")
    left = events.where("event_type = 'purchase'").select("user_id", "s").distinct()
    right = events.where("event_type = 'signup'").groupBy(F.col("s").alias("at_s")).agg(F.min("value").alias("value"))
    return asof(left, right, "s", "at_s", 86_400).select("user_id", "s", F.col("at.value").alias("last_value"))


@query("interval_join_events", f"SELECT count(*) AS n, count(DISTINCT v.user_id) AS users FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND {_SECOND.format('p.ts')} - {_SECOND.format('v.ts')} BETWEEN 0 AND 86400")
def _(spark, d):
    events = Tables(spark, d).events.select("user_id", "event_type", seconds("ts").alias("s"))
    views, buys = events.where("event_type = 'view'").select("user_id", F.col("s").alias("viewed")), events.where("event_type = 'purchase'").select("user_id", F.col("s").alias("bought"))
    return interval_join(views, buys, "user_id", "viewed", "bought", 0, 86_400).agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"))


@query("salted_join", "SELECT nk, count(*) AS n, round(sum(price), 2) AS paid FROM lines JOIN nation ON n_nationkey = nk GROUP BY 1")
def _(spark, d):
    t = Tables(spark, d)
    both = salted_join(t.lines(), t.nation.select(F.col("n_nationkey").cast("long").alias("nk"), "n_name"), ["nk"], 4)
    return both.groupBy("nk").agg(F.count("*").alias("n"), F.round(F.sum("price"), 2).alias("paid"))


@query("rollup_interactions", "SELECT nk, s % 5 AS lane, grouping_id(nk, s % 5) AS level, count(*) AS n FROM lines GROUP BY ROLLUP (nk, s % 5)")
def _(spark, d):
    rows = Tables(spark, d).lines().withColumn("lane", F.col("s") % 5)
    return rows.rollup("nk", "lane").agg(F.grouping_id().alias("level"), F.count("*").alias("n"))


@query("cube_interactions", "SELECT seg, region, grouping_id(seg, region) AS level, count(*) AS n FROM (SELECT c_mktsegment AS seg, n_regionkey AS region FROM customer JOIN nation ON n_nationkey = c_nationkey) GROUP BY CUBE (seg, region)")
def _(spark, d):
    t = Tables(spark, d)
    rows = t.customer.join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_mktsegment").alias("seg"), F.col("n_regionkey").alias("region"))
    return rows.cube("seg", "region").agg(F.grouping_id().alias("level"), F.count("*").alias("n"))


@query("pivot_event_types", "SELECT user_id, " + ", ".join(f"count(CASE WHEN event_type = '{k}' THEN 1 END) AS {k}" for k in ("click", "purchase", "view")) + " FROM events GROUP BY 1")
def _(spark, d):
    rows = Tables(spark, d).events.groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1)))
    return rows.na.fill(0)


@query("unpivot_prices", "SELECT p_partkey, 'p_size' AS name, p_size::DOUBLE AS amount FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")
def _(spark, d):
    part = Tables(spark, d).part.select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return part.unpivot(["p_partkey"], ["p_size", "p_retailprice"], "name", "amount")


@query("orders_without_lines", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def _(spark, d):
    t = Tables(spark, d)
    return t.orders.join(t.lineitem, F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query("semi_join_active", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT user_id FROM events WHERE event_type = 'purchase')")
def _(spark, d):
    t = Tables(spark, d)
    return t.customer.join(t.events.where("event_type = 'purchase'"), F.col("c_custkey") == F.col("user_id"), "left_semi").select("c_custkey")


@query("outer_join_suppliers", "SELECT s_suppkey, coalesce(n, 0) AS n FROM supplier LEFT JOIN (SELECT s, count(*) AS n FROM lines WHERE day > 10957 GROUP BY 1) ON s = s_suppkey")
def _(spark, d):
    t = Tables(spark, d)
    sold = t.lines().where("day > 10957").groupBy("s").agg(F.count("*").alias("n"))
    return t.supplier.join(sold, F.col("s_suppkey") == F.col("s"), "left").select("s_suppkey", F.coalesce("n", F.lit(0)).alias("n"))


@query("set_operations", "SELECT (SELECT count(*) FROM (SELECT v FROM lines WHERE s = 1 INTERSECT SELECT v FROM lines WHERE s = 2)) AS common, (SELECT count(*) FROM (SELECT v FROM lines WHERE s = 1 EXCEPT SELECT v FROM lines WHERE s = 2)) AS only_first, (SELECT count(*) FROM (SELECT v FROM lines WHERE s = 1 UNION SELECT v FROM lines WHERE s = 2)) AS either_one, (SELECT count(*) FROM (SELECT v FROM lines WHERE s = 1 INTERSECT ALL SELECT v FROM lines WHERE s = 2)) AS bag")
def _(spark, d):
    lines = Tables(spark, d).lines()
    a, b = lines.where("s = 1").select("v"), lines.where("s = 2").select("v")
    n = lambda df, name: df.agg(F.count("*").alias(name))
    return n(a.intersect(b), "common").join(n(a.subtract(b), "only_first")).join(n(a.union(b).distinct(), "either_one")).join(n(a.intersectAll(b), "bag"))


@query("top_n_per_group", "SELECT u, v, day FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY day DESC, v) AS n FROM (SELECT DISTINCT u, v, day FROM lines)) WHERE n <= 3")
def _(spark, d):
    return top_n(Tables(spark, d).lines().select("u", "v", "day").distinct(), ["u"], [F.desc("day"), F.col("v")], 3)


@query("window_ranks", "SELECT s_suppkey, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, ntile(4) OVER (ORDER BY s_acctbal, s_suppkey) AS quarter, round(cume_dist() OVER w, 6) AS cd FROM supplier WINDOW w AS (ORDER BY s_nationkey)")
def _(spark, d):
    w, total = Window.orderBy("s_nationkey"), Window.orderBy("s_acctbal", "s_suppkey")
    return Tables(spark, d).supplier.select("s_suppkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.ntile(4).over(total).alias("quarter"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("window_frames", "SELECT u, day, paid, round(sum(paid) OVER (PARTITION BY u ORDER BY day), 2) AS so_far, round(sum(paid) OVER (PARTITION BY u ORDER BY day RANGE BETWEEN 90 PRECEDING AND CURRENT ROW), 2) AS recent, lag(day) OVER (PARTITION BY u ORDER BY day) AS before FROM (SELECT u, day, round(sum(price), 2) AS paid FROM lines GROUP BY 1, 2)")
def _(spark, d):
    rows = Tables(spark, d).lines().groupBy("u", "day").agg(F.round(F.sum("price"), 2).alias("paid"))
    w = Window.partitionBy("u").orderBy("day")
    return rows.select("u", "day", "paid", F.round(F.sum("paid").over(w), 2).alias("so_far"), F.round(F.sum("paid").over(w.rangeBetween(-90, 0)), 2).alias("recent"), F.lag("day").over(w).alias("before"))


@query("percentiles", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.8), 6) AS p80 FROM events GROUP BY 1")
def _(spark, d):
    return Tables(spark, d).events.groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("median"), F.round(F.percentile("value", F.lit(0.8)), 6).alias("p80"))


@query("statistics", "SELECT l_returnflag, count(*) AS n, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS var, round(corr(l_quantity, l_extendedprice), 6) AS corr, max_by(l_orderkey, l_orderkey) AS top FROM lineitem GROUP BY 1")
def _(spark, d):
    return Tables(spark, d).lineitem.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("var"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.max_by("l_orderkey", "l_orderkey").alias("top"))


@query("string_functions", "SELECT page_id, lower(regexp_extract(url, '^https?://([^/]+)', 1)) AS host, length(url) AS n, regexp_replace(substr(url, 1, 12), '[^a-z]', '-', 'g') AS head FROM pages")
def _(spark, d):
    return Tables(spark, d).pages.select("page_id", F.lower(F.regexp_extract("url", "^https?://([^/]+)", 1)).alias("host"), F.length("url").alias("n"), F.regexp_replace(F.substring("url", 1, 12), "[^a-z]", "-").alias("head"))


@query("conditional_functions", "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size BETWEEN 10 AND 30 THEN 'medium' ELSE 'large' END AS kind, greatest(p_size, 10) AS at_least, nullif(p_size, 10) AS not_ten FROM part WHERE p_name LIKE '%a%' AND p_brand IS NOT NULL")
def _(spark, d):
    size = F.col("p_size")
    kind = F.when(size < 10, "small").when(size.between(10, 30), "medium").otherwise("large")
    return Tables(spark, d).part.where(F.col("p_name").like("%a%") & F.col("p_brand").isNotNull()).select("p_partkey", kind.alias("kind"), F.greatest(size, F.lit(10)).alias("at_least"), F.nullif(size, F.lit(10)).alias("not_ten"))


@query("date_functions", "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, date_diff('day', DATE '1970-01-01', (o_orderdate + INTERVAL 2 MONTH)::DATE)::INTEGER AS later FROM orders")
def _(spark, d):
    at = F.col("o_orderdate").cast("date")
    return Tables(spark, d).orders.select("o_orderkey", F.year(at).alias("y"), F.month(at).alias("m"), F.datediff(F.add_months(at, 2), F.lit("1970-01-01").cast("date")).alias("later"))


@query("array_functions", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)), 5) AS total, len(list_filter(embedding, lambda x: x > 0)) AS positive, len(embedding) AS n FROM embeddings")
def _(spark, d):
    vec = F.transform("embedding", lambda x: x.cast("double"))
    return Tables(spark, d).embeddings.select("vec_id", F.round(F.aggregate(vec, F.lit(0.0), lambda s, x: s + x), 5).alias("total"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.size("embedding").alias("n"))


@query("bit_functions", "SELECT p_partkey, bit_count(p_partkey) AS ones, (p_partkey << 3) & 255 AS low, xor(p_partkey, 85) AS flipped FROM part")
def _(spark, d):
    k = F.col("p_partkey")
    return Tables(spark, d).part.select("p_partkey", F.bit_count(k).alias("ones"), F.shiftleft(k, 3).bitwiseAND(F.lit(255)).alias("low"), k.bitwiseXOR(F.lit(85)).alias("flipped"))


@query("map_functions", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    counts = Tables(spark, d).events.groupBy("event_type").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return counts.select(F.explode(F.map_filter("m", lambda k, v: v > 0)).alias("event_type", "n"))


@query("sql_functions", "SELECT vec_id, round(list_dot_product(list_transform(embedding, lambda x: x::DOUBLE), list_transform(embedding, lambda x: x::DOUBLE)), 5) AS square FROM embeddings")
def _(spark, d):
    register(spark, Tables(spark, d))
    return spark.sql("SELECT vec_id, round(gs_dot(transform(embedding, x -> CAST(x AS DOUBLE)), transform(embedding, x -> CAST(x AS DOUBLE))), 5) AS square FROM gs_embeddings")


@query("lateral_top", "SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 1)")
def _(spark, d):
    register(spark, Tables(spark, d))
    return spark.sql("SELECT n_nationkey, c_custkey FROM gs_nation, LATERAL (SELECT c_custkey FROM gs_customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 1)")


for _fmt in ("json", "orc", "csv"):

    @query(f"round_trip_{_fmt}", "SELECT event_id, user_id, event_type, value FROM events")
    def _(spark, d, fmt=_fmt):
        return round_trip(Tables(spark, d).events.select("event_id", "user_id", "event_type", "value"), fmt)


@query("synthetic_arrivals", "SELECT item, v, (v * 7919) % 1000 AS price, 'tag' || (v % 13) AS tag FROM (SELECT p_partkey AS item, row_number() OVER (ORDER BY p_partkey) - 1 AS v FROM part)")
def _(spark, d):
    """One synthetic arrival for each part, in the order of their keys."""
    items = positions(Tables(spark, d).part.select(F.col("p_partkey").alias("item")), ["item"], "v")
    spark.dataSource.register(ItemArrivals)
    arrivals = spark.read.format("item_arrivals").option("rows", items.count()).option("partitions", 4).load()
    return items.join(arrivals, "v").select("item", "v", "price", "tag")


@query("grouped_udaf", "SELECT label, " + ", ".join(f"round(avg(embedding[{i + 1}]::DOUBLE), 6) AS x{i}" for i in range(8)) + " FROM embeddings GROUP BY 1")
def _(spark, d):
    """The mean vector of each label, as a grouped function over Arrow batches."""

    def mean(rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"label": [rows["label"].iloc[0]], "mean": [np.array(rows["vec"].tolist(), np.float64).mean(0)]})

    rows = Tables(spark, d).embeddings.select("label", F.slice("embedding", 1, 8).cast("array<double>").alias("vec"))
    found = rows.groupBy("label").applyInPandas(mean, "label int, mean array<double>")
    return found.select("label", *[F.round(F.get("mean", F.lit(i)), 6).alias(f"x{i}") for i in range(8)])


_LINES_BY_NATION = "SELECT nk, count(*) AS n, round(sum(price), 2) AS paid FROM lines JOIN nation ON n_nationkey = nk GROUP BY 1"
for _hint in ("broadcast", "merge", "shuffle_hash", "shuffle_replicate_nl"):

    @query(f"join_hint_{_hint}", _LINES_BY_NATION)
    def _(spark, d, hint=_hint):
        t = Tables(spark, d)
        nations = t.nation.select(F.col("n_nationkey").cast("long").alias("nk"))
        return t.lines().join(nations.hint(hint), "nk").groupBy("nk").agg(F.count("*").alias("n"), F.round(F.sum("price"), 2).alias("paid"))


@query("grouping_sets", "SELECT c_nationkey, c_mktsegment, count(*) AS n, grouping_id(c_nationkey, c_mktsegment) AS level FROM customer GROUP BY GROUPING SETS ((c_nationkey), (c_mktsegment), (c_nationkey, c_mktsegment))")
def _(spark, d):
    c = Tables(spark, d).customer
    sets = [[F.col("c_nationkey")], [F.col("c_mktsegment")], [F.col("c_nationkey"), F.col("c_mktsegment")]]
    return c.groupingSets(sets, "c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query("approximate_distinct", "SELECT event_type, true AS users_near, true AS median_near, true AS merged_near FROM events GROUP BY 1")
def _(spark, d):
    """Distinct users by HyperLogLog, sketches of the days merged to one, and an approximate median, each within its error."""
    events = Tables(spark, d).events.select("event_type", "user_id", "value", F.to_date("ts").alias("day"))
    per_day = events.groupBy("event_type", "day").agg(F.hll_sketch_agg("user_id").alias("sketch"))
    merged = per_day.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("merged"))
    both = events.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.countDistinct("user_id").alias("exact"), F.percentile_approx("value", 0.5, 10_000).alias("m"), F.percentile("value", F.lit(0.48)).alias("low"), F.percentile("value", F.lit(0.52)).alias("high"))
    near = lambda c: F.abs(F.col(c) - F.col("exact")) <= 0.1 * F.col("exact") + 3
    return both.join(merged, "event_type").select("event_type", near("users").alias("users_near"), F.col("m").between(F.col("low"), F.col("high")).alias("median_near"), near("merged").alias("merged_near"))


@query("observed_metrics", "SELECT count(*) AS n, count(*) FILTER (event_type = 'purchase') AS purchases, round(sum(value), 4) AS total FROM events")
def _(spark, d):
    """Counters that ride along with another job instead of a pass of their own."""
    seen = Observation(f"events-{uuid.uuid4().hex}")
    events = Tables(spark, d).events.observe(seen, F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("event_type") == "purchase", 1)).alias("purchases"), F.round(F.sum("value"), 4).alias("total"))
    events.select("user_id", "event_type", "value").write.format("noop").mode("overwrite").save()
    found = seen.get
    return spark.createDataFrame([(found["n"], found["purchases"], found["total"])], "n long, purchases long, total double")


@query("zorder_cross_check", "SELECT p_partkey, " + " | ".join(f"(((x{i} >> {b}) & 1) << {b * 3 + 2 - i})" for b in range(8) for i in range(3)) + " AS z FROM (SELECT p_partkey, p_partkey & 255 AS x0, (p_partkey >> 2) & 255 AS x1, (p_size & 255)::BIGINT AS x2 FROM part)")
def _(spark, d):
    """Z order by Arrow batches; its SQL, and the column expression of the index, give the same keys."""

    @F.pandas_udf("long")
    def weave(cells: pd.Series) -> pd.Series:
        x = np.array(cells.tolist(), np.int64).reshape(len(cells), 3)
        key = np.zeros(len(x), np.int64)
        for b in range(7, -1, -1):
            for i in range(3):
                key = (key << 1) | ((x[:, i] >> b) & 1)
        return pd.Series(key)

    k = F.col("p_partkey")
    cells = F.array(k.bitwiseAND(F.lit(255)), F.shiftright(k, 2).bitwiseAND(F.lit(255)), F.col("p_size").cast("long").bitwiseAND(F.lit(255)))
    rows = Tables(spark, d).part.select("p_partkey", cells.alias("cells"))
    both = rows.select("p_partkey", weave("cells").alias("z"), lsh.interleave(F.col("cells"), 3, 8).alias("own"))
    return both.select("p_partkey", F.when(F.col("z") == F.col("own"), F.col("z")).alias("z"))


@query("table_function", "SELECT p_partkey, unnest(range(1, len(words) + 1)) AS place, unnest(words) AS word FROM (SELECT p_partkey, string_split(p_name, ' ') AS words FROM part)")
def _(spark, d):
    """A table function: each part's words with their places, joined laterally."""

    @F.udtf(returnType="place bigint, word string")
    class Words:
        def eval(self, name: str):
            for place, word in enumerate((name or "").split(" "), 1):
                yield place, word

    spark.udtf.register("gs_words", Words)
    register(spark, Tables(spark, d))
    return spark.sql("SELECT p_partkey, w.place, w.word FROM gs_part, LATERAL gs_words(p_name) w")


@query("bucketed_join", "SELECT o.o_custkey, count(*) AS n FROM orders o JOIN lineitem l ON l.l_orderkey = o.o_orderkey GROUP BY 1")
def _(spark, d):
    """Both sides stored in buckets of the order key, so that the join reads them without an exchange."""
    t, tag = Tables(spark, d), uuid.uuid4().hex[:12]
    names = f"gs_orders_{tag}", f"gs_lines_{tag}"
    for name, rows in zip(names, (t.orders.select(F.col("o_orderkey").alias("k"), "o_custkey"), t.lineitem.select(F.col("l_orderkey").alias("k")))):
        save_bucketed(rows, name, 8, "k", "k", f"{shared_dir(spark)}/{name}")
    left, right = (spark.table(n) for n in names)
    return left.join(right.hint("merge"), "k").groupBy("o_custkey").agg(F.count("*").alias("n"))


@query("round_trip_text", "SELECT event_id || ' ' || event_type AS value FROM events")
def _(spark, d):
    return round_trip(Tables(spark, d).events.select(F.concat_ws(" ", "event_id", "event_type").alias("value")), "text")


# Streams: the replay of the events file, checked against the same question asked in SQL.


@query("stream_tumbling", f"SELECT {_SECOND.format('date_trunc(' + chr(39) + 'day' + chr(39) + ', ts)')} AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, d):
    out = jobs.replayed(jobs.tumbling(jobs.events_stream(spark, d)), "complete")
    return out.select(_epoch("start").alias("start"), "event_type", "n")


@query("stream_dedup", "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def _(spark, d):
    out = jobs.replayed(jobs.deduplicated(jobs.events_stream(spark, d)))
    return out.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@query("stream_group_state", f"SELECT h.g, count(*) AS n, max({_SECOND.format('e.ts')}) AS last_second FROM events e JOIN home h ON h.u = e.user_id GROUP BY 1")
def _(spark, d):
    members = G.home_groups(Tables(spark, d))
    out = jobs.replayed(jobs.group_state(jobs.with_groups(jobs.events_stream(spark, d), members)), "update")
    return out.groupBy("g").agg(F.max("n").alias("n"), F.max("last_second").alias("last"), F.lit(0).alias("z")).select("g", "n", _epoch("timestamp_seconds(last)").alias("last_second"))


@query("stream_purchases_after_views", f"SELECT count(*) AS n FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND {_SECOND.format('p.ts')} - {_SECOND.format('v.ts')} BETWEEN 0 AND 86400")
def _(spark, d):
    return jobs.replayed(jobs.purchases_after_views(jobs.events_stream(spark, d))).agg(F.count("*").alias("n"))


@query("stream_sliding", "SELECT start, event_type, count(*) AS n FROM (SELECT event_type, date_diff('day', DATE '1970-01-01', ts::DATE) - k AS start FROM events, (SELECT unnest(range(7)) AS k)) GROUP BY 1, 2")
def _(spark, d):
    out = jobs.replayed(jobs.sliding(jobs.events_stream(spark, d)), "complete")
    return out.select(F.datediff(F.col("start").cast("timestamp_ntz"), F.lit("1970-01-01").cast("date")).cast("long").alias("start"), "event_type", "n")


@query("stream_sessions", "SELECT user_id, min(us) // 1000000 AS start, max(us) // 1000000 + 1800 AS end, count(*) AS n FROM (SELECT user_id, us, sum(new) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT user_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) <= 1800000000 THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, k")
def _(spark, d):
    out = jobs.replayed(jobs.sessions(jobs.events_stream(spark, d)), "complete")
    return out.select("user_id", _epoch("start").alias("start"), _epoch("end").alias("end"), "n")


@query("stream_late_events", f"SELECT count(*) AS arrived, count(*) FILTER (s < mark) AS too_late, count(*) FILTER (s >= mark) AS in_time FROM (SELECT {_SECOND.format('ts')} AS s FROM events WHERE event_type = 'purchase'), (SELECT max(epoch_us(ts)) / 1000000.0 - 3600 AS mark FROM events WHERE event_type <> 'purchase')".replace("floor(epoch(ts))::BIGINT AS s FROM events WHERE event_type = 'purchase'", "epoch_us(ts) / 1000000.0 AS s FROM events WHERE event_type = 'purchase'"))
def _(spark, d):
    """Purchases arrive after all other events have moved the watermark: those that it has passed are dropped, and counted."""
    events = Tables(spark, d).events
    return jobs.late_rows(events.where("event_type <> 'purchase'"), events.where("event_type = 'purchase'"), "1 hour")
