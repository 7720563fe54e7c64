"""Operators around the methods: scans, predicates, joins, aggregates, windows, sets, functions, subqueries, event time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..registry import query
from ..sources import store
from ..sources.tables import hierarchy, table, views


def t(spark, sf, *names):
    return tuple(table(spark, sf, n) for n in names)


def ev(spark, sf) -> DataFrame:
    return table(spark, sf, "events")


def sql(name: str, text: str, oracle: str | None = None, *tables: str) -> None:
    """A query through Spark SQL; the oracle text differs only where the dialects do."""

    def run(spark, sf):
        views(spark, sf, *tables)
        return spark.sql(text)

    query(oracle or text, name)(run)


r6 = lambda c: F.round(c, 6)
_H = "events AS e JOIN customer AS c ON c.c_custkey = e.user_id JOIN nation AS n ON n.n_nationkey = c.c_nationkey JOIN region AS r ON r.r_regionkey = n.n_regionkey"

# ---- scans, sources, sinks --------------------------------------------------------------------------------
query("SELECT event_id, ts, user_id, event_type, value, props FROM events", "scan_events")(lambda spark, sf: ev(spark, sf))
query("SELECT l_orderkey, l_quantity FROM lineitem", "scan_pruned")(lambda spark, sf: table(spark, sf, "lineitem").select("l_orderkey", "l_quantity"))
query("SELECT l_orderkey, l_shipdate FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01'", "scan_pushdown")(
    lambda spark, sf: table(spark, sf, "lineitem").where(F.col("l_shipdate") >= F.expr("timestamp_ntz'1997-01-01'")).select("l_orderkey", "l_shipdate")
)
query("SELECT date_trunc('day', ts) AS day, user_id, count(*) AS n, min(value) AS low, max(value) AS high FROM events GROUP BY ALL", "store_roundtrip")(
    lambda spark, sf: store.facts(store.write_and_read(spark, sf))
)
query("SELECT date_trunc('day', ts) AS day, user_id, count(*) AS n, min(value) AS low, max(value) AS high FROM events WHERE ts >= TIMESTAMP '2024-01-10' AND ts < TIMESTAMP '2024-01-13' GROUP BY ALL", "store_pruned")(
    lambda spark, sf: store.facts(store.write_and_read(spark, sf).where("day between date'2024-01-10' and date'2024-01-12'"))
)
for _fmt, _tab in (("csv", "nation"), ("json", "supplier"), ("orc", "region")):
    query(f"SELECT * FROM {_tab}", f"{_fmt}_roundtrip")(lambda spark, sf, f=_fmt, n=_tab: store.roundtrip(table(spark, sf, n), f))
query("SELECT user_id, count(*) AS n, min(value) AS low, max(value) AS high FROM events GROUP BY user_id", "digest_to_json")(lambda spark, sf: store.through_json(spark, sf))
query(None, "source_simulated")(lambda spark, sf: store.simulated(spark, leaves=20, per_leaf=50, seed=3))

# ---- projection, predicates, conditionals -----------------------------------------------------------------
query("SELECT event_id, round(ln(1 + value), 9) AS logged, value / 1000 AS scaled FROM events", "proj_scaled")(
    lambda spark, sf: ev(spark, sf).select("event_id", F.round(F.log1p("value"), 9).alias("logged"), (F.col("value") / 1000).alias("scaled"))
)
query("SELECT event_id, value FROM events WHERE event_type IN ('error', 'click') AND ts >= TIMESTAMP '2024-01-08' AND ts < TIMESTAMP '2024-01-15' AND value BETWEEN 10 AND 100", "filter_slice")(
    lambda spark, sf: ev(spark, sf).where(F.col("event_type").isin("error", "click") & F.col("value").between(10, 100) & F.expr("ts >= timestamp_ntz'2024-01-08' and ts < timestamp_ntz'2024-01-15'")).select("event_id", "value")
)
query("SELECT c_custkey, c_name FROM customer WHERE c_name LIKE '%1%' AND regexp_matches(c_name, '[0-9]*7$')", "filter_like")(
    lambda spark, sf: table(spark, sf, "customer").where(F.col("c_name").like("%1%") & F.col("c_name").rlike("[0-9]*7$")).select("c_custkey", "c_name")
)
query("SELECT event_type, CASE WHEN value < 20 THEN 'good' WHEN value < 100 THEN 'fair' ELSE 'poor' END AS band, count(*) AS n FROM events GROUP BY ALL", "bucket_case")(
    lambda spark, sf: ev(spark, sf).groupBy("event_type", F.when(F.col("value") < 20, "good").when(F.col("value") < 100, "fair").otherwise("poor").alias("band")).agg(F.count("*").alias("n"))
)
query("SELECT user_id, CAST(count(*) FILTER (WHERE event_type = 'error') AS DOUBLE) / nullif(count(*) FILTER (WHERE event_type = 'click'), 0) AS ratio, coalesce(nullif(max(event_type), 'view'), 'none') AS top FROM events GROUP BY user_id", "fn_null")(
    lambda spark, sf: ev(spark, sf).groupBy("user_id").agg(F.try_divide(F.count_if(F.col("event_type") == "error"), F.count_if(F.col("event_type") == "click")).alias("ratio"), F.coalesce(F.nullif(F.max("event_type"), F.lit("view")), F.lit("none")).alias("top"))
)
query("SELECT event_id, value FROM events WHERE (event_id * 2654435761) % 100 = 7", "sample_hash")(lambda spark, sf: ev(spark, sf).where((F.col("event_id") * 2654435761) % 100 == 7).select("event_id", "value"))

# ---- joins ------------------------------------------------------------------------------------------------
query(f"SELECT r_name AS region, n_name AS nation, count(*) AS n FROM {_H} GROUP BY ALL", "join_hierarchy")(
    lambda spark, sf: ev(spark, sf).join(hierarchy(spark, sf), "user_id").groupBy("region", "nation").agg(F.count("*").alias("n"))
)


def _order_line(hint: str):
    def run(spark, sf):
        o, l = t(spark, sf, "orders", "lineitem")
        j = o.join(l.hint(hint), o.o_orderkey == l.l_orderkey)
        return j.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("quantity"))

    return run


query("SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 4) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL", "join_order_line")(_order_line("merge"))
query("SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL", "join_hash_hint")(
    lambda spark, sf: (lambda o, c: o.join(c.hint("shuffle_hash"), o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n")))(*t(spark, sf, "orders", "customer"))
)
for _how in ("left", "right", "full"):
    query(f"SELECT c_custkey, u.user_id, u.n FROM customer {_how.upper()} JOIN (SELECT user_id + 75 AS user_id, count(*) AS n FROM events GROUP BY user_id) AS u ON c_custkey = u.user_id", f"join_outer_{_how}")(
        lambda spark, sf, how=_how: (lambda c, u: c.join(u, c.c_custkey == u.user_id, how).select("c_custkey", "user_id", "n"))(table(spark, sf, "customer"), ev(spark, sf).groupBy((F.col("user_id") + 75).alias("user_id")).agg(F.count("*").alias("n")))
    )
query("SELECT DISTINCT user_id FROM events WHERE user_id IN (SELECT c_custkey FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey WHERE r_name = 'ASIA')", "leaves_in_region")(
    lambda spark, sf: ev(spark, sf).select("user_id").distinct().join(hierarchy(spark, sf).where("region = 'ASIA'"), "user_id", "left_semi")
)
query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events)", "customers_without_events")(
    lambda spark, sf: (lambda c, e: c.join(e, c.c_custkey == e.user_id, "left_anti").select("c_custkey"))(*t(spark, sf, "customer", "events"))
)
query("SELECT user_id, CAST(p AS DOUBLE) AS level FROM (SELECT DISTINCT user_id FROM events) AS u CROSS JOIN (SELECT unnest([0.5, 0.9, 0.99]) AS p) AS l", "cross_levels")(
    lambda spark, sf: ev(spark, sf).select("user_id").distinct().crossJoin(F.broadcast(spark.range(1).select(F.explode(F.array(F.lit(0.5), F.lit(0.9), F.lit(0.99))).alias("level"))))
)
query("SELECT band, count(*) AS n FROM events JOIN (VALUES ('p50', 30.0), ('p90', 110.0), ('p99', 230.0)) AS b(band, low) ON value > low GROUP BY band", "join_theta_sla")(
    lambda spark, sf: ev(spark, sf).join(F.broadcast(spark.sql("select * from values ('p50', 30.0D), ('p90', 110.0D), ('p99', 230.0D) as b(band, low)")), F.col("value") > F.col("low")).groupBy("band").agg(F.count("*").alias("n"))
)
@query("SELECT CAST(floor(value / 25) * 25 AS DOUBLE) AS lo, count(*) AS n FROM events GROUP BY ALL")
def join_range(spark, sf):
    """Cells [lo, lo + 25) meet values by the number of their cell, an equi-join, and the range is then a filter.

    Cells are all those between the extremes, a table small enough to be sent whole; where they are many, those that hold values.
    """
    e = ev(spark, sf).withColumn("cell", F.floor(F.col("value") / 25))
    a, b = e.agg(F.min("cell"), F.max("cell")).first()
    cells = spark.range(a, b + 1).select(F.col("id").alias("cell")) if a is not None and b - a < 30_000 else e.select("cell").distinct()
    return e.join(cells.withColumn("lo", F.col("cell") * 25.0), "cell").where("value >= lo and value < lo + 25").groupBy("lo").agg(F.count("*").alias("n"))


query("SELECT e.event_id, (SELECT max_by(p.event_id, (p.ts, p.event_id)) FROM events AS p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND (p.ts, p.event_id) < (e.ts, e.event_id)) AS previous FROM events AS e WHERE e.event_type = 'error'".replace("max_by(p.event_id, (p.ts, p.event_id))", "arg_max(p.event_id, row(p.ts, p.event_id))").replace("(p.ts, p.event_id) < (e.ts, e.event_id)", "row(p.ts, p.event_id) < row(e.ts, e.event_id)"), "join_asof")(
    lambda spark, sf: ev(spark, sf).withColumn("previous", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1))).where("event_type = 'error'").select("event_id", "previous")
)


@query("SELECT a.event_id AS error_id, b.event_id AS later_id FROM events AS a JOIN events AS b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'error'")
def join_interval(spark, sf):
    """Equi-join on user and six-hour bucket (the own and the next one), then the interval as a filter."""
    e = ev(spark, sf).select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    six = 6 * 3_600_000_000
    bucket = F.floor(F.col("us") / six)
    a = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("us").alias("a_us"), F.explode(F.array(bucket, bucket + 1)).alias("bucket"))
    b = e.select(F.col("event_id").alias("later_id"), "user_id", F.col("us").alias("b_us"), bucket.alias("bucket"))
    return a.join(b, ["user_id", "bucket"]).where((F.col("b_us") > F.col("a_us")) & (F.col("b_us") <= F.col("a_us") + six)).select("error_id", "later_id")


query("WITH o AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn FROM events) SELECT a.event_id, b.event_id AS next_id, round(b.value - a.value, 6) AS change FROM o AS a JOIN o AS b ON a.user_id = b.user_id AND b.rn = a.rn + 1", "join_self")(
    lambda spark, sf: (lambda o: o.alias("a").join(o.alias("b"), F.expr("a.user_id = b.user_id and b.rn = a.rn + 1")).select("a.event_id", F.col("b.event_id").alias("next_id"), F.round(F.col("b.value") - F.col("a.value"), 6).alias("change")))(
        ev(spark, sf).withColumn("rn", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
    )
)

# ---- aggregation ------------------------------------------------------------------------------------------
query("SELECT event_type, count(*) AS n, round(sum(value), 6) AS total, round(avg(value), 6) AS mean, min(value) AS low, max(value) AS high, round(stddev_samp(value), 6) AS sd FROM events GROUP BY event_type", "agg_basic")(
    lambda spark, sf: ev(spark, sf).groupBy("event_type").agg(F.count("*").alias("n"), r6(F.sum("value")).alias("total"), r6(F.avg("value")).alias("mean"), F.min("value").alias("low"), F.max("value").alias("high"), r6(F.stddev_samp("value")).alias("sd"))
)
query("SELECT user_id, max(event_type) AS last_type, min(props) AS first_props FROM events GROUP BY user_id", "agg_sort")(lambda spark, sf: ev(spark, sf).groupBy("user_id").agg(F.max("event_type").alias("last_type"), F.min("props").alias("first_props")))
query("SELECT date_trunc('day', ts) AS day, count(DISTINCT user_id) AS users FROM events GROUP BY ALL", "agg_distinct")(lambda spark, sf: ev(spark, sf).groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(F.count_distinct("user_id").alias("users")))
query("SELECT date_trunc('hour', ts) AS hour, count(*) AS n, count(*) FILTER (WHERE event_type = 'error') AS errors FROM events GROUP BY ALL", "agg_filter")(
    lambda spark, sf: ev(spark, sf).groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "error").alias("errors"))
)


def _dims(spark, sf):
    return ev(spark, sf).join(hierarchy(spark, sf), "user_id").select("region", "segment", "event_type")


_D = f"SELECT r_name AS region, c_mktsegment AS segment, event_type FROM {_H}"
query(f"SELECT region, segment, count(*) AS n FROM ({_D}) AS d GROUP BY ROLLUP (region, segment)", "agg_rollup")(lambda spark, sf: _dims(spark, sf).rollup("region", "segment").agg(F.count("*").alias("n")))
query(f"SELECT region, segment, event_type, count(*) AS n, CAST(grouping(region) * 4 + grouping(segment) * 2 + grouping(event_type) AS BIGINT) AS gid FROM ({_D}) AS d GROUP BY CUBE (region, segment, event_type)", "agg_cube")(
    lambda spark, sf: _dims(spark, sf).cube("region", "segment", "event_type").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("gid"))
)
query(f"SELECT region, segment, event_type, count(*) AS n FROM ({_D}) AS d GROUP BY GROUPING SETS ((region, segment), (event_type), ())", "agg_grouping_sets")(
    lambda spark, sf: _dims(spark, sf).groupingSets([("region", "segment"), ("event_type",), ()], "region", "segment", "event_type").agg(F.count("*").alias("n")).select("region", "segment", "event_type", "n")
)
query("SELECT event_type, quantile_disc(value, 0.5) AS p50, quantile_disc(value, 0.9) AS p90 FROM events GROUP BY event_type", "pivot_levels")(
    lambda spark, sf: __import__("cdfblend.operators.baselines", fromlist=["x"]).exact_quantiles(ev(spark, sf), ["event_type"], "value", [0.5, 0.9]).groupBy("event_type").pivot("level", [0.5, 0.9]).agg(F.first("value")).toDF("event_type", "p50", "p90")
)
query(" UNION ALL ".join(f"SELECT '{m}' AS metric, count({m}) AS n, round(sum({m}), 4) AS total FROM lineitem" for m in ("l_quantity", "l_discount", "l_tax")), "unpivot_metrics")(
    lambda spark, sf: table(spark, sf, "lineitem").unpivot([], ["l_quantity", "l_discount", "l_tax"], "metric", "v").groupBy("metric").agg(F.count("v").alias("n"), F.round(F.sum("v"), 4).alias("total"))
)
query("SELECT event_type, quantile_disc(value, 0.9) AS d90, round(quantile_cont(value, 0.9), 6) AS c90, round(median(value), 6) AS med FROM events GROUP BY event_type", "agg_percentiles")(
    lambda spark, sf: ev(spark, sf).groupBy("event_type").agg(F.expr("percentile_disc(0.9) within group (order by value)").alias("d90"), r6(F.expr("percentile_cont(0.9) within group (order by value)")).alias("c90"), r6(F.median("value")).alias("med"))
)
query("SELECT user_id, arg_max(event_id, row(value, event_id)) AS event_id FROM events GROUP BY user_id", "agg_maxby")(lambda spark, sf: ev(spark, sf).groupBy("user_id").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("event_id")))
query("SELECT user_id, date_trunc('hour', ts) AS hour, list_sort(list(value)) AS vals FROM events GROUP BY ALL", "agg_collect")(
    lambda spark, sf: ev(spark, sf).groupBy("user_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.array_sort(F.collect_list("value")).alias("vals"))
)
query("WITH m AS (SELECT event_type, avg(value) AS m, var_pop(value) AS v FROM events GROUP BY event_type) SELECT e.event_type, round(avg((value - m) ** 3) / any_value(v) ** 1.5, 5) AS skew, round(avg((value - m) ** 4) / any_value(v) ** 2 - 3, 5) AS kurt FROM events AS e JOIN m ON m.event_type = e.event_type GROUP BY e.event_type", "agg_moments")(
    lambda spark, sf: ev(spark, sf).groupBy("event_type").agg(F.round(F.skewness("value"), 5).alias("skew"), F.round(F.kurtosis("value"), 5).alias("kurt"))
)
query("SELECT user_id, date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY ALL HAVING count(*) >= 4", "agg_having")(
    lambda spark, sf: ev(spark, sf).groupBy("user_id", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(F.count("*").alias("n")).where("n >= 4")
)
query(None, "agg_acd")(lambda spark, sf: ev(spark, sf).groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users")))
query(None, "agg_hist")(lambda spark, sf: ev(spark, sf).groupBy("event_type").agg(F.histogram_numeric("value", F.lit(10)).alias("h")))

# ---- windows, order, limits, sets -------------------------------------------------------------------------
_by_value = lambda: Window.partitionBy("user_id").orderBy("value", "event_id")
_plain = lambda: Window.partitionBy("user_id").orderBy("value")
_arrive = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")
query("SELECT event_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 9) AS pr, ntile(4) OVER w AS nt FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value, event_id), v AS (PARTITION BY user_id ORDER BY value)", "win_rank")(
    lambda spark, sf: ev(spark, sf).select("event_id", F.row_number().over(_by_value()).alias("rn"), F.rank().over(_plain()).alias("rk"), F.dense_rank().over(_plain()).alias("dr"), F.round(F.percent_rank().over(_plain()), 9).alias("pr"), F.ntile(4).over(_by_value()).alias("nt"))
)
query("SELECT event_id, round(cume_dist() OVER (PARTITION BY user_id ORDER BY value), 9) AS share FROM events", "win_cume")(lambda spark, sf: ev(spark, sf).select("event_id", F.round(F.cume_dist().over(_plain()), 9).alias("share")))
query("SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER w) AS gap, lead(event_id) OVER w AS next_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "win_lag")(
    lambda spark, sf: (lambda us: ev(spark, sf).select("event_id", (us - F.lag(us).over(_arrive())).alias("gap"), F.lead("event_id").over(_arrive()).alias("next_id")))(F.unix_micros(F.col("ts").cast("timestamp")))
)
query("SELECT DISTINCT date_trunc('day', ts) AS day, first_value(value) OVER w AS first, last_value(value) OVER w AS last, nth_value(value, 3) OVER w AS third FROM events WINDOW w AS (PARTITION BY date_trunc('day', ts) ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", "win_value")(
    lambda spark, sf: (lambda w: ev(spark, sf).withColumn("day", F.date_trunc("day", "ts").cast("timestamp_ntz")).select("day", F.first("value").over(w).alias("first"), F.last("value").over(w).alias("last"), F.nth_value("value", 3).over(w).alias("third")).distinct())(
        Window.partitionBy("day").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    )
)
query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 19 PRECEDING AND CURRENT ROW), 6) AS moving FROM events", "win_rows")(
    lambda spark, sf: ev(spark, sf).select("event_id", r6(F.avg("value").over(_arrive().rowsBetween(-19, 0))).alias("moving"))
)
query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day_before FROM events", "win_range")(
    lambda spark, sf: ev(spark, sf).withColumn("s", F.unix_seconds(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)).alias("day_before"))
)
query("SELECT event_id, (row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1) // 41 AS batch FROM events", "win_batch_id")(lambda spark, sf: ev(spark, sf).select("event_id", F.floor((F.row_number().over(_arrive()) - 1) / 41).alias("batch")))
query("SELECT event_id, min(value) OVER w AS low, max(value) OVER w AS high FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)", "win_running_extremes")(
    lambda spark, sf: (lambda w: ev(spark, sf).select("event_id", F.min("value").over(w).alias("low"), F.max("value").over(w).alias("high")))(_arrive().rowsBetween(Window.unboundedPreceding, 0))
)
query("SELECT event_id, value FROM events ORDER BY value DESC, event_id", "sort_all")(lambda spark, sf: ev(spark, sf).select("event_id", "value").orderBy(F.desc("value"), "event_id"))
query("SELECT event_id, value FROM events ORDER BY value DESC, event_id LIMIT 25", "topk_tail")(lambda spark, sf: ev(spark, sf).select("event_id", "value").orderBy(F.desc("value"), "event_id").limit(25))
query(f"SELECT region, nation, p99 FROM (SELECT r_name AS region, n_name AS nation, quantile_disc(value, 0.99) AS p99, row_number() OVER (PARTITION BY r_name ORDER BY quantile_disc(value, 0.99) DESC, n_name) AS rn FROM {_H} GROUP BY r_name, n_name) AS z WHERE rn <= 2", "topk_per_region")(
    lambda spark, sf: ev(spark, sf).join(hierarchy(spark, sf), "user_id").groupBy("region", "nation").agg(F.expr("percentile_disc(0.99) within group (order by value)").alias("p99")).withColumn("rn", F.row_number().over(Window.partitionBy("region").orderBy(F.desc("p99"), "nation"))).where("rn <= 2").drop("rn")
)
query("SELECT event_id, value FROM events ORDER BY event_id LIMIT 20 OFFSET 40", "limit_offset")(lambda spark, sf: ev(spark, sf).select("event_id", "value").orderBy("event_id").offset(40).limit(20))


def _week(spark, sf, k):
    return ev(spark, sf).where(f"ts >= timestamp_ntz'2024-01-01' + interval {7 * k} days and ts < timestamp_ntz'2024-01-08' + interval {7 * k} days and value > 120").select("user_id")


_W = [f"SELECT user_id FROM events WHERE ts >= TIMESTAMP '2024-01-01' + INTERVAL {7 * k} DAY AND ts < TIMESTAMP '2024-01-08' + INTERVAL {7 * k} DAY AND value > 120" for k in (0, 1)]
for _name, _op, _fn in (("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b)), ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("set_except", "EXCEPT", lambda a, b: a.subtract(b)), ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    query(f"{_W[0]} {_op} {_W[1]}", _name)(lambda spark, sf, fn=_fn: fn(_week(spark, sf, 0), _week(spark, sf, 1)))

# ---- scalar functions -------------------------------------------------------------------------------------
query("SELECT c_custkey, upper(c_name) AS up, substr(c_name, 1, 4) AS head, split_part(c_name, '#', 2) AS tail, regexp_replace(c_name, '[0-9]', 'x', 'g') AS masked, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS padded, length(c_name) AS len FROM customer", "fn_string")(
    lambda spark, sf: table(spark, sf, "customer").select("c_custkey", F.upper("c_name").alias("up"), F.substring("c_name", 1, 4).alias("head"), F.split_part("c_name", F.lit("#"), F.lit(2)).alias("tail"), F.regexp_replace("c_name", "[0-9]", "x").alias("masked"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"), F.length("c_name").cast("long").alias("len"))
)
query("SELECT event_id, date_trunc('hour', ts) AS hour, CAST(dayofweek(ts) + 1 AS INT) AS dow, CAST(hour(ts) AS INT) AS h, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INT) AS days, CAST(CAST(ts AS DATE) + 7 AS DATE) AS later FROM events", "fn_date")(
    lambda spark, sf: ev(spark, sf).select("event_id", F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour"), F.dayofweek("ts").alias("dow"), F.hour("ts").alias("h"), F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("days"), F.date_add("ts", 7).alias("later"))
)
query("SELECT l_orderkey, l_linenumber, l_partkey, CAST(epoch(l_shipdate) - epoch(o_orderdate) AS DOUBLE) / 86400 AS days FROM lineitem JOIN orders ON o_orderkey = l_orderkey", "fn_interval")(
    lambda spark, sf: (lambda l, o: l.join(o, l.l_orderkey == o.o_orderkey).select("l_orderkey", "l_linenumber", "l_partkey", ((F.col("l_shipdate") - F.col("o_orderdate")).cast("interval second").cast("decimal(20,6)").cast("double") / 86400).alias("days")))(*t(spark, sf, "lineitem", "orders"))
)
query("SELECT event_id, round(ln(value + 1), 9) AS a, round(exp(value / 1000), 9) AS b, round(log10(value + 1), 9) AS c, round(pow(value, 0.3), 9) AS d, round(sqrt(value), 9) AS e, round(value, 1) AS f, greatest(value, 50) AS g, least(value, 50) AS h FROM events", "fn_math")(
    lambda spark, sf: ev(spark, sf).select("event_id", F.round(F.log(F.col("value") + 1), 9).alias("a"), F.round(F.exp(F.col("value") / 1000), 9).alias("b"), F.round(F.log10(F.col("value") + 1), 9).alias("c"), F.round(F.pow("value", F.lit(0.3)), 9).alias("d"), F.round(F.sqrt("value"), 9).alias("e"), F.round("value", 1).alias("f"), F.greatest("value", F.lit(50.0)).alias("g"), F.least("value", F.lit(50.0)).alias("h"))
)
query("SELECT event_id, round(ln(p / (1 - p)), 9) AS logit, round(1 / (1 + exp(-ln(p / (1 - p)))), 9) AS back FROM (SELECT event_id, greatest(least(value / 500, 0.995), 0.005) AS p FROM events) AS z", "fn_logit")(
    lambda spark, sf: ev(spark, sf).withColumn("p", F.greatest(F.least(F.col("value") / 500, F.lit(0.995)), F.lit(0.005))).select("event_id", F.round(F.log(F.col("p") / (1 - F.col("p"))), 9).alias("logit"), F.round(1 / (1 + F.exp(-F.log(F.col("p") / (1 - F.col("p"))))), 9).alias("back"))
)
_ARR = "(SELECT user_id, list_sort(list(value)) AS a FROM events GROUP BY user_id) AS z"
query(f"SELECT user_id, a[1] AS first, len(list_filter(a, lambda x: x > 50)) AS above, list_slice(a, 1, 3) AS low3, round(list_sum(list_transform(a, lambda x: x * 2)), 6) AS doubled FROM {_ARR}", "fn_array")(
    lambda spark, sf: ev(spark, sf).groupBy("user_id").agg(F.array_sort(F.collect_list("value")).alias("a")).select("user_id", F.element_at("a", 1).alias("first"), F.size(F.filter("a", lambda x: x > 50)).cast("long").alias("above"), F.slice("a", 1, 3).alias("low3"), r6(F.aggregate(F.transform("a", lambda x: x * 2), F.lit(0.0), lambda s, x: s + x)).alias("doubled"))
)
query("SELECT event_type, quantile_disc(value, 0.9) AS p90 FROM events GROUP BY event_type", "fn_map")(
    lambda spark, sf: ev(spark, sf).groupBy("event_type").agg(*[F.expr(f"percentile_disc({p}) within group (order by value)").alias(n) for p, n in ((0.5, "a"), (0.9, "b"))]).select("event_type", F.element_at(F.map_from_arrays(F.array(F.lit("p50"), F.lit("p90")), F.array("a", "b")), "p90").alias("p90"))
)
query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events", "fn_json")(lambda spark, sf: ev(spark, sf).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))
query("SELECT o_orderkey, CAST(CAST(o_totalprice AS DECIMAL(12, 2)) AS DOUBLE) AS price FROM orders", "fn_cast_decimal")(lambda spark, sf: table(spark, sf, "orders").select("o_orderkey", F.col("o_totalprice").cast("decimal(12,2)").cast("double").alias("price")))
query("SELECT dim, quantile_disc(x, 0.5) AS p50, quantile_disc(x, 0.9) AS p90 FROM (SELECT CAST(generate_subscripts(embedding, 1) - 1 AS INT) AS dim, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings) AS z GROUP BY dim", "emb_metrics")(
    lambda spark, sf: table(spark, sf, "embeddings").select(F.posexplode("embedding").alias("dim", "x")).groupBy("dim").agg(F.expr("percentile_disc(0.5) within group (order by cast(x as double))").alias("p50"), F.expr("percentile_disc(0.9) within group (order by cast(x as double))").alias("p90"))
)

# ---- subqueries and CTE -----------------------------------------------------------------------------------
sql("sub_scalar", "SELECT event_id, value FROM events WHERE value > (SELECT percentile_disc(0.99) WITHIN GROUP (ORDER BY value) FROM events)", None, "events")
sql("sub_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM events WHERE user_id = c_custkey AND event_type = 'error')", None, "events", "customer")
sql("sub_in", "SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 2)", None, "customer", "nation")
sql("sub_correlated", "SELECT event_id FROM events AS e WHERE value > (SELECT percentile_disc(0.5) WITHIN GROUP (ORDER BY value) FROM events AS x WHERE x.user_id = e.user_id)", None, "events")
sql("cte_hist", "WITH h AS (SELECT CAST(floor(ln(1 + value) * 4) AS BIGINT) AS cell FROM events) SELECT cell, count(*) AS n FROM h GROUP BY cell", None, "events")
sql(
    "lateral_levels",
    "SELECT user_id, level FROM (SELECT DISTINCT user_id FROM events) AS u LATERAL VIEW explode(array(0.5D, 0.9D)) AS level",
    "SELECT user_id, CAST(unnest([0.5, 0.9]) AS DOUBLE) AS level FROM (SELECT DISTINCT user_id FROM events) AS u",
    "events",
)

# ---- event-time windows (the batch twins of the streaming operators) ----------------------------------------
_ntz = lambda c: F.col(c).cast("timestamp_ntz")


def _windowed(spark, sf, w) -> DataFrame:
    e = ev(spark, sf).withColumn("ts", F.col("ts").cast("timestamp"))
    g = e.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), r6(F.sum("value")).alias("total"))
    return g.select(_ntz("w.start").alias("start"), "event_type", "n", "total")


_G = "SELECT {} AS start, event_type, count(*) AS n, round(sum(value), 6) AS total FROM events GROUP BY ALL"
query(_G.format("date_trunc('day', ts)"), "tumble_day")(lambda spark, sf: _windowed(spark, sf, F.window("ts", "1 day")))
query(_G.format("time_bucket(INTERVAL '5 minutes', ts, TIMESTAMP '1970-01-01')"), "tumble_5min")(lambda spark, sf: _windowed(spark, sf, F.window("ts", "5 minutes")))
query("SELECT time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') - k * INTERVAL '6 hours' AS start, event_type, count(*) AS n, round(sum(value), 6) AS total FROM events CROSS JOIN range(4) AS r(k) GROUP BY ALL", "slide_day")(
    lambda spark, sf: _windowed(spark, sf, F.window("ts", "1 day", "6 hours"))
)
query("""WITH g AS (SELECT *, CASE WHEN ts >= lag(ts) OVER w + INTERVAL '6 hours' OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM g)
SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, session""", "session_user")(
    lambda spark, sf: ev(spark, sf).withColumn("ts", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", _ntz("w.start").alias("start"), "n")
)
query("SELECT date_trunc('month', l_shipdate) AS month, count(*) AS n FROM lineitem GROUP BY ALL", "period_month")(lambda spark, sf: table(spark, sf, "lineitem").groupBy(F.date_trunc("month", "l_shipdate").cast("timestamp_ntz").alias("month")).agg(F.count("*").alias("n")))

# ---- UDF surface ------------------------------------------------------------------------------------------


@query("SELECT user_id, count(*) AS n, min(value) AS low, max(value) AS high FROM events GROUP BY user_id")
def sql_digest_agg(spark, sf):
    """``digest_agg`` and ``digest_rows`` from SQL."""
    from ..functions.sqlsurface import register

    register(spark)
    views(spark, sf, "events")
    spark.sql("SELECT user_id, digest_agg(value) AS d FROM events GROUP BY user_id").createOrReplaceTempView("user_digests")
    return spark.sql("SELECT user_id, d.n AS n, min(r.value) AS low, max(r.value) AS high FROM user_digests, LATERAL digest_rows(d.vals) AS r GROUP BY user_id, d.n")
