"""The experiment workloads on the given tables and on seeded simulations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracles as O
from ..functions import levels as L
from ..functions import readout as R
from ..operators import baselines as B
from ..operators import measures as A
from ..operators.digest import Scheme
from ..operators.leaf import summarize, summarize_arms
from ..operators.rollup import merge, merge_levels
from ..registry import query
from ..scratch import once
from ..sources import samples as T
from ..sources import simulate as S
from ..sources.tables import ORDER, hierarchy, table
from .methods import EXACT5, FIVE, LI_ORDER, VALUE, flat, leaf_lists, rolled

T6 = list(L.TABLE_6)
POOLED = Scheme(grid="logit:100:0.0025", report="list:0.0," + ",".join(map(repr, T6)) + ",1.0", batch=100, scale="log1p")
TIERS = Scheme(grid="uniform:100", report="report11", batch=100, scale="log1p")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One digest per user in one pass, rolled up to nations and regions, read at five levels."""
    e = table(spark, sf_dir, "events")
    d = summarize(e, ["user_id"], "value", ORDER["events"], Scheme(batch=41)).join(hierarchy(spark, sf_dir), "user_id")
    region = merge_levels(d.select("region", "nation", "user_id", "digest"), [["region", "nation"], ["region"]], scheme=Scheme(batch=100))[-1]
    return R.long(region, ["region"]).where(F.col("level").isin(0.05, 0.5, 0.9, 0.95, 0.99))


# ---- pooled stream ----------------------------------------------------------------------------------------
query("SELECT CAST(floor(ln(1 + value) / 0.25) AS BIGINT) AS cell, count(*) AS n FROM events GROUP BY ALL", "hist_events")(
    lambda spark, sf: table(spark, sf, "events").groupBy(F.floor(F.log1p("value") / 0.25).alias("cell")).agg(F.count("*").alias("n"))
)
query("SELECT CAST(floor(ln(1 + n_chars) / 0.25) AS BIGINT) AS cell, count(*) AS n FROM documents GROUP BY ALL", "hist_docs")(
    lambda spark, sf: table(spark, sf, "documents").groupBy(F.floor(F.log1p("n_chars") / 0.25).alias("cell")).agg(F.count("*").alias("n"))
)


def pooled(spark, sf, name: str, value: str) -> DataFrame:
    """``level, estimate, exact, difference, two_se, within`` of one pooled stream."""
    df = table(spark, sf, name)
    grids = (POOLED.report,)
    est = R.long(summarize(df, [], value, ORDER[name], POOLED), [], grids=grids).where(F.col("level").isin(T6))
    ex = B.exact_quantiles(df, [], value, T6, "disc")
    return A.within_two_se(A.compare(est, ex, []), A.asymptotic_se(df, value, T6)).drop("se")


query(None, "tab1_events")(lambda spark, sf: pooled(spark, sf, "events", "value"))
_LENGTHS = "SELECT 0 AS k, row_number() OVER (ORDER BY doc_id) AS rn, ln(1 + n_chars) AS x FROM documents"
_round = lambda df, *names: df.withColumns({c: F.round(c, 6) for c in names})


def pooled_sql() -> str:
    """As ``pooled`` of text lengths, by ten unrolled flushes: for tables of up to 1000 documents."""
    knots = f"WITH {O.unrolled(O.logit_list(100, 0.0025), 10, 100, _LENGTHS)}\nSELECT k, w AS n, m, p, v FROM kn_10"
    est = O.final(O.read_out([0.0, *T6, 1.0], knots), 1, "p AS level, exp(v) - 1 AS estimate")
    one = "SELECT CAST({p} AS DOUBLE) AS level, CAST(quantile_disc(n_chars, {p}) AS DOUBLE) AS exact, 2 * sqrt({p} * (1 - {p}) / count(n_chars)) * (quantile_cont(n_chars, {hi}) - quantile_cont(n_chars, {lo})) / ({hi} - {lo}) AS two_se FROM documents"
    exact = " UNION ALL ".join(one.format(p=p, hi=round(min(p + 0.01, 1.0), 12), lo=round(p - 0.01, 12)) for p in T6)
    return f"SELECT level, round(estimate, 6) AS estimate, round(exact, 6) AS exact, round(estimate - exact, 6) AS difference, round(two_se, 6) AS two_se, abs(estimate - exact) <= two_se AS within FROM ({est}) AS a JOIN ({exact}) AS b USING (level)"


query(pooled_sql(), "tab1_docs")(lambda spark, sf: _round(pooled(spark, sf, "documents", "n_chars"), "estimate", "exact", "difference", "two_se"))
query(" UNION ALL ".join(f"SELECT CAST({p} AS DOUBLE) AS level, quantile_disc(value, {p}) AS value FROM events" for p in T6), "tab1_exact")(
    lambda spark, sf: B.exact_quantiles(table(spark, sf, "events"), [], "value", T6)
)
SMALL_LOGIT = Scheme(grid="logit:30:0.0025", report="logit:30:0.0025", batch=60, scale="log1p")


def small_knots(docs: DataFrame) -> DataFrame:
    """``i, value``: the 30 knots of the pooled stream of text lengths in batches of 60, by id."""
    return summarize(docs, [], "n_chars", ["doc_id"], SMALL_LOGIT).select(F.posexplode("digest.vals").alias("i", "v")).select("i", F.round("v", 6).alias("value"))


# seventeen unrolled flushes: for tables of up to 1020 documents
query(O.final(O.unrolled(O.logit_list(30, 0.0025), 17, 60, _LENGTHS), 17, "m AS i, round(exp(v) - 1, 6) AS value"), "tab1_slice")(lambda spark, sf: small_knots(table(spark, sf, "documents")))

# ---- the small worked picture: five knots, batches of ten, the third flush ------------------------------------
_THIRTY = "SELECT * FROM (SELECT user_id AS k, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn, value AS x FROM events) AS z WHERE rn <= 30"


@query(O.final(O.unrolled(FIVE, 3, 10, _THIRTY), 3, f"k AS user_id, {VALUE}"))
def fig4_three_flushes(spark, sf):
    """Knots of each user right after the third flush, that is at T = 30; this state is the feature, and later events cannot change it."""
    from pyspark.sql import Window

    e = table(spark, sf, "events").withColumn("rn", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).where("rn <= 30")
    return flat(summarize(e, ["user_id"], "value", ["rn"], Scheme(grid="five", report="five", batch=10)), ["user_id"])


# ---- simulations of single leaves -----------------------------------------------------------------------------
UNIFORM = Scheme(grid="uniform:41", report="round41", batch=41)
LOGIT = Scheme(grid="round41", report="round41", batch=41, interp="logit")


def sim_small(spark, runs: int = 1000, sizes=(1000, 10_000)) -> DataFrame:
    """Ratios of both schemes; the queries that read different measures of one study share its runs."""
    arms = {"uniform+linear": UNIFORM, "logit+logit": LOGIT}
    return once(spark, ("sim_small", runs, tuple(sizes)), lambda: S.leaf_ratios(S.leaf_runs(spark, runs, sizes, arms)))


def table_small(spark, sf, sizes=(1000, 10_000)) -> DataFrame:
    """As ``sim_small``, with samples of three given columns as runs: as many of each size as the columns hold."""
    arms = {"uniform+linear": UNIFORM, "logit+logit": LOGIT}
    return once(spark, ("table_small", sf, tuple(sizes)), lambda: T.sample_ratios([T.population(spark, sf, name) for name in T.POPULATIONS], sizes, arms))


query(None, "sim_ratio")(lambda spark, sf: table_small(spark, sf))
# of the three columns, those whose values have a log
query(None, "sim_ratio_log")(
    lambda spark, sf: T.sample_ratios([T.population(spark, sf, name) for name in ("price", "total")], (1000, 10_000), {"uniform+linear/log": UNIFORM.but(scale="log"), "logit+logit/log": LOGIT.but(scale="log")})
)


LARGE = Scheme(grid="logit:1000:1e-6", report="list:0.0,0.01,0.05,0.1,0.25,0.5,0.75,0.9,0.95,0.99,1.0", batch=1000, interp="logit")


def sim_large(spark, runs: int = 1000, sizes=(1000, 10_000, 100_000, 1_000_000, 10_000_000), grid: str = "logit:1000:1e-6") -> DataFrame:
    """Ratios of large samples. How far the tracked levels reach is not stated for this study; the default is that of the roll-up study."""
    s = LARGE.but(grid=grid)
    return once(spark, ("sim_large", runs, tuple(sizes), grid), lambda: S.leaf_ratios(S.leaf_runs(spark, runs, sizes, {"logit1000": s}, ("lognormal",))))


def table_large(spark, sf, sizes=(1000, 10_000, 100_000, 1_000_000, 10_000_000)) -> DataFrame:
    """As ``sim_large``, with samples of the prices of lineitem, the longest given column, as runs."""
    return once(spark, ("table_large", sf, tuple(sizes)), lambda: T.sample_ratios([T.population(spark, sf, "price")], sizes, {"logit1000": LARGE}))


query(None, "sim_ratio_mid")(lambda spark, sf: S.ratio_by_size(table_large(spark, sf)))
query(None, "sim_growth")(lambda spark, sf: S.ratio_growth(table_large(spark, sf)))
query(None, "sim_rmse")(lambda spark, sf: table_small(spark, sf).select("arm", "dist", "n", "level", "rmse_est", "rmse_exact"))
query(None, "sim_bias")(lambda spark, sf: table_small(spark, sf).select("arm", "dist", "n", "level", "bias_est"))

# ---- three tiers ------------------------------------------------------------------------------------------
_hour = lambda: F.date_trunc("hour", "ts").cast("timestamp_ntz")
_day = lambda: F.date_trunc("day", "hour").cast("timestamp_ntz").alias("day")


def tiers(spark, sf, scheme: Scheme = TIERS) -> list[DataFrame]:
    """User-hour digests (raw, as cells are small), hours, days."""
    e = table(spark, sf, "events").withColumn("hour", _hour())
    cells = summarize(e, ["user_id", "hour"], "value", ORDER["events"], scheme)
    return [cells, *merge_levels(cells, [["hour"], [_day()]], scheme=scheme)]


def _facts(df: DataFrame, *keys: str) -> DataFrame:
    return df.select(*keys, F.col("digest.n").alias("n"), F.array_min("digest.vals").alias("low"), F.array_max("digest.vals").alias("high"))


query("SELECT date_trunc('hour', ts) AS hour, count(*) AS n, min(value) AS low, max(value) AS high FROM events GROUP BY ALL", "tiers_events_hour")(lambda spark, sf: _facts(tiers(spark, sf)[1], "hour"))
query("SELECT date_trunc('day', ts) AS day, count(*) AS n, min(value) AS low, max(value) AS high FROM events GROUP BY ALL", "tiers_events_day")(lambda spark, sf: _facts(tiers(spark, sf)[2], "day"))


def tiers_lineitem(spark, sf, scheme: Scheme = TIERS) -> list[DataFrame]:
    """Supplier-years, nation-years, region-years, regions: digests of full length from the first tier on."""
    l = table(spark, sf, "lineitem").withColumn("year", F.year("l_shipdate"))
    cells = summarize(l, ["l_suppkey", "year"], "l_extendedprice", ORDER["lineitem"], scheme)
    s, n, r = (table(spark, sf, t) for t in ("supplier", "nation", "region"))
    where = s.join(n, s.s_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey).select(F.col("s_suppkey").alias("l_suppkey"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))
    x = cells.join(where, "l_suppkey").select("region", "nation", "year", "l_suppkey", "digest")
    return merge_levels(x, [["region", "nation", "year"], ["region", "year"], ["region"]], scheme=scheme)


query("SELECT r_name AS region, count(*) AS n, min(l_extendedprice) AS low, max(l_extendedprice) AS high FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ALL", "tiers_lineitem")(
    lambda spark, sf: _facts(tiers_lineitem(spark, sf)[-1], "region")
)


def series(spark, sf, tier: int, key: str) -> DataFrame:
    """``key, level, estimate, exact, difference`` at the median and the 0.9 level."""
    e = table(spark, sf, "events").withColumn("hour", _hour()).withColumn("day", F.date_trunc("day", "ts").cast("timestamp_ntz"))
    d = tiers(spark, sf)[tier].select(key, F.explode(F.array(*[F.struct(F.lit(p).alias("level"), R.quantile_at("digest", p).alias("value")) for p in (0.5, 0.9)])).alias("c")).select(key, "c.level", "c.value")
    return A.compare(d, B.exact_quantiles(e, [key], "value", [0.5, 0.9]), [key])


U100, R11 = O.uniform_list(100), list(L.REPORT_11)
_HOURS = leaf_lists("SELECT date_trunc('hour', ts) AS k, ln(1 + value) AS x FROM events", U100, len(R11))
#: Digests of full hours on the log scale; an hour is one flush while it has at most 100 users.
_FULL_HOURS = f"WITH {_HOURS},\n{O.read_out(R11, 'SELECT k, n, m, p, v FROM dg')}\nSELECT k, w AS n, m, p, v FROM kn_1"
_SMALL_HOURS = f"WITH {_HOURS} SELECT k, n, x FROM rw"


def series_sql(tier: str) -> str:
    """As ``series``, curve by curve: hours from their values, days from the hours' digests in one flush."""
    small = "list_sort(list(exp(x) - 1))[CAST(greatest(1, ceil(level * any_value(n) - 1e-9)) AS BIGINT)]"
    est = f"SELECT k, p AS level, exp(v) - 1 AS estimate FROM ({_FULL_HOURS}) AS h UNION ALL SELECT k, level, {small} FROM ({_SMALL_HOURS}) AS h CROSS JOIN (VALUES (CAST(0.5 AS DOUBLE)), (0.9)) AS q(level) GROUP BY k, level"
    if tier == "day":
        raw = f"SELECT date_trunc('day', k) AS k, 1 AS rn, x FROM ({_SMALL_HOURS}) AS h"
        dig = f"SELECT date_trunc('day', k) AS k, 1 AS rn, epoch(k) AS cid, n, m, p, v FROM ({_FULL_HOURS}) AS h"
        days = f"WITH {O.unrolled(U100, 1, 10**9, raw, dig)}\nSELECT k, w AS n, m, p, v FROM kn_1"
        est = O.final(O.read_out(R11, days), 1, "k, p AS level, exp(v) - 1 AS estimate")
    exact = " UNION ALL ".join(f"SELECT date_trunc('{tier}', ts) AS k, CAST({p} AS DOUBLE) AS level, quantile_disc(value, {p}) AS exact FROM events GROUP BY ALL" for p in (0.5, 0.9))
    return f"SELECT k AS {tier}, level, estimate, exact, estimate - exact AS difference FROM ({est}) AS a JOIN ({exact}) AS b USING (k, level)"


_rounded = lambda tier: f"SELECT {tier}, level, round(estimate, 6) AS estimate, round(exact, 6) AS exact, round(difference, 6) AS difference FROM ({series_sql(tier)}) AS z"
_within = lambda tier: f"SELECT level, avg(CAST(abs(difference) <= CAST(0.10 AS DOUBLE) * abs(exact) AS DOUBLE)) AS fraction, count(*) AS cells FROM ({series_sql(tier)}) AS z GROUP BY level"
_three = ("estimate", "exact", "difference")
query(_rounded("hour") + " WHERE hour >= TIMESTAMP '2024-01-08' AND hour < TIMESTAMP '2024-01-15'", "fig7_series")(
    lambda spark, sf: _round(series(spark, sf, 1, "hour").where("hour >= timestamp_ntz'2024-01-08' and hour < timestamp_ntz'2024-01-15'"), *_three)
)
query(_rounded("day"), "fig8_series")(lambda spark, sf: _round(series(spark, sf, 2, "day"), *_three))
for _key, _trunc in (("hour", "hour"), ("day", "day")):
    query(" UNION ALL ".join(f"SELECT date_trunc('{_trunc}', ts) AS {_key}, CAST({p} AS DOUBLE) AS level, quantile_disc(value, {p}) AS value FROM events GROUP BY ALL" for p in (0.5, 0.9)), f"tab2_exact_{_key}")(
        lambda spark, sf, key=_key: B.exact_quantiles(table(spark, sf, "events").withColumn(key, F.date_trunc(key, "ts").cast("timestamp_ntz")), [key], "value", [0.5, 0.9])
    )
query(_within("hour"), "tab2_hour")(lambda spark, sf: A.within_fraction(series(spark, sf, 1, "hour"), ["level"]))
query(_within("day"), "tab2_day")(lambda spark, sf: A.within_fraction(series(spark, sf, 2, "day"), ["level"]))

# ---- inhomogeneous leaves -----------------------------------------------------------------------------------
def far_prices(spark, sf) -> DataFrame:
    """Every hundredth supplier sells at a hundred times the price."""
    return table(spark, sf, "lineitem").withColumn("price", F.when(F.col("l_suppkey") % 100 == 0, F.col("l_extendedprice") * 100).otherwise(F.col("l_extendedprice")))


def inhomog_suppliers(spark, sf, scheme: Scheme = EXACT5) -> DataFrame:
    return summarize(far_prices(spark, sf), ["l_suppkey"], "price", ORDER["lineitem"], scheme)


_TAILS = (0.01, 0.05, 0.1, 0.25, 0.5, 0.75, 0.9, 0.95, 0.99, 0.995, 0.999)


def inhomog_runs(spark, sf, leaves: int = 1000, record: str = "report10", knots: str = "logit:1000:1e-6", batch: int = 100) -> DataFrame:
    """As ``inhomogeneous_runs``, with the suppliers as leaves: ``run, arm, dist, n, level, estimate, exact, truth``.

    Runs are groups of about ``leaves`` suppliers, as many as the table holds and two at least; each pools all rows of its
    suppliers, and the truth is that of all rows.
    """
    digests = once(spark, ("inhomog_leaves", sf, record), lambda: inhomog_suppliers(spark, sf, Scheme(grid=record, report=record, batch=None)))
    runs = max(2, digests.count() // leaves)
    run, grids = F.pmod(F.xxhash64("l_suppkey"), F.lit(runs)).alias("run"), "list:0.0," + ",".join(map(repr, _TAILS)) + ",1.0"
    dealt = digests.select("*", run)
    orders = {"random": [F.xxhash64(F.col("l_suppkey"), F.lit(1)), "l_suppkey"], "sorted": [R.quantile_at("digest", 0.5, (record,)), "l_suppkey"]}
    est = None
    for scale in ("identity", "log"):
        for name, order in orders.items():
            d = merge(dealt, ["run"], "digest", order, Scheme(grid=knots, report=grids, batch=batch, interp="logit", scale=scale))
            arm = R.long(d, ["run"], grids=(grids,), digits=None).where(F.col("level").isin(*_TAILS)).withColumn("arm", F.lit(f"{scale}/{name}"))
            est = arm if est is None else est.unionAll(arm)
    rows = far_prices(spark, sf).select(F.lit("suppliers").alias("dist"), run, "price")
    exact = T.large_quantiles(rows, ["run"], "price", _TAILS).withColumnRenamed("value", "exact")
    truth = T.large_quantiles(rows, ["dist"], "price", _TAILS).withColumnRenamed("value", "truth")
    return est.withColumnRenamed("value", "estimate").join(exact, ["run", "level"]).join(truth, "level").select("run", "arm", "dist", F.lit(leaves).cast("long").alias("n"), "level", "estimate", "exact", "truth")


query(None, "inhomog_ratio")(lambda spark, sf: S.inhomogeneous_ratios(inhomog_runs(spark, sf)))


_FAR = "SELECT l_suppkey AS k, CASE WHEN l_suppkey % 100 = 0 THEN l_extendedprice * 100 ELSE l_extendedprice END AS x FROM lineitem"
query(rolled(_FAR, FIVE, "0", "k", 4, 25, VALUE), "inhomog_suppliers")(lambda spark, sf: flat(merge(inhomog_suppliers(spark, sf), [], "digest", ["l_suppkey"], EXACT5.but(batch=25)), []))
query(rolled(_FAR, FIVE, "0", "(SELECT v FROM dg WHERE dg.k = ll.k AND dg.m = 2), k", 4, 25, VALUE), "inhomog_sorted")(
    lambda spark, sf: flat(merge(inhomog_suppliers(spark, sf), [], "digest", [F.get("digest.vals", F.lit(2)), "l_suppkey"], EXACT5.but(batch=25)), [])
)

# ---- ablations --------------------------------------------------------------------------------------------


def _relative_error(est: DataFrame, exact: DataFrame, key: str) -> DataFrame:
    """``arm, error``: mean absolute relative error of every arm over keys and levels."""
    both = est.join(exact.select(key, "level", F.col("value").alias("exact")), [key, "level"])
    return both.groupBy("arm").agg(F.avg(F.abs(F.col("value") - F.col("exact")) / F.col("exact")).alias("error"))


def _arm_errors(spark, sf, arms: dict[str, Scheme]) -> DataFrame:
    """All arms from one pass over the events, against the exact values of each event type at the six levels."""
    e = table(spark, sf, "events")
    got = summarize_arms(e, ["event_type"], "value", ORDER["events"], {arm: s.but(report=POOLED.report) for arm, s in arms.items()})
    est = R.long(got, ["arm", "event_type"], grids=(POOLED.report,)).where(F.col("level").isin(T6))
    return _relative_error(est, B.exact_quantiles(e, ["event_type"], "value", T6), "event_type")


_part = lambda k: F.split("arm", "/")[k]
query(None, "ablate_sizes")(
    lambda spark, sf: _arm_errors(spark, sf, {f"{m}/{b}": Scheme(grid=f"uniform:{m}", batch=b) for m in (11, 41, 101) for b in (20, 100, 400)})
    .select(_part(0).cast("int").alias("knots"), _part(1).cast("int").alias("batch"), "error")
)
query(None, "ablate_scheme")(
    lambda spark, sf: _arm_errors(spark, sf, {f"{g}/{i}/{c}": Scheme(grid=g, batch=41, interp=i, scale=c) for g in ("uniform:41", "round41") for i in ("linear", "logit") for c in ("identity", "log1p")})
    .select(_part(0).alias("grid"), _part(1).alias("interp"), _part(2).alias("scale"), "error")
)


def record_errors(spark, sf, lengths=(5, 10, 20, 50)) -> DataFrame:
    """Roll-ups of leaf records of several lengths, all from one pass over the leaves."""
    quarters = "list:0.0,0.25,0.5,0.75,1.0"
    l, s = table(spark, sf, "lineitem"), table(spark, sf, "supplier")
    leaves = summarize_arms(l, ["l_suppkey"], "l_extendedprice", ORDER["lineitem"], {str(m): Scheme(grid=f"uniform:{m}", report=f"uniform:{m}", batch=None) for m in lengths})
    nations = merge(leaves.join(s, leaves.l_suppkey == s.s_suppkey), ["arm", "s_nationkey"], "digest", ["l_suppkey"], Scheme(grid="uniform:101", report=quarters, batch=10))
    est = R.long(nations, ["arm", "s_nationkey"], grids=(quarters,)).where(F.col("level").isin(0.25, 0.5, 0.75))
    exact = B.exact_quantiles(l.join(s, l.l_suppkey == s.s_suppkey), ["s_nationkey"], "l_extendedprice", [0.25, 0.5, 0.75])
    return _relative_error(est, exact, "s_nationkey").select(F.col("arm").cast("int").alias("record"), "error")


def record_errors_sql(lengths=(5, 10, 20, 50), flushes: int = 4) -> str:
    """As ``record_errors``: for nations of up to 40 suppliers."""
    nation = "(SELECT s_nationkey FROM supplier WHERE s_suppkey = {})".format
    prices = "SELECT l_suppkey AS k, l_extendedprice AS x FROM lineitem WHERE l_suppkey IN (SELECT s_suppkey FROM supplier)"
    arm = lambda m: rolled(prices, O.uniform_list(m), nation("ll.k"), "k", flushes, 10, f"{m} AS record, k, p, v", knots=O.uniform_list(101))
    est = " UNION ALL ".join(f"SELECT * FROM ({arm(m)}) AS z WHERE p IN (0.25, 0.5, 0.75)" for m in lengths)
    exact = " UNION ALL ".join(f"SELECT {nation('l_suppkey')} AS k, CAST({p} AS DOUBLE) AS p, quantile_disc(l_extendedprice, {p}) AS e FROM lineitem GROUP BY ALL" for p in (0.25, 0.5, 0.75))
    return f"SELECT CAST(record AS INT) AS record, round(avg(abs(v - e) / e), 9) AS error FROM ({est}) AS a JOIN ({exact}) AS b USING (k, p) GROUP BY record"


query(record_errors_sql(), "ablate_record_length")(lambda spark, sf: record_errors(spark, sf).withColumn("error", F.round("error", 9)))

# ---- slices, rankings, other domains ------------------------------------------------------------------------
_H = "events AS e JOIN customer AS c ON c.c_custkey = e.user_id JOIN nation AS n ON n.n_nationkey = c.c_nationkey JOIN region AS r ON r.r_regionkey = n.n_regionkey"
query(rolled(f"SELECT struct_pack(u := user_id, t := event_type, r := r_name) AS k, value AS x FROM {_H} WHERE event_type IN ('error', 'purchase')", FIVE, "struct_pack(r := k.r, t := k.t)", "k.u", 1, 10**9, f"k.r AS region, k.t AS event_type, {VALUE}", raw_below=5), "slice_region_type")(
    lambda spark, sf: flat(
        merge(summarize(table(spark, sf, "events").where(F.col("event_type").isin("error", "purchase")), ["user_id", "event_type"], "value", ORDER["events"], EXACT5).join(hierarchy(spark, sf), "user_id"), ["region", "event_type"], "digest", ["user_id"], EXACT5),
        ["region", "event_type"],
    )
)
query(f"SELECT n_name AS nation, count(*) AS n, quantile_disc(value, 0.99) AS p99, CAST(count(*) FILTER (WHERE event_type = 'error') AS DOUBLE) / count(*) AS error_share FROM {_H} GROUP BY n_name", "tail_by_nation")(
    lambda spark, sf: table(spark, sf, "events").join(hierarchy(spark, sf), "user_id").groupBy("nation").agg(F.count("*").alias("n"), F.expr("percentile_disc(0.99) within group (order by value)").alias("p99"), (F.count_if(F.col("event_type") == "error") / F.count("*")).alias("error_share"))
)
query(f"SELECT n_name AS nation, quantile_disc(value, 0.99) AS p99 FROM {_H} GROUP BY n_name ORDER BY p99 DESC, nation LIMIT 5", "worst_nations_topk")(
    lambda spark, sf: table(spark, sf, "events").join(hierarchy(spark, sf), "user_id").groupBy("nation").agg(F.expr("percentile_disc(0.99) within group (order by value)").alias("p99")).orderBy(F.desc("p99"), "nation").limit(5)
)
_DAYS = f"SELECT l_suppkey AS k, row_number() OVER (PARTITION BY l_suppkey ORDER BY {LI_ORDER}, o_orderdate) AS rn, (epoch(l_shipdate) - epoch(o_orderdate)) / 86400.0 AS x FROM lineitem JOIN orders ON o_orderkey = l_orderkey"


@query(O.final(O.unrolled(FIVE, 8, 100, _DAYS), 8, f"k AS l_suppkey, {VALUE}"))
def ship_delay_leaf(spark, sf):
    """Days from order to shipment per supplier; values of both signs, so the natural scale."""
    l, o = table(spark, sf, "lineitem"), table(spark, sf, "orders")
    j = l.join(o, l.l_orderkey == o.o_orderkey).withColumn("days", (F.unix_seconds(F.col("l_shipdate").cast("timestamp")) - F.unix_seconds(F.col("o_orderdate").cast("timestamp"))) / 86400)
    return flat(summarize(j, ["l_suppkey"], "days", [*ORDER["lineitem"], "o_orderdate"], Scheme(grid="five", report="five", batch=100)), ["l_suppkey"])


query("SELECT p_brand, CAST(p_size AS DOUBLE) AS atom, count(*) AS n FROM part WHERE p_size IN (1, 10, 25, 50) GROUP BY ALL", "spikes_part_size")(
    lambda spark, sf: __import__("cdfblend.operators.extensions", fromlist=["x"]).spike_counts(table(spark, sf, "part"), ["p_brand"], "p_size", [1, 10, 25, 50])
)
query(f"WITH {leaf_lists('SELECT quality AS k, toxic AS x FROM labels WHERE quality IS NOT NULL AND toxic IS NOT NULL', FIVE)} SELECT k AS quality, p AS level, round(v, 7) AS value FROM dg", "two_atom_labels")(
    lambda spark, sf: flat(summarize(table(spark, sf, "labels").where("quality is not null"), ["quality"], "toxic", ["doc_id"], EXACT5), ["quality"])
)
query(f"WITH {leaf_lists('SELECT lang AS k, n_chars AS x FROM documents', FIVE)} SELECT k AS lang, p AS level, round(v, 7) AS value FROM dg", "text_lengths")(
    lambda spark, sf: flat(summarize(table(spark, sf, "documents"), ["lang"], "n_chars", ["doc_id"], EXACT5), ["lang"])
)
query(f"WITH {leaf_lists('SELECT role AS k, length(text) AS x FROM conversations', FIVE)} SELECT k AS role, p AS level, round(v, 7) AS value FROM dg", "turn_lengths")(
    lambda spark, sf: flat(summarize(table(spark, sf, "conversations").withColumn("chars", F.char_length("text")), ["role"], "chars", ["conv_id", "turn"], EXACT5), ["role"])
)
query(f"WITH {leaf_lists('SELECT 0 AS k, length(html) AS x FROM pages', FIVE)} SELECT p AS level, round(v, 7) AS value FROM dg", "page_lengths")(
    lambda spark, sf: flat(summarize(table(spark, sf, "pages").withColumn("chars", F.char_length("html")), [], "chars", ["page_id"], EXACT5), [])
)
